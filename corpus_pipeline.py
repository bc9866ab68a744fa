"""Corpus preparation in five stages; each works on all that the one before it kept."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from rangeknn.llm import jaccard, packing, pii, substring, toxicity
from rangeknn.llm.queries import DEMO_KEY, toxicity_weights
from rangeknn.llm.storage import materialise, table, workers_import

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def with_length(rows: DataFrame, changed: Column, docs: DataFrame) -> DataFrame:
    """The columns of documents, n_chars counted anew where the text has changed."""
    length = F.when(changed, F.length("text")).otherwise(F.col("n_chars"))
    return rows.withColumn("n_chars", length.cast(docs.schema["n_chars"].dataType)).select(*COLUMNS)


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a score below one half stay; without a usable training label there is no model, and all stay."""
    workers_import(spark)
    weights = toxicity_weights(spark, docs, sf_dir)
    return (toxicity.score(docs, weights).where("score < 0.5") if weights else docs).select(*COLUMNS)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies the document with the smallest id stays; so do rows without an id."""
    workers_import(spark)
    found = materialise(jaccard.jaccard_components(docs).where("doc_id = component_id").select("doc_id").distinct(), "kept_ids")
    return docs.join(found, "doc_id", "left_semi").union(docs.where("doc_id is null")).select(*COLUMNS)


def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages that came earlier in the corpus are cut out; every document stays."""
    workers_import(spark)
    return with_length(substring.remove_repeats(docs, with_text=True), F.col("n_removed") > 0, docs)


def mask_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data become pseudonyms; n_chars follows, as some (addresses, dates) change their length."""
    workers_import(spark)
    return with_length(pii.pseudonymise(docs, DEMO_KEY), F.size("pii_kinds") > 0, docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    workers_import(spark)
    return packing.pack(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [
    ("toxicity", drop_toxic),
    ("ngram_jaccard", drop_near_copies),
    ("substring_dedup", cut_repeats),
    ("pii", mask_personal_data),
    ("packing", pack_sequences),
]

#: Hashed models, tokenizers and keyed permutations have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = materialise(stage(spark, docs, sf_dir), name)
    return docs
