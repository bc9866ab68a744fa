"""Given tables as objects (id, vec, attr) and as range queries (qid, qvec, lo, hi, k)."""

from __future__ import annotations

import os
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from rangeknn.functions.vectors import hash_text

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
_ROOT = str(Path(__file__).resolve().parents[2])


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table; Python workers are told where this package lies."""
    env = spark.sparkContext.environment
    if _ROOT not in env.get("PYTHONPATH", "").split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (_ROOT, env.get("PYTHONPATH", "")) if x)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def attach(vecs: DataFrame, attrs: DataFrame, left: str, right: str, attr: Column, vec: str = "embedding") -> DataFrame:
    """Vectors with an attribute: (id, vec, attr). Null and NaN attributes never match a range and go."""
    a = attrs.select(F.col(right).cast("bigint").alias("id"), attr.cast("double").alias("attr")).where("attr is not null and not isnan(attr)")
    return vecs.select(F.col(left).cast("bigint").alias("id"), F.col(vec).alias("vec")).join(a, "id")


def micros(c: str) -> Column:
    return F.unix_micros(F.col(c).cast("timestamp"))


def objects(spark: SparkSession, sf_dir: str, name: str = "E") -> DataFrame:
    """E: unrelated price; T: event time; TD: order date; P, PS: part price and size (ties);
    A: balances; D: hashed documents by length; V: line items by ship date."""
    t = lambda x: table(spark, sf_dir, x)
    if name == "D":
        docs = t("documents")
        vecs = hash_text(docs, "doc_id", "text")
        return vecs.join(docs.select(F.col("doc_id").alias("id"), F.col("n_chars").cast("double").alias("attr")), "id")
    if name == "V":
        rows = t("lineitem")
        cols = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]
        s = rows.agg(*(F.avg(c).alias(f"m{i}") for i, c in enumerate(cols)), *(F.stddev_pop(c).alias(f"s{i}") for i, c in enumerate(cols))).first()
        vec = F.array(*((F.col(c).cast("double") - F.lit(float(s[f"m{i}"]))) / F.lit(float(s[f"s{i}"])) for i, c in enumerate(cols)))
        key = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice"]
        return rows.select(F.xxhash64(*key).alias("id"), vec.alias("vec"), micros("l_shipdate").cast("double").alias("attr"))
    other = {"E": ("orders", "o_orderkey", F.col("o_totalprice")), "T": ("events", "event_id", micros("ts")), "TD": ("orders", "o_orderkey", micros("o_orderdate")), "P": ("part", "p_partkey", F.col("p_retailprice")), "PS": ("part", "p_partkey", F.col("p_size")), "A": ("customer", "c_custkey", F.col("c_acctbal"))}
    tab, key, attr = other[name]
    return attach(t("embeddings"), t(tab), "vec_id", key, attr)


def held_out(objs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(objects, queries): ids of residue 7 modulo 25 are the stated query set and leave the objects."""
    mine = F.pmod("id", F.lit(25)) == 7
    return objs.where(~mine), objs.where(mine).select(F.col("id").alias("qid"), F.col("vec").alias("qvec"))


def intervals(ranked: DataFrame, queries: DataFrame, share: float | None, k: int = 10) -> DataFrame:
    """Queries with the interval of the workload rule: ``share`` of the objects, or mixed (None)."""
    n = ranked.count()
    s = F.lit(share) if share is not None else F.pow(F.lit(2.0), -F.pmod("qid", F.lit(8)))
    w = F.greatest(F.lit(1), F.floor(s * n)).cast("bigint")
    first = F.lit(1) + F.pmod(F.pmod("qid", F.lit(2_147_483_647)) * 7919, F.lit(n) - w + 1)
    q = queries.withColumn("r_lo", first).withColumn("r_hi", first + w - 1)
    edge = ranked.select("rank", "attr")
    lo, hi = edge.select(F.col("rank").alias("r_lo"), F.col("attr").alias("lo")), edge.select(F.col("rank").alias("r_hi"), F.col("attr").alias("hi"))
    return q.join(lo, "r_lo").join(hi, "r_hi").select("qid", "qvec", "lo", "hi", F.lit(k).alias("k"))
