"""Distances between array columns, in double precision, and hashed text vectors."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _sum(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda s, x: s + x)


def l2_sq(a: Column, b: Column) -> Column:
    return _sum(F.zip_with(a, b, lambda x, y: (x.cast("double") - y) * (x.cast("double") - y)))


def l2(a: Column, b: Column) -> Column:
    return F.sqrt(l2_sq(a, b))


def dot(a: Column, b: Column) -> Column:
    return _sum(F.zip_with(a, b, lambda x, y: x.cast("double") * y))


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / (norm(a) * norm(b))


def normalise(a: Column) -> Column:
    return F.transform(a, lambda x: x / norm(a))


def hash_text(df: DataFrame, id_col: str, text_col: str, dim: int = 64) -> DataFrame:
    """(id, vec): signed hashed word counts of unit length; texts without words have no row."""
    words = df.select(F.col(id_col).alias("id"), F.explode(F.array_remove(F.split(F.lower(text_col), r"\W+"), "")).alias("w"))
    h = F.xxhash64("w")
    slots = words.groupBy("id", F.pmod(h, F.lit(dim)).cast("int").alias("slot")).agg(F.sum(F.when(h.bitwiseAND(F.lit(1 << 40)) == 0, 1.0).otherwise(-1.0)).alias("v"))
    parts = slots.groupBy("id").agg(F.map_from_entries(F.collect_list(F.struct("slot", "v"))).alias("m"))
    dense = parts.select("id", F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), lambda i: F.coalesce(F.try_element_at("m", i), F.lit(0.0))).alias("v")).where(F.exists("v", lambda x: x != 0))
    return dense.select("id", normalise(F.col("v")).alias("vec"))


def arrow_l2():
    """The distance as an Arrow UDF: column functions above are as good for a few rows, this is for bulk. Null if either is null
    or the lengths differ."""
    from pyspark.sql.functions import pandas_udf

    @pandas_udf("double")
    def l2_of(a: pd.Series, b: pd.Series) -> pd.Series:
        fits = [x is not None and y is not None and len(x) == len(y) for x, y in zip(a, b, strict=True)]
        return pd.Series([float(np.sqrt(((np.asarray(x, float) - np.asarray(y, float)) ** 2).sum())) if ok else None for x, y, ok in zip(a, b, fits, strict=True)], dtype="float64")

    return l2_of


def centroids(rows: DataFrame, key: str, vec: str = "vec") -> DataFrame:
    """(key, pos, mean): the mean vector of each key, from sums of Arrow batches; a large key is summed wherever its rows lie.

    Null vectors are left out; vectors of different length under one key give means of the positions they have.
    """
    kind = rows.schema[key].dataType.simpleString()

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column("vec")
            size = lists.value_lengths().to_numpy()
            row = np.repeat(np.arange(len(size)), size)
            pos = np.arange(len(row)) - np.repeat(np.cumsum(size) - size, size)
            flat = pa.table({"key": batch.column("key").take(pa.array(row)), "pos": pos, "v": lists.flatten().cast(pa.float64())})
            some = flat.group_by(["key", "pos"]).aggregate([("v", "sum"), ("v", "count")]).select(["key", "pos", "v_sum", "v_count"])
            yield from some.rename_columns(["key", "pos", "total", "n"]).to_batches()

    sums = rows.select(F.col(key).alias("key"), F.col(vec).alias("vec")).where("vec is not null").mapInArrow(partial, f"key {kind}, pos bigint, total double, n bigint")
    return sums.groupBy("key", "pos").agg((F.sum("total") / F.sum("n")).alias("mean")).withColumnRenamed("key", key)
