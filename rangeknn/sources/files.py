"""Objects and results in other formats than Parquet, always with an explicit schema."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType

FORMATS = ("parquet", "orc", "json", "csv")


def write(df: DataFrame, path: str, fmt: str = "parquet", by: str | None = None) -> None:
    """One folder, optionally one subfolder for each value of ``by``. CSV holds arrays as JSON text."""
    if fmt not in FORMATS:
        raise ValueError(f"format {fmt!r} is not one of {FORMATS}")
    if fmt == "csv":
        df = df.select(*(F.to_json(f.name).alias(f.name) if isinstance(f.dataType, ArrayType) else F.col(f.name) for f in df.schema))
    out = df.write.mode("overwrite").format(fmt).options(**({"header": "true"} if fmt == "csv" else {}))
    (out.partitionBy(by) if by else out).save(path)


def read(spark: SparkSession, path: str, schema, fmt: str = "parquet") -> DataFrame:
    """The columns of ``schema`` from what ``write`` has left; malformed rows raise instead of turning null."""
    if fmt not in FORMATS:
        raise ValueError(f"format {fmt!r} is not one of {FORMATS}")
    want = spark.createDataFrame([], schema).schema
    if fmt == "csv":
        flat = ", ".join(f"`{f.name}` {'string' if isinstance(f.dataType, ArrayType) else f.dataType.simpleString()}" for f in want)
        rows = spark.read.option("header", "true").option("mode", "FAILFAST").schema(flat).csv(path)
        return rows.select(*(F.from_json(f.name, f.dataType.simpleString(), {"mode": "FAILFAST"}).alias(f.name) if isinstance(f.dataType, ArrayType) else F.col(f.name) for f in want))
    opts = {"mode": "FAILFAST"} if fmt == "json" else {}
    return spark.read.options(**opts).schema(want).format(fmt).load(path).select(*want.names)
