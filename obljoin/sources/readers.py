"""Sources of padded tables. Files are read whole: a filter that skips row groups would show where the matches lie."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from obljoin.operators.padded import PaddedTable, load, where
from obljoin.operators.physical import Engine


def read(spark: SparkSession, kind: str, path: str, schema: StructType | str | None = None, **options: str) -> DataFrame:
    """parquet, orc, csv, json, jdbc (``path`` is the URL) or table; text formats need a schema."""
    if kind in ("csv", "json") and schema is None:
        raise ValueError(f"{kind} needs a schema: inferring one would read the data twice")
    if kind == "table":
        return spark.table(path)
    reader = spark.read.format(kind).options(**options)
    if schema is not None:
        reader = reader.schema(schema)
    return reader.option("url", path).load() if kind == "jdbc" else reader.load(path)


def source(engine: Engine, df: DataFrame, attrs: Sequence[str], condition: Column | None = None, rows: int | None = None) -> PaddedTable:
    """A padded table; rows that fail a secret condition become dummies, so the size stays that of the whole table."""
    if condition is None:
        return load(engine, df, attrs, rows)
    kept = df.select(*attrs, F.coalesce(condition, F.lit(False)).alias("__wanted"))
    whole = load(engine, kept.groupBy(*attrs).agg(F.max("__wanted").alias("__wanted")), [*attrs, "__wanted"], rows)
    out = where(whole, F.col("__wanted"))
    return PaddedTable(out.df.select(*attrs, "__real", "__pos"), tuple(attrs), out.rows, engine)
