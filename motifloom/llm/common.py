"""What the corpus operators share: text bytes and tables; durable frames, scratch paths and package shipping come from storage."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from motifloom.storage import durable, scratch, shared_dir, ship


def text_bytes(column: str = "text") -> Column:
    """The column's UTF-8 bytes; null counts as empty."""
    return F.coalesce(F.col(column).cast("string"), F.lit("")).cast("binary")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


__all__ = ["durable", "scratch", "shared_dir", "ship", "table", "text_bytes"]
