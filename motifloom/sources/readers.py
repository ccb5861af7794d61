"""Edge lists from files, and sinks for adjacency and matches."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", src: str = "src", dst: str = "dst", label: str | None = None, sep: str = " ") -> DataFrame:
    """Raw pairs (a, b[, elabel]) of a CSV, text, JSON or Parquet edge list.

    Text lines read `src dst [label]`; lines that start with # are comments.
    """
    if fmt == "text":
        parts = F.split(F.trim("value"), r"\s+")
        rows = spark.read.text(path).where(~F.col("value").startswith("#")).where(F.trim("value") != "").select(F.get(parts, F.lit(0)).alias("a"), F.get(parts, F.lit(1)).alias("b"), F.get(parts, F.lit(2)).cast("int").alias("elabel"))
        number = [F.col(c).cast("bigint").alias(c) for c in ("a", "b")]
        return rows.select(*number, "elabel")
    if fmt == "csv":
        schema = f"{src} bigint, {dst} bigint" + (f", {label} int" if label else "")
        rows = spark.read.csv(path, schema=schema, header=True, sep=sep)
    elif fmt == "json":
        rows = spark.read.json(path, schema=f"{src} bigint, {dst} bigint" + (f", {label} int" if label else ""))
    else:
        rows = spark.read.format(fmt).load(path)
    return rows.select(F.col(src).alias("a"), F.col(dst).alias("b"), *([F.col(label).cast("int").alias("elabel")] if label else []))


def write_matches(matches: DataFrame, path: str, batch: int | None = None, fmt: str = "parquet") -> None:
    """Appends matches (plain or compressed); a batch number becomes a partition column."""
    out = matches if batch is None else matches.withColumn("batch", F.lit(batch))
    writer = out.write.mode("append").format(fmt)
    (writer.partitionBy("batch") if batch is not None else writer).save(path)


def write_adjacency(adjacency: DataFrame, name: str, buckets: int) -> None:
    """Saves adjacency as a table bucketed by vertex, so that later joins on it move only the other side."""
    adjacency.write.mode("overwrite").bucketBy(buckets, "u").sortBy("u").saveAsTable(name)


def read_adjacency(g, name: str) -> None:
    """Makes a graph take its unlabelled neighbour lists from a table that write_adjacency saved."""
    g._kept[("adj", None, None, None, False, g.chunk)] = g.spark.table(name).select("u", "nbrs")
