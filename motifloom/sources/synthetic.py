"""Synthetic graphs as raw pairs, generated in parallel from spark.range."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def synthetic(spark: SparkSession, kind: str, **size) -> DataFrame:
    """Pairs (a, b): complete, cycle, path, grid, bipartite, uniform (n, p) or powerlaw (n, m, exponent)."""
    if kind in ("complete", "uniform"):
        n = size["n"]
        rows = spark.range(n).select(F.col("id").alias("a"), F.explode(F.sequence(F.col("id") + 1, F.lit(n))).alias("b")).where(F.col("b") < n)
        if kind == "uniform":
            coin = F.pmod(F.xxhash64("a", "b", F.lit(size.get("seed", 0))), F.lit(1_000_000))
            rows = rows.where(coin < int(size["p"] * 1_000_000))
        return rows
    if kind == "cycle":
        return spark.range(size["n"]).select(F.col("id").alias("a"), ((F.col("id") + 1) % size["n"]).alias("b"))
    if kind == "path":
        return spark.range(size["n"] - 1).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    if kind == "grid":
        rows, cols = size["rows"], size["cols"]
        cell = spark.range(rows * cols).select(F.col("id").alias("a"), (F.col("id") % cols).alias("x"))
        right = F.when(F.col("x") < cols - 1, F.col("a") + 1)
        down = F.when(F.col("a") < (rows - 1) * cols, F.col("a") + cols)
        return cell.select("a", F.explode(F.array(right, down)).alias("b")).where("b is not null")
    if kind == "bipartite":
        left, right = size["left"], size["right"]
        return spark.range(left * right).select((F.col("id") % left).alias("a"), (left + F.floor(F.col("id") / left)).alias("b"))
    if kind == "star":
        return spark.range(1, size["n"]).select(F.lit(0).cast("bigint").alias("a"), F.col("id").alias("b"))
    if kind == "powerlaw":
        # both ends of each edge are drawn with probability proportional to rank ** (-1 / (exponent - 1))
        n, m, power = size["n"], size["m"], 1.0 / (size.get("exponent", 2.5) - 1.0)

        def draw(salt: int):
            u = F.pmod(F.xxhash64("id", F.lit(salt), F.lit(size.get("seed", 0))), F.lit(1 << 40)) / float(1 << 40)
            return F.least(F.floor(n * F.pow(u, 1.0 / (1.0 - power))), F.lit(n - 1)).cast("bigint")

        return spark.range(m).select(draw(1).alias("a"), draw(2).alias("b"))
    raise ValueError(kind)
