"""Vectorised functions for SQL users: intersection sizes, local counts, combinations, local matches."""

from __future__ import annotations

from itertools import combinations as choose

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from motifloom.functions.kernels import Csr, cover
from motifloom.plans.pattern import QueryGraph


def _ids(name: str) -> T.StructType:
    return T.StructType([T.StructField(name, T.ArrayType(T.LongType()))])


@F.pandas_udf(T.LongType())
def sorted_intersect_size(a: pd.Series, b: pd.Series) -> pd.Series:
    """How many values two ascending arrays share."""
    return pd.Series([0 if x is None or y is None else len(np.intersect1d(x, y, assume_unique=True)) for x, y in zip(a, b)])


def local_count(edges: DataFrame, key: str, pattern: str) -> DataFrame:
    """key, matches: how often a pattern occurs in each group's own edges (u, v)."""
    q = QueryGraph.parse(pattern)

    def count(name: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        u, v = rows["u"].to_numpy(), rows["v"].to_numpy()
        csr = Csr(np.concatenate([u, v]), np.concatenate([v, u]))
        return pd.DataFrame({key: [name[0]], "matches": [sum(len(x) for x in cover(csr, q, True))]})

    return edges.select(key, "u", "v").groupBy(key).applyInPandas(count, f"{key} long, matches long")


@F.udtf(returnType=_ids("members"))
class Combinations:
    """All k-element subsets of an array, in order."""

    def eval(self, values: list, k: int):
        for c in choose(values, k):
            yield (list(c),)


@F.udtf(returnType=_ids("match"))
class LocalMatches:
    """Matches of a pattern text in an array of edge structs (two ids each)."""

    def eval(self, pattern: str, edges: list):
        q = QueryGraph.parse(pattern)
        u = np.array([e[0] for e in edges], np.int64)
        v = np.array([e[1] for e in edges], np.int64)
        for rows in cover(Csr(np.concatenate([u, v]), np.concatenate([v, u])), q, True):
            for r in rows.tolist():
                yield (r,)


def register(spark: SparkSession) -> None:
    spark.udtf.register("combinations", Combinations)
    spark.udtf.register("local_matches", LocalMatches)
    spark.udf.register("sorted_intersect_size", sorted_intersect_size)
