"""Batching: one partial result after the other, so that peak memory and shuffle follow the batch."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass
from functools import reduce

from py4j.protocol import Py4JError
from pyspark.errors import PySparkException
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifloom.plans.ir import JoinNode, UnitNode
from motifloom.plans.optimize import batch_vertex
from motifloom.storage import durable, meet, scratch

#: What an error says when a job failed for want of memory; others are no reason to shrink batches.
_MEMORY = ("OutOfMemory", "GC overhead", "Java heap space", "Cannot grow BufferHolder", "UnsafeRow", "MemoryError", "exceeding memory limits")


@dataclass(frozen=True)
class BatchSpec:
    """size: partial results per batch; min_size: how far it may shrink when memory fails."""

    size: int = 1_000_000
    min_size: int = 1_000
    #: For units without the batch vertex: keep them (cache) or build them again (recompute).
    miss: str = "cache"
    #: At most so many batches come out of an estimate, as each is a job.
    most: int = 256

    def batches(self, estimate: float) -> int:
        """How many batches an estimated number of partial results makes."""
        return min(self.most, max(1, math.ceil(estimate / self.size)))


def pick_binary(plan: JoinNode | UnitNode) -> int:
    return batch_vertex(plan)


def union(make: Callable[[int, int], DataFrame], batches: int) -> DataFrame:
    """All batches as one lazy frame."""
    return reduce(DataFrame.unionByName, [make(k, batches) for k in range(batches)])


def out_of_memory(error: Exception) -> bool:
    return any(sign in str(error) for sign in _MEMORY)


def _shrinking(run: Callable[[int], object], batches: int, spec: BatchSpec):
    """run(batches), again with twice as many when memory fails, down to batches of min_size."""
    size = spec.size
    while True:
        try:
            return run(batches)
        except (Py4JError, PySparkException) as error:
            size //= 2
            if size < spec.min_size or not out_of_memory(error):
                raise
            batches *= 2


def write(make: Callable[[int, int], DataFrame], batches: int, path: str, done: Callable[[int], bool] | None = None) -> None:
    """One job per batch, appended under its own partition; batches that are done already are skipped."""
    for k in range(batches):
        if done is None or not done(k):
            make(k, batches).write.mode("overwrite").parquet(f"{path}/batch={k}")


def in_turn(make: Callable[[int, int], DataFrame], batches: int, spec: BatchSpec | None = None) -> DataFrame:
    """All batches, each computed and written before the next one starts; read back from the shared folder."""

    def run(b: int) -> DataFrame:
        first = make(0, b)
        path = scratch(first.sparkSession, "batches")
        write(lambda k, n: first if k == 0 else make(k, n), b, path)
        return first.sparkSession.read.schema(first.schema).parquet(*[f"{path}/batch={k}" for k in range(b)])

    return _shrinking(run, batches, spec or BatchSpec())


def total(make: Callable[[int, int], DataFrame], batches: int, spec: BatchSpec | None = None) -> int:
    """Sum over batches of the one-row frames that make gives, one job after the other."""
    return _shrinking(lambda b: sum(make(k, b).first()[0] for k in range(b)), batches, spec or BatchSpec())


def hash_range_join(left: DataFrame, right: DataFrame, keys: list[str], ranges: int, hint: str | None = None, in_order: bool = False) -> DataFrame:
    """A join in `ranges` parts by the hash of its key, each part a join of its own.

    With in_order both sides are kept once and the parts run one after the other: the memory of the join
    is that of one range.
    """
    part = lambda df, k: df.where(F.pmod(F.xxhash64(*keys), F.lit(ranges)) == k)
    if in_order and ranges > 1:
        left, right = durable(left), durable(right)
        return in_turn(lambda k, b: meet(part(left, k), part(right, k), keys, hint), ranges)
    return reduce(DataFrame.unionByName, [meet(part(left, k), part(right, k), keys, hint) for k in range(ranges)])
