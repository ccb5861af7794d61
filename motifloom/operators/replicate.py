"""Full replication: every executor holds the arcs that the pattern can use; seeds are dealt round-robin; nothing else moves.

The sorted arcs are written to the shared folder, in rounds of vertices. If it is mounted, one task turns them into arrays there, which the workers
of all executors map; if it is a store, executors fetch the files as they fetch the package, and each makes the arrays on its disk. Neither the
driver nor a worker's heap holds the graph.
"""

from __future__ import annotations

import fcntl
import math
import os
import uuid
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark import SparkFiles
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifloom.functions.kernels import KERNELS, MappedCsr
from motifloom.functions.kernels import count as counted
from motifloom.operators import growth
from motifloom.operators.graph import DataGraph
from motifloom.plans.ir import use_symmetry
from motifloom.plans.optimize import cover_first
from motifloom.plans.pattern import QueryGraph
from motifloom.storage import file_names, local_path, release, scratch, ship, tidy

#: A graph may be replicated up to this size; beyond it the caller has to use another strategy.
BUDGET = 1 << 30
#: Arcs that are sorted at a time.
ROUND_ARCS = 64_000_000
#: Arcs that are read at a time when an executor builds its arrays.
BLOCK = 1 << 20


class GraphTooLarge(ValueError):
    """The graph does not fit the memory budget of one executor."""


def label_pairs(q: QueryGraph) -> list[tuple] | None:
    """The pairs of labels (both ways) that arcs of a match can have; None where a vertex may have any label."""
    if any(q.label(v) is None for v in q.vertices):
        return None
    return sorted({p for a, b in q.edges for p in ((q.label(a), q.label(b)), (q.label(b), q.label(a)))})


def check_size(g: DataGraph, budget: int = BUDGET, q: QueryGraph | None = None) -> None:
    """Counts the arcs that travel, offsets and, where there are any, labels."""
    size = g.estimated_bytes() + (16 * g.stats["n"] if g.has_labels else 0)
    if q is not None and g.has_labels and label_pairs(q):
        size += 8 * sum(g.label_pairs().get(p, 0) for p in label_pairs(q)) - 16 * g.stats["m"]
    if size > budget:
        raise GraphTooLarge(f"the graph takes about {size} bytes, the budget is {budget}")


def held_bytes(g: DataGraph, q: QueryGraph | None = None) -> int:
    """Of the arrays that _build makes: positions of neighbours, ids, offsets and labels in the widths that hold them."""
    pairs = label_pairs(q) if q is not None and g.has_labels else None
    arcs = sum(g.label_pairs().get(p, 0) for p in pairs) if pairs else 2 * g.stats["m"]
    n = sum(g.label_counts().get(x, 0) for x in {a for a, _ in pairs}) if pairs else g.stats["n"]
    ids = 4 if g.ranked and g.stats["n"] < 1 << 31 else 8
    label = _narrow(max((abs(x) for x in g.label_counts() if x is not None), default=0)).itemsize if g.has_labels else 0
    return arcs * (4 if n < 1 << 31 else 8) + n * (ids + _offset(arcs).itemsize + label)


def _refuse(g: DataGraph, q: QueryGraph | None, budget: int) -> None:
    if (size := held_bytes(g, q)) > budget:
        raise GraphTooLarge(f"the graph's arrays take {size} bytes, the budget is {budget}")


def _narrow(most: int) -> np.dtype:
    """The least signed type that holds numbers up to most."""
    return next(np.dtype(k) for k in (np.int8, np.int16, np.int32, np.int64) if most <= np.iinfo(k).max)


def _offset(arcs: int) -> np.dtype:
    """Of offsets into so many arcs, some steps beyond included."""
    return np.dtype(np.uint32 if arcs < (1 << 32) - (1 << 24) else np.int64)


def _place(name: str) -> str:
    """Where an executor finds a file: in the shared folder itself, or where Spark fetched it to."""
    return name if os.path.isabs(name) else SparkFiles.get(name)


def _columns(names: list[str], columns: list[str]):
    """The parts' columns block by block, in the order of the parts."""
    for name in names:
        with pq.ParquetFile(_place(name)) as file:
            for batch in file.iter_batches(BLOCK, columns=columns):
                yield [batch.column(c).to_numpy(zero_copy_only=False) for c in columns]


def _build(names: list[str], folder: str, labelled: bool) -> None:
    """ids, indptr, labels and indices (positions of neighbours) as arrays in folder, from arcs sorted by (u, v)."""
    os.makedirs(folder, exist_ok=True)
    ids, sizes, kinds = [np.empty(0, np.int64)], [np.empty(0, np.int64)], [np.empty(0, np.int64)]
    for u, *more in _columns(names, ["u", "ulabel"] if labelled else ["u"]):
        if not len(u):
            continue
        starts = np.flatnonzero(np.r_[True, u[1:] != u[:-1]])
        some, n = u[starts], np.diff(np.r_[starts, len(u)])
        if len(ids[-1]) and ids[-1][-1] == some[0]:  # a list that goes on in this block
            sizes[-1][-1] += n[0]
            starts, some, n = starts[1:], some[1:], n[1:]
        if len(some):
            ids.append(some)
            sizes.append(n)
            kinds.append(more[0][starts].astype(np.int64) if labelled else kinds[0])
    ids, indptr = np.concatenate(ids), np.concatenate([[0], np.cumsum(np.concatenate(sizes))]).astype(np.int64)
    del sizes
    np.save(f"{folder}/ids.npy", ids.astype(np.int32) if len(ids) and 0 <= ids[0] and ids[-1] < 1 << 31 else ids)
    np.save(f"{folder}/indptr.npy", indptr.astype(_offset(int(indptr[-1]))))
    if labelled:
        kinds = np.concatenate(kinds)
        np.save(f"{folder}/labels.npy", kinds.astype(_narrow(int(np.abs(kinds).max(initial=0)))))
    kind = np.int32 if len(ids) < 1 << 31 else np.int64
    place = None
    if len(ids) and ids[0] >= 0 and ids[-1] < 8 * len(ids) + BLOCK:  # ids are nearly dense: a table instead of searches
        place = np.zeros(ids[-1] + 1, kind)
        place[ids] = np.arange(len(ids), dtype=kind)
    with open(f"{folder}/indices.bin", "wb") as out:
        for (v,) in _columns(names, ["v"]):
            out.write((np.searchsorted(ids, v).astype(kind) if place is None else place[v]).tobytes())


_mapped: dict[str, MappedCsr] = {}


def _csr(token: str, names: list[str], labelled: bool) -> MappedCsr:
    """This executor's arrays, built by the first worker that asks and mapped by all."""
    if token not in _mapped and len(names) == 1 and os.path.isdir(names[0]):
        _mapped[token] = MappedCsr(names[0])
    if token not in _mapped:
        folder = os.path.join(os.path.abspath(SparkFiles.getRootDirectory()), f"replica-{token}")
        with open(f"{folder}.lock", "w") as lock:
            fcntl.flock(lock, fcntl.LOCK_EX)
            if not os.path.exists(f"{folder}/done"):
                _build(names, folder, labelled)
                open(f"{folder}/done", "w").close()
                for name in names:  # the arrays are what this executor needs from now on
                    if not os.path.isabs(name):
                        os.remove(SparkFiles.get(name))
        _mapped[token] = MappedCsr(folder)
    return _mapped[token]


def _local(shared: tuple, q: QueryGraph, kernel: str, symmetry: bool):
    def run(batches):
        csr = _csr(*shared)
        names = [f"v{i}" for i in q.vertices]
        for batch in batches:
            for rows in KERNELS[kernel](csr, q, symmetry, np.sort(batch.column(0).to_numpy())):
                yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(rows[:, i])) for i in range(q.n)], names=names)

    return run


def _number(shared: tuple, q: QueryGraph, kernel: str, symmetry: bool):
    def run(batches):
        csr = _csr(*shared)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array([counted(csr, q, kernel, symmetry, np.sort(batch.column(0).to_numpy()))], pa.int64())], names=["n"])

    return run


def _once(names: list[str], folder: str, labelled: bool):
    def run(batches):
        if any(batch.num_rows for batch in batches):
            _build(names, folder, labelled)
        yield pa.RecordBatch.from_arrays([pa.array([], pa.int64())], names=["id"])

    return run


def _sent(g: DataGraph, path: str, names: list[str]) -> list[str]:
    """Names of files that every executor fetches."""
    for name in names:
        g.spark.sparkContext.addFile(f"{path}/{name}")
    return [os.path.basename(name) for name in names]


def replica(g: DataGraph, budget: int = BUDGET, q: QueryGraph | None = None) -> tuple[str, list[str], bool]:
    """What an executor needs to hold the graph, or the arcs that q can use, at most `budget` bytes: token, folder of the arrays or names of files, labelled."""
    _refuse(g, q, budget)
    pairs = label_pairs(q) if q is not None and g.has_labels else None
    key = ("replica", tuple(pairs) if pairs else None)
    if key not in g._kept:
        ship(g.spark)
        arcs = g.arcs
        if g.directed:
            back = arcs.select(F.col("v").alias("u"), F.col("u").alias("v"), "elabel", F.col("vlabel").alias("ulabel"), F.col("ulabel").alias("vlabel"))
            arcs = arcs.unionByName(back).dropDuplicates(["u", "v"])
        if pairs:
            arcs = arcs.where(reduce(lambda x, y: x | y, [(F.col("ulabel") == a) & (F.col("vlabel") == b) for a, b in pairs]))
        label = [F.coalesce(F.col("ulabel").cast("bigint"), F.lit(-1)).alias("ulabel")] if g.has_labels else []
        arcs, rounds = arcs.select("u", "v", *label), math.ceil(held_bytes(g, q) / 4 / ROUND_ARCS)
        cuts = sorted({*(arcs.agg(F.percentile_approx("u", [k / rounds for k in range(1, rounds)])).first()[0] or [])}) if rounds > 1 else []
        path, names = scratch(g.spark, "replica"), []
        for k, (low, high) in enumerate(zip([None, *cuts], [*cuts, None])):
            some = arcs if low is None else arcs.where(F.col("u") > low)
            some = some if high is None else some.where(F.col("u") <= high)
            some.repartitionByRange("u", "v").sortWithinPartitions("u", "v").write.option("compression", "zstd").parquet(f"{path}/{k}")
            release(g.spark)
            names += [f"{k}/{name}" for name in file_names(g.spark, f"{path}/{k}")]
        if folder := local_path(g.spark, path):
            arrays = local_path(g.spark, scratch(g.spark, "arrays"))
            g.spark.range(0, 1, 1, 1).mapInArrow(_once([f"{folder}/{name}" for name in names], arrays, g.has_labels), "id long").collect()
            tidy(g.spark, [path])
            names = [arrays]
        else:
            names = _sent(g, path, names)
        g._kept[key] = (uuid.uuid4().hex, names, g.has_labels)
    return g._kept[key]


def run(g: DataGraph, q: QueryGraph, *, kernel: str = "cover", execution: str = "kernel", partitions: int = 0, budget: int = BUDGET, symmetry: str = "auto", **refused) -> DataFrame:
    """Matches v1..vn. execution: kernel (arrays in Arrow functions) or broadcast_join (growth with broadcast lists)."""
    if refused:
        raise ValueError(f"not useful for replication: {', '.join(refused)}")
    if execution == "broadcast_join" or q.directed or q.elabels:
        check_size(g, budget, q)
        return growth.run(g, q, symmetry=symmetry, hint="broadcast").select(*[f"v{v}" for v in q.vertices])
    schema = ", ".join(f"v{v} long" for v in q.vertices)
    return _seeds(g, q, partitions).mapInArrow(_local(replica(g, budget, q), q, kernel, use_symmetry(q, symmetry)), schema)


def count(g: DataGraph, q: QueryGraph, *, kernel: str = "cover", partitions: int = 0, budget: int = BUDGET, symmetry: str = "auto") -> DataFrame:
    """One row, column matches: the tasks count, and send a number per batch of seeds."""
    if q.directed or q.elabels:
        return run(g, q, symmetry=symmetry).agg(F.count(F.lit(1)).alias("matches"))
    parts = _seeds(g, q, partitions).mapInArrow(_number(replica(g, budget, q), q, kernel, use_symmetry(q, symmetry)), "n long")
    return parts.agg(F.coalesce(F.sum("n"), F.lit(0)).cast("bigint").alias("matches"))


def _seeds(g: DataGraph, q: QueryGraph, partitions: int) -> DataFrame:
    """id of every vertex that the first query vertex of the cover order can take, dealt round-robin."""
    first = cover_first(q)[0]
    seeds = g.vertices.select("id") if q.label(first) is None else g.vertices.where(F.col("label") == q.label(first)).select("id")
    p = partitions or int(g.spark.conf.get("spark.sql.shuffle.partitions"))
    return seeds.repartition(p, F.pmod("id", F.lit(p)))
