"""Benchmark decontamination by greedy string tiling.

Words are runs of letters and digits, lower-cased; a seed is a run of SEED words. Seeds of the
benchmark are joined to those of every document by rolling hash. For each document and item that
share seeds, the longest run of equal words that is still unmarked on both sides is marked, again
and again, until no run of SEED words is left: tiles never overlap and may lie in any order, so
reordered passages count as well. A document is contaminated by an item when its tiles cover at
least `coverage` of the item's words.

The benchmark's seed index is broadcast in blocks of at most INDEX_WORDS words; a larger benchmark
takes more blocks, each of which sees all documents. Documents never move.

Defined results: null text is empty text; an item of fewer than SEED words has no seeds and
contaminates nothing; null items or texts are skipped; repeated items count once per id; every input
row gives one output row, repeated ones too; an empty benchmark leaves every document clean; an empty
table gives an empty result; further columns are ignored, whatever their names; texts of any length are
read whole, in slices of bounded size.
"""

from __future__ import annotations

import heapq
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifloom.llm import arrays
from motifloom.llm.common import ship, text_bytes
from motifloom.llm.mixing import word_count

SEED = 5
COVERAGE = 0.5
INDEX_WORDS = 4_000_000
_FILTER_BITS = 22


class SeedIndex:
    """Seeds of a block of benchmark items."""

    def __init__(self, items: list[tuple[int, bytes]], seed: int = SEED):
        self.seed = seed
        self.ids = [i for i, _ in items]
        body = pa.array([t for _, t in items], pa.binary())
        self.words, self.first = arrays.words(*arrays.raw(body), arrays.PUNCTUATION) if items else (np.empty(0, np.uint64), np.zeros(1, np.int64))
        g, offsets = arrays.grams(self.words, self.first, seed, shorts=False)
        owner = np.repeat(np.arange(len(items)), np.diff(offsets))
        order = np.argsort(g, kind="stable")
        self.seeds, self.item, self.place = g[order], owner[order], (np.arange(len(g)) - offsets[:-1][owner])[order]
        self.filter = np.zeros(1 << _FILTER_BITS, bool)
        self.filter[self.seeds >> np.uint64(64 - _FILTER_BITS)] = True

    def size(self, item: int) -> int:
        return int(self.first[item + 1] - self.first[item])

    def hits(self, grams: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Pairs (index into grams, index into seeds) with equal hashes."""
        near = np.flatnonzero(self.filter[grams >> np.uint64(64 - _FILTER_BITS)])
        low, high = np.searchsorted(self.seeds, grams[near], "left"), np.searchsorted(self.seeds, grams[near], "right")
        times = high - low
        return np.repeat(near, times), np.repeat(low, times) + (np.arange(times.sum()) - np.repeat(np.cumsum(times) - times, times))


def tile(places: np.ndarray, spots: np.ndarray, seed: int, item_words: np.ndarray, text_words: np.ndarray) -> int:
    """How many words of an item greedy tiles cover, given where its seeds meet those of a text."""
    runs: list[tuple[int, int, int]] = []
    order = np.lexsort((places, spots - places))
    p, t = places[order], spots[order]
    ends = np.flatnonzero((np.diff(p) != 1) | (np.diff(t) != 1))
    for a, b in zip([0, *(ends + 1)], [*ends, len(p) - 1]):
        n = int(b - a) + seed
        if np.array_equal(item_words[p[a] : p[a] + n], text_words[t[a] : t[a] + n]):  # a rolling hash may collide
            runs.append((-n, int(p[a]), int(t[a])))
    heapq.heapify(runs)
    in_item, in_text = np.zeros(len(item_words), bool), defaultdict(bool)
    while runs:
        n, p0, t0 = heapq.heappop(runs)
        free = [not in_item[p0 + k] and not in_text[t0 + k] for k in range(-n)]
        if all(free):
            in_item[p0 : p0 - n] = True
            in_text.update((t0 + k, True) for k in range(-n))
            continue
        start = None
        for k in range(-n + 1):  # what is left of the run competes again
            if k < -n and free[k]:
                start = k if start is None else start
            elif start is not None:
                if k - start >= seed:
                    heapq.heappush(runs, (start - k, p0 + start, t0 + start))
                start = None
    return int(in_item.sum())


def _tiler(shared, coverage: float):
    def run(batches):
        index: SeedIndex = shared.value
        for batch in batches:
            at_items, at_best = batch.schema.get_field_index("items"), batch.schema.get_field_index("best_coverage")
            items, best = batch.column(at_items).to_pylist(), batch.column(at_best).to_pylist()
            row = 0
            for piece in arrays.slices(batch, "body"):
                h, first = arrays.words(*arrays.raw(piece.column(piece.schema.get_field_index("body"))), arrays.PUNCTUATION)
                g, offsets = arrays.grams(h, first, index.seed, shorts=False)
                gram, seed = index.hits(g)
                owner = np.searchsorted(offsets, gram, "right") - 1
                key = owner * len(index.ids) + index.item[seed]
                order = np.argsort(key, kind="stable")
                cuts = np.flatnonzero(np.diff(key[order])) + 1
                for group in np.split(order, cuts) if len(order) else []:
                    i, doc = int(index.item[seed[group[0]]]), int(owner[group[0]])
                    need = index.size(i)
                    covered = tile(index.place[seed[group]], gram[group] - offsets[doc], index.seed, index.words[index.first[i] : index.first[i + 1]], h[first[doc] : first[doc + 1]])
                    best[row + doc] = max(best[row + doc], covered / need)
                    if covered >= coverage * need:
                        items[row + doc] = sorted({*items[row + doc], index.ids[i]})
                row += len(piece)
            columns = list(batch.columns)
            columns[at_items], columns[at_best] = pa.array(items, pa.list_(pa.int64())), pa.array(best, pa.float64())
            yield pa.RecordBatch.from_arrays(columns, names=batch.schema.names)

    return run


def _tiled(rows: DataFrame, benchmark: DataFrame, coverage: float, seed: int, index_words: int) -> DataFrame:
    """rows (…, body) -> the same with items and best_coverage."""
    spark = rows.sparkSession
    ship(spark)
    valid = benchmark.where("item_id is not null and text is not null").select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text"))
    total = valid.agg(F.sum(word_count())).first()[0] or 0
    blocks = max(1, -(-total // index_words))
    rows = rows.withColumn("items", F.array().cast("array<bigint>")).withColumn("best_coverage", F.lit(0.0))
    kind = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields)
    for k in range(blocks):
        block = valid.where(F.pmod(F.xxhash64("item_id"), F.lit(blocks)) == k).orderBy("item_id", "text")
        items = [(r[0], r[1].encode()) for r in block.collect()]  # about index_words words
        rows = rows.mapInArrow(_tiler(spark.sparkContext.broadcast(SeedIndex(items, seed)), coverage), kind)
    return rows


def contamination(docs: DataFrame, benchmark: DataFrame, coverage: float = COVERAGE, seed: int = SEED, index_words: int = INDEX_WORDS) -> DataFrame:
    """One row per row of docs: doc_id, contaminated, n_items, items (ids, ascending), best_coverage."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_bytes().alias("body"))
    found = _tiled(rows, benchmark, coverage, seed, index_words)
    return found.select("doc_id", (F.size("items") > 0).alias("contaminated"), F.size("items").cast("long").alias("n_items"), "items", "best_coverage")


def keep_clean(docs: DataFrame, benchmark: DataFrame, coverage: float = COVERAGE, seed: int = SEED, index_words: int = INDEX_WORDS) -> DataFrame:
    """The rows of docs that no item contaminates, with all their columns."""
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), text_bytes().alias("body"))
    return _tiled(rows, benchmark, coverage, seed, index_words).where(F.size("items") == 0).select("row.*")
