"""Exact deduplication with compressed radix tries.

Texts are dealt by length and content hash. Each map task first merges its own copies in a trie, so
a text crosses the shuffle once per map task however often it occurs; each reduce task merges what
it was dealt into one trie. A terminal node holds the surviving identifier and the number of rows.
When a trie outgrows its memory budget its largest subtree moves to a file private to the task
attempt, which is reread as a trie of its own afterwards; a retried task starts afresh.

Defined results: null text is empty text; texts are equal when identical after lower-casing A-Z;
every input row gives one output row (rows repeating an id too: all those with the surviving id are
kept); a null id survives only when its group has no other; an empty table gives an empty result;
further columns are ignored.
"""

from __future__ import annotations

import hashlib
import pickle
import tempfile
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifloom.llm.common import ship, text_bytes

MEMORY = 64 << 20


def _shared(key: bytes, at: int, label: bytes) -> int:
    """Length of the common prefix of key[at:] and label."""
    low, high = 0, min(len(label), len(key) - at)
    while low < high:
        middle = (low + high + 1) // 2
        if key[at : at + middle] == label[:middle]:
            low = middle
        else:
            high = middle - 1
    return low


class _Node:
    __slots__ = ("label", "children", "best", "rows")

    def __init__(self, label: bytes, best=None, rows: int = 0):
        self.label, self.children, self.best, self.rows = label, None, best, rows


class _Run:
    """A subtree that was moved to a file: entries and the prefix they share."""

    def __init__(self, prefix: bytes):
        self.file, self.prefix = tempfile.TemporaryFile(), prefix

    def add(self, key: bytes, best, rows: int) -> None:
        self.prefix = self.prefix[: _shared(key, 0, self.prefix)]
        pickle.dump((key, best, rows), self.file)

    def entries(self):
        self.file.seek(0)
        try:
            while True:
                yield pickle.load(self.file)
        except EOFError:
            self.file.close()


class PatriciaTrie:
    """A radix trie over byte strings that merges (identifier, rows) at equal strings."""

    def __init__(self, largest: bool, memory: int = MEMORY, prefix: bytes = b""):
        self.pick = max if largest else min
        self.memory, self.prefix, self.held = memory, prefix, 0
        self.root = _Node(b"")
        self.weight: dict[int, int] = {}
        self.runs: dict[int, _Run] = {}
        self.spills = 0

    def _merge(self, node: _Node, best, rows: int) -> None:
        node.best = best if node.best is None else node.best if best is None else self.pick(node.best, best)
        node.rows += rows

    def add(self, key: bytes, best, rows: int = 1) -> None:
        """key must start with the trie's prefix."""
        self._insert(key, best, rows)
        if self.held > self.memory and self.weight:  # only now is the tree whole
            self._spill(max(self.weight, key=self.weight.__getitem__))

    def _insert(self, key: bytes, best, rows: int) -> None:
        at, node = len(self.prefix), self.root
        if at < len(key) and key[at] in self.runs:
            self.runs[key[at]].add(key, best, rows)
            return
        while at < len(key):
            head = key[at]
            child = node.children.get(head) if node.children else None
            if child is None:
                if node.children is None:
                    node.children = {}
                node.children[head] = _Node(key[at:], best, rows)
                self._grown(key, len(key) - at + 200)
                return
            same = len(child.label) if key.startswith(child.label, at) else _shared(key, at, child.label)
            if same < len(child.label):
                upper = _Node(child.label[:same])
                child.label = child.label[same:]
                upper.children = {child.label[0]: child}
                node.children[head] = upper
                self._grown(key, 200)
                child = upper
            at += same
            node = child
        self._merge(node, best, rows)

    def _grown(self, key: bytes, size: int) -> None:
        head = key[len(self.prefix)]
        self.weight[head] = self.weight.get(head, 0) + size
        self.held += size

    def _spill(self, head: int) -> None:
        node = self.root.children.pop(head)
        run = _Run(self.prefix + node.label)
        for key, best, rows in self._below(node, self.prefix):
            run.add(key, best, rows)
        self.runs[head] = run
        self.held -= self.weight.pop(head)
        self.spills += 1

    @staticmethod
    def _below(node: _Node, before: bytes):
        stack = [(node, before)]
        while stack:
            node, before = stack.pop()
            key = before + node.label
            if node.rows:
                yield key, node.best, node.rows
            stack.extend((child, key) for child in (node.children or {}).values())

    def items(self) -> Iterator[tuple[bytes, object, int]]:
        """All strings with their survivor and row count, each once."""
        yield from self._below(self.root, self.prefix)
        self.root, self.held = _Node(b""), 0
        for run in self.runs.values():
            below = PatriciaTrie(self.pick is max, self.memory, run.prefix)
            for entry in run.entries():
                below.add(*entry)
            yield from below.items()


def _batches(rows: Iterator[tuple], schema: pa.Schema, size: int = 4 << 20):
    held, weight = [], 0
    for row in rows:
        held.append(row)
        weight += 64 + sum(len(x) for x in row if isinstance(x, bytes))
        if weight > size:
            yield pa.RecordBatch.from_arrays([pa.array(c, t.type) for c, t in zip(zip(*held), schema)], schema=schema)
            held, weight = [], 0
    if held:
        yield pa.RecordBatch.from_arrays([pa.array(c, t.type) for c, t in zip(zip(*held), schema)], schema=schema)


_LOCAL = pa.schema([("n_bytes", pa.int64()), ("content_hash", pa.int64()), ("body", pa.binary()), ("best", pa.int64()), ("n_rows", pa.int64())])
_GROUP = pa.schema([("digest", pa.binary()), ("n_bytes", pa.int64()), ("best", pa.int64()), ("n_rows", pa.int64())])
_MEMBER = pa.schema([("doc_id", pa.int64()), ("digest", pa.binary())])


def _hash(body: bytes) -> int:
    return int.from_bytes(hashlib.sha256(body).digest()[:8], "big", signed=True)


def _local_tries(largest: bool, memory: int):
    def run(batches):
        trie = PatriciaTrie(largest, memory)
        for batch in batches:
            for i, body in zip(batch.column(0).to_pylist(), batch.column(1)):
                trie.add(body.as_py().lower(), i)
        yield from _batches(((len(k), _hash(k), k, best, n) for k, best, n in trie.items()), _LOCAL)

    return run


def _merged_tries(largest: bool, memory: int):
    def run(batches):
        trie = PatriciaTrie(largest, memory)
        for batch in batches:
            for body, best, n in zip(batch.column(0), batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                trie.add(body.as_py(), best, n)
        yield from _batches(((hashlib.sha256(k).digest(), len(k), best, n) for k, best, n in trie.items()), _GROUP)

    return run


def _members(batches):
    for batch in batches:
        digests = [hashlib.sha256(x.as_py().lower()).digest() for x in batch.column(1)]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(digests, pa.binary())], schema=_MEMBER)


def text_groups(docs: DataFrame, keep: str = "smallest", memory: int = MEMORY) -> DataFrame:
    """One row per different text: digest, n_bytes, best (surviving id), n_rows."""
    ship(docs.sparkSession)
    largest = {"smallest": False, "largest": True}[keep]
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_bytes().alias("body"))
    local = texts.mapInArrow(_local_tries(largest, memory), "n_bytes long, content_hash long, body binary, best long, n_rows long")
    return local.repartition("n_bytes", "content_hash").select("body", "best", "n_rows").mapInArrow(_merged_tries(largest, memory), "digest binary, n_bytes long, best long, n_rows long")


def exact_dedup(docs: DataFrame, keep: str = "smallest", memory: int = MEMORY) -> DataFrame:
    """One row per row of docs: doc_id, keep_id, group_size, kept, text_sha256, n_bytes."""
    groups = text_groups(docs, keep, memory)
    members = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_bytes().alias("body")).mapInArrow(_members, "doc_id long, digest binary")
    return members.join(groups, "digest").select(
        "doc_id",
        F.col("best").alias("keep_id"),
        F.col("n_rows").alias("group_size"),
        F.col("doc_id").eqNullSafe(F.col("best")).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
        "n_bytes",
    )
