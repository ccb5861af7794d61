"""Near-duplicate documents: MinHash signatures and a multi-index Hamming join.

A signature has CHUNKS chunks of LANES symbols of BITS bits. Two signatures that differ in at most
`distance` symbols differ in at most distance // CHUNKS symbols of some chunk (pigeonhole), so each
chunk is indexed under every choice of that many symbols left out: all pairs within the distance
share a key. At a similarity of 0.75 the number of differing symbols is binomial(36, 0.25), and a
distance of 17 misses a pair with a probability below 0.001; more similar pairs fare better.

Rows stay linear in groups of copies. Documents with equal shingle sets collapse into one
representative. In the first round each key links its members to its smallest one only. The second
round takes the keys whose members are then still in different components and settles every pair
there that is within the distance: members meet in cells of bounded size, a first pass on signatures
says which of them have such a pair (each pair is settled at the first key that it shares), and a
second pass compares the full shingle sets of those and gives out only links that join components.
Every link is confirmed on the full shingle sets; pairs are never rows.

Defined results: null text is empty text; a document without words has no shingles and no links; one
with fewer than five words has its whole sequence as its only shingle; a null id is nobody's
representative; rows that repeat an id each give a row; an empty table gives an empty result;
further columns are ignored.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from motifloom.llm import arrays
from motifloom.llm.common import durable, ship, text_bytes
from motifloom.llm.components import components

WIDTH = 5
PERCENT = 75
CHUNKS, LANES, BITS = 9, 4, 15
DISTANCE = 17
#: Members of one leader that meet in one task when links are confirmed.
FAN_OUT = 1024
#: Members of a key, and bytes of their shingle sets, of one side of a cell of the second round.
CELL_ROWS, CELL_BYTES = 2048, 32 << 20

_HASHES = CHUNKS * LANES
_MULTIPLY = np.random.default_rng(7).integers(1, 1 << 63, _HASHES, dtype=np.uint64) | np.uint64(1)
_FLIP = np.random.default_rng(11).integers(0, 1 << 63, _HASHES, dtype=np.uint64)
_CHUNK_NAMES = [f"c{i}" for i in range(CHUNKS)]


def shingle_sets(batch: pa.RecordBatch, column: str = "body"):
    """(rows, sorted distinct shingle hashes, offsets) of slices of a batch."""
    for piece in arrays.slices(batch, column):
        data, offsets = arrays.raw(piece.column(piece.schema.get_field_index(column)))
        h, first = arrays.words(data, offsets)
        yield piece, *arrays.unique_per_text(*arrays.grams(h, first, WIDTH))


def signatures(sets: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """CHUNKS packed integers per text; zeros for a text without shingles."""
    full = np.flatnonzero(np.diff(offsets) > 0)
    out = np.zeros((len(offsets) - 1, CHUNKS), np.int64)
    if len(full):
        for k in range(_HASHES):
            least = np.minimum.reduceat((sets ^ _FLIP[k]) * _MULTIPLY[k], offsets[:-1][full])
            symbol = (arrays.mix(least) >> np.uint64(64 - BITS)).astype(np.int64)
            out[full, k // LANES] |= symbol << np.int64(BITS * (k % LANES))
    return out


def _sums(values: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    total = np.zeros(len(values) + 1, np.uint64)
    np.cumsum(values, out=total[1:])
    return (total[offsets[1:]] - total[offsets[:-1]]).astype(np.int64)


def _sketch(batches):
    for batch in batches:
        for piece, sets, offsets in shingle_sets(batch):
            packed = signatures(sets, offsets)
            yield pa.RecordBatch.from_arrays(
                [piece.column(0), pa.array(np.diff(offsets)), pa.array(_sums(arrays.mix(sets + np.uint64(1)), offsets)), pa.array(_sums(arrays.mix(sets ^ _FLIP[0]), offsets)), *[pa.array(np.ascontiguousarray(packed[:, i])) for i in range(CHUNKS)]],
                names=["doc_id", "n_shingles", "set_a", "set_b", *_CHUNK_NAMES],
            )


def sketches(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, a 128-bit fingerprint of the shingle set (set_a, set_b), signature chunks."""
    ship(docs.sparkSession)
    kinds = ", ".join(f"{c} long" for c in ("doc_id", "n_shingles", "set_a", "set_b", *_CHUNK_NAMES))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_bytes().alias("body")).mapInArrow(_sketch, kinds)


def _masks(errors: int) -> list[int]:
    """Bit masks of a chunk with `errors` of its symbols left out, in every way."""
    from itertools import combinations

    lane = (1 << BITS) - 1
    return [sum(lane << (BITS * i) for i in range(LANES) if i not in out) for out in combinations(range(LANES), errors)]


def key_slots(distance: int = DISTANCE) -> list[tuple[int, int]]:
    """(chunk, mask) of every index key."""
    return [(i, m) for i in range(CHUNKS) for m in _masks(min(LANES - 1, distance // CHUNKS))]


def index_keys(distance: int = DISTANCE) -> Column:
    """All index keys of a row with signature chunks."""
    return F.array(*[F.xxhash64(F.lit(k), F.col(_CHUNK_NAMES[i]).bitwiseAND(F.lit(m))) for k, (i, m) in enumerate(key_slots(distance))])


def differing(left: str, right: str) -> Column:
    """In how many symbols the signatures of two aliased rows differ."""
    low = sum(((1 << (BITS - 1)) - 1) << (BITS * i) for i in range(LANES))
    top = sum((1 << (BITS - 1)) << (BITS * i) for i in range(LANES))
    each = []
    for c in _CHUNK_NAMES:
        x = F.col(f"{left}.{c}").bitwiseXOR(F.col(f"{right}.{c}"))
        each.append(F.bit_count((x.bitwiseAND(F.lit(low)) + F.lit(low)).bitwiseOR(x).bitwiseAND(F.lit(top))))
    return reduce(lambda a, b: a + b, each)


def _sets(batches):
    for batch in batches:
        for piece, sets, offsets in shingle_sets(batch):
            yield pa.RecordBatch.from_arrays([piece.column(0), pa.array([sets[a:b].tobytes() for a, b in zip(offsets, offsets[1:])], pa.binary())], names=["id", "shingles"])


def _confirm(percent: int):
    def run(batches):
        for batch in batches:
            good = []
            for x, y in zip(batch.column(2), batch.column(3)):
                a, b = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                small, large = (a, b) if len(a) <= len(b) else (b, a)
                at = np.searchsorted(large, small)
                at[at == len(large)] = 0
                both = int((large[at] == small).sum()) if len(large) else 0
                good.append(100 * both >= percent * (len(a) + len(b) - both) and both > 0)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], names=["a", "b"]).filter(pa.array(good, pa.bool_()))

    return run


def confirmed(pairs: DataFrame, docs: DataFrame, percent: int = PERCENT) -> DataFrame:
    """Those of the pairs (a, b), a durable frame, whose full shingle sets are similar enough."""
    ids = pairs.select(F.col("a").alias("doc_id")).unionByName(pairs.select(F.col("b").alias("doc_id"))).distinct()
    sets = durable(_set_table(docs, ids))
    fans = pairs.groupBy("b").agg(F.ceil(F.count(F.lit(1)) / FAN_OUT).cast("int").alias("fan"))
    left = pairs.join(sets.withColumnRenamed("id", "a").withColumnRenamed("shingles", "left"), "a").join(fans, "b")
    left = left.withColumn("salt", F.pmod(F.xxhash64("a"), F.col("fan")).cast("int"))
    right = sets.withColumnRenamed("id", "b").withColumnRenamed("shingles", "right").join(fans, "b").withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("fan") - 1)))
    return left.join(right.select("b", "salt", "right"), ["b", "salt"]).select("a", "b", "left", "right").mapInArrow(_confirm(percent), "a long, b long").distinct()


_MEMBER = ["key", "ci", "cj", "slot", "block", "rep", "component", *_CHUNK_NAMES]
_MEMBER_SQL = "key long, ci int, cj int, slot int, block int, rep long, component long, " + ", ".join(f"{c} long" for c in _CHUNK_NAMES)


def _mismatches(left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Differing symbols between every row of left and every row of right (packed chunks)."""
    low = np.int64(sum(((1 << (BITS - 1)) - 1) << (BITS * i) for i in range(LANES)))
    top = np.int64(sum((1 << (BITS - 1)) << (BITS * i) for i in range(LANES)))
    total = np.zeros((len(left), len(right)), np.uint8)
    for c in range(CHUNKS):
        x = left[:, c, None] ^ right[None, :, c]
        total += np.bitwise_count(((x & low) + low | x) & top)
    return total


def _open_pairs(cell: dict[str, np.ndarray], rows: np.ndarray, labels: np.ndarray, distance: int, slots) -> np.ndarray:
    """For some rows of a cell against all: pairs to settle here, as a boolean matrix.

    Settled here are pairs x < y of this cell's two blocks, in different components, within the
    distance, that share no earlier key.
    """
    packed, block, rep = cell["packed"], cell["block"], cell["rep"]
    ok = (rep[rows, None] < rep[None, :]) & (labels[rows, None] != labels[None, :])
    if cell["ci"] != cell["cj"]:
        ok &= block[rows, None] != block[None, :]
    if ok.any():
        ok &= _mismatches(packed[rows], packed) <= distance
    for i, mask in slots[: cell["slot"]]:
        if not ok.any():
            break
        ok &= ((packed[rows, i, None] ^ packed[None, :, i]) & np.int64(mask)) != 0
    return ok


def _cells(batches, extra: tuple[str, ...] = ()):
    """Cells of a partition sorted by key, ci, cj: a dict of arrays each."""
    held: list[pa.RecordBatch] = []
    last = None

    def whole():
        t = pa.Table.from_batches(held)
        get = lambda c: t.column(c).to_numpy()
        out = {"packed": np.stack([get(c) for c in _CHUNK_NAMES], 1), "block": get("block"), "rep": get("rep"), "component": get("component"), "table": t}
        out |= {c: int(t.column(c)[0].as_py()) for c in ("key", "ci", "cj", "slot")}
        return out | {c: t.column(c) for c in extra}

    for batch in batches:
        ids = np.stack([batch.column(batch.schema.get_field_index(c)).to_numpy() for c in ("key", "ci", "cj")], 1)
        cuts = [0, *(np.flatnonzero((ids[1:] != ids[:-1]).any(1)) + 1).tolist(), len(ids)]
        for a, b in zip(cuts, cuts[1:]):
            if a == b:
                continue
            now = tuple(ids[a])
            if last is not None and now != last:
                yield whole()
                held = []
            held.append(batch.slice(a, b - a))
            last = now
    if held:
        yield whole()


def _needed(distance: int):
    slots = key_slots(distance)

    def run(batches):
        for cell in _cells(batches):
            n = len(cell["rep"])
            wanted = np.zeros(n, bool)
            for a in range(0, n, 256):
                rows = np.arange(a, min(a + 256, n))
                ok = _open_pairs(cell, rows, cell["component"], distance, slots)
                wanted[rows] |= ok.any(1)
                wanted |= ok.any(0)
            if wanted.any():
                yield from cell["table"].filter(pa.array(wanted)).select(_MEMBER).combine_chunks().to_batches()

    return run


def _settled(distance: int, percent: int):
    slots = key_slots(distance)

    def run(batches):
        for cell in _cells(batches, ("shingles",)):
            sets = [np.frombuffer(x.as_buffer(), np.uint64) for x in cell["shingles"]]
            sizes = np.array([len(x) for x in sets])
            labels, found = cell["component"].copy(), []
            for i in range(len(sets)):
                ys = np.flatnonzero(_open_pairs(cell, np.array([i]), labels, distance, slots)[0])
                # what can be similar at all: neither set is much larger
                ys = ys[100 * np.minimum(sizes[ys], sizes[i]) >= percent * np.maximum(sizes[ys], sizes[i])]
                if not len(ys):
                    continue
                flat = np.concatenate([sets[y] for y in ys])
                at = np.searchsorted(sets[i], flat)
                at[at == sizes[i]] = 0
                both = np.add.reduceat((sets[i][at] == flat).astype(np.int64), np.concatenate([[0], np.cumsum(sizes[ys])[:-1]]))
                for y in ys[100 * both >= percent * (sizes[i] + sizes[ys] - both)]:
                    if labels[y] != labels[i]:
                        found.append((cell["rep"][y], cell["rep"][i]))
                        labels[labels == labels[y]] = labels[i]
            if found:
                a, b = zip(*found)
                yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

    return run


def _set_table(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """id, shingles (sorted, packed) of the documents with these ids (doc_id)."""
    bodies = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_bytes().alias("body")).join(ids, "doc_id")
    return bodies.select("doc_id", "body").mapInArrow(_sets, "id long, shingles binary")


def settle(shared: DataFrame, named: DataFrame, labels: DataFrame, docs: DataFrame, distance: int, percent: int) -> DataFrame:
    """Links (a, b) between the components that labels leaves, for all pairs of a key within the distance."""
    marked = shared.select("key", "slot", "rep").join(labels.withColumnRenamed("id", "rep"), "rep", "left").withColumn("component", F.coalesce("component", "rep"))
    split = marked.groupBy("key").agg(F.min("component").alias("low"), F.max("component").alias("high")).where("low < high").select("key")
    members = durable(marked.join(split, "key").join(named, "rep"))
    weights = members.groupBy("key").agg(F.greatest(F.ceil(F.count(F.lit(1)) / CELL_ROWS), F.ceil(F.sum("n_shingles") * 8 / CELL_BYTES)).cast("int").alias("blocks"))
    placed = members.join(weights, "key").withColumn("block", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int"))
    placed = placed.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    placed = placed.withColumn("ci", F.least("block", "other")).withColumn("cj", F.greatest("block", "other")).select(*_MEMBER)
    dealt = lambda df: df.repartition("key", "ci", "cj").sortWithinPartitions("key", "ci", "cj", "rep")
    needed = durable(dealt(placed).mapInArrow(_needed(distance), _MEMBER_SQL))
    sets = _set_table(docs, needed.select(F.col("rep").alias("doc_id")).distinct())
    full = needed.join(sets.withColumnRenamed("id", "rep"), "rep")
    return dealt(full.select(*_MEMBER, "shingles")).mapInArrow(_settled(distance, percent), "a long, b long").distinct()


def near_groups(docs: DataFrame, distance: int = DISTANCE, percent: int = PERCENT) -> DataFrame:
    """One row per row of docs: doc_id, n_shingles, component_id, kept, n_same_set."""
    rows = durable(sketches(docs))
    key = ["set_a", "set_b", "n_shingles", *_CHUNK_NAMES]
    reps = durable(rows.where("n_shingles > 0").groupBy(*key).agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("n_same_set")))
    named = reps.where("rep is not null").select("rep", "n_shingles", *_CHUNK_NAMES)
    keys = named.select("rep", F.posexplode(index_keys(distance)).alias("slot", "key"))
    leaders = keys.groupBy("key").agg(F.min("rep").alias("leader"), F.count(F.lit(1)).alias("members")).where("members > 1").select("key", "leader")
    shared = durable(keys.join(leaders, "key"))
    stars = shared.where("rep <> leader").select("rep", "leader").distinct()
    x, y = named.alias("x"), named.alias("y")
    near = stars.alias("s").join(x, F.col("s.rep") == F.col("x.rep")).join(y, F.col("s.leader") == F.col("y.rep"))
    near = durable(near.where(differing("x", "y") <= distance).select(F.col("s.rep").alias("a"), F.col("s.leader").alias("b")))
    first = durable(confirmed(near, docs, percent))
    labels = components(first)
    second = settle(shared, named, labels, docs, distance, percent)
    final = components(first.unionByName(second))

    classes = reps.join(final.withColumnRenamed("id", "rep"), "rep", "left").select(*[F.col(c).alias(f"r_{c}") for c in ("set_a", "set_b", "n_shingles")], F.coalesce("component", "rep").alias("component"), "n_same_set")
    same = [F.col(c) == F.col(f"r_{c}") for c in ("set_a", "set_b", "n_shingles")]
    joined = rows.select("doc_id", "n_shingles", "set_a", "set_b").join(classes, same, "left")
    component = F.when(F.col("n_shingles") > 0, F.col("component")).otherwise(F.col("doc_id"))
    return joined.select("doc_id", "n_shingles", component.alias("component_id"), F.col("doc_id").eqNullSafe(component).alias("kept"), F.coalesce("n_same_set", F.lit(1)).alias("n_same_set"))


def keep_first(docs: DataFrame, **options) -> DataFrame:
    """The rows of docs that stay, one document of each group, with all their columns."""
    kept = near_groups(docs, **options).where("kept").select(F.col("doc_id").alias("__kept_id")).distinct()
    return docs.join(kept, F.col("doc_id").cast("long").eqNullSafe(F.col("__kept_id")), "left_semi")
