"""Line deduplication by a deletion-neighbourhood join, in DataFrame functions only.

A line occurrence is dropped when an equal line, or one within one character edit, occurs earlier in
the corpus (by document id, then position), however short or long it is. Blank lines always stay.

Equal lines meet by a 128-bit hash. For near lines, every line that can have a partner emits its
deletion neighbourhood as hashed keys: the line itself and all variants with one character deleted;
equal variants are joined and the edit distance is verified. Two exact devices keep this small:

* One edit leaves the first or the last half of the shorter line as it was, so each line has four
  half keys (its own length's and the next shorter one's); a line whose half keys nobody shares has
  no partner and emits nothing.
* A line is cut into blocks, counted by the shorter line of a pair; the edit lies in one block, so two
  lines within one edit share what stands before and after it. A variant's key is the hash of all
  before, the varied block, and all after, and only blocks whose surroundings another line shares
  emit their variants. A line has at most MAX_BLOCKS blocks, so long lines cost in proportion.

Defined results: null text is empty text (one blank line); a null id comes last, and lines that only
documents without id have all stay; rows repeating an id count as one place and give a row each; an
empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from motifloom.llm.common import durable

#: Shortest line that takes part in the join: every line that is not blank.
MIN_LENGTH = 1
BLOCK, MAX_BLOCKS = 32, 64
#: Up to so many rows of ids are broadcast; beyond that they are joined by a shuffle.
BROADCAST_ROWS = 100_000
_POSITIONS = 1 << 32


def lines(docs: DataFrame) -> DataFrame:
    """doc_id, pos, line, place (a number that orders all occurrences)."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.posexplode(F.split(text, "\n", -1)).alias("pos", "line"))
    return rows.withColumn("place", (F.col("doc_id").cast("decimal(20,0)") * F.lit(_POSITIONS).cast("decimal(11,0)") + F.col("pos")).cast("decimal(32,0)"))


def _identity() -> list[Column]:
    return [F.xxhash64("line").alias("h1"), F.xxhash64(F.lit(1), F.col("line")).alias("h2")]


def _half_keys() -> list[Column]:
    """Four hashes of a line's halves, null where it is too short."""
    n, keys = F.length("line"), []
    for i, shorter in enumerate((n, n - 1)):
        half = F.floor(shorter / 2).cast("int")
        keys.append(F.when(n >= MIN_LENGTH, F.xxhash64(F.lit(0), shorter, F.left("line", half))).alias(f"k{2 * i}"))
        keys.append(F.when(n >= MIN_LENGTH, F.xxhash64(F.lit(1), shorter, F.right("line", shorter - half))).alias(f"k{2 * i + 1}"))
    return keys


def distinct_lines(docs: DataFrame) -> DataFrame:
    """h1, h2, first (the earliest place), n_rows, half keys k0 to k3 of every different line that is not blank."""
    rows = lines(docs).where(F.trim("line") != "").select("place", *_identity(), *_half_keys())
    return rows.groupBy("h1", "h2").agg(F.min("place").alias("first"), F.count(F.lit(1)).alias("n_rows"), *[F.min(f"k{i}").alias(f"k{i}") for i in range(4)])


def partnered(distinct: DataFrame) -> DataFrame:
    """h1, h2, first of the lines that share a half key with another line."""
    keys = distinct.where("k0 is not null").select("h1", "h2", "first", F.explode(F.array("k0", "k1", "k2", "k3")).alias("key"))
    shared = keys.groupBy("key").agg(F.min("h1").alias("low"), F.max("h1").alias("high")).where("low < high").select("key")
    return keys.join(shared, "key", "left_semi").select("h1", "h2", "first").distinct()


def blocks(line: Column) -> Column:
    """array<struct<shorter, place, around, block, whole>>: a line's blocks on its own and the next shorter grid.

    around says which blocks can hold the only difference of two lines: equal length of the shorter
    line, equal place, equal text before and after.
    """

    def grid(shorter: Column, extra: int, whole: bool) -> Column:
        width = F.greatest(F.lit(BLOCK), F.ceil(shorter / MAX_BLOCKS)).cast("int")

        def block(b):
            start = (b * width).cast("int")
            size = F.when(start + width >= shorter, F.length(line) - start).otherwise(width + extra).cast("int")
            around = F.xxhash64(shorter, b, F.left(line, start), F.lit(0), F.substring(line, start + size + 1, F.length(line)))
            return F.struct(around.alias("around"), F.substring(line, start + 1, size).alias("block"), F.lit(whole).alias("whole"))

        return F.transform(F.sequence(F.lit(0), F.floor(F.greatest(shorter - 1, F.lit(0)) / width).cast("int")), block)

    n = F.length(line)
    return F.concat(grid(n, 0, True), grid(n - 1, 1, False))


def variants(around: Column, block: Column, whole: Column) -> Column:
    """Hashed keys of a block with one character deleted, and of the block itself on the line's own grid."""
    n = F.length(block)
    varied = F.transform(F.sequence(F.lit(1), n), lambda i: F.xxhash64(around, F.concat(F.substring(block, F.lit(1), i - 1), F.substring(block, i + 1, n))))
    return F.array_distinct(F.concat(varied, F.when(whole, F.array(F.xxhash64(around, block))).otherwise(F.array().cast("array<bigint>"))))


def near_lines(docs: DataFrame, distinct: DataFrame) -> DataFrame:
    """h1, h2 of the lines that have an earlier line within one edit."""
    able = durable(partnered(distinct))
    wanted = able.select("h1", "h2", "first", F.floor(F.col("first") / F.lit(_POSITIONS).cast("decimal(11,0)")).cast("long").alias("doc_id"), F.pmod("first", F.lit(_POSITIONS).cast("decimal(11,0)")).cast("int").alias("pos"))
    if able.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS:
        wanted = F.broadcast(wanted)
    text = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(wanted, "doc_id")
    found = text.select("h1", "h2", "first", F.get(F.split("text", "\n", -1), F.col("pos")).alias("line")).distinct()
    found = durable(found)
    cut = found.select("h1", "h2", "first", F.explode(blocks(F.col("line"))).alias("c")).select("h1", "h2", "first", "c.around", "c.block", "c.whole")
    met = cut.groupBy("around").agg(F.min("h1").alias("low"), F.max("h1").alias("high")).where("low < high").select("around")
    keyed = cut.join(met, "around", "left_semi").select("h1", "h2", "first", F.explode(variants(F.col("around"), F.col("block"), F.col("whole"))).alias("key"))
    keyed = durable(keyed)
    a, b = keyed.alias("a"), keyed.alias("b")
    pairs = a.join(b, (F.col("a.key") == F.col("b.key")) & (F.col("a.first") > F.col("b.first"))).select(*[F.col(f"{t}.{c}").alias(f"{t}_{c}") for t in "ab" for c in ("h1", "h2")]).distinct()
    left, right = found.alias("x"), found.alias("y")
    texts = pairs.join(left, (F.col("a_h1") == F.col("x.h1")) & (F.col("a_h2") == F.col("x.h2"))).join(right, (F.col("b_h1") == F.col("y.h1")) & (F.col("b_h2") == F.col("y.h2")))
    close = texts.where(F.levenshtein(F.col("x.line"), F.col("y.line"), 1).between(0, 1))
    return close.select(F.col("a_h1").alias("h1"), F.col("a_h2").alias("h2")).distinct()


def decisions(docs: DataFrame) -> DataFrame:
    """doc_id, pos, near of every line occurrence to drop."""
    distinct = durable(distinct_lines(docs))
    near = near_lines(docs, distinct).withColumn("near", F.lit(True))
    doubtful = distinct.select("h1", "h2", "first", "n_rows").join(near, ["h1", "h2"], "left").where("n_rows > 1 or near")
    places = lines(docs).where(F.trim("line") != "").select("doc_id", "pos", "place", *_identity())
    dropped = places.join(doubtful, ["h1", "h2"]).where(F.coalesce("near", F.lit(False)) | ~F.col("place").eqNullSafe(F.col("first")))
    return dropped.select("doc_id", "pos", F.coalesce("near", F.lit(False)).alias("near"))


def report(docs: DataFrame) -> DataFrame:
    """One row per row of docs: doc_id, n_lines, n_exact, n_near (dropped), dropped (positions)."""
    mine = decisions(docs).distinct().groupBy(F.col("doc_id").alias("d_id")).agg(
        F.sum((~F.col("near")).cast("long")).alias("n_exact"), F.sum(F.col("near").cast("long")).alias("n_near"), F.array_sort(F.collect_set("pos")).alias("at")
    )
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.size(F.split(F.coalesce(F.col("text").cast("string"), F.lit("")), "\n", -1)).cast("long").alias("n_lines"))
    out = rows.join(mine, F.col("doc_id").eqNullSafe(F.col("d_id")), "left")
    return out.select("doc_id", "n_lines", F.coalesce("n_exact", F.lit(0)).alias("n_exact"), F.coalesce("n_near", F.lit(0)).alias("n_near"), F.coalesce(F.concat_ws(",", F.col("at").cast("array<string>")), F.lit("")).alias("dropped"))


def keep_earliest(docs: DataFrame) -> DataFrame:
    """docs with the dropped lines taken out of text; all other columns as they were."""
    mine = decisions(docs).groupBy(F.col("doc_id").alias("__d_id")).agg(F.collect_set("pos").alias("__at"))
    joined = docs.join(mine, F.col("doc_id").cast("long").eqNullSafe(F.col("__d_id")), "left")
    kept = F.array_join(F.filter(F.split("text", "\n", -1), lambda _, i: ~F.array_contains(F.col("__at"), i)), "\n")
    return joined.select(*[(F.when(F.col("__at").isNull(), F.col("text")).otherwise(kept).alias("text") if c == "text" else F.col(f"`{c}`")) for c in docs.columns])
