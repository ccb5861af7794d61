"""Mixing sources to target weights by weighted fair queueing.

Each source is a queue served in proportion to its target. Its documents stand in a shuffled order
(by the MD5 of seed and id) and its queue repeats, up to max_repeats passes. A document copy is sent
in packets of at most `packet` words; a packet's virtual finish time is the source's cumulative words
up to its end divided by the source's target. All packets are range-sorted by finish time over all
sources, and the mix is what stands before the total budget (the words of the corpus): the packet
that straddles the budget is cut to the words that remain, all later ones are left out. At the cut
every queue is at virtual time 1 but for one packet, so each source's words come within `packet` words
of its target.

Running totals are two-level, in the queues (hash buckets, then inside each) and in the sorted mix
(ranges, then inside each). No task ever holds a whole source or the whole mix, and texts are read once.

Defined results: null text has size 0; null sources form one source that sorts last; rows repeating
an id are separate documents; documents without words have a row and give nothing; a source of size 0
has target 0; an empty table gives an empty result; further columns are ignored, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from motifloom.llm.common import durable

WEIGHTS = (5.0, 2.0, 1.0)
MAX_REPEATS = 3
#: Words of a packet: how near a source's words come to its target.
PACKET = 64
#: Words are runs of other characters than space and tab to carriage return.
WORD = r"[^\x20\x09-\x0D]+"


def word_count(column: str = "text") -> Column:
    return F.coalesce(F.regexp_count(F.col(column).cast("string"), F.lit(WORD)), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, weights=WEIGHTS, max_repeats: int = MAX_REPEATS) -> DataFrame:
    """source, source_size -> and target: water filling with caps at max_repeats times the size.

    A source is above its cap exactly when the common level reaches cap / weight, so sources fill up
    in the order of that ratio, and the level after the k-th is known from running sums.
    """
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    ratio = Window.orderBy("ratio", F.col("source").asc_nulls_last())
    before = ratio.rowsBetween(Window.unboundedPreceding, -1)
    after = ratio.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    shares = F.array(*[F.lit(float(w)) for w in weights])
    ranked = sizes.withColumn("weight", F.get(shares, ((F.row_number().over(by_name) - 1) % len(weights)).cast("int")))
    ranked = ranked.withColumn("cap", F.col("source_size") * F.lit(max_repeats)).withColumn("ratio", F.col("cap") / F.col("weight"))
    levels = ranked.withColumn("rest", F.sum("source_size").over(Window.partitionBy()) - F.coalesce(F.sum("cap").over(before), F.lit(0)))
    levels = levels.withColumn("level", F.col("rest") / F.sum("weight").over(after))
    # the first source (by ratio) whose level stays below its ratio sets the level of all later ones
    final = F.min(F.when(F.col("level") <= F.col("ratio"), F.struct("ratio", F.col("source").isNull(), "source", "level"))).over(Window.partitionBy())
    return levels.select("source", "source_size", F.least(F.col("cap").cast("double"), F.col("weight") * F.coalesce(final["level"], F.lit(0.0))).alias("target"))


def sized_rows(docs: DataFrame, seed: int, carry: tuple[str, ...] = ()) -> DataFrame:
    """row (tells apart rows that repeat an id), doc_id, source, size, shuffled: computed once, as texts are long."""
    rows = docs.select(F.col("doc_id"), F.col("source").cast("string").alias("source"), word_count().alias("size"), *([F.struct(*[F.col(f"`{c}`") for c in carry]).alias("carried")] if carry else []))
    key = F.md5(F.concat_ws(":", F.lit(str(seed)), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))))
    return durable(rows.withColumn("shuffled", key).withColumn("row", F.monotonically_increasing_id()))


def queued(sized: DataFrame, weights=WEIGHTS, max_repeats: int = MAX_REPEATS, bucket_digits: int = 3) -> DataFrame:
    """One row per sized row: its source's words up to its end in the first pass (upto), its passes, the budget of all."""
    sized = sized.withColumn("bucket", F.substring("shuffled", 1, bucket_digits))
    buckets = sized.groupBy("source", "bucket").agg(F.sum("size").alias("bucket_size"))
    running = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    buckets = buckets.withColumn("before", F.coalesce(F.sum("bucket_size").over(running), F.lit(0)))
    targets = source_targets(buckets.groupBy("source").agg(F.sum("bucket_size").alias("source_size")), weights, max_repeats)
    targets = targets.withColumn("budget", F.sum("source_size").over(Window.partitionBy())).withColumnRenamed("source", "t_source")
    offsets = buckets.join(targets, F.col("source").eqNullSafe(F.col("t_source"))).select(
        F.col("source").alias("o_source"), F.col("bucket").alias("o_bucket"), "before", "source_size", "target", "budget"
    )
    inside = Window.partitionBy("source", "bucket").orderBy("shuffled", "doc_id", "size", "row").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    placed = sized.withColumn("upto", F.sum("size").over(inside))
    placed = placed.join(offsets, F.col("source").eqNullSafe(F.col("o_source")) & (F.col("bucket") == F.col("o_bucket"))).withColumn("upto", F.col("upto") + F.col("before"))
    passes = F.greatest(F.lit(1), F.least(F.lit(max_repeats), F.ceil(F.col("target") / F.greatest(F.col("source_size"), F.lit(1))).cast("int")))
    return placed.select("row", "doc_id", "source", "shuffled", "size", "source_size", "target", "budget", "upto", passes.alias("passes"))


def _clock(words: Column) -> Column:
    return F.when(F.col("target") > 0, words / F.col("target")).otherwise(F.lit(0.0))


def packets(placed: DataFrame, packet: int = PACKET) -> DataFrame:
    """Every packet of every copy: the columns of placed, pass, part (of the copy), words, finish."""
    copies = placed.withColumn("pass", F.explode(F.sequence(F.lit(0), F.col("passes") - 1)))
    last = F.greatest(F.ceil(F.col("size") / packet) - 1, F.lit(0)).cast("int")
    cut = copies.withColumn("part", F.explode(F.sequence(F.lit(0), last)))
    cut = cut.withColumn("sent", F.least(F.col("size"), (F.col("part").cast("long") + 1) * packet))
    end = F.col("pass") * F.col("source_size") + F.col("upto") - F.col("size") + F.col("sent")
    return cut.withColumn("words", F.col("sent") - F.col("part").cast("long") * packet).withColumn("finish", _clock(end)).drop("sent", "passes")


def truncated(cut: DataFrame) -> DataFrame:
    """The packets sorted over all sources and cut at the budget: taken says how many of a packet's words the mix has.

    Packets are dealt by ranges of the order and kept; the words of the ranges before give each range
    its offset, and a running sum inside each range does the rest.
    """
    order = _order()
    ranged = durable(cut.repartitionByRange(*order).withColumn("range", F.spark_partition_id()))
    sums = ranged.groupBy("range").agg(F.sum("words").alias("range_words"))
    before = F.sum("range_words").over(Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1))
    offsets = F.broadcast(sums.select("range", F.coalesce(before, F.lit(0)).alias("ahead")))  # a row per partition
    inside = Window.partitionBy("range").orderBy(*order).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    upto = F.sum("words").over(inside)
    mixed = ranged.withColumn("inside", upto).join(offsets, "range")
    taken = F.greatest(F.lit(0), F.least(F.col("words"), F.col("budget") - (F.col("ahead") + F.col("inside") - F.col("words"))))
    return mixed.withColumn("taken", taken.cast("long")).drop("inside", "ahead", "range")


def _order() -> tuple[Column, ...]:
    """Virtual finish time; ties go by source, then by the place in its queue."""
    return (F.col("finish"), F.col("source").asc_nulls_last(), *[F.col(c) for c in ("shuffled", "doc_id", "size", "row", "pass", "part")])


def mix(docs: DataFrame, weights=WEIGHTS, max_repeats: int = MAX_REPEATS, seed: int = 0, bucket_digits: int = 3, packet: int = PACKET, carry: tuple[str, ...] = ()) -> DataFrame:
    """One row per copy in the queues: doc_id, source, size, source_size, target, pass, start, finish, taken.

    start and finish are virtual times. carry names further columns of docs to keep. Every document
    has a row with pass 0 even if the mix takes nothing of it.
    """
    sized = sized_rows(docs, seed, carry)
    sent = truncated(packets(queued(sized, weights, max_repeats, bucket_digits), packet))
    copies = sent.groupBy("row", "doc_id", "source", "size", "source_size", "target", "pass", "upto").agg(F.max("finish").alias("finish"), F.sum("taken").alias("taken"))
    start = _clock(F.col("pass") * F.col("source_size") + F.col("upto") - F.col("size"))
    copies = copies.select("row", "doc_id", "source", "size", "source_size", "target", "pass", start.alias("start"), "finish", "taken")
    if not carry:
        return copies.drop("row")
    return copies.join(sized.select(F.col("row"), "carried"), "row").select(*[c for c in copies.columns if c != "row"], "carried.*")


def emit(copies: DataFrame) -> DataFrame:
    """The mix in the order of its virtual finish times, range-partitioned over the whole corpus."""
    return copies.where("taken > 0").repartitionByRange("finish", "source", "doc_id").sortWithinPartitions("finish", "source", "doc_id", "pass")


def taken_words(docs: DataFrame, weights=WEIGHTS, max_repeats: int = MAX_REPEATS, seed: int = 0, bucket_digits: int = 3, packet: int = PACKET) -> DataFrame:
    """One row per row of docs: doc_id, size, source_size, target, taken, first_start."""
    sent = truncated(packets(queued(sized_rows(docs, seed), weights, max_repeats, bucket_digits), packet))
    each = sent.groupBy("row", "doc_id", "size", "source_size", "target", "upto").agg(F.sum("taken").alias("taken"))
    return each.select("doc_id", "size", "source_size", "target", "taken", _clock(F.col("upto") - F.col("size")).alias("first_start"))
