"""Edge streams from events, incremental matching, and stateful counts per user."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from motifloom.operators import compress as packed
from motifloom.plans.ir import relation, use_symmetry
from motifloom.plans.pattern import QueryGraph


def events(stream: DataFrame, late: str = "30 minutes") -> DataFrame:
    """Events with a time-zone timestamp and a watermark."""
    return stream.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)


def _windows(width: str, slide: str | None, session: str | None):
    return F.session_window("ts", session) if session else F.window("ts", width, slide) if slide else F.window("ts", width)


def activity(stream: DataFrame, width: str = "10 minutes", slide: str | None = None, session: str | None = None, late: str = "30 minutes") -> DataFrame:
    """users per event type and window (tumbling, sliding, or a session per user): the groups that make edges."""
    keys = ["user_id"] if session else []
    grouped = events(stream, late).groupBy(_windows(width, slide, session).alias("w"), "event_type", *keys)
    return grouped.agg(F.array_sort(F.collect_set("user_id")).alias("users"))


def edges(stream: DataFrame, width: str = "10 minutes", slide: str | None = None, late: str = "30 minutes") -> DataFrame:
    """a, b: users with an event of one type in one window; a pair may come up once per window.

    Emitted in append mode when the watermark closes the window, so late events change nothing.
    """
    groups = activity(stream, width, slide, None, late)
    first = groups.select("w", "users", F.posexplode("users").alias("i", "a"))
    return first.select(F.col("w.end").alias("closed"), "a", F.explode(F.slice("users", F.col("i") + 2, F.greatest(F.size("users") - F.col("i") - 1, F.lit(0)))).alias("b"))


def distinct_edges(edge_stream: DataFrame, late: str = "30 minutes") -> DataFrame:
    """Each pair once within the watermark; needs an event-time column `closed`."""
    return edge_stream.withWatermark("closed", late).dropDuplicatesWithinWatermark(["a", "b"])


def interval_pairs(left: DataFrame, right: DataFrame, within: str = "10 minutes", late: str = "30 minutes") -> DataFrame:
    """A stream-stream join: events of one user at most `within` apart."""
    x = events(left, late).select(F.col("user_id").alias("u"), F.col("event_id").alias("a"), F.col("ts").alias("ta"))
    y = events(right, late).select(F.col("user_id"), F.col("event_id").alias("b"), F.col("ts").alias("tb"))
    return x.join(y, F.expr(f"u = user_id and tb >= ta and tb <= ta + interval {within} and a <> b")).select("u", "a", "b")


def delta_matches(old: DataFrame, new: DataFrame, q: QueryGraph, symmetry: str = "auto") -> DataFrame:
    """Matches that new edges bring: for the i-th query edge new, those before it old or new, those after it old.

    old and new are disjoint sets of edges (src < dst). Every match comes up once.
    """
    ordered = use_symmetry(q, symmetry)
    both = lambda e: e.select(F.col("src").alias("u"), F.col("dst").alias("v")).unionByName(e.select(F.col("dst").alias("u"), F.col("src").alias("v")))
    before, fresh = both(old), both(new)
    everything = before.unionByName(fresh)
    parts = []
    for i, start in enumerate(q.edges):
        left = [e for e in q.edges if e != start]
        rows, placed = _arc(fresh, start, q, ordered), list(start)
        while left:
            e = min((x for x in left if set(x) & set(placed)), key=lambda x: (-len(set(x) & set(placed)), x))
            left.remove(e)
            source = everything if q.edges.index(e) < i else before
            rows = rows.join(_arc(source, e, q, ordered), [f"v{x}" for x in e if x in placed])
            for x in e:
                if x not in placed:
                    for y in placed:
                        if (how := relation(q, x, y, ordered)) and not (y in e):
                            rows = rows.where(packed.compare(F.col(f"v{x}"), how, F.col(f"v{y}")))
                    placed.append(x)
        parts.append(rows.select(*[f"v{v}" for v in q.vertices]))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def _arc(arcs: DataFrame, e: tuple[int, int], q: QueryGraph, ordered: bool) -> DataFrame:
    a, b = e
    rows = arcs.select(F.col("u").alias(f"v{a}"), F.col("v").alias(f"v{b}"))
    how = relation(q, a, b, ordered)
    return rows.where(packed.compare(F.col(f"v{a}"), how, F.col(f"v{b}"))) if how else rows


def follow(edge_stream: DataFrame, q: QueryGraph, sink: Callable[[DataFrame, int], None], checkpoint: str, known: DataFrame | None = None) -> StreamingQuery:
    """Runs delta_matches for every micro-batch of edges (a, b) and hands the new matches to sink.

    The graph so far lies beside the stream's checkpoint, one folder per micro-batch, which only holds
    its own new edges. A restarted query reads the folders of the batches before; a batch that runs
    again writes its folder again.
    """
    spark, home = edge_stream.sparkSession, f"{checkpoint.rstrip('/')}-graph"
    kind = "src bigint, dst bigint"
    first = known.select("src", "dst") if known is not None else spark.createDataFrame([], kind)
    first.write.mode("overwrite").parquet(f"{home}/batch=-1")

    def batch(rows: DataFrame, number: int) -> None:
        graph = lambda: rows.sparkSession.read.schema(f"{kind}, batch bigint").parquet(home)
        old = graph().where(F.col("batch") < number).select("src", "dst")
        fresh = rows.select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).where("src <> dst").distinct()
        fresh.join(old, ["src", "dst"], "left_anti").write.mode("overwrite").parquet(f"{home}/batch={number}")
        new = graph().where(F.col("batch") == number).select("src", "dst")
        sink(delta_matches(old, new, q), number)

    return edge_stream.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).start()


def wedge_counts(edge_stream: DataFrame) -> DataFrame:
    """user, degree, wedges: running counts per vertex in arbitrary state, from edges (a, b), each seen once."""
    ends = edge_stream.select(F.explode(F.array(F.struct(F.col("a").alias("user"), F.col("b").alias("other")), F.struct(F.col("b").alias("user"), F.col("a").alias("other")))).alias("e")).select("e.*")

    def update(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        near = set(state.get[0]) if state.exists else set()
        for f in frames:
            near |= set(f["other"].tolist())
        state.update((sorted(near),))
        n = len(near)
        yield pd.DataFrame({"user": [key[0]], "degree": [n], "wedges": [n * (n - 1) // 2]})

    return ends.groupBy("user").applyInPandasWithState(update, "user long, degree long, wedges long", "near array<long>", "update", GroupStateTimeout.NoTimeout)
