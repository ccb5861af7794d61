"""Data graphs built from the given tables, with the same rules as SQL text for the oracles.

A builder gives the raw pairs (a, b[, elabel]) of a graph; operators.graph normalises them. The SQL of
a builder gives undirected pairs with a < b, or directed pairs, in a relation `pairs`.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from motifloom.plans.catalogue import CODE
from motifloom.storage import meet

TYPE_BASE = 10**12
PART_SHIFT = 10**8


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def _meet(members: DataFrame, who: str, on: list[str]) -> DataFrame:
    """Pairs of different members that share a group: a self-join on the group's key, by sort and merge."""
    left = members.select(F.col(who).alias("a"), *on)
    right = members.select(F.col(who).alias("b"), *on)
    return meet(left, right, on).where("a < b").select("a", "b")


def cobuy(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    items = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), "l_partkey", "l_shipdate")
    bought = meet(items, orders, ["o_orderkey"])
    bought = bought.select("o_custkey", "l_partkey", F.trunc(F.col("l_shipdate").cast("date"), "month").alias("month")).distinct()
    return _meet(bought, "o_custkey", ["l_partkey", "month"])


def coactive(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = table(spark, sf_dir, "events")
    bucket = F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 600)
    return _meet(events.select("user_id", "event_type", bucket.alias("bucket")).distinct(), "user_id", ["event_type", "bucket"])


def copurchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _meet(table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct(), "l_partkey", ["l_orderkey"])


def lattice(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    same_customer = F.lag("o_orderkey").over(Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey"))
    same_day = F.lag("o_orderkey").over(Window.partitionBy("o_orderdate").orderBy("o_orderkey"))
    near = orders.select(F.col("o_orderkey").alias("a"), F.array(same_customer, same_day).alias("before"))
    return near.select("a", F.explode("before").alias("b")).where("b is not null")


def supply(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("a"), (F.col("l_partkey") + PART_SHIFT).alias("b"))


def sharedline(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    lines = docs.select("doc_id", F.explode(F.split("text", "\n")).alias("line")).select("doc_id", F.trim("line").alias("line")).where(F.length("line") >= 40).distinct()
    shared = lines.groupBy("line").agg(F.count(F.lit(1)).alias("n")).where("n between 2 and 200").select("line")
    return _meet(meet(lines, shared, ["line"]), "doc_id", ["line"])


def doclines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents and the lines they share with others, however many: linear in the text, so no line is left out."""
    docs = table(spark, sf_dir, "documents")
    lines = docs.select("doc_id", F.explode(F.split("text", "\n")).alias("line")).select("doc_id", F.trim("line").alias("line")).where(F.length("line") >= 40).distinct()
    named = lines.select("doc_id", F.md5("line").alias("h"))
    shared = named.groupBy("h").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("h")
    return meet(named, shared, ["h"]).select(F.concat(F.lit("d:"), "doc_id").alias("a"), F.concat(F.lit("l:"), "h").alias("b"))


def scalefree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A synthetic graph as large as the tables: both ends of an edge fall on vertex k with weight k ** -1/2."""
    rows = table(spark, sf_dir, "lineitem").select(F.count(F.lit(1)).alias("n")).first()[0]
    draw = lambda salt: F.conv(F.substring(F.md5(F.concat(F.lit(salt), F.col("id").cast("string"))), 1, 8), 16, 10).cast("double") / 4294967296.0
    end = lambda salt: F.floor(draw(salt) * draw(salt) * (rows // 4)).cast("bigint")
    return spark.range(2 * rows).select(end("a").alias("a"), end("b").alias("b"))


def contacts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """coactive with the kind of event as edge label: 1 for the first kind by name, and so on."""
    events = table(spark, sf_dir, "events")
    kinds = events.select("event_type").distinct().withColumn("elabel", F.dense_rank().over(Window.orderBy("event_type")))  # a few kinds
    bucket = F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 600)
    seen = events.select("user_id", "event_type", bucket.alias("bucket")).distinct()
    left = seen.select(F.col("user_id").alias("a"), "event_type", "bucket")
    right = seen.select(F.col("user_id").alias("b"), "event_type", "bucket")
    return left.join(right, ["event_type", "bucket"]).where("a < b").join(F.broadcast(kinds), "event_type").select("a", "b", "elabel")


def weblink(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages")
    paths = F.explode(F.regexp_extract_all("html", F.lit('href="/([^"?#]*)'), F.lit(1)))
    return pages.select(F.concat(F.lit("h:"), F.regexp_extract("url", "//([^/]+)", 1)).alias("a"), paths.alias("p")).select("a", F.concat(F.lit("p:"), F.lower("p")).alias("b"))


def dialog(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn")
    here = F.col("conv_id") * 100000 + F.col("turn")
    after = turns.select("conv_id", (F.col("turn") - 1).alias("turn"))
    return turns.join(after, ["conv_id", "turn"]).select(here.alias("a"), (here + 1).alias("b")).distinct()


def typed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges between keys code * 10^12 + key of ten kinds of things."""
    t = {n: table(spark, sf_dir, n) for n in ("customer", "orders", "part", "supplier", "nation", "region", "lineitem")}

    def key(kind: str, column: str):
        return (F.lit(CODE[kind]) * F.lit(TYPE_BASE) + F.col(column).cast("bigint")).cast("bigint")

    def coded(df: DataFrame, column: str) -> DataFrame:
        names = df.select(column).distinct()
        return df.join(F.broadcast(names.withColumn("code", F.dense_rank().over(Window.orderBy(column)).cast("bigint"))), column)  # a few names

    def pairs(df: DataFrame, kind_a: str, a: str, kind_b: str, b: str) -> DataFrame:
        return df.select(key(kind_a, a).alias("a"), key(kind_b, b).alias("b"))

    c, o, p, s, n, li = t["customer"], t["orders"], t["part"], t["supplier"], t["nation"], t["lineitem"]
    bought = cobuy(spark, sf_dir).select(F.col("a").alias("x"), F.col("b").alias("y"))
    parts = [
        pairs(o, "customer", "o_custkey", "order", "o_orderkey"),
        pairs(li, "order", "l_orderkey", "part", "l_partkey"),
        pairs(li, "part", "l_partkey", "supplier", "l_suppkey"),
        pairs(li, "order", "l_orderkey", "supplier", "l_suppkey"),
        pairs(c, "customer", "c_custkey", "nation", "c_nationkey"),
        pairs(s, "supplier", "s_suppkey", "nation", "s_nationkey"),
        pairs(n, "nation", "n_nationkey", "region", "n_regionkey"),
        pairs(coded(p, "p_brand"), "part", "p_partkey", "brand", "code"),
        pairs(coded(p, "p_type"), "part", "p_partkey", "type", "code"),
        pairs(coded(c, "c_mktsegment"), "customer", "c_custkey", "segment", "code"),
        pairs(coded(o, "o_orderpriority"), "order", "o_orderkey", "priority", "code"),
        pairs(bought, "customer", "x", "customer", "y"),
    ]
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    return out


def _k(kind: str, column: str) -> str:
    return f"{CODE[kind]} * {TYPE_BASE} + CAST({column} AS BIGINT)"


_COBUY_SQL = (
    "WITH x AS (SELECT DISTINCT o_custkey AS c, l_partkey AS p, date_trunc('month', l_shipdate) AS m FROM orders JOIN lineitem ON o_orderkey = l_orderkey)"
    " SELECT DISTINCT x.c AS a, y.c AS b FROM x JOIN x AS y ON x.p = y.p AND x.m = y.m AND x.c < y.c"
)


def _typed_sql() -> str:
    def coded(tab: str, col: str) -> str:
        return f"(SELECT *, dense_rank() OVER (ORDER BY {col}) AS code FROM {tab})"

    rows = [
        ("customer", "o_custkey", "order", "o_orderkey", "orders"),
        ("order", "l_orderkey", "part", "l_partkey", "lineitem"),
        ("part", "l_partkey", "supplier", "l_suppkey", "lineitem"),
        ("order", "l_orderkey", "supplier", "l_suppkey", "lineitem"),
        ("customer", "c_custkey", "nation", "c_nationkey", "customer"),
        ("supplier", "s_suppkey", "nation", "s_nationkey", "supplier"),
        ("nation", "n_nationkey", "region", "n_regionkey", "nation"),
        ("part", "p_partkey", "brand", "code", coded("part", "p_brand")),
        ("part", "p_partkey", "type", "code", coded("part", "p_type")),
        ("customer", "c_custkey", "segment", "code", coded("customer", "c_mktsegment")),
        ("order", "o_orderkey", "priority", "code", coded("orders", "o_orderpriority")),
        ("customer", "a", "customer", "b", f"({_COBUY_SQL})"),
    ]
    union = " UNION ALL ".join(f"SELECT {_k(ka, a)} AS a, {_k(kb, b)} AS b FROM {src} AS s{i}" for i, (ka, a, kb, b, src) in enumerate(rows))
    return f"SELECT DISTINCT least(a, b) AS a, greatest(a, b) AS b FROM ({union}) WHERE a <> b"


@dataclass(frozen=True)
class Builder:
    name: str
    pairs: Callable[[SparkSession, str], DataFrame]
    sql: str
    directed: bool = False
    #: Column expression over `orig` that gives a vertex label, or None.
    label: str | None = None


BUILDERS = {
    b.name: b
    for b in (
        Builder("cobuy", cobuy, _COBUY_SQL),
        Builder(
            "coactive",
            coactive,
            "WITH x AS (SELECT DISTINCT user_id AS u, event_type AS t, CAST(floor(epoch(ts) / 600) AS BIGINT) AS k FROM events)"
            " SELECT DISTINCT x.u AS a, y.u AS b FROM x JOIN x AS y ON x.t = y.t AND x.k = y.k AND x.u < y.u",
        ),
        Builder("copurchase", copurchase, "SELECT DISTINCT x.l_partkey AS a, y.l_partkey AS b FROM lineitem x JOIN lineitem y ON x.l_orderkey = y.l_orderkey AND x.l_partkey < y.l_partkey"),
        Builder(
            "lattice",
            lattice,
            "WITH w AS (SELECT o_orderkey AS k, lag(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS p, lag(o_orderkey) OVER (PARTITION BY o_orderdate ORDER BY o_orderkey) AS q FROM orders)"
            " SELECT DISTINCT least(k, p) AS a, greatest(k, p) AS b FROM (SELECT k, p FROM w UNION ALL SELECT k, q FROM w) WHERE p IS NOT NULL",
        ),
        Builder("supply", supply, f"SELECT DISTINCT l_suppkey AS a, l_partkey + {PART_SHIFT} AS b FROM lineitem"),
        Builder(
            "sharedline",
            sharedline,
            "WITH x AS (SELECT DISTINCT doc_id AS d, trim(line) AS l FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(trim(line)) >= 40),"
            " y AS (SELECT l FROM x GROUP BY l HAVING count(*) BETWEEN 2 AND 200), z AS (SELECT x.d, x.l FROM x JOIN y ON x.l = y.l)"
            " SELECT DISTINCT z.d AS a, w.d AS b FROM z JOIN z AS w ON z.l = w.l AND z.d < w.d",
        ),
        Builder(
            "doclines",
            doclines,
            "WITH x AS (SELECT DISTINCT doc_id AS d, trim(line) AS l FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(trim(line)) >= 40),"
            " y AS (SELECT l FROM x GROUP BY l HAVING count(*) > 1) SELECT DISTINCT 'd:' || d AS a, 'l:' || md5(x.l) AS b FROM x JOIN y ON x.l = y.l",
        ),
        Builder(
            "scalefree",
            scalefree,
            "WITH n AS (SELECT count(*) AS n FROM lineitem), x AS (SELECT CAST('0x' || substr(md5('a' || i), 1, 8) AS BIGINT) / 4294967296.0::DOUBLE AS p, CAST('0x' || substr(md5('b' || i), 1, 8) AS BIGINT) / 4294967296.0::DOUBLE AS q, n // 4 AS w FROM n, unnest(range(0, 2 * n)) AS r(i)),"
            " y AS (SELECT CAST(floor(p * p * w) AS BIGINT) AS a, CAST(floor(q * q * w) AS BIGINT) AS b FROM x) SELECT DISTINCT least(a, b) AS a, greatest(a, b) AS b FROM y WHERE a <> b",
        ),
        Builder(
            "contacts",
            contacts,
            "WITH x AS (SELECT DISTINCT user_id AS u, event_type AS t, CAST(floor(epoch(ts) / 600) AS BIGINT) AS k FROM events), z AS (SELECT *, dense_rank() OVER (ORDER BY t) AS code FROM x)"
            " SELECT x.u AS a, y.u AS b, min(x.code) AS elabel FROM z AS x JOIN z AS y ON x.t = y.t AND x.k = y.k AND x.u < y.u GROUP BY x.u, y.u",
        ),
        Builder(
            "weblink",
            weblink,
            "SELECT DISTINCT 'h:' || regexp_extract(url, '//([^/]+)', 1) AS a, 'p:' || lower(p) AS b FROM (SELECT url, unnest(regexp_extract_all(html, 'href=\"/([^\"?#]*)', 1)) AS p FROM pages)",
        ),
        Builder("dialog", dialog, "SELECT DISTINCT x.conv_id * 100000 + x.turn AS a, x.conv_id * 100000 + x.turn + 1 AS b FROM conversations x JOIN conversations y ON x.conv_id = y.conv_id AND y.turn = x.turn + 1", directed=True),
        Builder("typed", typed, _typed_sql(), label=f"CAST(orig DIV {TYPE_BASE} AS INT)"),
    )
}
