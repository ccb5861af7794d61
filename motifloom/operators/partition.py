"""Hash and triangle partitions of a data graph, and their statistics."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifloom.operators.graph import DataGraph
from motifloom.storage import stored


def triangles(g: DataGraph) -> DataFrame:
    """x < y < z for every triangle: lists above each vertex, intersected along each edge.

    Lists hold only larger ids, that is, vertices of larger degree, so a hub's list is short.
    """
    if "triangles" not in g._kept:
        e = g.edges.select(F.least("src", "dst").alias("x"), F.greatest("src", "dst").alias("y")).distinct() if g.directed else g.edges.select(F.col("src").alias("x"), F.col("dst").alias("y"))
        above = e.groupBy(F.col("x").alias("u")).agg(F.collect_list("y").alias("up"))
        at_x, at_y = above.select(F.col("u").alias("x"), F.col("up").alias("ux")), above.select(F.col("u").alias("y"), F.col("up").alias("uy"))
        found = e.join(at_y, "y").join(at_x, "x").select("x", "y", F.explode(F.array_intersect("ux", "uy")).alias("z"))
        g._kept["triangles"] = stored(found, "triangles")
    return g._kept["triangles"]


def triangle_edges(g: DataGraph, ordered: bool = False) -> DataFrame:
    """u, a, b (a < b): the edge a-b stored with the anchor u; with ordered only where u < a."""
    t = triangles(g)
    low = t.select(F.col("x").alias("u"), F.col("y").alias("a"), F.col("z").alias("b"))
    if ordered:
        return low
    middle = t.select(F.col("y").alias("u"), F.col("x").alias("a"), F.col("z").alias("b"))
    high = t.select(F.col("z").alias("u"), F.col("x").alias("a"), F.col("y").alias("b"))
    return low.unionByName(middle).unionByName(high)


def triangle_index(g: DataGraph, ordered: bool = False) -> DataFrame:
    """u, a, ends (ascending): with the anchor u, for its neighbour a, the other ends of a's edges among u's neighbours.

    So ends holds the common neighbours of u and a. A row per arc and never one per anchor: no list is
    longer than the smaller degree of its two vertices, however many local edges a hub has. With ordered
    only edges above the anchor are kept.
    """
    key = ("tri", ordered)
    if key not in g._kept:
        local = triangle_edges(g, ordered)
        both = local.unionByName(local.select("u", F.col("b").alias("a"), F.col("a").alias("b")))
        g._kept[key] = both.groupBy("u", "a").agg(F.sort_array(F.collect_list("b")).alias("ends")).persist()
    return g._kept[key]


def clique_buds(g: DataGraph, m: int, ordered: bool = False) -> DataFrame:
    """v1 < … < vm for every m-clique with a common neighbour, and buds: all vertices next to all of them.

    Read off the triangle index of v1 alone. With the ordered index buds holds those above v1 only.
    """
    index = triangle_index(g, ordered)
    rows = index.where("u < a").select(F.col("u").alias("v1"), F.col("a").alias("v2"), F.col("ends").alias("buds"))
    for size in range(3, m + 1):
        names = [f"v{i}" for i in range(1, size)]
        last = F.col(names[-1])
        rows = rows.select(*names, "buds", F.explode(F.filter("buds", lambda e: e > last)).alias(f"v{size}"))
        near = index.select(F.col("u").alias("v1"), F.col("a").alias(f"v{size}"), "ends")
        rows = rows.join(near, ["v1", f"v{size}"]).select(*names, f"v{size}", F.array_intersect("buds", "ends").alias("buds")).where(F.size("buds") > 0)
    return rows


def _distinct_edges(rows: DataFrame, w: int, kind: str) -> DataFrame:
    sizes = rows.distinct().groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    return sizes.agg(F.lit(kind).alias("kind"), F.lit(w).cast("bigint").alias("workers"), (F.coalesce(F.sum("n"), F.lit(0)) / w).alias("avg_edges"), F.coalesce(F.max("n"), F.lit(0)).alias("max_edges"))


def _own(g: DataGraph, w: int) -> DataFrame:
    """part, a, b: each edge with the partitions of both its ends."""
    low, high = F.least("src", "dst"), F.greatest("src", "dst")
    e = g.edges.select(low.alias("a"), high.alias("b"))
    return e.select(F.explode(F.array(F.pmod("a", F.lit(w)), F.pmod("b", F.lit(w)))).alias("part"), "a", "b")


def hash_stats(g: DataGraph, w: int) -> DataFrame:
    """kind, workers, avg_edges, max_edges: distinct undirected edges held per partition id mod w."""
    return _distinct_edges(_own(g, w), w, "hash")


def triangle_stats(g: DataGraph, w: int, ordered: bool = False) -> DataFrame:
    local = triangle_edges(g, ordered).select(F.pmod("u", F.lit(w)).alias("part"), "a", "b")
    return _distinct_edges(_own(g, w).unionByName(local), w, "triangle_ordered" if ordered else "triangle")


def clique_table(g: DataGraph, k: int) -> DataFrame:
    """v1 < … < vk for every k-clique, grown from the triangles by one vertex per round."""
    if k == 2:
        return g.edges.select(F.least("src", "dst").alias("v1"), F.greatest("src", "dst").alias("v2"))
    rows = triangles(g).toDF("v1", "v2", "v3")
    above = g.edges.groupBy(F.least("src", "dst").alias("u")).agg(F.collect_list(F.greatest("src", "dst")).alias("up"))
    for size in range(4, k + 1):
        lists = []
        for i in range(1, size):
            rows = rows.join(above.select(F.col("u").alias(f"v{i}"), F.col("up").alias(f"_u{i}")), f"v{i}")
            lists.append(F.col(f"_u{i}"))
        found = lists[0]
        for other in lists[1:]:
            found = F.array_intersect(found, other)
        rows = rows.select(*[f"v{i}" for i in range(1, size)], F.explode(found).alias(f"v{size}"))
    return rows
