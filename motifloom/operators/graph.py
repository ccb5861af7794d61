"""Data graphs: normalisation, degree-ordered ids, adjacency, statistics."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from motifloom.sources.builders import BUILDERS
from motifloom.storage import durable, meet, release, scratch, stored, tidy

#: Neighbour lists are cut into chunks of about so many vertices.
CHUNK = 65_536
#: Up to so many vertices are ranked in one task; more are ranked by ranges.
RANK_IN_ONE_TASK = 2_000_000


@dataclass
class DataGraph:
    """A simple graph.

    vertices: id, label, orig, degree. edges: src, dst, elabel; src < dst unless directed. ids are
    ranks by degree, so the smaller of two ids never has the larger degree. labelled: the edges with the
    labels of their ends (slabel, dlabel), where there are labels.
    """

    vertices: DataFrame
    edges: DataFrame
    directed: bool = False
    ranked: bool = True
    name: str = ""
    #: Neighbour lists longer than this are cut into chunks.
    chunk: int = CHUNK
    _kept: dict = field(default_factory=dict, repr=False)

    @property
    def spark(self) -> SparkSession:
        return self.edges.sparkSession

    @property
    def arcs(self) -> DataFrame:
        """u, v, elabel, ulabel, vlabel: both directions of every edge, or one if directed."""
        if "arcs" not in self._kept:
            e = self.labelled if self.has_labels else self.edges.withColumns({"slabel": F.lit(None).cast("int"), "dlabel": F.lit(None).cast("int")})
            both = e.select(F.col("src").alias("u"), F.col("dst").alias("v"), "elabel", F.col("slabel").alias("ulabel"), F.col("dlabel").alias("vlabel"))
            if not self.directed:
                both = both.unionByName(e.select(F.col("dst").alias("u"), F.col("src").alias("v"), "elabel", F.col("dlabel").alias("ulabel"), F.col("slabel").alias("vlabel")))
            self._kept["arcs"] = both
        return self._kept["arcs"]

    has_labels: bool = False
    labelled: DataFrame | None = None

    def _arcs(self, ulabel=None, vlabel=None, elabel=None, inward: bool = False) -> DataFrame:
        a = self.arcs
        if inward and self.directed:
            a = a.select(F.col("v").alias("u"), F.col("u").alias("v"), "elabel", F.col("vlabel").alias("ulabel"), F.col("ulabel").alias("vlabel"))
        for column, value in (("ulabel", ulabel), ("vlabel", vlabel), ("elabel", elabel)):
            if value is not None:
                a = a.where(F.col(column) == value)
        return a.select("u", "v")

    def pairs(self, ulabel=None, vlabel=None, elabel=None, inward: bool = False) -> DataFrame:
        """u, v for every arc with these labels."""
        return self._arcs(ulabel, vlabel, elabel, inward)

    def lists(self, ulabel=None, vlabel=None, elabel=None, inward: bool = False) -> DataFrame:
        """u, nbrs (ascending): a hub has a row per chunk, whose members are spread evenly."""
        a = self._arcs(ulabel, vlabel, elabel, inward)
        if self.max_degree <= self.chunk:
            return a.groupBy("u").agg(F.sort_array(F.collect_list("v")).alias("nbrs"))
        parts = self.vertices.select(F.col("id").alias("u"), F.ceil(F.col("degree") / self.chunk).alias("parts"))
        a = a.join(parts, "u").withColumn("chunk", F.pmod("v", F.col("parts")))
        return a.groupBy("u", "chunk").agg(F.sort_array(F.collect_list("v")).alias("nbrs")).select("u", "nbrs")

    def adjacency(self, ulabel=None, vlabel=None, elabel=None, inward: bool = False) -> DataFrame:
        """The lists, kept by the executors."""
        key = ("adj", ulabel, vlabel, elabel, inward, self.chunk)
        if key not in self._kept:
            self._kept[key] = self.lists(ulabel, vlabel, elabel, inward).persist()
        return self._kept[key]

    @property
    def stats(self) -> dict:
        """n, m, average and maximum degree, and the sums of degree powers 1 to 8."""
        if "stats" not in self._kept:
            d = F.col("degree").cast("double")
            row = self.vertices.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.max("degree"), F.lit(0)).alias("max"), *[F.coalesce(F.sum(F.pow(d, F.lit(float(k)))), F.lit(0.0)).alias(f"s{k}") for k in range(1, 9)]).first()
            m = int(row["s1"] / 2)
            self._kept["stats"] = {"n": row["n"], "m": m, "max_degree": row["max"], "avg_degree": 2.0 * m / row["n"] if row["n"] else 0.0, "s": [float(row["n"]), *[row[f"s{k}"] for k in range(1, 9)]]}
        return self._kept["stats"]

    @property
    def whole_lists(self) -> bool:
        """Whether every vertex has its neighbours in one list."""
        return self.max_degree <= self.chunk

    @property
    def max_degree(self) -> int:
        return self.stats["max_degree"]

    def label_pairs(self) -> dict[tuple[int, int], int]:
        """How many arcs lead from one label to another; as many entries as pairs of labels."""
        if "labels" not in self._kept:
            self._kept["labels"] = {(r[0], r[1]): r[2] for r in self.arcs.groupBy("ulabel", "vlabel").count().collect()}
        return self._kept["labels"]

    def label_counts(self) -> dict[int, int]:
        if "label_counts" not in self._kept:
            self._kept["label_counts"] = {r[0]: r[1] for r in self.vertices.groupBy("label").count().collect()}
        return self._kept["label_counts"]

    def stats_frame(self) -> DataFrame:
        return self.vertices.agg(
            F.count(F.lit(1)).alias("vertices"), (F.coalesce(F.sum("degree"), F.lit(0)) / 2).cast("bigint").alias("edges"), F.coalesce(F.max("degree"), F.lit(0)).cast("bigint").alias("max_degree"), F.round(F.avg("degree"), 6).alias("avg_degree")
        )

    def estimated_bytes(self) -> int:
        """Of the graph as compressed sparse rows: two ids per edge and an offset per vertex."""
        return 16 * self.stats["m"] + 8 * self.stats["n"]


def global_rank(df: DataFrame, by: list[str], out: str = "id") -> DataFrame:
    """Numbers rows 1, 2, … in the order of `by` without gathering them in one task.

    Rows are range-partitioned and kept; the sizes of the ranges before give each range its offset.
    """
    df = df.withColumn("__n", F.lit(1))
    if df.limit(RANK_IN_ONE_TASK + 1).count() <= RANK_IN_ONE_TASK:
        return df.withColumn(out, F.row_number().over(Window.orderBy(*by)).cast("bigint")).drop("__n")
    ranged = durable(df.repartitionByRange(*by).withColumn("__part", F.spark_partition_id()))
    sizes = ranged.groupBy("__part").agg(F.count(F.lit(1)).alias("__size"))
    before = F.sum("__size").over(Window.orderBy("__part").rowsBetween(Window.unboundedPreceding, -1))
    offsets = sizes.select("__part", F.coalesce(before, F.lit(0)).alias("__before"))
    local = F.row_number().over(Window.partitionBy("__part").orderBy(*by))
    return ranged.join(F.broadcast(offsets), "__part").withColumn(out, (local + F.col("__before")).cast("bigint")).drop("__part", "__before", "__n")


def normalise(pairs: DataFrame, directed: bool = False, label: str | None = None, vertices: DataFrame | None = None, name: str = "", relabel: bool = True) -> DataGraph:
    """Raw pairs (a, b[, elabel]) -> a simple graph with ids ranked by (degree, key).

    Loops go, duplicate edges merge (the smallest edge label stays). label is an SQL expression over
    `orig`; vertices (orig[, label]) adds isolated vertices. relabel=False keeps integer keys as ids.
    """
    if "elabel" not in pairs.columns:
        pairs = pairs.withColumn("elabel", F.lit(None).cast("int"))
    pairs = pairs.where("a <> b")
    if not directed:
        pairs = pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"), "elabel")
    pairs = pairs.groupBy("a", "b").agg(F.min("elabel").alias("elabel"))
    raw = scratch(pairs.sparkSession, "pairs")
    pairs.write.option("compression", "zstd").parquet(raw)
    pairs = pairs.sparkSession.read.schema(pairs.schema).parquet(raw)
    release(pairs.sparkSession)
    ends = pairs.select(F.col("a").alias("orig")).unionByName(pairs.select(F.col("b").alias("orig")))
    degrees = ends.groupBy("orig").agg(F.count(F.lit(1)).cast("bigint").alias("degree"))
    if vertices is not None:
        degrees = vertices.select("orig").distinct().join(degrees, "orig", "left").select("orig", F.coalesce("degree", F.lit(0)).cast("bigint").alias("degree"))
    ids = global_rank(degrees, ["degree", "orig"]) if relabel else degrees.withColumn("id", F.col("orig").cast("bigint"))
    named = ids.withColumn("label", F.expr(label) if label else F.lit(None).cast("int"))
    if vertices is not None and "label" in vertices.columns:
        named = named.drop("label").join(vertices.select("orig", "label").distinct(), "orig", "left")
    named = stored(named, "ids")
    release(pairs.sparkSession)
    has_labels = bool(label) or (vertices is not None and "label" in vertices.columns)
    end = lambda key, out, kind: named.select(F.col("orig").alias(key), F.col("id").alias(out), *([F.col("label").alias(kind)] if has_labels else []))
    e = meet(meet(pairs, end("a", "x", "xlabel"), ["a"]), end("b", "y", "ylabel"), ["b"])
    turned = F.lit(False) if directed else F.col("x") > F.col("y")
    pick = lambda low, high: F.when(turned, F.col(high)).otherwise(F.col(low))
    columns = [pick("x", "y").alias("src"), pick("y", "x").alias("dst"), "elabel"]
    if has_labels:
        columns += [pick("xlabel", "ylabel").alias("slabel"), pick("ylabel", "xlabel").alias("dlabel")]
    table = named.select("id", "label", F.col("orig").cast("string").alias("orig"), "degree")
    edges = stored(e.select(*columns), "edges")
    # every later plan starts from two short scans
    graph = DataGraph(table, edges.select("src", "dst", "elabel"), directed, relabel, name, has_labels=has_labels, labelled=edges if has_labels else None)
    tidy(pairs.sparkSession, [raw])
    release(graph.spark)
    return graph


_built: dict = {}


def build(spark: SparkSession, sf_dir: str, name: str) -> DataGraph:
    """A prepared graph from the given tables; kept for the session, as all queries on it start from it."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _built:
        b = BUILDERS[name]
        _built[key] = normalise(b.pairs(spark, sf_dir), b.directed, b.label, name=name)
    return _built[key]


def from_lists(spark: SparkSession, edges, labels: dict | None = None, directed: bool = False, relabel: bool = True) -> DataGraph:
    """A graph from Python lists, for examples and tests."""
    pairs = spark.createDataFrame([(int(e[0]), int(e[1]), (int(e[2]) if len(e) > 2 else None)) for e in edges], "a bigint, b bigint, elabel int")
    vertices = spark.createDataFrame([(int(v), int(x)) for v, x in labels.items()], "orig bigint, label int") if labels else None
    return normalise(pairs, directed, vertices=vertices, relabel=relabel)
