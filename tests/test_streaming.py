"""Streams against batches on the same rows."""

import pytest
from pyspark.sql import functions as F

from motifloom import api
from motifloom.operators.graph import build, normalise
from motifloom.plans import catalogue
from motifloom.sources import table
from motifloom.streaming import edges as stream

SF = "/root/testdata/sf0.001"


@pytest.fixture()
def days(spark, tmp_path):
    """events, one Parquet file per replayed part in order of time."""
    e = table(spark, SF, "events").orderBy("ts")
    path = str(tmp_path / "events")
    e.coalesce(1).write.parquet(path)
    return path, e


def test_streamed_edges_are_the_batch_edges(spark, days, tmp_path):
    path, e = days
    source = spark.readStream.schema(e.schema).parquet(path)
    end = e.limit(1).withColumn("ts", F.expr("timestamp_ntz '2100-01-01 00:00:00'"))
    end.coalesce(1).write.mode("append").parquet(path)
    q = stream.edges(source).writeStream.format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "cp")).outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination(120)
    got = spark.read.parquet(str(tmp_path / "out")).select("a", "b").distinct()
    want = build(spark, SF, "coactive")
    assert got.count() == want.stats["m"]


def test_delta_rule_and_wedges(spark, tmp_path):
    g = build(spark, SF, "cobuy")
    q = catalogue.clique(3)
    old, new = g.edges.where("(src + dst) % 3 > 0").select("src", "dst"), g.edges.where("(src + dst) % 3 = 0").select("src", "dst")
    before = api.match(normalise(old.toDF("a", "b"), relabel=False), q, "growth").count()
    assert before + stream.delta_matches(old, new, q).count() == 768
    path = str(tmp_path / "edges")
    for i in range(3):
        g.edges.where(f"(src + dst) % 3 = {i}").select(F.col("src").alias("a"), F.col("dst").alias("b")).coalesce(1).write.mode("append").parquet(path)
    source = spark.readStream.schema("a long, b long").option("maxFilesPerTrigger", 1).parquet(path)
    seen = []
    run = stream.follow(source, q, lambda df, n: seen.append(df.count()), str(tmp_path / "cp"))
    run.processAllAvailable()
    run.stop()
    assert sum(seen) == 768 and len(seen) == 3
    counts = stream.wedge_counts(source).writeStream.format("memory").queryName("wedges").outputMode("update").option("checkpointLocation", str(tmp_path / "cp2")).start()
    counts.processAllAvailable()
    counts.stop()
    total = spark.sql("select sum(w) from (select user, max(wedges) as w from wedges group by user)").first()[0]
    assert total == 16669
