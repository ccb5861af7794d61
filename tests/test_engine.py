"""Plans, switches, state and clean-up of the engine."""

import os
import re
import time

import pytest
from pyspark.sql import functions as F

from motifloom import api, experiments, metrics, storage
from motifloom.operators import batching, binary, compress, partition, wco
from motifloom.operators.batching import BatchSpec
from motifloom.operators.graph import from_lists, normalise
from motifloom.plans import catalogue, optimize
from motifloom.plans.pattern import QueryGraph
from motifloom.registry import Q8_TREES
from motifloom.sources import readers, synthetic, write_adjacency
from motifloom.streaming import edges as stream


@pytest.fixture(scope="module")
def dense(spark):
    return normalise(synthetic(spark, "uniform", n=24, p=0.4, seed=2))


def plan_text(df):
    return re.sub(r"#\d+L?|plan_id=\d+|batches-\w+|Location.*?\n", "", df._jdf.queryExecution().optimizedPlan().toString())


def test_binary_switches_give_different_plans(dense):
    q, switches = catalogue.unlabelled("q2"), ({"triangle_index": "full", "compression": True}, {"triangle_index": "full"}, {"compression": True}, {"triangle_index": "ordered", "compression": True}, {})
    texts = [plan_text(api.match(dense, q, "binary", output="compressed" if s.get("compression") else "rows", **s)) for s in switches]
    assert len(set(texts)) == len(texts)
    trees = [binary.plan(dense, q, triangle_index=s.get("triangle_index")) for s in switches]
    assert [{u.kind for u in t.leaves} for t in trees] == [{"clique"}, {"clique"}, {"star"}, {"clique"}, {"star"}]
    assert [u.arrays for u in binary.with_arrays(trees[0], q, "full").leaves] == [(3,), (4,)]
    # the ordered index cannot give what may lie below its anchor
    assert all(not u.arrays for u in binary.with_arrays(trees[3], q, "ordered").leaves)
    assert binary.with_arrays(binary.plan(dense, catalogue.clique(4), triangle_index="ordered"), catalogue.clique(4), "ordered").arrays == (4,)


@pytest.mark.parametrize("name", ["q3", "q5"])
def test_switches_and_orders_agree(dense, name):
    q = catalogue.by_name(name)
    want = api.match(dense, q, "growth", output="count").first()[0]
    for options in ({"strategy": "binary", "triangle_index": "full", "compression": True}, {"strategy": "binary", "order": "cover_first", "compression": True}, {"strategy": "binary", "triangle_index": "ordered", "ranges": 2}, {"strategy": "wco", "split": "star"}, {"strategy": "wco", "split": "clique"}, {"strategy": "growth", "batching": BatchSpec(size=50)}, {"strategy": "replicated", "kernel": "decompose"}):
        assert api.match(dense, q, output="count", **options).first()[0] == want, options


def test_trees_of_ones_own(dense):
    q = catalogue.unlabelled("q8")
    want = api.match(dense, q, "growth", output="count").first()[0]
    for tree in Q8_TREES.values():
        assert set(tree.edges) == set(q.edges)
        assert api.match(dense, q, "binary", tree=tree, triangle_index="full", compression=True, output="count").first()[0] == want
    assert wco.groups_of(catalogue.unlabelled("q2"), "clique")[0] == (1, 2, 3)


def test_the_size_probe_reads_list_lengths_where_ids_prove_nothing(spark):
    edges = [(1, k) for k in range(2, 12)] + [(2, 3), (3, 4), (2, 4), (5, 6)]
    labels = {v: v % 2 for v in range(1, 12)}
    q = QueryGraph.from_edges([(1, 2), (1, 3), (2, 3)], labels=[1, 0, None])
    labelled = from_lists(spark, edges, labels=labels)
    assert "_size" in plan_text(api.match(labelled, q, "growth")) and "_size" not in plan_text(api.match(labelled, q, "growth", proposer="first"))
    plain = from_lists(spark, edges, relabel=False)  # 1 is the hub, and ids are no ranks
    triangle = catalogue.clique(3)
    assert "_size" in plan_text(api.match(plain, triangle, "growth"))
    assert sorted(map(tuple, api.match(plain, triangle, "growth").collect())) == sorted(triangle.brute_force(edges))
    assert "_size" not in plan_text(api.match(from_lists(spark, edges), triangle, "growth"))
    plain.chunk = 3
    assert sorted(map(tuple, api.match(plain, triangle, "growth").collect())) == sorted(triangle.brute_force(edges))


def test_a_hub_has_no_long_row_in_the_triangle_index(spark):
    hub = normalise(spark.createDataFrame([(0, k) for k in range(1, 41)] + [(k, k + 1) for k in range(1, 40)], "a long, b long"))
    rows = partition.triangle_index(hub).agg(F.max(F.size("ends")), F.sum(F.size("ends"))).first()
    assert rows[0] == 2  # common neighbours of an edge, not all local edges of the hub
    assert rows[1] == 6 * 39  # six entries for each of the 39 triangles
    assert api.match(hub, catalogue.unlabelled("q2"), "growth", triangle_index="full", output="count").first()[0] == 38


def test_merged_counting_below(spark):
    rows = [([1, 3, 5], [2, 3, 9]), ([], [1]), ([4], []), ([2, 2], [2, 3])]
    df = spark.createDataFrame(rows, "a array<long>, b array<long>").select(compress._below("a", "b").alias("n"))
    assert [r["n"] for r in df.collect()] == [sum(x < y for x in a for y in b) for a, b in rows]


def test_batches_run_in_turn(spark, dense):
    q = catalogue.unlabelled("q2")
    want = sorted(map(tuple, api.match(dense, q, "growth").collect()))
    for options in ({"strategy": "growth"}, {"strategy": "binary", "triangle_index": "full", "compression": True}):
        out = api.match(dense, q, batching=4, **options)
        folders = {os.path.dirname(f).rpartition("/")[2] for f in out.inputFiles()}
        assert folders <= {f"batch={k}" for k in range(4)} and len(folders) > 1
        assert sorted(map(tuple, out.collect())) == want
    assert BatchSpec(size=100).batches(950.0) == 10 and BatchSpec().batches(5.0) == 1
    seen = []

    def fails_first(k, b):
        seen.append(b)
        if b == 2:
            raise batching.PySparkException("java.lang.OutOfMemoryError: Java heap space")
        return spark.createDataFrame([(1,)], "n long")

    assert batching.total(fails_first, 2) == 4 and seen == [2, 4, 4, 4, 4]
    with pytest.raises(batching.PySparkException):
        batching.total(lambda k, b: (_ for _ in ()).throw(batching.PySparkException("a wrong column")), 2)


def test_runs_are_cancelled_at_the_cap(spark):
    began = time.perf_counter()
    run = metrics.timed(lambda: spark.range(1 << 34).agg(F.sum(F.sqrt("id")).alias("n")), repeat=1, cap=2.0)
    assert run["status"] == "over time" and time.perf_counter() - began < 60
    good = metrics.timed(lambda: spark.range(5).agg(F.count("id").alias("n")), repeat=2)
    assert good["status"] == "finished" and good["value"] == 5
    assert metrics.completion_rate([run, good]) == 0.5


def test_experiments_prepare_the_index_and_rate_only_strategies_that_ran(dense):
    dense._kept.pop(("tri", False), None)
    experiments.prepare(dense, catalogue.unlabelled("q2"), {"triangle_index": "full"})
    assert ("tri", False) in dense._kept
    rows = [{"experiment": "simple patterns", "method": "growth", "status": s} for s in ("finished", "over time")]
    assert experiments.completion(rows + [{"experiment": "switches", "method": "binary", "status": "finished"}]) == {"growth": 0.5}


def test_follow_knows_the_graph_after_a_restart(spark, tmp_path):
    path, seen = str(tmp_path / "edges"), []
    parts = [[(1, 2), (2, 3)], [(1, 3), (3, 4)], [(2, 4), (1, 4)]]
    for k, part in enumerate(parts):
        spark.createDataFrame(part, "a long, b long").coalesce(1).write.mode("append").parquet(path)
        source = spark.readStream.schema("a long, b long").parquet(path)
        run = stream.follow(source, catalogue.clique(3), lambda df, n: seen.extend(map(tuple, df.collect())), str(tmp_path / "cp"))
        run.processAllAvailable()
        run.stop()  # a new query goes on from the checkpoint
        assert len(seen) == [0, 1, 4][k]
    assert sorted(seen) == [(1, 2, 3), (1, 2, 4), (1, 3, 4), (2, 3, 4)]


def test_bucketed_adjacency_is_not_shuffled(spark, dense):
    name = "adjacency_test"
    write_adjacency(dense.adjacency(), name, 4)
    try:
        again = normalise(synthetic(spark, "uniform", n=24, p=0.4, seed=2))
        readers.read_adjacency(again, name)
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
        df = api.match(again, catalogue.clique(3), "growth")
        text = df._jdf.queryExecution().executedPlan().toString()
        assert df.count() == api.match(dense, catalogue.clique(3), "growth").count()
        assert "Bucketed: true" in text
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        spark.sql(f"DROP TABLE IF EXISTS {name}")


def test_scratch_paths_can_be_removed(spark):
    path = storage.scratch(spark, "gone")
    spark.range(3).write.parquet(path)
    assert storage.tidy(spark, [path]) == 1
    with pytest.raises(Exception):
        spark.read.parquet(path).count()


def test_measures(dense):
    q = catalogue.unlabelled("q2")
    assert metrics.growth_comm(dense, q, 1).first()["total"] == 0  # one worker: nothing moves
    many = metrics.growth_comm(dense, q, 8).first()
    assert many["worst"] <= many["total"] > 0
    assert {r["kind"] for r in metrics.partition_cost(dense, 4).collect()} == {"hash", "triangle", "triangle_ordered"}
    parts = [metrics.sampled_count(dense, q, 3, k).first()[0] // 3 for k in range(3)]
    assert sum(parts) == api.match(dense, q, "growth", output="count").first()[0]
    assert optimize.plan_cost(Q8_TREES["tailed"], binary.sizer(dense, catalogue.unlabelled("q8"), "bound")) < optimize.plan_cost(Q8_TREES["house"], binary.sizer(dense, catalogue.unlabelled("q8"), "bound"))
