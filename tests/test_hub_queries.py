"""The registered queries without SQL on hub-skewed, dense and sparse graphs, against brute force."""

from collections import defaultdict
from datetime import datetime, timedelta
from itertools import combinations

import pytest

from motifloom import api, registry
from motifloom.operators.graph import from_lists
from motifloom.plans import catalogue

START = datetime(2024, 1, 1)
#: order, part, supplier: supplier 0 sells every part, and orders 1 and 2 hold most parts together.
ITEMS = [(o, p, s) for o, parts in {1: range(5), 2: range(2, 7), 3: (0, 6)}.items() for p in parts for s in ({0, p % 3} if o == 1 else {0})]
ORDERS = [(k, k % 2, START + timedelta(days=(k * k) % 4)) for k in range(9)]
LINES = [f"a line of more than forty characters, number {i}" for i in range(4)]
DOCS = [(d, "\n".join(x for x, m in zip(LINES, ({0, 1, 2, 3, 4}, {3, 4, 5, 6}, {0, 6, 7}, {7, 5})) if d in m)) for d in range(8)]
EVENTS = [(u, "view" if k % 2 else "click", START + timedelta(seconds=600 * k)) for k, users in enumerate([(0, 1, 2, 3, 4), (3, 4, 5, 6), (6, 7, 0), (1, 5, 7)]) for u in users]
PAGES = [(f"http://h{h}/x", "".join(f'<a href="/p{p}?q=1">' for p in range(4) if h == 0 or (h + p) % 2)) for h in range(4)]


def groups(members):
    found = defaultdict(set)
    for key, who in members:
        found[key].add(who)
    return {e for g in found.values() for e in combinations(sorted(g), 2)}


def lattice():
    edges = set()
    for key in (lambda r: r[1], lambda r: r[2]):
        rows = defaultdict(list)
        for r in sorted(ORDERS, key=lambda r: (r[2], r[0])):
            rows[key(r)].append(r[0])
        edges |= {tuple(sorted(e)) for g in rows.values() for e in zip(g, g[1:])}
    return edges


GRAPHS = {
    "supply": {(s, 100 + p) for _, p, s in ITEMS},
    "copurchase": groups((o, p) for o, p, _ in ITEMS),
    "lattice": lattice(),
    "sharedline": groups((x, d) for d, t in DOCS for x in t.split("\n")),
    "coactive": groups(((k, t), u) for u, k, t in EVENTS),
    "weblink": {(h, 100 + p) for h in range(4) for p in range(4) if h == 0 or (h + p) % 2},
}
WANTED = ["q1_growth_supply", "q1_clique_supply", "q1_growth_weblink", "q1_clique_weblink", "q2_growth_copurchase", "q2_clique_copurchase", "q5_frontier_coactive", *(f"{q}_growth_{g}" for q in ("q1", "q2", "q3", "q4", "q5", "q6") for g in ("sharedline", "lattice")), *(f"{q}_{m}_{s}_lattice" for q in ("q2", "q5") for m in ("growth", "binary") for s in ("all", "nobatching", "notriangle", "nocompression", "orderedindex"))]


@pytest.fixture(scope="module")
def given(spark, tmp_path_factory):
    home = tmp_path_factory.mktemp("hubs")
    for name, rows, schema in (
        ("lineitem", ITEMS, "l_orderkey bigint, l_partkey bigint, l_suppkey bigint"),
        ("orders", ORDERS, "o_orderkey bigint, o_custkey bigint, o_orderdate timestamp_ntz"),
        ("documents", DOCS, "doc_id bigint, text string"),
        ("events", EVENTS, "user_id bigint, event_type string, ts timestamp_ntz"),
        ("pages", PAGES, "url string, html string"),
    ):
        spark.createDataFrame(rows, schema).coalesce(1).write.parquet(f"{home}/{name}.parquet")
    return str(home)


def test_queries_without_sql_match_brute_force(spark, given):
    known, want = registry.queries(), {}
    assert set(WANTED) <= set(known)
    for name in WANTED:
        pattern, graph = name.split("_")[0], name.split("_")[-1]
        if (pattern, graph) not in want:
            want[pattern, graph] = len(catalogue.by_name(pattern).brute_force(GRAPHS[graph]))
        got = known[name](spark, given)
        rows = got.collect()
        assert (len(rows) if "v1" in got.columns else rows[0][0]) == want[pattern, graph], name
    assert all(want[q, g] for q, g in (("q1", "supply"), ("q1", "weblink"), ("q2", "copurchase"), ("q5", "coactive"), ("q3", "sharedline")))


@pytest.mark.parametrize("options", [{"strategy": "growth"}, {"strategy": "binary", "unit": "clique"}], ids=str)
def test_batched_counts_run_one_job_after_the_other(spark, options):
    g = from_lists(spark, GRAPHS["copurchase"], relabel=False)
    out = api.match(g, catalogue.unlabelled("q2"), output="count", batching=2, triangle_index="full", **options)
    assert "Union" not in out._jdf.queryExecution().logical().toString()
    assert out.collect()[0][0] == len(catalogue.unlabelled("q2").brute_force(GRAPHS["copurchase"]))
