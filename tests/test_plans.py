"""Driver-side facts: structure functions, plans, shares, estimates."""

import pytest

from motifloom.plans import catalogue, estimate, optimize
from motifloom.plans.advisor import Cluster, decide
from motifloom.plans.ir import JoinNode, joins_of
from motifloom.plans.pattern import QueryGraph

STATS = {"n": 1498, "m": 10699, "avg_degree": 14.28, "max_degree": 39, "s": [1498.0, 21398.0, 362144.0, 7e6, 1.5e8, 3.3e9, 8e10, 2e12, 5e13]}
AUT = {"q1": 8, "q2": 4, "q3": 24, "q4": 2, "q5": 2, "q6": 12, "q7": 2, "q8": 4, "q9": 2}
RHO = {"q1": 2, "q2": 2, "q3": 2, "q4": 2.5, "q5": 2.5, "q6": 2.5, "q7": 3, "q8": 3, "q9": 3}
GREEDY = {"q4": ((1, 2, 5, 3, 4), {4, 5}), "q8": ((1, 2, 5, 3, 4, 6), {5, 6}), "q9": ((3, 1, 2, 4, 5, 6), {2, 6})}
COVER = {"q4": ((1, 2, 3, 4, 5), {4, 5}), "q8": ((1, 2, 3, 4, 5, 6), {5, 6}), "q9": ((3, 1, 5, 2, 4, 6), {2, 4, 6})}


@pytest.mark.parametrize("name", AUT)
def test_symmetry_and_bounds(name):
    q = catalogue.unlabelled(name)
    assert len(q.automorphisms) == AUT[name] and q.fractional_cover == RHO[name]


def test_orders():
    for name, (order, arrays) in GREEDY.items():
        q = catalogue.unlabelled(name)
        assert optimize.greedy(q) == order and set(optimize.compressible(q, order)) == arrays
    for name, (order, arrays) in COVER.items():
        q = catalogue.unlabelled(name)
        assert optimize.cover_first(q) == order and set(optimize.compressible(q, order)) == arrays
    assert catalogue.tailed_triangle().fractional_cover == 2


def test_worked_join_plans():
    q = catalogue.example()
    assert len(joins_of(optimize.star_cover_plan(q))) == 1
    assert len(joins_of(optimize.wedge_plan(q))) == 2
    tree = optimize.bushy(q, estimate.Sizer(q, STATS))
    assert isinstance(tree, JoinNode) and tree.key == (2, 4) and {u.kind for u in tree.leaves} == {"clique"}


def test_star_to_wedge_costs_no_more_under_the_uniform_model():
    for name in ("q4", "q5", "q8"):
        q = catalogue.unlabelled(name)
        stars = optimize.star_cover_plan(q)
        wedges = optimize.star_to_wedge(stars, q)
        assert set(wedges.edges) == set(q.edges) and all(len(u.vertices) <= 3 for u in wedges.leaves)
        sizer = estimate.Sizer(q, STATS, "uniform")
        assert optimize.plan_cost(wedges, sizer) <= 4 * max(optimize.plan_cost(stars, sizer), sizer(q.edges))


def test_shares():
    triangle = catalogue.clique(3)
    assert optimize.shares(triangle, 8) == (2, 2, 2) and optimize.shares(triangle, 64) == (4, 4, 4)
    assert optimize.shares(triangle, 30, "round_down") == (3, 3, 3)
    assert optimize.routed_edges(triangle, (2, 2, 2), 10699, True) == 3 * 2 * 10699
    with pytest.raises(ValueError):
        optimize.shares(triangle, 8, (3, 3, 3))


def test_estimates():
    q = catalogue.clique(3)
    stats = {"n": 4, "m": 6, "s": [4.0, 12.0, 36.0, 108.0]}
    assert estimate.power_law(q, stats) == pytest.approx(4.5)
    assert estimate.bound(q, 100) == 1000 and estimate.q_error(10, 5) == 2


def test_groups_need_both_conditions_with_the_ordered_index():
    q = catalogue.clique(4)
    full = optimize.growth_plan(q, triangle_index="full").rounds[-1].groups
    ordered = optimize.growth_plan(q, triangle_index="ordered").rounds[-1].groups
    assert full == ((1, (2, 3)),) and ordered == ((1, (2, 3)),)
    assert optimize.growth_plan(catalogue.unlabelled("q2"), triangle_index="ordered").rounds[-1].groups[0][1] in ((2,), ())


def test_parse_and_errors():
    q = QueryGraph.parse("a-b, b-c, a-c; a:1, b:2, c:2")
    assert q.n == 3 and q.labels == (1, 2, 2)
    assert QueryGraph.parse("a>b, b-[7]->c").directed
    with pytest.raises(ValueError):
        QueryGraph.parse("a~b")
    with pytest.raises(ValueError):
        optimize.growth_plan(QueryGraph.from_edges([(1, 2), (3, 4)]))


def test_advice():
    q = catalogue.unlabelled("q3")
    assert decide(q, STATS, Cluster(1 << 40)).strategy == "replicated"
    assert decide(q, STATS, Cluster(1000)).strategy == "binary"
    assert not decide(q, STATS | {"avg_degree": 2.3}, Cluster(1000)).compression
    assert decide(catalogue.unlabelled("q9"), STATS, Cluster(1000)).order == "cover_first"
