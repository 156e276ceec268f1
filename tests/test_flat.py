"""Pieces as arrays in the workers: results as by the kernel, and no shuffle of pieces."""

import pytest

from patternwalk import workloads
from patternwalk.functions import accuracy as A
from patternwalk.operators import enumerate as E
from patternwalk.operators import flat
from patternwalk.operators import law as L
from patternwalk.operators.kernel import Scores
from tests import toy

SF = "/root/testdata/sf0.001"
#: Queries whose pieces must not leave their worker before they are counted or returned.
LOCAL = ["neighbour_degree_p3", "piece_stats_p3", "piece_degrees_p3", "acceptance_p3_s1", "acceptance_p3_s2", "acceptance_p3_uniform", "acceptance_rate_p3", "asymmetric_pairs_p3", "swap_boxes_p3", "jump_law_p3"]


@pytest.mark.parametrize("name", LOCAL)
def test_pieces_are_not_shuffled(spark, name):
    plan = workloads.QUERIES[name](spark, SF)._jdf.queryExecution().optimizedPlan().toString()
    above = plan.split("MapInArrow")[0]
    assert "MapInArrow" in plan and not any(x in above for x in ("Join", "Aggregate", "Window", "Sort"))


@pytest.mark.parametrize("most", [3, 60_000])
@pytest.mark.parametrize("p", [2, 3, 4])
def test_degrees_are_the_kernels(spark, monkeypatch, most, p):
    monkeypatch.setattr(flat, "PIECES", most)
    found = {(r.gid, toy.mask(r.vs)): r.d for r in L.degrees(toy.database(spark), p).collect()}
    want = {}
    for gid in toy.LABELS:
        g = toy.graph(gid)
        want |= {(gid, s): sum(m.bit_count() for _, m in g.boxes(s)) for s in g.enumerate(p)}
    assert found == want


def test_pattern_counts_are_those_of_the_joins(spark):
    db = toy.database(spark)
    for p in (2, 3, 4):
        joined = E.piece_codes(db, E.enumerate_induced(db, p), p).groupBy("code", "gid").count()
        assert sorted(map(tuple, E.pattern_counts(db, p).collect())) == sorted(map(tuple, joined.collect()))


def test_residual_is_a_share_of_the_flow(spark, monkeypatch):
    """Flows grow with supports, and their rounding with them: a bound of 1e-12 must not depend on the number of graphs."""
    with monkeypatch.context() as m:
        m.setattr(L, "score_table", lambda *_: Scores("s1", [7_000_003 * (1 + t) for t in range(4)]))
        assert L.balance_residual(toy.database(spark), 3, "s1").first().residual < 1e-12
    plan = L.balance_residual(toy.database(spark), 3)._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan.split("MapInArrow")[0]


def test_supports_shuffle_patterns_not_pieces(spark):
    plan = workloads.QUERIES["pattern_support_p4_coarse"](spark, SF)._jdf.queryExecution().optimizedPlan().toString()
    assert "MapInArrow" in plan and "Join" not in plan.split("MapInArrow")[0]


def test_unvisited_graphs_have_no_distance(spark):
    samples = spark.createDataFrame([(1, [0, 1, 2]), (1, [0, 1, 2]), (1, [1, 2, 3])], "gid long, vs array<long>")
    law = L.stationary(toy.database(spark), 3, "uniform")
    assert [r.gid for r in A.visit_distance(samples, law).collect()] == [1]
    only = L.stationary(toy.database(spark), 3, only=samples.select("gid"))
    assert A.visit_distance(samples, only).collect() == A.visit_distance(samples, L.stationary(toy.database(spark), 3)).collect()
