from datetime import datetime, timedelta

import numpy as np
import pytest

from patternwalk import workloads
from patternwalk.model import GraphDB, least_of_component, pack, stats
from patternwalk.operators import flat
from patternwalk.sources import builders

SF, START = "/root/testdata/sf0.001", datetime(2024, 1, 1)


def _events(spark, tmp_path):
    hours = [0, 0, 5, 5, 21.5, 43, 43.001, 200, 201, 500]
    rows = [(u * 100 + (k * 7) % 10, START + timedelta(hours=h * (u + 1)), u, "abc"[k % 3], 10.0 * k) for u in range(3) for k, h in enumerate(hours)]
    rows += [(900, None, 0, "a", 1.0), (901, START, None, "b", 1.0), (902, START + timedelta(days=90), None, "b", 1.0), (903, START, 7, "c", 1.0), (100, START, 1, "a", 2.0), (100, START, 1, "a", 2.0)]
    spark.createDataFrame(rows, "event_id long, ts timestamp, user_id long, event_type string, value double").write.parquet(f"{tmp_path}/events.parquet")
    return str(tmp_path)


def test_proximity_is_packed_without_a_table_of_edges(spark, tmp_path):
    sf_dir = _events(spark, tmp_path)
    for alphabet in ("coarse", "fine", "skewed"):
        db = builders.proximity(spark, sf_dir, alphabet)
        assert db.packed is not None
        rows = lambda d: sorted(map(repr, d.collect()))
        assert rows(pack(db)) == rows(pack(GraphDB(db.vertices, db.edges)))
        plan = pack(db)._jdf.queryExecution().optimizedPlan().toString()
        assert plan.count("RepartitionByExpression") == 1 and "Join" not in plan
    assert rows(pack(db.restrict(db.vertices.where("gid = 1")))) == rows(pack(db).where("gid = 1"))


def test_copurchase_graphs_come_from_baskets_without_a_search_in_arrays(spark, tmp_path):
    def save(name, rows, schema):
        spark.createDataFrame(rows, schema).write.parquet(f"{tmp_path}/{name}.parquet")

    save("customer", [(1, 3, "B"), (2, 3, "A"), (3, None, "A"), (4, 3, "B")], "c_custkey long, c_nationkey int, c_mktsegment string")
    orders = [(10, 1, "2"), (11, 4, "1"), (12, 1, None), (13, 1, "2"), (20, 2, None), (21, 2, "3"), (30, 3, "1"), (40, 9, "1"), (50, 2, "1")]
    save("orders", [(o, c, p, START) for o, c, p in orders], "o_orderkey long, o_custkey long, o_orderpriority string, o_orderdate timestamp")
    lines = [(10, 1), (10, 2), (10, 2), (11, 1), (11, 2), (12, 2), (12, 3), (13, 7), (13, 8), (13, 99), (13, None), (20, 5), (20, 6), (21, 7), (21, 8), (30, 1), (30, 2), (40, 1), (40, 3), (50, 4)]
    save("lineitem", lines, "l_orderkey long, l_partkey long")
    save("part", [(k, f"b{k % 3}") for k in range(1, 9)], "p_partkey long, p_brand string")
    db = builders.copurchase(spark, str(tmp_path))
    assert sorted(map(tuple, db.edges.collect()), key=str) == [(300, 5, 6, None), (301, 1, 2, "1"), (301, 2, 3, None)]
    assert sorted(map(tuple, db.vertices.collect())) == [(300, 5, "b2"), (300, 6, "b0"), (301, 1, "b1"), (301, 2, "b2"), (301, 3, "b0")]
    assert stats(db).collect() == stats(GraphDB(db.vertices, db.edges)).collect() and stats(db).first()[:4] == (2, 5, 3, 3)
    assert "array_position" not in pack(db)._jdf.queryExecution().optimizedPlan().toString()
    held = db.stored()
    assert sorted(map(str, held.packed.collect())) == sorted(map(str, pack(GraphDB(db.vertices, db.edges)).collect()))


def test_components_by_their_least_vertex():
    draw = np.random.default_rng(5)
    for n, m in ((1, 0), (6, 3), (40, 25), (400, 390), (400, 0)):
        a, b = draw.integers(0, n, m), draw.integers(0, n, m)
        want = list(range(n))
        for _ in range(n):
            for x, y in zip(a, b):
                want[x] = want[y] = min(want[x], want[y])
        assert least_of_component(n, a, b).tolist() == want
    chain = np.arange(100_000)
    assert not least_of_component(100_001, chain, chain + 1).any()


@pytest.mark.parametrize("name", ["w2_complete_by_support", "w1_complete_by_size", "complete_growth", "complete_levelwise", "complete_maximal", "complete_closed", "pattern_lattice_walk"])
def test_complete_miners_need_no_table_of_edges(spark, monkeypatch, name):
    want = sorted(map(str, workloads.QUERIES[name](spark, SF).collect()))

    def without(spark, sf_dir, alphabet="coarse"):
        db = builders.proximity(spark, sf_dir, alphabet)
        return GraphDB(db.vertices, None, packed=db.packed)

    monkeypatch.setattr(workloads, "prox", without)
    assert sorted(map(str, workloads.QUERIES[name](spark, SF).collect())) == want and want


def test_edge_sets_with_all_their_vertices_grow_without_a_look_at_other_edges(monkeypatch):
    a, b = np.array([0, 0, 1, 2, 3, 1]), np.array([1, 2, 2, 3, 4, 4])
    chunk = flat.Chunk(np.array([1]), np.zeros(5, int), np.arange(5), np.zeros(5, int), ["v"], a, b, np.zeros(6, int), ["e"])
    live = np.array([True, True, True, True, True, False])
    pairs = chunk.grown([np.flatnonzero(live)], live, 3)
    assert list(zip(*map(list, pairs))) == [(0, 1), (0, 2), (1, 2), (1, 3), (2, 3), (3, 4)]
    looked = []
    whole = flat.spread
    monkeypatch.setattr(flat, "spread", lambda counts: looked.append(int(np.sum(counts))) or whole(counts))
    assert [list(c) for c in chunk.grown(pairs, live, 3)] == [[0], [1], [2]]
    assert sum(looked) == 0


def test_order_stars_are_packed_from_their_lines(spark, tmp_path):
    """As from tables of vertices and edges, where keys are missing as well; types and masks are those of all graphs."""
    from patternwalk.operators import support as S

    def save(name, rows, schema):
        spark.createDataFrame(rows, schema).write.parquet(f"{tmp_path}/{name}.parquet")

    save("customer", [(1, "B"), (2, None)], "c_custkey long, c_mktsegment string")
    save("orders", [(10, 1, "2"), (11, 2, "1"), (12, 9, None), (13, None, "2"), (14, 1, "3")], "o_orderkey long, o_custkey long, o_orderpriority string")
    lines = [(10, 1, 1, "N", "O"), (10, 1, 2, "N", "O"), (10, 2, 1, "R", None), (11, 1, 1, "A", "F"), (12, 9, 9, "A", "F"), (13, None, None, "A", "F"), (99, 1, 1, "A", "F"), (None, 1, 1, "A", "F")]
    save("lineitem", lines, "l_orderkey long, l_partkey long, l_suppkey long, l_returnflag string, l_linestatus string")
    save("part", [(1, "x"), (2, None)], "p_partkey long, p_type string")
    save("supplier", [(1, 5), (2, 6)], "s_suppkey long, s_nationkey long")
    save("nation", [(5, 0), (6, 1)], "n_nationkey long, n_regionkey long")
    rows = lambda d: sorted(map(repr, d.collect()))
    for sf_dir in (str(tmp_path), SF):
        db = builders.order_star(spark, sf_dir)
        whole = GraphDB(db.vertices, db.edges)
        assert rows(db.packed) == rows(pack(whole)) and rows(db.graphs()) == rows(whole.graphs())
    types = S.edge_support(whole)
    pairs = S.placed_types(db.packed)
    assert rows(S.numbered_types(pairs)) == rows(types)
    old, new = S.score_table(whole, types, "s2"), S.placed_scores(db, types, pairs)
    ks = range(len(old.support))
    assert old.support == new.support and [old.of([a, b]) for a in ks for b in ks] == [new.of([a, b]) for a in ks for b in ks]
