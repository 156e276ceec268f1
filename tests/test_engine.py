import numpy as np
import pytest
from pyspark.sql import functions as F

from patternwalk.functions import accuracy as A
from patternwalk.functions.rng import uniform, uniform_column
from patternwalk.model import GraphDB, components, largest_component, pack, simplify, stats, validate
from patternwalk.operators import complete as B
from patternwalk.operators import enumerate as E
from patternwalk.operators import law as L
from patternwalk.operators import queue as Q
from patternwalk.operators import sampler as W
from patternwalk.operators import support as S
from patternwalk.operators.mine import mine_top_k
from patternwalk.sources import builders, linegraph
from tests.toy import database

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def toy(spark):
    return database(spark)


@pytest.fixture(scope="module")
def users(spark):
    return builders.proximity(spark, SF, "coarse").stored()


def test_toy_supports_and_truth(toy):
    types = {(r.la, r.el, r.lb): r.tids for r in S.edge_support(toy, sets=True).collect()}
    assert types == {("A", "x", "B"): [1, 2, 3], ("A", "x", "C"): [1, 3], ("A", "y", "A"): [1, 2, 3], ("B", "y", "C"): [1, 2]}
    t = E.ground_truth(toy, 3).collect()
    assert sorted((r.support, r.s1_num, r.s1_den, r.s2) for r in t) == sorted([(3, 6, 2, 3), (2, 9, 3, 3), (2, 5, 2, 2), (2, 6, 2, 3), (2, 5, 2, 2), (2, 5, 2, 2), (1, 6, 2, 3), (1, 4, 2, 1)])
    assert E.ground_truth(toy, 4).count() == 17
    assert A.bound_violations(E.ground_truth(toy, 4)).count() == 0


def test_engines_agree(toy, users):
    for db, p in ((toy, 3), (toy, 4), (users, 3)):
        a = E.enumerate_induced(db, p).select("gid", F.concat_ws(",", "vs").alias("vs"))
        b = E.enumerate_induced(db, p, "kernel").select("gid", F.concat_ws(",", "vs").alias("vs"))
        assert a.exceptAll(b).count() == 0 and b.exceptAll(a).count() == 0
    perm = E.support_sets(E.piece_codes(users, E.enumerate_induced(users, 3), 3))
    truth = E.ground_truth(users, 3)
    key = lambda d: sorted((r.support, r.embeddings) for r in d.collect())
    assert key(perm) == key(truth)
    assert E.space_growth(users, [3, 4]).orderBy("p").collect() == [(3, 15152), (4, 59731)]


def test_induced_support_is_below_plain(toy):
    assert E.support_both(toy, 3).where("support_induced > support_plain").count() == 0


def test_law_by_relations(toy):
    boxes = {(r.u): r.box for r in L.swap_boxes(toy, 4).where("gid = 1 AND vs = array(0L, 1L, 2L, 3L)").collect()}
    assert boxes == {0: [4, 5], 1: [4, 5, 7], 3: [5, 7]}
    for s in ("uniform", "s1", "s2"):
        assert L.balance_residual(toy, 4, s).first().residual < 1e-12
    assert L.asymmetric_pairs(toy, 4).count() == 0 and L.unreached(toy, 3).count() == 0


def test_samples_do_not_depend_on_partitions_and_runs_join(spark, users):
    key = lambda d: sorted(tuple(r) for r in d.select("chain", "iter", "gid", "raw", "proposals").collect())
    whole = key(W.run_walks(users, 3, 400, chains=2))
    held = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "7")
    try:
        assert key(W.run_walks(users, 3, 400, chains=2)) == whole
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", held)
    a, state = W.run_walks(users, 3, 150, chains=2, want_state=True)
    b = W.run_walks(users, 3, 250, chains=2, first=151, state=state)
    assert key(a.unionByName(b)) == whole and len(whole) == 800


def test_schedules(users):
    g = W.eligible(users, 3)
    for mode in ("counter", "round_robin"):
        s = W.schedule(g, 100, mode=mode, chains=2)
        got = sorted((r.chain, i) for r in s.collect() for i in r.iters)
        assert got == [(c, i) for c in range(2) for i in range(1, 101)]
    n = W.schedule(g, 3000, mode="multinomial").agg(F.sum(F.size("iters")).alias("n")).first().n
    assert 2700 < n < 3300


def test_random_numbers_are_the_same_in_sql(spark):
    r = spark.range(50).select("id", uniform_column(7, F.col("id"), "x").alias("u")).collect()
    assert all(x.u == uniform(7, x.id, "x") for x in r) and uniform(7, 0, 3, 1) == 0.08446252597541792


def test_queues_agree(users):
    s = W.run_walks(users, 3, 1200)
    cols = ["code", "exp_support", "score", "last_time"]
    key = lambda d: sorted(tuple(r) for r in d.select(*cols).collect())
    exact = key(Q.replay_queue(s, Q.QueuePolicy(10**6, "off")))
    assert exact == key(Q.lossless_queue(s)) == key(Q.lossless_queue(s, method="inline"))
    assert key(Q.sharded_queue(s, Q.QueuePolicy(10**6, "off"), shards=3, epochs=2)) == exact
    bounded = Q.replay_queue(s, Q.QueuePolicy(40))
    assert bounded.count() == 40 and A.bound_violations(E.ground_truth(users, 3), bounded).count() == 0
    a, b = Q.replay_queue(s.where("iter <= 600"), Q.QueuePolicy(10**6, "off")), Q.replay_queue(s.where("iter > 600"), Q.QueuePolicy(10**6, "off"))
    assert [x[:2] for x in key(Q.merge_queues(a, b))] == [x[:2] for x in exact]


def test_mined_patterns_obey_the_bounds(users):
    top = mine_top_k(users, 3, k=50, m=1500)
    assert top.count() == 50 and A.bound_violations(E.ground_truth(users, 3), top).count() == 0
    assert mine_top_k(users, 3, k=5, m=0).count() == 0
    plain = mine_top_k(users, 3, k=20, m=300, induced=False)
    assert A.bound_violations(E.ground_truth(users, 3, induced=False), plain).count() == 0


def test_supersteps_equal_the_lazy_kernel(users):
    from patternwalk.operators import bsp

    db = users.restrict(users.vertices.where("gid < 3"))
    types = S.edge_support(db)
    _, first = W.run_walks(db, 3, 3, mode="round_robin", emit="lazy", types=types, want_state=True)
    walkers = first.select(F.col("chain").alias("walker"), "gid", "vs", "attempts", F.lit(0).alias("moved"))
    got = bsp.walk_in_supersteps(bsp.adjacency(db, types), walkers, S.score_table(db, types, "s2"), steps=4)
    _, last = W.run_walks(db, 3, 15, mode="round_robin", emit="lazy", types=types, want_state=True)
    key = lambda d: sorted((r.gid, list(r.vs), r.attempts) for r in d.collect())
    assert key(got) == key(last)


def test_complete_miners(toy):
    a = B.mine_complete(toy, 2)
    b = B.mine_complete(toy, 2, strategy="levelwise")
    assert sorted(map(tuple, a.collect())) == sorted(map(tuple, b.collect()))
    own = {r.code: r.support for r in a.where("n_vertices = 3").collect()}
    truth = {r.code: r.support for r in E.ground_truth(toy, 3, induced=False).where("support >= 2").collect()}
    assert own == truth
    top = {r.code for r in B.maximal(a).collect()}
    assert top <= {r.code for r in B.closed(a).collect()} <= {r.code for r in a.collect()}
    assert B.pattern_walk(a, 50).count() == 50
    assert {r.code for r in B.mine_complete(toy, 2, stop_after=1).collect()} < {r.code for r in a.collect()}


def test_measures():
    assert A.random_precision(500, 10**9) == 500 * 100 / 10**9
    assert A.tau_b(np.array([1, 2, 2, 3]), np.array([1, 2, 3, 3])) == pytest.approx(0.8)


def test_measures_in_spark(spark):
    truth = spark.createDataFrame([("a", 9), ("b", 8), ("c", 7), ("d", 6), ("z", 1)], "code string, support int")
    found = spark.createDataFrame([("b", 4, 0.0, 1), ("d", 3, 0.0, 1), ("x", 2, 0.0, 1), ("y", 1, 0.0, 1)], "code string, exp_support int, score double, last_time int")
    assert A.precision_at_k(truth, found, 4).first().precision == 50.0
    pairs = spark.createDataFrame([("p", 1, 1), ("q", 2, 2), ("r", 2, 3), ("s", 3, 3)], "code string, x int, y int")
    r = A.kendall_tau_b(pairs, "x", "y").first()
    assert (r.concordant, r.discordant) == (4, 0) and r.tau_b == pytest.approx(0.8)
    chains = spark.createDataFrame([(0, c) for c in "abc"] + [(1, c) for c in "bcd"], "chain int, code string")
    assert A.chain_jaccard(chains).first().distance == 0.5


def test_model_rules(spark):
    v = spark.createDataFrame([(1, 1, "A"), (1, 2, "B"), (1, 3, "C"), (1, 4, None)], "gid long, vid long, vlabel string")
    raw = spark.createDataFrame([(1, 2, 1, "y"), (1, 1, 2, "x"), (1, 3, 3, "z"), (1, 3, 9, None)], "gid long, src long, dst long, elabel string")
    proper = raw.where("dst < 9")
    found = {r["rule"] for r in validate(GraphDB(v, proper)).collect()}
    assert found == {"loop", "order", "parallel", "unlabelled vertex", "disconnected"}
    e = simplify(raw.where("dst < 9"))
    assert [tuple(r) for r in e.collect()] == [(1, 1, 2, "x")]
    db = GraphDB(v, e)
    assert sorted(tuple(r) for r in components(db).collect()) == [(1, 1, 1), (1, 2, 1), (1, 3, 3), (1, 4, 4)]
    assert sorted(r.vid for r in largest_component(db).vertices.collect()) == [1, 2]
    assert stats(db).first().n_graphs == 1


def test_files_round_trip(spark, toy, tmp_path):
    path = str(tmp_path / "graphs")
    linegraph.write(toy, path)
    for back in (linegraph.read(spark, path), linegraph.read_lines(spark, path)):
        assert sorted(map(tuple, back.vertices.collect())) == sorted(map(tuple, toy.vertices.collect()))
        assert sorted(map(tuple, back.edges.collect())) == sorted(map(tuple, toy.edges.collect()))


def test_plans(users):
    types = S.edge_support(users)
    plan = W.run_walks(users, 3, 100, types=types)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "MapInPandas" in plan
    packed = pack(users, types)._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in packed
    near = builders.proximity(users.spark, SF).edges._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in near and "NestedLoop" not in near and "props" not in near


def test_s2_is_exact_at_every_number_of_graphs(spark, monkeypatch):
    from patternwalk.model import EDGES, VERTICES, GraphDB
    from patternwalk.operators import support as S

    monkeypatch.setattr(S, "SKETCH_GRAPHS", 8)
    monkeypatch.setattr(S, "NUMBERED", 7, raising=False)
    v = [(g, i, c) for g in range(60) for i, c in enumerate("ABC" if g % 3 else "AAB")]
    e = [(g, 0, 1, "x") for g in range(60)] + [(g, 1, 2, "x") for g in range(60) if g % 2]
    db = GraphDB(spark.createDataFrame(v, VERTICES), spark.createDataFrame(e, EDGES))
    types = S.edge_support(db, sets=True)
    rows = {r.etype: set(r.tids) for r in types.collect()}
    scores = S.score_table(db, types, "s2")
    for a in rows:
        for b in rows:
            assert scores.of([a, b]) == (max(1, len(rows[a] & rows[b])), 1)
    assert S.score_table(db, types, "s2_hashed").of([0])[0] <= 8


def test_distinct_labels_beyond_two_edges(spark):
    from itertools import combinations

    from patternwalk.model import EDGES, VERTICES, GraphDB

    shapes = [[(0, 1), (1, 2), (0, 2), (2, 3), (3, 4)], [(0, 1), (1, 2), (0, 2), (2, 3)], [(0, 1), (1, 2), (2, 3), (3, 4)]]
    v = [(g, i, "ABCDE"[i]) for g in range(3) for i in range(5)]
    db = GraphDB(spark.createDataFrame(v, VERTICES), spark.createDataFrame([(g, a, b, "x") for g, es in enumerate(shapes) for a, b in es], EDGES))

    def connected(es):
        grown = set(es[0])
        for _ in es:
            grown |= {x for e in es if grown & set(e) for x in e}
        return all(set(e) <= grown for e in es)

    want = {}
    for es in {c for s in shapes for n in range(1, 6) for c in combinations(sorted(s), n) if connected(c)}:
        if (support := sum(set(es) <= set(s) for s in shapes)) >= 2:
            want[";".join(sorted(f"{'ABCDE'[a]},x,{'ABCDE'[b]}" for a, b in es))] = (support, len(es))
    assert max(n for _, n in want.values()) == 4
    assert {r.code: (r.support, r.n_edges) for r in B.mine_distinct_labels(db, 2).collect()} == want
    paths = GraphDB(db.vertices.where("gid < 2"), spark.createDataFrame([(g, a, a + 1, "x") for g in range(2) for a in range(4)], EDGES))
    assert {r.n_vertices for r in B.mine_complete(paths, 2, induced=True).collect()} == {2, 3, 4, 5}


def test_complete_experiments_have_no_edge_cap(toy, monkeypatch):
    """One run at the largest size and least support, every number of edges; sizes stop at 3, as the README says."""
    from patternwalk import workloads

    seen, mine = [], B.mine_complete
    monkeypatch.setattr(workloads, "prox", lambda *a: type("D", (), {"stored": lambda self: toy})())
    monkeypatch.setattr(workloads.B, "mine_complete", lambda db, x, **how: seen.append((x, how)) or mine(db, 0.6, **how))
    by_size = {r.max_size: r.patterns for r in workloads.QUERIES["w1_complete_by_size"](None, "").collect()}
    workloads.QUERIES["w2_complete_by_support"](None, "")
    assert seen == [(0.4, {"max_size": 3}), (0.11, {"max_size": 3})]
    assert {r.n_edges for r in mine(toy, 0.6, max_size=3).collect()} == {1, 2, 3} and by_size[2] < by_size[3]
