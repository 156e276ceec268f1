"""Registered queries: methods, measures and experiments on the given tables, and their SQL twins."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from patternwalk.functions import accuracy as A
from patternwalk.model import GraphDB, components, frequent, stats, validate
from patternwalk.operators import complete as B
from patternwalk.operators import enumerate as E
from patternwalk.operators import law as L
from patternwalk.operators import queue as Q
from patternwalk.operators import sampler as W
from patternwalk.operators import support as S
from patternwalk.operators.canon import respelled, with_code
from patternwalk.operators.mine import mine_sizes, mine_top_k, ranked
from patternwalk.plans import oracles as O
from patternwalk.plans.scratch import cut
from patternwalk.sources import builders
from patternwalk.sources.tables import table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
Query = Callable[[SparkSession, str], DataFrame]


def register(name: str, oracle: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if oracle is not None:
            ORACLES[name] = oracle
        return f

    return add


def prox(spark: SparkSession, sf_dir: str, alphabet: str = "coarse") -> GraphDB:
    return builders.proximity(spark, sf_dir, alphabet)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mine_top_k(prox(spark, sf_dir).stored(), 3, k=20, m=3000, score="s2")


joined = lambda c: F.concat_ws(",", F.transform(c, lambda x: x.cast("string")))
PX = O.proximity("coarse")
LIST = "array_to_string(vs, ',') AS vs"

# Databases and their statistics
_STATS = {
    **{f"proximity_{a}": (lambda s, d, a=a: builders.proximity(s, d, a), O.proximity(a)) for a in ("fine", "coarse", "skewed")},
    "order_star": (builders.order_star, O.STAR),
    "dialogue": (builders.dialogue, O.DIALOGUE),
    "token_adj": (builders.token_adj, O.tokens("documents", "doc_id")),
    "probe": (builders.probe, O.tokens("benchmark", "item_id")),
    "vector_radius": (builders.vector_radius, f"{O.VECTOR},{O.LARGEST}"),
    "copurchase": (builders.copurchase, f"{O.COPURCHASE},{O.LARGEST}"),
    "dom_tree": (builders.dom_tree, None),
    "two_class": (builders.two_class, O.tokens("documents", "doc_id", "doc_id IN (SELECT doc_id FROM labels)")),
    "synthetic": (builders.synthetic_on, O.SYNTHETIC),
}
for _name, (_build, _sql) in _STATS.items():
    recursive = "WITH RECURSIVE" if _sql and "reach AS" in _sql else "WITH"
    register(f"db_stats_{_name}", _sql and f"{recursive} {_sql} {O.STATS}")(lambda s, d, f=_build: stats(f(s, d)))


@register("validate_proximity", f"WITH {PX} SELECT gid, 'x' AS rule, 0::BIGINT AS n FROM e WHERE src >= dst")
def _(spark, sf_dir):
    return validate(prox(spark, sf_dir))


@register("components_vector_radius", f"WITH RECURSIVE {O.VECTOR}, {O.LARGEST}, rr AS (SELECT gid, vid, vid AS far FROM v UNION SELECT r.gid, r.vid, s.b FROM rr r JOIN sy s ON s.gid = r.gid AND s.a = r.far SEMI JOIN v ON v.gid = s.gid AND v.vid = s.b), cc AS (SELECT gid, vid, min(far) AS comp FROM rr GROUP BY ALL) SELECT gid, comp, count(*) AS n FROM cc GROUP BY ALL")
def _(spark, sf_dir):
    return components(builders.vector_radius(spark, sf_dir)).groupBy("gid", "comp").agg(F.count("*").alias("n"))


# Edge supports and scores
for _a in ("coarse", "fine", "skewed"):
    register(f"edge_support_{_a}", f"WITH {O.proximity(_a)}, {O.TYPES} SELECT etype::INT AS etype, la, el, lb, support FROM ty")(lambda s, d, a=_a: S.edge_support(prox(s, d, a)))


@register("edge_support_sets", f"WITH {PX}, {O.TYPES}, d AS (SELECT DISTINCT la, el, lb, gid FROM te) SELECT la, el, lb, count(*) AS support, string_agg(gid::VARCHAR, ',' ORDER BY gid) AS tids FROM d GROUP BY la, el, lb")
def _(spark, sf_dir):
    return S.edge_support(prox(spark, sf_dir), sets=True).select("la", "el", "lb", "support", joined("tids").alias("tids"))


@register("edge_support_order_star", f"WITH {O.STAR}, {O.TYPES} SELECT etype::INT AS etype, la, el, lb, support FROM ty")
def _(spark, sf_dir):
    return S.edge_support(builders.order_star(spark, sf_dir))


_P3 = f"WITH {PX}, {O.pieces(3)}"
_SMALL = f"WITH {O.proximity('coarse')}, {O.pieces(3)}, {O.TYPES}, {O.scores(3)}"


@register("score_s1_p3", f"{_SMALL} SELECT gid, {LIST}, s1_num, s1_den, s1 FROM s1s")
def _(spark, sf_dir):
    db = prox(spark, sf_dir)
    rows = S.piece_types(db, E.enumerate_induced(db, 3), S.edge_support(db))
    return S.score_s1(rows, ["gid", "vs"]).withColumn("vs", joined("vs"))


@register("score_s2_p3", f"{_SMALL} SELECT gid, {LIST}, s2 FROM s2s")
def _(spark, sf_dir):
    db = prox(spark, sf_dir)
    types = S.edge_support(db, sets=True)
    return S.score_s2(S.piece_types(db, E.enumerate_induced(db, 3), types), types, ["gid", "vs"]).withColumn("vs", joined("vs"))


@register("score_s2_min_bound", f"{_SMALL} SELECT gid, {LIST}, min(support) AS s2 FROM pe GROUP BY gid, pe.vs")
def _(spark, sf_dir):
    db = prox(spark, sf_dir)
    types = S.edge_support(db)
    return S.score_s2(S.piece_types(db, E.enumerate_induced(db, 3), types), types, ["gid", "vs"], "min_bound").withColumn("vs", joined("vs"))


# Enumeration and truth
@register("pieces_p3_count", f"{_P3} SELECT gid, count(*) AS n FROM s3 GROUP BY gid")
def _(spark, sf_dir):
    return E.enumerate_induced(prox(spark, sf_dir), 3).groupBy("gid").agg(F.count("*").alias("n"))


@register("pieces_p4_kernel_count", f"WITH {PX}, {O.pieces(4)} SELECT gid, count(*) AS n FROM s4 GROUP BY gid")
def _(spark, sf_dir):
    return E.space_size(prox(spark, sf_dir), 4)


@register("space_growth", f"WITH {PX}, {O.pieces(4)} SELECT 2 AS p, count(*)::BIGINT AS pieces FROM s2 UNION ALL SELECT 3, count(*) FROM s3 UNION ALL SELECT 4, count(*) FROM s4")
def _(spark, sf_dir):
    return E.space_growth(prox(spark, sf_dir), [2, 3, 4])


@register("space_estimate_p5")
def _(spark, sf_dir):
    return E.space_estimate(prox(spark, sf_dir), 5, samples=50)


for _a in ("coarse", "skewed"):
    for _p in (3, 4):
        if _p == 3 or _a == "coarse":
            register(f"pattern_support_p{_p}_{_a}", f"WITH {O.proximity(_a)}, {O.pieces(_p)}, {O.codes(_p)}, {O.SUPPORT} SELECT code, support, embeddings FROM su")(
                lambda s, d, a=_a, p=_p: E.supports_of(E.pattern_counts(prox(s, d, a), p))
            )


@register("ground_truth_p3", f"{_P3}, {O.codes(3)}, {O.SUPPORT} SELECT count(*) AS patterns, sum(support)::BIGINT AS supports, sum(embeddings)::BIGINT AS pieces, max(support) AS top FROM su")
def _(spark, sf_dir):
    return E.ground_truth(prox(spark, sf_dir), 3).agg(F.count("*").alias("patterns"), F.sum("support").alias("supports"), F.sum("embeddings").alias("pieces"), F.max("support").alias("top"))


@register("bounds_p3", f"{_SMALL}, {O.codes(3)}, {O.SUPPORT}, bd AS (SELECT code, any_value(s2) AS s2, any_value(s1_num) AS a, any_value(s1_den) AS b FROM cd JOIN s1s ON s1s.gid = cd.gid AND s1s.vs = cd.vs JOIN s2s ON s2s.gid = cd.gid AND s2s.vs = cd.vs GROUP BY code) SELECT code FROM su JOIN bd USING (code) WHERE support > s2 OR s2 * b > a")
def _(spark, sf_dir):
    return A.bound_violations(E.ground_truth(prox(spark, sf_dir), 3))


@register("induced_below_plain_p3", "SELECT ''::VARCHAR AS code, 0::BIGINT AS support_plain, 0::BIGINT AS support_induced WHERE false")
def _(spark, sf_dir):
    return E.support_both(prox(spark, sf_dir), 3).where("support_induced > support_plain")


@register("frequent_p3_minsup", f"{_P3}, {O.codes(3)}, {O.SUPPORT} SELECT code, support FROM su WHERE support >= ceil(0.4 * (SELECT count(DISTINCT gid) FROM v))")
def _(spark, sf_dir):
    db = prox(spark, sf_dir)
    found = E.support_sets(E.piece_codes(db, E.enumerate_induced(db, 3), 3))
    return frequent(found, 0.4, db.vertices.select("gid").distinct().count()).select("code", "support")


# The law of the walk
@register("neighbour_degree_p3", f"{_SMALL}, {O.law(3, 'uniform')} SELECT gid, {LIST}, d FROM dg")
def _(spark, sf_dir):
    return L.degrees(prox(spark, sf_dir), 3).where("d > 0").withColumn("vs", joined("vs"))


@register("swap_boxes_p3", f"{_SMALL}, {O.law(3, 'uniform')}, g AS (SELECT gid, vs, list_filter(vs, lambda y: NOT list_contains(ws, y))[1] AS u, list_filter(ws, lambda y: NOT list_contains(vs, y))[1] AS w FROM nb) SELECT gid, {LIST}, u, string_agg(w::VARCHAR, ',' ORDER BY w) AS box FROM g GROUP BY gid, g.vs, u")
def _(spark, sf_dir):
    return L.swap_boxes(prox(spark, sf_dir), 3).select("gid", joined("vs").alias("vs"), "u", joined("box").alias("box"))


for _s in ("uniform", "s1", "s2"):
    register(f"acceptance_p3_{_s}", f"{_SMALL}, {O.law(3, _s)} SELECT gid, {LIST}, count(*) AS moves, sum(floor(alpha * 1000000)::BIGINT)::BIGINT AS alphas, round(min(alpha), 9) AS least FROM tr GROUP BY gid, tr.vs")(
        lambda s, d, v=_s: L.acceptances(prox(s, d), 3, v).withColumn("least", F.round("least", 9)).withColumn("vs", joined("vs"))
    )


@register("acceptance_rate_p3", f"{_SMALL}, {O.law(3, 's2')} SELECT gid, round(sum(alpha / d) / count(DISTINCT vs), 9) AS rate FROM tr GROUP BY gid")
def _(spark, sf_dir):
    return L.acceptance_rates(prox(spark, sf_dir), 3).withColumn("rate", F.round("rate", 9))


@register("balance_residual_p3", f"{_SMALL}, {O.law(3, 's2')}, fl AS (SELECT gid, vs, ws, num / den * alpha / d AS f FROM tr) SELECT max(abs(a.f - b.f) / a.f) < 1e-12 AS balanced FROM fl a JOIN fl b ON a.gid = b.gid AND a.vs = b.ws AND a.ws = b.vs")
def _(spark, sf_dir):
    return L.balance_residual(prox(spark, sf_dir), 3).select((F.col("residual") < 1e-12).alias("balanced"))


@register("jump_law_p3", f"{_SMALL}, {O.law(3, 's2')}, a AS (SELECT gid, vs, any_value(num) * sum(alpha / d) AS w FROM tr GROUP BY gid, vs), z AS (SELECT gid, sum(w) AS z FROM a GROUP BY gid) SELECT gid, {LIST}, round(w / z, 9) AS pi FROM a JOIN z USING (gid)")
def _(spark, sf_dir):
    return L.stationary(prox(spark, sf_dir), 3, "s2", "accepted").select("gid", joined("vs").alias("vs"), F.round("pi", 9).alias("pi"))


@register("asymmetric_pairs_p3", f"{_SMALL}, {O.law(3, 'uniform')} SELECT a.gid, array_to_string(a.vs, ',') AS vs FROM nb a ANTI JOIN nb b ON a.gid = b.gid AND a.vs = b.ws AND a.ws = b.vs")
def _(spark, sf_dir):
    return L.asymmetric_pairs(prox(spark, sf_dir), 3).select("gid", joined("vs").alias("vs"))


@register("unreached_p3", "SELECT 0::BIGINT AS gid, 0::BIGINT AS parts WHERE false")
def _(spark, sf_dir):
    return L.unreached(prox(spark, sf_dir), 3)


# Schedules, walks, queues
_EL = "el AS (SELECT gid, row_number() OVER (ORDER BY gid) - 1 AS place FROM (SELECT gid FROM v GROUP BY gid HAVING count(*) >= 3) SEMI JOIN e USING (gid))"


@register("schedule_counter", f"WITH {PX}, {_EL}, {O.schedule(2000, 7, 2)} SELECT chain, gid, count(*) AS n, min(iter) AS first, max(iter) AS last FROM sd GROUP BY chain, gid")
def _(spark, sf_dir):
    s = W.schedule(W.eligible(prox(spark, sf_dir), 3), 2000, seed=7, chains=2)
    return s.select("chain", "gid", F.size("iters").cast("long").alias("n"), F.array_min("iters").alias("first"), F.array_max("iters").alias("last"))


@register("schedule_multinomial")
def _(spark, sf_dir):
    return W.schedule(W.eligible(prox(spark, sf_dir), 3), 2000, mode="multinomial").select("gid", F.size("iters").alias("n"))


def _walk_sql(score: str = "s2", m: int = 300, chains: int = 1, emit: str = "accepted", more: str = "") -> str:
    """The walk of coarse proximity graphs, its patterns' names, and what ``more`` names of the graphs' truth."""
    return f"WITH RECURSIVE {O.proximity('coarse')}, {O.pieces(3)}, {O.TYPES}, {O.scores(3)}, {O.law(3, score)}, {_EL}, {O.walk(m, chains, emit)}, {O.codes(3)}, {O.MINED}{more}"


_TRUTH = f", {O.SUPPORT}, tt AS (SELECT code, support, row_number() OVER (ORDER BY support DESC, code) AS tr FROM su)"


@register("walk_p3_samples", f"{_walk_sql()} SELECT iter, gid, {LIST} FROM smp")
def _(spark, sf_dir):
    return W.run_walks(prox(spark, sf_dir), 3, 300).select("iter", "gid", joined("vs").alias("vs"))


@register("walk_lazy_p3_samples", f"{_walk_sql(emit='lazy')} SELECT iter, gid, {LIST} FROM smp")
def _(spark, sf_dir):
    return W.run_walks(prox(spark, sf_dir), 3, 300, emit="lazy").select("iter", "gid", joined("vs").alias("vs"))


@register("walk_round_robin_p3", f"{_walk_sql().replace(O.schedule(300, 0, 1), 'sd AS (SELECT 0 AS chain, iter, gid FROM (SELECT unnest(range(1, 301)) AS iter) JOIN el ON place = (iter - 1) % (SELECT count(*) FROM el))')} SELECT iter, gid, {LIST} FROM smp")
def _(spark, sf_dir):
    return W.run_walks(prox(spark, sf_dir), 3, 300, mode="round_robin").select("iter", "gid", joined("vs").alias("vs"))


@register("walk_resumed_p3", f"{_walk_sql()} SELECT iter, gid, {LIST} FROM smp WHERE iter > 150")
def _(spark, sf_dir):
    """The second half of a run, from the saved states of the first."""
    db = prox(spark, sf_dir).stored()
    _, state = W.run_walks(db, 3, 150, want_state=True)
    return W.run_walks(db, 3, 150, first=151, state=cut(state, "state")).select("iter", "gid", joined("vs").alias("vs"))


@register("expected_support_p3", f"{_walk_sql()} SELECT code, exp_support, last_time FROM mq")
def _(spark, sf_dir):
    db = prox(spark, sf_dir)
    samples = W.run_walks(db, 3, 300)
    coded = samples.join(E.piece_codes(db, samples.select("gid", "vs").distinct(), 3), ["gid", "vs"])
    return Q.expected_support(coded).select("code", "exp_support", "last_time")


@register("walk_stats_p3", f"{_walk_sql('s2', 1000)}, pr AS (SELECT chain, gid, min(attempt) AS n FROM walk WHERE k = last GROUP BY chain, gid) SELECT chain, (SELECT count(*) FROM smp) AS samples, sum(n)::BIGINT AS proposals, round(((SELECT count(*) FROM smp) - count(*)) / sum(n), 9) AS acceptance FROM pr GROUP BY chain")
def _(spark, sf_dir):
    return W.walk_stats(W.run_walks(prox(spark, sf_dir).stored(), 3, 1000)).select("chain", "samples", "proposals", F.round("acceptance", 9).alias("acceptance"))


@register("walk_stats_lazy")
def _(spark, sf_dir):
    return W.walk_stats(W.run_walks(prox(spark, sf_dir).stored(), 3, 2000, emit="lazy"))


@register("walk_plain_p4")
def _(spark, sf_dir):
    return W.walk_stats(W.run_walks(prox(spark, sf_dir).stored(), 4, 300, induced=False))


for _s in ("uniform", "s1", "s2"):
    register(f"mine_top_k_{_s}", f"{_walk_sql(_s, 3000)} SELECT * FROM mined WHERE rank <= 100")(lambda s, d, v=_s: mine_top_k(prox(s, d).stored(), 3, k=100, m=3000, score=v, naming="permutation"))


@register("mine_chains", f"{_walk_sql('s2', 1000, 3)} SELECT * FROM mined WHERE rank <= 50")
def _(spark, sf_dir):
    return mine_top_k(prox(spark, sf_dir).stored(), 3, k=50, m=1000, chains=3, naming="permutation")


_KEPT = "x.code AS code, (-x.a)::INT AS exp_support, -x.b AS score, -x.c AS last_time"


@register("mine_bounded_queue", f"{_walk_sql('s2', 1000, more=', ' + O.replay(200))} SELECT 0 AS chain, place::INT AS rank, {_KEPT} FROM kept WHERE place <= 100")
def _(spark, sf_dir):
    return mine_top_k(prox(spark, sf_dir).stored(), 3, k=100, m=1000, queue=Q.QueuePolicy(200), naming="permutation")


@register("mine_sharded_queue")
def _(spark, sf_dir):
    return mine_top_k(prox(spark, sf_dir).stored(), 3, k=100, m=3000, queue=Q.QueuePolicy(200), shards=4)


@register("mine_plain")
def _(spark, sf_dir):
    return mine_top_k(prox(spark, sf_dir).stored(), 3, k=100, m=1000, induced=False)


@register("mine_sizes")
def _(spark, sf_dir):
    return mine_sizes(prox(spark, sf_dir).stored(), [2, 3, 4], k=20, m=1000)


@register("queue_exact_equals_lossless", f"{_walk_sql('s2', 500, more=', ' + O.replay(1_000_000))}, fin AS (SELECT {_KEPT} FROM kept), lq AS (SELECT code, exp_support, score, last_time FROM mq) SELECT code FROM ((SELECT * FROM fin EXCEPT ALL SELECT * FROM lq) UNION ALL (SELECT * FROM lq EXCEPT ALL SELECT * FROM fin))")
def _(spark, sf_dir):
    s = W.run_walks(prox(spark, sf_dir).stored(), 3, 2000)
    cols = ["code", "exp_support", "score", "last_time"]
    a, b = Q.replay_queue(s, Q.QueuePolicy(1_000_000, "off")).select(*cols), Q.lossless_queue(s).select(*cols)
    return a.exceptAll(b).unionByName(b.exceptAll(a)).select("code")


@register("sketch_queue", f"{_walk_sql('s2', 2000)} SELECT code, exp_support::BIGINT AS exp_support, score FROM mined ORDER BY exp_support DESC, code LIMIT 50")
def _(spark, sf_dir):
    """Sketches of so few graphs are exact."""
    return Q.sketch_queue(W.run_walks(prox(spark, sf_dir).stored(), 3, 2000), naming="permutation").orderBy(F.desc("exp_support"), "code").limit(50)


@register("merge_queues_of_chains", f"{_walk_sql('s2', 1000, 2)} SELECT code, count(DISTINCT gid)::INT AS exp_support, max(score) AS score, max(l) AS last_time FROM (SELECT *, max(t) OVER (PARTITION BY chain, code) AS l FROM fs) GROUP BY code")
def _(spark, sf_dir):
    q = cut(Q.replay_queue(W.run_walks(prox(spark, sf_dir).stored(), 3, 1000, chains=2), Q.QueuePolicy(10_000), naming="permutation"), "queues")
    return Q.merge_queues(q.where("chain = 0"), q.where("chain = 1")).select("code", "exp_support", "score", "last_time")


@register("queue_stats", f"{_walk_sql('s2', 1000, more=', ' + O.replay(200))} SELECT count(*) AS size, min(-x.a)::INT AS least_support, avg(CASE WHEN place > n - greatest(1, n // 2) THEN -x.b END) AS tail_mean, sum(length(x.code) + 8 * len(x.ids) + 24)::BIGINT AS bytes FROM kept")
def _(spark, sf_dir):
    return Q.queue_stats(Q.replay_queue(W.run_walks(prox(spark, sf_dir).stored(), 3, 1000), Q.QueuePolicy(200), naming="permutation"))


@register("precision_of_mined_p3", f"{_walk_sql('s2', 3000, more=_TRUTH)} SELECT 100 AS k, count(*) AS hits, count(*) * 100.0::DOUBLE / 100 AS precision FROM tt JOIN mined USING (code) WHERE tr <= 100 AND rank <= 100")
def _(spark, sf_dir):
    db = prox(spark, sf_dir).stored()
    truth = E.support_sets(E.piece_codes(db, E.enumerate_induced(db, 3), 3))
    return A.precision_at_k(truth, mine_top_k(db, 3, k=100, m=3000, naming="permutation"), 100)


@register("tau_of_mined_p3", f"""{_walk_sql('s2', 3000, more=_TRUTH)}, uu AS (SELECT tt.code, support, CASE WHEN rank <= 100 THEN exp_support ELSE 0 END AS x FROM tt LEFT JOIN mined USING (code) WHERE tr <= 100 OR rank <= 100),
 pp AS (SELECT sign(a.support - b.support) * sign(a.x - b.x) AS s, a.support <> b.support AS nx, a.x <> b.x AS ny FROM uu a JOIN uu b ON a.code < b.code)
 SELECT sum((s > 0)::INT)::BIGINT AS concordant, sum((s < 0)::INT)::BIGINT AS discordant, round((sum((s > 0)::INT) - sum((s < 0)::INT)) / sqrt(sum(nx::INT)::DOUBLE * sum(ny::INT)), 9) AS tau_b FROM pp""")
def _(spark, sf_dir):
    db = prox(spark, sf_dir).stored()
    truth = E.support_sets(E.piece_codes(db, E.enumerate_induced(db, 3), 3))
    u = A.union_for_tau(truth, mine_top_k(db, 3, k=100, m=3000, naming="permutation"), 100)
    return A.kendall_tau_b(u, "support", "exp_support").withColumn("tau_b", F.round("tau_b", 9))


@register("jaccard_of_mined_chains", f"{_walk_sql('s2', 1000, 3)}, o AS (SELECT chain, code FROM mined WHERE rank <= 100), n AS (SELECT chain, count(*) AS n FROM o GROUP BY chain), s AS (SELECT a.chain AS a, b.chain AS b, count(*) AS c FROM o a JOIN o b ON a.code = b.code AND a.chain < b.chain GROUP BY ALL) SELECT count(*) AS pairs, round(avg(1 - coalesce(c, 0) / (x.n + y.n - coalesce(c, 0))), 9) AS distance FROM n x JOIN n y ON x.chain < y.chain LEFT JOIN s ON s.a = x.chain AND s.b = y.chain")
def _(spark, sf_dir):
    found = mine_top_k(prox(spark, sf_dir).stored(), 3, k=100, m=1000, chains=3, naming="permutation")
    return A.chain_jaccard(found).withColumn("distance", F.round("distance", 9))


# Measures on deterministic inputs: a mined side is stood in for by a hash order that SQL knows
_MEASURE = f"""{_P3}, {O.codes(3)}, {O.SUPPORT},
tt AS (SELECT code, support, row_number() OVER (ORDER BY support DESC, code) AS tr FROM su),
ff AS (SELECT code, support % 7 + 1 AS exp_support, row_number() OVER (ORDER BY support % 7 DESC, code) AS qr FROM su)"""


def _sides(spark, sf_dir):
    db = prox(spark, sf_dir)
    truth = E.support_sets(E.piece_codes(db, E.enumerate_induced(db, 3), 3))
    found = truth.select("code", (F.col("support") % 7 + 1).cast("int").alias("exp_support"), F.lit(0.0).alias("score"), F.lit(0).cast("long").alias("last_time"))
    return truth, found


@register("precision_at_k", f"{_MEASURE} SELECT 100 AS k, count(*) AS hits, count(*) * 100.0::DOUBLE / 100 AS precision FROM tt JOIN ff USING (code) WHERE tr <= 100 AND qr <= 100")
def _(spark, sf_dir):
    truth, found = _sides(spark, sf_dir)
    return A.precision_at_k(truth, found.orderBy(F.desc("exp_support"), "code").limit(100), 100)


@register("precision_curve", f"{_MEASURE} SELECT k, count(code) AS hits, count(code) * 100.0::DOUBLE / k AS precision FROM (VALUES (50), (100), (200)) ks(k) LEFT JOIN (SELECT code, tr, qr FROM tt JOIN ff USING (code)) ON tr <= k AND qr <= k GROUP BY k")
def _(spark, sf_dir):
    return A.precision_curve(*_sides(spark, sf_dir), [50, 100, 200])


@register("kendall_tau_b", f"""{_MEASURE}, uu AS (SELECT code, support, CASE WHEN qr <= 100 THEN exp_support ELSE 0 END AS x FROM tt JOIN ff USING (code) WHERE tr <= 100 OR qr <= 100),
 pp AS (SELECT sign(a.support - b.support) * sign(a.x - b.x) AS s, a.support <> b.support AS nx, a.x <> b.x AS ny FROM uu a JOIN uu b ON a.code < b.code)
 SELECT sum((s > 0)::INT)::BIGINT AS concordant, sum((s < 0)::INT)::BIGINT AS discordant, round((sum((s > 0)::INT) - sum((s < 0)::INT)) / sqrt(sum(nx::INT)::DOUBLE * sum(ny::INT)), 9) AS tau_b FROM pp""")
def _(spark, sf_dir):
    truth, found = _sides(spark, sf_dir)
    u = A.union_for_tau(truth, found.orderBy(F.desc("exp_support"), "code").limit(100), 100)
    return A.kendall_tau_b(u, "support", "exp_support").withColumn("tau_b", F.round("tau_b", 9))


@register("chain_jaccard", "WITH o AS (SELECT DISTINCT user_id % 5 AS chain, floor(value)::BIGINT AS code FROM events), n AS (SELECT chain, count(*) AS n FROM o GROUP BY chain), s AS (SELECT a.chain AS a, b.chain AS b, count(*) AS c FROM o a JOIN o b ON a.code = b.code AND a.chain < b.chain GROUP BY ALL) SELECT count(*) AS pairs, round(avg(1 - coalesce(c, 0) / (x.n + y.n - coalesce(c, 0))), 9) AS distance FROM n x JOIN n y ON x.chain < y.chain LEFT JOIN s ON s.a = x.chain AND s.b = y.chain")
def _(spark, sf_dir):
    e = table(spark, sf_dir, "events").select((F.col("user_id") % 5).alias("chain"), F.floor("value").alias("code"))
    return A.chain_jaccard(e).withColumn("distance", F.round("distance", 9))


@register("gelman_rubin", "WITH p AS (SELECT user_id % 5 AS c, avg(value) AS m, var_samp(value) AS v, count(*) AS n FROM events GROUP BY c), q AS (SELECT avg(v) AS w, var_samp(m) AS b, avg(n) AS n, count(*) AS chains FROM p) SELECT chains, round(w, 6) AS w, round(b, 6) AS b_over_n, round(sqrt(((n - 1) / n * w + b) / w), 9) AS r_hat FROM q")
def _(spark, sf_dir):
    e = table(spark, sf_dir, "events").select((F.col("user_id") % 5).alias("chain"), "value")
    return A.gelman_rubin(e, "value").select("chains", F.round("w", 6).alias("w"), F.round("b_over_n", 6).alias("b_over_n"), F.round("r_hat", 9).alias("r_hat"))


_SCORED = "JOIN s1s ON s1s.gid = cd.gid AND s1s.vs = cd.vs JOIN s2s ON s2s.gid = cd.gid AND s2s.vs = cd.vs"
_ST = f"{_SMALL}, {O.codes(3)}, {O.SUPPORT}, pt AS (SELECT code, any_value(support)::DOUBLE AS support, any_value(s1)::DOUBLE AS s1, any_value(s2)::DOUBLE AS s2 FROM cd JOIN su USING (code) {_SCORED} GROUP BY code)"
_CORR = ", ".join(f"""r{_s} AS (SELECT code, support AS x, {_s} AS y, avg(i) OVER (PARTITION BY support) AS rx, avg(j) OVER (PARTITION BY {_s}) AS ry FROM (SELECT *, row_number() OVER (ORDER BY support) AS i, row_number() OVER (ORDER BY {_s}) AS j FROM pt)),
 k{_s} AS (SELECT (sum((s > 0)::INT) - sum((s < 0)::INT)) / sqrt(sum(nx::INT)::DOUBLE * sum(ny::INT)) AS t FROM (SELECT sign(a.x - b.x) * sign(a.y - b.y) AS s, a.x <> b.x AS nx, a.y <> b.y AS ny FROM r{_s} a JOIN r{_s} b ON a.code < b.code))""" for _s in ("s1", "s2"))


@register("score_correlation_p3", f"{_ST}, {_CORR} " + " UNION ALL ".join(f"SELECT '{_s}' AS score, round(corr(x, y), 6) AS pearson, round(corr(rx, ry), 6) AS spearman, round((SELECT t FROM k{_s}), 6) AS tau_b FROM r{_s}" for _s in ("s1", "s2")))
def _(spark, sf_dir):
    found = A.score_correlation(E.ground_truth(prox(spark, sf_dir), 3))
    return found.select("score", *[F.round(c, 6).alias(c) for c in ("pearson", "spearman", "tau_b")])


@register("score_correlation_skewed")
def _(spark, sf_dir):
    return A.score_correlation(E.ground_truth(prox(spark, sf_dir, "skewed"), 3))


@register("false_positive_rate_p3", f"{_ST} SELECT count(*) AS high, avg((support < 20)::INT) AS false_positive_rate FROM pt WHERE s2 >= 100")
def _(spark, sf_dir):
    return A.false_positive_rate(E.ground_truth(prox(spark, sf_dir), 3), "s2", 100.0, 20)


# Baselines
@register("blind_sample_p3", f"{_P3} SELECT gid, {LIST} FROM s3 ORDER BY {O.uniform(chr(39) + '0' + chr(39), 'gid::VARCHAR', 'array_to_string(s3.vs, chr(44))')}, gid LIMIT 500")
def _(spark, sf_dir):
    return B.blind_sample(prox(spark, sf_dir), 3, 500).select("gid", joined("vs").alias("vs"))


@register("direct_sample_p3")
def _(spark, sf_dir):
    return B.direct_sample(prox(spark, sf_dir), 3).select("gid", joined("vs").alias("vs"))


@register("complete_one_edge", f"WITH {PX}, {O.TYPES} SELECT '0,1,' || la || ',' || el || ',' || lb AS code, 2 AS n_vertices, 1 AS n_edges, support FROM ty WHERE support >= ceil(0.4 * (SELECT count(DISTINCT gid) FROM v))")
def _(spark, sf_dir):
    return B.mine_complete(prox(spark, sf_dir), 0.4, max_edges=1)


_PS = f"WITH {PX}, {O.plain_codes()}, fq AS (SELECT * FROM ps WHERE support >= ceil(0.8 * (SELECT count(DISTINCT gid) FROM v)))"
_spelled = lambda df: df.withColumn("code", respelled("code"))

for _k in ("growth", "levelwise"):
    register(f"complete_{_k}", f"{_PS} SELECT * FROM fq")(lambda s, d, k=_k: _spelled(B.mine_complete(prox(s, d), 0.8, max_size=3, strategy=k)))


@register("complete_maximal", f"{_PS} SELECT * FROM fq WHERE code NOT IN (SELECT part FROM parts JOIN fq USING (code))")
def _(spark, sf_dir):
    return _spelled(B.maximal(cut(B.mine_complete(prox(spark, sf_dir), 0.8, max_size=3), "complete")))


@register("complete_closed", f"{_PS} SELECT * FROM fq f WHERE NOT EXISTS (SELECT 1 FROM parts JOIN fq g USING (code) WHERE part = f.code AND g.support = f.support)")
def _(spark, sf_dir):
    return _spelled(B.closed(cut(B.mine_complete(prox(spark, sf_dir), 0.8, max_size=3), "complete")))


_IND = ", ".join(f"c{_p} AS (SELECT code, count(DISTINCT gid) AS support FROM ({O.codes(_p).removeprefix('cd AS ').strip()[1:-1]}) GROUP BY code)" for _p in (2, 3, 4))


@register("complete_induced", f"WITH {PX}, {O.pieces(4)}, {_IND} SELECT code, p AS n_vertices, len(list_filter(string_split(code, '|')[p + 1:], lambda x: x <> '-'))::INT AS n_edges, support FROM (SELECT *, 2 AS p FROM c2 UNION ALL SELECT *, 3 FROM c3 UNION ALL SELECT *, 4 FROM c4) WHERE support >= ceil(0.6 * (SELECT count(DISTINCT gid) FROM v))")
def _(spark, sf_dir):
    return _spelled(B.mine_complete(prox(spark, sf_dir).stored(), 0.6, max_size=4, induced=True))


@register("complete_stopped")
def _(spark, sf_dir):
    return B.mine_complete(prox(spark, sf_dir), 0.8, max_size=3, stop_after=20)


@register("pattern_lattice_walk")
def _(spark, sf_dir):
    return B.pattern_walk(B.mine_complete(prox(spark, sf_dir), 0.9, max_size=3), 500)


_TOK = O.tokens("documents", "doc_id")


@register("distinct_label_edges", f"WITH {_TOK}, {O.TYPES}, o AS (SELECT DISTINCT gid, la || ',' || el || ',' || lb AS k, la, lb FROM te), f AS (SELECT k AS code, count(*) AS support, 1 AS n_edges FROM o GROUP BY k HAVING count(*) >= 100), en AS (SELECT gid, k, unnest([la, lb]) AS v FROM o WHERE k IN (SELECT code FROM f)), tw AS (SELECT DISTINCT x.gid, x.k || ';' || y.k AS code FROM en x JOIN en y ON x.gid = y.gid AND x.v = y.v AND x.k < y.k) SELECT * FROM f UNION ALL SELECT code, count(*), 2 FROM tw GROUP BY code HAVING count(*) >= 100")
def _(spark, sf_dir):
    """The first two levels, which its SQL twin has; ``distinct_label_patterns`` has them all."""
    return B.mine_distinct_labels(builders.token_adj_packed(spark, sf_dir), 100, max_edges=2).select("code", "support", "n_edges")


@register("distinct_label_patterns")
def _(spark, sf_dir):
    return B.mine_distinct_labels(builders.token_adj_packed(spark, sf_dir), 100)


_TWO = O.tokens("documents", "doc_id", "doc_id IN (SELECT doc_id FROM labels)")


@register("discriminative_edges", f"WITH {_TWO}, {O.TYPES}, c AS (SELECT DISTINCT te.gid, la || '|' || lb AS code, quality AS y FROM te JOIN labels ON doc_id = te.gid), k AS (SELECT sum((quality = 0)::INT) AS n0, sum((quality = 1)::INT) AS n1 FROM labels) SELECT code, sum((y = 0)::INT)::BIGINT AS support_0, sum((y = 1)::INT)::BIGINT AS support_1, round(abs(sum((y = 0)::INT) / any_value(n0) - sum((y = 1)::INT) / any_value(n1)), 9) AS difference FROM c, k GROUP BY code HAVING count(*) >= 10")
def _(spark, sf_dir):
    db = builders.two_class(spark, sf_dir)
    coded = db.typed_edges().select("gid", F.concat_ws("|", "la", "lb").alias("code"))
    found = B.discriminative(coded, db.attrs.select("gid", F.col("quality").alias("y")))
    return found.where("support_0 + support_1 >= 10").select("code", "support_0", "support_1", F.round("difference", 9).alias("difference"))


@register("restricted_classes", f"WITH {O.DIALOGUE}, g AS (SELECT gid, count(*) AS n, count(*) = count(DISTINCT vlabel) AS distinct_labels, (SELECT count(*) FROM e WHERE e.gid = v.gid) AS n_e, (SELECT count(*) FROM e WHERE e.gid = v.gid) = count(*) - 1 AS connected FROM v GROUP BY gid) SELECT gid, n_e <= n - 1 AND connected AS is_forest, n_e <= n - 1 AND connected AS treewidth_le_2, distinct_labels FROM g")
def _(spark, sf_dir):
    return B.class_of(builders.dialogue(spark, sf_dir))


@register("restricted_classes_dom")
def _(spark, sf_dir):
    return B.class_of(builders.dom_tree(spark, sf_dir))


@register("pattern_features_p3")
def _(spark, sf_dir):
    db = prox(spark, sf_dir).stored()
    return B.pattern_features(db, mine_top_k(db, 3, k=20, m=2000), 3)


# Relations around the methods
@register("support_rollup", f"WITH {PX}, {O.TYPES} SELECT la, el, count(DISTINCT gid) AS graphs, count(*) AS edges FROM te GROUP BY ROLLUP (la, el)")
def _(spark, sf_dir):
    return prox(spark, sf_dir).typed_edges().rollup("la", F.col("elabel").alias("el")).agg(F.count_distinct("gid").alias("graphs"), F.count("*").alias("edges"))


@register("support_cube", f"WITH {PX}, {O.TYPES} SELECT la, lb, el, count(*) AS edges FROM te GROUP BY CUBE (la, lb, el)")
def _(spark, sf_dir):
    return prox(spark, sf_dir).typed_edges().cube("la", "lb", F.col("elabel").alias("el")).agg(F.count("*").alias("edges"))


_TE = f"WITH {PX}, {O.TYPES}"


@register("support_grouping_sets", f"{_TE} SELECT la, el, lb, count(DISTINCT gid) AS graphs FROM te GROUP BY GROUPING SETS ((la, lb), (el), ())")
def _(spark, sf_dir):
    prox(spark, sf_dir).typed_edges().createOrReplaceTempView("typed_edges")
    return spark.sql("SELECT la, elabel AS el, lb, count(DISTINCT gid) AS graphs FROM typed_edges GROUP BY GROUPING SETS ((la, lb), (elabel), ())")


@register("support_by_class_pivot", f"WITH {O.tokens('documents', 'doc_id', 'doc_id IN (SELECT doc_id FROM labels)')} SELECT vlabel, count(DISTINCT CASE WHEN quality = 0 THEN gid END) AS low, count(DISTINCT CASE WHEN quality = 1 THEN gid END) AS high FROM v JOIN labels ON doc_id = gid GROUP BY vlabel HAVING count(DISTINCT gid) >= 20")
def _(spark, sf_dir):
    """Supports of labels, a column for each class."""
    db = builders.two_class(spark, sf_dir)
    own = db.vertices.join(db.attrs.select("gid", F.col("quality").cast("string").alias("y")), "gid")
    wide = own.groupBy("vlabel").pivot("y", ["0", "1"]).agg(F.count_distinct("gid"))
    return wide.select("vlabel", F.coalesce("`0`", F.lit(0)).alias("low"), F.coalesce("`1`", F.lit(0)).alias("high")).where(F.col("low") + F.col("high") >= 20)


@register("support_growth", f"{_TE}, d AS (SELECT DISTINCT la, el, lb, gid FROM te) SELECT la, el, lb, gid, row_number() OVER w AS support, coalesce(gid - lag(gid) OVER w, -1) AS since, ntile(2) OVER w AS half FROM d WINDOW w AS (PARTITION BY la, el, lb ORDER BY gid)")
def _(spark, sf_dir):
    """How each edge type's support grows graph by graph, the gap since it last grew (-1 at first), and the half of its graphs."""
    by = Window.partitionBy("la", "el", "lb").orderBy("gid")
    own = prox(spark, sf_dir).typed_edges().select("la", F.col("elabel").alias("el"), "lb", "gid").distinct()
    return own.select("*", F.row_number().over(by).cast("long").alias("support"), F.coalesce(F.col("gid") - F.lag("gid").over(by), F.lit(-1)).alias("since"), F.ntile(2).over(by).cast("long").alias("half"))


@register("top_types_in_common", f"{_TE}, c AS (SELECT la, el, lb, count(DISTINCT gid) AS s, count(*) AS n FROM te GROUP BY la, el, lb) (SELECT la, el, lb FROM c ORDER BY s DESC, la, el, lb LIMIT 20) INTERSECT (SELECT la, el, lb FROM c ORDER BY n DESC, la, el, lb LIMIT 20)")
def _(spark, sf_dir):
    """Edge types that are among the top twenty both by graphs and by edges."""
    own = prox(spark, sf_dir).typed_edges().groupBy("la", F.col("elabel").alias("el"), "lb").agg(F.count_distinct("gid").alias("s"), F.count("*").alias("n"))
    top = lambda c: own.orderBy(F.desc(c), "la", "el", "lb").limit(20).select("la", "el", "lb")
    return top("s").intersect(top("n"))


@register("top_labels_lateral", f"WITH {PX}, c AS (SELECT gid, vlabel, count(*) AS n FROM v GROUP BY gid, vlabel) SELECT gid, vlabel, n FROM (SELECT *, row_number() OVER (PARTITION BY gid ORDER BY n DESC, vlabel) AS r FROM c) WHERE r <= 2")
def _(spark, sf_dir):
    """The two commonest labels of each graph, by a lateral subquery."""
    prox(spark, sf_dir).vertices.groupBy("gid", "vlabel").agg(F.count("*").alias("n")).createOrReplaceTempView("label_counts")
    return spark.sql("SELECT g.gid, t.vlabel, t.n FROM (SELECT gid, collect_list(struct(-n AS k, vlabel, n)) AS c FROM label_counts GROUP BY gid) g, LATERAL (SELECT x.vlabel, x.n FROM (SELECT explode(slice(array_sort(g.c), 1, 2)) AS x)) t")


@register("event_properties", "SELECT props->>'$.k' AS k, count(*) AS n, count(DISTINCT user_id) AS users FROM events GROUP BY ALL")
def _(spark, sf_dir):
    """A label taken from JSON."""
    return table(spark, sf_dir, "events").groupBy(F.get_json_object("props", "$.k").alias("k")).agg(F.count("*").alias("n"), F.count_distinct("user_id").alias("users"))


@register("sql_tau_b", f"{_MEASURE}, bo AS (SELECT code, tt.support, ff.exp_support FROM tt JOIN ff USING (code)), pp AS (SELECT sign(a.support - b.support) * sign(a.exp_support - b.exp_support) AS s, a.support <> b.support AS nx, a.exp_support <> b.exp_support AS ny FROM bo a JOIN bo b ON a.code < b.code) SELECT round((sum((s > 0)::INT) - sum((s < 0)::INT)) / sqrt(sum(nx::INT)::DOUBLE * sum(ny::INT)), 9) AS tau_b FROM pp")
def _(spark, sf_dir):
    """The aggregate function by its SQL name."""
    from patternwalk.functions import sql

    sql.register(spark)
    truth, found = _sides(spark, sf_dir)
    truth.join(found, "code").createOrReplaceTempView("two_sides")
    return spark.sql("SELECT round(tau_b(support, exp_support), 9) AS tau_b FROM two_sides")


@register("sql_edge_types", f"{_TE} SELECT concat_ws('|', la, el, lb) AS k, count(DISTINCT gid) AS support FROM te GROUP BY k")
def _(spark, sf_dir):
    from patternwalk.functions import sql

    sql.register(spark)
    prox(spark, sf_dir).typed_edges().createOrReplaceTempView("typed_edges")
    return spark.sql("SELECT edge_type_key(lb, elabel, la) AS k, count(DISTINCT gid) AS support FROM typed_edges GROUP BY 1")


@register("plain_pieces_p3", f"WITH {PX}, {O.plain_codes()} SELECT gid, code, count(*) AS n FROM (SELECT gid, code FROM o2 UNION ALL SELECT gid, code FROM o3) GROUP BY gid, code")
def _(spark, sf_dir):
    """Pieces that need not be induced, by graph and pattern."""
    return with_code(E.enumerate_plain(prox(spark, sf_dir), 3), method="inline", naming="permutation").groupBy("gid", "code").agg(F.count("*").alias("n"))


@register("walk_thin_p3")
def _(spark, sf_dir):
    """The cheap way to pieces that need not be induced."""
    return W.run_walks(prox(spark, sf_dir).stored(), 3, 1000, induced=False, plain_mode="thin").groupBy("n_edges").agg(F.count("*").alias("n"))


@register("giant_components", f"WITH RECURSIVE {O.VECTOR}, sy AS (SELECT gid, src AS a, dst AS b FROM e0 UNION ALL SELECT gid, dst, src FROM e0), rr AS (SELECT gid, vid, vid AS far FROM v0 UNION SELECT r.gid, r.vid, s.b FROM rr r JOIN sy s ON s.gid = r.gid AND s.a = r.far), cc AS (SELECT gid, vid, min(far) AS comp FROM rr GROUP BY ALL) SELECT gid, comp, count(*) AS n FROM cc GROUP BY ALL")
def _(spark, sf_dir):
    """Components of the vector graphs before they are cut to their largest."""
    from patternwalk.model import giant_components

    return giant_components(builders.vector_radius(spark, sf_dir, whole=True)).groupBy("gid", "comp").agg(F.count("*").alias("n"))


@register("piece_degrees_p3", f"{_SMALL} SELECT gid, {LIST}, CASE count(*) WHEN 3 THEN '2,2,2' ELSE '2,1,1' END AS degrees FROM pe GROUP BY gid, pe.vs")
def _(spark, sf_dir):
    return E.piece_shapes(prox(spark, sf_dir), 3).select("gid", joined("vs").alias("vs"), joined("degrees").alias("degrees"))


@register("as_of_checkpoint", "WITH o AS (SELECT user_id, event_id, epoch_us(ts) AS t, event_type, value FROM events), g AS (SELECT user_id, event_id, t, value FROM o WHERE event_type = 'purchase') SELECT user_id, event_id, checkpoint, round(gate, 9) AS gate FROM (SELECT o.user_id, o.event_id, g.event_id AS checkpoint, g.value AS gate, row_number() OVER (PARTITION BY o.event_id ORDER BY g.t DESC NULLS LAST, g.event_id DESC) AS n FROM o LEFT JOIN g ON g.user_id = o.user_id AND (g.t < o.t OR (g.t = o.t AND g.event_id <= o.event_id))) WHERE n = 1")
def _(spark, sf_dir):
    """The gate value in force at each event: that of its user's latest purchase, which is a checkpoint. Both sides are in one order, the last value carried on."""
    own = table(spark, sf_dir, "events").select("user_id", "event_id", F.col("ts").cast("timestamp").alias("t"), "event_type", "value")
    order = Window.partitionBy("user_id").orderBy("t", "event_id")
    last = lambda c: F.last(F.when(F.col("event_type") == "purchase", F.col(c)), ignorenulls=True).over(order)
    return own.select("user_id", "event_id", last("event_id").alias("checkpoint"), F.round(last("value"), 9).alias("gate"))


# Experiments
def _runs(per_run: DataFrame, by: list[str]) -> DataFrame:
    """Means and deviations of precision and tau-b over runs."""
    return per_run.groupBy(*by).agg(F.count("*").alias("runs"), F.avg("precision").alias("precision"), F.stddev("precision").alias("precision_sd"), F.avg("tau_b").alias("tau_b"), F.stddev("tau_b").alias("tau_b_sd"))


def _experiment(spark, sf_dir, alphabet, scores, k, ms, p=3, chains=10):
    """``score, iters, runs, precision, tau_b`` over ten chains, which are ten runs in one job."""
    db = prox(spark, sf_dir, alphabet).stored()
    types = cut(S.edge_support(db), "types")
    truth = cut(E.ground_truth(db, p, types=types).select("code", "support"), "truth")
    out = []
    for s in scores:
        samples = cut(with_code(W.run_walks(db, p, max(ms), s, chains=chains, types=types), method="inline").select("chain", "iter", "gid", "score", "code"), "samples")
        out.append(_runs(A.quality_trace(samples, truth, k, ms), ["iters"]).withColumn("score", F.lit(s)))
    return reduce(DataFrame.unionByName, out)


_FQ = f"WITH {PX}, {O.plain_codes()}, n AS (SELECT count(DISTINCT gid) AS n FROM v)"


@register("w1_complete_by_size", f"{_FQ} SELECT max_size, count(*) AS patterns FROM ps JOIN n ON support >= ceil(0.4 * n) JOIN (VALUES (2), (3)) z(max_size) ON n_vertices <= max_size GROUP BY max_size")
def _(spark, sf_dir):
    """Support 0.4, every pattern of up to three vertices; larger sizes are for :func:`complete_by_size`, see the README."""
    return complete_by_size(prox(spark, sf_dir), 0.4, (2, 3))


@register("w2_complete_by_support", f"{_FQ} SELECT x::DOUBLE AS minsup, count(*) AS patterns FROM ps JOIN n ON true JOIN (VALUES (0.28), (0.22), (0.17), (0.11)) z(x) ON support >= ceil(x * n - 1e-9) GROUP BY x")
def _(spark, sf_dir):
    db = prox(spark, sf_dir)
    found = cut(B.mine_complete(db, 0.11, max_size=3), "complete")
    n = db.vertices.select("gid").distinct().count()
    return reduce(DataFrame.unionByName, [frequent(found, x, n).agg(F.count("*").alias("patterns")).withColumn("minsup", F.lit(x)) for x in (0.28, 0.22, 0.17, 0.11)])


def complete_by_size(db: GraphDB, minsup: float, sizes: tuple[int, ...]) -> DataFrame:
    """Patterns of the complete miner by cap on the size. One run at the largest cap has all smaller ones."""
    found = cut(B.mine_complete(db, minsup, max_size=max(sizes)), "complete")
    return reduce(DataFrame.unionByName, [found.where(F.col("n_vertices") <= n).agg(F.count("*").alias("patterns")).withColumn("max_size", F.lit(n)) for n in sizes])


@register("w4_quality_by_iterations")
def _(spark, sf_dir):
    return _experiment(spark, sf_dir, "coarse", ("s1", "s2"), 100, [1000, 2000, 4000])


@register("w7_copurchase")
def _(spark, sf_dir):
    """Sizes 3 and 4; at size 3 with the quality of ten runs against the whole truth."""
    db = builders.copurchase(spark, sf_dir).stored()
    types = cut(S.edge_support(db), "types")
    truth = cut(E.ground_truth(db, 3, types=types).select("code", "support"), "truth")
    samples = cut(with_code(W.run_walks(db, 3, 2000, chains=10, types=types), method="inline").select("chain", "iter", "gid", "score", "code"), "samples")
    quality = _runs(A.quality_trace(samples, truth, 100, [1000, 2000]), ["iters"]).withColumn("p", F.lit(3))
    larger = mine_top_k(db, 4, k=100, m=2000, types=types).groupBy().agg(F.count("*").alias("patterns"), F.max("exp_support").alias("top")).withColumn("p", F.lit(4)).withColumn("iters", F.lit(2000))
    return quality.unionByName(larger, allowMissingColumns=True)


@register("w8_order_star")
def _(spark, sf_dir):
    """The most frequent patterns of whole order stars at sizes 5, 6 and 8."""
    db = builders.order_star(spark, sf_dir).stored()
    pairs = S.placed_types(db.packed)
    types = cut(S.numbered_types(pairs), "types")
    scores = spark.sparkContext.broadcast(S.placed_scores(db, types, pairs))
    return reduce(DataFrame.unionByName, [mine_top_k(db, p, k=100, m=3000, types=types, scores=scores).withColumn("p", F.lit(p)) for p in (5, 6, 8)])


@register("w8_order_star_quality")
def _(spark, sf_dir):
    """Ten runs at size 5 against the whole truth."""
    db = builders.order_star(spark, sf_dir).stored()
    types = cut(S.edge_support(db), "types")
    truth = cut(E.ground_truth(db, 5, types=types).select("code", "support"), "truth")
    samples = cut(with_code(W.run_walks(db, 5, 4000, chains=10, types=types), method="inline").select("chain", "iter", "gid", "score", "code"), "samples")
    return _runs(A.quality_trace(samples, truth, 100, [1000, 4000]), ["iters"])


@register("w9_time_by_size")
def _(spark, sf_dir):
    """Proposals and moves by size: the walk's own work, which grows about linearly; seconds are in bench.py."""
    db = prox(spark, sf_dir).stored()
    return reduce(DataFrame.unionByName, [W.walk_stats(W.run_walks(db, p, 300)).withColumn("p", F.lit(p)) for p in (3, 5, 7)])


@register("w10_targets")
def _(spark, sf_dir):
    """The three targets on the three alphabets, ten runs each."""
    return reduce(DataFrame.unionByName, [_experiment(spark, sf_dir, a, ("uniform", "s1", "s2"), 500, [2000]).withColumn("alphabet", F.lit(a)) for a in ("coarse", "fine", "skewed")])


@register("w11_queue_sizes")
def _(spark, sf_dir):
    """Precision and tau-b of ten runs by queue capacity, and what the queue held and refused."""
    db = prox(spark, sf_dir).stored()
    types = cut(S.edge_support(db), "types")
    truth = cut(E.ground_truth(db, 3, types=types).select("code", "support"), "truth")
    samples = cut(W.run_walks(db, 3, 2000, chains=10, types=types), "samples")
    out = []
    for c in (150, 300, 600):
        queue = cut(Q.replay_queue(samples, Q.QueuePolicy(c)), "queue")
        held = queue.agg(F.avg("gated").alias("gated"), F.avg("evicted").alias("evicted"), (F.count("*") / 10).alias("size"))
        quality = _runs(A.quality_by_run(truth, ranked(queue, 100, ("chain",)), 100, ["chain"]).withColumn("capacity", F.lit(c)), ["capacity"])
        out.append(quality.join(F.broadcast(held), F.lit(True)))  # one row each
    return reduce(DataFrame.unionByName, out)


@register("w12_effect_of_k")
def _(spark, sf_dir):
    db = prox(spark, sf_dir, "skewed").stored()
    types = cut(S.edge_support(db), "types")
    truth = cut(E.ground_truth(db, 3, types=types).select("code", "support"), "truth")
    samples = cut(with_code(W.run_walks(db, 3, 3000, chains=10, types=types), method="inline").select("chain", "iter", "gid", "score", "code"), "samples")
    return reduce(DataFrame.unionByName, [_runs(A.quality_trace(samples, truth, k, [3000]), ["iters"]).withColumn("k", F.lit(k)) for k in (100, 200, 300, 400, 500)])


@register("w13_chains")
def _(spark, sf_dir):
    """Ten chains at doubling checkpoints."""
    db = prox(spark, sf_dir).stored()
    samples = cut(with_code(W.run_walks(db, 3, 8000, chains=10), method="inline").select("chain", "iter", "gid", "score", "code"), "samples")
    return reduce(DataFrame.unionByName, [A.chain_jaccard(ranked(Q.expected_support(samples.where(F.col("iter") <= m), ("chain",)), 100, ("chain",))).withColumn("iters", F.lit(m)) for m in (1000, 2000, 4000, 8000)])


# Large graphs, convergence, streams, SQL surface, files
@register("bsp_walk_p3")
def _(spark, sf_dir):
    """Walkers by superstep; each starts from the kernel's first state of its graph."""
    from patternwalk.operators import bsp

    db = prox(spark, sf_dir).stored()
    types = S.edge_support(db)
    _, state = W.run_walks(db, 3, 60, types=types, want_state=True, burn_in=0)
    walkers = state.select(F.col("chain").alias("walker"), "gid", "vs", F.lit(0).cast("long").alias("attempts"), F.lit(0).alias("moved"))
    out = bsp.walk_in_supersteps(bsp.adjacency(db, types), walkers, S.score_table(db, types, "s2"), steps=3)
    return out.select("walker", "gid", joined("vs").alias("vs"), "attempts", "moved")


@register("run_until_agreement")
def _(spark, sf_dir):
    from patternwalk.operators.convergence import run_until

    _, trace = run_until(prox(spark, sf_dir).stored(), 3, k=50, epsilon=0.3, first=500, most=2000, chains=3)
    return spark.createDataFrame(trace, "iters long, distance double, r_hat double")


@register("stage_times")
def _(spark, sf_dir):
    from patternwalk.operators.convergence import stage_times

    return reduce(DataFrame.unionByName, [stage_times(prox(spark, sf_dir).stored(), p, 300) for p in (3, 6)])


@register("visit_distance_p3", f"{_walk_sql('s2', 4000, emit='lazy')}, z AS (SELECT gid, sum(num / den) AS z FROM sc GROUP BY gid), q AS (SELECT gid, vs, count(*) AS n FROM smp GROUP BY gid, vs), qn AS (SELECT gid, count(*) AS n FROM smp GROUP BY gid) SELECT sc.gid, round(sum(abs(num / den / z - coalesce(q.n, 0) / qn.n)) / 2, 9) AS distance FROM sc JOIN z ON z.gid = sc.gid JOIN qn ON qn.gid = sc.gid LEFT JOIN q ON q.gid = sc.gid AND q.vs = sc.vs GROUP BY sc.gid")
def _(spark, sf_dir):
    db = prox(spark, sf_dir).stored()
    samples = cut(W.run_walks(db, 3, 4000, emit="lazy"), "samples")
    return A.visit_distance(samples, L.stationary(db, 3, only=samples.select("gid"))).select("gid", F.round("distance", 9).alias("distance"))


_MODEL = f"{_SMALL}, {O.codes(3)}, z AS (SELECT gid, count(*) AS z FROM s3 GROUP BY gid), ms AS (SELECT code, cd.gid, count(*) / any_value(z) AS mass FROM cd JOIN z ON z.gid = cd.gid GROUP BY code, cd.gid) SELECT code, round(sum(1 - pow(1 - mass, 100)), 6) AS expected FROM ms GROUP BY code"


@register("expected_support_model_p3", _MODEL)
def _(spark, sf_dir):
    db = prox(spark, sf_dir)
    counts = cut(E.pattern_counts(db, 3), "counts")
    total = counts.groupBy("gid").agg(F.sum("n").alias("z"))
    mass = counts.join(total, "gid").select("code", "gid", (F.col("n") / F.col("z")).alias("mass"))
    visits = db.vertices.select("gid").distinct().withColumn("m", F.lit(100))
    return L.expected_support_model(mass, visits).withColumn("expected", F.round("expected", 6))


_DEN = f"{_SMALL} SELECT gid, {LIST}, count(*)::BIGINT AS n_edges, round(2 * count(*) / 6.0, 9) AS density FROM pe GROUP BY gid, pe.vs"


@register("piece_stats_p3", _DEN)
def _(spark, sf_dir):
    return E.piece_shapes(prox(spark, sf_dir), 3).select("gid", joined("vs").alias("vs"), "n_edges", F.round("density", 9).alias("density"))


@register("sql_surface", f"{_P3}, {O.codes(3)} SELECT count(*) AS pieces, count(DISTINCT code) AS patterns FROM cd")
def _(spark, sf_dir):
    from patternwalk.functions import sql

    sql.register(spark, prox(spark, sf_dir).stored())
    return spark.sql("SELECT count(*) AS pieces, count(DISTINCT code) AS patterns FROM (SELECT dfs_code(raw) AS code FROM enumerate_pieces(TABLE(gdb_packed), 3))")


@register("sql_reachability", f"WITH {O.DIALOGUE} SELECT gid, count(*) AS reached FROM v GROUP BY gid HAVING count(*) < 50")
def _(spark, sf_dir):
    """A recursive query: how many vertices the first one of each path reaches."""
    db = builders.dialogue(spark, sf_dir)
    db.vertices.createOrReplaceTempView("dlg_v")
    db.symmetric().createOrReplaceTempView("dlg_e")
    return spark.sql(
        "WITH RECURSIVE r(gid, vid, depth) AS (SELECT gid, min(vid), 0 FROM dlg_v GROUP BY gid UNION ALL SELECT r.gid, e.b, r.depth + 1 FROM r JOIN dlg_e e ON e.gid = r.gid AND e.a = r.vid WHERE e.b > r.vid AND r.depth < 50) SELECT gid, count(DISTINCT vid) AS reached FROM r GROUP BY gid"
    )


@register("stream_windows", "SELECT date_trunc('day', ts) AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def _(spark, sf_dir):
    """The streaming aggregate over everything there is, without late loss, as the batch engine runs the same plan."""
    from patternwalk.streaming.streams import windowed_activity

    e = table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return windowed_activity(e).withColumn("start", F.col("start").cast("timestamp_ntz"))


@register("w14_induced_at_ten_percent")
def _(spark, sf_dir):
    return B.mine_complete(builders.order_star(spark, sf_dir).stored(), 0.1, max_size=4, induced=True)


@register("w3_space_by_size", f"WITH {PX}, {O.pieces(5)} SELECT 3 AS p, count(*)::BIGINT AS pieces FROM s3 UNION ALL SELECT 4, count(*) FROM s4 UNION ALL SELECT 5, count(*) FROM s5")
def _(spark, sf_dir):
    return E.space_growth(prox(spark, sf_dir), [3, 4, 5])


@register("w5_long_runs")
def _(spark, sf_dir):
    return _experiment(spark, sf_dir, "coarse", ("s2",), 100, [2000, 4000, 8000])


@register("w6_scores_and_support", f"{_SMALL}, {O.codes(3)}, {O.SUPPORT} SELECT code, any_value(support) AS support, any_value(s1) AS s1, any_value(s2) AS s2 FROM cd JOIN su USING (code) JOIN s1s ON s1s.gid = cd.gid AND s1s.vs = cd.vs JOIN s2s ON s2s.gid = cd.gid AND s2s.vs = cd.vs GROUP BY code")
def _(spark, sf_dir):
    return E.ground_truth(prox(spark, sf_dir), 3).select(respelled("code").alias("code"), "support", "s1", "s2")


@register("w17_discriminative_pieces")
def _(spark, sf_dir):
    db = builders.two_class(spark, sf_dir)
    coded = E.piece_codes(db, E.enumerate_induced(db, 2), 2).select("gid", "code").distinct()
    return B.discriminative(coded, db.attrs.select("gid", F.col("quality").alias("y"))).orderBy(F.desc("gain"), "code").limit(100)
