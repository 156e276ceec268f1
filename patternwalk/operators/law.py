"""The chain's law: neighbours, transitions and stationary weights of all pieces, worked out where each graph is."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from patternwalk.model import GraphDB, pack
from patternwalk.operators.enumerate import enumerate_induced
from patternwalk.operators.flat import Chunk, Cores, lists, over_pieces, spread
from patternwalk.operators.kernel import Scores
from patternwalk.operators.support import graph_types, numbered_types, score_table
from patternwalk.plans.scratch import cut


def neighbours(db: GraphDB, p: int) -> DataFrame:
    """``gid, vs, ws``: pieces that share all but one vertex."""
    def make(c: Chunk) -> Iterator[dict]:
        sets = c.pieces(p)
        for x, y in c.cores(sets).pairs():
            yield {"gid": c.gids[c.graph[sets[x, 0]]], "vs": lists(c.vids[sets[x]]), "ws": lists(c.vids[sets[y]])}

    return over_pieces(pack(db), p, make, "gid long, vs array<long>, ws array<long>")


def swap_boxes(db: GraphDB, p: int) -> DataFrame:
    """``gid, vs, u, box``: what each vertex of a piece can be replaced by, in order.

    A worker gives each core once, with all vertices that make it a piece; each of them has the others as its box.
    """
    def make(c: Chunk) -> Iterator[dict]:
        sets = c.pieces(p)
        cores = c.cores(sets)
        met = np.flatnonzero(cores.size > 1)
        run, place = spread(cores.size[met])
        own = c.vids[sets.ravel()[cores.members[cores.first[met[run]] + place]]]
        of = cores.members[cores.first[met]]
        rest = sets[of // p][np.arange(p) != (of % p)[:, None]].reshape(len(met), p - 1)
        whole = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(cores.size[met])]).astype(np.int32)), pa.array(own))
        yield {"gid": c.gids[c.graph[sets[of // p, 0]]], "core": lists(c.vids[rest]) if p > 1 else pa.array([[]] * len(met), pa.list_(pa.int64())), "us": whole}

    met = over_pieces(pack(db), p, make, "gid long, core array<long>, us array<long>").select("gid", "core", F.array_sort("us").alias("us"))
    each = met.select("gid", "core", "us", F.explode("us").alias("u"))
    return each.select("gid", F.array_sort(F.array_append("core", F.col("u"))).alias("vs"), "u", F.array_remove("us", F.col("u")).alias("box"))


def degrees(db: GraphDB, p: int) -> DataFrame:
    """``gid, vs, d``: the number of each piece's neighbours, from the sizes of its cores' groups."""
    def make(c: Chunk) -> Iterator[dict]:
        sets = c.pieces(p)
        yield {"gid": c.gids[c.graph[sets[:, 0]]], "vs": lists(c.vids[sets]), "d": c.cores(sets).degrees()}

    return over_pieces(pack(db), p, make, "gid long, vs array<long>, d long")


class Law:
    """The pieces of a database of graphs under a score: packed once, scored in the workers."""

    def __init__(self, db: GraphDB, p: int, score: str, only: DataFrame | None = None) -> None:
        """``only``: the graphs asked for; supports are those of the whole database."""
        self.p = p
        if score == "uniform":
            self.packed, number, scores = pack(db if only is None else db.restrict(only)), {}, Scores("uniform")
        else:
            packed = cut(pack(db), "packed")
            pairs = cut(graph_types(packed), "graph-types")
            types = cut(numbered_types(pairs), "types")
            scores = score_table(db, types, score, pairs)
            number = {(r.la, r.el, r.lb): r.etype for r in types.collect()}
            self.packed = packed if only is None else packed.join(only.select("gid").distinct(), "gid", "left_semi")
        self.shared = db.spark.sparkContext.broadcast((number, scores))

    def over(self, what, schema: str) -> DataFrame:
        """``what(chunk, sets, cores, degrees, num, den)`` over all graphs."""
        p, shared = self.p, self.shared

        def make(c: Chunk) -> Iterator[dict]:
            sets = c.pieces(p)
            cores = c.cores(sets)
            yield from what(c, sets, cores, cores.degrees(), *c.scores(c.edges_of(sets), *shared.value))

        return over_pieces(self.packed, p, make, schema)


def _alpha(x, y, d, num, den) -> np.ndarray:
    return np.minimum(1.0, (d[x] * num[y] * den[x]) / (d[y] * num[x] * den[y]))


def _place(c: Chunk, sets: np.ndarray) -> dict:
    return {"gid": c.gids[c.graph[sets[:, 0]]], "vs": lists(c.vids[sets])}


def piece_scores(db: GraphDB, p: int, score: str) -> DataFrame:
    """``gid, vs, num, den``."""
    def of(c, sets, cores, d, num, den):
        yield {**_place(c, sets), "num": num, "den": den}

    return Law(db, p, score).over(of, "gid long, vs array<long>, num long, den long")


def transition_table(db: GraphDB, p: int, score: str = "s2") -> DataFrame:
    """``gid, vs, ws, alpha, prob``: proposals are uniform over neighbours; ``prob`` is that of proposing and accepting."""
    def of(c, sets, cores, d, num, den):
        for x, y in cores.pairs():
            yield {**_place(c, sets[x]), "ws": lists(c.vids[sets[y]]), "d": d[x], "num": num[x], "den": den[x], "d_y": d[y], "num_y": num[y], "den_y": den[y], "alpha": _alpha(x, y, d, num, den)}

    t = Law(db, p, score).over(of, "gid long, vs array<long>, ws array<long>, d long, num long, den long, d_y long, num_y long, den_y long, alpha double")
    return t.withColumn("prob", F.col("alpha") / F.col("d"))


def _rates(cores: Cores, d, num, den) -> np.ndarray:
    """Each piece's probability of moving on: the sum of its transitions."""
    out = np.zeros(len(d))
    for x, y in cores.pairs():
        out += np.bincount(x, weights=_alpha(x, y, d, num, den) / d[x], minlength=len(d))
    return out


def acceptances(db: GraphDB, p: int, score: str, unit: float = 1_000_000.0) -> DataFrame:
    """``gid, vs, moves, alphas, least`` of every piece that has a neighbour: its proposals, the sum of their acceptances in units, rounded down, and the least acceptance."""
    def of(c, sets, cores, d, num, den):
        total, least = np.zeros(len(d)), np.ones(len(d))
        for x, y in cores.pairs():
            alpha = _alpha(x, y, d, num, den)
            total += np.bincount(x, weights=np.floor(alpha * unit), minlength=len(d))
            if len(x):
                first = np.flatnonzero(np.diff(x, prepend=-1))
                least[x[first]] = np.minimum.reduceat(alpha, first)
        some = d > 0
        yield {**_place(c, sets[some]), "moves": d[some], "alphas": total[some].astype(np.int64), "least": least[some]}

    return Law(db, p, score).over(of, "gid long, vs array<long>, moves long, alphas long, least double")


def acceptance_rates(db: GraphDB, p: int, score: str = "s2") -> DataFrame:
    """``gid, rate``: the mean over a graph's pieces that have a neighbour of the probability of moving on."""
    def of(c, sets, cores, d, num, den):
        g, some = c.graph[sets[:, 0]], d > 0
        total = np.bincount(g, weights=_rates(cores, d, num, den), minlength=len(c.gids))
        n = np.bincount(g[some], minlength=len(c.gids))
        yield {"gid": c.gids[n > 0], "rate": total[n > 0] / n[n > 0]}

    return Law(db, p, score).over(of, "gid long, rate double")


def stationary(db: GraphDB, p: int, score: str = "s2", emit: str = "lazy", only: DataFrame | None = None) -> DataFrame:
    """``gid, vs, pi``: proportional to the score; for the accepted moves alone, to the score times the piece's acceptance rate. ``only``: of these graphs."""
    def of(c, sets, cores, d, num, den):
        w, g = num / den, c.graph[sets[:, 0]]
        some = np.ones(len(w), bool)
        if emit == "accepted":
            w, some = w * _rates(cores, d, num, den), d > 0
        total = np.bincount(g, weights=w, minlength=len(c.gids))
        yield {**_place(c, sets[some]), "pi": (w / total[g])[some] if some.any() else np.empty(0)}

    return Law(db, p, score, only).over(of, "gid long, vs array<long>, pi double")


def balance_residual(db: GraphDB, p: int, score: str = "s2") -> DataFrame:
    """``residual``: the largest difference between the flow from a piece to a neighbour and back, as a share of the flow; 1 where there is no way back."""
    def of(c, sets, cores, d, num, den):
        worst = 0.0
        for x, y in cores.pairs_by_core():
            flow = num[x] / den[x] * (_alpha(x, y, d, num, den) / d[x])
            there, back = np.argsort(x * len(d) + y), np.argsort(y * len(d) + x)
            if not (np.array_equal(x[there], y[back]) and np.array_equal(y[there], x[back])):
                worst = 1.0
            elif len(x):
                worst = max(worst, float((np.abs(flow[there] - flow[back]) / flow[there]).max()))
        yield {"residual": np.array([worst])}

    return Law(db, p, score).over(of, "residual double").agg(F.max("residual").alias("residual"))


def asymmetric_pairs(db: GraphDB, p: int) -> DataFrame:
    """``gid, vs, ws`` of the neighbours without a way back: none, if neighbours are right."""
    def make(c: Chunk) -> Iterator[dict]:
        sets = c.pieces(p)
        for x, y in c.cores(sets).pairs_by_core():
            there, back = x * len(sets) + y, y * len(sets) + x
            lost = np.zeros(len(x), bool) if np.array_equal(np.sort(there), np.sort(back)) else ~np.isin(there, back)
            yield {**_place(c, sets[x[lost]]), "ws": lists(c.vids[sets[y[lost]]])}

    return over_pieces(pack(db), p, make, "gid long, vs array<long>, ws array<long>")


def unreached(db: GraphDB, p: int) -> DataFrame:
    """``gid, parts`` of graphs whose pieces are not all reachable from each other."""
    from patternwalk.model import components

    pieces = enumerate_induced(db, p).withColumn("vid", F.xxhash64("vs"))
    edges = neighbours(db, p).select("gid", F.xxhash64("vs").alias("a"), F.xxhash64("ws").alias("b")).where("a < b").select("gid", F.col("a").alias("src"), F.col("b").alias("dst"), F.lit("").alias("elabel"))
    c = components(GraphDB(pieces.select("gid", "vid", F.lit("").alias("vlabel")), edges))
    return c.groupBy("gid").agg(F.count_distinct("comp").alias("parts")).where("parts > 1")


def expected_support_model(counted: DataFrame, visits: DataFrame) -> DataFrame:
    """Expected support if visits were independent draws from the law: ``counted`` has ``code, gid, mass`` (the law's mass of a pattern in a graph), ``visits`` has ``gid, m``."""
    return counted.join(visits, "gid").groupBy("code").agg(F.sum(1 - F.pow(1 - F.col("mass"), F.col("m"))).alias("expected"))
