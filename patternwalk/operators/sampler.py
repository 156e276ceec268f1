"""Which graph is sampled at which iteration, and the walks that answer.

The queue never feeds back into a walk, so the walks of all graphs and chains of an
epoch run at once: a graph's iterations travel to its packed row and one task walks them.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from patternwalk.functions.rng import uniform_column
from patternwalk.model import GraphDB, pack, unpacked
from patternwalk.operators.enumerate import graph_of
from patternwalk.operators.kernel import Scores, Walk, bits, thinned
from patternwalk.operators.support import edge_support, score_table
from patternwalk.plans.scratch import cut

SAMPLES = "chain int, iter long, gid long, vs array<long>, n_edges int, raw string, score_num long, score_den long, score double, degree long, proposals int"
STATE = "chain int, gid long, vs array<long>, es array<struct<a:long,b:long>>, attempts long"


#: Graphs are numbered by so many ranges of ids, each of which is one task's.
RANGES = 1024


def eligible(db: GraphDB, p: int) -> DataFrame:
    """Graphs with at least ``p`` vertices, numbered in order of id: places within a range of ids, and the ranges' counts before it."""
    big = db.graphs().where((F.col("n_vertices") >= p) & (F.col("n_edges") > 0)).select("gid")
    low, high = big.agg(F.min("gid"), F.max("gid")).first()
    width = 1 if low is None else (high - low) // RANGES + 1
    ranged = big.withColumn("range", F.floor((F.col("gid") - F.lit(low or 0)) / F.lit(width)))
    before = Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)  # over RANGES rows at most
    base = ranged.groupBy("range").count().select("range", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("base"))
    place = F.row_number().over(Window.partitionBy("range").orderBy("gid")) - 1
    return ranged.withColumn("nth", place).join(F.broadcast(base), "range").select("gid", (F.col("base") + F.col("nth")).cast("long").alias("place"))


def schedule(graphs: DataFrame, m: int, seed: int = 0, mode: str = "counter", chains: int = 1, first: int = 1) -> DataFrame:
    """``chain, gid, iters``: iterations ``first .. first + m - 1`` of each chain, each given to a graph.

    ``counter``: uniform draws, a function of the iteration. ``round_robin``: in turn.
    ``multinomial``: each graph draws its own number of visits (Poisson, the law of the
    counts when the total is free) and spreads them, so that nothing of length ``m`` is made or moved.
    """
    spark: SparkSession = graphs.sparkSession
    every = spark.range(chains).select(F.col("id").cast("int").alias("chain"))
    if mode == "multinomial":
        n = max(1, graphs.count())

        def draw(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            import numpy as np

            for frame in frames:
                rows = []
                for chain, gid in zip(frame["chain"], frame["gid"]):
                    rng = np.random.Generator(np.random.Philox(key=[(seed << 20) + int(chain), int(gid) & (2**63 - 1)], counter=[first, 0, 0, 0]))
                    k = int(rng.poisson(m / n))
                    if k:
                        rows.append((chain, gid, np.sort(first + rng.integers(0, m, k)).tolist()))
                yield pd.DataFrame(rows, columns=["chain", "gid", "iters"])

        return graphs.select("gid").join(every, F.lit(True)).mapInPandas(draw, "chain int, gid long, iters array<long>")
    n = graphs.count()
    rows = spark.range(first, first + m).select(F.col("id").alias("iter")).join(every, F.lit(True))
    if mode == "counter":
        place = F.floor(uniform_column(seed, F.col("chain"), F.col("iter")) * F.lit(n))
    elif mode == "round_robin":
        place = (F.col("iter") - 1) % n
    else:
        raise ValueError(mode)
    drawn = rows.withColumn("place", place.cast("long")).groupBy("chain", "place").agg(F.sort_array(F.collect_list("iter")).alias("iters"))
    return drawn.join(graphs, "place").select("chain", "gid", "iters")


def _walk(packed_visits: DataFrame, p: int, scores: Scores | Broadcast, seed: int, induced: bool, emit: str, burn_in: int, thin: int, what: str, plain_mode: str = "walk") -> DataFrame:
    shared = scores if isinstance(scores, Broadcast) else packed_visits.sparkSession.sparkContext.broadcast(scores)

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        target = shared.value
        for frame in frames:
            out, ends = [], []
            for row in frame.itertuples():
                g = graph_of(row)
                place = {v: i for i, v in enumerate(g.vids)}
                walk = Walk(g, p, target, (seed, row.chain, row.gid), induced or plain_mode == "thin", emit)
                fresh = row.old_vs is None
                if fresh:
                    if not walk.start():
                        continue
                else:
                    es = frozenset(tuple(sorted((place[e["a"]], place[e["b"]]))) for e in row.old_es)
                    walk.set(sum(1 << place[v] for v in row.old_vs), es)
                    walk.attempts = int(row.attempts)
                for k, i in enumerate(row.iters):
                    tried = 0 if fresh and k == 0 else walk.sample()
                    if what == "samples" and k >= burn_in and (k - burn_in) % thin == 0:
                        pairs = walk.pairs if induced or plain_mode != "thin" else thinned(g, walk.state, walk.pairs, (seed, row.chain, row.gid, walk.attempts, "thin"))
                        num, den = walk.score if pairs is walk.pairs else target.of(g.types(pairs))
                        out.append((row.chain, int(i), row.gid, [g.vids[v] for v in bits(walk.state)], len(pairs), g.raw(walk.state, pairs), num, den, num / den, walk.degree, tried))
                ends.append((row.chain, row.gid, [g.vids[v] for v in bits(walk.state)], [{"a": g.vids[a], "b": g.vids[b]} for a, b in sorted(walk.pairs)], walk.attempts))
            if what == "samples":
                yield pd.DataFrame(out, columns=[c.split()[0] for c in SAMPLES.split(", ")], dtype=object)
            else:
                yield pd.DataFrame(ends, columns=["chain", "gid", "vs", "es", "attempts"], dtype=object)

    return packed_visits.mapInPandas(run, SAMPLES if what == "samples" else STATE)


def run_walks(
    db: GraphDB,
    p: int,
    m: int,
    score: str = "s2",
    seed: int = 0,
    chains: int = 1,
    induced: bool = True,
    emit: str = "accepted",
    mode: str = "counter",
    first: int = 1,
    state: DataFrame | None = None,
    burn_in: int = 0,
    thin: int = 1,
    types: DataFrame | None = None,
    want_state: bool = False,
    plain_mode: str = "walk",
    scores: Scores | Broadcast | None = None,
):
    """The sample of each iteration (and, with ``want_state``, the states to go on from).

    ``plain_mode='thin'``, for pieces that need not be induced: the cheap way, which walks over
    induced pieces and emits a random connected part of each one's edges.

    ``scores``: what :func:`score_table` has for ``score``, for several runs on one database.
    Where graphs are packed already and visits are dealt by iteration, only the graphs that are visited get edge types.

    Draws depend on ``(seed, chain, graph, attempt)`` only: reruns, lost tasks and other
    partitionings give the same samples, and two runs of ``m / 2`` joined by their state equal one of ``m``.
    """
    types = cut(edge_support(db), "types") if types is None else types
    if db.packed is not None and mode != "multinomial":
        visits = cut(schedule(cut(eligible(db, p), "eligible"), m, seed, mode, chains, first), "visits")
        packed = pack(unpacked(cut(db.packed.join(visits.select("gid").distinct(), "gid", "left_semi"), "visited")), types)
    else:
        packed = pack(db, types)
        visits = schedule(eligible(db, p), m, seed, mode, chains, first)
    if state is None:
        joined = visits.join(packed, "gid").select("chain", "iters", *packed.columns, F.lit(None).cast("array<long>").alias("old_vs"), F.lit(None).cast("array<struct<a:long,b:long>>").alias("old_es"), F.lit(0).cast("long").alias("attempts"))
    else:
        held = state.select("chain", "gid", F.col("vs").alias("old_vs"), F.col("es").alias("old_es"), "attempts")
        joined = visits.join(packed, "gid").join(held, ["chain", "gid"], "left").select("chain", "iters", *packed.columns, "old_vs", "old_es", F.coalesce("attempts", F.lit(0)).alias("attempts"))
    scores = score_table(db, types, score) if scores is None else scores
    samples = _walk(joined, p, scores, seed, induced, emit, burn_in, thin, "samples", plain_mode)
    if not want_state:
        return samples
    moved = _walk(joined, p, scores, seed, induced, emit, burn_in, thin, "state", plain_mode)
    if state is not None:
        moved = moved.unionByName(state.join(moved.select("chain", "gid"), ["chain", "gid"], "left_anti"))
    return samples, moved


def walk_stats(samples: DataFrame) -> DataFrame:
    """Samples, proposals, acceptance and proposals per sample by chain; first states, which were not proposed, apart."""
    moved = F.col("proposals") > 0
    return samples.groupBy("chain").agg(F.count("*").alias("samples"), F.sum("proposals").alias("proposals"), (F.sum(moved.cast("int")) / F.sum("proposals")).alias("acceptance"), F.avg(F.when(moved, F.col("proposals"))).alias("proposals_per_move"))
