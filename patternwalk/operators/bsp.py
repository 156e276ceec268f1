"""Walks on a graph too large for a worker: walkers and adjacency meet by join, one step a superstep.

A superstep moves every walker by one proposal. The state's neighbour lists come by an
equi-join on ``(gid, vid)``; the proposed vertex's own list by a second one. The
arithmetic between the joins is that of the kernel on a small graph made of those lists,
with the same counters, so the walk is the kernel's walk with ``emit='lazy'``. Both
halves of a step are cut tables: a walker's row is read twice by the next join, and a plan
that grew with the steps would grow exponentially.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from patternwalk.functions.rng import uniform
from patternwalk.model import GraphDB
from patternwalk.operators.kernel import Scores, accepts
from patternwalk.plans.scratch import cut

WALKERS = "walker int, gid long, vs array<long>, attempts long, moved int"
_LISTS = "array<struct<v:long,n:array<struct<b:long,t:int>>>>"


def adjacency(db: GraphDB, types: DataFrame) -> DataFrame:
    """``gid, v, n``: each vertex with its neighbours and the types of the edges to them, in order."""
    e = db.typed_edges().withColumnRenamed("elabel", "el").join(types.select("etype", "la", "el", "lb"), ["la", "el", "lb"])
    both = e.select("gid", F.col("src").alias("v"), F.col("dst").alias("b"), "etype").unionByName(e.select("gid", F.col("dst").alias("v"), F.col("src").alias("b"), "etype"))
    return both.groupBy("gid", "v").agg(F.sort_array(F.collect_list(F.struct("b", F.col("etype").alias("t")))).alias("n"))


def _near(lists) -> dict[int, dict[int, int]]:
    return {int(x["v"]): {int(y["b"]): int(y["t"]) for y in x["n"]} for x in lists}


def _boxes(near: dict[int, dict[int, int]], state: list[int]) -> list[tuple[int, list[int]]]:
    out = []
    for u in state:
        rest, can = [v for v in state if v != u], None
        while rest:
            part, todo = {rest[0]}, [rest[0]]
            while todo:
                for w in near[todo.pop()]:
                    if w in rest and w not in part:
                        part.add(w)
                        todo.append(w)
            around = {w for v in part for w in near[v]}
            can = around if can is None else can & around
            rest = [v for v in rest if v not in part]
        out.append((u, sorted((can or set()) - set(state))))
    return out


def _types(near: dict[int, dict[int, int]], state: list[int]) -> list[int]:
    return [near[a][b] for i, a in enumerate(state) for b in state[i + 1 :] if b in near[a]]


def walk_in_supersteps(adj: DataFrame, walkers: DataFrame, scores: Scores, steps: int, seed: int = 0) -> DataFrame:
    """Walkers after ``steps`` proposals; ``walkers`` has the columns of ``WALKERS``."""
    shared = adj.sparkSession.sparkContext.broadcast(scores)

    def lists_of(w: DataFrame, column: str, name: str) -> DataFrame:
        asked = w.select("walker", "gid", F.explode(column).alias("v"))
        got = asked.join(adj, ["gid", "v"]).groupBy("walker", "gid").agg(F.sort_array(F.collect_list(F.struct("v", "n"))).alias(name))
        return w.join(got, ["walker", "gid"])

    def propose(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            out = []
            for r in frame.itertuples():
                state, near = sorted(int(v) for v in r.vs), _near(r.lists)
                boxes = _boxes(near, state)
                d = sum(len(c) for _, c in boxes)
                n = int(uniform(seed, r.walker, r.gid, r.attempts + 1, 0) * d)
                nxt = state
                for u, c in boxes:
                    if n < len(c):
                        nxt = sorted([v for v in state if v != u] + [c[n]])
                        break
                    n -= len(c)
                out.append((r.walker, r.gid, state, r.attempts, r.moved, nxt, d, _types(near, state)))
            yield pd.DataFrame(out, columns=["walker", "gid", "vs", "attempts", "moved", "ws", "d", "types"], dtype=object)

    def decide(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            out = []
            for r in frame.itertuples():
                if not r.d:
                    out.append((r.walker, r.gid, list(r.vs), r.attempts, r.moved))
                    continue
                state, near = [int(v) for v in r.ws], _near(r.lists)
                dy = sum(len(c) for _, c in _boxes(near, state))
                ok = accepts(uniform(seed, r.walker, r.gid, r.attempts + 1, 1), int(r.d), shared.value.of([int(t) for t in r.types]), dy, shared.value.of(_types(near, state)))
                out.append((r.walker, r.gid, state if ok else [int(v) for v in r.vs], r.attempts + 1, r.moved + int(ok)))
            yield pd.DataFrame(out, columns=["walker", "gid", "vs", "attempts", "moved"], dtype=object)

    adj = cut(adj, "adjacency")
    for _ in range(steps):
        asked = cut(lists_of(walkers, "vs", "lists").mapInPandas(propose, f"{WALKERS}, ws array<long>, d int, types array<int>"), "proposals")
        walkers = cut(lists_of(asked, "ws", "lists").mapInPandas(decide, WALKERS), "walkers")
    return walkers
