"""All pieces of a size, exactly: the ground truth."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce
from itertools import combinations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from patternwalk.functions.rng import uniform
from patternwalk.model import GraphDB, pack
from patternwalk.operators.canon import dfs_code, perm_code_sql, perm_name
from patternwalk.operators.flat import Chunk, lists, over_pieces
from patternwalk.operators.kernel import Graph, bits
from patternwalk.operators.support import edge_support, score_table
from patternwalk.plans.scratch import cut


def graph_of(row, etyp: bool = True) -> Graph:
    return Graph(row.vids, row.vlab, row.ea, row.eb, row.elab, row.etyp if etyp else [-1] * len(row.ea))


def enumerate_induced(db: GraphDB, p: int, engine: str = "sql") -> DataFrame:
    """``gid, vs``: the connected vertex sets of size ``p``.

    ``sql`` grows sets by joins and makes them distinct; ``kernel`` visits each set once
    within its graph's row and needs no shuffle beyond packing.
    """
    if engine == "kernel":
        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for frame in frames:
                for row in frame.itertuples():
                    g, out = graph_of(row), []
                    for s in g.enumerate(p):
                        out.append([g.vids[v] for v in bits(s)])
                        if len(out) == 50_000:
                            yield pd.DataFrame({"gid": row.gid, "vs": pd.Series(out, dtype=object)})
                            out = []
                    yield pd.DataFrame({"gid": [row.gid] * len(out), "vs": pd.Series(out, dtype=object)})

        return pack(db).mapInPandas(run, "gid long, vs array<long>")
    if p == 1:
        return db.vertices.select("gid", F.array("vid").alias("vs"))
    near = db.symmetric().select("gid", "a", "b")
    sets = db.edges.select("gid", F.array("src", "dst").alias("vs"))
    for _ in range(p - 2):
        grown = sets.select("gid", "vs", F.explode("vs").alias("a")).join(near, ["gid", "a"]).where(~F.array_contains("vs", F.col("b")))
        sets = grown.select("gid", F.array_sort(F.concat("vs", F.array("b"))).alias("vs")).distinct()
    return sets


def enumerate_plain(db: GraphDB, p: int) -> DataFrame:
    """``gid, vs, es, raw``: the connected pieces of ``p`` vertices with any edges that reach all of them; ``es`` are their edges."""
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for row in frame.itertuples():
                g, out = graph_of(row), []
                for s in g.enumerate(p):
                    vs = [g.vids[v] for v in bits(s)]
                    for pairs in g.spanning_subsets(s):
                        out.append((row.gid, vs, [{"a": g.vids[a], "b": g.vids[b]} for a, b in pairs], g.raw(s, pairs)))
                    if len(out) >= 20_000:
                        yield pd.DataFrame(out, columns=["gid", "vs", "es", "raw"], dtype=object)
                        out = []
                yield pd.DataFrame(out, columns=["gid", "vs", "es", "raw"], dtype=object)

    return pack(db).mapInPandas(run, "gid long, vs array<long>, es array<struct<a:long,b:long>>, raw string")


def piece_codes(db: GraphDB, pieces: DataFrame, p: int) -> DataFrame:
    """``gid, vs, code`` for small ``p``: the least spelling over vertex orders, all in the JVM."""
    v = db.vertices
    wide = pieces
    for i in range(p):
        wide = wide.withColumn(f"v{i}", F.get("vs", F.lit(i))).join(v.select("gid", F.col("vid").alias(f"v{i}"), F.col("vlabel").alias(f"l{i}")), ["gid", f"v{i}"])
    e = db.edges
    for i, j in combinations(range(p), 2):
        wide = wide.join(e.select("gid", F.col("src").alias(f"v{i}"), F.col("dst").alias(f"v{j}"), F.col("elabel").alias(f"e{i}{j}")), ["gid", f"v{i}", f"v{j}"], "left")
    code = perm_code_sql(p, lambda i: f"l{i}", lambda i, j: f"coalesce(e{i}{j}, '-')")
    return wide.select("gid", "vs", F.expr(code).alias("code"))


def support_sets(coded: DataFrame, sets: bool = False) -> DataFrame:
    """``code, support, embeddings`` (and ``tids``) from ``gid, code`` rows: per graph first, then over graphs."""
    per = coded.groupBy("code", "gid").agg(F.count("*").alias("n"))
    extra: list[Column] = [F.sort_array(F.collect_list("gid")).alias("tids")] if sets else []
    return per.groupBy("code").agg(F.count("*").alias("support"), F.sum("n").alias("embeddings"), *extra)


def pattern_counts(db: GraphDB, p: int) -> DataFrame:
    """``code, gid, n``: how many pieces of each pattern a graph has, counted where the graph is; codes are the least spellings."""
    def make(c: Chunk) -> Iterator[dict]:
        sets = c.pieces(p)
        which, names = c.named(sets, c.edges_of(sets), perm_name)
        of, n = np.unique(c.graph[sets[:, 0]] * max(1, len(names)) + which, return_counts=True)
        g, code = np.divmod(of, max(1, len(names)))
        yield {"code": pa.array([names[k] for k in code], pa.string()), "gid": c.gids[g], "n": n}

    return over_pieces(pack(db), p, make, "code string, gid long, n long")


def supports_of(counts: DataFrame) -> DataFrame:
    """``code, support, embeddings`` from the rows of :func:`pattern_counts`."""
    return counts.groupBy("code").agg(F.count("*").alias("support"), F.sum("n").alias("embeddings"))


def piece_shapes(db: GraphDB, p: int) -> DataFrame:
    """``gid, vs, n_edges, density, max_degree, degrees`` of every piece of size ``p``, as :func:`patternwalk.model.piece_stats` has them, without a shuffle of pieces."""
    def make(c: Chunk) -> Iterator[dict]:
        sets = c.pieces(p)
        there = c.edges_of(sets) >= 0
        degree = np.zeros((len(sets), p), np.int64)
        for k, (i, j) in enumerate(combinations(range(p), 2)):
            degree[:, i] += there[:, k]
            degree[:, j] += there[:, k]
        degree = -np.sort(-degree, axis=1)
        n = there.sum(axis=1)
        yield {"gid": c.gids[c.graph[sets[:, 0]]], "vs": lists(c.vids[sets]), "n_edges": n, "density": 2 * n / (p * (p - 1)), "max_degree": degree[:, 0], "degrees": lists(degree)}

    return over_pieces(pack(db), p, make, "gid long, vs array<long>, n_edges long, density double, max_degree long, degrees array<long>")


def ground_truth(db: GraphDB, p: int, induced: bool = True, types: DataFrame | None = None) -> DataFrame:
    """``code, support, embeddings, s1_num, s1_den, s1, s2`` of every pattern of size ``p``.

    Pieces never leave the worker: each graph gives one row per pattern that it has.
    """
    types = cut(edge_support(db), "types") if types is None else types
    s1, s2 = score_table(db, types, "s1"), score_table(db, types, "s2")
    shared = db.spark.sparkContext.broadcast((s1, s2))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        one, two = shared.value
        for frame in frames:
            for row in frame.itertuples():
                g, found = graph_of(row), {}
                for s in g.enumerate(p):
                    for pairs in [g.induced(s)] if induced else g.spanning_subsets(s):
                        raw = g.raw(s, pairs)
                        if raw in found:
                            found[raw][0] += 1
                        else:
                            t = g.types(pairs)
                            found[raw] = [1, *(one.of(t) if t else (0, 1)), two.of(t)[0] if t else 0]
                merged: dict[str, list] = {}
                for raw, x in found.items():
                    code = dfs_code(raw)
                    if code in merged:
                        merged[code][0] += x[0]
                    else:
                        merged[code] = x
                yield pd.DataFrame([(code, row.gid, *x) for code, x in merged.items()], columns=["code", "gid", "n", "s1_num", "s1_den", "s2"], dtype=object)

    per = pack(db, types).mapInPandas(run, "code string, gid long, n long, s1_num long, s1_den long, s2 long")
    out = per.groupBy("code").agg(F.count("*").alias("support"), F.sum("n").alias("embeddings"), F.first("s1_num").alias("s1_num"), F.first("s1_den").alias("s1_den"), F.first("s2").alias("s2"))
    return out.withColumn("s1", F.col("s1_num") / F.col("s1_den"))


def support_both(db: GraphDB, p: int) -> DataFrame:
    """``code, support_plain, support_induced``: an induced match is a plain one, so the first is never smaller."""
    types = edge_support(db)
    plain = ground_truth(db, p, induced=False, types=types).select("code", F.col("support").alias("support_plain"))
    own = ground_truth(db, p, types=types).select("code", F.col("support").alias("support_induced"))
    return plain.join(own, "code", "left").select("code", "support_plain", F.coalesce("support_induced", F.lit(0)).alias("support_induced"))


def space_size(db: GraphDB, p: int) -> DataFrame:
    """``gid, n``: connected vertex sets of size ``p`` by graph, counted where the graph is."""
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            yield pd.DataFrame({"gid": frame["gid"], "n": [sum(1 for _ in graph_of(r).enumerate(p)) for r in frame.itertuples()]})

    return pack(db).mapInPandas(run, "gid long, n long")


def space_growth(db: GraphDB, sizes: list[int]) -> DataFrame:
    """``p, pieces``: the whole space for each size."""
    return reduce(DataFrame.unionByName, [space_size(db, p).agg(F.sum("n").alias("pieces")).select(F.lit(p).alias("p"), "pieces") for p in sizes])


def space_estimate(db: GraphDB, p: int, samples: int = 200, seed: int = 7) -> DataFrame:
    """``gid, estimate``: unbiased by random probes of the enumeration tree (the product of the branch counts met), for sizes beyond reach."""
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            out = []
            for row in frame.itertuples():
                g, total = graph_of(row), 0.0
                n = len(g.vids)
                for k in range(samples):
                    root = int(uniform(seed, row.gid, k, "root") * n)
                    weight = float(n)
                    above = ~((1 << (root + 1)) - 1)
                    open_, touched = g.adj[root] & above, (1 << root) | g.adj[root]
                    for depth in range(1, p):
                        c = open_.bit_count()
                        if not c:
                            weight = 0.0
                            break
                        pick = int(uniform(seed, row.gid, k, depth) * c)
                        weight *= c
                        order = list(bits(open_))
                        v = order[pick]
                        open_ = sum(1 << w for w in order[pick + 1 :]) | (g.adj[v] & above & ~touched)
                        touched |= g.adj[v]
                    total += weight
                out.append((row.gid, total / samples))
            yield pd.DataFrame(out, columns=["gid", "estimate"])

    return pack(db).mapInPandas(run, "gid long, estimate double")
