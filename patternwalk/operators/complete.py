"""Complete miners and related methods: the baselines."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce
from math import ceil

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from patternwalk.functions.rng import uniform, uniform_column
from patternwalk.model import GraphDB, pack
from patternwalk.operators.canon import code_text, decode_code, dfs_code, edge_list_code
from patternwalk.operators.enumerate import enumerate_induced, graph_of, ground_truth
from patternwalk.operators.flat import Chunk, key_of, lists, over_pieces
from patternwalk.operators.kernel import bits
from patternwalk.operators.support import graph_types, numbered_types
from patternwalk.plans.scratch import cut

def _least(db: GraphDB, minsup: int | float) -> int:
    return minsup if isinstance(minsup, int) else max(1, ceil(minsup * db.vertices.select("gid").distinct().count() - 1e-9))


def mine_complete(db: GraphDB, minsup: int | float, max_size: int | None = None, strategy: str = "growth", induced: bool = False, stop_after: int | None = None, max_edges: int | None = None) -> DataFrame:
    """``code, n_vertices, n_edges, support`` of every frequent pattern.

    ``growth`` and ``levelwise`` grow embeddings edge by edge, level by level, and only those of
    frequent patterns go on; embeddings are grown anew at each level where their graph is, so that
    patterns alone are stored and shuffled. ``growth`` extends an
    embedding by every frequent edge next to it; ``levelwise`` also drops a candidate
    unless all its connected sub-patterns of one edge less were frequent. ``max_size`` caps
    vertices, ``stop_after`` the patterns expanded (the early-stopped form: what it has is not representative).
    With ``induced``, vertex sets are enumerated instead and sizes go up to ``max_size``, or to the first size without a frequent pattern.
    """
    least = _least(db, minsup)
    if induced:
        out, p = [], 2
        while max_size is None or p <= max_size:
            t = ground_truth(db, p).where(F.col("support") >= least)
            t = t.select("code", F.lit(p).alias("n_vertices"), F.size(F.split("code", ";")).alias("n_edges"), "support")
            out.append(t if max_size is not None else cut(t, "induced"))
            if max_size is None and not out[-1].limit(1).count():
                break
            p += 1
        return reduce(DataFrame.unionByName, out)
    spark = db.spark
    packed = cut(pack(db), "packed")
    types = numbered_types(graph_types(packed)).where(F.col("support") >= least)
    often = {(r.la, r.el, r.lb): 1 for r in types.select("la", "el", "lb").collect()}
    level, out, known = 1, [], None
    levels: list[set[str]] = []  # the frequent patterns of each number of edges so far
    while True:
        coded = over_pieces(packed, min(level + 1, max_size or level + 1), _grow(level, often, levels, max_size), "code string, graphs long")
        found = coded.groupBy("code").agg(F.sum("graphs").alias("support")).where(F.col("support") >= least)
        if strategy == "levelwise" and known is not None:
            found = cut(found, "candidates")
            found = found.join(_with_frequent_parts(found, known), "code", "left_semi")
        if stop_after is not None:
            found = found.orderBy("code").limit(stop_after)
        found = cut(found, "frequent")
        codes = {r.code for r in found.select("code").collect()}  # frequent patterns: what the miner is asked for
        if not codes:
            break
        out.append(found.withColumn("n_edges", F.lit(level)))
        if level == max_edges or (max_size is not None and level >= max_size * (max_size - 1) // 2):
            break
        known, level = found.select("code"), level + 1
        levels.append(codes)
    if not out:
        return spark.createDataFrame([], "code string, n_vertices int, n_edges int, support long")
    ends = F.flatten(F.transform(F.split("code", ";"), lambda e: F.slice(F.split(e, ","), 1, 2)))
    return reduce(DataFrame.unionByName, out).select("code", F.size(F.array_distinct(ends)).alias("n_vertices"), "n_edges", "support")


def _grow(level: int, often: dict, levels: list[set[str]], max_size: int | None):
    """``code, graphs`` of a chunk's edge sets of ``level`` edges: grown from single edges by frequent ones, only from frequent patterns."""
    levels = list(levels)

    def make(c: Chunk) -> Iterator[dict]:
        live = c.types(often, 0) == 1
        sets = [np.flatnonzero(live)]
        for n in range(level):
            if n:
                sets = c.grown(sets, live, max_size)
            if not len(sets[0]):
                return
            which, names = c.named_edges(sets, dfs_code)
            if n < level - 1:
                go_on = np.array([name in levels[n] for name in names])[which]
                sets = [x[go_on] for x in sets]
        graphs = np.unique(c.graph[c.a[sets[0]]] * len(names) + which) % len(names)
        yield {"code": pa.array(names, pa.string()), "graphs": np.bincount(graphs, minlength=len(names))}

    return make


def sub_patterns(code: str) -> list[str]:
    """Codes of the connected patterns with one edge less."""
    labels, edges = decode_code(code)
    out = set()
    for k in range(len(edges)):
        rest = edges[:k] + edges[k + 1 :]
        if not rest:
            continue
        used = sorted({v for a, b, _ in rest for v in (a, b)})
        grown, todo = {used[0]}, [used[0]]
        while todo:
            v = todo.pop()
            for a, b, _ in rest:
                if v in (a, b):
                    w = b if a == v else a
                    if w not in grown:
                        grown.add(w)
                        todo.append(w)
        if len(grown) == len(used):
            place = {v: i for i, v in enumerate(used)}
            out.add(code_text([labels[v] for v in used], [(place[a], place[b], x) for a, b, x in rest]))
    return sorted(out)


def _parts_of(patterns: DataFrame) -> DataFrame:
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            rows = [(c, s) for c in frame["code"] for s in sub_patterns(c)]
            yield pd.DataFrame(rows, columns=["code", "part"], dtype=object)

    return patterns.select("code").mapInPandas(run, "code string, part string")


def _with_frequent_parts(candidates: DataFrame, known: DataFrame) -> DataFrame:
    parts = _parts_of(candidates)
    lacking = parts.join(known.withColumnRenamed("code", "part"), "part", "left_anti").select("code").distinct()
    return parts.select("code").distinct().join(lacking, "code", "left_anti")


def maximal(patterns: DataFrame) -> DataFrame:
    """Frequent patterns that no frequent pattern of one edge more contains."""
    return patterns.join(_parts_of(patterns).select(F.col("part").alias("code")).distinct(), "code", "left_anti")


def closed(patterns: DataFrame) -> DataFrame:
    """Frequent patterns that no pattern of one edge more and equal support contains."""
    above = _parts_of(patterns).join(patterns.select("code", F.col("support").alias("support_above")), "code").select(F.col("part").alias("code"), "support_above")
    same = patterns.join(above, "code").where(F.col("support") == F.col("support_above")).select("code").distinct()
    return patterns.join(same, "code", "left_anti")


def pattern_walk(patterns: DataFrame, steps: int, seed: int = 0) -> DataFrame:
    """A Metropolis walk over the lattice of frequent patterns, uniform in the limit: ``step, code``. The lattice is the complete miner's output, so it is small enough to hold where a complete miner can run at all."""
    near: dict[str, set[str]] = {r.code: set() for r in patterns.select("code").collect()}
    for r in _parts_of(patterns).collect():
        if r.part in near:
            near[r.code].add(r.part)
            near[r.part].add(r.code)
    order = {c: sorted(n) for c, n in near.items()}
    rows, at = [], min(near) if near else None
    for k in range(steps if at is not None else 0):
        if order[at]:
            y = order[at][int(uniform(seed, k, 0) * len(order[at]))]
            if uniform(seed, k, 1) * len(order[y]) <= len(order[at]):
                at = y
        rows.append((k + 1, at))
    return patterns.sparkSession.createDataFrame(rows, "step int, code string")


def discriminative(coded: DataFrame, classes: DataFrame) -> DataFrame:
    """``code, support_0, support_1, difference, gain``: how well each pattern tells two classes of graphs apart; ``coded`` has ``gid, code``, ``classes`` has ``gid, y``."""
    n = classes.groupBy().agg(F.sum((F.col("y") == 0).cast("long")).alias("n0"), F.sum((F.col("y") == 1).cast("long")).alias("n1"))
    per = coded.select("gid", "code").distinct().join(classes, "gid").groupBy("code").agg(F.sum((F.col("y") == 0).cast("long")).alias("support_0"), F.sum((F.col("y") == 1).cast("long")).alias("support_1"))
    whole = per.join(F.broadcast(n), F.lit(True))

    def entropy(a, b):
        t = a + b
        h = lambda x: F.when((x > 0) & (t > 0), -(x / t) * F.log2(x / t)).otherwise(0.0)
        return h(a) + h(b)

    n0, n1, a, b = (F.col(c) for c in ("n0", "n1", "support_0", "support_1"))
    total = n0 + n1
    gain = entropy(n0, n1) - ((a + b) / total * entropy(a, b) + (total - a - b) / total * entropy(n0 - a, n1 - b))
    return whole.select("code", "support_0", "support_1", F.abs(a / n0 - b / n1).alias("difference"), gain.alias("gain"))


def mine_distinct_labels(db: GraphDB | DataFrame, minsup: int | float, max_edges: int | None = None) -> DataFrame:
    """Frequent connected edge sets where vertex labels are distinct in each graph: no isomorphism, no code, a plain relation. ``db`` may be packed graphs.

    A frequent set grows by every frequent edge of its graph that touches it, level by level, until no set is frequent.
    Sets are grown anew at each level where their graph is; counts of them alone, as numbers of edges, are shuffled.
    """
    packed = cut(pack(db) if isinstance(db, GraphDB) else db, "packed")
    spark = packed.sparkSession
    least = minsup if isinstance(minsup, int) else max(1, ceil(minsup * packed.count() - 1e-9))
    one = graph_types(packed).groupBy("la", "el", "lb").agg(F.count("*").alias("support")).where(F.col("support") >= least)
    rows = sorted((f"{r.la},{r.el},{r.lb}", r.la, r.el, r.lb, r.support) for r in one.collect())  # frequent edges, in order of their names
    found = spark.createDataFrame([([i], r[4], 1) for i, r in enumerate(rows)], "ks array<int>, support long, n_edges int")
    out, n = [found], 1
    shared = spark.sparkContext.broadcast({r[1:4]: i for i, r in enumerate(rows)})
    levels: list[set[tuple[int, ...]]] = []
    while rows and (max_edges is None or n < max_edges):
        n += 1
        counts = over_pieces(packed, min(n, 3), _grow_distinct(n, shared, levels), "ks array<int>, graphs long")
        found = cut(counts.groupBy("ks").agg(F.sum("graphs").alias("support")).where(F.col("support") >= least), "frequent")
        often = {tuple(r.ks) for r in found.select("ks").collect()}  # frequent patterns: what the miner is asked for
        if not often:
            break
        out.append(found.withColumn("n_edges", F.lit(n)))
        levels.append(often)
    names = spark.createDataFrame([([r[0] for r in rows],)], "names array<string>")
    coded = reduce(DataFrame.unionByName, out).join(F.broadcast(names), F.lit(True))
    return coded.select(F.array_join(F.transform("ks", lambda k: F.get("names", k)), ";").alias("code"), "support", "n_edges")


def _grow_distinct(level: int, shared, levels: list[set]):
    """``ks, graphs`` of a chunk's connected sets of ``level`` frequent edges; a set's edges, by their numbers, are in one graph once."""
    levels = list(levels)

    def make(c: Chunk) -> Iterator[dict]:
        kind = c.types(shared.value, -1)
        live = kind >= 0
        sets = [np.flatnonzero(live)]
        for n in range(1, level):
            if not len(sets[0]):
                return
            sets = c.grown(sets, live, None)
            ks = np.sort(np.stack([kind[x] for x in sets], axis=1), axis=1)
            _, first, of, count = np.unique(key_of(list(ks.T), len(shared.value)), return_index=True, return_inverse=True, return_counts=True)
            if n < level - 1:
                go_on = np.array([tuple(k) in levels[n - 1] for k in ks[first].tolist()], bool)[of]
                sets = [x[go_on] for x in sets]
        yield {"ks": lists(ks[first], np.int32), "graphs": count}

    return make


def class_of(db: GraphDB) -> DataFrame:
    """``gid, is_forest, treewidth_le_2, distinct_labels``: the restricted classes a graph is in. Treewidth two is tested by series-parallel reduction; outerplanar graphs all pass it."""
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            out = []
            for row in frame.itertuples():
                g = graph_of(row)
                near = [set(bits(m)) for m in g.adj]
                todo = [v for v in range(len(near)) if len(near[v]) <= 2]
                alive = set(range(len(near)))
                while todo:
                    v = todo.pop()
                    if v not in alive or len(near[v]) > 2:
                        continue
                    alive.discard(v)
                    ends = list(near[v])
                    for w in ends:
                        near[w].discard(v)
                    if len(ends) == 2:
                        near[ends[0]].add(ends[1])
                        near[ends[1]].add(ends[0])
                    todo += [w for w in ends if len(near[w]) <= 2]
                parts = len(g.parts((1 << len(g.vids)) - 1)) if g.vids else 0
                out.append((row.gid, len(g.edges) == len(g.vids) - parts, not alive, len(set(g.labels)) == len(g.labels)))
            yield pd.DataFrame(out, columns=["gid", "is_forest", "treewidth_le_2", "distinct_labels"])

    return pack(db).mapInPandas(run, "gid long, is_forest boolean, treewidth_le_2 boolean, distinct_labels boolean")


def blind_sample(db: GraphDB, p: int, m: int, seed: int = 0) -> DataFrame:
    """``m`` pieces drawn without aim: those of the least hash. Needs all pieces, which is why nobody can do it at size."""
    pieces = enumerate_induced(db, p, engine="kernel")
    return pieces.withColumn("u", uniform_column(seed, F.col("gid"), F.concat_ws(",", "vs"))).orderBy("u", "gid").limit(m)


def direct_sample(db: GraphDB, p: int, per_graph: int = 1, seed: int = 0) -> DataFrame:
    """Pieces drawn uniformly in each graph from the full list of its pieces."""
    pieces = enumerate_induced(db, p, engine="kernel").withColumn("u", uniform_column(seed, F.col("gid"), F.concat_ws(",", "vs")))
    return pieces.withColumn("k", F.row_number().over(Window.partitionBy("gid").orderBy("u"))).where(F.col("k") <= per_graph).drop("k", "u")


def pattern_features(db: GraphDB, codes: DataFrame, p: int) -> DataFrame:
    """``gid, code``: which graphs have which of the given patterns of size ``p`` (the sparse feature matrix)."""
    wanted = {r.code for r in codes.select("code").collect()}  # a top-k list

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for row in frame.itertuples():
                g, have = graph_of(row), set()
                for s in g.enumerate(p):
                    code = dfs_code(g.raw(s))
                    if code in wanted:
                        have.add(code)
                        if len(have) == len(wanted):
                            break
                yield pd.DataFrame({"gid": [row.gid] * len(have), "code": pd.Series(sorted(have), dtype=object)})

    return pack(db).mapInPandas(run, "gid long, code string")


def contains(db: GraphDB, codes: DataFrame, p: int) -> DataFrame:
    """``code, n``: in how many graphs each given pattern is found."""
    return codes.select("code").join(pattern_features(db, codes, p).groupBy("code").agg(F.count("*").alias("n")), "code", "left").select("code", F.coalesce("n", F.lit(0)).alias("n"))


__all__ = ["blind_sample", "class_of", "closed", "contains", "direct_sample", "discriminative", "edge_list_code", "maximal", "mine_complete", "mine_distinct_labels", "pattern_features", "pattern_walk", "sub_patterns"]
