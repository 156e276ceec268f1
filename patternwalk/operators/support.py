"""Edge types, their supports, and the scores that the walk aims at."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from patternwalk.model import GraphDB
from patternwalk.operators.flat import Chunk, key_of, over_pieces
from patternwalk.operators.kernel import Scores
from patternwalk.plans.scratch import cut

#: The width of the masks of the score ``s2_hashed``, which counts hashed graphs.
SKETCH_GRAPHS = 1 << 16
#: The masks of ``s2`` are exact at every number of graphs; more bytes of them than the driver takes are refused.
MAX_MASK_BYTES = 1 << 30
#: Graphs numbered in one task, about.
NUMBERED = 1 << 14
#: Edge types that the driver takes; more means labels that don't repeat, for which scores say nothing.
MAX_TYPES = 200_000

_CUSTOM: dict[str, Callable] = {}


def edge_support(db: GraphDB, sets: bool = False) -> DataFrame:
    """``etype, la, el, lb, support``: graphs that have an edge of each type; with ``sets``, their ids too.

    Types are numbered in label order. The (type, graph) pairs are made distinct before
    they are counted, so a common type is pre-aggregated where its graphs are.
    """
    pairs = db.typed_edges().select("la", F.col("elabel").alias("el"), "lb", "gid").distinct()
    out = [F.count("*").alias("support")] + ([F.sort_array(F.collect_list("gid")).alias("tids")] if sets else [])
    types = pairs.groupBy("la", "el", "lb").agg(*out)
    number = (F.row_number().over(Window.orderBy("la", "el", "lb")) - 1).cast("int")  # one row a type: labels, not data
    return types.withColumn("etype", number).select("etype", "la", "el", "lb", "support", *(["tids"] if sets else []))


def graph_types(packed: DataFrame) -> DataFrame:
    """``la, el, lb, gid``: the edge types of each packed graph, once each."""
    def make(c: Chunk) -> Iterator[dict]:
        x, y = c.label[c.a], c.label[c.b]
        x, y, g = np.minimum(x, y), np.maximum(x, y), c.graph[c.a]
        at = np.unique(key_of([g, x, c.elabel, y], max(len(c.gids), len(c.names), len(c.links))), return_index=True)[1] if len(g) else []
        yield {"la": [c.names[x[i]] for i in at], "el": [c.links[c.elabel[i]] for i in at], "lb": [c.names[y[i]] for i in at], "gid": c.gids[g[at]] if len(g) else []}

    return over_pieces(packed, 2, make, "la string, el string, lb string, gid long")


def placed_types(packed: DataFrame) -> DataFrame:
    """``la, el, lb, place``, a cut table: the edge types of each packed graph, once each, and a number of its own for each graph, by partition and row."""
    label = lambda i: F.get("vlab", i)
    ends = F.filter(F.arrays_zip("ea", "eb", "elab"), lambda e: (e["ea"] >= 0) & (e["eb"] >= 0))
    kinds = F.transform(ends, lambda e: F.struct(F.least(label(e["ea"]), label(e["eb"])).alias("la"), e["elab"].alias("el"), F.greatest(label(e["ea"]), label(e["eb"])).alias("lb")))
    each = packed.select(F.monotonically_increasing_id().alias("place"), F.array_distinct(kinds).alias("kinds"))
    return cut(each.select(F.explode("kinds").alias("k"), "place").select("k.la", "k.el", "k.lb", "place"), "placed-types")


def placed_scores(db: GraphDB, types: DataFrame, pairs: DataFrame) -> Scores:
    """The score ``s2`` from the rows of :func:`placed_types`: masks are made by number, without a join of graphs, a block of bits after the other."""
    rows = types.select("etype", "support").orderBy("etype").limit(MAX_TYPES + 1).collect()
    if len(rows) > MAX_TYPES:
        raise ValueError(f"more than {MAX_TYPES} edge types")
    n = db.packed.count()
    if len(rows) * n > 8 * MAX_MASK_BYTES:
        raise ValueError(f"exact masks of {n} graphs for {len(rows)} edge types are over {MAX_MASK_BYTES} bytes; s2_hashed and s2_bound are scores of their own")
    own = pairs.join(F.broadcast(types.select("etype", "la", "el", "lb")), ["la", "el", "lb"])
    own = own.select("etype", F.shiftright("place", 15).alias("block"), F.col("place").bitwiseAND(32767).alias("bit"))
    found = own.groupBy("block", "etype").agg(F.bitmap_construct_agg("bit").alias("bits")).collect()
    start = {b: 4096 * i for i, b in enumerate(sorted({r.block for r in found}))}
    masks = [bytearray(4096 * len(start)) for _ in rows]
    for r in found:
        masks[r.etype][start[r.block] : start[r.block] + 4096] = r.bits
    return Scores("s2", [r.support for r in rows], [int.from_bytes(m, "little") for m in masks])


def numbered_types(pairs: DataFrame) -> DataFrame:
    """:func:`edge_support` from the rows of :func:`graph_types`."""
    number = (F.row_number().over(Window.orderBy("la", "el", "lb")) - 1).cast("int")  # one row a type: labels, not data
    return pairs.groupBy("la", "el", "lb").agg(F.count("*").alias("support")).withColumn("etype", number).select("etype", "la", "el", "lb", "support")


def register_score(name: str, of_types: Callable) -> None:
    """A target of one's own: a positive integer, or a pair of integers as a ratio, from the list of a piece's edge types."""
    _CUSTOM[name] = of_types


def _numbered(graphs: DataFrame, n: int) -> DataFrame:
    """``gid, bit``: each graph with a number from 0 on, by hash classes of about ``NUMBERED`` graphs."""
    own = graphs.withColumn("class", F.pmod(F.xxhash64("gid"), F.lit(n // NUMBERED + 1)))
    sizes, starts, at = {r["class"]: r["count"] for r in own.groupBy("class").count().collect()}, [], 0
    for k in sorted(sizes):
        starts.append((k, at))
        at += sizes[k]
    first = graphs.sparkSession.createDataFrame(starts, "class long, first long")
    rank = F.row_number().over(Window.partitionBy("class").orderBy("gid")) - 1
    return own.withColumn("rank", rank).join(F.broadcast(first), "class").select("gid", (F.col("first") + F.col("rank")).alias("bit"))


def score_table(db: GraphDB, types: DataFrame, name: str, pairs: DataFrame | None = None) -> Scores:
    """What a worker needs to score a piece; ``pairs`` are the rows of :func:`graph_types`, where they are at hand. At most ``MAX_TYPES`` numbers and, for ``s2``, an exact mask of one bit a graph for each of them reach the driver.

    ``s2`` is the number of graphs at every size; masks of over ``MAX_MASK_BYTES`` are an error.
    ``s2_hashed`` counts hashed graphs in masks of ``SKETCH_GRAPHS`` bits, a positive score of its own that may be
    below or above ``s2``. ``s2_bound`` is the least support among the types, which needs no masks.
    """
    if name in _CUSTOM:
        return Scores(name, custom=_CUSTOM[name])
    if name == "uniform":
        return Scores(name)
    rows = types.select("etype", "support").orderBy("etype").limit(MAX_TYPES + 1).collect()
    if len(rows) > MAX_TYPES:
        raise ValueError(f"more than {MAX_TYPES} edge types")
    support = [r.support for r in rows]
    if name in ("s1", "s2_bound"):
        return Scores(name, support)
    if name not in ("s2", "s2_hashed"):
        raise ValueError(name)
    if name == "s2":
        n = db.vertices.select("gid").distinct().count()
        if len(support) * n > 8 * MAX_MASK_BYTES:
            raise ValueError(f"exact masks of {n} graphs for {len(support)} edge types are over {MAX_MASK_BYTES} bytes; s2_hashed and s2_bound are scores of their own")
        place = _numbered(db.vertices.select("gid").distinct(), n)
    else:
        place = db.vertices.select("gid").distinct().withColumn("bit", F.pmod(F.xxhash64("gid"), F.lit(SKETCH_GRAPHS)))
    pairs = db.typed_edges().withColumnRenamed("elabel", "el") if pairs is None else pairs
    pairs = pairs.join(F.broadcast(types.select("etype", "la", "el", "lb")), ["la", "el", "lb"]).select("gid", "etype").distinct()
    bucketed = pairs.join(place, "gid").groupBy("etype", F.floor(F.col("bit") / 32768).alias("part")).agg(F.bitmap_construct_agg((F.col("bit") % 32768).cast("long")).alias("bits"))
    ids = [0] * len(support)
    for r in bucketed.collect():
        ids[r.etype] |= int.from_bytes(bytes(r.bits), "little") << (32768 * int(r.part))
    return Scores("s2", support, ids)


def piece_types(db: GraphDB, pieces: DataFrame, types: DataFrame) -> DataFrame:
    """``gid, vs, etype, support`` for each induced edge of each piece."""
    own = pieces.select("gid", "vs", F.explode("vs").alias("src"))
    e = db.typed_edges().withColumnRenamed("elabel", "el").join(F.broadcast(types.select("etype", "la", "el", "lb", "support")), ["la", "el", "lb"])
    return own.join(e, ["gid", "src"]).where(F.array_contains("vs", F.col("dst"))).select("gid", "vs", "etype", "support")


def score_s1(edge_rows: DataFrame, by: list[str]) -> DataFrame:
    """Mean support of the edges, repeats counted, as a ratio and a double."""
    return edge_rows.groupBy(*by).agg(F.sum("support").alias("s1_num"), F.count("*").alias("s1_den")).withColumn("s1", F.col("s1_num") / F.col("s1_den"))


def score_s2(edge_rows: DataFrame, type_sets: DataFrame, by: list[str], mode: str = "exact") -> DataFrame:
    """Graphs that have every edge type of a piece.

    ``exact``: distinct types per piece are matched with the types' graphs, and graphs
    that have as many as the piece are counted; pieces are first reduced to distinct type
    sets, so the count is done once a set. ``min_bound``: the least support, an upper bound.
    """
    kinds = edge_rows.groupBy(*by).agg(F.sort_array(F.collect_set("etype")).alias("kinds"), F.min("support").alias("least"))
    if mode == "min_bound":
        return kinds.select(*by, F.col("least").alias("s2"))
    sets = kinds.select("kinds").distinct()
    need = F.size("kinds")
    matched = sets.select("kinds", F.explode("kinds").alias("etype")).join(type_sets.select("etype", F.explode("tids").alias("g")), "etype")
    counted = matched.groupBy("kinds", "g").agg(F.count("*").alias("n")).where(F.col("n") == need).groupBy("kinds").agg(F.count("*").alias("s2"))
    return kinds.join(counted, "kinds", "left").select(*by, F.coalesce("s2", F.lit(0)).alias("s2"))


def score_uniform() -> Column:
    return F.lit(1)
