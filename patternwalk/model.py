"""The data model: a database of labelled, simple, undirected graphs as three DataFrames."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from patternwalk.plans.scratch import cut, drop

VERTICES = "gid long, vid long, vlabel string"
EDGES = "gid long, src long, dst long, elabel string"
PACKED = "gid long, vids array<long>, vlab array<string>, ea array<int>, eb array<int>, elab array<string>, etyp array<int>"


@dataclass(frozen=True)
class GraphDB:
    """``vertices(gid, vid, vlabel)`` and ``edges(gid, src, dst, elabel)`` with ``src < dst``; ``attrs(gid, ...)`` where graphs have attributes.

    ``packed``: the same graphs as :func:`pack` has them, where a builder makes them without a table of edges.
    """

    vertices: DataFrame
    edges: DataFrame
    attrs: DataFrame | None = None
    packed: DataFrame | None = None

    @property
    def spark(self):
        return self.vertices.sparkSession

    def graphs(self) -> DataFrame:
        """``gid, n_vertices, n_edges`` of each graph that has a vertex."""
        if self.packed is not None:
            return self.packed.select("gid", F.size("vids").cast("long").alias("n_vertices"), F.size("ea").cast("long").alias("n_edges")).where("n_vertices > 0")
        v = self.vertices.groupBy("gid").agg(F.count("*").alias("n_vertices"))
        e = self.edges.groupBy("gid").agg(F.count("*").alias("n_edges"))
        return v.join(e, "gid", "left").select("gid", "n_vertices", F.coalesce("n_edges", F.lit(0)).alias("n_edges"))

    def symmetric(self) -> DataFrame:
        """``gid, a, b, elabel`` with each edge both ways."""
        e = self.edges
        return e.select("gid", F.col("src").alias("a"), F.col("dst").alias("b"), "elabel").unionByName(e.select("gid", F.col("dst").alias("a"), F.col("src").alias("b"), "elabel"))

    def typed_edges(self) -> DataFrame:
        """Edges with their end labels in order: ``la <= lb``."""
        v = self.vertices
        e = self.edges.join(v.select("gid", F.col("vid").alias("src"), F.col("vlabel").alias("l1")), ["gid", "src"]).join(v.select("gid", F.col("vid").alias("dst"), F.col("vlabel").alias("l2")), ["gid", "dst"])
        return e.select("gid", "src", "dst", "elabel", "l1", "l2", F.least("l1", "l2").alias("la"), F.greatest("l1", "l2").alias("lb"))

    def stored(self, name: str = "graphs") -> GraphDB:
        """The same database read from cut tables, so that its builder runs once."""
        if self.packed is not None:
            return unpacked(cut(self.packed, f"{name}-packed"), None if self.attrs is None else cut(self.attrs, f"{name}-attrs"))
        return GraphDB(cut(self.vertices, f"{name}-vertices"), cut(self.edges, f"{name}-edges"), None if self.attrs is None else cut(self.attrs, f"{name}-attrs"))

    def restrict(self, gids: DataFrame) -> GraphDB:
        keep = gids.select("gid").distinct()
        return GraphDB(self.vertices.join(keep, "gid", "left_semi"), self.edges.join(keep, "gid", "left_semi"), self.attrs, None if self.packed is None else self.packed.join(keep, "gid", "left_semi"))


def simplify(raw: DataFrame, keep: str = "min") -> DataFrame:
    """Undirected simple edges from any edge rows: loops go, parallels keep one label."""
    pick = F.min if keep == "min" else F.max
    return raw.where("src != dst").groupBy("gid", F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).agg(pick("elabel").alias("elabel"))


def components(db: GraphDB) -> DataFrame:
    """``gid, vid, comp``: the smallest vertex of each vertex's component, by union-find on packed graphs."""
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            out = []
            for g in frame.itertuples():
                root = list(range(len(g.vids)))

                def top(i, root=root):
                    while root[i] != i:
                        root[i] = i = root[root[i]]
                    return i

                for a, b in zip(g.ea, g.eb):
                    x, y = sorted((top(a), top(b)))
                    root[y] = x
                out += [(g.gid, int(v), int(g.vids[top(i)])) for i, v in enumerate(g.vids)]
            yield pd.DataFrame(out, columns=["gid", "vid", "comp"])

    return pack(db).select("gid", "vids", "ea", "eb").mapInPandas(run, "gid long, vid long, comp long")


def least_of_component(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The least vertex of each of ``n`` vertices' components: the greater root of an edge is hung below the smaller one until no edge has two."""
    root = np.arange(n)
    while len(a):
        x, y = root[a], root[b]
        apart = x != y
        a, b, x, y = a[apart], b[apart], x[apart], y[apart]
        np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))
        while not np.array_equal(up := root[root], root):
            root = up
    return root


def giant_components(db: GraphDB) -> DataFrame:
    """The same for graphs that no worker holds: each round every vertex takes its neighbours' least name, then its name's name, until nothing moves."""
    both = cut(db.symmetric().select("gid", "a", "b"), "both")
    names = cut(db.vertices.select("gid", "vid", F.col("vid").alias("comp")), "names")
    while True:
        near = both.join(names.select("gid", F.col("vid").alias("b"), F.col("comp").alias("of_b")), ["gid", "b"]).groupBy("gid", F.col("a").alias("vid")).agg(F.min("of_b").alias("least"))
        hooked = names.join(near, ["gid", "vid"], "left").select("gid", "vid", "comp", F.least("comp", F.coalesce("least", "comp")).alias("to"))
        jumped = hooked.join(hooked.select("gid", F.col("vid").alias("to"), F.col("to").alias("next")), ["gid", "to"]).select("gid", "vid", F.least("to", "next").alias("comp"), (F.least("to", "next") != F.col("comp")).alias("moved"))
        last, after = names, cut(jumped, "names")
        names = after.select("gid", "vid", "comp")
        names.cut_path = after.cut_path
        drop(last)
        if not after.where("moved").limit(1).count():
            drop(both)
            return names


def largest_component(db: GraphDB) -> GraphDB:
    """Each graph cut down to its largest component; ties go to the one with the smallest vertex."""
    comp = components(db)
    size = comp.groupBy("gid", "comp").agg(F.count("*").alias("n"))
    best = size.groupBy("gid").agg(F.max(F.struct("n", (-F.col("comp")).alias("c"))).alias("b")).select("gid", (-F.col("b.c")).alias("comp"))
    keep = comp.join(best, ["gid", "comp"]).select("gid", "vid")
    edges = db.edges.join(keep.withColumnRenamed("vid", "src"), ["gid", "src"], "left_semi").join(keep.withColumnRenamed("vid", "dst"), ["gid", "dst"], "left_semi")
    return GraphDB(db.vertices.join(keep, ["gid", "vid"], "left_semi"), edges.select("gid", "src", "dst", "elabel"), db.attrs)


def pack(db: GraphDB, etypes: DataFrame | None = None) -> DataFrame:
    """One row per graph with its labels and edges as arrays; edge ends are places in ``vids``.

    One shuffle by ``gid``. A graph is one row, so the largest must fit a worker;
    :func:`patternwalk.operators.bsp.walk_in_supersteps` serves graphs that don't.
    """
    if etypes is None and db.packed is not None:
        return db.packed
    v = db.vertices.groupBy("gid").agg(F.sort_array(F.collect_list(F.struct("vid", "vlabel"))).alias("v"))
    if etypes is None:
        e = db.edges.select("gid", "src", "dst", "elabel", F.lit(-1).alias("etype"))
    else:
        e = db.typed_edges().withColumnRenamed("elabel", "el").join(etypes.select("etype", "la", "el", "lb"), ["la", "el", "lb"]).select("gid", "src", "dst", F.col("el").alias("elabel"), "etype")
    e = e.groupBy("gid").agg(F.sort_array(F.collect_list(F.struct("src", "dst", "elabel", "etype"))).alias("e"))
    at = lambda c: F.transform("e", lambda x: F.array_position(F.col("v.vid"), x[c]).cast("int") - 1)
    both = v.join(e, "gid", "left").withColumn("e", F.coalesce("e", F.array().cast("array<struct<src:bigint,dst:bigint,elabel:string,etype:int>>")))
    packed = both.select("gid", F.col("v.vid").alias("vids"), F.col("v.vlabel").alias("vlab"), at("src").alias("ea"), at("dst").alias("eb"), F.col("e.elabel").alias("elab"), F.col("e.etype").alias("etyp"))
    return packed.repartition(workers(db.spark), "gid")


def unpacked(packed: DataFrame, attrs: DataFrame | None = None) -> GraphDB:
    """The database of packed graphs."""
    v = packed.select("gid", F.explode(F.arrays_zip("vids", "vlab")).alias("v"))
    vid = lambda i: F.get("vids", i)
    ends = F.transform(F.arrays_zip("ea", "eb", "elab"), lambda e: F.struct(vid(e["ea"]).alias("src"), vid(e["eb"]).alias("dst"), e["elab"].alias("elabel")))
    e = packed.select("gid", ends.alias("es")).select("gid", F.explode("es").alias("e"))
    return GraphDB(v.select("gid", F.col("v.vids").alias("vid"), F.col("v.vlab").alias("vlabel")), e.select("gid", "e.src", "e.dst", "e.elabel"), attrs, packed)


def workers(spark) -> int:
    """Partitions for kernels: their work is not in proportion to bytes, so adaptive merging of small partitions would leave cores idle."""
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), 2 * spark.sparkContext.defaultParallelism)


def validate(db: GraphDB) -> DataFrame:
    """``gid, rule, n``: how often each graph breaks a rule; empty for a proper database."""
    e, v = db.edges, db.vertices
    rows = [
        e.where("src = dst").groupBy("gid").agg(F.lit("loop").alias("rule"), F.count("*").alias("n")),
        e.where("src > dst").groupBy("gid").agg(F.lit("order").alias("rule"), F.count("*").alias("n")),
        e.groupBy("gid", F.least("src", "dst"), F.greatest("src", "dst")).count().where("count > 1").groupBy("gid").agg(F.lit("parallel").alias("rule"), F.count("*").alias("n")),
        v.where("vlabel IS NULL").groupBy("gid").agg(F.lit("unlabelled vertex").alias("rule"), F.count("*").alias("n")),
        e.where("elabel IS NULL").groupBy("gid").agg(F.lit("unlabelled edge").alias("rule"), F.count("*").alias("n")),
        e.select("gid", F.explode(F.array("src", "dst")).alias("vid")).join(v, ["gid", "vid"], "left_anti").groupBy("gid").agg(F.lit("unknown end").alias("rule"), F.count("*").alias("n")),
        components(db).groupBy("gid").agg(F.count_distinct("comp").alias("c")).where("c > 1").select("gid", F.lit("disconnected").alias("rule"), (F.col("c") - 1).alias("n")),
    ]
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out


def stats(db: GraphDB) -> DataFrame:
    """One row: graphs, vertices, edges, labels."""
    if db.packed is not None:
        own = cut(db.packed.select(F.size("vids").alias("n_v"), F.size("ea").alias("n_e"), F.array_distinct("vlab").alias("vlab"), F.array_distinct("elab").alias("elab")), "sizes")
        g = own.agg(F.count("*").alias("n_graphs"), F.sum("n_v").alias("n_vertices"), F.sum("n_e").cast("long").alias("n_edges"), F.max(F.col("n_v").cast("long")).alias("max_vertices"))
        v, e = (own.select(F.explode(c).alias("x")).agg(F.count_distinct("x").alias(n)) for c, n in (("vlab", "n_vlabels"), ("elab", "n_elabels")))
        return g.join(v, F.lit(True)).join(e, F.lit(True))
    g = db.graphs().agg(F.count("*").alias("n_graphs"), F.sum("n_vertices").alias("n_vertices"), F.sum("n_edges").cast("long").alias("n_edges"), F.max("n_vertices").alias("max_vertices"))
    v = db.vertices.agg(F.count_distinct("vlabel").alias("n_vlabels"))
    e = db.edges.agg(F.count_distinct("elabel").alias("n_elabels"))
    return g.join(v, F.lit(True)).join(e, F.lit(True))


def induced_edges(db: GraphDB, pieces: DataFrame) -> DataFrame:
    """Edges among the vertices of each piece; ``pieces`` has ``gid`` and ``vs``, an array of vertices."""
    own = pieces.select("gid", "vs", F.explode("vs").alias("src"))
    return own.join(db.edges, ["gid", "src"]).where(F.array_contains("vs", F.col("dst"))).select("gid", "vs", "src", "dst", "elabel")


def piece_stats(edges_of: DataFrame) -> DataFrame:
    """``gid, vs, n_edges, density, max_degree, degrees`` from the rows of :func:`induced_edges`; ``degrees`` falls."""
    ends = edges_of.select("gid", "vs", F.explode(F.array("src", "dst")).alias("v")).groupBy("gid", "vs", "v").agg(F.count("*").alias("d"))
    out = ends.groupBy("gid", "vs").agg((F.sum("d") / 2).cast("long").alias("n_edges"), F.max("d").alias("max_degree"), F.sort_array(F.collect_list("d"), False).alias("degrees"))
    p = F.size("vs")
    return out.withColumn("density", 2 * F.col("n_edges") / (p * (p - 1)))


def frequent(patterns: DataFrame, minsup: int | float, n_graphs: int | None = None) -> DataFrame:
    """Patterns of at least ``minsup`` graphs, or of at least that share of ``n_graphs``."""
    least: Column = F.lit(minsup) if isinstance(minsup, int) else F.ceil(F.lit(minsup * n_graphs) - 1e-9)
    return patterns.where(F.col("support") >= least)
