"""Graph databases built from ordinary tables."""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from patternwalk.functions.rng import uniform_column
from patternwalk.model import PACKED, GraphDB, largest_component, least_of_component, pack, simplify, unpacked, workers
from patternwalk.sources.tables import table

#: Radius of the proximity graphs, and the half of it that makes an edge near, in microseconds.
RADIUS, NEAR = 43 * 3_600_000_000, 77_400_000_000


def event_label(alphabet: str, kind="event_type", value="value"):
    """``fine``: type and value class; ``coarse``: type; ``skewed``: few common and many rare labels."""
    if alphabet == "coarse":
        return F.col(kind)
    v = F.col(value)
    if alphabet == "fine":
        return F.concat_ws(":", F.col(kind), F.when(v < 15, "0").when(v < 35, "1").when(v < 70, "2").otherwise("3"))
    if alphabet == "skewed":
        return F.when(v < 70, F.substring(kind, 1, 1)).otherwise(F.concat(F.col(kind), F.least(F.floor(v / 35), F.lit(6)).cast("string")))
    raise ValueError(alphabet)


def proximity(spark: SparkSession, sf_dir: str, alphabet: str = "fine") -> GraphDB:
    """A user's events, joined when close in time or consecutive.

    The range join is an equi-join on the time bucket and its successor, so a pair is
    met once and no user's events are paired beyond two buckets.
    """
    e = table(spark, sf_dir, "events").select(F.col("user_id").alias("gid"), F.col("event_id").alias("vid"), F.unix_micros(F.col("ts").cast("timestamp")).alias("t"), event_label(alphabet).alias("vlabel"))
    vertices, packed = e.select("gid", "vid", "vlabel"), _proximity_packed(e)
    e = e.select("gid", "vid", "t", F.floor(F.col("t") / RADIUS).alias("b"))
    late = e.select("gid", F.col("vid").alias("w"), F.col("t").alias("u"), F.explode(F.array("b", F.col("b") - 1)).alias("b"))
    after = (F.col("u") > F.col("t")) | ((F.col("u") == F.col("t")) & (F.col("w") > F.col("vid")))
    near = e.join(late, ["gid", "b"]).where(after & (F.col("u") - F.col("t") <= RADIUS)).select("gid", F.col("vid").alias("a"), F.col("w").alias("z"), (F.col("u") - F.col("t")).alias("gap"))
    order = Window.partitionBy("gid").orderBy("t", "vid")
    far = e.select("gid", F.col("vid").alias("a"), F.lead("vid").over(order).alias("z"), (F.lead("t").over(order) - F.col("t")).alias("gap")).where(F.col("gap") > RADIUS)
    rows = near.unionByName(far)
    label = F.when(F.col("gap") <= NEAR, "1").when(F.col("gap") <= RADIUS, "2").otherwise("3")
    return GraphDB(vertices, rows.select("gid", F.least("a", "z").alias("src"), F.greatest("a", "z").alias("dst"), label.alias("elabel")), packed=packed)


def _close(vids: np.ndarray, t: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The edges of one user's events, by rising ``vids``, as places in them, and the number of each edge's label less one."""
    order = np.lexsort((vids, t))
    t, n = t[order], len(t)
    more = np.searchsorted(t, t + RADIUS, "right") - np.arange(n) - 1
    alone = np.flatnonzero(more[:-1] == 0)  # the next event is further away than the radius
    a = np.repeat(np.arange(n), more)
    z = a + 1 + np.arange(len(a)) - np.repeat(np.cumsum(more) - more, more)
    x, y = vids[order[a]], vids[order[z]]
    other = (t[a] != t[z]) | (x != y)
    a, z = np.concatenate([a[other], alone]), np.concatenate([z[other], alone + 1])
    gap, ends = t[z] - t[a], np.searchsorted(vids, np.stack([vids[order[a]], vids[order[z]]]))
    src, dst, label = ends.min(axis=0), ends.max(axis=0), np.where(gap <= NEAR, 0, np.where(gap <= RADIUS, 1, 2))
    by = np.lexsort((label, dst, src))
    return src[by], dst[by], label[by]


def _proximity_packed(e: DataFrame) -> DataFrame:
    """The graphs of :func:`proximity` as :func:`patternwalk.model.pack` has them: ``e(gid, vid, t, vlabel)`` is shuffled once, and edges are made where a user's events are."""
    v = e.repartition(workers(e.sparkSession), "gid").groupBy("gid").agg(F.sort_array(F.collect_list(F.struct("vid", "vlabel", "t"))).alias("v"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            gid, vids, vlab, ts = batch.columns
            of, at = vids.flatten(), ts.flatten()
            usable = of.is_valid().to_numpy(zero_copy_only=False) & at.is_valid().to_numpy(zero_copy_only=False)
            of, at = (c.fill_null(0).to_numpy(zero_copy_only=False) for c in (of, at))
            first = np.concatenate([[0], np.cumsum(vids.value_lengths().to_numpy(zero_copy_only=False))])
            none = np.empty(0, np.int64)
            found = []
            for known, lo, hi in zip(gid.is_valid().to_pylist(), first[:-1], first[1:]):
                own = np.flatnonzero(usable[lo:hi])
                src, dst, label = _close(of[lo:hi][own], at[lo:hi][own]) if known and len(own) > 1 else (none, none, none)
                found.append((own[src], own[dst], label) if len(src) else (none, none, none))
            begin = pa.array(np.concatenate([[0], np.cumsum([len(f[0]) for f in found])]).astype(np.int32))
            ea, eb, label = (np.concatenate(c).astype(np.int32) for c in zip(*found)) if found else (none.astype(np.int32),) * 3
            elab = pa.DictionaryArray.from_arrays(pa.array(label), pa.array(["1", "2", "3"])).cast(pa.string())
            edges = [pa.ListArray.from_arrays(begin, c) for c in (pa.array(ea), pa.array(eb), elab, pa.array(np.full(len(ea), -1, np.int32)))]
            yield pa.RecordBatch.from_arrays([gid, vids, vlab, *edges], names=["gid", "vids", "vlab", "ea", "eb", "elab", "etyp"])

    return v.select("gid", F.col("v.vid").alias("vids"), F.col("v.vlabel").alias("vlab"), F.col("v.t").alias("ts")).mapInArrow(run, PACKED)


def copurchase(spark: SparkSession, sf_dir: str, year: int | None = None) -> GraphDB:
    """Parts bought in one order, by nation and market segment; the largest component of each."""
    o = table(spark, sf_dir, "orders")
    if year is not None:
        o = o.where(F.year("o_orderdate") == year)
    c = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_nationkey", "c_mktsegment")
    segments = c.select("c_mktsegment").distinct()
    place = segments.withColumn("k", F.rank().over(Window.orderBy("c_mktsegment")) - 1)  # a handful of segments
    o = o.join(c, "o_custkey").join(F.broadcast(place), "c_mktsegment").select("o_orderkey", "o_orderpriority", (F.col("c_nationkey") * 100 + F.col("k")).cast("long").alias("gid"))
    brand = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("part"), F.col("p_brand").alias("brand"))
    lines = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), F.col("l_partkey").alias("part")).join(brand, "part")
    baskets = lines.groupBy("o_orderkey").agg(F.sort_array(F.collect_set(F.struct("part", "brand"))).alias("ps"))
    own = baskets.join(o, "o_orderkey").where("gid IS NOT NULL").select("gid", F.struct(F.col("o_orderpriority").alias("link"), F.col("ps.part").alias("parts"), F.col("ps.brand").alias("brands")).alias("basket"))
    return unpacked(own.repartition(workers(spark), "gid").groupBy("gid").agg(F.collect_list("basket").alias("baskets")).mapInArrow(_bought_together, PACKED))


def _bought_together(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The largest component of each graph of ``gid, baskets``: parts joined when they share a basket, by the least link of those that they share. Of equally large ones, that with the smallest part."""
    names = [c.split()[0] for c in PACKED.split(", ")]
    kinds = [pa.int64(), pa.list_(pa.int64()), pa.list_(pa.string()), pa.list_(pa.int32()), pa.list_(pa.int32()), pa.list_(pa.string()), pa.list_(pa.int32())]
    for batch in batches:
        for at in range(batch.num_rows):
            link, parts, brands = batch.column(1).slice(at, 1).flatten().flatten()
            coded = link.dictionary_encode()
            order = sorted(coded.dictionary.to_pylist())
            rank = np.array([order.index(x) for x in coded.dictionary.to_pylist()] + [len(order)])  # none comes last
            size = parts.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
            vids, first, vertex = np.unique(parts.flatten().to_numpy(zero_copy_only=False), return_index=True, return_inverse=True)
            basket = np.repeat(np.arange(len(size)), size)
            more = np.cumsum(size)[basket] - np.arange(len(basket)) - 1  # parts of the same basket after each part
            a = np.repeat(np.arange(len(basket)), more)
            z = a + 1 + np.arange(len(a)) - np.repeat(np.cumsum(more) - more, more)
            label = rank[coded.indices.fill_null(len(order)).to_numpy(zero_copy_only=False)][basket[a]]
            a, z = vertex[a], vertex[z]
            a, z, label = a[a != z], z[a != z], label[a != z]
            by = np.lexsort((label, z, a))
            a, z, label = a[by], z[by], label[by]
            fresh = np.ones(len(a), bool)
            fresh[1:] = (a[1:] != a[:-1]) | (z[1:] != z[:-1])
            a, z, label = a[fresh], z[fresh], label[fresh]
            root = least_of_component(len(vids), a, z)
            kept = root == np.argmax(np.bincount(root))
            place, inside = np.cumsum(kept) - 1, kept[a]
            elab = pa.array([*order, None], pa.string()).take(pa.array(label[inside]))
            columns = [vids[kept], brands.flatten().take(pa.array(first[kept])), place[a[inside]].astype(np.int32), place[z[inside]].astype(np.int32), elab, np.full(int(inside.sum()), -1, np.int32)]
            whole = [pa.ListArray.from_arrays(pa.array([0, len(c)], pa.int32()), c if isinstance(c, pa.Array) else pa.array(c)) for c in columns]
            yield pa.RecordBatch.from_arrays([c.cast(k) for c, k in zip([batch.column(0).slice(at, 1), *whole], kinds)], names=names)


def order_star(spark: SparkSession, sf_dir: str, every: int = 1) -> GraphDB:
    """An order with its customer, lines, parts and suppliers: near-trees of about fourteen vertices."""
    line = table(spark, sf_dir, "lineitem")
    cols = line.columns
    line = line.where(F.col("l_orderkey") % every == 0)
    n = F.row_number().over(Window.partitionBy("l_orderkey").orderBy(*cols))
    line = line.select(F.col("l_orderkey").alias("gid"), "l_partkey", "l_suppkey", F.concat(F.lit("L:"), "l_returnflag", "l_linestatus").alias("flags"), n.cast("long").alias("n"))
    o = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("gid"), "o_custkey", "o_orderpriority").join(line.select("gid").distinct(), "gid", "left_semi")
    customer = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_mktsegment")
    part = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), "p_type")
    nation = table(spark, sf_dir, "nation").select(F.col("n_nationkey").alias("s_nationkey"), "n_regionkey")
    supplier = table(spark, sf_dir, "supplier").join(F.broadcast(nation), "s_nationkey").select(F.col("s_suppkey").alias("l_suppkey"), "n_regionkey")
    # vertex numbers: 0 order, 1 customer, then lines, parts and suppliers in ranges of their own
    lid, pid, sid = F.col("n") + 1, F.col("l_partkey") + 1_000_000, F.col("l_suppkey") + 1_000_000_000_000
    whole = line.join(o.select("gid"), "gid", "left_semi")
    vertices = (
        o.select("gid", F.lit(0).cast("long").alias("vid"), F.concat(F.lit("O:"), "o_orderpriority").alias("vlabel"))
        .unionByName(o.join(customer, "o_custkey").select("gid", F.lit(1).cast("long").alias("vid"), F.concat(F.lit("C:"), "c_mktsegment").alias("vlabel")))
        .unionByName(whole.select("gid", lid.alias("vid"), F.col("flags").alias("vlabel")))
        .unionByName(whole.join(part, "l_partkey").select("gid", pid.alias("vid"), F.concat(F.lit("P:"), "p_type").alias("vlabel")).distinct())
        .unionByName(whole.join(supplier, "l_suppkey").select("gid", sid.alias("vid"), F.concat(F.lit("S:"), F.col("n_regionkey").cast("string")).alias("vlabel")).distinct())
    )
    edges = (
        o.select("gid", F.lit(0).cast("long").alias("src"), F.lit(1).cast("long").alias("dst"), F.lit("oc").alias("elabel"))
        .unionByName(whole.select("gid", F.lit(0).cast("long").alias("src"), lid.alias("dst"), F.lit("ol").alias("elabel")))
        .unionByName(whole.select("gid", lid.alias("src"), pid.alias("dst"), F.lit("lp").alias("elabel")))
        .unionByName(whole.select("gid", lid.alias("src"), sid.alias("dst"), F.lit("ls").alias("elabel")))
    )
    return GraphDB(vertices, edges, packed=_star_packed(line, o, customer, part, supplier))


def _star_packed(line: DataFrame, o: DataFrame, customer: DataFrame, part: DataFrame, supplier: DataFrame) -> DataFrame:
    """The graphs of :func:`order_star` as :func:`patternwalk.model.pack` has them: lines and orders are shuffled by order once, and vertices and edges are made where an order's rows are."""
    def labels(of: DataFrame, key: str, label, name: str) -> DataFrame:
        return of.groupBy(key).agg(F.collect_list(F.struct(label.alias("vlabel"))).alias(name))

    own = line.join(labels(part, "l_partkey", F.concat(F.lit("P:"), "p_type"), "ps"), "l_partkey", "left")
    own = own.join(labels(supplier, "l_suppkey", F.concat(F.lit("S:"), F.col("n_regionkey").cast("string")), "ss"), "l_suppkey", "left")
    row = F.struct((F.col("n") + 1).alias("lid"), "flags", (F.col("l_partkey") + 1_000_000).alias("pid"), (F.col("l_suppkey") + 1_000_000_000_000).alias("sid"), "ps", "ss")
    spread = workers(line.sparkSession)
    own = own.select("gid", row.alias("row")).repartition(spread, "gid").groupBy("gid").agg(F.collect_list("row").alias("rows"))
    heads = o.join(labels(customer, "o_custkey", F.concat(F.lit("C:"), "c_mktsegment"), "cs"), "o_custkey", "left").select("gid", F.struct(F.concat(F.lit("O:"), "o_orderpriority").alias("vlabel"), "cs").alias("head"))
    heads = heads.repartition(spread, "gid").groupBy("gid").agg(F.collect_list("head").alias("heads"))
    vertex = lambda vid, label: F.struct(vid.cast("long").alias("vid"), label.alias("vlabel"))
    edge = lambda src, dst, label: F.struct(src.cast("long").alias("src"), dst.cast("long").alias("dst"), F.lit(label).alias("elabel"), F.lit(-1).alias("etype"))
    known = lambda rows, vid, of: F.array_distinct(F.flatten(F.transform(rows, lambda r: F.transform(F.coalesce(r[of], F.array().cast("array<struct<vlabel:string>>")), lambda x: vertex(r[vid], x["vlabel"])))))
    buyers = F.flatten(F.transform("heads", lambda h: F.transform(F.coalesce(h["cs"], F.array().cast("array<struct<vlabel:string>>")), lambda x: vertex(F.lit(1), x["vlabel"]))))
    v = F.concat(F.transform("heads", lambda h: vertex(F.lit(0), h["vlabel"])), buyers, F.transform("rows", lambda r: vertex(r["lid"], r["flags"])), known("rows", "pid", "ps"), known("rows", "sid", "ss"))
    e = F.concat(
        F.transform("heads", lambda h: edge(F.lit(0), F.lit(1), "oc")),
        F.transform("rows", lambda r: edge(F.lit(0), r["lid"], "ol")),
        F.transform("rows", lambda r: edge(r["lid"], r["pid"], "lp")),
        F.transform("rows", lambda r: edge(r["lid"], r["sid"], "ls")),
    )
    both = own.join(heads, "gid").select("gid", F.sort_array(v).alias("v"), F.sort_array(e).alias("e"))
    at = lambda c: F.transform("e", lambda x: F.array_position(F.col("v.vid"), x[c]).cast("int") - 1)
    return both.select("gid", F.col("v.vid").alias("vids"), F.col("v.vlabel").alias("vlab"), at("src").alias("ea"), at("dst").alias("eb"), F.col("e.elabel").alias("elab"), F.col("e.etype").alias("etyp"))


def vector_radius(spark: SparkSession, sf_dir: str, size: int = 50, least: float = 0.15, near: float = 0.25, whole: bool = False) -> GraphDB:
    """Vectors of one group joined when their cosine is at least ``least``; groups hold about ``size`` vectors. ``whole``: with all components, not only the largest."""
    v = table(spark, sf_dir, "embeddings").where("embedding IS NOT NULL")
    groups = max(1, v.count() // size)
    v = v.select((F.col("vec_id") % groups).alias("gid"), F.col("vec_id").alias("vid"), F.col("label").cast("string").alias("vlabel"), F.transform("embedding", lambda x: x.cast("double")).alias("x"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda p, q: p * q), F.lit(0.0), lambda s, z: s + z)
    v = v.withColumn("norm", F.sqrt(dot("x", "x")))
    pairs = v.alias("a").join(v.alias("b"), (F.col("a.gid") == F.col("b.gid")) & (F.col("a.vid") < F.col("b.vid")))
    cosine = F.round(dot("a.x", "b.x") / (F.col("a.norm") * F.col("b.norm")), 6)
    edges = pairs.select(F.col("a.gid").alias("gid"), F.col("a.vid").alias("src"), F.col("b.vid").alias("dst"), cosine.alias("c")).where(F.col("c") >= least)
    db = GraphDB(v.select("gid", "vid", "vlabel"), edges.select("gid", "src", "dst", F.when(F.col("c") >= near, "1").otherwise("2").alias("elabel")))
    return db if whole else largest_component(db)


def _plain_words(text: str):
    return F.filter(F.split(F.lower(text), " "), lambda w: w.rlike("^[a-z]{2,}$"))


def _token_graphs(texts: DataFrame) -> GraphDB:
    """``texts(gid, text)``: distinct plain words as vertices, neighbours in the text as edges."""
    kept = texts.select("gid", _plain_words("text").alias("ws"))
    at = kept.select("gid", F.posexplode("ws").alias("i", "w"))
    vid = F.dense_rank().over(Window.partitionBy("gid").orderBy("w")).cast("long") - 1
    at = at.withColumn("vid", vid)
    following = F.lead("vid").over(Window.partitionBy("gid").orderBy("i"))
    raw = at.select("gid", F.col("vid").alias("src"), following.alias("dst"), F.lit("n").alias("elabel")).where("dst IS NOT NULL")
    return GraphDB(at.select("gid", "vid", F.col("w").alias("vlabel")).distinct(), simplify(raw))


def token_adj(spark: SparkSession, sf_dir: str) -> GraphDB:
    """Words of a document next to each other: graphs whose vertices have distinct labels."""
    return _token_graphs(table(spark, sf_dir, "documents").select(F.col("doc_id").alias("gid"), "text"))


def token_adj_packed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The graphs of :func:`token_adj` as :func:`patternwalk.model.pack` has them, each made from its text where that is read. Ids that repeat share a graph, so they go the longer way."""
    texts = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("gid"), "text")
    if texts.groupBy("gid").count().where("count > 1").limit(1).count():
        return pack(_token_graphs(texts))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for gid, ws in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                if ws:
                    vlab = sorted(set(ws))
                    at = {w: i for i, w in enumerate(vlab)}
                    ids = [at[w] for w in ws]
                    e = sorted({(min(a, b), max(a, b)) for a, b in zip(ids, ids[1:]) if a != b})
                    rows.append((gid, list(range(len(vlab))), vlab, [a for a, _ in e], [b for _, b in e], ["n"] * len(e), [-1] * len(e)))
            kinds = [pa.int64(), pa.list_(pa.int64()), pa.list_(pa.string()), pa.list_(pa.int32()), pa.list_(pa.int32()), pa.list_(pa.string()), pa.list_(pa.int32())]
            columns = zip(*rows) if rows else [[]] * 7
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds)], names=["gid", "vids", "vlab", "ea", "eb", "elab", "etyp"])

    return texts.select("gid", _plain_words("text").alias("ws")).mapInArrow(run, PACKED)


def two_class(spark: SparkSession, sf_dir: str) -> GraphDB:
    """Word graphs of labelled documents, their labels as attributes."""
    labels = table(spark, sf_dir, "labels").select(F.col("doc_id").alias("gid"), "quality", "toxic")
    db = token_adj(spark, sf_dir).restrict(labels)
    return GraphDB(db.vertices, db.edges, labels)


def probe(spark: SparkSession, sf_dir: str) -> GraphDB:
    return _token_graphs(table(spark, sf_dir, "benchmark").select(F.col("item_id").alias("gid"), "text"))


def dialogue(spark: SparkSession, sf_dir: str) -> GraphDB:
    """Turns of a conversation: paths."""
    c = table(spark, sf_dir, "conversations").select(F.col("conv_id").alias("gid"), F.col("turn").alias("vid"), F.col("role").alias("vlabel"))
    following = F.lead("vid").over(Window.partitionBy("gid").orderBy("vid"))
    e = c.select("gid", F.col("vid").alias("src"), following.alias("dst"), F.lit("next").alias("elabel")).where("dst IS NOT NULL")
    return GraphDB(c, e)


_TAG = re.compile(r"<!--.*?-->|<(script|style)\b.*?</\1\s*>|<(/?)([a-zA-Z][a-zA-Z0-9]*)[^>]*>", re.S)
_VOID = frozenset("area base br col embed hr img input link meta source track wbr".split())


def dom_tree(spark: SparkSession, sf_dir: str) -> GraphDB:
    """The elements of a page under their parents, by a tolerant scan of its tags."""
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            out = []
            for gid, html in zip(frame["gid"], frame["html"]):
                open_, n = [(0, "#")], 0
                out.append((gid, 0, "#", -1))
                for m in _TAG.finditer(html or ""):
                    name = (m[1] or m[3] or "").lower()
                    if not name:
                        continue
                    if m[2]:
                        if any(t == name for _, t in open_[1:]):
                            while open_.pop()[1] != name:
                                pass
                        continue
                    if name == "p" and open_[-1][1] == "p":
                        open_.pop()
                    n += 1
                    out.append((gid, n, name, open_[-1][0]))
                    if name not in _VOID and not m[1]:
                        open_.append((n, name))
            yield pd.DataFrame(out, columns=["gid", "vid", "vlabel", "up"], dtype=object)

    rows = table(spark, sf_dir, "pages").select(F.col("page_id").alias("gid"), "html").mapInPandas(run, "gid long, vid long, vlabel string, up long")
    return GraphDB(rows.select("gid", "vid", "vlabel"), rows.where("up >= 0").select("gid", F.col("up").alias("src"), F.col("vid").alias("dst"), F.lit("child").alias("elabel")))


def synthetic(spark: SparkSession, n_graphs: int = 100, size: int = 250, n_vlabels: int = 20, n_elabels: int = 5, degree: float = 4.0, seed: int = 7) -> GraphDB:
    """Random connected graphs: a random tree and extra random edges, labels drawn by hash."""
    h = lambda *c: F.abs(F.xxhash64(F.lit(seed), *c))
    v = spark.range(n_graphs).select(F.col("id").alias("gid"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(size - 1).cast("long"))).alias("vid"))
    v = v.withColumn("vlabel", F.concat(F.lit("v"), (h(F.lit("v"), "gid", "vid") % n_vlabels).cast("string")))
    tree = v.where("vid > 0").select("gid", (h(F.lit("t"), "gid", "vid") % F.col("vid")).alias("src"), F.col("vid").alias("dst"))
    extra = v.select("gid", F.col("vid").alias("src"), F.explode(F.sequence(F.lit(1), F.lit(max(1, round(degree / 2 - 1))))).alias("k")).select("gid", "src", (h(F.lit("x"), "gid", "src", "k") % size).alias("dst"))
    e = tree.unionByName(extra).withColumn("elabel", F.concat(F.lit("e"), (h(F.lit("e"), "gid", F.least("src", "dst"), F.greatest("src", "dst")) % n_elabels).cast("string")))
    return GraphDB(v, simplify(e))


def synthetic_on(spark: SparkSession, sf_dir: str, n_vlabels: int = 20, n_elabels: int = 5, seed: int = 7) -> GraphDB:
    """Random connected graphs as :func:`synthetic` makes them, one for each user, with a vertex for each of the user's events: a random tree and an extra random edge a vertex, drawn by the events' ids."""
    below = lambda n, *key: F.floor(uniform_column(seed, *key) * n).cast("long")
    own = table(spark, sf_dir, "events").select(F.col("user_id").alias("gid"), "event_id")
    by = Window.partitionBy("gid")
    own = own.select("gid", "event_id", (F.row_number().over(by.orderBy("event_id")) - 1).cast("long").alias("vid"), F.count("*").over(by).alias("size"))
    tree = own.where("vid > 0").select("gid", below(F.col("vid"), F.lit("t"), F.col("event_id")).alias("src"), F.col("vid").alias("dst"))
    extra = own.select("gid", F.col("vid").alias("src"), below(F.col("size"), F.lit("x"), F.col("event_id")).alias("dst"))
    ends = [F.col("gid"), F.least("src", "dst"), F.greatest("src", "dst")]
    edges = tree.unionByName(extra).withColumn("elabel", F.concat(F.lit("e"), below(F.lit(n_elabels), F.lit("e"), *ends).cast("string")))
    return GraphDB(own.select("gid", "vid", F.concat(F.lit("v"), below(F.lit(n_vlabels), F.lit("v"), F.col("event_id")).cast("string")).alias("vlabel")), simplify(edges))
