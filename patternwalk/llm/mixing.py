"""Operator 9: mix overlapping sources to target weights by min-cost flow.

Documents are aggregated by membership pattern, the sorted set of sources that
claim them. A pattern supplies its words once at no cost and, repeat by repeat, at
a rising cost, so the cost of repetition is convex. Each source takes its quota.
The flow of least cost says how many words of each pattern go to each source.
Documents of a pattern are then taken in a seeded order until its words are reached.

Only sums leave the executors: one row per pattern (at most ``MAX_PATTERNS``, checked)
and one per pattern and hash bucket. The seeded order of a pattern is not sorted as a
whole: sums per bucket of the order's hash find the bucket in which the words are
reached, and only that bucket's rows are ranked.

Defined results: null text has size 0 and is taken with 0 words; a null source is a
source of its own, after all others; repeated rows (same id) share their place in
the order and are taken together; an empty table gives an empty result; extra
columns are not read.
"""

from __future__ import annotations

from collections import defaultdict, deque

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from patternwalk.plans.scratch import cut

WORD = r"[^\x20\x09-\x0D]+"
MAX_PATTERNS = 100_000
#: The seeded order is cut into so many buckets of its hash.
BUCKETS = 1 << 12
_EPS = 1e-6


def word_count(text: str | Column) -> Column:
    text = F.col(text) if isinstance(text, str) else text
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(WORD)).cast("long")


def quotas(sizes: list[int], weights: list[float], ratio: float = 1.5, most: float = 2.0, total: int | None = None) -> list[float]:
    """Shares of ``ratio`` times ``total`` (all sizes) by weight; none above ``most`` times its size, the excess shared again."""
    order = sorted(range(len(sizes)), key=lambda i: (most * sizes[i] / weights[i], i))
    budget, weight, out = ratio * (sum(sizes) if total is None else total), float(sum(weights)), [0.0] * len(sizes)
    for n, i in enumerate(order):
        if most * sizes[i] * weight > budget * weights[i]:
            for j in order[n:]:
                out[j] = budget / weight * weights[j]
            break
        out[i] = most * sizes[i]
        budget -= out[i]
        weight -= weights[i]
    return out


def cycled_weights(n: int, cycle: tuple[float, ...] = (3.0, 1.0, 2.0)) -> list[float]:
    return [cycle[i % len(cycle)] for i in range(n)]


def route(supply: dict[tuple, float], quota: dict, repeats: int = 2) -> dict[tuple[tuple, object], float]:
    """Words from each pattern to each of its sources at the least cost; the ``r``-th use of a pattern's words costs ``r`` a word.

    Successive shortest paths on each connected part of the pattern-source graph; a
    part with one source needs none.
    """
    by_source = defaultdict(list)
    for p in supply:
        for s in p:
            by_source[s].append(p)
    flow: dict = {}
    seen: set = set()
    for start in quota:
        if start in seen:
            continue
        seen.add(start)
        sources, patterns, todo = [], {}, [start]
        while todo:
            s = todo.pop()
            sources.append(s)
            for p in by_source[s]:
                patterns[p] = None
                for t in p:
                    if t not in seen and t in quota:
                        seen.add(t)
                        todo.append(t)
        _part(list(patterns), sources, supply, quota, repeats, flow)
    return flow


def _part(patterns: list, sources: list, supply: dict, quota: dict, repeats: int, flow: dict) -> None:
    """Nodes are numbered, patterns first; a residual step from a source back to a pattern frees that pattern's words for another source."""
    n = len(patterns)
    number = {s: n + i for i, s in enumerate(sources)}
    used = [0.0] * n
    left = [quota[s] for s in sources]
    given: list[dict[int, float]] = [{} for _ in sources]

    def step(p: int) -> tuple[float, float]:
        """Cost of the next word of a pattern and how many words have that cost."""
        for r in range(1, repeats + 1):
            if used[p] < r * supply[patterns[p]] - _EPS:
                return float(r - 1), r * supply[patterns[p]] - used[p]
        return float("inf"), 0.0

    while any(x > _EPS for x in left):
        dist = [c if room > _EPS else float("inf") for c, room in map(step, range(n))] + [float("inf")] * len(sources)
        via = [-1] * len(dist)
        todo = deque(p for p in range(n) if dist[p] < float("inf"))
        while todo:
            x = todo.popleft()
            onward = [number[s] for s in patterns[x] if s in number] if x < n else [p for p, words in given[x - n].items() if words > _EPS]
            for y in onward:
                if dist[x] < dist[y] - _EPS:
                    dist[y], via[y] = dist[x], x
                    todo.append(y)
        ends = [i for i, x in enumerate(left) if x > _EPS and dist[n + i] < float("inf")]
        if not ends:
            break
        end = min(ends, key=lambda i: (dist[n + i], i))
        path = [n + end]
        while via[path[-1]] >= 0:
            path.append(via[path[-1]])
        path.reverse()
        pairs = list(zip(path, path[1:]))
        amount = min([left[end], step(path[0])[1], *(given[a - n][b] for a, b in pairs if a >= n)])
        used[path[0]] += amount
        left[end] -= amount
        for a, b in pairs:
            if a < n:
                given[b - n][a] = given[b - n].get(a, 0.0) + amount
            else:
                given[a - n][b] -= amount
    for i, s in enumerate(sources):
        for p, words in given[i].items():
            if words > _EPS:
                flow[patterns[p], s] = words


def place(id_col: str, seed: int) -> Column:
    """A document's place in the seeded order, from 0 to 2**48."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), F.coalesce(F.col(id_col).cast("string"), F.lit("null")))), 1, 12), 16, 10).cast("long")


def mix(docs: DataFrame, members: Column, weights=cycled_weights, ratio: float = 1.5, repeats: int = 2, seed: int = 17, id_col: str = "doc_id", text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """``(doc_id, members, size, copies, taken)`` and ``keep``.

    ``members``: an array of source names per row. ``weights``: the sources' weights,
    given their number, in order of name, null last. ``copies`` is how often the mix holds a document.
    """
    spark = docs.sparkSession
    keep = keep or []
    names = F.coalesce(members, F.array(F.lit(None).cast("string")))
    sized = cut(
        docs.select(F.col(id_col).alias("doc_id"), F.array_sort(F.array_distinct(names)).alias("members"), word_count(text_col).alias("size"), place(id_col, seed).alias("place"), *[F.col(c).alias(f"kept_{c}") for c in keep]),
        "sized",
    )
    sums = sized.groupBy("members").agg(F.sum("size").alias("words")).limit(MAX_PATTERNS + 1).collect()
    if len(sums) > MAX_PATTERNS:
        raise ValueError(f"more than {MAX_PATTERNS} membership patterns: merge rare sources first")
    supply = {tuple(r.members): int(r.words) for r in sums}
    sources = sorted({s for p in supply for s in p}, key=lambda s: (s is None, s or ""))
    size_of = {s: sum(n for p, n in supply.items() if s in p) for s in sources}
    quota = dict(zip(sources, quotas([size_of[s] for s in sources], weights(len(sources)), ratio, float(repeats), sum(supply.values())))) if sources else {}
    words = defaultdict(float)
    for (p, _), n in route(supply, quota, repeats).items():
        words[p] += n
    plan = []
    for p, n in supply.items():
        base = min(repeats, int((words[p] + 1e-3) // n)) if n else 0
        plan.append((list(p), base, max(0.0, words[p] - base * n)))
    plan_df = spark.createDataFrame(plan, "p array<string>, base int, rest double")
    width = (1 << 48) // BUCKETS
    bucket = F.floor(F.col("place") / F.lit(width)).cast("int")
    sums_by = sized.groupBy("members", bucket.alias("bucket")).agg(F.sum("size").alias("words"))
    running = Window.partitionBy("members").orderBy("bucket")
    edge = (
        sums_by.withColumn("through", F.sum("words").over(running))
        .join(F.broadcast(plan_df), F.col("members") == F.col("p"))
        .where("through > rest")
        .groupBy("members")
        .agg(F.min(F.struct("bucket", (F.col("through") - F.col("words")).alias("before"))).alias("e"))
        .select(F.col("members").alias("m"), F.col("e.bucket").alias("edge"), F.col("e.before").alias("before"))
    )
    steps = plan_df.join(edge, F.col("p") == F.col("m"), "left").select("p", "base", "rest", F.coalesce("edge", F.lit(BUCKETS)).alias("edge"), F.coalesce("before", F.lit(0)).alias("before"))
    steps = spark.createDataFrame(steps.collect(), steps.schema)  # as many rows as patterns, checked above
    rows = sized.withColumn("bucket", bucket).join(F.broadcast(steps), F.col("members") == F.col("p"))
    inside = rows.where("bucket != edge").withColumn("more", (F.col("bucket") < F.col("edge")).cast("int"))
    through = F.col("before") + F.sum("size").over(Window.partitionBy("members").orderBy("place"))
    at_edge = rows.where("bucket = edge").withColumn("more", (through - F.col("size") / 2 <= F.col("rest")).cast("int"))
    out = inside.unionByName(at_edge).withColumn("copies", F.when(F.col("size") > 0, F.least(F.col("base") + F.col("more"), F.lit(repeats))).otherwise(F.col("base") * 0))
    named = spark.createDataFrame([(s, size_of[s], quota[s]) for s in sources], "name string, source_size long, target double")
    out = out.select("doc_id", "members", "size", "copies", (F.col("copies") * F.col("size")).alias("taken"), *[F.col(f"kept_{c}").alias(c) for c in keep])
    return out.withColumn("first_source", F.element_at("members", 1)).join(F.broadcast(named), F.col("first_source").eqNullSafe(F.col("name"))).drop("name")


def query(spark, sf_dir: str) -> DataFrame:
    from patternwalk.sources.tables import table

    docs = table(spark, sf_dir, "documents")
    found = mix(docs, F.array(F.col("source")))
    return found.select("doc_id", "size", "source_size", "target", F.col("taken").cast("long").alias("taken"), F.col("first_source").alias("source"))


ORACLE = r"""
WITH sized AS (
  SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size,
         ('0x' || substr(md5('17:' || coalesce(doc_id::VARCHAR, 'null')), 1, 12))::BIGINT AS place
  FROM documents),
src AS (SELECT source, sum(size)::BIGINT AS source_size FROM sized GROUP BY source),
ranked AS (SELECT *, (CASE (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 WHEN 0 THEN 3.0 WHEN 1 THEN 1.0 ELSE 2.0 END)::DOUBLE AS w FROM src),
filled AS (
  SELECT *, sum(w) OVER late AS w_left, 1.5 * sum(source_size) OVER () - 2.0 * (sum(source_size) OVER early - source_size) AS b_left
  FROM ranked
  WINDOW early AS (ORDER BY 2.0 * source_size / w, source NULLS LAST ROWS UNBOUNDED PRECEDING),
         late AS (ORDER BY 2.0 * source_size / w, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING)),
level AS (SELECT min(CASE WHEN 2.0 * source_size * w_left > b_left * w THEN 2.0 * source_size / w END) AS r0 FROM filled),
rate AS (SELECT arg_min(b_left / w_left, 2.0 * source_size / w) AS rate FROM filled, level WHERE 2.0 * source_size * w_left > b_left * w),
goal AS (SELECT source, source_size, CASE WHEN r0 IS NOT NULL AND 2.0 * source_size / w >= r0 THEN (SELECT rate FROM rate) * w ELSE 2.0 * source_size END AS target FROM filled, level),
step AS (SELECT *, CASE WHEN source_size = 0 THEN 0 ELSE least(2, floor((target + 1e-3) / source_size)) END AS base FROM goal),
taken AS (
  SELECT s.doc_id, s.size, t.source_size, t.target, s.source,
         CASE WHEN s.size = 0 THEN 0 ELSE least(2, t.base + CASE WHEN sum(s.size) OVER (PARTITION BY s.source ORDER BY s.place) - s.size / 2.0 <= greatest(0.0, t.target - t.base * t.source_size) THEN 1 ELSE 0 END) * s.size END AS taken
  FROM sized s JOIN step t ON s.source IS NOT DISTINCT FROM t.source)
SELECT doc_id, size, source_size, target::DOUBLE AS target, taken::BIGINT AS taken, source FROM taken
"""
