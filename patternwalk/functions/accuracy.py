"""Cost and accuracy measures over mined and true patterns."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from patternwalk.operators.queue import expected_support, queue_order


def true_top(truth: DataFrame, k: int) -> DataFrame:
    """The ``k`` patterns of most support; ties by code."""
    return truth.orderBy(F.desc("support"), "code").limit(k)


def precision_at_k(truth: DataFrame, found: DataFrame, k: int) -> DataFrame:
    """``k, hits, precision``: the percentage of the true top ``k`` in the found top ``k`` (both already cut to ``k``)."""
    hits = true_top(truth, k).select("code").join(found.select("code").distinct(), "code", "left_semi")
    return hits.agg(F.count("*").alias("hits")).select(F.lit(k).alias("k"), "hits", (F.col("hits") * 100.0 / k).alias("precision"))


def precision_tie_aware(truth: DataFrame, found: DataFrame, k: int) -> DataFrame:
    """As above, but any pattern of at least the ``k``-th support counts as true."""
    least = true_top(truth, k).agg(F.min("support").alias("least"))
    hits = found.select("code").distinct().join(truth, "code").join(F.broadcast(least), F.col("support") >= F.col("least"))
    return hits.agg(F.count("*").alias("n")).select(F.lit(k).alias("k"), F.least("n", F.lit(k)).alias("hits"), (F.least("n", F.lit(k)) * 100.0 / k).alias("precision"))


def precision_curve(truth: DataFrame, queue: DataFrame, ks: list[int]) -> DataFrame:
    """Precision for each ``k`` from one ranking of each side."""
    t = true_top(truth, max(ks)).withColumn("tr", F.row_number().over(Window.orderBy(F.desc("support"), "code"))).select("code", "tr")
    q = queue.orderBy(*queue_order()).limit(max(ks)).withColumn("qr", F.row_number().over(Window.orderBy(*queue_order()))).select("code", "qr")
    both = t.join(q, "code")
    spark = truth.sparkSession
    each = spark.createDataFrame([(k,) for k in ks], "k int")
    return each.join(F.broadcast(both), (F.col("tr") <= F.col("k")) & (F.col("qr") <= F.col("k")), "left").groupBy("k").agg(F.count("code").alias("hits")).withColumn("precision", F.col("hits") * 100.0 / F.col("k"))


def union_for_tau(truth: DataFrame, found: DataFrame, k: int) -> DataFrame:
    """``code, support, exp_support`` over the true and the found top ``k``; a pattern never sampled has expected support 0."""
    codes = true_top(truth, k).select("code").unionByName(found.select("code")).distinct()
    return codes.join(truth.select("code", "support"), "code", "left").join(found.select("code", "exp_support"), "code", "left").select("code", F.coalesce("support", F.lit(0)).alias("support"), F.coalesce("exp_support", F.lit(0)).alias("exp_support"))


def kendall_tau_b(pairs: DataFrame, x: str, y: str, key: str = "code") -> DataFrame:
    """``n, concordant, discordant, tau_b`` of up to some thousands of items (twice ``k``), over all pairs of them."""
    a = pairs.select(F.col(key).alias("ka"), F.col(x).alias("xa"), F.col(y).alias("ya"))
    b = F.broadcast(pairs.select(F.col(key).alias("kb"), F.col(x).alias("xb"), F.col(y).alias("yb")))
    s = F.signum(F.col("xa") - F.col("xb")) * F.signum(F.col("ya") - F.col("yb"))
    counted = a.join(b, F.col("ka") < F.col("kb")).agg(
        F.sum((s > 0).cast("long")).alias("concordant"), F.sum((s < 0).cast("long")).alias("discordant"), F.sum((F.col("xa") != F.col("xb")).cast("long")).alias("nx"), F.sum((F.col("ya") != F.col("yb")).cast("long")).alias("ny")
    )
    return counted.select("concordant", "discordant", ((F.col("concordant") - F.col("discordant")) / F.sqrt(F.col("nx").cast("double") * F.col("ny"))).alias("tau_b"))


def tau_b(x: np.ndarray, y: np.ndarray) -> float:
    """The same in ``n log n``: inversions counted by merging, for rankings too long to pair."""
    order = np.lexsort((y, x))
    x, y = np.asarray(x)[order], np.asarray(y)[order]
    n = len(x)
    pairs = n * (n - 1) // 2
    tied = lambda *c: sum(k * (k - 1) // 2 for k in np.unique(np.stack(c, 1), axis=0, return_counts=True)[1].tolist())
    tx, ty, both = tied(x), tied(y), tied(x, y)

    def inversions(v: list) -> tuple[int, list]:
        if len(v) < 2:
            return 0, v
        (a, left), (b, right) = inversions(v[: len(v) // 2]), inversions(v[len(v) // 2 :])
        out, i, j, total = [], 0, 0, a + b
        while i < len(left) and j < len(right):
            if left[i] <= right[j]:
                out.append(left[i])
                i += 1
            else:
                out.append(right[j])
                j += 1
                total += len(left) - i
        return total, out + left[i:] + right[j:]

    discordant = inversions(y.tolist())[0]
    concordant = pairs - tx - ty + both - discordant
    return (concordant - discordant) / ((pairs - tx) * (pairs - ty)) ** 0.5


def tau_by(pairs: DataFrame, by: list[str], x: str, y: str) -> DataFrame:
    """``by, tau_b`` of each group; a group is at most the two top lists of one run, so one task holds it."""
    kinds = {f.name: f.dataType.simpleString() for f in pairs.schema.fields}

    def run(key: tuple, frame: pd.DataFrame) -> pd.DataFrame:
        with np.errstate(invalid="ignore"):
            return pd.DataFrame([[*key, float(tau_b(frame[x].to_numpy(float), frame[y].to_numpy(float)))]], columns=[*by, "tau_b"])

    return pairs.select(*by, x, y).groupBy(*by).applyInPandas(run, ", ".join(f"{c} {kinds[c]}" for c in by) + ", tau_b double")


def quality_by_run(truth: DataFrame, queues: DataFrame, k: int, by: list[str]) -> DataFrame:
    """``by, precision, tau_b`` of each run's top ``k``; ``queues`` has ``by, rank, code, exp_support``."""
    top = F.broadcast(true_top(truth, k).select("code", "support"))  # k rows
    found = queues.where(F.col("rank") <= k).select(*by, "code", "exp_support")
    hits = found.join(top.select("code"), "code", "left_semi").groupBy(*by).agg(F.count("*").alias("hits"))
    runs = found.select(*by).distinct()
    wanted = runs.join(top, F.lit(True)).select(*by, "code").unionByName(found.select(*by, "code")).distinct()
    both = wanted.join(truth.select("code", "support"), "code", "left").join(found, [*by, "code"], "left").select(*by, F.coalesce("support", F.lit(0)).alias("support"), F.coalesce("exp_support", F.lit(0)).alias("exp_support"))
    tau = tau_by(both, by, "support", "exp_support")
    return runs.join(hits, by, "left").join(tau, by, "left").select(*by, (F.coalesce("hits", F.lit(0)) * 100.0 / k).alias("precision"), "tau_b")


def score_correlation(patterns: DataFrame) -> DataFrame:
    """``score, pearson, spearman, tau_b`` of support with each score. Ranks are made within a score's own column, one task for each pair: for the patterns of a ground truth."""
    out = []
    for s in ("s1", "s2"):
        def run(key: tuple, frame: pd.DataFrame) -> pd.DataFrame:
            x, y = frame["support"].to_numpy(float), frame["value"].to_numpy(float)
            mean_rank = lambda v: pd.Series(v).rank().to_numpy()
            return pd.DataFrame([[key[0], np.corrcoef(x, y)[0, 1], np.corrcoef(mean_rank(x), mean_rank(y))[0, 1], tau_b(x, y)]], columns=["score", "pearson", "spearman", "tau_b"])

        out.append(patterns.select(F.lit(s).alias("score"), F.col("support").cast("double").alias("support"), F.col(s).cast("double").alias("value")).groupBy("score").applyInPandas(run, "score string, pearson double, spearman double, tau_b double"))
    return reduce(DataFrame.unionByName, out)


def quality_trace(samples: DataFrame, truth: DataFrame, k: int, checkpoints: list[int], by: tuple[str, ...] = ("chain",)) -> DataFrame:
    """``by, iters, precision, tau_b`` of the lossless queue at each checkpoint; ``samples`` has ``code``."""
    queues = []
    for m in checkpoints:
        q = expected_support(samples.where(F.col("iter") <= m), by)
        queues.append(q.withColumn("iters", F.lit(m)).withColumn("rank", F.row_number().over(Window.partitionBy(*by).orderBy(*queue_order()))).where(F.col("rank") <= k))
    return quality_by_run(truth, reduce(DataFrame.unionByName, queues), k, [*by, "iters"])


def repeat(per_run: DataFrame, by: list[str], value: str) -> DataFrame:
    """Mean and deviation over runs; runs are a column, so they were one job."""
    return per_run.groupBy(*by).agg(F.count("*").alias("runs"), F.avg(value).alias("mean"), F.stddev(value).alias("sd"))


def bound_violations(truth: DataFrame, found: DataFrame | None = None) -> DataFrame:
    """Patterns against ``exp_support <= support <= s2 <= s1``; must be empty."""
    bad = truth.where((F.col("support") > F.col("s2")) | (F.col("s2") * F.col("s1_den") > F.col("s1_num"))).select("code")
    if found is not None:
        bad = bad.unionByName(found.join(truth.select("code", "support"), "code", "left").where(F.coalesce("support", F.lit(0)) < F.col("exp_support")).select("code"))
    return bad


def false_positive_rate(truth: DataFrame, score: str, score_least: float, support_least: int) -> DataFrame:
    """The share of patterns of a high score whose support is low."""
    return truth.where(F.col(score) >= score_least).agg(F.count("*").alias("high"), F.avg((F.col("support") < support_least).cast("int")).alias("false_positive_rate"))


def chain_jaccard(topk: DataFrame) -> DataFrame:
    """``pairs, distance``: mean Jaccard distance between the chains' top lists; ``topk`` has ``chain, code``."""
    own = topk.select("chain", "code").distinct()
    size = own.groupBy("chain").agg(F.count("*").alias("n"))
    a, b = size.select(F.col("chain").alias("a"), F.col("n").alias("na")), size.select(F.col("chain").alias("b"), F.col("n").alias("nb"))
    shared = own.select(F.col("chain").alias("a"), "code").join(own.select(F.col("chain").alias("b"), "code"), "code").where("a < b").groupBy("a", "b").agg(F.count("*").alias("both"))
    every = a.join(F.broadcast(b), F.col("a") < F.col("b")).join(shared, ["a", "b"], "left").withColumn("both", F.coalesce("both", F.lit(0)))
    return every.agg(F.count("*").alias("pairs"), F.avg(1 - F.col("both") / (F.col("na") + F.col("nb") - F.col("both"))).alias("distance"))


def gelman_rubin(trace: DataFrame, value: str = "score", by: tuple[str, ...] = ()) -> DataFrame:
    """R-hat of a traced quantity over chains of equal length; ``trace`` has ``chain`` and the value."""
    per = trace.groupBy(*by, "chain").agg(F.avg(value).alias("mean"), F.var_samp(value).alias("var"), F.count("*").alias("n"))
    whole = per.groupBy(*by).agg(F.avg("var").alias("w"), F.var_samp("mean").alias("b_over_n"), F.avg("n").alias("n"), F.count("*").alias("chains"))
    return whole.withColumn("r_hat", F.sqrt(((F.col("n") - 1) / F.col("n") * F.col("w") + F.col("b_over_n")) / F.col("w"))).select(*by, "chains", "w", "b_over_n", "r_hat")


def visit_distance(samples: DataFrame, law: DataFrame) -> DataFrame:
    """Total variation between the visits of each graph's pieces and a law ``(gid, vs, pi)``; a graph without visits has none."""
    n = samples.groupBy("gid").agg(F.count("*").alias("all"))
    seen = samples.groupBy("gid", "vs").agg(F.count("*").alias("n")).join(n, "gid").select("gid", "vs", (F.col("n") / F.col("all")).alias("share"))
    both = law.select("gid", "vs", "pi").join(n.select("gid"), "gid", "left_semi").join(seen, ["gid", "vs"], "full_outer")
    return both.groupBy("gid").agg((F.sum(F.abs(F.coalesce("pi", F.lit(0.0)) - F.coalesce("share", F.lit(0.0)))) / 2).alias("distance"))


def random_precision(k: int, n: int) -> float:
    """Percent of the top ``k`` that ``k`` blind draws from ``n`` pieces are expected to hold."""
    return 100.0 * k / n


def queue_bytes(queue: DataFrame) -> DataFrame:
    return queue.agg(F.sum(F.length("code") + 8 * F.size("idset") + 24).alias("bytes"))


