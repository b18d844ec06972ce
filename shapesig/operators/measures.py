"""Accuracy and cost measures of a search."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shapesig.operators.prepare import Frame


def recall_at_k(approx: DataFrame, exact: DataFrame, ks: list[int], ties: bool = False) -> DataFrame:
    """(k, recall): share of each query's exact k best that the approximate k best hold, meaned over queries.

    The denominator is k, or the number of exact neighbours where fewer exist.
    With ``ties`` a returned shape counts if it is no farther than the exact k-th.
    """
    want = exact.select("qid", "pid", F.col("rank").alias("want"), F.col("jd").alias("want_jd"))
    got = approx.select("qid", "pid", F.col("rank").alias("got"), F.col("jd").alias("got_jd"))
    grid = F.explode(F.array(*map(F.lit, ks))).alias("k")
    if ties:
        limit = want.select("*", grid).where("want <= k").groupBy("qid", "k").agg(F.max("want_jd").alias("limit"), F.count(F.lit(1)).alias("n"))
        hits = got.select("*", grid).where("got <= k").join(F.broadcast(limit), ["qid", "k"]).where("got_jd <= limit").groupBy("qid", "k").agg(F.count(F.lit(1)).alias("h"))
        per = limit.join(hits, ["qid", "k"], "left").withColumn("r", F.least(F.coalesce("h", F.lit(0)), F.col("n")) / F.col("n"))
    else:
        met = want.join(got, ["qid", "pid"], "left").select("*", grid).where("want <= k")
        per = met.groupBy("qid", "k").agg((F.sum(F.when(F.col("got") <= F.col("k"), 1).otherwise(0)) / F.count(F.lit(1))).alias("r"))
    return per.groupBy("k").agg(F.round(F.avg("r"), 6).alias("recall"))


def hit_rate_at_k(approx: DataFrame, exact: DataFrame, ks: list[int]) -> DataFrame:
    """(k, hit_rate): share of the returned k best that are among the exact k best; queries without a return are left out."""
    want = exact.select("qid", "pid", F.col("rank").alias("want"))
    met = approx.select("qid", "pid", "rank", F.explode(F.array(*map(F.lit, ks))).alias("k")).where("rank <= k").join(want, ["qid", "pid"], "left")
    per = met.groupBy("qid", "k").agg(F.avg(F.when(F.col("want") <= F.col("k"), 1).otherwise(0)).alias("r"))
    return per.groupBy("k").agg(F.round(F.avg("r"), 6).alias("hit_rate"))


def mean_distance_at_k(found: DataFrame, ks: list[int]) -> DataFrame:
    """(k, mean_jd) over all returned neighbours up to rank k."""
    return found.select("jd", "rank", F.explode(F.array(*map(F.lit, ks))).alias("k")).where("rank <= k").groupBy("k").agg(F.round(F.avg("jd"), 6).alias("mean_jd"))


def pruning(candidates: DataFrame, shapes: int, queries: int, exclude_self: bool = True) -> DataFrame:
    """(cands, pruned_pct): candidates after bands are merged, and what share of all pairs they spare."""
    return pruned(candidates.agg(F.count(F.lit(1)).alias("cands")), shapes, queries, exclude_self)


def pruned(counts: DataFrame, shapes: int, queries: int, exclude_self: bool = True) -> DataFrame:
    """``pruning`` of candidates that were counted (``cands``) in parts."""
    pairs = queries * (shapes - 1 if exclude_self else shapes)
    total = counts.agg(F.coalesce(F.sum("cands"), F.lit(0)).cast("bigint").alias("cands"))
    return total.withColumn("pruned_pct", F.round(F.lit(100.0) * (1 - F.col("cands") / F.lit(float(max(1, pairs)))), 6))


def attempt_stats(hits: DataFrame) -> DataFrame:
    """Per shape: mean and variance of the first-hit values over slots."""
    return hits.where("h IS NOT NULL").groupBy("pid").agg(F.avg("h").alias("mean_h"), F.var_samp("h").alias("var_h"), F.count(F.lit(1)).alias("slots"))


def equal_share(a: DataFrame, b: DataFrame) -> DataFrame:
    """(qid, pid, share): equal slots of two long signatures among slots that both have."""
    met = a.select(F.col("pid").alias("qid"), "slot", F.col("h").alias("g")).join(b, "slot").where(F.col("g").isNotNull() & F.col("h").isNotNull())
    return met.groupBy("qid", "pid").agg(F.avg(F.when(F.col("g") == F.col("h"), 1.0).otherwise(0.0)).alias("share"))


def estimate_jaccard(a: str, b: str):
    """Similarity estimated from two wide signatures: the share of equal slots, as a column."""
    both = F.zip_with(a, b, lambda u, v: F.when(u == v, 1.0).otherwise(0.0))
    return F.aggregate(both, F.lit(0.0), lambda s, v: s + v) / F.size(both)


def sparsity(poly: DataFrame, frame: Frame) -> DataFrame:
    """Quantiles of the chance that a point of the frame falls in a shape."""
    s = F.col("area2") / F.lit(2.0 * frame.area)
    return poly.agg(F.count(F.lit(1)).alias("shapes"), F.round(F.avg(s), 9).alias("mean_s"), F.round(F.min(s), 9).alias("min_s"), F.round(F.max(s), 9).alias("max_s"), F.round(F.avg(1 / s), 6).alias("mean_attempts"))


def size_ratio(poly: DataFrame, slots: int) -> DataFrame:
    """Bytes of rings as text against bytes of signatures."""
    from shapesig.functions.geometry import to_wkt

    return poly.agg(F.sum(F.octet_length(to_wkt(F.col("ring")))).alias("ring_bytes"), (F.count(F.lit(1)) * 4 * slots).alias("signature_bytes")).withColumn("ratio", F.round(F.col("ring_bytes") / F.col("signature_bytes"), 6))


def timed(df: DataFrame) -> float:
    """Seconds to run a plan into no sink."""
    t = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - t


def cost_report(hash_s: float, refine_s: float, exact_s: float) -> dict[str, float]:
    """Hashing, lookup with refinement, their total, brute force, and the ratio cut (not rounded) to one decimal."""
    total = hash_s + refine_s
    return {"hash_s": hash_s, "refine_s": refine_s, "total_s": total, "exact_s": exact_s, "speedup": int(exact_s / total * 10 + 1e-9) / 10 if total else 0.0}


def tradeoff(runs: dict[tuple[str, int], tuple[DataFrame, DataFrame]]) -> DataFrame:
    """(layer, m, k, recall, cands, pruned_pct) of runs keyed by layer and length: recall and pruning frames."""
    out = None
    for (layer, m), (recall, pruned) in runs.items():
        row = recall.crossJoin(F.broadcast(pruned)).select(F.lit(layer).alias("layer"), F.lit(m).alias("m"), "k", "recall", "cands", "pruned_pct")
        out = row if out is None else out.unionByName(row)
    return out
