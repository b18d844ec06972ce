"""Choice of the physical form from counts, and remedies for hot buckets."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shapesig.functions import theory
from shapesig.operators.search import MOST_QUERY_BYTES


@dataclass(frozen=True)
class Choice:
    form: str  # of the first-hit stage
    broadcast_probes: bool
    bounds: bool
    salts: int


def choose(shapes: int, queries: int, mean_vertices: float, slots: int, mean_attempts: float, largest_bucket: int = 0, in_jvm: bool = False) -> Choice:
    """The forms for a search.

    Row-local Arrow hashing shuffles nothing and stops at first hits, so it is the
    rule; without Python workers the gridded join serves where points times shapes
    are many, array functions where they are few. Probes are broadcast while their
    codes are small. A bucket above a million entries is salted.
    """
    if not in_jvm:
        form = "arrow"
    elif shapes * slots * mean_attempts > 1e8:
        form = "grid"
    else:
        form = "expr" if mean_vertices <= 32 else "sql"
    return Choice(form, queries * 64 * max(1, slots) <= MOST_QUERY_BYTES, shapes * mean_vertices > 1e5, max(1, -(-largest_bucket // 1_000_000)))


def tune_from_distances(near: DataFrame, spread: DataFrame, recall: float) -> tuple[int, int]:
    """(m, bands) for a recall from exact distances (jd) of true neighbours and of all pairs, both as 101 quantiles."""
    grid = [i / 100 for i in range(101)]
    a, b = (df.agg(F.percentile("jd", grid).alias("p")).first()["p"] or [1.0] for df in (near, spread))
    return theory.tune([1 - x for x in a], [1 - x for x in b], recall)


def salted_candidates(queries: DataFrame, index: DataFrame, salts: int) -> DataFrame:
    """Distinct (qid, pid) that share a bucket: shapes of a bucket are dealt over salts, queries go to all of them."""
    dealt = index.withColumn("salt", F.pmod(F.xxhash64("pid"), F.lit(salts)).cast("int"))
    q = queries.select("band", "key", F.col("code").alias("qcode"), F.col("pid").alias("qid"), F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt"))
    met = dealt.join(q, ["band", "key", "salt"]).where((F.col("code") == F.col("qcode")) & (F.col("qid") != F.col("pid")))
    return met.select("qid", "pid").distinct()
