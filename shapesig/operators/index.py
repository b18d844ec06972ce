"""Bucket tables: shapes keyed by the code of each band of their signature."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shapesig.operators.prepare import Frame


def bucket_index(sig: DataFrame, m: int, bands: int = 2) -> DataFrame:
    """(band, code, key, pid) of (pid, sig); a band with an open slot is left out."""
    length = F.size("sig") / bands
    parts = F.transform(F.sequence(F.lit(0), F.lit(bands - 1)), lambda b: F.struct(b.alias("band"), F.slice("sig", (b * length).cast("int") + 1, m).alias("values")))
    rows = sig.select("pid", F.inline(parts)).where(~F.exists("values", lambda v: v.isNull()))
    code = F.array_join(F.transform("values", lambda v: v.cast("string")), "-")
    return rows.select("band", code.alias("code"), "pid").withColumn("key", F.xxhash64("band", "code"))


#: Rows of query codes that may be broadcast: some 60 MB.
MOST_PROBES = 1_000_000


def candidates(queries: DataFrame, index: DataFrame, exclude_self: bool = True, how: str | None = None) -> DataFrame:
    """Distinct (qid, pid) that share a bucket in some band.

    ``how``: ``broadcast`` the queries' codes, so that the index isn't shuffled, or
    join by ``shuffle_hash`` or ``merge``, for which both sides are hashed. By default
    the codes are counted, up to ``MOST_PROBES``, and broadcast only if they are fewer.
    """
    q = queries.select("band", "key", F.col("code").alias("qcode"), F.col("pid").alias("qid"))
    if how is None:
        how = "broadcast" if q.limit(MOST_PROBES + 1).count() <= MOST_PROBES else "merge"
    met = index.join(q.hint(how), ["band", "key"]).where(F.col("code") == F.col("qcode"))
    if exclude_self:
        met = met.where(F.col("qid") != F.col("pid"))
    return met.select("qid", "pid").distinct()


def save(index: DataFrame, frame: Frame, path: str, files: int = 64) -> None:
    """Write an index and its frame: one folder a band, each file a range of keys, so that probes skip by key."""
    index.repartitionByRange(files, "band", "key").sortWithinPartitions("band", "key").write.mode("overwrite").partitionBy("band").parquet(f"{path}/buckets")
    spark = index.sparkSession
    spark.createDataFrame([(frame.to_json(),)], "frame string").coalesce(1).write.mode("overwrite").json(f"{path}/frame")


def load(spark: SparkSession, path: str) -> tuple[DataFrame, Frame]:
    return spark.read.parquet(f"{path}/buckets"), Frame.from_json(spark.read.json(f"{path}/frame").first()["frame"])


def bucket_stats(index: DataFrame) -> DataFrame:
    """Per band: buckets, entries, the largest bucket and its share."""
    sizes = index.groupBy("band", "code").agg(F.count(F.lit(1)).alias("cnt"))
    return sizes.groupBy("band").agg(F.count(F.lit(1)).alias("buckets"), F.sum("cnt").alias("entries"), F.max("cnt").alias("largest"), F.round(F.max("cnt") / F.sum("cnt"), 6).alias("largest_share"))
