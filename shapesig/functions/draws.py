"""The shared sample points as a DataFrame: each draw depends on its key alone."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from shapesig.operators.prepare import Frame


def uniform(base: int, slot: Column, axis: str, attempt: Column) -> Column:
    text = F.concat_ws(":", F.lit(str(base)), slot.cast("string"), F.lit(axis), attempt.cast("string"))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("bigint")


def coordinate(u: Column, low: int, high: int) -> Column:
    return F.lit(low).cast("bigint") + 2 * F.shiftright(u * F.lit((high - low) // 2).cast("bigint"), 32) + 1


def samples(spark: SparkSession, frame: Frame, slots: list[int], first: int, last: int, base_seed: int = 42) -> DataFrame:
    """(slot, attempt, px, py) for attempts ``first..last`` of each slot; rows are slots times attempts, a parameter."""
    per = last - first + 1
    ids = spark.range(len(slots) * per)
    slot = F.element_at(F.array(*map(F.lit, slots)), (F.col("id") / per).cast("int") + 1)
    rows = ids.select(slot.alias("slot"), (F.col("id") % per + first).cast("int").alias("attempt"))
    return rows.select("slot", "attempt", coordinate(uniform(base_seed, F.col("slot"), "x", F.col("attempt")), frame.xmin, frame.xmax).alias("px"), coordinate(uniform(base_seed, F.col("slot"), "y", F.col("attempt")), frame.ymin, frame.ymax).alias("py"))
