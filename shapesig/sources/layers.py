"""Polygon layers derived from the given tables, each by a fixed rule that SQL can repeat.

Builders: ``star`` (distinct points by angle round their mean), ``hull`` (their
convex hull), ``radial`` (a vector as radii at even angles) and ``box``. Sized
variants scale a ring about its box minimum by an integer percentage.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from shapesig.functions import geometry as G
from shapesig.functions.kernels import radial
from shapesig.operators import prepare as P
from shapesig.session import table

LETTERS = "abcdefghijklmnopqrstuvwx"
ALPHABET = "abcdefghijklmnopqrstuvwxyz"


def _long(c: Column) -> Column:
    return c.cast("bigint")


def _even(c: Column) -> Column:
    return 2 * _long(F.floor(c))


def _days(c: Column, since: str) -> Column:
    return F.datediff(c.cast("date"), F.lit(since).cast("date"))


#: Point layers: table, key, x, y (even numbers).
POINTS: dict[str, tuple[str, Callable[[], tuple[Column, Column, Column]]]] = {
    "cust": ("orders", lambda: (F.col("o_custkey"), 4 * _long(_days(F.col("o_orderdate"), "1995-01-01")), _even(F.col("o_totalprice") / 100))),
    "flag": ("lineitem", lambda: (F.col("l_partkey") * 4 + F.when(F.col("l_returnflag") == "A", 0).when(F.col("l_returnflag") == "N", 1).otherwise(2), _even(F.col("l_quantity") * 40), _even(F.col("l_extendedprice") / 50))),
    "supp": ("lineitem", lambda: (F.col("l_suppkey") * 2 + F.when(F.col("l_linestatus") == "F", 0).otherwise(1), 4 * _long(_days(F.col("l_shipdate"), "1995-01-01")), _even(F.col("l_extendedprice") / 50))),
    "user": ("events", lambda: (F.col("user_id"), 8 * _long(F.hour("ts") * 60 + F.minute("ts")), _even(F.least(F.greatest(F.col("value"), F.lit(0.0)), F.lit(500.0)) * 10))),
    "order": ("lineitem", lambda: (F.col("l_orderkey"), _even(F.col("l_quantity") * 40), _even(F.col("l_extendedprice") / 50))),
    "part": ("lineitem", lambda: (F.col("l_partkey"), _even(F.col("l_quantity") * 40), _even(F.col("l_extendedprice") / 50))),
}

#: Text layers: table, key, text.
TEXTS = {"doc": ("documents", "doc_id", "text"), "page": ("pages", "page_id", "html"), "turn": ("conversations", "conv_id", "text"), "bench": ("benchmark", "item_id", "text")}


def star_rings(points: DataFrame) -> DataFrame:
    """(pid, ring) of (pid, x, y): distinct points by angle round their mean, then distance, x, y; integers but for the angle."""
    sets = points.groupBy("pid").agg(F.collect_set(F.struct("x", "y")).alias("pts"))
    n = F.size("pts")
    total = lambda a: F.aggregate(F.transform("pts", lambda p: p[a]), F.lit(0).cast("bigint"), lambda s, v: s + v)
    held = sets.select("pid", "pts", n.alias("n"), total("x").alias("sx"), total("y").alias("sy"))

    def keyed(p: Column) -> Column:
        dx, dy = F.col("n") * p["x"] - F.col("sx"), F.col("n") * p["y"] - F.col("sy")
        return F.struct(F.round(F.atan2(dy.cast("double"), dx.cast("double")), 9).alias("a"), (dx * dx + dy * dy).alias("r"), p["x"].alias("x"), p["y"].alias("y"))

    return held.select("pid", F.transform(F.array_sort(F.transform("pts", keyed)), lambda k: F.struct(k["x"].alias("x"), k["y"].alias("y"))).alias("ring"))


def _hull(points: list[tuple[int, int]]) -> list[tuple[int, int]]:
    pts = sorted(set(points))
    if len(pts) < 3:
        return pts

    def half(seq: list[tuple[int, int]]) -> list[tuple[int, int]]:
        out: list[tuple[int, int]] = []
        for p in seq:
            while len(out) > 1 and (out[-1][0] - out[-2][0]) * (p[1] - out[-2][1]) - (out[-1][1] - out[-2][1]) * (p[0] - out[-2][0]) <= 0:
                out.pop()
            out.append(p)
        return out[:-1]

    return half(pts) + half(pts[::-1])


def hull_rings(points: DataFrame) -> DataFrame:
    """(pid, ring): the convex hull of each key's points, counter-clockwise from the leftmost."""
    sets = points.groupBy("pid").agg(F.collect_set(F.struct("x", "y")).alias("pts"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rings = [[{"x": x, "y": y} for x, y in _hull([(p["x"], p["y"]) for p in pts])] for pts in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rings, pa.list_(pa.struct([("x", pa.int64()), ("y", pa.int64())])))], ["pid", "ring"])

    return sets.mapInArrow(run, f"pid long, ring {G.RING}")


def _radial_rings(rows: DataFrame, radii: Callable[[pa.RecordBatch], np.ndarray]) -> DataFrame:
    """(pid, ring) from the rows' first column and a matrix of radii made of the others."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            x, y = radial(radii(batch))
            points = pa.StructArray.from_arrays([pa.array(x.reshape(-1)), pa.array(y.reshape(-1))], ["x", "y"])
            ends = (np.arange(len(x) + 1) * x.shape[1]).astype(np.int32)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(pa.array(ends), points)], ["pid", "ring"])

    return rows.mapInArrow(run, f"pid long, ring {G.RING}")


def letter_counts(text: Column) -> list[Column]:
    low = F.lower(F.coalesce(text, F.lit("")))
    return [_long(F.length(low) - F.length(F.replace(low, F.lit(c), F.lit("")))) for c in ALPHABET]


def text_rings(rows: DataFrame, key: str, text: str) -> DataFrame:
    """(pid, ring): shares of the letters a to x among all letters as radii; texts of one key count together."""
    counts = rows.select(F.col(key).alias("pid"), *(c.alias(f"n_{a}") for c, a in zip(letter_counts(F.col(text)), ALPHABET, strict=True)))
    sums = counts.groupBy("pid").agg(*(F.sum(f"n_{a}").alias(f"n_{a}") for a in ALPHABET))

    def radii(batch: pa.RecordBatch) -> np.ndarray:
        n = np.stack([np.asarray(batch.column(i + 1)).astype(np.float64) for i in range(len(ALPHABET))], 1)
        return 400.0 + 3600 * np.sqrt(n[:, : len(LETTERS)] / np.maximum(n.sum(1), 1)[:, None])

    return _radial_rings(sums, radii)


def vector_rings(rows: DataFrame) -> DataFrame:
    """(pid, ring): components as radii; a null vector gives no ring."""

    def radii(batch: pa.RecordBatch) -> np.ndarray:
        v = np.asarray(batch.column(1).flatten()).astype(np.float64).reshape(batch.num_rows, -1)
        return 2000 * np.maximum(0.05, 0.4 + v)

    return _radial_rings(rows.where("embedding IS NOT NULL").select(F.col("vec_id").alias("pid"), "embedding"), radii)


def box_ring(hx: Column, hy: Column) -> Column:
    return F.array(*(F.struct((sx * hx).alias("x"), (sy * hy).alias("y")) for sx, sy in ((-1, -1), (1, -1), (1, 1), (-1, 1))))


def percentages(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(pid, pct) of a sized variant."""
    t = lambda n: table(spark, sf_dir, n)
    pct = lambda v: _long(F.round(v))
    grown = lambda k: pct(100 * F.pow(F.lit(1.1), k))
    if name == "cust_sized":
        return t("customer").select(F.col("c_custkey").alias("pid"), grown(F.col("c_nationkey")).alias("pct"))
    if name == "cust_bal":
        return t("customer").select(F.col("c_custkey").alias("pid"), pct(15 + 85 * F.greatest(F.col("c_acctbal"), F.lit(0.0)) / 10000).alias("pct"))
    if name == "supp_sized":
        return t("supplier").select(F.explode(F.array(F.col("s_suppkey") * 2, F.col("s_suppkey") * 2 + 1)).alias("pid"), grown(F.col("s_nationkey")).alias("pct"))
    if name == "doc_sized":
        return t("documents").select(F.col("doc_id").alias("pid"), pct(100 * F.pow(F.col("n_chars").cast("double"), F.lit(0.25))).alias("pct"))
    return t("embeddings").select(F.col("vec_id").alias("pid"), pct(100 * F.pow(F.lit(1.25), F.col("label"))).alias("pct"))


SIZED = {"cust_sized": "cust", "cust_bal": "cust", "flag_sized": "flag", "supp_sized": "supp", "doc_sized": "doc", "emb_sized": "emb"}
NAMES = (*POINTS, *TEXTS, "emb", "box_part", "box_acct", *SIZED)


def rings(spark: SparkSession, sf_dir: str, name: str, builder: str = "star") -> DataFrame:
    """(pid, ring) of a layer, before validation and centring."""
    if name in SIZED:
        base = rings(spark, sf_dir, SIZED[name], builder)
        if name == "flag_sized":
            return base.withColumn("ring", G.scale_percent(F.col("ring"), _long(F.round(100 * F.pow(F.lit(1.1), F.floor(F.col("pid") / 4) % 25)))))
        return base.join(percentages(spark, sf_dir, name), "pid").select("pid", G.scale_percent(F.col("ring"), F.col("pct")).alias("ring"))
    if name in POINTS:
        source, columns = POINTS[name]
        pid, x, y = columns()
        points = table(spark, sf_dir, source).select(_long(pid).alias("pid"), x.alias("x"), y.alias("y"))
        return hull_rings(points) if builder == "hull" else star_rings(points)
    if name in TEXTS:
        source, key, text = TEXTS[name]
        return text_rings(table(spark, sf_dir, source), key, text)
    if name == "emb":
        return vector_rings(table(spark, sf_dir, "embeddings"))
    if name == "box_part":
        p = table(spark, sf_dir, "part")
        return p.select(F.col("p_partkey").alias("pid"), box_ring(20 * _long(F.col("p_size")), 2 * _long(F.floor((F.col("p_retailprice") - 899) / 2)) + 2).alias("ring"))
    s = table(spark, sf_dir, "supplier").select((F.col("s_suppkey") * 2).alias("pid"), F.col("s_acctbal").alias("bal"))
    c = table(spark, sf_dir, "customer").select((F.col("c_custkey") * 2 + 1).alias("pid"), F.col("c_acctbal").alias("bal"))
    half = 2 * _long(F.floor(F.abs("bal") / 10)) + 2
    return s.unionByName(c).select("pid", box_ring(half, half).alias("ring"))


def build(spark: SparkSession, sf_dir: str, name: str, builder: str = "star", kind: str = "area") -> DataFrame:
    """The prepared layer: valid rings, centred, with area, centre and box."""
    return P.prepare(rings(spark, sf_dir, name, builder), kind)
