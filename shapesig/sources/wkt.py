"""Rings as well-known text, well-known binary and GeoJSON, by JVM expressions where they can express it."""

from __future__ import annotations

import struct
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from shapesig.functions import geometry as G

_PAIR = r"([-+0-9.eE]+)\s+([-+0-9.eE]+)"


def format_rings(df: DataFrame) -> DataFrame:
    """(pid, wkt), closed rings of whole numbers."""
    return df.select("pid", G.to_wkt(F.col("ring")).alias("wkt"))


def ring_of(text: Column, scale: float = 1.0) -> Column:
    """The outer ring of POLYGON text as an open ring on the even lattice, null if it is none (a multipolygon or malformed)."""
    body = F.regexp_extract(text, r"(?i)^\s*POLYGON\s*\(\s*\(([^()]*)\)", 1)
    points = F.transform(F.split(body, ","), lambda p: F.split(F.trim(p), r"\s+"))
    ring = F.transform(points, lambda p: F.struct(*((2 * F.round(F.get(p, F.lit(i)).try_cast("double") * scale / 2).cast("bigint")).alias(a) for i, a in enumerate("xy"))))
    n = F.size(ring)
    opened = F.when((n > 1) & (F.element_at(ring, 1) == F.element_at(ring, -1)), F.slice(ring, 1, n - 1)).otherwise(ring)
    bad = F.exists(ring, lambda p: p["x"].isNull() | p["y"].isNull())
    return F.when((body != "") & ~bad, opened)


def parse(df: DataFrame, column: str = "wkt", scale: float = 1.0) -> DataFrame:
    """All columns and ``ring``; null where the text holds no single polygon."""
    return df.withColumn("ring", ring_of(F.col(column), scale))


def read_wkt(spark: SparkSession, path: str, sep: str = "\t", column: int = 1, scale: float = 1.0) -> tuple[DataFrame, DataFrame]:
    """(pid, ring) of delimited text whose first field is the id, and the rejected lines with a reason."""
    rows = spark.read.text(path).select(F.split("value", sep).alias("f"), "value")
    told = rows.select(F.get("f", F.lit(0)).try_cast("bigint").alias("pid"), ring_of(F.get("f", F.lit(column)), scale).alias("ring"), "value")
    bad = F.when(F.col("pid").isNull(), "no id").when(F.col("ring").isNull(), "no polygon")
    marked = told.withColumn("reason", bad)
    return marked.where("reason IS NULL").select("pid", "ring"), marked.where("reason IS NOT NULL").select("value", "reason")


def to_wkb(df: DataFrame) -> DataFrame:
    """(pid, wkb): little-endian polygons of one closed ring."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for ring in batch.column(1).to_pylist():
                pts = [*ring, ring[0]] if ring else []
                out.append(struct.pack("<BIII", 1, 3, 1, len(pts)) + b"".join(struct.pack("<dd", p["x"], p["y"]) for p in pts))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.binary())], ["pid", "wkb"])

    return df.select("pid", "ring").mapInArrow(run, "pid long, wkb binary")


def from_wkb(df: DataFrame) -> DataFrame:
    """(pid, ring) of polygons in either byte order; other geometries give a null ring."""
    kind = pa.list_(pa.struct([("x", pa.int64()), ("y", pa.int64())]))

    def ring(blob: bytes | None) -> list[dict] | None:
        if not blob or len(blob) < 13:
            return None
        e = "<" if blob[0] == 1 else ">"
        shape, rings, n = struct.unpack_from(f"{e}III", blob, 1)
        if shape != 3 or rings < 1 or len(blob) < 13 + 16 * n:
            return None
        v = struct.unpack_from(f"{e}{2 * n}d", blob, 13)
        pts = [{"x": 2 * round(v[2 * i] / 2), "y": 2 * round(v[2 * i + 1] / 2)} for i in range(n)]
        return pts[:-1] if n > 1 and pts[0] == pts[-1] else pts

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([ring(b) for b in batch.column(1).to_pylist()], kind)], ["pid", "ring"])

    return df.select("pid", "wkb").mapInArrow(run, f"pid long, ring {G.RING}")


def to_geojson(df: DataFrame) -> DataFrame:
    """(pid, geojson)."""
    closed = F.concat("ring", F.slice("ring", 1, 1))
    shape = F.struct(F.lit("Polygon").alias("type"), F.array(F.transform(closed, lambda p: F.array(p["x"], p["y"]))).alias("coordinates"))
    return df.select("pid", F.to_json(shape).alias("geojson"))


def from_geojson(df: DataFrame, column: str = "geojson") -> DataFrame:
    """(pid, ring) of GeoJSON polygons; null for anything else."""
    got = F.from_json(column, "struct<type:string,coordinates:array<array<array<double>>>>")
    ring = F.transform(F.get(got["coordinates"], F.lit(0)), lambda p: F.struct(*((2 * F.round(F.get(p, F.lit(i)) / 2).cast("bigint")).alias(a) for i, a in enumerate("xy"))))
    return df.select("pid", F.when(got["type"] == "Polygon", F.slice(ring, 1, F.greatest(F.size(ring) - 1, F.lit(0)))).alias("ring"))


def from_rows(spark: SparkSession, rings: dict[int, list[tuple[int, int]]]) -> DataFrame:
    """(pid, ring) of rings in memory."""
    return spark.createDataFrame([(k, [(int(x), int(y)) for x, y in r]) for k, r in rings.items()], f"pid long, ring {G.RING}")


def write(df: DataFrame, path: str, fmt: str = "parquet") -> None:
    """Results as Parquet, CSV or JSON."""
    df.write.mode("overwrite").format(fmt).option("header", "true").save(path)
