"""Validation, centring, local boxes and the frame that all shapes share."""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import asdict, dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from shapesig.functions import geometry as G
from shapesig.functions.kernels import centred_rings


@dataclass(frozen=True)
class Frame:
    """The rectangle in which points are drawn; stored with an index, so that later shapes hash alike."""

    xmin: int
    xmax: int
    ymin: int
    ymax: int

    @property
    def area(self) -> int:
        return (self.xmax - self.xmin) * (self.ymax - self.ymin)

    @property
    def key(self) -> tuple[int, int, int, int]:
        return (self.xmin, self.xmax, self.ymin, self.ymax)

    def to_json(self) -> str:
        return json.dumps(asdict(self))

    @staticmethod
    def from_json(text: str) -> Frame:
        return Frame(**json.loads(text))


def distinct_vertices(df: DataFrame) -> DataFrame:
    """Rings without a repeated closing vertex or repeated neighbours."""
    ring = F.col("ring")
    open_ring = F.when((F.size(ring) > 1) & (F.element_at(ring, 1) == F.element_at(ring, -1)), F.slice(ring, 1, F.size(ring) - 1)).otherwise(ring)
    return df.withColumn("ring", open_ring)


def validate(df: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Usable rings, and the rest with the reason: null, fewer than 3 distinct vertices, or no area."""
    opened = distinct_vertices(df)
    reason = F.when(F.col("ring").isNull(), "null ring").when(F.size(F.array_distinct("ring")) < 3, "fewer than 3 vertices").when(G.area2(F.col("ring")) == 0, "zero area")
    told = opened.withColumn("reason", reason)
    return told.where("reason IS NULL").drop("reason"), told.where("reason IS NOT NULL").select("pid", "reason")


def center(df: DataFrame, kind: str = "area") -> DataFrame:
    """Rings moved so that their centre is the origin, with ``area2``, the centre, the local box; row by row.

    Coordinates are first taken from the ring's own box minimum, so copies of a
    shape that lie elsewhere give the same centred ring.
    """
    if kind == "none":
        placed = df.withColumn("cx", F.lit(0).cast("bigint")).withColumn("cy", F.lit(0).cast("bigint"))
    else:
        low = df.withColumn("x0", G.axis_min(F.col("ring"), "x")).withColumn("y0", G.axis_min(F.col("ring"), "y"))
        low = low.withColumn("ring", G.shift(F.col("ring"), -F.col("x0"), -F.col("y0"))).withColumn("c", G.centroid(F.col("ring"), kind))
        placed = low.withColumn("ring", G.shift(F.col("ring"), -F.col("c.x"), -F.col("c.y"))).withColumn("cx", F.col("x0") + F.col("c.x")).withColumn("cy", F.col("y0") + F.col("c.y")).drop("x0", "y0", "c")
    return placed.withColumn("area2", F.abs(G.area2(F.col("ring")))).withColumn("box", G.box(F.col("ring")))


def global_frame(*layers: DataFrame, pad: int = 0) -> Frame:
    """The rectangle round all local boxes; four numbers come to the driver."""
    boxes = reduce(DataFrame.unionByName, (x.select("box") for x in layers))
    r = boxes.agg(F.min("box.xmin").alias("xmin"), F.max("box.xmax").alias("xmax"), F.min("box.ymin").alias("ymin"), F.max("box.ymax").alias("ymax")).first()
    if r["xmin"] is None:
        return Frame(-2, 2, -2, 2)
    return Frame(r["xmin"] - 2 * pad, r["xmax"] + 2 * pad, r["ymin"] - 2 * pad, r["ymax"] + 2 * pad)


def out_of_frame(df: DataFrame, frame: Frame) -> DataFrame:
    """Prepared shapes that a frozen frame doesn't enclose."""
    return df.where((F.col("box.xmin") < frame.xmin) | (F.col("box.xmax") > frame.xmax) | (F.col("box.ymin") < frame.ymin) | (F.col("box.ymax") > frame.ymax))


def with_sparsity(df: DataFrame, frame: Frame) -> DataFrame:
    """The chance that a point of the frame falls in the shape."""
    return df.withColumn("sparsity", F.col("area2") / F.lit(2.0 * frame.area))


PREPARED = f"pid long, ring {G.RING}, cx long, cy long, area2 long, box struct<xmin:long,xmax:long,ymin:long,ymax:long>"
_RING = pa.list_(pa.struct([("x", pa.int64()), ("y", pa.int64())]))


def prepare(df: DataFrame, kind: str = "area") -> DataFrame:
    """(pid, ring, cx, cy, area2, box) of the valid rings, centred: ``validate`` and ``center`` in one pass over flat arrays.

    The same as ``center(validate(df)[0])`` on every ring; array functions are
    interpreted per element, this is not. Other columns are not carried.
    """
    if kind != "area":
        c = center(validate(df)[0], kind)
        return c.select("pid", "ring", "cx", "cy", "area2", "box")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            batch = batch.filter(batch.column(1).is_valid())
            ring = batch.column(1)
            size = np.diff(np.asarray(ring.offsets).astype(np.int64))
            flat = ring.flatten()
            x, y = (np.asarray(flat.field(k)).astype(np.int64) for k in (0, 1))
            ok, out_x, out_y, n, cx, cy, area2, box = centred_rings(x, y, size)
            points = pa.StructArray.from_arrays([pa.array(out_x), pa.array(out_y)], ["x", "y"])
            rings = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(n)]).astype(np.int32)), points)
            boxes = pa.StructArray.from_arrays([pa.array(c) for c in box], ["xmin", "xmax", "ymin", "ymax"])
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(pa.array(ok)), rings, pa.array(cx), pa.array(cy), pa.array(area2), boxes], ["pid", "ring", "cx", "cy", "area2", "box"])

    return df.select("pid", "ring").mapInArrow(run, PREPARED)


def edges(df: DataFrame) -> DataFrame:
    """(pid, idx, x1, y1, x2, y2): the relational view of rings."""
    def edge(p: Column, q: Column) -> Column:
        return F.struct(p["x"].alias("x1"), p["y"].alias("y1"), q["x"].alias("x2"), q["y"].alias("y2"))

    e = df.select("pid", F.posexplode(F.zip_with("ring", G.turned(F.col("ring")), edge)).alias("idx", "e"))
    return e.select("pid", "idx", "e.*")
