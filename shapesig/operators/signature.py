"""Shape signatures: for each slot, the ordinal of the first shared point inside the shape.

Four forms give the same values: ``arrow`` (row-local, stops at the first hit;
for production), ``sql`` (range join and parity count; the reference), ``expr``
(array functions only) and ``grid`` (points keyed by cell, an equi-join).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shapesig.functions import geometry as G
from shapesig.functions.draws import samples
from shapesig.functions.kernels import SLOTS_PER_BAND, first_hits, first_hits_of, inside, points
from shapesig.operators.prepare import Frame, edges

CAP = 4096


def slots_of(m: int, bands: int = 2) -> list[int]:
    if not 1 <= m <= SLOTS_PER_BAND:
        raise ValueError(f"signature length must be 1 to {SLOTS_PER_BAND}")
    return [b * SLOTS_PER_BAND + i for b in range(bands) for i in range(m)]


def _flat(ring: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Coordinates of all rings in a row, and the number of vertices of each."""
    flat = ring.flatten()
    x, y = (np.asarray(flat.field(k)).astype(np.int64) for k in (0, 1))
    return x, y, np.diff(np.asarray(ring.offsets).astype(np.int64))


def _xy(ring: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    x, y, size = _flat(ring)
    ends = np.cumsum(size)
    for a, b in zip(ends - size, ends, strict=True):
        yield x[a:b], y[a:b]


def first_hit(poly: DataFrame, frame: Frame, slots: list[int], cap: int | None = CAP, base_seed: int = 42, precheck: bool = True, form: str = "arrow") -> DataFrame:
    """(pid, slot, h) in long form; h is null where no point up to ``cap`` falls in the shape.

    ``arrow`` takes None for no cap: it draws until every slot is hit. The other forms join with a table of points and need one.
    """
    if cap is None and form != "arrow":
        raise ValueError(f"the form {form} needs a cap")
    return {"arrow": first_hit_arrow, "sql": first_hit_sql, "expr": first_hit_expr, "grid": first_hit_grid}[form](poly, frame, slots, cap, base_seed, precheck)


def first_hit_arrow(poly: DataFrame, frame: Frame, slots: list[int], cap: int | None = None, base_seed: int = 42, precheck: bool = True) -> DataFrame:
    key, wanted = frame.key, tuple(slots)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            h = first_hits_of(*_flat(batch.column(1)), key, wanted, cap, base_seed, precheck)
            pids = np.repeat(np.asarray(batch.column(0)), len(wanted))
            flat = h.reshape(-1)
            yield pa.RecordBatch.from_arrays([pa.array(pids), pa.array(np.tile(np.array(wanted, np.int32), len(h))), pa.array(flat.astype(np.int32), mask=flat == 0)], ["pid", "slot", "h"])

    return poly.select("pid", "ring").mapInArrow(run, "pid long, slot int, h int")


def first_hit_sql(poly: DataFrame, frame: Frame, slots: list[int], cap: int = CAP, base_seed: int = 42, precheck: bool = True) -> DataFrame:
    points = F.broadcast(samples(poly.sparkSession, frame, slots, 1, cap, base_seed))  # slots x cap rows, parameters both
    near = (F.col("px") > F.col("box.xmin")) & (F.col("px") < F.col("box.xmax")) & (F.col("py") > F.col("box.ymin")) & (F.col("py") < F.col("box.ymax"))
    met = poly.select("pid", "box").join(points, near) if precheck else poly.select("pid").crossJoin(points)
    return _parity(met.select("pid", "slot", "attempt", "px", "py"), poly, slots)


def contained(poly: DataFrame, points: DataFrame) -> DataFrame:
    """(pid, slot, attempt) of the points (slot, attempt, px, py) inside each shape."""
    near = (F.col("px") > F.col("box.xmin")) & (F.col("px") < F.col("box.xmax")) & (F.col("py") > F.col("box.ymin")) & (F.col("py") < F.col("box.ymax"))
    return _inside(poly.select("pid", "box").join(points, near).select("pid", "slot", "attempt", "px", "py"), poly).select("pid", "slot", "attempt")


def holding(poly: DataFrame, frame: Frame, slot: int, last: int, base_seed: int = 42) -> DataFrame:
    """(pid, attempts): which of a slot's first points lie inside each shape; ``contained`` row by row, without a join."""
    key = frame.key

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        px, py = (v[0] for v in points(key, (slot,), 1, last, base_seed))
        for batch in batches:
            held = [np.flatnonzero(inside(x, y, px, py)) + 1 for x, y in _xy(batch.column(1))]
            ends = np.cumsum([0, *map(len, held)]).astype(np.int32)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([np.zeros(0, np.int64), *held]).astype(np.int32)))], ["pid", "attempts"])

    return poly.select("pid", "ring").mapInArrow(run, "pid long, attempts array<int>")


def _inside(met: DataFrame, poly: DataFrame) -> DataFrame:
    e = edges(poly)
    crossing = ((F.col("y1") > F.col("py")) != (F.col("y2") > F.col("py"))) & (((F.col("x2") - F.col("x1")) * (F.col("py") - F.col("y1")) - (F.col("y2") - F.col("y1")) * (F.col("px") - F.col("x1"))) * F.when(F.col("y2") > F.col("y1"), 1).otherwise(-1) > 0)
    return met.join(e, "pid").where(crossing).groupBy("pid", "slot", "attempt").agg((F.count(F.lit(1)) % 2).alias("odd")).where("odd = 1")


def _parity(met: DataFrame, poly: DataFrame, slots: list[int]) -> DataFrame:
    hits = _inside(met, poly).groupBy("pid", "slot").agg(F.min("attempt").alias("h"))
    every = poly.select("pid", F.explode(F.array(*map(F.lit, slots))).alias("slot"))
    return every.join(hits, ["pid", "slot"], "left").select("pid", "slot", F.col("h").cast("int").alias("h"))


def first_hit_expr(poly: DataFrame, frame: Frame, slots: list[int], cap: int = CAP, base_seed: int = 42, precheck: bool = True) -> DataFrame:
    spark = poly.sparkSession
    lists = samples(spark, frame, slots, 1, cap, base_seed).groupBy("slot").agg(F.array_sort(F.collect_list(F.struct("attempt", "px", "py"))).alias("points"))
    met = poly.select("pid", "ring", "box").crossJoin(F.broadcast(lists))
    box = F.col("box")

    def hit(p):
        near = (p["px"] > box["xmin"]) & (p["px"] < box["xmax"]) & (p["py"] > box["ymin"]) & (p["py"] < box["ymax"])
        return F.when(near, G.contains(F.col("ring"), p["px"], p["py"])).otherwise(False) if precheck else G.contains(F.col("ring"), p["px"], p["py"])

    return met.select("pid", "slot", F.array_min(F.transform(F.filter("points", hit), lambda p: p["attempt"])).cast("int").alias("h"))


def first_hit_grid(poly: DataFrame, frame: Frame, slots: list[int], cap: int = CAP, base_seed: int = 42, precheck: bool = True, cells: int = 16) -> DataFrame:
    """Points by cell of the frame, shapes by the cells of their box: a hash join on the cell instead of a range join."""
    wide, high = max(1, -(-(frame.xmax - frame.xmin) // cells)), max(1, -(-(frame.ymax - frame.ymin) // cells))

    def cell(v, low: int, size: int):
        return F.floor((v - low) / size).cast("int")

    points = samples(poly.sparkSession, frame, slots, 1, cap, base_seed).withColumn("gx", cell(F.col("px"), frame.xmin, wide)).withColumn("gy", cell(F.col("py"), frame.ymin, high))
    spread = poly.select("pid", "box", F.explode(F.sequence(cell(F.col("box.xmin"), frame.xmin, wide), cell(F.col("box.xmax"), frame.xmin, wide))).alias("gx")).select("*", F.explode(F.sequence(cell(F.col("box.ymin"), frame.ymin, high), cell(F.col("box.ymax"), frame.ymin, high))).alias("gy"))
    near = (F.col("px") > F.col("box.xmin")) & (F.col("px") < F.col("box.xmax")) & (F.col("py") > F.col("box.ymin")) & (F.col("py") < F.col("box.ymax"))
    return _parity(spread.join(F.broadcast(points), ["gx", "gy"]).where(near).select("pid", "slot", "attempt", "px", "py"), poly, slots)


def wide(hits: DataFrame) -> DataFrame:
    """(pid, sig): the values of all slots in slot order, nulls kept."""
    return hits.groupBy("pid").agg(F.transform(F.array_sort(F.collect_list(F.struct("slot", "h"))), lambda s: s["h"]).alias("sig"))


def signature(poly: DataFrame, frame: Frame, m: int, bands: int = 2, cap: int | None = None, base_seed: int = 42, rounds: int = 1, unresolved: str = "null") -> DataFrame:
    """(pid, sig array<int>) with ``bands`` times ``m`` values, made row by row without a shuffle.

    Without a ``cap`` points are drawn until every slot is hit, so that every shape
    lies in every band. ``unresolved``: slots that a cap leaves open stay null (``null``), are tried in ``rounds`` more caps of four times the size (``extend``), or get
    the value 0, a bucket of their own (``own_bucket``).
    """
    key, wanted = frame.key, tuple(slots_of(m, bands))
    last = cap if cap is None or unresolved != "extend" else cap * 4**rounds

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            h = first_hits_of(*_flat(batch.column(1)), key, wanted, last, base_seed)
            flat = pa.array(h.reshape(-1).astype(np.int32), mask=(h.reshape(-1) == 0) & (unresolved != "own_bucket"))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(pa.array(np.arange(len(h) + 1, dtype=np.int32) * len(wanted)), flat)], ["pid", "sig"])

    return poly.select("pid", "ring").mapInArrow(run, "pid long, sig array<int>")


def attempt_costs(poly: DataFrame, frame: Frame, slots: list[int], cap: int | None = None, base_seed: int = 42, precheck: bool = True) -> DataFrame:
    """(pid, attempts, tests): points drawn and inside tests done for all slots."""
    key, wanted = frame.key, tuple(slots)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for x, y in _xy(batch.column(1)):
                seen = [0, 0]
                first_hits(x, y, key, wanted, cap, base_seed, precheck, seen)
                out.append(seen)
            a = np.array(out, np.int64).reshape(-1, 2)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(a[:, 0]), pa.array(a[:, 1])], ["pid", "attempts", "tests"])

    return poly.select("pid", "ring").mapInArrow(run, "pid long, attempts long, tests long")
