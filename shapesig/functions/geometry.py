"""Ring expressions that stay in the JVM.

A ring is ``array<struct<x: bigint, y: bigint>>``, open, on even lattice numbers.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

RING = "array<struct<x:bigint,y:bigint>>"


def turned(ring: Column) -> Column:
    """The ring begun at its second vertex: pairs with ``ring`` give the edges."""
    return F.concat(F.slice(ring, 2, F.greatest(F.size(ring) - 1, F.lit(0))), F.slice(ring, 1, 1))


def _sum(values: Column) -> Column:
    return F.aggregate(values, F.lit(0).cast("bigint"), lambda a, v: a + v)


def _total(items: Column, field: str) -> Column:
    return _sum(F.transform(items, lambda p: p[field]))


def _moment(pairs: Column, field: str) -> Column:
    return _sum(F.transform(pairs, lambda e: e["c"] * e[field]))


def cross(p: Column, q: Column) -> Column:
    return p["x"] * q["y"] - q["x"] * p["y"]


def area2(ring: Column) -> Column:
    """Twice the signed area: positive counter-clockwise."""
    return _sum(F.zip_with(ring, turned(ring), cross))


def axis_min(ring: Column, axis: str) -> Column:
    return F.array_min(F.transform(ring, lambda p: p[axis]))


def axis_max(ring: Column, axis: str) -> Column:
    return F.array_max(F.transform(ring, lambda p: p[axis]))


def box(ring: Column) -> Column:
    return F.struct(*(f(ring, a).alias(f"{a}{n}") for a in "xy" for f, n in ((axis_min, "min"), (axis_max, "max"))))


def shift(ring: Column, dx: Column, dy: Column) -> Column:
    return F.transform(ring, lambda p: F.struct((p["x"] + dx).alias("x"), (p["y"] + dy).alias("y")))


def scale_percent(ring: Column, percent: Column) -> Column:
    """The ring scaled about its box minimum by an integer percentage, on the even lattice."""
    x0, y0 = axis_min(ring, "x"), axis_min(ring, "y")

    def at(v: Column, low: Column) -> Column:
        return 2 * F.floor((v - low) * percent / F.lit(200)).cast("bigint")

    return F.transform(ring, lambda p: F.struct(at(p["x"], x0).alias("x"), at(p["y"], y0).alias("y")))


def centroid(ring: Column, kind: str = "area") -> Column:
    """The centre, floored to the even lattice, of a ring with minimum 0 on both axes.

    ``kind``: ``area`` (of mass), ``vertex`` (mean), ``box`` (middle) or ``none``
    (the origin of the coordinates as given).
    """
    if kind == "box":
        return F.struct(*((2 * F.floor(axis_max(ring, a) / 4).cast("bigint")).alias(a) for a in "xy"))
    if kind == "vertex":
        return F.struct(*((2 * F.floor(_total(ring, a) / (2 * F.size(ring))).cast("bigint")).alias(a) for a in "xy"))
    pair = F.zip_with(ring, turned(ring), lambda p, q: F.struct(cross(p, q).alias("c"), (p["x"] + q["x"]).alias("x"), (p["y"] + q["y"]).alias("y")))
    total = _total(pair, "c")
    return F.struct(*(F.when(total != 0, 2 * F.call_function("div", F.abs(_moment(pair, a)), 6 * F.abs(total))).otherwise(F.lit(0)).cast("bigint").alias(a) for a in "xy"))


def perimeter(ring: Column) -> Column:
    side = F.zip_with(ring, turned(ring), lambda p, q: F.sqrt(((p["x"] - q["x"]) * (p["x"] - q["x"]) + (p["y"] - q["y"]) * (p["y"] - q["y"])).cast("double")))
    return F.aggregate(side, F.lit(0.0), lambda a, v: a + v)


def contains(ring: Column, px: Column, py: Column) -> Column:
    """Crossing parity: an edge counts if one end is above the point and the edge passes strictly right of it."""
    crossing = F.zip_with(
        ring,
        turned(ring),
        lambda p, q: ((p["y"] > py) != (q["y"] > py)) & (((q["x"] - p["x"]) * (py - p["y"]) - (q["y"] - p["y"]) * (px - p["x"])) * F.when(q["y"] > p["y"], 1).otherwise(-1) > 0),
    )
    return F.size(F.filter(crossing, lambda c: c)) % 2 == 1


def to_wkt(ring: Column) -> Column:
    closed = F.concat(ring, F.slice(ring, 1, 1))
    return F.concat(F.lit("POLYGON (("), F.array_join(F.transform(closed, lambda p: F.concat_ws(" ", p["x"].cast("string"), p["y"].cast("string"))), ", "), F.lit("))"))
