"""Functions, table functions and views for SQL users."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from shapesig.functions import kernels as K
from shapesig.operators import index as ix
from shapesig.operators import prepare as P
from shapesig.operators.signature import signature, slots_of
from shapesig.sources import layers


def _arrays(ring) -> tuple[np.ndarray, np.ndarray]:
    return np.array([p["x"] for p in ring], np.int64), np.array([p["y"] for p in ring], np.int64)


@F.pandas_udf(T.DoubleType())
def ring_area(ring: pd.Series) -> pd.Series:
    return pd.Series(K.Rings.of(list(ring)).area)


@F.pandas_udf(T.DoubleType())
def ring_jaccard(a: pd.Series, b: pd.Series) -> pd.Series:
    """Area Jaccard similarity of two rings as placed."""
    return pd.Series([1 - float(K.distances(K.Rings.of([x]), K.Rings.of([y]))[0]) for x, y in zip(a, b, strict=True)])


@F.pandas_udf(T.BooleanType())
def ring_contains(ring: pd.Series, px: pd.Series, py: pd.Series) -> pd.Series:
    return pd.Series([bool(K.inside(*_arrays(r), np.array([x], np.int64), np.array([y], np.int64))[0]) for r, x, y in zip(ring, px, py, strict=True)])


def ring_signature(frame: P.Frame, m: int, bands: int = 2, cap: int | None = None):
    """A column function ring -> array<int> under a frame."""
    key, slots = frame.key, tuple(slots_of(m, bands))

    @F.pandas_udf("array<int>")
    def run(ring: pd.Series) -> pd.Series:
        return pd.Series([[int(h) or None for h in K.first_hits(*_arrays(r), key, slots, cap)] for r in ring])

    return run


class SamplePoints:
    """sample_points(xmin, xmax, ymin, ymax, slots, attempts): the shared points of slots 0 to slots - 1."""

    def eval(self, xmin: int, xmax: int, ymin: int, ymax: int, slots: int, attempts: int) -> Iterator[tuple]:
        px, py = K.points((xmin, xmax, ymin, ymax), tuple(range(slots)), 1, attempts)
        for s in range(slots):
            for a in range(attempts):
                yield s, a + 1, int(px[s, a]), int(py[s, a])


class Probe:
    """probe(sig, bands): a signature's bucket codes."""

    def eval(self, sig: list, bands: int) -> Iterator[tuple]:
        m = len(sig) // bands
        for b in range(bands):
            part = sig[b * m : (b + 1) * m]
            if all(h is not None for h in part):
                yield b, "-".join(map(str, part))


def register(spark: SparkSession) -> None:
    spark.udf.register("ring_area", ring_area)
    spark.udf.register("ring_jaccard", ring_jaccard)
    spark.udf.register("ring_contains", ring_contains)
    spark.udtf.register("sample_points", F.udtf(SamplePoints, returnType="slot int, attempt int, px long, py long"))
    spark.udtf.register("probe", F.udtf(Probe, returnType="band int, code string"))


def views(spark: SparkSession, sf_dir: str, name: str, m: int = 3, bands: int = 2) -> P.Frame:
    """Temporary views v_<layer>, v_<layer>_sig and v_<layer>_index, and their frame."""
    poly = layers.build(spark, sf_dir, name)
    frame = P.global_frame(poly)
    sig = signature(poly, frame, m, bands)
    for df, tail in ((poly, ""), (sig, "_sig"), (ix.bucket_index(sig, m, bands), "_index")):
        df.createOrReplaceTempView(f"v_{name}{tail}")
    return frame


__all__ = ["Probe", "SamplePoints", "register", "ring_area", "ring_contains", "ring_jaccard", "ring_signature", "views"]
