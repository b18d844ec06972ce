"""Closed forms of first-hit hashing and of banded lookup, as numbers and as columns."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column


def expected_attempts(s):
    """Mean of a first-hit value for a shape that covers share ``s`` of the frame."""
    return 1 / s


def attempt_variance(s):
    return (1 - s) / (s * s)


def collision(j, m: int = 1):
    """Chance that ``m`` slots agree for shapes of similarity ``j``."""
    return j**m


def scurve(j: float, m: int, bands: int) -> float:
    """Chance to meet in at least one of ``bands`` buckets."""
    return 1 - (1 - j**m) ** bands


def unresolved(s: float, cap: int) -> float:
    """Chance that a slot is open after ``cap`` attempts."""
    return (1 - s) ** cap


def scurve_column(j: Column, m: int, bands: int) -> Column:
    from pyspark.sql import functions as F

    return 1 - F.pow(1 - F.pow(j, m), bands)


def predicted(neighbours: Sequence[float], pairs: Sequence[float], m: int, bands: int) -> tuple[float, float]:
    """Recall over true neighbours' similarities, and pruning in percent over random pairs'."""
    n, p = np.asarray(neighbours, float), np.asarray(pairs, float)
    return float(np.mean(1 - (1 - n**m) ** bands)), float(100 * (1 - np.mean(1 - (1 - p**m) ** bands)))


def tune(neighbours: Sequence[float], pairs: Sequence[float], recall: float, lengths: Sequence[int] = range(1, 7), bands: Sequence[int] = (1, 2, 4, 8, 16, 32)) -> tuple[int, int]:
    """(m, bands) that prune most among those predicted to reach the recall; ties by fewer slots."""
    best = None
    for t in bands:
        for m in lengths:
            r, pruned = predicted(neighbours, pairs, m, t)
            if r >= recall and (best is None or (pruned, -m * t) > best[0]):
                best = ((pruned, -m * t), (m, t))
    return best[1] if best else (1, max(bands))


def refine_seconds(pruned_pct: float, brute_seconds: float) -> float:
    """Rough refinement time: the part of brute force that pruning leaves."""
    return (1 - pruned_pct / 100) * brute_seconds


def tests_per_slot(box_area: float, area: float) -> float:
    """Inside tests that follow the box check until the first hit."""
    return box_area / area
