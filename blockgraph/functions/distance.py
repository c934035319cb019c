"""Distances between vector columns as built-in expressions, and in numpy.

Every metric is in the form that smaller is closer: ``ip`` is the negated
inner product. Vectors are ARRAY<DOUBLE>; float columns are cast first.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

METRICS = ("l2", "l2sq", "ip", "cosine")


def _sum(parts: Column) -> Column:
    return F.aggregate(parts, F.lit(0.0), lambda s, x: s + x)


def dot(a: Column, b: Column) -> Column:
    return _sum(F.zip_with(a, b, lambda x, y: x * y))


def l2sq(a: Column, b: Column) -> Column:
    return _sum(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)))


def l2(a: Column, b: Column) -> Column:
    return F.sqrt(l2sq(a, b))


def neg_ip(a: Column, b: Column) -> Column:
    return -dot(a, b)


def cosine(a: Column, b: Column) -> Column:
    return F.lit(1.0) - dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


def distance(a: Column, b: Column, metric: str) -> Column:
    return {"l2": l2, "l2sq": l2sq, "ip": neg_ip, "cosine": cosine}[metric](a, b)


def pairwise(x: np.ndarray, y: np.ndarray, metric: str) -> np.ndarray:
    """Distances of all rows of x to all rows of y, in double precision and in
    direct form, so that equal vectors have distance 0 exactly."""
    x, y = np.atleast_2d(np.asarray(x, float)), np.atleast_2d(np.asarray(y, float))
    if metric == "ip":
        return -(x @ y.T)
    if metric == "cosine":
        return 1 - (x @ y.T) / np.sqrt((x * x).sum(1)[:, None] * (y * y).sum(1)[None, :])
    out = np.empty((len(x), len(y)))
    step = max(1, 4_000_000 // max(1, y.size))
    for i in range(0, len(x), step):
        d = x[i : i + step, None, :] - y[None, :, :]
        out[i : i + step] = np.einsum("ijk,ijk->ij", d, d)
    return np.sqrt(out) if metric == "l2" else out
