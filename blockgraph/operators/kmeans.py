"""Lloyd's k-means over a distributed table of vectors."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import mixed


def start(points: DataFrame, k: int) -> np.ndarray:
    """k rows in hash order of their ids."""
    return np.array([r.vec for r in points.select("vec", mixed(F.col("vec_id")).alias("h"), "vec_id").orderBy("h", "vec_id").limit(k).collect()], float)


def assign_local(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Nearest centroid, ties to the lowest, direct distances."""
    out = np.empty(len(x), np.int64)
    step = max(1, 2_000_000 // max(1, c.size))
    for i in range(0, len(x), step):
        d = x[i : i + step, None, :] - c[None]
        out[i : i + step] = np.einsum("ijk,ijk->ij", d, d).argmin(1)
    return out


def step(points: DataFrame, c: np.ndarray) -> np.ndarray:
    """One round: every partition sends k sums, never its points. A cluster
    without points keeps its centroid."""
    sent = points.sparkSession.sparkContext.broadcast(c)

    def run(batches):
        c = sent.value
        total, n = np.zeros(c.shape), np.zeros(len(c), np.int64)
        for b in batches:
            if len(b):
                x = np.array(b["vec"].tolist(), float)
                a = assign_local(x, c)
                np.add.at(total, a, x)
                n += np.bincount(a, minlength=len(c))
        hit = np.flatnonzero(n)
        if len(hit):  # a partition may hold no rows
            yield pd.DataFrame({"cluster": hit, "total": [total[i].tolist() for i in hit], "n": n[hit]})

    parts = points.select("vec").mapInPandas(run, "cluster long, total array<double>, n long")
    dim = c.shape[1]
    sums = parts.groupBy("cluster").agg(F.sum("n").alias("n"), *(F.sum(F.get("total", F.lit(i))).alias(f"s{i}") for i in range(dim))).collect()
    out = c.copy()
    for r in sums:
        out[r.cluster] = np.array([r[f"s{i}"] for i in range(dim)]) / r.n
    return out


def fit(points: DataFrame, k: int, iters: int = 8) -> np.ndarray:
    c = start(points, k)
    for _ in range(iters):
        new = step(points, c)
        if np.allclose(new, c, atol=1e-12):
            break
        c = new
    return c
