"""Product quantisation: train, encode, distance tables."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kmeans


def sub_slices(dim: int, n_sub: int) -> list[slice]:
    edge = [dim * i // n_sub for i in range(n_sub + 1)]
    return [slice(a, b) for a, b in zip(edge, edge[1:])]


def sub_count_for_budget(budget_bytes: float, n: int, dim: int) -> int:
    """One byte a code: as many subspaces as the budget has bytes a vector."""
    return max(1, min(dim, int(budget_bytes // max(n, 1))))


def train_local(x: np.ndarray, n_sub: int, n_codes: int = 256, iters: int = 8, seed: int = 7) -> list[np.ndarray]:
    from .layout import _lloyd

    out = []
    for s in sub_slices(x.shape[1], n_sub):
        part = np.asarray(x[:, s], float)
        if len(part) <= n_codes:
            out.append(part.copy())
            continue
        a, _ = _lloyd(part, n_codes, iters, seed)
        k = a.max() + 1
        out.append(np.array([part[a == j].mean(0) if (a == j).any() else part[0] for j in range(k)]))
    return out


def encode_local(x: np.ndarray, book: list[np.ndarray]) -> np.ndarray:
    """n x n_sub bytes; ties go to the lowest code."""
    out = np.zeros((len(x), len(book)), np.uint8)
    for m, (s, c) in enumerate(zip(sub_slices(x.shape[1], len(book)), book)):
        if len(x) and len(c):
            step = max(1, 2_000_000 // max(1, c.size))
            for i in range(0, len(x), step):
                d = x[i : i + step, s]
                out[i : i + step, m] = ((d[:, None, :] - c[None]) ** 2).sum(2).argmin(1)
    return out


def lookup(q: np.ndarray, book: list[np.ndarray], metric: str) -> np.ndarray:
    """Part distances of a query to every code: n_sub x codes; their sum over
    a vector's codes orders like the metric (squared for l2)."""
    out = np.full((len(book), max(map(len, book))), np.inf)
    for m, (s, c) in enumerate(zip(sub_slices(len(q), len(book)), book)):
        out[m, : len(c)] = -(c @ q[s]) if metric in ("ip", "cosine") else ((c - q[s]) ** 2).sum(1)
    return out


def train(base: DataFrame, n_sub: int, n_codes: int, iters: int, dim: int) -> DataFrame:
    """(sub, code, centroid) by k-means in each subspace over a whole table."""
    out = None
    for m, s in enumerate(sub_slices(dim, n_sub)):
        part = base.select("vec_id", F.slice("vec", s.start + 1, s.stop - s.start).alias("vec"))
        c = kmeans.fit(part, n_codes, iters)
        got = base.sparkSession.createDataFrame([(m, i, row.tolist()) for i, row in enumerate(c)], "sub int, code int, centroid array<double>")
        out = got if out is None else out.unionAll(got)
    return out


def encoder(spark, book: list[np.ndarray]):
    """encode as a scalar function of a vector column, over iterators of
    batches: the codebook is taken up once for each task."""
    sent = spark.sparkContext.broadcast(book)

    @F.pandas_udf("binary")
    def codes(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        book = sent.value
        for x in batches:
            yield pd.Series([r.tobytes() for r in encode_local(np.array(x.tolist(), float).reshape(len(x), -1), book)], dtype=object)

    return codes


def encode(base: DataFrame, book: list[np.ndarray]) -> DataFrame:
    """(vec_id, codes binary)."""
    sent = base.sparkSession.sparkContext.broadcast(book)  # n_sub x codes x part: fixed by parameters

    def run(batches):
        for b in batches:
            if len(b):
                yield pd.DataFrame({"vec_id": b["vec_id"], "codes": [r.tobytes() for r in encode_local(np.array(b["vec"].tolist(), float), sent.value)]})

    return base.select("vec_id", "vec").mapInPandas(run, "vec_id long, codes binary")
