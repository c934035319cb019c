"""Exact search: the ground truth of every experiment.

A batch of queries is held against all base rows in blocks. The queries are
packed into rows of bounded size, so what is broadcast is one pack at a time by
its size, and each base partition keeps only its own best k of each query (or
what is inside the radius) before anything is shuffled.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.distance import pairwise
from ..functions.hashing import mixed
from ..session import stored

#: Queries are collected and broadcast in packs of at most this many values.
PACK_VALUES = 4_000_000
#: Distances of a batch that are held at once (16 MB).
TILE_VALUES = 2_000_000
HITS = "query_id long, vec_id long, dist double"


def _packs(queries: DataFrame):
    """Queries in bounded packs of (ids, matrix)."""
    ids, vecs = [], []
    for r in queries.select("query_id", "qvec").toLocalIterator():
        ids.append(r.query_id)
        vecs.append(r.qvec)
        if len(vecs) * len(vecs[0]) >= PACK_VALUES:
            yield np.array(ids, np.int64), np.array(vecs, float)
            ids, vecs = [], []
    if ids:
        yield np.array(ids, np.int64), np.array(vecs, float)


def _nearest(ids: np.ndarray, d: np.ndarray, k: int) -> np.ndarray:
    """Row numbers of the k best by (distance, id)."""
    if len(d) > 4 * k:
        edge = np.partition(d, k - 1)[k - 1]
        near = np.flatnonzero(d <= edge)
        return near[np.lexsort((ids[near], d[near]))[:k]]
    return np.lexsort((ids, d))[:k]


def nearest_each(ids: np.ndarray, x: np.ndarray, q: np.ndarray, k: int, metric: str, digits: int = 6) -> list[tuple[np.ndarray, np.ndarray]]:
    """(rows, distances) of the k best of each query by (rounded distance, id).
    For l2, products of the vectors tell which rows may be among them, with room for
    their rounding, and only these have their distances taken by differences."""
    if metric not in ("l2", "l2sq") or len(ids) <= 4 * k:
        d = np.round(pairwise(q, x, metric), digits) + 0.0
        return [(r, row[r]) for row in d for r in (_nearest(ids, row, k),)]
    size, own = np.einsum("ij,ij->i", x, x), np.einsum("ij,ij->i", q, q)
    about = size - 2 * (q @ x.T)  # less the query's own square
    edge = np.partition(about, k - 1, axis=1)[:, k - 1] + own
    # a product errs by far less than this; rounding moves a distance by half a digit
    slack = 1e-12 * (own + size.max(initial=0)) + 1e-300
    half = 10.0**-digits
    top = np.maximum(edge, 0) + slack
    top = (np.sqrt(top) + half) ** 2 if metric == "l2" else top + half
    near_q, near_x = np.nonzero(about <= (top + slack - own)[:, None])
    d = x[near_x] - q[near_q]
    d = np.einsum("ij,ij->i", d, d)
    d = np.round(np.sqrt(d) if metric == "l2" else d, digits) + 0.0
    ends = np.searchsorted(near_q, np.arange(len(q) + 1))
    out = []
    for a, b in zip(ends, ends[1:]):
        best = np.lexsort((ids[near_x[a:b]], d[a:b]))[:k]
        out.append((near_x[a:b][best], d[a:b][best]))
    return out


def _scan(base: DataFrame, queries: DataFrame, pick) -> DataFrame:
    """pick(ids, vectors, queries): (rows, distances) of each query."""
    spark = base.sparkSession
    out = None
    for qids, q in _packs(queries):
        sent = spark.sparkContext.broadcast((qids, q))

        def run(batches, sent=sent):
            qids, q = sent.value
            for b in batches:
                if not len(b):
                    continue
                ids, vecs = b["vec_id"].to_numpy(), np.array(b["vec"].tolist(), float)
                step = max(1, TILE_VALUES // len(ids))
                for i in range(0, len(q), step):
                    found = pick(ids, vecs, q[i : i + step])
                    yield pd.DataFrame({
                        "query_id": np.repeat(qids[i : i + step], [len(r) for r, _ in found]),
                        "vec_id": np.concatenate([ids[r] for r, _ in found]),
                        "dist": np.concatenate([d for _, d in found]),
                    })

        part = base.select("vec_id", "vec").mapInPandas(run, HITS)
        out = part if out is None else out.unionAll(part)
    return out if out is not None else spark.createDataFrame([], HITS)


def rank_hits(hits: DataFrame, k: int | None, digits: int = 6) -> DataFrame:
    """Best k of each query, distances to six decimals, ties by id."""
    hits = hits.select("query_id", "vec_id", (F.round("dist", digits) + F.lit(0.0)).alias("dist"))
    w = Window.partitionBy("query_id").orderBy("dist", "vec_id")
    out = hits.withColumn("rank", F.row_number().over(w))
    return (out if k is None else out.where(F.col("rank") <= k)).select("query_id", "rank", "vec_id", "dist")


def knn(base: DataFrame, queries: DataFrame, k: int, metric: str = "l2", exclude_self: bool = False, digits: int = 6) -> DataFrame:
    """(query_id, rank, vec_id, dist): the k nearest rows of each query."""
    keep = k + 1 if exclude_self else k
    # rounding may reorder what differs beyond six decimals: keep those ties too
    hits = _scan(base, queries, lambda ids, x, q: nearest_each(ids, x, q, keep, metric, digits))
    if exclude_self:
        hits = hits.where("query_id <> vec_id")
    return rank_hits(hits, k, digits)


def radius(base: DataFrame, queries: DataFrame, r: float, metric: str = "l2", exclude_self: bool = False) -> DataFrame:
    """(query_id, rank, vec_id, dist): all rows within r of each query."""
    def inside(ids, x, q):
        return [(rows, d[rows]) for d in pairwise(q, x, metric) for rows in (np.flatnonzero(np.round(d, 6) <= r),)]

    hits = _scan(base, queries, inside)
    if exclude_self:
        hits = hits.where("query_id <> vec_id")
    return rank_hits(hits, None)


def sample_queries(base: DataFrame, every: int = 100, rest: int = 0) -> DataFrame:
    return base.where(F.pmod("vec_id", F.lit(every)) == rest).select(F.col("vec_id").alias("query_id"), F.col("vec").alias("qvec"))


def without(base: DataFrame, queries: DataFrame) -> DataFrame:
    """The base of a not-in-database workload."""
    return base.join(queries.select(F.col("query_id").alias("vec_id")), "vec_id", "left_anti")


#: Rows of a cell that one task holds against their neighbours, and of a tile of these.
CELL_ROWS, TILE_ROWS = 4096, 64
#: Tasks that the cells are dealt to, at least.
SPREAD = 64


def _tiles(x: np.ndarray) -> list[np.ndarray]:
    """Row numbers in tiles: cut in two along the widest dimension while too many."""
    out, todo = [], [np.arange(len(x))]
    while todo:
        rows = todo.pop()
        if len(rows) <= TILE_ROWS:
            out.append(rows)
            continue
        wide = int(np.argmax(np.ptp(x[rows], axis=0)))
        rows = rows[np.argsort(x[rows, wide], kind="stable")]
        todo += [rows[: len(rows) // 2], rows[len(rows) // 2 :]]
    return out


def pairs_within(x: np.ndarray, y: np.ndarray, r: float):
    """Row numbers (of x, of y) of all pairs within r (l2, six decimals), a tile of x
    at a time: rows of y outside its box are left out, products tell which of the
    others may be near, and these have their distances taken by differences."""
    size, room = np.einsum("ij,ij->i", y, y), r + 1e-5
    for rows in _tiles(x):
        part = x[rows]
        low, high = part.min(0) - room, part.max(0) + room
        at = np.arange(len(y))
        for dim in np.argsort(np.ptp(part, axis=0), kind="stable"):
            v = y[at, dim]
            at = at[(v >= low[dim]) & (v <= high[dim])]
        step = max(1, TILE_VALUES // len(rows))
        for i in range(0, len(at), step):
            some = at[i : i + step]
            own = np.einsum("ij,ij->i", part, part)[:, None]
            about = own + size[some] - 2 * (part @ y[some].T)
            a, b = np.nonzero(about <= room * room + 1e-12 * (own + size[some]))
            a, b = rows[a], some[b]
            d = x[a] - y[b]
            near = np.round(np.sqrt(np.einsum("ij,ij->i", d, d)), 6) <= r
            if near.any():
                yield a[near], b[near]


def _near_pairs(nodes: DataFrame, r: float, dims: tuple[int, ...], cell_rows: int) -> DataFrame:
    """(a, b): ordered pairs of different nodes within r. Nodes meet in a grid of cells
    wider than r over two dimensions: each in its own cell, and as a neighbour in that
    and the adjacent ones. Cells of many nodes are cut into parts by a hash."""
    names = [f"c{i}" for i in dims[:2]]
    cell = [F.floor(F.get("vec", F.lit(i)) / F.lit(r + 1e-5)).alias(c) for i, c in zip(dims, names)]
    own = nodes.select("node", "vec", *cell)
    near = own
    for c in names:
        near = near.withColumn(c, F.explode(F.array(*(F.col(c) + s for s in (-1, 0, 1)))))
    size = own.groupBy(*names).agg(F.count(F.lit(1)).alias("n"))
    crowded = stored(size.where(F.col("n") > cell_rows).select(*names, F.ceil(F.col("n") / cell_rows).cast("int").alias("cut")), "crowded")
    share = F.lit(0).alias("share")
    if not crowded.isEmpty():
        own, near = (t.join(crowded.hint("merge"), names, "left").withColumn("cut", F.coalesce("cut", F.lit(1))) for t in (own, near))
        share = F.pmod(mixed(F.col("node")), F.col("cut")).cast("int").alias("share")
        near = near.select(*names, F.explode(F.sequence(F.lit(0), F.col("cut") - 1)).alias("share"), "node", "vec", F.lit(False).alias("own"))
    else:
        near = near.select(*names, share, "node", "vec", F.lit(False).alias("own"))
    both = own.select(*names, share, "node", "vec", F.lit(True).alias("own")).unionAll(near)

    def run(pdf):
        mine = pdf["own"].to_numpy(bool)
        empty = pd.DataFrame({"a": np.zeros(0, np.int64), "b": np.zeros(0, np.int64)})
        if not mine.any():
            return empty
        ids, x = pdf["node"].to_numpy(), np.array(pdf["vec"].tolist(), float)
        i, j = ids[mine], ids[~mine]
        found = [(i[a], j[b]) for a, b in pairs_within(x[mine], x[~mine], r)]
        if not found:
            return empty
        a, b = (np.concatenate(f) for f in zip(*found))
        return pd.DataFrame({"a": a[a != b], "b": b[a != b]})

    spark = nodes.sparkSession  # by a number, or Spark merges what is small but takes long
    tasks = max(SPREAD, int(spark.conf.get("spark.sql.shuffle.partitions")))
    return both.repartition(tasks, *names, "share").groupBy(*names, "share").applyInPandas(run, "a long, b long")


def near_classes(base: DataFrame, r: float, dims: tuple[int, ...], cell_rows: int = CELL_ROWS) -> DataFrame:
    """(vec_id, class_id, n_links) of every row: rows within r (l2) of each other
    are linked, and a class is named by its smallest id. Equal vectors are one
    node. Nodes meet in a grid of cells wider than r over the first two of ``dims``,
    so every linked pair lies in the same or in adjacent cells."""
    base = stored(base.select("vec_id", "vec"), "vectors")  # read twice, made once
    nodes = stored(base.groupBy("vec").agg(F.min("vec_id").alias("node"), F.count(F.lit(1)).alias("size")), "nodes")
    pairs = stored(_near_pairs(nodes, r, dims, cell_rows), "near")
    # a node without a pair is its own class
    label = stored(pairs.select(F.col("a").alias("node")).distinct().select("node", F.col("node").alias("label")), "labels")
    total = lambda df: df.agg(F.sum(F.col("label").cast("decimal(38,0)"))).first()[0]
    before = total(label)
    while True:
        low = pairs.join(label.select(F.col("node").alias("b"), "label"), "b").groupBy(F.col("a").alias("node")).agg(F.min("label").alias("low"))
        moved = stored(label.join(low, "node", "left").select("node", F.least("label", "low").alias("label")), "labels")
        jump = moved.select(F.col("node").alias("label"), F.col("label").alias("next"))
        label = stored(moved.join(jump, "label").select("node", F.col("next").alias("label")), "labels")
        after = total(label)
        if after == before:
            break
        before = after
    links = pairs.join(nodes.select(F.col("node").alias("b"), "size"), "b").groupBy(F.col("a").alias("node")).agg(F.sum("size").alias("others"))
    of = nodes.join(label, "node", "left").join(links, "node", "left").select("vec", F.coalesce("label", "node").alias("class_id"), (F.col("size") - 1 + F.coalesce("others", F.lit(0))).alias("n_links"))
    return base.join(of, "vec").select("vec_id", "class_id", "n_links")
