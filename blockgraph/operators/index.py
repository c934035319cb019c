"""Indexes on Spark: one task builds a segment, one task searches a batch of
queries on a segment, one shuffle merges what the segments found.

The index is a table (segment_id, part, n_parts, payload): a segment's packed
arrays in parts of bounded size. ``segments_for`` gives the number of segments
that keeps each below ``max_vectors``, so a segment fits the memory of one Python
worker; a larger table has more segments, never larger ones.
"""

from __future__ import annotations

from dataclasses import asdict, dataclass, field, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import mixed, mixed_np
from ..functions.distance import pairwise
from . import graph, kmeans, layout, lockstep, pq, search
from .budget import block_geometry

PART_BYTES = 16 << 20
INDEX = "segment_id int, part int, n_parts int, payload binary"


@dataclass(frozen=True)
class Build:
    builder: str = "vamana"
    metric: str = "l2"
    max_degree: int = 16
    build_list: int = 64
    layout: str = "freq"
    layout_options: tuple = ()  # freq without options counts neighbours where they are now
    block_cap: int = 0  # 0: from block_kb
    block_kb: float = 4
    elem_bytes: int = 4
    entry: str = "medoid"  # or "fixed" (the smallest id) or "random" (by seed)
    sample_ratio: float = 0.1
    nav_degree: int = 8
    nav_source: str = "sample"  # or "layers" (upper layers of the builder)
    n_sub: int = 16
    n_codes: int = 64
    hot_ratio: float = 0.0
    hot_queries: int = 50
    seed: int = 7

    def cap(self, dim: int) -> int:
        return self.block_cap or block_geometry(1, dim, self.elem_bytes, self.max_degree, self.block_kb).block_cap


# --- segments ----------------------------------------------------------------


def segments_for(n_vectors: int, max_vectors: int, slack: float = 0.1) -> int:
    """How many hash segments hold ``max_vectors`` at most; ``slack`` is room
    for the spread of a hash."""
    return max(1, -(-n_vectors * int(1000 * (1 + slack)) // (1000 * max_vectors)))


def assign(base: DataFrame, n_segments: int | None = None, method: str = "hash", iters: int = 5, max_vectors: int | None = None) -> DataFrame:
    """base with segment_id: by a hash of the id, or by the nearest of k-means
    centroids (``assign_to`` with ``centroids``). With ``max_vectors`` the number
    of segments follows from the rows, and segments of a cluster that is larger
    are split by a hash (``split_large``)."""
    if max_vectors is not None:
        n_segments = max(n_segments or 1, segments_for(base.count(), max_vectors))
        return split_large(assign(base, n_segments, method, iters), max_vectors)[0]
    if method == "hash":
        return base.withColumn("segment_id", F.pmod(mixed(F.col("vec_id")), F.lit(n_segments)).cast("int"))
    return assign_to(base, kmeans.fit(base, n_segments, iters))


def split_large(assigned: DataFrame, max_vectors: int) -> tuple[DataFrame, DataFrame]:
    """The same rows with segments above the bound split by a hash of the id, in
    new numbers, and (old, segment_id): which segments came from which. Routed
    queries join the latter. Both have a row a segment beside the vectors."""
    size = assigned.groupBy("segment_id").agg(F.count(F.lit(1)).alias("n"))
    parts = size.select(F.col("segment_id").alias("old"), F.when(F.col("n") <= max_vectors, 1).otherwise(F.ceil(F.col("n") * 1.1 / max_vectors)).cast("int").alias("parts"))
    # a segment is a number of one row here, so the window holds as many rows as there are segments
    first = F.coalesce(F.sum("parts").over(Window.orderBy("old").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).cast("int")
    parts = parts.withColumn("first", first)
    rows = assigned.withColumnRenamed("segment_id", "old").join(F.broadcast(parts), "old")
    split = rows.withColumn("segment_id", (F.col("first") + F.pmod(F.xxhash64("vec_id"), F.col("parts"))).cast("int")).drop("old", "parts", "first")
    return split, parts.select("old", F.explode(F.sequence(F.col("first"), F.col("first") + F.col("parts") - 1)).alias("segment_id"))


def assign_to(base: DataFrame, centroids: np.ndarray) -> DataFrame:
    sent = base.sparkSession.sparkContext.broadcast(centroids)

    def run(batches):
        for b in batches:
            if len(b):
                yield b.assign(segment_id=kmeans.assign_local(np.array(b["vec"].tolist(), float), sent.value).astype(np.int32))

    return base.select("vec_id", "vec").mapInPandas(run, "vec_id long, vec array<double>, segment_id int")


def route(queries: DataFrame, centroids: np.ndarray, n_probe: int) -> DataFrame:
    """(query_id, qvec, segment_id) of the n_probe nearest segments."""
    sent = queries.sparkSession.sparkContext.broadcast(centroids)

    def run(batches):
        c = sent.value
        for b in batches:
            if len(b):
                x = np.array(b["qvec"].tolist(), float)
                near = np.argsort(pairwise(x, c, "l2"), axis=1, kind="stable")[:, :n_probe]
                i = np.repeat(np.arange(len(b)), near.shape[1])
                yield b.iloc[i].assign(segment_id=near.ravel().astype(np.int32))

    return queries.select("query_id", "qvec").mapInPandas(run, "query_id long, qvec array<double>, segment_id int")


def everywhere(queries: DataFrame, n_segments: int) -> DataFrame:
    return queries.select("query_id", "qvec", F.explode(F.sequence(F.lit(0), F.lit(n_segments - 1))).alias("segment_id"))


# --- building ----------------------------------------------------------------


def build_segment(ids: np.ndarray, x: np.ndarray, b: Build) -> tuple[search.Segment, dict]:
    """The index of one segment and the seconds of each step."""
    import time

    seconds, t = {}, time.perf_counter()

    def lap(name):
        nonlocal t
        now = time.perf_counter()
        seconds[name] = now - t
        t = now

    order = np.argsort(ids, kind="stable")
    ids, x = ids[order], np.asarray(x, float)[order]
    nbrs, entry, upper = graph.build(b.builder, x, ids, b.metric, b.max_degree, b.build_list, b.seed)
    lap("graph")
    return laid_out(ids, x, nbrs, entry, b, upper, lap=lap), seconds


def bare(b: Build) -> Build:
    """What of a build the graph and the codes depend on, the rest the cheapest."""
    return Build(b.builder, b.metric, b.max_degree, b.build_list, layout="idpack", sample_ratio=0, n_sub=b.n_sub, n_codes=b.n_codes, seed=b.seed)


def laid_out(ids: np.ndarray, x: np.ndarray, nbrs: np.ndarray, entry: int, b: Build, upper=(), coded: tuple | None = None, lap=lambda name: None) -> search.Segment:
    """A segment from its graph; ``coded``: its codebook and codes, if there are any yet."""
    if b.entry != "medoid" and len(ids):
        entry = 0 if b.entry == "fixed" else int(np.random.default_rng(b.seed).integers(len(ids)))
    block = layout.make(b.layout, nbrs, x, b.cap(x.shape[1]), **(dict(b.layout_options) or ({"map": "live"} if b.layout.startswith("freq") else {})))
    lap("shuffle")
    nav_rows = nav_nbrs = None
    nav_entry = -1
    if b.nav_source == "layers" and upper:
        nav_rows = np.array(sorted({i for layer in upper for i in layer}), np.int64)
        at = {int(r): j for j, r in enumerate(nav_rows)}
        lists = [sorted({at[v] for layer in upper for v in layer.get(int(r), [])}) for r in nav_rows]
        nav_nbrs = np.full((len(nav_rows), max(1, max(map(len, lists)))), -1, np.int32)
        for j, l in enumerate(lists):
            nav_nbrs[j, : len(l)] = l
        nav_entry = at[entry]
    elif b.sample_ratio > 0 and len(ids):
        h = mixed_np(ids)
        nav_rows = np.flatnonzero(h < int(b.sample_ratio * 2**32))
        if not len(nav_rows):
            nav_rows = np.array([int(np.argmin(h))])
        kind = b.builder if b.builder != "hnsw" else "vamana"
        nav_nbrs, nav_entry, _ = graph.build(kind, x[nav_rows], ids[nav_rows], b.metric, min(b.nav_degree, max(1, len(nav_rows) - 1)), b.build_list, b.seed)
    lap("navigator")
    book, codes = coded or ([], None)
    if not coded and b.n_sub and len(ids):
        # cosine is the inner product of vectors of norm one
        unit = x / np.maximum(np.sqrt((x * x).sum(1))[:, None], 1e-30) if b.metric == "cosine" else x
        book = pq.train_local(unit, min(b.n_sub, x.shape[1]), b.n_codes, seed=b.seed)
        codes = pq.encode_local(unit, book)
    lap("codes")
    seg = search.Segment(ids, x, nbrs, np.asarray(block, np.int64), b.metric, entry, book, codes, nav_rows, nav_nbrs, nav_entry)
    if b.hot_ratio > 0 and len(ids):
        seg.hot = hot_rows(seg, b)
    lap("hot")
    return seg


def hot_rows(seg: search.Segment, b: Build) -> frozenset:
    """Rows visited most by sample queries on the vertex-at-a-time search."""
    counts = np.zeros(len(seg.ids), np.int64)
    sample = np.argsort(mixed_np(seg.ids + 99), kind="stable")[: b.hot_queries]
    o = search.vertex_options(search.Options(), cache=False)
    for i in sample:
        run = search._Run(seg, seg.vecs[i], o, None)
        run.go()
        counts[sorted(run.done)] += 1
    n = int(np.ceil(b.hot_ratio * len(seg.ids)))
    return frozenset(np.lexsort((np.arange(len(counts)), -counts))[:n].tolist())


def _rows_of(segment_id: int, data: bytes) -> pd.DataFrame:
    parts = [data[i : i + PART_BYTES] for i in range(0, len(data), PART_BYTES)]
    return pd.DataFrame({"segment_id": np.int32(segment_id), "part": np.arange(len(parts), dtype=np.int32), "n_parts": np.int32(len(parts)), "payload": parts})


#: Partitions by segment: many more than segments, so that few share a task. Given
#: as a number, Spark doesn't merge them, however small their tables are.
SPREAD = 64


def build(base: DataFrame, b: Build) -> DataFrame:
    """base: segment_id, vec_id, vec."""

    def run(pdf):
        seg, _ = build_segment(pdf["vec_id"].to_numpy(), np.array(pdf["vec"].tolist(), float), b)
        return _rows_of(int(pdf["segment_id"].iloc[0]), seg.pack())

    return base.select("segment_id", "vec_id", "vec").repartition(SPREAD, "segment_id").groupBy("segment_id").applyInPandas(run, INDEX)


def derive(index: DataFrame, builds: list[Build]) -> DataFrame:
    """The indexes of several builds that are ``bare`` the same, from the stored one
    of that: (variant, ...) with the number of the build. A task for each and segment."""

    def run(pdf):
        at, s, seg = int(pdf["variant"].iloc[0]), int(pdf["segment_id"].iloc[0]), load(pdf)
        seg = laid_out(seg.ids, seg.vecs, seg.nbrs, seg.entry, builds[at], coded=(seg.book, seg.codes))
        return _rows_of(s, seg.pack()).assign(variant=np.int32(at))

    if any(bare(b) != bare(builds[0]) or b.nav_source != "sample" for b in builds):
        raise ValueError("these builds don't share a graph")
    every = index.withColumn("variant", F.explode(F.sequence(F.lit(0), F.lit(len(builds) - 1))))
    return every.repartition(SPREAD, "segment_id", "variant").groupBy("segment_id", "variant").applyInPandas(run, f"{INDEX}, variant int")


def build_seconds(base: DataFrame, b: Build) -> DataFrame:
    """(segment_id, step, seconds) of a build."""

    def run(pdf):
        _, s = build_segment(pdf["vec_id"].to_numpy(), np.array(pdf["vec"].tolist(), float), b)
        return pd.DataFrame({"segment_id": np.int32(pdf["segment_id"].iloc[0]), "step": list(s), "seconds": list(s.values())})

    return base.select("segment_id", "vec_id", "vec").groupBy("segment_id").applyInPandas(run, "segment_id int, step string, seconds double")


def load(pdf: pd.DataFrame) -> search.Segment:
    pdf = pdf.sort_values("part")
    if len(pdf) != pdf["n_parts"].iloc[0]:
        raise ValueError("parts of a segment are missing")
    return search.Segment.unpack(b"".join(pdf["payload"]))


def ids(index: DataFrame) -> DataFrame:
    """(segment_id, vec_id) of all that is indexed."""
    return per_segment(index, lambda s, seg: pd.DataFrame({"segment_id": np.int32(s), "vec_id": seg.ids}), "segment_id int, vec_id long")


def per_segment(index: DataFrame, fn, schema: str) -> DataFrame:
    """fn(segment_id, Segment) -> pandas frame, for each segment."""

    def run(pdf):
        return fn(int(pdf["segment_id"].iloc[0]), load(pdf))

    return index.groupBy("segment_id").applyInPandas(run, schema)


def edges(index: DataFrame) -> DataFrame:
    """(segment_id, src, dst, pos)."""

    def fn(s, seg):
        r, p = np.nonzero(seg.nbrs >= 0)
        return pd.DataFrame({"segment_id": np.int32(s), "src": seg.ids[r], "dst": seg.ids[seg.nbrs[r, p]], "pos": p.astype(np.int32)})

    return per_segment(index, fn, "segment_id int, src long, dst long, pos int")


def layout_table(index: DataFrame) -> DataFrame:
    """(segment_id, vec_id, block_id, slot)."""

    def fn(s, seg):
        slot = np.empty(len(seg.ids), np.int32)
        for m in seg.members:
            slot[m] = np.arange(len(m))
        return pd.DataFrame({"segment_id": np.int32(s), "vec_id": seg.ids, "block_id": seg.block, "slot": slot})

    return per_segment(index, fn, "segment_id int, vec_id long, block_id long, slot int")


# --- searching ---------------------------------------------------------------

FOUND = "query_id long, segment_id int, kind string, vec_id long, dist double, ios long, hops long, nav_hops long, restarts long, rounds long, used long, loaded long, blocks long, util double, io_ms double, ms double, step int, block_id long"


@dataclass(frozen=True)
class Ask:
    """What to search for: k or r, and by which method."""

    k: int = 10
    r: float | None = None
    method: str = "block"  # "vertex", "radius_by_topk" (block) or "vertex_radius_by_topk"
    options: search.Options = field(default_factory=search.Options)


def answer(seg: search.Segment, q: np.ndarray, ask: Ask, visible: np.ndarray | None = None, run=None) -> search.Found:
    """One query on one segment. ``visible`` says which rows may be answers;
    the others still lead the search. A top-k search that ends with fewer than k
    visible rows is asked again with twice the list, all reads counted, until it
    has k or the list holds the segment."""
    o = ask.options
    if ask.method.startswith("vertex"):
        o = search.vertex_options(o, cache=o.cache)
    if ask.r is not None:
        f = search.radius_by_topk(seg, q, ask.r, o, run=run) if ask.method.endswith("radius_by_topk") else search.radius_search(seg, q, ask.r, o, run)
        return f if visible is None else search.only(f, visible)
    want = min(ask.k, len(seg.ids) if visible is None else int(visible.sum()))
    total = search.Found([], [])
    while True:
        f = search.anns(seg, q, ask.k if visible is None else len(seg.ids), o, run)
        if visible is not None:
            f = search.only(f, visible)
            f.rows, f.dists = f.rows[: ask.k], f.dists[: ask.k]
        total = search.added(total, f)
        if len(f.rows) >= want or o.cand_size >= len(seg.ids):
            return total
        o = replace(o, cand_size=2 * o.cand_size)


def answers(seg: search.Segment, queries: list, ask: Ask, visible: np.ndarray | None = None) -> list[search.Found]:
    """``answer`` of each query over arrays; those of a top-k search side by side."""
    o = ask.options
    if ask.method.startswith("vertex"):
        o = search.vertex_options(o, cache=o.cache)
    n = len(seg.ids)
    restart = ask.r is not None and ask.method.endswith("radius_by_topk")
    if ask.r is not None and not restart or not lockstep.supports(seg, o):
        return [answer(seg, np.array(q, float), ask, visible) for q in queries]
    x = np.array(queries, float).reshape(len(queries), -1)
    out, left = [search.Found([], []) for _ in x], np.arange(len(x))
    if restart:
        out = lockstep_restarts(seg, x, ask.r, o)
        return out if visible is None else [search.only(f, visible) for f in out]
    want = min(ask.k, n if visible is None else int(visible.sum()))
    while len(left):
        if lockstep.supports(seg, o):
            found = lockstep.anns(seg, x[left], ask.k, o, visible)
        else:  # the list has become too long
            found = [search.anns(seg, q, ask.k if visible is None else n, o) for q in x[left]]
            if visible is not None:
                for f in found:
                    search.only(f, visible)
                    f.rows, f.dists = f.rows[: ask.k], f.dists[: ask.k]
        for i, f in zip(left, found):
            out[i] = search.added(out[i], f)
        left = left[[len(f.rows) < want and o.cand_size < n for f in found]]
        o = replace(o, cand_size=2 * o.cand_size)
    return out


def lockstep_restarts(seg: search.Segment, x: np.ndarray, r: float, o: search.Options, k0: int = 10, growth: int = 2) -> list[search.Found]:
    """``search.radius_by_topk`` of each query, the queries of a turn side by side."""
    out, left, k = [search.Found([], []) for _ in x], np.arange(len(x)), k0
    while len(left):
        turn = replace(o, cand_size=max(o.cand_size, k))
        found = lockstep.anns(seg, x[left], k, turn) if lockstep.supports(seg, turn) else [search.anns(seg, q, k, turn) for q in x[left]]
        for i, f in zip(left, found):
            out[i] = search.added(out[i], f)
        left = left[[not (len(f.rows) < k or f.dists[-1] > r or k >= len(seg.ids)) for f in found]]
        k *= growth
        for i in left:
            out[i].restarts += 1
    for f in out:
        inside = [(v, d) for v, d in zip(f.rows, f.dists) if d <= r]
        f.rows, f.dists = [v for v, _ in inside], [d for _, d in inside]
    return out


def _with_visible(index: DataFrame, visible: DataFrame) -> DataFrame:
    """The index with a part -1 for each segment: its rows that may be answers."""

    def pack(pdf):
        return pd.DataFrame({"segment_id": pdf["segment_id"].iloc[:1].astype(np.int32), "part": np.int32(-1), "n_parts": np.int32(0), "payload": [np.sort(pdf["vec_id"].to_numpy(np.int64)).tobytes()]})

    shown = ids(index).join(visible.select("vec_id").distinct(), "vec_id", "left_semi")
    return index.unionByName(shown.groupBy("segment_id").applyInPandas(pack, INDEX))


def run_queries(index: DataFrame, routed: DataFrame, ask: Ask, slices: int = 1, visible: DataFrame | None = None) -> DataFrame:
    """Rows of three kinds: ``hit`` (vec_id, dist), ``stat`` (counters of a
    query on a segment) and, with options.rows, ``step`` (reads of blocks).
    ``visible``: (vec_id) of the rows that may be answers, all if not given."""
    if visible is not None:
        index = _with_visible(index, visible)
    return serve(index, routed, ask, lambda rows: (load(rows), None, None), slices, visible is not None)


def serve(segments: DataFrame, routed: DataFrame, ask: Ask, start, slices: int = 1, masked: bool = False) -> DataFrame:
    """Answer the queries of each segment in one task, or in ``slices`` tasks.
    start(rows of a segment) gives the segment, what makes a query's run (None:
    over arrays) and what to call at the end (or None)."""
    names = [x.split()[0] for x in FOUND.split(", ")]
    kinds = {"long": "Int64", "int": "Int32", "double": "float64", "string": "object"}
    typed = lambda frame: frame.astype({c: kinds[t] for c, t in map(str.split, FOUND.split(", "))})

    def run(key, left, right):
        out, hits = [], []
        shown = None
        if masked:
            shown, left = left[left["part"] < 0], left[left["part"] >= 0]
        if len(left) and len(right):
            seg, make, close = start(left)
            s = int(left["segment_id"].iloc[0])
            mask = None
            if masked:
                mask = np.isin(seg.ids, np.frombuffer(shown["payload"].iloc[0], np.int64)) if len(shown) else np.zeros(len(seg.ids), bool)
            qs = right["qvec"].tolist()
            for qid, f in zip(right["query_id"].tolist(), answers(seg, qs, ask, mask) if make is None else (answer(seg, np.array(q, float), ask, mask, make) for q in qs)):
                blank = dict.fromkeys(names) | {"query_id": qid, "segment_id": s}
                hits.append((qid, seg.ids[f.rows] if f.rows else seg.ids[:0], f.dists))
                out.append(blank | {"kind": "stat", "ms": f.total_s * 1000, "io_ms": f.io_s * 1000} | {n: getattr(f, n) for n in search.COUNTERS})
                out += [blank | {"kind": "step", "step": a, "block_id": b, "used": u, "loaded": n} for a, b, u, n in f.trace]
            if close:
                close()
        frame = typed(pd.DataFrame(out, columns=names))
        if any(len(x) for _, x, _ in hits):  # by column: there may be millions
            found = {"query_id": np.repeat([q for q, _, _ in hits], [len(x) for _, x, _ in hits]), "vec_id": np.concatenate([x for _, x, _ in hits]), "dist": np.concatenate([np.array(d, float) for _, _, d in hits])}
            frame = pd.concat([frame, typed(pd.DataFrame(found).assign(segment_id=s, kind="hit").reindex(columns=names))], ignore_index=True)
        return frame

    right = routed.select("query_id", "qvec", "segment_id")
    keys = ["segment_id"]
    if slices > 1:  # a segment is visited by several tasks, each with some queries
        segments = segments.withColumn("slice", F.explode(F.sequence(F.lit(0), F.lit(slices - 1))))
        right = right.withColumn("slice", F.pmod(mixed(F.col("query_id")), F.lit(slices)).cast("int"))
        keys.append("slice")
    segments, right = (x.repartition(SPREAD, *keys) for x in (segments, right))
    return segments.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInPandas(run, FOUND)


def merge(found: DataFrame, k: int | None) -> DataFrame:
    """(query_id, rank, vec_id, dist): the best over all segments."""
    hits = found.where("kind = 'hit'").select("query_id", "vec_id", "dist")
    w = Window.partitionBy("query_id").orderBy("dist", "vec_id")
    out = hits.withColumn("rank", F.row_number().over(w))
    return (out if k is None else out.where(F.col("rank") <= k)).select("query_id", "rank", "vec_id", "dist")


def stats(found: DataFrame) -> DataFrame:
    """Counters of each query, summed over its segments."""
    names = (*search.COUNTERS, "io_ms", "ms")
    return found.where("kind = 'stat'").groupBy("query_id").agg(*(F.sum(n).alias(n) for n in names))


def describe(b: Build) -> dict:
    return asdict(b)
