"""Near-duplicates by the Jaccard similarity of word-shingle sets, with SimHash
fingerprints compared in bit planes before the sets are.

Rows with equal sets are merged into one node by a 128-bit digest. The shingles
of a node are put in one order for all nodes, common ones last. Two sets of
similarity s or more share a shingle among the first n - ceil(s n) + 1 of each,
so pairs that meet under such a shingle hold every pair that is looked for,
whatever the order is; a sample of the nodes tells which shingles are common,
which only decides how many pairs meet.

Nodes that meet under a shingle are a group of fingerprints, stored and compared
as in ``simhash``: 64 of them to a block, planes of bits, carry-save counters,
blocks abandoned once all are beyond the radius. At a Jaccard similarity of 0.8
two fingerprints differ in 9.7 bits on average, with a deviation of 2.9;
``radius`` stands five deviations above that, and unrelated texts differ in 32.
Pairs within the radius are compared by their whole sets, which are computed
anew from the texts of the nodes that have such a pair; so nothing that is not
similar is ever linked.

In a few rounds first, each node is only held against few others: of the shingles
under which it meets nodes that it isn't joined with yet, it takes that which most
nodes have, and there the smallest node, in later rounds ``REPS`` nodes drawn by a
hash from the largest component. Pairs that this already joins are not compared
again, so a large group of near copies costs a few rows for each member and not
one for each pair; what is left apart after the rounds is compared in full. The
places of a shared shingle in both sets discard pairs that can't reach s. Groups
beyond ``block`` are dealt out in parts.

Edge cases: a text of fewer than k words is one shingle; texts without words
have equal (empty) sets and are linked; a row without an id makes no node and
takes the component of its set (null if no other row has it); an empty table
gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, materialise, portions
from .components import components
from .simhash import asked_pairs, majority, shingle_hashes

#: Similarity as a fraction, so that every bound is exact.
SIMILARITY = (4, 5)
RADIUS = 24
REPS = 8
SAMPLE_ROWS, COMMON = 20_000, 100_000


def _texts(df: DataFrame) -> DataFrame:
    return df.select(F.col("doc_id").cast("long").alias("doc_id"), "text")


def _digest(grams: np.ndarray) -> bytes:
    return xxhash.xxh3_128_digest(grams.tobytes())


def shingle_sets(df: DataFrame, k: int = 5) -> DataFrame:
    """(doc_id, sig, grams): sorted distinct shingle hashes and their digest."""

    def run(batches):
        for b in portions(batches):
            grams = [np.unique(shingle_hashes(t, k)) for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(map(_digest, grams), pa.binary()), pa.array([g.tobytes() for g in grams], pa.binary())], names=["doc_id", "sig", "grams"])

    return _texts(df).mapInArrow(run, "doc_id long, sig binary, grams binary")


def prefix(n: int, similarity: tuple[int, int] = SIMILARITY) -> int:
    """How many of n ordered shingles a similar set must meet."""
    p, q = similarity
    return n + p * n // -q + 1 if n else 0


def similar(a: np.ndarray, b: np.ndarray, similarity: tuple[int, int] = SIMILARITY) -> bool:
    p, q = similarity
    both = len(np.intersect1d(a, b, assume_unique=True))
    return q * both >= p * (len(a) + len(b) - both)


def _common(df: DataFrame, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Shingles that occur twice or more in a sample of the rows, and how often."""
    n = df.count()
    part = shingle_sets(df.where(F.pmod(F.xxhash64("doc_id"), F.lit(max(1, n // SAMPLE_ROWS))) == 0), k).select("grams")

    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(b"".join(b.column(0).to_pylist()), np.int64))], names=["h"])

    seen = part.mapInArrow(run, "h long").groupBy("h").agg(F.count(F.lit(1)).alias("c")).where("c > 1")
    got = seen.orderBy(F.desc("c"), "h").limit(COMMON).toArrow()  # plain columns, not an object for each row on the driver
    keys, counts = got.column("h").to_numpy().astype(np.int64).view(np.uint64), got.column("c").to_numpy().astype(np.int64)
    order = np.argsort(keys)
    return keys[order], counts[order]


def summaries(df: DataFrame, k: int, similarity: tuple[int, int]) -> DataFrame:
    """(doc_id, sig, fp, n, first): digest, fingerprint and size of each row's
    set, and those of its shingles under which similar sets meet, in order."""
    sent = df.sparkSession.sparkContext.broadcast(_common(df, k))

    def run(batches):
        keys, counts = sent.value
        for b in portions(batches):
            sig, fp, n, first = [], [], [], []
            for t in b.column(1).to_pylist():
                every = shingle_hashes(t, k)
                s = np.unique(every)
                often = np.zeros(len(s), np.int64)
                if len(keys) and len(s):
                    at = np.minimum(np.searchsorted(keys, s), len(keys) - 1)
                    often = np.where(keys[at] == s, counts[at], 0)
                sig.append(_digest(s))
                fp.append(majority(every))
                n.append(len(s))
                first.append(s[np.lexsort((s, often))[: prefix(len(s), similarity)]].tobytes())
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array(sig, pa.binary()), pa.array(np.array(fp, np.uint64).view(np.int64)), pa.array(n, pa.int32()), pa.array(first, pa.binary())], names=["doc_id", "sig", "fp", "n", "first"]
            )

    return _texts(df).mapInArrow(run, "doc_id long, sig binary, fp long, n int, first binary")


def _unfolded(nodes: DataFrame) -> DataFrame:
    """(h, node, place): the shingles under which a node meets others, and
    their places in its order."""

    def run(batches):
        for b in portions(batches):
            h = [np.frombuffer(g, np.int64) for g in b.column(1).to_pylist()]
            size = [len(x) for x in h]
            place = np.concatenate([np.arange(n, dtype=np.int32) for n in size])
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(h)), pa.array(np.repeat(b.column(0).to_numpy(), size)), pa.array(place)], names=["h", "node", "place"])

    return nodes.select("node", "first").mapInArrow(run, "h long, node long, place int")


def _near(rows: DataFrame, radius: int, block: int, similarity: tuple[int, int]) -> DataFrame:
    """(a, b): distinct pairs of an asking row and another one of the same
    shingle, not of the same root, with fingerprints within the radius, whose
    sets can be similar by their sizes n and by what is left from the shingle
    on. rows: h, node, fp, n, left, root, asks, c and m (rows and asking rows of
    the shingle)."""
    p, s = similarity[0], sum(similarity)
    half = max(1, block // 2)
    rows = materialise(rows, "met")
    n_rows, most = rows.agg(F.count(F.lit(1)), F.max("c")).first()
    rest = ["node", "fp", "root", "asks", "n", "left"]
    whole = rows.where(F.col("c") <= block) if (most or 0) > block else rows
    kept, asking = whole.withColumn("asks", F.lit(False)), whole.where("asks")
    dealt = kept.unionAll(asking).select("h", F.lit(0).alias("i"), F.lit(0).alias("j"), *rest)
    if whole is not rows:  # only rows of crowded shingles are copied
        crowded = rows.where(F.col("c") > block)
        cut = lambda n: F.ceil(F.col(n) / half).cast("int")
        deal = lambda n: F.pmod(F.xxhash64("node"), cut(n)).cast("int")
        copies = lambda n: F.explode(F.sequence(F.lit(0), cut(n) - 1))
        dealt = dealt.unionAll(crowded.withColumn("asks", F.lit(False)).select("h", deal("c").alias("i"), copies("m").alias("j"), *rest))
        dealt = dealt.unionAll(crowded.where("asks").select("h", copies("c").alias("i"), deal("m").alias("j"), *rest))
    tasks = max(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), n_rows // 500_000)
    dealt = dealt.repartition(tasks, "h", "i", "j").select(F.xxhash64("h", "i", "j").alias("g"), *rest)

    def run(batches):
        got = [b for b in batches if b.num_rows]
        if not got:
            return
        g, node, fp, root, asks, n, left = (np.concatenate([b.column(i).to_numpy(zero_copy_only=False) for b in got]) for i in range(7))
        order = np.lexsort((node, g))
        g, node, fp, root, asks, n, left = (x[order] for x in (g, node, fp.view(np.uint64), root, asks, n.astype(np.int64), left.astype(np.int64)))
        q, x = np.flatnonzero(asks), np.flatnonzero(~asks)
        found, held = [], 0
        for i, j in asked_pairs(fp[x], g[x], fp[q], g[q], radius):
            i, j = q[i], x[j]
            apart = (root[i] != root[j]) & (np.minimum(left[i], left[j]) * s >= (n[i] + n[j]) * p)
            pairs = np.stack([node[i[apart]], node[j[apart]]], 1)
            found.append(np.unique(np.sort(pairs, axis=1), axis=0))
            held += len(found[-1])
            if held > 1_000_000:
                yield _pairs(np.unique(np.concatenate(found), axis=0))
                found, held = [], 0
        if held:
            yield _pairs(np.unique(np.concatenate(found), axis=0))

    out = materialise(dealt.mapInArrow(run, "a long, b long").distinct(), "pairs")
    discard(rows)
    return out


def _pairs(p: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(p[:, 0]), pa.array(p[:, 1])], names=["a", "b"])


def _verified(pairs: DataFrame, sets_of, similarity: tuple[int, int]) -> DataFrame:
    """The stored pairs (a, b) whose sets are similar. sets_of: node ids to (node, grams)."""
    ids = materialise(pairs.select(F.col("a").alias("node")).unionAll(pairs.select(F.col("b").alias("node"))).distinct(), "members")
    held = materialise(sets_of(ids), "sets")
    one, two = (held.select(F.col("node").alias(c), F.col("grams").alias(f"g{c}")) for c in "ab")
    both = pairs.join(one.hint("merge"), "a").join(two.hint("merge"), "b").select("a", "b", "ga", "gb")

    def run(batches):
        for b in portions(batches):
            x, y = b.column(2).to_pylist(), b.column(3).to_pylist()
            ok = [similar(np.frombuffer(u, np.uint64), np.frombuffer(v, np.uint64), similarity) for u, v in zip(x, y)]
            yield b.select([0, 1]).filter(pa.array(ok, pa.bool_()))

    out = materialise(both.mapInArrow(run, "a long, b long"), "similar")
    discard(pairs, ids, held)
    return out


def _apart(rows: DataFrame, roots: DataFrame | None, turn: int) -> DataFrame:
    """(h, node, place, root, main, reps, c, m): the rows of shingles that
    several components share; main is the largest of these, reps some of its
    nodes, c and m count all rows and those outside main."""
    if roots is None:
        met = rows.groupBy("h").agg(F.count(F.lit(1)).alias("c"), F.min("node").alias("main")).where("c > 1")
        return materialise(rows.join(met, "h").select("h", "node", "place", F.col("node").alias("root"), "main", F.array("main").alias("reps"), "c", (F.col("c") - 1).alias("m")), "apart")
    rooted = rows.select("h", "node", "place").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    drawn = F.array(*(F.min_by("node", F.xxhash64("node", F.lit(turn * REPS + i))) for i in range(REPS)))
    of_root = rooted.groupBy("h", "root").agg(F.count(F.lit(1)).alias("k"), drawn.alias("reps"))
    of_h = of_root.groupBy("h").agg(F.max(F.struct("k", (-F.col("root")).alias("main"), "reps")).alias("x"), F.sum("k").alias("c"), F.count(F.lit(1)).alias("roots")).where("roots > 1")
    of_h = of_h.select("h", (-F.col("x.main")).alias("main"), "x.reps", "c", (F.col("c") - F.col("x.k")).alias("m"))
    return materialise(rooted.join(of_h, "h").select("h", "node", "place", "root", "main", "reps", "c", "m"), "apart")


def links(nodes: DataFrame, sets_of, similarity: tuple[int, int] = SIMILARITY, radius: int = RADIUS, rounds: int = 2, block: int = 4096) -> DataFrame:
    """(a, b): links that span all pairs of similar sets. nodes: node, fp, n,
    first; sets_of: see _verified."""
    prints = nodes.select("node", "fp", "n")
    found, roots = None, None
    rows = materialise(_unfolded(nodes), "meetings")
    for turn in range(rounds + 1):
        before, rows = rows, _apart(rows, roots, turn)
        discard(before)
        if turn < rounds:
            best = rows.where("root <> main").groupBy("node").agg(F.max(F.struct("c", "h", "reps")).alias("x"))
            pick = materialise(best.select("node", F.explode(F.array_distinct("x.reps")).alias("h")), "picks")
            size = pick.groupBy("h").agg(F.count(F.lit(1)).alias("c"))
            ask = size.select("h", F.col("h").alias("node"), F.lit(True).alias("asks"))
            met = pick.select("h", "node", F.lit(False).alias("asks")).unionAll(ask).join(prints, "node").join(size, "h")
            met = met.select("h", "node", "fp", "n", F.col("n").alias("left"), F.col("node").alias("root"), "asks", "c", F.lit(1).alias("m"))
        else:
            pick = rows
            met = rows.join(prints, "node").select("h", "node", "fp", "n", (F.col("n") - F.col("place")).alias("left"), "root", (F.col("root") != F.col("main")).alias("asks"), "c", "m")
        near = _verified(_near(met, radius, block, similarity), sets_of, similarity)
        discard(pick)
        # what earlier rounds have joined goes on as its components' stars
        found = near if roots is None else near.unionAll(roots.where("node <> root").select(F.col("node").alias("a"), F.col("root").alias("b")))
        if turn < rounds:
            roots = components(found)
            discard(near)
    return found


def near_duplicates(df: DataFrame, similarity: tuple[int, int] = SIMILARITY, k: int = 5, broadcast_ids: int = 500_000, radius: int = RADIUS, block: int = 4096) -> DataFrame:
    """(doc_id, component_id) of every row. Sets of ids are broadcast up to
    ``broadcast_ids`` of them; beyond, both sides are shuffled."""
    every = materialise(summaries(df, k, similarity), "summaries")
    of_sig = materialise(every.groupBy("sig").agg(F.min("doc_id").alias("node")).where("node is not null"), "nodes")
    late = materialise(every.select("doc_id", "sig").join(of_sig, "sig").where("doc_id <> node").select("doc_id", "sig").distinct(), "copies")
    n_late = late.count()
    late_side = F.broadcast(late) if n_late <= broadcast_ids else late.hint("merge")
    nodes = every.where("doc_id is not null").join(late_side, ["doc_id", "sig"], "left_anti").select(F.col("doc_id").alias("node"), "fp", "n", "first")

    def sets_of(ids: DataFrame) -> DataFrame:
        side = F.broadcast(ids) if ids.count() <= broadcast_ids else ids.hint("merge")
        texts = df.join(side.withColumnRenamed("node", "doc_id"), "doc_id", "left_semi")
        return shingle_sets(texts, k).join(late_side, ["doc_id", "sig"], "left_anti").select(F.col("doc_id").alias("node"), "grams")

    # an id with several texts is a node for each of them; they share its component
    roots = components(links(nodes, sets_of, similarity, radius, block=block))
    of_set = of_sig.join(roots, "node", "left").select("sig", F.coalesce("root", "node").alias("component_id"))
    return every.select("doc_id", "sig").join(of_set, "sig", "left").select("doc_id", "component_id")
