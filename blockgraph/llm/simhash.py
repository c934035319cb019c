"""SimHash near-duplicates with bit-sliced comparison.

A fingerprint has 64 bits, each the majority of that bit over the hashes of a
text's word shingles. Equal fingerprints are first merged into one node. Two
fingerprints within ``radius`` bits agree on at least ``bands - radius`` of
``bands`` bit ranges, so every choice of that many ranges gives a key, and all
pairs within the radius meet under some key: no candidate is lost.

Under a key, fingerprints are stored vertically: 64 of them share a block of
64 words, one word for each bit plane. A fingerprint is compared with a whole
block by xor-ing each plane with its own bit and adding the result to bitwise
counters with carry-save adders, three planes at a time; blocks in which every
lane has passed the radius are abandoned. A key shared by more than
``block`` fingerprints is dealt out as pairs of parts of that size, so no task
holds an unbounded key. Each group sends on a spanning forest of its links,
and the forests are joined into components.

Edge cases: a null or empty text has fingerprint zero and links like any other;
a row without an id makes no node, and its component is that of its fingerprint
(null if no other row has it); repeated rows share a component; an empty table
gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import itertools
from math import comb

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import LOWER_TABLE, as_text, materialise, own, portions
from .components import components

SEED = 42
ALL = np.uint64(0xFFFFFFFFFFFFFFFF)


def shingle_hashes(text: str | None, k: int = 4) -> np.ndarray:
    """XXH64 of all k-word shingles, repeats included."""
    words = as_text(text).translate(LOWER_TABLE).split()
    if not words:
        return np.empty(0, np.uint64)
    joined = b" ".join(words)
    size = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(size + 1) - 1
    starts = ends - size
    k = min(k, len(words))
    h = xxhash.xxh64_intdigest
    spans = zip(starts[: len(words) - k + 1].tolist(), ends[k - 1 :].tolist())
    return np.fromiter((h(joined[s:e], SEED) for s, e in spans), np.uint64, len(words) - k + 1)


def majority(hashes: np.ndarray) -> int:
    """The fingerprint: bits set in over half of the hashes."""
    n = len(hashes)
    if not n:
        return 0
    bits = np.unpackbits(hashes.astype(">u8").view(np.uint8)).reshape(n, 64)
    total = np.zeros(64, np.int64)
    for i in range(0, n, 255):  # sums of up to 255 bits fit a byte
        total += np.add.reduce(bits[i : i + 255], axis=0, dtype=np.uint8)
    return int.from_bytes(np.packbits(2 * total > n).tobytes(), "big")


def fingerprints(df: DataFrame, k: int = 4, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, fp): fp is the fingerprint as a signed long."""

    def run(batches):
        for b in portions(batches):
            fp = np.array([majority(shingle_hashes(t, k)) for t in b.column(1).to_pylist()], np.uint64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fp.view(np.int64))], names=["doc_id", "fp"])

    src = df.select(F.col(id_col).cast("long").alias("doc_id"), text)
    return src.mapInArrow(run, "doc_id long, fp long")


def band_edges(bands: int, bits: int = 64) -> list[int]:
    return [bits * i // bands for i in range(bands + 1)]


def choose_bands(n: int, radius: int) -> int:
    """The fewest ranges for which a key is expected to hold few fingerprints."""
    for bands in range(radius + 2, 4 * radius + 4):
        width = 64 * (bands - radius) // bands
        if n >> width < 64 or comb(bands + 1, radius) > 500:
            return bands
    return radius + 2


def keys(fp: Column, bands: int, radius: int) -> Column:
    """All keys of a fingerprint: the chosen ranges' bits, and which they are."""
    edge = band_edges(bands)
    out = []
    for i, chosen in enumerate(itertools.combinations(range(bands), bands - radius)):
        mask = sum(((1 << (edge[c + 1] - edge[c])) - 1) << edge[c] for c in chosen)
        mask = mask - (1 << 64) if mask >= 1 << 63 else mask
        out.append(F.struct(F.lit(i).alias("choice"), fp.bitwiseAND(F.lit(mask).cast("long")).alias("bits")))
    return F.array(*out)


def _exceeds(c: list[np.ndarray], over: np.ndarray, radius: int) -> np.ndarray:
    """Lanes whose counter is above the radius."""
    gt, eq = over.copy(), ~over
    for level in reversed(range(len(c))):
        if radius >> level & 1:
            eq &= c[level]
        else:
            gt |= eq & c[level]
            eq &= ~c[level]
    return gt


def near_lanes(planes: np.ndarray, word: np.ndarray, query: np.ndarray, lanes: np.ndarray, radius: int, every: int = 12):
    """Indices into the (query, word) pairs and, for each, the lanes within the
    radius. planes: 64 x words; lanes: which lanes of the word count."""
    at = np.arange(len(word))
    levels = max(1, int(radius).bit_length())
    c = [np.zeros(len(word), np.uint64) for _ in range(levels)]
    over = ~lanes
    zero = np.uint64(0)
    for first in range(0, 64, every):
        last = min(64, first + every)
        for b in range(first, last, 3):
            d = [planes[p][word] ^ (zero - (query >> np.uint64(p) & np.uint64(1))) for p in range(b, min(b + 3, last))]
            while len(d) < 3:
                d.append(np.zeros(len(word), np.uint64))
            x, y, z = d
            add, carry = x ^ y ^ z, (x & y) | (z & (x ^ y))
            for i in range(levels):
                if i == 0:
                    up = c[0] & add
                    c[0] ^= add
                elif i == 1:
                    s = c[1] ^ up
                    nxt = (c[1] & up) | (s & carry)
                    c[1] = s ^ carry
                    up = nxt
                else:
                    nxt = c[i] & up
                    c[i] ^= up
                    up = nxt
            over |= up | carry if levels == 1 else up
        dead = _exceeds(c, over, radius)
        keep = np.flatnonzero(dead != ALL)
        if len(keep) < len(word):
            at, word, query, over = at[keep], word[keep], query[keep], over[keep]
            c = [x[keep] for x in c]
        if not len(word):
            return at, word
    return at, ~_exceeds(c, over, radius)


def _join(label: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    """Merge the labels of linked members, in place; a label is the smallest
    member of its component."""
    while len(a):
        la, lb = label[a], label[b]
        m = la != lb
        if not m.any():
            return
        a, b, la, lb = a[m], b[m], la[m], lb[m]
        np.minimum.at(label, np.maximum(la, lb), np.minimum(la, lb))
        while True:
            hop = label[label]
            if (hop == label).all():
                break
            label[:] = hop


def forest(fp: np.ndarray, group: np.ndarray, radius: int, slice_pairs: int = 65536) -> np.ndarray:
    """label[i]: the smallest index in the component of i, where members of
    the same group within the radius are linked. group is sorted."""
    n = len(fp)
    label = np.arange(n)
    if not n:
        return label
    first = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])
    size = np.diff(np.r_[first, n])
    rank = np.arange(n) - np.repeat(first, size)
    words_of = (size + 63) // 64
    word0 = np.cumsum(words_of) - words_of
    own = np.repeat(word0, size) + rank // 64
    lane = (rank % 64).astype(np.uint64)
    one = np.uint64(1)
    starts = np.flatnonzero(np.r_[True, own[1:] != own[:-1]])
    planes = np.empty((64, len(starts)), np.uint64)
    for b in range(64):
        planes[b] = np.bitwise_or.reduceat((fp >> np.uint64(b) & one) << lane, starts)
    filled = np.diff(np.r_[starts, n])
    valid = np.where(filled == 64, ALL, (one << (filled % 64).astype(np.uint64)) - one)
    # a member meets its own word (later lanes) and the later words of its group
    todo = np.repeat(word0 + words_of, size) - own
    todo[(rank == np.repeat(size, size) - 1)] = 0
    upto = np.cumsum(todo)
    at = 0
    while at < n:
        stop = max(at + 1, int(np.searchsorted(upto, (upto[at - 1] if at else 0) + slice_pairs, "right")))
        q = np.repeat(np.arange(at, stop), todo[at:stop])
        at = stop
        if not len(q):
            continue
        step = np.arange(len(q)) - np.repeat(np.cumsum(todo[q[0] : stop]) - todo[q[0] : stop], todo[q[0] : stop])
        w = own[q] + step
        later = np.where(step == 0, ~((one << lane[q]) | ((one << lane[q]) - one)), ALL)
        i, lanes = near_lanes(planes, w, fp[q], valid[w] & later, radius)
        if len(i):
            bits = np.unpackbits(lanes.astype("<u8").view(np.uint8), bitorder="little").reshape(-1, 64)
            pair, hit = np.nonzero(bits)
            _join(label, q[i[pair]], starts[w[i[pair]]] + hit)
    return label


def link_forest(nodes: DataFrame, radius: int, block: int = 4096) -> DataFrame:
    """(a, b): links between nodes (node long, fp long) that span all pairs
    within the radius that meet under some key."""
    spark = nodes.sparkSession
    n = nodes.count()
    bands = choose_bands(n, radius)
    keyed = nodes.select("node", "fp", F.explode(keys(F.col("fp"), bands, radius)).alias("k")).select("node", "fp", "k.choice", "k.bits")
    crowded = keyed.groupBy("choice", "bits").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > block)
    crowded = materialise(crowded.select("choice", "bits", F.ceil(F.col("n") / (block // 2)).cast("int").alias("parts")), "crowded")
    if crowded.isEmpty():
        dealt = keyed.select("node", "fp", "choice", "bits", F.lit(0).alias("i"), F.lit(0).alias("j"))
    else:
        part = F.pmod(F.xxhash64("fp"), F.col("parts")).cast("int")
        both = keyed.join(crowded, ["choice", "bits"], "left").withColumn("parts", F.coalesce("parts", F.lit(1))).withColumn("p", part)
        other = F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("o")
        dealt = both.select("node", "fp", "choice", "bits", "p", other).select("node", "fp", "choice", "bits", F.least("p", "o").alias("i"), F.greatest("p", "o").alias("j"))
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), n * comb(bands, radius) // 1_000_000)
    dealt = dealt.repartition(tasks, "choice", "bits", "i", "j").select("node", "fp", F.xxhash64("choice", "bits", "i", "j").alias("g"))

    def run(batches):
        got = [(b.column(0).to_numpy(), b.column(1).to_numpy(), b.column(2).to_numpy()) for b in batches if b.num_rows]
        if not got:
            return
        node, fp, g = (np.concatenate(x) for x in zip(*got))
        order = np.lexsort((node, g))
        node, fp, g = node[order], fp[order].view(np.uint64), g[order]
        label = forest(fp, g, radius)
        linked = np.flatnonzero(label != np.arange(len(label)))
        pairs = np.unique(np.stack([node[linked], node[label[linked]]], 1), axis=0) if len(linked) else np.empty((0, 2), np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], names=["a", "b"])

    return dealt.mapInArrow(run, "a long, b long")


def asked_pairs(fp: np.ndarray, group: np.ndarray, asked: np.ndarray, asked_group: np.ndarray, radius: int, slice_pairs: int = 65536):
    """Pairs (index into asked, index into fp) of the same group within the
    radius, in bounded slices. group and asked_group are sorted; the members of
    a group are stored as bit planes, and each asked fingerprint is compared
    with all blocks of its group."""
    if not len(fp) or not len(asked):
        return
    first = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])
    size = np.diff(np.r_[first, len(fp)])
    rank = np.arange(len(fp)) - np.repeat(first, size)
    words_of = (size + 63) // 64
    word0 = np.cumsum(words_of) - words_of
    own = np.repeat(word0, size) + rank // 64
    one = np.uint64(1)
    starts = np.flatnonzero(np.r_[True, own[1:] != own[:-1]])
    lane = (rank % 64).astype(np.uint64)
    planes = np.stack([np.bitwise_or.reduceat((fp >> np.uint64(b) & one) << lane, starts) for b in range(64)])
    filled = np.diff(np.r_[starts, len(fp)])
    valid = np.where(filled == 64, ALL, (one << (filled % 64).astype(np.uint64)) - one)
    g = np.minimum(np.searchsorted(group[first], asked_group), len(first) - 1)
    todo = np.where(group[first][g] == asked_group, words_of[g], 0)
    upto = np.cumsum(todo)
    at = 0
    while at < len(asked):
        stop = max(at + 1, int(np.searchsorted(upto, (upto[at - 1] if at else 0) + slice_pairs, "right")))
        q = np.repeat(np.arange(at, stop), todo[at:stop])
        step = np.arange(len(q)) - np.repeat(np.cumsum(todo[at:stop]) - todo[at:stop], todo[at:stop])
        at = stop
        if not len(q):
            continue
        w = word0[g[q]] + step
        i, lanes = near_lanes(planes, w, asked[q], valid[w], radius)
        if len(i):
            pair, hit = np.nonzero(np.unpackbits(lanes.astype("<u8").view(np.uint8), bitorder="little").reshape(-1, 64))
            yield q[i[pair]], starts[w[i[pair]]] + hit


def near_duplicates(df: DataFrame, radius: int = 4, k: int = 4) -> DataFrame:
    """(doc_id, fp, component_id) of every row."""
    prints = materialise(fingerprints(df, k), "prints")
    nodes = materialise(prints.groupBy("fp").agg(F.min("doc_id").alias("node")).where("node is not null"), "nodes")
    roots = components(link_forest(nodes, radius))
    of_fp = nodes.join(roots, "node", "left").select("fp", F.coalesce("root", "node").alias("component_id"))
    return prints.join(of_fp, "fp", "left").select("doc_id", "fp", "component_id")


def hex_of(fp: Column) -> Column:
    return F.lower(F.lpad(F.hex(fp), 16, "0"))


def keep_one(df: DataFrame, radius: int = 4, k: int = 4, broadcast_ids: int = 500_000) -> DataFrame:
    """The row of each component with the smallest id; rows without an id, which
    can't be told apart, stay. The ids to drop are broadcast up to
    ``broadcast_ids`` of them; beyond, both sides are shuffled by id."""
    return keep_first(df, near_duplicates(df.select("doc_id", "text"), radius, k), broadcast_ids)


def keep_first(df: DataFrame, classes: DataFrame, broadcast_ids: int = 500_000) -> DataFrame:
    """keep_one for any classes (doc_id, component_id) of the rows of df."""
    found = materialise(classes.select("doc_id", "component_id"), "classes")
    late = materialise(found.where("doc_id <> component_id").select("doc_id").distinct(), "late")
    kept = df.join(F.broadcast(late) if late.count() <= broadcast_ids else late.hint("merge"), "doc_id", "left_anti")
    if not found.where("doc_id = component_id").groupBy("doc_id").count().where("count > 1").isEmpty():
        kept = kept.where("doc_id is not null").dropDuplicates(["doc_id"]).unionByName(df.where("doc_id is null"))
    return kept.select(*own(df))
