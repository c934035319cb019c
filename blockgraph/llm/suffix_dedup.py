"""Exact removal of repeated byte strings with per-shard suffix arrays.

A byte goes if it is covered by a string of ``length`` bytes that also starts
earlier, in a document with a smaller id or further to the front of the same
one. Strings never cross documents and are judged on the input.

Sorting the suffixes of whole texts would cost far more than what repeats, so
the work is first narrowed down, without losing a pair. Each window of
``length`` bytes has an anchor, the position of the smallest hashed ``GRAM``
bytes inside it; equal windows have equal anchors. Runs of windows with one
anchor form a context of at most ``2 * length - GRAM`` bytes. Then:

1. Each chunk of documents sends its distinct anchor and context hashes, sixteen
   bytes a context and no text, to buckets by anchor hash.
2. A bucket answers each chunk which of its anchors occur twice, and which of
   these have differing contexts. Everything else can't repeat.
3. A chunk sends on one of its equal contexts, with its bytes where contexts
   differ; all but the first of equal contexts repeat whole.
4. A shard of contexts builds a suffix array (Larsson-Sadakane refinement: sort
   by the first seven bytes, then double, sorting only groups that are still
   tied) and the common prefixes of neighbours (Kasai, for all contexts side by
   side). Neighbours that share ``length`` bytes are equal windows, and all but
   the earliest repeat.
5. An anchor with more than ``hot`` contexts is dealt over many shards. What a
   shard finds to be its earliest is merged across shards: the shards' sorted
   runs of window fingerprints meet by range, and each run looks its windows up
   in the others by binary search.
6. The removed ranges go back to the chunks, which cut the texts.

Documents are packed by chunk into compressed rows, so a shuffle of texts
moves about a third of their bytes. Chunks are bounded in bytes, not in rows.

Edge cases: a null or empty text has nothing to remove; documents without an id
come last in the order, equal ids are ordered by chunk and text; repeated rows
are documents of their own, so the second of two equal rows goes; texts shorter
than ``length`` stay; an empty table gives an empty result; extra columns are
ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import as_text, chunk_count, materialise, portions, text_bytes

GRAM = 32
LAST = np.iinfo(np.int64).max
_TABLE = np.random.default_rng(20).integers(0, 2**63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_BASE = 0x9E3779B97F4A7C15 | 1


# --- suffix arrays -----------------------------------------------------------


def suffix_array(text: np.ndarray, depth: int | None = None) -> np.ndarray:
    """Positions in the order of their suffixes; with ``depth``, in the order of
    the first ``depth`` bytes at least, ties by position."""
    n = len(text)
    if not n:
        return np.empty(0, np.int64)
    padded = np.concatenate([text.astype(np.uint64) + np.uint64(1), np.zeros(8, np.uint64)])
    key = np.zeros(n, np.uint64)  # seven 9-bit symbols, so that the end sorts first
    for j in range(7):
        key = key << np.uint64(9) | padded[j : j + n]
    sa = np.argsort(key, kind="stable")
    ordered = key[sa]
    new = np.r_[True, ordered[1:] != ordered[:-1]]
    rank = np.empty(n + 1, np.int64)
    rank[n] = -1
    group = np.flatnonzero(new)[np.cumsum(new) - 1]
    rank[sa] = group
    h = 7
    tied = ~(new & np.r_[new[1:], True])
    at = np.flatnonzero(tied)
    while len(at) and (depth is None or h < depth):
        who = sa[at]
        first = rank[who]
        second = rank[np.minimum(who + h, n)]
        order = np.lexsort((second, first))
        who, first, second = who[order], first[order], second[order]
        sa[at] = who
        new = np.r_[True, (first[1:] != first[:-1]) | (second[1:] != second[:-1])]
        rank[who] = at[np.flatnonzero(new)[np.cumsum(new) - 1]]
        at = at[~(new & np.r_[new[1:], True])]
        h *= 2
    return sa


def common_prefixes(text: np.ndarray, sa: np.ndarray, starts: np.ndarray | None = None, cap: int | None = None) -> np.ndarray:
    """lcp[r]: bytes that the suffixes of rank r - 1 and r share (0 at rank 0),
    at most ``cap``. Kasai's rule, that the next position shares at least one
    byte less, runs down every part of the text (``starts``) at once."""
    n = len(text)
    lcp = np.zeros(n, np.int64)
    if n < 2:
        return lcp
    cap = n if cap is None else cap
    rank = np.empty(n, np.int64)
    rank[sa] = np.arange(n)
    starts = np.zeros(1, np.int64) if starts is None else starts
    ends = np.r_[starts[1:], n]
    order = np.argsort(starts - ends, kind="stable")  # longest part first
    starts, ends = starts[order], ends[order]
    size = ends - starts
    have = np.zeros(len(starts), np.int64)
    word = np.zeros(n + 8, np.uint64)  # eight bytes from each position
    tail = np.concatenate([text.astype(np.uint64), np.zeros(16, np.uint64)])
    for j in range(8):
        word = word << np.uint64(8) | tail[j : j + n + 8]
    live = len(starts)
    for j in range(int(size[0])):
        while live and size[live - 1] <= j:
            live -= 1
        here = starts[:live] + j
        r = rank[here]
        there = sa[np.maximum(r - 1, 0)]
        k = np.maximum(have[:live] - 1, 0)
        k[r == 0] = 0
        go = np.flatnonzero((r > 0) & (k < cap))
        while len(go):  # eight bytes at a time
            a, b = here[go] + k[go], there[go] + k[go]
            ok = (np.maximum(a, b) + 8 <= n) & (k[go] < cap)
            same = ok & (word[np.minimum(a, n)] == word[np.minimum(b, n)])
            k[go[same]] += 8
            go = go[same]
        go = np.flatnonzero((r > 0) & (k < cap))
        while len(go):
            a, b = here[go] + k[go], there[go] + k[go]
            ok = np.maximum(a, b) < n
            same = ok & (text[np.minimum(a, n - 1)] == text[np.minimum(b, n - 1)]) & (k[go] < cap)
            k[go[same]] += 1
            go = go[same]
        k = np.minimum(k, cap)
        have[:live] = k
        lcp[r] = k
    return lcp


# --- anchors -----------------------------------------------------------------


def _mix(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(31))
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(29)
    return x


def _gram_hashes(data: np.ndarray) -> np.ndarray:
    """Hash of the GRAM bytes from each position, by doubling."""
    x, step, mult = _TABLE[data], 1, _BASE
    while step < GRAM:
        x = x[:-step] * np.uint64(mult) + x[step:]
        mult = mult * mult % 2**64
        step *= 2
    return _mix(x)


def runs(data: np.ndarray, length: int, slice_bytes: int = 1 << 20):
    """Runs of windows of one document that share an anchor: first window,
    number of windows, anchor hash."""
    n = len(data)
    span = length - GRAM + 1
    first, count, hashes = [], [], []
    for lo in range(0, max(0, n - length + 1), slice_bytes):
        part = data[lo : min(n, lo + slice_bytes + length - 1)]
        h = _gram_hashes(part)
        low = (h & ~np.uint64(0xFFFFFF)) | np.arange(len(h), dtype=np.uint64)
        step = 1
        while step * 2 <= span:
            low = np.minimum(low[:-step], low[step:])
            step *= 2
        if span > step:
            low = np.minimum(low[: len(low) - (span - step)], low[span - step :])
        at = (low & np.uint64(0xFFFFFF)).astype(np.int64)
        new = np.flatnonzero(np.r_[True, at[1:] != at[:-1]])
        first.append(new + lo)
        count.append(np.diff(np.r_[new, len(at)]))
        hashes.append(h[at[new]])
    if not first:
        return np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0, np.uint64)
    return np.concatenate(first), np.concatenate(count), np.concatenate(hashes)


class Chunk:
    """The documents of a chunk in a fixed order, joined."""

    def __init__(self, table: pa.Table):
        ids, texts = [], []
        for r in table.to_pylist():
            blob, at = zstandard.decompress(r["blob"], max_output_size=r["size"]) if r["size"] else b"", 0
            for d, k in zip(r["ids"], r["sizes"]):
                ids.append(d)
                texts.append(blob[at : at + k])
                at += k
        order = sorted(range(len(ids)), key=lambda i: (ids[i] is None, ids[i] or 0, xxhash.xxh64_intdigest(texts[i])))
        self.ids = [ids[i] for i in order]
        self.texts = [texts[i] for i in order]
        self.key = np.array([LAST if d is None else d for d in self.ids], np.int64)
        self.size = np.array([len(t) for t in self.texts], np.int64)
        self.start = np.cumsum(self.size) - self.size
        self.joined = b"".join(self.texts)

    def runs(self, length: int, group_bytes: int = 1 << 20):
        """All runs: document index, first window in it, windows, anchor hash.
        Short documents are hashed together, windows across them are cut out."""
        data = np.frombuffer(self.joined, np.uint8)
        docs, first, count, hashes = [], [], [], []
        i = 0
        while i < len(self.size):
            j, total = i + 1, int(self.size[i])
            while j < len(self.size) and total + self.size[j] <= group_bytes:
                total += int(self.size[j])
                j += 1
            lo = int(self.start[i])
            f, c, h = runs(data[lo : lo + total], length)
            if j > i + 1 and len(f):
                f, c, h = _within(f, c, h, self.start[i:j] - lo, self.size[i:j], length)
            d = np.searchsorted(self.start[i:j] - lo, f, "right") - 1 + i
            # empty documents share their start with the next: take the one with bytes
            docs.append(d)
            first.append(f + lo - self.start[d])
            count.append(c)
            hashes.append(h)
            i = j
        if not docs:
            e = np.empty(0, np.int64)
            return e, e, e, np.empty(0, np.uint64)
        return tuple(np.concatenate(x) for x in (docs, first, count, hashes))


def _within(f, c, h, start, size, length):
    """Cut runs to the windows that lie in one document. A run may touch
    several short documents."""
    full = np.flatnonzero(size >= length)
    lo, hi = start[full], start[full] + size[full] - length + 1  # window starts of each
    a = np.searchsorted(hi, f, "right")  # first document whose windows end behind f
    b = np.searchsorted(lo, f + c, "left")  # first document that begins behind the run
    n = np.maximum(b - a, 0)
    run = np.repeat(np.arange(len(f)), n)
    if not len(run):
        return f[:0], c[:0], h[:0]
    doc = np.arange(len(run)) - np.repeat(np.cumsum(n) - n, n) + a[run]
    x, y = np.maximum(f[run], lo[doc]), np.minimum(f[run] + c[run], hi[doc])
    ok = y > x
    return x[ok], (y - x)[ok], h[run[ok]]


def pack(df: DataFrame, chunks: int, id_col: str, text: str, hold_bytes: int = 24 << 20) -> DataFrame:
    """(chunk, ids, sizes, size, blob): documents of a chunk in compressed rows."""

    def run(batches):
        held: dict[int, tuple[list, list]] = {}
        weight = 0

        def flush():
            c = zstandard.ZstdCompressor(level=1)
            for chunk in sorted(held):
                ids, texts = held[chunk]
                blob = b"".join(texts)
                yield pa.RecordBatch.from_arrays(
                    [pa.array([chunk], pa.int32()), pa.array([ids], pa.list_(pa.int64())), pa.array([list(map(len, texts))], pa.list_(pa.int64())), pa.array([len(blob)], pa.int64()), pa.array([c.compress(blob)], pa.binary())],
                    names=["chunk", "ids", "sizes", "size", "blob"],
                )
            held.clear()

        for b in portions(batches):
            for chunk, d, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist()):
                t = as_text(t)
                ids, texts = held.setdefault(chunk, ([], []))
                ids.append(d)
                texts.append(t)
                weight += len(t) + 16
                if weight >= hold_bytes:
                    yield from flush()
                    weight = 0
        yield from flush()

    src = df.select(F.pmod(F.xxhash64(id_col, text), F.lit(chunks)).cast("int").alias("chunk"), F.col(id_col).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"))
    return src.mapInArrow(run, "chunk int, ids array<long>, sizes array<long>, size long, blob binary")


# --- the steps ---------------------------------------------------------------


def _context_hashes(chunk: Chunk, docs, first, count, length: int) -> np.ndarray:
    a = chunk.start[docs] + first
    b = a + count + length - 1
    mv, h = memoryview(chunk.joined), xxhash.xxh64_intdigest
    return np.fromiter((h(mv[x:y]) for x, y in zip(a.tolist(), b.tolist())), np.uint64, len(a))


def _bucket(h: np.ndarray, buckets: int) -> np.ndarray:
    return ((h >> np.uint64(40)) % np.uint64(buckets)).astype(np.int64)


def _by_bucket(bucket: np.ndarray):
    """(bucket, indices) of each bucket that occurs."""
    order = np.argsort(bucket, kind="stable")
    got = bucket[order]
    at = np.flatnonzero(np.r_[True, got[1:] != got[:-1]]) if len(got) else np.empty(0, np.int64)
    for x, y in zip(at, np.r_[at[1:], len(got)]):
        yield int(got[x]), order[x:y]


ASK = "bucket int, chunk int, h binary, c binary, twice binary"


def _ask(packed: DataFrame, length: int, buckets: int) -> DataFrame:
    def run(key, table):
        chunk = Chunk(table)
        docs, first, count, h = chunk.runs(length)
        c = _context_hashes(chunk, docs, first, count, length)
        order = np.lexsort((c, h))
        h, c = h[order], c[order]
        new = np.flatnonzero(np.r_[True, (h[1:] != h[:-1]) | (c[1:] != c[:-1])]) if len(h) else np.empty(0, np.int64)
        twice = np.diff(np.r_[new, len(h)]) > 1
        h, c = h[new], c[new]
        rows = [(b, key[0].as_py(), h[i].tobytes(), c[i].tobytes(), np.packbits(twice[i]).tobytes()) for b, i in _by_bucket(_bucket(h, buckets))]
        return pa.Table.from_pylist([dict(zip(("bucket", "chunk", "h", "c", "twice"), r)) for r in rows], _schema(ASK))

    return packed.groupBy("chunk").applyInArrow(run, ASK)


def _schema(ddl: str) -> pa.Schema:
    kinds = {"int": pa.int32(), "long": pa.int64(), "binary": pa.binary(), "string": pa.string()}
    return pa.schema([(n, kinds[t]) for n, t in (x.split() for x in ddl.split(", "))])


ANSWER = "chunk int, h binary, parts binary"


def _answer(asked: DataFrame, hot: int) -> DataFrame:
    """For each chunk its repeated anchors, with 0 if all contexts are equal, 1
    if they differ, and the number of shards beyond ``hot`` contexts."""

    def run(key, table):
        chunk = table.column("chunk").to_pylist()
        hs = [np.frombuffer(x, np.uint64) for x in table.column("h").to_pylist()]
        cs = [np.frombuffer(x, np.uint64) for x in table.column("c").to_pylist()]
        ts = [np.unpackbits(np.frombuffer(x, np.uint8), count=len(h)).astype(bool) for x, h in zip(table.column("twice").to_pylist(), hs)]
        h, c, t = np.concatenate(hs), np.concatenate(cs), np.concatenate(ts)
        order = np.lexsort((c, h))
        g, cc = h[order], c[order]
        new = np.flatnonzero(np.r_[True, g[1:] != g[:-1]])
        size = np.diff(np.r_[new, len(g)])
        twice = np.add.reduceat(t[order].astype(np.int64), new) > 0
        kinds = np.add.reduceat(np.r_[True, (cc[1:] != cc[:-1]) | (g[1:] != g[:-1])].astype(np.int64), new)
        keep = (size > 1) | twice
        keys = g[new][keep]
        parts = np.where(kinds[keep] == 1, 0, np.where(size[keep] > hot, -(-2 * size[keep] // hot), 1)).astype(np.int32)
        out = []
        if len(keys):
            for k, x in zip(chunk, hs):
                x = np.unique(x)
                i = np.minimum(np.searchsorted(keys, x), len(keys) - 1)
                ok = keys[i] == x
                if ok.any():
                    out.append({"chunk": k, "h": x[ok].tobytes(), "parts": parts[i[ok]].tobytes()})
        return pa.Table.from_pylist(out, _schema(ANSWER))

    return asked.groupBy("bucket").applyInArrow(run, ANSWER)


SEND = "bucket int, chunk int, h binary, fp binary, key binary, doc binary, first binary, count binary, text binary, text_size long, removed binary"


def _send(packed: DataFrame, answers: DataFrame, length: int, buckets: int) -> DataFrame:
    """Contexts that may repeat, by shard; bucket -1 has the chunk's own ranges."""

    def run(key, left, right):
        hs = [np.frombuffer(x, np.uint64) for x in right.column("h").to_pylist()]
        if not left.num_rows or not hs:
            return pa.Table.from_pylist([], _schema(SEND))
        keys = np.concatenate(hs)
        parts = np.concatenate([np.frombuffer(x, np.int32) for x in right.column("parts").to_pylist()])
        order = np.argsort(keys)
        keys, parts = keys[order], parts[order]
        chunk = Chunk(left)
        docs, first, count, h = chunk.runs(length)
        i = np.minimum(np.searchsorted(keys, h), len(keys) - 1)
        ok = np.flatnonzero(keys[i] == h)
        docs, first, count, h, p = docs[ok], first[ok], count[ok], h[ok], parts[i[ok]]
        fp = _context_hashes(chunk, docs, first, count, length)
        order = np.lexsort((first, docs, fp, h))  # documents are in order of their ids
        docs, first, count, h, p, fp = (x[order] for x in (docs, first, count, h, p, fp))
        new = np.r_[True, (h[1:] != h[:-1]) | (fp[1:] != fp[:-1])]
        again = np.flatnonzero(~new)
        a, b, d = _union(docs[again], first[again], first[again] + count[again] + length - 1)
        number = key[0].as_py()
        rows = [{"bucket": -1, "chunk": number, "removed": np.stack([d, a, b]).astype(np.int64).tobytes()}] if len(d) else []
        keep = np.flatnonzero(new)
        docs, first, count, h, p, fp = (x[keep] for x in (docs, first, count, h, p, fp))
        bucket = _bucket(h, buckets)
        salted = p > 1
        spread = (fp % np.maximum(p, 1).astype(np.uint64)) * np.uint64(0x9E3779B1) + h
        bucket = np.where(salted, buckets + ((spread >> np.uint64(20)) % np.uint64(buckets)).astype(np.int64), bucket)
        for q, i in _by_bucket(bucket):
            texts = []
            for j in i[p[i] > 0].tolist():
                x = int(chunk.start[docs[j]] + first[j])
                texts.append(chunk.joined[x : x + int(count[j]) + length - 1])
            blob = b"".join(texts)
            rows.append({
                "bucket": q, "chunk": number, "h": h[i].tobytes(), "fp": fp[i].tobytes(), "key": chunk.key[docs[i]].tobytes(), "doc": docs[i].tobytes(), "first": first[i].tobytes(),
                "count": (count[i] * np.where(p[i] > 0, 1, -1)).tobytes(), "text": zstandard.compress(blob, 1), "text_size": len(blob), "removed": b"",
            })
        return pa.Table.from_pylist(rows, _schema(SEND))

    return packed.groupBy("chunk").cogroup(answers.groupBy("chunk")).applyInArrow(run, SEND)


def _union(docs: np.ndarray, a: np.ndarray, b: np.ndarray):
    """Maximal ranges by document: starts, ends, documents."""
    if not len(docs):
        return a, b, docs
    order = np.lexsort((a, docs))
    docs, a, b = docs[order], a[order], b[order]
    wide = int(max(b.max(), 1)) + 1
    reach = np.maximum.accumulate(docs * wide + b)
    new = np.flatnonzero(np.r_[True, docs[1:] * wide + a[1:] > reach[:-1]])
    return a[new], (reach[np.r_[new[1:] - 1, len(a) - 1]] - docs[new] * wide), docs[new]


OUT = "chunk int, removed binary, w1 binary, w2 binary, key binary, doc binary, first binary"


BODY_BYTES = 1 << 20


def _windows_of(data, start, size, n, got, chunk, many, length, salted):
    """Late windows of some contexts as (chunk, doc, start, end); of a salted
    shard also the earliest ones and their fingerprints."""
    m = size[many]
    at = np.cumsum(m) - m
    body = data[np.repeat(start[many] - at, m) + np.arange(int(m.sum()))]
    sa = suffix_array(body)  # the whole order: Kasai needs it
    lcp = common_prefixes(body, sa, at, length)
    # leave out positions that begin no window; the least prefix in between counts
    of = np.repeat(np.arange(len(many)), m)
    inside = np.arange(len(body)) - at[of]
    ranks = np.flatnonzero((inside < n[many][of])[sa])
    least = np.minimum.reduceat(lcp[: ranks[-1] + 1], np.r_[0, ranks[:-1] + 1])
    pos = sa[ranks]
    group = np.cumsum(np.r_[True, least[1:] < length]) - 1
    c = many[of[pos]]
    f = got["first"][c] + inside[pos]
    order = np.lexsort((f, got["doc"][c], chunk[c], got["key"][c], group))
    first = np.r_[True, group[order][1:] != group[order][:-1]]
    x, y = order[~first], order[first] if salted else order[:0]
    mv = memoryview(body.tobytes())
    spans = [(int(i), int(i) + length) for i in pos[y]]
    prints = [np.fromiter((xxhash.xxh64_intdigest(mv[i:j], seed) for i, j in spans), np.uint64, len(y)) for seed in (1, 2)]
    return (chunk[c[x]], got["doc"][c[x]], f[x], f[x] + length), (chunk[c[y]], got["key"][c[y]], got["doc"][c[y]], f[y]), prints


def _resolve(sent: DataFrame, length: int, buckets: int) -> DataFrame:
    """Removed ranges by chunk; of salted shards also their earliest windows."""

    def run(key, table):
        rows = table.to_pylist()
        got = {c: np.concatenate([np.frombuffer(r[c], t) for r in rows]) for c, t in (("h", np.uint64), ("fp", np.uint64), ("key", np.int64), ("doc", np.int64), ("first", np.int64), ("count", np.int64))}
        chunk = np.concatenate([np.full(len(r["h"]) // 8, r["chunk"], np.int64) for r in rows])
        has, n = got["count"] > 0, np.abs(got["count"])
        size = np.where(has, n + length - 1, 0)
        text = b"".join(zstandard.decompress(r["text"], max_output_size=r["text_size"]) if r["text_size"] else b"" for r in rows)
        del rows
        start = np.cumsum(size) - size
        order = np.lexsort((got["first"], got["doc"], chunk, got["key"], got["fp"], got["h"]))
        h, fp = got["h"][order], got["fp"][order]
        new = np.r_[True, (h[1:] != h[:-1]) | (fp[1:] != fp[:-1])]
        again, once = order[~new], order[new]
        cut = [(chunk[again], got["doc"][again], got["first"][again], got["first"][again] + n[again] + length - 1)]
        # contexts of anchors with more than one context
        hh = got["h"][once]
        salted = key[0].as_py() >= buckets
        alone = np.r_[True, hh[1:] != hh[:-1]] & np.r_[hh[1:] != hh[:-1], True] if len(hh) else np.empty(0, bool)
        many = once[(has[once]) & (~alone | salted)]
        rest = []
        data = np.frombuffer(text, np.uint8)
        # equal windows have one anchor, so suffix arrays of a few anchors at a
        # time lose nothing, and their size is bounded
        weight = np.cumsum(size[many])
        fresh = np.flatnonzero(np.r_[True, got["h"][many][1:] != got["h"][many][:-1]]) if len(many) else np.empty(0, np.int64)
        lo = 0
        while lo < len(many):
            full = (weight[lo - 1] if lo else 0) + BODY_BYTES
            ends = fresh[(fresh > lo) & (weight[np.maximum(fresh - 1, 0)] <= full)]
            later = fresh[fresh > lo]
            hi = int(ends[-1]) if len(ends) else int(later[0]) if len(later) else len(many)
            if weight[-1] <= full:
                hi = len(many)
            part, lo = many[lo:hi], hi
            late, early, prints = _windows_of(data, start, size, n, got, chunk, part, length, salted)
            cut.append(late)
            for q, i in _by_bucket(early[0]):
                rest.append({"chunk": q, "removed": b"", "w1": prints[0][i].tobytes(), "w2": prints[1][i].tobytes(), "key": early[1][i].tobytes(), "doc": early[2][i].tobytes(), "first": early[3][i].tobytes()})
        k, d, a, b = (np.concatenate(x) for x in zip(*cut))
        out = []
        for q, i in _by_bucket(k):
            a_, b_, d_ = _union(d[i], a[i], b[i])
            out.append({"chunk": q, "removed": np.stack([d_, a_, b_]).astype(np.int64).tobytes()})
        return pa.Table.from_pylist(out + rest, _schema(OUT))

    return sent.where("bucket >= 0").groupBy("bucket").applyInArrow(run, OUT)


def _merge_shards(windows: DataFrame, length: int) -> DataFrame:
    """Across salted shards: equal windows meet by fingerprint range, and each
    shard's sorted run is looked up in the earliest of all by binary search."""
    kinds = {"w1": np.int64, "w2": np.int64, "key": np.int64, "doc": np.int64, "first": np.int64}

    def unfold(batches):
        for b in batches:
            for r in b.to_pylist():
                cols = [np.frombuffer(r[c], t) for c, t in kinds.items()]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(cols[0]), r["chunk"], np.int32)), *map(pa.array, cols)], names=["chunk", *kinds])

    def run(batches):
        got = [b for b in batches if b.num_rows]
        if not got:
            return
        table = pa.Table.from_batches(got)
        w1, w2, key, chunk, doc, first = (table.column(c).to_numpy() for c in ("w1", "w2", "key", "chunk", "doc", "first"))
        order = np.lexsort((first, doc, chunk, key, w2, w1))
        a, b = w1[order], w2[order]
        head = np.r_[True, (a[1:] != a[:-1]) | (b[1:] != b[:-1])]
        earliest = order[head]
        # w1 alone places a window among the heads; w2 tells apart the rare equals
        i = np.searchsorted(a[head], w1, "left")
        while True:
            off = (w2[earliest[np.minimum(i, len(earliest) - 1)]] != w2) & (w1[earliest[np.minimum(i, len(earliest) - 1)]] == w1)
            if not off.any():
                break
            i[off] += 1
        late = np.flatnonzero(earliest[i] != np.arange(len(w1)))
        out = []
        for q, j in _by_bucket(chunk[late].astype(np.int64)):
            z = late[j]
            a_, b_, d_ = _union(doc[z], first[z], first[z] + length)
            out.append({"chunk": q, "removed": np.stack([d_, a_, b_]).astype(np.int64).tobytes()})
        yield from pa.Table.from_pylist(out, _schema("chunk int, removed binary")).to_batches()

    flat = windows.mapInArrow(unfold, "chunk int, w1 long, w2 long, key long, doc long, first long")
    parts = max(int(windows.sparkSession.conf.get("spark.sql.shuffle.partitions")), 8)
    return flat.repartition(parts, "w1").mapInArrow(run, "chunk int, removed binary")


def removed_ranges(packed: DataFrame, length: int, buckets: int, hot: int) -> DataFrame:
    """(chunk, removed): int64 triples of document, start and end."""
    asked = _ask(packed, length, buckets)
    answers = materialise(_answer(asked, hot), "answers")
    sent = materialise(_send(packed, answers, length, buckets), "contexts")
    found = materialise(_resolve(sent, length, buckets), "ranges")
    merged = _merge_shards(found.where("w1 is not null").select("chunk", "w1", "w2", "key", "doc", "first"), length)
    return sent.where("bucket = -1").select("chunk", "removed").unionAll(found.where("w1 is null").select("chunk", "removed")).unionAll(merged)


def remove_repeats(df: DataFrame, length: int = 100, chunk_bytes: int = 16 << 20, hot: int = 4_000, id_col: str = "doc_id", text: str = "text", keep_bytes: bool = True, buckets: int | None = None) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256, spans (start and end
    of each removed range) and, with keep_bytes, the remaining bytes."""
    if length < GRAM + 2:
        raise ValueError(f"length is {GRAM + 2} at least")
    spark = df.sparkSession
    total = text_bytes(df, text)
    chunks = chunk_count(spark, total, chunk_bytes)
    buckets = buckets or max(int(spark.conf.get("spark.sql.shuffle.partitions")), total // 30_000_000, 1)
    packed = pack(df, chunks, id_col, text)
    ranges = removed_ranges(packed, length, buckets, hot)

    def run(key, left, right):
        chunk = Chunk(left)
        triples = [np.frombuffer(x, np.int64).reshape(3, -1) for x in right.column("removed").to_pylist() if x]
        d, a, b = np.concatenate(triples, axis=1) if triples else np.empty((3, 0), np.int64)
        a, b, d = _union(d, a, b)
        cuts = np.searchsorted(d, np.arange(len(chunk.ids) + 1))
        n_removed, n_spans, digest, spans, kept = [], [], [], [], []
        for i, t in enumerate(chunk.texts):
            own = list(zip(a[cuts[i] : cuts[i + 1]].tolist(), b[cuts[i] : cuts[i + 1]].tolist()))
            rest, at = [], 0
            for x, y in own:
                rest.append(t[at:x])
                at = y
            rest.append(t[at:])
            rest = b"".join(rest)
            n_removed.append(len(t) - len(rest))
            n_spans.append(len(own))
            digest.append(hashlib.sha256(rest).hexdigest())
            spans.append([{"start": x, "end": y} for x, y in own])
            kept.append(rest)
        cols = {"doc_id": pa.array(chunk.ids, pa.int64()), "n_bytes": pa.array(chunk.size), "n_removed": pa.array(n_removed, pa.int64()), "n_spans": pa.array(n_spans, pa.int64()), "kept_sha256": pa.array(digest, pa.string())}
        if keep_bytes:
            cols |= {"spans": pa.array(spans, pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))), "kept": pa.array(kept, pa.binary())}
        return pa.table(cols)

    schema = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + (", spans array<struct<start: long, end: long>>, kept binary" if keep_bytes else "")
    return packed.groupBy("chunk").cogroup(ranges.groupBy("chunk")).applyInArrow(run, schema)
