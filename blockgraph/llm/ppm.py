"""Prediction by partial matching over bytes.

The trie of byte contexts up to ``order`` symbols is kept as tables of byte
strings packed into longs: a context is a string without its last symbol, its
parent is the string without its first. A text starts in a context of
``order`` boundary bytes (0xFF, which UTF-8 never uses) and ends with one more,
so the code lengths of all texts are those of a proper model.

Escape estimation: with counts n over the successors of a context that are not
excluded, q of them distinct and N in all,
  method C: symbol n / (N + q), escape q / (N + q);
  method D: symbol (2n - 1) / (2N), escape q / (2N).
Symbol exclusion: successors seen in a longer context that escaped take no part
in the shorter ones. Below the empty context all symbols not excluded are
equally likely. A shorter context has all successors of a longer one, so what is
excluded depends on the longer context alone, and the code length of a symbol
in its full context is a function of one string of order + 1 bytes. This is
what makes the pretrained model a table: each distinct string is coded once.

Pretrained scoring on Spark. Texts are dealt into chunks of bounded size by a
hash. Each chunk sends its distinct strings and tokens with their training
counts, packed, never positions or texts. Strings are dealt by the last three bytes
of their context, so each task holds whole subtrees of the trie and no common pair
of letters fills one; the contexts of length 0 to 2 have at most 2 ** 24 counts,
whatever the corpus, and are broadcast. Each chunk gets
back the code lengths of its own strings, in the order that it knows, and scores
its texts. All counts cover
all training texts, and nothing is capped.

Adaptive scoring (``adaptive``) learns from each text while coding it, starting
from nothing.

Edge cases: a null text is empty and has only its end; null ids are scored and
train; repeated rows count each; an empty table gives an empty result; with no
training text all symbols are equally likely, and the base score of a token is
log10(0.5 / 0.5) = 0.
"""

from __future__ import annotations

import ctypes
import math
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import LARGE_ROWS, small_batches
from .common import LOWER_TABLE, as_text, chunk_count, discard, materialise, portions, text_bytes

END = 0xFF
#: Key of the end token in the word table; words hash to 63 bits above it.
END_KEY = -1


def adaptive_log10(data: bytes, order: int = 4, escape: str = "C") -> float:
    """Code length, as log10 of the probability, of one text that the model
    learns while it reads."""
    trie: dict[bytes, Counter] = defaultdict(Counter)
    symbols = bytes([END]) * order + data + bytes([END])
    total = 0.0
    for i in range(order, len(symbols)):
        total += symbol_log10(trie, symbols[i - order : i], symbols[i], escape)
        for k in range(order + 1):
            trie[symbols[i - k : i]][symbols[i]] += 1
    return total


def symbol_log10(trie, context: bytes, symbol: int, escape: str = "C") -> float:
    """log10 probability of a symbol after a context, by the definition."""
    out, excluded = 0.0, set()
    for k in range(len(context), -1, -1):
        seen = trie.get(context[len(context) - k :])
        if not seen:
            continue
        left = {s: n for s, n in seen.items() if s not in excluded}
        if not left:
            continue
        n, q = sum(left.values()), len(left)
        if symbol in left:
            return out + math.log10(left[symbol] / (n + q) if escape == "C" else (2 * left[symbol] - 1) / (2 * n))
        out += math.log10(q / (n + q) if escape == "C" else q / (2 * n))
        excluded |= set(left)
    return out - math.log10(256 - len(excluded))


def packed(data: np.ndarray, width: int) -> np.ndarray:
    """All substrings of the given width as longs, first byte highest."""
    n = len(data) - width + 1
    out = np.zeros(max(n, 0), np.int64)
    for j in range(width):
        out <<= 8
        out |= data[j : j + n]
    return out


def framed(texts: list[bytes], order: int) -> tuple[np.ndarray, np.ndarray]:
    """All texts with their boundary bytes in one array, and the number of
    symbols (bytes and one end) of each. Every text brings its own context, so
    the string that ends at a symbol starts order bytes before it."""
    pad = bytes([END]) * order
    blob = b"".join([x for t in texts for x in (pad, t, b"\xff")])
    return np.frombuffer(blob, np.uint8), np.array([len(t) + 1 for t in texts], np.int64)


def strings_of(texts: list[bytes], order: int) -> tuple[np.ndarray, np.ndarray]:
    """The string of each symbol, texts one after the other, and symbols a text."""
    data, sizes = framed(texts, order)
    grams = packed(data, order + 1)
    if not len(sizes):
        return grams, sizes
    # between two texts, order strings cross the boundary
    starts = np.cumsum(sizes + order) - (sizes + order)
    keep = np.ones(len(grams), bool)
    for k in range(1, order + 1):
        keep[starts[1:] - k] = False
    return grams[keep], sizes


def distinct(keys: np.ndarray, weights: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct keys and how often each occurs (or its weights' sum)."""
    if not len(keys):
        return keys, np.empty(0, np.int64)
    if weights is None:
        keys = np.sort(keys)
        at = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
        return keys[at], np.diff(np.r_[at, len(keys)])
    order = np.argsort(keys, kind="stable")
    keys = keys[order]
    at = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
    return keys[at], np.add.reduceat(weights[order], at)


class Tally:
    """Distinct keys with training counts, gathered in bounded steps."""

    def __init__(self):
        self.parts: list[tuple[np.ndarray, np.ndarray]] = []
        self.keys, self.counts = np.empty(0, np.int64), np.empty(0, np.int64)
        self.waiting = 0

    def add(self, keys: np.ndarray, train: bool) -> None:
        k, n = distinct(keys)
        self.parts.append((k, n if train else np.zeros(len(k), np.int64)))
        self.waiting += len(k)
        if self.waiting > 1_000_000 + len(self.keys) // 2:
            self.fold()

    def fold(self) -> None:
        parts = [(self.keys, self.counts), *self.parts]
        self.keys, self.counts = distinct(np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts]))
        self.parts, self.waiting = [], 0


def token_key(token: bytes) -> int:
    return xxhash.xxh64_intdigest(token) >> 1


def _text_slices(texts: list[bytes], flags: list[bool], step: int = 2 << 20):
    """Runs of texts with the same flag, of about step bytes."""
    for flag in (True, False):
        part, size = [], 0
        for t, f in zip(texts, flags):
            if f == flag:
                part.append(t)
                size += len(t)
                if size >= step:
                    yield flag, part
                    part, size = [], 0
        if part:
            yield flag, part


def _planes(x: np.ndarray) -> bytes:
    """The bytes of x by place, so that places that vary little meet."""
    return zstandard.compress(np.ascontiguousarray(x.view(np.uint8).reshape(-1, x.itemsize).T).tobytes(), 1)


def _from_planes(data: bytes, kind) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(zstandard.decompress(data), np.uint8).reshape(np.dtype(kind).itemsize, -1).T).view(kind).ravel()


def squeeze(x: np.ndarray) -> bytes:
    """Sorted integers as compressed steps."""
    return _planes(np.diff(x, prepend=np.int64(0)))


def unsqueeze(data: bytes) -> np.ndarray:
    return np.cumsum(_from_planes(data, np.int64))


def squeeze_values(x: np.ndarray) -> bytes:
    """Doubles, the shorter of two ways: as they are, or the distinct ones, most
    frequent first, and their numbers."""
    plain = bytes(4) + _planes(x)
    values, at, n = np.unique(x, return_inverse=True, return_counts=True)
    if 2 * len(values) > len(x):
        return plain
    by_count = np.argsort(-n, kind="stable")
    number = np.empty(len(values), np.uint32)
    number[by_count] = np.arange(len(values), dtype=np.uint32)
    table = _planes(values[by_count])
    return min(plain, len(table).to_bytes(4, "little") + table + _planes(number[at]), key=len)


def unsqueeze_values(data: bytes) -> np.ndarray:
    end = 4 + int.from_bytes(data[:4], "little")
    if end == 4:
        return _from_planes(data[4:], np.float64)
    return _from_planes(data[4:end], np.float64)[_from_planes(data[end:], np.uint32)]


STRINGS = "chunk int, bucket int, keys binary, counts binary"


def _bucket(keys: np.ndarray, buckets: int) -> np.ndarray:
    """By the last three bytes of the context."""
    tail = (keys >> 8 & 0xFFFFFF).astype(np.uint64)
    return ((tail * np.uint64(0x9E3779B1) >> np.uint64(11)) % np.uint64(buckets)).astype(np.int64)


def _token_bucket(keys: np.ndarray, buckets: int) -> np.ndarray:
    return keys % buckets  # the keys are hashes


def _packed(df: DataFrame, chunks: int, train: Column, id_col: str, text: str, hold_bytes: int = 16 << 20, only: tuple[int, int] = (1, 0)) -> DataFrame:
    """(chunk, ids, flags, sizes, blob): texts by chunk in compressed rows, about
    a third of their bytes; of the chunks with remainder only[1] to only[0]."""
    src = df.select(F.pmod(F.xxhash64(id_col, text), F.lit(chunks)).cast("int").alias("chunk"), F.col(id_col).alias("doc_id"), F.col(text).cast("string").alias("text"), F.coalesce(train, F.lit(False)).alias("train"))
    doc_type = dict(src.dtypes)["doc_id"]
    src = src.where(F.pmod(F.col("chunk"), F.lit(only[0])) == only[1])

    def run(batches):
        held: dict[int, tuple[list, list, list]] = {}
        weight, kind = 0, None

        def flush():
            for chunk in sorted(held):
                ids, flags, texts = held[chunk]
                yield pa.RecordBatch.from_arrays(
                    [pa.array([chunk], pa.int32()), pa.array([ids], pa.list_(kind)), pa.array([flags], pa.list_(pa.bool_())), pa.array([list(map(len, texts))], pa.list_(pa.int64())), pa.array([zstandard.compress(b"".join(texts), 1)], pa.binary())],
                    names=["chunk", "ids", "flags", "sizes", "blob"],
                )
            held.clear()

        for b in portions(batches):
            kind = b.column(1).type
            for chunk, d, t, f in zip(*(b.column(i).to_pylist() for i in range(4))):
                ids, flags, texts = held.setdefault(chunk, ([], [], []))
                ids.append(d)
                flags.append(f)
                texts.append(as_text(t))
                weight += len(texts[-1]) + 16
                if weight >= hold_bytes:
                    yield from flush()
                    weight = 0
        yield from flush()

    return src.mapInArrow(run, f"chunk int, ids array<{doc_type}>, flags array<boolean>, sizes array<long>, blob binary")


def _texts(table: pa.Table) -> tuple[list, list[bytes], list[bool]]:
    """Ids, texts and training flags of a chunk."""
    ids, texts, flags = [], [], []
    for r in table.select(["ids", "flags", "sizes", "blob"]).to_pylist():
        blob, at = zstandard.decompress(r["blob"]) if sum(r["sizes"]) else b"", 0
        ids += r["ids"]
        flags += r["flags"]
        for n in r["sizes"]:
            texts.append(blob[at : at + n])
            at += n
    return ids, texts, flags


def _own_tokens(texts: list[bytes], flags: list[bool]) -> tuple[np.ndarray, np.ndarray]:
    """Sorted keys of the tokens of some texts, the end first, with their
    training counts."""
    words: dict[bool, Counter] = {True: Counter(), False: Counter()}
    for t, f in zip(texts, flags):
        words[f].update(t.translate(LOWER_TABLE).split())
    train = words[True]
    tokens = list(train.keys() | words[False].keys())
    keys, counts = distinct(np.fromiter(map(token_key, tokens), np.int64, len(tokens)), np.fromiter((train.get(t, 0) for t in tokens), np.int64, len(tokens)))
    return np.r_[END_KEY, keys], np.r_[sum(flags), counts]


def _own_token_keys(texts: list[bytes]) -> np.ndarray:
    """The keys of ``_own_tokens``, without counts."""
    tokens: set[bytes] = set()
    for t in texts:
        tokens.update(t.translate(LOWER_TABLE).split())
    return np.r_[END_KEY, distinct(np.fromiter(map(token_key, tokens), np.int64, len(tokens)))[0]]


def _own_strings(texts: list[bytes], flags: list[bool], order: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct strings of some texts, with their training counts."""
    grams = Tally()
    for f, part in _text_slices(texts, flags):
        grams.add(strings_of(part, order)[0], f)
    grams.fold()
    return grams.keys, grams.counts


def _own_keys(texts: list[bytes], order: int) -> np.ndarray:
    """Sorted distinct strings of some texts, without counts, in bounded steps."""
    keys, parts, waiting = np.empty(0, np.int64), [], 0
    for _, part in _text_slices(texts, [True] * len(texts), 1 << 20):
        parts.append(distinct(strings_of(part, order)[0])[0])
        waiting += len(parts[-1])
        if waiting > 500_000 + len(keys) // 2:
            keys, parts, waiting = distinct(np.concatenate([keys, *parts]))[0], [], 0
    return distinct(np.concatenate([keys, *parts]))[0]


def _release() -> None:
    """Give back to the system what a worker has freed: a worker that is used
    again would keep what an earlier task took at its peak."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc only
    if trim is not None:
        trim(0)


def _shares(place: np.ndarray, buckets: int):
    """(bucket, positions in order) of the buckets that hold anything."""
    # a stable sort of shorts is by digits, several times as fast as that of longs
    by_place = np.argsort(place.astype(np.uint16) if buckets <= 1 << 16 else place, kind="stable")
    edge = np.searchsorted(place[by_place], np.arange(buckets + 1))
    for q in range(buckets):
        if edge[q] < edge[q + 1]:
            yield q, by_place[edge[q] : edge[q + 1]]


def _in_portions(table: pa.Table) -> pa.Table:
    """The same rows in small batches, each of which Spark takes in as a whole."""
    return pa.Table.from_batches(list(portions(table.to_batches(), 1 << 20)), table.schema)


def _chunk_rows(docs: DataFrame, order: int, buckets: int) -> DataFrame:
    """The distinct strings of every chunk, packed by bucket, with their counts
    in its training texts; from bucket ``buckets`` on the same for its tokens."""

    def run(key, table):
        _release()
        _, texts, flags = _texts(table)
        chunk, rows = key[0].as_py(), []
        for first, (keys, counts), place in ((buckets, _own_tokens(texts, flags), _token_bucket), (0, _own_strings(texts, flags, order), _bucket)):
            for q, i in _shares(place(keys, buckets), buckets):
                rows.append({"chunk": chunk, "bucket": first + q, "keys": squeeze(keys[i]), "counts": squeeze(np.cumsum(counts[i]))})
        return _in_portions(pa.Table.from_pylist(rows, pa.schema([("chunk", pa.int32()), ("bucket", pa.int32()), ("keys", pa.binary()), ("counts", pa.binary())])))

    return docs.groupBy("chunk").applyInArrow(run, STRINGS)


def _counts(data: bytes) -> np.ndarray:
    return np.diff(unsqueeze(data), prepend=np.int64(0))


def _near_root(strings: DataFrame, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """Training counts of all strings of three bytes (sorted strings, counts):
    2 ** 24 at most. Every task sends each of them once."""

    def run(batches):
        keys, counts = np.empty(0, np.int64), np.empty(0, np.int64)
        for b in batches:
            for k, n in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                k, n = distinct(unsqueeze(k) & 0xFFFFFF, _counts(n))
                keys, counts = distinct(np.r_[keys, k[n > 0]], np.r_[counts, n[n > 0]])
        yield pa.RecordBatch.from_arrays([pa.array(keys), pa.array(counts)], names=["three", "n"])

    rows = strings.where(F.col("bucket") < buckets).select("keys", "counts").mapInArrow(run, "three long, n long")
    got = rows.groupBy("three").agg(F.sum("n").alias("n")).toArrow()
    keys, counts = (got.column(c).to_numpy().astype(np.int64) for c in ("three", "n"))
    order = np.argsort(keys)
    return keys[order], counts[order]


def code_strings(keys: np.ndarray, counts: np.ndarray, order: int, three: tuple[np.ndarray, np.ndarray], escape: str = "C") -> np.ndarray:
    """log10 code probability of each distinct string (sorted keys of order + 1
    bytes). counts are training counts; a caller passes all strings that share
    their last three context bytes, so every longer context is complete. three:
    the strings of three bytes in all training texts and their counts."""
    symbol = keys & 255
    done = np.zeros(len(keys), bool)
    out = np.zeros(len(keys))
    # excluded successors of the longer context: how many, and their counts here
    q_ex, n_ex = np.zeros(len(keys), np.int64), np.zeros(len(keys), np.int64)
    tables = {}
    t_keys, t_counts = keys[counts > 0], counts[counts > 0]
    for k in range(order, 2, -1):
        tables[k] = (t_keys, t_counts)
        if k > 3:
            t_keys, t_counts = distinct(t_keys & ((1 << 8 * k) - 1), t_counts)
    for k in (2, 1, 0):
        tables[k] = three if k == 2 else distinct(tables[k + 1][0] & ((1 << 8 * (k + 1)) - 1), tables[k + 1][1])
    for k in range(order, -1, -1):
        g, n = tables[k]
        ctx = g >> 8
        at = np.flatnonzero(np.r_[True, ctx[1:] != ctx[:-1]]) if len(ctx) else np.empty(0, np.int64)
        c_keys, total, kinds = ctx[at], np.add.reduceat(n, at) if len(at) else n, np.diff(np.r_[at, len(g)]) if len(at) else at
        mine = keys & ((1 << 8 * (k + 1)) - 1)
        find = lambda table, want: (np.minimum(np.searchsorted(table, want), max(len(table) - 1, 0)), )
        if len(c_keys):
            (i,) = find(c_keys, mine >> 8)
            there = c_keys[i] == mine >> 8
            (j,) = find(g, mine)
            seen = g[j] == mine
            left, q = total[i] - n_ex, kinds[i] - q_ex
            live = there & ~done & (q > 0)
            hit = live & seen
            base = np.where(live, left + q if escape == "C" else 2 * left, 1)
            out[hit] += np.log10((n[j][hit] if escape == "C" else 2 * n[j][hit] - 1) / base[hit])
            done |= hit
            miss = live & ~seen
            out[miss] += np.log10(q[miss] / base[miss])
            q_ex = np.where(there, kinds[i], q_ex)
        if k > 0:
            # what this context's successors count in its parent
            p_keys, p_counts = tables[k - 1]
            if len(g):
                parent = g & ((1 << 8 * k) - 1)
                share = np.add.reduceat(p_counts[np.searchsorted(p_keys, parent)], at)
                n_ex = np.where(there, share[i], 0)
            else:
                n_ex = np.zeros(len(keys), np.int64)
    rest = ~done
    out[rest] -= np.log10(256 - q_ex[rest])
    assert len(symbol) == len(out)
    return out


def _coded(strings: DataFrame, buckets: int, order: int, escape: str, three: tuple[np.ndarray, np.ndarray]) -> DataFrame:
    """(chunk, bucket, values): code lengths of the strings a chunk has, in the
    order in which it has sent them."""
    sent = strings.sparkSession.sparkContext.broadcast(three)

    def run(key, table):
        parts = [(unsqueeze(k), _counts(n)) for k, n in zip(table.column("keys").to_pylist(), table.column("counts").to_pylist())]
        keys, counts = distinct(np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts]))
        value = code_strings(keys, counts, order, sent.value, escape)
        values = [squeeze_values(value[np.searchsorted(keys, p[0])]) for p in parts]
        return _in_portions(pa.table({"chunk": table.column("chunk"), "bucket": table.column("bucket"), "values": pa.array(values, pa.binary())}))

    return strings.where(F.col("bucket") < buckets).groupBy("bucket").applyInArrow(run, "chunk int, bucket int, values binary")


def _counted(strings: DataFrame, buckets: int) -> DataFrame:
    """(chunk, bucket, values): training counts, over all chunks, of the tokens
    a chunk has, in its order; and a row without values a bucket with its tokens
    (n) and distinct tokens (v) in training."""

    def run(key, table):
        parts = [(unsqueeze(k), _counts(n)) for k, n in zip(table.column("keys").to_pylist(), table.column("counts").to_pylist())]
        keys, counts = distinct(np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts]))
        values = [squeeze(np.cumsum(counts[np.searchsorted(keys, p[0])])) for p in parts]
        rest = [0] * len(parts)
        return _in_portions(pa.table({
            "chunk": pa.array([*table.column("chunk").to_pylist(), -1], pa.int32()), "bucket": pa.array([key[0].as_py()] * (len(parts) + 1), pa.int32()),
            "values": pa.array([*values, None], pa.binary()),
            "n": pa.array([*rest, int(counts.sum())], pa.int64()), "v": pa.array([*rest, int((counts > 0).sum())], pa.int64()),
        }))

    return strings.where(F.col("bucket") >= buckets).groupBy("bucket").applyInArrow(run, "chunk int, bucket int, values binary, n long, v long")


class StringTable:
    """Open-addressing lookup of longs, all queries at once."""

    def __init__(self, keys: np.ndarray, values: np.ndarray):
        self.bits = max(4, int(1.4 * len(keys)).bit_length())  # 0.36 to 0.72 full
        self.keys = np.full(1 << self.bits, -(1 << 62), np.int64)
        self.values = np.zeros(1 << self.bits)
        for first in range(0, len(keys), 1 << 18):
            self._put(keys[first : first + (1 << 18)], values[first : first + (1 << 18)])

    def _put(self, keys: np.ndarray, values: np.ndarray) -> None:
        left = np.arange(len(keys))
        at = self._slot(keys)
        while len(left):
            free = self.keys[at] == -(1 << 62)
            self.keys[at[free]] = keys[left[free]]  # of several, the last stays
            won = self.keys[at] == keys[left]
            self.values[at[won]] = values[left[won]]
            left, at = left[~won], (at[~won] + 1) & (len(self.keys) - 1)

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return (keys.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(64 - self.bits)).astype(np.int64)

    def get(self, keys: np.ndarray) -> np.ndarray:
        at = self._slot(keys)
        out = self.values[at]
        wrong = np.flatnonzero(self.keys[at] != keys)
        at = at[wrong]
        while len(wrong):
            at = (at + 1) & (len(self.keys) - 1)
            ok = self.keys[at] == keys[wrong]
            out[wrong[ok]] = self.values[at[ok]]
            wrong, at = wrong[~ok], at[~ok]
        return out


def _score_chunk(texts: list[bytes], table: StringTable, tokens: dict[int, float], unknown: float, order: int):
    """tokens: log10 probability by key; ``unknown`` is that of a token that
    training never saw, which no other has."""
    score = np.zeros(len(texts))
    first, size = 0, 0
    for i, t in enumerate(texts):
        size += len(t)
        if size >= 512 << 10 or i == len(texts) - 1:
            grams, sizes = strings_of(texts[first : i + 1], order)
            at = np.cumsum(sizes) - sizes
            score[first : i + 1] = np.add.reduceat(table.get(grams), at)
            first, size = i + 1, 0
    known: dict[bytes, float] = {}
    n_tokens, n_known, base = [], [], []
    end = tokens[END_KEY]
    for t in texts:
        words = t.translate(LOWER_TABLE).split()
        total, seen = end, int(end != unknown)
        for w in words:
            x = known.get(w)
            if x is None:
                x = known[w] = tokens[token_key(w)]
            total += x
            seen += x != unknown
        n_tokens.append(len(words) + 1)
        n_known.append(seen)
        base.append(total)
    return n_tokens, n_known, base, score


def score(df: DataFrame, train: Column, order: int = 6, escape: str = "D", chunk_bytes: int = 8 << 20, id_col: str = "doc_id", text: str = "text", turns: int = 2) -> DataFrame:
    """Pretrained scores of every row: doc_id, train, n_tokens, n_known,
    train_tokens, base_score, score. ``train`` says which rows to learn from.
    Code lengths go back to the chunks in ``turns``, each of which scores a part
    of the chunks, so that only that part of them is shuffled at a time."""
    if not 2 <= order <= 6:
        raise ValueError("order is from 2 to 6")
    with small_batches(df.sparkSession):  # all parts are written before this ends
        return _score(df, train, order, escape, chunk_bytes, id_col, text, turns)


def _score(df: DataFrame, train: Column, order: int, escape: str, chunk_bytes: int, id_col: str, text: str, turns: int) -> DataFrame:
    spark = df.sparkSession
    size = text_bytes(df, text)
    chunks = chunk_count(spark, size, chunk_bytes)
    buckets = max(int(spark.conf.get("spark.sql.shuffle.partitions")), size // (16 << 20))
    docs = _packed(df, chunks, train, id_col, text)
    strings = materialise(_chunk_rows(docs, order, buckets), "strings", options=LARGE_ROWS)
    three = _near_root(strings, buckets)
    words = materialise(_counted(strings, buckets), "tokens", options=LARGE_ROWS)
    known = words.where("values is null").agg(F.sum("n").alias("n"), F.sum("v").alias("v")).first()
    total, vocabulary = known.n or 0, known.v or 0
    coded = materialise(_coded(strings, buckets, order, escape, three), "coded", options=LARGE_ROWS)
    discard(strings)
    values = coded.unionAll(words.where("values is not null").select("chunk", "bucket", "values"))
    doc_type = dict(df.dtypes)[id_col]

    scale = np.float64(total + 0.5 * (vocabulary + 1))

    def run(key, left, right):
        _release()
        kind = left.schema.field("ids").type.value_type
        ids, texts, flags = _texts(left)
        n_tokens, n_known, base, got = [], [], [], []
        if texts:
            sent = dict(zip(right.column("bucket").to_pylist(), right.column("values").to_pylist()))
            del left, right
            keys = _own_token_keys(texts)
            lengths = np.empty(len(keys))
            for q, i in _shares(_token_bucket(keys, buckets), buckets):
                lengths[i] = np.log10((_counts(sent[buckets + q]) + 0.5) / scale)
            tokens = dict(zip(keys.tolist(), lengths.tolist()))
            keys = _own_keys(texts, order)
            lengths = np.empty(len(keys))
            for q, i in _shares(_bucket(keys, buckets), buckets):
                lengths[i] = unsqueeze_values(sent.pop(q))
            table = StringTable(keys, lengths)
            del keys, lengths, sent, i
            n_tokens, n_known, base, got = _score_chunk(texts, table, tokens, float(np.log10((np.int64(0) + 0.5) / scale)), order)
        return pa.table({
            "doc_id": pa.array(ids, kind), "train": pa.array(flags, pa.bool_()),
            "n_tokens": pa.array(n_tokens, pa.int64()), "n_known": pa.array(n_known, pa.int64()), "train_tokens": pa.array([total] * len(texts), pa.int64()),
            "base_score": pa.array(base, pa.float64()), "score": pa.array(got, pa.float64()),
        })

    schema = f"doc_id {doc_type}, train boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"
    out = None
    tasks = 4 * -(-chunks // turns)  # few tasks get more than one chunk, which they would hold at once
    for turn in range(turns):
        mine = F.pmod(F.col("chunk"), F.lit(turns)) == turn
        left, right = _packed(df, chunks, train, id_col, text, only=(turns, turn)), values.where(mine)
        part = left.repartition(tasks, "chunk").groupBy("chunk").cogroup(right.repartition(tasks, "chunk").groupBy("chunk")).applyInArrow(run, schema)
        part = materialise(part, "scores")
        out = part if out is None else out.unionAll(part)
    discard(coded, words)
    return out


def adaptive(df: DataFrame, order: int = 4, escape: str = "C", id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, n_bytes, score): each text coded by a model that starts empty."""

    def run(batches):
        for b in batches:
            data = [as_text(t) for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array([len(x) for x in data], pa.int64()), pa.array([adaptive_log10(x, order, escape) for x in data], pa.float64())], names=["doc_id", "n_bytes", "score"]
            )

    src = df.select(F.col(id_col).alias("doc_id"), F.col(text).cast("string").alias("text"))
    return src.mapInArrow(run, f"doc_id {src.dtypes[0][1]}, n_bytes long, score double")
