"""Benchmark decontamination by latent semantic retrieval.

Words are in lower case; punctuation separates them. The vocabulary is that of
the benchmark; words in more than ``max_df`` of all corpus blocks are left out
as stop words (but for the ``rarest`` of each passage), and counts over all
documents give the idf. Documents are
cut into overlapping windows of ``3 * block`` words, one at each block, so that
every benchmark passage of up to ``2 * block`` words lies whole in some window
(longer items are cut into passages).

A randomised SVD of the matrix of corpus windows and benchmark passages gives
the latent space: each pass over the rows multiplies by the current basis and
sums the products by term, a power pass sharpens it. Its corpus rows are the
windows that share ``min_terms`` vocabulary words with some passage; the rest
has nothing of the directions that tell passages apart. The benchmark rows are
weighted up to the mass of the corpus rows, so their directions are kept.

Candidates come from the latent space alone: every window of every document
that holds a vocabulary word is placed in it, and is a candidate for all passages
with which its cosine reaches ``min_cosine``. What shares only stop words with a
passage, or so few of its words among other passages' words that the cosine stays
below, is not found; tests measure the recall against brute force. For each, the longest common subsequence of words decides: a
leak covers ``strong`` of the passage's words in order, or ``weak`` of them
and ``answer_share`` of the answer, the passage's last ``answer_words`` words.

The benchmark is a query set against all rows; it passes through the driver,
``items_at_once`` items at a time, each with a space of its own, and is compared
in blocks. Texts are cut into words once: all steps after that read the numbers of
their words in the benchmark's vocabulary (two bytes a word), which also decide the
common subsequences, so candidates are never stored nor joined.

Edge cases: null or empty documents and items have no windows or passages;
items without a word in the vocabulary can't be found; equal items are reported
each; repeated documents are reported once for each id; very long texts are read whole;
an empty table gives an
empty result; extra columns are ignored.
"""

from __future__ import annotations

from collections import defaultdict
from itertools import chain, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, materialise, own, portions

PUNCTUATION = b".,;:!?\"'`()[]{}*#$%&|<>-_/\\=+~^@"
OTHER_PUNCTUATION = "«»“”‘’„…–—¿¡"
_SPACED = bytes(32 if c in PUNCTUATION else c for c in range(256))


def raw_words(text: str) -> list[bytes]:
    """Lower-case words in UTF-8; punctuation separates words."""
    if not text.isascii():
        for c in OTHER_PUNCTUATION:
            text = text.replace(c, " ")
    return text.lower().encode("utf-8", "surrogatepass").translate(_SPACED).split()


def words_of(text: str | None) -> list[str]:
    return [w.decode("utf-8", "surrogatepass") for w in raw_words(text or "")]


def ids_of(words: list[bytes], vocabulary: dict[bytes, int]) -> np.ndarray:
    """Terms of the words, -1 outside the vocabulary."""
    return np.fromiter(map(vocabulary.get, words, repeat(-1)), np.int32, len(words))


def lcs_mask(a: list, b: list) -> list[int]:
    """Positions of a that a longest common subsequence of a and b uses."""
    where: dict = defaultdict(int)
    for i, w in enumerate(a):
        where[w] |= 1 << i
    full = (1 << len(a)) - 1
    v, rows = full, []
    for w in b:
        m = where.get(w, 0)
        u = v & m
        v = ((v + u) | (v - u)) & full
        rows.append(v)
    # walk back: a zero bit in a row marks a step of the length profile
    out, i, j = [], len(a) - 1, len(b) - 1
    while i >= 0 and j >= 0:
        if rows[j] >> i & 1:  # no step here: position i adds nothing
            i -= 1
        elif j > 0 and not rows[j - 1] >> i & 1:
            j -= 1
        else:
            out.append(i)
            i -= 1
            j -= 1
    return out[::-1]


def lcs_length(a_where: dict, n: int, b: list) -> int:
    """Length only; a as bit positions of each word."""
    full = (1 << n) - 1
    v = full
    for w in b:
        m = a_where.get(w)
        if m:
            u = v & m
            v = ((v + u) | (v - u)) & full
    return n - v.bit_count()


class Passages:
    """The benchmark in passages of up to 2 * block words."""

    def __init__(self, items: list[tuple[int, str]], block: int):
        self.words, self.item = [], []
        for item, text in items:
            w = words_of(text)
            n = max(1, -(-len(w) // (2 * block)))
            for i in range(n if w else 0):
                self.words.append(w[len(w) * i // n : len(w) * (i + 1) // n])
                self.item.append(item)
        self.where = []
        for w in self.words:
            at: dict[str, int] = defaultdict(int)
            for i, x in enumerate(w):
                at[x] |= 1 << i
            self.where.append(dict(at))

    def vocabulary(self) -> list[str]:
        return sorted({w for p in self.words for w in p})


#: Bytes of word numbers that are worked on at once.
PORTION = 1 << 19


def _dtype(vocabulary: dict) -> np.dtype:
    return np.dtype("<i2" if len(vocabulary) < 1 << 15 else "<i4")


def numbered(docs: DataFrame, vocabulary: dict[bytes, int]) -> DataFrame:
    """(doc_id, ids): the words of each text by their numbers in the vocabulary,
    -1 outside it, as bytes."""
    sent = docs.sparkSession.sparkContext.broadcast(vocabulary)

    def run(batches):
        vocab = sent.value
        kind = _dtype(vocab)
        for b in portions(batches):
            ids = [ids_of(raw_words(t), vocab).astype(kind).tobytes() if t else b"" for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(ids, pa.binary())], names=["doc_id", "ids"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, ids binary")


def _ids(column, kind: np.dtype) -> list[np.ndarray]:
    return [np.frombuffer(x, kind).astype(np.int32) for x in column.to_pylist()]


def block_counts(texts: DataFrame, vocabulary: dict, block: int) -> tuple[np.ndarray, int]:
    """In how many blocks of all documents each term occurs, and all blocks."""
    terms, kind = len(vocabulary), _dtype(vocabulary)

    def run(batches):
        df, n = np.zeros(terms, np.int64), 0
        for b in portions(batches, PORTION):
            at, term = [], []
            for ids in _ids(b.column(0), kind):
                hit = np.flatnonzero(ids >= 0)
                at.append(hit // block + n)
                term.append(ids[hit])
                n += -(-len(ids) // block)
            if at:
                df += np.bincount(np.unique(np.concatenate(at) * terms + np.concatenate(term)) % terms, minlength=terms)
        hit = np.flatnonzero(df)
        yield pa.RecordBatch.from_arrays([pa.array(np.r_[hit, -1].astype(np.int32)), pa.array(np.r_[df[hit], n])], names=["term", "n"])

    out = texts.select("ids").mapInArrow(run, "term int, n long").groupBy("term").agg(F.sum("n").alias("n")).collect()
    df = np.zeros(terms, np.int64)
    total = 0
    for r in out:
        if r.term < 0:
            total = r.n
        else:
            df[r.term] = r.n
    return df, total


def shared_windows(docs: list[np.ndarray], block: int, lists: tuple[np.ndarray, np.ndarray], need: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(document, window) of those that share enough distinct terms with some
    passage. lists: offsets and passages of each term."""
    off, passages = lists
    size = np.array([len(x) for x in docs], np.int64)
    doc = np.repeat(np.arange(len(docs)), size)
    term = np.concatenate(docs) if docs else np.empty(0, np.int32)
    pos = np.arange(len(term)) - np.repeat(np.cumsum(size) - size, size)
    hit = np.flatnonzero(term >= 0)
    doc, term, pos = doc[hit], term[hit].astype(np.int64), pos[hit]
    n_windows = np.maximum(1, -(-(size - 2 * block) // block))
    most = int(n_windows.max()) if len(size) else 1
    # each word lies in up to three windows, each term in some passages
    w = (pos // block)[:, None] - np.arange(3)[None, :]
    i, j = np.nonzero((w >= 0) & (w < n_windows[doc][:, None]))
    place, term = doc[i] * most + w[i, j], term[i]
    n = (off[1:] - off[:-1])[term]
    k = np.repeat(np.arange(len(term)), n)
    p = passages[np.arange(len(k)) - np.repeat(np.cumsum(n) - n, n) + off[term][k]]
    pair = place[k] * len(need) + p
    key = np.unique(pair * np.int64(len(off)) + term[k]) // len(off)
    at = np.flatnonzero(np.r_[True, key[1:] != key[:-1]]) if len(key) else np.empty(0, np.int64)
    count, key = np.diff(np.r_[at, len(key)]), key[at]
    places = np.unique(key[count >= need[key % len(need)]] // len(need))
    return places // most, places % most


def windows(texts: DataFrame, kind: np.dtype, term_of: np.ndarray, block: int, lists: tuple[np.ndarray, np.ndarray], need: np.ndarray) -> DataFrame:
    """(terms array<int>): windows with enough terms of one passage. term_of: the
    term of each word of the vocabulary, and at last of the others, -1 if none."""
    sent = texts.sparkSession.sparkContext.broadcast((term_of, lists, need))

    def run(batches):
        term_of, lists, need = sent.value
        for b in portions(batches, PORTION):
            ids = [term_of[x] for x in _ids(b.column(0), kind)]
            terms = []
            for d, w in zip(*(x.tolist() for x in shared_windows(ids, block, lists, need))):
                got = ids[d][w * block : (w + 3) * block]
                terms.append(got[got >= 0])
            yield pa.RecordBatch.from_arrays([pa.array(terms, pa.list_(pa.int32()))], names=["terms"])

    return texts.select("ids").mapInArrow(run, "terms array<int>")


def all_windows(ids: list[np.ndarray], block: int, weighted: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text, start, place): every window that holds a term, and where its terms
    put it in the latent space, to a factor that a cosine leaves out. ``weighted``
    is the place of each term. A window is three blocks, so blocks are placed
    once and added up."""
    size = np.array([len(x) for x in ids], np.int64)
    blocks = np.maximum(3, -(-size // block))  # short texts have empty blocks
    first = np.cumsum(blocks) - blocks
    term = np.concatenate(ids) if ids else np.empty(0, np.int32)
    hit = np.flatnonzero(term >= 0)
    text = np.repeat(np.arange(len(ids)), size)[hit]
    of = first[text] + (hit - (np.cumsum(size) - size)[text]) // block
    place = np.zeros((int(blocks.sum()), weighted.shape[1]), np.float32)
    at = np.flatnonzero(np.r_[True, of[1:] != of[:-1]]) if len(of) else of
    # the first terms of all blocks, then their second ones and so on: a block
    # has ``block`` of them at most, and no block is met twice in a step
    nth = np.arange(len(of)) - np.repeat(at, np.diff(np.r_[at, len(of)]))
    turn = np.argsort(nth, kind="stable")
    edges = np.searchsorted(nth[turn], np.arange(block + 1))
    for a, b in zip(edges, edges[1:]):
        place[of[turn[a:b]]] += weighted[term[hit[turn[a:b]]]]
    held = np.zeros(len(place), bool)
    held[of] = True
    text = np.repeat(np.arange(len(ids)), blocks - 2)
    start = np.arange(len(text)) - np.repeat(np.cumsum(blocks - 2) - (blocks - 2), blocks - 2)
    b = first[text] + start
    keep = np.flatnonzero(held[b] | held[b + 1] | held[b + 2])
    b = b[keep]
    return text[keep], start[keep] * block, place[b] + place[b + 1] + place[b + 2]


def _rows(batch_terms: pa.ListArray, idf: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Offsets, terms and weights of normalised TF-IDF rows (a repeated term
    stands as often as it occurs)."""
    off = batch_terms.offsets.to_numpy().astype(np.int64)
    terms = batch_terms.values.to_numpy()[off[0] : off[-1]]
    off = off - off[0]
    n = len(off) - 1
    row = np.repeat(np.arange(n), np.diff(off))
    key, count = np.unique(row * len(idf) + terms, return_counts=True)
    norm = np.sqrt(np.bincount(key // len(idf), (count * idf[key % len(idf)]) ** 2, n))
    return off, terms, idf[terms] / np.maximum(norm, 1e-12)[row]


def _multiply(off: np.ndarray, terms: np.ndarray, w: np.ndarray, basis: np.ndarray) -> np.ndarray:
    out = np.zeros((len(off) - 1, basis.shape[1]), np.float32)
    full = np.flatnonzero(np.diff(off))
    if len(full):
        out[full] = np.add.reduceat(basis[terms] * w[:, None].astype(np.float32), off[full], axis=0)
    return out


def _summed(key, table):
    """Parts of one slice added up."""
    total = sum(np.frombuffer(p, np.float32).astype(float) for p in table.column("part").to_pylist())
    first = table.slice(0, 1).drop_columns(["part", "n"])
    return first.append_column("part", pa.array([total.astype(np.float32).tobytes()], pa.binary())).append_column("n", pa.array([sum(table.column("n").to_pylist())], pa.int64()))


def _gram_product(rows: DataFrame, idf: np.ndarray, basis: np.ndarray, slices: int = 16, fan_in: int = 64) -> tuple[np.ndarray, float]:
    """A'A times the basis, summed over all rows, and the rows' number. A task
    sends one terms x rank matrix in slices; ``fan_in`` tasks' slices are added
    first, then those sums, so the driver gets one matrix whatever the tasks."""
    sent = rows.sparkSession.sparkContext.broadcast((idf, basis))

    def run(batches):
        from pyspark import TaskContext

        idf, basis = sent.value
        total, n = np.zeros(basis.shape), 0
        for b in batches:
            if not b.num_rows:
                continue
            off, terms, w = _rows(b.column(0), idf)
            y = _multiply(off, terms, w, basis)
            order = np.argsort(terms, kind="stable")
            t = terms[order]
            at = np.flatnonzero(np.r_[True, t[1:] != t[:-1]])
            row = np.repeat(np.arange(len(off) - 1), np.diff(off))[order]
            total[t[at]] += np.add.reduceat(y[row] * w[order][:, None].astype(np.float32), at, axis=0)
            n += b.num_rows
        parts = [p.astype(np.float32).tobytes() for p in np.array_split(total, slices)]
        node = TaskContext.get().partitionId() // fan_in
        yield pa.RecordBatch.from_arrays([pa.array([node] * slices, pa.int32()), pa.array(range(slices), pa.int32()), pa.array(parts, pa.binary()), pa.array([n] + [0] * (slices - 1), pa.int64())], names=["node", "slice", "part", "n"])

    parts = rows.select("terms").mapInArrow(run, "node int, slice int, part binary, n long")
    some = parts.groupBy("node", "slice").applyInArrow(_summed, "node int, slice int, part binary, n long")
    whole = some.select("slice", "part", "n").groupBy("slice").applyInArrow(_summed, "slice int, part binary, n long").collect()
    total, n = np.zeros(basis.shape), sum(r.n for r in whole)
    edges = np.cumsum([0, *map(len, np.array_split(np.empty(len(basis)), slices))])
    for r in whole:
        total[edges[r.slice] : edges[r.slice + 1]] = np.frombuffer(r.part, np.float32).reshape(-1, basis.shape[1])
    return total, n


def latent_basis(rows: DataFrame, bench_rows: list[np.ndarray], idf: np.ndarray, rank: int, passes: int = 1, oversample: int = 8, seed: int = 11) -> np.ndarray:
    """terms x rank: leading right singular vectors of corpus rows and
    benchmark rows, by a randomised range finder with power passes."""
    terms = len(idf)
    width = min(rank + oversample, terms)
    basis = np.linalg.qr(np.random.default_rng(seed).standard_normal((terms, width)))[0].astype(np.float32)
    bench = pa.array([x.tolist() for x in bench_rows], pa.list_(pa.int32()))
    off, t, w = _rows(bench, idf)
    dense = np.zeros((len(bench_rows), terms), np.float32)
    np.add.at(dense, (np.repeat(np.arange(len(bench_rows)), np.diff(off)), t), w)
    for last in range(passes + 1):
        product, n = _gram_product(rows, idf, basis)
        up = max(1.0, n / max(1, len(bench_rows)))
        product += up * (dense.T @ (dense @ basis))
        if last < passes:
            basis = np.linalg.qr(product)[0].astype(np.float32)
    values, turn = np.linalg.eigh((basis.T @ product + (basis.T @ product).T) / 2)
    return (basis @ turn[:, np.argsort(-values)[:rank]]).astype(np.float32)


SCHEMA = "doc_id long, item_id long, cosine double, lcs_ratio double, answer_ratio double"


def find_leaks(
    docs: DataFrame, benchmark: DataFrame, block: int = 32, max_df: float = 0.005, min_terms: int = 3, rarest: int = 8, rank: int = 128, min_cosine: float = 0.4,
    strong: float = 0.7, weak: float = 0.6, answer_words: int = 8, answer_share: float = 0.75, items_at_once: int = 20_000,
) -> DataFrame:
    """(doc_id, item_id, cosine, lcs_ratio, answer_ratio): the best window of
    each document and item that passes the checks."""
    spark, out, part = docs.sparkSession, None, []
    items = benchmark.where("item_id is not null and text is not null").select(F.col("item_id").cast("long").alias("item_id"), "text").orderBy("item_id", "text")
    options = (block, max_df, min_terms, rarest, rank, min_cosine, strong, weak, answer_words, answer_share)
    for r in chain(items.toLocalIterator(), [None]):
        if r is not None:
            part.append((r.item_id, r.text))
        if part and (r is None or len(part) == items_at_once):
            found = _leaks_of(docs, part, *options)
            out, part = found if out is None else out.unionAll(found), []
    if out is None:
        return spark.createDataFrame([], SCHEMA)
    return out.groupBy("doc_id", "item_id").agg(*(F.max(c).alias(c) for c in ("cosine", "lcs_ratio", "answer_ratio")))


def _leaks_of(docs, items, block, max_df, min_terms, rarest, rank, min_cosine, strong, weak, answer_words, answer_share) -> DataFrame:
    """The leaks of some items, perhaps several of a document and item."""
    spark = docs.sparkSession
    passages = Passages(items, block)
    vocabulary = {w: i for i, w in enumerate(passages.vocabulary())}
    if not vocabulary:
        return spark.createDataFrame([], SCHEMA)
    kind = _dtype(vocabulary)
    texts = materialise(numbered(docs, {w.encode("utf-8", "surrogatepass"): i for w, i in vocabulary.items()}), "words")
    df, blocks = block_counts(texts, vocabulary, block)
    # a passage that has leaked everywhere makes its own words common: the
    # rarest of each passage always stay
    stay = {w for p in passages.words for w in sorted(set(p), key=lambda w: (df[vocabulary[w]], w))[:rarest]}
    kept = [w for w, i in vocabulary.items() if w in stay or df[i] <= max(max_df * blocks, 5)]
    idf = np.log((1 + blocks) / (1 + df[[vocabulary[w] for w in kept]])) + 1
    terms = {w: i for i, w in enumerate(kept)}
    term_of = np.full(len(vocabulary) + 1, -1, np.int32)
    term_of[[vocabulary[w] for w in kept]] = np.arange(len(kept))
    mine = [np.array([terms[w] for w in p if w in terms], np.int32) for p in passages.words]
    distinct = [np.unique(x) for x in mine]
    need = np.array([min(min_terms, len(x)) for x in distinct])
    flat = np.concatenate(distinct)
    by_term = np.argsort(flat, kind="stable")
    off = np.searchsorted(flat[by_term], np.arange(len(kept) + 1))
    rows = materialise(windows(texts, kind, term_of, block, (off, np.repeat(np.arange(len(mine)), [len(x) for x in distinct])[by_term]), need), "windows")
    basis = latent_basis(rows, mine, idf, min(rank, len(kept)))
    discard(rows)
    off, t, w = _rows(pa.array([x.tolist() for x in mine], pa.list_(pa.int32())), idf)
    target = _multiply(off, t, w, basis)
    size = np.linalg.norm(target, axis=1)
    target = np.where(size[:, None] > 0, target / np.maximum(size, 1e-12)[:, None], 0).astype(np.float32)
    weighted = (basis * idf[:, None]).astype(np.float32)
    spelled = [[vocabulary[w] for w in p] for p in passages.words]  # what is no word of the vocabulary matches nothing
    where = [{vocabulary[w]: bits for w, bits in at.items()} for at in passages.where]
    sent = spark.sparkContext.broadcast((term_of, weighted, target, spelled, where, passages.item))

    def run(batches):
        term_of, weighted, target, spelled, where, item = sent.value
        for b in portions(batches, PORTION):
            names, ids = b.column(0).to_pylist(), _ids(b.column(1), kind)
            doc, start, places = all_windows([term_of[x] for x in ids], block, weighted)
            best: dict[tuple[int, int], tuple] = {}
            for a in range(0, len(doc), 8192):
                y = places[a : a + 8192]
                y /= np.maximum(np.linalg.norm(y, axis=1), 1e-12)[:, None]
                for first in range(0, len(target), 1024):
                    cos = y @ target[first : first + 1024].T
                    for i, p in zip(*(x.tolist() for x in np.nonzero(cos >= min_cosine))):
                        q, d = first + p, int(doc[a + i])
                        text = ids[d][start[a + i] : start[a + i] + 3 * block].tolist()
                        n = len(spelled[q])
                        ratio = lcs_length(where[q], n, text) / n
                        if ratio < weak:
                            continue
                        tail = max(1, min(answer_words, n))
                        answer = sum(x >= n - tail for x in lcs_mask(spelled[q], text)) / tail
                        if ratio >= strong or answer >= answer_share:
                            k = (names[d], item[q])
                            best[k] = max(best.get(k, (0,)), (ratio, answer, float(cos[i, p])))
            cols = list(zip(*((d, q, c, r, x) for (d, q), (r, x, c) in best.items()))) or [(), (), (), (), ()]
            types = (pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.float64())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types)], names=["doc_id", "item_id", "cosine", "lcs_ratio", "answer_ratio"])

    return texts.where("doc_id is not null").select("doc_id", "ids").mapInArrow(run, SCHEMA)


def remove_leaks(docs: DataFrame, benchmark: DataFrame, broadcast_ids: int = 500_000, **options) -> DataFrame:
    """The documents without a leak; those without an id stay."""
    ids = materialise(find_leaks(docs, benchmark, **options).select("doc_id").distinct(), "leaks")
    return docs.join(F.broadcast(ids) if ids.count() <= broadcast_ids else ids, "doc_id", "left_anti").select(*own(docs))
