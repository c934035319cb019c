"""Searches over one segment: vertex search in memory, vertex and block search
on blocks, for the k nearest and for a radius. All reads of blocks are counted.
"""

from __future__ import annotations

import heapq
import io
import math
import time
from bisect import bisect_right
from itertools import chain, islice
from dataclasses import dataclass, field
from functools import cached_property, partial

import numpy as np

from . import pq
from .graph import keep_nearest


@dataclass
class Segment:
    """The index of a segment. Rows are in the order of their ids."""

    ids: np.ndarray
    vecs: np.ndarray
    nbrs: np.ndarray
    block: np.ndarray
    metric: str
    entry: int
    book: list = field(default_factory=list)
    codes: np.ndarray | None = None
    nav_rows: np.ndarray | None = None
    nav_nbrs: np.ndarray | None = None
    nav_entry: int = -1
    hot: frozenset = frozenset()

    def __post_init__(self):
        order = np.argsort(self.block, kind="stable")
        at = np.searchsorted(self.block[order], np.arange((self.block.max() if len(self.block) else -1) + 2))
        self.members = [order[a:b] for a, b in zip(at, at[1:])]

    @cached_property
    def near_lists(self) -> list[list[int]]:
        """Neighbours of all rows, as lists."""
        return [[v for v in x if v >= 0] for x in self.nbrs.tolist()]

    @cached_property
    def member_lists(self) -> list[list[int]]:
        return [m.tolist() for m in self.members]

    @cached_property
    def code_places(self) -> np.ndarray:
        """Where the codes of all rows are in a flat table of ``lookup``."""
        return self.codes.astype(np.intp) + np.arange(self.codes.shape[1])[None, :] * max(map(len, self.book))

    def pack(self) -> bytes:
        buffer = io.BytesIO()
        arrays = {"ids": self.ids, "vecs": self.vecs, "nbrs": self.nbrs, "block": self.block, "codes": self.codes, "nav_rows": self.nav_rows, "nav_nbrs": self.nav_nbrs}
        arrays = {k: v for k, v in arrays.items() if v is not None} | {f"book{i}": c for i, c in enumerate(self.book)}
        np.savez(buffer, meta=np.array([self.entry, self.nav_entry, len(self.book)]), hot=np.array(sorted(self.hot), np.int64), metric=np.array(self.metric), **arrays)
        return buffer.getvalue()

    @staticmethod
    def unpack(data: bytes) -> Segment:
        z = np.load(io.BytesIO(data))
        entry, nav_entry, books = z["meta"].tolist()
        get = lambda k: z[k] if k in z.files else None
        return Segment(z["ids"], z["vecs"], z["nbrs"], z["block"], str(z["metric"]), entry, [z[f"book{i}"] for i in range(books)], get("codes"), get("nav_rows"), get("nav_nbrs"), nav_entry, frozenset(z["hot"].tolist()))


@dataclass
class Options:
    cand_size: int = 40
    prune_ratio: float = 0.3
    pipelined: bool = True
    routing: str = "pq"  # or "exact"
    beam_width: int = 1
    navigator: bool = True
    nav_cand_size: int = 10
    n_entry: int = 4
    cache: bool = False
    result_scope: str = "survivors"  # or "block"
    keep_blocks: str = "none"  # "last" or "all": buffered blocks cost nothing
    grow_ratio: float = 0.5
    rows: bool = False  # trace rows


@dataclass
class Found:
    rows: list
    dists: list
    ios: int = 0
    hops: int = 0
    nav_hops: int = 0
    restarts: int = 0
    used: int = 0
    loaded: int = 0
    blocks: int = 0
    util: float = 0.0  # summed over blocks: used vertices over all in it
    rounds: int = 0
    io_s: float = 0.0
    total_s: float = 0.0
    trace: list = field(default_factory=list)


COUNTERS = ("ios", "hops", "nav_hops", "restarts", "rounds", "used", "loaded", "blocks", "util")


def added(total: Found, f: Found) -> Found:
    """f's answers with the costs of both."""
    for n in (*COUNTERS, "io_s", "total_s"):
        setattr(f, n, getattr(total, n) + getattr(f, n))
    f.trace = total.trace + f.trace
    return f


def only(f: Found, visible: np.ndarray) -> Found:
    """f without the answers that aren't visible."""
    keep = [(r, d) for r, d in zip(f.rows, f.dists) if visible[r]]
    f.rows, f.dists = [r for r, _ in keep], [d for _, d in keep]
    return f


def exact(seg: Segment, q: np.ndarray, rows) -> np.ndarray:
    """Distances of a query to some rows."""
    v = seg.vecs[rows]
    if seg.metric == "ip":
        return -(v @ q)
    if seg.metric == "cosine":
        return 1 - (v @ q) / np.sqrt(np.einsum("ij,ij->i", v, v) * (q @ q))
    d = v - q
    d = np.einsum("ij,ij->i", d, d)
    return np.sqrt(d) if seg.metric == "l2" else d


def vertex_in_memory(nbrs: np.ndarray, dist, entry: int, width: int) -> tuple[list[tuple[float, int]], int]:
    """Best-first search with a list of the given width; the list and the hops.
    Width 1 is plain descent."""
    pool = [(float(dist(np.array([entry]))[0]), entry)]
    seen, done = {entry}, set()
    first = 0  # all of the pool before this are done
    while True:
        while first < len(pool) and pool[first][1] in done:
            first += 1
        if first == len(pool):
            return pool, len(done)
        u = pool[first][1]
        done.add(u)
        new = [v for v in np.asarray(nbrs[u]).tolist() if v >= 0 and v not in seen]
        if new:
            seen.update(new)
            first = keep_nearest(pool, list(zip(dist(np.array(new)).tolist(), new)), width, first)


def entry_rows(seg: Segment, q: np.ndarray, o: Options) -> tuple[list[int], int]:
    if o.navigator and seg.nav_rows is not None and len(seg.nav_rows):
        rows = seg.nav_rows
        pool, hops = vertex_in_memory(seg.nav_nbrs, lambda js: exact(seg, q, rows[js]), seg.nav_entry, max(o.nav_cand_size, o.n_entry))
        return [int(rows[j]) for _, j in pool[: o.n_entry]], hops
    return ([seg.entry] if seg.entry >= 0 else []), 0


def survivors_kept(size: int, ratio: float) -> int:
    """How many of a block's other vertices are explored."""
    return math.ceil((size - 1) * ratio - 1e-9)


#: Values of the vectors of a segment up to which a query has all distances taken at once.
SMALL_VALUES = 1 << 18


class _Run:
    """One query on one segment."""

    def __init__(self, seg: Segment, q: np.ndarray, o: Options, radius: float | None):
        self.seg, self.q, self.o, self.radius = seg, np.asarray(q, float), o, radius
        self.cap = o.cand_size
        self.pool: list[tuple[float, int]] = []
        self.first = 0  # all rows of the pool before this are done
        self.known: set[int] = set()  # rows that have been in the pool
        self.done: set[int] = set()
        self.kicked: list[tuple[float, int]] = []
        self.hits: dict[int, float] = {}
        self.out = Found([], [])
        self.buffer: set[int] = set()
        self.waiting: list[int] = []
        self.table = pq.lookup(self.q, seg.book, seg.metric) if o.routing == "pq" and seg.book else None
        self.in_memory = isinstance(seg.vecs, np.ndarray)
        self.every: list[float] | None = None  # exact and routing distances of all rows,
        self.routes: list[float] | None = None  # once most of them will be asked for

    def whole(self) -> bool:
        """The segment is small, the list holds it, or an eighth of it has been met: over
        arrays, the distances of all rows at once then cost less than those of each step."""
        return self.in_memory and (self.seg.vecs.size <= SMALL_VALUES or self.cap >= len(self.seg.ids) or 8 * len(self.done) >= len(self.seg.ids))

    def exact(self, rows: list[int]) -> list[float]:
        if self.every is None:
            if not self.whole():
                return exact(self.seg, self.q, rows).tolist()
            self.every = exact(self.seg, self.q, slice(None)).tolist()
        return [self.every[r] for r in rows]

    def route(self, rows: list[int], charge: bool) -> list[float]:
        """Routing distances; exact ones of rows that aren't loaded cost reads."""
        if self.table is not None:
            if self.routes is None:
                if not self.whole():
                    return self.table.ravel().take(self.seg.code_places[rows]).sum(1).tolist()
                self.routes = self.table.ravel().take(self.seg.code_places).sum(1).tolist()
            return [self.routes[r] for r in rows]
        if charge:
            for b in {int(self.seg.block[r]) for r in rows if not (self.o.cache and r in self.seg.hot)} - self.buffer:
                self.read(b, None)
        return self.exact(rows)

    def read(self, block: int, target: int | None) -> None:
        """Count a read; over arrays nothing moves (``block_search`` reads files)."""
        self.out.ios += 1
        if self.o.keep_blocks == "all":
            self.buffer.add(block)
        elif self.o.keep_blocks == "last" or self.table is None:
            self.buffer = {block}

    def add(self, rows, charge: bool = True) -> None:
        known = self.known
        new = [r for r in dict.fromkeys(rows) if r not in known]
        if not new:
            return
        known.update(new)
        got = list(zip(self.route(new, charge), new))
        if self.radius is None:  # what falls out of the list is forgotten, but not looked at again
            self.first = keep_nearest(self.pool, got, self.cap, self.first)
            return
        for x in got:
            if len(self.pool) >= self.cap:
                if x > self.pool[-1]:
                    self.kick(x)
                    continue
                self.kick(self.pool.pop())
            self.put(x)

    def put(self, x: tuple[float, int]) -> None:
        """Into its place of the pool, which a long list would take long to sort."""
        i = bisect_right(self.pool, x)
        self.pool.insert(i, x)
        self.first = min(self.first, i)

    def kick(self, x: tuple[float, int]) -> None:
        if x[1] not in self.done:
            heapq.heappush(self.kicked, x)

    def hit(self, row: int, d: float) -> None:
        if self.radius is None or round(d, 6) <= self.radius:
            self.hits[row] = d

    def expand(self, rows: list[int]) -> None:
        """Put the neighbours of some rows on the list, all at once."""
        rows = [r for r in rows if r not in self.done]
        if rows:
            self.done.update(rows)
            if self.in_memory:
                self.add(chain.from_iterable(map(self.seg.near_lists.__getitem__, rows)))
            else:
                near = self.seg.nbrs[rows].ravel()
                self.add(near[near >= 0].tolist())

    def targets(self) -> list[int]:
        pool, done = self.pool, self.done
        while self.first < len(pool) and pool[self.first][1] in done:
            self.first += 1
        return list(islice((pool[i][1] for i in range(self.first, len(pool)) if pool[i][1] not in done), self.o.beam_width))

    def load(self, target: int) -> list[int]:
        """Read the target's block; the target and the survivors become
        results. Returns the survivors, nearest first."""
        self.out.hops += 1
        if self.o.cache and target in self.seg.hot:
            if target not in self.hits:
                self.hit(target, self.exact([target])[0])
            return []
        b = int(self.seg.block[target])
        if b not in self.buffer or self.o.keep_blocks == "none":
            self.read(b, target)
        members = self.seg.member_lists[b]
        n = survivors_kept(len(members), self.o.prune_ratio)
        kept: list[int] = []
        if n or self.o.result_scope == "block":
            d = self.exact(members)
            near = sorted(zip(d, members))
            near.remove((d[members.index(target)], target))
            kept = [r for _, r in near[:n]]
            self.hit(target, d[members.index(target)])
            for x, r in near if self.o.result_scope == "block" else near[:n]:
                self.hit(r, x)
        else:
            self.hit(target, self.exact([target])[0])
        self.out.blocks += 1
        self.out.used += 1 + len(kept)
        self.out.loaded += len(members)
        self.out.util += (1 + len(kept)) / len(members)
        if self.o.rows:
            self.out.trace.append((self.out.hops, b, 1 + len(kept), len(members)))
        return kept

    def choose(self) -> list[int]:
        """The next targets; survivors that wait are explored first if the
        list has none, and a radius search widens its list if it pays."""
        while True:
            now = self.targets()
            if now:
                return now
            if self.waiting:
                self.expand(self.waiting)  # the last block's survivors
                self.waiting = []
            elif not self.grow():
                return []

    def grow(self) -> bool:
        """Double the list if most of it are hits and rows were kicked out."""
        if self.radius is None or not self.pool or not self.kicked:
            return False
        if len(self.hits) / len(self.pool) < self.o.grow_ratio:
            return False
        self.cap *= 2
        self.out.restarts += 1
        while self.kicked and len(self.pool) < self.cap:
            self.put(heapq.heappop(self.kicked))
        return True

    def apply(self, now: list[int]) -> None:
        """Read the targets' blocks and take in what they bring."""
        self.out.rounds += 1
        loaded = [(u, self.load(u)) for u in now]
        if self.o.pipelined:
            # while the blocks were read, the survivors of the last ones
            self.expand(self.waiting)
            self.waiting = []
        self.expand(now)
        for _, kept in loaded:
            self.waiting += kept
        if not self.o.pipelined:
            self.expand(self.waiting)
            self.waiting = []

    def begin(self) -> None:
        start, self.out.nav_hops = entry_rows(self.seg, self.q, self.o)
        if start:
            for r, d in zip(start, self.exact(start)):
                self.hit(r, d)
            self.add(start, charge=False)

    def finish(self) -> Found:
        order = sorted((round(d, 6) + 0.0, r) for r, d in self.hits.items())
        self.out.rows, self.out.dists = [r for _, r in order], [d for d, _ in order]
        return self.out

    def go(self) -> Found:
        began = time.perf_counter()
        self.begin()
        while now := self.choose():
            self.apply(now)
        self.out.total_s = time.perf_counter() - began
        return self.finish()


def anns(seg: Segment, q: np.ndarray, k: int, o: Options, run=None) -> Found:
    """``run`` makes a query's run, by default over arrays in memory."""
    out = (run or partial(_Run, seg))(q, o, None).go()
    out.rows, out.dists = out.rows[:k], out.dists[:k]
    return out


def radius_search(seg: Segment, q: np.ndarray, r: float, o: Options, run=None) -> Found:
    return (run or partial(_Run, seg))(q, o, r).go()


def vertex_options(o: Options, cache: bool = True) -> Options:
    """The vertex-at-a-time baseline: fixed entry, no pruning survivors."""
    from dataclasses import replace

    return replace(o, prune_ratio=0.0, navigator=False, cache=cache, pipelined=False, result_scope="survivors")


def radius_by_topk(seg: Segment, q: np.ndarray, r: float, o: Options, k0: int = 10, growth: int = 2, run=None) -> Found:
    """Baseline: the k nearest with growing k until the last one is outside;
    all reads are paid again."""
    from dataclasses import replace

    total, k = Found([], []), k0
    while True:
        total = added(total, anns(seg, q, k, replace(o, cand_size=max(o.cand_size, k)), run))
        if len(total.rows) < k or total.dists[-1] > r or k >= len(seg.ids):
            break
        k *= growth
        total.restarts += 1
    inside = [(x, d) for x, d in zip(total.rows, total.dists) if d <= r]
    total.rows, total.dists = [x for x, _ in inside], [d for _, d in inside]
    return total
