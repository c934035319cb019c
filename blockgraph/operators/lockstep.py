"""Top-k searches of many queries on one segment, side by side over arrays.

Each query makes the moves that ``search._Run`` makes for it alone, with the same
answers and counters; but a move of all queries is a few array operations, where
alone it is a few for each query. A query that has ended waits for no other one.
A query's seconds are its share of the batch.
"""

from __future__ import annotations

import time

import numpy as np

from . import pq
from .search import Found, Options, Segment, survivors_kept

#: Marks (query, row) that are held for a batch at once, and queries in one.
MARKS, MOST = 3_000_000, 512
#: Longer lists cost more to keep in order for all queries than for one at a time.
LONGEST = 1024


def supports(seg: Segment, o: Options) -> bool:
    return isinstance(seg.vecs, np.ndarray) and seg.metric in ("l2", "l2sq") and 0 < o.cand_size <= LONGEST and len(seg.ids) > 0 and o.keep_blocks == "none" and o.result_scope == "survivors" and not o.rows


def anns(seg: Segment, queries: np.ndarray, k: int, o: Options, visible: np.ndarray | None = None) -> list[Found]:
    """``search.anns`` of each query, without the answers that aren't visible."""
    step = max(1, min(MOST, MARKS // len(seg.ids)))
    out: list[Found] = []
    for i in range(0, len(queries), step):
        began = time.perf_counter()
        part = _Batch(seg, np.asarray(queries[i : i + step], float), o).go(k, visible)
        for f in part:
            f.total_s = (time.perf_counter() - began) / len(part)
        out += part
    return out


class _Lists:
    """The candidate lists of a batch on one graph: sorted, of at most cap rows.
    Row n of n stands for an empty place and counts as done."""

    def __init__(self, nbrs: np.ndarray, n_queries: int, cap: int, route):
        self.nbrs, self.cap, self.route = nbrs, cap, route
        self.n, self.width = len(nbrs), len(nbrs) + 1
        self.known = np.zeros(n_queries * self.width, bool)
        self.done = np.zeros(n_queries * self.width, bool)
        self.done[self.n :: self.width] = True
        self.first = np.empty(n_queries * self.width, np.int32)
        self.d = np.full((n_queries, cap), np.inf)
        self.r = np.full((n_queries, cap), self.n)

    def targets(self, a: np.ndarray, beam: int = 1) -> np.ndarray:
        """The first rows of some queries' lists that aren't done, or -1."""
        rows = self.r[a]
        open_ = ~self.done[a[:, None] * self.width + rows]
        if beam == 1:
            at = open_.argmax(1)[:, None]
        else:
            at = np.argsort(~open_, axis=1, kind="stable")[:, :beam]
        return np.where(np.take_along_axis(open_, at, 1), np.take_along_axis(rows, at, 1), -1)

    def expand(self, a: np.ndarray, rows: np.ndarray) -> None:
        """Put the neighbours of rows[i] on the list of query a[i]; -1 is no row."""
        q, r = np.repeat(a, rows.shape[1]), rows.ravel()
        key = q * self.width + r
        open_ = r >= 0
        open_[open_] = ~self.done[key[open_]]
        q, r = q[open_], r[open_]
        self.done[key[open_]] = True
        v = self.nbrs[r]
        there = v >= 0
        self.add(np.repeat(q, there.sum(1)), v[there].astype(np.int64))

    def add(self, q: np.ndarray, v: np.ndarray, charge: bool = True) -> None:
        """Rows for the lists of queries, which are in order."""
        key = q * self.width + v
        new = ~self.known[key]
        q, v, key = q[new], v[new], key[new]
        at = np.arange(len(key), dtype=np.int32)
        self.first[key[::-1]] = at[::-1]  # the last one that is written stays
        new = self.first[key] == at
        q, v, key = q[new], v[new], key[new]
        self.known[key] = True
        if not len(q):
            return
        d = self.route(q, v, charge)
        near = d <= self.d[q, -1]
        q, v, d = q[near], v[near], d[near]
        if not len(q):
            return
        begin = np.flatnonzero(np.r_[True, q[1:] != q[:-1]])
        size = np.diff(np.r_[begin, len(q)])
        u, line = q[begin], np.repeat(np.arange(len(begin)), size)
        place = self.cap + np.arange(len(q)) - begin[line]
        ds, rs = np.full((len(u), self.cap + size.max()), np.inf), np.full((len(u), self.cap + size.max()), self.n)
        ds[:, : self.cap], rs[:, : self.cap] = self.d[u], self.r[u]
        ds[line, place], rs[line, place] = d, v
        order = np.argsort(ds, axis=1)
        ds, rs = np.take_along_axis(ds, order, 1), np.take_along_axis(rs, order, 1)
        ties = np.flatnonzero(((ds[:, 1:] == ds[:, :-1]) & (rs[:, 1:] < rs[:, :-1])).any(1))
        if len(ties):
            order = np.lexsort((rs[ties], ds[ties]), axis=-1)
            ds[ties], rs[ties] = np.take_along_axis(ds[ties], order, 1), np.take_along_axis(rs[ties], order, 1)
        self.d[u], self.r[u] = ds[:, : self.cap], rs[:, : self.cap]


class _Batch:
    def __init__(self, seg: Segment, queries: np.ndarray, o: Options):
        self.seg, self.q, self.o = seg, queries, o
        n = len(queries)
        self.table = None
        if o.routing == "pq" and seg.book:
            self.table = np.concatenate([pq.lookup(x, seg.book, seg.metric).ravel() for x in queries])
            self.row = len(self.table) // n
        self.lists = _Lists(seg.nbrs, n, o.cand_size, self.route)
        names = ("ios", "hops", "nav_hops", "rounds", "used", "loaded", "blocks")
        self.count = {c: np.zeros(n, np.int64) for c in names}
        self.util = np.zeros(n)
        self.buffer: list[set[int]] = [set() for _ in range(n)]  # exact routing only
        self.hot = np.zeros(len(seg.ids), bool)
        self.hot[sorted(seg.hot)] = o.cache
        sizes = np.array([len(m) for m in seg.members])
        self.members = np.full((len(sizes), sizes.max()), -1)
        for b, m in enumerate(seg.members):
            self.members[b, : len(m)] = m
        self.sizes, self.kept = sizes, np.array([survivors_kept(s, o.prune_ratio) for s in range(sizes.max() + 1)])
        self.waiting = np.full((n, max(1, o.beam_width * int(self.kept.max()))), -1)
        self.hits: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

    def exact(self, q: np.ndarray, rows: np.ndarray) -> np.ndarray:
        d = self.seg.vecs[rows] - self.q[q]
        d = np.einsum("ij,ij->i", d, d)
        return np.sqrt(d) if self.seg.metric == "l2" else d

    def route(self, q: np.ndarray, rows: np.ndarray, charge: bool) -> np.ndarray:
        if self.table is not None:
            return self.table.take(self.seg.code_places[rows] + (q * self.row)[:, None]).sum(1)
        if charge:
            self.charge(q, rows)
        return self.exact(q, rows)

    def charge(self, q: np.ndarray, rows: np.ndarray) -> None:
        """Reads for exact distances of rows that aren't loaded; the last block read
        is the buffer, so the order is that of a query alone."""
        blocks, cold = self.seg.block[rows], ~self.hot[rows]
        begin = np.flatnonzero(np.r_[True, q[1:] != q[:-1]])
        for a, e in zip(begin.tolist(), [*begin[1:].tolist(), len(q)]):
            i = int(q[a])
            for b in set(blocks[a:e][cold[a:e]].tolist()) - self.buffer[i]:
                self.count["ios"][i] += 1
                self.buffer[i] = {b}

    def load(self, a: np.ndarray, targets: np.ndarray) -> np.ndarray:
        """Read the targets' blocks; the survivors of each query, -1 for none."""
        c, beam = self.count, targets.shape[1]
        line, col = np.nonzero(targets >= 0)
        q, t = a[line], targets[line, col]
        np.add.at(c["hops"], q, 1)
        dt = self.exact(q, t)
        self.hits.append((q, t, dt))
        most = int(self.kept.max())
        out = np.full((len(a), beam, max(1, most)), -1)
        cold = ~self.hot[t]
        line, col, q, t = line[cold], col[cold], q[cold], t[cold]
        b = self.seg.block[t]
        np.add.at(c["ios"], q, 1)
        if self.table is None:
            for i, x in zip(q.tolist(), b.tolist()):
                self.buffer[i] = {x}
        size = self.sizes[b]
        n = self.kept[size]
        if most and len(q):
            rows = self.members[b]
            others = (rows >= 0) & (rows != t[:, None])
            d = np.full(rows.shape, np.inf)
            d[others] = self.exact(np.repeat(q, others.sum(1)), rows[others])
            order = np.argsort(d, axis=1, kind="stable")[:, :most]
            taken = np.arange(order.shape[1]) < n[:, None]
            near = np.where(taken, np.take_along_axis(rows, order, 1), -1)
            out[line, col, : near.shape[1]] = near
            self.hits.append((np.repeat(q, n), near[taken], np.take_along_axis(d, order, 1)[taken]))
        np.add.at(c["blocks"], q, 1)
        np.add.at(c["used"], q, 1 + n)
        np.add.at(c["loaded"], q, size)
        np.add.at(self.util, q, (1 + n) / size)
        return out.reshape(len(a), -1)

    def begin(self) -> None:
        seg, o, every = self.seg, self.o, np.arange(len(self.q))
        if o.navigator and seg.nav_rows is not None and len(seg.nav_rows):
            rows = seg.nav_rows
            nav = _Lists(seg.nav_nbrs, len(every), max(o.nav_cand_size, o.n_entry), lambda q, v, charge: self.exact(q, rows[v]))
            nav.add(every, np.full(len(every), seg.nav_entry))
            a = every
            while len(a):
                t = nav.targets(a)
                a, t = a[t[:, 0] >= 0], t[t[:, 0] >= 0]
                self.count["nav_hops"][a] += 1
                nav.expand(a, t)
            at = nav.r[:, : o.n_entry]
            q, col = np.nonzero(at < nav.n)
            start = rows[at[q, col]]
        elif seg.entry >= 0:
            q, start = every, np.full(len(every), seg.entry)
        else:
            return
        self.hits.append((q, start, self.exact(q, start)))
        self.lists.add(q, start, charge=False)

    def apply(self, a: np.ndarray, targets: np.ndarray) -> None:
        self.count["rounds"][a] += 1
        kept = self.load(a, targets)
        if self.o.pipelined:
            turns = [self.waiting[a], targets]
            self.waiting[a] = -1
            self.waiting[a, : kept.shape[1]] = kept
        else:
            turns = [targets, kept]
        # at once, unless each turn has reads of its own
        for rows in [np.concatenate(turns, 1)] if self.table is not None else turns:
            self.lists.expand(a, rows)

    def go(self, k: int, visible: np.ndarray | None) -> list[Found]:
        self.begin()
        a = np.arange(len(self.q))
        while len(a):
            t = self.lists.targets(a, self.o.beam_width)
            some = t[:, 0] >= 0
            rest = a[~some]
            rest = rest[(self.waiting[rest] >= 0).any(1)]
            if len(rest):  # the last block's survivors
                self.lists.expand(rest, self.waiting[rest])
                self.waiting[rest] = -1
            if some.any():
                self.apply(a[some], t[some])
            a = np.sort(np.r_[a[some], rest])
        return self.finish(k, visible)

    def finish(self, k: int, visible: np.ndarray | None) -> list[Found]:
        q, r, d = (np.concatenate([x[i] for x in self.hits]) if self.hits else np.zeros(0, int) for i in range(3))
        if visible is not None:
            q, r, d = q[visible[r]], r[visible[r]], d[visible[r]]
        order = np.lexsort((r, q))
        q, r, d = q[order], r[order], d[order]
        new = np.r_[True, (q[1:] != q[:-1]) | (r[1:] != r[:-1])][: len(q)]
        q, r, d = q[new], r[new], d[new]
        ends = np.searchsorted(q, np.arange(len(self.q) + 1))
        out = []
        for i, (x, y) in enumerate(zip(ends, ends[1:])):
            rows, dists = r[x:y], d[x:y]
            if len(rows) > k:  # what may be among the k nearest once it is rounded
                near = dists <= np.partition(dists, k - 1)[k - 1] + 1e-6
                rows, dists = rows[near], dists[near]
            best = sorted((round(e, 6) + 0.0, v) for e, v in zip(dists.tolist(), rows.tolist()))[:k]
            f = Found([v for _, v in best], [e for e, _ in best], util=float(self.util[i]))
            for c, x in self.count.items():
                setattr(f, c, int(x[i]))
            out.append(f)
        return out
