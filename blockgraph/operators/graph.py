"""Proximity graphs over the vectors of one segment (numpy, one task each).

A graph is an int32 array n x max_degree of row numbers, -1 behind the last
neighbour. Rows are in the order of vector ids, so row numbers order like ids.
"""

from __future__ import annotations

import heapq
from bisect import bisect_right

import numpy as np

from ..functions.distance import pairwise

#: Up to this many vectors, all distances are held in memory (128 MB).
TABLE_ROWS = 4096
#: Beyond, distances of so many pairs are taken at once (4 MB), to so many digits.
ROW_VALUES, DIGITS = 1 << 19, 9


class Space:
    """Distances between rows of a matrix. Graphs for ``ip`` are built on the
    vectors with one more value that makes all norms equal, where the order by
    inner product is the order by Euclidean distance."""

    def __init__(self, x: np.ndarray, metric: str):
        x = np.asarray(x, float)
        if metric == "ip" and len(x):
            norm = (x * x).sum(1)
            x = np.c_[x, np.sqrt(np.maximum(norm.max() - norm, 0))]
        if metric == "cosine" and len(x):
            x = x / np.maximum(np.sqrt((x * x).sum(1))[:, None], 1e-30)
        self.x, self.n = x, len(x)
        self.table = pairwise(x, x, "l2") if self.n <= TABLE_ROWS else None

    def to(self, i: int, js: np.ndarray) -> np.ndarray:
        if self.table is not None:
            return self.table[i, js]
        d = self.x[js] - self.x[i]
        return np.sqrt(np.einsum("ij,ij->i", d, d))

    def asked(self, i: int):
        """Distances from a row that is asked about often: rows -> list."""
        if self.table is not None:
            at = self.table[i].tolist().__getitem__
            return lambda js: list(map(at, js))
        return lambda js: self.to(i, np.array(js)).tolist()

    def row(self, i: int) -> np.ndarray:
        return self.table[i] if self.table is not None else self.to(i, np.arange(self.n))

    def near(self, p: np.ndarray, c: np.ndarray) -> np.ndarray:
        """Distances from the rows p to the rows c[i] of each."""
        if self.table is not None:
            return np.array([self.to(i, js) for i, js in zip(p.tolist(), c)])
        d = self.x[c] - self.x[p][:, None, :]
        return np.round(np.sqrt(np.einsum("ijk,ijk->ij", d, d)), DIGITS)

    def among(self, c: np.ndarray) -> np.ndarray:
        """Distances between the rows of each c[i]. Without a table they come from
        products and, like those of ``near``, to so many digits that equal ones are equal."""
        if self.table is not None:
            return self.table.ravel().take((c * self.n)[:, :, None] + c[:, None, :])
        v = self.x[c]
        size = np.einsum("ijk,ijk->ij", v, v)
        return np.round(np.sqrt(np.maximum(size[:, :, None] + size[:, None, :] - 2 * (v @ v.transpose(0, 2, 1)), 0)), DIGITS)

    def rows(self, targets: list[int]):
        """The distances to all rows of each target, as lists; without a table, of
        some targets at a time."""
        if self.table is not None:
            for t in targets:
                yield self.table[t].tolist()
            return
        size = np.einsum("ij,ij->i", self.x, self.x)
        step = max(1, ROW_VALUES // max(1, self.n))
        for i in range(0, len(targets), step):
            t = targets[i : i + step]
            for row in np.round(np.sqrt(np.maximum(size[t][:, None] + size - 2 * (self.x[t] @ self.x.T), 0)), DIGITS):
                yield row.tolist()


def medoid(space: Space) -> int:
    """The row nearest to the mean; ties by row."""
    if not space.n:
        return -1
    d = space.x - space.x.mean(0)
    return int(np.argmin(np.einsum("ij,ij->i", d, d)))


def knn_lists(space: Space, k: int) -> np.ndarray:
    """The k nearest other rows of each row, by (distance, row)."""
    k = min(k, space.n - 1)
    out = np.full((space.n, max(k, 0)), -1, np.int32)
    for i in range(space.n):
        d = space.row(i).copy()
        d[i] = np.inf
        near = np.argpartition(d, k - 1)[:k] if k and k < space.n - 1 else np.delete(np.arange(space.n), i)
        if k:
            edge = d[near].max()
            near = np.flatnonzero(d <= edge)
            near = near[near != i]
            out[i] = near[np.lexsort((near, d[near]))][:k]
    return out


def walk(space: Space, lists: list, entry: int, target: int, width: int, at: list | None = None) -> list[int]:
    """Rows expanded by a best-first search for a row of the space; ``at``: its
    distances to all rows, if they are there."""
    dist = None
    if at is None:
        if space.table is None:
            dist = space.asked(target)
        else:
            at = space.table[target].tolist()
    pool, seen, done = [(at[entry] if at else dist([entry])[0], entry)], {entry}, []
    expanded = set()
    first, size, worst = 0, 1, pool[0][0]  # all of the pool before first are expanded
    while True:
        while first < size and pool[first][1] in expanded:
            first += 1
        if first == size:
            return done
        u = pool[first][1]
        expanded.add(u)
        done.append(u)
        new = [v for v in lists[u] if v not in seen]
        if not new:
            continue
        seen.update(new)
        if at is None:
            first = keep_nearest(pool, list(zip(dist(new), new)), width, first)
            size = len(pool)
            continue
        for v in new:  # as keep_nearest does, without its calls
            d = at[v]
            if size == width:
                if d > worst:
                    continue
                if (d, v) > pool[-1]:
                    continue
                pool.pop()
            else:
                size += 1
            i = bisect_right(pool, (d, v))
            pool.insert(i, (d, v))
            worst = pool[-1][0]
            if i < first:
                first = i


def keep_nearest(pool: list, new: list, width: int, first: int) -> int:
    """Put new pairs into a sorted pool of at most ``width``; ``first`` moves back
    to the lowest place taken."""
    room = width - len(pool)
    if room < len(new):
        if room <= 0:
            last = pool[-1]
            new = [x for x in new if x < last]
        if len(new) > room:
            new.sort()
    for x in new:
        if len(pool) >= width:
            if x > pool[-1]:
                break  # they are sorted, so none of the others is nearer
            pool.pop()
        i = bisect_right(pool, x)
        pool.insert(i, x)
        if i < first:
            first = i
    return first


def robust_prune(space: Space, p: int, candidates, degree: int, alpha: float) -> list[int]:
    """Keep the nearest candidate, drop those much nearer to it than to p,
    repeat; at most ``degree`` stay."""
    c = sorted(set(candidates) - {p})
    return prune_all(space, [p], [c], degree, alpha)[0] if c else []


def prune_all(space: Space, p: list[int], candidates: list[list[int]], degree: int, alpha: float) -> list[list[int]]:
    """``robust_prune`` of several rows with equally many candidates, which are
    sorted and without the row itself."""
    p, c = np.array(p, np.int64), np.array(candidates, np.int64)
    d = space.near(p, c)
    order = np.argsort(d, axis=1, kind="stable")
    c, d = np.take_along_axis(c, order, 1), np.take_along_axis(d, order, 1)
    near = space.among(c)
    near *= alpha
    # what each would drop, as bits: most is asked for with numbers so small
    drops = np.packbits(~(near > d[:, None, :]), axis=2, bitorder="little")
    bits, w, m = drops.tobytes(), drops.shape[2], c.shape[1]
    out = []
    for i, row in enumerate(c.tolist()):
        kept, gone, at = [], 0, i * m * w
        for j, v in enumerate(row):
            if gone >> j & 1:
                continue
            kept.append(v)
            if len(kept) == degree:
                break
            gone |= int.from_bytes(bits[at + j * w : at + j * w + w], "little")
        out.append(kept)
    return out


def _padded(lists: list, degree: int) -> np.ndarray:
    out = np.full((len(lists), degree), -1, np.int32)
    for i, x in enumerate(lists):
        out[i, : len(x)] = x
    return out


def vamana(space: Space, degree: int, build_list: int = 64, alpha: float = 1.2, seed: int = 7) -> np.ndarray:
    """Two passes of search and robust prune from a random regular graph; rows
    that end up without a way from the medoid are connected."""
    n = space.n
    if n < 2:
        return np.full((n, degree), -1, np.int32)
    rng = np.random.default_rng(seed)
    lists = [[int(v) for v in rng.choice(n - 1, min(degree, n - 1), replace=False)] for _ in range(n)]
    lists = [[v + (v >= i) for v in x] for i, x in enumerate(lists)]
    start = medoid(space)
    for a in (1.0, alpha):
        order = rng.permutation(n).tolist()
        for i, at in zip(order, space.rows(order)):
            visited = walk(space, lists, start, i, build_list, at)
            lists[i] = robust_prune(space, i, visited + lists[i], degree, a)
            full = []
            for v in lists[i]:
                if i not in lists[v]:
                    lists[v].append(i)
                    if len(lists[v]) > degree:
                        full.append(v)
            if full:  # all have one neighbour too many
                for v, kept in zip(full, prune_all(space, full, [sorted(lists[v]) for v in full], degree, a)):
                    lists[v] = kept
    return _padded(connect(space, lists, start, degree), degree)


def connect(space: Space, lists: list, root: int, degree: int) -> list:
    """Make every row reachable from the root: an unreached row is hung on the
    nearest reached row with room, or takes the place of its longest edge that
    is not needed by the tree of the search."""
    parent = {root: -1}
    queue = [root]
    while True:
        while queue:
            u = queue.pop()
            for v in lists[u]:
                if v not in parent:
                    parent[v] = u
                    queue.append(v)
        if len(parent) == space.n:
            return lists
        u = next(i for i in range(space.n) if i not in parent)
        reached = np.array(sorted(parent))
        for v in reached[np.lexsort((reached, space.to(u, reached)))].tolist():
            if len(lists[v]) < degree:
                lists[v].append(u)
            else:
                spare = [w for w in lists[v] if parent.get(w) != v]
                if not spare:
                    continue
                far = max(spare, key=lambda w: (float(space.to(v, np.array([w]))[0]), w))
                lists[v][lists[v].index(far)] = u
            parent[u] = v
            queue.append(u)
            break
        else:
            raise ValueError("no room to connect the graph: raise the degree")


def nsg(space: Space, degree: int, build_list: int = 64, knn_k: int = 32) -> np.ndarray:
    """Monotonic-path graph: neighbours by the relative-neighbour rule among
    the rows met on the way from the medoid, then connected."""
    if space.n < 2:
        return np.full((space.n, degree), -1, np.int32)
    knn = [[int(v) for v in x if v >= 0] for x in knn_lists(space, knn_k)]
    root = medoid(space)
    lists = [robust_prune(space, i, walk(space, knn, root, i, build_list) + knn[i], degree, 1.0) for i in range(space.n)]
    for i in range(space.n):
        for v in list(lists[i]):
            if i not in lists[v]:
                lists[v] = robust_prune(space, v, [*lists[v], i], degree, 1.0) if len(lists[v]) >= degree else [*lists[v], i]
    return _padded(connect(space, lists, root, degree), degree)


def hnsw_levels(ids: np.ndarray, m: int) -> np.ndarray:
    """Geometric levels, drawn from a hash of the id."""
    h = np.asarray(ids, np.int64).view(np.uint64) + np.uint64(0x9E3779B97F4A7C15)
    for shift, mult in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        h = (h ^ (h >> np.uint64(shift))) * np.uint64(mult)
    u = ((h ^ (h >> np.uint64(31))).astype(float) + 1) / 2.0**64
    return np.floor(-np.log(u) / np.log(max(m, 2))).astype(int)


def hnsw(space: Space, ids: np.ndarray, m: int, build_list: int = 64) -> list[dict[int, list[int]]]:
    """Layers of a hierarchical small-world graph, the lowest first; layer 0
    has degree up to 2 m, the others m. Rows are inserted in order."""
    levels = hnsw_levels(ids, m)
    layers: list[dict[int, list[int]]] = []
    top = -1
    for i in range(space.n):
        level = int(levels[i])
        entry = top
        for k in range(len(layers) - 1, level, -1):
            near = walk(space, layers[k], entry, i, 1)
            entry = min(near, key=lambda v: (float(space.to(i, np.array([v]))[0]), v))
        for k in range(min(level, len(layers) - 1), -1, -1):
            degree = 2 * m if k == 0 else m
            near = walk(space, layers[k], entry, i, build_list)
            layers[k][i] = robust_prune(space, i, near, degree, 1.0)
            for v in layers[k][i]:
                layers[k][v].append(i)
                if len(layers[k][v]) > degree:
                    layers[k][v] = robust_prune(space, v, layers[k][v], degree, 1.0)
            entry = min(near, key=lambda v: (float(space.to(i, np.array([v]))[0]), v))
        while len(layers) <= level:
            layers.append({i: []})
            top = i
    return layers


def build(kind: str, x: np.ndarray, ids: np.ndarray, metric: str, degree: int, build_list: int = 64, seed: int = 7) -> tuple[np.ndarray, int, list]:
    """(neighbours, entry row, upper layers) by any of the builders."""
    space = Space(x, metric)
    if kind == "vamana":
        return vamana(space, degree, build_list, seed=seed), medoid(space), []
    if kind == "nsg":
        return nsg(space, degree, build_list), medoid(space), []
    if kind == "knn":
        lists = knn_lists(space, degree)
        out = np.full((space.n, degree), -1, np.int32)
        out[:, : lists.shape[1]] = lists
        return out, medoid(space), []
    if kind == "hnsw":
        layers = hnsw(space, ids, max(2, degree // 2), build_list)
        base = layers[0] if layers else {}
        root = next(iter(layers[-1])) if layers else -1
        lists = connect(space, [list(base.get(i, [])) for i in range(space.n)], root, degree) if space.n else []
        return _padded(lists, degree), root, layers[1:]
    raise ValueError(kind)


def reachable(nbrs: np.ndarray, root: int) -> np.ndarray:
    seen = np.zeros(len(nbrs), bool)
    queue = [root] if root >= 0 else []
    if queue:
        seen[root] = True
    while queue:
        u = heapq.heappop(queue)
        for v in nbrs[u]:
            if v >= 0 and not seen[v]:
                seen[v] = True
                heapq.heappush(queue, int(v))
    return seen
