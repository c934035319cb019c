"""Block layouts of one segment's graph (numpy, one task each).

A layout gives each row a position; block = position // cap unless stated
otherwise. Functions return the block of each row.
"""

from __future__ import annotations

import itertools
import time

import numpy as np


def n_blocks(n: int, cap: int) -> int:
    return -(-n // cap)


def overlap(nbrs: np.ndarray, block: np.ndarray) -> np.ndarray:
    """OR of each row: neighbours in its block over the others in its block."""
    size = np.bincount(block) if len(block) else np.zeros(0, int)
    near = (nbrs >= 0) & (block[np.maximum(nbrs, 0)] == block[:, None])
    others = size[block] - 1
    return np.where(others > 0, near.sum(1) / np.maximum(others, 1), 0.0)


def idpack(n: int, cap: int) -> np.ndarray:
    return np.arange(n) // cap


def pad_order(nbrs: np.ndarray) -> np.ndarray:
    """Walk the rows upwards; a row not yet placed is placed and its neighbours
    not yet placed behind it."""
    n = len(nbrs)
    placed = np.zeros(n, bool)
    order = []
    for u in range(n):
        if placed[u]:
            continue
        for v in (u, *nbrs[u]):
            if v >= 0 and not placed[v]:
                placed[v] = True
                order.append(int(v))
    return np.array(order, int)


def pad(nbrs: np.ndarray, cap: int, spill: str = "continue") -> np.ndarray:
    """``continue``: a run goes on in the next block, so the number of blocks is
    least. ``skip``: neighbours that find the block full wait for their turn."""
    n = len(nbrs)
    block = np.full(n, -1)
    if spill == "continue":
        block[pad_order(nbrs)] = np.arange(n) // cap
        return block
    at, used = 0, 0
    for u in range(n):
        if block[u] >= 0:
            continue
        if used == cap:
            at, used = at + 1, 0
        block[u] = at
        used += 1
        for v in nbrs[u]:
            if v >= 0 and block[v] < 0 and used < cap:
                block[v] = at
                used += 1
    return block


def _preferences(near: list[int], old: list[int]) -> list[tuple[int, int]]:
    """(count, block) of a row's neighbours, most first, ties by block."""
    counts: dict[int, int] = {}
    for v in near:
        b = old[v]
        if v >= 0 and b >= 0:
            counts[b] = counts.get(b, 0) + 1
    return sorted(((c, b) for b, c in counts.items()), key=lambda x: (-x[0], x[1]))


def _refill(nbrs: np.ndarray, old: np.ndarray, cap: int, order: np.ndarray, overflow: str, live: bool) -> np.ndarray:
    """One round: each row goes to the block with most of its neighbours that
    has room. ``immediate``: who finds none takes an empty block at once (or the
    least filled); ``deferred``: after all others, the lowest with room."""
    n = len(nbrs)
    rho = n_blocks(n, cap)
    new, load, late = [-1] * n, [0] * rho, []
    near, where = nbrs.tolist(), old.tolist()
    for u in order.tolist():
        for _, b in _preferences(near[u], where):
            if load[b] < cap:
                new[u] = b
                load[b] += 1
                break
        else:
            if overflow == "deferred":
                late.append(u)
                continue
            b = load.index(min(load))  # an empty one is the least filled
            new[u] = b
            load[b] += 1
        if live:
            where[u] = new[u]
    b = 0
    for u in sorted(late):
        while load[b] >= cap:  # blocks only fill up
            b += 1
        new[u] = b
        load[b] += 1
    return np.array(new, int)


def freq(nbrs, cap, init=None, max_iter=8, min_gain=0.01, overflow="deferred", keep="last", map="frozen", priority=False):
    """Rounds of refilling by neighbour counts; returns (block, history of OR).

    ``map='frozen'`` counts neighbours where they were before the round, as the
    definition has it; it gains where vectors are clustered and loses where they
    aren't. ``'live'`` counts them where they already are, which gains on both
    (``curve_beta`` has a set on which neither does), and is what an index uses by
    default. ``priority`` takes rows by their best
    count in place of their id. A round that gains less than ``min_gain`` is the
    last. ``keep='last'`` returns the last layout, whatever its OR; ``'best'`` the
    best of all rounds, which is the initial layout if no round gains."""
    block = pad(nbrs, cap) if init is None else init
    history = [float(overlap(nbrs, block).mean()) if len(block) else 0.0]
    best = (history[0], block)
    for _ in range(max_iter):
        order = np.arange(len(nbrs))
        if priority:
            where = block.tolist()
            top = np.array([max((c for c, _ in _preferences(x, where)), default=0) for x in nbrs.tolist()])
            order = np.lexsort((order, -top))
        block = _refill(nbrs, block, cap, order, overflow, map == "live")
        history.append(float(overlap(nbrs, block).mean()) if len(block) else 0.0)
        if history[-1] > best[0]:
            best = (history[-1], block)
        if history[-1] - history[-2] < min_gain:
            break
    return (best[1] if keep == "best" else block), history


def freq_grid(nbrs, cap, settings):
    """(history, seconds) of ``freq`` for each (max_iter, min_gain, map, overflow).
    Limits of rounds and gain only end a run earlier, so each map and overflow
    is run once, as far as any setting goes."""
    def end(h, most, gain):
        return next((r for r in range(1, min(most, len(h) - 1) + 1) if h[r] - h[r - 1] < gain), most)

    runs = {}
    for how, over in dict.fromkeys(x[2:] for x in settings):
        mine = [x[:2] for x in settings if x[2:] == (how, over)]
        block, h, at = None, [], [0.0]
        while not h or any(end(h, *x) > len(h) - 1 for x in mine):
            began = time.perf_counter()
            block, got = freq(nbrs, cap, block, 1, -9.0, map=how, overflow=over)
            at.append(at[-1] + time.perf_counter() - began)
            h += got[1:] if h else got
        runs[how, over] = h, at
    out = []
    for most, gain, how, over in settings:
        h, at = runs[how, over]
        r = end(h, most, gain)
        out.append((h[: r + 1], at[r]))
    return out


def swap(nbrs, cap, init=None, max_iter=4, min_gain=0.01, schedule="sequential"):
    """For two neighbours of a row in different blocks, exchange the members of
    lowest OR if the sum of OR over both blocks' rows rises; OR(G) can't fall.
    ``schedule='matching'`` weighs all pairs of blocks against the same layout and
    carries out the best that share no block, which can be done side by side.
    Returns (block, history)."""
    where = (pad(nbrs, cap) if init is None else init).tolist()
    n = len(nbrs)
    lists = [[v for v in x if v >= 0] for x in nbrs.tolist()]
    sets = [set(x) for x in lists]
    members: dict[int, list[int]] = {}
    for u, b in enumerate(where):
        members.setdefault(b, []).append(u)
    # OR is told by whole numbers: a row's neighbours in its block, of which there are others[block] at most
    named_by: list[set[int]] = [set() for _ in range(n)]
    for v, near in enumerate(sets):
        for w in near:
            named_by[w].add(v)
    held = {b: set(m) for b, m in members.items()}
    others = {b: max(1, len(m) - 1) for b, m in members.items()}
    count = [len(near & held[b]) for near, b in zip(sets, where)]
    place = lambda b: min(range(len(members[b])), key=lambda i: count[members[b][i]])
    lowest = {b: place(b) for b in members}
    changes = dict.fromkeys(members, 0)
    vain: dict[tuple[int, int], tuple[int, int]] = {}  # pairs that gained nothing, and the changes of both by then
    history = [float(overlap(nbrs, np.array(where, int)).mean()) if n else 0.0]

    def rise(x, p, q):
        """What the counts of a block rise by if q takes p's place."""
        rest = held[x] - {p}
        return len(rest & sets[q]) + len(rest & named_by[q]) - len(rest & sets[p]) - len(rest & named_by[p])

    def put(x, i, p, q):
        held[x].remove(p)
        for v in held[x] & named_by[p]:
            count[v] -= 1
        for v in held[x] & named_by[q]:
            count[v] += 1
        held[x].add(q)
        members[x][i], where[q] = q, x
        count[q] = len(sets[q] & held[x])

    def exchange(x, y, keep):
        """The gain of exchanging the lowest members, which is done if it is kept."""
        i, j = lowest[x], lowest[y]
        p, q = members[x][i], members[y][j]
        gain = rise(x, p, q) / others[x] + rise(y, q, p) / others[y]
        if gain <= 1e-12:
            vain[x, y] = changes[x], changes[y]
            vain[y, x] = changes[y], changes[x]
        elif keep:
            put(x, i, p, q)
            put(y, j, q, p)
            for b in (x, y):
                changes[b] += 1
                lowest[b] = place(b)
        return gain

    for _ in range(max_iter):
        if schedule == "matching":
            pairs = {tuple(sorted(xy)) for near in lists for xy in itertools.combinations({where[v] for v in near}, 2)}
            gains = sorted(((-exchange(x, y, False), x, y) for x, y in sorted(pairs)))
            busy: set[int] = set()
            for g, x, y in gains:
                if g < -1e-12 and x not in busy and y not in busy:
                    exchange(x, y, True)
                    busy |= {x, y}
        else:
            for near in lists:
                for a, e in itertools.combinations(near, 2):
                    x, y = where[a], where[e]
                    if x != y and vain.get((x, y)) != (changes[x], changes[y]):
                        exchange(x, y, True)
        history.append(float(overlap(nbrs, np.array(where, int)).mean()) if n else 0.0)
        if history[-1] - history[-2] < min_gain:
            break
    return np.array(where, int), history


def _lloyd(x: np.ndarray, k: int, iters: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(seed)
    c = x[np.sort(rng.choice(len(x), min(k, len(x)), replace=False))].astype(float)
    for _ in range(iters):
        d = (x * x).sum(1)[:, None] - 2 * x @ c.T + (c * c).sum(1)[None, :]
        a = d.argmin(1)
        for j in range(len(c)):
            if (a == j).any():
                c[j] = x[a == j].mean(0)
    return a, np.take_along_axis(d, a[:, None], 1)[:, 0]


def kmeans_pack(x: np.ndarray, cap: int, iters: int = 10, seed: int = 7) -> np.ndarray:
    """Clusters one after the other, nearest to the centre first, cut into blocks."""
    if not len(x):
        return np.zeros(0, int)
    a, d = _lloyd(np.asarray(x, float), n_blocks(len(x), cap), iters, seed)
    block = np.empty(len(x), int)
    block[np.lexsort((np.arange(len(x)), d, a))] = np.arange(len(x)) // cap
    return block


def gp_hier(x: np.ndarray, cap: int, iters: int = 6, seed: int = 7) -> np.ndarray:
    """Split clusters in two, sizes in whole blocks, until one block is left."""
    x = np.asarray(x, float)
    order, stack = [], [np.arange(len(x))]
    while stack:
        part = stack.pop()
        if len(part) <= cap:
            order.append(part)
            continue
        a, _ = _lloyd(x[part], 2, iters, seed)
        c0, c1 = (x[part][a == j].mean(0) if (a == j).any() else x[part].mean(0) for j in (0, 1))
        lean = ((x[part] - c0) ** 2).sum(1) - ((x[part] - c1) ** 2).sum(1)
        half = n_blocks(len(part), cap) // 2 * cap
        ranked = part[np.lexsort((part, lean))]
        stack += [ranked[half:], ranked[:half]]
    block = np.empty(len(x), int)
    block[np.concatenate(order) if order else np.zeros(0, int)] = np.arange(len(x)) // cap
    return block


def gp_grow(nbrs: np.ndarray, cap: int, criterion: str = "cut") -> np.ndarray:
    """Grow two parts from two seeds, turn by turn adding the row with most
    edges into the part (``cut``: less those into the other), recursively."""
    n = len(nbrs)
    links = [set() for _ in range(n)]
    for u in range(n):
        for v in nbrs[u]:
            if v >= 0:
                links[u].add(int(v))
                links[int(v)].add(u)
    order, stack = [], [list(range(n))]
    while stack:
        part = stack.pop()
        if len(part) <= cap:
            order.append(part)
            continue
        inside = set(part)
        goal = [n_blocks(len(part), cap) // 2 * cap]
        goal.append(len(part) - goal[0])
        s0 = part[0]
        far = [v for v in part if v not in links[s0] and v != s0]
        s1 = far[-1] if far else part[-1]
        sides, gain = [[], []], [dict(), dict()]
        free = dict.fromkeys(part)
        for k, s in ((0, s0), (1, s1)):
            gain[k][s] = 1
        while free:
            k = 0 if len(sides[0]) * goal[1] <= len(sides[1]) * goal[0] else 1
            if len(sides[k]) >= goal[k]:
                k = 1 - k
            best = max(gain[k], key=lambda v: (gain[k][v] - (gain[1 - k].get(v, 0) if criterion == "cut" else 0), -v)) if gain[k] else next(iter(free))
            sides[k].append(best)
            del free[best]
            gain[0].pop(best, None)
            gain[1].pop(best, None)
            for v in links[best] & inside:
                if v in free:
                    gain[k][v] = gain[k].get(v, 0) + 1
        stack += [sorted(sides[1]), sorted(sides[0])]
    block = np.empty(n, int)
    block[np.array(list(itertools.chain(*order)), int)] = np.arange(n) // cap
    return block


def optimal(nbrs: np.ndarray, cap: int) -> float:
    """Best OR over all partitions into full blocks (tiny graphs only)."""
    n = len(nbrs)
    sets = [set(x[x >= 0].tolist()) for x in nbrs]

    def rate(m):
        s = set(m)
        return sum(len(sets[v] & s) / (len(m) - 1) for v in m) if len(m) > 1 else 0.0

    def best(left: tuple) -> float:
        if not left:
            return 0.0
        sizes = {min(cap, len(left))} | ({len(left) % cap} if len(left) % cap and len(left) > cap else set())
        out = 0.0
        for k in sizes:
            for rest in itertools.combinations(left[1:], k - 1):
                m = (left[0], *rest)
                out = max(out, rate(m) + best(tuple(v for v in left if v not in m)))
        return out

    return best(tuple(range(n))) / n if n else 0.0


def clique_instance(sizes: list[int]) -> np.ndarray:
    """Disjoint cliques: their rows pack into full blocks without loss exactly
    if the sizes can be grouped to fill the blocks."""
    n, width = sum(sizes), max(sizes) - 1
    out = np.full((n, max(width, 1)), -1, np.int32)
    at = 0
    for s in sizes:
        for i in range(s):
            out[at + i, : s - 1] = [at + j for j in range(s) if j != i]
        at += s
    return out


def make(kind: str, nbrs: np.ndarray, x: np.ndarray, cap: int, **options) -> np.ndarray:
    """A layout by name."""
    if kind == "idpack":
        return idpack(len(nbrs), cap)
    if kind == "pad":
        return pad(nbrs, cap, **options)
    if kind == "freq":
        return freq(nbrs, cap, **options)[0]
    if kind == "swap":
        return swap(nbrs, cap, **options)[0]
    if kind == "freq_swap":
        return swap(nbrs, cap, init=freq(nbrs, cap, **options)[0])[0]
    if kind == "kmeans_pack":
        return kmeans_pack(x, cap, **options)
    if kind == "gp_hier":
        return gp_hier(x, cap, **options)
    if kind == "gp_grow":
        return gp_grow(nbrs, cap, **options)
    if kind == "gp_restream":
        return freq(nbrs, cap, priority=True, **options)[0]
    raise ValueError(kind)


LAYOUTS = ("idpack", "pad", "freq", "swap", "freq_swap", "kmeans_pack", "gp_hier", "gp_grow", "gp_restream")
