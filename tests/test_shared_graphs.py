import itertools
import time

import numpy as np

from blockgraph.operators import graph, index, layout


def _same(a, b):
    for n in ("ids", "vecs", "nbrs", "block", "codes", "nav_rows", "nav_nbrs"):
        x, y = getattr(a, n), getattr(b, n)
        assert (x is None) == (y is None) and (x is None or np.array_equal(x, y)), n
    assert (a.entry, a.nav_entry, a.hot, a.metric) == (b.entry, b.nav_entry, b.hot, b.metric)
    assert all(np.array_equal(x, y) for x, y in zip(a.book, b.book, strict=True))


def test_derived_indexes_are_those_built_alone(spark):
    x = np.random.default_rng(3).normal(size=(240, 8))
    base = spark.createDataFrame([(int(i), [float(z) for z in v], int(i % 2)) for i, v in enumerate(x)], "vec_id long, vec array<double>, segment_id int")
    builds = [index.Build(sample_ratio=0.2), index.Build(sample_ratio=0, hot_ratio=0.1), index.Build(layout="swap", entry="fixed"), index.Build(layout="kmeans_pack", entry="random", block_cap=5)]
    made = index.derive(index.build(base, index.bare(builds[0])), builds).toPandas()
    assert len(made) == 8
    for (variant, s), rows in made.groupby(["variant", "segment_id"]):
        mine = np.arange(s, 240, 2)
        _same(index.load(rows), index.build_segment(mine, x[mine], builds[variant])[0])


def _plain_swap(nbrs, cap, rounds=4):
    """By the definition: every pair is weighed anew."""
    block = layout.pad(nbrs, cap).copy()
    sets = [set(x[x >= 0].tolist()) for x in nbrs]
    members = {}
    for u, b in enumerate(block.tolist()):
        members.setdefault(b, []).append(u)
    rate = lambda m: [len(sets[v] & set(m)) / max(1, len(m) - 1) for v in m]
    mean = [layout.overlap(nbrs, block).mean()]
    for _ in range(rounds):
        for row in nbrs:
            for a, e in itertools.combinations(row[row >= 0].tolist(), 2):
                x, y = int(block[a]), int(block[e])
                if x == y:
                    continue
                before = rate(members[x]), rate(members[y])
                i, j = (int(np.argmin(r)) for r in before)
                p, q = members[x][i], members[y][j]
                members[x][i], members[y][j] = q, p
                if sum(rate(members[x])) + sum(rate(members[y])) - sum(map(sum, before)) > 1e-12:
                    block[p], block[q] = y, x
                else:
                    members[x][i], members[y][j] = p, q
        mean.append(layout.overlap(nbrs, block).mean())
        if mean[-1] - mean[-2] < 0.01:
            break
    return block, mean


def test_swap_is_the_plain_one_without_weighing_a_pair_twice():
    nbrs = graph.build("vamana", np.random.default_rng(5).normal(size=(150, 6)), np.arange(150), "l2", 12)[0]
    for cap in (1, 4, 7, 11):
        block, history = layout.swap(nbrs, cap)
        plain, mean = _plain_swap(nbrs, cap)
        assert np.array_equal(block, plain) and np.allclose(history, mean)
    wide = graph.build("knn", np.random.default_rng(6).normal(size=(1500, 6)), np.arange(1500), "l2", 16)[0]
    began = time.process_time()
    layout.swap(wide, 23)
    assert time.process_time() - began < 8  # tens of seconds when each pair was weighed each time
