import itertools

import numpy as np
import pytest

from blockgraph.operators import graph, index, layout, layout_rounds, measures


def square(edges, n, width=4):
    out = np.full((n, width), -1, np.int32)
    for u in range(n):
        mine = sorted({b for a, b in edges if a == u} | {a for a, b in edges if b == u})
        out[u, : len(mine)] = mine
    return out


def block_or(nbrs, members):
    block = np.ones(len(nbrs), int)
    block[list(members)] = 0
    return layout.overlap(nbrs, block)[list(members)].mean()


def test_small_examples():
    star = square([(0, 7), (0, 8), (0, 14)], 16)
    assert block_or(star, (0, 7, 8, 14)) == pytest.approx(1 / 2)
    four = square([(0, 7), (0, 8), (12, 7), (12, 8)], 16)
    assert block_or(four, (0, 7, 8, 12)) == pytest.approx(2 / 3)
    assert layout.overlap(square([], 1), np.zeros(1, int)).tolist() == [0]
    clique = layout.clique_instance([4])
    assert layout.overlap(clique, np.zeros(4, int)).mean() == 1


def random_graph(seed, n=60, d=6):
    x = np.random.default_rng(seed).standard_normal((n, 3))
    return x, graph.build("knn", x, np.arange(n), "l2", d)[0]


@pytest.mark.parametrize("kind", layout.LAYOUTS)
def test_layouts_are_partitions(kind):
    x, nbrs = random_graph(1)
    for cap in (1, 4, 7, 100):
        block = layout.make(kind, nbrs, x, cap)
        size = np.bincount(block)
        assert len(block) == 60 and size.max() <= cap and len(size) == layout.n_blocks(60, cap)
        assert 0 <= layout.overlap(nbrs, block).min() and layout.overlap(nbrs, block).max() <= 1


def test_swap_never_falls():
    for seed in range(3):
        x, nbrs = random_graph(seed)
        for init in (layout.idpack(60, 5), layout.pad(nbrs, 5)):
            for how in ("sequential", "matching"):
                block, history = layout.swap(nbrs, 5, init=init, min_gain=-1, schedule=how)
                assert all(b >= a - 1e-12 for a, b in itertools.pairwise(history)) and history[-1] > history[0]
                assert np.bincount(block).max() <= 5 and layout.overlap(nbrs, block).mean() == pytest.approx(history[-1])


def test_cliques_pack_and_optimum():
    nbrs = layout.clique_instance([2, 2, 4])
    best = layout.optimal(nbrs, 4)
    assert best == pytest.approx((4 * 1 + 4 * (1 / 3)) / 8)
    for kind in ("pad", "freq", "swap", "gp_grow", "gp_restream"):
        assert layout.overlap(nbrs, layout.make(kind, nbrs, np.zeros((8, 1)), 4)).mean() <= best + 1e-12
    assert layout.overlap(nbrs, layout.pad(nbrs, 4)).mean() == pytest.approx(best)


def test_rounds_equal_walks(spark):
    x, nbrs = random_graph(5, 50, 5)
    r, p = np.nonzero(nbrs >= 0)
    edges = spark.createDataFrame([(0, int(a), int(nbrs[a, b]), int(b)) for a, b in zip(r, p)], "segment_id int, src long, dst long, pos int")
    vertices = spark.createDataFrame([(0, i) for i in range(50)], "segment_id int, vec_id long")
    got = {r.vec_id: r.block_id for r in layout_rounds.pad(vertices, edges, 6).collect()}
    want = layout.pad(nbrs, 6)
    assert [got[i] for i in range(50)] == want.tolist()
    old = spark.createDataFrame([(0, i, int(b)) for i, b in enumerate(want)], "segment_id int, vec_id long, block_id long")
    got = {r.vec_id: r.block_id for r in layout_rounds.freq_round(vertices, edges, old, 6).collect()}
    assert [got[i] for i in range(50)] == layout._refill(nbrs, want, 6, np.arange(50), "deferred", False).tolist()
    rate = measures.overlap_ratio(edges, old).first().overlap
    assert rate == pytest.approx(layout.overlap(nbrs, want).mean())


def test_graphs():
    x = np.random.default_rng(2).standard_normal((150, 8))
    for kind in ("vamana", "nsg", "hnsw", "knn"):
        nbrs, root, upper = graph.build(kind, x, np.arange(150), "l2", 16)
        for i, row in enumerate(nbrs):
            mine = row[row >= 0].tolist()
            assert i not in mine and len(set(mine)) == len(mine)
        if kind != "knn":
            assert graph.reachable(nbrs, root).all()
    assert graph.build("hnsw", x, np.arange(150), "l2", 16)[2]
    for kind in ("vamana", "nsg", "hnsw", "knn"):
        for n in (0, 1, 2):
            seg, _ = index.build_segment(np.arange(n), x[:n], index.Build(builder=kind, max_degree=4))
            assert index.load(index._rows_of(0, seg.pack())).ids.tolist() == list(range(n))


def test_freq_on_clusters():
    """Rounds raise OR where vectors are clustered, and the last is returned."""
    rng = np.random.default_rng(9)
    centres = rng.standard_normal((30, 16))
    x = centres[rng.integers(0, 30, 600)] + rng.standard_normal((600, 16)) * 0.2
    nbrs = graph.build("knn", x, np.arange(600), "l2", 16)[0]
    for how in ("frozen", "live"):
        block, h = layout.freq(nbrs, 12, max_iter=8, map=how)
        assert h[-1] > h[0] + 0.05 and layout.overlap(nbrs, block).mean() == pytest.approx(h[-1])
    flat = graph.build("knn", rng.standard_normal((600, 32)), np.arange(600), "l2", 16)[0]
    block, h = layout.freq(flat, 12, min_gain=-9.0)
    assert len(h) == 9 and layout.overlap(flat, block).mean() == pytest.approx(h[-1])
