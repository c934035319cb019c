import numpy as np
import pytest

from blockgraph.operators import graph, index, layout, search


@pytest.fixture(scope="module")
def seg():
    x = np.random.default_rng(1).standard_normal((300, 6))
    return index.build_segment(np.arange(300) * 3, x, index.Build(max_degree=8, block_cap=6))[0]


@pytest.mark.parametrize("routing", ["pq", "exact"])
@pytest.mark.parametrize("radius", [None, 1.5])
def test_list_that_holds_the_segment_takes_all_distances_at_once(seg, monkeypatch, routing, radius):
    asked = []
    plain = search.exact
    monkeypatch.setattr(search, "exact", lambda s, q, rows: asked.append(rows) or plain(s, q, rows))
    run = search._Run(seg, seg.vecs[5] + 0.1, search.Options(cand_size=1000, routing=routing, navigator=False), radius)
    f = run.go()
    d = np.round(plain(seg, run.q, slice(None)), 6)
    want = np.lexsort((np.arange(300), d))
    want = want if radius is None else want[d[want] <= radius]
    got = f.rows[:40] if radius is None else f.rows
    assert got == want[: len(got)].tolist() and (radius is None or len(got) == len(want))
    assert f.ios >= 50 and len(asked) <= 2


def test_pruning_asks_the_table_once(monkeypatch):
    x = np.random.default_rng(2).standard_normal((200, 5))
    table, plain = graph.Space(x, "l2"), graph.Space(x, "l2")
    plain.table = None
    asked = []
    to = table.to
    monkeypatch.setattr(table, "to", lambda i, js: asked.append(i) or to(i, js))
    for p in range(20):
        assert graph.robust_prune(table, p, range(100), 12, 1.2) == graph.robust_prune(plain, p, range(100), 12, 1.2)
    assert len(asked) == 20


def test_pool_keeps_the_nearest():
    rng = np.random.default_rng(3)
    for width in (1, 3, 8):
        pool, all_, first = [], [], 0
        for i in range(40):
            new = [(float(d), 10 * i + j) for j, d in enumerate(rng.integers(0, 9, rng.integers(0, 6)))]
            all_ += new
            first = graph.keep_nearest(pool, new, width, len(pool))
            assert pool == sorted(all_)[:width]
            assert all(x in pool[first:] for x in new if x in pool)


def test_grid_of_rounds_runs_each_map_and_overflow_once(seg, monkeypatch):
    settings = [(b, t, m, o) for b in (2, 5) for t in (0.05, 0.001, -9.0) for m in ("frozen", "live") for o in ("deferred", "immediate")]
    want = [layout.freq(seg.nbrs, 6, max_iter=b, min_gain=t, map=m, overflow=o)[1] for b, t, m, o in settings]
    rounds, plain = [], layout._refill
    monkeypatch.setattr(layout, "_refill", lambda *a: rounds.append(a) or plain(*a))
    assert [h for h, _ in layout.freq_grid(seg.nbrs, 6, settings)] == want
    assert len(rounds) == 4 * 5
