import itertools

import numpy as np

from blockgraph.operators import graph, index, search


def test_walks_over_a_table_meet_what_walks_without_one_meet():
    x = np.random.default_rng(8).normal(size=(400, 5))
    with_table, without = graph.Space(x, "l2"), graph.Space(x, "l2")
    without.table = None
    lists = [r.tolist() for r in graph.knn_lists(with_table, 12)]
    for target, width in itertools.product(range(0, 400, 37), (1, 5, 64, 400)):
        got = graph.walk(with_table, lists, 0, target, width)
        assert got == graph.walk(without, lists, 0, target, width)
        assert graph.robust_prune(with_table, target, got + lists[target], 8, 1.2) == graph.robust_prune(without, target, got + lists[target], 8, 1.2)


def test_small_segments_take_all_distances_at_once(monkeypatch):
    x = np.random.default_rng(9).normal(size=(600, 16))
    seg, _ = index.build_segment(np.arange(600), x, index.Build(build_list=16))
    calls = []
    exact = search.exact
    monkeypatch.setattr(search, "exact", lambda s, q, rows: calls.append(rows) or exact(s, q, rows))

    def found():
        calls.clear()
        got = [index.answer(seg, q + 0.01, index.Ask(10, options=search.Options(navigator=False, **o))) for q in x[:40] for o in ({}, {"routing": "exact"})]
        return [(f.rows, f.dists, f.ios, f.hops, f.util) for f in got], len(calls)

    small = found()
    monkeypatch.setattr(search, "SMALL_VALUES", 0)
    assert found()[0] == small[0] and small[1] == 80
