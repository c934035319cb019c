import time

import numpy as np
import pytest

from blockgraph.operators import graph, index, lockstep, search

RNG = np.random.default_rng(12)
X = RNG.normal(size=(700, 16))
X[500:520] = X[3]  # equal vectors: ties by row
FIELDS = ("rows", "dists", "restarts", *search.COUNTERS)


def told(f):
    return [getattr(f, n) for n in FIELDS]


@pytest.fixture(scope="module")
def seg():
    return index.build_segment(np.arange(0, 1400, 2), X, index.Build(max_degree=10, n_codes=16, hot_ratio=0.1, block_cap=7))[0]


@pytest.mark.parametrize("options", [{}, {"prune_ratio": 0.0}, {"prune_ratio": 1.0}, {"pipelined": False}, {"routing": "exact"}, {"routing": "exact", "cache": True, "pipelined": False}, {"beam_width": 4}, {"beam_width": 3, "routing": "exact"}, {"navigator": False, "cache": True}, {"cand_size": 5}, {"cand_size": 160}])
def test_side_by_side_is_one_after_the_other(seg, options, monkeypatch):
    monkeypatch.setattr(lockstep, "MARKS", 700 * 25)  # several batches
    qs = [*(X[:8] + 0.05), X[3], X[510]]
    asks = [index.Ask(10, options=search.Options(**options)), index.Ask(7, method="vertex", options=search.Options(**options)), index.Ask(r=3.9, method="radius_by_topk", options=search.Options(**options))]
    for ask in asks:
        for visible in (None, np.arange(700) % 9 == 0, np.arange(700) < 4):
            want = [told(index.answer(seg, q, ask, visible)) for q in qs]
            assert [told(f) for f in index.answers(seg, qs, ask, visible)] == want


def test_queries_of_a_segment_take_no_loop_of_their_own(spark, monkeypatch):
    def alone(*a, **k):
        raise AssertionError("a query ran by itself")

    s = index.build_segment(np.arange(700), X, index.Build(max_degree=10, n_codes=16))[0]
    monkeypatch.setattr(search, "_Run", alone)
    assert len(index.answers(s, list(X[:50]), index.Ask(10))) == 50


def test_graphs_of_larger_segments_are_the_same_in_fewer_steps(monkeypatch):
    want = graph.build("vamana", X, np.arange(700), "l2", 12)[0]
    calls = []
    to = graph.Space.to
    monkeypatch.setattr(graph.Space, "to", lambda self, i, js: calls.append(len(js)) or to(self, i, js))
    monkeypatch.setattr(graph, "TABLE_ROWS", 100)
    began = time.process_time()
    y = X[:500]  # without the equal vectors, whose distances are zero by products only nearly
    got = graph.build("vamana", y, np.arange(500), "l2", 12)[0]
    assert len(calls) < 500 and time.process_time() - began < 20
    monkeypatch.setattr(graph, "TABLE_ROWS", 4096)
    assert np.array_equal(got, graph.build("vamana", y, np.arange(500), "l2", 12)[0]) and len(want) == 700
