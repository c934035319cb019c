import numpy as np
import pytest
from pyspark.sql import functions as F

from blockgraph.functions.distance import pairwise
from blockgraph.operators import exact, postings


@pytest.mark.parametrize("metric", ["l2", "l2sq", "ip", "cosine"])
def test_nearest_rows_by_products_are_those_by_differences(metric):
    rng = np.random.default_rng(2)
    for x in (rng.normal(size=(400, 8)), rng.integers(1, 4, (400, 4)).astype(float), 1000 + rng.normal(size=(400, 3)) * 1e-4, np.ones((400, 5))):
        ids = rng.permutation(400)
        for k in (1, 7, 90, 400):
            for q, (rows, d) in zip(x[:20], exact.nearest_each(ids, x, x[:20], k, metric)):
                want = np.round(pairwise(q, x, metric)[0], 6) + 0.0
                best = np.lexsort((ids, want))[:k]
                assert np.array_equal(rows, best) and np.array_equal(d, want[best])


def test_lists_send_on_no_more_than_the_nearest(spark):
    x = np.round(np.random.default_rng(4).normal(size=(500, 6)), 1)
    x[100:130] = x[7]
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, vec array<double>")
    q = exact.sample_queries(df, 25)
    p, probes = postings.assign(df, x[:9], 3, 0.6), postings.probe(q, x[:9], 9, None)
    want = sorted(map(tuple, exact.knn(df, q, 8).collect()))
    for parts in ({}, {"part_rows": 20, "part_queries": 3}):
        got = postings.search(p, probes, 8, **parts)
        assert sorted(map(tuple, got.collect())) == want
    some = probes.where("list_id < 3")  # of a part of the lists
    inside = {(r.list_id, r.vec_id) for r in p.collect()}
    got = {(r.query_id, r.vec_id) for r in postings.search(p, some, 500).collect()}
    assert got == {(r.query_id, v) for r in some.collect() for at, v in inside if at == r.list_id}
    plan = postings.search(p, probes, 8)._jdf.queryExecution().optimizedPlan().toString()
    assert "FlatMapCoGroupsInPandas" in plan  # pairs of a query and a vector are no rows
    assert postings.search(p.where(F.lit(False)), probes, 8).collect() == []


def test_pairs_within_a_radius_are_all_found():
    rng = np.random.default_rng(6)
    for x, r in ((rng.integers(0, 30, (500, 5)).astype(float), 6.0), (rng.normal(size=(400, 9)) * 3, 5.5), (np.zeros((150, 3)), 1.0)):
        y = np.concatenate([x[:200], x[50:90]])
        got = sorted((int(a), int(b)) for i, j in exact.pairs_within(x, y, r) for a, b in zip(i, j))
        assert got == [tuple(p) for p in np.argwhere(np.round(pairwise(x, y, "l2"), 6) <= r).tolist()]


def test_crowded_cells_are_cut_and_pairs_apart_are_no_rows(spark, monkeypatch):
    x = np.random.default_rng(7).integers(0, 14, (300, 3)).astype(float)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, vec array<double>")
    plans, plain = {}, exact.stored

    def seen(t, name="table", *a):
        plans[name] = t._jdf.queryExecution().optimizedPlan().toString()
        return plain(t, name, *a)

    monkeypatch.setattr(exact, "stored", seen)
    want = sorted(map(tuple, exact.near_classes(df, 2.0, (0, 1, 2)).collect()))
    assert "FlatMapGroupsInPandas" in plans["near"] and "Join" not in plans["near"]
    assert sorted(map(tuple, exact.near_classes(df, 2.0, (0, 1, 2), cell_rows=3).collect())) == want
    assert "sequence(" in plans["near"]
    link = np.round(pairwise(x, x, "l2"), 6) <= 2.0
    assert [n for _, _, n in want] == (link.sum(1) - 1).tolist()
