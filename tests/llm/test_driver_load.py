"""What near-dedup asks of the driver, and copies that it makes of rows."""

import numpy as np

from blockgraph.llm import components as module
from blockgraph.llm import similar

from .test_similar import brute, corpus


def _plans(monkeypatch, where):
    """Plans of all tables that a module stores from now on."""
    plans, store = [], where.materialise

    def stored(df, *rest, **named):
        plans.append(df._jdf.queryExecution().optimizedPlan().toString())
        return store(df, *rest, **named)

    monkeypatch.setattr(where, "materialise", stored)
    return plans


def _roots(n, edges):
    root = list(range(n))
    for a, b in edges:
        x, y = root[a], root[b]
        root = [min(x, y) if r in (x, y) else r for r in root]
    return {i: root[i] for i in {*sum(edges, ())}}


def test_stars_need_no_round_and_no_hub_no_broadcast(spark, monkeypatch):
    plans = _plans(monkeypatch, module)
    stars = [(i, i % 10) for i in range(10, 200)]
    got = {r.node: r.root for r in module.components(spark.createDataFrame(stars, "a long, b long")).collect()}
    assert got == _roots(200, stars) and len(plans) == 1
    chain = [(i, i + 1) for i in range(60) if i % 7]
    got = {r.node: r.root for r in module.components(spark.createDataFrame(chain, "a long, b long")).collect()}
    assert got == _roots(61, chain)
    assert len(plans) > 2 and not any("broadcast" in p for p in plans)


def test_hubs_are_broadcast(spark, monkeypatch):
    plans = _plans(monkeypatch, module)
    rng = np.random.default_rng(5)
    edges = [(int(a), int(b)) for a, b in rng.integers(0, 150, (60, 2)) if a != b] + [(149, i) for i in range(40, 90)]
    got = {r.node: r.root for r in module.components(spark.createDataFrame(edges, "a long, b long"), least_hub=20).collect()}
    assert got == _roots(150, edges) and any("broadcast" in p for p in plans)


def test_rows_of_small_groups_are_not_copied(spark, monkeypatch):
    plans = _plans(monkeypatch, similar)
    texts = corpus()
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    want = dict(enumerate(brute(texts)))
    assert {r.doc_id: r.component_id for r in similar.near_duplicates(df).collect()} == want
    assert not any("sequence(" in p for p in plans)
    assert {r.doc_id: r.component_id for r in similar.near_duplicates(df, block=8).collect()} == want
    assert any("sequence(" in p for p in plans)  # crowded ones are dealt in parts
