import numpy as np
from pyspark.sql import functions as F

from blockgraph.functions.distance import pairwise
from blockgraph.operators import exact, index
from blockgraph.sources import block_file


def points(spark, n, dim, scale=1.0):
    x = np.round(np.random.default_rng(5).standard_normal((n, dim)) * scale)
    return x, spark.createDataFrame([(3 * i, v.tolist()) for i, v in enumerate(x)], "vec_id long, vec array<double>")


def test_blocks_of_a_graph_that_no_task_holds(spark):
    x, df = points(spark, 100, 6, 100)
    whole = index.build(index.assign(df, 1), index.Build(builder="knn", max_degree=8, block_cap=12, layout="idpack", sample_ratio=0, n_sub=0))
    row = lambda r: (r.segment_id, r.block_id, r.slot, r.vec_id, tuple(r.vec), tuple(r.nbrs))
    want = sorted(map(row, block_file.vertices(block_file.blocks_table(whole)).collect()))
    got = block_file.vertices(block_file.blocks_by_id(df, index.edges(whole), 12))
    assert sorted(map(row, got.collect())) == want and len(want) == 100
    alone = block_file.vertices(block_file.blocks_by_id(df.where("vec_id = 0"), index.edges(whole).where("src < 0"), 12)).first()
    assert (alone.block_id, alone.vec_id, alone.nbrs) == (0, 0, [])


def test_near_classes_never_broadcast_the_exploded_nodes(spark, monkeypatch):
    x, df = points(spark, 300, 4, 6)
    plans, plain = {}, exact.stored

    def seen(t, name="table", *a):
        plans[name] = t._jdf.queryExecution().executedPlan().toString()
        return plain(t, name, *a)

    monkeypatch.setattr(exact, "stored", seen)
    got = {r.vec_id: (r.class_id, r.n_links) for r in exact.near_classes(df, 4.0, (0, 1)).collect()}
    assert "Generate" in plans["near"] and "Broadcast" not in plans["near"]
    link = np.round(pairwise(x, x, "l2"), 6) <= 4.0
    label = np.arange(300)
    while True:
        low = np.array([label[row].min() for row in link])
        if (low == label).all():
            break
        label = low
    assert got == {3 * i: (3 * int(label[i]), int(link[i].sum()) - 1) for i in range(300)}
