import numpy as np
import pytest
from pyspark.errors import AnalysisException
from pyspark.sql import functions as F

from blockgraph import vector_queries
from blockgraph.operators import exact, index, kmeans, search


def points(spark, n=60, dim=4, seed=3):
    x = np.random.default_rng(seed).standard_normal((n, dim))
    return x, spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, vec array<double>")


def test_kmeans_step_with_empty_partitions(spark):
    x, df = points(spark)
    spread = df.repartition(3, F.pmod("vec_id", F.lit(1)))  # one partition has all rows
    assert sorted(spread.rdd.glom().map(len).collect()) == [0, 0, 60]
    a = kmeans.assign_local(x, x[:2])
    assert np.allclose(kmeans.step(spread, x[:2]), [x[a == i].mean(0) for i in (0, 1)])


def test_segments_follow_rows():
    assert [vector_queries.segments_by_rows(n) for n in (0, 1, 2_500, 2_501, 10_256, 20_000, 100_000, 100_001, 1_000_000)] == [1, 1, 1, 2, 5, 8, 8, 9, 80]


def test_segments_are_built_by_several_tasks(spark):
    _, df = points(spark, 240)
    built = index.build(index.assign(df, 6), index.Build(builder="knn", max_degree=4, layout="idpack", sample_ratio=0, n_sub=0))
    tasks = built.select("segment_id", F.spark_partition_id().alias("task")).distinct().collect()
    assert len({r.segment_id for r in tasks}) == 6 and len({r.task for r in tasks}) > 3


def test_hits_of_several_segments_are_exact(spark):
    x, df = points(spark, 240)
    built = index.build(index.assign(df, 6), index.Build(builder="vamana", max_degree=8, block_cap=6))
    q = exact.sample_queries(df, 40)
    got = index.merge(index.run_queries(built, index.everywhere(q, 6), index.Ask(7, options=search.Options(cand_size=1000)), 2), 7)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, exact.knn(df, q, 7).collect()))


def test_search_list_stays_sorted_and_finds_the_first_open_row():
    x = np.random.default_rng(1).standard_normal((300, 6))
    seg, _ = index.build_segment(np.arange(300), x, index.Build(max_degree=8, block_cap=6))
    run = search._Run(seg, x[5] + 0.1, search.Options(cand_size=1000), None)
    run.begin()
    while now := run.choose():
        assert run.pool == sorted(run.pool) and now == [next(r for _, r in run.pool if r not in run.done)]
        assert all(r in run.done for _, r in run.pool[: run.first])
        run.apply(now)
    assert len(run.done) == 300


def test_scan_holds_a_tile_of_distances_at_once(spark, monkeypatch):
    x, df = points(spark, 200)
    q = df.select(F.col("vec_id").alias("query_id"), F.col("vec").alias("qvec"))
    want = sorted(map(tuple, exact.knn(df, q, 5, exclude_self=True).collect()))

    def small(a, b, metric, whole=exact.pairwise):
        assert len(a) * len(b) <= 1000
        return whole(a, b, metric)

    monkeypatch.setattr(exact, "TILE_VALUES", 1000)
    monkeypatch.setattr(exact, "pairwise", small)
    assert sorted(map(tuple, exact.knn(df.coalesce(1), q, 5, exclude_self=True).collect())) == want


@pytest.mark.parametrize("name", ["block_geometry", "io_model", "memory_table", "pq_bytes", "segment_capacity"])
def test_space_arithmetic_reads_the_given_tables(spark, tmp_path, name):
    for table, key in (("embeddings", "vec_id"), ("documents", "doc_id"), ("events", "event_id")):
        spark.read.parquet(f"/root/testdata/sf0.001/{table}.parquet").where(F.col(key) < 300).write.parquet(f"{tmp_path}/{table}.parquet")
    f = vector_queries.Q[name]
    part, whole = (sorted(map(tuple, f(spark, d).collect())) for d in (str(tmp_path), "/root/testdata/sf0.001"))
    assert len(part) == len(whole) and (part != whole or name in ("pq_bytes", "segment_capacity"))  # small sets fit any budget
    with pytest.raises(AnalysisException):  # no table, no result
        f(spark, f"{tmp_path}/none").collect()


def test_graph_and_cost_need_no_task_with_all_vectors(spark, monkeypatch):
    def build(*a, **k):
        raise AssertionError("one task would get all vectors")

    sf = "/root/testdata/sf0.01"
    monkeypatch.setattr(index, "build", build)
    n = spark.read.parquet(f"{sf}/embeddings.parquet").count()
    assert vector_queries.Q["graph_degree_stats"](spark, sf).first() == (n, 16 * n, 16, 16)
    assert sum(r.n * r.in_degree for r in vector_queries.Q["indegree_hist"](spark, sf).collect()) == 16 * n
    assert vector_queries.Q["disk_cost"](spark, sf).first()[0] == -(-n // 12)
