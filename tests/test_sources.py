import numpy as np
import pytest

from blockgraph.functions import features
from blockgraph.operators import catalog, exact, index, search
from blockgraph.sources import vectors
from blockgraph.streaming import changes

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("fmt", ["parquet", "json", "csv"])
def test_text_and_parquet(spark, tmp_path, fmt):
    v = features.emb_f32(spark, SF).where("vec_id < 20")
    vectors.write(v, str(tmp_path / "v"), fmt)
    got = vectors.read(spark, str(tmp_path / "v"), fmt)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, v.collect()))


@pytest.mark.parametrize("fmt", ["fvecs", "bvecs"])
def test_records(spark, tmp_path, fmt):
    x = np.arange(60).reshape(12, 5)
    (tmp_path / "a.bin").write_bytes(vectors.records(x[:7], fmt))
    (tmp_path / "b.bin").write_bytes(vectors.records(x[7:], fmt))
    (tmp_path / "c.bin").write_bytes(b"")
    got = {r.vec_id: r.vec for r in vectors.read(spark, str(tmp_path), fmt).collect()}
    assert got == {i: row.tolist() for i, row in enumerate(x.astype(float))}


def test_pushdown(spark):
    df = vectors.table(spark, SF, "events", ["event_id"], "user_id > 5")
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(user_id), GreaterThan(user_id,5)]" in plan and "ReadSchema: struct<event_id:bigint,user_id:bigint>" in plan


def test_save_and_load(spark, tmp_path):
    v = features.emb_f32(spark, SF)
    b = index.Build(layout="pad", layout_options=(("spill", "continue"),))
    i = index.build(index.assign(v, 3), b)
    catalog.save(i, str(tmp_path), "emb", b)
    back, settings = catalog.load(spark, str(tmp_path), "emb")
    assert settings == b
    q = exact.sample_queries(v)
    hits = lambda x: sorted(map(tuple, index.merge(index.run_queries(x, index.everywhere(q, 3), index.Ask(3)), 3).collect()))
    assert hits(back) == hits(i)


def test_rebuild_and_replay(spark):
    v = features.emb_f32(spark, SF).where("vec_id < 60")
    dyn = changes.DynamicIndex(spark, v, index.Build(max_degree=8), threshold=25)
    ev = spark.read.parquet(f"{SF}/events.parquet")
    batch = changes.from_events(ev.where("event_id < 40"), v)
    dyn.commit(batch, 0)
    before = sorted(r.vec_id for r in dyn.snapshot().collect())
    dyn.commit(batch, 0)
    assert sorted(r.vec_id for r in dyn.snapshot().collect()) == before and dyn.version == 0
    q = exact.sample_queries(v)
    ask = index.Ask(60, options=search.Options(cand_size=999))
    one = sorted(map(tuple, dyn.search(q, ask).collect()))
    want = sorted(map(tuple, exact.knn(dyn.snapshot(), q, 60).collect()))
    assert one == want
    dyn.commit(changes.from_events(ev.where("event_id between 40 and 200"), v), 1)
    assert dyn.version == 1 and not dyn.batches()
    assert sorted(map(tuple, dyn.search(q, ask).collect())) == sorted(map(tuple, exact.knn(dyn.snapshot(), q, 60).collect()))
    assert '"version": 1' in dyn.manifest()
