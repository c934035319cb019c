import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import functions as F

from blockgraph import session
from blockgraph.llm import ppm


def test_own_keys_are_the_distinct_strings():
    rng = np.random.default_rng(2)
    texts = [bytes(rng.integers(97, 101, 400_000, dtype=np.uint8)) for _ in range(4)] + [b"", b"ab"]
    assert np.array_equal(ppm._own_keys(texts, 6), ppm._own_strings(texts, [True] * len(texts), 6)[0])
    assert not len(ppm._own_keys([], 6))


def test_small_batches_hold_within_and_not_after(spark):
    before = spark.conf.get(session.BATCH_ROWS)
    with session.small_batches(spark):
        sizes = spark.range(0, 2500, 1, 1).mapInArrow(lambda bs: (b.slice(0, 1).set_column(0, "id", __import__("pyarrow").array([b.num_rows])) for b in bs), "id long").collect()
    assert max(r.id for r in sizes) == 1000 and spark.conf.get(session.BATCH_ROWS) == before


def test_small_batches_hold_bytes_too(spark):
    wide = spark.range(0, 40, 1, 1).selectExpr("id", "repeat('x', 200000) as t")
    count = lambda bs: (pa.RecordBatch.from_pydict({"id": [b.num_rows]}) for b in bs)
    with session.small_batches(spark):
        sizes = [r.id for r in wide.mapInArrow(count, "id long").collect()]
    assert sum(sizes) == 40 and max(sizes) <= 8
    assert spark.conf.get(session.READ_ROWS) == "4096"


def test_large_rows_are_stored_in_small_groups(spark):
    # a row group, and so a page of it, used to hold all that a task wrote
    wide = spark.range(0, 60, 1, 1).select("id", F.expr("transform(sequence(1, 200), i -> sha2(cast(id * 200 + i as string), 512))").cast("string").cast("binary").alias("b"))
    kept = session.stored(wide.withColumn("b", F.concat(*["b"] * 12)), "wide", options=session.LARGE_ROWS)
    files = [pq.ParquetFile(f.removeprefix("file:").replace("///", "/")) for f in kept.inputFiles()]
    groups = [f.metadata.row_group(i) for f in files for i in range(f.metadata.num_row_groups)]
    assert sum(g.num_rows for g in groups) == 60 and max(g.total_byte_size for g in groups) < 6 << 20
    assert {g.column(1).compression for g in groups} == {"UNCOMPRESSED"}
    session.discard(kept)


def test_portions_of_a_result_keep_its_rows():
    t = pa.table({"k": list(range(50)), "v": pa.array([bytes([i]) * 200_000 for i in range(50)], pa.binary())})
    cut = ppm._in_portions(t)
    assert cut.equals(t) and max(b.nbytes for b in cut.to_batches()) < 2 << 20
    assert ppm._in_portions(t.slice(0, 0)).equals(t.slice(0, 0))
