"""SQL names for the vector operators: scalar functions in SQL itself, so they
stay in generated code, and table functions over one segment's index."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from ..operators import index, search


def register(spark: SparkSession, segment: DataFrame) -> None:
    """segment: the index of one segment, whose parts are sent to the tasks. Its
    size is that of a segment (``index.assign`` with max_vectors), whatever the
    table's."""
    if segment.select("segment_id").distinct().count() > 1:
        raise ValueError("table functions take the index of one segment; use index.run_queries for more")
    rows = segment.collect()
    payload = spark.sparkContext.broadcast(b"".join(r.payload for r in sorted(rows, key=lambda r: r.part)))

    class VectorSearch:
        def __init__(self):
            self.seg = None

        def eval(self, q: list, k: int, cand_size: int):
            self.seg = self.seg or search.Segment.unpack(payload.value)
            f = index.answer(self.seg, q, index.Ask(k, options=search.Options(cand_size=cand_size)))
            for r, d in zip(f.rows, f.dists):
                yield int(self.seg.ids[r]), float(d)

    class VectorRange:
        def __init__(self):
            self.seg = None

        def eval(self, q: list, r: float, cand_size: int, grow_ratio: float):
            self.seg = self.seg or search.Segment.unpack(payload.value)
            f = index.answer(self.seg, q, index.Ask(r=r, options=search.Options(cand_size=cand_size, grow_ratio=grow_ratio)))
            for row, d in zip(f.rows, f.dists):
                yield int(self.seg.ids[row]), float(d)

    for name, cls in (("vector_search", VectorSearch), ("vector_range", VectorRange)):
        spark.udtf.register(name, udtf(cls, returnType="vec_id: bigint, dist: double"))
    spark.sql("create or replace temporary function l2(a array<double>, b array<double>) returns double return sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0d, (s, x) -> s + x))")
    spark.sql("create or replace temporary function neg_ip(a array<double>, b array<double>) returns double return -aggregate(zip_with(a, b, (x, y) -> x * y), 0d, (s, x) -> s + x)")
