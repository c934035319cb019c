"""Accuracy, locality and cost measures as DataFrame operations."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def recall(got: DataFrame, truth: DataFrame, k: int, queries: DataFrame) -> DataFrame:
    """(query_id, recall): overlap of the k-sets over k; a query without a hit
    has recall 0."""
    both = got.where(F.col("rank") <= k).join(truth.where(F.col("rank") <= k).select("query_id", "vec_id"), ["query_id", "vec_id"])
    n = both.groupBy("query_id").agg(F.count(F.lit(1)).alias("n"))
    return queries.select("query_id").join(n, "query_id", "left").select("query_id", (F.coalesce("n", F.lit(0)) / F.lit(float(k))).alias("recall"))


def range_ap(got: DataFrame, truth: DataFrame, queries: DataFrame) -> DataFrame:
    """(query_id, ap, n_truth): returned over exact hits; 1 if there are none."""
    g = got.groupBy("query_id").agg(F.count(F.lit(1)).alias("g"))
    t = truth.groupBy("query_id").agg(F.count(F.lit(1)).alias("t"))
    out = queries.select("query_id").join(t, "query_id", "left").join(g, "query_id", "left")
    return out.select("query_id", F.when(F.col("t").isNull(), 1.0).otherwise(F.coalesce("g", F.lit(0)) / F.col("t")).alias("ap"), F.coalesce("t", F.lit(0)).alias("n_truth"))


def mean_ios(stats: DataFrame) -> DataFrame:
    return stats.agg(F.avg("ios").alias("mean_ios"))


def vertex_utilisation(trace: DataFrame) -> DataFrame:
    """Mean share of used vertices over the loaded blocks; trace: used, loaded."""
    return trace.agg(F.avg(F.col("used") / F.col("loaded")).alias("xi"))


def path_length(stats: DataFrame) -> DataFrame:
    return stats.agg(F.avg("hops").alias("ell"))


def overlap_ratio(edges: DataFrame, layout: DataFrame, level: str = "graph") -> DataFrame:
    """OR of each vertex, the mean of each block, or the mean of the graph."""
    place = layout.select("segment_id", "vec_id", "block_id")
    size = place.groupBy("segment_id", "block_id").agg(F.count(F.lit(1)).alias("size"))
    src = place.select("segment_id", F.col("vec_id").alias("src"), F.col("block_id").alias("b"))
    dst = place.select("segment_id", F.col("vec_id").alias("dst"), F.col("block_id").alias("c"))
    near = edges.join(src, ["segment_id", "src"]).join(dst, ["segment_id", "dst"]).where("b = c").groupBy("segment_id", F.col("src").alias("vec_id")).agg(F.count(F.lit(1)).alias("near"))
    v = place.join(size, ["segment_id", "block_id"]).join(near, ["segment_id", "vec_id"], "left")
    v = v.select("segment_id", "block_id", "vec_id", F.when(F.col("size") > 1, F.coalesce("near", F.lit(0)) / (F.col("size") - 1)).otherwise(0.0).alias("overlap"))
    if level == "vertex":
        return v
    keys = ("segment_id", "block_id") if level == "block" else ("segment_id",)
    return v.groupBy(*keys).agg(F.avg("overlap").alias("overlap"))


def blocks_of_topk(truth: DataFrame, layout: DataFrame, k: int) -> DataFrame:
    """Mean number of distinct blocks that hold the k exact neighbours."""
    got = truth.where(F.col("rank") <= k).join(layout.select("vec_id", "segment_id", "block_id"), "vec_id")
    return got.groupBy("query_id").agg(F.countDistinct("segment_id", "block_id").alias("blocks")).agg(F.avg("blocks").alias("mean_blocks"))


def at_accuracy(curve: DataFrame, keys: tuple[str, ...], accuracy: str, cost: str, target: float) -> DataFrame:
    """Cost at a target accuracy, between the two points of the curve around it."""
    w = Window.partitionBy(*keys).orderBy(accuracy, cost)
    c = curve.withColumn("a0", F.lag(accuracy).over(w)).withColumn("c0", F.lag(cost).over(w))
    hit = c.where((F.col(accuracy) >= target) & (F.col("a0").isNull() | (F.col("a0") < target)))
    a, b = F.col("a0"), F.col(accuracy)
    value = F.when(a.isNull(), F.col(cost)).otherwise(F.col("c0") + (F.col(cost) - F.col("c0")) * (target - a) / (b - a))
    return hit.select(*keys, value.alias(cost))
