"""Vectors made from the given tables: floats as they are, bytes, letter
histograms of texts, measures of order lines, events of users."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

LETTERS = "abcdefghijklmnopqrstuvwxyz"


def emb_f32(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    return t.select("vec_id", F.col("embedding").cast("array<double>").alias("vec"))


def to_u8(vec: Column) -> Column:
    return F.transform(vec, lambda x: F.floor((x.cast("double") + 1) * 127.5 + 0.5).cast("double"))


def emb_u8(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    return t.select("vec_id", to_u8(F.col("embedding")).alias("vec"))


def letter_histogram(text: Column) -> Column:
    """26 values 0..255: thousandths of the text's characters, capped."""
    n = F.length(text)
    return F.array(*(F.least(F.lit(255), F.expr("0") + F.floor((n - F.length(F.replace(text, F.lit(c), F.lit("")))) * 1000 / F.greatest(n, F.lit(1)))).cast("double") for c in LETTERS))


def doc_u8(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return t.select(F.col("doc_id").alias("vec_id"), letter_histogram(F.coalesce("text", F.lit(""))).alias("vec"))


def line_u8(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = spark.read.parquet(f"{sf_dir}/lineitem.parquet")
    clip = lambda x: F.least(F.lit(255), F.greatest(F.lit(0), F.floor(x))).cast("double")
    days = F.pmod(F.datediff("l_shipdate", F.lit("1995-01-01")), F.lit(256))
    parts = (F.col("l_quantity"), F.col("l_extendedprice") / 500, F.round(F.col("l_discount") * 1000), F.round(F.col("l_tax") * 1000), days)
    v = t.select((F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("vec_id"), F.array(*map(clip, parts)).alias("vec"))
    return v.groupBy("vec_id").agg(F.min("vec").alias("vec"))  # line numbers repeat within some orders


def clustered_f32(spark: SparkSession, sf_dir: str, n_clusters: int = 40) -> DataFrame:
    """The embeddings drawn towards the first ``n_clusters`` of them: vectors in
    clusters, which the embeddings themselves are not."""
    v = emb_f32(spark, sf_dir)
    centre = v.where(F.col("vec_id") < n_clusters).select(F.col("vec_id").alias("c"), F.col("vec").alias("centre"))  # n_clusters rows
    return v.join(F.broadcast(centre), F.pmod("vec_id", F.lit(n_clusters)) == F.col("c")).select("vec_id", F.zip_with("vec", "centre", lambda x, y: x * 0.25 + y).alias("vec"))


EVENT_TYPES = ("click", "error", "purchase", "signup", "view")


def user_vec(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = spark.read.parquet(f"{sf_dir}/events.parquet")
    counts = t.groupBy("user_id").pivot("event_type", list(EVENT_TYPES)).count()
    return counts.select(F.col("user_id").alias("vec_id"), F.array(*(F.coalesce(F.col(c), F.lit(0)).cast("double") for c in EVENT_TYPES)).alias("vec"))


SETS = {"emb_f32": emb_f32, "clustered_f32": clustered_f32, "emb_u8": emb_u8, "doc_u8": doc_u8, "line_u8": line_u8, "user_vec": user_vec}
