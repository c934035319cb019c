"""A corpus pipeline from the operators of ``blockgraph.llm``.

Each stage takes (spark, docs, sf_dir) and works on all that the stage before
it kept. ``run`` writes each result to the shared folder and reads it back, so
that a lost executor never costs more than the stage at hand.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockgraph.llm import bpe, decontaminate, line_dedup, quality, simhash, similar
from blockgraph.llm.common import documents, materialise, own
from blockgraph.llm.queries import rank_file


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops what a rule of the cascade rejects."""
    return quality.keep_good(docs)


def line_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Takes the boilerplate lines of each source out of the texts; equal texts
    count as one page, so that copies are left to the next stage."""
    out = line_dedup.clean(docs, F.col("source"), counts=False, distinct_pages=True).withColumn("n_chars", F.length("text").cast("long"))
    return out.select(*own(docs))


def simhash_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each group of near-duplicates: SimHash fingerprints
    are compared in bit planes, and texts whose sets of five-word shingles have a
    Jaccard similarity of 0.8 or more are linked."""
    return simhash.keep_first(docs, similar.near_duplicates(docs.select("doc_id", "text")))


def decontaminate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that hold a benchmark passage."""
    return decontaminate.remove_leaks(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def byte_bpe_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Encodes and decodes what is left."""
    return bpe.digests(docs, *rank_file())


STAGES = [
    ("quality rules", quality_rules),
    ("line dedup", line_dedup_stage),
    ("SimHash near-dedup", simhash_stage),
    ("benchmark decontamination", decontaminate_stage),
    ("byte-level BPE", byte_bpe_stage),
]

#: SQL can't express fingerprints, latent search and BPE; tests/llm compares
#: run() with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
