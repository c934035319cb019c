"""Queries of the corpus operators and the SQL of those that SQL can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, decontaminate, html_text, line_dedup, ppm, quality, simhash, suffix_dedup, token_rollup, toxicity
from .common import at_exit, crc_fold, documents, materialise, shared_dir

TOKENIZER = "byte_bpe_multi_50k.tiktoken"


def rank_file(name: str = TOKENIZER) -> tuple[str, str]:
    """Path of a rank file and the pattern that goes with it."""
    import public_tokenizers

    return public_tokenizers.path(name), public_tokenizers.PATTERN


def op1_ppm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    held = crc_fold(F.col("doc_id")) == 1
    out = ppm.score(documents(spark, sf_dir).select("doc_id", "text"), ~held)
    return out.select("doc_id", (~F.col("train")).alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")


def op2_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract(spark.read.parquet(f"{sf_dir}/pages.parquet"))


def op3_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.find_leaks(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def op4_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    cols = ("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")
    return quality.judge(documents(spark, sf_dir).select("doc_id", "text")).select(*cols)


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir).select("doc_id", "source", "text")
    out = line_dedup.clean(docs, F.col("source"))
    return out.select("doc_id", "source", "n_lines", "n_dropped", F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))


def op6_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.remove_repeats(documents(spark, sf_dir), keep_bytes=False)


def op7_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(documents(spark, sf_dir))
    return found.select("doc_id", simhash.hex_of(F.col("fp")).alias("fingerprint"), "component_id")


def op8_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.digests(documents(spark, sf_dir), *rank_file())


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir).select("doc_id", "text")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").where(crc_fold(F.col("doc_id")) != 0)
    out = toxicity.score(docs, toxicity.fit(docs, labels))
    return out.select("doc_id", (crc_fold(F.col("doc_id")) == 0).alias("held_out"), "score", "predicted")


def _changes(counts: DataFrame, op: str, old, new) -> DataFrame:
    return counts.select(F.lit(op).alias("op"), "doc_id", "source", "lang", "tokenizer", old.cast("long").alias("old_tokens"), new.cast("long").alias("new_tokens"))


def _rollup(spark: SparkSession, sf_dir: str, counts: DataFrame, name: str) -> DataFrame:
    """Three batches, one of them sent twice: all documents come in, those
    labelled toxic go, and the word counts of those labelled good are revised
    to hold an end token."""
    import uuid

    rollup = token_rollup.TokenRollup(spark, at_exit(spark, f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"))
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").where("doc_id is not null")
    toxic = labels.where("toxic = 1").select("doc_id").distinct()
    good = labels.groupBy("doc_id").agg(F.max("toxic").alias("t"), F.max("quality").alias("q")).where("t = 0 and q = 1").select("doc_id")
    n, none = F.col("n"), F.lit(0)
    rollup.apply("load", _changes(counts, "insert", none, n))
    gone = _changes(counts.join(toxic, "doc_id", "left_semi"), "delete", n, none)
    rollup.apply("toxic", gone)
    rollup.apply("end-token", _changes(counts.where("tokenizer = 'ws-words@1'").join(good, "doc_id", "left_semi"), "revise", n, n + 1))
    rollup.apply("toxic", gone)
    rollup.compact()
    return rollup.totals().select("source", "lang", "tokenizer", "n_docs", "n_tokens")


def _word_counts(docs: DataFrame) -> DataFrame:
    n = F.size(quality.word_array(F.col("text"))).cast("long")
    return docs.select("doc_id", "source", "lang", F.lit("ws-words@1").alias("tokenizer"), n.alias("n"))


def op10_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Totals for two tokenizer versions, white-space words and byte BPE."""
    docs = documents(spark, sf_dir)
    tokens = bpe.count(docs, *rank_file(), keep=("doc_id", "source", "lang"))
    tokens = materialise(tokens, "counts")  # one row a document; the two versions are unfolded on reading
    both = F.explode(F.array(*(F.struct(F.lit(t).alias("tokenizer"), F.col(c).alias("n")) for t, c in (("ws-words@1", "n_words"), ("byte-bpe-multi-50k@1", "n_tokens")))))
    counts = tokens.select("doc_id", "source", "lang", both.alias("x")).select("doc_id", "source", "lang", "x.*")
    return _rollup(spark, sf_dir, counts, "rollup")


def llm_word_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same rollup for words only, which SQL can follow."""
    return _rollup(spark, sf_dir, materialise(_word_counts(documents(spark, sf_dir)), "counts"), "word-rollup")


def queries() -> dict:
    own = (op1_ppm_score, op2_html_text, op3_decontaminate, op4_quality_rules, op5_line_dedup, op6_suffix_dedup, op7_simhash, op8_byte_bpe, op9_toxicity, op10_token_counts, llm_word_rollup)
    return {f.__name__: f for f in own}
