"""Helpers shared by the corpus operators."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import at_exit, discard, shared_dir  # noqa: F401
from ..session import stored as materialise  # noqa: F401

#: White space of the word rules: space and the controls 9 to 13.
SPACE = "\\x20\\x09-\\x0D"
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER_TABLE = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def own(df: DataFrame) -> list[Column]:
    """The columns of df, whatever characters their names have."""
    return [F.col("`" + c.replace("`", "``") + "`") for c in df.columns]


def portions(batches, size: int = 2 << 20):
    """Arrow batches cut into slices of about ``size`` bytes (one row at least).
    Spark bounds a batch by its bytes; this bounds what is unpacked at once."""
    for b in batches:
        step = max(1, b.num_rows * size // max(1, b.nbytes))
        for at in range(0, b.num_rows, step):
            yield b.slice(at, step)


def crc_fold(doc_id: Column, folds: int = 5) -> Column:
    """crc32 of the id's decimal text, modulo folds (null ids: -1)."""
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(folds)), F.lit(-1))


def text_bytes(df: DataFrame, col: str = "text") -> int:
    return df.select(F.sum(F.octet_length(F.col(col)).cast("long"))).first()[0] or 0


def chunk_count(spark: SparkSession, total_bytes: int, chunk_bytes: int) -> int:
    return max(spark.sparkContext.defaultParallelism, math.ceil(total_bytes / chunk_bytes), 1)


def as_text(s: str | None) -> bytes:
    """UTF-8 bytes; a null text is empty."""
    return b"" if s is None else s.encode("utf-8", "surrogatepass")
