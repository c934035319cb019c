"""Readers and writers of vectors: Parquet, text (CSV, JSON) and binary records
(an int32 dimension in front of each vector: .fvecs with floats, .bvecs with
bytes). All give (vec_id, vec ARRAY<DOUBLE>)."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None, where: str | None = None) -> DataFrame:
    """A given table; columns and filter reach the scan."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    df = df.where(where) if where else df
    return df.select(*columns) if columns else df


def read(spark: SparkSession, path: str, fmt: str) -> DataFrame:
    if fmt == "parquet":
        return spark.read.parquet(path).select("vec_id", F.col("vec").cast("array<double>").alias("vec"))
    if fmt == "json":
        return spark.read.schema("vec_id long, vec array<double>").json(path)
    if fmt == "csv":
        t = spark.read.schema("vec_id long, vec string").option("header", "true").csv(path)
        return t.select("vec_id", F.split("vec", " ").cast("array<double>").alias("vec"))
    if fmt in ("fvecs", "bvecs"):
        return _records(spark, path, fmt)
    raise ValueError(fmt)


def write(df: DataFrame, path: str, fmt: str) -> None:
    v = df.select("vec_id", F.col("vec").cast("array<double>").alias("vec"))
    if fmt == "csv":
        v.select("vec_id", F.array_join(F.col("vec").cast("array<string>"), " ").alias("vec")).write.option("header", "true").csv(path)
    else:
        getattr(v.write, fmt)(path)


def records(x: np.ndarray, fmt: str) -> bytes:
    """The binary form of a matrix."""
    kind = {"fvecs": "<f4", "bvecs": "u1"}[fmt]
    head = np.full((len(x), 1), x.shape[1], "<i4").view("u1").reshape(len(x), 4)
    return np.hstack([head, np.ascontiguousarray(x, kind).view("u1").reshape(len(x), -1)]).tobytes()


def _records(spark: SparkSession, path: str, fmt: str) -> DataFrame:
    """A file is one row of ``binaryFile``; ids count on over files in the
    order of their names. Large sets come as many files of bounded size."""
    kind, width = {"fvecs": ("<f4", 4), "bvecs": ("u1", 1)}[fmt]
    files = spark.read.format("binaryFile").load(path)

    def count(batches):
        for b in batches:
            yield pd.DataFrame({"path": b["path"], "n": [len(c) // (4 + width * int.from_bytes(c[:4], "little")) if len(c) else 0 for c in b["content"]]})

    sizes = files.select("path", "content").mapInPandas(count, "path string, n long").orderBy("path").collect()  # a row for each file
    start, at = {}, 0
    for r in sizes:
        start[r.path] = at
        at += r.n

    def run(batches):
        for b in batches:
            for p, c in zip(b["path"], b["content"]):
                if len(c):
                    dim = int.from_bytes(c[:4], "little")
                    rows = np.frombuffer(c, "u1").reshape(-1, 4 + width * dim)[:, 4:]
                    x = np.ascontiguousarray(rows).view(kind).astype(float)
                    for i in range(0, len(x), 10_000):
                        yield pd.DataFrame({"vec_id": np.arange(i, min(i + 10_000, len(x))) + start[p], "vec": list(x[i : i + 10_000])})

    return files.select("path", "content").mapInPandas(run, "vec_id long, vec array<double>")
