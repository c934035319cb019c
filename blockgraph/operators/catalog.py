"""Indexes on disk: parts by segment, and a manifest that names the version."""

from __future__ import annotations

from dataclasses import fields

from pyspark.sql import DataFrame, SparkSession

from . import index

MANIFEST = "name string, version int, path string, settings string"


def save(indexed: DataFrame, root: str, name: str, build: index.Build, version: int = 1) -> str:
    """Write the parts, then the manifest; readers see a version once its
    manifest is there."""
    import json

    spark = indexed.sparkSession
    path = f"{root}/{name}/v{version}"
    indexed.write.partitionBy("segment_id").parquet(f"{path}/parts")
    settings = json.dumps(index.describe(build), sort_keys=True)
    spark.createDataFrame([(name, version, path, settings)], MANIFEST).coalesce(1).write.parquet(f"{path}/manifest")
    return path


def load(spark: SparkSession, root: str, name: str, version: int = 1) -> tuple[DataFrame, index.Build]:
    import json

    m = spark.read.schema(MANIFEST).parquet(f"{root}/{name}/v{version}/manifest").first()
    known = {f.name for f in fields(index.Build)}
    settings = {k: tuple(map(tuple, v)) if k == "layout_options" else v for k, v in json.loads(m.settings).items() if k in known}
    parts = spark.read.schema("part int, n_parts int, payload binary, segment_id int").parquet(f"{m.path}/parts")
    return parts.select("segment_id", "part", "n_parts", "payload"), index.Build(**settings)
