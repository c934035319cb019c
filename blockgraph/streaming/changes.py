"""A dynamic index: changes arrive as a stream, a static index answers the rest.

Each micro-batch is committed to a folder of its own id, so a replay rewrites
the same rows. The snapshot is the newest change of each vector; a search joins
the static index, where changed vectors lead the way but are no answers, and an
exact search over the small changed set. Past ``threshold`` changes the static index is built anew from the
snapshot and the folders it holds are left behind, by a new version.
"""

from __future__ import annotations

import json
import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators import exact, index
from ..session import at_exit, shared_dir, stored

CHANGES = "vec_id long, vec array<double>, op string, ts timestamp, event_id long"


def from_events(events: DataFrame, vectors: DataFrame) -> DataFrame:
    """Errors delete a vector, purchases put a scaled copy, others do nothing;
    works on a stream and on a table."""
    n = vectors.count()
    op = F.when(F.col("event_type") == "error", "delete").when(F.col("event_type") == "purchase", "upsert")
    e = events.select("event_id", "ts", F.pmod("event_id", F.lit(n)).alias("vec_id"), op.alias("op")).where("op is not null")
    return e.join(vectors.select("vec_id", "vec"), "vec_id").select("vec_id", F.transform("vec", lambda x: x * 0.5).alias("vec"), "op", "ts", "event_id")


def newest(changes: DataFrame) -> DataFrame:
    """The last change of each vector by (ts, event_id)."""
    return changes.groupBy("vec_id").agg(F.max_by(F.struct("vec", "op"), F.struct("ts", "event_id")).alias("c")).select("vec_id", "c.vec", "c.op")


class DynamicIndex:
    def __init__(self, spark: SparkSession, base: DataFrame, build: index.Build, n_segments: int = 1, threshold: int = 10_000):
        self.spark, self.build, self.n_segments, self.threshold = spark, build, n_segments, threshold
        self.root = at_exit(spark, f"{shared_dir(spark)}/dynamic-{uuid.uuid4().hex}")
        self.version = 0
        self._static(base)

    def _static(self, base: DataFrame) -> None:
        self.base = stored(base.select("vec_id", "vec"), "base")
        self.index = stored(index.build(index.assign(self.base, self.n_segments), self.build), "index")

    def commit(self, batch: DataFrame, epoch: int) -> None:
        """For foreachBatch."""
        batch.write.mode("overwrite").parquet(f"{self._folder()}/batch={epoch}")
        if self.changes().count() > self.threshold:
            self.rebuild()

    def changes(self) -> DataFrame:
        if not self.batches():
            return self.spark.createDataFrame([], CHANGES)
        return self.spark.read.schema(f"{CHANGES}, batch long").parquet(self._folder()).drop("batch")

    def _folder(self) -> str:
        return f"{self.root}/v{self.version}"

    def batches(self) -> list[int]:
        """What has been committed to this version, by the folder."""
        where = self.spark._jvm.org.apache.hadoop.fs.Path(self._folder())
        fs = where.getFileSystem(self.spark._jsc.hadoopConfiguration())
        names = [f.getPath().getName() for f in fs.listStatus(where)] if fs.exists(where) else []
        return sorted(int(n.partition("=")[2]) for n in names if n.startswith("batch="))

    def snapshot(self) -> DataFrame:
        now = newest(self.changes())
        return self.base.join(now.select("vec_id"), "vec_id", "left_anti").unionByName(now.where("op = 'upsert'").select("vec_id", "vec"))

    def rebuild(self) -> None:
        self._static(self.snapshot())
        self.version += 1

    def search(self, queries: DataFrame, ask: index.Ask) -> DataFrame:
        now = stored(newest(self.changes()), "changed")
        still = self.base.join(now.select("vec_id"), "vec_id", "left_anti").select("vec_id")
        old = index.run_queries(self.index, index.everywhere(queries, self.n_segments), ask, visible=still).where("kind = 'hit'").select("query_id", "vec_id", "dist")
        fresh = now.where("op = 'upsert'")
        k = ask.k if ask.r is None else None
        new = exact.knn(fresh, queries, ask.k, self.build.metric) if k else exact.radius(fresh, queries, ask.r, self.build.metric)
        return exact.rank_hits(old.unionByName(new.select("query_id", "vec_id", "dist")), k)

    def manifest(self) -> str:
        return json.dumps({"version": self.version, "batches": self.batches(), **index.describe(self.build)}, sort_keys=True)


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream of files."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    s = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return s.withColumn("ts", F.col("ts").cast("timestamp"))  # event time is an instant, whatever the file says


def drain(stream: DataFrame, sink, mode: str = "append") -> None:
    """Run a stream over what is there now, each batch into ``sink``."""
    spark = stream.sparkSession
    q = stream.writeStream.outputMode(mode).option("checkpointLocation", at_exit(spark, f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}")).trigger(availableNow=True).foreachBatch(sink).start()
    q.awaitTermination()


def answer_stream(queries: DataFrame, indexed: DataFrame, n_segments: int, ask: index.Ask) -> DataFrame:
    """(query_id, rank, vec_id, dist) of a stream of queries (query_id, qvec) on a
    static index, after all of its input; a replayed batch rewrites its answers."""
    spark = queries.sparkSession
    root = at_exit(spark, f"{shared_dir(spark)}/answers-{uuid.uuid4().hex}")

    def sink(df, epoch):
        found = index.run_queries(indexed, index.everywhere(df, n_segments), ask)
        index.merge(found, ask.k if ask.r is None else None).write.mode("overwrite").parquet(f"{root}/batch={epoch}")

    drain(queries, sink)
    return spark.read.schema("query_id long, rank int, vec_id long, dist double, batch long").parquet(root).drop("batch")


def result(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """What a stream has put out after all of its input, as a table: the last
    batch in complete mode, all batches in append mode."""
    spark = stream.sparkSession
    root = at_exit(spark, f"{shared_dir(spark)}/sink-{uuid.uuid4().hex}")
    paths: list[str] = []

    def sink(df, epoch):
        path = f"{root}/{epoch}"
        df.write.mode("overwrite").parquet(path)
        if path not in paths:
            paths.append(path)

    drain(stream, sink, mode)
    use = paths[-1:] if mode == "complete" else paths
    return spark.read.schema(stream.schema).parquet(*use) if use else spark.createDataFrame([], stream.schema)
