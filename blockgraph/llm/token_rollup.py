"""Token totals kept up to date by deltas.

A batch is a table of changes ``(op, doc_id, source, lang, tokenizer,
old_tokens, new_tokens)``: ``insert`` adds a document's count, ``delete`` takes
it away, ``revise`` replaces it. Each change becomes a signed row (document
count and token count), the batch is summed by source, language and tokenizer
version, and only those sums are stored, one folder for each batch id. A
folder counts once Spark has put ``_SUCCESS`` into it, so a batch that is
applied again is either finished (nothing happens) or rewritten whole. Totals
are the sums over committed folders; ``compact`` folds them into one and
remembers which ids it holds.

Edge cases: null counts are 0, null source, language or tokenizer form groups
of their own, unknown ops and null ops change nothing, groups whose documents
and tokens both came to nothing are left out of the totals, an empty batch is
committed as such, other columns are ignored.
"""

from __future__ import annotations

import re
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

KEYS = ("source", "lang", "tokenizer")
SCHEMA = "source string, lang string, tokenizer string, d_docs long, d_tokens long"


def signed(changes: DataFrame) -> DataFrame:
    """Signed deltas of a change table, summed by key."""
    old, new = (F.coalesce(F.col(c).cast("long"), F.lit(0)) for c in ("old_tokens", "new_tokens"))
    op = F.col("op")
    docs = F.when(op == "insert", 1).when(op == "delete", -1).otherwise(0).cast("long")
    tokens = F.when(op == "insert", new).when(op == "delete", -old).when(op == "revise", new - old).otherwise(F.lit(0))
    return (
        changes.where(op.isin("insert", "delete", "revise"))
        .select(*(F.col(k).cast("string").alias(k) for k in KEYS), docs.alias("d_docs"), tokens.alias("d_tokens"))
        .groupBy(*KEYS)
        .agg(F.sum("d_docs").alias("d_docs"), F.sum("d_tokens").alias("d_tokens"))
    )


class TokenRollup:
    """A rollup stored in a folder that all executors share."""

    def __init__(self, spark: SparkSession, root: str):
        self.spark, self.root = spark, root.rstrip("/")
        jvm = spark._jvm
        self._path = jvm.org.apache.hadoop.fs.Path
        self._fs = self._path(self.root).getFileSystem(spark._jsc.hadoopConfiguration())

    def _exists(self, path: str) -> bool:
        return self._fs.exists(self._path(path))

    def committed(self) -> list[str]:
        """Ids of the committed batches, whether folded or not."""
        return sorted(set(self._pending()) | set(self._folded()))

    def _names(self, folder: str) -> list[str]:
        if not self._exists(folder):
            return []
        return [s.getPath().getName() for s in self._fs.listStatus(self._path(folder))]

    def _base(self) -> str | None:
        """The newest snapshot that is whole."""
        done = [n for n in self._names(f"{self.root}/base") if self._exists(f"{self.root}/base/{n}/ids/_SUCCESS")]
        return f"{self.root}/base/{max(done)}" if done else None

    def _folded(self) -> list[str]:
        base = self._base()
        return [r[0] for r in self.spark.read.parquet(f"{base}/ids").toLocalIterator()] if base else []

    def _pending(self) -> list[str]:
        return [n.removeprefix("batch=") for n in self._names(f"{self.root}/delta") if self._exists(f"{self.root}/delta/{n}/_SUCCESS")]

    def apply(self, batch_id: str, changes: DataFrame) -> bool:
        """Commit a batch; False if its id has been committed before."""
        if not re.fullmatch(r"[\w.-]+", str(batch_id)):
            raise ValueError("a batch id has letters, digits, dots, dashes and underscores only")
        where = f"{self.root}/delta/batch={batch_id}"
        if self._exists(f"{where}/_SUCCESS") or str(batch_id) in self._folded():
            return False
        signed(changes).write.mode("overwrite").parquet(where)
        return True

    def deltas(self) -> DataFrame:
        folded, base = set(self._folded()), self._base()
        paths = [f"{self.root}/delta/batch={b}" for b in self._pending() if b not in folded]
        out = self.spark.read.schema(SCHEMA).parquet(*paths) if paths else self.spark.createDataFrame([], SCHEMA)
        return out.unionByName(self.spark.read.schema(SCHEMA).parquet(f"{base}/sums")) if base else out

    def totals(self) -> DataFrame:
        return (
            self.deltas()
            .groupBy(*KEYS)
            .agg(F.sum("d_docs").alias("n_docs"), F.sum("d_tokens").alias("n_tokens"))
            .where("n_docs <> 0 or n_tokens <> 0")
        )

    def compact(self) -> None:
        """Fold all committed deltas into a new snapshot; it counts once its
        list of ids is written, which comes last."""
        ids = self.committed()
        name = f"{len(self._names(f'{self.root}/base')):08d}-{uuid.uuid4().hex[:8]}"
        self.deltas().groupBy(*KEYS).agg(F.sum("d_docs").alias("d_docs"), F.sum("d_tokens").alias("d_tokens")).coalesce(1).write.parquet(f"{self.root}/base/{name}/sums")
        self.spark.createDataFrame([(i,) for i in ids], "id string").coalesce(1).write.parquet(f"{self.root}/base/{name}/ids")

    def stream_sink(self, prefix: str = "stream"):
        """For ``writeStream.foreachBatch``: a replayed micro-batch has the
        same id and so changes nothing."""
        return lambda df, epoch: self.apply(f"{prefix}-{epoch}", df)
