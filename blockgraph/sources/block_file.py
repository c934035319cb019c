"""Blocks of a graph as rows and as files of fixed-size records.

As a table, a block is a row with its members as an array of structs, stored by
segment. As a file (``write_file`` / ``BlockFile``) a block is ``block_kb`` KB at
offset block * size: each vertex has its values (float32), degree and padded
neighbour ids (uint32), so one positioned read gets a block.
"""

from __future__ import annotations

import os

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..operators import index, layout_rounds

MEMBERS = "array<struct<vec_id: long, vec: array<double>, nbrs: array<long>>>"


def blocks_table(indexed: DataFrame) -> DataFrame:
    """(segment_id, block_id, members)."""

    def fn(s, seg):
        rows = []
        for b, m in enumerate(seg.members):
            rows.append((s, b, [(int(seg.ids[r]), seg.vecs[r].tolist(), seg.ids[seg.nbrs[r][seg.nbrs[r] >= 0]].tolist()) for r in m]))
        return pd.DataFrame(rows, columns=["segment_id", "block_id", "members"])

    return index.per_segment(indexed, fn, f"segment_id int, block_id long, members {MEMBERS}")


def blocks_by_id(vectors: DataFrame, edges: DataFrame, cap: int) -> DataFrame:
    """``blocks_table`` of one segment packed by id, from (vec_id, vec) and
    (segment_id, src, dst, pos): no task holds more than some blocks."""
    place = layout_rounds.running(vectors.select(F.lit(0).alias("segment_id"), "vec_id", F.lit(1).alias("n")), "vec_id", "n", "first")
    near = edges.groupBy(F.col("src").alias("vec_id")).agg(F.transform(F.sort_array(F.collect_list(F.struct("pos", "dst"))), lambda x: x["dst"]).alias("nbrs"))
    rows = vectors.join(place.select("vec_id", F.floor(F.col("first") / cap).cast("long").alias("block_id")), "vec_id").join(near, "vec_id", "left")
    member = F.struct("vec_id", "vec", F.coalesce("nbrs", F.array().cast("array<long>")).alias("nbrs"))
    return rows.groupBy(F.lit(0).alias("segment_id"), "block_id").agg(F.sort_array(F.collect_list(member)).alias("members"))


def vertices(blocks: DataFrame) -> DataFrame:
    """(segment_id, block_id, slot, vec_id, vec, nbrs)."""
    return blocks.select("segment_id", "block_id", F.posexplode("members").alias("slot", "m")).select("segment_id", "block_id", "slot", "m.*")


EMPTY = 0xFFFFFFFF


def write_file(path: str, vecs: np.ndarray, nbrs: np.ndarray, block: np.ndarray, block_bytes: int = 4096) -> int:
    """Write a segment's blocks; returns the vertices a block holds. Which rows
    a block holds is the map that stays in memory: it goes to ``path.ids``."""
    n, dim = vecs.shape
    degree = nbrs.shape[1]
    cap = block_bytes // (4 * dim + 4 + 4 * degree)
    slots = np.full((int(block.max()) + 1 if n else 0, cap), EMPTY, "<u4")
    with open(path, "wb") as f:
        for b in range(len(slots)):
            m = np.flatnonzero(block == b)
            if len(m) > cap:
                raise ValueError("a block holds more vertices than fit")
            slots[b, : len(m)] = m
            part = b"".join(vecs[r].astype("<f4").tobytes() + np.uint32((nbrs[r] >= 0).sum()).tobytes() + np.where(nbrs[r] < 0, 0, nbrs[r]).astype("<u4").tobytes() for r in m)
            f.write(part.ljust(block_bytes, b"\0"))
    slots.tofile(f"{path}.ids")
    return cap


class BlockFile:
    """Positioned reads of blocks, all counted."""

    def __init__(self, path: str, dim: int, degree: int, block_bytes: int = 4096):
        self.fd, self.dim, self.degree, self.block_bytes, self.reads = os.open(path, os.O_RDONLY), dim, degree, block_bytes, 0
        self.record = 4 * dim + 4 + 4 * degree
        self.slots = np.fromfile(f"{path}.ids", "<u4").reshape(-1, block_bytes // self.record)

    def read(self, block: int) -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
        data = os.pread(self.fd, self.block_bytes, block * self.block_bytes)
        self.reads += 1
        rows = self.slots[block][self.slots[block] != EMPTY]
        vecs, nbrs = [], []
        for i in range(len(rows)):
            at = i * self.record + 4 * self.dim
            n = int.from_bytes(data[at : at + 4], "little")
            vecs.append(np.frombuffer(data, "<f4", self.dim, i * self.record))
            nbrs.append(np.frombuffer(data, "<u4", n, at + 4))
        return rows, np.array(vecs, float), nbrs

    def close(self) -> None:
        os.close(self.fd)


class BlockFileSource(DataSource):
    """``spark.read.format("block_file").option("dim", ..).option("degree", ..)
    .load(path)``: (block_id, row, vec, nbrs), in partitions of whole blocks."""

    @classmethod
    def name(cls) -> str:
        return "block_file"

    def schema(self) -> str:
        return "block_id long, row long, vec array<double>, nbrs array<long>"

    def reader(self, schema):
        return _Reader(self.options)


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.options = options

    def partitions(self):
        size = int(self.options.get("block_bytes", "4096"))
        n = os.path.getsize(self.options["path"]) // size
        step = max(1, int(self.options.get("blocks_a_partition", "256")))
        return [InputPartition((a, min(n, a + step))) for a in range(0, n, step)]

    def read(self, partition):
        o = self.options
        f = BlockFile(o["path"], int(o["dim"]), int(o["degree"]), int(o.get("block_bytes", "4096")))
        for b in range(*partition.value):
            for r, v, l in zip(*f.read(b)):
                yield (b, int(r), [float(x) for x in v], [int(x) for x in l])
        f.close()
