"""The search as supersteps over a table of blocks.

For large batches: in each superstep every query names the blocks it reads next,
the names are joined with the table of blocks, so a block that many queries
need is read once, and all queries move on by one round. What the method holds
in memory (navigator, codes, the map of ids to blocks) is one row for each
segment; vectors and neighbours come from blocks only. The rounds are those of
``search``, so answers and counts of reads are the same as with one task for
each segment.
"""

from __future__ import annotations

import io
import pickle

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import stored
from . import index, search

STATE = "segment_id int, query_id long, state binary, blocks array<long>"


class _Lookup(dict):
    """Rows that have come with a block, indexed like a matrix."""

    def __getitem__(self, rows):
        if isinstance(rows, (list, np.ndarray)):
            return np.array([dict.__getitem__(self, int(r)) for r in rows])
        return dict.__getitem__(self, int(rows))


def split(indexed: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(segment_id, payload) of what stays in memory, and (segment_id,
    block_id, payload) of the blocks."""

    def memory(s, seg):
        nav = {} if seg.nav_rows is None else {int(r): seg.vecs[r] for r in seg.nav_rows}
        if seg.entry >= 0:
            nav[seg.entry] = seg.vecs[seg.entry]
        keep = {"ids": seg.ids, "block": seg.block, "metric": seg.metric, "entry": seg.entry, "book": seg.book, "codes": seg.codes, "nav_rows": seg.nav_rows, "nav_nbrs": seg.nav_nbrs, "nav_entry": seg.nav_entry, "hot": seg.hot, "nav": nav}
        keep["hot_rows"] = {int(r): (seg.vecs[r], seg.nbrs[r]) for r in seg.hot}
        return pd.DataFrame([(s, pickle.dumps(keep))], columns=["segment_id", "payload"])

    def blocks(s, seg):
        rows = []
        for b, m in enumerate(seg.members):
            buffer = io.BytesIO()
            np.savez(buffer, rows=m, vecs=seg.vecs[m], nbrs=seg.nbrs[m])
            rows.append((s, b, buffer.getvalue()))
        return pd.DataFrame(rows, columns=["segment_id", "block_id", "payload"])

    return (index.per_segment(indexed, memory, "segment_id int, payload binary"), index.per_segment(indexed, blocks, "segment_id int, block_id long, payload binary"))


def _segment(keep: dict, pages: pd.DataFrame) -> search.Segment:
    seg = search.Segment(keep["ids"], _Lookup(keep["nav"]), _Lookup(), keep["block"], keep["metric"], keep["entry"], keep["book"], keep["codes"], keep["nav_rows"], keep["nav_nbrs"], keep["nav_entry"], keep["hot"])
    for r, (v, n) in keep["hot_rows"].items():
        seg.vecs[r], seg.nbrs[r] = v, n
    for payload in pages["payload"]:
        z = np.load(io.BytesIO(payload))
        for r, v, n in zip(z["rows"].tolist(), z["vecs"], z["nbrs"]):
            seg.vecs[r], seg.nbrs[r] = v, n
    return seg


def _freeze(run: search._Run, now: list[int]) -> bytes:
    seg = run.seg
    run.seg = None
    held = {r: dict.__getitem__(seg.nbrs, r) for r in run.waiting}
    return pickle.dumps((run, now, held))


def _thaw(state: bytes, seg: search.Segment) -> tuple[search._Run, list[int]]:
    run, now, held = pickle.loads(state)
    for r, n in held.items():
        seg.nbrs[r] = n
    run.seg = seg
    return run, now


def run_queries(indexed: DataFrame, routed: DataFrame, ask: index.Ask) -> DataFrame:
    """Like ``index.run_queries`` (hits and counters). Routing by exact distance
    would read vectors outside the blocks at hand and is refused."""
    o = ask.options
    if ask.method.startswith("vertex"):
        o = search.vertex_options(o, cache=o.cache)
    if o.routing != "pq" or ask.method.endswith("topk"):
        raise ValueError("supersteps route by codes and don't restart")
    spark = indexed.sparkSession
    memory, pages = (stored(x, "frontier") for x in split(indexed))

    def start(key, left, right):
        rows = []
        if len(left):
            seg = _segment(pickle.loads(left["payload"].iloc[0]), right.iloc[:0].assign(payload=[]))
            if not seg.book and len(seg.ids):
                raise ValueError("the index has no codes")
            for q, v in zip(right["query_id"], right["qvec"]):
                run = search._Run(seg, np.array(v, float), o, ask.r)
                run.begin()
                now = run.choose()
                rows.append((int(key[0]), int(q), _freeze(run, now), [int(seg.block[u]) for u in now]))
                run.seg = seg
        return pd.DataFrame(rows, columns=["segment_id", "query_id", "state", "blocks"])

    def advance(key, left, right):
        rows = []
        if len(left):
            kept = right[right["block_id"] < 0]
            seg = _segment(pickle.loads(kept["payload"].iloc[0]), right[right["block_id"] >= 0])
            for q, state in zip(left["query_id"], left["state"]):
                run, now = _thaw(state, seg)
                run.apply(now)
                now = run.choose()
                rows.append((int(key[0]), int(q), _freeze(run, now), [int(seg.block[u]) for u in now]))
        return pd.DataFrame(rows, columns=["segment_id", "query_id", "state", "blocks"])

    states = stored(memory.groupBy("segment_id").cogroup(routed.select("segment_id", "query_id", "qvec").groupBy("segment_id")).applyInPandas(start, STATE), "frontier")
    done = None
    while True:  # each round, every live query reads at least one block it has not read
        over = states.where(F.size("blocks") == 0)
        done = over if done is None else done.unionAll(over)
        live = states.where(F.size("blocks") > 0)
        if live.isEmpty():
            break
        asked = live.select("segment_id", F.explode("blocks").alias("block_id")).distinct()
        read = pages.join(asked, ["segment_id", "block_id"]).select("segment_id", "block_id", "payload")
        held = memory.join(live.select("segment_id").distinct(), "segment_id").select("segment_id", F.lit(-1).cast("long").alias("block_id"), "payload")
        states = stored(live.groupBy("segment_id").cogroup(read.unionAll(held).groupBy("segment_id")).applyInPandas(advance, STATE), "frontier")

    names = [x.split()[0] for x in index.FOUND.split(", ")]

    def finish(key, left, right):
        out = []
        if len(left) and len(right):
            ids = pickle.loads(right["payload"].iloc[0])["ids"]
            for q, state in zip(left["query_id"], left["state"]):
                f = pickle.loads(state)[0].finish()
                if ask.r is None:
                    f.rows, f.dists = f.rows[: ask.k], f.dists[: ask.k]
                blank = dict.fromkeys(names) | {"query_id": int(q), "segment_id": int(key[0])}
                out += [blank | {"kind": "hit", "vec_id": int(ids[r]), "dist": d} for r, d in zip(f.rows, f.dists)]
                out.append(blank | {"kind": "stat"} | {n: getattr(f, n) for n in search.COUNTERS})
        frame = pd.DataFrame(out, columns=names)
        for x in index.FOUND.split(", "):
            c, t = x.split()
            frame[c] = frame[c].astype({"long": "Int64", "int": "Int32", "double": "float64", "string": "object"}[t])
        return frame

    return done.groupBy("segment_id").cogroup(memory.groupBy("segment_id")).applyInPandas(finish, index.FOUND)
