"""Block layouts as DataFrame rounds, for graphs that don't fit one task.

``pad`` and one round of ``freq`` are sequential walks in id order. Both have an
order-exact parallel form:

* A row opens a run of ``pad`` (it is a leader) if no leader before it has it
  as a neighbour. Undecided rows become leaders once all smaller rows that have
  them as neighbours are decided non-leaders, and non-leaders once one of those
  is a leader. A row belongs to its smallest leader, and the order is by owner,
  then the place in the owner's list.
* A round of ``freq`` with a fixed old layout is a serial dictatorship: blocks
  that take the smallest ids of those who ask. Deferred acceptance gives the
  same assignment: each free row asks its next block, each block keeps its
  ``cap`` smallest ids and sends the others on.

Each round is written to the shared folder; counts decide when to stop.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import stored


def pad(vertices: DataFrame, edges: DataFrame, cap: int) -> DataFrame:
    """(segment_id, vec_id, block_id). vertices: segment_id, vec_id; edges:
    segment_id, src, dst, pos."""
    key = ["segment_id"]
    before = stored(edges.where("src < dst").select("segment_id", "src", "dst").distinct(), "smaller")
    state = stored(vertices.select("segment_id", "vec_id", F.lit(0).alias("s")), "state")  # 0 open, 1 leader, 2 not
    while True:  # the smallest open row of each segment is decided in every round
        left = state.where("s = 0").count()
        if not left:
            break
        src = state.select("segment_id", F.col("vec_id").alias("src"), F.col("s").alias("t"))
        seen = before.join(src, [*key, "src"]).groupBy("segment_id", F.col("dst").alias("vec_id")).agg(F.max(F.when(F.col("t") == 1, 1).otherwise(0)).alias("led"), F.max(F.when(F.col("t") == 0, 1).otherwise(0)).alias("open"))
        now = state.join(seen, [*key, "vec_id"], "left")
        decided = F.when(F.col("s") != 0, F.col("s")).when(F.coalesce("led", F.lit(0)) == 1, 2).when(F.coalesce("open", F.lit(0)) == 0, 1).otherwise(0)
        state = stored(now.select("segment_id", "vec_id", decided.alias("s")), "state")
    lead = state.where("s = 1").select("segment_id", F.col("vec_id").alias("src"))
    claims = edges.join(lead, [*key, "src"]).select("segment_id", F.col("dst").alias("vec_id"), F.col("src").alias("owner"), "pos")
    own = lead.select("segment_id", F.col("src").alias("vec_id"), F.col("src").alias("owner"), F.lit(-1).alias("pos"))
    # a leader is placed at its own turn; another row by its smallest leader
    first = claims.join(lead.select("segment_id", F.col("src").alias("vec_id")), [*key, "vec_id"], "left_anti").groupBy("segment_id", "vec_id").agg(F.min(F.struct("owner", "pos")).alias("m"))
    placed = own.unionByName(first.select("segment_id", "vec_id", "m.owner", "m.pos"))
    # the place of a row: what earlier owners bring, then its place in its owner's run
    run = placed.groupBy("segment_id", "owner").agg(F.count(F.lit(1)).alias("n"))
    run = running(run, "owner", "n", "first")
    place = F.col("first") + F.row_number().over(Window.partitionBy("segment_id", "owner").orderBy("pos")) - 1
    return placed.join(run.select("segment_id", "owner", "first"), [*key, "owner"]).select("segment_id", "vec_id", F.floor(place / cap).cast("long").alias("block_id"))


def running(rows: DataFrame, by: str, n: str, out: str, span: int = 1 << 16) -> DataFrame:
    """rows with ``out``: the sum of n over all rows of the segment with a
    smaller ``by``. Ranges of ``span`` values are summed first, so that no task
    holds more than a range of a segment, or one number for each of its ranges."""
    ranged = rows.withColumn("__bg_range", F.floor(F.col(by) / span))
    sums = ranged.groupBy("segment_id", "__bg_range").agg(F.sum(n).alias("t"))
    before = Window.partitionBy("segment_id").orderBy("__bg_range").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.select("segment_id", "__bg_range", F.coalesce(F.sum("t").over(before), F.lit(0)).alias("__bg_before"))
    inner = Window.partitionBy("segment_id", "__bg_range").orderBy(by).rowsBetween(Window.unboundedPreceding, -1)
    both = ranged.join(sums, ["segment_id", "__bg_range"]).withColumn(out, F.col("__bg_before") + F.coalesce(F.sum(n).over(inner), F.lit(0)))
    return both.drop("__bg_range", "__bg_before")


def freq_round(vertices: DataFrame, edges: DataFrame, old: DataFrame, cap: int) -> DataFrame:
    """(segment_id, vec_id, block_id) after one round with deferred overflow."""
    key = ["segment_id"]
    count = edges.join(old.select("segment_id", F.col("vec_id").alias("dst"), "block_id"), [*key, "dst"]).groupBy("segment_id", F.col("src").alias("vec_id"), "block_id").agg(F.count(F.lit(1)).alias("n"))
    order = F.row_number().over(Window.partitionBy("segment_id", "vec_id").orderBy(F.desc("n"), "block_id"))
    wishes = stored(count.select("segment_id", "vec_id", "block_id", order.alias("wish")), "wishes")
    state = stored(vertices.select("segment_id", "vec_id", F.lit(1).alias("wish")), "asks")
    seat = F.row_number().over(Window.partitionBy("segment_id", "block_id").orderBy("vec_id"))
    while True:  # a row that is turned down never asks the same block again
        asked = state.join(wishes, [*key, "vec_id", "wish"], "left")
        ranked = asked.where("block_id is not null").withColumn("seat", seat)
        turned = stored(ranked.where(F.col("seat") > cap).select("segment_id", "vec_id"), "turned")
        if turned.isEmpty():
            break
        state = stored(state.join(turned.withColumn("t", F.lit(1)), [*key, "vec_id"], "left").select("segment_id", "vec_id", (F.col("wish") + F.coalesce("t", F.lit(0))).alias("wish")), "asks")
    final = state.join(wishes, [*key, "vec_id", "wish"], "left")
    seated = final.where("block_id is not null").select("segment_id", "vec_id", "block_id")
    # the rest, by id, into the lowest blocks with room
    n = vertices.groupBy("segment_id").agg(F.ceil(F.count(F.lit(1)) / cap).cast("long").alias("rho"))
    blocks = n.select("segment_id", F.explode(F.sequence(F.lit(0).cast("long"), F.col("rho") - 1)).alias("block_id"))
    load = seated.groupBy("segment_id", "block_id").agg(F.count(F.lit(1)).alias("used"))
    room = blocks.join(load, [*key, "block_id"], "left").withColumn("free", cap - F.coalesce("used", F.lit(0))).where("free > 0")
    seats = room.select("segment_id", "block_id", F.explode(F.sequence(F.lit(1), F.col("free").cast("int"))).alias("i"))
    seats = seats.select("segment_id", "block_id", F.row_number().over(Window.partitionBy("segment_id").orderBy("block_id", "i")).alias("k"))
    late = final.where("block_id is null").select("segment_id", "vec_id", F.row_number().over(Window.partitionBy("segment_id").orderBy("vec_id")).alias("k"))
    return seated.unionByName(late.join(seats, [*key, "k"]).select("segment_id", "vec_id", "block_id"))
