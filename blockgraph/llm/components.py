"""Connected components of a link table by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, materialise


def _with_low(edges: DataFrame, heavy: int | None) -> DataFrame:
    """(a, b, m): each edge with the smallest b of its a. The minima of nodes
    with ``heavy`` edges or more are broadcast, so that no hub goes to one task;
    the caller sets ``heavy`` to a share of all edges, which bounds their number,
    and to None where no node has so many, which spares the driver the broadcast."""
    low = edges.groupBy("a").agg(F.min("b").alias("m"), F.count(F.lit(1)).alias("n"))
    if heavy is None:
        return edges.join(low.select("a", "m").hint("merge"), "a").select("a", "b", "m")
    hubs = F.broadcast(low.where(F.col("n") >= heavy).select("a", F.col("m").alias("hub")))
    known = edges.join(hubs, "a", "left")
    rest = known.where("hub is null").select("a", "b").join(low.where(F.col("n") < heavy).select("a", "m").hint("merge"), "a")
    return known.where("hub is not null").select("a", "b", F.col("hub").alias("m")).unionAll(rest.select("a", "b", "m"))


def _large(edges: DataFrame, heavy: int | None) -> DataFrame:
    both = edges.select("a", "b").unionAll(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    return _with_low(both, heavy).where("b > a").select(F.col("b").alias("a"), F.least("a", "m").alias("b")).where("a <> b").distinct()


def _small(edges: DataFrame, heavy: int | None) -> DataFrame:
    down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    moved = _with_low(down, heavy)
    # the smallest neighbour itself stands for the node's own link
    return moved.select(F.when(F.col("b") == F.col("m"), F.col("a")).otherwise(F.col("b")).alias("a"), F.col("m").alias("b")).where("a <> b").distinct()


def _shape(edges: DataFrame) -> tuple[int, int, int]:
    """How many edges (a > b, distinct) there are, the most that a node has, and
    how many nodes keep the edges from being stars around their smallest nodes."""
    ends = edges.select(F.col("a").alias("x"), F.lit(1).alias("up"), F.lit(0).alias("down")).unionAll(edges.select(F.col("b").alias("x"), F.lit(0).alias("up"), F.lit(1).alias("down")))
    each = ends.groupBy("x").agg(F.sum("up").alias("up"), F.sum("down").alias("down"))
    got = each.agg(F.sum("up"), F.max(F.col("up") + F.col("down")), F.count_if(F.expr("up > 1 or up > 0 and down > 0"))).first()
    return tuple(n or 0 for n in got)


def components(edges: DataFrame, hub_share: int = 5000, least_hub: int = 250) -> DataFrame:
    """(node, root) for every node with a link; root is the smallest node that
    it reaches. edges: a, b (long). Each round is written to the shared folder;
    rounds end when every component is a star around its smallest node. A node
    with more than 2 / ``hub_share`` of all edges, and ``least_hub`` or more, is
    a hub, so there are at most ``hub_share`` of them. The small step of a round
    groups by nodes with no more edges than they had before the large one."""
    now = materialise(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "links")
    total, most, uneven = _shape(now)
    while uneven:
        heavy = max(least_hub, 2 * total // hub_share)
        heavy = heavy if most >= heavy else None
        last, now = now, materialise(_small(_large(now, heavy), heavy), "links")
        discard(last)
        total, most, uneven = _shape(now)
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).unionAll(now.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())
