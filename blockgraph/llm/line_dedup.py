"""Site-relative line frequency, in DataFrame expressions only.

Pages are grouped by host; for each host and line, the pages that contain the
line are divided by the pages of the host, and lines above ``ratio`` (and on
``min_pages`` pages at least) are dropped as boilerplate. Lines compare by
their trimmed text (space, tab and carriage return at the ends); blank lines
are never dropped.

A line is represented by two independent 64-bit hashes, so each page sends 16
bytes a distinct line and no text, counts are combined before they are
shuffled, and a common line or a host with a third of all pages costs its
reducer one row a map task. A host with L distinct lines a page on average
has at most L / ratio boilerplate lines. These lists are broadcast if all of
them together stay below ``broadcast_lines``; beyond that, pages and lists are
joined on host and a salt of the page.

Pages are rows; with ``distinct_pages`` equal texts of a host are one page, so
that a document that has been copied often is not taken for boilerplate and is
left to near-deduplication.

Edge cases: a null host is a host of its own; a null text has no lines and
stays null; a page repeated as a row counts once for each row unless pages are
distinct; very long texts are taken whole; an empty table gives an empty result;
extra columns pass through.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialise

TRIM = " \t\r"
SALTS = 64


def host_of_url(url: Column) -> Column:
    """Lower-case host of a URL, null if there is none."""
    return F.lower(F.nullif(F.regexp_extract(url, r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?([^/:?#]+)", 1), F.lit("")))


def line_key(line: Column) -> Column:
    t = F.btrim(line, F.lit(TRIM))
    return F.struct(F.xxhash64(t).alias("a"), F.xxhash64(F.lit("line"), t).alias("b"))


def _lines(text: Column) -> Column:
    return F.split(text, "\n")


def boilerplate(df: DataFrame, host: Column, text: Column, ratio: float, min_pages: int, distinct_pages: bool = False) -> DataFrame:
    """(host, a, b) of the lines above the ratio, with their page counts."""
    pages = df.select(F.coalesce(F.concat(F.lit("h"), host.cast("string")), F.lit("n")).alias("__bg_host"), text.alias("__bg_text"))
    keys = F.array_distinct(F.transform(F.filter(_lines(F.col("__bg_text")), lambda x: F.btrim(x, F.lit(TRIM)) != ""), line_key))
    if distinct_pages:
        page = F.struct(F.xxhash64("__bg_text").alias("a"), F.xxhash64(F.lit("page"), "__bg_text").alias("b"))
        pages = pages.select("__bg_host", page.alias("p"), keys.alias("k")).groupBy("__bg_host", "p").agg(F.first("k").alias("k"))
        # read twice, so that equal pages meet once
        pages = materialise(pages.select("__bg_host", "k"), "pages")
        keys = F.col("k")
    totals = pages.groupBy("__bg_host").agg(F.count(F.lit(1)).alias("__bg_pages"))
    counts = (
        pages.select("__bg_host", F.explode(keys).alias("k"))
        .groupBy("__bg_host", F.col("k.a").alias("a"), F.col("k.b").alias("b"))
        .agg(F.count(F.lit(1)).alias("__bg_n"))
        .where(F.col("__bg_n") >= min_pages)
    )
    return counts.join(totals, "__bg_host").where(F.col("__bg_n") > ratio * F.col("__bg_pages"))


def mark(df: DataFrame, host: Column, text: str = "text", ratio: float = 0.05, min_pages: int = 3, broadcast_lines: int = 200_000, distinct_pages: bool = False) -> DataFrame:
    """Adds __bg_drop: the keys of the boilerplate lines of the row's host."""
    found = materialise(boilerplate(df, host, F.col(text), ratio, min_pages, distinct_pages).select("__bg_host", "a", "b"), "boilerplate")
    by_host = found.groupBy("__bg_host").agg(F.collect_list(F.struct("a", "b")).alias("__bg_drop"))
    keyed = df.withColumn("__bg_host", F.coalesce(F.concat(F.lit("h"), host.cast("string")), F.lit("n")))
    if found.count() <= broadcast_lines:
        return keyed.join(F.broadcast(by_host), "__bg_host", "left").drop("__bg_host")
    salted = keyed.withColumn("__bg_salt", F.pmod(F.xxhash64(F.col(text)), F.lit(SALTS)).cast("int"))
    spread = by_host.withColumn("__bg_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    return salted.join(spread, ["__bg_host", "__bg_salt"], "left").drop("__bg_host", "__bg_salt")


def clean(df: DataFrame, host: Column, text: str = "text", ratio: float = 0.05, min_pages: int = 3, counts: bool = True, broadcast_lines: int = 200_000, distinct_pages: bool = False) -> DataFrame:
    """df with boilerplate lines taken out of ``text`` and, with counts, n_lines
    and n_dropped (long), which replace columns of these names."""
    out = mark(df, host, text, ratio, min_pages, broadcast_lines, distinct_pages).withColumn("__bg_all", _lines(F.col(text)))
    drop = F.col("__bg_drop")
    blank = lambda x: F.btrim(x, F.lit(TRIM)) == ""
    out = out.withColumn("__bg_kept", F.when(drop.isNull(), F.col("__bg_all")).otherwise(F.filter("__bg_all", lambda x: blank(x) | ~F.array_contains(drop, line_key(x)))))
    new = {text: F.array_join("__bg_kept", "\n")}
    if counts:
        new["n_lines"] = F.coalesce(F.size("__bg_all"), F.lit(0)).cast("long")
        new["n_dropped"] = F.coalesce(F.size("__bg_all") - F.size("__bg_kept"), F.lit(0)).cast("long")
    return out.withColumns(new).drop("__bg_drop", "__bg_all", "__bg_kept")
