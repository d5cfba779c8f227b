"""Line dedup by the number of distinct sites that a line is seen on (DataFrame functions only)."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import clear, save, same

#: Shares of all lines at or above which a line counts as heavy; at most this many lines can be so.
HEAVY = 1000


def _spread_join(big: DataFrame, small: DataFrame, total: int) -> DataFrame:
    """``big`` with ``small`` (distinct ``h1, h2`` and ``n``, the rows each has in ``big``).

    Lines that hold a thousandth of all rows or more are a thousand at most and are broadcast; the
    others are joined by shuffle, and no key there is large.
    """
    heavy = F.broadcast(small.filter(F.col("n") * HEAVY >= total))
    light = small.filter(F.col("n") * HEAVY < total)
    rest = big.join(heavy, ["h1", "h2"], "left_anti")
    return big.join(heavy, ["h1", "h2"]).unionByName(rest.join(light, ["h1", "h2"]))


def lines_of(docs: DataFrame) -> DataFrame:
    """Non-blank lines as 128-bit hashes of the line without outer spaces: ``doc_id, th, site, pos, h1, h2``."""
    line = F.trim("line")
    split = docs.select(F.col("doc_id"), F.xxhash64("text").alias("th"), F.coalesce(F.concat(F.lit("="), F.col("source")), F.lit("")).alias("site"), F.posexplode(F.split("text", "\n")).alias("pos", "line"))
    return split.filter(line != "").select("doc_id", "th", "site", "pos", F.xxhash64(line).alias("h1"), F.xxhash64(F.lit(1), line).alias("h2"))


def boilerplate(lines: DataFrame, min_sites: int = 10, lg_k: int = 12) -> DataFrame:
    """Lines seen on ``min_sites`` distinct sites or more: ``h1, h2, n, first``.

    Each line has one HyperLogLog sketch of its sites, built before the shuffle and merged after it.
    Estimates further from ``min_sites`` than three standard errors (and one site) settle a line; the
    lines in between are counted exactly, over distinct (line, site) pairs.
    """
    total = lines.count()
    band = max(1, math.ceil(3 * 1.04 / math.sqrt(2**lg_k) * min_sites))
    met = lines.groupBy("h1", "h2").agg(F.count("*").alias("n"), F.hll_sketch_estimate(F.hll_sketch_agg("site", F.lit(lg_k))).alias("sites"), F.min(F.struct("doc_id", "th", "pos")).alias("first"))
    met = save(met.filter((F.col("n") >= min_sites) & (F.col("sites") >= min_sites - band)), "spread")
    near = met.filter(F.abs(F.col("sites") - min_sites) <= band)
    pairs = _spread_join(lines, near.select("h1", "h2", "n"), total).select("h1", "h2", "site").distinct()
    exact = pairs.groupBy("h1", "h2").agg(F.count("*").alias("exact")).filter(F.col("exact") >= min_sites)
    sure = met.filter(F.col("sites") > min_sites + band)
    return sure.select("h1", "h2", "n", "first").unionByName(near.join(exact, ["h1", "h2"]).select("h1", "h2", "n", "first"))


def counts_of(docs: DataFrame) -> tuple[str, str]:
    """Names of the two columns that :func:`spread_lines` adds: ``_n_lines`` and ``_n_removed``, longer where the table has such already."""
    return clear("_n_lines", docs.columns), clear("_n_removed", docs.columns)


def spread_lines(docs: DataFrame, min_sites: int = 10, lg_k: int = 12, keep_first: bool = True) -> DataFrame:
    """Every document with ``_n_lines``, ``_n_removed`` (see :func:`counts_of`) and its text without cross-site boilerplate.

    A site is a ``source`` (null is one of its own); a line is what stands between newlines, compared
    without outer spaces; blank lines are never removed and not counted. A line on ``min_sites`` sites
    or more is taken out of every text; with ``keep_first`` its first occurrence (smallest doc_id, then
    position) stays, so nothing leaves the corpus altogether. Texts that lose no line are
    returned as they were; null stays null. All other columns pass through. Equal rows share
    one decision. Texts are hashed in one pass, and cross the network once, to meet their removed lines.
    """
    lines = save(lines_of(docs), "lines")
    total = lines.count()
    found = save(boilerplate(lines, min_sites, lg_k), "boilerplate")
    hits = _spread_join(lines, found, total)
    if keep_first:
        hits = hits.filter(~F.struct("doc_id", "th", "pos").eqNullSafe(F.col("first")))
    gone = hits.groupBy("doc_id", "th").agg(F.collect_set("pos").alias("_gone")).select(F.col("doc_id").alias("_id"), F.col("th").alias("_th"), "_gone")
    h = clear("h", docs.columns)
    keyed = docs.withColumn(h, F.xxhash64("text"))
    on = same([F.col("a.doc_id"), F.col(f"a.`{h}`")], [F.col("b._id"), F.col("b._th")])
    joined = keyed.alias("a").join(gone.alias("b"), on, "left")
    split = F.split(F.col("a.text"), "\n")
    kept = F.array_join(F.filter(split, lambda x, i: ~F.array_contains(F.col("b._gone"), i)), "\n")
    text = F.when(F.col("b._gone").isNull(), F.col("a.text")).otherwise(kept)
    n_lines = F.coalesce(F.size(F.filter(split, lambda x: F.trim(x) != "")), F.lit(0))
    n_lines = F.when(F.col("a.text").isNull(), 0).otherwise(n_lines)
    columns = [text.alias("text") if c == "text" else F.col(f"a.`{c}`") for c in docs.columns]
    names = counts_of(docs)
    return joined.select(*columns, n_lines.cast("long").alias(names[0]), F.coalesce(F.array_size("b._gone"), F.lit(0)).cast("long").alias(names[1]))
