"""Sharding by proportional stratified interleaving."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import running_start, same, save

#: Rows aimed at in one bucket of a distributed ranking.
BUCKET_ROWS = 4096


def interleave(docs: DataFrame, shards: int = 16, seed: int = 42) -> DataFrame:
    """Deals documents over shards so that every shard has the corpus's mixture of sources.

    Rows of a source are shuffled by a seeded hash and ranked; rank over the source's size is a
    fraction, and all rows in order of that fraction are cut into ``shards`` runs whose counts
    differ by one at most (the ``rows`` law). Ranks are exact and come from counts of hash and
    fraction buckets plus a rank inside each bucket, so a source holding most rows is spread over
    as many buckets as it needs and only ids move.

    Reads ``doc_id, text, source`` and ignores other columns. Null text has size 1; a null source
    is a source of its own; equal rows rank next to each other. An empty table gives no row.
    Returns ``doc_id, source, size, text_crc32, shard, slot, position``.
    """
    size = (F.coalesce(F.octet_length("text"), F.lit(0)) + 1).cast("long")
    crc = F.crc32(F.coalesce(F.col("text"), F.lit("")).cast("binary"))
    mixed = F.expr(f"xxhash64({seed}L, doc_id, crc32(cast(coalesce(text, '') as binary)))")
    base = save(docs.select("doc_id", F.col("source"), size.alias("size"), crc.alias("text_crc32"), mixed.alias("h")), "dealt")
    total = base.count()
    bits = max(0, math.ceil(math.log2(max(1, total / BUCKET_ROWS))))
    spread = F.shiftrightunsigned("h", 64 - bits) if bits else F.lit(0).cast("long")
    rows = base.withColumn("bucket", spread)

    counts = rows.groupBy("source", "bucket").agg(F.count("*").alias("n"))
    starts = running_start(counts, ["source"], "bucket", "n", "before")
    sums = base.groupBy("source").agg(F.count("*").alias("of_source")).alias("s")
    starts = starts.alias("c").join(sums, F.col("c.source").eqNullSafe(F.col("s.source"))).select("c.source", "c.bucket", "c.before", "s.of_source")
    within = W.partitionBy("source", "bucket").orderBy("h", "doc_id", "text_crc32")
    ranked = rows.withColumn("r", F.row_number().over(within)).alias("a")
    keys = same([F.col("a.source"), F.col("a.bucket")], [F.col("b.source"), F.col("b.bucket")])
    fraction = (2 * (F.col("b.before") + F.col("a.r")) - 1).cast("double") / (2 * F.col("b.of_source"))
    ordered = save(ranked.join(starts.alias("b"), keys).select("a.doc_id", "a.source", "a.size", "a.text_crc32", "a.h", fraction.alias("f")), "fractions")

    rows = ordered.withColumn("bucket", F.floor(F.col("f") * 2**bits).cast("long"))
    starts = running_start(rows.groupBy("bucket").agg(F.count("*").alias("n")), [], "bucket", "n", "before").alias("b")
    within = W.partitionBy("bucket").orderBy("f", F.xxhash64("source"), "h", "doc_id", "text_crc32")
    placed = rows.withColumn("r", F.row_number().over(within)).alias("a").join(starts, F.col("a.bucket") == F.col("b.bucket"))
    out = placed.select("a.doc_id", "a.source", "a.size", "a.text_crc32", (F.col("b.before") + F.col("a.r") - 1).cast("long").alias("position"))
    shard = F.expr(f"position * {shards}L div {max(1, total)}L").cast("int")
    first = F.expr(f"(shard * {total}L + {shards - 1}L) div {shards}L")
    return out.withColumn("shard", shard).withColumn("slot", (F.col("position") - first).cast("long"))
