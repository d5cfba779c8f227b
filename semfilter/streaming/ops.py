"""Streams: a frozen plan on arriving documents, windows over its decisions, and a watch on drift."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.registry import key
from ..sources.tables import scratch, table


def stream(spark: SparkSession, sf: str, name: str, limit: int | None = None) -> DataFrame:
    """A table as a file stream; the given files are linked into a folder of the stream's own by Spark."""
    path = scratch(spark)
    src = table(spark, sf, name)
    if "ts" in src.columns:
        src = src.withColumn("ts", F.col("ts").cast("timestamp"))
    (src if limit is None else src.limit(limit)).write.parquet(path)
    return spark.readStream.schema(src.schema).parquet(path)


def drain(df: DataFrame, mode: str = "append", each=None) -> DataFrame:
    """Runs a stream over all that is there and returns what it wrote; a second start continues from its checkpoint."""
    spark = df.sparkSession
    out, mark = scratch(spark), scratch(spark)

    def keep(batch: DataFrame, batch_id: int) -> None:
        target = f"{out}/batch={batch_id}"  # a repeated batch overwrites itself
        (batch if each is None else each(batch, batch_id)).write.mode("overwrite").parquet(target)

    q = df.writeStream.outputMode(mode).option("checkpointLocation", mark).trigger(availableNow=True).foreachBatch(keep).start()
    q.awaitTermination()
    return spark.read.parquet(out).drop("batch")


def _days(w) -> F.Column:
    return F.date_format(w, "yyyy-MM-dd HH:mm")


@key("stream_scan", "SELECT count(*) AS n FROM events")
def stream_scan(spark, sf):
    return drain(stream(spark, sf, "events").select("event_id")).agg(F.count("*").alias("n"))


@key("stream_deploy", "SELECT CASE WHEN n_chars >= 1000 THEN 'auto' ELSE 'oracle' END AS origin, count(*) AS n FROM documents GROUP BY 1")
def stream_deploy(spark, sf):
    """A frozen scorer and threshold: sure documents get its answer, the rest queue for the oracle."""
    conf = F.least(F.col("n_chars") / 2000.0, F.lit(1.0))
    marked = stream(spark, sf, "documents").select("doc_id", F.when(conf >= 0.5, "auto").otherwise("oracle").alias("origin"))
    return drain(marked).groupBy("origin").agg(F.count("*").alias("n"))


_LOW = "CASE WHEN value < 10 THEN 1 ELSE 0 END"


@key("stream_tumbling", f"SELECT strftime(time_bucket(INTERVAL 1 DAY, ts), '%Y-%m-%d %H:%M') AS start, count(*) AS n, CAST(sum({_LOW}) AS BIGINT) AS cascaded FROM events GROUP BY 1")
def stream_tumbling(spark, sf):
    return _windowed(table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp")), F.window("ts", "1 day"))


def _windowed(events: DataFrame, w) -> DataFrame:
    got = events.groupBy(w.alias("w")).agg(F.count("*").alias("n"), F.sum(F.expr(_LOW)).cast("long").alias("cascaded"))
    return got.select(_days("w.start").alias("start"), "n", "cascaded")


@key("stream_sliding", f"SELECT strftime(start, '%Y-%m-%d %H:%M') AS start, count(*) AS n, CAST(sum({_LOW}) AS BIGINT) AS cascaded FROM (SELECT value, time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 6 HOUR * k AS start FROM events, range(4) r(k)) GROUP BY 1")
def stream_sliding(spark, sf):
    return _windowed(table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp")), F.window("ts", "1 day", "6 hours"))


@key("stream_session", """SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M') AS start, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM
    (SELECT *, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) IS NULL THEN 1 ELSE 0 END AS fresh FROM events)) GROUP BY user_id, s""")
def stream_session(spark, sf):
    e = table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return e.groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count("*").alias("n")).select("user_id", _days("w.start").alias("start"), "n")


@key("stream_tumbling_live", f"SELECT CAST(sum(n) AS BIGINT) AS n, CAST(sum(cascaded) AS BIGINT) AS cascaded FROM (SELECT count(*) AS n, sum({_LOW}) AS cascaded FROM events)")
def stream_tumbling_live(spark, sf):
    """The same windows over a stream, in update mode; the last state of each window counts."""
    s = stream(spark, sf, "events").withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n"), F.sum(F.expr(_LOW)).alias("cascaded"))
    got = drain(s, "update", lambda b, i: b.withColumn("batch_id", F.lit(i)))
    last = got.groupBy("w").agg(F.max_by("n", "batch_id").alias("n"), F.max_by("cascaded", "batch_id").alias("cascaded"))
    return last.agg(F.sum("n").alias("n"), F.sum("cascaded").alias("cascaded"))


@key("stream_late")
def stream_late(spark, sf):
    """Rows behind the watermark are dropped: two files, the second one far older."""
    path, out, mark = scratch(spark), scratch(spark), scratch(spark)
    e = table(spark, sf, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    mid = e.agg(F.percentile_approx(F.col("ts").cast("double"), 0.5).alias("m")).first()["m"]
    schema = e.schema
    for part in (e.filter(F.col("ts").cast("double") >= mid), e.filter(F.col("ts").cast("double") < mid)):
        part.coalesce(1).write.mode("append").parquet(path)
        q = (
            spark.readStream.schema(schema).parquet(path).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day").alias("w")).count()
            .writeStream.outputMode("append").format("parquet").option("path", out).option("checkpointLocation", mark).trigger(availableNow=True).start()
        )
        q.awaitTermination()
    kept = spark.read.schema("w struct<start: timestamp, end: timestamp>, count long").parquet(out).agg(F.coalesce(F.sum("count"), F.lit(0)).alias("kept"))
    return kept.crossJoin(e.agg(F.count("*").alias("all"))).select("kept", "all", (F.col("kept") < F.col("all")).alias("late_dropped"))


@key("stream_dedup", "SELECT count(DISTINCT event_id) AS n FROM events")
def stream_dedup(spark, sf):
    twice = stream(spark, sf, "events").union(stream(spark, sf, "events"))
    return drain(twice.withWatermark("ts", "400 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id")).agg(F.count("*").alias("n"))


@key("stream_static_join", "SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1")
def stream_static_join(spark, sf):
    c = table(spark, sf, "customer").select("c_custkey", "c_mktsegment")
    return drain(stream(spark, sf, "events").join(c, F.col("user_id") == F.col("c_custkey")).select("c_mktsegment")).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@key("stream_interval_join", "SELECT count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def stream_interval_join(spark, sf):
    a = stream(spark, sf, "events").filter("event_type = 'click'").select(F.col("user_id").alias("u"), F.col("ts").alias("t")).withWatermark("t", "400 days")
    b = stream(spark, sf, "events").filter("event_type = 'purchase'").select("user_id", "ts", "event_id").withWatermark("ts", "400 days")
    return drain(a.join(b, F.expr("u = user_id AND ts >= t AND ts <= t + INTERVAL 1 HOUR")).select("event_id")).agg(F.count("*").alias("n"))


@key("stream_drift", "SELECT CAST(floor(least(value, 99) / 25) AS INT) AS cell, count(*) AS n FROM events GROUP BY 1")
def stream_drift(spark, sf):
    """Running counts of score ranges, kept as state, to be held against those at calibration."""
    s = stream(spark, sf, "events").select(F.floor(F.least("value", F.lit(99)) / 25).cast("int").alias("cell"))

    def count(k: tuple, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        total = (state.get[0] if state.exists else 0) + sum(len(p) for p in parts)
        state.update((total,))
        yield pd.DataFrame({"cell": [k[0]], "n": [total]})

    got = s.groupBy("cell").applyInPandasWithState(count, "cell int, n long", "n long", "update", "NoTimeout")
    return drain(got, "update").groupBy("cell").agg(F.max("n").alias("n"))


@key("stream_modes", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def stream_modes(spark, sf):
    s = stream(spark, sf, "events").groupBy("event_type").agg(F.count("*").alias("n"))
    return drain(s, "complete")


def foreach_batch_counts(spark: SparkSession, sf: str) -> DataFrame:
    return drain(stream(spark, sf, "documents").select("doc_id", "lang"), each=lambda b, i: b.groupBy("lang").count())
