"""Aggregations, grouping sets and windows."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..plans.method_queries import TABLE_LEDGER, TABLE_RUNS, answers, table_ledger, table_runs, truth
from ..plans.registry import key
from ..sources.tables import table, views
from .relational import n, plain

plain("agg_global", "SELECT count(*) AS n, round(sum(l_quantity), 2)::DOUBLE AS quantity, round(avg(l_discount), 6)::DOUBLE AS discount FROM lineitem")(lambda t: t.lineitem.agg(n(), F.round(F.sum("l_quantity"), 2).alias("quantity"), F.round(F.avg("l_discount"), 6).alias("discount")))
plain("agg_group", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_extendedprice), 2)::DOUBLE AS price FROM lineitem GROUP BY 1, 2")(lambda t: t.lineitem.groupBy("l_returnflag", "l_linestatus").agg(n(), F.round(F.sum("l_extendedprice"), 2).alias("price")))
plain("agg_having", "SELECT source, count(*) AS n FROM documents GROUP BY 1 HAVING count(*) > 49")(lambda t: t.documents.groupBy("source").agg(n()).filter("n > 49"))
plain("agg_distinct", "SELECT lang, count(DISTINCT source) AS sources FROM documents GROUP BY 1")(lambda t: t.documents.groupBy("lang").agg(F.countDistinct("source").alias("sources")))


@key("agg_approx_distinct")
def agg_approx_distinct(spark, sf):
    e = table(spark, sf, "events").agg(F.approx_count_distinct("user_id", 0.02).alias("a"), F.countDistinct("user_id").alias("exact"))
    return e.select("exact", (F.abs(F.col("a") - F.col("exact")) <= 0.05 * F.col("exact")).alias("within_5_percent"))


@key("agg_count_if", f"SELECT query_id, count(*) FILTER (WHERE y = 1) AS yes, count(*) FILTER (WHERE p_star > 0.9) AS sure FROM {truth()} t GROUP BY 1")
def agg_count_if(spark, sf):
    return answers(spark, sf).groupBy("query_id").agg(F.count_if(F.col("y") == 1).alias("yes"), F.count_if(F.col("p_star") > 0.9).alias("sure"))


_FILTERED = f"SELECT query_id, coalesce(sum(tokens) FILTER (WHERE y = 1), 0) AS tokens FROM {TABLE_LEDGER} GROUP BY query_id"


@key("agg_filter_clause", f"SELECT query_id, CAST(tokens AS BIGINT) AS tokens FROM ({_FILTERED})")
def agg_filter_clause(spark, sf):
    views(spark, sf, "labels", "documents")
    return spark.sql(_FILTERED)


@key("agg_bool", f"SELECT query_id, bool_and(p_star > 0) AS all_positive, bool_or(y = 1) AS any_yes FROM {TABLE_LEDGER} GROUP BY 1")
def agg_bool(spark, sf):
    return table_ledger(spark, sf).groupBy("query_id").agg(F.bool_and(F.col("p_star") > 0).alias("all_positive"), F.bool_or(F.col("y") == 1).alias("any_yes"))


plain("agg_avg_std", "SELECT lang, round(avg(n_chars), 4)::DOUBLE AS mean, round(stddev_samp(n_chars), 4)::DOUBLE AS spread FROM documents GROUP BY 1")(lambda t: t.documents.groupBy("lang").agg(F.round(F.avg("n_chars"), 4).alias("mean"), F.round(F.stddev_samp("n_chars"), 4).alias("spread")))


@key("agg_corr", f"SELECT query_id, round(corr(tokens, p_star), 6)::DOUBLE AS r FROM {truth()} t GROUP BY 1")
def agg_corr(spark, sf):
    return answers(spark, sf).groupBy("query_id").agg(F.round(F.corr("tokens", "p_star"), 6).alias("r"))


@key("agg_min_max_by", f"SELECT corpus, query_id, arg_min(method, e2e_s) AS cheapest, arg_max(method, e2e_s) AS dearest FROM {TABLE_RUNS} GROUP BY 1, 2")
def agg_min_max_by(spark, sf):
    return table_runs(spark, sf).groupBy("corpus", "query_id").agg(F.min_by("method", "e2e_s").alias("cheapest"), F.max_by("method", "e2e_s").alias("dearest"))


plain("agg_mode", "SELECT mode(lang) AS lang FROM documents")(lambda t: t.documents.agg(F.mode("lang").alias("lang")))


@key("agg_percentile", f"SELECT query_id, round(quantile_cont(prob, 0.1), 6)::DOUBLE AS p10, round(quantile_cont(prob, 0.5), 6)::DOUBLE AS p50, round(quantile_cont(prob, 0.9), 6)::DOUBLE AS p90 FROM {truth(prebuilt=True)} t GROUP BY 1")
def agg_percentile(spark, sf):
    return answers(spark, sf).groupBy("query_id").agg(*[F.round(F.percentile("prob", q), 6).alias(f"p{int(q * 100)}") for q in (0.1, 0.5, 0.9)])


@key("agg_percentile_approx")
def agg_percentile_approx(spark, sf):
    d = table(spark, sf, "documents")
    a = d.agg(F.percentile_approx("n_chars", 0.5, 1000).alias("a")).first()["a"]
    return d.agg((F.abs(F.avg((F.col("n_chars") <= a).cast("double")) - 0.5) <= 0.02).alias("within_rank_error"))


plain("agg_collect", "SELECT conv_id, string_agg(role, '>' ORDER BY turn) AS roles FROM conversations GROUP BY 1")(lambda t: t.conversations.groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("turn", "role"))).alias("s")).select("conv_id", F.concat_ws(">", "s.role").alias("roles")))
plain("agg_partial_final", "SELECT user_id, count(*) AS n, round(sum(value), 6)::DOUBLE AS total FROM events GROUP BY 1")(
    lambda t: t.events.withColumn("salt", F.pmod(F.xxhash64("event_id"), F.lit(8))).groupBy("user_id", "salt").agg(n("k"), F.sum("value").alias("v")).groupBy("user_id").agg(F.sum("k").alias("n"), F.round(F.sum("v"), 6).alias("total"))
)


plain("agg_sort_based", "SELECT source, string_agg(lang, ',' ORDER BY lang) AS langs FROM (SELECT DISTINCT source, lang FROM documents) GROUP BY 1")(lambda t: t.documents.groupBy("source").agg(F.array_join(F.sort_array(F.collect_set("lang")), ",").alias("langs")))


@key("agg_pivot", f"PIVOT {TABLE_LEDGER} ON purpose IN ('vote', 'train', 'cal', 'cascade') USING count(*) GROUP BY query_id")
def agg_pivot(spark, sf):
    return table_ledger(spark, sf).groupBy("query_id").pivot("purpose", ["vote", "train", "cal", "cascade"]).count().na.fill(0)


@key("agg_unpivot", f"SELECT query_id, purpose, count(*) AS n FROM {TABLE_LEDGER} GROUP BY 1, 2")
def agg_unpivot(spark, sf):
    return agg_pivot(spark, sf).unpivot("query_id", ["vote", "train", "cal", "cascade"], "purpose", "n").filter("n > 0")


@key("agg_histogram", f"SELECT query_id, CAST(least(floor(prob * 64), 63) AS BIGINT) AS bin, count(*) AS n FROM {truth(prebuilt=True)} t GROUP BY 1, 2")
def agg_histogram(spark, sf):
    return answers(spark, sf).groupBy("query_id", (F.width_bucket("prob", F.lit(0.0), F.lit(1.0), F.lit(64)) - 1).cast("long").alias("bin")).agg(n())


plain("agg_rollup", "SELECT lang, source, count(*) AS n FROM documents GROUP BY ROLLUP (lang, source)")(lambda t: t.documents.rollup("lang", "source").agg(n()))
plain("agg_cube", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")(lambda t: t.orders.cube("o_orderstatus", "o_orderpriority").agg(n()))

for _name, _sql in {
    "agg_grouping_sets": "SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())",
    "agg_grouping_id": "SELECT lang, source, CAST(grouping(lang) * 2 + grouping(source) AS INT) AS g, count(*) AS n FROM documents GROUP BY CUBE (lang, source)",
}.items():

    @key(_name, _sql)
    def _sets(spark, sf, sql=_sql):
        views(spark, sf, "documents")
        return spark.sql(sql)


# ---- windows -------------------------------------------------------------------------------------
def by_lang():
    return W.partitionBy("lang").orderBy(F.desc("n_chars"), "doc_id")


def by_user():
    return W.partitionBy("user_id").orderBy("ts", "event_id")


def whole_user():
    return by_user().rowsBetween(W.unboundedPreceding, W.unboundedFollowing)


for _name, _sql, _f in (
    ("win_row_number", "row_number()", lambda: F.row_number()), ("win_rank", "rank()", lambda: F.rank()), ("win_dense_rank", "dense_rank()", lambda: F.dense_rank()), ("win_ntile", "ntile(5)", lambda: F.ntile(5)),
):
    plain(_name, f"SELECT doc_id, CAST({_sql} OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id) AS INT) AS v FROM documents")(lambda t, f=_f: t.documents.select("doc_id", f().over(by_lang()).cast("int").alias("v")))
for _name, _sql, _f in (("win_percent_rank", "percent_rank()", lambda: F.percent_rank()), ("win_cume_dist", "cume_dist()", lambda: F.cume_dist())):
    plain(_name, f"SELECT doc_id, round({_sql} OVER (PARTITION BY lang ORDER BY n_chars), 6)::DOUBLE AS v FROM documents")(lambda t, f=_f: t.documents.select("doc_id", F.round(f().over(W.partitionBy("lang").orderBy("n_chars")), 6).alias("v")))
for _name, _sql, _f in (
    ("win_lag", "lag(event_id) OVER u", lambda: F.lag("event_id").over(by_user())), ("win_lead", "lead(event_id) OVER u", lambda: F.lead("event_id").over(by_user())),
    ("win_first_last", "last_value(event_id) OVER (u ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) - first_value(event_id) OVER u", lambda: F.last("event_id").over(whole_user()) - F.first("event_id").over(whole_user())),
    ("win_nth", "nth_value(event_id, 2) OVER (u ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)", lambda: F.nth_value("event_id", 2).over(whole_user())),
):
    plain(_name, f"SELECT event_id, coalesce({_sql}, -1) AS v FROM events WINDOW u AS (PARTITION BY user_id ORDER BY ts, event_id)")(lambda t, f=_f: t.events.select("event_id", F.coalesce(f(), F.lit(-1)).alias("v")))


@key("win_running_sum", f"SELECT doc_id, round(sum(round(least(p_star, 1 - p_star), 9)) OVER (ORDER BY round(least(p_star, 1 - p_star), 9), doc_id), 5)::DOUBLE AS s FROM {truth(('Q04',))} t")
def win_running_sum(spark, sf):
    e = F.round(F.least("p_star", 1 - F.col("p_star")), 9)
    w = W.partitionBy("query_id").orderBy("e", "doc_id").rowsBetween(W.unboundedPreceding, 0)
    return answers(spark, sf, ("Q04",)).withColumn("e", e).select("doc_id", F.round(F.sum("e").over(w), 5).alias("s"))


plain("win_moving_avg", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 6 PRECEDING AND CURRENT ROW), 6)::DOUBLE AS v FROM events")(lambda t: t.events.select("event_id", F.round(F.avg("value").over(by_user().rowsBetween(-6, 0)), 6).alias("v")))
plain("win_range_frame", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_orderstatus ORDER BY o_custkey RANGE BETWEEN 10 PRECEDING AND 10 FOLLOWING) AS n FROM orders")(lambda t: t.orders.select("o_orderkey", F.count("*").over(W.partitionBy("o_orderstatus").orderBy("o_custkey").rangeBetween(-10, 10)).alias("n")))
plain("win_partition_total", "SELECT lang, source, round(count(*) * 1.0 / sum(count(*)) OVER (PARTITION BY lang), 6)::DOUBLE AS share FROM documents GROUP BY 1, 2")(lambda t: t.documents.groupBy("lang", "source").agg(n()).select("lang", "source", F.round(F.col("n") / F.sum("n").over(W.partitionBy("lang")), 6).alias("share")))
plain("win_dedup_latest", "SELECT user_id, event_id FROM events QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, event_id DESC) = 1")(lambda t: t.events.groupBy("user_id").agg(F.max(F.struct("ts", "event_id")).alias("m")).select("user_id", "m.event_id"))
