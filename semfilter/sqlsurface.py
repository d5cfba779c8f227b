"""SQL and UDF surface: functions, table functions, grouped and cogrouped maps, and a marked predicate in SQL text."""

from __future__ import annotations

import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .calibrate import bounds
from .cascades.methods import METHODS, Bench
from .config import Config
from .oracle import StoredOracle
from .plans.method_queries import answers, truth
from .plans.registry import key
from .proxy import nets
from .sources import catalogue as cat
from .sources.tables import save, table, views


def functions(spark: SparkSession) -> None:
    """Registers the scalar functions of the engine for SQL."""
    for name, args, body in (
        ("conf_of", "p DOUBLE", "2 * abs(p - 0.5D)"), ("eta_of", "p DOUBLE", "least(p, 1 - p)"),
        ("bce_of", "p DOUBLE, t DOUBLE", "-t * ln(greatest(p, 1e-7D)) - (1 - t) * ln(greatest(1 - p, 1e-7D))"), ("blend_of", "e DOUBLE, u DOUBLE, w DOUBLE", "(1 - w) * e + w * u"),
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS DOUBLE RETURN {body}")


@key("udf_sql_functions", f"SELECT query_id, round(avg(2 * abs(prob - 0.5)), 6)::DOUBLE AS conf, round(avg(least(p_star, 1 - p_star)), 6)::DOUBLE AS eta, round(avg(0.94 * prob + 0.06 * p_star), 6)::DOUBLE AS blend FROM {truth(prebuilt=True)} t GROUP BY 1")
def udf_sql_functions(spark, sf):
    functions(spark)
    answers(spark, sf).createOrReplaceTempView("sem_answers")
    return spark.sql("SELECT query_id, round(avg(conf_of(prob)), 6) AS conf, round(avg(eta_of(p_star)), 6) AS eta, round(avg(blend_of(prob, p_star, 0.06D)), 6) AS blend FROM sem_answers GROUP BY 1")


@key("udf_pandas_scalar", "SELECT k::INT AS k, round(1 - pow(0.05, 1.0 / k), 6)::DOUBLE AS upper FROM range(1, 30) r(k)")
def udf_pandas_scalar(spark, sf):
    @F.pandas_udf("double")
    def upper(n: pd.Series) -> pd.Series:
        return n.map(lambda v: bounds.binom_upper(0, int(v)))

    return spark.range(1, 30).select(F.col("id").cast("int").alias("k"), F.round(upper("id"), 6).alias("upper"))


@key("udf_arrow_map", f"SELECT query_id, count(*) AS n FROM {truth()} t WHERE p_star > 0.5 GROUP BY 1")
def udf_arrow_map(spark, sf):
    def keep(parts: Iterator) -> Iterator:
        import pyarrow.compute as pc

        for b in parts:
            yield b.filter(pc.greater(b.column(1), 0.5))

    return answers(spark, sf).select("query_id", "p_star").mapInArrow(keep, "query_id string, p_star double").groupBy("query_id").agg(F.count("*").alias("n"))


@key("udf_grouped_map", f"SELECT query_id, round(max(p_star), 6)::DOUBLE AS most FROM {truth()} t GROUP BY 1")
def udf_grouped_map(spark, sf):
    def top(p: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"query_id": p["query_id"].iloc[:1], "most": [round(p["p_star"].max(), 6)]})

    return answers(spark, sf).select("query_id", "p_star").groupBy("query_id").applyInPandas(top, "query_id string, most double")


@key("udf_grouped_agg", f"SELECT query_id, round(sum(c * w) / (sum(c) + 0.001), 6)::DOUBLE AS risk FROM (SELECT query_id, 2 * abs(prob - 0.5) AS c, CASE WHEN y = 1 THEN 1 - prob ELSE prob END AS w FROM {truth(prebuilt=True)} t) GROUP BY 1")
def udf_grouped_agg(spark, sf):
    @F.pandas_udf("double")
    def risk(p: pd.Series, y: pd.Series) -> float:
        return round(nets.soft_risk(p.to_numpy(), y.to_numpy()), 6)

    return answers(spark, sf).groupBy("query_id").agg(risk("prob", "y").alias("risk"))


@key("udf_cogrouped_map", f"SELECT query_id, count(*) FILTER (WHERE doc_id % 10 = 0) AS n_train, count(*) FILTER (WHERE doc_id % 10 = 1) AS n_cal FROM {truth()} t GROUP BY 1")
def udf_cogrouped_map(spark, sf):
    def both(t: pd.DataFrame, c: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"query_id": [t["query_id"].iloc[0]], "n_train": [len(t)], "n_cal": [len(c)]})

    a = answers(spark, sf).select("query_id", "doc_id")
    return a.filter("doc_id % 10 = 0").groupBy("query_id").cogroup(a.filter("doc_id % 10 = 1").groupBy("query_id")).applyInPandas(both, "query_id string, n_train long, n_cal long")


@key("udf_table_function", "SELECT doc_id, CAST(length(text) > 1000 AS INT) AS yhat FROM documents")
def udf_table_function(spark, sf):
    from pyspark.sql.functions import udtf

    class Score:
        """A frozen plan over a relation: one row in, one decision out."""

        def eval(self, row):
            yield row["doc_id"], int(len(row["text"] or "") > 1000)

    spark.udtf.register("sem_score", udtf(Score, returnType="doc_id: bigint, yhat: int"))
    views(spark, sf, "documents")
    return spark.sql("SELECT * FROM sem_score(TABLE(SELECT doc_id, text FROM documents))")


_MARK = re.compile(r"SEM_FILTER\(\s*(\w+)\s*,\s*'([^']*)'\s*,\s*([0-9.]+)\s*\)")


def sql(spark: SparkSession, sf_dir: str, text: str, method: str = "prebuilt_cascade") -> DataFrame:
    """SQL with one marked predicate ``SEM_FILTER(column, 'query id', target)`` on ``documents``.

    The predicate is planned and run first; its decisions become a view that the rest of the statement meets by a
    semi-join on ``doc_id``, so everything else stays with Catalyst.
    """
    m = _MARK.search(text)
    views(spark, sf_dir)
    if not m:
        return spark.sql(text)
    q, alpha = m[2], float(m[3])
    if q not in cat.ALL:
        raise ValueError(f"unknown predicate {q}")
    got = METHODS[method](Bench.documents(spark, sf_dir, (q,), Config(alpha=alpha)))
    name = f"sem_accepted_{q.lower()}"
    save(got.predictions.filter("yhat = 1").select("doc_id")).createOrReplaceTempView(name)
    return spark.sql(f"{text[: m.start()]}doc_id IN (SELECT doc_id FROM {name}){text[m.end() :]}")


@key("sql_sem_filter", f"SELECT d.lang, count(*) AS n FROM documents d JOIN {truth(('Q01',))} t USING (doc_id) WHERE t.y = 1 GROUP BY 1")
def sql_sem_filter(spark, sf):
    return sql(spark, sf, "SELECT lang, count(*) AS n FROM documents WHERE SEM_FILTER(text, 'Q01', 0.9) GROUP BY lang", "exhaustive")


@key("sem_explain")
def sem_explain(spark, sf):
    from .api import sem_filter

    b = Bench.documents(spark, sf, ("Q01",))
    got = sem_filter(table(spark, sf, "documents").select("doc_id", "text"), StoredOracle(b.answers), "written in German", 0.9, "prebuilt_cascade", Config(), "Q01", b.answers.select("doc_id", "prob"))
    return spark.createDataFrame([(i, s) for i, s in enumerate(got.explain().split("\n"))], "step int, what string")


