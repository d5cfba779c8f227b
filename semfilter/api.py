"""The filter as an operator on a corpus of one's own."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import features as feat
from .cascades.methods import METHODS, Bench, Result, nothing
from .config import Config
from .oracle import CallableOracle
from .sources.tables import save


@dataclass
class SemResult:
    """What a filter decided, what it cost, and how it came to that."""

    predictions: DataFrame
    run: dict
    detail: Result

    def accepted(self, df: DataFrame, id_col: str = "doc_id") -> DataFrame:
        """The rows whose predicate holds; a semi-join, so columns stay as they were."""
        yes = self.predictions.filter("yhat = 1").select(F.col("doc_id").alias(id_col))
        return df.join(yes, id_col, "left_semi")

    def explain(self) -> str:
        r = self.run
        steps = [f"{r['method']} at target {r['alpha']}", f"labels: vote {r['n_vote']}, train {r['n_train']}, calibration {r['n_cal']}, cascade {r['n_cascade']}, all {r['n_oracle']}", f"threshold {r['tau']:.4f}, second phase {r['phase2']}", f"proxy {r['proxy_s']:.1f} s, oracle {r['oracle_s']:.1f} s"]
        return "\n".join(steps)


def sem_filter(df: DataFrame, oracle, asks: str, alpha: float = 0.9, method: str = "two_phase", cfg: Config | None = None, query_id: str = "Q", scores: DataFrame | None = None) -> SemResult:
    """Labels every document of ``doc_id, text`` with the oracle's likely answer, to corpus accuracy ``alpha``.

    ``oracle`` is a function of a list of texts that gives each one's probability of yes, or an object whose ``label`` takes
    ``query_id, doc_id`` and gives ``query_id, doc_id, y, p_star, tokens``. It is asked for the ledger's requests only, each document once at
    most. ``scores`` (``doc_id, prob``) is what ``prebuilt_cascade`` needs. The measures of a run are unknown (NaN) where only an oracle on request is given.

    One decision for each distinct id: of rows that repeat one the least text counts. Rows with a null id take no part, null
    text is empty, other columns are ignored, and an empty table gives no decision and no call.
    """
    cfg = replace(cfg or Config(), alpha=alpha)
    docs = df.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text")).filter("doc_id IS NOT NULL")
    if not docs.groupBy("doc_id").count().filter("count > 1").isEmpty():
        docs = docs.groupBy("doc_id").agg(F.min("text").alias("text"))
    vectors = save(feat.build(docs, cfg.emb_dim))
    n = vectors.count()
    if callable(oracle):
        oracle = CallableOracle(oracle, query_id, docs)
    prior = None
    if scores is not None:
        tokens = docs.select("doc_id", F.size(F.split("text", " ")).cast("long").alias("tokens"))
        prior = save(scores.select(F.lit(query_id).alias("query_id"), "doc_id", "prob").join(tokens, "doc_id"))
    b = Bench(df.sparkSession, (query_id,), {query_id: asks}, None, vectors, n, cfg.scaled(max(1, n)), oracle=oracle, prior=prior)
    got = METHODS[method](b) if n else nothing(b, method)
    return SemResult(got.predictions, got.runs.iloc[0].to_dict(), got)
