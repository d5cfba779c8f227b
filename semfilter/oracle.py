"""Oracles that answer a predicate with a hard label and its probability, and the ledger of what was paid for."""

from __future__ import annotations

import hashlib
import json
import uuid
from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .sources import catalogue as cat
from .sources.tables import save, scratch, table, views

ORACLE_MS, PREBUILT_MS = 0.2586, 0.0323


def uniform(*parts) -> F.Column:
    """A number in [0, 1) hashed from the parts; the same in every engine and partitioning."""
    key = F.concat(*[p.cast("string") if hasattr(p, "cast") else F.lit(str(p)) for p in parts])
    return F.conv(F.substring(F.md5(key.cast("binary")), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def prob_from_logprobs(lp_yes, lp_no):
    """Probability of yes from the log-probabilities of the two answer tokens."""
    return F.exp(lp_yes) / (F.exp(lp_yes) + F.exp(lp_no))


class PlantedOracle:
    """The simulated oracle: planted predicates on ``documents`` or on another corpus in its shape."""

    def __init__(self, spark: SparkSession, sf_dir: str, queries: tuple[str, ...] = cat.ALL, mode: str = "argmax", corpus: DataFrame | None = None):
        self.spark, self.sf_dir, self.queries, self.mode, self.corpus = spark, sf_dir, tuple(queries), mode, corpus

    def answers(self) -> DataFrame:
        """``query_id, doc_id, p_star, y, tokens, prob`` for all pairs: one scan, wide, then unpivoted."""
        views(self.spark, self.sf_dir, "documents", "benchmark")
        if self.corpus is not None:
            self.corpus.createOrReplaceTempView("documents")
        d, c = cat.Spark, cat.catalogue()
        cols = [f"{cat.p_star(c[q])} AS p_{q}" for q in self.queries]
        wide = self.spark.sql(f"SELECT doc_id, CAST(size(filter(split(text, ' '), x -> x <> '')) AS BIGINT) AS tokens, {', '.join(cols)} FROM ({cat.rich(d, self.queries)}) documents")
        if self.corpus is not None:
            views(self.spark, self.sf_dir, "documents")
        clip = {q: f"least(greatest(p_{q}, 1e-12D), 1 - 1e-12D)" for q in self.queries}
        parts = ", ".join(f"named_struct('query_id', '{q}', 'p_star', p_{q}, 'y', {cat.answer(q, f'p_{q}', self.mode)}, 'prob', {cat.prebuilt_p(clip[q], q)})" for q in self.queries)
        return wide.select("doc_id", "tokens", F.explode(F.expr(f"array({parts})")).alias("r")).select("r.query_id", "doc_id", "r.p_star", F.col("r.y").cast("int").alias("y"), "tokens", "r.prob")


class TableOracle:
    """Answers from a table of labels; probability 0.98 for yes and 0.02 for no."""

    def __init__(self, labels: DataFrame, column: str, query_id: str):
        self.labels, self.column, self.query_id = labels, column, query_id

    def answers(self) -> DataFrame:
        y = F.col(self.column).cast("int")
        return self.labels.filter(y.isNotNull()).select(F.lit(self.query_id).alias("query_id"), "doc_id", F.when(y == 1, 0.98).otherwise(0.02).alias("p_star"), y.alias("y"))


class StoredOracle:
    """An oracle whose answers lie in a table, ``query_id, doc_id, y, p_star, tokens``; hands out those asked for."""

    def __init__(self, answers: DataFrame):
        self.answers = answers

    def label(self, wanted: DataFrame) -> DataFrame:
        got = wanted.select("query_id", "doc_id").join(self.answers, ["query_id", "doc_id"])
        return got.select("query_id", "doc_id", "y", "p_star", (F.col("tokens") if "tokens" in self.answers.columns else F.lit(0)).cast("long").alias("tokens"))


class CallableOracle:
    """An oracle behind a function of a list of texts that gives the probability of yes for each, such as a model's endpoint.

    ``texts`` has ``doc_id, text``. A batch has ``timeout`` seconds and is tried ``retries`` times more; its answers are written to the shared
    scratch folder before the next one is asked, under a name made of the query and the batch's ids, where a task or job that is run again
    finds them. So a failure costs one batch at most.
    """

    def __init__(self, ask: Callable[[list[str]], list[float]], query_id: str, texts: DataFrame | None = None, batch: int = 32, retries: int = 3, timeout: float = 600.0):
        self.ask, self.query_id, self.texts, self.batch, self.retries, self.timeout = ask, query_id, texts, batch, retries, timeout
        self.store: str | None = None

    def label(self, wanted: DataFrame) -> DataFrame:
        """Answers for the documents of ``wanted`` (``doc_id``, and ``text`` if the oracle has no texts of its own)."""
        ask, size, retries, query, timeout = self.ask, self.batch, self.retries, self.query_id, self.timeout
        self.store = store = self.store or scratch(wanted.sparkSession)
        docs = wanted.select("doc_id", "text") if self.texts is None else wanted.select("doc_id").distinct().join(self.texts.select("doc_id", "text"), "doc_id")

        def answered(fs, path: str, texts: list[str]) -> list[float]:
            from pyarrow import fs as pafs

            if fs.get_file_info(path).type == pafs.FileType.File:
                with fs.open_input_stream(path) as f:
                    return json.loads(f.read())
            for left in range(retries, -1, -1):
                pool = ThreadPoolExecutor(1)
                try:
                    ps = [float(p) for p in pool.submit(ask, texts).result(timeout)]
                    break
                except Exception:
                    if not left:
                        raise
                finally:
                    pool.shutdown(wait=False)
            if len(ps) != len(texts):
                raise ValueError(f"the oracle gave {len(ps)} answers to {len(texts)} texts")
            draft = f"{path}.{uuid.uuid4().hex}"
            with fs.open_output_stream(draft) as f:
                f.write(json.dumps(ps).encode())
            fs.move(draft, path)
            return ps

        def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            from pyarrow import fs as pafs

            fs, base = pafs.FileSystem.from_uri(store)
            fs.create_dir(base, recursive=True)
            for part in parts:
                for k in range(0, len(part), size):
                    own = part.iloc[k : k + size]
                    name = hashlib.sha256(json.dumps([query, own["doc_id"].tolist()]).encode()).hexdigest()
                    ps = answered(fs, f"{base}/{name}", own["text"].tolist())
                    yield pd.DataFrame({"query_id": query, "doc_id": own["doc_id"], "y": [int(p >= 0.5) for p in ps], "p_star": ps, "tokens": own["tokens"]})

        text = F.coalesce("text", F.lit(""))
        rows = docs.select("doc_id", text.alias("text"), F.size(F.split(text, " ")).cast("long").alias("tokens"))
        dealt = rows.repartition("doc_id").sortWithinPartitions("doc_id")  # the same batches whenever the same documents are asked for
        return save(dealt.mapInPandas(run, "query_id string, doc_id long, y int, p_star double, tokens long"))


LEDGER = "query_id string, doc_id long, y int, p_star double, tokens long, purpose string, round int"


class Ledger:
    """Labels bought so far, a row for each (query, document), never two; only what is missing reaches the oracle."""

    def __init__(self, source, spark: SparkSession | None = None):
        """``source`` is an oracle, or a table of its answers."""
        stored = isinstance(source, DataFrame)
        self.oracle = StoredOracle(source) if stored else source
        self.rows = (source.sparkSession if stored else spark).createDataFrame([], LEDGER)

    def request(self, wanted: DataFrame, purpose: str, round_: int = 0) -> DataFrame:
        """Buys what is not bought yet of ``query_id, doc_id``; the new rows, already written."""
        keys = ["query_id", "doc_id"]
        new = save(wanted.select(*keys).distinct().join(self.rows.select(*keys), keys, "left_anti"))
        got = self.oracle.label(new).select("query_id", "doc_id", "y", "p_star", "tokens", F.lit(purpose).alias("purpose"), F.lit(round_).alias("round"))
        got = save(got)
        self.rows = self.rows.unionByName(got)
        return got

    def reuse(self, purposes: list[str], as_purpose: str) -> DataFrame:
        """Rows bought for one step, for another one to use; nothing is paid."""
        return self.rows.filter(F.col("purpose").isin(purposes)).withColumn("purpose", F.lit(as_purpose))


def against_truth(ledger: DataFrame, labels: DataFrame, column: str) -> DataFrame:
    """How the oracle and an external truth agree: counts for each pair of answers."""
    return ledger.join(labels.select("doc_id", F.col(column).cast("int").alias("truth")), "doc_id").groupBy("query_id", "y", "truth").agg(F.count("*").alias("n"))


def quality_oracle(spark: SparkSession, sf_dir: str, column: str) -> TableOracle:
    return TableOracle(table(spark, sf_dir, "labels"), column, column)
