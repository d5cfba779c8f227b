"""From raw documents to token ids: language, lines, near-duplicates, mixture, encoding.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame, which is written as Parquet and read again
as the next one's documents. All but the last return the columns of ``documents``.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from semfilter.llm import line_spread, mixture_lang, odd_sketch, piece_lattice, pivotal_mix
from semfilter.llm.common import read_table, save


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps documents in languages learned from the labelled ones, however many they mix; texts without a letter go."""
    return mixture_lang.known_language(docs)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Takes lines seen on ten sites or more out of every document but the first that has them.

    Documents that consisted of such lines only go; ``n_chars`` follows the text.
    """
    n_lines, n_removed = (F.col(f"`{c}`") for c in line_spread.counts_of(docs))
    cut = line_spread.spread_lines(docs).filter((n_lines == 0) | (n_removed < n_lines))
    length = F.when(n_removed > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))
    return cut.select(*[length.alias("n_chars") if c == "n_chars" else F.col(f"`{c}`") for c in docs.columns])


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates, the one with the smallest id; unlike texts that share an id all stay."""
    return odd_sketch.one_of_each(docs)


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mixture of sources takes them: none, once, twice."""
    return pivotal_mix.mixed_documents(docs)


def encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Ids of every text, and whether they decode to it: ``doc_id, ids, n_tokens, round_trip``."""
    pieces = piece_lattice.Pieces.load(public_tokenizers.path("piece_bpe_32k.model"))
    out = piece_lattice.encode(docs, pieces, decoded=True)
    return out.select("doc_id", "ids", F.size("ids").cast("long").alias("n_tokens"), (F.col("decoded") == F.coalesce("text", F.lit(""))).alias("round_trip"))


STAGES = [("language_id", language), ("line_dedup", lines), ("near_dedup", near_duplicates), ("source_mixing", mixture), ("sentencepiece", encoding)]

#: SQL cannot express the learned language, the random mixture or the encoding; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the whole ``documents`` table."""
    docs = read_table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = save(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
