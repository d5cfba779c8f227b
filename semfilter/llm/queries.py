"""Queries of the training-data operators, with their SQL twins where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import interleave, line_spread, mixture_lang, odd_sketch, packed_ids, piece_lattice, pivotal_mix, span_dedup, tile_links, topk_blocks
from .common import read_table

Query = Callable[[SparkSession, str], DataFrame]


def op1_packed_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents", "doc_id", "text")
    return packed_ids.packed_corpus(docs, public_tokenizers.path("word_bpe_49k.json"), end_id=2, payload=False)


def op2_span_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return span_dedup.without_repeats(read_table(spark, sf_dir, "documents", "doc_id", "text"))


def op3_piece_lattice(spark: SparkSession, sf_dir: str) -> DataFrame:
    pieces = piece_lattice.Pieces.load(public_tokenizers.path("piece_bpe_32k.model"))
    out = piece_lattice.encode(read_table(spark, sf_dir, "documents", "doc_id", "text"), pieces, decoded=True)
    return out.select("doc_id", "ids", F.size("ids").cast("long").alias("n_tokens"), (F.col("decoded") == F.coalesce("text", F.lit(""))).alias("round_trip"))


def op4_topk_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk_blocks.top_k(read_table(spark, sf_dir, "embeddings", "vec_id", "embedding"))


def op5_tile_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tile_links.near_vectors(read_table(spark, sf_dir, "embeddings")).select("vec_id", "n_links", "component_id", "kept")


def op6_interleave(spark: SparkSession, sf_dir: str) -> DataFrame:
    dealt = interleave.interleave(read_table(spark, sf_dir, "documents", "doc_id", "text", "source"))
    return dealt.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "source")


def op7_pivotal_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = pivotal_mix.mix(read_table(spark, sf_dir, "documents", "doc_id", "text", "source"))
    return mixed.select(F.col("id").alias("doc_id"), "size", "source_size", "target", (F.col("copies") * F.col("size")).cast("long").alias("taken"), "copies", "source")


def op8_odd_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    return odd_sketch.near_duplicates(read_table(spark, sf_dir, "documents", "doc_id", "text"))


def op9_line_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    clean = line_spread.spread_lines(read_table(spark, sf_dir, "documents", "doc_id", "text", "source"))
    return clean.select("doc_id", "text", F.col("_n_lines").alias("n_lines"), F.col("_n_removed").alias("n_removed"))


def op10_mixture_lang(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents", "doc_id", "text", "lang")
    out = mixture_lang.identify(docs, mixture_lang.fit(docs))
    held_out = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0
    return out.select("doc_id", F.coalesce(held_out, F.lit(False)).alias("held_out"), "lang_pred", "score", F.size("mixture").alias("n_languages"))


QUERIES: dict[str, Query] = {f.__name__: f for f in (op10_mixture_lang, op9_line_spread, op8_odd_sketch, op1_packed_ids, op2_span_dedup, op3_piece_lattice, op4_topk_blocks, op5_tile_links, op6_interleave, op7_pivotal_mix)}

TOPK_SQL = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS t FROM embeddings
           WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, d.vec_id, CAST(list_dot_product(CAST(q.t AS DOUBLE[]), CAST(d.t AS DOUBLE[])) AS BIGINT) AS score
      FROM v q JOIN v d ON q.vec_id <> d.vec_id WHERE q.vec_id % 50 = 0)
SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score
FROM s QUALIFY rank <= 5
"""

LINKS_SQL = """
WITH RECURSIVE v AS (SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS e FROM embeddings
  WHERE embedding IS NOT NULL AND label IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(embedding, lambda x: x <> 0)) > 0),
l AS (SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.label = b.label AND a.vec_id <> b.vec_id
      WHERE list_dot_product(a.e, b.e) / (sqrt(list_dot_product(a.e, a.e)) * sqrt(list_dot_product(b.e, b.e))) >= 0.93),
r AS (SELECT a AS node, a AS seen FROM l UNION SELECT r.node, l.b FROM r JOIN l ON r.seen = l.a),
c AS (SELECT node, min(seen) AS component FROM r GROUP BY node), n AS (SELECT a, count(*) AS k FROM l GROUP BY a)
SELECT e.vec_id, coalesce(n.k, 0) AS n_links, coalesce(c.component, e.vec_id) AS component_id, coalesce(c.component, e.vec_id) = e.vec_id AS kept
FROM embeddings e LEFT JOIN n ON n.a = e.vec_id LEFT JOIN c ON c.node = e.vec_id
"""

SHINGLES_SQL = r"""
WITH RECURSIVE w AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
g AS (SELECT doc_id, CASE WHEN len(w) >= 5 THEN list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' '))) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END AS g FROM w),
c AS (SELECT min(doc_id) AS rep, list_sort(g) AS k, len(list_sort(g)) AS n FROM g WHERE len(g) > 0 GROUP BY ALL),
x AS (SELECT rep, n, unnest(k) AS s FROM c),
l AS (SELECT a.rep AS a, b.rep AS b FROM x a JOIN x b ON a.s = b.s AND a.rep <> b.rep GROUP BY a.rep, b.rep, a.n, b.n HAVING 100 * count(*) >= 75 * (a.n + b.n - count(*))),
r AS (SELECT rep AS node, rep AS seen FROM c UNION SELECT r.node, l.b FROM r JOIN l ON r.seen = l.a),
m AS (SELECT node, min(seen) AS component FROM r GROUP BY node)
SELECT g.doc_id, CAST(len(g.g) AS BIGINT) AS n_shingles, coalesce(m.component, g.doc_id) AS component_id, coalesce(m.component, g.doc_id) = g.doc_id AS kept
FROM g LEFT JOIN c ON list_sort(g.g) = c.k LEFT JOIN m ON m.node = c.rep
"""

SPREAD_SQL = """
WITH s AS (SELECT doc_id, source, string_split(text, chr(10)) AS t FROM documents),
l AS (SELECT doc_id, source, unnest(t) AS line, unnest(range(len(t))) AS pos FROM s),
k AS (SELECT doc_id, pos, trim(line) AS k, count(*) OVER (PARTITION BY trim(line)) AS n FROM l WHERE trim(line) <> ''),
b AS (SELECT trim(line) AS k FROM l WHERE trim(line) <> '' GROUP BY 1 HAVING count(DISTINCT coalesce('=' || source, '')) >= 10),
o AS (SELECT doc_id, pos, row_number() OVER (PARTITION BY k ORDER BY doc_id, pos) AS o FROM k SEMI JOIN b USING (k)),
g AS (SELECT doc_id, list(pos) AS gone FROM o WHERE o > 1 GROUP BY doc_id)
SELECT s.doc_id, array_to_string([s.t[i + 1] for i in range(len(s.t)) if NOT list_contains(coalesce(g.gone, []), i)], chr(10)) AS text,
       CAST(len(list_filter(s.t, lambda x: trim(x) <> '')) AS BIGINT) AS n_lines, CAST(coalesce(len(g.gone), 0) AS BIGINT) AS n_removed
FROM s LEFT JOIN g USING (doc_id)
"""

ORACLES: dict[str, str] = {"op9_line_spread": SPREAD_SQL, "op8_odd_sketch": SHINGLES_SQL, "op4_topk_blocks": TOPK_SQL, "op5_tile_links": LINKS_SQL}
