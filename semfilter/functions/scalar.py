"""Scalar functions a user of the filter needs, each as one query."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import features as feat
from ..operators.relational import n, plain
from ..oracle import uniform
from ..plans.method_queries import LEDGER, answers, truth, u
from ..plans.registry import key
from ..sources.catalogue import LEXICON, Duck, normal
from ..sources.tables import normalise, strip_html, table, words


def fn(name: str, tab: str, ident: str, spark_expr: str, duck_expr: str | None = None, where: str = "true"):
    """One expression on one table, in both engines."""
    plain(name, f"SELECT {ident}, {duck_expr or spark_expr} AS v FROM {tab} WHERE {where}")(lambda t: getattr(t, tab).filter(where).selectExpr(ident, f"{spark_expr} AS v"))


# ---- strings ---------------------------------------------------------------------------------------
fn("fn_length", "documents", "doc_id", "CAST(length(text) AS BIGINT)")
fn("fn_lower_upper", "part", "p_partkey", "concat(lower(p_name), '/', upper(p_brand))")
fn("fn_trim", "part", "p_partkey", "trim(concat('  ', p_name, ' '))")
fn("fn_substr", "part", "p_partkey", "substr(p_name, 2, 5)")
fn("fn_concat_ws", "part", "p_partkey", "concat_ws('|', p_name, p_brand, p_type)")
fn("fn_split_size", "documents", "doc_id", "CAST(size(split(text, ' ')) AS BIGINT)", "CAST(len(string_split(text, ' ')) AS BIGINT)")
fn("fn_regexp_extract", "pages", "page_id", "regexp_extract(url, '^[a-z]+://([^/]+)', 1)")
fn("fn_regexp_replace", "documents", "doc_id", "md5(regexp_replace(text, '[0-9]+', '#'))", "md5(regexp_replace(text, '[0-9]+', '#', 'g'))")
fn("fn_regexp_count", "documents", "doc_id", "CAST(regexp_count(text, '[0-9]+') AS BIGINT)", "CAST(len(regexp_extract_all(text, '[0-9]+')) AS BIGINT)")
fn("fn_translate", "part", "p_partkey", "translate(p_name, 'aeiou', '12345')")
fn("fn_lpad", "part", "p_partkey", "lpad(CAST(p_size AS STRING), 5, '0')", "lpad(CAST(p_size AS VARCHAR), 5, '0')")
fn("fn_levenshtein", "part", "p_partkey", "CAST(levenshtein(p_name, p_type) AS BIGINT)")
fn("fn_md5", "documents", "doc_id", "md5(text)")
fn("fn_instr", "documents", "doc_id", "CAST(instr(text, 'the') AS BIGINT)")
fn("fn_initcap", "part", "p_partkey", "initcap(p_name)", "array_to_string(list_transform(string_split(p_name, ' '), lambda w: upper(w[1]) || lower(w[2:])), ' ')")
_STRIP = "trim(regexp_replace(regexp_replace(regexp_replace(regexp_replace(html, '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '<[^>]*>', ' ', 'g'), '&[a-zA-Z#0-9]+;', ' ', 'g'), '\\s+', ' ', 'g'))"
plain("fn_html_strip", f"SELECT page_id, CAST(length({_STRIP}) AS BIGINT) AS v FROM pages")(lambda t: t.pages.select("page_id", F.length(strip_html(F.col("html"))).cast("long").alias("v")))

# ---- text features -----------------------------------------------------------------------------------
_TOK = "list_filter(regexp_split_to_array(lower(text), '[^a-zà-ÿ]+'), lambda x: x <> '')"
_STOK = "filter(split(lower(text), '[^a-zà-ÿ]+'), x -> x <> '')"
fn("feat_word_count", "documents", "doc_id", "CAST(size(filter(split(text, ' '), x -> x <> '')) AS BIGINT)", "CAST(len(list_filter(string_split(text, ' '), lambda x: x <> '')) AS BIGINT)")
fn("feat_mean_word_len", "documents", "doc_id", f"round(aggregate({_STOK}, 0L, (a, x) -> a + length(x)) / greatest(size({_STOK}), 1), 6)", f"round(coalesce(list_sum(list_transform({_TOK}, lambda x: length(x))), 0) * 1.0 / greatest(len({_TOK}), 1), 6)::DOUBLE")
fn("feat_type_token_ratio", "documents", "doc_id", f"round(size(array_distinct({_STOK})) / greatest(size({_STOK}), 1), 6)", f"round(len(list_distinct({_TOK})) * 1.0 / greatest(len({_TOK}), 1), 6)::DOUBLE")
fn("feat_vowel_share", "documents", "doc_id", "round((length(text) - length(regexp_replace(lower(text), '[aeiou]', ''))) / greatest(length(text), 1), 6)", "round((length(text) - length(regexp_replace(lower(text), '[aeiou]', '', 'g'))) * 1.0 / greatest(length(text), 1), 6)::DOUBLE")
fn("feat_digit_flag", "documents", "doc_id", "text RLIKE '[0-9]'", "regexp_matches(text, '[0-9]')")
fn("feat_lexicon_flag", "documents", "doc_id", f"lower(text) RLIKE '{'|'.join(LEXICON)}'", f"regexp_matches(lower(text), '{'|'.join(LEXICON)}')")
fn("feat_junk_flag", "documents", "doc_id", "contains(text, '%%%') OR contains(text, '###') OR contains(text, '***')")
plain("feat_exact_dup", "SELECT doc_id, count(*) OVER (PARTITION BY md5(text)) > 1 AS v FROM documents")(
    lambda t: (lambda d: d.join(d.groupBy("h").agg(n()), "h").select("doc_id", (F.col("n") > 1).alias("v")))(t.documents.select("doc_id", F.md5("text").alias("h")))
)
plain("feat_benchmark_overlap", "SELECT doc_id, count(*) AS n FROM documents d JOIN benchmark b ON contains(d.text, b.text) GROUP BY 1")(lambda t: t.documents.alias("d").join(F.broadcast(t.benchmark.alias("b")), F.expr("contains(d.text, b.text)")).groupBy("doc_id").agg(n()))
plain("feat_ngrams", "SELECT g, count(*) AS n FROM (SELECT unnest(list_transform(range(1, length(text) - 1), lambda i: substr(text, i, 3))) AS g FROM documents WHERE length(text) > 2) GROUP BY 1 ORDER BY n DESC, g LIMIT 20")(
    lambda t: t.documents.filter("length(text) > 2").select(F.split("text", "").alias("c")).select(F.explode(F.expr("transform(sequence(0, size(c) - 3), i -> concat(c[i], c[i + 1], c[i + 2]))")).alias("g")).groupBy("g").agg(n()).orderBy(F.desc("n"), "g").limit(20)
)
fn("feat_token_set", "documents", "doc_id", f"CAST(size(array_distinct({_STOK})) AS BIGINT)", f"CAST(len(list_distinct({_TOK})) AS BIGINT)")


@key("feat_hashed_vector")
def feat_hashed_vector(spark, sf):
    v = feat.build(table(spark, sf, "documents"), 64)
    return v.select("doc_id", F.size("toks").alias("n_toks"), F.round(F.expr("aggregate(emb, 0D, (a, x) -> a + cast(x as double) * x)"), 4).alias("norm2"))


# ---- dates -------------------------------------------------------------------------------------------
fn("fn_date_trunc", "orders", "o_orderkey", "date_format(date_trunc('month', o_orderdate), 'yyyy-MM-dd')", "strftime(date_trunc('month', o_orderdate), '%Y-%m-%d')")
fn("fn_date_diff", "orders", "o_orderkey", "CAST(datediff(o_orderdate, date '1992-01-01') AS BIGINT)", "CAST(date_diff('day', date '1992-01-01', CAST(o_orderdate AS DATE)) AS BIGINT)")
fn("fn_extract", "orders", "o_orderkey", "CAST(extract(year FROM o_orderdate) * 100 + extract(month FROM o_orderdate) AS BIGINT)")
fn("fn_date_add", "orders", "o_orderkey", "date_format(date_add(CAST(o_orderdate AS DATE), 30), 'yyyy-MM-dd')", "strftime(CAST(o_orderdate AS DATE) + 30, '%Y-%m-%d')")
fn("fn_to_timestamp", "orders", "o_orderkey", "date_format(to_timestamp(concat(date_format(o_orderdate, 'yyyy-MM-dd'), ' 12:00:00')), 'yyyy-MM-dd HH:mm:ss')", "strftime(strptime(strftime(o_orderdate, '%Y-%m-%d') || ' 12:00:00', '%Y-%m-%d %H:%M:%S'), '%Y-%m-%d %H:%M:%S')")
fn("fn_interval_arith", "events", "event_id", "date_format(ts + INTERVAL 90 MINUTES, 'yyyy-MM-dd HH:mm:ss')", "strftime(ts + INTERVAL 90 MINUTES, '%Y-%m-%d %H:%M:%S')")
plain("fn_time_bucket", "SELECT strftime(time_bucket(INTERVAL 1 DAY, ts), '%Y-%m-%d') AS day, count(*) AS n FROM events GROUP BY 1")(lambda t: t.events.groupBy(F.window(F.col("ts").cast("timestamp"), "1 day").alias("w")).agg(n()).select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "n"))

# ---- mathematics -------------------------------------------------------------------------------------
fn("fn_exp_ln", "documents", "doc_id", "round(exp(ln(n_chars + 1) / 3), 6)", "round(exp(ln(n_chars + 1) / 3), 6)::DOUBLE")
fn("fn_sigmoid", "documents", "doc_id", "round(1 / (1 + exp(-(n_chars - 2000) / 1000)), 6)", "round(1 / (1 + exp(-(n_chars - 2000) / 1000)), 6)::DOUBLE")
fn("fn_logit", "documents", "doc_id", "round(ln((n_chars + 1) / 40000 / (1 - (n_chars + 1) / 40000)), 6)", "round(ln((n_chars + 1) / 40000 / (1 - (n_chars + 1) / 40000)), 6)::DOUBLE")
fn("fn_pow_sqrt", "documents", "doc_id", "round(pow(n_chars, 0.25) + sqrt(n_chars), 6)", "round(pow(n_chars, 0.25) + sqrt(n_chars), 6)::DOUBLE")
fn("fn_abs_sign", "documents", "doc_id", "CAST(abs(n_chars - 2000) * sign(n_chars - 2000) AS BIGINT)")
fn("fn_round_floor_ceil", "lineitem", "l_orderkey", "CAST(floor(l_extendedprice) + ceil(l_tax) + round(l_discount) AS BIGINT)")
fn("fn_least_greatest", "documents", "doc_id", "least(greatest(n_chars, 100), 5000)")
fn("fn_clip", "documents", "doc_id", "round(least(greatest(n_chars / 5000, 0.1D), 0.9D), 6)", "round(least(greatest(n_chars / 5000, 0.1), 0.9), 6)::DOUBLE")


@key("fn_width_bucket", f"SELECT doc_id, CAST(floor(prob * 20) + 1 AS BIGINT) AS v FROM {truth(('Q04',), prebuilt=True)} t")
def fn_width_bucket(spark, sf):
    return answers(spark, sf, ("Q04",)).select("doc_id", F.width_bucket("prob", F.lit(0.0), F.lit(1.0), F.lit(20)).alias("v"))


# ---- vectors and arrays ------------------------------------------------------------------------------
_E0 = "(SELECT embedding AS e0 FROM embeddings WHERE vec_id = 0)"


def _pair(name: str, duck: str, spark_expr: str):
    plain(name, f"SELECT vec_id, round({duck}, 5)::DOUBLE AS v FROM (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS a, CAST(e0 AS DOUBLE[]) AS b FROM embeddings, {_E0})")(
        lambda t: t.embeddings.crossJoin(F.broadcast(t.embeddings.filter("vec_id = 0").select(F.col("embedding").cast("array<double>").alias("b")))).withColumn("a", F.col("embedding").cast("array<double>")).selectExpr("vec_id", f"round({spark_expr}, 5) AS v")
    )


_DOT = "aggregate(zip_with({x}, {y}, (p, q) -> p * q), 0D, (s, v) -> s + v)"
_pair("fn_dot", "list_dot_product(a, b)", _DOT.format(x="a", y="b"))
_pair("fn_norm", "sqrt(list_dot_product(a, a))", f"sqrt({_DOT.format(x='a', y='a')})")
_pair("fn_cosine", "list_cosine_similarity(a, b)", f"{_DOT.format(x='a', y='b')} / sqrt({_DOT.format(x='a', y='a')} * {_DOT.format(x='b', y='b')})")
_pair("fn_l2", "list_distance(a, b)", "sqrt(aggregate(zip_with(a, b, (p, q) -> (p - q) * (p - q)), 0D, (s, v) -> s + v))")
fn("fn_array_sum", "embeddings", "vec_id", "round(aggregate(embedding, 0D, (a, x) -> a + x), 5)", "round(list_sum(CAST(embedding AS DOUBLE[])), 5)::DOUBLE")
fn("fn_transform", "embeddings", "vec_id", "round(element_at(transform(embedding, x -> cast(x as double) * 2), 3), 6)", "round(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * 2)[3], 6)::DOUBLE")
fn("fn_filter_array", "embeddings", "vec_id", "CAST(size(filter(embedding, x -> x > 0)) AS BIGINT)", "CAST(len(list_filter(embedding, lambda x: x > 0)) AS BIGINT)")
fn("fn_aggregate_array", "embeddings", "vec_id", "round(aggregate(embedding, 0D, (a, x) -> a + cast(x as double) * x), 5)", "round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 5)::DOUBLE")
fn("fn_zip_with", "embeddings", "vec_id", "round(element_at(zip_with(embedding, slice(embedding, 2, 64), (x, y) -> cast(x as double) + y), 1), 6)", "round(CAST(embedding[1] AS DOUBLE) + embedding[2], 6)::DOUBLE")
fn("fn_slice", "embeddings", "vec_id", "round(aggregate(slice(embedding, 2, 3), 0D, (a, x) -> a + x), 6)", "round(list_sum(CAST(embedding[2:4] AS DOUBLE[])), 6)::DOUBLE")
fn("fn_array_max", "embeddings", "vec_id", "CAST(array_max(embedding) AS DOUBLE)", "CAST(list_max(embedding) AS DOUBLE)")
fn("fn_array_distinct", "documents", "doc_id", "CAST(size(array_distinct(split(text, ' '))) AS BIGINT)", "CAST(len(list_distinct(string_split(text, ' '))) AS BIGINT)")
fn("fn_array_sort", "documents", "doc_id", "element_at(array_sort(split(text, ' ')), -1)", "list_sort(string_split(text, ' '))[-1]")
fn("fn_array_overlap", "documents", "doc_id", "arrays_overlap(split(text, ' '), array('the', 'der', 'la'))", "list_has_any(string_split(text, ' '), ['the', 'der', 'la'])")
fn("fn_flatten", "documents", "doc_id", "CAST(size(flatten(transform(split(text, '\\n'), x -> split(x, ' ')))) AS BIGINT)", "CAST(len(flatten(list_transform(string_split(text, chr(10)), lambda x: string_split(x, ' ')))) AS BIGINT)")
fn("fn_sequence", "part", "p_partkey", "CAST(aggregate(sequence(1, p_size), 0, (a, x) -> a + x) AS BIGINT)", "CAST(list_sum(range(1, p_size + 1)) AS BIGINT)")
plain("fn_explode", "SELECT w, count(*) AS n FROM (SELECT unnest(string_split(text, ' ')) AS w FROM documents) GROUP BY 1 ORDER BY n DESC, w LIMIT 20")(lambda t: t.documents.select(F.explode(F.split("text", " ")).alias("w")).groupBy("w").agg(n()).orderBy(F.desc("n"), "w").limit(20))
plain("fn_posexplode", "SELECT doc_id, pos - 1 AS pos, w FROM (SELECT doc_id, unnest(x) AS w, generate_subscripts(x, 1) AS pos FROM (SELECT doc_id, list_slice(string_split(text, ' '), 1, 4) AS x FROM documents))")(lambda t: t.documents.select("doc_id", F.posexplode(F.slice(F.split("text", " "), 1, 4)).alias("pos", "w")).withColumn("pos", F.col("pos").cast("long")))

# ---- json, maps, structs, nulls ------------------------------------------------------------------------
fn("fn_json_get", "events", "event_id", "CAST(get_json_object(props, '$.k') AS BIGINT)", "CAST(json_extract_string(props, '$.k') AS BIGINT)")
fn("fn_from_json", "events", "event_id", "CAST(from_json(props, 'k INT').k * 2 AS BIGINT)", "CAST(CAST(json_extract_string(props, '$.k') AS INT) * 2 AS BIGINT)")
fn("fn_to_json", "events", "event_id", "to_json(named_struct('id', event_id, 'type', event_type))", "CAST(to_json({'id': event_id, 'type': event_type}) AS VARCHAR)")
fn("fn_map_from_arrays", "part", "p_partkey", "CAST(element_at(map_from_arrays(array('a', 'b'), array(p_size, p_size + 1)), 'b') AS BIGINT)", "CAST(map(['a', 'b'], [p_size, p_size + 1])['b'] AS BIGINT)")
fn("fn_map_keys_values", "part", "p_partkey", "concat_ws(',', map_keys(map(p_brand, p_type)))", "array_to_string(map_keys(map([p_brand], [p_type])), ',')")
fn("fn_struct_field", "part", "p_partkey", "named_struct('b', p_brand, 's', p_size).b", "struct_pack(b := p_brand, s := p_size).b")


@key("fn_map_agg_segments", f"SELECT query_id, count(*) FILTER (WHERE purpose = 'cal') AS cal, count(*) FILTER (WHERE purpose = 'cascade') AS cascade FROM {LEDGER} GROUP BY 1")
def fn_map_agg_segments(spark, sf):
    m = spark.sql(f"SELECT query_id, purpose, count(*) AS n FROM {LEDGER} GROUP BY 1, 2").groupBy("query_id").agg(F.map_from_entries(F.collect_list(F.struct("purpose", "n"))).alias("m"))
    return m.select("query_id", F.coalesce(F.col("m")["cal"], F.lit(0)).alias("cal"), F.coalesce(F.col("m")["cascade"], F.lit(0)).alias("cascade"))


plain("fn_coalesce", "SELECT doc_id, coalesce(quality, -1) AS v FROM documents LEFT JOIN labels USING (doc_id)")(lambda t: t.documents.select("doc_id").join(t.labels, "doc_id", "left").select("doc_id", F.coalesce("quality", F.lit(-1)).alias("v")))
fn("fn_nullif", "labels", "doc_id", "coalesce(nullif(quality, 1), 9)")
fn("fn_case", "labels", "doc_id", "CASE WHEN quality = 1 THEN 'good' WHEN toxic = 1 THEN 'toxic' ELSE 'other' END")
fn("fn_if", "labels", "doc_id", "if(quality = toxic, 'same', 'differs')", "CASE WHEN quality = toxic THEN 'same' ELSE 'differs' END")
fn("fn_try_cast", "part", "p_partkey", "coalesce(try_cast(p_brand AS INT), -1)")

# ---- hashes --------------------------------------------------------------------------------------------
plain("fn_md5_uniform", f"SELECT doc_id, round({u('doc_id', chr(39) + ':u' + chr(39))}, 9)::DOUBLE AS v FROM documents")(lambda t: t.documents.select("doc_id", F.round(uniform(F.col("doc_id"), ":u"), 9).alias("v")))
plain("fn_bernoulli_hash", f"SELECT doc_id, {u('doc_id', chr(39) + ':u' + chr(39))} < 0.3 AS v FROM documents")(lambda t: t.documents.select("doc_id", (uniform(F.col("doc_id"), ":u") < 0.3).alias("v")))
plain("fn_normal_hash", f"SELECT doc_id, round({normal('CAST(doc_id AS VARCHAR)', 'g', Duck)}, 6)::DOUBLE AS v FROM documents")(lambda t: t.documents.select("doc_id", F.round(F.expr(normal("CAST(doc_id AS STRING)", "g")), 6).alias("v")))

# ---- corpora -------------------------------------------------------------------------------------------
_NW = "CAST(len(list_filter(regexp_split_to_array({}, '\\s+'), lambda x: x <> '')) AS INT)"
plain("corpus_documents", f"SELECT doc_id, {_NW.format('text')} AS n_tokens, md5(text) AS h FROM documents")(lambda t: normalise(t.documents, "doc_id", "text", "lang", "source").select("doc_id", "n_tokens", F.md5("text").alias("h")))
plain("corpus_pages", f"SELECT page_id AS doc_id, {_NW.format(_STRIP)} AS n_tokens FROM pages")(lambda t: normalise(t.pages.withColumn("html", strip_html(F.col("html"))), "page_id", "html", "url").select("doc_id", "n_tokens"))
plain("corpus_conversations", "SELECT conv_id AS doc_id, md5(string_agg(role || ': ' || text, chr(10) ORDER BY turn)) AS h FROM conversations GROUP BY 1")(
    lambda t: t.conversations.groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("turn", F.concat_ws(": ", "role", "text").alias("s")))).alias("x")).select(F.col("conv_id").alias("doc_id"), F.md5(F.concat_ws("\n", "x.s")).alias("h"))
)
plain("corpus_rows", "SELECT p_partkey AS doc_id, concat_ws(' ', p_name, p_brand, p_type, CAST(p_size AS VARCHAR)) AS text FROM part")(lambda t: t.part.select(F.col("p_partkey").alias("doc_id"), F.concat_ws(" ", "p_name", "p_brand", "p_type", F.col("p_size").cast("string")).alias("text")))
plain("corpus_vectors", "SELECT vec_id AS doc_id, CAST(len(embedding) AS BIGINT) AS dim FROM embeddings")(lambda t: t.embeddings.select(F.col("vec_id").alias("doc_id"), F.size("embedding").cast("long").alias("dim")))
plain("corpus_exact_dedup", "SELECT min(doc_id) AS doc_id, count(*) AS copies FROM documents GROUP BY md5(text)")(lambda t: t.documents.groupBy(F.md5("text").alias("h")).agg(F.min("doc_id").alias("doc_id"), n("copies")).drop("h"))
plain("corpus_truncate", "SELECT doc_id, array_to_string(list_slice(string_split(text, ' '), 1, 50), ' ') AS text FROM documents")(lambda t: t.documents.select("doc_id", F.array_join(F.slice(F.split("text", " "), 1, 50), " ").alias("text")))
plain("corpus_stats", f"SELECT lang, count(*) AS n, round(avg({_NW.format('text')}), 4)::DOUBLE AS mean_tokens FROM documents GROUP BY 1")(lambda t: t.documents.groupBy("lang").agg(n(), F.round(F.avg(words(F.col("text"))), 4).alias("mean_tokens")))
