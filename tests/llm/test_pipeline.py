import pytest

C = pytest.importorskip("corpus_pipeline")
from pyspark.sql import functions as F  # noqa: E402

from semfilter.llm import interleave, line_spread, odd_sketch, pivotal_mix, span_dedup  # noqa: E402
from semfilter.llm.common import components, save  # noqa: E402
from semfilter.llm.odd_sketch import near_duplicates  # noqa: E402


def test_stages(spark, sf01):
    docs = spark.read.parquet(f"{sf01}/documents.parquet")
    before = docs
    for name, f in C.STAGES:
        after = save(f(spark, before, sf01), name)
        if name != C.STAGES[-1][0]:
            assert after.columns == docs.columns
        if name == "near_dedup":
            left = near_duplicates(after).toPandas()
            assert left["kept"].all()
        before = after
    assert before.filter("NOT round_trip").count() == 0 and before.count() > 500


def test_stages_on_odd_rows(spark, sf):
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    rows = [(1, None, None, None, None), (2, "", "en", "s", 0), (None, "the of and", None, None, 10), (4, "the and of was " * 50_000, "en", "t", 800_000), (4, "the and of", "en", "t", 10), (4, "the and of", "en", "t", 10)]
    train = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "lang", "source", "n_chars")
    for docs in (spark.createDataFrame([], schema), spark.createDataFrame(rows, schema), train.union(spark.createDataFrame(rows, schema))):
        before = docs
        for name, f in C.STAGES:
            before = save(f(spark, before, sf), name)
        before.count()


def test_clashing_names(spark):
    """Extra columns with names that the operators use inside pass through as they came."""
    extra = ["_h", "h", "_n_lines", "_n_removed", "_key", "_turn", "turn", "_n", "n", "size", "_size", "_id", "_th", "_gone", "_copies", "_source", "id", "copies", "th", "pos", "line", "key", "node"]
    rows = [(i, f"a line of all\nown words of document number {i} stand here", None if i == 4 else f"s{i % 12}", *range(len(extra))) for i in range(40)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, " + ", ".join(f"{c} int" for c in extra))
    for out in (line_spread.spread_lines(docs), pivotal_mix.mixed_documents(docs), odd_sketch.one_of_each(docs)):
        got = out.select(*docs.columns).drop("text").distinct().collect()
        assert got and all(tuple(r)[2:] == tuple(range(len(extra))) for r in got)
    names = line_spread.counts_of(docs)
    assert line_spread.spread_lines(docs).columns == [*docs.columns, *names]
    assert line_spread.spread_lines(docs).filter(F.col(names[1]) > 0).count() > 0


def test_very_long_texts(spark):
    """A text of a megabyte beside short ones, results checked."""
    long = "\n".join(f"row {i} of a very long text with words" for i in range(30_000))
    rows = [(1, long, "a"), (2, "row 7 of a very long text with words\nx y z", "b"), *((10 + i, "row 7 of a very long text with words\nown " + str(i), f"s{i}") for i in range(10))]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    cut = {r["doc_id"]: r for r in line_spread.spread_lines(docs).collect()}
    assert cut[1]["text"] == long and cut[2]["text"] == "x y z" and cut[12]["text"] == "own 2"
    sizes = {r["id"]: r["size"] for r in pivotal_mix.mix(docs).collect()}
    assert sizes[1] == len(long.split()) and sizes[2] == 12
    dealt = interleave.interleave(docs).collect()
    assert {r["doc_id"]: r["size"] for r in dealt}[1] == len(long) + 1 and sorted(r["position"] for r in dealt) == list(range(len(rows)))
    spans = {r["doc_id"]: r["n_removed"] for r in span_dedup.without_repeats(docs.union(spark.createDataFrame([(99, long, "q")], docs.schema))).collect()}
    assert spans[1] == 0 and spans[99] > 25_000


def test_components(spark):
    e = spark.createDataFrame([(i, i + 1) for i in range(50)] + [(100, 90), (90, 95), (7, 7), (300, 301), (301, 300)], "a long, b long")
    got = {r["node"]: r["component"] for r in components(e).collect()}
    assert got == {**dict.fromkeys(range(51), 0), 100: 90, 90: 90, 95: 90, 300: 300, 301: 300}
    assert components(e.limit(0)).count() == 0
