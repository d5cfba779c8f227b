import numpy as np
import pytest

P = pytest.importorskip("public_tokenizers")
S = pytest.importorskip("sentencepiece")
from semfilter.llm import mixture_lang as M  # noqa: E402
from semfilter.llm import piece_lattice as K  # noqa: E402
from semfilter.llm.queries import QUERIES  # noqa: E402

MODEL = P.path("piece_bpe_32k.model")


def test_held_out_accuracy(spark, sf01):
    got = QUERIES["op10_mixture_lang"](spark, sf01).join(spark.read.parquet(f"{sf01}/documents.parquet").select("doc_id", "lang"), "doc_id").filter("held_out").toPandas()
    assert len(got) > 100 and (got["lang"] == got["lang_pred"]).mean() > 0.98


def test_mixtures_are_found(spark, sf01):
    docs = spark.read.parquet(f"{sf01}/documents.parquet")
    model = M.fit(docs)
    t = {r["lang"]: r["text"][:1500] for r in docs.filter("n_chars > 2000").collect()}
    rows = [(1, t["de"] + " " + t["fr"] + " " + t["fr"]), (2, t["en"]), (3, None), (4, "12 34 !"), (5, ""), (6, "\U0001f600"), (7, "the " * 200_000)]
    df = spark.createDataFrame([(i, x, "q") for i, x in rows], "doc_id long, text string, score string")
    got = {r["doc_id"]: r for r in M.identify(df, model).collect()}
    mixed = got[1]["mixture"]
    assert mixed["de"] + mixed["fr"] > 0.9 and mixed["de"] > 0.2 and got[1]["lang_pred"] == "fr" and 0.5 < got[1]["score"] < 0.8
    assert got[2]["mixture"] == {"en": 1.0}
    assert all((got[i]["lang_pred"], got[i]["score"]) == ("und", 0.0) for i in (3, 4, 5, 6)) and got[7]["lang_pred"] == "en"
    kept = M.known_language(docs.union(docs.limit(1).select("doc_id", M.F.lit(None).cast("string"), "lang", "source", "n_chars")))
    assert kept.columns == docs.columns and kept.count() == docs.count()


def test_texts_in_many_languages_are_kept(spark, sf01):
    docs = spark.read.parquet(f"{sf01}/documents.parquet")
    model = M.fit(docs)
    t = {r["lang"]: " ".join(M.words_of(r["text"])[:300]) for r in docs.filter("n_chars > 4000").collect()}
    assert len(t) == len(model.names) == 4
    rows = [(10**7, " ".join(t.values())), (10**7 + 1, " ".join(x for k, x in t.items() if k != "en"))]
    new = spark.createDataFrame([(i, x, "q", "s", 1) for i, x in rows], docs.select("doc_id", "text", "lang", "source", "n_chars").schema)
    got = {r["doc_id"]: r["mixture"] for r in M.identify(new, model).collect()}
    assert set(got[10**7]) == set(t) and min(got[10**7].values()) > 0.15
    assert set(got[10**7 + 1]) == set(t) - {"en"}
    assert M.known_language(docs.select(new.columns).union(new.withColumn("lang", M.F.lit(None)))).filter(f"doc_id >= {10**7}").count() == 2


def test_set_sizes_equal_a_full_search():
    rng = np.random.default_rng(3)
    sizes = rng.integers(1, 200, 60)
    home = np.concatenate([rng.integers(0, rng.integers(1, 7), n) for n in sizes])
    ratio = rng.random((len(home), 6)).astype(np.float32) ** 12
    ratio[np.arange(len(home)), home] = 1
    shares, count = M.infer(ratio, sizes)
    assert ((shares > 0).sum(axis=1) <= count).all() and set(count) >= {1, 2, 4, 6}
    for i, cut in enumerate(np.cumsum(sizes) - sizes):
        alone, k = M.infer(ratio[cut : cut + sizes[i]], sizes[i : i + 1])
        assert k[0] == count[i] and np.allclose(alone[0], shares[i], atol=1e-4)


def test_labels_and_names_are_no_inputs(spark):
    rows = [(i, f"{'alpha beta gamma' if i % 2 else 'zwei drei vier'} {i}", "xx" if i % 2 else "yy") for i in range(60)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = M.fit(df)
    a = {r["doc_id"]: r["lang_pred"] for r in M.identify(df, model).collect()}
    b = {r["doc_id"]: r["lang_pred"] for r in M.identify(df.withColumn("lang", M.F.lit("zz")), model).collect()}
    assert a == b == {i: l for i, _, l in rows}
    assert {r["lang_pred"] for r in M.identify(df, M.fit(df.limit(0))).collect()} == {"und"}


def test_likelihood_rises():
    rng = np.random.default_rng(0)
    ratio = rng.random((500, 4)).astype(np.float32)
    doc, cuts = np.repeat(np.arange(5), 100), np.arange(0, 500, 100)
    last = -np.inf
    for rounds in (1, 2, 5, 20):
        _, value = M._em(ratio, doc, cuts, np.full((5, 4), 0.25, np.float32), rounds)
        assert value.sum() >= last - 1e-3
        last = value.sum()


def as_unigram() -> S.SentencePieceProcessor:
    """The model's pieces and scores, marked as a unigram model: field 3 of the trainer's settings (field 2) becomes 1."""

    def number(b, i):
        n = s = 0
        while True:
            n |= (b[i] & 127) << s
            s, i = s + 7, i + 1
            if b[i - 1] < 128:
                return n, i

    def fields(b):
        i = 0
        while i < len(b):
            start = i
            k, i = number(b, i)
            body = None
            if k & 7 == 0:
                _, i = number(b, i)
            elif k & 7 == 2:
                n, i = number(b, i)
                body, i = b[i : i + n], i + n
            else:
                i += 4 if k & 7 == 5 else 8
            yield k >> 3, b[start:i], body

    out = b""
    for f, raw, body in fields(open(MODEL, "rb").read()):
        if f == 2:
            body = b"".join(x[:1] + b"\x01" if g == 3 else x for g, x, _ in fields(body))
            size, n = b"", len(body)
            while n > 127:
                size, n = size + bytes([n & 127 | 128]), n >> 7
            raw = raw[:1] + size + bytes([n]) + body
        out += raw
    return S.SentencePieceProcessor(model_proto=out)


def best(word, pieces):
    """Viterbi by hand over one word; ties keep the earlier start."""
    worst = min(s for _, s in pieces.text.values()) - K.UNKNOWN
    top = [(0.0, -1, -1)]
    for e in range(1, len(word) + 1):
        here = None
        for s in range(max(0, e - 16), e):
            hit = pieces.text.get(word[s:e]) or ((-1, worst) if e - s == 1 else None)
            if hit and (here is None or top[s][0] + hit[1] > here[0]):
                here = (top[s][0] + hit[1], s, hit[0])
        top.append(here)
    out, at = [], len(word)
    while at:
        _, s, i = top[at]
        out.append((s, i))
        at = s
    return [x for s, i in reversed(out) for x in ([i] if i >= 0 else pieces.fallback(word[s]))]


TEXTS = ["Hello  world\n a b  ", " x", "", None, "ﬁ ① q", "the theathe withered", "naïve Ünïcode — 漢字 \U0001f600", "a" * 300, "tab\tand\r\nmore, and. More... a.b, (c). d.\ne,", "▁ sign", "the " * 3000]


def test_encoding_is_the_best_path(spark):
    pieces = K.Pieces.load(MODEL)
    df = spark.createDataFrame([(i, t, "z") for i, t in enumerate(TEXTS)], "doc_id long, text string, ids string").repartition(3)
    got = K.decode(K.encode(df, pieces), pieces).collect()
    lib = as_unigram()
    assert len(got) == len(TEXTS)
    assert {(r["doc_id"], r["decoded"]) for r in K.encode(df, pieces, decoded=True).collect()} == {(r["doc_id"], r["decoded"]) for r in got}
    for r in got:
        want = best(K.BLANK + r["text"].replace(" ", K.BLANK), pieces) if r["text"] else []
        assert r["ids"] == want
        assert r["decoded"] == (r["text"] or "").replace("▁", " ")
        if r["text"] and len(r["text"]) < 100 and "  " not in r["text"]:
            score = sum(lib.get_score(i) for i in r["ids"])
            assert score >= max(sum(lib.get_score(i) for i in n) for n in lib.nbest_encode_as_ids(r["text"], 3)) - 1e-3


def test_words_beyond_the_head_meet_their_documents(spark, monkeypatch):
    pieces = K.Pieces.load(MODEL)
    df = spark.createDataFrame([(i, t) for i, t in enumerate(TEXTS)], "doc_id long, text string")
    whole = {r["doc_id"]: r["ids"] for r in K.encode(df, pieces).collect()}
    monkeypatch.setattr(K, "HEAD_WORDS", 2)
    assert {r["doc_id"]: r["ids"] for r in K.encode(df, pieces).collect()} == whole
    assert K.encode(df.limit(0), pieces).count() == 0


def test_words_of_any_length(spark):
    """Words of several windows and chunks, up to 200,000 characters, against the fold by hand."""
    pieces = K.Pieces.load(MODEL)
    rng = np.random.default_rng(5)
    words = ["".join(rng.choice(list("abcdehinorst"), n)) for n in (1, 63, 64, 65, 127, 128, 129, 1000)]
    words += ["a" * 200_000, "".join(rng.choice(list("etaoin漢x"), 20_000))]
    df = spark.createDataFrame([(i, w) for i, w in enumerate(words)] + [(99, None), (98, "")], "k int, word string")
    got = {r["k"]: [(p & 0xFFFFFFFF) - 1 for p in r["path"]] for r in K.lattice(df, pieces, "k").collect()}
    assert got[99] == got[98] == []
    for i, w in enumerate(words):
        want = best(w, pieces)
        assert [x for x in got[i] if x >= 0] == [x for x in want if x not in set(pieces.fallback("漢"))]
    texts = spark.createDataFrame([(1, " ".join([*words[:8], words[-1]])), (1, words[-1]), (None, "x"), (2, "the cat " * 100_000)], "doc_id long, text string")
    out = K.encode(texts, pieces, decoded=True).collect()
    assert len(out) == 4 and all(r["decoded"] == r["text"] for r in out)
    assert next(r["ids"] for r in out if r["text"] == words[-1]) == best(K.BLANK + words[-1], pieces)


def test_groups_stay_near_their_size_however_large_a_batch():
    import pyarrow as pa

    texts = ["x" * 50_000] * 100 + [None, "", "y" * 3_000_000, "z"]
    batch = pa.RecordBatch.from_arrays([pa.array(range(len(texts))), pa.array(texts)], ["doc_id", "text"])
    groups = list(K._grouped(iter([batch, batch.slice(0, 0), batch.slice(100, 2)])))
    assert [r for g in groups for r in g.column("text").to_pylist()] == [*texts, None, ""]
    assert all(g.num_rows == 1 or g.nbytes <= K.GROUP_BYTES + 4096 for g in groups) and len(groups) < 12


def test_head_is_hashed_once_a_task(monkeypatch):
    """Groups of documents look their words up in one table; none of them hashes the whole head again."""
    import pickle
    from types import SimpleNamespace

    import pyarrow as pa

    def again(*_, **__):
        raise AssertionError("the head was hashed for a group")

    pieces = K.Pieces.load(MODEL)
    monkeypatch.setattr(K, "GROUP_BYTES", 64)
    monkeypatch.setattr(K.pc, "index_in", again)
    head = pa.array([K.BLANK + "the", K.BLANK + "cat"])
    batch = pa.RecordBatch.from_arrays([pa.array(range(20)), pa.array(["the cat qzx" + "j" * (i % 3) for i in range(20)])], ["doc_id", "text"])
    rows = [r for b in K._sender(SimpleNamespace(value=head, _value=head), pieces)(iter([batch])) for r in b.to_pylist()]
    packs = [p for p in (pickle.loads(r["pack"]) for r in rows if r["pack"]) if len(p) == 2]
    assert len(packs) > 3 and all({0, 1} < set(p[0].tolist()) and max(p[0]) >= 2 for p in packs)


def test_lattices_of_many_words_are_those_of_each(spark):
    pieces = K.Pieces.load(MODEL)
    rng = np.random.default_rng(7)
    words = [K.BLANK + "".join(rng.choice(list("etaoinsh漢"), rng.integers(1, 30))) for _ in range(300)] + ["a" * 3000]
    table = K.PieceTable(pieces)
    got = table.edges(words).to_pylist()
    assert got == [table.edges([w]).to_pylist()[0] for w in words]
    assert all([(x["e"], x["s"]) for x in g] == sorted({(x["e"], x["s"]) for x in g}) for g in got)
    df = spark.createDataFrame([(i, w.replace(K.BLANK, "")) for i, w in enumerate(words)] + [(999, " ".join(w.replace(K.BLANK, "") for w in words))], "doc_id long, text string")
    assert {r["doc_id"]: r["ids"] for r in K.encode(df, pieces).collect() if r["doc_id"] < 301} == {i: best(K.BLANK + w.replace(K.BLANK, ""), pieces) for i, w in enumerate(words)}


def test_short_words_are_folded_by_place(spark, monkeypatch):
    """Short words outside the head go through a fold without structs, long ones through that over edges; both give the best path."""
    import pickle
    from types import SimpleNamespace

    import pyarrow as pa

    pieces = K.Pieces.load(MODEL)
    rng = np.random.default_rng(11)
    words = ["".join(rng.choice(list("etaoinsh漢é\U0001f600"), rng.integers(1, 40))) for _ in range(400)] + ["e" * 63, "e" * 64, "t" * 300, "漢", "the"]
    want = {i: best(K.BLANK + w, pieces) for i, w in enumerate(words)}
    df = spark.createDataFrame([*enumerate(words), (9999, " ".join(words))], "doc_id long, text string").coalesce(1)
    monkeypatch.setattr(K, "HEAD_WORDS", 2)
    monkeypatch.setattr(K, "SENT_CHARS", 100)
    for chars in (64, 12):
        monkeypatch.setattr(K, "SHORT_CHARS", chars)
        got = {r["doc_id"]: r["ids"] for r in K.encode(df, pieces).collect()}
        assert got.pop(9999) == [i for d in want.values() for i in d] and got == want
    monkeypatch.setattr(K, "SHORT_CHARS", 64)
    batch = pa.RecordBatch.from_arrays([pa.array([0]), pa.array([" ".join(words)])], ["doc_id", "text"])
    head = pa.array([], pa.string())
    rows = [r for b in K._sender(SimpleNamespace(value=head, _value=head), pieces)(iter([batch])) for r in b.to_pylist()]
    by_edge = [len(w) for r in rows if r["words"] for w in r["words"]]
    assert len(by_edge) == 2 and sum(len(r["places"]) for r in rows if r["places"]) == len({*words}) - 2
    assert all(sum(map(len, r["places"])) <= 100 or len(r["places"]) == 1 for r in rows if r["places"])
    assert all(len(pickle.loads(r["pack"])) == 4 for r in rows if r["places"])


def test_the_longest_of_equal_edges_leads_back():
    """Among equal scores the edge that starts first wins, also where the fold gives scores only."""
    pieces = K.Pieces({"a": (5, -1.0), "aa": (6, -2.0), "aaa": (7, -3.0), "b": (8, -1.5)}, None, 0, frozenset())
    words = ["aaaa", "aab", "xb", "b", "aaaaaaa"]
    _, sent = K.PieceTable(pieces).places(words)
    top = []
    for w in words:
        score = [0.0]
        for e in range(1, len(w) + 1):
            score.append(max(score[s] + (pieces.text[w[s:e]][1] if w[s:e] in pieces.text else -13.0) for s in range(e) if w[s:e] in pieces.text or e - s == 1))
        top += score
    got = [[(c & 0xFFFFFFFF) - 1 for c in p] for p in K._back(np.array(top), *sent).to_pylist()]
    assert got == [[5, 7], [6, 8], [-1, 8], [8], [5, 7, 7]] == [[i or -1 for i in best(w, pieces)] for w in words]


def test_words_are_counted_in_memory_that_is_given_back(monkeypatch):
    """The counter leaves Arrow's grouping alone: it runs in a pool of memory that a worker keeps for as long as it lives."""
    import pyarrow as pa

    def grouping(*_):
        raise AssertionError("Arrow groups words")

    monkeypatch.setattr(pa.TableGroupBy, "aggregate", grouping)
    monkeypatch.setattr(K, "GROUP_BYTES", 2_000)
    monkeypatch.setattr(K, "COUNTED_WORDS", 100, raising=False)
    texts = [" ".join([*(f"w{k}" for k in range(t, t + 300)), f"once{t}", "long" * 50, "é"]) for t in range(0, 600, 100)]
    batches = [pa.RecordBatch.from_arrays([pa.array([*texts, None])], ["text"])] * 2
    got = [r for b in K._counter(False, [])(iter(batches)) for r in b.to_pylist()]
    want = {}
    for w in (K.BLANK + w for t in texts * 2 for w in t.split() if len(w) < 64):
        want[w] = want.get(w, 0) + 1
    assert {r["word"]: r["n"] for r in got} == want and [r["word"] for r in got] == sorted(want)
    monkeypatch.setattr(K, "HELD_WORDS", 500)  # given on in parts: words seen once in a part are not worth remembering
    got = [r for b in K._counter(False, [])(iter(batches)) for r in b.to_pylist()]
    assert {r["word"] for r in got} <= {*want} and all(1 < r["n"] <= want[r["word"]] for r in got)
