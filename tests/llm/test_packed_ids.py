import zlib

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

P = pytest.importorskip("public_tokenizers")
from semfilter.llm import packed_ids as K  # noqa: E402

PATH = P.path("word_bpe_49k.json")


@settings(max_examples=60, deadline=None)
@given(st.lists(st.one_of(st.integers(0, 50_000), st.integers(0, 3), st.integers(0, 2**64 - 1)), max_size=4000))
def test_pack_round_trip(ids):
    a = np.array(ids, np.uint64)
    words, anchors, escapes = K.pack(a)
    assert (K.unpack(words, len(a), escapes) == a).all()
    for k in range(len(anchors)):
        assert (K.unpack_stretch(words, anchors, len(a), k, escapes) == a[k * K.STRETCH : (k + 1) * K.STRETCH]).all()


def test_pack_is_word_aligned_and_dense():
    assert len(K.pack(np.ones(60, np.uint64))[0]) == 1
    assert len(K.pack(np.full(4, 2**15 - 1, np.uint64))[0]) == 1
    assert len(K.pack(np.array([2**60], np.uint64))[0]) == 2


@settings(max_examples=80, deadline=None)
@given(st.lists(st.text(max_size=40), max_size=5))
def test_words_give_the_ids_of_the_whole(texts):
    enc = K.WordEncoder.of_worker(PATH)
    assert enc.by_words
    ids, sizes = enc.encode(pa.array(texts, pa.string()))
    at = 0
    for t, n in zip(texts, sizes, strict=True):
        assert ids[at : at + n].tolist() == enc.model.encode(t, add_special_tokens=False).ids
        at += n


def test_caches_turn_over(monkeypatch):
    monkeypatch.setattr(K, "CACHE_WORDS", 3)
    enc = K.WordEncoder(PATH)
    for t in ("a b c d", "b e f g h", "a b", "x y z w v", "a d"):
        assert enc.encode(pa.array([t]))[0].tolist() == enc.model.encode(t, add_special_tokens=False).ids


def test_tokenizers_that_keep_blanks_get_whole_texts():
    enc = K.WordEncoder(P.path("byte_bpe_50k.json"))
    assert not enc.by_words
    t = "two  blanks\nand a line"
    assert enc.encode(pa.array([t, None]))[0].tolist() == enc.model.encode(t, add_special_tokens=False).ids


def test_files(spark, tmp_path):
    rows = [(5, "b c"), (2, None), (9, ""), (7, "word " * 70_000), (2, "again"), (None, "no id"), (3, "x")]
    docs = spark.createDataFrame([(d, t, 1) for d, t in rows], "doc_id long, text string, start int").repartition(3)
    out = K.read_ids(spark, K.write_ids(docs, str(tmp_path / "ids"), PATH)).orderBy("start").collect()
    enc = K.WordEncoder.of_worker(PATH)
    want = sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, r[1] is not None, r[1] or ""))
    at = 0
    for got, (d, t) in zip(out, want, strict=True):
        ids = np.array([*enc.model.encode(t or "", add_special_tokens=False).ids, 2], "<u4")
        assert (got["doc_id"], got["start"], got["n_tokens"], got["ids_crc32"]) == (d, at, len(ids), zlib.crc32(ids.tobytes()))
        assert bytes(got["ids"]) == ids.tobytes()
        at += len(ids)


def test_empty_table(spark):
    assert K.packed_corpus(spark.createDataFrame([], "doc_id long, text string"), PATH).count() == 0
