"""Substring dedup by sliding spans of consecutive sentences."""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import save, session_defaults

#: A span is the shortest run of SENTENCES sentences or more that has SPAN_WORDS words or more; pieces that
#: long sentences are cut to count as sentences in a run of more than LONG words.
SENTENCES, SPAN_WORDS = 3, 8
#: Sentences of more than LONG words are cut after every word whose hash is the least of some WINDOW words
#: in a row, shorter ones of more than WINDOW in two, so no piece has more than WINDOW. Any 46 words that two
#: texts share hold a whole span cut alike in both: 2 * WINDOW - 1 words up to the first common cut,
#: SENTENCES * WINDOW of the span, and LONG of a last sentence that is short in one text and long in the other.
LONG, WINDOW = 12, 7
#: Shares of all spans at or above which one counts as heavy; at most this many can be so.
HEAVY = 1000
#: Ids of texts that lose something, up to which they are broadcast (8 bytes each).
BROADCAST_IDS = 500_000

_SENTENCE = re.compile(r"[^.!?\n]*(?:[.!?]+[\"')\]»”]*(?=\s|$)\s*|[.!?]+|\n\s*|$)")
_WORD = re.compile(r"\S+")


def sentences(text: str) -> tuple[list[int], list[int], list[bytes]]:
    """Starts of a text's pieces, their words' counts, and hashes of their words in lower case."""
    return cut(text)[:3]


def cut(text: str) -> tuple[list[int], list[int], list[bytes], list[bool]]:
    """As ``sentences``, and whether a sentence ends with each piece.

    A sentence ends after ``.``, ``!`` or ``?`` before white space, and at newlines; one of more than
    ``WINDOW`` words is cut where its own words say so, so the same passage is cut alike in any surroundings. Joined, the
    sentences are the text; those without words belong to the sentence before.
    """
    starts, counts, hashes, closes = [], [], [], []
    at = 0
    pieces = []
    end = len(text)
    while at < end:
        m = _SENTENCE.match(text, at)
        nxt = max(m.end(), at + 1)
        pieces.append((at, nxt))
        at = nxt
    found = [(lo, hi, words) for lo, hi in _joined(text, pieces) if (words := text[lo:hi].lower().split())]
    last = lasts([words for _, _, words in found if len(words) > WINDOW])
    for lo, hi, words in found:
        if len(words) <= WINDOW:
            starts.append(lo)
            counts.append(len(words))
            hashes.append(xxhash.xxh3_128_digest(" ".join(words)))
            closes.append(True)
            continue
        stops = [m.end() for m in _WORD.finditer(text, lo, hi)]
        begin, k = lo, 0
        for e in next(last):
            starts.append(begin)
            counts.append(e - k)
            hashes.append(xxhash.xxh3_128_digest(" ".join(words[k:e])))
            closes.append(e == len(words))
            begin, k = stops[e - 1], e
    if starts:
        starts[0] = 0
    return starts, counts, hashes, closes


def lasts(runs: list[list[str]]) -> Iterator[list[int]]:
    """For each run of more than ``WINDOW`` words: how many words it has up to each cut, and in all.

    A run of more than ``LONG`` words is cut after every word whose hash is the least of some ``WINDOW`` words
    of it, ties included: which these are depends on the ``WINDOW`` - 1 words on either side only. A shorter
    one is cut once, after the first word of least hash that leaves ``WINDOW`` or fewer on both sides.
    """
    if not runs:
        return
    sizes = np.array([len(words) for words in runs])
    ends = np.cumsum(sizes)
    h = np.fromiter((xxhash.xxh3_64_intdigest(w) for words in runs for w in words), np.uint64, int(ends[-1]))
    n = len(h) - WINDOW + 1
    least = h[:n].copy()
    for k in range(1, WINDOW):
        np.minimum(least, h[k : n + k], out=least)
    inside = np.repeat(sizes > LONG, sizes)  # windows that end within their long run
    inside[(ends[:, None] - np.arange(1, WINDOW)).ravel()] = False
    after = np.zeros(len(h), bool)
    for k in range(WINDOW):
        after[k : n + k] |= inside[:n] & (least == h[k : n + k])
    after[ends - 1] = True
    for size, end in zip(sizes.tolist(), ends.tolist(), strict=True):
        begin = end - size
        if size > LONG:
            yield (np.flatnonzero(after[begin:end]) + 1).tolist()
        else:
            yield [size - WINDOW + int(h[end - WINDOW - 1 : begin + WINDOW].argmin()), size]


def _joined(text: str, pieces: list[tuple[int, int]]) -> Iterator[tuple[int, int]]:
    """Pieces that end inside a word (3.14, a.b) joined with what follows."""
    lo = None
    for a, b in pieces:
        lo = a if lo is None else lo
        if b < len(text) and not text[b - 1].isspace() and not text[b].isspace():
            continue
        yield lo, b
        lo = None
    if lo is not None:
        yield lo, len(text)


def ends_of(counts: list[int], closes: list[bool]) -> np.ndarray:
    """Where the span of each piece ends, beyond the text if there are too few words or pieces."""
    n = len(counts)
    total = np.concatenate([[0], np.cumsum(counts, dtype=np.int64)])
    done = np.concatenate([[0], np.cumsum(closes, dtype=np.int64)])
    part = np.concatenate([[False], ~np.array(closes[:-1], bool)])[:n]  # begins within a sentence
    need = done[:-1] + SENTENCES + part
    whole = np.maximum(np.searchsorted(total, total[:-1] + SPAN_WORDS), np.searchsorted(done, need))
    parts = np.maximum(np.searchsorted(total, total[:-1] + LONG + 1), np.arange(n) + SENTENCES)
    return np.minimum(whole, parts)


def spans(counts: list[int], hashes: list[bytes], closes: list[bool]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First piece and two 64-bit hashes of every span of a text."""
    ends = ends_of(counts, closes)
    first = np.flatnonzero(ends <= len(counts))
    if not len(first):
        return np.empty(0, np.int64), np.empty(0, np.uint64), np.empty(0, np.uint64)
    raw = np.frombuffer(b"".join(hashes), "<u8").reshape(-1, 2)
    size = ends[first] - first
    a, b = np.full(len(first), 7, np.uint64), np.full(len(first), 11, np.uint64)
    for k in range(int(size.max())):
        on = np.flatnonzero(size > k) if k >= SENTENCES else slice(None)
        at = first[on] + k
        x, y = (a[on] ^ raw[at, 0]) * np.uint64(0x9E3779B97F4A7C15), (b[on] ^ raw[at, 1]) * np.uint64(0xC2B2AE3D27D4EB4F)
        a[on], b[on] = x ^ (x >> np.uint64(29)), y ^ (y >> np.uint64(31))
    return first, a, b


def _emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A row for each span; one without hash for each repeat within its own text."""
    for batch in batches:
        docs, at, a, b, again = [], [], [], [], []
        for k, text in enumerate(batch.column(1).to_pylist()):
            if text:
                first, x, y = spans(*cut(text)[1:])
                if len(first):
                    _, once = np.unique(x, return_index=True)
                    later = np.ones(len(first), bool)
                    later[once] = False
                    docs.append(np.full(len(first), k))
                    at.append(first)
                    a.append(x)
                    b.append(y)
                    again.append(later)
        if docs:
            none = np.concatenate(again)
            h = pa.array(np.concatenate(a).astype(np.int64), mask=none)
            g = pa.array((np.concatenate(b) >> np.uint64(32)).astype(np.uint32).astype(np.int32), mask=none)
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(np.concatenate(docs))), pa.array(np.concatenate(at).astype(np.int32)), h, g], ["doc_id", "at", "h", "g"])


def cleaned(text: str, gone: list[int]) -> tuple[str, int]:
    """A text without the sentences of the spans that begin at ``gone``, and how many those are."""
    starts, counts, _, closes = cut(text)
    out, until = np.zeros(len(starts), bool), ends_of(counts, closes)
    for f in gone:
        out[f : until[f]] = True
    ends = [*starts[1:], len(text)]
    return "".join(text[s:e] for s, e, o in zip(starts, ends, out, strict=True) if not o), int(out.sum())


def _rewrite(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        texts, removed = [], []
        for text, gone in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
            got = cleaned(text, gone) if text and gone else (text, 0)
            texts.append(got[0])
            removed.append(got[1])
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string()), pa.array(removed, pa.int64())], ["doc_id", "text", "n_removed"])


def without_repeats(docs: DataFrame) -> DataFrame:
    """Every document's text without the sentences that a span repeats from elsewhere.

    Every sentence begins a span; spans are hashed and grouped over the whole corpus, where the
    document with the smallest id that has one keeps it. In all others its sentences go, as do those of
    later repeats within one document. Heavy spans (a thousandth of all or more, so a thousand at
    most) reach their documents by broadcast, the others by shuffle. Texts that lose something meet
    their spans by shuffle; the ids of those texts are broadcast, while few, to let the others pass.

    Reads ``doc_id, text`` and ignores other columns. Null stays null, empty stays empty; texts with
    fewer than three sentences or eight words have no span. ``doc_id`` names a document: rows that repeat one
    keep or lose the same places. A null id takes no part. Returns ``doc_id, text, n_removed`` for every row.
    """
    session_defaults(docs.sparkSession)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    found = save(texts.filter("doc_id IS NOT NULL").mapInArrow(_emit, "doc_id long, at int, h long, g int"), "spans")
    met = found.filter("h IS NOT NULL")
    total = met.count()
    owners = met.groupBy("h", "g").agg(F.count("*").alias("n"), F.min("doc_id").alias("owner")).filter("n > 1")
    owners = save(owners, "owners")
    heavy = F.broadcast(owners.filter(F.col("n") * HEAVY >= total))
    light = owners.filter(F.col("n") * HEAVY < total)
    rest = met.join(heavy, ["h", "g"], "left_anti").join(light, ["h", "g"])
    hits = met.join(heavy, ["h", "g"]).unionByName(rest).filter("doc_id <> owner").select("doc_id", "at").union(found.filter("h IS NULL").select("doc_id", "at"))
    gone = save(hits.groupBy("doc_id").agg(F.collect_set("at").alias("gone")), "gone")
    few = gone.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS
    schema = "doc_id long, text string, n_removed long"
    if not few:
        return texts.join(gone, "doc_id", "left").select("doc_id", "text", "gone").mapInArrow(_rewrite, schema)
    ids = F.broadcast(gone.select("doc_id"))
    whole = texts.join(ids, "doc_id", "left_anti").select("doc_id", "text", F.lit(0).cast("long").alias("n_removed"))
    cut = texts.join(ids, "doc_id", "left_semi").join(gone.hint("shuffle_hash"), "doc_id").select("doc_id", "text", "gone")
    return whole.union(cut.mapInArrow(_rewrite, schema))
