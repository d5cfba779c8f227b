"""Token ids in Simple-8b words: coder, block files and their reader."""

from __future__ import annotations

import os
import re
import zlib
from array import array
from collections.abc import Iterator
from itertools import accumulate, chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import scratch_dir, session_defaults

# Fixed values of the format: payload bits of one id for selectors 2 to 15 (60 // bits ids a word).
# Selector 0 announces that the next word is one id of more than 60 bits; selector 1 is unused.
BITS = (1, 2, 3, 4, 5, 6, 7, 8, 10, 12, 15, 20, 30, 60)
COUNTS = tuple(60 // b for b in BITS)
_SELECTOR = np.zeros(61, np.int64)
_SELECTOR[list(COUNTS)] = np.arange(2, 16)
#: Ids in one stretch; each stretch starts a new word, whose index the block keeps.
STRETCH = 1024
#: A block is closed once it has so many ids; a document never crosses blocks.
BLOCK_IDS = 65_536
#: Words remembered with their ids by one worker, in each of two generations.
CACHE_WORDS = 400_000

#: Bytes of text whose words are looked up together.
GROUP_BYTES = 12 << 20

_U = np.uint64
_LATIN = re.compile("[a-zß-öø-ÿ]+")


def pack(ids: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Codes unsigned ids. Returns the words, each stretch's first word, and the escaped words' indices."""
    ids = np.ascontiguousarray(ids, dtype=_U)
    n = len(ids)
    if not n:
        return np.empty(0, _U), np.empty(0, np.uint32), np.empty(0, np.uint32)
    top = int(ids.max())
    if top < 1 << 16:
        width = _widths16()[ids.astype(np.int64)]
    else:
        width = np.searchsorted(_U(1) << np.arange(64, dtype=_U), ids, side="right").astype(np.uint8)
    at = np.arange(n, dtype=np.int32)
    left = np.minimum(np.minimum(STRETCH - at % STRETCH, n - at), 60).astype(np.uint8)
    step = np.ones(n, np.uint8)
    widest = {1: width}  # over so many ids from each place, by doubling
    for s in range(14, 1, -1):  # from few wide ids to many narrow ones
        bits, count = BITS[s - 2], COUNTS[s - 2]
        half = 1 << (count.bit_length() - 1)
        if half not in widest:
            before = widest[half // 2]
            widest[half] = np.maximum(before, _ahead(before, half // 2))
        ok = (np.maximum(widest[half], _ahead(widest[half], count - half)) <= bits) & (left >= count)
        if not ok.any():
            break
        np.maximum(step, ok.view(np.uint8) * np.uint8(count), out=step)
    hops, i, chain = step.tolist(), 0, []
    while i < n:
        chain.append(i)
        i += hops[i]
    pos = np.array(chain, np.int64)
    sel = _SELECTOR[step[pos]]
    if top >> 60:
        sel[width[pos] > 60] = 0
    slots = np.arange(len(pos), dtype=np.int64)
    escapes = np.empty(0, np.int64)
    if top >> 60:
        raw = sel == 0
        slots = slots + np.concatenate([[0], np.cumsum(raw)[:-1]])
        escapes = slots[raw] + 1
    words = np.zeros(len(pos) + len(escapes), _U)
    for s in np.unique(sel):
        rows, out = pos[sel == s], slots[sel == s]
        if s == 0:
            words[out + 1] = ids[rows]
            continue
        bits, count = BITS[s - 2], COUNTS[s - 2]
        shifts = np.arange(count, dtype=_U) * _U(bits)
        packed = np.bitwise_or.reduce(ids[rows[:, None] + np.arange(count)] << shifts, axis=1)
        words[out] = packed | (_U(s) << _U(60))
    anchors = slots[np.searchsorted(pos, np.arange(0, n, STRETCH))]
    return words, anchors.astype(np.uint32), escapes.astype(np.uint32)


def _ahead(a: np.ndarray, k: int) -> np.ndarray:
    """What stands k places further on; beyond the end nothing fits."""
    return np.concatenate([a[k:], np.full(min(k, len(a)), 255, np.uint8)]) if k else a


def unpack(words: np.ndarray, n: int, escapes: np.ndarray | None = None) -> np.ndarray:
    """The ids of coded words; all words of one selector are opened at once."""
    words = np.asarray(words, _U)
    out = np.empty(n, _U)
    sel = (words >> _U(60)).astype(np.int64)
    counts = np.array((1, 0, *COUNTS), np.int64)[sel]
    live = np.ones(len(words), bool)
    if escapes is not None and len(escapes):
        counts[escapes] = 0
        live[escapes] = False
    start = np.cumsum(counts) - counts
    for s in np.unique(sel[live]):
        rows = np.flatnonzero(live & (sel == s))
        if s == 0:
            out[start[rows]] = words[rows + 1]
            continue
        bits, count = BITS[s - 2], COUNTS[s - 2]
        shifts = np.arange(count, dtype=_U) * _U(bits)
        out[start[rows][:, None] + np.arange(count)] = (words[rows][:, None] >> shifts) & _U((1 << bits) - 1)
    return out


def unpack_stretch(words: np.ndarray, anchors: np.ndarray, n: int, k: int, escapes: np.ndarray | None = None) -> np.ndarray:
    """Only stretch ``k`` of a block, found by its anchor."""
    lo = int(anchors[k])
    hi = int(anchors[k + 1]) if k + 1 < len(anchors) else len(words)
    inside = None if escapes is None else escapes[(escapes >= lo) & (escapes < hi)] - lo
    return unpack(words[lo:hi], min(STRETCH, n - k * STRETCH), inside)


def _widths16(table: list = []) -> np.ndarray:  # noqa: B006  made once a process
    if not table:
        table.append(np.maximum(1, np.ceil(np.log2(np.arange(1 << 16) + 1.0))).astype(np.uint8))
    return table[0]


class _Known:
    """Words with their ids, in one flat array."""

    def __init__(self) -> None:
        self.place: dict[str, int] = {}
        self.ids, self.ends = array("I"), array("q", [0])

    def add(self, words: list[str], ids: list[list[int]]) -> None:
        self.place.update(zip(words, range(len(self.place), len(self.place) + len(words)), strict=True))
        self.ids.extend(chain.from_iterable(ids))
        self.ends.extend(list(accumulate(map(len, ids), initial=self.ends[-1]))[1:])

    def of(self, word: str):
        k = self.place[word]
        return self.ids[self.ends[k] : self.ends[k + 1]]


class WordEncoder:
    """Ids of whole texts with the tokenizers library, each distinct word of a batch looked up once.

    A tokenizer whose pre-tokenizer drops white space gives the ids of a text as those of its words
    in order; only ASCII blanks are cut here, so any other white space stays the library's matter. A
    tokenizer that treats blanks otherwise is given whole texts. Words are kept in two generations of
    ``CACHE_WORDS``, so memory is bounded and frequent words stay.
    """

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # Spark's tasks are the parallelism
        from tokenizers import Tokenizer

        self.model = Tokenizer.from_file(path)
        self.model.no_padding()
        self.model.no_truncation()
        self.known, self.older = _Known(), _Known()
        probe = ["Ab", "cd.", "e"]
        apart = [i for w in probe for i in self._ids(w)]
        self.by_words = all(self._ids(s.join(probe)) == apart for s in (" ", "\n", "  ", "\t", "\r\n", "\v", "\f"))
        self.caseless = self._ids("AbC ÉD") == self._ids("abc Éd")
        self.stops = [c for c in ",." if self._ids(f"Ab{c} é{c}") == [i for w in ("Ab", c, "é", c) for i in self._ids(w)]]
        self.plain = self._plainer()
        self.special = [t.content.lower() for t in self.model.get_added_tokens_decoder().values()]

    def _plainer(self):
        """The model without normaliser and pattern, for small Latin letters, which neither changes nor cuts; or nothing."""
        from tokenizers import Tokenizer, pre_tokenizers

        model = Tokenizer.from_str(self.model.to_str())
        model.normalizer = None
        model.pre_tokenizer = pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)
        letters = [chr(c) for c in range(256) if _LATIN.fullmatch(chr(c))]
        probes = [*letters, "".join(letters), *(a + b for a in "aeß" for b in letters), "thereinéüber", "straße"]
        return model if all(model.encode(w, add_special_tokens=False).ids == self._ids(w) for w in probes) else None

    def _ids(self, text: str) -> list[int]:
        return self.model.encode(text, add_special_tokens=False).ids

    @classmethod
    def of_worker(cls, path: str) -> WordEncoder:
        """The encoder that this worker process keeps from task to task."""
        import tokenizers

        kept = tokenizers.__dict__.setdefault("_word_encoders", {})
        if path not in kept:
            kept[path] = cls(path)
        return kept[path]

    def _places(self, words: list[str]) -> np.ndarray:
        if len(self.known.place) > CACHE_WORDS:
            self.known, self.older = _Known(), self.known
        known, older = self.known, self.older
        get = known.place.get
        out = [get(w) for w in words]
        gaps = [k for k, p in enumerate(out) if p is None]
        if gaps:
            lacking = [words[k] for k in gaps]
            old = [w for w in lacking if w in older.place]
            known.add(old, [older.of(w) for w in old])
            new = [w for w in lacking if w not in older.place]
            plain = [w for w in new if _LATIN.fullmatch(w)] if self.plain else []
            rest = [w for w in new if not _LATIN.fullmatch(w)] if plain else new
            for model, some in ((self.plain, plain), (self.model, rest)):
                for k in range(0, len(some), 2048):
                    part = some[k : k + 2048]
                    known.add(part, [e.ids for e in model.encode_batch_fast(part, add_special_tokens=False)])
            for k in gaps:
                out[k] = get(words[k])
        return np.array(out, np.int64)

    def _words(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Places of all words one after another, and how many each text has.

        Where the tokenizer looks away from case, ASCII capitals are lowered first (unless that could
        make one of its special tokens), and letters with one stop behind them are taken as two words.
        """
        if self.caseless:
            low = pc.ascii_lower(texts)
            if not any(pc.any(pc.match_substring(low, s)).as_py() for s in self.special):
                texts = low
        lists = pc.ascii_split_whitespace(texts)
        coded = lists.flatten().dictionary_encode()
        kinds, index = coded.dictionary, coded.indices.to_numpy()
        bounds = lists.offsets.to_numpy() - lists.offsets[0].as_py()
        if not self.stops or not len(kinds):
            return self._places(kinds.to_pylist())[index], np.diff(bounds)
        split = pc.match_substring_regex(kinds, rf"^\pL+[{''.join(self.stops)}]$")
        stem = pc.if_else(split, pc.utf8_slice_codeunits(kinds, 0, -1), kinds).dictionary_encode()
        place = self._places([*self.stops, *stem.dictionary.to_pylist()])
        first = place[len(self.stops) :][stem.indices.to_numpy()]
        last = pc.fill_null(pc.index_in(pc.utf8_slice_codeunits(kinds, -1), pa.array(self.stops)), 0).to_numpy()
        two = split.to_numpy(zero_copy_only=False)
        many = 1 + two[index]
        total = np.concatenate([[0], np.cumsum(many)])
        out = np.repeat(first[index], many)
        ends = total[1:][two[index]] - 1
        out[ends] = place[last[index[two[index]]]]
        return out, np.diff(total[bounds])

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts one after another, and how many each has; null as empty."""
        texts = pc.fill_null(texts, "")
        if not self.by_words:
            got = [self._ids(t) for t in texts.to_pylist()]
            return np.array([i for g in got for i in g], np.uint32), np.array([len(g) for g in got], np.int64)
        word, counts = self._words(texts)
        ends, flat = np.frombuffer(self.known.ends, np.int64), np.frombuffer(self.known.ids, np.uint32)
        size = ends[word + 1] - ends[word]
        total = np.concatenate([[0], np.cumsum(size)])
        ids = flat[np.repeat(ends[word] - total[:-1], size) + np.arange(total[-1])]
        return ids, np.diff(total[np.concatenate([[0], np.cumsum(counts)])])


FILE_SCHEMA = "shard int, block int, doc_lo long, doc_hi long, doc_ids binary, lengths binary, start_in_shard long, n_ids long, words binary, anchors binary, escapes binary"


def _grouped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """Batches put together up to ``GROUP_BYTES``, so that a word is looked up less often."""
    held: list[pa.RecordBatch] = []
    for b in batches:
        if b.num_rows:
            held.append(b)
        if sum(x.nbytes for x in held) >= GROUP_BYTES:
            yield pa.Table.from_batches(held)
            held = []
    if held:
        yield pa.Table.from_batches(held)


def _coder(path: str, end_id: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = WordEncoder.of_worker(path)
        ids, docs, lens, n, start, block, shard = [], [], [], 0, 0, 0, 0

        def close() -> pa.RecordBatch:
            nonlocal ids, docs, lens, n, start, block
            words, anchors, escapes = pack(np.concatenate(ids))
            known = [d for d in docs if d is not None]
            row = {
                "shard": shard, "block": block, "doc_lo": min(known, default=None), "doc_hi": max(known, default=None),
                "doc_ids": np.array([-1 if d is None else d for d in docs], "<i8").tobytes(), "lengths": np.array(lens, "<i8").tobytes(),
                "start_in_shard": start, "n_ids": n, "words": words.astype("<u8").tobytes(), "anchors": anchors.tobytes(), "escapes": escapes.tobytes(),
            }
            start, block, n, ids, docs, lens = start + n, block + 1, 0, [], [], []
            return pa.RecordBatch.from_pylist([row], schema=_ARROW)

        for table in _grouped(batches):
            shard = table.column(2)[0].as_py()
            flat, sizes = enc.encode(table.column(1).combine_chunks())
            flat = np.insert(flat, np.cumsum(sizes), end_id)
            at = 0
            for doc, size in zip(table.column(0).to_pylist(), (sizes + 1).tolist(), strict=True):
                ids.append(flat[at : at + size])
                docs.append(doc)
                lens.append(size)
                at, n = at + size, n + size
                if n >= BLOCK_IDS:
                    yield close()
        if docs:
            yield close()

    return run


_ARROW = pa.schema([("shard", pa.int32()), ("block", pa.int32()), ("doc_lo", pa.int64()), ("doc_hi", pa.int64()), ("doc_ids", pa.binary()), ("lengths", pa.binary()), ("start_in_shard", pa.int64()), ("n_ids", pa.int64()), ("words", pa.binary()), ("anchors", pa.binary()), ("escapes", pa.binary())])


def write_ids(docs: DataFrame, path: str, tokenizer: str, end_id: int = 2) -> str:
    """Encodes every whole text and writes the ids, documents in ascending ``doc_id``, to ``path``.

    The file format is a folder of Parquet files whose rows are blocks: whole documents, their
    lengths, Simple-8b words, the first word of every stretch of 1024 ids, the escaped words, and the
    ids before the block within its shard; a shard is one range of doc_id. ``path`` + ``.shards`` has
    every shard's ids and those before it. Texts cross the network once, sorted by range.

    Reads ``doc_id, text`` and ignores other columns; null and empty text give the end id alone;
    rows of equal doc_id follow each other by text; a null doc_id sorts first and reads back as null;
    ids of -1 are not allowed. An empty table writes a folder without blocks.
    """
    session_defaults(docs.sparkSession)
    ranged = docs.select("doc_id", "text").repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    blocks = ranged.withColumn("shard", F.spark_partition_id()).mapInArrow(_coder(tokenizer, end_id), FILE_SCHEMA)
    blocks.write.option("compression", "none").parquet(path)  # packed words do not shrink any more
    spark = docs.sparkSession
    sums = spark.read.schema(FILE_SCHEMA).parquet(path).groupBy("shard").agg(F.sum("n_ids").alias("n_ids"))
    before = F.coalesce(F.sum("n_ids").over(W.orderBy("shard").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    sums.withColumn("start", before.cast("long")).write.parquet(f"{path}.shards")
    return path


def _reader(payload: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["shard", "doc_id", "at", "n_tokens", "ids_crc32", "ids"]
        for batch in batches:
            for row in batch.to_pylist():
                ids = unpack(np.frombuffer(row["words"], "<u8"), row["n_ids"], np.frombuffer(row["escapes"], np.uint32)).astype("<u4")
                lens = np.frombuffer(row["lengths"], "<i8")
                ends = np.cumsum(lens)
                parts = [ids[e - n : e] for n, e in zip(lens.tolist(), ends.tolist(), strict=True)]
                docs = [None if d == -1 else d for d in np.frombuffer(row["doc_ids"], "<i8").tolist()]
                cols = [pa.array([row["shard"]] * len(docs), pa.int32()), pa.array(docs, pa.int64()), pa.array(ends - lens + row["start_in_shard"], pa.int64()), pa.array(lens, pa.int64()), pa.array([zlib.crc32(p) for p in parts], pa.int64())]
                if payload:
                    cols.append(pa.array([p.tobytes() for p in parts], pa.binary()))
                yield pa.RecordBatch.from_arrays(cols, names[: len(cols)])

    return run


def read_ids(spark: SparkSession, path: str, payload: bool = True) -> DataFrame:
    """Documents of the files at ``path``: ``doc_id, start, n_tokens, ids_crc32``, and ``ids`` (little-endian uint32
    bytes) unless ``payload`` is off."""
    session_defaults(spark)
    blocks = spark.read.schema(FILE_SCHEMA).parquet(path).select("shard", "start_in_shard", "n_ids", "doc_ids", "lengths", "words", "escapes")
    docs = blocks.mapInArrow(_reader(payload), "shard int, doc_id long, at long, n_tokens long, ids_crc32 long" + ", ids binary" * payload)
    shards = spark.read.schema("shard int, n_ids long, start long").parquet(f"{path}.shards")
    return docs.join(shards.select("shard", "start"), "shard").select("doc_id", (F.col("start") + F.col("at")).alias("start"), "n_tokens", "ids_crc32", *["ids"] * payload)


def packed_corpus(docs: DataFrame, tokenizer: str, end_id: int = 2, payload: bool = True) -> DataFrame:
    """Writes to the shared scratch folder and reads back; see :func:`write_ids` and :func:`read_ids`."""
    import uuid

    spark = docs.sparkSession
    return read_ids(spark, write_ids(docs, f"{scratch_dir(spark)}/ids-{uuid.uuid4().hex}", tokenizer, end_id), payload)


__all__ = ["WordEncoder", "pack", "packed_corpus", "read_ids", "unpack", "unpack_stretch", "write_ids"]
