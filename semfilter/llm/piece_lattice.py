"""SentencePiece encoding as a relational lattice, and decoding."""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import lean, save, session_defaults

#: The sign that stands for a blank.
BLANK = "▁"
#: Most frequent words whose ids are broadcast, and the longest that may be so (some 40 bytes a word, by both bounds).
HEAD_WORDS, HEAD_CHARS = 1 << 18, 64
#: Bytes of text that are counted and looked up together; distinct words that one task counts before it gives them on, and how many it gives on at once.
GROUP_BYTES, HELD_WORDS, COUNTED_WORDS = 1 << 20, 300_000, 50_000
#: Words whose ids are written together, words whose lattices are sent together, and words of texts sent together: rows of some 150 KB, as the JVM keeps arrays of 512 KB apart.
STEP_WORDS, SENT_WORDS, SENT_PLACES = 25_000, 128, 20_000
#: Longest word outside the head whose lattice is sent place by place, and characters of such words in a row; longer words are sent edge by edge.
SHORT_CHARS, SENT_CHARS = 64, 3_000
#: Rows of lattices that are made at once, unless their words have more characters than this: edges take much more room.
MADE_ROWS, MADE_CHARS = 8, 16_384
#: Steps to a power of two by which words are told apart by frequency.
STEPS = 16
#: Characters of a word that are exploded from one row, and edges or places that are folded together.
WINDOW, CHUNK = 64, 1024
#: What an unknown character costs beyond the worst piece, as in the public library.
UNKNOWN = 10.0


@dataclass(frozen=True)
class Pieces:
    """A vocabulary: pieces of text with id and score, bytes' ids (None without byte fallback), and control ids."""

    text: dict[str, tuple[int, float]]
    bytes_: tuple[int, ...] | None
    unknown: int
    silent: frozenset[int]

    @classmethod
    def load(cls, path: str) -> Pieces:
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        text, of_byte, silent = {}, {}, set()
        for i in range(sp.vocab_size()):
            if sp.is_byte(i):
                of_byte[int(sp.id_to_piece(i)[3:5], 16)] = i
            elif sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i):
                silent.add(i)
            else:
                text[sp.id_to_piece(i)] = (i, float(sp.get_score(i)))
        found = tuple(of_byte[b] for b in range(256)) if len(of_byte) == 256 else None
        if any(BLANK in p.lstrip(BLANK) for p in text):
            raise ValueError("a piece has a blank inside: words can't be encoded apart")
        return cls(text, found, sp.unk_id(), frozenset(silent))

    def longest(self) -> int:
        """Characters of the longest piece."""
        return max(map(len, self.text), default=1)

    def fallback(self, char: str) -> list[int]:
        """Ids of a character that no piece has."""
        return [self.bytes_[b] for b in char.encode("utf-8", "surrogatepass")] if self.bytes_ else [self.unknown]


def _stops(pieces: Pieces) -> list[str]:
    """Signs that no piece has behind a letter: a word's last one is encoded apart from it."""
    return [c for c in ".,;:!?" if not any(a.isalpha() and b == c for p in pieces.text for a, b in zip(p, p[1:], strict=False))]


def words_of(texts: pa.Array, newline: bool, stops: list[str]) -> tuple[pa.Array, np.ndarray]:
    """Words of texts one after another, and how many each text has.

    A word is blank signs and what follows, as the library puts one before the text; newlines are words if
    no piece holds one (``newline``), and so is a stop at the end of letters. No piece reaches from
    one word into another, so words can be encoded apart.
    """
    texts = pc.fill_null(texts, "")
    led = pc.binary_join_element_wise(pa.scalar(" "), texts, "")
    marked = pc.replace_substring(pc.if_else(pc.equal(texts, ""), "", led), " ", f" {BLANK}")
    for _ in range(2):  # pairs, then pairs of pairs: runs of blanks stay together
        marked = pc.replace_substring(marked, f"{BLANK} {BLANK}", BLANK + BLANK)
    if newline:
        marked = pc.replace_substring(marked, "\n", " \n ")
    if stops:
        signs = "".join(stops)
        marked = pc.replace_substring_regex(marked, rf"(\pL)([{signs}])( |$)", r"\1 \2\3")
    lists = pc.split_pattern(marked, " ")
    flat = lists.flatten()
    keep = pc.not_equal(flat, "")
    seen = np.concatenate([[0], np.cumsum(keep.to_numpy(zero_copy_only=False))])
    offsets = lists.offsets.to_numpy() - lists.offsets[0].as_py()
    return flat.filter(keep), np.diff(seen[offsets])


def _cut(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
    """A batch in pieces of about ``GROUP_BYTES`` of text (its last column), a longer text alone; Spark's batches are several times as large."""
    ends, lo = np.cumsum(pc.fill_null(pc.binary_length(batch.column(batch.num_columns - 1)), 0).to_numpy(zero_copy_only=False).astype(np.int64)), 0
    while lo < batch.num_rows:
        hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + GROUP_BYTES, "right")))
        yield batch.slice(lo, hi - lo)
        lo = hi


def _grouped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    lean()
    held: list[pa.RecordBatch] = []
    for batch in batches:
        for b in _cut(batch):
            if held and sum(x.nbytes for x in held) + b.nbytes > GROUP_BYTES:
                yield pa.Table.from_batches(held)
                held = []
            held.append(b)
    if held:
        yield pa.Table.from_batches(held)
    held = []
    lean()


def _counter(newline: bool, stops: list[str]):
    """Words that a task sees more than once, with their number: only such words can be worth remembering."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, int] = {}  # Arrow's own grouping runs in a pool of memory that a worker never gives back
        for group in _grouped(batches):
            found = pc.value_counts(words_of(group.column(0).combine_chunks(), newline, stops)[0])
            found = found.filter(pc.less_equal(pc.utf8_length(found.field(0)), HEAD_CHARS))
            for word, n in zip(_strings(found.field(0)), found.field(1).to_numpy().tolist(), strict=True):
                held[word] = held.get(word, 0) + n
            if len(held) > HELD_WORDS:
                yield from _counted(held)
                held = {}
        yield from _counted(held)
        held = {}
        lean()

    return run


def _counted(held: dict[str, int]) -> Iterator[pa.RecordBatch]:
    often = sorted(w for w, n in held.items() if n > 1)  # neighbours share beginnings, which compress
    for lo in range(0, len(often), COUNTED_WORDS):
        some = often[lo : lo + COUNTED_WORDS]
        yield pa.RecordBatch.from_arrays([pa.array(some, pa.string()), pa.array([held[w] for w in some], pa.int64())], ["word", "n"])


class PieceTable:
    """Pieces by length, as sorted hashes of their characters, with those of all their beginnings."""

    def __init__(self, pieces: Pieces):
        self.worst = min((s for _, s in pieces.text.values()), default=0.0) - UNKNOWN
        by: dict[int, dict[int, tuple[int, float]]] = {}
        starts: dict[int, set[int]] = {}
        for p, (i, s) in pieces.text.items():
            h = np.zeros(1, np.uint64)
            for k, c in enumerate(p, 1):
                h = self.step(h, np.array([ord(c)], np.uint64))
                starts.setdefault(k, set()).add(int(h[0]))
            by.setdefault(len(p), {})[int(h[0])] = (i, s)
        self.starts = {k: np.array(sorted(v), np.uint64) for k, v in starts.items()}
        self.rows = {}
        for k, v in by.items():
            keys = sorted(v)
            self.rows[k] = (np.array(keys, np.uint64), np.array([v[x][0] for x in keys], np.int32), np.array([v[x][1] for x in keys]))

    @staticmethod
    def step(h: np.ndarray, c: np.ndarray) -> np.ndarray:
        h = (h + c + np.uint64(0x9E3779B97F4A7C15)) * np.uint64(0xD6E8FEB86659FD93)
        return h ^ (h >> np.uint64(32))

    @staticmethod
    def find(keys: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        at = np.minimum(np.searchsorted(keys, h), len(keys) - 1)
        return at, keys[at] == h

    def found(self, words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Characters of each word, and end, start, id and score of all edges, places being counted over all words; longer edges come later.

        Every place begins substrings of growing length, exploded a length at a time while some piece begins
        so; those found in the table of that length (an equi-join on the hash) are edges.
        """
        code = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
        size = np.fromiter(map(len, words), np.int64, len(words))
        end = np.repeat(np.cumsum(size), size)
        at, h = np.arange(len(code)), np.zeros(len(code), np.uint64)
        single, got = np.zeros(len(code), bool), []
        for length in range(1, max(self.starts, default=0) + 1):
            inside = at + length <= end[at]
            at, h = at[inside], h[inside]
            h = self.step(h, code[at + length - 1])
            if length in self.rows:
                keys, ids, scores = self.rows[length]
                k, hit = self.find(keys, h)
                got.append((at[hit] + length, at[hit], ids[k[hit]], scores[k[hit]]))
                if length == 1:
                    single[at[hit]] = True
            _, more = self.find(self.starts[length], h)
            at, h = at[more], h[more]
            if not len(at):
                break
        lone = np.flatnonzero(~single)
        got.insert(0, (lone + 1, lone, np.full(len(lone), -1, np.int32), np.full(len(lone), self.worst)))
        e, s, i, w = (np.concatenate(x) for x in zip(*got, strict=True))
        return size, e, s, i, w

    def edges(self, words: list[str]) -> pa.Array:
        """Edges of each word's lattice by end, then start, as :func:`lattice` makes them of one word: those found, grouped by word."""
        size, e, s, i, w = self.found(words)
        begin = np.repeat(np.cumsum(size) - size, size)
        order = np.argsort(e * (len(begin) + 1) + s)  # no two edges have both ends in common
        e, s, i, w = e[order], s[order], i[order], w[order]
        first = begin[s]
        many = np.bincount(np.repeat(np.arange(len(words)), size)[s], minlength=len(words))
        flat = [pa.array((e - first).astype(np.int32)), pa.array((s - first).astype(np.int32)), pa.array(w), pa.array(((s - first) << 32) + i + 1)]
        return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(many)]), pa.int32()), pa.StructArray.from_arrays(flat, ["e", "s", "w", "c"]))

    def places(self, words: list[str]) -> tuple[pa.Array, tuple]:
        """The same edges grouped by word and the place where they end: scores by length, the longest first, -inf for a length
        without a piece. Beside them what :func:`_back` needs: characters of words, lengths of places, scores and ids."""
        size, e, s, i, w = self.found(words)
        longest = np.zeros(int(size.sum()), np.int64)
        longest[e - 1] = e - s  # the last one written stays
        ends = np.cumsum(longest)
        at = ends[e - 1] - (e - s)
        scores, ids = np.full(int(longest.sum()), -np.inf), np.full(int(longest.sum()), -1, np.int32)
        scores[at], ids[at] = w, i
        lists = pa.array(scores)
        for many in (longest, size):
            lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(many)]), pa.int32()), lists)
        return lists, (size, longest, scores, ids)


def piece_table(spark: SparkSession, pieces: Pieces) -> DataFrame:
    """The vocabulary as a relation, ``piece, id, w``; its size is that of the model."""
    rows = pa.table({"piece": list(pieces.text), "id": pa.array([i for i, _ in pieces.text.values()], pa.int32()), "w": [w for _, w in pieces.text.values()]})
    return spark.createDataFrame(rows, "piece string, id int, w double")


def edges(words: DataFrame, pieces: Pieces, keys: list[str]) -> DataFrame:
    """Edges of the words' lattices, ``keys, e, s, w, id``, end, start, score and id, and a row without edge for each null word.

    Words are exploded to windows, windows to places, places to substrings no longer than the longest piece, and those equi-joined with the
    pieces. A character that is no piece gives an edge with id -1. Rows stay in the partition of their word.
    """
    longest = pieces.longest()
    worst = min((w for _, w in pieces.text.values()), default=0.0) - UNKNOWN
    at = words.select(*keys, "word", F.explode_outer(F.expr(f"if(word <> '', sequence(0, (length(word) - 1) div {WINDOW} * {WINDOW}, {WINDOW}), null)")).alias("at"))
    part = at.select(*keys, "at", F.expr(f"if(length(word) <= {WINDOW}, word, substr(word, at + 1, {WINDOW + longest - 1}))").alias("part")).withColumn("size", F.length("part"))
    place = part.select(*keys, "at", "part", "size", F.explode_outer(F.expr(f"sequence(0, least(size, {WINDOW}) - 1)")).alias("p"))
    run = place.select(*keys, "at", "part", "p", F.explode_outer(F.expr(f"sequence(1, least(size - p, {longest}))")).alias("k"))
    sub = run.select(*keys, (F.col("at") + F.col("p")).alias("s"), "k", F.expr("substr(part, p + 1, k)").alias("piece"))
    hit = sub.join(F.broadcast(piece_table(words.sparkSession, pieces)), "piece", "left").filter("id IS NOT NULL OR k = 1 OR k IS NULL")
    return hit.select(*keys, (F.col("s") + F.col("k")).alias("e"), "s", F.coalesce("w", F.lit(worst)).alias("w"), F.coalesce("id", F.lit(-1)).alias("id"))


def _fold(longest: int) -> str:
    """Viterbi over a word's edges by end, then start: for every place but the first the edge that reaches it best, as its code.

    The candidate for the place at hand is kept beside the lists; a better edge takes its place, an equal one does not, so among equal scores
    the one that starts first wins, as in the public library. Spark copies what a fold keeps at each step, so the inner fold, over ``CHUNK`` edges,
    keeps the places of these edges and as many before them as a piece may reach, and the outer one lays older places aside.
    """

    def step(base: str) -> str:
        cost = f"(x.w + if(x.s = a.e, a.w, a.b[x.s{base}]))"
        return f"""if(x.e > a.e, named_struct('b', array_append(a.b, a.w), 'p', array_append(a.p, a.c), 'e', x.e, 'w', {cost}, 'c', x.c),
            if({cost} > a.w, named_struct('b', a.b, 'p', a.p, 'e', a.e, 'w', {cost}, 'c', x.c), a))"""

    state = "b:array<double>,p:array<bigint>,e:int,w:double,c:bigint"
    none = f"cast(named_struct('b', array(), 'p', array(), 'e', 0, 'w', 0D, 'c', 0L) as struct<{state}>)"
    short = f"aggregate(edges, {none}, (a, x) -> {step('')}, a -> array_append(a.p, a.c))"
    inner = f"aggregate(part, named_struct('b', o.b, 'p', o.p, 'e', o.e, 'w', o.w, 'c', o.c), (a, x) -> {step(' - o.base')})"
    old = f"greatest(size(r.b) - {longest}, 0)"
    aside = f"named_struct('done', array_append(o.done, slice(r.p, 1, {old})), 'b', slice(r.b, {old} + 1, {longest}), 'p', slice(r.p, {old} + 1, {longest}), 'base', o.base + {old}, 'e', r.e, 'w', r.w, 'c', r.c)"
    start = f"cast(named_struct('done', array(), 'b', array(), 'p', array(), 'base', 0, 'e', 0, 'w', 0D, 'c', 0L) as struct<done:array<array<bigint>>,b:array<double>,p:array<bigint>,base:int,e:int,w:double,c:bigint>)"
    nested = f"aggregate({_chunks('edges')}, {start}, (o, part) -> transform(array({inner}), r -> {aside})[0], o -> concat(flatten(o.done), o.p, array(o.c)))"
    return f"if(size(edges) <= {CHUNK}, {short}, {nested})"


def _scores() -> str:
    """The same recurrence over a word's places, as :meth:`PieceTable.places` groups edges: the highest score up to each place, the
    first one's 0 included. It keeps one array and makes no struct, which costs Spark more than all else in a step of :func:`_fold`."""
    return "aggregate(places, array(0D), (b, ws) -> array_append(b, array_max(transform(ws, (w, k) -> b[k + size(b) - size(ws)] + w))))"


def _back(top: np.ndarray, size: np.ndarray, longest: np.ndarray, scores: np.ndarray, ids: np.ndarray) -> pa.Array:
    """Best paths of words from their places' highest scores: the longest edge that attains a place's score leads there, and
    the words' last places lead back; codes as :func:`lattice` gives them."""
    word = np.repeat(np.arange(len(size)), size)
    place, end = np.repeat(np.arange(len(word)), longest), np.cumsum(longest)
    length = end[place] - np.arange(len(place))
    here = place + word[place] + 1  # a word has one score more than places
    hits = np.flatnonzero(top[here - length] + scores == top[here])
    hits = hits[np.diff(place[hits], prepend=-1) > 0]
    if len(hits) != len(word):
        raise ValueError("scores of a word do not belong to its lattice")
    reach, first = length[hits], np.cumsum(size) - size
    used, at, low = np.zeros(len(word), bool), first + size - 1, first
    while len(at):
        used[at] = True
        at = at - reach[at]
        on = at >= low
        at, low = at[on], low[on]
    kept = np.flatnonzero(used)
    start = kept + 1 - reach[kept] - first[word[kept]]
    many = np.bincount(word[kept], minlength=len(size))
    codes = (start << 32) + ids[hits[kept]] + 1
    return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(many)]), pa.int32()), pa.array(codes, pa.int64()))


def _chunks(array: str) -> str:
    return f"transform(sequence(0, (size({array}) - 1) div {CHUNK}), c -> slice({array}, c * {CHUNK} + 1, {CHUNK}))"


def _walk() -> str:
    """The best path back from the last place, as its edges' codes in order; in chunks, as the fold."""
    step = "if(a.k = a.at, named_struct('k', a.k - 1, 'at', cast(shiftright(x, 32) as int), 'cur', array_append(a.cur, x)), named_struct('k', a.k - 1, 'at', a.at, 'cur', a.cur))"
    places = "slice(reverse(best), 1, size(best) - 1)"
    short = f"aggregate({places}, named_struct('k', size(best) - 1, 'at', size(best) - 1, 'cur', cast(array() as array<bigint>)), (a, x) -> {step}, a -> reverse(a.cur))"
    inner = f"aggregate(part, named_struct('k', o.k, 'at', o.at, 'cur', cast(array() as array<bigint>)), (a, x) -> {step})"
    start = "cast(named_struct('k', size(best) - 1, 'at', size(best) - 1, 'done', array()) as struct<k:int,at:int,done:array<array<bigint>>>)"
    aside = "named_struct('k', r.k, 'at', r.at, 'done', array_append(o.done, r.cur))"
    nested = f"aggregate({_chunks(places)}, {start}, (o, part) -> transform(array({inner}), r -> {aside})[0], o -> reverse(flatten(o.done)))"
    return f"if(size(best) <= {CHUNK}, {short}, {nested})"


def lattice(words: DataFrame, pieces: Pieces, key: str = "word", parts: int | None = None) -> DataFrame:
    """Best segmentation of each ``word``: ``key, path``, its pieces in order (start * 2**32 + id + 1).

    Words (a row for each ``key``, which may be the word) are dealt once, over ``parts`` partitions;
    :func:`edges` explodes and joins them, edges are grouped by word where they are, and two folds with Spark's
    ``aggregate`` find the best path. Null and empty words have an empty one.
    """
    dealt = words.select(F.col(f"`{key}`").alias("key0"), "word")
    found = edges(dealt.repartition(parts, "key0") if parts else dealt.repartition("key0"), pieces, ["key0"])
    code = F.shiftleft(F.col("s").cast("long"), 32) + F.col("id") + 1
    edge = F.when(F.col("e").isNotNull(), F.struct(F.col("e").cast("int").alias("e"), F.col("s").cast("int").alias("s"), "w", code.alias("c")))
    met = found.groupBy("key0").agg(F.sort_array(F.collect_list(edge)).alias("edges"))
    return met.select("key0", F.expr(_fold(pieces.longest())).alias("best")).select(F.col("key0").alias(key), F.expr(_walk()).alias("path"))


def _flat(lists: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Values of a list column one after another, and how many each row has."""
    return lists.flatten().to_numpy(zero_copy_only=False), np.diff(lists.offsets.to_numpy())


def _ids(paths: pa.Array, unknown: dict[int, str], pieces: Pieces) -> pa.Array:
    """Ids of paths, unknown characters spelled by the ids of their bytes; ``unknown`` has the words with such, by number."""
    flat, many = _flat(paths)
    ids, at = (flat & 0xFFFFFFFF) - 1, flat >> 32
    cuts = np.concatenate([[0], np.cumsum(many)])
    if (ids < 0).any():
        owner = np.repeat(np.arange(len(many)), many)
        spelled = [[i] if i >= 0 else pieces.fallback(unknown[o][s]) for i, s, o in zip(ids.tolist(), at.tolist(), owner.tolist(), strict=True)]
        ids, cuts = np.array([i for x in spelled for i in x], np.int64), np.concatenate([[0], np.cumsum([len(x) for x in spelled])])[cuts]
    return pa.ListArray.from_arrays(pa.array(cuts, pa.int32()), pa.array(ids, pa.int32()))


def _strings(words: pa.Array) -> list[str]:
    """Words as Python's strings; ``to_pylist`` makes a scalar of each first."""
    return words.to_numpy(zero_copy_only=False).tolist()


def _coded(texts: pa.Array, known: dict[str, int], newline: bool, stops: list[str]) -> tuple[pa.DictionaryArray, np.ndarray, np.ndarray, np.ndarray]:
    """Words of texts by number, words a text, and for each distinct word its place among the known ones or, below 0, none; and the unknown ones."""
    words, counts = words_of(texts, newline, stops)
    coded = words.dictionary_encode()
    place = np.fromiter((known.get(w, -1) for w in _strings(coded.dictionary)), np.int64, len(coded.dictionary))
    return coded, counts, place, np.flatnonzero(place < 0)


def _sender(head, pieces: Pieces):
    """Groups of documents: rows of lattices of the words that are not in the head, short ones first, then a row that tells where each distinct word's ids are,
    then rows of texts with their words by number. Rows are kept small, a text apart from others being one row at least."""
    table, (newline, stops) = PieceTable(pieces), _plan(pieces)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = {w: k for k, w in enumerate(_strings(head.value))}  # once a task; Arrow would hash the whole head again for every group
        lattices = pa.list_(pa.list_(pa.struct([("e", pa.int32()), ("s", pa.int32()), ("w", pa.float64()), ("c", pa.int64())])))
        by_place = pa.list_(pa.list_(pa.list_(pa.float64())))
        schema = pa.schema([("words", lattices), ("places", by_place), ("pack", pa.binary())])

        def row(words: pa.Array | None = None, places: pa.Array | None = None, pack: tuple | None = None) -> pa.RecordBatch:
            lists = [pa.nulls(1, t) if x is None else pa.ListArray.from_arrays(pa.array([0, len(x)], pa.int32()), x).cast(t) for x, t in ((words, lattices), (places, by_place))]
            return pa.RecordBatch.from_arrays([*lists, pa.array([pack and pickle.dumps(pack, protocol=5)], pa.binary())], schema=schema)

        for group in _grouped(batches):
            coded, counts, place, rare = _coded(group.column(1).combine_chunks(), known, newline, stops)
            size = pc.utf8_length(coded.dictionary).to_numpy(zero_copy_only=False)[rare]
            rare, size = (np.concatenate([x[size <= SHORT_CHARS], x[size > SHORT_CHARS]]) for x in (rare, size))
            own = coded.dictionary.take(pa.array(rare))
            ends, short, lo = np.cumsum(size, dtype=np.int64), int(np.count_nonzero(size <= SHORT_CHARS)), 0
            while lo < short:
                hi = min(short, max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + SENT_CHARS, "right"))))
                places, sent = table.places(_strings(own.slice(lo, hi - lo)))
                yield row(places=places, pack=sent)
                lo = hi
            while lo < len(rare):
                some = _strings(own.slice(lo, SENT_WORDS * MADE_ROWS))
                many = table.edges(some if sum(map(len, some)) <= MADE_CHARS else some[:SENT_WORDS])
                lo += len(many)
                for at in range(0, len(many), SENT_WORDS):
                    yield row(words=many.slice(at, SENT_WORDS))
            place[rare] = np.arange(len(rare)) + len(known)
            index, ends, docs, lo = coded.indices.to_numpy(), np.concatenate([[0], np.cumsum(counts)]), group.combine_chunks(), 0
            packs = [(place.astype(np.int32), _unknown(own, pieces))]
            while lo < len(counts):
                hi = max(lo + 1, int(np.searchsorted(ends, ends[lo] + SENT_PLACES, "right")) - 1)
                packs.append((_packed(docs.slice(lo, hi - lo)), counts[lo:hi], index[ends[lo] : ends[hi]]))
                lo = hi
            for pack in packs:
                yield row(pack=pack)
        known.clear()
        forget(head)

    return run


def forget(shared) -> None:
    """Drops a worker's copy of what was broadcast, and what else is free; its next task reads it again."""
    if hasattr(shared, "_value"):
        del shared._value
    lean()


def _unknown(words: pa.Array, pieces: Pieces) -> dict[int, str]:
    """Words by number that have a character that is no piece."""
    single = {p for p in pieces.text if len(p) == 1}
    return {k: w for k, w in enumerate(_strings(words)) if not single.issuperset(w)}


def _packed(table: pa.Table) -> bytes:
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, table.schema) as out:
        out.write_table(table)
    return sink.getvalue().to_pybytes()


def _encode(head, pieces: Pieces, decoded: bool, names: list[str]):
    """Ids of the documents of each group, from the head and from the paths that come just before its texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean()
        letters = letters_of(pieces) if decoded else None
        paths: list[pa.Array] = []
        group: tuple = ()
        for batch in batches:
            for words, top, pack in zip(*batch.columns, strict=True):
                if not pack.is_valid:
                    paths.append(words.values)
                    continue
                sent = pickle.loads(pack.as_buffer())
                if top.is_valid:
                    paths.append(_back(_flat(top.values)[0], *sent))
                elif len(sent) == 2:
                    group, paths = gathered(*sent, paths), []
                    lean()
                else:
                    yield from encoded(pa.ipc.open_stream(sent[0]).read_all(), *sent[1:], *group, letters)
        forget(head)

    def gathered(place: np.ndarray, unknown: dict[int, str], paths: list[pa.Array]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the distinct words of a group one after another, and where those of each begin and end."""
        known = head.value
        own = _ids(pa.concat_arrays(paths) if paths else pa.array([], pa.list_(pa.int64())), unknown, pieces)
        used, rare = np.flatnonzero(place < len(known)), np.flatnonzero(place >= len(known))
        rare = rare[np.argsort(place[rare])]  # short words were sent first
        if len(rare) != len(own):
            raise ValueError("a group of documents did not get the words it asked for")
        flat, many = _flat(pa.concat_arrays([known.take(pa.array(place[used])), own]))
        ends = np.cumsum(many)
        spans = np.empty((len(place), 2), np.int64)
        spans[np.concatenate([used, rare])] = np.stack([ends - many, ends], axis=1)
        return flat, spans

    def encoded(docs: pa.Table, counts: np.ndarray, index: np.ndarray, flat: np.ndarray, spans: np.ndarray, letters: tuple | None) -> Iterator[pa.RecordBatch]:
        doc, text, ends, lo = docs.column(0).combine_chunks(), docs.column(1).combine_chunks(), np.concatenate([[0], np.cumsum(counts)]), 0
        while lo < len(counts):  # a few documents at a time: positions take much more room than texts
            hi = max(lo + 1, int(np.searchsorted(ends, ends[lo] + STEP_WORDS, "right")) - 1)
            begin, end = spans[index[ends[lo] : ends[hi]]].T
            size = end - begin
            total = np.concatenate([[0], np.cumsum(size)])
            out = flat[np.repeat(begin - total[:-1], size) + np.arange(total[-1])]
            made = pa.ListArray.from_arrays(pa.array(total[ends[lo : hi + 1] - ends[lo]], pa.int32()), pa.array(out, pa.int32()))
            more = [decode_ids(made, *letters)] if letters else []
            yield pa.RecordBatch.from_arrays([doc.slice(lo, hi - lo), text.slice(lo, hi - lo), made, *more], names)
            lo = hi

    return run


def frequent(docs: DataFrame, pieces: Pieces) -> DataFrame:
    """Words of the corpus that are worth remembering, ``word, n``: at most ``HEAD_WORDS``, none longer than ``HEAD_CHARS``.

    Words are counted task by task; how many there are at each level of frequency (a few hundred rows) says down to
    which one the head reaches. Any head gives the same encoding.
    """
    counted = docs.select("text").mapInArrow(_counter(*_plan(pieces)), "word string, n long").groupBy("word").agg(F.sum("n").alias("n"))
    counted = save(counted.withColumn("level", F.floor(F.log2("n") * STEPS).cast("int")), "counts")
    levels = sorted(((r["level"], r["m"]) for r in counted.groupBy("level").agg(F.count("*").alias("m")).collect()), reverse=True)
    least, room = None, HEAD_WORDS
    for level, m in levels:
        if m > room:
            break
        least, room = level, room - m
    head = counted.filter(F.col("level") >= least) if least is not None else counted.limit(0)
    return head.select("word", "n")


def _plan(pieces: Pieces) -> tuple[bool, list[str]]:
    return not any("\n" in p for p in pieces.text), _stops(pieces)


def encode(docs: DataFrame, pieces: Pieces, decoded: bool = False) -> DataFrame:
    """Ids of every whole text by the highest sum of piece scores: ``doc_id, text, ids``; with ``decoded``, also
    what :func:`decode` makes of them, in the same pass.

    The distinct words of the head (:func:`frequent`), most of what texts consist of, go through :func:`lattice` once, and their ids are broadcast.
    The others are met group by group of documents, some ``GROUP_BYTES`` each: their edges are exploded and joined in
    Arrow, since Spark would sort some 26 rows for each of them, and folds find their paths: over places those of words of up to ``SHORT_CHARS``, over
    edges, as in the head, those of longer ones. So neither texts nor rare words are shuffled, and no word is too long or too rare. Blanks become the blank sign and one is put before the text, as in the library.

    Reads ``doc_id, text``; other columns are ignored. Null and empty texts have no ids; a null doc_id
    is kept, and rows that repeat one are encoded each for itself.
    """
    spark = docs.sparkSession
    session_defaults(spark)
    best = lattice(frequent(docs, pieces), pieces, parts=-(-HEAD_WORDS // 16_384))
    top = best.select("word", "path").toArrow().combine_chunks()
    words, paths = (c.chunk(0) if c.num_chunks else pa.array([], c.type) for c in top.columns)
    heads, ids = spark.sparkContext.broadcast(words), spark.sparkContext.broadcast(_ids(paths, _unknown(words, pieces), pieces))
    sent = docs.select("doc_id", "text").mapInArrow(_sender(heads, pieces), "words array<array<struct<e:int,s:int,w:double,c:bigint>>>, places array<array<array<double>>>, pack binary")
    paths = F.expr(f"transform(transform(words, edges -> {_fold(pieces.longest())}), best -> {_walk()})").alias("paths")
    folded = sent.select(paths, F.expr(f"transform(places, places -> {_scores()})").alias("top"), "pack")
    schema = f"doc_id {dict(docs.dtypes)['doc_id']}, text string, ids array<int>" + ", decoded string" * decoded
    return folded.mapInArrow(_encode(ids, pieces, decoded, ["doc_id", "text", "ids", "decoded"][: 3 + decoded]), schema)


def spell(pieces: Pieces) -> list[bytes]:
    """Bytes that each id stands for."""
    out = [b""] * (max([i for i, _ in pieces.text.values()] + list(pieces.bytes_ or ()) + [pieces.unknown]) + 1)
    for p, (i, _) in pieces.text.items():
        out[i] = p.replace(BLANK, " ").encode("utf-8", "surrogatepass")
    for b, i in enumerate(pieces.bytes_ or ()):
        out[i] = bytes([b])
    return out


def letters_of(pieces: Pieces) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """What ids stand for, as one run of bytes with each id's begin and size."""
    table = spell(pieces)
    size = np.array([len(b) for b in table], np.int64)
    return np.frombuffer(b"".join(table), np.uint8), np.cumsum(size) - size, size


def decode_ids(lists: pa.Array, raw: np.ndarray, begin: np.ndarray, size_of: np.ndarray) -> pa.Array:
    """Texts of lists of ids."""
    ids, counts = _flat(lists)
    size = size_of[ids]
    total = np.concatenate([[0], np.cumsum(size)])
    data = raw[np.repeat(begin[ids] - total[:-1], size) + np.arange(total[-1])].tobytes()
    ends = total[np.concatenate([[0], np.cumsum(counts)])].tolist()
    texts = [data[a + 1 : b].decode("utf-8", "replace") for a, b in zip(ends, ends[1:], strict=False)]
    return pa.array(texts, pa.string(), mask=lists.is_null().to_numpy(zero_copy_only=False))


def _decode(letters: tuple):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([*batch.columns, decode_ids(batch.column(batch.num_columns - 1), *letters)], [*batch.schema.names, "decoded"])

    return run


def decode(encoded: DataFrame, pieces: Pieces) -> DataFrame:
    """Adds ``decoded``, the text of the last column ``ids``: pieces joined, blank signs as blanks, the first one dropped.

    Control ids stand for nothing; bytes that are not UTF-8 become the replacement character; null ids give null.
    """
    session_defaults(encoded.sparkSession)
    names = [c for c in encoded.columns if c != "ids"]
    schema = ", ".join(f"`{c}` {k}" for c, k in encoded.select(*names, "ids").dtypes) + ", decoded string"
    return encoded.select(*names, "ids").mapInArrow(_decode(letters_of(pieces)), schema)


__all__ = ["Pieces", "decode", "encode", "frequent", "lattice"]
