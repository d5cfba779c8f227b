"""MinHash near-duplicates: banded candidates, odd-sketch estimates, confirmation on full shingle sets."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import clear, components, save, session_defaults, tidy

#: MinHash samples, and how they are banded: a pair of similarity 0.75 misses all bands with chance (1 - 0.75**4)**32, 5e-6.
SAMPLES, BANDS = 128, 32
#: Bits of the odd sketch, and standard deviations that an estimate may be off before a pair is dropped unread.
SKETCH_BITS, SIGMAS = 512, 6.0
WIDTH = 5
#: Candidate ids up to which they are broadcast (8 bytes each); beyond, texts are joined by shuffle.
BROADCAST_IDS = 500_000
#: Members of one block of a bucket, and shingles of one (a single longer text may exceed them); two blocks are compared at a time.
BLOCK, BLOCK_SHINGLES = 1024, 1 << 20
#: Cells of a table of pairs held at a time.
CELLS = 1 << 18
#: Words remembered with their hashes by one worker.
CACHE_WORDS = 150_000

_rng = np.random.default_rng(20_240)
_XOR = _rng.integers(0, 2**32, SAMPLES, dtype=np.uint32)
_MUL = _rng.integers(0, 2**32, SAMPLES, dtype=np.uint32) | np.uint32(1)
_PLACE = _rng.integers(0, 2**32, SAMPLES, dtype=np.uint32) | np.uint32(1)
_MIX = _rng.integers(0, 2**63, WIDTH, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


class WordHashes(dict):
    """64-bit hashes of words, remembered."""

    def __missing__(self, word: bytes) -> int:
        self[word] = h = xxhash.xxh3_64_intdigest(word)
        return h


def _finish(h: np.ndarray) -> np.ndarray:
    h ^= h >> np.uint64(32)
    h *= np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(29)
    return h


def shingle_sets(texts: list[str | None], known: WordHashes, width: int = WIDTH) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each text.

    Words are what is between ASCII blanks, A-Z lower-cased; a shingle is ``width`` words, a shorter
    text is one shingle as a whole, and a text without words has none.
    """
    if len(known) > CACHE_WORDS:
        known.clear()
    parts = [(t or "").encode("utf-8", "surrogatepass").lower().split() for t in texts]
    flat = [w for p in parts for w in p]
    h = np.fromiter(map(known.__getitem__, flat), np.uint64, len(flat))
    n = len(h) - width + 1
    if n > 0:
        s = h[:n] * _MIX[0]
        for k in range(1, width):
            s = (s ^ (s >> np.uint64(31))) * _MIX[k] + h[k : k + n]
        s = _finish(s)
    out, at = [], 0
    for p in parts:
        m = len(p)
        if m >= width:
            out.append(np.unique(s[at : at + m - width + 1]))
        else:
            out.append(np.array([xxhash.xxh3_64_intdigest(b" ".join(p), seed=m)] if m else [], np.uint64))
        at += m
    return out


def signatures(sets: list[np.ndarray]) -> np.ndarray:
    """MinHash samples of non-empty sets, one row each."""
    flat = np.concatenate(sets)
    x = (flat >> np.uint64(32)).astype(np.uint32)
    cuts = np.cumsum([0, *map(len, sets[:-1])])
    out = np.empty((len(sets), SAMPLES), np.uint32)
    for k in range(SAMPLES):
        out[:, k] = np.minimum.reduceat((x ^ _XOR[k]) * _MUL[k], cuts)
    return out


def band_keys(sig: np.ndarray) -> np.ndarray:
    """One 64-bit key for each band, the band's number mixed in."""
    rows = sig.reshape(len(sig), BANDS, -1).astype(np.uint64)
    key = np.broadcast_to(np.arange(1, BANDS + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15), rows.shape[:2]).copy()
    for k in range(rows.shape[2]):
        key = _finish((key ^ rows[:, :, k]) * np.uint64(0xC2B2AE3D27D4EB4F))
    return key.astype(np.int64)


def odd_sketches(sig: np.ndarray) -> np.ndarray:
    """Parity bitmaps: each sample toggles the bit that its place and value hash to."""
    bit = ((sig * _PLACE) ^ ((sig * _PLACE) >> np.uint32(15))) * np.uint32(0x2C1B3C6D)
    bit = (bit >> np.uint32(32 - SKETCH_BITS.bit_length() + 1)).astype(np.int64)
    flat = np.bincount((bit + np.arange(len(sig))[:, None] * SKETCH_BITS).ravel(), minlength=len(sig) * SKETCH_BITS)
    return np.packbits((flat & 1).astype(np.uint8).reshape(len(sig), -1), axis=1).view("<i8")


def most_odd_bits(threshold: float) -> int:
    """Bits in which sketches of a pair at the threshold differ at most, ``SIGMAS`` deviations allowed for.

    Sets of samples at similarity J differ in 2k(1 - J) elements; d toggles leave n/2 (1 - exp(-2d/n)) odd bits.
    """
    d = 2 * SAMPLES * (1 - threshold)
    spread = np.sqrt(4 * SAMPLES * threshold * (1 - threshold) + d)
    return int(np.ceil(SKETCH_BITS / 2 * (1 - np.exp(-2 * (d + SIGMAS * spread) / SKETCH_BITS))))


def estimate(odd: np.ndarray | int) -> np.ndarray | float:
    """Similarity that a number of odd bits stands for."""
    share = np.minimum(2 * np.asarray(odd, float) / SKETCH_BITS, 1 - 1e-9)
    return 1 + SKETCH_BITS / (4 * SAMPLES) * np.log(1 - share)


def _signer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    known = WordHashes()
    for batch in batches:
        sets = shingle_sets(batch.column(1).to_pylist(), known)
        full = [k for k, s in enumerate(sets) if len(s)]
        ids = batch.column(0)
        h = [xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None for s in sets]
        bands: list = [None] * len(sets)
        sketch: list = [None] * len(sets)
        if full:
            sig = signatures([sets[k] for k in full])
            for k, b, o in zip(full, band_keys(sig), odd_sketches(sig), strict=True):
                bands[k], sketch[k] = b, o
        cols = [ids, pa.array([len(s) for s in sets], pa.int64()), pa.array(h, pa.binary()), pa.array(bands, pa.list_(pa.int64())), pa.array(sketch, pa.list_(pa.int64()))]
        yield pa.RecordBatch.from_arrays(cols, ["id", "n", "same", "bands", "sketch"])


def _setter(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Sets of the texts that a class is looked for in; another text of the same id is passed over."""
    known = WordHashes()
    for batch in batches:
        sets = shingle_sets(batch.column(1).to_pylist(), known)
        own = pa.array([xxhash.xxh3_128_digest(s.tobytes()) == h for s, h in zip(sets, batch.column(2).to_pylist(), strict=True)], pa.bool_())
        yield pa.RecordBatch.from_arrays([batch.column(0).filter(own), pa.array([s.tobytes() for s in sets], pa.binary()).filter(own)], ["node", "shingles"])


def _digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows with the hash of their text's set."""
    known = WordHashes()
    for batch in batches:
        sets = shingle_sets(batch.column(1).to_pylist(), known)
        h = [xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None for s in sets]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(h, pa.binary()), batch.column(2)], ["id", "same", "row"])


def _confirm(percent: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            good = []
            for x, y in zip(batch.column(2), batch.column(3), strict=True):
                u, v = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                both = len(np.intersect1d(u, v, assume_unique=True))
                good.append(100 * both >= percent * (len(u) + len(v) - both))
            mask = pa.array(good, pa.bool_())
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(mask), batch.column(1).filter(mask)], ["a", "b"])

    return run


class Postings:
    """Which of some sets hold a shingle."""

    def __init__(self, sets: list[np.ndarray]):
        flat = np.concatenate(sets)
        owner = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
        order = np.argsort(flat, kind="stable")
        self.flat, self.owner, self.n = flat[order], owner[order], len(sets)

    def common(self, s: np.ndarray) -> np.ndarray:
        """Shingles that each set shares with ``s``."""
        lo, hi = np.searchsorted(self.flat, s, "left"), np.searchsorted(self.flat, s, "right")
        size = hi - lo
        at = np.repeat(lo - np.cumsum(size) + size, size) + np.arange(size.sum())
        return np.bincount(self.owner[at], minlength=self.n)


def links_between(ids, comps, sizes, sketches, sets, side, most: int, percent: int) -> list[tuple[int, int]]:
    """Links that join components among some documents: enough to reach what all pairs would reach.

    ``side`` has 0 and 1 for documents of two blocks, of which only pairs across are asked for, or 2
    throughout for one block. Documents outside the largest component are compared with
    all others of another component that length and odd sketch admit, on their full sets.
    """
    comp = comps.copy()
    names, counts = np.unique(comp, return_counts=True)
    postings, out = None, []
    for a in np.flatnonzero(comp != names[counts.argmax()]).tolist():
        near = np.flatnonzero(admitted(comp, sizes, sketches, side, np.array([a]), most, percent)[0])
        if not len(near):
            continue
        if len(near) < 4:
            both = np.array([len(np.intersect1d(sets[a], sets[b], assume_unique=True)) for b in near])
        else:
            postings = postings or Postings(sets)
            both = postings.common(sets[a])[near]
        for b in near[100 * both >= percent * (sizes[near] + sizes[a] - both)].tolist():
            if comp[a] != comp[b]:
                out.append((int(ids[a]), int(ids[b])))
                comp[comp == max(comp[a], comp[b])] = min(comp[a], comp[b])
    return out


def admitted(comp, sizes, sketches, side, rows, most: int, percent: int) -> np.ndarray:
    """Which documents (columns) lengths, odd sketches and sides let link with some of them (``rows``), of other components."""
    ok = (comp[None, :] != comp[rows, None]) & (100 * np.minimum(sizes[None, :], sizes[rows, None]) >= percent * np.maximum(sizes[None, :], sizes[rows, None]))
    ok &= (side[None, :] != side[rows, None]) | (side[rows, None] == 2)
    i, j = np.nonzero(ok)
    bits = sketches.view(np.uint64)
    ok[i, j] = np.bitwise_count(bits[rows[i]] ^ bits[j]).sum(axis=1) <= most
    return ok


def hopeful(comp, sizes, sketches, side, most: int, percent: int) -> np.ndarray:
    """Documents that could link with one of another component, as far as lengths and sketches tell."""
    out, step = np.zeros(len(comp), bool), max(1, CELLS // max(1, len(comp)))
    for at in range(0, len(comp), step):
        rows = np.arange(at, min(at + step, len(comp)))
        out[rows] = admitted(comp, sizes, sketches, side, rows, most, percent).any(axis=1)
    return out


def _groups(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """Rows of one bucket and pair of blocks after another; they come sorted by them (the first three columns)."""
    held, at = [], None
    for b in batches:
        k = np.stack([b.column(c).to_numpy().astype(np.int64) for c in range(3)])
        ends = np.append(np.flatnonzero((k[:, 1:] != k[:, :-1]).any(axis=0)) + 1, b.num_rows)
        for lo, hi in zip([0, *ends[:-1].tolist()], ends.tolist(), strict=True):
            if lo == hi:
                continue
            here = tuple(k[:, lo].tolist())
            if held and here != at:
                yield pa.Table.from_batches(held)
                held = []
            at = here
            held.append(b.slice(lo, hi - lo))
    if held:
        yield pa.Table.from_batches(held)


def _column(t: pa.Table, name: str) -> np.ndarray:
    return t.column(name).to_numpy().astype(np.int64)


def _sketches(t: pa.Table) -> np.ndarray:
    return np.concatenate([c.flatten().to_numpy() for c in t.column("sketch").chunks]).reshape(t.num_rows, -1)


def _prune(most: int, percent: int):
    """Of each pair of blocks, the documents that sketches leave a chance of a link between components."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in _groups(batches):
            comp = _column(t, "comp")
            if (comp == comp[0]).all():
                continue
            on = hopeful(comp, _column(t, "n"), _sketches(t), _column(t, "side"), most, percent)
            if on.any():
                yield from t.filter(pa.array(on)).combine_chunks().to_batches()

    return run


def _open(most: int, percent: int):
    """Links that join components within each pair of blocks."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in _groups(batches):
            sets = [np.frombuffer(s.as_buffer(), np.uint64) for c in t.column("shingles").chunks for s in c]
            found = links_between(_column(t, "node"), _column(t, "comp"), _column(t, "n"), _sketches(t), sets, _column(t, "side"), most, percent)
            if found:
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*found, strict=True)], ["a", "b"])

    return run


@dataclass(frozen=True)
class Classes:
    """Rows with their sets' hash, ids that repeat, classes of equal sets, and the linked classes' components."""

    signed: DataFrame  # id, n, same: a row of the table each
    repeated: DataFrame | None  # ids of more than one row, if there are any
    classes: DataFrame  # node, same, id, n: one row for each set that occurs
    reach: DataFrame  # node, root: classes with a link


def grouped(docs: DataFrame, percent: int = 75, same_id: bool = False) -> Classes:
    """Finds the links between classes of equal shingle sets; with ``same_id``, classes that share an id are linked as well.

    Classes meet in band buckets, and a bucket is not expanded into pairs: its members are compared with
    its first and last one (by number), and links give members labels. Buckets that hold several labels are cut into blocks of
    bounded rows and shingles, and within two blocks at a time documents of different labels are compared; full sets travel only for
    those that lengths and odd sketches leave a chance there. Each pair is dropped by length, then by its odd
    sketch, and what is left is confirmed on the full sets. Labels are contracted before the search for components.
    """
    session_defaults(docs.sparkSession)
    words = docs.select(F.col("doc_id").cast("long").alias("id"), "text")
    signed = save(words.mapInArrow(tidy(_signer), "id long, n long, same binary, bands array<long>, sketch array<long>"), "signed")
    named = signed.filter("id IS NOT NULL")
    repeated = save(named.groupBy("id").agg(F.count("*").alias("rows")).filter("rows > 1").select("id"), "repeated")
    repeated = None if repeated.isEmpty() else repeated
    found = named.filter("n > 0").groupBy("same").agg(F.min_by(F.struct("id", "n", "bands", "sketch"), "id").alias("c"))
    classes = save(found.select(F.monotonically_increasing_id().alias("node"), "same", "c.*"), "classes")  # numbers hold: they are read back
    most = most_odd_bits(percent / 100)

    spread = classes.select("node", "n", F.explode("bands").alias("key"))
    shared = spread.groupBy("key").agg(F.count("*").alias("m"), F.min("node").alias("first"), F.max("node").alias("last")).filter("m > 1").drop("m")
    members = save(spread.join(shared, "key"), "members")
    wanted = save(classes.join(members.select("node").distinct(), "node", "left_semi").select("node", "id", "same"), "wanted")
    facts = classes.select("node", "n", "sketch")

    few = wanted.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS
    texts = words.join(F.broadcast(wanted) if few else wanted, "id")

    def built(rows: DataFrame) -> DataFrame:
        return rows.select("node", "text", "same").mapInArrow(tidy(_setter), "node long, shingles binary")

    if repeated is None:
        sets = save(built(texts), "sets")
    else:  # rows that repeat an id may bring a set more than once
        sets = save(built(texts.join(repeated, "id", "left_anti")).union(built(texts.join(repeated, "id", "left_semi")).dropDuplicates(["node"])), "sets")

    ends = members.select("node", F.explode(F.array("first", "last")).alias("lead")).filter("node <> lead")
    star = ends.select(F.least("node", "lead").alias("a"), F.greatest("node", "lead").alias("b")).distinct()
    x, y = (facts.select(F.col("node").alias(k), F.col("n").alias("n" + k), F.col("sketch").alias("s" + k)) for k in "ab")
    odd = " + ".join(f"bit_count(sa[{p}] ^ sb[{p}])" for p in range(SKETCH_BITS // 64))
    sized = star.join(x, "a").join(y, "b").filter(f"100 * least(na, nb) >= {percent} * greatest(na, nb)").filter(F.expr(odd) <= most).select("a", "b")
    u, v = (sets.select(F.col("node").alias(k), F.col("shingles").alias("s" + k)) for k in "ab")
    links = save(sized.join(u, "a").join(v, "b").select("a", "b", "sa", "sb").mapInArrow(tidy(_confirm(percent)), "a long, b long"), "links")

    # the least neighbour, then its least neighbour: sound labels, mostly whole components already
    near = links.union(links.select("b", "a")).groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("node"), F.least("a", "m").alias("m"))
    near = save(near, "least")
    labels = save(near.join(near.select(F.col("node").alias("m"), F.col("m").alias("label")), "m").select("node", "label"), "labels")

    now = members.join(labels, "node", "left").select("key", "node", "n", F.coalesce("label", "node").alias("comp"))
    blocks = F.greatest(F.ceil(F.count("*") / BLOCK), F.ceil(F.sum("n") / BLOCK_SHINGLES)).cast("int")
    mixed = now.groupBy("key").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), blocks.alias("nb")).filter("lo < hi").select("key", "nb")
    cut = now.join(mixed, "key").withColumn("blk", F.pmod(F.xxhash64("node"), F.col("nb")).cast("int"))
    met = cut.withColumn("o", F.explode(F.sequence(F.lit(0), F.col("nb") - 1))).withColumn("i", F.least("blk", "o")).withColumn("j", F.greatest("blk", "o"))
    met = met.withColumn("side", F.when(F.col("i") == F.col("j"), 2).otherwise((F.col("blk") == F.col("j")).cast("int")))
    shape = "key long, i int, j int, node long, comp long, n long, side int, sketch array<long>"
    cells = met.join(facts.drop("n"), "node").select("key", "i", "j", "node", "comp", "n", "side", "sketch")
    left = save(cells.repartition("key", "i", "j").sortWithinPartitions("key", "i", "j").mapInArrow(tidy(_prune(most, percent)), shape), "left")
    full = left.join(sets, "node").select("key", "i", "j", "node", "comp", "n", "side", "sketch", "shingles")
    more = save(full.repartition("key", "i", "j").sortWithinPartitions("key", "i", "j").mapInArrow(tidy(_open(most, percent)), "a long, b long"), "links")

    if same_id and repeated is not None:
        homes = named.filter("n > 0").join(repeated, "id").join(classes.select("same", "node"), "same").select("id", "node")
        more = more.union(homes.join(homes.groupBy("id").agg(F.min("node").alias("b")), "id").select(F.col("node").alias("a"), "b"))
    links = links.union(more)
    for k in "ab":
        links = links.join(labels.select(F.col("node").alias(k), "label"), k, "left").withColumn(k, F.coalesce("label", k)).drop("label")
    roots = save(components(links), "roots")
    ours = labels.join(roots.withColumnRenamed("node", "label"), "label", "left").select("node", F.coalesce("component", "label").alias("root"))
    reach = ours.union(roots.join(labels, "node", "left_anti").select("node", F.col("component").alias("root")))
    return Classes(signed.select("id", "n", "same"), repeated, classes.select("node", "same", "id", "n"), save(reach, "reach"))


def near_duplicates(docs: DataFrame, percent: int = 75) -> DataFrame:
    """Documents with the component of near-duplicates that each belongs to, by 100 * common >= ``percent`` * union.

    Reads ``doc_id, text``; other columns are ignored. A text with fewer than five words is one
    shingle; null, empty and blank texts have no shingle and link with nothing. ``doc_id`` names a
    document: all rows of an id, whatever their texts, belong to one component. A null id takes no part and comes back
    as its own. Returns ``doc_id, n_shingles, component_id, kept`` for every row; how links are found is told at :func:`grouped`.
    """
    g = grouped(docs, percent, same_id=True)
    linked = g.classes.join(g.reach, "node")
    lows = linked.groupBy("root").agg(F.min("id").alias("low"))
    named = g.classes.select("same", "node", "id").join(g.reach.join(lows, "root").select("node", "low"), "node", "left").select("same", F.coalesce("low", "id").alias("component"))
    out = g.signed.alias("s").join(named.alias("c"), F.col("s.same") == F.col("c.same"), "left").select("s.id", "s.n", F.coalesce("c.component", "s.id").alias("component"))
    if g.repeated is not None:  # an id may have rows without words as well
        least = out.join(g.repeated, "id").groupBy("id").agg(F.min("component").alias("least"))
        out = out.join(least, "id", "left").select("id", "n", F.coalesce("least", "component").alias("component"))
    return out.select(F.col("id").alias("doc_id"), F.col("n").alias("n_shingles"), F.when(F.col("id").isNotNull(), F.col("component")).alias("component_id"), F.coalesce(F.col("component") == F.col("id"), F.lit(True)).alias("kept"))


def one_of_each(docs: DataFrame, percent: int = 75) -> DataFrame:
    """The documents without near-duplicates of another one, with their columns as they came.

    Of texts that links connect, the row with the smallest id stays, of several rows of that id one of any class the smallest in
    number. An id alone connects nothing here: rows that repeat one with unlike texts all stay, and rows whose id and shingle set
    are equal are cut to one, as are rows of one id without words. Rows with a null id all stay.
    """
    g = grouped(docs, percent)
    lost = g.classes.join(g.reach, "node").groupBy("root").agg(F.min(F.struct("id", "node")).alias("m"))
    gone = g.reach.join(lost, "root").filter("node <> m.node").select("node")
    stay = g.classes.join(gone, "node", "left_anti").select("id", "same")
    wordless = g.signed.filter("n = 0 AND id IS NOT NULL").select("id", "same")
    keep = stay.unionByName(wordless)
    own = clear("k", docs.columns)
    lone = keep if g.repeated is None else keep.join(g.repeated, "id", "left_anti")
    d = docs.alias("d")
    names = [F.col(f"d.`{c}`") for c in docs.columns]
    out = d.join(lone.select(F.col("id").alias(own)), F.col("d.doc_id").cast("long") == F.col(own), "left_semi").select(*names).unionByName(docs.filter("doc_id IS NULL"))
    if g.repeated is None:
        return out
    twice = docs.join(g.repeated.select(F.col("id").alias(own)), F.col("doc_id").cast("long") == F.col(own), "left_semi")
    signed = twice.select(F.col("doc_id").cast("long").alias("id"), "text", F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    kind = signed.schema["row"].dataType.simpleString()
    signed = signed.mapInArrow(tidy(_digest), f"id long, same binary, row {kind}").dropDuplicates(["id", "same"])
    kept = signed.alias("d").join(keep.join(g.repeated, "id").distinct().alias("k"), (F.col("d.id") == F.col("k.id")) & F.col("d.same").eqNullSafe(F.col("k.same")), "left_semi")
    return out.unionByName(kept.select("row.*"))
