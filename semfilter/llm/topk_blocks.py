"""Exact top-k by inner product, pruning whole blocks by summed term maxima."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import save, session_defaults

#: Vectors in one block of a forward index, in one segment (and components, for long vectors), and queries travelling together.
BLOCK, SEGMENT, CELLS, QUERIES = 64, 32_768, 1 << 21, 4096
#: Segments of smaller tables hold so many vectors, up to so many segments; segments that one task meets, where there are many.
LITTLE, SPREAD, TILE = 2048, 16, 4
#: Queries scored together, best blocks each of them takes first, and blocks after which kth scores are renewed.
TOGETHER, AHEAD, RENEW = 1024, 4, 16
#: Scores beyond these stand at them; the least one also says that no kth score is known.
LEAST, MOST = -(2**63), 2**63 - 1
INDEX = "seg int, dim int, kind string, ids binary, copies binary, docs binary, most binary, least binary"
ASKED = "dim int, asked string, qids binary, queries binary, floors binary, firsts binary"


def quantised(vectors: DataFrame, scale: int = 256) -> DataFrame:
    """``vec_id`` and ``terms``, floor(scale * x) of each component in double, kept within a long; unusable vectors are left out."""
    usable = F.col("embedding").isNotNull() & ~F.exists("embedding", lambda x: x.isNull() | F.isnan(x) | (F.abs(x.cast("double")) == float("inf")))
    terms = F.transform("embedding", lambda x: F.floor(x.cast("double") * scale).cast("long"))
    return vectors.filter("vec_id IS NOT NULL").filter(usable).select(F.col("vec_id").cast("long").alias("vec_id"), terms.alias("terms"))


def _kind(a: np.ndarray, b: np.ndarray) -> type:
    """Numbers in which every sum of products is exact: floats, longs or, beyond those, Python's own."""
    if not a.size or not b.size:
        return np.int64
    most = float(np.abs(a.astype(float)).max()) * float(np.abs(b.astype(float)).max()) * a.shape[1]
    return np.float32 if most < 2.0**24 else np.float64 if most < 2.0**53 else np.int64 if most < 2.0**62 else object


def bounds(queries: np.ndarray, most: np.ndarray, least: np.ndarray) -> np.ndarray:
    """Sum over terms of the larger product of each query with each block's largest and least value."""
    return np.maximum(queries, 0) @ most.T + np.minimum(queries, 0) @ least.T


@dataclass(frozen=True)
class Segment:
    """A range of documents cut into blocks: forward rows, and the largest and least value of every term in each block."""

    ids: np.ndarray
    copies: np.ndarray
    docs: np.ndarray
    most: np.ndarray
    least: np.ndarray

    @classmethod
    def of(cls, ids: np.ndarray, docs: np.ndarray, copies: np.ndarray | None = None) -> Segment:
        cuts = np.arange(0, len(ids), BLOCK)
        return cls(ids, np.ones(len(ids), np.int64) if copies is None else copies, docs, np.maximum.reduceat(docs, cuts, axis=0), np.minimum.reduceat(docs, cuts, axis=0))

    def search(self, qids: np.ndarray, queries: np.ndarray, k: int, floors: np.ndarray | None = None) -> tuple[tuple, np.ndarray]:
        """Best k rows for each query, with repeats, as arrays of query, id and score, and how many blocks were scored for each.

        Unless their kth scores are known, queries take their blocks of the best bounds first; then all others whose bound reaches a query's
        kth score are scored, together for such queries; an equal bound is still scored for its ties. ``floors`` has kth scores that are known already (``LEAST``: not).
        """
        kind = _kind(queries, self.docs)
        docs, most, least = (x.astype(kind) for x in (self.docs, self.most, self.least))
        floors = np.full(len(qids), LEAST) if floors is None else floors
        got, scored = [], np.zeros(len(qids), np.int64)
        for lo in range(0, len(qids), TOGETHER):
            part = slice(lo, lo + TOGETHER)
            asked = queries[part].astype(kind)
            one = self._by_query if kind is object else self._together
            found, scored[part] = one(qids[part], asked, docs, bounds(asked, most, least), k, floors[part])
            got.append(found)
        return tuple(np.concatenate([g[i] for g in got]) if got else np.zeros(0, np.int64) for i in range(3)), scored

    def _together(self, qids: np.ndarray, asked: np.ndarray, docs: np.ndarray, bound: np.ndarray, k: int, floors: np.ndarray) -> tuple[tuple, np.ndarray]:
        kth, many = floors.copy(), np.zeros(len(qids), np.int64)
        top, fresh = [np.zeros(0, np.int64)] * 3, []

        def renew() -> None:
            nonlocal top, fresh
            if not fresh:
                return
            q, s, i = (np.concatenate(x) for x in zip(top, *fresh, strict=True))
            order = np.lexsort((i, -s, q))
            q, s, i = q[order], s[order], i[order]
            rank = np.arange(len(q)) - np.searchsorted(q, q)
            top, fresh = [x[rank < k] for x in (q, s, i)], []
            last = rank == k - 1
            kth[q[last]] = np.maximum(kth[q[last]], s[last])

        def score(b: int, on: np.ndarray) -> None:
            at = slice(b * BLOCK, (b + 1) * BLOCK)
            many[on] += 1
            s = (asked if len(on) == len(asked) else asked[on]) @ docs[at].T
            q, r = np.divmod(np.flatnonzero((s >= kth[on].astype(s.dtype)[:, None]).ravel()), s.shape[1])
            ids = self.ids[at][r]
            other = ids != qids[on[q]]
            q, r, ids = q[other], r[other], ids[other]
            if len(q):
                n = np.minimum(self.copies[at][r], k)
                fresh.append([np.repeat(x, n) for x in (on[q], s[q, r].astype(np.int64), ids)])

        def reached(b: int) -> np.ndarray:
            return bound[:, b] >= kth.astype(bound.dtype)

        blocks, ahead = bound.shape[1], min(AHEAD, bound.shape[1]) if (floors == LEAST).any() else 0
        turn = np.argsort(-bound, axis=1, kind="stable")[:, :ahead] if ahead else None
        done = np.zeros(bound.shape, bool)
        for j in range(ahead):
            for b in np.unique(turn[:, j]).tolist():
                on = np.flatnonzero((turn[:, j] == b) & reached(b))
                if len(on):
                    score(b, on)
            done[np.arange(len(qids)), turn[:, j]] = True
            renew()
        for n, b in enumerate(np.argsort(-bound.max(axis=0), kind="stable").tolist() if blocks > ahead else [], 1):
            on = np.flatnonzero(~done[:, b] & reached(b))
            if len(on):
                score(b, on)
            if n % RENEW == 0:
                renew()
        renew()
        q, s, i = top
        return (qids[q], i, s), many

    def _by_query(self, qids: np.ndarray, asked: np.ndarray, docs: np.ndarray, bound: np.ndarray, k: int, floors: np.ndarray) -> tuple[tuple, np.ndarray]:
        """The same for sums beyond a long, in Python's integers."""
        turn = np.argsort(-bound, axis=1, kind="stable")
        out, scored = [], np.zeros(len(qids), np.int64)
        for q, own in enumerate(qids.tolist()):
            top: list[tuple] = []
            kth = None if floors[q] == LEAST else int(floors[q])
            for b in turn[q].tolist():
                if kth is not None and bound[q, b] < kth:
                    break
                scored[q] += 1
                at = slice(b * BLOCK, (b + 1) * BLOCK)
                s = docs[at] @ asked[q]
                keep = self.ids[at] != own if kth is None else (self.ids[at] != own) & (s >= kth).astype(bool)
                if keep.any():
                    found = zip(s[keep].tolist(), self.ids[at][keep].tolist(), self.copies[at][keep].tolist(), strict=True)
                    top = sorted([*top, *((-int(x), i) for x, i, n in found for _ in range(min(n, k)))])[:k]
                    if len(top) == k:
                        kth = -top[-1][0] if kth is None else max(kth, -top[-1][0])
            out += [(own, i, min(MOST, max(LEAST, -x))) for x, i in top]
        return tuple(np.array([o[i] for o in out], np.int64) for i in range(3)), scored


def search_segment(ids: np.ndarray, docs: np.ndarray, qids: np.ndarray, queries: np.ndarray, k: int) -> tuple[list, int]:
    """Best k of one segment for some queries, and how many blocks were scored in all."""
    found, scored = Segment.of(ids, docs).search(qids, queries, k)
    return list(zip(*(x.tolist() for x in found), strict=True)), int(scored.sum())


def _narrow(*arrays: np.ndarray) -> tuple[str, list[bytes]]:
    """The shortest integers that hold all of the arrays, and the arrays so written."""
    ends = [int(e) for a in arrays if a.size for e in (a.min(), a.max())]
    kind = next(x for x in ("<i2", "<i4", "<i8") if all(np.iinfo(x).min <= e <= np.iinfo(x).max for e in ends))
    return kind, [a.astype(kind).tobytes() for a in arrays]


def _matrix(raw: bytes, dim: int, kind: str) -> np.ndarray:
    return np.frombuffer(raw, kind).reshape(-1, dim)


def _pack(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Rows of a range, in order of their ids, as segments of one length of vectors."""

    def packed(rows: pd.DataFrame, dim: int) -> pd.DataFrame:
        docs = np.stack(rows["terms"].to_numpy()).astype("<i8").reshape(len(rows), dim)
        seg = Segment.of(rows["vec_id"].to_numpy("<i8"), docs, rows["copies"].to_numpy("<i8"))
        kind, blobs = _narrow(seg.docs, seg.most, seg.least)
        own = {c: [getattr(seg, c).astype("<i8").tobytes()] for c in ("ids", "copies")}
        return pd.DataFrame({"seg": [int(rows["seg"].iloc[0])], "dim": [dim], "kind": [kind], **own, **{c: [x] for c, x in zip(("docs", "most", "least"), blobs, strict=True)}})

    held: dict[int, list[pd.DataFrame]] = {}
    for part in parts:
        for dim, rows in part.groupby("dim", sort=True):
            held.setdefault(int(dim), []).append(rows)
            if sum(map(len, held[int(dim)])) >= min(SEGMENT, max(BLOCK, CELLS // int(dim))):
                yield packed(pd.concat(held.pop(int(dim))), int(dim))
    for dim, rows in held.items():
        yield packed(pd.concat(rows), dim)


def _gather(*keys: str):
    """Queries of one group as one row, with what is known of them."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("vec_id")
        own = {k: [int(pdf[k].iloc[0])] for k in keys}
        kind, (queries,) = _narrow(np.stack(pdf["terms"].to_numpy()))
        known = {name: [pdf[c].to_numpy("<i8").tobytes()] for name, c in (("qids", "vec_id"), ("floors", "kth"), ("firsts", "first"))}
        return pd.DataFrame({**own, "asked": [kind], "queries": [queries], **known})

    return run


def _promise(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """The best bound of each query in the segments that a task meets, and the first segment that has it."""
    best: dict[tuple, tuple] = {}
    for part in parts:
        for row in part.itertuples(index=False):
            queries, most, least = _matrix(row.queries, row.dim, row.asked), _matrix(row.most, row.dim, row.kind), _matrix(row.least, row.dim, row.kind)
            bound = np.concatenate([bounds(queries[lo : lo + TOGETHER].astype(float), most.astype(float), least.astype(float)).max(axis=1) for lo in range(0, len(queries), TOGETHER)])
            seg, key = np.full(len(bound), row.seg, np.int64), (row.dim, row.qids)
            if key in best:
                had, where = best[key]
                better = (bound > had) | ((bound == had) & (seg < where))
                bound, seg = np.where(better, bound, had), np.where(better, seg, where)
            best[key] = bound, seg
    for (_, qids), (bound, seg) in best.items():
        yield pd.DataFrame({"vec_id": np.frombuffer(qids, "<i8"), "seg": seg.astype(np.int32), "bound": bound})


def _search(k: int, first: bool, count: bool = False):
    """Searches a segment for some queries: for those whose first segment it is, or for the others, from their kth scores on."""

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in parts:
            for row in part.itertuples(index=False):
                qids, floors, firsts = (np.frombuffer(x, "<i8") for x in (row.qids, row.floors, row.firsts))
                on = (firsts == row.seg) == first
                seg = Segment(*(np.frombuffer(x, "<i8") for x in (row.ids, row.copies)), *(_matrix(x, row.dim, row.kind) for x in (row.docs, row.most, row.least)))
                found, scored = seg.search(qids[on], _matrix(row.queries, row.dim, row.asked)[on], k, floors[on])
                if count:
                    yield pd.DataFrame({"query_id": qids[on], "blocks": len(seg.most), "scored": scored})
                else:
                    yield pd.DataFrame(dict(zip(("query_id", "vec_id", "score"), found, strict=True)))

    return run


def _parts(total: int) -> int:
    """Ranges that documents are cut into."""
    return max(1, -(-total // SEGMENT), min(SPREAD, -(-total // LITTLE)))


def _rounds(vectors: DataFrame, is_query: str, k: int, scale: int, count: bool = False) -> DataFrame:
    session_defaults(vectors.sparkSession)
    terms = quantised(vectors, scale).withColumn("dim", F.size("terms")).filter("dim > 0")
    rows = save(terms.groupBy("vec_id", "dim", "terms").agg(F.count("*").alias("copies")), "terms")
    total, n_asked = rows.count(), rows.filter(is_query).count()
    ranged = rows.repartitionByRange(_parts(total), "vec_id", F.xxhash64("terms")).sortWithinPartitions("vec_id", "terms")
    index = save(ranged.withColumn("seg", F.spark_partition_id()).mapInPandas(_pack, INDEX), "index")
    last = index.agg(F.max("seg")).first()[0] or 0
    wide = max(1, min(TILE, last // 64))
    index = index.withColumn("tile", F.expr(f"seg div {wide}").cast("int"))

    asked = rows.filter(is_query).groupBy("vec_id").agg(F.min("terms").alias("terms")).withColumn("dim", F.size("terms"))
    asked = asked.withColumn("grp", F.pmod(F.xxhash64(F.lit(7), "vec_id"), F.lit(max(1, -(-n_asked // QUERIES)))).cast("int")).withColumn("kth", F.lit(LEAST))
    everywhere = F.explode(F.sequence(F.lit(0), F.lit(last // wide))).alias("tile")

    # every join is a merge: what is joined grows with the table, so none of it may be gathered on the driver for a broadcast
    groups = asked.withColumn("first", F.lit(-1)).groupBy("grp", "dim").applyInPandas(_gather("grp", "dim"), f"grp int, {ASKED}")
    blocks = index.select("tile", "seg", "dim", "kind", "most", "least")
    promised = groups.drop("grp").select("*", everywhere).join(blocks.hint("merge"), ["tile", "dim"]).mapInPandas(_promise, "vec_id long, seg int, bound double")
    firsts = save(promised.groupBy("vec_id").agg(F.max_by("seg", F.struct("bound", -F.col("seg"))).alias("first")), "firsts")

    known = asked.join(firsts.hint("merge"), "vec_id")
    shares = firsts.groupBy("first").agg(F.ceil(F.count("*") / QUERIES).alias("shares"))
    shared = known.join(shares.hint("merge"), "first").withColumn("share", F.expr("pmod(xxhash64(7, vec_id), shares)").cast("int"))
    own = shared.withColumn("seg", F.col("first")).groupBy("seg", "share", "dim").applyInPandas(_gather("seg", "dim", "share"), f"seg int, share int, {ASKED}")
    met = own.join(index.hint("merge"), ["seg", "dim"]).repartition("seg", "share")
    answer = "query_id long, blocks long, scored long" if count else "query_id long, vec_id long, score long"
    near = save(met.mapInPandas(_search(k, True), "query_id long, vec_id long, score long"), "near")
    kth = near.groupBy("query_id").agg(F.sort_array(F.collect_list("score"), asc=False).alias("s")).select(F.col("query_id").alias("vec_id"), F.get("s", F.lit(k - 1)).alias("kth"))
    again = known.drop("kth").join(kth.hint("merge"), "vec_id", "left").withColumn("kth", F.coalesce("kth", F.lit(LEAST))).groupBy("grp", "dim").applyInPandas(_gather("grp", "dim"), f"grp int, {ASKED}")
    rest = again.drop("grp").select("*", everywhere).join(index.hint("merge"), ["tile", "dim"]).mapInPandas(_search(k, False, count), answer)
    return met.mapInPandas(_search(k, True, True), answer).union(rest) if count else near.union(rest)


def top_k(vectors: DataFrame, is_query: str = "vec_id % 50 = 0", k: int = 5, scale: int = 256) -> DataFrame:
    """The k vectors with the highest integer inner product for each query row, ties to the smaller id.

    Vectors in order of their ids are cut into segments, and those into blocks of ``BLOCK`` with their terms' largest and least values.
    A query's bound for a block sums these by term. It is searched first in the segment that has its best bound, block by block in falling
    order of bounds until they are below its kth score; that kth score goes with it into all other segments, where only blocks
    whose bound reaches it are scored and only rows that reach it are returned. Queries meet segments in groups of about ``QUERIES``; no pair leaves a task.

    Vectors that are null, empty or hold null or non-finite components take no part, as query or as
    candidate; vectors only meet queries of their own length. Every row is a candidate, so rows that repeat an id may fill several ranks, but
    a query never finds its own id; of several rows of an id that asks, the least by value does. Terms and scores beyond a long stand at its limits,
    order and bounds are exact all the same. Fewer candidates than k give fewer rows; an empty table gives none. Returns ``query_id, rank, vec_id, score``.
    """
    found = _rounds(vectors, is_query, k, scale)
    rank = F.row_number().over(W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", rank).filter(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def pruning(vectors: DataFrame, is_query: str = "vec_id % 50 = 0", k: int = 5, scale: int = 256) -> DataFrame:
    """How many blocks there are for each query, and how many of them :func:`top_k` scores: ``query_id, blocks, scored``."""
    return _rounds(vectors, is_query, k, scale, count=True).groupBy("query_id").agg(F.sum("blocks").alias("blocks"), F.sum("scored").alias("scored"))
