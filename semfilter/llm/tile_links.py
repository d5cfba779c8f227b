"""Near-duplicate vectors: int8 tile products with rigorous bounds, full precision where they leave doubt."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import components, save, session_defaults

#: Vectors in one block; two blocks make a tile.
BLOCK = 2048
#: Pairs recomputed in double precision at a time.
CHUNK = 32_768


def quantise(unit: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Int8 codes of unit rows, each row's scale, the norm of what the codes stand for, and the norm of what they miss."""
    scale = np.maximum(np.abs(unit).max(axis=1), 1e-300) / 127
    codes = np.rint(unit / scale[:, None]).astype(np.int8)
    stood = codes * scale[:, None]
    return codes, scale, np.linalg.norm(stood, axis=1), np.linalg.norm(unit - stood, axis=1)


def code_products(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Exact integer products of int8 rows; float32 holds every partial sum below 2**24."""
    out = np.zeros((len(a), len(b)), np.float32 if a.shape[1] <= 1024 else np.float64)
    for c in range(0, a.shape[1], 1024):
        out += a[:, c : c + 1024].astype(np.float32) @ b[:, c : c + 1024].astype(np.float32).T
    return out


def tile(left: np.ndarray, right: np.ndarray, threshold: float) -> tuple[np.ndarray, np.ndarray, int]:
    """Index pairs of rows whose cosine in double precision reaches the threshold; and pairs recomputed.

    With codes standing for u' and missing e, the product of two rows differs from that of their
    codes by at most |u'||f| + |e||v'| + |e||f|. Pairs surely above or below by that bound are
    settled; the others are recomputed from the vectors themselves.
    """
    ln, rn = np.linalg.norm(left, axis=1), np.linalg.norm(right, axis=1)
    lq, ls, lu, le = quantise(left / ln[:, None])
    rq, rs, ru, re = quantise(right / rn[:, None])
    near = code_products(lq, rq) * ls[:, None] * rs[None, :]
    slack = lu[:, None] * re[None, :] + le[:, None] * ru[None, :] + le[:, None] * re[None, :] + 1e-6
    sure = near - slack >= threshold
    doubt = (near + slack >= threshold) & ~sure
    i, j = np.nonzero(doubt)
    good = np.zeros(len(i), bool)
    for c in range(0, len(i), CHUNK):
        s = slice(c, c + CHUNK)
        good[s] = np.einsum("ij,ij->i", left[i[s]], right[j[s]]) / (ln[i[s]] * rn[j[s]]) >= threshold
    si, sj = np.nonzero(sure)
    return np.concatenate([si, i[good]]), np.concatenate([sj, j[good]]), len(i)


def forest(i: np.ndarray, j: np.ndarray, n: int) -> np.ndarray:
    """Least index reachable from each of n nodes over the pairs."""
    label = np.arange(n)
    while len(i):
        m = np.minimum(label[i], label[j])
        new = label.copy()
        np.minimum.at(new, i, m)
        np.minimum.at(new, j, m)
        np.minimum.at(new, label[i], m)
        np.minimum.at(new, label[j], m)
        new = new[new]
        if (new == label).all():
            break
        label = new
    return label


def _tiles(threshold: float):
    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in parts:
            for row in part.itertuples(index=False):
                a, b = np.frombuffer(row.ids, "<i8"), np.frombuffer(row.ids2, "<i8")
                u = np.frombuffer(row.vecs, "<f8").reshape(len(a), -1)
                v = np.frombuffer(row.vecs2, "<f8").reshape(len(b), -1)
                i, j, _ = tile(u, v, threshold)
                one = row.i == row.j
                keep = (a[i] != b[j]) & ((i < j) if one else True)
                i, j = i[keep], j[keep]
                ids = a if one else np.concatenate([a, b])
                far = j if one else j + len(a)
                links = np.bincount(i, minlength=len(ids)) + np.bincount(far, minlength=len(ids))
                order = np.argsort(ids, kind="stable")  # least index becomes least id
                place = np.empty(len(ids), np.int64)
                place[order] = np.arange(len(ids))
                root = ids[order][forest(place[i], place[far], len(ids))][place]
                hit = links > 0
                yield pd.DataFrame({"vec_id": ids[hit], "links": links[hit], "root": root[hit]})

    return run


def _pack(pdf: pd.DataFrame) -> pd.DataFrame:
    pdf = pdf.sort_values("vec_id")
    return pd.DataFrame({"label": [pdf["label"].iloc[0]], "dim": [pdf["dim"].iloc[0]], "i": [pdf["i"].iloc[0]], "n": [pdf["n"].iloc[0]], "ids": [pdf["vec_id"].to_numpy("<i8").tobytes()], "vecs": [np.stack(pdf["v"].to_numpy()).astype("<f8").tobytes()]})


def near_vectors(vectors: DataFrame, threshold: float = 0.93) -> DataFrame:
    """Links and components of vectors of one label with cosine at or above ``threshold``.

    A label's vectors are cut by hash into blocks of about ``BLOCK``, whatever its share of the rows;
    every two blocks of a label make a tile, and tiles are the unit of work. A tile returns one row
    for each linked vector: how many links it has there, and the least id it reaches there; sums
    and a component search over those stars give the whole. Pairs stay inside the tile.

    Vectors that are null, zero, empty or hold null or non-finite components, and rows with a null label
    or id, link with nothing. Rows of equal id do not link with each other. Every row of the table
    comes back once: ``vec_id, label, n_links, component_id, kept``.
    """
    session_defaults(vectors.sparkSession)
    usable = F.col("embedding").isNotNull() & ~F.exists("embedding", lambda x: x.isNull() | F.isnan(x) | (F.abs(x.cast("double")) == float("inf"))) & F.exists("embedding", lambda x: x != 0)
    rows = vectors.filter("vec_id IS NOT NULL AND label IS NOT NULL").filter(usable)
    rows = rows.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("label").cast("string").alias("label"), F.size("embedding").alias("dim"), F.col("embedding").cast("array<double>").alias("v"))
    blocks = rows.groupBy("label", "dim").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("n"))
    cut = rows.join(blocks, ["label", "dim"]).withColumn("i", F.pmod(F.xxhash64("vec_id"), F.col("n")).cast("int"))
    packed = save(cut.groupBy("label", "dim", "i").applyInPandas(_pack, "label string, dim int, i int, n int, ids binary, vecs binary"), "blocks")
    first = packed.withColumn("j", F.explode(F.sequence("i", F.col("n") - 1)))
    second = packed.select("label", "dim", F.col("i").alias("j"), F.col("ids").alias("ids2"), F.col("vecs").alias("vecs2"))
    width = max(1, vectors.sparkSession.sparkContext.defaultParallelism)
    met = first.join(second, ["label", "dim", "j"]).repartition(width * 4, "label", "i", "j").select("i", "j", "ids", "vecs", "ids2", "vecs2")
    stars = save(met.mapInPandas(_tiles(threshold), "vec_id long, links long, root long"), "stars")
    links = stars.groupBy("vec_id").agg(F.sum("links").alias("n_links"))
    reach = components(stars.filter("vec_id <> root"), "vec_id", "root")
    found = links.alias("l").join(reach.alias("r"), F.col("l.vec_id") == F.col("r.node"), "left").select(F.col("l.vec_id").alias("_id"), "n_links", "component")
    out = vectors.select("vec_id", "label").alias("a").join(found.alias("b"), F.col("a.vec_id") == F.col("b._id"), "left")
    comp = F.coalesce("b.component", F.col("a.vec_id").cast("long"))
    return out.select("a.vec_id", "a.label", F.coalesce("b.n_links", F.lit(0)).cast("long").alias("n_links"), comp.alias("component_id"), F.coalesce(comp == F.col("a.vec_id"), F.lit(True)).alias("kept"))
