"""Document and query vectors: hashed character trigrams, and distinct hashed tokens."""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

_TOKEN = re.compile(r"\w+|[^\w\s]+")
#: Ids that tokens are hashed to, and the table of seeded vectors they stand for.
TOKEN_IDS = 4096


def embed(text: str, dim: int) -> np.ndarray:
    """Unit vector of hashed byte trigrams of the whole text, square roots of counts, signed."""
    raw = np.frombuffer(f" {text.lower()} ".encode("utf-8", "surrogatepass"), np.uint8).astype(np.uint32)
    if len(raw) < 3:
        return np.zeros(dim, np.float32)
    code = (raw[:-2] << np.uint32(16)) ^ (raw[1:-1] << np.uint32(8)) ^ raw[2:]
    h = code * np.uint32(0x9E3779B1)
    h ^= h >> np.uint32(15)
    count = np.bincount((h % np.uint32(dim * 8)).astype(np.int64), minlength=dim * 8)
    sign = np.where(np.arange(dim * 8) // dim % 2, -1.0, 1.0)
    v = (np.sqrt(count) * sign).reshape(8, dim).sum(axis=0)
    return (v / max(float(np.linalg.norm(v)), 1e-12)).astype(np.float32)


def token_ids(text: str) -> list[int]:
    """Distinct hashed tokens of the whole text, ``TOKEN_IDS`` at most."""
    return sorted({zlib.crc32(t.encode("utf-8", "surrogatepass")) % TOKEN_IDS for t in set(_TOKEN.findall(text.lower()))})


def token_table(dim: int, seed: int = 42) -> np.ndarray:
    return np.random.default_rng(seed).normal(size=(TOKEN_IDS, dim)).astype(np.float32) / np.sqrt(dim)


@lru_cache(4)
def token_vectors(dim: int, seed: int = 42) -> np.ndarray:
    """The table in double, made once a process; not to be written to."""
    out = token_table(dim, seed).astype(float)
    out.setflags(write=False)
    return out


def build(docs: DataFrame, dim: int = 128) -> DataFrame:
    """``doc_id, emb, toks`` of whole texts, in one narrow pass."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [t or "" for t in b.column(1).to_pylist()]
            emb = pa.array([embed(t, dim) for t in texts], pa.list_(pa.float32()))
            yield pa.RecordBatch.from_arrays([b.column(0), emb, pa.array([token_ids(t) for t in texts], pa.list_(pa.int32()))], ["doc_id", "emb", "toks"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, emb array<float>, toks array<int>")
