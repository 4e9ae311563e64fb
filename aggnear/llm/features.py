"""Hashed byte n-gram counts of whole texts, and bounded training samples."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Bytes counted at once; longer texts are counted piece by piece.
_PIECE = 1 << 18


def gram_counts(texts: list[bytes], orders: tuple[int, ...], buckets: int, table: np.ndarray | None = None) -> np.ndarray:
    """texts x buckets counts of hashed byte n-grams; table maps bytes first. N-grams stay within a text."""
    out = np.zeros((len(texts), buckets), np.float32)
    rows, size = [], 0

    def flush():
        if not rows:
            return
        data = np.frombuffer(b"".join(t for _, t in rows), np.uint8)
        if table is not None:
            data = table[data]
        data = data.astype(np.uint32)
        length = np.array([len(t) for _, t in rows])
        own = np.repeat(np.arange(len(rows)), length)
        flat = np.zeros(len(rows) * buckets, np.int64)
        code = np.zeros(len(data), np.uint32)
        for n in range(1, max(orders) + 1):
            code = data if n == 1 else code[:-1] * np.uint32(257) + data[n - 1 :]
            if n in orders:
                first, last = own[: len(code)], own[n - 1 :]
                h = ((code + np.uint32(n)) * np.uint32(2654435761)) >> np.uint32(16)
                at = (first * buckets + h % np.uint32(buckets))[first == last]
                flat += np.bincount(at, minlength=len(flat))
        flat = flat.reshape(len(rows), buckets)
        np.add.at(out, [i for i, _ in rows], flat.astype(np.float32))

    for i, t in enumerate(texts):
        for a in range(0, len(t), _PIECE):
            rows.append((i, t[max(0, a - max(orders) + 1) : a + _PIECE] if a else t[:_PIECE]))
            size += len(rows[-1][1])
            if size > _PIECE or len(rows) >= 64:
                flush()
                rows, size = [], 0
    flush()
    return out


def bucket_of(doc_id: Column, parts: int) -> Column:
    """crc32 of the id as text, modulo parts; null ids give null."""
    return F.crc32(doc_id.cast("string").cast("binary")) % parts


def first_by_hash(rows: DataFrame, n: int, seed: int = 5) -> DataFrame:
    """n rows of least hashed id: a sample that depends on nothing but the ids."""
    return rows.orderBy(F.xxhash64(F.lit(seed), "doc_id"), "doc_id").limit(n)
