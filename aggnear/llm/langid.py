"""Language identification by nearest centroids.

A text becomes a unit vector of TF-IDF weights over hashed byte n-grams (orders one to three) of its
lower-cased letters. Each language is several centroids, found by spherical k-means over a bounded
sample of labelled texts; a text gets the language of the centroid of largest cosine, and is rejected
if its distance to it is beyond the language's limit, learned from labelled texts held out of a first fit.

Defined results: a null text or one without a letter has language ``und``, score 0, and is rejected;
with no labelled text at all everything is ``und``; texts of any length are read whole; null ids are
not trained on and not held out; repeated rows are judged each; of centroids that are equally near the
first by language name wins; extra columns are not read.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import tokens
from .common import slices, table
from .features import bucket_of, gram_counts

BUCKETS = 4096
ORDERS = (1, 2, 3)
#: Bounds of the training sample: texts per language, and languages.
SAMPLE, LANGUAGES = 300, 200
CENTROIDS = 3
#: Distances beyond this quantile of a language's held-out texts by this part of what is left to 1 are rejected.
QUANTILE, MARGIN = 0.99, 0.4
#: Random letters lie beyond the limit by this, where held-out texts leave room.
CLEAR = 0.02
#: Languages with fewer texts take the limit of the held-out texts of all.
ENOUGH = 20

_LETTERS = np.full(256, 32, np.uint8)
_LETTERS[97:123] = np.arange(97, 123)
_LETTERS[128:] = np.arange(128, 256)


def _lower(text: str | None) -> bytes | None:
    """Lower-cased UTF-8 bytes; None without a letter."""
    if not text or not any(map(str.isalpha, text)):
        return None
    return text.lower().encode("utf-8", "replace")


def _tf(texts: list[bytes]) -> np.ndarray:
    return np.log1p(gram_counts(texts, ORDERS, BUCKETS, _LETTERS))


def _unit(x: np.ndarray) -> np.ndarray:
    return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)


@dataclass
class Model:
    idf: np.ndarray
    centroids: np.ndarray
    names: list[str]
    limit: np.ndarray

    def judge(self, texts: list[bytes]):
        """(language index of the nearest centroid, cosine) per text."""
        cos = _unit(_tf(texts) * self.idf) @ self.centroids.T
        best = cos.argmax(axis=1)
        return best, cos[np.arange(len(texts)), best]


def _cluster(x: np.ndarray, k: int, rng) -> np.ndarray:
    k = min(k, len(x))
    c = x[[0]]
    while len(c) < k:  # farthest first
        c = np.vstack([c, x[[(x @ c.T).max(axis=1).argmin()]]])
    for _ in range(10):
        own = (x @ c.T).argmax(axis=1)
        c = np.vstack([_unit(x[own == i].sum(axis=0, keepdims=True)) if (own == i).any() else c[[i]] for i in range(len(c))])
    return c


def train(docs: DataFrame, sample: int = SAMPLE, centroids: int = CENTROIDS) -> Model | None:
    """Fit on ``sample`` rows of docs(doc_id, text, lang) per language, those of least hashed id."""
    h = F.xxhash64(F.lit(5), "doc_id")
    ids = docs.filter("lang is not null and doc_id is not null and text is not null").select("doc_id", "lang")
    wanted = ids.groupBy("lang").count().orderBy(F.col("count").desc(), "lang").limit(LANGUAGES)
    ids = ids.join(F.broadcast(wanted), "lang")  # at most LANGUAGES rows
    # a share of each language that holds its `sample` least hashes, then exactly those
    ids = ids.filter((h.cast("double") / 2.0**64 + 0.5) * F.col("count") <= sample + 10 * sample**0.5 + 50)
    ids = ids.withColumn("n", F.row_number().over(Window.partitionBy("lang").orderBy(h, "doc_id"))).filter(F.col("n") <= sample)
    ids = ids.select("doc_id").distinct()  # at most SAMPLE * LANGUAGES ids
    rows = docs.join(F.broadcast(ids), "doc_id").filter("lang is not null").select("lang", "text")

    def run(batches):
        tokens.forget()
        for batch in slices(batches):
            lang, text = batch.column(0).to_pylist(), [_lower(t) for t in batch.column(1).to_pylist()]
            for at in range(0, len(text), 64):
                some = [(l, t) for l, t in zip(lang[at : at + 64], text[at : at + 64]) if t]
                if some:
                    tf = _tf([t for _, t in some]).astype("<f2")
                    yield pa.RecordBatch.from_arrays([pa.array([l for l, _ in some]), pa.array([x.tobytes() for x in tf], pa.binary())], names=["lang", "tf"])

    got = sorted((r.lang, bytes(r.tf)) for r in rows.mapInArrow(run, "lang string, tf binary").collect())
    if not got:
        return None
    langs = np.array([g[0] for g in got], dtype=object)
    tf = np.stack([np.frombuffer(g[1], "<f2").astype(np.float32) for g in got])
    idf = np.log((1 + len(tf)) / (1 + (tf > 0).sum(axis=0))).astype(np.float32) + 1
    x = _unit(tf * idf)
    parts, names, held, rng = [], [], {}, None
    for lang in sorted(set(langs)):
        own = x[langs == lang]
        c = _cluster(own, centroids, rng)
        held[lang] = np.concatenate([1 - (own[i::2] @ _cluster(own[1 - i :: 2], centroids, rng).T).max(axis=1) for i in (0, 1)]) if len(own) > 1 else np.zeros(0)
        parts.append(c), names.extend([lang] * len(c))
    every = np.concatenate(list(held.values()))

    rng = np.random.default_rng(5)
    noise = [b" ".join(rng.integers(97, 123, n, dtype=np.uint8).tobytes() for n in rng.integers(2, 10, 300)) for _ in range(32)]
    noise = _unit(_tf(noise) * idf)

    def limit(lang, c):
        far, beyond = held[lang], float((1 - noise @ c).min())
        far = far if len(far) >= ENOUGH else every
        if len(far) < ENOUGH:  # too few to learn from
            far, margin = np.append(far, 0.0), 0.8
            return far.max() + margin * max(0.0, 1 - far.max())
        q = float(np.quantile(far, QUANTILE))
        return max(q, min(q + MARGIN * max(0.0, 1 - q), beyond - CLEAR))

    return Model(idf, np.vstack(parts).astype(np.float32), names, np.array([limit(*x) for x in zip(names, np.vstack(parts))]))


def identify(docs: DataFrame, model: Model | None) -> DataFrame:
    """docs(doc_id, text) -> doc_id, lang_pred, score, distance, rejected."""

    def run(batches):
        tokens.forget()
        for batch in slices(batches):
            low = [_lower(t) for t in batch.column(1).to_pylist()]
            has = [i for i, t in enumerate(low) if t] if model else []
            lang, score, far = ["und"] * len(low), np.zeros(len(low)), np.ones(len(low), bool)
            if has:
                best, cos = model.judge([low[i] for i in has])
                score[has] = np.clip(cos, 0, 1)
                far[has] = 1 - cos > model.limit[best]
                for i, b in zip(has, best):
                    lang[i] = model.names[b]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(lang), pa.array(score), pa.array(1 - score), pa.array(far)], names=["doc_id", "lang_pred", "score", "distance", "rejected"])

    x = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return x.mapInArrow(run, "doc_id long, lang_pred string, score double, distance double, rejected boolean")


def keep_identified(docs: DataFrame, model: Model | None) -> DataFrame:
    """The rows of docs that are not rejected, their columns as they are."""
    names, kinds = docs.columns, docs.schema

    def run(batches):
        tokens.forget()
        for batch in slices(batches):
            low = [_lower(t) for t in batch.column(at_text).to_pylist()]
            has = [i for i, t in enumerate(low) if t]
            stay = np.zeros(len(low), bool)
            if has and model:
                best, cos = model.judge([low[i] for i in has])
                stay[has] = 1 - cos <= model.limit[best]
            yield batch.filter(pa.array(stay))

    at_text = names.index("text")
    return docs.mapInArrow(run, kinds)


def op7_langid(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    model = train(docs.filter(bucket_of(F.col("doc_id"), 3) != 1))
    out = identify(docs, model)
    held = F.coalesce(bucket_of(F.col("doc_id"), 3) == 1, F.lit(False))
    return out.select("doc_id", held.alias("held_out"), "lang_pred", "score", "rejected")
