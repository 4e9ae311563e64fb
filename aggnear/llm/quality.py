"""Quality classifier: random-indexing word vectors, pooled per document, and a small network.

Random indexing: every word (hashed to a bucket) has a fixed sparse ternary index vector; a word's
vector is the sum of the index vectors of its neighbours over the training texts. A text is pooled
into the mean of its words' vectors, the mean of their index vectors, and the mean of the index
vectors of its byte trigrams, which stand in for words never seen. A network of two layers on these,
fitted with numpy, gives a logit, and a temperature fitted on texts kept aside turns it into a
calibrated probability. Word vectors and network are fitted on a bounded sample of labelled texts
(``SAMPLE``); every whole text is scored.

Defined results: null and empty texts are scored like a text without words; without labels of both
kinds the score is the share of label 1 (0.5 without any); a doc_id with several labels counts as its
least; labels other than 0 and 1 are not learned from; null ids are not learned from and not held
out; rows that repeat an id are learned from and scored each; the order of equal scores means
nothing; extra columns are not read.
"""

from __future__ import annotations

from dataclasses import dataclass
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import parallelism, slices, stage, table
from .features import bucket_of, first_by_hash, gram_counts

#: Most labelled texts that the model is fitted on.
SAMPLE = 6000
WORDS, GRAMS, DIM, HIDDEN = 4096, 4096, 64, 32
WINDOW = 2
_CHUNK = 64


def _index_vectors(n: int, seed: int) -> np.ndarray:
    """n sparse ternary rows: eight entries of +1 or -1 each."""
    rng = np.random.default_rng(seed)
    out = np.zeros((n, DIM), np.float32)
    at = np.argsort(rng.random((n, DIM)), axis=1)[:, :8]
    np.put_along_axis(out, at, rng.choice(np.array([-1, 1], np.float32), (n, 8)), axis=1)
    return out


INDEX, GRAM_INDEX = _index_vectors(WORDS, 1), _index_vectors(GRAMS, 2)


class _Buckets(dict):
    def __missing__(self, word):
        if len(self) > 200_000:
            self.clear()
        self[word] = b = crc32(word) % WORDS
        return b


def _words(text: bytes, cache: _Buckets) -> np.ndarray:
    return np.fromiter(map(cache.__getitem__, text.split()), np.int64)


def _neighbours(batches):
    """One task's sums of neighbours' index vectors per word bucket."""
    cache, out = _Buckets(), np.zeros((WORDS, DIM))
    for batch in slices(batches):
        for text in batch.column(0).to_pylist():
            w = _words(text or b"", cache)
            for off in range(1, WINDOW + 1):
                np.add.at(out, w[:-off], INDEX[w[off:]])
                np.add.at(out, w[off:], INDEX[w[:-off]])
    yield pa.RecordBatch.from_arrays([pa.array([out.astype("<f8").tobytes()], pa.binary())], names=["sums"])


def pool(texts: list[bytes | None], vectors: np.ndarray) -> np.ndarray:
    """Texts -> pooled features."""
    cache = _Buckets()
    texts = [t or b"" for t in texts]
    words = np.stack([np.bincount(_words(t, cache), minlength=WORDS) for t in texts]).astype(np.float32)
    grams = gram_counts(texts, (3,), GRAMS)
    n, g = np.maximum(words.sum(axis=1, keepdims=True), 1), np.maximum(grams.sum(axis=1, keepdims=True), 1)
    return np.hstack([words / n @ vectors, words / n @ INDEX, grams / g @ GRAM_INDEX]).astype(np.float32)


@dataclass
class Network:
    mean: np.ndarray
    scale: np.ndarray
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: float
    temperature: float = 1.0

    def logits(self, x: np.ndarray) -> np.ndarray:
        return np.tanh((x - self.mean) / self.scale @ self.w1 + self.b1) @ self.w2 + self.b2

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.logits(x) / self.temperature, -50, 50)))


def _loss(z, y) -> float:
    return float(np.mean(np.logaddexp(0, z) - y * z))


def fit(x: np.ndarray, y: np.ndarray, seed: int = 3, steps: int = 400) -> Network:
    """Adam on the logistic loss with weight decay; a fifth of the rows sets the temperature and the stopping step."""
    rng = np.random.default_rng(seed)
    aside = np.arange(len(x)) % 5 == 0
    xs, ys, xv, yv = x[~aside], y[~aside], x[aside], y[aside]
    mean, scale = xs.mean(axis=0), xs.std(axis=0) + 1e-6
    a, av = (xs - mean) / scale, (xv - mean) / scale
    p = [rng.standard_normal((x.shape[1], HIDDEN)) / np.sqrt(x.shape[1]), np.zeros(HIDDEN), rng.standard_normal(HIDDEN) / np.sqrt(HIDDEN), np.zeros(1)]
    m, v, best = [np.zeros_like(q) for q in p], [np.zeros_like(q) for q in p], (np.inf, p)
    for t in range(1, steps + 1):
        h = np.tanh(a @ p[0] + p[1])
        z = h @ p[2] + p[3][0]
        d = (1 / (1 + np.exp(-z)) - ys) / len(ys)
        dh = np.outer(d, p[2]) * (1 - h * h)
        grads = [a.T @ dh + 1e-3 * p[0], dh.sum(axis=0), h.T @ d + 1e-3 * p[2], np.array([d.sum()])]
        for i, g in enumerate(grads):
            m[i] = 0.9 * m[i] + 0.1 * g
            v[i] = 0.999 * v[i] + 0.001 * g * g
            p[i] = p[i] - 0.01 * (m[i] / (1 - 0.9**t)) / (np.sqrt(v[i] / (1 - 0.999**t)) + 1e-8)
        if t % 10 == 0 and len(yv):
            now = _loss(np.tanh(av @ p[0] + p[1]) @ p[2] + p[3][0], yv)
            best = min(best, (now, [q.copy() for q in p]), key=lambda b: b[0])
    p = best[1] if len(yv) else p
    net = Network(mean, scale, p[0], p[1], p[2], float(p[3][0]))
    if len(yv):
        z = net.logits(xv)
        net.temperature = min(np.geomspace(0.25, 8, 60), key=lambda s: _loss(z / s, yv))
    return net


@dataclass
class Model:
    vectors: np.ndarray
    net: Network | None
    share: float

    def score(self, texts) -> np.ndarray:
        if self.net is None:
            return np.full(len(texts), self.share)
        return np.concatenate([self.net.score(pool(texts[a : a + _CHUNK], self.vectors)) for a in range(0, len(texts), _CHUNK)] or [np.zeros(0)])


def train(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> Model:
    """docs(doc_id, text), labels(doc_id, quality): fit on the ``sample`` labelled rows of least hashed id."""
    given = labels.filter("quality in (0, 1) and doc_id is not null").groupBy("doc_id").agg(F.min("quality").alias("quality"))
    given = first_by_hash(given, sample)
    rows = docs.select("doc_id", F.col("text").cast("binary").alias("text")).join(F.broadcast(given), "doc_id")  # at most `sample` rows
    few = stage(rows.coalesce(max(1, min(16, parallelism(docs.sparkSession)))), "quality-sample")  # a bounded sample in few files, so few sums come back
    sums = few.select("text").mapInArrow(_neighbours, "sums binary").collect()
    vectors = sum((np.frombuffer(bytes(r.sums), "<f8").reshape(WORDS, DIM) for r in sums), np.zeros((WORDS, DIM)))
    vectors = (vectors / np.maximum(np.linalg.norm(vectors, axis=1, keepdims=True), 1e-9)).astype(np.float32)

    def run(batches):
        for part in slices(batches, _CHUNK):
            x = pool(part.column(1).to_pylist(), vectors)
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array([r.astype("<f4").tobytes() for r in x], pa.binary()), part.column(2)], names=["doc_id", "x", "y"])

    got = sorted((r.doc_id, bytes(r.x), r.y) for r in few.select("doc_id", "text", F.col("quality").cast("long").alias("y")).mapInArrow(run, "doc_id long, x binary, y long").collect())
    y = np.array([g[2] for g in got], float)
    share = float(y.mean()) if len(y) else 0.5
    if len(set(y)) < 2:
        return Model(vectors, None, share)
    order = np.random.default_rng(0).permutation(len(got))
    x = np.stack([np.frombuffer(g[1], "<f4") for g in got]).astype(float)
    return Model(vectors, fit(x[order], y[order]), share)


def score(docs: DataFrame, model: Model) -> DataFrame:
    """docs(doc_id, text) -> doc_id, score."""

    def run(batches):
        for batch in slices(batches):
            s = model.score(batch.column(1).to_pylist())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.asarray(s, float))], names=["doc_id", "score"])

    x = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("text"))
    return x.mapInArrow(run, "doc_id long, score double")


def op9_quality(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    labels = table(spark, sf_dir, "labels").select("doc_id", "quality").filter(bucket_of(F.col("doc_id"), 5) != 0)
    out = score(docs, train(docs, labels))
    held = F.coalesce(bucket_of(F.col("doc_id"), 5) == 0, F.lit(False))
    return out.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))
