"""Embedding near-duplicates through spherical-cap filters.

A filter is a direction; a vector passes it if their inner product reaches the cap height. The
directions are products of small random codes: the (randomly rotated) space is cut into a few
blocks, each block has its own codewords, and every combination of one codeword per block is a
direction. A vector's passing directions are found by list decoding: combinations are grown block
by block and dropped as soon as the best completion stays below the cap. Vectors of a label that
share a direction are compared exactly, in double precision; a pair that shares several counts in
the least of them only.

Parameters follow the number of vectors: ``PER_VECTOR`` expected directions for each vector in each
of ``CODES`` independent codes, and so many directions in all that one holds about ``PER_FILTER`` vectors of the largest label. Work and
rows moved thus grow in proportion to the input. Copies of one vector are one node with a
multiplicity; a direction held by more than ``BLOCK`` vectors is compared in pairs of salted blocks,
so no task gets an unbounded group and no pair of vectors becomes a row.

Defined results: vectors that are null, zero, or hold null or non-finite components, and those with a
null label, link with nothing; vectors of different lengths do not link; rows that repeat a vec_id
are one vector (the least by label and components); a null vec_id gives one row without component;
extra columns are not read; an empty table gives an empty result.
"""

from __future__ import annotations

import math
from statistics import NormalDist

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import parallelism, stage, table
from .components import components
from .topk import usable

PER_VECTOR = 13
PER_FILTER = 48
#: Independent codes for labels of 5000 vectors, two more for each power of ten: a pair that one code separates is rarely separated by the others.
CODES = 3
BLOCK = 2048
_CAP = "label long, code long, rep long, mult long, codes binary, vec binary"
_FOUND = pa.schema([("rep", pa.int64()), ("n", pa.int64()), ("low", pa.int64())])


class Code:
    """Random product code for vectors of one length; equal arguments give an equal code everywhere."""

    def __init__(self, dim: int, filters: int, per_vector: float, seed: int = 11):
        rng = np.random.default_rng([seed, dim])
        self.blocks = 1
        while self.blocks < dim and filters ** (1 / self.blocks) > 128:
            self.blocks += 1
        self.blocks = min(max(self.blocks, 2), dim)
        self.words = max(2, int(np.ceil(filters ** (1 / self.blocks))))
        self.turn = np.linalg.qr(rng.standard_normal((dim, dim)))[0]
        self.cuts = np.linspace(0, dim, self.blocks + 1).astype(int)
        self.books = []
        for a, b in zip(self.cuts, self.cuts[1:]):
            w = rng.standard_normal((b - a, self.words))
            self.books.append(w / np.linalg.norm(w, axis=0) / np.sqrt(self.blocks))
        share = min(per_vector / self.words**self.blocks, 0.5)
        self.cap = NormalDist().inv_cdf(1 - share) / np.sqrt(dim)
        # sums of few codewords have thinner tails than the normal law: lower the cap until vectors pass as many as wanted
        probe = rng.standard_normal((200, dim))
        probe /= np.linalg.norm(probe, axis=1, keepdims=True)
        while self.cap > 0 and len(self.decode(probe)[0]) < per_vector * len(probe):
            self.cap -= 0.005

    def decode(self, v: np.ndarray):
        """Unit rows -> (row, direction) of all directions whose cap holds the row."""
        v = v @ self.turn
        s = [v[:, a:b] @ w for a, b, w in zip(self.cuts, self.cuts[1:], self.books)]
        best = [x.max(axis=1) for x in s]
        rest = [sum(best[b + 1 :], np.zeros(len(v))) for b in range(self.blocks)]
        row, code, total = np.arange(len(v)), np.zeros(len(v), np.int64), np.zeros(len(v))
        for b in range(self.blocks):
            grown = total[:, None] + s[b][row]
            i, j = np.nonzero(grown + rest[b][row][:, None] >= self.cap)
            row, code, total = row[i], code[i] * self.words + j, grown[i, j]
        return row, code


def _decode(filters: int, per_vector: float, single: bool, codes: int):
    books: dict[int, list[Code]] = {}

    def codes_of(d: int) -> list[Code]:
        if d not in books:
            books[d] = [Code(d, filters, per_vector, 11 + i) for i in range(codes)]
        return books[d]

    def run(batches):
        for batch in batches:
            reps, mult, label = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1, 2))
            ends = batch.column(3).offsets.to_numpy()
            flat = batch.column(3).values.to_numpy(zero_copy_only=False).astype(np.float64)
            for d in np.unique(np.diff(ends)):
                rows = np.flatnonzero(np.diff(ends) == d)
                for at in range(0, len(rows), 256):
                    own = rows[at : at + 256]
                    v = flat[ends[own][:, None] + np.arange(d)[None, :]]
                    raw = [x.tobytes() for x in (v.astype(np.float32) if single else v)]
                    got = [(r, c + i * b.words**b.blocks) for i, b in enumerate(codes_of(int(d))) for r, c in [b.decode(_unit(v))]]
                    r, c = (np.concatenate(x) for x in zip(*got))
                    order = np.argsort(r, kind="stable")
                    r, c = r[order], c[order]
                    lists = [x.astype(np.int64).tobytes() for x in np.split(c, np.cumsum(np.bincount(r, minlength=len(own)))[:-1])]
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(label[own][r]), pa.array(c), pa.array(reps[own][r]), pa.array(mult[own][r]), pa.array([lists[i] for i in r], pa.binary()), pa.array([raw[i] for i in r], pa.binary())],
                        names=["label", "code", "rep", "mult", "codes", "vec"],
                    )

    return run


def _unit(v: np.ndarray) -> np.ndarray:
    v = v / np.abs(v).max(axis=1, keepdims=True)
    return v / np.linalg.norm(v, axis=1, keepdims=True)


def _shared_before(codes: list[np.ndarray], code: int, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Whether rows i and j share a direction below code."""
    lower = [c[c < code] for c in codes]
    size = np.array([len(c) for c in lower])
    flat = np.concatenate(lower) if len(lower) else np.zeros(0, np.int64)
    names, col, often = np.unique(flat, return_inverse=True, return_counts=True)
    row = np.repeat(np.arange(len(lower)), size)
    seen = np.zeros(len(i), bool)
    use = often[col] > 1
    row, col = row[use], np.unique(col[use], return_inverse=True)[1]
    for at in range(0, int(col.max(initial=-1)) + 1, 2048):
        pick = (col >= at) & (col < at + 2048)
        held = np.zeros((len(lower), min(2048, int(col.max()) + 1 - at)), np.float32)
        held[row[pick], col[pick] - at] = 1
        if len(i) * 16 > len(lower) ** 2:
            seen |= (held @ held.T)[i, j] > 0
        else:
            for p in range(0, len(i), 4096):
                seen[p : p + 4096] |= (held[i[p : p + 4096]] * held[j[p : p + 4096]]).any(axis=1)
    return seen


def _compare(code, side_a, side_b, rep, mult, salt, codes, vec, least, kind):
    """One direction's (or block pair's) vectors -> (rep, weighted links, least linked rep)."""
    width = np.array([len(x) for x in vec])
    n, low = np.zeros(len(rep), np.int64), np.arange(len(rep))
    order = np.argsort(rep, kind="stable")
    for d in np.unique(width):
        at = order[width[order] == d]
        left = at if side_a == side_b else at[salt[at] == side_a]
        right = at if side_a == side_b else at[salt[at] == side_b]
        if not len(left) or not len(right):
            continue
        a, b = (_unit(np.frombuffer(b"".join(vec[x] for x in side), kind).reshape(len(side), -1).astype(np.float64)) for side in (left, right))
        near = a @ b.T >= least
        if side_a == side_b:
            near = np.triu(near, 1)
        i, j = np.nonzero(near)
        i, j = left[i], right[j]
        if not len(i):
            continue
        new = ~_shared_before([np.frombuffer(x, np.int64) for x in codes], code, i, j)
        np.add.at(n, i[new], mult[j[new]])
        np.add.at(n, j[new], mult[i[new]])
        by_rank = np.empty(len(rep), np.int64)
        by_rank[order] = np.arange(len(rep))
        label = by_rank.copy()
        while True:
            was = label.copy()
            np.minimum.at(label, i, label[j])
            np.minimum.at(label, j, label[i])
            label = label[order][label]
            if (was == label).all():
                break
        low = np.where(label != by_rank, order[label], low)
    hit = (n > 0) | (low != np.arange(len(rep)))
    return rep[hit], n[hit], rep[low[hit]]


def _groups(least: float, kind: str):
    names = ("label", "code", "pa", "pb")

    def split(batches):
        held = None
        for batch in batches:
            t = pa.Table.from_batches([batch]) if held is None else pa.concat_tables([held, pa.Table.from_batches([batch])]).combine_chunks()
            key = np.stack([t[c].to_numpy() for c in names])
            starts = np.flatnonzero(np.r_[True, (key[:, 1:] != key[:, :-1]).any(axis=0)]) if t.num_rows else np.zeros(0, int)
            for a, b in zip(starts, starts[1:]):
                if b - a > 1:
                    yield t.slice(a, b - a)
            held = t.slice(starts[-1]) if len(starts) else None
        if held is not None and held.num_rows > 1:
            yield held

    def run(batches):
        for t in split(batches):
            one = [t[c][0].as_py() for c in names]
            cols = [t[c].to_numpy() for c in ("rep", "mult", "salt")]
            got = _compare(one[1], one[2], one[3], *cols, t["codes"].to_pylist(), t["vec"].to_pylist(), least, kind)
            if len(got[0]):
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in got], schema=_FOUND)

    return run


def near_vectors(vectors: DataFrame, least: float = 0.93, per_vector: float = PER_VECTOR) -> DataFrame:
    """vectors(vec_id, embedding, label) -> vec_id, n_links, component_id, kept."""
    one = F.struct(F.col("label").cast("long").alias("label"), F.col("embedding").cast("array<double>").alias("embedding"))
    x = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), one.alias("v")).groupBy("vec_id").agg(F.min("v").alias("v"))
    x = x.select("vec_id", "v.label", "v.embedding")
    live = F.col("vec_id").isNotNull() & F.col("label").isNotNull() & usable(F.col("embedding")) & F.exists("embedding", lambda c: c != 0)
    x = stage(x.withColumn("live", live), "cap-vectors")
    alike = stage(x.filter("live").groupBy("label", "embedding").agg(F.min("vec_id").alias("rep"), F.count("*").alias("mult")), "cap-distinct")
    largest = alike.groupBy("label").count().agg(F.max("count")).first()[0] or 0
    filters = max(64, int(per_vector * largest / PER_FILTER))
    codes = CODES + 2 * max(0, round(math.log10(max(largest, 1) / 5000)))  # higher caps separate more pairs
    single = vectors.schema["embedding"].dataType.elementType.typeName() == "float"
    n = parallelism(vectors.sparkSession)
    caps = alike.select("rep", "mult", "label", "embedding").repartition(n, "rep").mapInArrow(_decode(filters, per_vector, single, codes), _CAP)
    caps = stage(caps, "cap-passes")
    big = stage(caps.groupBy("label", "code").count().filter(F.col("count") > BLOCK), "cap-large")
    parts = F.ceil(F.coalesce("count", F.lit(1)) / BLOCK).cast("int")
    caps = caps.join(big, ["label", "code"], "left").withColumn("parts", parts)
    caps = caps.withColumn("salt", F.pmod(F.xxhash64("rep"), "parts").cast("int"))
    pair = F.transform(F.sequence(F.lit(0), F.col("parts") - 1), lambda j: F.struct(F.least("salt", j).alias("pa"), F.greatest("salt", j).alias("pb")))
    caps = caps.withColumn("pair", F.explode(pair)).select("label", "code", F.col("pair.pa").alias("pa"), F.col("pair.pb").alias("pb"), "rep", "mult", "salt", "codes", "vec")
    keys = ["label", "code", "pa", "pb"]
    found = caps.repartition(n, *keys).sortWithinPartitions(*keys, "rep").mapInArrow(_groups(least, "<f4" if single else "<f8"), "rep long, n long, low long")
    found = stage(found, "cap-found")
    links = found.groupBy("rep").agg(F.sum("n").alias("n"))
    roots = components(found.select(F.col("rep").alias("a"), F.col("low").alias("b")))
    node = alike.join(links, "rep", "left").join(roots.withColumnRenamed("id", "rep"), "rep", "left")
    node = stage(node.select("label", "embedding", (F.coalesce("n", F.lit(0)) + F.col("mult") - 1).alias("n_links"), F.coalesce("root", "rep").alias("component_id")), "cap-nodes")
    linked = x.filter("live").join(node, ["label", "embedding"]).select("vec_id", "n_links", "component_id")
    alone = x.filter("not live").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return linked.union(alone).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))


def op3_caps(spark, sf_dir: str) -> DataFrame:
    return near_vectors(table(spark, sf_dir, "embeddings").select("vec_id", "embedding", "label"))


SQL = """
WITH RECURSIVE e AS (SELECT vec_id, label, embedding::DOUBLE[] AS v FROM embeddings),
p AS (SELECT a.vec_id AS a, b.vec_id AS b FROM e a JOIN e b ON a.label = b.label AND a.vec_id <> b.vec_id
      WHERE list_cosine_similarity(a.v, b.v) >= 0.93),
r(a, b) AS (SELECT vec_id, vec_id FROM e UNION SELECT r.a, p.b FROM r JOIN p ON r.b = p.a),
c AS (SELECT a, min(b) AS component_id FROM r GROUP BY a),
n AS (SELECT a, count(*) AS n FROM p GROUP BY a)
SELECT e.vec_id, coalesce(n.n, 0)::BIGINT AS n_links, c.component_id, e.vec_id = c.component_id AS kept
FROM e JOIN c ON c.a = e.vec_id LEFT JOIN n ON n.a = e.vec_id
"""
