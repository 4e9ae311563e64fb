"""Exact top-k inner-product search by a three-phase uniform threshold scheme.

Each component x becomes ``floor(scale * x)``. Equal vectors are one node, which keeps the least ids of
its rows: no answer needs more than k + 1 of them. A node is cut into ``LISTS`` segments of its
dimensions; segment j of all nodes is score list j, a table of its own, so a query's score is the sum
of its partial scores in the lists, and no list alone knows a score.

1. Every list is read apart and gives, per query vector, its k + 1 largest partial scores. What these
   name is added up exactly; the (k + 1)-th best sum is a safe cutoff ``tau``: no answer is below it.
2. The cutoffs go to all tasks of every list. A node that reaches ``tau`` has ``tau / LISTS`` or more in
   one list, so only entries over that uniform threshold are collected; of them an entry stays only if
   its partial score and the most that its other segments can add (the uniform threshold, or the
   product of their norms if that is less) reach ``tau``.
3. Scores of collected nodes that some list did not send are resolved: the missing partial scores are
   fetched from their lists by id and added exactly. The k + 1 best nodes give the k best rows.

Rows and queries meet in blocks: a list is dealt into chunks of about ``CHUNK`` nodes and every query
vector goes to each chunk once, by shuffle; nothing passes through the driver and no node meets another
in a join. ``search`` also gives the tables of all phases, for counters.

Defined results: vectors that are null or hold null or non-finite components take no part, as query
or as candidate; vectors meet only vectors of the same length; an empty vector scores 0; a null id
takes no part; rows that repeat id and vector are candidates each, but for a query's own id, which is
never its candidate; of query rows that repeat an id with different vectors the least vector is asked;
ties go to the smaller id; scores beyond the range of a long saturate; fewer than k candidates give
fewer rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import parallelism, stage, table

LISTS = 2
#: Nodes of a chunk; a task holds one chunk of one list, 4 MB for 32 components.
CHUNK = 16384
#: Queries multiplied with a chunk at once.
AT_ONCE = 256
_EXACT = float(1 << 53)
_ENTRY = "q long, node long, part double, sure boolean"
_MEET = ("chunk", "asks", "id", "d", "part", "rest", "tau")


def usable(vector) -> F.Column:
    bad = F.exists(vector, lambda x: x.isNull() | F.isnan(x.cast("double")) | (F.abs(x.cast("double")) == float("inf")))
    return F.coalesce(~bad, F.lit(False))


def _ticks(df: DataFrame, scale: float) -> DataFrame:
    """Usable rows as (vec_id, v): whole numbers held as doubles."""
    x = df.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("e"))
    x = x.filter(F.col("vec_id").isNotNull() & usable(F.col("e")))
    whole = lambda c: F.when(F.abs(c) < _EXACT, F.floor(c).cast("double")).otherwise(c)
    return x.select("vec_id", F.transform("e", lambda c: whole(c * F.lit(scale))).alias("v"))


def _nodes(rows: DataFrame, keep: int) -> DataFrame:
    """rows(vec_id, v) -> node, v, ids: distinct vectors with the ``keep`` least ids of each (and how often they stand)."""
    once = rows.groupBy("v", "vec_id").agg(F.count("*").alias("n"))
    order = Window.partitionBy("v").orderBy("vec_id")
    once = once.withColumn("r", F.row_number().over(order)).filter(F.col("r") <= keep)  # limited before the shuffle too
    ids = F.array_sort(F.collect_list(F.struct("vec_id", F.least("n", F.lit(keep)).alias("n"))))  # at most ``keep`` entries
    x = once.groupBy("v").agg(ids.alias("ids"))
    return x.select(F.monotonically_increasing_id().alias("node"), "v", "ids")


def _segment(j: int):
    """Segment j of an array column v, and the norm of the other segments."""
    size, least = F.size("v"), lambda i: F.floor(F.size("v") * i / LISTS).cast("int")
    part = F.slice("v", least(j) + 1, least(j + 1) - least(j))
    square = lambda a: F.aggregate(a, F.lit(0.0), lambda s, c: s + c * c)
    rest = F.concat(F.slice("v", F.lit(1), least(j)), F.slice("v", least(j + 1) + 1, size - least(j + 1)))
    return part, F.sqrt(square(rest))


def _meet(rows: DataFrame, asked: DataFrame, chunks: int, n: int, run) -> DataFrame:
    """List rows(node, chunk, ...) and asked(q, ..., tau) dealt by chunk: a chunk's rows first, then every query."""
    r = rows.select("chunk", F.lit(0).alias("asks"), F.col("node").alias("id"), "d", "part", "rest", F.lit(None).cast("double").alias("tau"))
    a = asked.select(F.explode(F.sequence(F.lit(0), F.lit(chunks - 1))).alias("chunk"), F.lit(1).alias("asks"), F.col("q").alias("id"), "d", "part", "rest", "tau")
    return r.unionByName(a).repartition(n, "chunk").sortWithinPartitions("chunk", "asks").mapInArrow(run, _ENTRY)


def _matrices(batch: pa.RecordBatch, at: np.ndarray):
    """Rows ``at`` of a batch by vector length: (d, ids, parts, rest, tau)."""
    ids, d, rest, tau = (batch.column(i).to_numpy(zero_copy_only=False)[at] for i in (2, 3, 5, 6))
    lists = batch.column(4)
    ends, flat = lists.offsets.to_numpy(), lists.values.to_numpy(zero_copy_only=False)
    for one in np.unique(d):
        own = np.flatnonzero(d == one)
        start = ends[at[own]]
        width = int(ends[at[own[0]] + 1] - start[0])
        yield int(one), ids[own], flat[start[:, None] + np.arange(width)], rest[own], tau[own].astype(float)


def _products(emit):
    """Batches of one list sorted by (chunk, asks) -> what ``emit`` takes of the products of queries and the chunk."""

    def run(batches):
        chunk, held = None, {}
        for batch in batches:
            if not batch.num_rows:
                continue
            key = batch.column(0).to_numpy() * 2 + batch.column(1).to_numpy()
            edges = np.flatnonzero(np.diff(key)) + 1
            for at in np.split(np.arange(len(key)), edges):
                if key[at[0]] // 2 != chunk:
                    chunk, held = int(key[at[0]]) // 2, {}
                if key[at[0]] % 2 == 0:
                    for d, *more in _matrices(batch, at):
                        held.setdefault(d, []).append(more)
                    continue
                held = {d: x if isinstance(x, tuple) else tuple(np.concatenate(c) for c in zip(*x)) for d, x in held.items()}
                for d, q, qv, q_rest, tau in _matrices(batch, at):
                    if d not in held:
                        continue
                    node, v, rest, _ = held[d]
                    for a in range(0, len(q), AT_ONCE):
                        b = slice(a, a + AT_ONCE)
                        size = np.abs(qv[b]).max(initial=0) * np.abs(v).max(initial=0) * max(d, 1)
                        with np.errstate(over="ignore", invalid="ignore"):
                            p = np.nan_to_num(qv[b] @ v.T)
                            i, j = emit(p, q_rest[b], rest, tau[b])
                        yield pa.RecordBatch.from_arrays(
                            [pa.array(q[b][i]), pa.array(node[j]), pa.array(p[i, j]), pa.array(np.full(len(i), bool(size < _EXACT / LISTS)))],
                            names=["q", "node", "part", "sure"],
                        )

    return run


def _heads(keep: int):
    """Phase 1: the leading entries of a chunk's list."""

    def emit(p, q_rest, rest, tau):
        n = min(keep, p.shape[1])
        top = np.argpartition(-p, n - 1, axis=1)[:, :n]
        return np.repeat(np.arange(len(p)), n), top.ravel()

    return _products(emit)


def _over(p, q_rest, rest, tau):
    """Phase 2: the entries over the uniform threshold that can still reach the cutoff."""
    slack = 1e-9 * (np.abs(tau) + 1)
    most = np.minimum(np.outer(q_rest, rest) * (1 + 1e-9), (tau * (LISTS - 1) / LISTS)[:, None]) if LISTS == 2 else np.outer(q_rest, rest) * (1 + 1e-9)
    low = np.isneginf(tau)[:, None]
    return np.nonzero(low | ((p >= (tau / LISTS - slack)[:, None]) & (p + most >= (tau - slack)[:, None])))


def _dot(batches):
    """(q, node, known, a, b) -> known plus the exact inner product, saturated to a long."""
    for batch in batches:
        if not batch.num_rows:
            continue
        known = batch.column(2).to_numpy(zero_copy_only=False)
        a, b = batch.column(3), batch.column(4)
        ea, eb = a.offsets.to_numpy(), b.offsets.to_numpy()
        fa, fb = a.values.to_numpy(zero_copy_only=False), b.values.to_numpy(zero_copy_only=False)
        size = np.abs(fa).max(initial=0) * np.abs(fb).max(initial=0) * max(1, int(np.diff(ea).max(initial=0)))
        if size < _EXACT and np.abs(known).max(initial=0) < _EXACT:
            own = np.repeat(np.arange(len(known)), np.diff(ea))
            product = fa[ea[0] : ea[-1]] * fb[eb[0] : eb[-1]]
            score = (known + np.bincount(own, product, len(known))).astype(np.int64)
        else:
            whole = [int(k) + sum(int(x) * int(y) for x, y in zip(fa[s:e].tolist(), fb[t : t + e - s].tolist())) for k, s, e, t in zip(known.tolist(), ea[:-1], ea[1:], eb[:-1])]
            score = np.array([max(-(1 << 63), min((1 << 63) - 1, x)) for x in whole], np.int64)
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(score)], names=["q", "node", "score"])


def _exactly(pairs: DataFrame, asked: DataFrame, rows: DataFrame) -> DataFrame:
    """pairs(q, node, known), asked(q, a), rows(node, b) -> q, node, score = known + a . b."""
    x = pairs.join(asked, "q").join(rows, "node").select("q", "node", "known", "a", "b")
    return x.mapInArrow(_dot, "q long, node long, score long")


def search(vectors: DataFrame, queries: DataFrame, k: int = 10, scale: float = 1024.0) -> tuple[DataFrame, dict[str, DataFrame]]:
    """The answer of ``top_k``, and the tables between: nodes, heads and cutoffs (phase 1), over (phase 2), missing (what phase 3 fetches)."""
    n, keep = parallelism(vectors.sparkSession), k + 1
    nodes = stage(_nodes(_ticks(vectors, scale), keep), "topk-nodes")
    once = _ticks(queries, scale).groupBy("vec_id").agg(F.min("v").alias("v"))
    once = stage(once, "topk-queries")
    asked = once.groupBy("v").agg(F.min("vec_id").alias("q"))  # equal vectors ask once
    asked = stage(asked.select("q", "v"), "topk-asked")
    many = nodes.count()
    chunks = max(1, -(-many // CHUNK), min(n, many // 1024))
    dealt = nodes.withColumn("chunk", F.pmod(F.xxhash64("node"), F.lit(chunks)).cast("int"))
    lists, sides = [], []
    for j in range(LISTS):
        part, rest = _segment(j)
        lists.append(stage(dealt.select("node", "chunk", F.size("v").alias("d"), part.alias("part"), rest.alias("rest")), f"topk-list{j}"))
        sides.append(asked.select("q", F.size("v").alias("d"), part.alias("part"), rest.alias("rest")))
    none = F.lit(None).cast("double")
    by_part = Window.partitionBy("q").orderBy(F.col("part").desc(), "node")
    heads = None
    for rows, ask in zip(lists, sides):
        x = _meet(rows, ask.withColumn("tau", none), chunks, n, _heads(keep))
        x = x.withColumn("r", F.row_number().over(by_part)).filter(F.col("r") <= keep).select("q", "node")
        heads = x if heads is None else heads.union(x)
    heads = stage(heads.distinct(), "topk-heads")
    full_a, full_b = asked.select("q", F.col("v").alias("a")), nodes.select("node", F.col("v").alias("b"))
    zero = F.lit(0.0).alias("known")
    by_score = Window.partitionBy("q").orderBy(F.col("score").desc(), "node")
    known = _exactly(heads.select("q", "node", zero), full_a, full_b)
    cut = known.withColumn("r", F.row_number().over(by_score)).filter(F.col("r") == keep)
    cut = stage(cut.select("q", F.col("score").cast("double").alias("tau")), "topk-cutoffs")
    over = None
    for j, (rows, ask) in enumerate(zip(lists, sides)):
        x = ask.join(cut, "q", "left").withColumn("tau", F.coalesce("tau", F.lit(float("-inf"))))
        x = _meet(rows, x, chunks, n, _products(_over)).withColumn("list", F.lit(1 << j))
        over = x if over is None else over.union(x)
    over = stage(over, "topk-over")
    sent = over.groupBy("q", "node").agg(F.sum("part").alias("known"), F.min("sure").alias("sure"), F.bit_or("list").alias("has"))
    sent = stage(sent, "topk-sent")
    missing = sent.filter(F.col("sure") & (F.col("has") != (1 << LISTS) - 1))
    scores = sent.filter(F.col("sure") & (F.col("has") == (1 << LISTS) - 1)).select("q", "node", F.col("known").cast("long").alias("score"))
    if LISTS == 2:  # the one part that is not there
        for j in range(LISTS):
            some = missing.filter(F.col("has") == 1 << (1 - j)).select("q", "node", "known")
            scores = scores.union(_exactly(some, sides[j].select("q", F.col("part").alias("a")), lists[j].select("node", F.col("part").alias("b"))))
        rest = sent.filter(~F.col("sure"))
    else:
        rest = sent.filter(~F.col("sure")).union(missing)
    scores = scores.union(_exactly(rest.select("q", "node", zero), full_a, full_b))
    first = nodes.select("node", F.col("ids")[0]["vec_id"].alias("least"), "ids")
    best = scores.join(first, "node")
    by_row = Window.partitionBy("q").orderBy(F.col("score").desc(), "least")
    best = best.withColumn("r", F.row_number().over(by_row)).filter(F.col("r") <= keep).select("q", "score", F.explode("ids").alias("i"))
    members = once.join(asked, "v").select("q", F.col("vec_id").alias("query_id"))
    x = best.select("q", "score", F.col("i.vec_id").alias("vec_id"), F.col("i.n").alias("n"))
    top = Window.partitionBy("q").orderBy(F.col("score").desc(), "vec_id")  # the leading k + 1 ids hold k other than the query's own
    x = x.withColumn("r", F.row_number().over(top)).filter(F.col("r") <= keep).join(members, "q").filter("vec_id <> query_id")
    x = x.withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("n").cast("int"))))
    order = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id", "copy")
    x = x.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
    return x, {"nodes": nodes, "heads": heads, "cutoffs": cut, "over": over, "missing": missing}


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 10, scale: float = 1024.0) -> DataFrame:
    """vectors(vec_id, embedding), queries(vec_id, embedding) -> query_id, rank, vec_id, score."""
    return search(vectors, queries, k, scale)[0]


def op8_topk(spark, sf_dir: str) -> DataFrame:
    x = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return top_k(x, x.filter(F.col("vec_id") % 100 == 0))


SQL = """
WITH e AS (SELECT vec_id, list_transform(embedding, lambda x: floor(1024 * x::DOUBLE)) AS v FROM embeddings
           WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND vec_id IS NOT NULL),
s AS (SELECT q.vec_id AS query_id, c.vec_id, list_inner_product(q.v, c.v)::BIGINT AS score
      FROM e q JOIN e c ON q.vec_id % 100 = 0 AND q.vec_id <> c.vec_id AND len(q.v) = len(c.v))
SELECT query_id, (row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id))::INT AS rank, vec_id, score
FROM s QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) <= 10
"""
