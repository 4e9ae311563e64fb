"""SimHash near-duplicates by multi-index hashing.

A fingerprint has bit b set if more than half of its document's shingle hashes have. Two
fingerprints within ``RADIUS`` bits agree, in one of a few segments, within a small radius of that
segment (the pigeonhole rule: with r = q * m + a over m segments, radius q in the first a + 1, q - 1 in
the others). Every distinct fingerprint is entered under its own segment values and under the values
in the ball around them; what meets under a value is compared on all bits. A ball of radius one
needs only the values with one set bit cleared, as of two values that differ in one bit one has it set.

Documents with equal fingerprints are one node, so groups of copies cost nothing; a value shared by
more than ``BLOCK`` entries is compared in pairs of salted blocks; of the links under a value that
many share only the nearest ones that connect the same nodes (a least spanning forest) become rows.
Where links are verified, ``keep_one`` compares the nodes that these rows bring together, but no verified link, once more in all pairs.

``keep_one`` links texts by the similarity itself: fingerprints of ``WIDE`` words of 64 bits, which for
texts alike to 0.8 differ in 15 % of the bits, give candidates within ``WIDE_RADIUS`` bits, and
candidates link if the Jaccard similarity of their shingle sets is ``ALIKE`` or more. Its segments are
drawn bit sets, wider for larger tables so that few strangers meet, and as many more of them as keep
the share of pairs that never meet below ``MISSED``.

Defined results: null texts, and texts without words, have fingerprint zero and link like any other;
a null doc_id never names a component (a group of nothing but nulls has component null) and in
``keep_one`` links nothing; rows that repeat a doc_id are fingerprinted each; extra columns are not
read by ``near_texts`` and carried along by ``keep_one``; an empty table gives an empty result.
"""

from __future__ import annotations

import math
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import tokens
from .common import drop, parallelism, positional, slices, stage, table
from .components import components

SHINGLE = 4
RADIUS = 4
SEED = 42
SEGMENTS = 3
BLOCK = 8192
#: Near texts of ``keep_one``: words a shingle, 64-bit words a fingerprint, bits that candidates may differ in, similarity.
NEAR_SHINGLE, WIDE, WIDE_RADIUS, ALIKE = 5, 2, 30, 0.8
#: Share of the bits that texts just alike enough differ in (with some room), and the share of them that may never meet.
DIFFER, MISSED = 0.18, 0.03
_SMALL = 32
_EDGE = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("dist", pa.int32())])


def _spread(h: np.ndarray, word: int) -> np.ndarray:
    """The hash itself for word 0, an independent-looking mix of it for the further words of wide fingerprints."""
    if word == 0:
        return h
    x = h + np.uint64(word) * np.uint64(0x9E3779B97F4A7C15)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def fingerprint(text: bytes | None, k: int = SHINGLE, width: int = 1) -> list[int]:
    """The fingerprint of a UTF-8 text as ``width`` unsigned 64-bit words."""
    words = (text or b"").lower().split()
    if not words:
        return [0] * width
    grams = [b" ".join(words)] if len(words) < k else map(b" ".join, zip(*(words[i:] for i in range(k))))
    digest = xxhash.xxh64_intdigest
    h = np.array([digest(g, SEED) for g in grams], dtype=np.uint64)
    out = []
    for w in range(width):
        ones = np.zeros(64, np.int64)
        for at in range(0, len(h), 1 << 16):
            part = _spread(h[at : at + (1 << 16)], w).astype("<u8")
            ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
        out.append(int(np.packbits(2 * ones > len(h), bitorder="little").view("<u8")[0]))
    return out


def _fingerprints(k: int, width: int):
    def run(batches):
        tokens.forget()
        for batch in slices(batches):
            fp = np.array([fingerprint(t, k, width) for t in batch.column(1).to_pylist()], dtype=np.uint64).reshape(-1, width).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), *batch.columns[2:], *(pa.array(np.ascontiguousarray(x)) for x in fp.T)], names=["doc_id", *batch.schema.names[2:], *_words(width)])

    return run


def _words(width: int) -> list[str]:
    return [f"fp{w}" for w in range(width)]


def with_fingerprints(docs: DataFrame, k: int = SHINGLE, width: int = 1, *more) -> DataFrame:
    """docs(doc_id, text) -> doc_id, ``more`` (longs), fp0.. (signed longs), id: the node, fp0 itself if there is but one word."""
    x = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("text"), *more)
    names = _words(width)
    x = x.mapInArrow(_fingerprints(k, width), ", ".join(f"{c} long" for c in ("doc_id", *x.columns[2:], *names)))
    return x.withColumn("id", F.col("fp0") if width == 1 else F.xxhash64(*names))


def segments(radius: int, many: int) -> list[tuple[tuple[int, ...], int]]:
    """(bits, ball radius) of segments that miss no pair within the radius, for one word."""
    q, a = divmod(radius, many)
    edges = [round(64 * i / many) for i in range(many + 1)]
    return [(tuple(range(lo, hi)), q if i <= a else q - 1) for i, (lo, hi) in enumerate(zip(edges, edges[1:])) if i <= a or q > 0]


def wide_segments(width: int, rows: int) -> list[tuple[tuple[int, ...], int]]:
    """Drawn bit sets with balls of radius one for a table of so many fingerprints.

    About log2(rows) - 7 bits each, and so many that pairs that differ in ``DIFFER`` of the bits meet but for ``MISSED``.
    """
    bits = min(max(10, rows.bit_length() - 7), 24)
    meet = (1 - DIFFER) ** bits + bits * DIFFER * (1 - DIFFER) ** (bits - 1)
    many = math.ceil(math.log(MISSED) / math.log(1 - meet))
    rng, out, deck = np.random.default_rng(19), [], []
    for _ in range(many):  # dealt from shuffled decks of all bits, so that segments overlap little
        if len(deck) < bits:
            deck = rng.permutation(64 * width).tolist()
        out.append((tuple(sorted(deck[:bits])), 1))
        deck = deck[bits:]
    return out


def _value(words: list[np.ndarray], at: tuple[int, ...]) -> np.ndarray:
    """The bits ``at`` of each fingerprint, next to one another."""
    out = np.zeros(len(words[0]), np.uint64)
    if at == tuple(range(at[0], at[-1] + 1)) and at[0] // 64 == at[-1] // 64:
        return (words[at[0] // 64] >> np.uint64(at[0] % 64)) & np.uint64((1 << len(at)) - 1)
    for i, b in enumerate(at):
        out |= ((words[b // 64] >> np.uint64(b % 64)) & np.uint64(1)) << np.uint64(i)
    return out


def _entries(plan, width: int):
    """(id, fp0..) -> (key, own, id, fp0..) for the own value and the ball of each segment."""

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            words = [batch.column(1 + w).to_numpy().view(np.uint64) for w in range(width)]
            held: list = []
            for s, (bits, ball) in enumerate(plan):
                v = _value(words, bits)
                base = np.uint64(s << 40)
                held.append((v | base, np.ones(len(v), bool), np.arange(len(v))))
                for r in range(1, ball + 1):
                    for flip in combinations(range(len(bits)), r):
                        mask = np.uint64(sum(1 << b for b in flip))
                        at = np.flatnonzero((v & mask) == mask) if ball == 1 else np.arange(len(v))
                        held.append(((v[at] ^ mask) | base, np.zeros(len(at), bool), at))
                    if sum(len(x[0]) for x in held) > 1 << 17:
                        yield _entry(held, batch)
                        held = []
            if held:
                yield _entry(held, batch)

    return run


def _entry(held, batch):
    key, own, at = (np.concatenate(x) for x in zip(*held))
    rest = batch.take(pa.array(at))
    return pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), pa.array(own), *rest.columns], names=["key", "own", *rest.schema.names])


def _far(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.bitwise_count(a ^ b).sum(axis=-1, dtype=np.int32)


def _forest(i: np.ndarray, j: np.ndarray, d: np.ndarray, n: int) -> np.ndarray:
    """Indices of the edges (i, j) of a least spanning forest over n nodes: every tree takes its nearest way out, until none is left."""
    label, chosen = np.arange(n), []
    left = np.argsort(d, kind="stable")
    while True:
        left = left[label[i[left]] != label[j[left]]]
        if not len(left):
            return np.concatenate(chosen) if chosen else np.zeros(0, np.int64)
        first = np.full(n, len(left))
        for side in (i, j):
            np.minimum.at(first, label[side[left]], np.arange(len(left)))
        new = left[np.unique(first[first < len(left)])]
        chosen.append(new)
        while True:
            was = label.copy()
            a, b = label[i[new]], label[j[new]]
            np.minimum.at(label, a, b)
            np.minimum.at(label, b, a)
            label = label[label]
            if (label == was).all():
                break


def _link(radius: int, width: int):
    def edges(a, b, d):
        return pa.RecordBatch.from_arrays([pa.array(a), pa.array(b), pa.array(d.astype(np.int32))], schema=_EDGE)

    def pairs(ids, fp, size, start):
        """All pairs within the (small) groups at once."""
        a, b = [], []
        for n in np.unique(size):
            at = start[size == n]
            i, j = np.triu_indices(n, 1)
            a.append((at[:, None] + i).ravel()), b.append((at[:, None] + j).ravel())
        if not a:
            return
        a, b = np.concatenate(a), np.concatenate(b)
        far = _far(fp[a], fp[b])
        hit = (ids[a] != ids[b]) & (far <= radius)
        if hit.any():
            lo, hi = np.minimum(ids[a[hit]], ids[b[hit]]), np.maximum(ids[a[hit]], ids[b[hit]])
            got = np.unique(np.stack([lo, hi, far[hit]]), axis=1)
            yield edges(*got)

    def group(ids, fp, own):
        """A large group: own values against all of it, in blocks, thinned to a least forest."""
        ids, first, back = np.unique(ids, return_index=True, return_inverse=True)
        fp, mine = fp[first], np.zeros(len(ids), bool)
        np.logical_or.at(mine, back, own)
        mine = np.flatnonzero(mine)
        step = max(1, (1 << 20) // len(ids))
        i, j, d = (np.zeros(0, np.int64) for _ in range(3))
        for at in range(0, len(mine), step):
            far = _far(fp[mine[at : at + step], None], fp[None])
            r, c = np.nonzero(far <= radius)
            far, r = far[r, c], mine[at : at + step][r]
            i, j, d = np.concatenate([i, r[r != c]]), np.concatenate([j, c[r != c]]), np.concatenate([d, far[r != c]])
            if len(i) > 4 * len(ids):
                keep = _forest(i, j, d, len(ids))
                i, j, d = i[keep], j[keep], d[keep]
        if len(i):
            keep = _forest(i, j, d, len(ids))
            yield edges(ids[np.minimum(i[keep], j[keep])], ids[np.maximum(i[keep], j[keep])], d[keep])

    def solve(key, own, ids, fp):
        start = np.flatnonzero(np.r_[True, (key[1:] != key[:-1]).any(axis=1)])
        size = np.diff(np.r_[start, len(key)])
        live = (np.add.reduceat(own.astype(np.int64), start) > 0) & (size > 1)
        start, size = start[live], size[live]
        few = size <= _SMALL
        s, n = start[few], size[few]
        for at in range(0, len(s), 2000):
            yield from pairs(ids, fp, n[at : at + 2000], s[at : at + 2000])
        for a, n in zip(start[~few], size[~few]):
            yield from group(ids[a : a + n], fp[a : a + n], own[a : a + n])

    def run(batches):
        held = None
        for batch in batches:
            if not batch.num_rows:
                continue
            key = np.stack([batch.column(c).to_numpy() for c in (0, 1, 2)], axis=1)
            fp = np.stack([batch.column(5 + w).to_numpy().view(np.uint64) for w in range(width)], axis=1)
            now = key, batch.column(3).to_numpy(zero_copy_only=False), batch.column(4).to_numpy(), fp
            if held is not None:
                now = tuple(np.concatenate(x) for x in zip(held, now))
            cut = int(np.flatnonzero((now[0] == now[0][-1]).all(axis=1))[0])
            if cut:
                yield from solve(*(x[:cut] for x in now))
            held = tuple(x[cut:] for x in now)
        if held is not None:
            yield from solve(*held)

    return run


def near_fingerprints(prints: DataFrame, radius: int, width: int, plan) -> DataFrame:
    """Distinct prints(id, fp0..) -> staged (a, b, dist), a < b: pairs within the radius that meet in a segment."""
    n, names = parallelism(prints.sparkSession), _words(width)
    entries = prints.select("id", *names).repartition(n, "id").mapInArrow(_entries(plan, width), "key long, own boolean, id long, " + ", ".join(f"{c} long" for c in names))
    entries = stage(entries, "simhash-entries")
    keys = ["key", "pa", "pb"]
    x = _blocks(entries, ["key"]).select(*keys, "own", "id", *names)
    found = x.repartition(n, *keys).sortWithinPartitions(*keys).mapInArrow(_link(radius, width), "a long, b long, dist int")
    found = stage(found.groupBy("a", "b").agg(F.min("dist").alias("dist")), "simhash-edges")
    drop(entries)
    return found


def _blocks(entries: DataFrame, by: list[str]) -> DataFrame:
    """(Staged) entries with pa and pb: those of a value shared by more than BLOCK meet in pairs of salted blocks."""
    big = stage(entries.groupBy(*by).count().filter(F.col("count") > BLOCK), "simhash-large")
    x = entries.join(big, by, "left").withColumn("parts", F.ceil(F.coalesce("count", F.lit(1)) / BLOCK).cast("int"))
    x = x.withColumn("salt", F.pmod(F.xxhash64("id"), "parts").cast("int"))
    pair = F.transform(F.sequence(F.lit(0), F.col("parts") - 1), lambda j: F.struct(F.least("salt", j).alias("pa"), F.greatest("salt", j).alias("pb")))
    x = x.withColumn("pair", F.explode(pair))
    return x.withColumn("pa", F.col("pair.pa").cast("long")).withColumn("pb", F.col("pair.pb").cast("long")).drop("pair", "parts", "salt", "count")


def _across(radius: int, width: int, plan):
    """Rows (part, key, pa, pb, own, id, root, fp0..) sorted by the first four -> (a, b): every pair of different
    roots within the radius that meets under a value, in the first segment where it does."""
    masks = np.array([[sum(1 << b % 64 for b in bits if b // 64 == w) for w in range(width)] for bits, _ in plan], np.uint64)

    def solve(key, own, ids, roots, fp):
        order = np.argsort(ids, kind="stable")
        own, ids, roots, fp = own[order], ids[order], roots[order], fp[order]
        mine, seen = np.flatnonzero(own), masks[: int(key[1]) >> 40]
        step = max(1, (1 << 20) // len(ids))
        for at in range(0, len(mine), step):
            some = mine[at : at + step]
            r, c = np.nonzero((roots[some, None] != roots) & (_far(fp[some, None], fp[None]) <= radius))
            r = some[r]
            new = ~own[c] | (r < c)
            r, c = r[new], c[new]
            new = np.ones(len(r), bool)
            for m in seen:
                new &= np.bitwise_count((fp[r] ^ fp[c]) & m).sum(axis=1) > 1  # met there: all segments have balls of radius one
            a, b = ids[np.minimum(r, c)[new]], ids[np.maximum(r, c)[new]]
            if len(a):
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names=["a", "b"])

    def run(batches):
        held = None
        for batch in batches:
            if not batch.num_rows:
                continue
            cols = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
            now = np.stack(cols[:4], axis=1), *cols[4:7], np.stack([c.view(np.uint64) for c in cols[7:]], axis=1)
            if held is not None:
                now = tuple(np.concatenate(x) for x in zip(held, now))
            cuts = np.flatnonzero(np.r_[True, (now[0][1:] != now[0][:-1]).any(axis=1)])
            for a, b in zip(cuts[:-1], cuts[1:]):
                yield from solve(now[0][a], *(x[a:b] for x in now[1:]))
            held = tuple(x[cuts[-1] :] for x in now)
        if held is not None:
            yield from solve(held[0][0], *held[1:])

    return run


def _passed_over(near: DataFrame, roots: DataFrame, prints: DataFrame, radius: int, width: int, plan) -> DataFrame | None:
    """Pairs (a, b) within the radius that ``near`` leaves out, between nodes that verified links (id, root) do not connect.

    Forests keep together what a value's pairs connect, so such pairs lie between roots that pairs of ``near``
    connect: only their nodes are entered again, and compared with those of the same part.
    """
    n, names = parallelism(prints.sparkSession), _words(width)
    x = near.select("a", "b")
    for c in "ab":
        x = x.join(roots.select(F.col("id").alias(c), F.col("root").alias(f"root_{c}")), c, "left").withColumn(f"root_{c}", F.coalesce(f"root_{c}", c))
    x = stage(x, "simhash-rooted")
    apart = components(x.select(F.col("root_a").alias("a"), F.col("root_b").alias("b")))
    apart = stage(apart.select(F.col("id").alias("root"), F.col("root").alias("part")), "simhash-apart")
    if apart.isEmpty():
        return None
    nodes = x.select(F.col("a").alias("id"), F.col("root_a").alias("root")).union(x.select("b", "root_b")).distinct().join(apart, "root")
    nodes = stage(nodes, "simhash-open")
    kinds = "key long, own boolean, id long, " + ", ".join(f"{c} long" for c in names)
    entries = prints.select("id", *names).join(nodes.select("id"), "id", "left_semi").repartition(n, "id").mapInArrow(_entries(plan, width), kinds)
    entries = stage(entries.join(nodes, "id"), "simhash-entries")
    keys = ["part", "key", "pa", "pb"]
    x = _blocks(entries, ["part", "key"]).select(*keys, "own", "id", "root", *names)
    x = x.repartition(n, *keys).sortWithinPartitions(*keys).mapInArrow(_across(radius, width, plan), "a long, b long")
    found = stage(x.distinct().join(near.select("a", "b"), ["a", "b"], "left_anti"), "simhash-over")
    drop(entries)
    return found


def link_fingerprints(prints: DataFrame, radius: int = RADIUS, many: int = SEGMENTS) -> DataFrame:
    """Distinct prints(id, fp0) -> (id, root) of those that a chain of links connects to others; no link is missed."""
    return components(near_fingerprints(prints, radius, 1, segments(radius, many)).select("a", "b"))


def _least_of(prints: DataFrame, roots: DataFrame) -> DataFrame:
    """prints(id, first_id), roots(id, root) -> staged (id, component_id)."""
    x = stage(prints.join(roots, "id", "left").select("id", "first_id", F.coalesce("root", "id").alias("root")), "simhash-roots")
    least = stage(x.groupBy("root").agg(F.min("first_id").alias("component_id")), "simhash-least")  # so that both sides of the join are plain and can be split
    return stage(x.join(least, "root").select("id", "component_id"), "simhash-named")


def near_texts(docs: DataFrame, k: int = SHINGLE, radius: int = RADIUS) -> DataFrame:
    """docs(doc_id, text) -> doc_id, id, fp0, component_id, a row per row."""
    rows = stage(with_fingerprints(docs, k), "simhash-prints")
    prints = stage(rows.groupBy("id", "fp0").agg(F.min("doc_id").alias("first_id")), "simhash-distinct")
    named = _least_of(prints, link_fingerprints(prints, radius))
    return rows.join(named, "id").select("doc_id", "id", "fp0", "component_id")


def shingle_set(text: bytes | None, k: int) -> np.ndarray:
    """Sorted distinct 32-bit hashes of the shingles."""
    words = (text or b"").lower().split()
    grams = [b" ".join(words)] if 0 < len(words) < k else map(b" ".join, zip(*(words[i:] for i in range(k))))
    digest = xxhash.xxh64_intdigest
    return np.unique(np.array([digest(g, SEED) & 0xFFFFFFFF for g in grams], dtype=np.uint32))


def _sets(k: int):
    def run(batches):
        for batch in slices(batches):
            for at in range(0, batch.num_rows, 16):
                part = batch.slice(at, 16)
                sets = [shingle_set(t, k).tobytes() for t in part.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sets, pa.binary())], names=["id", "grams"])

    return run


def _alike(least: float):
    """(a, b, grams of a, grams of b) -> (a, b) of the pairs that are alike."""

    def run(batches):
        for batch in slices(batches, 64):
            stay = []
            for x, y in zip(batch.column(2), batch.column(3)):
                x, y = np.frombuffer(x.as_py(), np.uint32), np.frombuffer(y.as_py(), np.uint32)
                if min(len(x), len(y)) < least * max(len(x), len(y)):
                    stay.append(False)
                    continue
                both = len(np.intersect1d(x, y, assume_unique=True))
                stay.append(both >= least * (len(x) + len(y) - both))
            yield pa.RecordBatch.from_arrays(batch.columns[:2], names=["a", "b"]).filter(pa.array(stay, pa.bool_()))

    return run


def _verified(near: DataFrame, prints: DataFrame, docs: DataFrame, k: int, least: float, plan) -> DataFrame:
    """near(a, b, dist) -> (id, root) over the pairs whose texts are alike.

    The nearest pairs of each node are verified first; of the others only those between nodes that
    are not connected yet, so a large group of near copies costs a few verified pairs a node. Last come
    the pairs that least forests have left out, between nodes that are still not connected.
    """
    wanted = near.select(F.col("a").alias("id")).union(near.select("b")).distinct()
    text = docs.select(F.col("doc_id").cast("long").alias("first_id"), F.col("text").cast("binary").alias("text")).withColumn("print", F.xxhash64("text"))
    own = prints.select("id", "first_id", "print").join(wanted, "id", "left_semi")
    own = text.join(own.hint("merge"), ["first_id", "print"]).dropDuplicates(["id"]).select("id", "text")
    sets = stage(own.mapInArrow(_sets(k), "id long, grams binary"), "simhash-sets")
    a, b = (sets.select(F.col("id").alias(c), F.col("grams").alias(f"grams_{c}")) for c in "ab")

    def alike(pairs):
        x = pairs.select("a", "b").join(a, "a").join(b, "b").select("a", "b", "grams_a", "grams_b")
        return stage(x.mapInArrow(_alike(least), "a long, b long"), "simhash-links")

    ends = near.select("a", "b", "dist", F.col("a").alias("id")).union(near.select("a", "b", "dist", F.col("b").alias("id")))
    first = Window.partitionBy("id").orderBy("dist", "a", "b")
    near_ends = ends.withColumn("r", F.row_number().over(first)).filter("r <= 2").select("a", "b").distinct()
    near_ends = stage(near_ends, "simhash-first")
    links = alike(near_ends)
    roots = stage(components(links), "simhash-part")
    rest = near.select("a", "b").join(near_ends, ["a", "b"], "left_anti")
    for c in "ab":
        rest = rest.join(roots.select(F.col("id").alias(c), F.col("root").alias(f"root_{c}")), c, "left")
    rest = stage(rest.filter("coalesce(root_a, a) <> coalesce(root_b, b)").select("a", "b"), "simhash-rest")
    links = links.union(alike(rest))
    roots = stage(components(links), "simhash-part")
    over = _passed_over(near, roots, prints, WIDE_RADIUS, WIDE, plan)
    return roots if over is None else components(links.union(alike(over)))


def keep_one(docs: DataFrame, k: int = NEAR_SHINGLE, alike: float = ALIKE) -> DataFrame:
    """The rows of docs that stay when one document, that of least id, stays of each group of near texts.

    Rows with a null id stay. An id that goes takes all its rows along; of rows that repeat a staying
    id, the first by text stays.
    """
    names = _words(WIDE)
    x = with_fingerprints(docs, k, WIDE, F.xxhash64(F.col("text").cast("binary")).alias("print"))
    rows = stage(x.filter("doc_id is not null"), "simhash-prints")
    one = F.min(F.struct("doc_id", "print")).alias("one")
    prints = rows.groupBy("id", *names).agg(one).select("id", *names, F.col("one.doc_id").alias("first_id"), F.col("one.print").alias("print"))
    prints = stage(prints, "simhash-distinct")
    plan = wide_segments(WIDE, prints.count())
    near = near_fingerprints(prints, WIDE_RADIUS, WIDE, plan)
    named = _least_of(prints, _verified(near, prints, docs, k, alike, plan))
    found = stage(rows.join(named, "id").select("doc_id", "component_id"), "simhash-found")
    gone = found.filter("doc_id <> component_id").select("doc_id").distinct()
    again = found.groupBy("doc_id").agg(F.count("*").alias("n")).filter("n > 1").select("doc_id")
    bad = stage(gone.select(F.col("doc_id").alias("simhash_id")), "simhash-gone")
    rows, at = positional(docs)
    is_it = F.col(at["doc_id"]).cast("long") == F.col("simhash_id")
    x = rows.join(bad.hint("merge"), is_it, "left_anti")
    # ids that repeat: those that stay as the least of their group, first row by text
    stay = again.join(gone, "doc_id", "left_anti").select(F.col("doc_id").alias("simhash_id"))
    stay = stage(stay, "simhash-again")
    order = Window.partitionBy(at["doc_id"]).orderBy(F.col(at["text"]).asc_nulls_first(), *rows.columns)
    dup = rows.join(stay, is_it, "left_semi").withColumn("simhash_row", F.row_number().over(order))
    x = x.join(stay, is_it, "left_anti")
    return x.unionByName(dup.filter("simhash_row = 1").drop("simhash_row")).toDF(*docs.columns)


def op10_simhash(spark, sf_dir: str) -> DataFrame:
    x = near_texts(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return x.select("doc_id", F.lower(F.lpad(F.hex("fp0"), 16, "0")).alias("fingerprint"), "component_id")
