"""Content-addressed store of token ids.

A document's ids are cut where a rolling hash over the last ``SPAN`` ids has its high bits zero, so
equal passages are cut alike wherever they stand. Chunks are named by the SHA-256 of their bytes and
stored once. The folder of a store holds three tables:

* ``chunks``: digest, n (ids), payload (ids as little-endian unsigned 16- or 32-bit integers);
* ``recipes``: in ascending doc_id order (nulls first), the document's chunk digests and lengths, its
  Merkle root, and its place within its part of the order;
* ``manifest``: per part of the order, its documents, its ids, the ids of all parts before it and the
  Merkle root over its documents;
* ``store``: one row, the store's root over the parts.

Reading back, each stored chunk is hashed against its name, each recipe against its root, each part of
the order against the manifest and the manifest against the store's root; whatever does not match
raises. A document's checksum is put together from its chunks' checksums (the checksum of a
concatenation is linear in them), so no payload crosses the network; ``documents_of`` gives ids.

Defined results: a null or empty text is the end id alone; repeated rows have a recipe each, ties of
doc_id in order of their roots; extra columns are not read; an empty table gives an empty store.
"""

from __future__ import annotations

from bisect import bisect_left
from hashlib import sha256
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import drop, new_folder, parallelism, slices, stage, table
from .tokens import default_path, encode_batches

SPAN, LOW, MEAN_BITS, HIGH = 4, 128, 9, 4096
_GEAR = np.random.default_rng(17).integers(0, 1 << 32, (SPAN, 65536), dtype=np.uint32)
_LOG = "doc_id long, n long, root binary, digests array<binary>, lengths array<int>, payloads array<binary>"


def cut_points(ids: np.ndarray) -> list[int]:
    """Ends of the chunks of an id stream."""
    n = len(ids)
    if n <= LOW:
        return [n]
    low = ids.astype(np.uint16)
    h = _GEAR[0][low[: n - SPAN + 1]]
    for j in range(1, SPAN):
        h += _GEAR[j][low[j : n - SPAN + 1 + j]]
    marks = (np.flatnonzero(h >> np.uint32(32 - MEAN_BITS) == 0) + SPAN).tolist()
    ends, at = [], 0
    while at < n:
        i = bisect_left(marks, at + LOW)
        at = min(marks[i] if i < len(marks) else n, at + HIGH, n)
        ends.append(at)
    return ends


def merkle(leaves: list[bytes]) -> bytes:
    """Root over leaves in order; a leaf without a partner goes up as it is."""
    if not leaves:
        return sha256(b"").digest()
    while len(leaves) > 1:
        pairs = [sha256(b"\x01" + a + b).digest() for a, b in zip(leaves[::2], leaves[1::2])]
        leaves = pairs + leaves[2 * len(pairs) :]
    return leaves[0]


def _pack(ids: np.ndarray) -> tuple[bytes, int]:
    """Bytes of a document's ids, and the bytes of each."""
    kind = "<u2" if int(ids.max(initial=0)) < 1 << 16 else "<u4"
    return ids.astype(kind).tobytes(), int(kind[2])


def unpack(payload: bytes, n: int) -> np.ndarray:
    return np.frombuffer(payload, "<u2" if len(payload) == 2 * n else "<u4").astype("<u4")


def _chunk(path: str):
    def run(batches):
        kinds = [pa.int64(), pa.binary(), pa.list_(pa.binary()), pa.list_(pa.int32()), pa.list_(pa.binary())]
        for batch in slices(batches, 256):
            at, rows = [], []
            for i, ids in encode_batches(path, batch.column(1).to_pylist()):
                ends = cut_points(ids)
                raw, size = _pack(ids)
                loads = [raw[a * size : b * size] for a, b in zip([0, *ends[:-1]], ends)]
                digests = [sha256(x).digest() for x in loads]
                at.append(i)
                rows.append((len(ids), merkle(digests), digests, [b - a for a, b in zip([0, *ends[:-1]], ends)], loads))
                if len(rows) == 256:
                    yield _rows(batch, at, rows, kinds)
                    at, rows = [], []
            if rows:
                yield _rows(batch, at, rows, kinds)

    return run


def _rows(batch, at, rows, kinds):
    return pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(at)), *(pa.array(c, k) for c, k in zip(zip(*rows), kinds))], names=["doc_id", "n", "root", "digests", "lengths", "payloads"])


def _number(batches):
    """Within a part of the order: position and ids before."""
    part, row, ids = TaskContext.get().partitionId(), 0, 0
    for batch in batches:
        n = batch.column(1).to_numpy()
        before = ids + np.cumsum(n) - n
        yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(np.full(len(n), part)), pa.array(np.arange(row, row + len(n))), pa.array(before)], names=[*batch.schema.names, "part", "row", "before"])
        row, ids = row + len(n), ids + int(n.sum())


def _manifest(batches):
    """Rows (part, doc_id, n, root) sorted by part and row -> (part, docs, n, root) per part.

    A document's leaf holds its id too. A part's root is that over its blocks of 1024 documents, so a
    part is never held at once.
    """
    part, leaves, blocks, ids, docs = None, [], [], 0, 0

    def close():
        root = merkle(blocks + ([merkle(leaves)] if leaves else []))
        yield pa.RecordBatch.from_arrays([pa.array([part]), pa.array([docs]), pa.array([ids]), pa.array([root], pa.binary())], names=["part", "docs", "n", "root"])

    for batch in batches:
        for p, doc, n, root in zip(*(c.to_pylist() for c in batch.columns)):
            if p != part:
                if part is not None:
                    yield from close()
                part, leaves, blocks, ids, docs = p, [], [], 0, 0
            leaves.append(sha256(b"\x00" + str(doc).encode() + b" " + root).digest())
            ids += n
            docs += 1
            if len(leaves) == 1024:
                blocks.append(merkle(leaves))
                leaves = []
    if part is not None:
        yield from close()


def _parts(recipes: DataFrame) -> DataFrame:
    x = recipes.select("part", "row", "doc_id", "n", "root").repartition(parallelism(recipes.sparkSession), "part").sortWithinPartitions("part", "row")
    return x.select("part", "doc_id", "n", "root").mapInArrow(_manifest, "part long, docs long, n long, root binary")


def _store_root(manifest: DataFrame) -> bytes:
    """Root over the parts in order; a row per part comes to the driver, as many as the store was written in."""
    rows = sorted((r.part, r.docs, r.n, r.base, bytes(r.root)) for r in manifest.select("part", "docs", "n", "base", "root").collect())
    return merkle([sha256(b"\x02" + repr(r[:4]).encode() + r[4]).digest() for r in rows])


def write(docs: DataFrame, folder: str, path: str | None = None) -> None:
    """Write docs(doc_id, text) as a store into the (new, shared) folder."""
    spark = docs.sparkSession
    x = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("text"))
    log = stage(x.mapInArrow(_chunk(path or default_path()), _LOG), "ids-log", f"{folder}/log", "zstd")
    one = log.select(F.explode(F.arrays_zip("digests", "lengths", "payloads")).alias("c"))
    one = one.select(F.col("c.digests").alias("digest"), F.col("c.lengths").alias("n"), F.col("c.payloads").alias("payload"))
    one.dropDuplicates(["digest"]).write.option("compression", "zstd").parquet(f"{folder}/chunks")
    order = log.select("doc_id", "n", "root", "digests", "lengths").repartitionByRange(parallelism(spark), "doc_id").sortWithinPartitions("doc_id", "root")
    kinds = "doc_id long, n long, root binary, digests array<binary>, lengths array<int>, part long, row long, before long"
    recipes = stage(order.mapInArrow(_number, kinds), "ids-recipes", f"{folder}/recipes")
    drop(log)
    earlier = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)  # one row per part of the order
    manifest = stage(_parts(recipes).withColumn("base", F.coalesce(F.sum("n").over(earlier), F.lit(0))), "ids-manifest", f"{folder}/manifest")
    spark.createDataFrame([(bytearray(_store_root(manifest)),)], "root binary").write.parquet(f"{folder}/store")


def _append_zeros() -> list[np.ndarray]:
    """Per k, tables (4 x 256) that take a crc32 to that of its bytes with 2**k zero bytes put after, less the zeros' own."""
    column = np.array([0xEDB88320, *(1 << i for i in range(31))], dtype=np.uint64)  # one zero bit

    def apply(m, v):
        out = np.zeros_like(v)
        for i in range(32):
            out ^= np.where((v >> np.uint64(i)) & np.uint64(1), m[i], np.uint64(0))
        return out

    for _ in range(3):
        column = apply(column, column)
    tables = []
    for _ in range(48):
        tables.append(np.stack([apply(column, np.arange(256, dtype=np.uint64) << np.uint64(8 * j)) for j in range(4)]))
        column = apply(column, column)
    return tables


def shifted_crc(crc: np.ndarray, after: np.ndarray, tables=[]) -> np.ndarray:  # noqa: B006  built once a process
    """What chunks' checksums add to that of a whole with so many bytes after them; the whole's is their xor."""
    if not tables:
        tables.extend(_append_zeros())
    crc = crc.astype(np.uint64)
    for k in range(int(after.max(initial=0)).bit_length()):
        at = np.flatnonzero((after >> k) & 1)
        v = crc[at]
        crc[at] = np.bitwise_xor.reduce([tables[k][j][(v >> np.uint64(8 * j)) & np.uint64(255)] for j in range(4)])
    return crc.astype(np.int64)


def _check_chunks(batches):
    for batch in batches:
        crc = []
        for digest, n, payload in zip(*(c.to_pylist() for c in batch.columns)):
            if sha256(payload).digest() != digest:
                raise ValueError("a stored chunk does not match its name")
            crc.append(crc32(unpack(payload, n).tobytes()))
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(crc, pa.int64())], names=["digest", "crc"])


def _check_recipes(batches):
    """A row per chunk of each recipe, with the bytes that follow it."""
    for batch in batches:
        n, roots, digests, lengths = (batch.column(i).to_pylist() for i in range(4))
        at, names, after = [], [], []
        for i, (total, root, ds, ls) in enumerate(zip(n, roots, digests, lengths)):
            if merkle(ds) != root or sum(ls) != total:
                raise ValueError("a recipe does not match its root")
            at += [i] * len(ds)
            names += ds
            after += (4 * (total - np.cumsum(ls))).tolist()
        rest = batch.take(pa.array(at, pa.int64()))
        yield pa.RecordBatch.from_arrays([pa.array(names, pa.binary()), pa.array(after, pa.int64()), *(rest.column(i) for i in (4, 5, 6, 7, 0))], names=["digest", "after", "doc_id", "part", "row", "before", "n"])


def _shift(batches):
    for batch in batches:
        if batch.column(1).null_count:
            raise ValueError("a recipe names a chunk that is not stored")
        part = shifted_crc(batch.column(1).to_numpy(), batch.column(0).to_numpy())
        yield pa.RecordBatch.from_arrays([pa.array(part), *batch.columns[2:]], names=["crc", *batch.schema.names[2:]])


_KEYS = ["doc_id", "part", "row", "before", "n"]


def read(spark: SparkSession, folder: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, from the files, all hashes checked on the way."""
    recipes = spark.read.parquet(f"{folder}/recipes").select("n", "root", "digests", "lengths", "doc_id", "part", "row", "before")
    uses = recipes.mapInArrow(_check_recipes, "digest binary, after long, doc_id long, part long, row long, before long, n long")
    chunks = spark.read.parquet(f"{folder}/chunks").select("digest", "n", "payload").mapInArrow(_check_chunks, "digest binary, crc long")
    x = uses.join(chunks, "digest", "left").select("after", F.col("crc"), *_KEYS).mapInArrow(_shift, "crc long, " + ", ".join(f"{k} long" for k in _KEYS))
    x = x.groupBy(*_KEYS).agg(F.bit_xor("crc").alias("ids_crc32"))
    return x.join(_checked_manifest(spark, folder), "part").select("doc_id", (F.col("base") + F.col("before")).alias("start"), F.col("n").alias("n_tokens"), "ids_crc32")


def _checked_manifest(spark: SparkSession, folder: str) -> DataFrame:
    """(part, base) of a manifest that is held against the store's root now, and against the recipes when it is read."""
    theirs = spark.read.parquet(f"{folder}/manifest")
    if [bytes(r.root) for r in spark.read.parquet(f"{folder}/store").collect()] != [_store_root(theirs)]:
        raise ValueError("the manifest does not match the store's root")
    mine = _parts(spark.read.parquet(f"{folder}/recipes")).select("part", F.struct("docs", "n", "root").alias("mine"))
    both = theirs.select("part", "base", F.struct("docs", "n", "root").alias("theirs")).join(mine, "part", "full")
    bad = F.raise_error(F.lit("the recipes do not match the manifest"))
    return both.select("part", F.when(F.col("mine").eqNullSafe(F.col("theirs")), F.col("base")).otherwise(bad.cast("long")).alias("base"))


def verify(spark: SparkSession, folder: str) -> bool:
    """Whether everything that is stored matches its hash."""
    try:
        read(spark, folder).write.format("noop").mode("overwrite").save()
    except Exception:  # noqa: BLE001  raised in workers, each kind under a name of its own
        return False
    return True


def documents_of(spark: SparkSession, folder: str, doc_ids: DataFrame) -> DataFrame:
    """doc_ids(doc_id) -> doc_id, start, ids: the documents themselves."""
    recipes = spark.read.parquet(f"{folder}/recipes").join(doc_ids.select("doc_id").distinct(), "doc_id", "left_semi")
    uses = recipes.select("doc_id", "part", "row", "before", F.posexplode("digests").alias("pos", "digest"))
    x = uses.join(spark.read.parquet(f"{folder}/chunks"), "digest")
    x = x.groupBy("doc_id", "part", "row", "before").agg(F.array_sort(F.collect_list(F.struct("pos", "n", "payload"))).alias("parts"))

    def run(batches):
        for batch in batches:
            ids = [np.concatenate([unpack(p["payload"], p["n"]) for p in parts]).astype(np.int32) for parts in batch.column(3).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array(ids, pa.list_(pa.int32()))], names=["doc_id", "part", "before", "ids"])

    x = x.select("doc_id", "part", "before", "parts").mapInArrow(run, "doc_id long, part long, before long, ids array<int>")
    return x.join(_checked_manifest(spark, folder), "part").select("doc_id", (F.col("base") + F.col("before")).alias("start"), "ids")


def op1_idstore(spark, sf_dir: str) -> DataFrame:
    folder = new_folder(spark, "idstore")
    write(table(spark, sf_dir, "documents").select("doc_id", "text"), folder)
    return read(spark, folder)
