"""Mixing sources to target weights by Pareto order sampling.

Each source gets a target number of words: a weighted share of the wanted total, never above
``max_copies`` times what the source holds, what is cut off going to the others by weight. A
document is expected in proportion to its own weight (``odds``: one for all, the number of binary
digits of its size, or a column), but at most ``max_copies`` times; the rate is the one at which the
source's expected words are its target. The whole part of that is allocated with certainty, the
fraction is its inclusion probability ``p`` in an ordered sample. Documents are ranked by ``(u/(1-u)) / (p/(1-p))``
with ``u`` a hash of the id, and the sample is the longest start of that order that stays within the
words still wanted, closed by the one document further down whose size comes nearest to what is then
short (if any brings the sum nearer). Nothing is sorted globally: a histogram of the rank finds the one rank bucket in
which the cut lies, and only that bucket's rows are ordered.

Defined results: null texts have size 0; null sources form one source, ranked last; repeated rows
(same id and size) share one decision; sources without words have target 0; an empty table gives an
empty result; columns of the input other than those named are carried along untouched.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import positional, stage, table, word_count

#: Rank buckets per source; a bucket holds about 1/BUCKETS of a source's rows.
BUCKETS = 4096
_TOP = 1 << 52


def uniform(doc_id: Column, seed: int) -> Column:
    """A number strictly between 0 and 1 that depends on the id and the seed alone."""
    digits = F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(doc_id.cast("string"), F.lit("null")))), 1, 13)
    return (F.conv(digits, 16, 10).cast("long").cast("double") + F.lit(0.5)) / F.lit(float(_TOP))


def targets(sizes: DataFrame, cycle=(3, 1, 2), share: float = 1.5, max_copies: int = 2) -> DataFrame:
    """(source, source_size) -> the same with weight and target in words.

    Water level: with sources ordered by cap per unit of weight, the level is the first for which
    the sources before are at their cap and this one is not; later ones give lower levels. One row per source, so the unkeyed
    windows run over as many rows as there are sources.
    """
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    w = F.element_at(F.array(*[F.lit(float(x)) for x in cycle]), ((F.row_number().over(by_name) - 1) % len(cycle) + 1).cast("int"))
    x = sizes.withColumn("weight", w).withColumn("cap", (F.col("source_size") * max_copies).cast("double"))
    order = Window.orderBy(F.col("cap") / F.col("weight"), F.col("source").asc_nulls_last())
    before, after = order.rowsBetween(Window.unboundedPreceding, -1), order.rowsBetween(0, Window.unboundedFollowing)
    everything = Window.partitionBy()
    level = (F.sum("source_size").over(everything) * F.lit(share) - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / F.sum("weight").over(after)
    x = x.withColumn("level", level)
    x = x.withColumn("level", F.max(F.when(F.col("level") * F.col("weight") <= F.col("cap"), F.col("level"))).over(everything))
    full = F.least(F.col("cap"), F.coalesce(F.col("level") * F.col("weight"), F.col("cap")))
    return x.select("source", "source_size", "weight", full.alias("target"))


def _rank(u: Column, p: Column) -> Column:
    p = F.greatest(F.least(p, F.lit(1 - 1e-12)), F.lit(1e-12))
    return (u / (1 - u)) / (p / (1 - p))


def _bucket(q: Column, target: Column, source_size: Column) -> Column:
    """Bucket of a rank, in units of its source's mean odds so that buckets hold like numbers of rows."""
    _, p = _copies(F.coalesce(F.try_divide(target, source_size), F.lit(0.0)))
    p = F.greatest(F.least(p, F.lit(1 - 1e-12)), F.lit(1e-12))
    x = q * (p / (1 - p))
    return F.floor(x / (1 + x) * BUCKETS).cast("int")


def _copies(e: Column) -> tuple[Column, Column]:
    whole = F.floor(e + F.lit(1e-12))
    return whole, F.greatest(e - whole, F.lit(0.0))


def rates(rows: DataFrame, goal: DataFrame, max_copies: int = 2) -> DataFrame:
    """goal(source, source_size, target) plus rate: expected copies per unit of weight, null where all documents are at the most.

    Water level within a source: its distinct weights from the largest down are at max_copies before
    the first whose rate stays below that. The windows run over the distinct weights of a source.
    """
    levels = rows.groupBy("source", "g").agg(F.sum("size").alias("s")).alias("v").join(goal.alias("t"), F.col("v.source").eqNullSafe(F.col("t.source")))
    order = Window.partitionBy("v.source").orderBy(F.col("g").desc())
    before, after = order.rowsBetween(Window.unboundedPreceding, -1), order.rowsBetween(0, Window.unboundedFollowing)
    left = F.col("target") - max_copies * F.coalesce(F.sum("s").over(before), F.lit(0))
    x = levels.select("v.source", "g", F.try_divide(left, F.sum(F.col("g") * F.col("s")).over(after)).alias("rate"))
    x = x.groupBy("source").agg(F.max(F.when(F.col("rate") * F.col("g") <= max_copies, F.col("rate"))).alias("rate"))
    return goal.alias("t").join(x.alias("x"), F.col("t.source").eqNullSafe(F.col("x.source"))).select("t.*", "rate")


def _expected(rate: Column, g: Column, source_size: Column, max_copies: int) -> Column:
    most = F.lit(float(max_copies))
    return F.when((source_size > 0) & (g > 0), F.least(F.coalesce(rate * g, most), most)).otherwise(F.lit(0.0))


def cuts(rows: DataFrame, goal: DataFrame, seed: int, max_copies: int = 2) -> DataFrame:
    """The plan per source: expected copies per unit of weight and the last rank that is taken.

    rows: doc_id, source, size, g (relative weight). goal: source, source_size, target, rate.
    """
    same = rows.groupBy("source", "doc_id", "size", "g").agg(F.count("*").alias("rows"))
    x = same.alias("r").join(goal.alias("t"), F.col("r.source").eqNullSafe(F.col("t.source")))
    e = _expected(F.col("rate"), F.col("g"), F.col("source_size"), max_copies)
    whole, p = _copies(e)
    x = x.select("r.source", "doc_id", "size", (F.col("size") * F.col("rows")).alias("words"), "target", "source_size", whole.alias("whole"), _rank(uniform(F.col("doc_id"), seed), p).alias("q"), (p > 0).alias("open"))
    x = stage(x.withColumn("bucket", _bucket(F.col("q"), F.col("target"), F.col("source_size"))), "mix-ranks")
    sums = x.groupBy("source", "bucket").agg(
        F.sum(F.when(F.col("open"), F.col("words")).otherwise(0)).alias("here"),
        F.sum(F.col("whole") * F.col("words")).alias("sure"),
        F.first("target").alias("target"),
    )
    along = Window.partitionBy("source").orderBy("bucket")
    sums = sums.withColumn("left", F.col("target") - F.sum("sure").over(Window.partitionBy("source")))
    sums = sums.withColumn("before", F.sum("here").over(along) - F.col("here"))
    edge = sums.filter((F.col("before") <= F.col("left")) & (F.col("here") > 0)).groupBy("source").agg(
        F.max_by(F.struct("bucket", "before", "left"), "bucket").alias("edge")
    )
    edge = stage(edge.select(F.col("source").alias("edge_source"), "edge"), "mix-edges")
    x = x.filter("open").join(edge, F.col("source").eqNullSafe(F.col("edge_source")))
    key = F.struct("q", F.col("doc_id").alias("id"), "size")
    run = Window.partitionBy("source").orderBy("q", "doc_id", "size").rowsBetween(Window.unboundedPreceding, 0)
    inside = x.filter(F.col("bucket") == F.col("edge.bucket")).withColumn("upto", F.col("edge.before") + F.sum("words").over(run))
    last = inside.filter(F.col("upto") <= F.col("edge.left")).groupBy("edge_source").agg(F.max(key).alias("cut"), F.max("upto").alias("upto"))
    plan = edge.alias("e").join(last.alias("l"), F.col("e.edge_source").eqNullSafe(F.col("l.edge_source")), "left")
    plan = stage(plan.select(F.col("e.edge_source").alias("plan_source"), "e.edge", "cut", (F.col("edge.left") - F.coalesce("upto", "edge.before")).alias("short")), "mix-cuts")
    rest = x.drop("edge").join(plan, F.col("source").eqNullSafe(F.col("plan_source")))
    rest = rest.filter((F.col("bucket") > F.col("edge.bucket")) | ((F.col("bucket") == F.col("edge.bucket")) & F.coalesce(key > F.col("cut"), F.lit(True))))
    off = F.abs(F.col("words") - F.col("short"))
    closing = rest.filter(off < F.col("short")).groupBy("plan_source").agg(F.min(F.struct(off.alias("off"), key.alias("key"))).alias("c"))
    out = goal.alias("t").join(plan.alias("e"), F.col("t.source").eqNullSafe(F.col("e.plan_source")), "left")
    out = out.join(closing.alias("l"), F.col("t.source").eqNullSafe(F.col("l.plan_source")), "left")
    return out.select(
        F.col("t.source").alias("mix_source"),
        "source_size",
        "target",
        F.col("rate").alias("mix_rate"),
        F.col("edge.bucket").alias("mix_bucket"),
        F.col("cut").alias("mix_cut"),
        F.col("c.key").alias("mix_closing"),
    )


def _weight(odds: str | None, size: Column, at=lambda c: c) -> Column:
    if odds is None:
        return F.lit(1.0)
    if odds == "size":
        return F.length(F.bin(size + 1)).cast("double")
    return F.greatest(F.coalesce(F.col(at(odds)).cast("double"), F.lit(0.0)), F.lit(0.0))


def mix(docs: DataFrame, *, cycle=(3, 1, 2), share: float = 1.5, max_copies: int = 2, seed: int = 7, odds: str | None = None) -> DataFrame:
    """docs plus mix_size, mix_source_size, mix_target and mix_copies (how often the mix takes the row).

    odds: None (all documents of a source alike), ``"size"`` (in proportion to the binary digits of the
    size plus one, so the middle of a long scale stands closer to its ends), or the name of a column
    of weights, null and negative ones counting as 0; it should have few distinct values.
    """
    size = word_count(F.col("text"))
    rows = docs.select("doc_id", "source", size.alias("size"), *([F.col(odds)] if odds and odds != "size" else []))
    rows = stage(rows.select("doc_id", "source", "size", _weight(odds, F.col("size")).alias("g")), "mix-sizes")
    sums = stage(rows.groupBy("source").agg(F.sum("size").alias("source_size")), "mix-sources")
    goal = targets(sums, cycle, share, max_copies).select("source", "source_size", "target")
    plan = stage(cuts(rows, stage(rates(rows, goal, max_copies), "mix-goal"), seed, max_copies), "mix-plan")
    named, at = positional(docs)
    x = named.withColumn("mix_size", word_count(F.col(at["text"]))).withColumn("mix_g", _weight(odds, F.col("mix_size"), at.get))
    x = x.join(plan, F.col(at["source"]).eqNullSafe(F.col("mix_source")))
    doc_id = F.col(at["doc_id"])
    whole, p = _copies(_expected(F.col("mix_rate"), F.col("mix_g"), F.col("source_size"), max_copies))
    q = _rank(uniform(doc_id, seed), p)
    bucket = _bucket(q, F.col("target"), F.col("source_size"))
    key = F.struct(q.alias("q"), doc_id.alias("id"), F.col("mix_size").alias("size"))
    in_cut = F.coalesce(key <= F.col("mix_cut"), F.lit(False))
    take = (p > 0) & ((bucket < F.col("mix_bucket")) | ((bucket == F.col("mix_bucket")) & in_cut) | F.coalesce(key == F.col("mix_closing"), F.lit(False)))
    copies = (whole + F.coalesce(take, F.lit(False)).cast("int")).cast("int")
    x = x.select(*at.values(), "mix_size", F.col("source_size").alias("mix_source_size"), F.col("target").alias("mix_target"), copies.alias("mix_copies"))
    return x.toDF(*docs.columns, *MIXED)


#: Columns that mix puts after those of its input.
MIXED = ("mix_size", "mix_source_size", "mix_target", "mix_copies")


def repeated(docs: DataFrame, **options) -> DataFrame:
    """The mix itself: each row of docs as often as it is taken, columns as they are."""
    mine = ("doc_id", "source", "text", options.get("odds"))
    x = mix(docs.toDF(*[c if c in mine else f"m{i}" for i, c in enumerate(docs.columns)]), **options)
    x = x.filter("mix_copies > 0").withColumn("mix_copy", F.explode(F.sequence(F.lit(1), F.col("mix_copies"))))
    return x.drop(*MIXED, "mix_copy").toDF(*docs.columns)


def op6_mix(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "source", "text")
    x = mix(docs, odds="size")
    return x.select(
        "doc_id",
        F.col("mix_size").alias("size"),
        F.col("mix_source_size").alias("source_size"),
        F.col("mix_target").alias("target"),
        (F.col("mix_copies") * F.col("mix_size")).alias("taken"),
        F.col("mix_copies").alias("copies"),
    )


SQL = r"""
WITH d0 AS (
  SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size,
         (('0x' || substr(md5('7:' || coalesce(doc_id::VARCHAR, 'null')), 1, 13))::BIGINT + 0.5::DOUBLE) / 4503599627370496::DOUBLE AS u
  FROM documents),
d AS (SELECT *, length(bin(size + 1))::DOUBLE AS g FROM d0),
s AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
w AS (SELECT *, [3.0, 1.0, 2.0][(row_number() OVER (ORDER BY source ASC NULLS LAST) - 1) % 3 + 1]::DOUBLE AS weight,
             (source_size * 2)::DOUBLE AS cap FROM s),
l AS (SELECT *, (sum(source_size) OVER () * 1.5::DOUBLE
               - coalesce(sum(cap) OVER (ORDER BY cap / weight, source ASC NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
              / sum(weight) OVER (ORDER BY cap / weight, source ASC NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM w),
m AS (SELECT *, max(CASE WHEN level * weight <= cap THEN level END) OVER () AS flat FROM l),
t AS (SELECT source, source_size, least(cap, coalesce(flat * weight, cap)) AS target FROM m),
v AS (SELECT source, g, sum(size)::BIGINT AS s FROM d GROUP BY source, g),
r AS (SELECT v.source, g, (target - 2 * coalesce(sum(s) OVER (PARTITION BY v.source ORDER BY g DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
             / nullif(sum(g * s) OVER (PARTITION BY v.source ORDER BY g DESC ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING), 0) AS rate
      FROM v JOIN t ON v.source IS NOT DISTINCT FROM t.source),
y AS (SELECT source, max(rate) FILTER (rate * g <= 2) AS rate FROM r GROUP BY source),
e AS (SELECT d.*, t.source_size, t.target, CASE WHEN t.source_size > 0 THEN least(coalesce(rate * g, 2.0::DOUBLE), 2.0::DOUBLE) ELSE 0 END AS e
      FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source JOIN y ON d.source IS NOT DISTINCT FROM y.source),
f AS (SELECT *, floor(e + 1e-12)::BIGINT AS whole, greatest(e - floor(e + 1e-12), 0) AS p0 FROM e),
q AS (SELECT *, (u / (1 - u)) / (greatest(least(p0, 1 - 1e-12), 1e-12) / (1 - greatest(least(p0, 1 - 1e-12), 1e-12))) AS q FROM f),
c AS (SELECT *, target - sum(whole * size) OVER (PARTITION BY source) AS wanted,
             CASE WHEN p0 > 0 THEN sum(size) OVER (PARTITION BY source ORDER BY q, doc_id, size RANGE UNBOUNDED PRECEDING) END AS upto,
             size * count(*) OVER (PARTITION BY source, doc_id, size) AS words FROM q),
h AS (SELECT *, wanted - coalesce(max(CASE WHEN upto <= wanted THEN upto END) OVER (PARTITION BY source), 0) AS short FROM c),
z AS (SELECT source, arg_min({'id': doc_id, 's': size}, {'a': abs(words - short), 'q': q, 'i': doc_id, 's': size}) AS z FROM h
      WHERE p0 > 0 AND upto > wanted AND abs(words - short) < short GROUP BY source),
k AS (SELECT h.*, whole + (p0 > 0 AND (upto <= wanted OR coalesce(h.doc_id = z.z.id AND h.size = z.z.s, false)))::BIGINT AS copies
      FROM h LEFT JOIN z ON h.source IS NOT DISTINCT FROM z.source)
SELECT doc_id, size, source_size, target, (copies * size)::BIGINT AS taken, copies::INT AS copies FROM k
"""
