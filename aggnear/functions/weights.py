"""Weighted medians and prefix profiles of query groups."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

_AXES = {"x": "qx", "y": "qy"}


def unweighted(query: DataFrame) -> DataFrame:
    """The same group with every weight 1."""
    return query.withColumn("w", F.lit(1).cast("long"))


def merge_axis(query: DataFrame, axis: str = "x") -> DataFrame:
    """(query_id, v, w): one row per distinct coordinate, weights added up."""
    return query.groupBy("query_id", F.col(_AXES[axis]).alias("v")).agg(F.sum("w").alias("w"))


def _running(query: DataFrame, axis: str) -> DataFrame:
    order = Window.partitionBy("query_id").orderBy("v")
    upto, all_ = order.rowsBetween(Window.unboundedPreceding, 0), Window.partitionBy("query_id")
    m = merge_axis(query, axis)
    wv = F.col("w") * F.col("v")
    return m.select(
        "query_id", "v", "w",
        F.sum("w").over(upto).alias("cw"), F.sum(wv).over(upto).alias("cwv"),
        F.sum("w").over(all_).alias("w_total"), F.sum(wv).over(all_).alias("wv_total"),
    )


def axis_anchor(query: DataFrame, axis: str = "x") -> DataFrame:
    """(query_id, a, a_hi, w_total): the interval of all minimisers; a is the lower weighted median."""
    r = _running(query, axis)
    return r.groupBy("query_id").agg(
        F.min(F.when(2 * F.col("cw") >= F.col("w_total"), F.col("v"))).alias("a"),
        F.min(F.when(2 * F.col("cw") > F.col("w_total"), F.col("v"))).alias("a_hi"),
        F.max("w_total").alias("w_total"),
    )


def axis_anchor_by_selection(query: DataFrame, axis: str = "x", fan: int = 64) -> DataFrame:
    """The same as ``axis_anchor`` without a sort: bucket sums, keep the bucket that crosses half the weight, repeat.

    Rounds are log(span) / log(fan); each is one pass with a partial aggregate, so one very large
    group is no single task's work.
    """
    m = merge_axis(query, axis)
    total = m.groupBy("query_id").agg(F.sum("w").alias("w_total"), F.min("v").alias("lo0"), F.max("v").alias("hi0"))
    out = None
    for name, hit in (("a", lambda c: 2 * c >= F.col("w_total")), ("a_hi", lambda c: 2 * c > F.col("w_total"))):
        state = total.select("query_id", "w_total", F.col("lo0").alias("lo"), F.col("hi0").alias("hi"), F.lit(0).cast("long").alias("below"))
        span = total.agg(F.max(F.col("hi0") - F.col("lo0"))).first()[0] or 0
        while span > 0:
            width = F.greatest(F.lit(1), F.ceil((F.col("hi") - F.col("lo") + 1) / fan)).cast("long")
            b = m.join(state, "query_id").filter(F.col("v").between(F.col("lo"), F.col("hi"))).withColumn("width", width)
            b = b.withColumn("b", F.expr("(v - lo) div width"))
            b = b.groupBy("query_id", "w_total", "lo", "hi", "below", "width", "b").agg(F.sum("w").alias("w"))
            run = Window.partitionBy("query_id").orderBy("b").rowsBetween(Window.unboundedPreceding, 0)
            b = b.withColumn("c", F.col("below") + F.sum("w").over(run)).filter(hit(F.col("c")))
            first = b.groupBy("query_id", "w_total").agg(F.min_by(F.struct("lo", "hi", "width", "b", "w", "c"), "b").alias("s"))
            lo = F.col("s.lo") + F.col("s.b") * F.col("s.width")
            state = first.select("query_id", "w_total", lo.alias("lo"), F.least(F.col("s.hi"), lo + F.col("s.width") - 1).alias("hi"), (F.col("s.c") - F.col("s.w")).alias("below"))
            span = 0 if span < fan else -(-(span + 1) // fan) - 1
        one = m.join(state, "query_id").filter(F.col("v").between(F.col("lo"), F.col("hi"))).groupBy("query_id", "w_total").agg(F.min("v").alias(name))
        out = one if out is None else out.join(one.drop("w_total"), "query_id")
    return out.select("query_id", "a", "a_hi", "w_total")


def anchor(query: DataFrame, how: str = "sort") -> DataFrame:
    """(query_id, ax, ax_hi[, ay, ay_hi], w_total): a global minimum point of each group's distance."""
    one = {"sort": axis_anchor, "select": axis_anchor_by_selection}[how]
    x = one(query, "x").withColumnsRenamed({"a": "ax", "a_hi": "ax_hi"})
    if "qy" not in query.columns:
        return x
    y = one(query, "y").withColumnsRenamed({"a": "ay", "a_hi": "ay_hi"}).drop("w_total")
    return x.join(y, "query_id")


def profile(query: DataFrame, axis: str = "x") -> DataFrame:
    """(query_id, arr: sorted array of v, cw, cwv, w_total, wv_total)."""
    entry = F.struct("v", "cw", "cwv")
    return _running(query, axis).groupBy("query_id").agg(
        F.array_sort(F.collect_list(entry)).alias("arr"), F.max("w_total").alias("w_total"), F.max("wv_total").alias("wv_total")
    )


def profile_rows(query: DataFrame, axis: str = "x") -> DataFrame:
    """Flat form with prefix and suffix sums: query_id, v, cw, cwv, sw, swv."""
    r = _running(query, axis)
    suffix = F.col("w_total") - F.col("cw") + F.col("w")
    suffix_v = F.col("wv_total") - F.col("cwv") + F.col("w") * F.col("v")
    return r.select("query_id", "v", "cw", "cwv", suffix.alias("sw"), suffix_v.alias("swv"))


def intervals(query: DataFrame, axis: str = "x") -> DataFrame:
    """(query_id, i, lo, hi, slope, rest): the pieces of each group's axis function, lo and hi null where open.

    Piece i lies between the i-th and the next distinct coordinate, so a group of m has m + 1 pieces.
    """
    r = _running(query, axis)
    order = Window.partitionBy("query_id").orderBy("v")
    slope = 2 * F.col("cw") - F.col("w_total")
    own = r.select("query_id", F.row_number().over(order).cast("long").alias("i"), F.col("v").alias("lo"), F.lead("v").over(order).alias("hi"), slope.alias("slope"), (F.col("wv_total") - 2 * F.col("cwv")).alias("rest"))
    none = F.lit(None).cast("long")
    first = r.groupBy("query_id").agg(F.min("v").alias("hi"), F.max("w_total").alias("w_total"), F.max("wv_total").alias("wv_total"))
    first = first.select("query_id", F.lit(0).cast("long").alias("i"), none.alias("lo"), "hi", (-F.col("w_total")).alias("slope"), F.col("wv_total").alias("rest"))
    return first.unionByName(own)


def sorted_groups(query: DataFrame) -> DataFrame:
    """query rows -> (query_id, q): one array of (v, w) per group, ascending: the form that ``q_sorted`` searches take."""
    return merge_axis(query, "x").groupBy("query_id").agg(F.array_sort(F.collect_list(F.struct("v", "w"))).alias("q"))


def _running_sums(batches):
    """(query_id, v array, w array) -> the profile of each, in one pass over the flat values."""
    for batch in batches:
        lists, w = batch.column(1), batch.column(2).flatten().to_numpy(zero_copy_only=False)
        v = lists.flatten().to_numpy(zero_copy_only=False)
        size = lists.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
        end = np.cumsum(size)
        inner = np.ones(len(v), bool)
        inner[(end - size)[size > 0]] = False  # the first entry of each list
        if (np.diff(v, prepend=v[:1]) < 0)[inner].any():
            raise ValueError("query: q is not in ascending order")
        upto = []
        for x in (w, w * v):
            total = np.r_[0, np.cumsum(x)]
            upto.append(total[1:] - np.repeat(total[end - size], size))
        entries = pa.StructArray.from_arrays([pa.array(v), *map(pa.array, upto)], names=["v", "cw", "cwv"])
        arr = pa.ListArray.from_arrays(pa.array(np.r_[0, end].astype(np.int32)), entries)
        last = np.maximum(end - 1, 0)
        totals = [pa.array(np.where(size > 0, x[last], 0) if len(x) else size * 0) for x in upto]
        yield pa.RecordBatch.from_arrays([batch.column(0), arr, *totals], names=["query_id", "arr", "w_total", "wv_total"])


def profile_of_sorted(groups: DataFrame, axis: str = "x") -> DataFrame:
    """groups(query_id, q) -> the profile, by one pass over each array: no shuffle, no sort; an array out of order raises."""
    x = groups.select(F.col("query_id").cast("long").alias("query_id"), F.transform("q", lambda e: e["v"].cast("long")).alias("v"), F.transform("q", lambda e: e["w"].cast("long")).alias("w"))
    return x.mapInArrow(_running_sums, "query_id long, arr array<struct<v:bigint,cw:bigint,cwv:bigint>>, w_total long, wv_total long")


def anchor_of_sorted(groups: DataFrame) -> DataFrame:
    """groups(query_id, q) -> query_id, ax, ax_hi, w_total, from the profile's running weights."""
    x = profile_of_sorted(groups)
    first = lambda hit: F.array_min(F.transform(F.filter("arr", hit), lambda e: e["v"]))
    return x.select("query_id", first(lambda e: 2 * e["cw"] >= F.col("w_total")).alias("ax"), first(lambda e: 2 * e["cw"] > F.col("w_total")).alias("ax_hi"), "w_total")
