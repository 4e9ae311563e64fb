"""Connected components over an edge table by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop, stage


def _mark(edges: DataFrame):
    return edges.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("s")).first()


def components(edges: DataFrame) -> DataFrame:
    """edges(a, b) of ids -> (id, root): each id with an edge to another one, and the least id it reaches.

    A round hangs the larger neighbours of every node under its least neighbour, then all
    neighbours of every node under the least one; it ends when the edges, kept as larger id ->
    smaller id, are stars around the roots. Node minima are pre-aggregated and staged, so the join
    that hands them out is between two plain shuffles and can split a node with very many edges.
    Null ids and loops are ignored.
    """
    e = edges.filter("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    e = stage(e, "edges")
    last = _mark(e)
    while last.n:
        both = e.union(e.select("v", "u"))
        low = stage(both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")), "edge-low")
        large = stage(both.filter("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct(), "edge-large")
        low2 = stage(large.groupBy("u").agg(F.min("v").alias("m")), "edge-low")
        down = large.join(low2, "u").filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        small = stage(down.union(low2.select("u", F.col("m").alias("v"))).distinct(), "edge-small")
        drop(e, low, large, low2)
        e, mark = small, _mark(small)
        if mark == last:
            break
        last = mark
    return e.select(F.col("u").alias("id"), F.col("v").alias("root")).union(e.select(F.col("v"), F.col("v"))).distinct()
