"""The given tables as point sets and query groups, in whole-number ticks; and point files."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def cents(c: str) -> Column:
    return F.round(F.col(c) * 100).cast("long")


def micros(c: Column) -> Column:
    return F.round(c.cast("double") * 1_000_000).cast("long")


def words(c: str) -> Column:
    return F.size(F.split(F.col(c), " ")).cast("long")


def days(c: str) -> Column:
    return F.datediff(F.col(c).cast("date"), F.lit("1970-01-01").cast("date")).cast("long")


def points(df: DataFrame, point_id, x, y=None, own=None) -> DataFrame:
    cols = [_c(point_id).alias("point_id"), _c(x).alias("x")]
    cols += [_c(y).alias("y")] if y is not None else []
    cols += [_c(own).alias("own")] if own is not None else []
    return df.select(*cols)


def query(df: DataFrame, query_id, qx, qy=None, w=1) -> DataFrame:
    cols = [_c(query_id).alias("query_id"), _c(qx).alias("qx")]
    cols += [_c(qy).alias("qy")] if qy is not None else []
    return df.select(*cols, (F.lit(w) if isinstance(w, int) else _c(w)).cast("long").alias("w"))


def _c(x) -> Column:
    return (F.col(x) if isinstance(x, str) else x if isinstance(x, Column) else F.lit(x)).cast("long")


def read_points(spark: SparkSession, path: str, kind: str = "parquet", plane: bool = True) -> DataFrame:
    """A point file (parquet, csv with header, json lines or orc) with a fixed schema."""
    from ..model import LINE_POINTS, PLANE_POINTS

    reader = spark.read.schema(PLANE_POINTS if plane else LINE_POINTS)
    return (reader.option("header", True) if kind == "csv" else reader).format(kind).load(path)


def write_answer(answer: DataFrame, path: str, kind: str = "parquet") -> None:
    """An answer or counters table, replaced at this path; kind ``noop`` times a plan without output."""
    w = answer.write.mode("overwrite")
    w.format("noop").save() if kind == "noop" else w.format(kind).save(path)


# Point sets ------------------------------------------------------------------------------------


def customer_line(spark, d) -> DataFrame:
    return points(table(spark, d, "customer"), "c_custkey", cents("c_acctbal"))


def supplier_by_nation(spark, d) -> DataFrame:
    return query(table(spark, d, "supplier"), "s_nationkey", cents("s_acctbal"), w=1 + F.col("s_suppkey") % 3)


def embeddings_plane(spark, d) -> DataFrame:
    e = table(spark, d, "embeddings")
    return points(e, "vec_id", micros(F.col("embedding")[0]), micros(F.col("embedding")[1]), own="label")


def embeddings_query(spark, d, most: int | None = None, eighths: int = 8) -> DataFrame:
    """All vectors of a label are its group; ``most`` takes those of smaller id (worked examples), eighths vary m (each holds those before it)."""
    e = table(spark, d, "embeddings")
    e = e if most is None else e.filter(F.col("vec_id") < most)
    e = e if eighths == 8 else e.filter(F.pmod(F.xxhash64("vec_id"), F.lit(8)) < eighths)
    return query(e, "label", micros(F.col("embedding")[0]), micros(F.col("embedding")[1]), w=1 + F.col("vec_id") % 4)


def brand(c: str = "p_brand") -> Column:
    return F.regexp_replace(F.col(c), "[^0-9]", "").cast("long")


def part_plane(spark, d) -> DataFrame:
    return points(table(spark, d, "part"), "p_partkey", F.col("p_size") * 100, cents("p_retailprice"), own=brand())


def part_query(spark, d) -> DataFrame:
    return query(table(spark, d, "part").filter(F.col("p_type") == "ECONOMY"), brand(), F.col("p_size") * 100, cents("p_retailprice"))


def part_sales_query(spark, d) -> DataFrame:
    sold = table(spark, d, "lineitem").groupBy("l_partkey").agg(F.sum("l_quantity").cast("long").alias("sold"))
    p = table(spark, d, "part").join(sold, F.col("p_partkey") == F.col("l_partkey"))
    return query(p, brand(), F.col("p_size") * 100, cents("p_retailprice"), w="sold")


def lineitem_plane(spark, d) -> DataFrame:
    return points(table(spark, d, "lineitem"), F.col("l_orderkey") * 10 + F.col("l_linenumber"), cents("l_quantity"), cents("l_extendedprice"))


def part_by_brand(spark, d) -> DataFrame:
    return query(table(spark, d, "part"), brand(), F.col("p_size") * 100, cents("p_retailprice"), w=1 + F.col("p_partkey") % 3)


def dearest_order_query(spark, d) -> DataFrame:
    """The lines of the order of the highest total price, weighted by line number."""
    lines = table(spark, d, "lineitem")
    placed = table(spark, d, "orders").join(lines.select(F.col("l_orderkey").alias("o_orderkey")), "o_orderkey", "left_semi")
    one = placed.orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(1).select(F.col("o_orderkey").alias("l_orderkey"))
    return query(lines.join(one, "l_orderkey"), "l_orderkey", cents("l_quantity"), cents("l_extendedprice"), w="l_linenumber")


def priority() -> Column:
    return F.substring("o_orderpriority", 1, 1).cast("long")


def orders_plane(spark, d) -> DataFrame:
    return points(table(spark, d, "orders"), "o_orderkey", days("o_orderdate") * 100, cents("o_totalprice"))


def orders_query(spark, d) -> DataFrame:
    return query(table(spark, d, "orders"), "o_custkey", days("o_orderdate") * 100, cents("o_totalprice"), w=priority())


def events_plane(spark, d) -> DataFrame:
    return points(table(spark, d, "events"), "event_id", F.unix_seconds(F.col("ts").cast("timestamp")), cents("value"))


def events_query(spark, d) -> DataFrame:
    e = table(spark, d, "events").filter(F.col("event_type") == "purchase")
    return query(e, "user_id", F.unix_seconds(F.col("ts").cast("timestamp")), cents("value"))


def documents_plane(spark, d) -> DataFrame:
    return points(table(spark, d, "documents"), "doc_id", "n_chars", words("text"))


def documents_query(spark, d) -> DataFrame:
    x = table(spark, d, "documents").join(table(spark, d, "labels").filter("quality = 1"), "doc_id")
    return query(x, F.lit(1), "n_chars", words("text"), w=1 + F.col("toxic"))


def benchmark_query(spark, d) -> DataFrame:
    return query(table(spark, d, "benchmark"), F.lit(1), F.length("text"), words("text"))


def pages_plane(spark, d) -> DataFrame:
    return points(table(spark, d, "pages"), "page_id", F.length("url"), F.length("html"))


def pages_query(spark, d) -> DataFrame:
    return query(table(spark, d, "pages"), F.lit(1), F.length("url"), F.length("html"))


def conversations_plane(spark, d) -> DataFrame:
    return points(table(spark, d, "conversations"), F.col("conv_id") * 100 + F.col("turn"), F.col("turn") * 100, F.length("text"))


def conversations_query(spark, d) -> DataFrame:
    return query(table(spark, d, "conversations").filter("role = 'system'"), F.lit(1), F.col("turn") * 100, F.length("text"))
