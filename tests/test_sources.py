"""Point files, answers, staged tables and SQL functions."""

import os

import pytest
from pyspark.sql import functions as F

from aggnear import staging
from aggnear.plans import plane, sqlsurface
from aggnear.sources import adapters as A


@pytest.mark.parametrize("kind", ["parquet", "csv", "json", "orc"])
def test_point_files_and_answers(spark, tmp_path, kind):
    p = spark.createDataFrame([(i, i * 3, 7 - i) for i in range(9)], "point_id long, x long, y long")
    w = p.write.mode("overwrite")
    (w.option("header", True) if kind == "csv" else w).format(kind).save(str(tmp_path / "p"))
    back = A.read_points(spark, str(tmp_path / "p"), kind)
    assert sorted(map(tuple, back.collect())) == sorted(map(tuple, p.collect()))
    q = spark.createDataFrame([(1, 4, 4, 1)], "query_id long, qx long, qy long, w long")
    got = plane.topk(back, q, 3)
    A.write_answer(got, str(tmp_path / "a"))
    assert sorted(map(tuple, spark.read.parquet(str(tmp_path / "a")).collect())) == sorted(map(tuple, got.collect()))
    A.write_answer(got, "", "noop")


def test_sql_functions(spark):
    sqlsurface.install(spark)
    spark.createDataFrame([(1, 0, 0), (2, 4, 0), (3, 4, 4), (4, 0, 4), (5, 2, 2), (6, 2, 0)], "point_id long, x long, y long").createOrReplaceTempView("hull_points")
    ring = spark.sql("SELECT hull_agg(point_id, x, y) AS h FROM hull_points").first().h
    assert {p.point_id for p in ring} == {1, 2, 3, 4}
    cells = spark.sql("SELECT * FROM grid_cells(array(1L, 5L, 1L), array(2L))").collect()
    assert len(cells) == 6 and (cells[0].xlo, cells[0].xhi, cells[0].yhi) == (None, 1, 2)
    assert [r.n for r in spark.sql("SELECT piece_of(array(1L, 4L, 9L), c) AS n FROM VALUES (0L), (4L), (5L), (99L) AS t(c)").collect()] == [0, 2, 2, 3]


def test_staged_tables_are_removed(spark):
    x = staging.stage(spark.range(5).toDF("a"), "gone")
    at = staging._made[-1].removeprefix("file:")
    assert x.count() == 5 and os.path.isdir(at)
    assert staging.drop_staged(spark) >= 1 and not os.path.exists(at) and not staging._made


def test_search_in_an_array(spark):
    from aggnear.functions.profile import upto

    x = spark.createDataFrame([([], 1), ([1, 3, 3, 8], 3), ([1, 3, 3, 8], 0), ([1, 3, 3, 8], 9), (list(range(0, 2000, 2)), 777)], "a array<long>, c long")
    assert [r.n for r in x.select(upto(F.col("a"), F.col("c")).alias("n")).collect()] == [0, 3, 0, 4, 389]
