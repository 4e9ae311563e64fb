"""Fixed examples of FIXTURES.md (values from the tables at sf0.01, or worked out by hand)."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from aggnear.functions import weights
from aggnear.functions.profile import Group
from aggnear.operators import frontier, line, peel
from aggnear.plans import plane
from aggnear.sources import adapters as A

D = "/root/testdata/sf0.01"


def rows(df, *cols):
    return [tuple(r[c] for c in cols) for r in df.orderBy("rank").collect()]


def test_line_flat_minimum(spark):
    q = A.supplier_by_nation(spark, D).filter("query_id = 7")
    a = weights.anchor(q).first()
    assert (a.ax, a.ax_hi, a.w_total) == (579082, 797339, 10)
    p = A.customer_line(spark, D)
    assert rows(line.topk(p, q, 3), "point_id", "x", "agg_dist") == [(4, 651584, 2429732), (10, 682713, 2429732), (19, 582164, 2429732)]
    far = rows(line.topk(p, q, 3, "farthest"), "point_id", "x", "agg_dist")
    assert far == [(407, -99428, 6913564), (1086, -99374, 6913024), (470, -98825, 6907534)]


def test_line_single_query_point(spark):
    q = A.supplier_by_nation(spark, D).filter("query_id = 12")
    p = A.customer_line(spark, D)
    got = rows(line.topk(p, q, 3), "point_id", "x", "agg_dist")
    assert got == [(919, 854165, 1835), (658, 854033, 1967), (809, 853889, 2111)]
    assert [r[1] for r in rows(line.topk(p, q, 3, "farthest"), "point_id", "agg_dist")] == [955428, 955374, 954825]


def test_plane_general_position(spark):
    q = A.embeddings_query(spark, D, 100).filter("query_id = 3")
    p = A.embeddings_plane(spark, D)
    a = weights.anchor(q).first()
    assert (a.ax, a.ay, a.w_total) == (-67978, 40796, 22)
    near = rows(plane.topk(p, q, 4), "point_id", "agg_dist")
    assert near == [(187, 4689740), (236, 4693706), (364, 4697508), (66, 4698720)]
    far = rows(plane.topk(p, q, 4, "farthest"), "point_id", "agg_dist")
    assert far == [(392, 13450554), (492, 11713814), (154, 11275906), (328, 10901724)]
    quads = frontier.quadrants(p, q)
    counts = {r.quad: r["count"] for r in quads.groupBy("quad").count().collect()}
    assert counts == {1: 102, 2: 47, 3: 89, 4: 203}
    vertices = {r.quad: r["count"] for r in frontier.minimal(quads).groupBy("quad").count().collect()}
    assert vertices == {1: 6, 2: 7, 3: 5, 4: 9}


def test_plane_ties_on_both_axes(spark):
    q = A.part_query(spark, D).filter("query_id = 17")
    got = rows(plane.topk(A.part_plane(spark, D), q, 4), "point_id", "x", "y", "agg_dist")
    assert got == [(651, 2700, 96510, 39800), (1645, 2700, 96450, 39860), (660, 2700, 96600, 39890), (1654, 2600, 96540, 39910)]


def test_cell_leaves_and_comes_back():
    g = Group.of(1, [293, 210], [219, 205], [3, 5])
    assert g.anchor == (210, 205)
    at, search = peel.quadrant_answer(g, 1, "nearest", 3, [1, 2, 3], [366, 279, 392], [252, 394, 398])
    assert search.q.ids[at].tolist() == [1, 2, 3] and search.f[at].tolist() == [1333, 1857, 2709]
    assert search.count["reentered"] == 1 and search.count["lambda"] == 2


def test_cell_coefficients_by_hand(spark):
    from aggnear.operators import cells

    g = Group.of(1, [293, 210], [219, 205], [3, 5])
    q = spark.createDataFrame([(1, 293, 219, 3), (1, 210, 205, 5)], "query_id long, qx long, qy long, w long")
    got = {(r.ci, r.cj): (r.ca, r.cb, r.cc) for r in cells.coefficients(q).collect()}
    assert got[2, 2] == (8, 8, -3611) and got[1, 2] == (2, 8, -1853)
    assert int(g(np.array([366]), np.array([252]))[0]) == 1333


def test_rejected_inputs(spark):
    p = spark.createDataFrame([(1, 1, 1)], "point_id long, x long, y long")
    q = spark.createDataFrame([(1, 0, 0, 1)], "query_id long, qx long, qy long, w long")
    with pytest.raises(ValueError):
        plane.topk(p, q, 0)
    with pytest.raises(ValueError):
        plane.topk(p, q, 1, "sideways")
    with pytest.raises(Exception, match="positive"):
        plane.topk(p, q.withColumn("w", F.lit(0)), 1).collect()
    with pytest.raises(Exception, match="null"):
        plane.topk(p.withColumn("x", F.lit(None).cast("long")), q, 1).collect()
    with pytest.raises(OverflowError):
        Group.of(1, [1 << 50], [0], [1 << 20])
