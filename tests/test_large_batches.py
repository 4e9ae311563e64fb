"""Batches of query points that are too large to travel with the plan."""

import random

import pytest

from aggnear.functions import profile
from aggnear.functions.profile import groups_or_table, merged
from aggnear.model import check_k, checked_query
from aggnear.operators import local, metrics, tiles
from aggnear.operators.layout import build_plane
from aggnear.plans import plane
from aggnear.staging import stage


def _tables(spark, own: bool):
    rnd = random.Random(5)
    at = lambda: rnd.randrange(-500, 500)
    points = [(i, at(), at(), rnd.choice([1, 2, 3, None])) for i in range(3000)]
    query = [(q, at() // q, at() + 100 * q, rnd.randrange(1, 5)) for q in (1, 2, 3, 4) for _ in range(60)]
    p = spark.createDataFrame(points, "point_id long, x long, y long, own long")
    return p if own else p.drop("own"), spark.createDataFrame(query, "query_id long, qx long, qy long, w long")


@pytest.mark.parametrize("own", [False, True])
@pytest.mark.parametrize("direction", ["nearest", "farthest"])
def test_tiles_and_peel_answer_batches_of_any_size(spark, monkeypatch, direction, own):
    p, q = _tables(spark, own)
    want = sorted(plane.topk(p, q, 7, direction, strategy="scan").collect())
    layout = build_plane(p, slabs=6, bands=6)
    monkeypatch.setattr(profile, "BLOCK_ROWS", 50)
    monkeypatch.setattr(tiles, "CHUNK", 40)
    for strategy in ("tiles", "peel_grouped"):
        assert sorted(plane.topk(layout, q, 7, direction, strategy=strategy).collect()) == want


def test_tiles_read_of_a_batch_of_any_size(spark, monkeypatch):
    p, q = _tables(spark, False)
    layout, q = build_plane(p, slabs=6, bands=6), stage(merged(checked_query(q)), "query")
    want = sorted(metrics.tiles_read(layout, groups_or_table(q), check_k(7)).collect())
    monkeypatch.setattr(profile, "BLOCK_ROWS", 50)
    assert sorted(metrics.tiles_read(layout, groups_or_table(q), 7).collect()) == want


@pytest.mark.parametrize("direction", ["nearest", "farthest"])
def test_dealt_scan_looks_at_few_points(spark, monkeypatch, direction):
    """A first look bounds a group's answers, flat tiles are answered by their least points: few rows are sent, and all ties are found."""
    rnd = random.Random(8)
    points = [(rnd.randrange(5000), rnd.randrange(2000), rnd.randrange(2000)) for _ in range(6000)]
    query = [(g, rnd.randrange(2000), rnd.randrange(2000), 1) for g in range(40) for _ in range(4)]  # even weights: flat between the middle ones
    query += [(50, rnd.randrange(2000), rnd.randrange(2000), 3) for _ in range(90)]
    p, q = spark.createDataFrame(points, "point_id long, x long, y long"), spark.createDataFrame(query, "query_id long, qx long, qy long, w long")
    want = sorted(plane.topk(p, q, 5, direction, strategy="scan").collect())
    sent = []
    whole = local._answers
    monkeypatch.setattr(local, "TILE", 40)
    monkeypatch.setattr(local, "_answers", lambda k, sign: sent.append(k) or whole(k, sign))
    assert sorted(plane.topk(p, q, 5, direction, strategy="scan_dealt").collect()) == want and sent
    monkeypatch.setattr(local, "LEAST", 0)
    assert sorted(plane.topk(p, q, 5, direction, strategy="scan_dealt").collect()) == want
    _, tiles = local._tiles(p, len(points))
    batch = lambda tau: spark.createDataFrame([(*r, 0, tau.get(r[0])) for r in sorted(query)], "query_id long, qx long, qy long, w long, away long, tau long").toArrow().combine_chunks().to_batches()
    sign = 1 if direction == "nearest" else -1
    rows = [sum(b.num_rows for b in local._wanted(tiles, 5, sign)(batch(t))) for t in ({}, {r.query_id: sign * r.agg_dist for r in want if r["rank"] == 5})]
    assert rows[1] < rows[0]
