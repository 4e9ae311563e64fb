"""The grid of cells made in strips."""

import numpy as np
from pyspark.sql import functions as F

from aggnear.functions.profile import Group
from aggnear.model import checked_query
from aggnear.operators import cells


def test_a_large_grid_is_made_in_many_places(spark):
    rng, m = np.random.default_rng(5), 2 * 512 + 70
    x, y, w = rng.permutation(5000)[:m], rng.permutation(60)[np.arange(m) % 60], rng.integers(1, 5, m)
    rows = [(1, *map(int, r)) for r in zip(x, y, w)] + [(2, 5, 5, 1), (2, 9, 5, 2)]
    q = checked_query(spark.createDataFrame(rows, "query_id long, qx long, qy long, w long"))
    # as large tables are joined: no broadcast, no small partitions put together
    large = {"spark.sql.adaptive.coalescePartitions.enabled": "false", "spark.sql.autoBroadcastJoinThreshold": "-1"}
    held = {c: spark.conf.get(c) for c in large}
    try:
        for c, v in large.items():
            spark.conf.set(c, v)
        got = cells.coefficients(q).withColumn("at", F.spark_partition_id()).toPandas()
    finally:
        for c, v in held.items():
            spark.conf.set(c, v)
    assert len(got) == (m + 1) * 61 + 3 * 2 and not got.duplicated(["query_id", "ci", "cj"]).any()
    one = got[got.query_id == 1]
    assert one["at"].nunique() > 1  # a group is no single task's work
    g = Group.of(1, x, y, w)
    px, py = rng.integers(-10, 5010, 300), rng.integers(-10, 70, 300)
    form = one.set_index(["ci", "cj"]).loc[list(zip(np.searchsorted(g.fx.v, px, "right"), np.searchsorted(g.fy.v, py, "right")))]
    assert (form.ca.to_numpy() * px + form.cb.to_numpy() * py + form.cc.to_numpy() == g(px, py)).all()
