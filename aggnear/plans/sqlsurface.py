"""SQL surface: views, table functions, a hull aggregate and a coefficient function."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import Row

from ..functions.profile import BLOCK_ROWS, Group, few_groups
from ..operators.layout import hull
from ..operators.local import best


class TopkGroup:
    """topk_group(TABLE(rows), k): rows kind 'p' (point_id, x, y) and 'q' (query point: w, x, y) of one query_id partition.

    SELECT * FROM topk_group(TABLE(rows) PARTITION BY query_id, 10)
    """

    def __init__(self):
        self.p, self.q, self.k, self.id = [], [], 1, None

    def eval(self, row: Row, k: int):
        self.k, self.id = k, row["query_id"]
        if row["kind"] == "q":
            self.q.append((row["x"], row["y"], row["w"]))
        else:
            self.p.append((row["point_id"], row["x"], row["y"]))

    def terminate(self):
        if not self.p or not self.q:
            return
        g = Group.of(self.id, *zip(*self.q))
        ids, x, y = (np.array(c, np.int64) for c in zip(*self.p))
        f = g(x, y)
        for n, i in enumerate(best(f, ids, x, y, self.k, 1)):
            yield self.id, n + 1, int(ids[i]), int(x[i]), int(y[i]), int(f[i])


class GridCells:
    """grid_cells(xs, ys): the cells of the grid through sorted coordinates, bounds null where open."""

    def eval(self, xs: list, ys: list):
        ex, ey = [None, *sorted(set(xs)), None], [None, *sorted(set(ys)), None]
        for i in range(len(ex) - 1):
            for j in range(len(ey) - 1):
                yield i, j, ex[i], ex[i + 1], ey[j], ey[j + 1]


def hull_agg(point_id: pd.Series, x: pd.Series, y: pd.Series) -> list:
    """Convex hull of a group's points."""
    i, a, b = (s.to_numpy(np.int64) for s in (point_id, x, y))
    return [{"point_id": int(i[n]), "x": int(a[n]), "y": int(b[n])} for n in hull(a, b, i)]


def piece_of(arr: pd.Series, c: pd.Series) -> pd.Series:
    """How many entries of each sorted array are at or below the coordinate (Arrow, searchsorted)."""
    return pd.Series([int(np.searchsorted(a, x, side="right")) for a, x in zip(arr, c)])


def install(spark: SparkSession, points: DataFrame | None = None, query: DataFrame | None = None) -> None:
    """Register the functions, and points and query as views, with the session."""
    spark.udtf.register("topk_group", F.udtf(TopkGroup, returnType="query_id long, rank long, point_id long, x long, y long, agg_dist long"))
    spark.udtf.register("grid_cells", F.udtf(GridCells, returnType="ci long, cj long, xlo long, xhi long, ylo long, yhi long"))
    spark.udf.register("piece_of", F.pandas_udf(piece_of, "long"))
    spark.udf.register("hull_agg", F.pandas_udf(hull_agg, "array<struct<point_id:long,x:long,y:long>>"))
    if points is not None:
        points.createOrReplaceTempView("points")
    if query is not None:
        query.createOrReplaceTempView("query")


def topk_sql(spark: SparkSession, k: int) -> DataFrame:
    """The scan over the views ``points`` and ``query`` in SQL with a parameter marker: one row a group meets the points, no row per query point.

    The groups are handed to every task, so their size is checked.
    """
    if not few_groups(spark.table("query")):
        raise ValueError(f"more than {BLOCK_ROWS} query rows: use plane.topk")
    return spark.sql(
        """
        WITH g AS (SELECT query_id, collect_list(named_struct('qx', qx, 'qy', qy, 'w', w)) AS rows FROM query GROUP BY query_id),
        f AS (SELECT /*+ BROADCAST(g) */ g.query_id, p.point_id, p.x, p.y,
                     aggregate(g.rows, 0L, (s, q) -> s + q.w * (abs(p.x - q.qx) + abs(p.y - q.qy))) AS agg_dist FROM points p CROSS JOIN g),
        r AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY agg_dist, point_id, x, y) AS BIGINT) AS rank FROM f)
        SELECT query_id, rank, point_id, x, y, agg_dist FROM r WHERE rank <= :k
        """,
        args={"k": k},
    )
