"""DuckDB text of the point sets, query groups, and of the answers by definition."""

from __future__ import annotations

_E = "round(embedding[{i}]::DOUBLE * 1000000)::BIGINT"
_DAY = "(datediff('day', DATE '1970-01-01', o_orderdate::DATE)::BIGINT)"
_BRAND = "regexp_replace(p_brand, '[^0-9]', '', 'g')::BIGINT"
_WORDS = "len(string_split({c}, ' '))::BIGINT"


def c(x: str) -> str:
    return f"round({x} * 100)::BIGINT"


_TS = "floor(epoch(ts))::BIGINT"

POINTS = {
    "customer": f"SELECT c_custkey::BIGINT AS point_id, {c('c_acctbal')} AS x FROM customer",
    "orders_price": f"SELECT o_orderkey::BIGINT AS point_id, {c('o_totalprice')} AS x FROM orders",
    "orders_day": f"SELECT o_orderkey::BIGINT AS point_id, {_DAY} AS x FROM orders",
    "supplier": f"SELECT s_suppkey::BIGINT AS point_id, {c('s_acctbal')} AS x FROM supplier",
    "embeddings": f"SELECT vec_id::BIGINT AS point_id, {_E.format(i=1)} AS x, {_E.format(i=2)} AS y, label::BIGINT AS own FROM embeddings",
    "part": f"SELECT p_partkey::BIGINT AS point_id, (p_size * 100)::BIGINT AS x, {c('p_retailprice')} AS y, {_BRAND} AS own FROM part",
    "lineitem": f"SELECT (l_orderkey * 10 + l_linenumber)::BIGINT AS point_id, {c('l_quantity')} AS x, {c('l_extendedprice')} AS y FROM lineitem",
    "orders": f"SELECT o_orderkey::BIGINT AS point_id, {_DAY} * 100 AS x, {c('o_totalprice')} AS y FROM orders",
    "events": f"SELECT event_id::BIGINT AS point_id, {_TS} AS x, {c('value')} AS y FROM events",
    "documents": f"SELECT doc_id::BIGINT AS point_id, n_chars::BIGINT AS x, {_WORDS.format(c='text')} AS y FROM documents",
    "pages": "SELECT page_id::BIGINT AS point_id, length(url)::BIGINT AS x, length(html)::BIGINT AS y FROM pages",
    "conversations": "SELECT (conv_id * 100 + turn)::BIGINT AS point_id, (turn * 100)::BIGINT AS x, length(text)::BIGINT AS y FROM conversations",
}
POINTS["embeddings_all"] = POINTS["embeddings"].replace(", label::BIGINT AS own", "")
QUERIES = {
    "supplier": f"SELECT s_nationkey::BIGINT AS query_id, {c('s_acctbal')} AS qx, (1 + s_suppkey % 3)::BIGINT AS w FROM supplier",
    "orders_price": f"SELECT o_custkey::BIGINT AS query_id, {c('o_totalprice')} AS qx, 1::BIGINT AS w FROM orders",
    "orders_day": f"SELECT o_custkey::BIGINT AS query_id, {_DAY} AS qx, left(o_orderpriority, 1)::BIGINT AS w FROM orders",
    "segment": f"SELECT ascii(c_mktsegment)::BIGINT AS query_id, {c('c_acctbal')} AS qx, 1::BIGINT AS w FROM customer",
    "embeddings": f"SELECT label::BIGINT AS query_id, {_E.format(i=1)} AS qx, {_E.format(i=2)} AS qy, (1 + vec_id % 4)::BIGINT AS w FROM embeddings",
    "part": f"SELECT {_BRAND} AS query_id, (p_size * 100)::BIGINT AS qx, {c('p_retailprice')} AS qy, 1::BIGINT AS w FROM part WHERE p_type = 'ECONOMY'",
    "part_sales": f"SELECT {_BRAND} AS query_id, (p_size * 100)::BIGINT AS qx, {c('p_retailprice')} AS qy, s.sold AS w FROM part "
    f"JOIN (SELECT l_partkey, sum(l_quantity)::BIGINT AS sold FROM lineitem GROUP BY 1) s ON p_partkey = l_partkey",
    "lineitem": f"SELECT l_orderkey::BIGINT AS query_id, {c('l_quantity')} AS qx, {c('l_extendedprice')} AS qy, l_linenumber::BIGINT AS w FROM lineitem "
    f"WHERE l_orderkey = (SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem) ORDER BY o_totalprice DESC, o_orderkey LIMIT 1)",
    "brands": f"SELECT {_BRAND} AS query_id, (p_size * 100)::BIGINT AS qx, {c('p_retailprice')} AS qy, (1 + p_partkey % 3)::BIGINT AS w FROM part",
    "orders": f"SELECT o_custkey::BIGINT AS query_id, {_DAY} * 100 AS qx, {c('o_totalprice')} AS qy, left(o_orderpriority, 1)::BIGINT AS w FROM orders",
    "events": f"SELECT user_id::BIGINT AS query_id, {_TS} AS qx, {c('value')} AS qy, 1::BIGINT AS w FROM events WHERE event_type = 'purchase'",
    "documents": f"SELECT 1::BIGINT AS query_id, n_chars::BIGINT AS qx, {_WORDS.format(c='text')} AS qy, (1 + toxic)::BIGINT AS w FROM documents JOIN labels USING (doc_id) WHERE quality = 1",
    "benchmark": f"SELECT 1::BIGINT AS query_id, length(text)::BIGINT AS qx, {_WORDS.format(c='text')} AS qy, 1::BIGINT AS w FROM benchmark",
    "pages": "SELECT 1::BIGINT AS query_id, length(url)::BIGINT AS qx, length(html)::BIGINT AS qy, 1::BIGINT AS w FROM pages",
    "conversations": "SELECT 1::BIGINT AS query_id, (turn * 100)::BIGINT AS qx, length(text)::BIGINT AS qy, 1::BIGINT AS w FROM conversations WHERE role = 'system'",
}


def base(p: str, q: str, plane: bool = True) -> str:
    """CTEs p, q and f: every point's distance to every group."""
    own = " AND (p.own IS NULL OR p.own <> q.query_id)" if "AS own" in POINTS[p] else ""
    term = "abs(p.x - q.qx)" + (" + abs(p.y - q.qy)" if plane else "")
    y = ", p.y" if plane else ""
    return f"""WITH q0 AS ({QUERIES[q]}), p0 AS ({POINTS[p]}),
q AS (SELECT query_id, qx{', qy' if plane else ''}, sum(w)::BIGINT AS w FROM q0 GROUP BY ALL),
p AS (SELECT *, row_number() OVER () AS copy FROM p0),
f AS (SELECT q.query_id, p.point_id, p.x{y}, p.copy, sum(q.w * ({term}))::BIGINT AS agg_dist
      FROM p JOIN q ON true{own} GROUP BY ALL)"""


def topk(p: str, q: str, k: int, direction: str = "nearest", plane: bool = True, also: str = "") -> str:
    down = " DESC" if direction == "farthest" else ""
    y = ", y" if plane else ""
    return f"""{base(p, q, plane)},
r AS (SELECT *, row_number() OVER (PARTITION BY query_id{also} ORDER BY agg_dist{down}, point_id, x{y}) AS rank FROM f)
SELECT query_id, rank, point_id, x{y}, agg_dist FROM r WHERE rank <= {k}"""


def anchors(q: str, axis: str = "qx") -> str:
    return f"""q AS (SELECT query_id, {axis} AS v, sum(w)::BIGINT AS w FROM ({QUERIES[q]}) GROUP BY ALL),
c AS (SELECT *, sum(w) OVER (PARTITION BY query_id ORDER BY v) AS cw, sum(w) OVER (PARTITION BY query_id) AS wt FROM q)"""


def _median(axis: str, name: str) -> str:
    return f"""{name} AS (SELECT query_id, min(v) FILTER (2 * cw >= wt) AS a FROM (
  SELECT *, sum(w) OVER (PARTITION BY query_id ORDER BY v) AS cw, sum(w) OVER (PARTITION BY query_id) AS wt
  FROM (SELECT query_id, {axis} AS v, sum(w) AS w FROM q0 GROUP BY ALL)) GROUP BY query_id)"""


def quads(p: str, q: str, direction: str = "nearest") -> str:
    """CTE z: every point's quadrant and own coordinates u, v per group."""
    own = (
        "z AS (SELECT * FROM z0)"
        if direction == "nearest"
        else """z AS (SELECT * REPLACE (max(u) OVER (PARTITION BY query_id, quad) - u AS u, max(v) OVER (PARTITION BY query_id, quad) - v AS v) FROM z0)"""
    )
    return f"""{base(p, q)}, {_median('qx', 'mx')}, {_median('qy', 'my')},
z0 AS (SELECT f.*, mx.a AS ax, my.a AS ay, abs(x - mx.a) AS u, abs(y - my.a) AS v,
  (CASE WHEN y > my.a THEN CASE WHEN x > mx.a THEN 1 ELSE 2 END ELSE CASE WHEN x > mx.a THEN 4 ELSE 3 END END)::BIGINT AS quad
  FROM f JOIN mx USING (query_id) JOIN my USING (query_id)),
{own}"""


_OVER = "b.query_id = a.query_id AND b.quad = a.quad AND b.u <= a.u AND b.v <= a.v AND (b.u < a.u OR b.v < a.v)"


def frontier(p: str, q: str, direction: str = "nearest") -> str:
    return f"{quads(p, q, direction)} SELECT query_id, quad, point_id, x, y FROM z a WHERE NOT EXISTS (SELECT 1 FROM z b WHERE {_OVER})"


def exposed(p: str, q: str) -> str:
    """What appears when the frontier points of even id are gone."""
    return f"""{quads(p, q)}, m AS (SELECT * FROM z a WHERE NOT EXISTS (SELECT 1 FROM z b WHERE {_OVER})),
l AS (SELECT * FROM z WHERE (query_id, point_id) NOT IN (SELECT (query_id, point_id) FROM m WHERE point_id % 2 = 0))
SELECT query_id, quad, point_id, x, y FROM l a WHERE NOT EXISTS (SELECT 1 FROM l b WHERE {_OVER})
AND (query_id, point_id) NOT IN (SELECT (query_id, point_id) FROM m)"""


def frontier_cells(p: str, q: str) -> str:
    line = "(SELECT count(DISTINCT l.q{c}) FROM q0 l WHERE l.query_id = a.query_id AND (CASE WHEN a.quad IN {plus} THEN 1 ELSE -1 END) * (l.q{c} - a.a{c}) <= a.{u})"
    ci, cj = line.format(c="x", u="u", plus="(1, 4)"), line.format(c="y", u="v", plus="(1, 2)")
    return f"""{quads(p, q)}, m AS (SELECT * FROM z a WHERE NOT EXISTS (SELECT 1 FROM z b WHERE {_OVER})),
c AS (SELECT a.*, {ci}::BIGINT AS ci, {cj}::BIGINT AS cj FROM m a)
SELECT query_id, quad, ci, cj, arg_min(point_id, (u, v, point_id, x, y)) AS entry_id, arg_min(point_id, (v, u, point_id, x, y)) AS floor_id
FROM c GROUP BY ALL"""


def coefficients(q: str) -> str:
    side = """{n} AS (SELECT query_id, i, (2 * coalesce(sum(w) FILTER (r <= i), 0) - sum(w))::BIGINT AS c, (sum(w * v) - 2 * coalesce(sum(w * v) FILTER (r <= i), 0))::BIGINT AS k
  FROM (SELECT *, dense_rank() OVER (PARTITION BY query_id ORDER BY v) AS r FROM (SELECT query_id, {a} AS v, w FROM q0)) s
  JOIN (SELECT query_id AS qq, unnest(range(0, count(DISTINCT {a}) + 1)) AS i FROM q0 GROUP BY query_id) g ON g.qq = s.query_id GROUP BY query_id, i)"""
    return f"""WITH q0 AS ({QUERIES[q]}), {side.format(n='sx', a='qx')}, {side.format(n='sy', a='qy')}
SELECT sx.query_id, sx.i AS ci, sy.i AS cj, sx.c AS ca, sy.c AS cb, sx.k + sy.k AS cc FROM sx JOIN sy USING (query_id)"""


def cell_optimum(p: str, q: str, direction: str = "nearest") -> str:
    down = " DESC" if direction == "farthest" else ""
    line = "(SELECT count(DISTINCT l.q{c}) FROM q0 l WHERE l.query_id = f.query_id AND l.q{c} <= f.{c})::BIGINT"
    return f"""{base(p, q)}, c AS (SELECT f.*, {line.format(c='x')} AS ci, {line.format(c='y')} AS cj FROM f),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id, ci, cj ORDER BY agg_dist{down}, point_id) AS n FROM c)
SELECT query_id, ci, cj, point_id, agg_dist FROM r WHERE n = 1"""


def drag(p: str, segs: list[tuple], keep: str = "true") -> str:
    rows = ", ".join("(" + ", ".join("NULL" if v is None else f"'{v}'" if isinstance(v, str) else str(v) for v in s) + ")" for s in segs)
    move, span = "CASE WHEN axis = 'v' THEN x ELSE y END", "CASE WHEN axis = 'v' THEN y ELSE x END"
    return f"""WITH p AS (SELECT * FROM ({POINTS[p]}) WHERE {keep}),
s(seg_id, axis, dir, lo, hi, start) AS (VALUES {rows}),
h AS (SELECT s.seg_id::BIGINT AS seg_id, p.point_id, x, y, row_number() OVER (PARTITION BY s.seg_id ORDER BY ({move} - start) * dir, {span}, point_id) AS n
  FROM p JOIN s ON ({move} - start) * dir >= 0 AND (lo IS NULL OR {span} >= lo) AND (hi IS NULL OR {span} < hi))
SELECT seg_id, point_id, x, y FROM h WHERE n = 1"""
