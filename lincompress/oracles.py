"""SQL over raw rows that gives what the compressed fits must give; closed forms for small designs."""

from __future__ import annotations

LINE = "SELECT l_returnflag AS rf, l_linestatus AS ls, l_discount AS disc, l_quantity AS qty, l_extendedprice AS price, l_tax AS tax, l_suppkey AS supp FROM lineitem"
PANEL = """SELECT u.user_id, u.user_id % 2 AS arm, u.user_id % 5 AS tier, d.t, coalesce(f.n, 0)::DOUBLE AS y
FROM (SELECT DISTINCT user_id FROM events) u CROSS JOIN (SELECT unnest(range(30)) AS t) d
LEFT JOIN (SELECT user_id, date_diff('day', DATE '2024-01-01', ts::DATE) AS t, count(*) AS n FROM events GROUP BY 1, 2) f ON f.user_id = u.user_id AND f.t = d.t"""
ORDERS = "SELECT o_custkey AS cust, o_custkey % 2 AS arm, o_orderpriority AS prio, year(o_orderdate) AS yr, o_totalprice AS total, (o_orderstatus = 'F')::INT AS is_f FROM orders"


def two_parameters(table: str, x: str, y: str, cov: str = "homoskedastic", cluster: str | None = None, weight: str | None = None, weight_kind: str = "analytic", digits: int = 4) -> str:
    """Intercept and slope with standard errors, from raw rows: bread and meat of a two-column design written out."""
    w = weight or "1.0"
    rows = "sum(w)" if weight and weight_kind == "frequency" else "count(*)"
    power = "w" if weight_kind == "frequency" else "w * w"
    meat = {
        "homoskedastic": "SELECT s2 * a AS m00, s2 * b AS m01, s2 * c AS m11 FROM (SELECT sum(w * e * e) / (any_value(n) - 2) AS s2, any_value(a) AS a, any_value(b) AS b, any_value(c) AS c FROM r)",
        "ehw": f"SELECT sum({power} * e * e) AS m00, sum({power} * e * e * x) AS m01, sum({power} * e * e * x * x) AS m11 FROM r",
        "cluster": "SELECT sum(u * u) AS m00, sum(u * v) AS m01, sum(v * v) AS m11 FROM (SELECT sum(w * e) AS u, sum(w * e * x) AS v FROM r GROUP BY g)",
    }[cov]
    return f"""WITH d AS (SELECT ({x})::DOUBLE AS x, ({y})::DOUBLE AS y, ({w})::DOUBLE AS w, {cluster or '0'} AS g FROM ({table})),
s AS (SELECT {rows} AS n, sum(w) AS a, sum(w * x) AS b, sum(w * x * x) AS c, sum(w * y) AS p, sum(w * x * y) AS q FROM d),
k AS (SELECT *, (c * p - b * q) / (a * c - b * b) AS c0, (a * q - b * p) / (a * c - b * b) AS c1 FROM s),
r AS (SELECT d.*, k.n, k.a, k.b, k.c, d.y - k.c0 - k.c1 * d.x AS e FROM d, k),
m AS ({meat}),
v AS (SELECT k.c0, k.c1, c / (a * c - b * b) AS i00, -b / (a * c - b * b) AS i01, a / (a * c - b * b) AS i11, m00, m01, m11 FROM k, m)
SELECT '(intercept)' AS term, round(c0, {digits}) AS coef, round(sqrt(i00 * i00 * m00 + 2 * i00 * i01 * m01 + i01 * i01 * m11), {digits}) AS se FROM v
UNION ALL SELECT 'x', round(c1, {digits}), round(sqrt(i01 * i01 * m00 + 2 * i01 * i11 * m01 + i11 * i11 * m11), {digits}) FROM v"""


def lines_by_group(table: str, group: str, x: str, y: str, cluster: str) -> str:
    """Intercept and slope of each group (h) with their cluster covariance, from raw rows. Clusters lie within groups, so a model with
    the group, x and all products is these lines side by side."""
    return f"""SELECT h, c0, c1, n, i00 * i00 * m00 + 2 * i00 * i01 * m01 + i01 * i01 * m11 AS v00, i00 * i01 * m00 + (i00 * i11 + i01 * i01) * m01 + i01 * i11 * m11 AS v01,
  i01 * i01 * m00 + 2 * i01 * i11 * m01 + i11 * i11 * m11 AS v11
FROM (WITH d AS (SELECT {group} AS h, ({x})::DOUBLE AS x, ({y})::DOUBLE AS y, {cluster} AS g FROM ({table})),
  s AS (SELECT h, count(*) AS a, sum(x) AS b, sum(x * x) AS c, sum(y) AS p, sum(x * y) AS q FROM d GROUP BY h),
  k AS (SELECT h, a, (c * p - b * q) / (a * c - b * b) AS c0, (a * q - b * p) / (a * c - b * b) AS c1, c / (a * c - b * b) AS i00, -b / (a * c - b * b) AS i01, a / (a * c - b * b) AS i11 FROM s),
  u AS (SELECT d.h, d.g, sum(d.y - k.c0 - k.c1 * d.x) AS u, sum((d.y - k.c0 - k.c1 * d.x) * d.x) AS v FROM d JOIN k ON d.h = k.h GROUP BY d.h, d.g),
  m AS (SELECT h, sum(u * u) AS m00, sum(u * v) AS m01, sum(v * v) AS m11 FROM u GROUP BY h)
  SELECT k.h, k.a AS n, c0, c1, i00, i01, i11, m00, m01, m11 FROM k JOIN m ON k.h = m.h)"""
