"""The experiment workloads on the given tables, one query for each method, with SQL over raw rows beside it."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from lincompress.operators import baselines, compress as C, explore, measures
from lincompress.operators.fit import COMPRESSIONS, cate, effect_over_time, fit_compressed, fit_linear, fit_lpm, fit_moments_expanded, linear, mean_variance, posterior, predict
from lincompress.operators.glm import fit_glm, fit_logistic, loglik_grad
from lincompress.operators.gram import dense, gram_long, gram_packed
from lincompress.oracles import LINE, ORDERS, PANEL, lines_by_group, two_parameters
from lincompress.plans import binning
from lincompress.plans.design import ModelSpec, cat, expr, inter, num, parse_formula, poly, resolve
from lincompress.plans.planner import plan_strategy
from lincompress.plans.registry import Registry
from lincompress.sources.tables import load

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def line(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "lineitem").select(
        F.col("l_returnflag").alias("rf"), F.col("l_linestatus").alias("ls"), F.col("l_discount").alias("disc"), F.col("l_quantity").alias("qty"),
        F.col("l_extendedprice").alias("price"), F.col("l_tax").alias("tax"), F.col("l_suppkey").alias("supp"),
    )


def panel(spark: SparkSession, d: str, periods: int = 30) -> DataFrame:
    """Users by days, zero-filled: facts are summed by user and day first, so the join is of panel size."""
    events = load(spark, d, "events").select("user_id", F.datediff("ts", F.lit("2024-01-01")).alias("t"))
    facts = events.groupBy("user_id", "t").agg(F.count(F.lit(1)).alias("n"))
    days = spark.range(periods).select(F.col("id").cast("int").alias("t"))
    grid = events.select("user_id").distinct().crossJoin(F.broadcast(days))
    rows = grid.join(facts, ["user_id", "t"], "left")
    return rows.select("user_id", (F.col("user_id") % 2).cast("int").alias("arm"), (F.col("user_id") % 5).cast("int").alias("tier"), "t", F.coalesce("n", F.lit(0)).cast("double").alias("y"))


def orders(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "orders").select(
        F.col("o_custkey").alias("cust"), (F.col("o_custkey") % 2).cast("int").alias("arm"), F.col("o_orderpriority").alias("prio"), F.year("o_orderdate").alias("yr"),
        F.col("o_totalprice").alias("total"), (F.col("o_orderstatus") == "F").cast("int").alias("is_f"),
    )


X = ModelSpec("price", (num("disc"),), cluster="supp")
PANEL_SPEC = ModelSpec("y", (num("arm"), num("t")), cluster="user_id", time="t")
PANEL_INTER = PANEL_SPEC.with_terms(inter(num("arm"), num("t")))
CELLS = ModelSpec("qty", (cat("rf"), cat("ls"), num("disc")))


def table(spark: SparkSession, fit, digits: int = 4, names: dict | None = None, k: int = 0) -> DataFrame:
    rows = [((names or {}).get(n, n), round(float(b), digits), round(float(s), digits)) for n, b, s in zip(fit.names, fit.coef[:, k] if fit.coef.ndim == 2 else fit.coef, fit.se(k) if fit.coef.ndim == 2 else fit.se(), strict=True)]
    return spark.createDataFrame(rows, "term string, coef double, se double")


def values(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


# ---- compressions -------------------------------------------------------------------------------------------------------

_BY = f"FROM ({LINE}) GROUP BY rf, ls, disc"


@query("compress_none", f"SELECT rf, ls, disc, qty FROM ({LINE})")
def _(s, d):
    return C.uncompressed(line(s, d), CELLS).df


@query("compress_frequency", f"SELECT rf, ls, disc, qty, count(*) AS cnt {_BY}, qty")
def _(s, d):
    return C.compress_frequency(line(s, d), CELLS).df


@query("compress_frequency_joint", f"SELECT rf, ls, disc, qty, tax, count(*) AS cnt {_BY}, qty, tax")
def _(s, d):
    return C.compress_frequency(line(s, d), replace(CELLS, outcomes=("qty", "tax")), joint=True).df


@query("compress_frequency_continuous", f"SELECT count(*) AS records FROM (SELECT DISTINCT rf, ls, disc, price FROM ({LINE}))")
def _(s, d):
    return C.compress_frequency(line(s, d), replace(CELLS, outcomes=("price",))).df.agg(F.count(F.lit(1)).alias("records"))


@query("compress_means", f"SELECT rf, ls, disc, count(*) AS cnt, round(avg(qty), 6) AS mean_qty {_BY}")
def _(s, d):
    return C.compress_means(line(s, d), CELLS).df.withColumn("mean_qty", F.round("mean_qty", 6))


@query("compress_stats", f"SELECT rf, ls, disc, count(*) AS cnt, sum(qty) AS sy_qty, sum(qty * qty) AS syy_qty {_BY}")
def _(s, d):
    return C.compress_stats(line(s, d), CELLS).df


@query("compress_stats_exact", f"SELECT rf, ls, disc, count(*) AS cnt, sum(price::DECIMAL(12,2))::DOUBLE AS sy, sum((price::DECIMAL(12,2) * price::DECIMAL(12,2))::DECIMAL(24,4))::DOUBLE AS syy {_BY}")
def _(s, d):
    return C.compress_stats(line(s, d), replace(CELLS, outcomes=("price",)), exact="decimal(12,2)").df.select("rf", "ls", "disc", "cnt", F.col("sy_price").cast("double").alias("sy"), F.col("syy_price").cast("double").alias("syy"))


@query("compress_stats_centred", f"SELECT rf, ls, disc, count(*) AS cnt, round(var_pop(qty) * count(*), 4) AS m2_qty {_BY}")
def _(s, d):
    return C.compress_stats(line(s, d), CELLS, centred=True).df.select("rf", "ls", "disc", "cnt", F.round("m2_qty", 4).alias("m2_qty"))


@query("compress_stats_multi", f"SELECT rf, ls, disc, count(*) AS cnt, sum(qty) AS sy_qty, sum(qty * qty) AS syy_qty, round(sum(tax), 6) AS sy_tax, round(sum(tax * tax), 6) AS syy_tax, round(sum(qty * tax), 4) AS sxy_qty_tax {_BY}")
def _(s, d):
    df = C.compress_stats(line(s, d), replace(CELLS, outcomes=("qty", "tax")), cross=True).df
    return df.withColumns({"sy_tax": F.round("sy_tax", 6), "syy_tax": F.round("syy_tax", 6), "sxy_qty_tax": F.round("sxy_qty_tax", 4)})


@query("compress_weighted", f"SELECT rf, ls, disc, count(*) AS cnt, sum(qty) AS sw, round(sum(qty * tax), 4) AS swy_tax, round(sum(qty * tax * tax), 4) AS swyy_tax, sum(qty * qty) AS sw2, round(sum(qty * qty * tax), 4) AS sw2y_tax, round(sum(qty * qty * tax * tax), 4) AS sw2yy_tax {_BY}")
def _(s, d):
    df = C.compress_weighted(line(s, d), replace(CELLS, outcomes=("tax",), weight="qty", weight_kind="analytic")).df
    return df.withColumns({c: F.round(c, 4) for c in ("swy_tax", "swyy_tax", "sw2y_tax", "sw2yy_tax")})


@query("compress_binary", f"SELECT prio, yr::INT AS yr, count(*) AS cnt, sum(is_f)::BIGINT AS sy_is_f FROM ({ORDERS}) GROUP BY prio, yr")
def _(s, d):
    return C.compress_binary(orders(s, d), ModelSpec("is_f", (cat("prio"), num("yr")))).df


@query("compress_within_cluster", f"SELECT supp, disc, count(*) AS cnt, sum(qty) AS sy_qty, sum(qty * qty) AS syy_qty FROM ({LINE}) GROUP BY supp, disc")
def _(s, d):
    return C.compress_within_cluster(line(s, d), ModelSpec("qty", (num("disc"),), cluster="supp")).df


@query("compress_cluster_moments", f"SELECT supp, count(*) AS cnt, round(sum(disc), 6) AS x, round(sum(disc * disc), 6) AS xx, sum(qty) AS y, round(sum(disc * qty), 4) AS xy FROM ({LINE}) GROUP BY supp")
def _(s, d):
    df = C.compress_cluster_moments(line(s, d), ModelSpec("qty", (num("disc"),), cluster="supp")).df
    return df.select("supp", "cnt", F.round(F.get("xx", 1), 6).alias("x"), F.round(F.get("xx", 2), 6).alias("xx"), F.get("xy_qty", 0).alias("y"), F.round(F.get("xy_qty", 1), 4).alias("xy"))


@query("compress_static", f"SELECT user_id, arm::INT AS arm, count(*) AS cnt, sum(y) AS sy, sum(y * y) AS syy, sum(t)::DOUBLE AS dsum, sum(t * y)::DOUBLE AS dy, sum(t * t)::DOUBLE AS dd FROM ({PANEL}) GROUP BY user_id, arm")
def _(s, d):
    df = C.compress_static(panel(s, d), PANEL_SPEC).df
    return df.select("user_id", "arm", "cnt", F.col("sy_y").alias("sy"), F.col("syy_y").alias("syy"), F.get("dsum", 0).alias("dsum"), F.get("dy_y", 0).alias("dy"), F.get("dd", 0).alias("dd"))


@query("compress_trend", SQL["compress_static"])
def _(s, d):
    df = C.compress_trend(panel(s, d), PANEL_SPEC).df
    return df.select("user_id", "arm", "cnt", F.col("sy_y").alias("sy"), F.col("syy_y").alias("syy"), F.get("dsum", 0).alias("dsum"), F.get("dy_y", 0).alias("dy"), F.get("dd", 0).alias("dd"))


@query("panel_interaction_trend")
def _(s, d):
    return table(s, fit_compressed(C.compress_trend(panel(s, d), PANEL_INTER), "cluster"), 6)


@query("compress_balanced_units", f"SELECT user_id, arm::INT AS arm, sum(y) AS sy, string_agg(y::INT::VARCHAR, ',' ORDER BY t) AS ys FROM ({PANEL}) GROUP BY user_id, arm")
def _(s, d):
    df = C.compress_balanced(panel(s, d), PANEL_SPEC).df
    return df.select("user_id", "arm", F.col("sy_y").alias("sy"), F.array_join(F.transform("y_y", lambda v: v.cast("int").cast("string")), ",").alias("ys"))


@query("compress_between_cluster", f"WITH p AS ({PANEL}), u AS (SELECT user_id, arm, list(y ORDER BY t) AS ys FROM p GROUP BY 1, 2) SELECT arm::INT AS arm, count(*) AS k, sum(list_sum(ys)) AS total, sum(list_sum(ys) * list_sum(ys)) AS outer_total FROM u GROUP BY arm")
def _(s, d):
    df = C.compress_between_cluster(panel(s, d), PANEL_SPEC).df
    add = lambda c: F.aggregate(c, F.lit(0.0), lambda a, b: a + b)
    return df.select(F.get("matrix", 0)["arm"].alias("arm"), "k", add("sy_y").alias("total"), add("q_y").alias("outer_total"))


@query("merge_increments", f"SELECT rf, ls, disc, count(*) AS cnt, sum(qty) AS sy_qty, sum(qty * qty) AS syy_qty {_BY}")
def _(s, d):
    rows = line(s, d)
    parts = [C.compress_stats(rows.where(F.col("supp") % 3 == k), CELLS) for k in range(3)]
    return C.merge(C.merge(parts[0], parts[1]), parts[2]).df


@query("rollup_features", f"SELECT rf, count(*) AS cnt, sum(qty) AS sy_qty, sum(qty * qty) AS syy_qty FROM ({LINE}) GROUP BY rf")
def _(s, d):
    return C.rollup(C.compress_stats(line(s, d), CELLS), ["ls", "disc"]).df


@query("expand_frequency", f"SELECT rf, ls, disc, qty FROM ({LINE})")
def _(s, d):
    return C.expand_frequency(C.compress_frequency(line(s, d), CELLS))


# ---- binning ------------------------------------------------------------------------------------------------------------

@query("bin_decile", "WITH q AS (SELECT quantile_cont(c_acctbal, [0.1,0.2,0.3,0.4,0.5,0.6,0.7,0.8,0.9]) AS qs FROM customer) SELECT c_custkey, len(list_filter(qs, lambda x: x <= c_acctbal))::INT AS bin FROM customer, q")
def _(s, d):
    return binning.bin_quantile(load(s, d, "customer"), "c_acctbal", 10, name="bin").select("c_custkey", "bin")


@query("bin_ntile", "SELECT c_custkey, (ntile(10) OVER (ORDER BY c_acctbal, c_custkey))::INT AS bin FROM customer")
def _(s, d):
    return binning.bin_ntile(load(s, d, "customer"), "c_acctbal", "c_custkey", 10, "bin").select("c_custkey", "bin")


@query("bin_width", f"SELECT (floor((qty - 1) / 5) + 1)::BIGINT AS bin, count(*) AS n FROM ({LINE}) GROUP BY 1")
def _(s, d):
    return line(s, d).groupBy(binning.bin_width("qty", 10, 1, 51).cast("bigint").alias("bin")).agg(F.count(F.lit(1)).alias("n"))


@query("round_feature", "SELECT c_custkey, floor(c_acctbal / 500) * 500 AS bal FROM customer")
def _(s, d):
    return load(s, d, "customer").select("c_custkey", binning.round_feature("c_acctbal", 500.0).cast("double").alias("bal"))


@query("range_join_bins", "SELECT c_custkey, (CASE WHEN c_acctbal < 0 THEN 0 WHEN c_acctbal < 2500 THEN 1 WHEN c_acctbal < 5000 THEN 2 ELSE 3 END)::INT AS bin FROM customer")
def _(s, d):
    return binning.range_join(load(s, d, "customer"), "c_acctbal", [0.0, 2500.0, 5000.0], "bin").select("c_custkey", "bin")


@query("bin_compression", f"SELECT 'raw' AS design, count(DISTINCT (rf, ls, qty, disc)) AS records FROM ({LINE}) UNION ALL SELECT 'binned', count(DISTINCT (rf, ls, floor((qty - 1) / 5), disc)) FROM ({LINE})")
def _(s, d):
    rows = line(s, d)
    raw = C.compress_stats(rows, ModelSpec("price", (cat("rf"), cat("ls"), num("qty"), num("disc")))).df
    bins = C.compress_stats(rows, ModelSpec("price", (cat("rf"), cat("ls"), expr("width_bucket(qty, 1, 51, 10)", "bin"), num("disc")))).df
    one = lambda df, n: df.agg(F.lit(n).alias("design"), F.count(F.lit(1)).alias("records"))
    return one(raw, "raw").unionAll(one(bins, "binned"))


# ---- coefficients and covariances ---------------------------------------------------------------------------------------

def _fit_query(name: str, kind: str, cov: str, spec: ModelSpec = X, sql: str | None = None, source=line, names=None, **options):
    @query(name, sql)
    def run(s, d):
        rows = source(s, d)
        return table(s, fit_linear(rows, spec, kind, cov, **options), names=names or {"disc": "x", "arm": "x"})


_FLAT = two_parameters(LINE, "disc", "price")
for _kind in ("none", "frequency", "stats"):
    _fit_query(f"ols_coef_{ {'none': 'none', 'frequency': 'freq', 'stats': 'stats'}[_kind]}", _kind, "homoskedastic", sql=_FLAT)
SQL["ols_coef_means"] = f"SELECT term, coef FROM ({_FLAT})"


@query("ols_coef_means", SQL["ols_coef_means"])
def _(s, d):
    return table(s, baselines.wls_means(line(s, d), X), names={"disc": "x"}).drop("se")


_EHW, _CLUSTER = two_parameters(LINE, "disc", "price", "ehw"), two_parameters(LINE, "disc", "price", "cluster", "supp")
_PANEL_ARM = ModelSpec("y", (num("arm"),), cluster="user_id", time="t")
_ARM_CLUSTER = two_parameters(PANEL, "arm", "y", "cluster", "user_id", digits=6)
_fit_query("cov_homoskedastic", "stats", "homoskedastic", sql=_FLAT)
_fit_query("cov_ehw", "stats", "ehw", sql=_EHW)
_fit_query("cov_ehw_frequency", "frequency", "ehw", sql=_EHW)
_fit_query("cov_ehw_rows", "none", "ehw", sql=_EHW)
_fit_query("cov_cluster_within", "within", "cluster", sql=_CLUSTER)
_fit_query("cov_cluster_rows", "none", "cluster", sql=_CLUSTER)
_fit_query("cov_cluster_moments", "cluster_moments", "cluster", sql=_CLUSTER)
_fit_query("cov_ehw_packed", "stats", "ehw", sql=_EHW, method="packed")


@query("cov_cluster_moments_expanded", _CLUSTER)
def _(s, d):
    return table(s, fit_moments_expanded(C.compress_cluster_moments(line(s, d), X)), names={"disc": "x"})


@query("cov_cluster_means", _CLUSTER)
def _(s, d):
    return table(s, fit_compressed(C.compress_means(line(s, d), X, cluster=True), "cluster"), names={"disc": "x"})


@query("cov_cluster_frequency", _CLUSTER)
def _(s, d):
    return table(s, fit_compressed(C.compress_frequency(line(s, d), X, cluster=True), "cluster"), names={"disc": "x"})


def _panel_query(name: str, kind: str, cov: str = "cluster"):
    @query(name, two_parameters(PANEL, "arm", "y", cov, "user_id", digits=6))
    def run(s, d):
        return table(s, fit_linear(panel(s, d), _PANEL_ARM, kind, cov), 6, {"arm": "x"})


for _name, _kind, _cov in (
    ("cov_cluster_between", "between", "cluster"), ("cov_cluster_static", "static", "cluster"), ("cov_cluster_balanced", "balanced", "cluster"),
    ("cov_ehw_between", "between", "ehw"), ("cov_ehw_balanced", "balanced", "ehw"), ("cov_homoskedastic_static", "static", "homoskedastic"), ("cov_homoskedastic_moments", "cluster_moments", "homoskedastic"),
):
    _panel_query(_name, _kind, _cov)


@query("cov_means_lossy", f"""WITH d AS (SELECT disc AS x, avg(price) AS y, count(*)::DOUBLE AS w FROM ({LINE}) GROUP BY disc),
s AS (SELECT count(*) AS g, sum(w) AS a, sum(w * x) AS b, sum(w * x * x) AS c, sum(w * y) AS p, sum(w * x * y) AS q FROM d),
k AS (SELECT *, (c * p - b * q) / (a * c - b * b) AS c0, (a * q - b * p) / (a * c - b * b) AS c1 FROM s),
e AS (SELECT sum(d.w * (d.y - k.c0 - k.c1 * d.x) * (d.y - k.c0 - k.c1 * d.x)) / (any_value(k.g) - 2) AS s2 FROM d, k)
SELECT 'x' AS term, round(c1, 4) AS coef, round(sqrt(s2 * a / (a * c - b * b)), 4) AS se FROM k, e""")
def _(s, d):
    return table(s, baselines.wls_means(line(s, d), X), names={"disc": "x"}).where("term = 'x'")


@query("cov_small_sample", f"""WITH b AS ({_EHW}), n AS (SELECT count(*) AS n FROM lineitem) SELECT 'HC1' AS kind, term, round(se * sqrt(n / (n - 2.0)), 3) AS se FROM b, n
UNION ALL SELECT 'CR1', term, round(se * sqrt(g / (g - 1.0) * (n - 1.0) / (n - 2.0)), 3) FROM ({_CLUSTER}), n, (SELECT count(DISTINCT l_suppkey) AS g FROM lineitem)""")
def _(s, d):
    hc = fit_compressed(C.compress_stats(line(s, d), X), "ehw", small_sample="HC1")
    cr = fit_compressed(C.compress_within_cluster(line(s, d), X), "cluster", small_sample="CR1")
    rows = [(k, {"disc": "x"}.get(n, n), round(float(v), 3)) for k, f in (("HC1", hc), ("CR1", cr)) for n, v in zip(f.names, f.se(), strict=True)]
    return values(s, rows, "kind string, term string, se double")


@query("cov_cluster_one_row_each", _EHW)
def _(s, d):
    rows = line(s, d).withColumn("supp", F.monotonically_increasing_id())
    return table(s, fit_compressed(C.uncompressed(rows, X), "cluster"), names={"disc": "x"})


@query("ols_two_regressors", f"""WITH d AS (SELECT price - avg(price) OVER () AS y, disc - avg(disc) OVER () AS a, qty - avg(qty) OVER () AS b FROM ({LINE})),
s AS (SELECT count(*) AS n, sum(a * a) AS aa, sum(b * b) AS bb, sum(a * b) AS ab, sum(a * y) AS ay, sum(b * y) AS byy FROM d),
k AS (SELECT *, aa * bb - ab * ab AS det, (ay * bb - byy * ab) / (aa * bb - ab * ab) AS c1, (byy * aa - ay * ab) / (aa * bb - ab * ab) AS c2 FROM s),
e AS (SELECT sum((y - c1 * a - c2 * b) * (y - c1 * a - c2 * b)) / (any_value(n) - 3) AS s2 FROM d, k)
SELECT 'disc' AS term, round(c1, 4) AS coef, round(sqrt(s2 * bb / det), 4) AS se FROM k, e UNION ALL SELECT 'qty', round(c2, 4), round(sqrt(s2 * aa / det), 4) FROM k, e""")
def _(s, d):
    fit = fit_linear(line(s, d), parse_formula("price ~ disc + qty"), "stats")
    return table(s, fit).where("term <> '(intercept)'")


_SATURATED = f"WITH m AS (SELECT rf, ls, avg(qty) AS m FROM ({LINE}) GROUP BY rf, ls) SELECT rf, ls, round(m, 6) AS fitted FROM m"


@query("ols_saturated", _SATURATED)
def _(s, d):
    rows = line(s, d)
    spec = resolve(rows, parse_formula("qty ~ C(rf)*C(ls)"))
    cf = C.compress_stats(rows, spec)
    return predict(fit_compressed(cf), cf.df, spec).select("rf", "ls", F.round("fitted", 6).alias("fitted"))


@query("ols_interaction_added_later", _SATURATED)
def _(s, d):
    rows = line(s, d)
    cf = C.compress_stats(rows, resolve(rows, parse_formula("qty ~ C(rf) + C(ls)")))
    later = cf.with_terms(inter(cf.spec.terms[0], cf.spec.terms[1]))
    return predict(fit_compressed(later), later.df, later.spec).select("rf", "ls", F.round("fitted", 6).alias("fitted"))


@query("predict_se", f"""WITH m AS (SELECT arm, avg(y) AS m, count(*) AS n FROM ({PANEL}) GROUP BY arm),
u AS (SELECT p.arm, sum(p.y - m.m) AS u FROM ({PANEL}) p JOIN m ON p.arm = m.arm GROUP BY p.arm, p.user_id)
SELECT m.arm::INT AS arm, round(any_value(m.m), 6) AS fitted, round(sqrt(sum(u * u)) / any_value(m.n), 6) AS fitted_se FROM u JOIN m ON u.arm = m.arm GROUP BY m.arm""")
def _(s, d):
    cf = C.compress_static(panel(s, d), _PANEL_ARM)
    grid = s.createDataFrame([(0,), (1,)], "arm int")
    return predict(fit_compressed(cf, "cluster"), grid, cf.spec).select("arm", F.round("fitted", 6).alias("fitted"), F.round("fitted_se", 6).alias("fitted_se"))


_MAIN = f"""WITH p AS ({PANEL}), c AS (SELECT *, arm - avg(arm) OVER () AS a, t - avg(t) OVER () AS b, y - avg(y) OVER () AS z FROM p),
k AS (SELECT sum(a * z) / sum(a * a) AS ba, sum(b * z) / sum(b * b) AS bt, sum(a * a) AS aa, sum(b * b) AS bb FROM c),
u AS (SELECT user_id, sum(a * (z - ba * a - bt * b)) AS ua, sum(b * (z - ba * a - bt * b)) AS ub FROM c, k GROUP BY user_id)
SELECT 'arm' AS term, round(any_value(ba), 6) AS coef, round(sqrt(sum(ua * ua)) / any_value(aa), 6) AS se FROM u, k
UNION ALL SELECT 't', round(any_value(bt), 6), round(sqrt(sum(ub * ub)) / any_value(bb), 6) FROM u, k"""
_ARM_LINES = f"WITH a AS ({lines_by_group(PANEL, 'arm', 't', 'y', 'user_id')}), z AS (SELECT * FROM a WHERE h = 0), o AS (SELECT * FROM a WHERE h = 1)"
_INTER = f"""{_ARM_LINES} SELECT '(intercept)' AS term, round(c0, 6) AS coef, round(sqrt(v00), 6) AS se FROM z UNION ALL SELECT 't', round(c1, 6), round(sqrt(v11), 6) FROM z
UNION ALL SELECT 'arm', round(o.c0 - z.c0, 6), round(sqrt(o.v00 + z.v00), 6) FROM z, o UNION ALL SELECT 'arm:t', round(o.c1 - z.c1, 6), round(sqrt(o.v11 + z.v11), 6) FROM z, o"""


def _panel_main(kind):
    def run(s, d):
        fit = fit_linear(panel(s, d), PANEL_SPEC, kind, "cluster")
        return table(s, fit, 6).where("term <> '(intercept)'")

    return run


def _panel_inter(kind):
    def run(s, d):
        return table(s, fit_linear(panel(s, d), PANEL_INTER, kind, "cluster"), 6)

    return run


for _kind in ("none", "within", "cluster_moments", "static", "balanced", "between"):
    query(f"panel_main_{_kind}", _MAIN)(_panel_main(_kind))
    query(f"panel_interaction_{_kind}", _INTER)(_panel_inter(_kind))


@query("panel_interaction_added_later", _INTER)
def _(s, d):
    cf = C.compress_static(panel(s, d), PANEL_SPEC).with_terms(inter(num("arm"), num("t")))
    return table(s, fit_compressed(cf, "cluster"), 6)


@query("panel_effect_by_day", f"""{_ARM_LINES} SELECT d.t::DOUBLE AS t, round(o.c0 + o.c1 * d.t - z.c0 - z.c1 * d.t, 6) AS effect,
round(sqrt(o.v00 + z.v00 + 2 * d.t * (o.v01 + z.v01) + d.t * d.t * (o.v11 + z.v11)), 6) AS se FROM z, o, (VALUES (0), (10), (29)) d(t)""")
def _(s, d):
    fit = fit_linear(panel(s, d), PANEL_INTER, "balanced", "cluster")
    return values(s, [(float(t), round(v, 6), round(e, 6)) for t, v, e in effect_over_time(fit, "arm", "t", [0, 10, 29])], "t double, effect double, se double")


_TIERS = ModelSpec("y", (cat("tier"), num("t"), inter(cat("tier"), num("t"))), cluster="user_id", time="t")
_TIER_SQL = f"""WITH a AS ({lines_by_group(PANEL, 'tier', 't', 'y', 'user_id')}), z AS (SELECT * FROM a WHERE h = 0), k AS (SELECT * FROM a WHERE h > 0)
SELECT '(intercept)' AS term, round(c0, 6) AS coef, round(sqrt(v00), 6) AS se FROM z UNION ALL SELECT 't', round(c1, 6), round(sqrt(v11), 6) FROM z
UNION ALL SELECT 'tier[' || k.h || ']', round(k.c0 - z.c0, 6), round(sqrt(k.v00 + z.v00), 6) FROM z, k UNION ALL SELECT 'tier[' || k.h || ']:t', round(k.c1 - z.c1, 6), round(sqrt(k.v11 + z.v11), 6) FROM z, k"""
_WAYS = ("none", "within", "cluster_moments", "static", "balanced", "between")


@query("panel_cluster_parity", f"SELECT kind, term, coef, se FROM ({_TIER_SQL}) CROSS JOIN (SELECT unnest({list(_WAYS)}) AS kind)")
def _(s, d):
    """Ten coefficients (a line for each tier) with cluster errors, by all ways to keep clusters."""
    rows = panel(s, d).cache()
    spec = resolve(rows, _TIERS)
    out = []
    for kind in _WAYS:
        fit = fit_linear(rows, spec, kind, "cluster")
        out += [(kind, n, round(float(b), 6), round(float(e), 6)) for n, b, e in zip(fit.names, fit.coef[:, 0], fit.se(), strict=True)]
    rows.unpersist()
    return values(s, out, "kind string, term string, coef double, se double")


@query("panel_unbalanced_static", two_parameters(ORDERS, "arm", "total", "cluster", "cust", digits=3))
def _(s, d):
    spec = ModelSpec("total", (num("arm"),), cluster="cust")
    return table(s, fit_compressed(C.compress_static(orders(s, d), spec), "cluster"), 3, {"arm": "x"})


@query("panel_unbalanced_within", two_parameters(ORDERS, "yr - 1995", "total", "cluster", "cust", digits=3))
def _(s, d):
    spec = ModelSpec("total", (expr("yr - 1995", "x"),), cluster="cust")
    return table(s, fit_compressed(C.compress_within_cluster(orders(s, d), spec), "cluster"), 3)


# ---- weights, many outcomes, binary outcomes ----------------------------------------------------------------------------

@query("lpm_ehw", two_parameters(ORDERS, "arm", "is_f", "ehw", digits=6))
def _(s, d):
    return table(s, fit_lpm(orders(s, d), ModelSpec("is_f", (num("arm"),))), 6, {"arm": "x"})


def _weighted(name, cov, kind):
    @query(name, two_parameters(LINE, "disc", "price", cov, weight="qty", weight_kind=kind))
    def run(s, d):
        spec = ModelSpec("price", (num("disc"),), weight="qty", weight_kind=kind)
        return table(s, fit_compressed(C.compress_weighted(line(s, d), spec), cov), names={"disc": "x"})


_weighted("wls_homoskedastic", "homoskedastic", "analytic")
_weighted("wls_ehw", "ehw", "analytic")
_weighted("wls_probability_ehw", "ehw", "probability")
_weighted("wls_frequency_df", "homoskedastic", "frequency")
_weighted("wls_frequency_ehw", "ehw", "frequency")


@query("wls_cluster", two_parameters(LINE, "disc", "price", "cluster", "supp", weight="qty"))
def _(s, d):
    spec = ModelSpec("price", (num("disc"),), cluster="supp", weight="qty", weight_kind="analytic")
    return table(s, fit_compressed(C.compress_weighted(line(s, d), spec, cluster=True), "cluster"), names={"disc": "x"})


@query("multi_outcome_coef", " UNION ALL ".join(f"SELECT '{y}' AS outcome, term, coef, se FROM ({two_parameters(LINE, 'disc', y, 'ehw', digits=5)})" for y in ("qty", "price", "tax")))
def _(s, d):
    fit = fit_compressed(C.compress_stats(line(s, d), ModelSpec(("qty", "price", "tax"), (num("disc"),))), "ehw")
    return values(s, [(y, {"disc": "x"}.get(n, n), round(b, 5), round(e, 5)) for y, n, b, e, *_ in fit.rows()], "outcome string, term string, coef double, se double")


_PANEL_TWO = "SELECT user_id, arm, t, y, y * y + t AS z FROM (" + PANEL + ")"


def _two(s, d):
    return panel(s, d).withColumn("z", F.col("y") * F.col("y") + F.col("t"))


def _multi_cluster(kind: str):
    @query(f"multi_outcome_cluster_{kind}", " UNION ALL ".join(f"SELECT '{y}' AS outcome, term, coef, se FROM ({two_parameters(_PANEL_TWO, 'arm', y, 'cluster', 'user_id', digits=6)})" for y in ("y", "z")))
    def run(s, d):
        fit = fit_linear(_two(s, d), replace(_PANEL_ARM, outcomes=("y", "z")), kind, "cluster")
        return values(s, [(y, {"arm": "x"}.get(n, n), round(b, 6), round(e, 6)) for y, n, b, e, *_ in fit.rows()], "outcome string, term string, coef double, se double")


for _kind in ("within", "cluster_moments", "static", "balanced", "between"):
    _multi_cluster(_kind)


_ODDS = f"WITH a AS (SELECT arm, sum(is_f)::DOUBLE AS s, count(*) - sum(is_f)::DOUBLE AS f FROM ({ORDERS}) GROUP BY arm), z AS (SELECT * FROM a WHERE arm = 0), o AS (SELECT * FROM a WHERE arm = 1)"
_LOGIT = ModelSpec("is_f", (num("arm"),))


@query("logistic_fit", f"{_ODDS} SELECT '(intercept)' AS term, round(ln(z.s / z.f), 6) AS coef FROM z UNION ALL SELECT 'arm', round(ln(o.s / o.f) - ln(z.s / z.f), 6) FROM z, o")
def _(s, d):
    return table(s, fit_logistic(C.compress_binary(orders(s, d), _LOGIT)), 6).drop("se")


@query("logistic_se", f"{_ODDS} SELECT '(intercept)' AS term, round(sqrt(1 / z.s + 1 / z.f), 6) AS se FROM z UNION ALL SELECT 'arm', round(sqrt(1 / z.s + 1 / z.f + 1 / o.s + 1 / o.f), 6) FROM z, o")
def _(s, d):
    return table(s, fit_logistic(C.compress_binary(orders(s, d), _LOGIT)), 6).drop("coef")


@query("logistic_loglik", f"{_ODDS} SELECT round(sum(s * ln(s / (s + f)) + f * ln(f / (s + f))), 4) AS loglik FROM a")
def _(s, d):
    return values(s, [(round(fit_logistic(C.compress_binary(orders(s, d), _LOGIT)).loglik, 4),)], "loglik double")


@query("logistic_rows", f"{_ODDS} SELECT 'arm' AS term, round(ln(o.s / o.f) - ln(z.s / z.f), 6) AS coef FROM z, o")
def _(s, d):
    return table(s, baselines.logistic_rows(orders(s, d), _LOGIT), 6).where("term = 'arm'").drop("se")


@query("logistic_gradient", f"{_ODDS} SELECT 'arm' AS term, round(ln(o.s / o.f) - ln(z.s / z.f), 4) AS coef FROM z, o")
def _(s, d):
    return table(s, fit_logistic(C.compress_binary(orders(s, d), _LOGIT), solver="gradient", tol=1e-14), 4).where("term = 'arm'").drop("se")


@query("logistic_loglik_at_zero", f"SELECT round(-count(*) * ln(2.0), 4) AS loglik, round(sum(is_f - 0.5), 4) AS gradient FROM ({ORDERS})")
def _(s, d):
    value, grad, *_ = loglik_grad(C.compress_binary(orders(s, d), _LOGIT), np.zeros(2))
    return values(s, [(round(value, 4), round(float(grad[0]), 4))], "loglik double, gradient double")


@query("logistic_mllib", f"{_ODDS} SELECT round(ln(o.s / o.f) - ln(z.s / z.f), 4) AS coef FROM z, o")
def _(s, d):
    return values(s, [(round(float(baselines.mllib_logistic(orders(s, d), _LOGIT).coefficients[0]), 4),)], "coef double")


@query("poisson_fit", f"WITH a AS (SELECT avg(y) FILTER (arm = 0) AS m0, avg(y) FILTER (arm = 1) AS m1, sum(y) FILTER (arm = 0) AS s0, sum(y) FILTER (arm = 1) AS s1 FROM ({PANEL})) SELECT '(intercept)' AS term, round(ln(m0), 6) AS coef, round(sqrt(1 / s0), 6) AS se FROM a UNION ALL SELECT 'arm', round(ln(m1) - ln(m0), 6), round(sqrt(1 / s0 + 1 / s1), 6) FROM a")
def _(s, d):
    return table(s, fit_glm(C.compress_stats(panel(s, d), ModelSpec("y", (num("arm"),))), "poisson"), 6)


@query("logistic_quality")
def _(s, d):
    """quality ~ lang + length bin on labelled documents."""
    rows = load(s, d, "labels").join(load(s, d, "documents").select("doc_id", "lang", "n_chars"), "doc_id")
    rows = rows.select("quality", "lang", F.least(F.lit(6), F.floor(F.log2(F.greatest(F.col("n_chars"), F.lit(2)) / 64.0))).cast("int").alias("len"))
    spec = resolve(rows, ModelSpec("quality", (cat("lang"), num("len"))))
    return table(s, fit_logistic(C.compress_binary(rows, spec)), 6)


# ---- effects, baselines, exploration ------------------------------------------------------------------------------------

_BINNED = """WITH q AS (SELECT quantile_cont(c_acctbal, [0.2,0.4,0.6,0.8]) AS qs FROM customer),
r AS (SELECT o_custkey % 2 AS arm, len(list_filter(qs, lambda x: x <= c_acctbal))::INT AS bin, o_totalprice AS y FROM orders JOIN customer ON o_custkey = c_custkey, q)"""


def _binned(s, d):
    customers = binning.bin_quantile(load(s, d, "customer"), "c_acctbal", 5, name="bin").select("c_custkey", "bin")
    rows = load(s, d, "orders").join(customers, F.col("o_custkey") == F.col("c_custkey"))
    return rows.select((F.col("o_custkey") % 2).cast("int").alias("arm"), "bin", F.col("o_totalprice").alias("y"), F.col("o_custkey").alias("cust"))


@query("binned_ate", _BINNED + ", c AS (SELECT y - avg(y) OVER (PARTITION BY bin) AS z, arm - avg(arm) OVER (PARTITION BY bin) AS a FROM r) SELECT round(sum(a * z) / sum(a * a), 4) AS effect FROM c")
def _(s, d):
    fit = fit_linear(_binned(s, d), ModelSpec("y", (num("arm"), cat("bin"))), "stats")
    return values(s, [(round(float(fit.coef[1, 0]), 4),)], "effect double")


@query("binned_cate", _BINNED + " SELECT bin, round(avg(y) FILTER (arm = 1) - avg(y) FILTER (arm = 0), 4) AS effect FROM r GROUP BY bin")
def _(s, d):
    fit = fit_linear(_binned(s, d), ModelSpec("y", (num("arm"), cat("bin"), inter(num("arm"), cat("bin")))), "stats")
    return values(s, [(k, round(v, 4)) for k, (_, v, _) in enumerate(cate(fit, "arm", [f"bin[{b}]" for b in range(1, 5)]))], "bin int, effect double")


@query("ate_diff_means", f"SELECT round(avg(total) FILTER (arm = 1) - avg(total) FILTER (arm = 0), 4) AS effect, round(sqrt(var_samp(total) FILTER (arm = 1) / count(*) FILTER (arm = 1) + var_samp(total) FILTER (arm = 0) / count(*) FILTER (arm = 0)), 4) AS se FROM ({ORDERS})")
def _(s, d):
    return baselines.diff_means(orders(s, d), "total", "arm").select(F.round("effect", 4).alias("effect"), F.round("se", 4).alias("se"))


_PREPOST = f"SELECT user_id, any_value(arm) AS arm, sum(y) FILTER (t < 15) AS pre, sum(y) FILTER (t >= 15) AS post FROM ({PANEL}) GROUP BY user_id"


def _pre_post(s, d):
    return panel(s, d).groupBy("user_id").agg(F.max("arm").alias("arm"), F.sum(F.when(F.col("t") < 15, F.col("y"))).alias("pre"), F.sum(F.when(F.col("t") >= 15, F.col("y"))).alias("post"))


@query("cuped_adjusted", f"WITH p AS ({_PREPOST}), k AS (SELECT covar_samp(post, pre) / var_samp(pre) AS th, avg(pre) AS m FROM p), z AS (SELECT arm, post - th * (pre - m) AS y FROM p, k) SELECT round(avg(y) FILTER (arm = 1) - avg(y) FILTER (arm = 0), 6) AS effect, round(sqrt(var_samp(y) FILTER (arm = 1) / count(*) FILTER (arm = 1) + var_samp(y) FILTER (arm = 0) / count(*) FILTER (arm = 0)), 6) AS se, round(any_value(th), 6) AS theta FROM z, k")
def _(s, d):
    return baselines.cuped(_pre_post(s, d), "post", "pre", "arm").select(*[F.round(c, 6).alias(c) for c in ("effect", "se", "theta")])


@query("cuped_regression", f"WITH p AS ({_PREPOST}), c AS (SELECT arm - avg(arm) OVER () AS a, pre - avg(pre) OVER () AS b, post - avg(post) OVER () AS z FROM p), s AS (SELECT sum(a * a) AS aa, sum(b * b) AS bb, sum(a * b) AS ab, sum(a * z) AS az, sum(b * z) AS bz FROM c) SELECT round((az * bb - bz * ab) / (aa * bb - ab * ab), 6) AS effect FROM s")
def _(s, d):
    return values(s, [(round(float(fit_linear(_pre_post(s, d), parse_formula("post ~ arm + pre"), "stats").coef[1, 0]), 6),)], "effect double")


@query("fixed_effects", f"WITH c AS (SELECT cust, total - avg(total) OVER (PARTITION BY cust) AS z, yr - avg(yr) OVER (PARTITION BY cust) AS x FROM ({ORDERS})) SELECT round(sum(x * z) / sum(x * x), 3) AS slope FROM c")
def _(s, d):
    rows = C.within_transform(orders(s, d).select("cust", "yr", "total"), ["yr", "total"], "cust")
    fit = fit_compressed(C.compress_cluster_moments(rows, ModelSpec("total", (num("yr"),), intercept=False, cluster="cust")), "cluster")
    return values(s, [(round(float(fit.coef[0, 0]), 3),)], "slope double")


@query("mllib_normal", f"SELECT round(regr_slope(price, disc), 3) AS slope, round(regr_intercept(price, disc), 3) AS intercept FROM ({LINE})")
def _(s, d):
    m = baselines.mllib_linear(line(s, d), X)
    return values(s, [(round(float(m.coefficients[0]), 3), round(float(m.intercept), 3))], "slope double, intercept double")


@query("sgd_gap", "SELECT unnest(['rows', 'compressed']) AS input, true AS close")
def _(s, d):
    rows = line(s, d).withColumn("price", F.col("price") / 1000.0)
    exact = fit_compressed(C.compress_stats(rows, X))
    near = lambda b: bool(abs(b[1] - exact.coef[1, 0]) < 4 * exact.se()[1])
    raw, _ = baselines.sgd_linear(rows, X, epochs=15)
    small, _ = baselines.sgd_linear(C.compress_stats(rows, X), epochs=60)
    return values(s, [("rows", near(raw)), ("compressed", near(small))], "input string, close boolean")


@query("builtin_regression", f"SELECT round(regr_slope(price, disc), 4) AS slope, round(regr_intercept(price, disc), 4) AS intercept, round(regr_r2(price, disc), 9) AS r2, regr_count(price, disc)::BIGINT AS n FROM ({LINE})")
def _(s, d):
    return baselines.builtin_regression(line(s, d), "price", "disc").select(F.round("slope", 4).alias("slope"), F.round("intercept", 4).alias("intercept"), F.round("r2", 9).alias("r2"), "n")


_SEEN = ModelSpec("price", (num("qty"), num("disc"), cat("rf")))


@query("explore_summary", f"SELECT 'qty' AS feature, count(*)::DOUBLE AS n, round(sum(qty::DECIMAL(12,2))::DOUBLE / count(*), 9) AS mean, round(var_samp(qty), 9) AS variance, min(qty) AS min, max(qty) AS max FROM ({LINE}) UNION ALL SELECT 'disc', count(*)::DOUBLE, round(sum(disc::DECIMAL(12,2))::DOUBLE / count(*), 9), round(var_samp(disc), 9), min(disc), max(disc) FROM ({LINE})")
def _(s, d):
    return explore.feature_summary(C.compress_stats(line(s, d), _SEEN), ["qty", "disc"], exact="decimal(12,2)").withColumns({"mean": F.round("mean", 9), "variance": F.round("variance", 9)})


@query("explore_quantile", f"SELECT q, quantile_cont(qty, q) AS value FROM ({LINE}), (VALUES (0.1::DOUBLE), (0.5), (0.9)) v(q) GROUP BY q".replace("quantile_cont(qty, q)", "CASE q WHEN 0.1 THEN quantile_cont(qty, 0.1) WHEN 0.5 THEN quantile_cont(qty, 0.5) ELSE quantile_cont(qty, 0.9) END"))
def _(s, d):
    return explore.feature_quantiles(C.compress_stats(line(s, d), _SEEN), "qty", [0.1, 0.5, 0.9])


@query("explore_corr", f"SELECT count(*)::DOUBLE AS n, round(corr(qty, disc), 8) AS corr FROM ({LINE})")
def _(s, d):
    return explore.feature_corr(C.compress_stats(line(s, d), _SEEN), "qty", "disc").withColumn("corr", F.round("corr", 8))


@query("explore_cooccurrence", f"SELECT rf, disc, count(*) AS n FROM ({LINE}) GROUP BY rf, disc")
def _(s, d):
    return explore.cooccurrence(C.compress_stats(line(s, d), _SEEN), "rf", "disc")


@query("explore_histogram", f"SELECT (floor((qty - 1) / 5) + 1)::BIGINT AS bin, count(*) AS n FROM ({LINE}) GROUP BY 1")
def _(s, d):
    return explore.feature_histogram(C.compress_stats(line(s, d), _SEEN), "qty", 10, 1.0, 51.0)


@query("explore_outcome", f"SELECT 'price' AS outcome, count(*)::DOUBLE AS n, round(avg(price), 4) AS mean, round(var_samp(price) / 1e6, 4) AS variance FROM ({LINE})")
def _(s, d):
    return mean_variance(C.compress_stats(line(s, d), _SEEN)).withColumns({"mean": F.round("mean", 4), "variance": F.round(F.col("variance") / 1e6, 4)})


@query("explore_outcome_by", f"SELECT rf, count(*)::DOUBLE AS n, round(avg(price), 4) AS mean, round(stddev_samp(price) / sqrt(count(*)), 4) AS se FROM ({LINE}) GROUP BY rf")
def _(s, d):
    return explore.outcome_by(C.compress_stats(line(s, d), _SEEN), "rf").withColumns({"mean": F.round("mean", 4), "se": F.round("se", 4)})


@query("explore_segment", two_parameters(LINE + " WHERE l_returnflag = 'A'", "disc", "price"))
def _(s, d):
    cf = C.compress_stats(line(s, d), _SEEN).where("rf = 'A'")
    return table(s, fit_compressed(cf, spec=ModelSpec("price", (num("disc"),))), names={"disc": "x"})


@query("registry_rollup", _FLAT)
def _(s, d):
    held = Registry()
    held.add(C.compress_stats(line(s, d), _SEEN))
    return table(s, fit_compressed(held.find(ModelSpec("price", (num("disc"),)))), names={"disc": "x"})


@query("posterior_draw")
def _(s, d):
    cf = C.compress_stats(line(s, d), X)
    mean, cov, draw = posterior(cf, 1.0, seed=3)
    return values(s, [(n, float(m), float(math.sqrt(v)), float(x)) for n, m, v, x in zip(["(intercept)", "disc"], mean, np.diag(cov), draw, strict=True)], "term string, mean double, sd double, draw double")


@query("saved_frame", _FLAT)
def _(s, d):
    from lincompress.sources.scratch import shared_folder

    path = shared_folder(s, "frame")
    C.save_compressed(C.compress_stats(line(s, d), X), path)
    return table(s, fit_compressed(C.load_compressed(s, path, X)), names={"disc": "x"})


@query("polynomial_fit", f"WITH m AS (SELECT qty - avg(qty) OVER () AS a, qty * qty - avg(qty * qty) OVER () AS b, price AS y FROM ({LINE})), s AS (SELECT sum(a * a) AS aa, sum(b * b) AS bb, sum(a * b) AS ab, sum(a * y) AS ay, sum(b * y) AS byy FROM m) SELECT round((ay * bb - byy * ab) / (aa * bb - ab * ab), 3) AS linear FROM s")
def _(s, d):
    return values(s, [(round(float(fit_compressed(C.compress_stats(line(s, d), ModelSpec("price", (poly("qty", 2),)))).coef[1, 0]), 3),)], "linear double")


# ---- many features ------------------------------------------------------------------------------------------------------

def _parts(s, d):
    parts = load(s, d, "part").select("p_partkey", "p_brand", "p_type")
    rows = load(s, d, "lineitem").select("l_partkey", "l_quantity").join(parts, F.col("l_partkey") == F.col("p_partkey"))
    return rows.select(F.col("p_brand").alias("brand"), F.col("p_type").alias("kind"), F.col("l_quantity").alias("qty"))


@query("wide_dummies", "SELECT p_brand AS brand, p_type AS kind, round(avg(l_quantity), 6) AS fitted FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand, p_type")
def _(s, d):
    """Brand by type dummies with all products (about 150 columns): the fit of a saturated model is the cell mean."""
    rows = _parts(s, d)
    spec = resolve(rows, parse_formula("qty ~ C(brand)*C(kind)"))
    cf = C.compress_stats(rows, spec).cache()
    fit = fit_compressed(cf, on_alias="drop")
    return cf.df.select("brand", "kind", F.round(linear(fit.coef[:, 0], [c for _, c in spec.design()]), 6).alias("fitted"))


def _brand_types(s, d):
    rows = _parts(s, d)
    return C.compress_stats(rows, resolve(rows, parse_formula("qty ~ C(brand) + C(kind)")))


_BRAND_TYPES = "SELECT p_brand AS brand, p_type AS kind, count(*)::DOUBLE AS n FROM lineitem JOIN part ON l_partkey = p_partkey WHERE p_brand > (SELECT min(p_brand) FROM part) AND p_type > (SELECT min(p_type) FROM part) GROUP BY p_brand, p_type"


def _entries(s, cf, gram):
    names = [n for n, _ in cf.spec.design()]
    cut = lambda n: n.split("[", 1)[1][:-1]
    rows = [(cut(a), cut(b), float(gram[i, j])) for i, a in enumerate(names) for j, b in enumerate(names) if a.startswith("brand[") and b.startswith("kind[") and gram[i, j]]
    return values(s, rows, "brand string, kind string, n double")


@query("wide_gram_packed", _BRAND_TYPES)
def _(s, d):
    """Gram entries of two sets of dummies are the counts of their pairs."""
    cf = _brand_types(s, d)
    return _entries(s, cf, gram_packed(cf))


@query("wide_gram_long", _BRAND_TYPES)
def _(s, d):
    cf = _brand_types(s, d)
    return _entries(s, cf, dense(gram_long(cf), len(cf.spec.design())))


@query("wide_vectors")
def _(s, d):
    """Label on 64 components that never repeat: compression can't help, the packed Gram still fits it in one pass."""
    rows = load(s, d, "embeddings").select(F.col("label").cast("double").alias("y"), *[F.get("embedding", i).cast("double").alias(f"x{i}") for i in range(64)])
    return table(s, fit_compressed(C.uncompressed(rows, ModelSpec("y", tuple(num(f"x{i}") for i in range(64)))), "ehw"), 6)


@query("solve_in_sql", f"SELECT round(regr_slope(price, disc), 4) AS slope, round(regr_intercept(price, disc), 4) AS intercept FROM ({LINE})")
def _(s, d):
    """Two coefficients as one expression over the compressed rows, nothing on the driver."""
    w, x, y = F.col("cnt"), F.col("disc"), F.col("sy_price")
    a, b, c, p, q = (F.sum(v) for v in (w, w * x, w * x * x, y, x * y))
    det = a * c - b * b
    return C.compress_stats(line(s, d), X).df.agg(F.round((a * q - b * p) / det, 4).alias("slope"), F.round((c * p - b * q) / det, 4).alias("intercept"))


@query("logistic_sandwich")
def _(s, d):
    """Robust and cluster errors of the logistic coefficients."""
    spec = ModelSpec("is_f", (num("arm"),), cluster="cust")
    cf = C.compress_binary(orders(s, d), spec, cluster=True)
    out = [(n, float(b), float(r), float(c)) for n, b, r, c in zip(("(intercept)", "arm"), fit_logistic(cf).coef, fit_logistic(cf, sandwich="ehw").se(), fit_logistic(cf, sandwich="cluster").se(), strict=True)]
    return values(s, out, "term string, coef double, se_ehw double, se_cluster double")


# ---- measures -----------------------------------------------------------------------------------------------------------

@query("measure_ratio", f"SELECT 'frequency' AS kind, count(*) AS n, (SELECT count(*) FROM (SELECT DISTINCT rf, ls, disc, qty FROM ({LINE}))) AS records FROM lineitem UNION ALL SELECT 'means', count(*), (SELECT count(*) FROM (SELECT DISTINCT rf, ls, disc FROM ({LINE}))) FROM lineitem UNION ALL SELECT 'stats', count(*), (SELECT count(*) FROM (SELECT DISTINCT rf, ls, disc FROM ({LINE}))) FROM lineitem UNION ALL SELECT 'none', count(*), count(*) FROM lineitem")
def _(s, d):
    return values(s, measures.ratio(line(s, d), CELLS, ["none", "frequency", "means", "stats"]), "kind string, n long, records long")


@query("measure_break_even", f"WITH p AS ({PANEL}), k AS (SELECT count(DISTINCT user_id) AS c, count(DISTINCT t) AS t, count(DISTINCT arm) AS a, count(DISTINCT (arm, tier)) AS b FROM p) SELECT 'arm' AS design, (a * t + a * (t * t + t))::DOUBLE AS between_numbers, (c * t)::DOUBLE AS row_numbers, a <= c / (t + 2) AS pays FROM k UNION ALL SELECT 'arm_tier', (b * t + b * (t * t + t))::DOUBLE, (c * t)::DOUBLE, b <= c / (t + 2) FROM k")
def _(s, d):
    p = panel(s, d)
    c, t, a, b = p.agg(F.count_distinct("user_id"), F.count_distinct("t"), F.count_distinct("arm"), F.count_distinct("arm", "tier")).first()
    rows = []
    for name, g in (("arm", a), ("arm_tier", b)):
        m = measures.stored_numbers(g, c, t)
        rows.append((name, float(m["between"]), float(m["rows"]), bool(g <= m["most_groups"])))
    return values(s, rows, "design string, between_numbers double, row_numbers double, pays boolean")


@query("measure_memory", "WITH k AS (SELECT count(DISTINCT user_id) AS c, count(DISTINCT ts::DATE) AS t FROM events) SELECT 'rows' AS layout, c * t * 10 * 4 AS bytes FROM k UNION ALL SELECT 'units', c * 10 * 4 FROM k")
def _(s, d):
    """Bytes of ten features for every user and day of the events, and for every user alone."""
    c, t = load(s, d, "events").agg(F.count_distinct("user_id"), F.count_distinct(F.to_date("ts"))).first()
    return values(s, [("rows", measures.model_bytes(c * t, 10)), ("units", measures.model_bytes(c, 10))], "layout string, bytes long")


_LOSSY = SQL["cov_means_lossy"]


@query("measure_parity", f"SELECT k.kind, coef, se, passes FROM ({_FLAT}), (VALUES ('none', 0), ('frequency', 3), ('stats', 1)) k(kind, passes) WHERE term = 'x' UNION ALL SELECT 'means', coef, se, 1 FROM ({_LOSSY})")
def _(s, d):
    """Slope, its error and the passes over raw rows that three outcomes take, by way of compression; group means lose the spread."""
    rows, ys = line(s, d), ("price", "qty", "tax")
    out = []
    for kind, passes in (("none", 0), ("frequency", len(ys)), ("stats", 1)):
        spec = replace(X, outcomes=ys[:1] if kind == "frequency" else ys, cluster=None)
        fit = fit_linear(rows, spec, kind)
        out.append((kind, round(float(fit.coef[1, 0]), 4), round(float(fit.se()[1]), 4), passes))
    lossy = baselines.wls_means(rows, X)
    return values(s, [*out, ("means", round(float(lossy.coef[1, 0]), 4), round(float(lossy.se()[1]), 4), 1)], "kind string, coef double, se double, passes int")


@query("measure_lossy_deficit", f"SELECT round(sum(m2), 0) AS deficit FROM (SELECT var_pop(price) * count(*) / 1e6 AS m2 FROM ({LINE}) GROUP BY disc)")
def _(s, d):
    rows = line(s, d)
    full, lossy = fit_compressed(C.compress_stats(rows, X)), baselines.wls_means(rows, X)
    return values(s, [(round(float(full.rss[0] - lossy.rss[0]) / 1e6, 0),)], "deficit double")


_RECORDS = lambda y: f"(SELECT count(*) FROM (SELECT DISTINCT rf, ls, disc, {y} FROM ({LINE})))"


@query("measure_passes", f"SELECT o AS outcomes, o AS frequency_passes, CASE o WHEN 1 THEN {_RECORDS('qty')} WHEN 2 THEN {_RECORDS('qty')} + {_RECORDS('tax')} ELSE {_RECORDS('qty')} + {_RECORDS('tax')} + {_RECORDS('price')} END AS frequency_records, 1 AS stats_passes, (SELECT count(*) FROM (SELECT DISTINCT rf, ls, disc FROM ({LINE}))) AS stats_records FROM (VALUES (1), (2), (3)) v(o)")
def _(s, d):
    rows, ys = line(s, d), ("qty", "tax", "price")
    each = [C.compress_frequency(rows, replace(CELLS, outcomes=(y,))).df.count() for y in ys]
    out = [(o, o, sum(each[:o]), 1, C.compress_stats(rows, replace(CELLS, outcomes=ys[:o])).df.count()) for o in range(1, 4)]
    return values(s, out, "outcomes int, frequency_passes int, frequency_records long, stats_passes int, stats_records long")


@query("measure_power")
def _(s, d):
    """Smallest detectable effect without covariates, with the control variate, and with bins of the pre-period."""
    pp = _pre_post(s, d).withColumn("bin", F.ntile(5).over(Window.orderBy("pre", "user_id")))
    plain = baselines.diff_means(pp, "post", "arm").first().se
    adjusted = baselines.cuped(pp, "post", "pre", "arm").first().se
    binned = fit_linear(pp, ModelSpec("post", (num("arm"), cat("bin"))), "stats", "ehw").se()[1]
    return values(s, [(n, float(v), measures.minimum_detectable(float(v))) for n, v in (("means", plain), ("control_variate", adjusted), ("bins", binned))], "design string, se double, detectable double")


@query("measure_coverage")
def _(s, d):
    """Interval coverage of an injected effect over hash-seeded assignments."""
    rows = panel(s, d).select("user_id", "t", "y")
    spec = ModelSpec("y", (num("arm"),), cluster="user_id", time="t", roles={"arm": "static"})
    m = measures.coverage(rows, spec, "arm", 0.5, range(12), "cluster", "static")
    return values(s, [tuple(m.values())], "bias double, sd double, coverage double, rejected double")


@query("measure_bins")
def _(s, d):
    """Records, effect and its standard error as the number of bins grows."""
    customers, rows = load(s, d, "customer"), load(s, d, "orders")
    out = []
    for k in (2, 5, 10, 50):
        joined = rows.join(binning.bin_quantile(customers, "c_acctbal", k, name="bin").select("c_custkey", "bin"), F.col("o_custkey") == F.col("c_custkey"))
        cf = C.compress_stats(joined.select((F.col("o_custkey") % 2).cast("int").alias("arm"), "bin", F.col("o_totalprice").alias("y")), resolve(joined.select("bin", F.lit(0).alias("arm"), F.lit(0.0).alias("y")), ModelSpec("y", (num("arm"), cat("bin")))))
        fit = fit_compressed(cf, "ehw")
        out.append((k, fit.records, float(fit.coef[1, 0]), float(fit.se()[1])))
    return values(s, out, "bins int, records long, effect double, se double")


_CLUSTERED = "CASE WHEN pairs < 0.5 * n THEN 'within' WHEN NOT even THEN 'static' WHEN groups <= c / (t + 2) THEN 'between' ELSE 'balanced' END"
_GRID = f"SELECT count(*) AS n, count(DISTINCT (user_id, arm, t)) AS pairs, count(DISTINCT user_id) AS c, count(DISTINCT t) AS t, true AS even, count(DISTINCT arm) AS g1, count(DISTINCT (arm, tier)) AS g2 FROM ({PANEL})"


@query("planner_choices", f"""SELECT 'lineitem' AS input, CASE WHEN count(DISTINCT (rf, ls, disc)) > 0.5 * count(*) THEN 'none' ELSE 'stats' END AS strategy FROM ({LINE})
UNION ALL SELECT 'embeddings', CASE WHEN count(DISTINCT (embedding[1], embedding[2])) > 0.5 * count(*) THEN 'none' ELSE 'stats' END FROM embeddings
UNION ALL SELECT 'panel_arm', {_CLUSTERED.replace('groups', 'g1')} FROM ({_GRID}) UNION ALL SELECT 'panel_arm_tier', {_CLUSTERED.replace('groups', 'g2')} FROM ({_GRID})
UNION ALL SELECT 'orders', CASE WHEN count(DISTINCT (cust, arm, total)) < 0.5 * count(*) THEN 'within' ELSE 'static' END FROM ({ORDERS})""")
def _(s, d):
    vectors = load(s, d, "embeddings").select(F.get("embedding", 0).alias("a"), F.get("embedding", 1).alias("b"), F.col("label").cast("double").alias("y"))
    p = panel(s, d)
    wide = ModelSpec("y", (num("arm"), cat("tier"), num("t")), cluster="user_id", time="t")
    o = orders(s, d).withColumn("day", F.col("total"))
    plans = [
        ("lineitem", plan_strategy(line(s, d), CELLS)), ("embeddings", plan_strategy(vectors, ModelSpec("y", (num("a"), num("b"))))),
        ("panel_arm", plan_strategy(p, PANEL_SPEC, "cluster")), ("panel_arm_tier", plan_strategy(p, wide, "cluster")),
        ("orders", plan_strategy(o, ModelSpec("total", (num("arm"), num("day")), cluster="cust"), "cluster")),
    ]
    return values(s, [(n, q.strategy) for n, q in plans], "input string, strategy string")


@query("flagship")
def flagship(s, d):
    """Compressed once; coefficients with homoskedastic and heteroskedasticity-consistent errors."""
    rows = line(s, d)
    spec = resolve(rows, CELLS)
    cf = C.compress_stats(rows, spec).cache()
    return table(s, fit_compressed(cf), 8).withColumn("cov", F.lit("homoskedastic")).unionAll(table(s, fit_compressed(cf, "ehw"), 8).withColumn("cov", F.lit("ehw")))


