"""More experiment workloads: weekly panels, binary outcomes of several features, sampling weights, injected effects, wide sparse designs."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lincompress.functions import linexpr
from lincompress.operators import compress as C
from lincompress.operators.fit import fit_cells, fit_compressed, fit_linear, fit_lpm, linear
from lincompress.operators.glm import fit_logistic
from lincompress.oracles import LINE, ORDERS, PANEL, lines_by_group, two_parameters
from lincompress.plans import binning
from lincompress.plans.design import ModelSpec, cat, inter, num, resolve
from lincompress.sources.tables import load, sample_rows
from lincompress.workloads import line, orders, panel, table, values

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


# ---- weekly panel: few periods, so that grouping equal matrices pays for more features ---------------------------------

WEEKLY = f"SELECT user_id, any_value(tier) AS tier, t // 6 AS t, sum(y) AS y FROM ({PANEL}) GROUP BY user_id, t // 6"


def _weekly(s, d):
    week = F.floor(F.col("t") / 6).cast("int").alias("t")
    return panel(s, d).groupBy("user_id", week).agg(F.max("tier").alias("tier"), F.sum("y").alias("y"))


def _lines_sql(rows: str) -> str:
    return f"""WITH a AS ({lines_by_group(rows, 'tier', 't', 'y', 'user_id')}), z AS (SELECT * FROM a WHERE h = 0), k AS (SELECT * FROM a WHERE h > 0)
SELECT '(intercept)' AS term, round(c0, 6) AS coef, round(sqrt(v00), 6) AS se FROM z UNION ALL SELECT 't', round(c1, 6), round(sqrt(v11), 6) FROM z
UNION ALL SELECT 'tier[' || k.h || ']', round(k.c0 - z.c0, 6), round(sqrt(k.v00 + z.v00), 6) FROM z, k UNION ALL SELECT 'tier[' || k.h || ']:t', round(k.c1 - z.c1, 6), round(sqrt(k.v11 + z.v11), 6) FROM z, k"""


def _weekly_fit(kind: str):
    @query(f"panel_weekly_{kind}", _lines_sql(WEEKLY))
    def run(s, d):
        spec = ModelSpec("y", (cat("tier"), num("t"), inter(cat("tier"), num("t"))), cluster="user_id", time="t")
        return table(s, fit_linear(_weekly(s, d), spec, kind, "cluster"), 6)


for _kind in ("none", "static", "balanced", "between"):
    _weekly_fit(_kind)


@query("features_name_cluster", two_parameters(ORDERS, "cust", "total", "cluster", "cust", digits=3))
def _(s, d):
    """The features hold the cluster's id, so the cluster adds no key."""
    spec = ModelSpec("total", (num("cust"),), cluster="cust")
    rows = orders(s, d)
    assert C.features_determine_cluster(rows, spec)
    return table(s, fit_compressed(C.compress_determined(rows, spec), "cluster"), 3, {"cust": "x"})


# ---- binary outcomes ----------------------------------------------------------------------------------------------------

EVENTS = "SELECT user_id % 2 AS arm, hour(ts) // 6 AS part, (event_type = 'purchase')::INT AS buy FROM events"


def _events(s, d):
    return load(s, d, "events").select((F.col("user_id") % 2).cast("int").alias("arm"), F.floor(F.hour("ts") / 6).cast("int").alias("part"), (F.col("event_type") == "purchase").cast("int").alias("buy"))


@query("lpm_purchase", two_parameters(EVENTS, "arm", "buy", "ehw", digits=6))
def _(s, d):
    return table(s, fit_lpm(_events(s, d), ModelSpec("buy", (num("arm"),))), 6, {"arm": "x"})


@query("lpm_toxic_by_language", """WITH m AS (SELECT lang, avg(toxic) AS p, count(*) AS n FROM labels JOIN documents USING (doc_id) GROUP BY lang), z AS (SELECT * FROM m ORDER BY lang LIMIT 1)
SELECT 'lang[' || m.lang || ']' AS term, round(m.p - z.p, 6) AS coef, round(sqrt(m.p * (1 - m.p) / m.n + z.p * (1 - z.p) / z.n), 6) AS se FROM m, z WHERE m.lang > z.lang""")
def _(s, d):
    rows = load(s, d, "labels").join(load(s, d, "documents").select("doc_id", "lang"), "doc_id").select("lang", F.col("toxic").cast("int").alias("toxic"))
    return table(s, fit_lpm(rows, ModelSpec("toxic", (cat("lang"),))), 6).where("term <> '(intercept)'")


def _margins(name: str, rows, spec: ModelSpec, sums: dict[str, str], sql: str):
    """A logistic fit is the maximum exactly if fitted and observed totals agree for every design column; ``sums`` names their columns."""

    @query(name, sql)
    def run(s, d):
        df = rows(s, d)
        full = resolve(df, spec)
        cf = C.compress_binary(df, full)
        fit = fit_logistic(cf)
        eta = linear(fit.coef, [c for _, c in full.design()])
        held = cf.df.withColumn("_e", F.col("cnt") / (1 + F.exp(-eta)))
        parts = [held.groupBy(F.lit(m).alias("margin"), F.col(c).cast("string").alias("level")).agg(F.round(F.sum("_e"), 4).alias("total")) for m, c in sums.items()]
        out = parts[0]
        for part in parts[1:]:
            out = out.unionAll(part)
        return out


def _margin_sql(rows: str, y: str, sums: dict[str, str]) -> str:
    return " UNION ALL ".join(f"SELECT '{m}' AS margin, {c}::VARCHAR AS level, round(sum({y})::DOUBLE, 4) AS total FROM ({rows}) GROUP BY {c}" for m, c in sums.items())


_EVENT_SUMS, _ORDER_SUMS = {"arm": "arm", "part": "part"}, {"prio": "prio", "arm": "arm"}
_margins("logistic_purchase", _events, ModelSpec("buy", (num("arm"), cat("part"))), _EVENT_SUMS, _margin_sql(EVENTS, "buy", _EVENT_SUMS))
_margins("logistic_status", orders, ModelSpec("is_f", (cat("prio"), num("arm"))), _ORDER_SUMS, _margin_sql(ORDERS, "is_f", _ORDER_SUMS))


@query("logistic_robust", f"""WITH m AS (SELECT arm, avg(is_f) AS p, count(*) AS n FROM ({ORDERS}) GROUP BY arm),
u AS (SELECT o.arm, o.cust, sum(o.is_f - m.p) AS u, sum((o.is_f - m.p) * (o.is_f - m.p)) AS q FROM ({ORDERS}) o JOIN m ON o.arm = m.arm GROUP BY o.arm, o.cust),
v AS (SELECT u.arm, any_value(m.p) AS p, sum(u * u) / pow(any_value(m.n * m.p * (1 - m.p)), 2) AS c, sum(q) / pow(any_value(m.n * m.p * (1 - m.p)), 2) AS e FROM u JOIN m ON u.arm = m.arm GROUP BY u.arm),
z AS (SELECT * FROM v WHERE arm = 0), o AS (SELECT * FROM v WHERE arm = 1)
SELECT '(intercept)' AS term, round(ln(p / (1 - p)), 6) AS coef, round(sqrt(e), 6) AS se_ehw, round(sqrt(c), 6) AS se_cluster FROM z
UNION ALL SELECT 'arm', round(ln(o.p / (1 - o.p)) - ln(z.p / (1 - z.p)), 6), round(sqrt(o.e + z.e), 6), round(sqrt(o.c + z.c), 6) FROM z, o""")
def _(s, d):
    cf = C.compress_binary(orders(s, d), ModelSpec("is_f", (num("arm"),), cluster="cust"), cluster=True).cache()
    e, c = fit_logistic(cf, sandwich="ehw"), fit_logistic(cf, sandwich="cluster")
    rows = [(n, *(round(float(v), 6) for v in r)) for n, *r in zip(e.names, e.coef, e.se(), c.se(), strict=True)]
    cf.df.unpersist()
    return values(s, rows, "term string, coef double, se_ehw double, se_cluster double")


# ---- weights and injected effects ---------------------------------------------------------------------------------------

_SAMPLED = f"SELECT *, CASE WHEN rf = 'A' THEN 1.0 ELSE 2.0 END AS w FROM ({LINE}) WHERE rf = 'A' OR supp % 2 = 0"


@query("wls_sampling_rates", two_parameters(_SAMPLED, "disc", "price", "ehw", weight="w", weight_kind="probability"))
def _(s, d):
    """Half of the suppliers stand for all but flag A, which is there whole: weights are one over the sampling rate."""
    rows = line(s, d).where("rf = 'A' or supp % 2 = 0").withColumn("w", F.when(F.col("rf") == "A", 1.0).otherwise(2.0))
    spec = ModelSpec("price", (num("disc"),), weight="w", weight_kind="probability")
    return table(s, fit_linear(rows, spec, "weighted", "ehw"), names={"disc": "x"})


_INJECTED = """WITH q AS (SELECT quantile_cont(c_acctbal, [0.1,0.2,0.3,0.4,0.5,0.6,0.7,0.8,0.9]) AS qs FROM customer),
r AS (SELECT o_custkey % 2 AS arm, len(list_filter(qs, lambda x: x <= c_acctbal))::INT AS bin, o_totalprice / 1000 + pow(c_acctbal / 1000, 2) AS y FROM orders JOIN customer ON o_custkey = c_custkey, q)"""
#: The injected effect in each tenth of the balance.
_EFFECT = "5 + 3 * (bin >= 5)::INT + 0.5 * bin"


@query("injected_nonlinear", f"""{_INJECTED}, e AS (SELECT bin, arm, y + arm * ({_EFFECT}) AS y FROM r)
SELECT bin, round(avg(y) FILTER (arm = 1) - avg(y) FILTER (arm = 0), 6) AS effect, round(sqrt(var_pop(y) FILTER (arm = 1) / count(*) FILTER (arm = 1) + var_pop(y) FILTER (arm = 0) / count(*) FILTER (arm = 0)), 6) AS se FROM e GROUP BY bin""")
def _(s, d):
    """An outcome that is quadratic in a feature, with an effect that differs by tenths of it: dummies and their products catch both."""
    customers = binning.bin_quantile(load(s, d, "customer"), "c_acctbal", 10, name="bin").select("c_custkey", "bin", "c_acctbal")
    rows = load(s, d, "orders").join(customers, F.col("o_custkey") == F.col("c_custkey")).withColumn("arm", (F.col("o_custkey") % 2).cast("int"))
    effect = 5 + 3 * (F.col("bin") >= 5).cast("int") + 0.5 * F.col("bin")
    rows = rows.select("arm", "bin", (F.col("o_totalprice") / 1000 + F.pow(F.col("c_acctbal") / 1000, F.lit(2)) + F.col("arm") * effect).alias("y"))
    spec = ModelSpec("y", (cat("bin"), inter(num("arm"), cat("bin", ref=-1))))
    fit = fit_linear(rows, spec, "stats", "ehw")
    first = [i for i, n in enumerate(fit.names) if n.startswith("arm:")]
    return values(s, [(k, round(float(fit.coef[i, 0]), 6), round(float(fit.se()[i]), 6)) for k, i in enumerate(first)], "bin int, effect double, se double")


@query("injected_linear_misses", f"""{_INJECTED}, e AS (SELECT bin, arm, y + arm * ({_EFFECT}) AS y FROM r), t AS (SELECT bin, avg(y) FILTER (arm = 1) - avg(y) FILTER (arm = 0) AS b, count(*) AS n, count(*) FILTER (arm = 1) AS k FROM e GROUP BY bin)
SELECT round(sum(b * k * (n - k) / n) / sum(k * (n - k) / n), 6) AS effect FROM t""")
def _(s, d):
    """One effect for all, with the same dummies: the bins' effects weighted by their information."""
    customers = binning.bin_quantile(load(s, d, "customer"), "c_acctbal", 10, name="bin").select("c_custkey", "bin", "c_acctbal")
    rows = load(s, d, "orders").join(customers, F.col("o_custkey") == F.col("c_custkey")).withColumn("arm", (F.col("o_custkey") % 2).cast("int"))
    effect = 5 + 3 * (F.col("bin") >= 5).cast("int") + 0.5 * F.col("bin")
    rows = rows.select("arm", "bin", (F.col("o_totalprice") / 1000 + F.pow(F.col("c_acctbal") / 1000, F.lit(2)) + F.col("arm") * effect).alias("y"))
    fit = fit_linear(rows, ModelSpec("y", (num("arm"), cat("bin"))), "stats")
    return values(s, [(round(float(fit.coef[1, 0]), 6),)], "effect double")


def _bin_value(kind: str, of: str):
    sql = f"WITH q AS (SELECT quantile_cont(c_acctbal, [0.25,0.5,0.75]) AS qs FROM customer), b AS (SELECT c_custkey, c_acctbal, len(list_filter(qs, lambda x: x <= c_acctbal)) AS k FROM customer, q), m AS (SELECT k, {of} AS v FROM b GROUP BY k) SELECT c_custkey, round(v, 6) AS value FROM b JOIN m ON b.k = m.k"

    @query(f"bin_value_{kind}", sql)
    def run(s, d):
        return binning.bin_quantile(load(s, d, "customer"), "c_acctbal", 4, name="bin", value=kind).select("c_custkey", F.round("bin", 6).alias("value"))


_bin_value("mean", "avg(c_acctbal)")
_bin_value("mid", "(min(c_acctbal) + max(c_acctbal)) / 2")


# ---- hand-off, samples, vectors -----------------------------------------------------------------------------------------

@query("local_hand_off", two_parameters(LINE, "disc", "price", "ehw"))
def _(s, d):
    """The compressed rows as an Arrow table on the driver, fitted there with numpy alone, then back as a frame."""
    spec = ModelSpec("price", (num("disc"),))
    local = C.to_local(C.compress_stats(line(s, d), spec))
    w, x, y, q = (np.asarray(local[c], float) for c in ("cnt", "disc", "sy_price", "syy_price"))
    m = np.column_stack([np.ones_like(x), x])
    gram = (m * w[:, None]).T @ m
    beta = np.linalg.solve(gram, m.T @ y)
    f = m @ beta
    meat = (m * (q - 2 * f * y + w * f * f)[:, None]).T @ m
    again = fit_compressed(C.from_local(s, local, "stats", spec), "ehw")
    assert np.allclose(again.coef[:, 0], beta, rtol=1e-8)
    se = np.sqrt(np.diag(np.linalg.solve(gram, np.linalg.solve(gram, meat).T)))
    return values(s, [(n, round(float(b), 4), round(float(v), 4)) for n, b, v in zip(("(intercept)", "x"), beta, se, strict=True)], "term string, coef double, se double")


@query("sampled_cuts")
def _(s, d):
    """Cut points from a tenth of the rows, bins and fit from all of them."""
    rows = line(s, d)
    cuts = binning.cut_points(sample_rows(rows, 0.1, seed=4), "price", 10)
    binned = rows.withColumn("bin", binning.bin_by_cuts("price", cuts))
    return binned.groupBy("bin").agg(F.count(F.lit(1)).alias("n"))


_VECTOR = "SELECT vec_id, embedding[1]::DOUBLE AS a, embedding[2]::DOUBLE AS b, embedding[3]::DOUBLE AS c FROM embeddings"


@query("vector_expressions", f"SELECT vec_id, round(2 * a, 6) AS twice, round(a + b, 6) AS both, round(a * c, 6) AS outer_ac, round(b * c, 6) AS kron_bc, round(a * a * a + a * b * b + a * c * c, 6) AS product FROM ({_VECTOR})")
def _(s, d):
    """Scaling, sums, packed outer and Kronecker products, and a packed symmetric matrix times a vector."""
    v = F.transform(F.slice("embedding", 1, 3), lambda x: x.cast("double"))
    rows = load(s, d, "embeddings").select("vec_id", v.alias("v")).withColumn("m", linexpr.outer_packed(F.col("v")))
    shifted = F.concat(F.slice("v", 2, 2), F.slice("v", 1, 1))
    r = lambda c: F.round(c, 6)
    return rows.select(
        "vec_id", r(F.get(linexpr.vec_scale(F.col("v"), F.lit(2.0)), 0)).alias("twice"), r(F.get(linexpr.vec_add(F.col("v"), shifted), 0)).alias("both"), r(F.get("m", 2)).alias("outer_ac"),
        r(F.get(linexpr.kron_vec(F.col("v"), F.col("v")), 5)).alias("kron_bc"), r(F.get(linexpr.mat_vec(F.col("m"), F.col("v")), 0)).alias("product"),
    )


# ---- thousands of features ----------------------------------------------------------------------------------------------

_PARTS = "SELECT l_partkey AS part, l_quantity AS qty FROM lineitem"


@query("wide_sparse_fit", f"WITH m AS (SELECT part, avg(qty) AS m, count(*) AS n, sum(qty * qty) - count(*) * avg(qty) * avg(qty) AS ss FROM ({_PARTS}) GROUP BY part) SELECT part, round(m, 6) AS fitted, round(sqrt(greatest(ss, 0)) / n, 6) AS se FROM m")
def _(s, d):
    """A dummy for every part, however many: cell means and their robust errors, from non-zero entries only; nothing of the number of parts is on the driver."""
    rows = load(s, d, "lineitem").select(F.col("l_partkey").alias("part"), F.col("l_quantity").alias("qty"))
    cf = C.compress_stats(rows, ModelSpec("qty", (cat("part", ref="none"),), intercept=False))
    return fit_cells(cf).select(F.col("level").alias("part"), F.round("coef_qty", 6).alias("fitted"), F.round("se_qty", 6).alias("se"))
