"""Small frames with answers by hand, as exact fractions."""

from dataclasses import replace

import numpy as np
import pytest

from lincompress.functions import udx
from lincompress.operators import baselines, compress as C, measures
from lincompress.operators.fit import COMPRESSIONS, fit_cells, fit_compressed, fit_moments_expanded, mean_variance, posterior, wald
from lincompress.operators.glm import Separated, fit_logistic
from lincompress.operators.solve import Aliased
from lincompress.plans.design import ModelSpec, cat, inter, num, parse_formula, poly, resolve

CROSS = [(0, 1, 1), (0, 1, 2), (0, 4, 3), (1, 2, 1), (1, 2, 2), (1, 3, 3), (1, 5, 4), (2, 6, 1), (2, 6, 3), (2, 8, 4)]
SPEC = ModelSpec("y", (num("x"),), cluster="c")


@pytest.fixture(scope="module")
def cross(spark):
    return spark.createDataFrame(CROSS, "x int, y int, c int").cache()


@pytest.fixture(scope="module")
def panel(spark):
    ys = {1: (0, [1, 2, 2]), 2: (0, [2, 2, 5]), 3: (1, [3, 3, 7]), 4: (1, [1, 4, 6])}
    return spark.createDataFrame([(u, a, t, float(y)) for u, (a, v) in ys.items() for t, y in enumerate(v)], "u int, arm int, t int, y double").cache()


PANEL = ModelSpec("y", (num("arm"), num("t"), inter(num("arm"), num("t"))), cluster="u", time="t")


def test_four_records(cross):
    rows = lambda df: sorted(map(tuple, df.collect()))
    assert rows(C.compress_frequency(cross, SPEC).df) == [(0, 1, 2), (0, 4, 1), (1, 2, 2), (1, 3, 1), (1, 5, 1), (2, 6, 2), (2, 8, 1)]
    assert [(r.x, r.cnt, round(r.mean_y, 9)) for r in C.compress_means(cross, SPEC).df.orderBy("x").collect()] == [(0, 3, 2), (1, 4, 3), (2, 3, round(20 / 3, 9))]
    assert rows(C.compress_stats(cross, SPEC).df) == [(0, 3, 6, 18), (1, 4, 12, 42), (2, 3, 20, 136)]


@pytest.mark.parametrize("kind", ["none", "frequency", "stats", "within"])
def test_cross_section(cross, kind):
    fit = fit_compressed(COMPRESSIONS[kind](cross, SPEC))
    assert np.allclose(fit.coef[:, 0], [22 / 15, 7 / 3]) and np.isclose(fit.rss[0], 284 / 15) and np.isclose(fit.rss[0] / fit.df, 71 / 30)
    assert np.allclose(fit.cov[0], [[142 / 225, -71 / 180], [-71 / 180, 71 / 180]])
    assert np.allclose(fit_compressed(COMPRESSIONS[kind](cross, SPEC), "ehw").cov[0], [[3973 / 6750, -232 / 675], [-232 / 675, 389 / 1350]])
    assert np.allclose(fit_compressed(COMPRESSIONS[kind](cross, SPEC), method="packed").cov[0], fit.cov[0])


@pytest.mark.parametrize("kind", ["none", "within", "cluster_moments"])
def test_cross_section_clusters(cross, kind):
    fit = fit_compressed(COMPRESSIONS[kind](cross, SPEC), "cluster")
    assert np.allclose(fit.cov[0], [[55223 / 101250, -628 / 2025], [-628 / 2025, 1229 / 4050]]) and fit.clusters == 4


def test_means_lose_the_variance(cross):
    lossy, full = baselines.wls_means(cross, SPEC), fit_compressed(C.compress_stats(cross, SPEC))
    assert np.allclose(lossy.coef, full.coef) and np.isclose(lossy.cov[0][1, 1], 32 / 45) and not np.isclose(lossy.cov[0][1, 1], full.cov[0][1, 1])


@pytest.mark.parametrize("kind", ["none", "within", "cluster_moments", "static", "balanced", "between"])
def test_balanced_panel(panel, kind):
    fit = fit_compressed(COMPRESSIONS[kind](panel, PANEL), "cluster")
    assert np.allclose(fit.coef[:, 0], [4 / 3, 5 / 12, 1, 5 / 4])
    assert np.allclose(np.diag(fit.cov[0]), [1 / 72, 53 / 288, 1 / 8, 5 / 32])
    flat = fit_compressed(COMPRESSIONS[kind](panel, PANEL))
    assert np.isclose(flat.rss[0], 109 / 12) and np.allclose(np.diag(flat.cov[0]), [545 / 1152, 545 / 576, 109 / 384, 109 / 192])
    if kind in ("none", "within", "balanced", "between"):
        assert np.allclose(np.diag(fit_compressed(COMPRESSIONS[kind](panel, PANEL), "ehw").cov[0]), [29 / 216, 925 / 1728, 23 / 72, 283 / 576])


def test_between_statistics(panel):
    rows = sorted(C.compress_between_cluster(panel, PANEL).df.collect(), key=lambda r: r.matrix[0].arm)
    assert [r.k for r in rows] == [2, 2] and [list(r.sy_y) for r in rows] == [[3, 4, 7], [4, 7, 13]]
    assert list(rows[0].q_y) == [5, 6, 12, 6, 8, 14, 12, 14, 29] and list(rows[1].q_y) == [10, 13, 27, 13, 25, 45, 27, 45, 85]


def test_interaction_after_compression(panel):
    main = replace(PANEL, terms=PANEL.terms[:2])
    for kind in ("static", "balanced", "within", "between"):
        later = COMPRESSIONS[kind](panel, main).with_terms(PANEL.terms[2])
        assert np.allclose(fit_compressed(later, "cluster").cov[0], fit_compressed(C.uncompressed(panel, PANEL), "cluster").cov[0])
    with pytest.raises(ValueError):
        COMPRESSIONS["static"](panel, main).with_terms(poly("t", 2))
    with pytest.raises(ValueError):
        COMPRESSIONS["cluster_moments"](panel, main).with_terms(PANEL.terms[2])
    slim = fit_compressed(C.compress_balanced(panel, PANEL, keep_y=False), "cluster")
    assert np.allclose(np.diag(slim.cov[0]), [1 / 72, 53 / 288, 1 / 8, 5 / 32])
    assert np.allclose(fit_moments_expanded(C.compress_cluster_moments(panel, PANEL)).cov[0], slim.cov[0])


def test_trend_has_closed_moments(panel):
    fit = fit_compressed(C.compress_trend(panel, PANEL), "cluster")
    assert np.allclose(fit.coef[:, 0], [4 / 3, 5 / 12, 1, 5 / 4]) and np.allclose(np.diag(fit.cov[0]), [1 / 72, 53 / 288, 1 / 8, 5 / 32])
    shorter = panel.where("not (u = 2 and t = 0)")
    a, b = fit_compressed(C.compress_trend(shorter, PANEL), "cluster"), fit_compressed(C.uncompressed(shorter, PANEL), "cluster")
    assert np.allclose(a.cov[0], b.cov[0])
    with pytest.raises(Exception, match="gaps"):
        C.compress_trend(panel.where("not (u = 2 and t = 1)"), PANEL).df.collect()


def test_unbalanced_is_refused_and_static_takes_it(panel):
    part = panel.where("not (u = 2 and t = 1)")
    with pytest.raises(C.Unbalanced):
        C.compress_balanced(part, PANEL)
    a, b = (fit_compressed(COMPRESSIONS[k](part, PANEL), "cluster") for k in ("static", "none"))
    assert np.allclose(a.coef, b.coef) and np.allclose(a.cov[0], b.cov[0])


def test_logistic(spark):
    rows = [(0, int(i < 3)) for i in range(10)] + [(1, int(i < 6)) for i in range(10)]
    df = spark.createDataFrame(rows, "x int, y int")
    spec = ModelSpec("y", (num("x"),))
    fit = fit_logistic(C.compress_binary(df, spec))
    assert np.allclose(fit.coef, [np.log(3 / 7), np.log(3.5)]) and np.isclose(fit.se()[1], np.sqrt(1 / 3 + 1 / 7 + 1 / 6 + 1 / 4))
    assert np.allclose(baselines.logistic_rows(df, spec).coef, fit.coef)
    with pytest.raises(Separated):
        fit_logistic(C.compress_binary(df.selectExpr("x", "x as y"), spec))
    with pytest.raises(Exception, match="neither 0 nor 1"):
        C.compress_binary(df.selectExpr("x", "2 as y"), spec).df.collect()


def test_weights(spark, cross):
    weighted = cross.selectExpr("x", "y", "c", "1 + c % 3 as w")
    expanded = weighted.selectExpr("x", "y", "c", "explode(sequence(1, w)) as r")
    freq = replace(SPEC, weight="w", weight_kind="frequency")
    for cov in ("homoskedastic", "ehw"):
        assert np.allclose(fit_compressed(C.compress_weighted(weighted, freq), cov).cov[0], fit_compressed(C.uncompressed(expanded, SPEC), cov).cov[0])
    ana = replace(SPEC, weight="w", weight_kind="analytic")
    ones = cross.selectExpr("x", "y", "c", "1 as w")
    for cov in ("homoskedastic", "ehw"):
        assert np.allclose(fit_compressed(C.compress_weighted(ones, ana), cov).cov[0], fit_compressed(C.compress_stats(cross, SPEC), cov).cov[0])
        raw = fit_compressed(C.uncompressed(weighted, ana), cov)
        assert np.allclose(fit_compressed(C.compress_weighted(weighted, ana), cov).cov[0], raw.cov[0])
    ten = weighted.withColumn("w", weighted.w * 10)
    a, b = (fit_compressed(C.compress_weighted(d, ana), "ehw") for d in (weighted, ten))
    assert np.allclose(a.coef, b.coef) and np.allclose(a.cov[0], b.cov[0])
    with pytest.raises(Exception, match="negative"):
        C.compress_weighted(weighted.withColumn("w", -weighted.w), ana).df.collect()


def test_small_sample_forms(cross):
    x = np.array([[1, r[0]] for r in CROSS], float)
    y = np.array([r[1] for r in CROSS], float)
    bread = np.linalg.inv(x.T @ x)
    e = y - x @ bread @ x.T @ y
    h = np.einsum("ij,jk,ik->i", x, bread, x)
    for name, power in (("HC2", 1), ("HC3", 2)):
        want = bread @ (x.T * (e**2 / (1 - h) ** power)) @ x @ bread
        assert np.allclose(fit_compressed(C.compress_stats(cross, SPEC), "ehw", small_sample=name).cov[0], want)


def test_degenerate(spark, cross):
    twice = cross.selectExpr("x", "y", "c", "x * 2 as z")
    with pytest.raises(Aliased) as caught:
        fit_compressed(C.compress_stats(twice, ModelSpec("y", (num("x"), num("z")))))
    assert caught.value.columns == [2]
    kept = fit_compressed(C.compress_stats(twice, ModelSpec("y", (num("x"), num("z")))), on_alias="drop")
    assert np.allclose(kept.coef[:2, 0], [22 / 15, 7 / 3]) and kept.coef[2, 0] == 0
    with pytest.raises(Aliased):
        fit_compressed(C.compress_stats(cross.limit(0), SPEC))
    one = fit_compressed(C.compress_stats(cross.selectExpr("x", "7 as y", "c"), SPEC))
    assert np.allclose(one.rss, 0) and np.allclose(one.coef[:, 0], [7, 0])
    bad = spark.createDataFrame([(1, None, 1)], "x int, y int, c int")
    with pytest.raises(Exception, match="null in y"):
        C.compress_stats(bad, SPEC).df.collect()
    assert C.compress_stats(bad, SPEC, nulls="drop").df.count() == 0
    zero = spark.createDataFrame([(-0.0, 1.0), (0.0, 2.0)], "x double, y double")
    assert C.compress_stats(zero, ModelSpec("y", (num("x"),))).df.count() == 1


def test_merge_rollup_and_moments(cross):
    spec = ModelSpec("y", (num("x"), num("c")))
    whole = C.compress_stats(cross, spec)
    parts = [C.compress_stats(cross.where(f"y % 2 = {k}"), spec) for k in (0, 1)]
    key = lambda cf: sorted(map(tuple, cf.df.select("x", "c", "cnt", "sy_y", "syy_y").collect()))
    assert key(C.merge(*parts)) == key(whole)
    assert sorted(map(tuple, C.rollup(whole, ["c"]).df.select("x", "cnt", "sy_y", "syy_y").collect())) == [(0, 3, 6, 18), (1, 4, 12, 42), (2, 3, 20, 136)]
    m = mean_variance(whole).first()
    y = [r[1] for r in CROSS]
    assert m.n == 10 and np.isclose(m.mean, np.mean(y)) and np.isclose(m.variance, np.var(y, ddof=1))


def test_formula_and_wald(cross):
    spec = resolve(cross, parse_formula("y ~ C(x) + c"))
    assert [n for n, _ in spec.design()] == ["(intercept)", "x[1]", "x[2]", "c"]
    fit = fit_compressed(C.compress_stats(cross, spec))
    f, p = wald(fit, [[0, 1, 0, 0], [0, 0, 1, 0]])
    assert f > 0 and 0 < p < 1
    assert parse_formula("y ~ 0 + a*b").intercept is False
    assert cat("x", levels=["a", "b"]).columns()[0][0] == "x[b]"


def test_storage_rule():
    assert measures.stored_numbers(2, 150, 30)["most_groups"] == pytest.approx(150 / 32)
    assert measures.model_bytes(10**9, 10) == 40 * 10**9 and measures.model_bytes(10**7, 10) == 400 * 10**6


def test_posterior_is_the_ridge_form(cross):
    x = np.array([[1.0, r[0]] for r in CROSS])
    y = np.array([float(r[1]) for r in CROSS])
    beta = np.linalg.solve(x.T @ x, x.T @ y)
    sigma2 = ((y - x @ beta) ** 2).sum() / (len(y) - 2)
    mean, cov, draw = posterior(C.compress_stats(cross, SPEC), 0.5, seed=3)
    precision = x.T @ x + 0.5 * np.eye(2)
    assert np.allclose(mean, np.linalg.solve(precision, x.T @ y)) and np.allclose(precision @ cov, sigma2 * np.eye(2)) and len(draw) == 2


def test_table_function_in_sql(spark, cross):
    udx.register_all(spark)
    C.compress_stats(cross.selectExpr("x", "y", "x * 2 as z"), ModelSpec("y", (num("x"), num("z")))).df.createOrReplaceTempView("_frame")
    fit = lambda right, cov: spark.sql(f"SELECT * FROM fit_linear(TABLE(_frame) WITH SINGLE PARTITION, 'y ~ {right}', '{cov}')").collect()
    for cov in ("homoskedastic", "ehw"):
        want = fit_compressed(C.compress_stats(cross, SPEC), cov)
        got = {r.term: (r.coef, r.se) for r in fit("x", cov)}
        assert np.allclose([got[t] for t in ("(intercept)", "x")], np.column_stack([want.coef[:, 0], np.sqrt(np.diag(want.cov[0]))]))
    with pytest.raises(Exception, match="aliased"):
        fit("x + z", "ehw")


def test_cells_of_more_levels_than_the_driver_takes(spark, tmp_path):
    """12,000 parts: cell means and robust errors by hand; nulls are a level; the long form gives the same where it can."""
    from lincompress.studies import QUERIES

    n = 12_000
    rows = spark.range(3 * n).selectExpr("id % 12000 as l_partkey", "cast(id % 12000 % 7 + 2 * floor(id / 12000) as double) as l_quantity")
    rows.unionAll(spark.sql("SELECT cast(null as bigint), cast(5 as double)")).write.parquet(str(tmp_path / "lineitem.parquet"))
    got = {r.part: (r.fitted, r.se) for r in QUERIES["wide_sparse_fit"](spark, str(tmp_path)).collect()}
    assert len(got) == n + 1 and got[None] == (5.0, 0.0)
    assert all(got[p] == (p % 7 + 2.0, round(8**0.5 / 3, 6)) for p in range(n))
    few = spark.createDataFrame([(p, float(y)) for p, y in ((1, 2), (1, 5), (2, 1), (2, 1), (3, 4), (3, 9), (3, 0))], "part long, qty double")
    spec = ModelSpec("qty", (cat("part", ref="none"),), intercept=False)
    long = fit_compressed(C.compress_stats(few, resolve(few, spec)), "ehw", method="long")
    for frame in (C.compress_stats(few, spec), C.compress_frequency(few, spec), C.compress_stats(few, spec, centred=True)):
        cells = fit_cells(frame).orderBy("level").collect()
        assert np.allclose([r.coef_qty for r in cells], long.coef[:, 0]) and np.allclose([r.se_qty for r in cells], long.se())
    with pytest.raises(ValueError, match="one set of dummies"):
        fit_cells(C.compress_stats(few, ModelSpec("qty", (cat("part", levels=(1, 2, 3)),))))


def test_generated_panel_is_that_of_the_given_customers(spark, tmp_path):
    from lincompress.relops import QUERIES

    spark.createDataFrame([(1, 4, 2.5), (3, 1, -1.5), (2, 5, 0.0)], "c_custkey long, c_nationkey int, c_acctbal double").write.parquet(str(tmp_path / "customer.parquet"))
    got = QUERIES["io_generator"](spark, str(tmp_path))
    assert got.inputFiles() and sorted(map(tuple, got.where("t in (0, 19)").collect())) == [(0, 2, 0, 1, 0.0, 0.0), (0, 2, 19, 1, 19.0, 361.0), (1, 1, 0, 2, 2.0, 10.0), (1, 1, 19, 2, 40.0, 808.0)]
    assert got.count() == 40


def test_memory_is_that_of_the_given_panel(spark, tmp_path):
    from lincompress.workloads import QUERIES

    spark.sql("SELECT * FROM VALUES (1, timestamp_ntz'2024-01-01 00:00:00'), (1, timestamp_ntz'2024-01-01 23:00:00'), (2, timestamp_ntz'2024-01-03 01:00:00'), (7, timestamp_ntz'2024-01-03 02:00:00') AS e(user_id, ts)").write.parquet(str(tmp_path / "events.parquet"))
    assert {r.layout: r.bytes for r in QUERIES["measure_memory"](spark, str(tmp_path)).collect()} == {"rows": 3 * 2 * 10 * 4, "units": 3 * 10 * 4}


def test_recursion_starts_from_the_given_line_items(spark, tmp_path):
    from lincompress.relops import QUERIES

    spark.createDataFrame([("A", "F", 1.0), ("A", "F", 4.0), ("N", "O", 3.0), ("N", "O", 9.0)], "l_returnflag string, l_linestatus string, l_quantity double").write.parquet(str(tmp_path / "lineitem.parquet"))
    got = {(r.flag, r.status, r.k): r.v for r in QUERIES["op_recursive"](spark, str(tmp_path)).collect()}
    assert len(got) == 16 and [got["A", "F", k] for k in (1, 2, 3)] == [1.0, 1.625, round((1.625 + 2.25 / 1.625) / 2, 9)]
    assert got["A", "F", 8] == 1.5 and got["N", "O", 8] == 3.0
