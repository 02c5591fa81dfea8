"""How often raw rows are read, counted where they are made."""

import numpy as np
import pytest

from lincompress.operators import compress as C, gram
from lincompress.operators.fit import fit_compressed, fit_linear
from lincompress.operators.glm import fit_logistic
from lincompress.plans.design import ModelSpec, inter, num

SPEC = ModelSpec("y", (num("arm"), num("t"), inter(num("arm"), num("t"))), cluster="unit", time="t")
N = 400


@pytest.fixture
def counted(spark):
    seen = spark.sparkContext.accumulator(0)

    def watch(batches):
        for b in batches:
            seen.add(b.num_rows)
            yield b

    rows = spark.range(N).selectExpr("id % 40 as unit", "cast(id % 40 % 2 as int) as arm", "cast(id div 40 as int) as t", "cast((id * 37) % 11 as double) as y", "cast((id * 53) % 7 as double) as z", "cast((id * 31) % 3 > 0 as int) as b")
    return rows.mapInArrow(watch, rows.schema), seen


@pytest.mark.parametrize("kind,cov", [("stats", "ehw"), ("frequency", "ehw"), ("within", "cluster"), ("cluster_moments", "cluster"), ("static", "cluster"), ("balanced", "cluster"), ("between", "cluster"), ("stats", "homoskedastic")])
@pytest.mark.parametrize("ys", [("y",), ("y", "z")])
@pytest.mark.parametrize("local", [True, False])
def test_one_pass(counted, kind, cov, ys, local, monkeypatch):
    df, seen = counted
    if kind == "frequency" and len(ys) > 1:
        pytest.skip("a frame of one outcome")
    if not local:
        monkeypatch.setattr(gram.local_rows, "__defaults__", (None, 0))
    spec = ModelSpec(ys, SPEC.terms, cluster="unit", time="t")
    fit = fit_linear(df, spec, kind, cov)
    assert seen.value == N
    base = fit_linear(df, spec, "none", cov)
    assert np.allclose(fit.coef, base.coef, rtol=1e-9) and all(np.allclose(a, b, rtol=1e-8) for a, b in zip(fit.cov, base.cov, strict=True))


def test_planned_fit(counted):
    df, seen = counted
    fit_linear(df, SPEC, "auto", "ehw")
    assert seen.value == 2 * N
    fit_linear(df, SPEC, "auto", "cluster")
    assert seen.value == 5 * N


def test_iterations_read_no_raw_rows(counted, monkeypatch):
    df, seen = counted
    spec = ModelSpec("b", (num("arm"), num("t")), cluster="unit")
    a = fit_logistic(C.compress_binary(df, spec, cluster=True), sandwich="cluster")
    assert seen.value == N and a.iterations > 2
    monkeypatch.setattr(gram.local_rows, "__defaults__", (None, 0))
    b = fit_logistic(C.compress_binary(df, spec, cluster=True), sandwich="cluster")
    assert seen.value == 2 * N and np.allclose(a.cov, b.cov, rtol=1e-8) and np.allclose(a.coef, b.coef, rtol=1e-8)


def test_many_equal_rows(spark):
    cf = C.compress_frequency(spark.createDataFrame([(1.0, 2.0)] * 7 + [(3.0, 4.0)], "x double, y double"), ModelSpec("y", (num("x"),)))
    assert sorted(map(tuple, C.expand_frequency(cf, block=3).collect())) == [(1.0, 2.0)] * 7 + [(3.0, 4.0)]


def test_static_roles_see_nulls(spark):
    rows = [(u, t, None if u == 1 and t == 0 else 5.0, float(t + u)) for u in range(4) for t in range(3)]
    df = spark.createDataFrame(rows, "unit int, t int, x double, y double")
    cf = C.compress_static(df, ModelSpec("y", (num("x"),), cluster="unit"), nulls="level")
    assert cf.extra["roles"]["x"] == "dynamic"
    cf.release()


def test_large_offsets_keep_variances(spark):
    from lincompress.operators.explore import feature_corr, feature_summary
    from lincompress.operators.fit import mean_variance

    rng = np.random.default_rng(0)
    x = 1e8 + rng.integers(0, 9, 500)
    y = 3 * x + rng.integers(0, 5, 500)
    df = spark.createDataFrame([(float(a), float(b)) for a, b in zip(x, y, strict=True)], "x double, y double")
    cf = C.compress_stats(df, ModelSpec("y", (num("x"),)), centred=True).cache()
    assert np.isclose(feature_summary(cf, ["x"]).first().variance, np.var(x, ddof=1), rtol=1e-9)
    assert np.isclose(mean_variance(cf).first().variance, np.var(y, ddof=1), rtol=1e-9)
    both = C.compress_stats(df, ModelSpec("y", (num("x"), num("y")))).cache()
    assert np.isclose(feature_corr(both, "x", "y").first()["corr"], np.corrcoef(x, y)[0, 1], rtol=1e-9)
