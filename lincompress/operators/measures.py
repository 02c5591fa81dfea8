"""Cost and accuracy measures."""

from __future__ import annotations

import math
import time

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lincompress.operators import compress as C
from lincompress.operators.baselines import ols_rows
from lincompress.operators.compress import CompressedFrame
from lincompress.operators.fit import COMPRESSIONS, FitResult, fit_compressed
from lincompress.plans.design import ModelSpec
from lincompress.plans.planner import break_even


def ratio(df: DataFrame, spec: ModelSpec, kinds: list[str]) -> list[tuple[str, int, int]]:
    """(kind, raw rows, records)."""
    n = df.count()
    return [(k, n, COMPRESSIONS[k](df, spec).df.count()) for k in kinds]


def parity(a: FitResult, b: FitResult) -> dict[str, float]:
    """Largest absolute and relative gaps of coefficients and covariances."""
    gap = lambda x, y: float(np.abs(x - y).max())
    rel = lambda x, y: float((np.abs(x - y) / np.maximum(np.abs(y), 1e-300)).max())
    va, vb = np.array([np.diag(v) for v in a.cov]), np.array([np.diag(v) for v in b.cov])
    return {"coef_gap": gap(a.coef, b.coef), "coef_rel": rel(a.coef, b.coef), "var_gap": gap(va, vb), "var_rel": rel(va, vb)}


def strategy_table(df: DataFrame, spec: ModelSpec, kinds: list[str], cov: str = "homoskedastic") -> list[tuple]:
    """(kind, rows, records, coefficient gap, variance gap, passes for all outcomes) against the row-level fit."""
    base, n, out = ols_rows(df, spec, cov), df.count(), []
    for kind in kinds:
        if kind == "frequency" and len(spec.outcomes) > 1:
            fits = [fit_compressed(C.compress_frequency(df, spec, y), cov) for y in spec.outcomes]
            gaps = [parity(f, FitResult(base.names, (y,), base.coef[:, [k]], [base.cov[k]], base.n, base.records, base.df, base.rss[[k]], base.r2[[k]], base.kind, cov, base.bread)) for k, (y, f) in enumerate(zip(spec.outcomes, fits, strict=True))]
            out.append((kind, n, sum(f.records for f in fits), max(g["coef_rel"] for g in gaps), max(g["var_rel"] for g in gaps), len(fits)))
        else:
            fit = fit_compressed(COMPRESSIONS[kind](df, spec), cov)
            g = parity(fit, base)
            out.append((kind, n, fit.records, g["coef_rel"], g["var_rel"], 0 if kind == "none" else 1))
    return out


def model_bytes(rows: int, columns: int, width: int = 4) -> int:
    """Memory of a dense table of floats."""
    return rows * columns * width


def frame_bytes(cf: CompressedFrame) -> int:
    """What Spark's cache holds for the frame."""
    df = cf.df.persist()
    try:
        df.count()
        return int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    finally:
        df.unpersist()


def stored_numbers(groups: int, clusters: int, periods: int) -> dict[str, float]:
    """Between-cluster storage against a row for each cluster and period, and the largest number of groups that pays."""
    return {"between": groups * periods + groups * (periods * periods + periods), "rows": clusters * periods, "most_groups": break_even(clusters, periods)}


def timed(f, repeats: int = 3) -> float:
    """Median seconds after one warm-up."""
    f()
    took = []
    for _ in range(repeats):
        t = time.perf_counter()
        f()
        took.append(time.perf_counter() - t)
    return sorted(took)[len(took) // 2]


def split_times(df: DataFrame, spec: ModelSpec, kind: str, cov: str) -> dict[str, float]:
    """Seconds to compress (into the cache) and to fit from the cache."""
    t = time.perf_counter()
    cf = COMPRESSIONS[kind](df, spec).cache()
    records = cf.df.count()
    mid = time.perf_counter()
    fit_compressed(cf, cov)
    end = time.perf_counter()
    cf.df.unpersist()
    return {"records": records, "compress_s": mid - t, "fit_s": end - mid}


def minimum_detectable(se: float, alpha: float = 0.05, power: float = 0.8) -> float:
    """Smallest effect found with the given power by a two-sided normal test."""
    from lincompress.functions.tails import norm_cdf

    def quantile(p: float) -> float:
        lo, hi = -10.0, 10.0
        for _ in range(100):
            mid = (lo + hi) / 2
            lo, hi = (mid, hi) if norm_cdf(mid) < p else (lo, mid)
        return lo

    return se * (quantile(1 - alpha / 2) + quantile(power))


def coverage(df: DataFrame, spec: ModelSpec, arm: str, tau: float, seeds: range, cov: str = "homoskedastic", kind: str = "stats") -> dict[str, float]:
    """Repeated hash-seeded assignment of arms by cluster (or row id column ``unit``): bias, interval coverage, and how often an effect of zero is rejected when tau is 0."""
    unit = spec.cluster or "unit"
    y = spec.outcomes[0]
    inside, errors = 0, []
    for seed in seeds:
        rows = df.withColumn(arm, F.pmod(F.xxhash64(F.col(unit), F.lit(seed)), F.lit(2)).cast("int"))
        rows = rows.withColumn(y, F.col(y) + tau * F.col(arm))
        fit = fit_compressed(COMPRESSIONS[kind](rows, spec), cov)
        i = fit.names.index(arm)
        errors.append(fit.coef[i, 0] - tau)
        inside += abs(errors[-1]) <= 1.959963984540054 * fit.se()[i]
    share = float(inside) / len(seeds)
    return {"bias": float(np.mean(errors)), "sd": float(np.std(errors)), "coverage": share, "rejected": 1 - share}


def slope(points: list[tuple[float, float]]) -> float:
    """Log-log slope of time against size."""
    x, y = np.log([p[0] for p in points]), np.log([p[1] for p in points])
    return float(((x - x.mean()) * (y - y.mean())).sum() / ((x - x.mean()) ** 2).sum()) if len(points) > 1 else math.nan
