"""What the compressed fits are compared with: row-level fits, lossy group means, gradient descent, adjusted means."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lincompress.operators import compress as C
from lincompress.operators.compress import CompressedFrame
from lincompress.operators.fit import FitResult, fit_compressed
from lincompress.operators.glm import GlmResult, fit_logistic
from lincompress.operators.gram import stats_view
from lincompress.plans.design import ModelSpec, resolve


def ols_rows(df: DataFrame, spec: ModelSpec, cov: str = "homoskedastic", **options) -> FitResult:
    return fit_compressed(C.uncompressed(df, resolve(df, spec)), cov, **options)


def wls_frequency(df: DataFrame, spec: ModelSpec, outcome: str | None = None, cov: str = "homoskedastic") -> FitResult:
    return fit_compressed(C.compress_frequency(df, resolve(df, spec), outcome), cov)


def wls_means(df: DataFrame, spec: ModelSpec) -> FitResult:
    """Regression of group means weighted by counts: coefficients of the rows, but residual variance between groups only (over G - p)."""
    return fit_compressed(C.compress_means(df, resolve(df, spec)))


def logistic_rows(df: DataFrame, spec: ModelSpec, **options) -> GlmResult:
    return fit_logistic(C.uncompressed(df, resolve(df, spec)), **options)


def mllib_linear(df: DataFrame, spec: ModelSpec):
    """Spark's own normal-equation solver on rows (or on compressed rows, weighted)."""
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.regression import LinearRegression

    names, rows = _vectors(C.uncompressed(df, resolve(df, spec)))
    features = VectorAssembler(inputCols=names, outputCol="features").transform(rows)
    return LinearRegression(solver="normal", regParam=0.0, labelCol="y", weightCol="w", standardization=False).fit(features)


def mllib_logistic(df: DataFrame, spec: ModelSpec):
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import VectorAssembler

    names, rows = _vectors(C.uncompressed(df, resolve(df, spec)))
    features = VectorAssembler(inputCols=names, outputCol="features").transform(rows)
    return LogisticRegression(regParam=0.0, labelCol="y", weightCol="w", tol=1e-12, maxIter=200).fit(features)


def _vectors(cf: CompressedFrame) -> tuple[list[str], DataFrame]:
    x = [(n, c) for n, c in cf.spec.design() if n != "(intercept)"]
    names = [f"x{i}" for i in range(len(x))]
    return names, stats_view(cf).select(*[c.alias(n) for n, (_, c) in zip(names, x, strict=True)], (F.col("_s0") / F.col("_w")).alias("y"), F.col("_w").alias("w"))


def sgd_linear(data: DataFrame | CompressedFrame, spec: ModelSpec | None = None, epochs: int = 20, batch: int = 512, rate: float = 0.3, seed: int = 0) -> tuple[np.ndarray, list[float]]:
    """Mini-batch gradient descent, averaged over partitions after each epoch; on compressed rows the weights take the place of repeats.

    Features are standardised by one aggregate. Returns coefficients and the largest gap to the last epoch's, by epoch.
    """
    cf = data if isinstance(data, CompressedFrame) else C.uncompressed(data, resolve(data, spec))
    x = [(n, c) for n, c in cf.spec.design()]
    view = stats_view(cf).select(F.array(*[c for _, c in x]).alias("x"), F.col("_w"), F.col("_s0")).persist()
    p, w = len(x), F.sum("_w")
    first = view.agg(*[(F.sum(F.get("x", i) * F.col("_w")) / w).alias(f"m{i}") for i in range(p)], *[(F.sum(F.pow(F.get("x", i), F.lit(2)) * F.col("_w")) / w).alias(f"v{i}") for i in range(p)]).first()
    mean = np.array([first[f"m{i}"] for i in range(p)])
    scale = np.sqrt(np.maximum(np.array([first[f"v{i}"] for i in range(p)]) - mean**2, 0))
    const = scale == 0
    mean[const], scale[const] = 0, 1
    beta, gaps = np.zeros(p), []
    for epoch in range(epochs):
        start, step = beta.copy(), rate / (1 + 0.5 * epoch)

        def each(batches: Iterator[pa.RecordBatch], start=start, step=step, epoch=epoch) -> Iterator[pa.RecordBatch]:
            b, seen, order = start.copy(), 0.0, np.random.default_rng(seed + epoch)
            for rows in batches:
                xs = (np.asarray(rows.column(0).flatten(), float).reshape(rows.num_rows, p) - mean) / scale
                ws, ss = np.asarray(rows.column(1), float), np.asarray(rows.column(2), float)
                pick = order.permutation(len(ws))
                for k in range(0, len(pick), batch):
                    i = pick[k : k + batch]
                    b += step * xs[i].T @ (ss[i] - ws[i] * (xs[i] @ b)) / ws[i].sum()
                seen += ws.sum()
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(p + 1, dtype=np.int32)), pa.array(np.r_[b * seen, seen])], names=["i", "v"])

        got = {r.i: r.v for r in view.mapInArrow(each, "i int, v double").groupBy("i").agg(F.sum("v").alias("v")).collect()}
        beta = np.array([got[i] / got[p] for i in range(p)])
        gaps.append(float(np.abs(beta - start).max()))
    view.unpersist()
    out = beta / scale
    if const.any():
        out[np.flatnonzero(const)[0]] -= (beta / scale * mean).sum()
    return out, gaps


def diff_means(df: DataFrame, y: str, arm: str) -> DataFrame:
    """Difference of arm means (arm 0/1) with its unpooled standard error."""
    a = F.col(arm)
    t, c = F.avg(F.when(a == 1, F.col(y))), F.avg(F.when(a == 0, F.col(y)))
    vt, vc = F.var_samp(F.when(a == 1, F.col(y))), F.var_samp(F.when(a == 0, F.col(y)))
    return df.agg((t - c).alias("effect"), F.sqrt(vt / F.count_if(a == 1) + vc / F.count_if(a == 0)).alias("se"))


def cuped(df: DataFrame, y: str, pre: str, arm: str) -> DataFrame:
    """Difference of arm means after removing what the pre-period value explains (theta from all rows)."""
    moments = df.agg((F.covar_samp(pre, y) / F.var_samp(pre)).alias("_theta"), F.avg(pre).alias("_pre"))
    adjusted = df.crossJoin(F.broadcast(moments)).withColumn("_y", F.col(y) - F.col("_theta") * (F.col(pre) - F.col("_pre")))
    return diff_means(adjusted, "_y", arm).crossJoin(moments.select(F.col("_theta").alias("theta")))


def builtin_regression(df: DataFrame, y: str, x: str) -> DataFrame:
    return df.agg(*[getattr(F, f"regr_{f}")(y, x).alias(f) for f in ("slope", "intercept", "r2", "sxx", "sxy", "syy")], F.regr_count(y, x).alias("n"))
