"""Logistic and Poisson regression on compressed counts and sums; every iteration reads the compressed rows only.

A small frame (``gram.LOCAL`` numbers, checked) goes to the driver once and is iterated there; a larger one is persisted, and an iteration is one
aggregate over it.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lincompress.operators.compress import CompressedFrame
from lincompress.operators.fit import linear
from lincompress.operators.gram import local_rows, stats_view, sums
from lincompress.operators.solve import inverse_spd


@dataclass
class GlmResult:
    names: list[str]
    coef: np.ndarray
    cov: np.ndarray
    loglik: float
    iterations: int
    n: float
    records: int

    def se(self) -> np.ndarray:
        return np.sqrt(np.diag(self.cov))

    def coefficients(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(n, float(b), float(s)) for n, b, s in zip(self.names, self.coef, self.se(), strict=True)], "term string, coef double, se double")


class Separated(ValueError):
    """A combination of features tells the outcome for certain; the likelihood has no maximum."""


def _mean(eta, family: str):
    if family == "poisson":
        return F.exp(F.least(eta, F.lit(700.0)))
    return F.lit(1.0) / (F.lit(1.0) + F.exp(-F.greatest(F.least(eta, F.lit(700.0)), F.lit(-700.0))))


def loglik_grad(cf: CompressedFrame, beta: np.ndarray, family: str = "logistic", view: DataFrame | None = None) -> tuple[float, np.ndarray, np.ndarray, float, int]:
    """Log-likelihood (without terms free of coefficients), gradient, information, rows and records; one aggregate."""
    view = stats_view(cf) if view is None else view
    x = [c for _, c in cf.spec.design()]
    held = view.withColumn("_eta", linear(beta, x)).withColumn("_mu", _mean(F.col("_eta"), family))
    w, s, eta, mu = F.col("_w"), F.col("_s0"), F.col("_eta"), F.col("_mu")
    # log(1 + e^eta) without overflow
    cumulant = mu if family == "poisson" else F.greatest(eta, F.lit(0.0)) + F.log1p(F.exp(-F.abs(eta)))
    spread = w * mu if family == "poisson" else w * mu * (F.lit(1.0) - mu)
    (info,), grad, flat = sums(held, x, [spread], [s - w * mu], [s * eta - w * cumulant, w, F.lit(1.0)])
    return float(flat[0]), grad[:, 0], info, float(flat[1]), int(flat[2])


class _Local:
    """The same sums from records that the driver holds."""

    def __init__(self, x: np.ndarray, values: np.ndarray, codes: np.ndarray | None):
        self.x, (self.w, self.s, self.q), self.codes = x, values.T, codes

    def mean(self, beta: np.ndarray, family: str) -> tuple[np.ndarray, np.ndarray]:
        eta = self.x @ beta
        return eta, np.exp(np.minimum(eta, 700)) if family == "poisson" else 1 / (1 + np.exp(-np.clip(eta, -700, 700)))

    def loglik_grad(self, beta: np.ndarray, family: str) -> tuple[float, np.ndarray, np.ndarray, float, int]:
        eta, mu = self.mean(beta, family)
        cumulant = mu if family == "poisson" else np.maximum(eta, 0) + np.log1p(np.exp(-np.abs(eta)))
        spread = self.w * mu * (1 if family == "poisson" else 1 - mu)
        return float((self.s * eta - self.w * cumulant).sum()), self.x.T @ (self.s - self.w * mu), (self.x * spread[:, None]).T @ self.x, float(self.w.sum()), len(self.w)

    def meat(self, beta: np.ndarray, family: str, sandwich: str) -> np.ndarray:
        mu = self.mean(beta, family)[1]
        if sandwich == "ehw":
            return (self.x * (self.q - 2 * mu * self.s + self.w * mu * mu)[:, None]).T @ self.x
        u = np.array([np.bincount(self.codes, c * (self.s - self.w * mu)) for c in self.x.T])
        return u @ u.T


def fit_glm(cf: CompressedFrame, family: str = "logistic", tol: float = 1e-10, max_iter: int = 50, solver: str = "newton", sandwich: str | None = None) -> GlmResult:
    """solver newton (with halved steps where the likelihood falls) or gradient (preconditioned by the first information); sandwich: ehw or cluster."""
    names = [n for n, _ in cf.spec.design()]
    view = stats_view(cf).persist()
    by = cf.spec.cluster if sandwich == "cluster" else None
    try:
        table = local_rows(view, [c for _, c in cf.spec.design()], [F.col("_w"), F.col("_s0"), F.col("_q0")], by) if cf.kind != "none" else None
        held = _Local(*table) if table else None
        look = (lambda b: held.loglik_grad(b, family)) if held else (lambda b: loglik_grad(cf, b, family, view))
        beta, first = np.zeros(len(names)), None
        value, grad, info, n, records = look(beta)
        for turn in range(1, max_iter * (20 if solver == "gradient" else 1) + 1):
            if first is None or solver == "newton":
                first = inverse_spd(info)
            step = first @ grad
            for _ in range(30):
                trial = look(beta + step)
                if trial[0] >= value - 1e-12 * abs(value):
                    break
                step /= 2
            beta, before = beta + step, value
            value, grad, info, *_ = trial
            if family == "logistic" and (np.abs(beta).max() > 30 or np.diag(info).min() < 1e-9 * n):
                raise Separated("coefficients grow without bound")
            if abs(value - before) <= tol * (abs(value) + tol) and np.abs(grad).max() <= 1e-6 * max(1.0, n):
                break
        bread = inverse_spd(info)
        cov = bread
        if sandwich:
            cov = bread @ (held.meat(beta, family, sandwich) if held else _meat(cf, view, beta, family, sandwich)) @ bread
        return GlmResult(names, beta, cov, value, turn, n, records)
    finally:
        view.unpersist()


def _meat(cf: CompressedFrame, view: DataFrame, beta: np.ndarray, family: str, sandwich: str) -> np.ndarray:
    x = [c for _, c in cf.spec.design()]
    held = view.withColumn("_mu", _mean(linear(beta, x), family))
    w, s, q, mu = F.col("_w"), F.col("_s0"), F.col("_q0"), F.col("_mu")
    if sandwich == "ehw":
        return sums(held, x, [q - 2 * mu * s + w * mu * mu])[0][0]
    per = held.groupBy(f"`{cf.spec.cluster}`").agg(*[F.sum(c * (s - w * mu)).alias(f"_u{i}") for i, c in enumerate(x)])
    return sums(per, [F.col(f"_u{i}") for i in range(len(x))], [F.lit(1.0)])[0][0]


def fit_logistic(cf: CompressedFrame, **options) -> GlmResult:
    return fit_glm(cf, "logistic", **options)


def logit(p: float) -> float:
    return math.log(p / (1 - p))
