"""Linear fits from raw rows or compressed frames, with homoskedastic, heteroskedasticity-consistent and cluster covariances.

A compressed frame is computed once: a small one (``gram.LOCAL`` numbers, checked) goes to the driver and is fitted there, a larger one is
persisted, scanned for the coefficients and again for what depends on them (residual sums by group, and the scores of
clusters), for all outcomes together. Of larger frames only sums of model size reach the driver. Raw rows (kind none) are scanned twice.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from lincompress.functions.tails import f_sf, t_quantile, t_sf
from lincompress.operators import compress as C
from lincompress.operators.compress import CompressedFrame, packed, split_design
from lincompress.operators.gram import local_rows, sparse_entries, sparse_sums, stats_view, sums, total
from lincompress.operators.solve import inverse_spd
from lincompress.plans.design import ModelSpec, resolve

ROWS = ("none", "frequency", "means", "stats", "binary", "weighted", "within")


@dataclass
class FitResult:
    names: list[str]
    outcomes: tuple[str, ...]
    coef: np.ndarray  # p by outcomes
    cov: list[np.ndarray]
    n: float
    records: int
    df: float
    rss: np.ndarray
    r2: np.ndarray
    kind: str
    estimator: str
    bread: np.ndarray
    clusters: int | None = None

    def se(self, k: int = 0) -> np.ndarray:
        return np.sqrt(np.maximum(np.diag(self.cov[k]), 0))

    def rows(self, level: float = 0.95) -> list[tuple]:
        q = t_quantile(0.5 + level / 2, self.df) if self.df > 0 else math.nan
        out = []
        for k, y in enumerate(self.outcomes):
            for name, b, s in zip(self.names, self.coef[:, k], self.se(k), strict=True):
                t = b / s if s > 0 else math.nan
                out.append((y, name, float(b), float(s), float(t), 2 * t_sf(abs(t), self.df) if s > 0 else math.nan, float(b - q * s), float(b + q * s)))
        return out

    def coefficients(self, spark: SparkSession, level: float = 0.95) -> DataFrame:
        return spark.createDataFrame(self.rows(level), "outcome string, term string, coef double, se double, t double, p double, lo double, hi double")

    def covariance(self, spark: SparkSession) -> DataFrame:
        rows = [(y, a, b, float(self.cov[k][i, j])) for k, y in enumerate(self.outcomes) for i, a in enumerate(self.names) for j, b in enumerate(self.names)]
        return spark.createDataFrame(rows, "outcome string, a string, b string, v double")

    def summary(self, spark: SparkSession) -> DataFrame:
        rows = [(y, float(self.n), int(self.records), float(self.df), float(self.rss[k]), float(self.rss[k] / self.df) if self.df > 0 else None, float(self.r2[k]), self.kind, self.estimator) for k, y in enumerate(self.outcomes)]
        return spark.createDataFrame(rows, "outcome string, n double, records long, df double, rss double, sigma2 double, r2 double, kind string, estimator string")


def linear(coef: np.ndarray, x: list[Column]) -> Column:
    """The fitted value as an expression with literal coefficients; one array expression when there are many."""
    pairs = [(float(b), c) for b, c in zip(coef, x, strict=True) if b]
    if not pairs:
        return F.lit(0.0)
    if len(pairs) > 12:  # deep sums take the optimizer long
        return F.aggregate(F.zip_with(F.array(*[F.lit(b) for b, _ in pairs]), F.array(*[c for _, c in pairs]), lambda a, b: a * b), F.lit(0.0), lambda a, b: a + b)
    out = pairs[0][1] * pairs[0][0]
    for b, c in pairs[1:]:
        out = out + c * b
    return out


def _df(spec: ModelSpec, n: float, weight: float, p: int) -> float:
    """Frequency weights stand for rows; other weights count the rows that carry them."""
    return (weight if spec.weight_kind == "frequency" else n) - p


def fit_compressed(cf: CompressedFrame, cov: str = "homoskedastic", spec: ModelSpec | None = None, small_sample: str | None = None, on_alias: str = "error", method: str = "auto", cluster: str | None = None) -> FitResult:
    """Fit from a compressed frame alone. cov: homoskedastic, ehw or cluster; small_sample: HC1, HC2, HC3 or CR1; cluster names a coarser key column than the model's cluster."""
    if spec is not None:
        extra = set(spec.keys) - set(cf.keys)
        if extra:
            raise ValueError(f"not in the frame: {sorted(extra)}")
        cf = replace(cf, spec=spec)
    if cf.kind == "none":
        return _fit_rows(cf, cov, small_sample, on_alias, method, cluster)
    level = cf.df.storageLevel
    keep = not (level.useMemory or level.useDisk)
    if keep:
        cf = replace(cf, df=cf.df.persist())
    try:
        if cf.kind == "between":
            return _fit_between(cf, cov, on_alias) if cov == "cluster" else _fit_rows(between_rows(cf), cov, small_sample, on_alias, method, None)
        if cf.kind == "balanced" and cov == "ehw":
            return _fit_rows(balanced_rows(cf), cov, small_sample, on_alias, method, None)
        if cf.kind not in ROWS:
            return _fit_blocks(cf, cov, on_alias, small_sample)
        return _fit_rows(cf, cov, small_sample, on_alias, method, cluster)
    finally:
        if keep:
            cf.df.unpersist()


class _Local:
    """Sums of a frame that the driver holds."""

    def __init__(self, names: list[str], x: np.ndarray, values: np.ndarray, codes: np.ndarray | None):
        self.x, self.v, self.codes = x, dict(zip(names, values.T, strict=True)), codes

    def first(self, o: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        w = self.v["_w"]
        s, q = (np.array([self.v[f"{c}{k}"] for k in range(o)]) for c in ("_s", "_q"))
        return (self.x * w[:, None]).T @ self.x, self.x.T @ s.T, np.r_[w.sum(), self.v["_n"].sum(), len(w), q.sum(axis=1), s.sum(axis=1)]

    def second(self, coef: np.ndarray, cov: str, squared: bool, lever: np.ndarray | None, power: int) -> tuple[np.ndarray, list[np.ndarray], int | None]:
        w, rss, meats, clusters = self.v["_w"], [], [], None
        for k, beta in enumerate(coef.T):
            f, s = self.x @ beta, self.v[f"_s{k}"]
            if f"_c{k}" in self.v:
                r = self.v[f"_c{k}"] + w * (np.divide(s, w, out=np.zeros_like(s), where=w > 0) - f) ** 2
            else:
                r = w * f * f - 2 * f * s + self.v[f"_q{k}"]
            rss.append(max(r.sum(), 0.0))
            if cov == "ehw":
                e = self.v["_w2"] * f * f - 2 * f * self.v[f"_t{k}"] + self.v[f"_r{k}"] if squared else r
                if lever is not None:
                    e = e / (1 - np.einsum("ij,ij->i", self.x @ lever, self.x)) ** power
                meats.append((self.x * e[:, None]).T @ self.x)
            elif cov == "cluster":
                clusters = int(self.codes.max()) + 1 if len(self.codes) else 0
                u = np.array([np.bincount(self.codes, c * (s - w * f), clusters) for c in self.x.T])
                meats.append(u @ u.T)
        return np.array(rss), meats, clusters


class _Spread:
    """The same sums of a frame that stays on the cluster: one job for each call, whatever the number of outcomes."""

    def __init__(self, view: DataFrame, x: list[Column], by: str | None, method: str):
        self.view, self.x, self.by, self.method = view, x, by, method

    def first(self, o: int):
        s, q = ([F.col(f"{c}{k}") for k in range(o)] for c in ("_s", "_q"))
        (gram,), xy, flat = sums(self.view, self.x, [F.col("_w")], s, [F.col("_w"), F.col("_n"), F.lit(1.0), *q, *s], self.method)
        return gram, xy, flat

    def second(self, coef, cov, squared, lever, power):
        x, p, o, w = self.x, len(self.x), coef.shape[1], F.col("_w")
        held = self.view.withColumns({f"_f{k}": linear(coef[:, k], x) for k in range(o)})
        rs, es, scores = [], [], []
        for k in range(o):
            f, s = F.col(f"_f{k}"), F.col(f"_s{k}")
            if f"_c{k}" in held.columns:
                rs.append(F.col(f"_c{k}") + w * F.pow(F.try_divide(s, w) - f, F.lit(2)))
            else:
                rs.append(w * f * f - 2 * f * s + F.col(f"_q{k}"))
            es.append(F.col("_w2") * f * f - 2 * f * F.col(f"_t{k}") + F.col(f"_r{k}") if squared else rs[-1])
            scores.append(s - w * f)
        if cov == "homoskedastic":
            return np.maximum(total(held, rs), 0), [], None
        if cov == "ehw":
            if lever is not None:
                h = sum((x[i] * x[j] * float(lever[i, j]) for i in range(p) for j in range(p) if lever[i, j]), F.lit(0.0))
                es = [e / F.pow(F.lit(1.0) - h, F.lit(power)) for e in es]
            meats, _, flat = sums(held, x, es, (), rs, self.method)
            return np.maximum(flat, 0), meats, None
        per = held.groupBy(f"`{self.by}`").agg(*[F.sum(c * scores[k]).alias(f"_u{k}_{i}") for k in range(o) for i, c in enumerate(x)], *[F.sum(r).alias(f"_r{k}") for k, r in enumerate(rs)])
        (meat,), _, flat = sums(per, [F.col(f"_u{k}_{i}") for k in range(o) for i in range(p)], [F.lit(1.0)], (), [F.lit(1.0), *[F.col(f"_r{k}") for k in range(o)]], self.method)
        return np.maximum(flat[1:], 0), [meat[k * p : (k + 1) * p, k * p : (k + 1) * p] for k in range(o)], int(flat[0])


class _Long:
    """The same sums for thousands of mostly empty columns: work goes with non-zero entries, and only those of model size come back."""

    def __init__(self, view: DataFrame, spec: ModelSpec, p: int):
        self.view, self.p = view.withColumn("_x", sparse_entries(spec)), p

    def _dense(self, pairs: DataFrame, k: int) -> list[np.ndarray]:
        out = [np.zeros((self.p, self.p)) for _ in range(k)]
        t = pairs.toArrow()
        i, j = t["i"].to_numpy(), t["j"].to_numpy()
        for n, m in enumerate(out):
            m[i, j] = m[j, i] = t[f"v{n}"].to_numpy()
        return out

    def first(self, o: int):
        s, q = ([F.col(f"{c}{k}") for k in range(o)] for c in ("_s", "_q"))
        pairs, single = sparse_sums(self.view, [F.col("_w")], s)
        t, xy = single.toArrow(), np.zeros((self.p, o))
        for k in range(o):
            xy[t["i"].to_numpy(), k] = t[f"v{k}"].to_numpy()
        return self._dense(pairs, 1)[0], xy, total(self.view, [F.col("_w"), F.col("_n"), F.lit(1.0), *q, *s])

    def second(self, coef, cov, squared, lever, power):
        if cov == "cluster" or lever is not None or squared:
            raise ValueError("the long form gives homoskedastic and plain robust covariances")
        o, w = coef.shape[1], F.col("_w")
        fits = {}
        for k in range(o):
            b = F.lit([float(v) for v in coef[:, k]])
            fits[f"_f{k}"] = F.aggregate("_x", F.lit(0.0), lambda a, e: a + e["v"] * F.get(b, e["i"]))  # noqa: B023
        held = self.view.withColumns(fits)
        rs = [F.greatest(w * F.col(f"_f{k}") * F.col(f"_f{k}") - 2 * F.col(f"_f{k}") * F.col(f"_s{k}") + F.col(f"_q{k}"), F.lit(0.0)) for k in range(o)]
        meats = self._dense(sparse_sums(held, rs)[0], o) if cov == "ehw" else []
        return total(held, rs), meats, None


def fit_cells(cf: CompressedFrame) -> DataFrame:
    """A fit whose design is one set of dummies without intercept, of any number of levels, which stays on the cluster: level, coefficient and robust error of each outcome.

    It is the long form with entries named by their level: a row has one non-zero entry, so the Gram matrix and the middle of the
    covariance are diagonal, one sum by level each, and no level or matrix reaches the driver. Nulls are a level.
    """
    spec, view = cf.spec, stats_view(cf)
    if spec.intercept or len(spec.terms) != 1 or spec.terms[0].kind != "cat" or spec.terms[0].args[2] != "none":
        raise ValueError("the design is not one set of dummies with all its levels and no intercept")
    if "_w2" in view.columns:
        raise ValueError("cells have plain robust errors, without sampling weights")
    o, w = range(len(spec.outcomes)), F.col("_w")
    rows = view.withColumn("level", F.col(f"`{spec.terms[0].args[0]}`"))
    fits = rows.groupBy(F.col("level").alias("_level")).agg(F.sum(w).alias("_g"), *[F.try_divide(F.sum(f"_s{k}"), F.sum(w)).alias(f"_b{k}") for k in o])
    held = rows.join(fits, F.col("level").eqNullSafe(F.col("_level")))
    rs = []
    for k in o:
        b, s = F.col(f"_b{k}"), F.col(f"_s{k}")
        rs.append(F.col(f"_c{k}") + w * F.pow(F.try_divide(s, w) - b, F.lit(2)) if f"_c{k}" in view.columns else F.greatest(w * b * b - 2 * b * s + F.col(f"_q{k}"), F.lit(0.0)))
    out = held.groupBy("level").agg(F.first("_g").alias("_g"), *[F.first(f"_b{k}").alias(f"coef_{y}") for k, y in enumerate(spec.outcomes)], *[F.sum(r).alias(f"_r{k}") for k, r in enumerate(rs)])
    return out.select("level", *[c for k, y in enumerate(spec.outcomes) for c in (F.col(f"coef_{y}"), F.try_divide(F.sqrt(f"_r{k}"), F.col("_g")).alias(f"se_{y}"))])


def _fit_rows(cf, cov, small_sample, on_alias, method, cluster) -> FitResult:
    spec, view = cf.spec, stats_view(cf)
    names, x = [n for n, _ in spec.design()], [c for _, c in spec.design()]
    p, o = len(x), len(spec.outcomes)
    if cov not in ("homoskedastic", "ehw", "cluster"):
        raise ValueError(f"unknown covariance {cov}")
    by = (cluster or spec.cluster) if cov == "cluster" else None
    if cov == "cluster" and (not by or by not in view.columns):
        raise ValueError("the frame holds no cluster")
    if small_sample in ("HC2", "HC3") and spec.weight and spec.weight_kind != "frequency":
        raise ValueError("leverage differs within a group of unequal weights")
    values = [c for c in view.columns if c.startswith("_") and c not in spec.keys and c != spec.cluster]
    table = local_rows(view, x, [F.col(c) for c in values], by) if cf.kind != "none" and method == "auto" else None
    held = _Local(values, *table) if table else _Long(view, spec, p) if method == "long" else _Spread(view, x, by, method)
    gram, xy, flat = held.first(o)
    weight, n, records, yy, ys = flat[0], flat[1], int(flat[2]), flat[3 : 3 + o], flat[3 + o :]
    bread = inverse_spd(gram, on_alias)
    coef = bread @ xy
    coef += bread @ (xy - gram @ coef)
    df = _df(spec, n, weight, p) if cf.kind != "means" else records - p
    squared = "_w2" in values and spec.weight_kind != "frequency"
    rss, meats, clusters = held.second(coef, cov, squared, bread if small_sample in ("HC2", "HC3") else None, 1 if small_sample == "HC2" else 2)
    scale = 1.0
    if cov == "ehw" and small_sample == "HC1":
        scale = n / (n - p)
    elif cov == "cluster" and small_sample == "CR1":
        scale = clusters / (clusters - 1) * (n - 1) / (n - p)
    if cov == "homoskedastic":
        covs = [bread * r / df if df > 0 else bread * math.nan for r in rss]
    else:
        covs = [bread @ m @ bread * scale for m in meats]
    spread = yy - np.divide(ys**2, weight, out=np.zeros(o), where=np.full(o, weight > 0))
    r2 = 1 - np.divide(rss, spread, out=np.full(o, math.nan), where=spread > 0)
    return FitResult(names, spec.outcomes, coef, covs, weight if spec.weight_kind == "frequency" else n, records, df, rss, r2, cf.kind, cov, bread, clusters)


def _blocks(cf: CompressedFrame):
    """For frames of one row a cluster: the rows, and functions that give the cluster's Gram entry and cross-product as Columns."""
    spec = cf.spec
    if cf.kind == "cluster_moments":
        at = {ij: i for i, ij in enumerate(packed(len(spec.design())))}
        return cf.df, lambda i, j: F.get("xx", at[min(i, j), max(i, j)]), lambda i, y: F.get(f"xy_{y}", i), None
    statics, dynamics, places = split_design(spec, cf.extra["roles"])
    rows = cf.df.select("*", *[c.alias(f"_a{k}") for k, c in enumerate(statics)])
    a = [F.col(f"_a{k}") for k in range(len(statics))]
    d = len(dynamics) - 1
    at = {ij: i for i, ij in enumerate(packed(d))}
    if cf.kind == "balanced":
        grid = cf.extra["periods"].select(cf.spec.time, *[c.alias(f"_d{i}") for i, c in enumerate(dynamics)]).orderBy(cf.spec.time).collect()
        m = np.array([[float(r[f"_d{i}"]) for i in range(d + 1)] for r in grid])
        shared = m.T @ m
        for y in spec.outcomes:
            if cf.extra["keep_y"]:
                dots = [F.aggregate(F.zip_with(f"y_{y}", F.array(*[F.lit(float(v)) for v in m[:, i]]), lambda u, v: u * v), F.lit(0.0), lambda u, v: u + v) for i in range(1, d + 1)]
                rows = rows.withColumn(f"dy_{y}", F.array(*dots) if dots else F.array().cast("array<double>"))
        moment = lambda s, t: F.lit(float(shared[s, t]))
    else:
        shared = None

        def moment(s: int, t: int) -> Column:
            if not s or not t:
                return F.col("cnt").cast("double") if s == t else F.get("dsum", max(s, t) - 1)
            return F.get("dd", at[min(s, t) - 1, max(s, t) - 1])

    cross = lambda t, y: F.get(f"dy_{y}", t - 1) if t else F.col(f"sy_{y}")
    kron = (places, a, shared) if shared is not None else None
    return rows, lambda i, j: a[places[i][0]] * a[places[j][0]] * moment(places[i][1], places[j][1]), lambda i, y: a[places[i][0]] * cross(places[i][1], y), kron


def _fit_blocks(cf: CompressedFrame, cov: str, on_alias: str, small_sample: str | None = None, expanded: bool = False) -> FitResult:
    spec = cf.spec
    if cov == "ehw":
        raise ValueError(f"{cf.kind} rows hold no residual sums by feature")
    rows, m, v, kron = _blocks(cf)
    names, p, ys = [n for n, _ in spec.design()], len(spec.design()), spec.outcomes
    where = packed(p)
    tail = [F.col("cnt"), F.lit(1.0), *[F.col(f"syy_{y}") for y in ys], *[F.col(f"sy_{y}") for y in ys]]
    cross = [v(i, y) for y in ys for i in range(p)]
    o, table = len(ys), None if expanded else local_rows(rows, [], [m(i, j) for i, j in where] + cross + tail)
    if table:
        cells = table[1]
        flat = cells.sum(axis=0)
        entries, flat = flat[: len(where)], flat[len(where) :]
    elif kron:
        # balanced: each entry is a shared moment of periods times a sum over units of two static factors
        places, a, shared = kron
        pairs = sorted({tuple(sorted((places[i][0], places[j][0]))) for i, j in where})
        flat = total(rows, [a[i] * a[j] for i, j in pairs] + cross + tail)
        of = dict(zip(pairs, flat, strict=False))
        entries = [shared[places[i][1], places[j][1]] * of[tuple(sorted((places[i][0], places[j][0])))] for i, j in where]
        flat = flat[len(pairs) :]
    else:
        flat = total(rows, [m(i, j) for i, j in where] + cross + tail)
        entries, flat = flat[: len(where)], flat[len(where) :]
    gram = np.zeros((p, p))
    for (i, j), e in zip(where, entries, strict=True):
        gram[i, j] = gram[j, i] = e
    xy = flat[: p * o].reshape(o, p).T
    n, clusters, yy, sy = flat[p * o], int(flat[p * o + 1]), flat[p * o + 2 : p * o + 2 + o], flat[p * o + 2 + o :]
    bread = inverse_spd(gram, on_alias)
    coef = bread @ xy
    coef += bread @ (xy - gram @ coef)
    df, covs = n - p, []
    rss = np.array([max(yy[k] - coef[:, k] @ xy[:, k], 0.0) for k in range(o)])
    for k, y in enumerate(ys):
        if cov == "homoskedastic":
            covs.append(bread * rss[k] / df)
            continue
        if table:
            grams = np.zeros((len(cells), p, p))
            for a, (i, j) in enumerate(where):
                grams[:, i, j] = grams[:, j, i] = cells[:, a]
            u = cells[:, len(where) + k * p : len(where) + (k + 1) * p] - grams @ coef[:, k]
            scale = clusters / (clusters - 1) * (n - 1) / (n - p) if small_sample == "CR1" else 1.0
            covs.append(bread @ (u.T @ u) @ bread * scale)
            continue
        taken = lambda i: linear(coef[:, k], [m(i, j) for j in range(p)])  # noqa: B023, E731
        if expanded:
            named = rows.select(*[v(i, y).alias(f"_v{i}") for i in range(p)], *[taken(i).alias(f"_g{i}") for i in range(p)])
            vs, gs = ([F.col(f"_{c}{i}") for i in range(p)] for c in "vg")
            vv, gv, gg = (total(named, [a * b for a in s for b in t]).reshape(p, p) for s, t in ((vs, vs), (gs, vs), (gs, gs)))
            meat = vv - gv - gv.T + gg
        else:
            scores = rows.select(*[(v(i, y) - taken(i)).alias(f"_u{i}") for i in range(p)])
            (meat,), _, _ = sums(scores, [F.col(f"_u{i}") for i in range(p)], [F.lit(1.0)])
        scale = clusters / (clusters - 1) * (n - 1) / (n - p) if small_sample == "CR1" else 1.0
        covs.append(bread @ meat @ bread * scale)
    r2 = 1 - rss / np.where(yy - sy**2 / n > 0, yy - sy**2 / n, math.nan)
    return FitResult(names, ys, coef, covs, n, clusters, df, rss, r2, cf.kind, cov, bread, clusters)


def fit_moments_expanded(cf: CompressedFrame) -> FitResult:
    """The cluster covariance as products of sums, not of scores: the same value by another road."""
    return _fit_blocks(cf, "cluster", "error", expanded=True)


def between_rows(cf: CompressedFrame) -> CompressedFrame:
    """Sufficient statistics by place in the matrix; squares stand on the diagonal of the outer products."""
    ys = cf.spec.outcomes
    rows = cf.df.select(F.posexplode("matrix").alias("_i", "_m"), "k", *[c for y in ys for c in (f"sy_{y}", f"q_{y}")])
    n, i = F.size(f"sy_{ys[0]}"), F.col("_i")
    sums_ = [c for y in ys for c in (F.get(f"sy_{y}", i).alias(f"sy_{y}"), F.get(f"q_{y}", i * n + i).alias(f"syy_{y}"))]
    return CompressedFrame(rows.select("_m.*", F.col("k").alias("cnt"), *sums_), "stats", replace(cf.spec, cluster=None))


def balanced_rows(cf: CompressedFrame) -> CompressedFrame:
    """The panel's rows again; needs the outcomes kept."""
    if not cf.extra["keep_y"]:
        raise ValueError("outcomes were not kept")
    spec = cf.spec
    periods = cf.extra["periods"].orderBy(spec.time).agg(F.sort_array(F.collect_list(F.struct("*"))).alias("_p"))
    rows = cf.df.crossJoin(F.broadcast(periods))
    rows = rows.select("*", F.posexplode("_p").alias("_i", "_t"))
    static = [k for k in cf.df.columns if not k.startswith(("y_", "sy_", "syy_")) and k != "cnt"]
    time = [c for c in cf.extra["periods"].columns if c not in static]
    rows = rows.select(*static, *[F.col(f"_t.`{c}`") for c in time], *[F.get(f"y_{y}", F.col("_i")).alias(y) for y in spec.outcomes])
    return CompressedFrame(rows, "none", spec)


def _fit_between(cf: CompressedFrame, cov: str, on_alias: str) -> FitResult:
    """Cluster covariance from groups of clusters with one feature matrix: no cluster is looked at again."""
    ys, spec = cf.spec.outcomes, cf.spec
    base = _fit_rows(between_rows(cf), "homoskedastic", None, on_alias, "auto", None)
    x = [c for _, c in spec.design()]
    cells = cf.df.select("g1", "g2", F.posexplode("matrix").alias("_i", "_m")).select("g1", "g2", "_i", "_m.*")
    cells = cells.select("g1", "g2", F.struct("_i", F.array(*x).alias("x")).alias("r")).groupBy("g1", "g2").agg(F.sort_array(F.collect_list("r")).alias("r"))
    stored = [c for y in ys for c in (f"sy_{y}", f"q_{y}")]
    rows = cells.select("g1", "g2", F.flatten(F.transform("r", lambda s: s["x"])).alias("x")).join(cf.df.select("g1", "g2", "k", *stored), ["g1", "g2"])
    beta, p, o = base.coef, len(x), len(ys)

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out, clusters, groups = np.zeros((o, p, p)), 0, 0
        for batch in batches:
            for row in zip(*batch.columns, strict=True):
                flat, k = np.asarray(row[0].values, float), row[1].as_py()
                m = flat.reshape(-1, p)
                for j in range(o):
                    s, q = (np.asarray(row[2 + 2 * j + c].values, float) for c in (0, 1))
                    f = m @ beta[:, j]
                    cross = np.outer(s, f)
                    out[j] += m.T @ (q.reshape(len(s), len(s)) - cross - cross.T + k * np.outer(f, f)) @ m
                clusters, groups = clusters + k, groups + 1
        flat = np.r_[out.ravel(), clusters, groups]
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(flat), dtype=np.int32)), pa.array(flat)], names=["i", "v"])

    got = np.zeros(o * p * p + 2)
    for r in rows.select("x", "k", *stored).mapInArrow(each, "i int, v double").groupBy("i").agg(F.sum("v").alias("v")).collect():
        got[r.i] = r.v
    base.cov = [base.bread @ m @ base.bread for m in got[:-2].reshape(o, p, p)]
    base.kind, base.estimator, base.clusters, base.records = "between", "cluster", int(got[-2]), int(got[-1])
    return base


COMPRESSIONS = {
    "none": C.uncompressed, "frequency": C.compress_frequency, "means": C.compress_means, "stats": C.compress_stats, "weighted": C.compress_weighted,
    "binary": C.compress_binary, "within": C.compress_within_cluster, "cluster_moments": C.compress_cluster_moments, "static": C.compress_static,
    "balanced": C.compress_balanced, "between": C.compress_between_cluster,
}


def fit_linear(df: DataFrame, spec: ModelSpec, strategy: str = "auto", cov: str = "homoskedastic", **options) -> FitResult:
    """Compress, then fit. strategy auto asks the planner."""
    spec = resolve(df, spec)
    planned = strategy == "auto"
    if planned:
        from lincompress.plans.planner import plan_strategy

        strategy = plan_strategy(df, spec, cov).strategy
    try:
        cf = COMPRESSIONS[strategy](df, spec)
    except C.Unbalanced:
        if not planned:
            raise
        cf = C.compress_static(df, spec)  # periods that repeat alike in all clusters, which the planner's marks can't tell
    try:
        return fit_compressed(cf, cov, **options)
    finally:
        cf.release()


def fit_lpm(df: DataFrame, spec: ModelSpec, cov: str = "ehw") -> FitResult:
    """Linear probability model: a 0/1 outcome is its own square, so counts and successes are enough."""
    spec = resolve(df, spec)
    return fit_compressed(C.compress_binary(df, spec, cluster=cov == "cluster"), cov)


def mean_variance(cf: CompressedFrame) -> DataFrame:
    """Mean and variance (n - 1) of each outcome from its sums: spread inside the records, and of the records about the mean."""
    view = stats_view(cf)
    ys = range(len(cf.spec.outcomes))
    n = F.sum("_w")
    means = view.agg(n.alias("_n0"), *[(F.sum(f"_s{k}") / n).alias(f"_m{k}") for k in ys])
    rows = []
    held = view.crossJoin(F.broadcast(means))  # one row
    for k, y in enumerate(cf.spec.outcomes):
        own = F.try_divide(F.col(f"_s{k}"), F.col("_w"))
        inside = F.col(f"_c{k}") if cf.extra.get("centred") else F.col(f"_q{k}") - own * F.col(f"_s{k}")
        spread = F.sum(F.greatest(inside, F.lit(0.0)) + F.col("_w") * F.pow(own - F.col(f"_m{k}"), F.lit(2)))
        rows.append(F.struct(F.lit(y).alias("outcome"), F.first("_n0").alias("n"), F.first(f"_m{k}").alias("mean"), F.try_divide(spread, F.first("_n0") - 1).alias("variance")))
    return held.agg(F.array(*rows).alias("r")).select(F.inline("r"))


def contrast(fit: FitResult, l: np.ndarray, k: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """Values and covariance of linear combinations of coefficients."""
    l = np.atleast_2d(np.asarray(l, float))
    return l @ fit.coef[:, k], l @ fit.cov[k] @ l.T


def wald(fit: FitResult, l: np.ndarray, k: int = 0) -> tuple[float, float]:
    """F statistic and its tail for combinations that should be zero."""
    value, cov = contrast(fit, l, k)
    f = float(value @ np.linalg.solve(cov, value)) / len(value)
    return f, f_sf(f, len(value), fit.df)


def effect_rows(fit: FitResult, rows: list[tuple[str, dict[str, float]]], k: int = 0) -> list[tuple]:
    """(label, effect, se) of named combinations given as term -> factor."""
    l = np.array([[combo.get(n, 0.0) for n in fit.names] for _, combo in rows])
    value, cov = contrast(fit, l, k)
    return [(label, float(v), float(math.sqrt(max(c, 0)))) for (label, _), v, c in zip(rows, value, np.diag(cov), strict=True)]


def ate(fit: FitResult, treatment: str, k: int = 0) -> tuple[float, float]:
    (_, v, s), = effect_rows(fit, [(treatment, {treatment: 1.0})], k)
    return v, s


def cate(fit: FitResult, treatment: str, by: list[str], k: int = 0) -> list[tuple]:
    """Effect at the reference level and at each level that has a product with the treatment."""
    combos = [("(reference)", {treatment: 1.0})]
    for level in by:
        name = f"{treatment}:{level}" if f"{treatment}:{level}" in fit.names else f"{level}:{treatment}"
        combos.append((level, {treatment: 1.0, name: 1.0}))
    return effect_rows(fit, combos, k)


def effect_over_time(fit: FitResult, treatment: str, time: str, at: list[float], k: int = 0) -> list[tuple]:
    name = f"{treatment}:{time}" if f"{treatment}:{time}" in fit.names else f"{time}:{treatment}"
    return effect_rows(fit, [(t, {treatment: 1.0, name: float(t)}) for t in at], k)


def predict(fit: FitResult, df: DataFrame, spec: ModelSpec, k: int = 0) -> DataFrame:
    """Adds fitted and its standard error, as expressions."""
    x = [c for _, c in spec.design()]
    cov = fit.cov[k]
    var = sum((x[i] * x[j] * float(cov[i, j]) for i in range(len(x)) for j in range(len(x))), F.lit(0.0))
    return df.withColumns({"fitted": linear(fit.coef[:, k], x), "fitted_se": F.sqrt(F.greatest(var, F.lit(0.0)))})


def posterior(cf: CompressedFrame, ridge: float = 1.0, seed: int = 0, k: int = 0) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Mean, covariance and one draw of the coefficients under a normal prior of precision ridge / sigma^2."""
    fit = fit_compressed(cf)
    gram = inverse_spd(fit.bread)
    cov = inverse_spd(gram + ridge * np.eye(len(gram)))
    mean = cov @ gram @ fit.coef[:, k]
    cov = cov * fit.rss[k] / fit.df
    return mean, cov, np.random.default_rng(seed).multivariate_normal(mean, cov)

