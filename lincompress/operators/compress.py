"""Compressions: one aggregate each, whose rows replace the raw rows in every later fit.

Column names: ``cnt`` rows, ``sy_<y>`` and ``syy_<y>`` sums of an outcome and its square, ``mean_<y>``; with weights ``sw``,
``swy_``, ``swyy_`` and the same with squared weights ``sw2``, ``sw2y_``, ``sw2yy_``. All but means without counts add up, so
frames merge and roll up.

Every compression reads the raw rows once. Those by cluster that must look at their own result (which features are constant in
a cluster, whether all clusters share their periods) keep it persisted for that; ``release`` frees it.
"""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from lincompress.plans.design import ModelSpec, Term, classify_roles, keyed


@dataclass(frozen=True)
class CompressedFrame:
    df: DataFrame
    kind: str
    spec: ModelSpec
    extra: dict = field(default_factory=dict)

    @property
    def keys(self) -> list[str]:
        return list(self.spec.keys)

    def cache(self) -> CompressedFrame:
        return replace(self, df=self.df.cache())

    def release(self) -> None:
        """Frees what the compression kept."""
        if "held" in self.extra:
            self.extra["held"].unpersist()

    def where(self, condition) -> CompressedFrame:
        """A segment; lossless when the condition reads key columns only."""
        return replace(self, df=self.df.where(condition))

    def with_terms(self, *terms: Term) -> CompressedFrame:
        """More terms over the columns of the frame, without compressing again."""
        if self.kind in ("cluster_moments",):
            raise ValueError("cluster moments hold no features; compress again with the new term")
        if self.kind in ("static", "balanced"):
            for t in terms:
                roles = [self.extra["roles"][k] for x in t.leaves() for k, _ in x.keys]
                if t.kind != "inter" or roles.count("dynamic") > 1:
                    raise ValueError("rows of one cluster allow new static x static and static x dynamic products only")
        new = {n for t in terms for n, _ in t.keys} - set(self.keys)
        if new:
            raise ValueError(f"not among the key columns: {sorted(new)}")
        return replace(self, spec=self.spec.with_terms(*terms))


def _key_columns(spec: ModelSpec) -> list[str]:
    return [f"`{k}`" for k in spec.keys]


def _sums(y: str, exact: str | None, centred: bool) -> list[Column]:
    c = F.col(f"`{y}`").cast(exact) if exact else F.col(f"`{y}`").cast("double")
    out = [F.sum(c).alias(f"sy_{y}"), F.sum(c * c).alias(f"syy_{y}")]
    return out + ([(F.var_pop(c) * F.count(F.lit(1))).alias(f"m2_{y}")] if centred else [])


def uncompressed(df: DataFrame, spec: ModelSpec, nulls: str = "error") -> CompressedFrame:
    return CompressedFrame(keyed(df, spec, spec.cluster, spec.weight, nulls=nulls), "none", spec)


def compress_frequency(df: DataFrame, spec: ModelSpec, outcome: str | None = None, joint: bool = False, cluster: bool = False, nulls: str = "error") -> CompressedFrame:
    """Distinct (features, one outcome) with a count; joint keys on all outcomes together."""
    ys = spec.outcomes if joint else (outcome or spec.outcomes[0],)
    spec = replace(spec, outcomes=tuple(ys))
    by = [*_key_columns(spec), *[f"`{y}`" for y in ys if y not in spec.keys], *[f"`{spec.cluster}`"] * (cluster and spec.cluster not in spec.keys)]
    return CompressedFrame(keyed(df, spec, spec.cluster if cluster else None, nulls=nulls).groupBy(*by).agg(F.count(F.lit(1)).alias("cnt")), "frequency", spec)


def compress_means(df: DataFrame, spec: ModelSpec, cluster: bool = False, nulls: str = "error") -> CompressedFrame:
    by = [*_key_columns(spec), *[f"`{spec.cluster}`"] * (cluster and spec.cluster not in spec.keys)]
    out = keyed(df, spec, spec.cluster if cluster else None, nulls=nulls).groupBy(*by).agg(F.count(F.lit(1)).alias("cnt"), *[F.avg(F.col(f"`{y}`").cast("double")).alias(f"mean_{y}") for y in spec.outcomes])
    return CompressedFrame(out, "means", spec)


def compress_stats(df: DataFrame, spec: ModelSpec, exact: str | None = None, centred: bool = False, cross: bool = False, nulls: str = "error") -> CompressedFrame:
    """Sufficient statistics by features, all outcomes in one pass. exact: a decimal type for sums that don't depend on order; cross adds sums of products of outcomes."""
    aggs = [F.count(F.lit(1)).alias("cnt")]
    for y in spec.outcomes:
        aggs += _sums(y, exact, centred)
    if cross:
        ys = spec.outcomes
        aggs += [F.sum(F.col(f"`{a}`").cast("double") * F.col(f"`{b}`").cast("double")).alias(f"sxy_{a}_{b}") for i, a in enumerate(ys) for b in ys[i + 1 :]]
    return CompressedFrame(keyed(df, spec, nulls=nulls).groupBy(*_key_columns(spec)).agg(*aggs), "stats", spec, {"centred": centred})


def compress_weighted(df: DataFrame, spec: ModelSpec, cluster: bool = False, nulls: str = "error") -> CompressedFrame:
    """Sums at the weight and at its square; the weight is no key. Rows of zero weight count no row; negative ones are an error."""
    w = F.col(f"`{spec.weight}`").cast("double")
    w = F.when(w < 0, F.raise_error(F.lit("negative weight")).cast("double")).otherwise(w)
    aggs = [F.count_if(w > 0).alias("cnt")]
    for p, name in ((w, "sw"), (w * w, "sw2")):
        aggs.append(F.sum(p).alias(name))
        for y in spec.outcomes:
            c = F.col(f"`{y}`").cast("double")
            aggs += [F.sum(p * c).alias(f"{name}y_{y}"), F.sum(p * c * c).alias(f"{name}yy_{y}")]
    by = [*_key_columns(spec), *[f"`{spec.cluster}`"] * (cluster and spec.cluster not in spec.keys)]
    return CompressedFrame(keyed(df, spec, spec.weight, spec.cluster if cluster else None, nulls=nulls).groupBy(*by).agg(*aggs), "weighted", spec)


def compress_binary(df: DataFrame, spec: ModelSpec, cluster: bool = False, nulls: str = "error") -> CompressedFrame:
    """Counts and successes of outcomes that are 0 or 1."""
    aggs = [F.count(F.lit(1)).alias("cnt")]
    for y in spec.outcomes:
        c = F.col(f"`{y}`").cast("double")
        checked = F.when(c.isin(0.0, 1.0), c.cast("long")).otherwise(F.raise_error(F.lit(f"{y} is neither 0 nor 1")).cast("long"))
        aggs.append(F.sum(checked).alias(f"sy_{y}"))
    by = [*_key_columns(spec), *[f"`{spec.cluster}`"] * (cluster and spec.cluster not in spec.keys)]
    return CompressedFrame(keyed(df, spec, spec.cluster if cluster else None, nulls=nulls).groupBy(*by).agg(*aggs), "binary", spec)


def compress_within_cluster(df: DataFrame, spec: ModelSpec, exact: str | None = None, nulls: str = "error") -> CompressedFrame:
    """The cluster id joins the key."""
    aggs = [F.count(F.lit(1)).alias("cnt")]
    for y in spec.outcomes:
        aggs += _sums(y, exact, False)
    by = [*_key_columns(spec), *[f"`{spec.cluster}`"] * (spec.cluster not in spec.keys)]
    return CompressedFrame(keyed(df, spec, spec.cluster, nulls=nulls).groupBy(*by).agg(*aggs), "within", spec)


def features_determine_cluster(df: DataFrame, spec: ModelSpec) -> bool:
    """Whether the cluster id adds nothing to the key, so that its maximum in each group is enough."""
    rows = keyed(df, spec, spec.cluster, nulls="level")
    return not rows.groupBy(*_key_columns(spec)).agg((F.min(spec.cluster) < F.max(spec.cluster)).alias("more")).where("more").limit(1).count()


def compress_determined(df: DataFrame, spec: ModelSpec, nulls: str = "error") -> CompressedFrame:
    """Sufficient statistics by features alone, with the cluster that they determine; features found in two clusters are an error."""
    aggs = [F.count(F.lit(1)).alias("cnt")]
    for y in spec.outcomes:
        aggs += _sums(y, None, False)
    rows = keyed(df, spec, spec.cluster, nulls=nulls).withColumn("_cluster", F.col(f"`{spec.cluster}`"))
    out = rows.groupBy(*_key_columns(spec)).agg(*aggs, F.min("_cluster").alias("_lo"), F.max("_cluster").alias("_hi"))
    kind = out.schema["_hi"].dataType
    one = F.when(F.col("_lo").eqNullSafe(F.col("_hi")), F.col("_hi")).otherwise(F.raise_error(F.lit("the features don't determine the cluster")).cast(kind))
    return CompressedFrame((out.withColumn("cnt", F.when(one.isNotNull(), F.col("cnt"))) if spec.cluster in spec.keys else out.withColumn(spec.cluster, one)).drop("_lo", "_hi"), "within", spec)


def packed(n: int) -> list[tuple[int, int]]:
    """Places of the upper triangle, row by row."""
    return [(i, j) for i in range(n) for j in range(i, n)]


def compress_cluster_moments(df: DataFrame, spec: ModelSpec, nulls: str = "error") -> CompressedFrame:
    """One row for each cluster with the cross-products of its design (packed) and outcomes."""
    names = [n for n, _ in spec.design()]
    rows = keyed(df, spec, spec.cluster, nulls=nulls)
    rows = rows.select(F.col(f"`{spec.cluster}`"), *[F.col(f"`{y}`").cast("double").alias(f"_y{k}") for k, y in enumerate(spec.outcomes)], *[c.alias(f"_x{i}") for i, (_, c) in enumerate(spec.design())])
    x = [F.col(f"_x{i}") for i in range(len(names))]
    aggs = [F.count(F.lit(1)).alias("cnt"), F.array(*[F.sum(x[i] * x[j]) for i, j in packed(len(x))]).alias("xx")]
    for k, y in enumerate(spec.outcomes):
        c = F.col(f"_y{k}")
        aggs += [F.array(*[F.sum(v * c) for v in x]).alias(f"xy_{y}"), F.sum(c).alias(f"sy_{y}"), F.sum(c * c).alias(f"syy_{y}")]
    return CompressedFrame(rows.groupBy(f"`{spec.cluster}`").agg(*aggs), "cluster_moments", spec)


def _split(spec: ModelSpec, roles: dict[str, str]) -> tuple[list[Column], list[Column], list[tuple[int, int]], list[str]]:
    statics: list[Column] = [F.lit(1.0)]
    dynamics: list[Column] = [F.lit(1.0)]
    names: list[str] = [""]
    seen: dict[tuple, list[int]] = {}

    def places(term: Term) -> tuple[str, list[int]]:
        role = "dynamic" if any(roles[k] == "dynamic" for k, _ in term.keys) else "static"
        held = dynamics if role == "dynamic" else statics
        if term not in seen:
            seen[term] = list(range(len(held), len(held) + len(term.columns())))
            held += [c for _, c in term.columns()]
            names.extend([n for n, _ in term.columns()] if role == "dynamic" else [])
        return role, seen[term]

    out = [(0, 0)] if spec.intercept else []
    for t in spec.terms:
        of = {roles[k] for x in t.leaves() for k, _ in x.keys}
        if t.kind == "inter" and len(of) == 2:
            a, b = t.args
            if any(x.kind == "inter" for x in t.args) or len({roles[k] for k, _ in a.keys}) > 1 or len({roles[k] for k, _ in b.keys}) > 1:
                raise ValueError(f"{t.name}: write products as one static and one dynamic term")
            (ra, pa), (_, pb) = places(a), places(b)
            out += [(i, j) if ra == "static" else (j, i) for i in pa for j in pb]
        else:
            role, p = places(t)
            out += [(i, 0) if role == "static" else (0, i) for i in p]
    return statics, dynamics, out, names


def split_design(spec: ModelSpec, roles: dict[str, str]) -> tuple[list[Column], list[Column], list[tuple[int, int]]]:
    """Static factors, dynamic factors, and each design column as (place among statics, place among dynamics); place 0 is the constant 1 of either."""
    return _split(spec, roles)[:3]


def _roles(df: DataFrame, spec: ModelSpec) -> dict[str, str]:
    return dict(spec.roles) or classify_roles(df, spec)


#: Design columns up to which products of all are summed, so that features need not be told apart before.
ONE_PASS = 24


def _moments(d: list[Column], outcomes: tuple[str, ...]) -> list[Column]:
    """Count, sums and cross-products of d (packed), and sums of the outcomes (columns _y0..) with their squares and products with d."""
    none = F.array().cast("array<double>")
    aggs = [F.count(F.lit(1)).alias("cnt"), (F.array(*map(F.sum, d)) if d else none).alias("dsum"), (F.array(*[F.sum(d[i] * d[j]) for i, j in packed(len(d))]) if d else none).alias("dd")]
    for k, y in enumerate(outcomes):
        c = F.col(f"_y{k}")
        aggs += [F.sum(c).alias(f"sy_{y}"), F.sum(c * c).alias(f"syy_{y}"), (F.array(*[F.sum(v * c) for v in d]) if d else none).alias(f"dy_{y}")]
    return aggs


def compress_static(df: DataFrame, spec: ModelSpec, nulls: str = "error") -> CompressedFrame:
    """One row for each cluster: static keys, counts, sums of y, and moments of the dynamic factors only.

    With unknown roles, one aggregate sums the moments of all terms beside the least and greatest value of each key; the roles
    are read off its rows, and static factors are left out of the moments. Wide models look for the roles first.
    """
    rows = keyed(df, spec, spec.cluster, nulls=nulls)
    ys = [F.col(f"`{y}`").cast("double").alias(f"_y{k}") for k, y in enumerate(spec.outcomes)]
    parts: dict[str, Column] = {}
    for t in spec.terms:
        for x in (t, *(t.args if t.kind == "inter" else ())):
            parts |= dict(x.columns())
    if spec.roles or len(parts) > ONE_PASS:
        roles = _roles(df, spec)
        _, dynamics, _ = split_design(spec, roles)
        by = list(dict.fromkeys([spec.cluster, *[k for k in spec.keys if roles[k] == "static"]]))
        rows = rows.select(*[F.col(f"`{k}`") for k in by], *ys, *[d.alias(f"_d{i}") for i, d in enumerate(dynamics) if i])
        out = rows.groupBy(*[f"`{k}`" for k in by]).agg(*_moments([F.col(f"_d{i}") for i in range(1, len(dynamics))], spec.outcomes))
        return CompressedFrame(out, "static", spec, {"roles": roles})
    keys = [k for k in spec.keys if k != spec.cluster]
    rows = rows.select(F.col(f"`{spec.cluster}`"), *[F.col(f"`{k}`").alias(f"_k{i}") for i, k in enumerate(keys)], *ys, *[c.alias(f"_d{i}") for i, c in enumerate(parts.values())])
    seen = [F.struct(F.min(f"_k{i}").alias("lo"), F.max(f"_k{i}").alias("hi"), F.count(f"_k{i}").alias("n")).alias(f"_k{i}") for i in range(len(keys))]
    held = rows.groupBy(f"`{spec.cluster}`").agg(*seen, *_moments([F.col(f"_d{i}") for i in range(len(parts))], spec.outcomes)).persist()
    same = [F.bool_and((F.col(f"_k{i}.lo") == F.col(f"_k{i}.hi")) & (F.col(f"_k{i}.n") == F.col("cnt")) | (F.col(f"_k{i}.n") == 0)).alias(f"s{i}") for i in range(len(keys))]
    flags = held.agg(*same).first() if keys else ()
    roles = {k: "dynamic" if flags[i] is False else "static" for i, k in enumerate(keys)} | ({spec.cluster: "static"} if spec.cluster in spec.keys else {})
    names, all_names = _split(spec, roles)[3][1:], list(parts)
    at, pair = [all_names.index(n) for n in names], {ij: k for k, ij in enumerate(packed(len(parts)))}
    pick = lambda column, places: F.array(*[F.get(column, k) for k in places]) if places else F.array().cast("array<double>")
    columns = [F.col(f"`{spec.cluster}`"), *[F.col(f"_k{i}.lo").alias(k) for i, k in enumerate(keys) if roles[k] == "static"], "cnt", pick("dsum", at).alias("dsum")]
    columns.append(pick("dd", [pair[min(at[i], at[j]), max(at[i], at[j])] for i, j in packed(len(at))]).alias("dd"))
    for y in spec.outcomes:
        columns += [f"sy_{y}", f"syy_{y}", pick(f"dy_{y}", at).alias(f"dy_{y}")]
    return CompressedFrame(held.select(*columns), "static", spec, {"roles": roles, "held": held})


def compress_trend(df: DataFrame, spec: ModelSpec, nulls: str = "error") -> CompressedFrame:
    """Static compression when the only dynamic feature is the period, a whole number without gaps in each cluster.

    The moments of the periods then follow from their first and last; only the product with y is summed. A gap or a repeat is an error.
    """
    roles = _roles(df, spec)
    if [t for t in spec.terms if t.kind != "inter" and any(roles[k] == "dynamic" for k, _ in t.keys) and (t.kind, t.name) != ("num", spec.time)]:
        raise ValueError("only a linear trend in the time column has closed moments")
    static = [k for k in spec.keys if roles[k] == "static"]
    t = F.col(f"`{spec.time}`").cast("double")
    aggs = [F.count(F.lit(1)).alias("cnt"), F.min(t).alias("_lo"), F.max(t).alias("_hi"), F.count_distinct(t).alias("_t")]
    for y in spec.outcomes:
        c = F.col(f"`{y}`").cast("double")
        aggs += [F.sum(c).alias(f"sy_{y}"), F.sum(c * c).alias(f"syy_{y}"), F.array(F.sum(t * c)).alias(f"dy_{y}")]
    rows = keyed(df, spec, spec.cluster, nulls=nulls).groupBy(*[f"`{k}`" for k in dict.fromkeys([spec.cluster, *static])]).agg(*aggs)
    lo, hi, n = F.col("_lo"), F.col("_hi"), F.col("cnt").cast("double")
    whole = (F.col("_t") == F.col("cnt")) & (hi - lo + 1 == n)
    n = F.when(whole, n).otherwise(F.raise_error(F.lit("periods of a cluster have gaps or repeats")).cast("double"))
    upto = lambda m: m * (m + 1) * (2 * m + 1) / 6
    rows = rows.withColumns({"dsum": F.array((lo + hi) * n / 2), "dd": F.array(upto(hi) - upto(lo - 1) + 0 * n)}).drop("_lo", "_hi", "_t")
    return CompressedFrame(rows, "static", spec, {"roles": roles})


class Unbalanced(ValueError):
    """Clusters don't share one set of periods; compress_static takes such panels."""


def _by_cluster(df: DataFrame, spec: ModelSpec, nulls: str) -> DataFrame:
    """The rows of each cluster as one sorted array r of structs (time, keys, outcomes), with their number."""
    rows = keyed(df, spec, spec.cluster, spec.time, nulls=nulls)
    inside = [F.col(f"`{k}`") for k in dict.fromkeys([spec.time, *spec.keys]) if k and k != spec.cluster]
    r = F.struct(*inside, *[F.col(f"`{y}`").cast("double").alias(f"_y{k}") for k, y in enumerate(spec.outcomes)])
    return rows.groupBy(f"`{spec.cluster}`").agg(F.count(F.lit(1)).alias("cnt"), F.sort_array(F.collect_list(r)).alias("r"))


def compress_balanced(df: DataFrame, spec: ModelSpec, keep_y: bool = True, nulls: str = "error") -> CompressedFrame:
    """Units (static keys and the outcomes of all periods as an array) and periods (dynamic keys), for panels where all clusters share the periods.

    One pass gathers the rows of each cluster; roles, the check and the periods are read off the arrays.
    """
    held = _by_cluster(df, spec, nulls).persist()
    keys = [k for k in spec.keys if k != spec.cluster]
    of = lambda k: F.transform("r", lambda s: s[k])
    checks = [F.min("cnt") == F.max("cnt"), F.bool_and(F.size(F.array_distinct(of(spec.time))) == F.col("cnt")), F.first("r")]
    for k in keys:
        shape = [F.xxhash64(F.transform("r", lambda s: F.struct(s[spec.time], s[k])), F.lit(seed)) for seed in (0, 1)]  # noqa: B023
        checks += [F.bool_and(F.size(F.array_distinct(of(k))) == 1), (F.min(shape[0]) == F.max(shape[0])) & (F.min(shape[1]) == F.max(shape[1]))]
    times = F.xxhash64(of(spec.time))
    row = held.agg(*checks, F.min(times) == F.max(times)).first()
    found = {k: "static" if row[3 + 2 * i] in (True, None) else "dynamic" for i, k in enumerate(keys)}
    roles = dict(spec.roles) or found | ({spec.cluster: "static"} if spec.cluster in spec.keys else {})
    wrong = [k for k in keys if roles[k] == "static" and found[k] == "dynamic"]
    if wrong:
        held.unpersist()
        raise ValueError(f"not constant in each cluster: {wrong}")
    shared = all(row[4 + 2 * i] for i, k in enumerate(keys) if roles[k] == "dynamic")
    if row[0] is not None and not (row[0] and row[1] and row[-1] and shared):
        held.unpersist()
        raise Unbalanced("clusters differ in their periods")
    dynamic = list(dict.fromkeys([spec.time, *[k for k in keys if roles[k] == "dynamic"]]))
    kind = held.schema["r"].dataType.elementType
    periods = df.sparkSession.createDataFrame([tuple(r[k] for k in dynamic) for r in row[2] or ()], type(kind)([kind[k] for k in dynamic]))
    columns = [F.col(f"`{spec.cluster}`"), *[F.get("r", 0)[k].alias(k) for k in keys if roles[k] == "static"], F.col("cnt")]
    add = lambda c, f: F.aggregate("r", F.lit(0.0), lambda a, s: a + f(s[c]))
    for k, y in enumerate(spec.outcomes):
        columns += [add(f"_y{k}", lambda v: v).alias(f"sy_{y}"), add(f"_y{k}", lambda v: v * v).alias(f"syy_{y}"), of(f"_y{k}").alias(f"y_{y}")]
    units = held.select(*columns)
    if not keep_y:
        _, dynamics, _ = split_design(spec, roles)
        grid = periods.select(*[c.alias(f"_d{i}") for i, c in enumerate(dynamics)], spec.time).orderBy(spec.time).collect()
        for y in spec.outcomes:
            dots = [F.aggregate(F.zip_with(f"y_{y}", F.array(*[F.lit(float(r[f"_d{i}"])) for r in grid]), lambda a, b: a * b), F.lit(0.0), lambda a, b: a + b) for i in range(1, len(dynamics))]
            units = units.withColumn(f"dy_{y}", F.array(*dots) if dots else F.array().cast("array<double>")).drop(f"y_{y}")
    return CompressedFrame(units, "balanced", spec, {"roles": roles, "periods": periods, "keep_y": keep_y, "held": held})


#: Numbers that a task holds before it sends its partial sums.
PARTIAL = 8_000_000


def compress_between_cluster(df: DataFrame, spec: ModelSpec, max_periods: int = 400, nulls: str = "error") -> CompressedFrame:
    """Clusters with equal feature matrices become one row: the matrix, how many clusters, and for every outcome its sums and outer products.

    The array of one cluster is bounded by max_periods rows (an error beyond); groups are named by 128 bits of hash. Tasks add up
    outer products by group before they send them, so what is shuffled goes with groups, not clusters.
    """
    ys, seen = spec.outcomes, list(spec.keys)
    rows = keyed(df, spec, spec.cluster, nulls=nulls)
    r = F.struct(F.struct(*[F.col(f"`{k}`") for k in seen]).alias("f"), *[F.col(f"`{y}`").cast("double").alias(f"y{k}") for k, y in enumerate(ys)])
    per = rows.groupBy(f"`{spec.cluster}`").agg(F.count(F.lit(1)).alias("t"), F.sort_array(F.collect_list(r)).alias("r"))
    per = per.withColumn("r", F.when(F.col("t") > max_periods, F.raise_error(F.lit("a cluster has too many rows for between-cluster compression")).cast(per.schema["r"].dataType)).otherwise(F.col("r")))
    per = per.select(F.transform("r", lambda s: s["f"]).alias("matrix"), *[F.transform("r", lambda s: s[f"y{k}"]).alias(f"y{k}") for k in range(len(ys))])  # noqa: B023
    held = per.withColumns({"g1": F.xxhash64("matrix"), "g2": F.xxhash64("matrix", F.lit(1))}).persist()
    by = ["g1", "g2"]

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[tuple[int, int], np.ndarray] = {}
        size = 0

        def out() -> pa.RecordBatch:
            lengths = [len(v) for v in sums.values()]
            keys = [np.repeat(np.array([g[k] for g in sums], np.int64), lengths) for k in (0, 1)]
            places = np.concatenate([np.arange(n, dtype=np.int32) for n in lengths])
            return pa.RecordBatch.from_arrays([*map(pa.array, keys), pa.array(places), pa.array(np.concatenate(list(sums.values())))], names=["g1", "g2", "i", "v"])

        for batch in batches:
            names = zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)
            for i, g in enumerate(names):
                y = [np.asarray(batch.column(2 + k)[i].values, float) for k in range(len(ys))]
                new = np.concatenate([[1.0], *[x for v in y for x in (v, np.outer(v, v).ravel())]])
                if g in sums:
                    sums[g] += new
                else:
                    sums[g] = new
                    size += len(new)
                if size > PARTIAL:
                    yield out()
                    sums, size = {}, 0
        if sums:
            yield out()

    heads = held.groupBy(*by).agg(F.first("matrix").alias("matrix"))
    added = held.select(*by, *[f"y{k}" for k in range(len(ys))]).mapInArrow(partial, "g1 long, g2 long, i int, v double").groupBy(*by, "i").agg(F.sum("v").alias("v"))
    added = added.groupBy(*by).agg(F.transform(F.sort_array(F.collect_list(F.struct("i", "v"))), lambda s: s["v"]).alias("v"))
    t = F.size("matrix")
    out = heads.join(added, by).withColumn("k", F.get("v", 0).cast("long"))
    for k, y in enumerate(ys):
        start = F.lit(2) + F.lit(k) * (t + t * t)
        out = out.withColumns({f"sy_{y}": F.slice("v", start, t), f"q_{y}": F.slice("v", start + t, t * t)})
    return CompressedFrame(out.drop("v"), "between", spec, {"held": held})


_ADD = ("cnt", "sw", "sy_", "syy_", "swy_", "swyy_", "sw2", "m2_", "sxy_")


def merge(a: CompressedFrame, b: CompressedFrame) -> CompressedFrame:
    """Both inputs as one: sums add up. Means are weighted by their counts; frames with centred sums must be built anew."""
    if (a.kind, a.spec.outcomes, list(a.spec.keys)) != (b.kind, b.spec.outcomes, list(b.spec.keys)):
        raise ValueError("frames of different kinds or models")
    return _regroup(replace(a, df=a.df.unionByName(b.df)), list(a.spec.keys), a.spec)


def _regroup(cf: CompressedFrame, keys: list[str], spec: ModelSpec) -> CompressedFrame:
    by = [f"`{k}`" for k in dict.fromkeys([*keys, *[spec.cluster] * (bool(spec.cluster) and spec.cluster in cf.df.columns)])]
    if cf.kind == "frequency":
        by += [f"`{y}`" for y in spec.outcomes if y not in keys]
    if any(c.startswith("m2_") for c in cf.df.columns):
        raise ValueError("centred sums do not add up; compress without them to merge")
    if cf.kind not in ("frequency", "means", "stats", "binary", "weighted", "within"):
        raise ValueError(f"{cf.kind} rows are already one for each cluster")
    aggs = [F.sum(c).alias(c) for c in cf.df.columns if c.startswith(_ADD)]
    aggs += [(F.sum(F.col(c) * F.col("cnt")) / F.sum("cnt")).alias(c) for c in cf.df.columns if c.startswith("mean_")]
    return replace(cf, df=cf.df.groupBy(*by).agg(*aggs), spec=spec)


def rollup(cf: CompressedFrame, drop: list[str]) -> CompressedFrame:
    """A narrower model from the same frame: terms over the dropped keys go, the rest add up."""
    terms = tuple(t for t in cf.spec.terms if not {n for n, _ in t.keys} & set(drop))
    spec = replace(cf.spec, terms=terms)
    return _regroup(cf, [k for k in cf.keys if k not in drop], spec)


def expand_frequency(cf: CompressedFrame, block: int = 1_000_000) -> DataFrame:
    """Rows again from frequency records; a count beyond a block is dealt to rows of one block first, so no array is longer."""
    blocks = cf.df.withColumn("_b", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("cnt") - 1) / block).cast("long"))))
    size = F.least(F.lit(block).cast("long"), F.col("cnt") - F.col("_b") * block)
    return blocks.withColumn("_r", F.explode(F.sequence(F.lit(1).cast("long"), size))).drop("_r", "_b", "cnt")


def within_transform(df: DataFrame, columns: list[str], by: str) -> DataFrame:
    """Deviations from cluster means, for fixed effects; by an aggregate and a join, so a large cluster is no single task."""
    means = df.groupBy(by).agg(*[F.avg(c).alias(f"_m{i}") for i, c in enumerate(columns)])
    out = df.join(means, by)
    return out.withColumns({c: F.col(c) - F.col(f"_m{i}") for i, c in enumerate(columns)}).drop(*[f"_m{i}" for i in range(len(columns))])


def save_compressed(cf: CompressedFrame, path: str, mode: str = "error") -> None:
    """Parquet, with what is needed to check a later reader's model beside it."""
    cf.df.write.mode(mode).parquet(f"{path}/rows")
    note = {"kind": cf.kind, "outcomes": cf.spec.outcomes, "keys": list(cf.spec.keys.items()), "roles": cf.extra.get("roles")}
    cf.df.sparkSession.createDataFrame([(json.dumps(note),)], "value string").coalesce(1).write.mode(mode).text(f"{path}/note")
    if "periods" in cf.extra:
        cf.extra["periods"].write.mode(mode).parquet(f"{path}/periods")


def to_local(cf: CompressedFrame, most: int = 10_000_000) -> pa.Table:
    """The compressed rows in the driver's memory as an Arrow table, for analysis there; more than ``most`` rows are an error."""
    table = cf.df.limit(most + 1).toArrow()
    if table.num_rows > most:
        raise ValueError(f"more than {most} compressed rows")
    return table


def from_local(spark, table: pa.Table, kind: str, spec: ModelSpec, **extra) -> CompressedFrame:
    """A frame again from an Arrow table (or pandas frame) of compressed rows."""
    return CompressedFrame(spark.createDataFrame(table), kind, spec, extra)


def load_compressed(spark, path: str, spec: ModelSpec) -> CompressedFrame:
    note = json.loads(spark.read.text(f"{path}/note").first()[0])
    if list(map(list, spec.keys.items())) != note["keys"] or list(spec.outcomes) != note["outcomes"]:
        raise ValueError("the saved frame belongs to another model")
    extra = {"roles": note["roles"]} if note["roles"] else {}
    if note["kind"] == "balanced":
        extra["periods"] = spark.read.parquet(f"{path}/periods")
        extra["keep_y"] = f"y_{spec.outcomes[0]}" in spark.read.parquet(f"{path}/rows").columns
    return CompressedFrame(spark.read.parquet(f"{path}/rows"), note["kind"], spec, extra)
