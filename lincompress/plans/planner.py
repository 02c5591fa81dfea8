"""Choice of a compression from a few counts: one aggregate over the raw rows, and one more by cluster where neither means nor pairs repeat."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lincompress.plans.design import ModelSpec, keyed


@dataclass
class Plan:
    strategy: str
    why: str
    counts: dict

    def explain(self) -> str:
        return f"{self.strategy}: {self.why} ({', '.join(f'{k}={v}' for k, v in self.counts.items())})"


def break_even(clusters: int, periods: int) -> float:
    """Most groups of equal feature matrices at which storing outer products takes no more numbers than rows."""
    return clusters / (periods + 2)


def plan_strategy(df: DataFrame, spec: ModelSpec, cov: str = "homoskedastic", most: float = 0.5) -> Plan:
    rows = keyed(df, spec, spec.cluster, spec.time, nulls="level")
    keys = F.xxhash64(*[f"`{k}`" for k in spec.keys]) if spec.keys else F.lit(0)
    clustered = cov == "cluster" and bool(spec.cluster)
    pairs = [F.approx_count_distinct(F.xxhash64(f"`{spec.cluster}`", *[f"`{k}`" for k in spec.keys]), 0.02)] if clustered else []
    n, groups, *within = rows.agg(F.count(F.lit(1)), F.approx_count_distinct(keys, 0.02), *pairs).first()
    counts = {"n": n, "groups": groups}
    if not n:
        return Plan("none", "no rows", counts)
    if not clustered:
        if spec.weight:
            return Plan("weighted", "weights given", counts)
        if groups / n > most:
            return Plan("none", "features hardly repeat; bin or round them", counts)
        return Plan("stats", "features repeat", counts)
    counts["within"] = within[0]
    if within[0] / n < most:
        return Plan("within", "rows repeat within clusters", counts)
    # roles, shapes and static values of all clusters in one more pass; shapes are added up without order, so a large cluster is no array
    names = [k for k in spec.keys if k != spec.cluster]
    same = [(F.min(f"`{k}`").eqNullSafe(F.max(f"`{k}`")) & F.count(f"`{k}`").isin(F.lit(0), F.count(F.lit(1)))).alias(f"_s{i}") for i, k in enumerate(names)]
    by = [F.count(F.lit(1)).alias("_t"), *same, *[F.xxhash64(F.min(f"`{k}`")).alias(f"_v{i}") for i, k in enumerate(names)]]
    if spec.time:
        by += [F.bit_xor(F.xxhash64(f"`{spec.time}`", F.lit(i), f"`{k}`")).alias(f"_x{i}") for i, k in enumerate([*names, spec.time])]
    per = rows.groupBy(f"`{spec.cluster}`").agg(*by)
    # an order-free mark of the values that are constant in the cluster
    static = F.xxhash64(*[F.when(F.col(f"_s{i}"), F.col(f"_v{i}")).otherwise(F.lit(0)) for i in range(len(names))]) if names else F.lit(0)
    shapes = [F.col(f"_x{i}") for i in range(len(names) + 1)] if spec.time else []
    c = per.agg(F.count(F.lit(1)), F.max("_t"), F.min("_t"), F.approx_count_distinct(static, 0.02), *[F.bool_and(f"_s{i}") for i in range(len(names))], *[F.min(x) == F.max(x) for x in shapes]).first()
    roles = dict(spec.roles) or {k: "static" if c[4 + i] else "dynamic" for i, k in enumerate(names)}
    if not any(r == "static" for r in roles.values()):
        return Plan("cluster_moments", "no feature is constant within clusters", counts)
    counts |= {"clusters": c[0], "periods": c[1], "static_groups": c[3]}
    like = [c[4 + len(names) + i] for i, k in enumerate([*names, spec.time]) if spec.time and (k == spec.time or roles.get(k) == "dynamic")]
    balanced = bool(spec.time) and c[1] == c[2] and all(like)
    if not balanced:
        return Plan("static", "static features, unbalanced", counts)
    if c[3] <= break_even(c[0], c[1]):
        return Plan("between", "few distinct feature matrices", counts)
    return Plan("balanced", "all clusters share the periods", counts)
