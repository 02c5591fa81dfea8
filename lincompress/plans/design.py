"""Model specifications: outcomes, terms and roles, as Column expressions over key columns.

A term names the columns that enter the group key of a compressed frame and the design columns made from them. Design
columns can be evaluated on raw rows and on compressed rows alike, because both carry the key columns.
"""

from __future__ import annotations

import itertools
import re
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Term:
    name: str
    keys: tuple[tuple[str, str], ...]  # key column and the SQL that makes it from raw rows
    kind: str
    args: tuple = ()

    def columns(self) -> list[tuple[str, Column]]:
        """Design columns over the key columns."""
        if self.kind == "num":
            return [(self.name, F.col(f"`{self.name}`").cast("double"))]
        if self.kind == "poly":
            base = F.col(f"`{self.args[0]}`").cast("double")
            return [(self.args[0] if k == 1 else f"{self.args[0]}^{k}", base if k == 1 else F.pow(base, F.lit(k))) for k in range(1, self.args[1] + 1)]
        if self.kind == "cat":
            column, levels, ref = self.args
            if levels is None:
                raise ValueError(f"levels of {column} are not resolved")
            drop = levels[0] if ref is None else ref
            return [(f"{column}[{v}]", F.when(F.col(f"`{column}`") == F.lit(v), 1.0).otherwise(0.0)) for v in levels if v != drop]
        a, b = self.args
        return [(f"{x}:{y}", u * v) for (x, u), (y, v) in itertools.product(a.columns(), b.columns())]

    def leaves(self) -> list[Term]:
        return [x for t in self.args for x in t.leaves()] if self.kind == "inter" else [self]


def num(column: str) -> Term:
    return Term(column, ((column, f"`{column}`"),), "num")


def cat(column: str, levels: list | tuple | None = None, ref=None) -> Term:
    return Term(column, ((column, f"`{column}`"),), "cat", (column, None if levels is None else tuple(levels), ref))


def poly(column: str, degree: int) -> Term:
    return Term(f"poly({column},{degree})", ((column, f"`{column}`"),), "poly", (column, degree))


def expr(sql: str, name: str) -> Term:
    """A named expression; it becomes a key column itself."""
    return Term(name, ((name, sql),), "num")


def inter(a: Term, b: Term) -> Term:
    return Term(f"{a.name}:{b.name}", tuple(dict.fromkeys(a.keys + b.keys)), "inter", (a, b))


@dataclass(frozen=True)
class ModelSpec:
    outcomes: tuple[str, ...]
    terms: tuple[Term, ...] = ()
    intercept: bool = True
    treatment: str | None = None
    cluster: str | None = None
    time: str | None = None
    weight: str | None = None
    weight_kind: str | None = None
    roles: dict[str, str] = field(default_factory=dict, compare=False)

    def __post_init__(self):
        object.__setattr__(self, "outcomes", (self.outcomes,) if isinstance(self.outcomes, str) else tuple(self.outcomes))
        object.__setattr__(self, "terms", tuple(self.terms))
        if self.weight_kind not in (None, "frequency", "analytic", "probability", "importance"):
            raise ValueError(f"unknown weight kind {self.weight_kind}")
        if (self.weight is None) != (self.weight_kind is None):
            raise ValueError("weight and weight_kind go together")

    @property
    def keys(self) -> dict[str, str]:
        """Key columns in order, with the SQL that makes each from raw rows."""
        out: dict[str, str] = {}
        for t in self.terms:
            for name, sql in t.keys:
                if out.setdefault(name, sql) != sql:
                    raise ValueError(f"two expressions are named {name}")
        return out

    def design(self) -> list[tuple[str, Column]]:
        out = [("(intercept)", F.lit(1.0))] if self.intercept else []
        for t in self.terms:
            out += t.columns()
        names = [n for n, _ in out]
        if len(set(names)) < len(names):
            raise ValueError(f"design columns repeat: {names}")
        return out

    def with_terms(self, *terms: Term) -> ModelSpec:
        return replace(self, terms=self.terms + terms)


def _fill(term: Term, levels: dict[str, tuple]) -> Term:
    if term.kind == "cat" and term.args[1] is None:
        return replace(term, args=(term.args[0], levels[term.args[0]], term.args[2]))
    if term.kind == "inter":
        return replace(term, args=tuple(_fill(t, levels) for t in term.args))
    return term


def resolve(df: DataFrame, spec: ModelSpec, max_levels: int = 10_000) -> ModelSpec:
    """Checks columns and fills in unknown levels of categorical terms (one distinct for each, at most max_levels values reach the driver)."""
    missing = [c for c in (*spec.outcomes, spec.cluster, spec.time, spec.weight) if c and c not in df.columns]
    if missing:
        raise ValueError(f"no such columns: {missing}")
    levels: dict[str, tuple] = {}
    for leaf in (x for t in spec.terms for x in t.leaves()):
        if leaf.kind == "cat" and leaf.args[1] is None and leaf.args[0] not in levels:
            column = leaf.args[0]
            found = [r[0] for r in df.select(column).where(F.col(column).isNotNull()).distinct().limit(max_levels + 1).collect()]
            if len(found) > max_levels:
                raise ValueError(f"{column} has more than {max_levels} levels; bin it")
            levels[column] = tuple(sorted(found))
    return replace(spec, terms=tuple(_fill(t, levels) for t in spec.terms))


def keyed(df: DataFrame, spec: ModelSpec, *more: str, nulls: str = "error") -> DataFrame:
    """Key columns, outcomes and what else is named, from raw rows. nulls: error, drop, or level (nulls stay a group of their own)."""
    others = [c for c in dict.fromkeys([*spec.outcomes, *more]) if c]
    out = df.select(*[F.expr(sql).alias(name) for name, sql in spec.keys.items()], *[F.col(f"`{c}`") for c in others if c not in spec.keys])
    if nulls == "drop":
        out = out.dropna()
    elif nulls == "error":
        for c in out.columns:
            message = F.lit(f"null in {c}; drop such rows or make them a level")
            out = out.withColumn(c, F.coalesce(F.col(f"`{c}`"), F.raise_error(message).cast(out.schema[c].dataType))) if out.schema[c].nullable and c in spec.outcomes else out
    elif nulls != "level":
        raise ValueError(nulls)
    return out


def parse_formula(text: str, **options) -> ModelSpec:
    """``y1 + y2 ~ a + C(b) + a:C(b) + poly(t,2)``; ``0`` drops the intercept, ``a*b`` is a + b + a:b."""
    left, right = text.split("~")

    def one(s: str) -> Term:
        s = s.strip()
        if m := re.fullmatch(r"C\((\w+)\)", s):
            return cat(m[1])
        if m := re.fullmatch(r"poly\((\w+)\s*,\s*(\d+)\)", s):
            return poly(m[1], int(m[2]))
        if not re.fullmatch(r"\w+", s):
            raise ValueError(f"can't read term {s!r}")
        return num(s)

    terms, intercept = [], True
    for part in re.split(r"\+(?![^(]*\))", right):
        part = part.strip()
        if part in ("0", "1"):
            intercept = part == "1"
        elif "*" in part:
            a, b = map(one, part.split("*"))
            terms += [a, b, inter(a, b)]
        elif ":" in part:
            a, b = map(one, part.split(":"))
            terms.append(inter(a, b))
        else:
            terms.append(one(part))
    return ModelSpec(tuple(y.strip() for y in left.split("+")), tuple(terms), intercept, **options)


def classify_roles(df: DataFrame, spec: ModelSpec) -> dict[str, str]:
    """Key column -> static (one value in every cluster) or dynamic; one aggregate by cluster."""
    keys = [k for k in spec.keys if k != spec.cluster]
    same = keyed(df, spec, spec.cluster, nulls="level").groupBy(spec.cluster).agg(*[(F.min(k).eqNullSafe(F.max(k)) & F.count(k).isin(F.lit(0), F.count(F.lit(1)))).alias(k) for k in keys])
    row = same.agg(*[F.bool_and(k).alias(k) for k in keys]).first()
    return {k: "static" if row[k] or row[k] is None else "dynamic" for k in keys} | ({spec.cluster: "static"} if spec.cluster in spec.keys else {})
