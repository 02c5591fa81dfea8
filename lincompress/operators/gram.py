"""Sums of products over compressed rows: wide aggregates, packed partial sums in Arrow, or sparse long form."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from lincompress.operators.compress import CompressedFrame, packed
from lincompress.plans.design import ModelSpec, Term

#: Numbers that the driver takes: a compressed frame of this size or less is fitted there in numpy, with one job.
LOCAL = 8_000_000
#: Aggregates in one row up to here; beyond, whole-stage code generation gives up, so numpy partial sums take over.
WIDE = 90


def stats_view(cf: CompressedFrame) -> DataFrame:
    """Every kind in one form: keys, cluster, w (weight), n (rows), s0.. and q0.. (weighted sums of y and y squared), w2, t0.., r0.. (the same at squared weights)."""
    spec, df = cf.spec, cf.df
    ys = list(enumerate(spec.outcomes))
    d = lambda c: F.col(f"`{c}`").cast("double")
    one = F.lit(1.0)
    if cf.kind == "none":
        w = d(spec.weight) if spec.weight else one
        cols = {"w": w, "n": F.when(w > 0, 1.0).otherwise(0.0)} | {f"s{k}": w * d(y) for k, y in ys} | {f"q{k}": w * d(y) * d(y) for k, y in ys}
        cols |= {"w2": w * w} | {f"t{k}": w * w * d(y) for k, y in ys} | {f"r{k}": w * w * d(y) * d(y) for k, y in ys}
    elif cf.kind == "frequency":
        cols = {"w": d("cnt"), "n": d("cnt")} | {f"s{k}": d("cnt") * d(y) for k, y in ys} | {f"q{k}": d("cnt") * d(y) * d(y) for k, y in ys}
    elif cf.kind == "means":
        cols = {"w": d("cnt"), "n": d("cnt")} | {f"s{k}": d("cnt") * d(f"mean_{y}") for k, y in ys} | {f"q{k}": d("cnt") * d(f"mean_{y}") * d(f"mean_{y}") for k, y in ys}
    elif cf.kind in ("stats", "within", "binary"):
        cols = {"w": d("cnt"), "n": d("cnt")} | {f"s{k}": d(f"sy_{y}") for k, y in ys} | {f"q{k}": d(f"sy_{y}" if cf.kind == "binary" else f"syy_{y}") for k, y in ys}
        if cf.extra.get("centred"):
            cols |= {f"c{k}": d(f"m2_{y}") for k, y in ys}
    elif cf.kind == "weighted":
        cols = {"w": d("sw"), "n": d("cnt"), "w2": d("sw2")}
        for k, y in ys:
            cols |= {f"s{k}": d(f"swy_{y}"), f"q{k}": d(f"swyy_{y}"), f"t{k}": d(f"sw2y_{y}"), f"r{k}": d(f"sw2yy_{y}")}
    else:
        raise ValueError(f"{cf.kind} frames have their own moments")
    keep = [F.col(f"`{c}`") for c in dict.fromkeys([*spec.keys, spec.cluster]) if c and c in df.columns]
    return df.select(*keep, *[c.alias(f"_{n}") for n, c in cols.items()])


def total(df: DataFrame, values: list[Column]) -> np.ndarray:
    """Sums of expressions over all rows, in one row."""
    if not values:
        return np.zeros(0)
    row = df.agg(*[F.sum(v).alias(f"a{i}") for i, v in enumerate(values)]).first()
    return np.array([0.0 if x is None else float(x) for x in row])


def local_rows(df: DataFrame, x: list[Column], values: list[Column], by: str | None = None, most: int = LOCAL) -> tuple[np.ndarray, np.ndarray, np.ndarray | None] | None:
    """Design, values and numbers of clusters of all rows, if they are no more than ``most`` numbers; else None. One job."""
    rows = most // (len(x) + len(values))
    columns = [F.array(*x, *values).alias("v"), *[F.col(f"`{by}`").alias("by")] * bool(by)]
    table = df.select(*columns).limit(rows + 1).toArrow()
    if table.num_rows > rows:
        return None
    flat = np.asarray(table["v"].combine_chunks().flatten().fill_null(0.0), float).reshape(table.num_rows, len(x) + len(values))
    codes = table["by"].combine_chunks().dictionary_encode(null_encoding="encode").indices.to_numpy() if by else None
    return flat[:, : len(x)], flat[:, len(x) :], codes


def _arrow_sums(df: DataFrame, x: list[Column], w: list[Column], s: list[Column], extra: list[Column]) -> np.ndarray:
    """Per weight the packed X'WX, then X's, then plain sums: numpy in each partition, added up by place."""
    p, nw, ns, ne = len(x), len(w), len(s), len(extra)
    none = F.array().cast("array<double>")
    rows = df.select(F.array(*x).alias("x"), F.array(*w).alias("w") if w else none.alias("w"), F.array(*s).alias("s") if s else none.alias("s"), F.array(*extra).alias("e") if extra else none.alias("e"))
    upper = np.triu_indices(p)

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = None
        for batch in batches:
            if not batch.num_rows:
                continue
            flat = lambda k, m: np.asarray(batch.column(k).flatten(), float).reshape(batch.num_rows, m)
            xs, ws, ss, es = flat(0, p), flat(1, nw), flat(2, ns), flat(3, ne)
            part = np.concatenate([*[((xs * ws[:, [k]]).T @ xs)[upper] for k in range(nw)], (xs.T @ ss).ravel(), es.sum(axis=0)])
            out = part if out is None else out + part
        if out is not None:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(out), dtype=np.int32)), pa.array(out)], names=["i", "v"])

    size = nw * len(upper[0]) + p * ns + ne
    out = np.zeros(size)
    for r in rows.mapInArrow(each, "i int, v double").groupBy("i").agg(F.sum("v").alias("v")).collect():
        out[r.i] = r.v
    return out


def sums(df: DataFrame, x: list[Column], w: list[Column], s: list[Column] = (), extra: list[Column] = (), method: str = "auto") -> tuple[list[np.ndarray], np.ndarray, np.ndarray]:
    """X'WX for each weight, X's for all s (p by number of s), and sums of the extra expressions, in one job."""
    p, places, s, extra = len(x), packed(len(x)), list(s), list(extra)
    if method == "auto":
        method = "wide" if len(w) * len(places) + p * len(s) + len(extra) <= WIDE else "packed"
    names = df.select("*", *[c.alias(f"_x{i}") for i, c in enumerate(x)])
    xs = [F.col(f"_x{i}") for i in range(p)]
    if method == "wide":
        flat = total(names, [k * xs[i] * xs[j] for k in w for i, j in places] + [v * c for v in xs for c in s] + extra)
    else:
        flat = _arrow_sums(names, xs, list(w), s, extra)
    grams = []
    for k in range(len(w)):
        m = np.zeros((p, p))
        for (i, j), v in zip(places, flat[k * len(places) : (k + 1) * len(places)], strict=True):
            m[i, j] = m[j, i] = v
        grams.append(m)
    at = len(w) * len(places)
    return grams, flat[at : at + p * len(s)].reshape(p, len(s)), flat[at + p * len(s) :]


def gram_wide(cf: CompressedFrame) -> np.ndarray:
    return sums(stats_view(cf), [c for _, c in cf.spec.design()], [F.col("_w")], method="wide")[0][0]


def gram_packed(cf: CompressedFrame) -> np.ndarray:
    return sums(stats_view(cf), [c for _, c in cf.spec.design()], [F.col("_w")], method="packed")[0][0]


def sparse_entries(spec: ModelSpec) -> Column:
    """The non-zero design entries of a row as an array of (i, v). A set of dummies is one lookup, whatever its number of levels."""

    def term(t: Term, at: int) -> tuple[Column, int]:
        if t.kind == "cat":
            column, levels, ref = t.args
            kept = [x for x in levels if x != (levels[0] if ref is None else ref)]
            place = F.try_element_at(F.create_map(*[F.lit(x) for i, v in enumerate(kept) for x in (v, i)]), F.col(f"`{column}`"))
            return F.when(place.isNull(), empty).otherwise(F.array(entry(place + F.lit(at), F.lit(1.0)))), len(kept)
        if t.kind == "inter":
            (a, m), (b, n) = term(t.args[0], 0), term(t.args[1], 0)
            return F.flatten(F.transform(a, lambda x: F.transform(b, lambda y: entry(x["i"] * n + y["i"] + F.lit(at), x["v"] * y["v"])))), m * n
        return F.array(*[entry(F.lit(at + k), c) for k, (_, c) in enumerate(t.columns())]), len(t.columns())

    entry = lambda i, v: F.struct(i.cast("int").alias("i"), v.cast("double").alias("v"))
    empty = F.array().cast("array<struct<i:int,v:double>>")
    parts, at = ([F.array(entry(F.lit(0), F.lit(1.0)))], 1) if spec.intercept else ([], 0)
    for t in spec.terms:
        column, n = term(t, at)
        parts, at = [*parts, column], at + n
    return F.filter(F.concat(*parts) if parts else empty, lambda e: e["v"] != 0)


def sparse_sums(rows: DataFrame, w: list[Column], s: list[Column] = ()) -> tuple[DataFrame, DataFrame]:
    """(i, j, v0..) of X'WX for each weight, upper triangle, and (i, v0..) of X's; rows hold the entries in _x. Work goes with non-zero entries."""
    named = rows.select("_x", *[c.alias(f"_w{k}") for k, c in enumerate(w)], *[c.alias(f"_v{k}") for k, c in enumerate(s)])
    one = named.withColumn("_a", F.explode("_x"))
    two = one.withColumn("_b", F.explode(F.filter("_x", lambda e: e["i"] >= F.col("_a.i"))))
    pairs = two.groupBy(F.col("_a.i").alias("i"), F.col("_b.i").alias("j")).agg(*[F.sum(F.col(f"_w{k}") * F.col("_a.v") * F.col("_b.v")).alias(f"v{k}") for k in range(len(w))])
    single = one.groupBy(F.col("_a.i").alias("i")).agg(*[F.sum(F.col(f"_v{k}") * F.col("_a.v")).alias(f"v{k}") for k in range(len(s))] or [F.lit(0.0).alias("v0")])
    return pairs, single


def gram_long(cf: CompressedFrame) -> DataFrame:
    """(i, j, v) of the upper triangle from non-zero entries only, for thousands of mostly empty columns."""
    rows = stats_view(cf).withColumn("_x", sparse_entries(cf.spec))
    return sparse_sums(rows, [F.col("_w")])[0].withColumnRenamed("v0", "v")


def dense(entries: DataFrame, p: int) -> np.ndarray:
    out = np.zeros((p, p))
    for r in entries.collect():
        out[r.i, r.j] = out[r.j, r.i] = r.v
    return out
