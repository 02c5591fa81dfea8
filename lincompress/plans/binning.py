"""Binning and rounding of features with many values, to compress more."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def cut_points(df: DataFrame, column: str, k: int = 10, method: str = "exact", accuracy: int = 10_000) -> list[float]:
    """The inner quantiles. exact sorts the distinct values, approx sketches them."""
    qs = [i / k for i in range(1, k)]
    agg = F.percentile(column, F.array(*map(F.lit, qs))) if method == "exact" else F.percentile_approx(column, qs, accuracy)
    return list(dict.fromkeys(float(x) for x in df.agg(agg).first()[0] or []))


def bin_by_cuts(column: str | Column, cuts: list[float]) -> Column:
    """0 for values up to the first cut (exclusive), and so on; nulls stay null."""
    c = F.col(column) if isinstance(column, str) else column
    if not cuts:
        return F.when(c.isNotNull(), 0)
    return F.when(c.isNotNull(), F.size(F.filter(F.array(*map(F.lit, cuts)), lambda x: x <= c)))


def bin_quantile(df: DataFrame, column: str, k: int = 10, method: str = "exact", name: str | None = None, value: str = "label") -> DataFrame:
    """Adds a bin of equal counts; value: label, mid (of the bin's range) or mean (of its values), the last two by a join with k rows."""
    name = name or f"{column}_bin"
    out = df.withColumn(name, bin_by_cuts(column, cut_points(df, column, k, method)))
    if value == "label":
        return out
    of = F.avg(column) if value == "mean" else (F.min(column) + F.max(column)) / 2
    means = out.groupBy(name).agg(of.alias("_value"))
    return out.join(F.broadcast(means), name, "left").drop(name).withColumnRenamed("_value", name)


def bin_ntile(df: DataFrame, column: str, key: str, k: int = 10, name: str | None = None) -> DataFrame:
    """Bins of exactly equal counts, ties split by key. One global order: for frames of units, not of events."""
    return df.withColumn(name or f"{column}_bin", F.ntile(k).over(Window.orderBy(column, key)))


def bin_width(column: str | Column, k: int, lo: float, hi: float) -> Column:
    """1 to k over [lo, hi), 0 below and k + 1 above."""
    c = F.col(column) if isinstance(column, str) else column
    return F.width_bucket(c, F.lit(float(lo)), F.lit(float(hi)), F.lit(k))


def round_feature(column: str | Column, step: float) -> Column:
    c = F.col(column) if isinstance(column, str) else column
    return F.floor(c / step) * step


def range_join(df: DataFrame, column: str, cuts: list[float], name: str) -> DataFrame:
    """The same bins by an inequality join with a broadcast table of ranges (one row for each cut)."""
    spark = df.sparkSession
    edges = [float("-inf"), *cuts, float("inf")]
    ranges = spark.createDataFrame([(i, a, b) for i, (a, b) in enumerate(zip(edges, edges[1:], strict=False))], f"{name} int, _lo double, _hi double")
    return df.join(F.broadcast(ranges), (F.col(column) >= F.col("_lo")) & (F.col(column) < F.col("_hi"))).drop("_lo", "_hi")
