"""Exploration on a compressed frame: every figure equals the one over the raw rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lincompress.operators.compress import CompressedFrame
from lincompress.operators.gram import stats_view


def _with_means(cf: CompressedFrame, columns: list[str], exact: str | None = None) -> DataFrame:
    """The frame beside its number of rows and the means of some columns (one row, joined by broadcast). exact: a decimal type to sum in."""
    n = F.sum("cnt").cast("double")
    value = lambda c: F.col(f"`{c}`").cast(exact) if exact else F.col(f"`{c}`").cast("double")
    means = cf.df.agg(n.alias("_n"), *[(F.sum(value(c) * F.col("cnt")).cast("double") / n).alias(f"_m{i}") for i, c in enumerate(columns)])
    return cf.df.crossJoin(F.broadcast(means))


def feature_summary(cf: CompressedFrame, columns: list[str], exact: str | None = None) -> DataFrame:
    """feature, n, mean, variance (n - 1), min, max. Variances are about the mean; sums of a decimal type don't depend on the order of rows."""
    w, parts = F.col("cnt").cast("double"), []
    for i, c in enumerate(columns):
        x = F.col(f"`{c}`").cast("double")
        parts.append(F.struct(F.lit(c).alias("feature"), F.first("_n").alias("n"), F.first(f"_m{i}").alias("mean"), F.try_divide(F.sum(w * F.pow(x - F.col(f"_m{i}"), F.lit(2))), F.first("_n") - 1).alias("variance"), F.min(x).alias("min"), F.max(x).alias("max")))
    return _with_means(cf, columns, exact).agg(F.array(*parts).alias("r")).select(F.inline("r"))


def feature_quantiles(cf: CompressedFrame, column: str, qs: list[float]) -> DataFrame:
    return cf.df.agg(F.percentile(column, F.array(*map(F.lit, qs)), F.col("cnt")).alias("v")).select(F.posexplode("v").alias("i", "value")).select(F.get(F.array(*map(F.lit, qs)), F.col("i")).alias("q"), "value")


def feature_corr(cf: CompressedFrame, a: str, b: str) -> DataFrame:
    w, x, y = F.col("cnt").cast("double"), F.col(f"`{a}`").cast("double") - F.col("_m0"), F.col(f"`{b}`").cast("double") - F.col("_m1")
    return _with_means(cf, [a, b]).agg(F.first("_n").alias("n"), F.try_divide(F.sum(w * x * y), F.sqrt(F.sum(w * x * x) * F.sum(w * y * y))).alias("corr"))


def cooccurrence(cf: CompressedFrame, a: str, b: str) -> DataFrame:
    return cf.df.groupBy(a, b).agg(F.sum("cnt").alias("n"))


def feature_histogram(cf: CompressedFrame, column: str, bins: int, lo: float, hi: float) -> DataFrame:
    return cf.df.groupBy(F.width_bucket(F.col(column).cast("double"), F.lit(lo), F.lit(hi), F.lit(bins)).alias("bin")).agg(F.sum("cnt").alias("n"))


def outcome_by(cf: CompressedFrame, column: str) -> DataFrame:
    """Mean of the first outcome with its standard error at each value of a feature; spread is about the means of records and values."""
    own = F.col("_s0") / F.col("_w")
    view = stats_view(cf).withColumn("_o", own).withColumn("_i", F.greatest(F.col("_q0") - own * F.col("_s0"), F.lit(0.0)))
    means = view.groupBy(F.col(f"`{column}`").alias("_key")).agg(F.sum("_w").alias("n"), (F.sum("_s0") / F.sum("_w")).alias("mean"))
    spread = F.sum(F.col("_i") + F.col("_w") * F.pow(F.col("_o") - F.col("mean"), F.lit(2)))
    found = view.join(means, F.col(f"`{column}`").eqNullSafe(F.col("_key"))).groupBy("_key", "n", "mean")
    return found.agg(F.sqrt(F.try_divide(spread, (F.col("n") - 1) * F.col("n"))).alias("se")).withColumnRenamed("_key", column)
