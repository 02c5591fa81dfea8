"""Timing experiments: raw rows against compressed records. Run ``python experiments.py [rows in millions] [folder for panels]``; prints Markdown tables."""

from __future__ import annotations

import math
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from pyspark.sql import SparkSession  # noqa: E402
from pyspark.sql import functions as F  # noqa: E402

from lincompress.operators import baselines, compress as C, explore  # noqa: E402
from lincompress.operators.fit import fit_compressed, fit_linear  # noqa: E402
from lincompress.operators.glm import fit_logistic  # noqa: E402
from lincompress.operators.measures import timed  # noqa: E402
from lincompress.plans.design import ModelSpec, inter, num  # noqa: E402
from lincompress.sources.tables import panel_generator  # noqa: E402

SPEC = ModelSpec("y", tuple(num(c) for c in ("arm", "x1", "x2", "x3", "t")), cluster="unit", time="t", roles={"arm": "static", "x1": "static", "x2": "static", "x3": "static", "t": "dynamic"})


def held(spark: SparkSession, units: int, periods: int):
    df = panel_generator(spark, units, periods).persist()
    df.count()
    return df


def stored(spark: SparkSession, folder: str, units: int, periods: int):
    """The panel as files, so that fits from rows pay for their scans."""
    path = f"{folder}/panel-{units}-{periods}"
    panel_generator(spark, units, periods, partitions=16).write.mode("overwrite").parquet(path)
    return spark.read.parquet(path)


def line(*cells) -> None:
    print("| " + " | ".join(f"{c:.3f}" if isinstance(c, float) else str(c) for c in cells) + " |", flush=True)


def main(millions: float, folder: str) -> None:
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").config("spark.driver.memory", "12g").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    print("\nSeconds to fit, by rows (100 periods, read from files): from rows, compressed and fitted, and from the kept records\n")
    line("rows", "records", "iid rows", "iid compress + fit", "iid kept", "robust rows", "robust compress + fit", "robust kept")
    line(*["---"] * 8)
    for share in (0.01, 0.1, 1.0):
        df = stored(spark, folder, int(millions * 1e4 * share), 100)
        covs = ("homoskedastic", "ehw")
        raw = [[timed(lambda k=k, c=c: fit_linear(df, SPEC, k, c), 2) for k in ("none", "stats")] for c in covs]  # before any cache that their plans would meet
        cf = C.compress_stats(df, SPEC).cache()
        records = cf.df.count()
        line(df.count(), records, *[x for c, r in zip(covs, raw, strict=True) for x in (*r, timed(lambda c=c: fit_compressed(cf, c), 2))])
        cf.df.unpersist()
    print("\nSeconds for cluster covariances with a treatment x time product, by periods (100,000 units, read from files)\n")
    spec = SPEC.with_terms(inter(num("arm"), num("t")))
    kinds = ("within", "cluster_moments", "static", "balanced")
    line("periods", "rows", *[f"{k}, compress + fit" for k in kinds], "static, kept", "rows / static kept", "T / 2")
    line(*["---"] * 9)
    for periods in (5, 10, 30, 100):
        df = stored(spark, folder, 100_000, periods)
        rows, *took = [timed(lambda k=k: fit_linear(df, spec, k, "cluster"), 2) for k in ("none", *kinds)]
        cf = C.compress_static(df, spec).cache()
        cf.df.count()
        kept = timed(lambda: fit_compressed(cf, "cluster"), 2)
        cf.df.unpersist()
        line(periods, rows, *took, kept, rows / kept, periods / 2)
    print("\nSeconds to fit records on the cluster, by their number (same columns); the slope is that of the logarithms between the last two\n")
    line("records", "seconds", "slope")
    line(*["---"] * 3)
    before = None
    for records in (100_000, 1_000_000, 10_000_000, 40_000_000):
        i = F.col("id")
        rows = spark.range(records).select((i % 2).alias("arm"), (i % 3).alias("x1"), (i % 5).alias("x2"), (i % 7).alias("x3"), (i % 100).alias("t"), F.lit(3).alias("cnt"), (i % 11).cast("double").alias("sy_y"), (i % 11 * 5).cast("double").alias("syy_y"))
        frame = C.CompressedFrame(rows.persist(), "stats", SPEC)
        frame.df.count()
        took = timed(lambda: fit_compressed(frame, "ehw", method="wide"), 2)
        line(records, took, math.log(took / before[1]) / math.log(records / before[0]) if before else "")
        before = records, took
        frame.df.unpersist()
    df = held(spark, int(millions * 1e6 / 60), 30)
    print("\nSeconds for many outcomes: one pass against one pass each\n")
    line("outcomes", "frequency passes", "one pass")
    line(*["---"] * 3)
    many = df.withColumns({f"y{k}": F.round(F.col("y") * k, 1) for k in range(1, 5)}).persist()
    many.count()
    for o in (1, 2, 4):
        ys = tuple(f"y{k}" for k in range(1, o + 1))
        s = ModelSpec(ys, SPEC.terms)
        line(o, timed(lambda s=s, ys=ys: [fit_compressed(C.compress_frequency(many, s, y)) for y in ys], 2), timed(lambda s=s: fit_compressed(C.compress_stats(many, s)), 2))
    print("\nOther seconds\n")
    line("what", "rows", "compressed")
    line(*["---"] * 3)
    binary = many.withColumn("z", (F.col("y") > 1.5).cast("int")).persist()
    binary.count()
    s = ModelSpec("z", SPEC.terms)
    cb = C.compress_binary(binary, s).cache()
    cb.df.count()
    line("logistic", timed(lambda: baselines.logistic_rows(binary, s), 1), timed(lambda: fit_logistic(cb), 2))
    line("Spark's normal solver / sufficient statistics", timed(lambda: baselines.mllib_linear(df, SPEC), 2), timed(lambda: fit_compressed(C.compress_stats(df, SPEC)), 2))
    cf = C.compress_stats(df, SPEC).cache()
    cf.df.count()
    line("median of a feature", timed(lambda: df.agg(F.median("t")).collect(), 2), timed(lambda: explore.feature_quantiles(cf, "t", [0.5]).collect(), 2))
    line("correlation", timed(lambda: df.agg(F.corr("x1", "t")).collect(), 2), timed(lambda: explore.feature_corr(cf, "x1", "t").collect(), 2))
    spark.stop()


if __name__ == "__main__":
    main(float(sys.argv[1]) if len(sys.argv) > 1 else 5.0, sys.argv[2] if len(sys.argv) > 2 else "/tmp/panels")
