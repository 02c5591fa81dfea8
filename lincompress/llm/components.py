"""Connected components by alternating large-star and small-star steps; only counts reach the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lincompress.llm.common import materialise, remove


def _least(sym: DataFrame) -> DataFrame:
    """(a, b, m): each edge with the least of a and its neighbours. Combined before the shuffle; AQE splits hot nodes of the join."""
    low = sym.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("_a"), F.least("a", "m").alias("m"))
    return sym.join(low, F.col("a") == F.col("_a")).drop("_a")


def _both(edges: DataFrame) -> DataFrame:
    return edges.select("a", "b").unionAll(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))


def _large(edges: DataFrame) -> DataFrame:
    return _least(_both(edges)).where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()


def _small(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    near = _least(down)
    return near.select(F.col("b").alias("a"), F.col("m").alias("b")).unionAll(near.select("a", F.col("m").alias("b"))).where("a <> b").distinct()


def _mark(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())


def roots(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(node, root) for every node that an edge touches; root is the smallest node of its component. edges: a, b (long)."""
    now = materialise(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    mark = _mark(now)
    for _ in range(most_rounds):
        if not mark[0]:
            break
        after = materialise(_small(_large(now)), "edges")
        new = _mark(after)
        remove(now)
        now, old, mark = after, mark, new
        if new == old:
            break
    else:
        raise RuntimeError("components did not settle")
    stars = now.select(F.col("a").alias("node"), F.col("b").alias("root"))
    return stars.unionAll(stars.select(F.col("root").alias("node"), "root")).distinct()
