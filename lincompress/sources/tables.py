"""Reading and writing tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register_views(spark: SparkSession, sf_dir: str) -> None:
    for name in TABLES:
        load(spark, sf_dir, name).createOrReplaceTempView(name)


def read_text_table(spark: SparkSession, path: str, kind: str, schema: str) -> DataFrame:
    """CSV (with a header), JSON lines or ORC, with an explicit schema."""
    reader = spark.read.schema(schema)
    return reader.csv(path, header=True) if kind == "csv" else reader.format(kind).load(path)


def write_table(df: DataFrame, path: str, kind: str = "parquet", partition_by: list[str] = (), mode: str = "error") -> None:
    writer = df.write.mode(mode).format(kind)
    writer = writer.option("header", True) if kind == "csv" else writer
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def save_bucketed(df: DataFrame, table: str, cluster: str, buckets: int) -> None:
    """A table bucketed by cluster: later aggregates by cluster need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, cluster).sortBy(cluster).saveAsTable(table)


def panel_generator(spark: SparkSession, units: int, periods: int, tau: float = 0.5, partitions: int | None = None) -> DataFrame:
    """A balanced panel made from hashes: unit, t, arm, x1..x4 (static, few levels), y with a noise term shared by each unit."""
    n = units * periods
    rows = spark.range(0, n, 1, partitions) if partitions else spark.range(n)
    u, t = F.col("id") % units, (F.col("id") / F.lit(units)).cast("int")
    noise = lambda salt, *c: F.pmod(F.xxhash64(F.lit(salt), *c), F.lit(10_000)) / 10_000.0 - 0.5
    rows = rows.select(u.alias("unit"), t.alias("t"))
    rows = rows.withColumns({"arm": F.pmod(F.xxhash64("unit"), F.lit(2)).cast("int")} | {f"x{k}": F.pmod(F.xxhash64("unit", F.lit(k)), F.lit(k + 2)).cast("int") for k in range(1, 5)})
    return rows.withColumn("y", F.lit(1.0) + tau * F.col("arm") + 0.1 * F.col("x1") + 0.02 * F.col("t") + noise(1, F.col("unit")) + noise(2, F.col("unit"), F.col("t")))


def panel_of(units: DataFrame, periods: int) -> DataFrame:
    """A balanced panel of given units: their rows, once for each period t."""
    return units.withColumn("t", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(periods - 1).cast("long"))))


def sample_rows(df: DataFrame, share: float, seed: int = 0, by: str | None = None, shares: dict | None = None) -> DataFrame:
    """A reproducible sample for choosing cut points, never for a fit; with ``by`` each value has its own share."""
    return df.sampleBy(by, shares, seed) if by else df.sample(share, seed=seed)


def follow(spark: SparkSession, sf_dir: str, name: str, files_per_batch: int | None = None) -> DataFrame:
    """A table's files as a stream."""
    reader = spark.readStream.schema(load(spark, sf_dir, name).schema).option("pathGlobFilter", f"{name}*.parquet").option("recursiveFileLookup", "true")
    return (reader.option("maxFilesPerTrigger", files_per_batch) if files_per_batch else reader).parquet(sf_dir)
