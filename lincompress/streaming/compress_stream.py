"""Compression as a streaming aggregate, and fits that follow it."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lincompress.operators.compress import CompressedFrame, merge
from lincompress.plans.design import ModelSpec


def _sums(outcomes) -> list:
    out = [F.count(F.lit(1)).alias("cnt")]
    for y in outcomes:
        c = F.col(y).cast("double")
        out += [F.sum(c).alias(f"sy_{y}"), F.sum(c * c).alias(f"syy_{y}")]
    return out


def compress_stream(stream: DataFrame, spec: ModelSpec, window: Callable | None = None, watermark: tuple[str, str] | None = None) -> DataFrame:
    """Sufficient statistics over a stream; state is a row for each distinct feature vector (and window). Works on batches too.

    window: e.g. ``lambda: F.window("ts", "1 day")`` or ``F.session_window("ts", "30 minutes")``; watermark: (column, delay).
    """
    if watermark and stream.isStreaming:
        stream = stream.withWatermark(*watermark)
    by = [F.expr(sql).alias(name) for name, sql in spec.keys.items()]
    return stream.groupBy(*([window().alias("window")] if window else []), *by).agg(*_sums(spec.outcomes))


def dedup(stream: DataFrame, key: str, time: str, delay: str) -> DataFrame:
    """Each event once, within the watermark."""
    if stream.isStreaming:
        return stream.withWatermark(time, delay).dropDuplicatesWithinWatermark([key])
    return stream.dropDuplicates([key])


def late_rows(batch: DataFrame, time: str, delay: str, seen: str) -> DataFrame:
    """How many rows a watermark would drop after the time ``seen``."""
    return batch.agg(F.count_if(F.col(time) < F.lit(seen).cast("timestamp") - F.expr(f"interval {delay}")).alias("late"), F.count(F.lit(1)).alias("rows"))


def run_available(out: DataFrame, name: str, checkpoint: str, mode: str = "complete") -> DataFrame:
    """Everything that is there, into files beside the checkpoint, which executors write: a complete result replaces the last one, other modes keep a folder for each batch (a retry overwrites it)."""
    store, seen = f"{checkpoint}-rows", []

    def write(batch: DataFrame, batch_id: int) -> None:
        part = "all" if mode == "complete" else f"batch-{batch_id}"
        batch.write.mode("overwrite").parquet(f"{store}/{part}")
        if part not in seen:
            seen.append(part)

    query = out.writeStream.outputMode(mode).queryName(name).foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    reader = out.sparkSession.read.schema(out.schema)
    return reader.parquet(*[f"{store}/{part}" for part in seen]) if seen else out.sparkSession.createDataFrame([], out.schema)


def refresh_each_batch(store: str, spec: ModelSpec, after: Callable[[CompressedFrame, int], None] | None = None) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: each batch's statistics go to a folder named by its id (a retry overwrites it), the frame is their sum."""

    def apply(batch: DataFrame, batch_id: int) -> None:
        compress_stream(batch, spec).write.mode("overwrite").parquet(f"{store}/batch={batch_id}")
        if after:
            after(stored(batch.sparkSession, store, spec), batch_id)

    return apply


def stored(spark, store: str, spec: ModelSpec) -> CompressedFrame:
    rows = spark.read.parquet(store).drop("batch")
    empty = CompressedFrame(rows.limit(0), "stats", spec)
    return merge(CompressedFrame(rows, "stats", spec), empty)


def moments_by_user(stream: DataFrame, cluster: str, x: str, y: str):
    """A row for each user kept as state (count, sums, products), emitted when it changes."""
    from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

    schema = f"{cluster} long, cnt long, sx double, sy double, sxx double, sxy double, syy double"

    class Moments(StatefulProcessor):
        def init(self, handle: StatefulProcessorHandle) -> None:
            self.state = handle.getValueState("m", "cnt long, sx double, sy double, sxx double, sxy double, syy double")

        def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer_values) -> Iterator[pd.DataFrame]:
            m = list(self.state.get()) if self.state.exists() else [0, 0.0, 0.0, 0.0, 0.0, 0.0]
            for r in rows:
                a, b = r[x].astype(float), r[y].astype(float)
                m = [m[0] + len(r), *[p + float(q) for p, q in zip(m[1:], (a.sum(), b.sum(), (a * a).sum(), (a * b).sum(), (b * b).sum()), strict=True)]]
            self.state.update(tuple(m))
            yield pd.DataFrame([[key[0], *m]], columns=[c.split()[0] for c in schema.split(", ")])

        def close(self) -> None:
            pass

    return stream.groupBy(cluster).transformWithStateInPandas(Moments(), schema, "Update", "None")
