"""Quality classifier: regularised quadratic discriminant over transformed statistics of a text.

Each class has a mean and a covariance, shrunk towards the diagonal of the pooled covariance. Their Cholesky factors are
made once and travel with the scoring function; the score is the logistic of half the difference of squared Mahalanobis
distances, with the log-determinants and the log prior odds. Class sums come from all labelled rows.

Edge cases: a null text counts as empty and gets a score too; labels without a document, or null labels, teach nothing; of
repeated labels of one id the largest counts; repeated documents get a row each; with no row of one class every score is 1 or 0
for the other, and 0.5 with no row at all; an empty table gives an empty result. Other columns are never looked at.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lincompress.llm.common import materialise, numbered, read, remainder
from lincompress.operators.solve import _lower_inverse

MODULUS, HELD, KEEP = 4, 2, 0.7
SHRINK, RIDGE = 0.1, 1e-4
NAMES = ("words", "word_length", "upper", "digits", "symbols", "marks", "shouts", "distinct", "lines", "repeated_lines", "bars", "doubles")


def statistics(text: str | None) -> list[float]:
    """Logarithms of smoothed ratios, which are nearer to normal than the ratios."""
    data = (text or "").encode("utf-8", "replace")
    seen = np.bincount(np.frombuffer(data, np.uint8), minlength=256)
    words = data.split()
    n, letters = len(words), int(seen[65:91].sum() + seen[97:123].sum())
    lines = [x for x in data.split(b"\n") if x.strip()]
    of = lambda chars: int(seen[list(chars)].sum())
    part = lambda a, b, s=0.01: math.log((a + s) / (b + 2 * s))
    chars = sum(map(len, words))
    return [
        math.log1p(n), part(chars, n, 1), part(of(range(65, 91)), letters), part(of(range(48, 58)), chars), part(of(b"#*$%&<>@^~"), n), part(of(b".,;:?"), n),
        part(of(b"!"), n), part(len(set(words)), n, 1), part(len(lines), n, 0.5), part(len(lines) - len(set(lines)), len(lines)), part(of(b"|"), n), part(sum(map(bytes.__eq__, words, words[1:])), n),
    ]


def features(docs: DataFrame) -> DataFrame:
    """doc_id and x, the statistics of the text."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = [statistics(t.as_py()) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(x, pa.list_(pa.float64()))], names=["doc_id", "x"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(each, "doc_id long, x array<double>")


def fit(labelled: DataFrame, shrink: float = SHRINK, ridge: float = RIDGE) -> dict | None:
    """labelled: x, quality. One aggregate; two rows reach the driver."""
    p = len(NAMES)
    pairs = [(i, j) for i in range(p) for j in range(i, p)]
    x = [F.get("x", i) for i in range(p)]
    # covariances about the mean, merged pairwise: no difference of large sums
    sums = [F.count(F.lit(1)).alias("n"), *[F.avg(x[i]).alias(f"m{i}") for i in range(p)], *[F.covar_pop(x[i], x[j]).alias(f"c{i}_{j}") for i, j in pairs]]
    rows = {r.quality: r for r in labelled.where("quality in (0, 1)").groupBy("quality").agg(*sums).collect()}
    if not rows:
        return None
    moments = {}
    for k, r in rows.items():
        mean = np.array([r[f"m{i}"] for i in range(p)])
        cov = np.zeros((p, p))
        for i, j in pairs:
            cov[i, j] = cov[j, i] = r[f"c{i}_{j}"]
        moments[k] = (r.n, mean, cov)
    total = sum(m[0] for m in moments.values())
    pooled = np.diag(np.maximum(np.diag(sum(m[0] * m[2] for m in moments.values())) / total, 0) + ridge)
    out = {"only": None if len(moments) == 2 else float(next(iter(moments)))}
    for k, (n, mean, cov) in moments.items():
        factor = np.linalg.cholesky((1 - shrink) * cov + shrink * pooled + ridge * np.eye(p))
        out[k] = (mean, _lower_inverse(factor), 2 * np.log(np.diag(factor)).sum(), math.log(n / total))
    return out


def densities(model: dict, x: np.ndarray, k: int) -> np.ndarray:
    mean, inverse_factor, log_det, log_prior = model[k]
    z = (x - mean) @ inverse_factor.T
    return log_prior - 0.5 * (log_det + (z * z).sum(axis=1))


def scores(model: dict | None, x: np.ndarray) -> np.ndarray:
    x = x.reshape(-1, len(NAMES))
    if model is None or model["only"] is not None:
        return np.full(len(x), 0.5 if model is None else model["only"])
    return 1 / (1 + np.exp(-np.clip(densities(model, x, 1) - densities(model, x, 0), -700, 700)))


def scored(frame: DataFrame, model: dict | None) -> DataFrame:
    """doc_id and score for rows of doc_id and x."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            score = scores(model, np.array(batch.column(1).to_pylist(), float))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(score)], names=["doc_id", "score"])

    return frame.select("doc_id", "x").mapInArrow(each, "doc_id long, score double")


def classify(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted."""
    frame = materialise(features(docs), "features")
    known = labels.where("quality is not null").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("quality").alias("quality"))
    train = frame.where(remainder(F.col("doc_id"), MODULUS) != HELD).join(known, "doc_id")
    found = scored(frame, fit(train.select("x", "quality")))
    return found.select("doc_id", (remainder(F.col("doc_id"), MODULUS) == HELD).alias("held_out"), "score", (F.col("score") >= KEEP).cast("int").alias("predicted"))


def op9_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classify(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels"))


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents that are not predicted 0. The score depends on the text alone, so it is computed beside each row."""
    labels = read(spark, sf_dir, "labels").where("quality is not null").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("quality").alias("quality"))
    # statistics are made before the join with the labels, so no text is shuffled
    train = features(docs.where(remainder(F.col("doc_id"), MODULUS) != HELD))
    model = fit(train.join(labels, "doc_id").select("x", "quality"))

    if model is None:
        return docs
    text = docs.columns.index("text")

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for k in range(0, whole.num_rows, 512):
                batch = whole.slice(k, 512)
                yield batch.filter(pa.array(scores(model, np.array([statistics(t.as_py()) for t in batch.column(text)], float)) >= KEEP))

    plain = numbered(docs, "doc_id", "text")
    return plain.mapInArrow(keep, plain.schema).toDF(*docs.columns)
