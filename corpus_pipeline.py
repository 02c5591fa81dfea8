"""The corpus pipeline: documents in, packed token sequences out; each stage calls one operator of lincompress.llm."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from lincompress.llm import line_dedup, near_copies, packing, quality_classifier, quality_rules
from lincompress.llm.common import materialise, read

STAGES = [
    ("quality_rules", quality_rules.stage),
    ("quality_classifier", quality_classifier.stage),
    ("line_dedup", line_dedup.stage),
    ("simhash_near_dedup", near_copies.stage),
    ("packing", packing.stage),
]

#: The classifier, the similarity components and the tokenizer are beyond SQL; tests/llm holds each against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
        if name != STAGES[-1][0]:
            docs = materialise(docs, name)
    return docs
