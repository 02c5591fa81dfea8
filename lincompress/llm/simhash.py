"""SimHash near-duplicates through anchor-point covering.

A fingerprint has 64 bits. Bits 1 to 63 are covered by the perfect one-error-correcting code of length 63: its words are the
anchors, each point lies within the covering radius 1 of exactly one of them, and the last bit is carried along. Each
distinct fingerprint is replicated to the anchors around it, and what shares an anchor is compared there, pair by pair.

How far around: two fingerprints at 2 or fewer differing bits have a midpoint within 1 of both, and the anchor of that midpoint
lies within covering radius + threshold / 2 of both. So that reach covers every pair, with at most 32 replicas; covering radius +
threshold on one side alone would take 652. An anchor's ball holds at most 4,034 fingerprints, whatever the input, so a task
compares its members all against all in blocks; what leaves it is a forest that joins what is linked, not the pairs.

Edge cases: a null text counts as empty; a text without words has fingerprint zero, linked like any other; repeated rows
share a fingerprint; ids that are null link the same way but never name a component that has another id; an empty table
gives an empty result. Other columns are never looked at.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from lincompress.llm import components
from lincompress.llm.common import materialise, read

SEED, WIDTH, THRESHOLD = 42, 3, 2
_ALL = (1 << 64) - 1


def fingerprint(text: str | None, width: int = WIDTH) -> bytes:
    """The 8 bytes of a text's SimHash, most significant bit first."""
    import xxhash

    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return bytes(8)
    n = max(1, len(words) - width + 1)
    lengths = np.fromiter(map(len, words), np.int64, len(words)) + 1
    ends = np.cumsum(lengths)
    starts = (ends - lengths)[:n].tolist()
    stops = (ends[min(width, len(words)) - 1 :] - 1).tolist()
    line, digest = b" ".join(words), xxhash.xxh64_digest
    marks = np.frombuffer(b"".join([digest(line[a:b], SEED) for a, b in zip(starts, stops, strict=True)]), np.uint8).reshape(n, 8)
    votes = np.zeros(64, np.int64)
    for k in range(0, n, 8192):
        votes += np.unpackbits(marks[k : k + 8192], axis=1).sum(axis=0, dtype=np.int64)
    return np.packbits(2 * votes > n).tobytes()


def with_fingerprints(docs: DataFrame, width: int = WIDTH) -> DataFrame:
    """doc_id, fp (the fingerprint as a signed long)."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            marks = b"".join(fingerprint(x.as_py(), width) for x in batch.column(1))
            fp = np.frombuffer(marks, ">i8").astype(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fp)], names=["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(each, "doc_id long, fp long")


def _bits(k: int) -> int:
    """The positions 1 to 63 whose number has bit k, as a mask (position p at bit p - 1)."""
    return sum(1 << (p - 1) for p in range(1, 64) if p >> k & 1)


def _syndrome(x: Column) -> Column:
    """The position where x differs from its anchor, 0 for an anchor itself."""
    out = F.lit(0)
    for k in range(6):
        out = out.bitwiseOR((F.bit_count(x.bitwiseAND(F.lit(_bits(k)))) % 2).cast("int") * (1 << k))
    return out


def anchors(fps: DataFrame) -> DataFrame:
    """(anchor, fp): each fingerprint with all anchors within covering radius plus half the threshold."""
    low = F.col("fp").bitwiseAND(F.lit((1 << 63) - 1))
    df = fps.select("fp", low.alias("x")).withColumn("s", _syndrome(F.col("x")))
    return df.select("fp", F.explode(F.expr(
        "if(s = 0, array(x), concat(array(x ^ shiftleft(1L, s - 1)), "
        "transform(filter(sequence(1, 63), i -> i < (s ^ i)), i -> x ^ shiftleft(1L, i - 1) ^ shiftleft(1L, (s ^ i) - 1))))"
    )).alias("anchor"))


def _forest(members: np.ndarray) -> list[tuple[int, int]]:
    """Links that join all members within 2 bits of each other; every pair is compared."""
    members = np.unique(members)
    if len(members) == 2:
        a, b = members.tolist()
        return [(b, a)] if ((a ^ b) & _ALL).bit_count() <= THRESHOLD else []
    first = np.arange(len(members))

    def find(i: int) -> int:
        while first[i] != i:
            first[i] = first[first[i]]
            i = first[i]
        return i

    out, bits = [], members.view(np.uint64)
    for k in range(0, len(bits), 256):
        near = np.bitwise_count(bits[k : k + 256, None] ^ bits[None, :]) <= THRESHOLD
        for i, j in np.argwhere(near).tolist():
            if i + k < j:
                x, y = find(i + k), find(j)
                if x != y:
                    first[max(x, y)] = min(x, y)
                    out.append((int(members[j]), int(members[i + k])))
    return out


def links(fps: DataFrame) -> DataFrame:
    """(a, b): links that join all fingerprints within 2 bits; fps: distinct column fp."""
    balls = anchors(fps).groupBy("anchor").agg(F.collect_list("fp").alias("members")).where(F.size("members") > 1).select("members")

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            flat, cuts = batch.column(0).flatten().to_numpy(), batch.column(0).offsets.to_numpy()
            cuts = cuts - cuts[0]
            found = [link for x, y in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True) for link in _forest(flat[x:y])]
            a, b = zip(*found, strict=True) if found else ((), ())
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

    return balls.mapInArrow(compare, "a long, b long").distinct()


def classes(docs: DataFrame, width: int = WIDTH) -> DataFrame:
    """doc_id, fp, component_id: the smallest doc_id that links reach."""
    prints = materialise(with_fingerprints(docs, width), "prints")
    distinct = materialise(prints.groupBy("fp").agg(F.min("doc_id").alias("least")), "distinct")
    found = materialise(components.roots(links(distinct.select("fp"))), "roots")
    named = distinct.join(found, distinct.fp == found.node, "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    lowest = named.groupBy("root").agg(F.min("least").alias("component_id"))
    names = named.join(lowest, "root").select(F.col("fp").alias("_fp"), "component_id")
    return prints.join(names, prints.fp == F.col("_fp")).drop("_fp")


def op10_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = classes(read(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
