"""Language identification with hyperdimensional profiles.

Every letter has a random vector of +1 and -1 that its code point seeds, in whatever script; all that is no letter is one symbol. A trigram is bound by multiplying the vectors of its
letters, permuted (rotated) by their place; a document bundles (adds up) its trigrams and a language bundles its training
documents, each at unit length. A document gets the language whose profile, less the mean profile, has the largest cosine
with it; ties go to the first name. Profiles are summed in whole numbers, so they don't depend on the order of rows.

Edge cases: a text that is null or has no letter gets ``und`` and score 0, as does every text when nothing was learned; rows
with a null language teach nothing; repeated rows count and get a row each; an empty table gives an empty result. Other columns
are never looked at.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lincompress.llm.common import read, remainder

MODULUS, HELD, SIZE, UNIT = 5, 0, 1024, 1 << 20
#: Characters that are bundled at once.
BLOCK = 1 << 20


#: Numbers of trigrams up to this many are kept in a table; those of larger alphabets are sorted.
TABLE = 1 << 22
#: Counts by text and trigram that are held at once.
CELLS = 1 << 24


def letter_vector(code: int, size: int = SIZE) -> np.ndarray:
    """+1 or -1 for each component: the bits of hashes of (code point, place)."""
    with np.errstate(over="ignore"):
        x = np.uint64(code + 1) * np.uint64(0x9E3779B97F4A7C15) + np.arange(-(-size // 64), dtype=np.uint64) * np.uint64(0xD1342543DE82EF95)
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        x ^= x >> np.uint64(31)
    return np.unpackbits(x.astype("<u8").view(np.uint8))[:size].astype(np.int8) * 2 - 1


class Bundler:
    """Numbers letters as it meets them: 0 for what is no letter, 1, 2, ... for letters; results don't depend on the numbers."""

    def __init__(self, size: int = SIZE):
        self.size = size
        self.number = np.full(0x110000, -1, np.int32)
        self.vectors = np.zeros((64, size), np.int8)
        self.vectors[0], self.letters = letter_vector(-1, size), 1
        self.at = np.zeros(0, np.int32)

    def numbers(self, codes: np.ndarray) -> np.ndarray:
        out = self.number[codes]
        if len(out) and out.min() < 0:
            for c in np.unique(codes[out < 0]).tolist():
                if not chr(c).isalpha():
                    self.number[c] = 0
                    continue
                if self.letters == len(self.vectors):
                    self.vectors = np.concatenate([self.vectors, np.zeros_like(self.vectors)])
                self.vectors[self.letters] = letter_vector(c, self.size)
                self.number[c] = self.letters
                self.letters += 1
            out = self.number[codes]
        return out

    def codes(self, text: str) -> np.ndarray:
        """Trigrams of the letters (three letter numbers of 21 bits), with one boundary for each run of other characters; empty without a letter."""
        s = self.numbers(np.frombuffer(text.lower().encode("utf-32-le", "replace"), "<u4"))
        s = np.concatenate([[0], s, [0]]).astype(np.int64)
        s = s[np.r_[True, (s[1:] > 0) | (s[:-1] > 0)]]
        return s[:-2] << 42 | s[1:-1] << 21 | s[2:] if len(s) > 2 else s[:0]

    def bundle(self, texts: list[str | None]) -> np.ndarray:
        """A vector for each text, of unit length; zero without a letter."""
        out = np.zeros((len(texts), self.size), np.float32)
        block: list[tuple[int, np.ndarray]] = []
        held = 0
        for i, text in enumerate(texts):
            codes = self.codes(text or "")
            for k in range(0, len(codes), BLOCK):
                block.append((i, codes[k : k + BLOCK]))
                held += len(block[-1][1])
                if held >= BLOCK:
                    self._add(out, block)
                    block, held = [], 0
        self._add(out, block)
        norm = np.linalg.norm(out, axis=1, keepdims=True)
        return np.divide(out, norm, out=out, where=norm > 0)

    def _add(self, out: np.ndarray, block: list[tuple[int, np.ndarray]]) -> None:
        if not block:
            return
        docs = np.array([i for i, _ in block])
        codes = np.concatenate([c for _, c in block])
        low, n = (1 << 21) - 1, self.letters
        if n**3 <= TABLE:
            dense = (codes >> 42) * (n * n) + (codes >> 21 & low) * n + (codes & low)
            if len(self.at) < n**3:
                self.at = np.zeros(n**3, np.int32)
            self.at[dense] = 1
            found = np.flatnonzero(self.at)
            self.at[found] = np.arange(len(found))
            place = self.at[dense]
            self.at[found] = 0
            found = (found // (n * n)) << 42 | (found // n % n) << 21 | found % n
        else:
            found, place = np.unique(codes, return_inverse=True)
        if len(block) > 1 and len(block) * len(found) > CELLS:
            self._add(out, block[: len(block) // 2])
            self._add(out, block[len(block) // 2 :])
            return
        cell = np.repeat(np.arange(len(docs)), [len(c) for _, c in block]) * len(found) + place
        counts = np.bincount(cell, minlength=len(docs) * len(found)).reshape(len(docs), len(found)).astype(np.float32)
        v = self.vectors[:n]
        first, second = np.roll(v, 2, axis=1), np.roll(v, 1, axis=1)
        for k in range(0, len(found), 4096):
            part = found[k : k + 4096]
            bound = first[part >> 42] * second[part >> 21 & low] * v[part & low]
            np.add.at(out, docs, counts[:, k : k + 4096] @ bound.astype(np.float32))


def profiles(docs: DataFrame) -> tuple[list[str], np.ndarray]:
    """Names and unit profiles, less their mean; docs: text, lang. What reaches the driver is a vector for each language."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bundler, sums = Bundler(), {}
        for whole in batches:
            for k in range(0, whole.num_rows, 512):
                batch = whole.slice(k, 512)
                vectors = np.rint(bundler.bundle(batch.column(0).to_pylist()).astype(np.float64) * UNIT).astype(np.int64)
                langs = np.array(batch.column(1).to_pylist(), object)
                for name in set(langs):
                    sums[name] = sums.get(name, 0) + vectors[langs == name].sum(axis=0)
        for name, v in sums.items():
            yield pa.RecordBatch.from_arrays([pa.array([name] * len(v)), pa.array(np.arange(len(v), dtype=np.int32)), pa.array(v)], names=["lang", "i", "v"])

    rows = docs.where("lang is not null").select("text", F.col("lang").cast("string").alias("lang")).mapInArrow(each, "lang string, i int, v long").groupBy("lang", "i").agg(F.sum(F.col("v").cast("decimal(38,0)")).alias("v")).collect()
    names = sorted({r.lang for r in rows})
    out = np.zeros((len(names), SIZE))
    for r in rows:
        out[names.index(r.lang), r.i] = float(r.v)
    norm = np.linalg.norm(out, axis=1, keepdims=True)
    out = np.divide(out, norm, out=out, where=norm > 0)
    if len(names) > 1:
        out -= out.mean(axis=0)
        norm = np.linalg.norm(out, axis=1, keepdims=True)
        out = np.divide(out, norm, out=out, where=norm > 0)
    return names, out


def predict(docs: DataFrame, names: list[str], vectors: np.ndarray) -> DataFrame:
    """doc_id, lang_pred, score (the cosine, at least 0); docs: doc_id, text."""
    vectors = vectors.T.astype(np.float32)

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bundler = Bundler()
        for whole in batches:
            for k in range(0, whole.num_rows, 512):
                batch = whole.slice(k, 512)
                found = bundler.bundle(batch.column(1).to_pylist())
                some = found.any(axis=1) & bool(names)
                if names:
                    cosine = found @ vectors
                    best = cosine.argmax(axis=1)
                    score = np.where(some, np.clip(cosine.max(axis=1), 0, 1), 0).astype(np.float64)
                else:
                    best, score = np.zeros(len(found), int), np.zeros(len(found))
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([names[b] if s else "und" for b, s in zip(best, some, strict=True)]), pa.array(score)], names=["doc_id", "lang_pred", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(each, "doc_id long, lang_pred string, score double")


def op7_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    names, vectors = profiles(docs.where(remainder(F.col("doc_id"), MODULUS) != HELD))
    found = predict(docs, names, vectors)
    return found.select("doc_id", (remainder(F.col("doc_id"), MODULUS) == HELD).alias("held_out"), "lang_pred", "score")
