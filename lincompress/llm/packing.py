"""Mixture-controlled packing: deficit round-robin over one token queue for each source.

Documents are tokenised once and stand in the queue of their source. Queues are served token by token: at time t a queue of
weight w has a credit of w * t tokens, what it has been served is that credit rounded, and the rest is its deficit, half a
token at most. A window of ``length`` tokens ends when that many have been served, so what a queue has been served at the end of
window k, the cut (k, queue), follows from k alone. Every task that needs a cut computes it, deficits carry over windows and
partitions without being sent, each window holds each live queue's target share to a token or two, and none but the last has
padding. A queue that has run dry leaves its share to the others.

Weights are targets by name, or a power of the queues' tokens: 1 keeps the corpus's own shares (all queues run dry together),
less lifts small sources. A document's place in its queue is a sum of three: tokens before its block, a block being what
one task tokenised, and tokens before it in the block. Only sums by (source, block) are shuffled; no task sees a queue.

Edge cases: a null or empty text is only its end token; a null source is the queue ''; repeated rows are separate documents;
a document without id is packed too; an empty table gives no pieces; more queues than a quarter of ``length`` are an error, as
a window could not hold them all. A queue without a target gets the least one. Other columns are never looked at.
"""

from __future__ import annotations

import math
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from lincompress.llm.common import materialise, read

LENGTH, QUANTUM, END_ID = 2048, 1, 1
#: The query's mixture: a source's target share goes with this power of its tokens.
POWER = 0.7
#: Entries of the caches of a worker, from space-separated chunk and from word to ids; a cache is emptied when full.
CACHE, WORDS = 600_000, 400_000
#: The same beside other stages, where an executor has less room: with these, emptied after each task, a process peaks at 167 MB instead of 297.
LEAN = 150_000, 100_000
#: Rows of sums by (source, block) up to here are broadcast (some 30 bytes each); more are joined by shuffle.
BROADCAST_ROWS = 200_000
#: Marks that end a word and are a word of their own for the tokenizer when they stand alone.
MARKS = (b".", b",", b"!", b"?", b";", b":")


def _encoder(path: str):
    """Text -> ids as bytes (uint16, little-endian). White space never enters an id, so chunks between it are encoded apart and cached.

    A new chunk of plain characters is cut into the tokenizer's own words, each of which goes to its merge model once; every
    other chunk goes through the whole tokenizer. A worker keeps its caches from task to task.
    """
    import os
    import sys
    import types

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    shelf = sys.modules.setdefault("_token_shelf", types.ModuleType("_token_shelf")).__dict__
    if path not in shelf:
        shelf[path] = _Encoder(path)
    return shelf[path].encode


def _forget() -> None:
    """Empties the caches of this worker: other stages need the memory."""
    import gc
    import sys

    shelf = sys.modules.get("_token_shelf")
    for encoder in list(vars(shelf).values()) if shelf else ():
        if hasattr(encoder, "chunks") and encoder.chunks:
            encoder.chunks.clear()
            encoder.words.clear()
            gc.collect()
    pa.default_memory_pool().release_unused()


class _Encoder:
    def __init__(self, path: str):
        import json

        import regex
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        if self.tok.get_vocab_size() > 65536:
            raise ValueError("ids are kept in 16 bits")
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.cut = regex.compile(spec["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"]).findall
        self.plain = regex.compile(r"[!-;=-~\u00a1-\u00ac\u00ae-\u024f]+").fullmatch
        visible = {*range(33, 127), *range(161, 173), *range(174, 256)}
        rest = (c for c in range(256) if c not in visible)
        self.shown = {c: 256 + k for k, c in enumerate(rest)}
        self.model = self.tok.model.tokenize
        self.chunks, self.words = _Memo(self.chunk), _Memo(self.word)

    def word(self, word: str) -> bytes:
        shown = word if word.isascii() else word.encode().decode("latin-1").translate(self.shown)
        return array("H", [t.id for t in self.model(shown)]).tobytes()

    def chunk(self, chunk: bytes) -> bytes:
        if chunk.isalpha():  # ASCII letters only, as of bytes
            return self.words[chunk.lower().decode()]
        if chunk[-1:] in MARKS and chunk[:-1].isalpha():
            return self.words[chunk[:-1].lower().decode()] + self.words[chunk[-1:].decode()]
        text = chunk.decode()
        if self.plain(text):
            text = text.lower()
            if text.isalpha():
                parts = (text,)
            elif text[:-1].isalpha() and text[-1].encode() in MARKS:
                parts = (text[:-1], text[-1])
            else:
                parts = self.cut(text)
            return b"".join(map(self.words.__getitem__, parts))
        return np.array(self.tok.encode(text, add_special_tokens=False).ids, "<u2").tobytes()

    def encode(self, texts: list[str], limits: tuple[int, int] = (CACHE, WORDS)) -> list[bytes]:
        out, (most, most_words) = [], limits
        for text in texts:
            data = text.encode("utf-8", "replace")
            parts = (data if b"<|" in data else data.lower()).split()
            out.append(b"".join(map(self.chunks.__getitem__, parts)))
            if len(self.words) > most_words:
                self.words.clear()
            if len(self.chunks) > most:
                self.chunks.clear()
        return out


class _Memo(dict):
    """Values of a function, kept."""

    def __init__(self, of):
        super().__init__()
        self.of = of

    def __missing__(self, key):
        value = self[key] = self.of(key)
        return value


def tokenise(docs: DataFrame, path: str, end_id: int = END_ID, forget: bool = False) -> DataFrame:
    """doc_id, source, block (the task), inner (tokens of the source before it in the block), n (ids with the end), ids (binary, uint16).

    forget: caches are smaller and end with the task. Each worker of an executor has caches of its own, beside a heap that earlier stages have filled.
    """

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from encoded(batches)
        finally:
            if forget:
                _forget()

    def encoded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        encode, block, end = _encoder(path), TaskContext.get().partitionId(), np.array([end_id], "<u2").tobytes()
        served: dict[str, int] = {}
        for whole in batches:
            for k in range(0, whole.num_rows, 256):
                batch = whole.slice(k, 256)
                ids = [x + end for x in encode([x or "" for x in batch.column(2).to_pylist()], LEAN if forget else (CACHE, WORDS))]
                inner = []
                for source, x in zip(batch.column(1).to_pylist(), ids, strict=True):
                    inner.append(served.get(source, 0))
                    served[source] = inner[-1] + len(x) // 2
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0), batch.column(1), pa.array([block] * len(ids), pa.int64()), pa.array(inner, pa.int64()), pa.array([len(x) // 2 for x in ids], pa.int64()), pa.array(ids, pa.binary())],
                    names=["doc_id", "source", "block", "inner", "n", "ids"],
                )

    given = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("source").cast("string"), F.lit("")).alias("source"), "text")
    return given.mapInArrow(each, "doc_id long, source string, block long, inner long, n long, ids binary")


class Cuts:
    """What every queue has been served at the end of a window, as a function of the window alone."""

    def __init__(self, tokens: list[int], weights: list[float], length: int):
        self.n, self.w, self.length = np.array(tokens, np.int64), np.array(weights, float) / (sum(weights) or 1), length
        self.total = int(self.n.sum())
        # served(t) without rounding is linear between the times at which queues run dry
        self.dry = np.r_[0.0, np.sort(self.n / self.w)] if len(self.n) else np.zeros(1)
        self.level = np.array([np.minimum(self.n, self.w * t).sum() for t in self.dry])

    def served(self, t: np.ndarray) -> np.ndarray:
        return np.minimum(self.n, np.floor(t[:, None] * self.w + 0.5).astype(np.int64))

    def at(self, windows: np.ndarray) -> np.ndarray:
        """A row of tokens served for each window (those of the windows before it); rows add up to length * window, the total at most."""
        goal = np.clip(windows * self.length, 0, self.total)
        rough = np.interp(goal, self.level, self.dry)
        live = np.maximum((self.w * (self.n > rough[:, None] * self.w)).sum(axis=1), self.w.min())
        reach = (len(self.w) + 2) / live
        low, high = np.maximum(rough - reach, 0), rough + reach
        for _ in range(24):
            middle = (low + high) / 2
            early = self.served(middle).sum(axis=1) <= goal
            low, high = np.where(early, middle, low), np.where(early, high, middle)
        least, most = self.served(low), self.served(high)
        # tokens that fall due together are served in the order of the queues
        left = goal - least.sum(axis=1)
        room = np.cumsum(most - least, axis=1)
        out = least + np.clip(left[:, None] - (room - (most - least)), 0, most - least)
        out[goal >= self.total] = self.n
        out[goal <= 0] = 0
        return out

    def spans(self, queue: np.ndarray, at: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, ...]:
        """Row, start (in the document), size, window and offset of every piece of documents that stand at ``at`` in their queues."""
        def about(place: np.ndarray) -> np.ndarray:
            return np.interp((place + 0.5) / self.w[queue], self.dry, self.level).astype(np.int64) // self.length

        first, last = np.maximum(about(at) - 1, 0), about(at + n - 1) + 1
        count = last - first + 1
        row = np.repeat(np.arange(len(at)), count)
        window = np.arange(len(row)) - np.repeat(np.cumsum(count) - count - first, count)
        names, place = np.unique(np.r_[window, window + 1], return_inverse=True)
        cuts = self.at(names)
        begin, end, q = cuts[place[: len(row)]], cuts[place[len(row) :]], queue[row]
        here = np.arange(len(row))
        before = np.cumsum(end - begin, axis=1)[here, q] - (end - begin)[here, q]
        lo, hi = np.maximum(at[row], begin[here, q]), np.minimum((at + n)[row], end[here, q])
        keep = hi > lo
        return row[keep], (lo - at[row])[keep], (hi - lo)[keep], window[keep], (before + lo - begin[here, q])[keep]


def queues(tokens: DataFrame, length: int, targets: dict[str, float] | None = None, power: float = 1.0) -> tuple[DataFrame, Cuts]:
    """Rows source, block, queue (a number) and before (tokens of the source in earlier blocks), and the cuts; tokens: source, block, n."""
    sums = materialise(tokens.groupBy("source", "block").agg(F.sum("n").alias("n")), "sums")
    most = length // 4
    found = [(r.source, int(r.n)) for r in sums.groupBy("source").agg(F.sum("n").alias("n")).orderBy("source").limit(most + 1).collect()]
    if len(found) > most:
        raise ValueError(f"windows of {length} tokens hold at most {most} queues; group the sources")
    weights = [float(n) ** power for _, n in found]
    if targets:
        weights = [float(targets.get(s, min(targets.values()))) for s, _ in found]
    number = {s: i for i, (s, _) in enumerate(found)}
    named = tokens.sparkSession.createDataFrame(list(number.items()), "source string, queue int")
    order = Window.partitionBy("source").orderBy("block").rowsBetween(Window.unboundedPreceding, 0)
    before = sums.select("source", "block", (F.sum("n").over(order) - F.col("n")).alias("before")).join(F.broadcast(named), "source")
    small = len(found) * sums.select("block").distinct().count() <= BROADCAST_ROWS
    return (F.broadcast(before) if small else before), Cuts([n for _, n in found], weights, length)


def schedule(lengths: DataFrame, length: int = LENGTH, targets: dict[str, float] | None = None, power: float = 1.0) -> DataFrame:
    """row, start, size, sequence_id, offset for rows (row, doc_id, source, n), queued by doc_id inside blocks of hashed ids."""
    blocks = max(1, math.isqrt(lengths.count()))
    inside = Window.partitionBy("source", "block").orderBy("doc_id", "row").rowsBetween(Window.unboundedPreceding, 0)
    docs = lengths.withColumn("block", F.pmod(F.xxhash64("doc_id", "row"), F.lit(blocks))).withColumn("inner", F.sum("n").over(inside) - F.col("n"))
    before, cuts = queues(docs, length, targets, power)

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            name, queue, at, n = (np.asarray(c) for c in batch.columns)
            row, *columns = cuts.spans(queue, at, n)
            yield pa.RecordBatch.from_arrays([pa.array(name[row]), *map(pa.array, columns)], names=["row", "start", "size", "sequence_id", "offset"])

    placed = docs.join(before, ["source", "block"]).select("row", "queue", (F.col("before") + F.col("inner")).alias("at"), "n")
    return placed.mapInArrow(each, "row long, start long, size long, sequence_id long, offset long")


PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def pack(docs: DataFrame, path: str, length: int = LENGTH, targets: dict[str, float] | None = None, power: float = 1.0, with_ids: bool = False, forget: bool = False) -> DataFrame:
    """A row for each piece; with_ids adds its ids (array of int). forget: workers keep less in their token caches and nothing after a task, for the sake of other work."""
    tokens = materialise(tokenise(docs, path, forget=forget), "tokens")
    before, cuts = queues(tokens.select("source", "block", "n"), length, targets, power)
    placed = tokens.join(before, ["source", "block"]).select("doc_id", "ids", "queue", (F.col("before") + F.col("inner")).alias("at"), "n")
    names = [x.split()[0] for x in PIECES.split(", ")] + ["ids"] * with_ids

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for k in range(0, whole.num_rows, 512):
                batch = whole.slice(k, 512)
                queue, at, n = (np.asarray(batch.column(i)) for i in (2, 3, 4))
                row, start, size, sequence, offset = cuts.spans(queue, at, n)
                per_doc, spans = np.bincount(row, minlength=len(n)), list(zip((4 * start).tolist(), (4 * (start + size)).tolist(), strict=True))
                marks, parts, done, crc = [], [], 0, zlib.crc32
                for ids, m in zip(batch.column(1), per_doc.tolist(), strict=True):
                    wide = np.frombuffer(ids.as_buffer(), "<u2").astype("<u4")
                    view, mine = memoryview(wide).cast("B"), spans[done : done + m]
                    marks += [crc(view[a:b]) for a, b in mine]
                    if with_ids:
                        parts += [wide[a // 4 : b // 4].tolist() for a, b in mine]
                    done += m
                columns = [batch.column(0).take(pa.array(row)), *map(pa.array, (start, size)), pa.array(marks, pa.int64()), *map(pa.array, (n[row], sequence, offset))]
                yield pa.RecordBatch.from_arrays([*columns, *[pa.array(parts, pa.list_(pa.int32()))] * with_ids], names=names)

    return placed.mapInArrow(each, PIECES + (", ids array<int>" if with_ids else ""))


def _path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op6_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(read(spark, sf_dir, "documents"), _path(), power=POWER)


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack(docs, _path(), power=POWER, forget=True)
