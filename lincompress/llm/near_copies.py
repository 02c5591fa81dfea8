"""Near copies for the pipeline: shingles of five words, similarity 0.8 or more, on top of the SimHash operator.

Two texts with a Jaccard similarity of 0.8 differ in about ten of 64 SimHash bits, far beyond what links at 2 bits can reach.
So each text gets, beside the fingerprint of all its shingles (linked through anchor points), fingerprints of eight samples of
one shingle each, the least under eight seeded orders. A sample is shared with a probability of the similarity, so texts at 0.8
share none of the eight once in 400,000. Texts that share a sample meet in a group, and every pair of a group is either in one
component or compared exactly:

1. Each text that shares two samples with the group's head, drawn by lot for each sample, is compared with it. These links and
   those from the anchors make the first components; they only save work.
2. Groups with more than one component are cut into cells of texts of like size, and large cells into pairs of blocks. In a
   cell, pairs of different components are bounded: two texts share at most the sum, over 256 classes of shingles, of the
   lesser count. Texts of pairs that could reach the similarity bring their shingles, and the cell compares them exactly.

Links between the first components join those to the last ones. No step makes a row for each pair of a group.

Edge cases: equal texts are one node; a null text counts as empty, and texts without words are one group; texts of one to four
words have the one shingle of all their words; of a component the smallest id stays (an id that is null is the largest), of
repeated rows one; an empty table gives an empty result. Other columns are kept, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lincompress.llm import components, simhash
from lincompress.llm.common import materialise, numbered

WIDTH, SIMILARITY, SAMPLES = 5, 0.8, 8
#: Samples that a text must share with a head to be compared with it first; all other pairs that share one meet in cells.
SHARED = 2
#: Classes of shingles that are counted, and shingles of a block: two blocks of a cell meet in one row.
CLASSES, BLOCK = 256, 50_000
LAST = (1 << 63) - 1
#: Rows to drop up to this number are broadcast (16 bytes each); more are joined by shuffle.
BROADCAST_ROWS = 500_000


def shingles(text: str | None, width: int = WIDTH) -> np.ndarray:
    """Hashes of all shingles, repeats included; none without words."""
    import xxhash

    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    n = max(1, len(words) - width + 1)
    lengths = np.fromiter(map(len, words), np.int64, len(words)) + 1
    ends = np.cumsum(lengths)
    starts, stops = (ends - lengths)[:n].tolist(), (ends[min(width, len(words)) - 1 :] - 1).tolist()
    line, digest = b" ".join(words), xxhash.xxh64_digest
    return np.frombuffer(b"".join([digest(line[a:b], simhash.SEED) for a, b in zip(starts, stops, strict=True)]), ">u8").astype(np.uint64)


def _fingerprint(marks: np.ndarray) -> int:
    if not len(marks):
        return 0
    votes, big = np.zeros(64, np.int64), marks.astype(">u8").view(np.uint8).reshape(-1, 8)
    for k in range(0, len(marks), 8192):
        votes += np.unpackbits(big[k : k + 8192], axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * votes > len(marks)).tobytes(), "big", signed=True)


def prints(docs: DataFrame, width: int = WIDTH, samples: int = SAMPLES) -> DataFrame:
    """id, node, fp, least (a value for each sample), n (distinct shingles) and sketch (their counts by class, 255 for more); docs: id, node, text."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rng = np.random.default_rng(91)
        odd, shift = rng.integers(0, 1 << 63, samples, np.uint64) * np.uint64(2) + np.uint64(1), rng.integers(0, 1 << 63, samples, np.uint64)
        for batch in batches:
            fps, least, n, sketch = [], [], [], []
            for text in batch.column(2):
                marks = shingles(text.as_py(), width)
                fps.append(_fingerprint(marks))
                marks = np.unique(marks)
                n.append(len(marks))
                sketch.append(np.minimum(np.bincount((marks % np.uint64(CLASSES)).astype(np.int64), minlength=CLASSES), 255).astype(np.uint8).tobytes())
                with np.errstate(over="ignore"):
                    least.append([] if not len(marks) else [int((marks * a + b).min().view(np.int64)) for a, b in zip(odd, shift, strict=True)])
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(fps, pa.int64()), pa.array(least, pa.list_(pa.int64())), pa.array(n, pa.int64()), pa.array(sketch, pa.binary())], names=["id", "node", "fp", "least", "n", "sketch"])

    return docs.select("id", "node", "text").mapInArrow(each, "id long, node long, fp long, least array<long>, n long, sketch binary")


def _sets(nodes: DataFrame, docs: DataFrame, found: DataFrame, width: int) -> DataFrame:
    """n and set (sorted hashes of the distinct shingles) for each of the distinct nodes."""
    # of equal texts one is enough
    nodes = materialise(found.select("id", "node").join(nodes, "node").groupBy("node").agg(F.min("id").alias("id")), "compared")
    nodes = F.broadcast(nodes) if nodes.count() <= BROADCAST_ROWS else nodes.hint("shuffle_hash")

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [np.unique(shingles(t.as_py(), width)).astype("<u8").tobytes() for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found, pa.binary())], names=["n", "set"])

    texts = docs.join(nodes, ["id", "node"], "left_semi").select("node", "text").mapInArrow(sets, "n long, set binary")
    return materialise(texts.dropDuplicates(["n"]), "sets")


def _similar(pairs: DataFrame, docs: DataFrame, found: DataFrame, width: int, similarity: float) -> DataFrame:
    """The pairs (a, b) of nodes whose texts are similar enough, compared exactly."""
    texts = _sets(pairs.select(F.explode(F.array("a", "b")).alias("node")).distinct(), docs, found, width)
    met = pairs.join(texts.select(F.col("n").alias("a"), F.col("set").alias("x")), "a").join(texts.select(F.col("n").alias("b"), F.col("set").alias("y")), "b")

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            good = []
            for x, y in zip(batch.column(2), batch.column(3), strict=True):
                x, y = np.frombuffer(x.as_buffer(), "<u8"), np.frombuffer(y.as_buffer(), "<u8")
                both = len(np.intersect1d(x, y, assume_unique=True))
                good.append(both >= similarity * (len(x) + len(y) - both))
            keep = pa.array(good, pa.bool_())
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(keep), batch.column(1).filter(keep)], names=["a", "b"])

    return met.select("a", "b", "x", "y").mapInArrow(judge, "a long, b long")


def _meet(sampled: DataFrame) -> DataFrame:
    """node and head of each group of two or more that share a value under j; heads differ from j to j."""
    lot = F.struct(F.xxhash64("node", "j").alias("lot"), "node")
    heads = sampled.groupBy("j", "value").agg(F.min(lot)["node"].alias("head"), F.count(F.lit(1)).alias("n")).where("n > 1")
    return sampled.join(heads, ["j", "value"]).select("node", "head")


CELL = ["j", "value", "band", "low", "high"]


def _cells(sampled: DataFrame, roots: DataFrame, similarity: float) -> DataFrame:
    """The texts of each pair of blocks, with root, own (of the upper band) and part; sampled: node, j, value, n; roots: node, root."""
    tagged = sampled.join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    mixed = lambda *key: tagged.groupBy(*key).agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.sum("n").alias("sum")).where("lo < hi")
    tagged = materialise(tagged.join(mixed("j", "value").select("j", "value"), ["j", "value"]), "mixed")
    # sizes of similar texts differ by 1 / similarity at most: the same band or neighbours, with some room for rounding
    band = F.floor(F.log(F.col("n")) / (1.01 * np.log(1 / similarity)))
    tagged = tagged.withColumn("at", band).withColumn("band", F.explode(F.array(F.col("at"), F.col("at") + 1))).withColumn("own", F.col("at") == F.col("band")).drop("at")
    blocks = mixed("j", "value", "band").select("j", "value", "band", F.ceil(F.col("sum") / BLOCK).cast("int").alias("blocks"))
    placed = tagged.join(blocks, ["j", "value", "band"]).withColumn("part", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    other = placed.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    return other.select("j", "value", "band", F.least("part", "other").alias("low"), F.greatest("part", "other").alias("high"), "node", "root", "own", "part", "n")


def _each_cell(cells: DataFrame, payload: str, judge, schema: str) -> DataFrame:
    """What judge returns for each cell: columns after the cell's key; judge gets node, root, n, may (which pairs are to be compared) and the payloads."""
    rows = cells.groupBy(*CELL).agg(F.collect_list(F.struct("node", "root", "own", "part", "n", F.col(payload).alias("payload"))).alias("members")).where(F.size("members") > 1)
    n_key = len(CELL)

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            members, at, out, sizes = batch.column(n_key).flatten(), 0, [], []
            node, root, own, part, n = (members.field(k).to_numpy(zero_copy_only=False) for k in range(5))
            for size in batch.column(n_key).value_lengths().to_pylist():
                here = slice(at, at := at + size)
                o, p, r = own[here], part[here], root[here]
                may = (r[:, None] != r) & (o[:, None] | o)
                if p.min() != p.max():
                    may &= p[:, None] != p
                got = judge(node[here], r, n[here], np.triu(may), members.field(5).slice(here.start, size)) if may.any() else np.zeros((0, len(schema.split(","))), np.int64)
                out.append(got)
                sizes.append(len(got))
            rows = np.concatenate(out) if out else np.zeros((0, len(schema.split(","))), np.int64)
            keys = [np.repeat(batch.column(k).to_numpy(), sizes) for k in range(n_key)]
            yield pa.RecordBatch.from_arrays([*map(pa.array, keys), *[pa.array(c) for c in rows.T.copy()]], names=[*CELL, *[x.split()[0] for x in schema.split(", ")]])

    kinds = dict(cells.dtypes)
    return rows.mapInArrow(each, ", ".join(f"{c} {kinds[c]}" for c in CELL) + ", " + schema)


def _exact(cells: DataFrame, nodes: DataFrame, docs: DataFrame, found: DataFrame, width: int, similarity: float) -> DataFrame:
    """Links (a, b) between roots: a forest for each cell of all pairs of different roots that are similar enough."""

    def could(node, root, n, may, sketches):
        counts = np.frombuffer(b"".join(sketches.to_pylist()), np.uint8).reshape(len(node), CLASSES)
        full, marked = (counts == 255).any(axis=1), np.zeros(len(node), bool)
        for i in np.flatnonzero(may.any(axis=1)):
            js = np.flatnonzero(may[i])
            js = js[(np.minimum(n[i], n[js]) >= similarity * np.maximum(n[i], n[js]) - 1e-6)]
            most = np.minimum(counts[i], counts[js]).sum(axis=1, dtype=np.int64)
            good = js[(most * (1 + similarity) >= similarity * (n[i] + n[js]) - 1e-6) | full[i] | full[js]]
            if len(good):
                marked[i] = marked[good] = True
        return node[marked][:, None]

    marked = materialise(_each_cell(cells.join(nodes.select("node", "sketch"), "node"), "sketch", could, "node long"), "marked")
    texts = _sets(marked.select("node").distinct(), docs, found, width)

    def joined(node, root, n, may, sets):
        marks = [np.frombuffer(x.as_buffer(), "<u8") for x in sets]
        n = np.array([len(x) for x in marks], np.int64)
        values, which, times = np.unique(np.concatenate(marks), return_inverse=True, return_counts=True)
        shared = times[which] > 1  # the others are in no pair
        column, row = (np.cumsum(times > 1) - 1)[which[shared]], np.repeat(np.arange(len(n)), n)[shared]
        order = np.argsort(column, kind="stable")
        column, row, both = column[order], row[order], np.zeros((len(n), len(n)), np.float32)
        for k in range(0, int(column[-1]) + 1 if len(column) else 0, 4096):
            a, b = np.searchsorted(column, (k, k + 4096))
            table = np.zeros((len(n), 4096), np.float32)
            table[row[a:b], column[a:b] - k] = 1
            both += table @ table.T
        both = both.astype(np.int64)
        first, links = {}, []

        def find(x):
            while x in first:
                x = first[x]
            return x

        for i, j in np.argwhere(may & (both >= similarity * (n[:, None] + n - both))).tolist():
            x, y = find(int(root[i])), find(int(root[j]))
            if x != y:
                first[max(x, y)] = min(x, y)
                links.append((x, y))
        return np.array(links, np.int64).reshape(-1, 2)

    again = marked.join(cells, [*CELL, "node"]).join(texts.select(F.col("n").alias("node"), "set"), "node")
    return _each_cell(again, "set", joined, "a long, b long").select("a", "b").distinct()


def groups(docs: DataFrame, width: int = WIDTH, similarity: float = SIMILARITY, samples: int = SAMPLES) -> DataFrame:
    """id, node, root for rows of id, node, text: root names the component of near copies."""
    found = materialise(prints(docs, width, samples), "prints")
    nodes = materialise(found.dropDuplicates(["node"]).select("node", "fp", "least", "n", "sketch"), "nodes")
    by_print = nodes.groupBy("fp").agg(F.min("node").alias("first"))
    near = simhash.links(by_print.select("fp"))
    first = by_print.select("fp", "first")
    equal = nodes.join(first, "fp").select(F.col("node").alias("a"), F.col("first").alias("b"))
    linked = near.join(first.select(F.col("fp").alias("a"), F.col("first").alias("x")), "a").join(first.select(F.col("fp").alias("b"), F.col("first").alias("y")), "b").select(F.col("x").alias("a"), F.col("y").alias("b"))
    sampled = nodes.select("node", "n", F.posexplode("least").alias("j", "value"))
    pairs = _meet(sampled).where("node <> head").select(F.least("node", "head").alias("a"), F.greatest("node", "head").alias("b")).distinct()
    least = nodes.select("node", "least")
    pairs = pairs.join(least.select(F.col("node").alias("a"), F.col("least").alias("x")), "a").join(least.select(F.col("node").alias("b"), F.col("least").alias("y")), "b")
    shared = F.size(F.filter(F.zip_with("x", "y", lambda x, y: x == y), lambda e: e))
    pairs = materialise(pairs.where(shared >= SHARED).select("a", "b"), "pairs")
    edges = _similar(pairs, docs, found, width, similarity).unionAll(linked).unionAll(equal)
    roots = materialise(components.roots(edges), "roots")
    cells = materialise(_cells(sampled, roots, similarity), "cells")
    over = components.roots(_exact(cells, nodes, docs, found, width, similarity)).select(F.col("node").alias("root"), F.col("root").alias("last"))
    named = found.select("id", "node").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    return named.join(over, "root", "left").select("id", "node", F.coalesce("last", "root").alias("root"))


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents without all but the first of each group of near copies."""
    plain = numbered(docs, "doc_id", "text")
    keyed = plain.withColumns({"_near_id": F.coalesce(F.col("doc_id").cast("long"), F.lit(LAST)), "_near_text": F.xxhash64(F.coalesce("text", F.lit("")))})
    found = materialise(groups(keyed.select(F.col("_near_id").alias("id"), F.col("_near_text").alias("node"), "text")), "groups")
    stays = found.groupBy("root").agg(F.min(F.struct("id", "node")).alias("stays"))
    goes = materialise(found.join(stays, "root").where(F.struct("id", "node") != F.col("stays")).select(F.col("id").alias("_near_id"), F.col("node").alias("_near_text")).distinct(), "goes")
    goes = F.broadcast(goes) if goes.count() <= BROADCAST_ROWS else goes.hint("shuffle_hash")
    kept = keyed.join(goes, ["_near_id", "_near_text"], "left_anti")
    if found.groupBy("id", "node").count().where("count > 1").limit(1).count():
        kept = kept.dropDuplicates(["_near_id", "_near_text"])
    return kept.select(*plain.columns).toDF(*docs.columns)
