"""SentencePiece encoding by forward filtering and backward sampling, and lossless decoding.

A text with a space put before it is cut into units (spaces with the characters after them, or a line feed); no piece of
the vocabulary crosses a unit's border, so the piece lattice falls apart into one lattice for each unit. The forward pass sums,
for each place, the weights of all segmentations up to it; it runs once for each distinct unit of a batch, for all of them at
a time. The backward pass draws for each occurrence, from its end, a last piece in proportion to the weights before it.
Random numbers are hashes of the row key and the place in the text, so a row gets the same segmentation in any batch,
partition or retry. Characters without a piece are spelled in byte pieces, and so is the character that pieces use for a
space, so decoding gives back every text.

The vocabulary is of the merge kind, whose scores are ranks; a piece of rank r weighs (r + 10) ** -sharpness, a Zipf law.

Edge cases: a null or empty text is a single space, as for the library; unpaired surrogates become question marks; rows that repeat a key and a text get the same
ids; a null key has the seed of 0; an empty table gives an empty result. Other columns are never looked at.
"""

from __future__ import annotations

import re
import zlib
from collections import defaultdict
from collections.abc import Iterator
from itertools import count

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lincompress.llm.common import read

SHARPNESS, BATCH = 1.0, 6 << 20
#: Weights are scaled by this factor for each byte, so that long units neither vanish nor overflow.
PER_BYTE = 12.0
#: Units beyond this number of bytes take their forward pass in logarithms.
LONG = 160
_BASE = np.uint64(0x100000001B3)


def _random(seed: np.ndarray, place: np.ndarray) -> np.ndarray:
    """Numbers in [0, 1) from a seed and a place (splitmix64)."""
    with np.errstate(over="ignore"):
        x = seed + place.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return ((x ^ (x >> np.uint64(31))) >> np.uint64(11)).astype(np.float64) * 2.0**-53


class Vocabulary:
    """Pieces as bytes with their weights; by length, sorted hashes of whole pieces and of their prefixes."""

    def __init__(self, pieces: list[tuple[int, bytes, float]], byte_ids: dict[int, int]):
        self.text: dict[int, bytes] = {i: b for i, b, _ in pieces} | {i: bytes([b]) for b, i in byte_ids.items()}
        self.of = {b: (i, w) for i, b, w in pieces}
        least = min((w for _, _, w in pieces), default=1.0)
        self.byte_weight, self.byte_ids = least, np.array([byte_ids.get(b, -1) for b in range(256)])
        self.longest = max((len(b) for _, b, _ in pieces), default=0)
        known: dict[int, dict[int, tuple[int, float]]] = defaultdict(dict)
        for i, b, w in pieces:
            h = 0
            for k, c in enumerate(b, 1):
                h = (h * int(_BASE) + c + 1) % 2**64
                known[k].setdefault(h, (-1, 0.0))
            known[len(b)][h] = (i, w)
        # by length: sorted hashes of all prefixes, with the piece (or -1) and its weight
        self.known = {}
        for k, v in known.items():
            hashes = sorted(v)
            self.known[k] = (np.array(hashes, np.uint64), np.array([v[h][0] for h in hashes], np.int32), np.array([v[h][1] for h in hashes]))
        feed = b"\n" if not any(b"\n" in b for _, b, _ in pieces) else b""
        self.units = re.compile(rb" +[^ \n]*|\n|[^ \n]+" if feed else rb" +[^ ]*|[^ ]+").findall
        size = max(self.text, default=-1) + 1
        parts = [self.text.get(i, b"") for i in range(size)]
        self.flat = np.frombuffer(b"".join(parts), np.uint8)
        self.sizes = np.array([len(x) for x in parts], np.int64)
        self.starts = np.cumsum(self.sizes) - self.sizes

    @classmethod
    def load(cls, path: str, sharpness: float = SHARPNESS) -> Vocabulary:
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        pieces, byte_ids = [], {}
        for i in range(sp.get_piece_size()):
            if sp.is_byte(i):
                byte_ids[int(sp.id_to_piece(i)[3:5], 16)] = i
            elif not (sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i)):
                pieces.append((i, sp.id_to_piece(i).replace("▁", " ").encode(), (10.0 - sp.get_score(i)) ** -sharpness))
        return cls(pieces, byte_ids)

    def edges(self, data: np.ndarray, unit_end: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Start, length, piece and weight of every edge in the joined bytes of units; unit_end: end of each byte's unit."""
        first = (data & 0xC0) != 0x80
        at = np.flatnonzero(first).astype(np.int32)
        out = []
        alone = np.zeros(len(data), bool)
        width = np.diff(np.r_[at, len(data)])
        width_at = np.zeros(len(data), np.int32)
        width_at[at] = width
        h = np.zeros(len(at), np.uint64)
        with np.errstate(over="ignore"):
            for k in range(1, self.longest + 1):
                fits = at + k <= unit_end[at]
                at, h = at[fits], h[fits]
                h = h * _BASE + data[at + k - 1].astype(np.uint64) + np.uint64(1)
                hashes, ids, weights = self.known[k]
                where = np.searchsorted(hashes, h)
                where[where == len(hashes)] = 0
                live = np.flatnonzero(hashes[where] == h)
                at, h, where = at[live], h[live], where[live]
                if not len(at):
                    break
                hit = np.flatnonzero(ids[where] >= 0)
                start, where = at[hit], where[hit]
                out.append((start, np.full(len(start), k, np.int32), ids[where], weights[where]))
                alone[start[width_at[start] == k]] = True
        lost = np.flatnonzero(first & ~alone)
        if len(lost):
            w = width_at[lost]
            at = np.repeat(lost - (np.cumsum(w) - w), w) + np.arange(int(w.sum()))
            out.append((at, np.ones(len(at), np.int32), self.byte_ids[data[at]], np.full(len(at), self.byte_weight)))
        if not out:
            return tuple(np.zeros(0, np.int64) for _ in range(3)) + (np.zeros(0),)
        return tuple(np.concatenate(x) for x in zip(*out, strict=True))

    def decode(self, ids: np.ndarray) -> bytes:
        """The bytes that pieces stand for."""
        size = self.sizes[ids]
        at = np.repeat(self.starts[ids] - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))
        return self.flat[at].tobytes()


def _forward(units: list[bytes], vocabulary: Vocabulary):
    """For each node with an edge into it: edges sorted by end, their starts, pieces, probabilities and running sums."""
    sizes = np.array([len(u) for u in units], np.int64)
    data = np.frombuffer(b"".join(units), np.uint8)
    starts = np.cumsum(sizes) - sizes
    owner = np.repeat(np.arange(len(units), dtype=np.int32), sizes)
    begin, length, piece, weight = vocabulary.edges(data, (starts + sizes).astype(np.int32)[owner])
    unit = owner[begin]
    # a unit has one node more than bytes: node of byte b of unit u is b + u
    source = begin.astype(np.int32) + unit
    length = length.astype(np.int32)
    target = source + length
    depth = target - unit - starts.astype(np.int32)[unit]
    deepest = int(depth.max()) if len(depth) else 0
    depth = depth.astype(np.uint16 if deepest < 65536 else np.int64)
    del begin, owner
    # the edges of one length are in order already, so a merging sort by end is cheap, and one by small depths is by digits
    order = np.argsort(target, kind="stable")
    source, target, piece, length, weight, depth = source[order], target[order], piece[order].astype(np.int32), length[order], weight[order], depth[order]
    unit = unit[order] if sizes.max(initial=0) > LONG else None
    order = np.argsort(depth, kind="stable")
    scaled = weight * PER_BYTE ** np.arange(vocabulary.longest + 2.0)[length]
    first = starts + np.arange(len(units))
    total = np.zeros(len(data) + len(units))
    total[first] = 1.0
    from_node, to_node, scaled, depth = source[order], target[order], scaled[order], depth[order]
    logs = None
    if unit is not None:
        logs, log_weight, long = np.full(len(total), -np.inf), np.log(weight)[order], (sizes[unit] > LONG)[order]
        logs[first] = 0.0
    del weight, unit
    by_depth = np.zeros(len(source))
    cuts = np.flatnonzero(np.r_[True, depth[1:] != depth[:-1], True]) if len(depth) else np.zeros(1, int)
    for a, b in zip(cuts[:-1], cuts[1:], strict=True):
        t = to_node[a:b]
        group = np.flatnonzero(np.r_[True, t[1:] != t[:-1]])
        spread = np.diff(np.r_[group, len(t)])
        if depth[a] <= LONG:
            x = total[from_node[a:b]] * scaled[a:b]
            s = np.add.reduceat(x, group)
            total[t[group]] = s
            s = np.repeat(s, spread)
            by_depth[a:b] = np.divide(x, s, out=np.zeros(b - a), where=s > 0)
        if logs is not None:
            x = logs[from_node[a:b]] + log_weight[a:b]
            m = np.maximum.reduceat(x, group)
            e = np.exp(x - np.repeat(m, spread))
            s = np.add.reduceat(e, group)
            logs[t[group]] = m + np.log(s)
            by_depth[a:b] = np.where(long[a:b], e / np.repeat(s, spread), by_depth[a:b])
    share = np.empty_like(by_depth)
    share[order] = by_depth
    del from_node, to_node, scaled, by_depth, order
    group = np.flatnonzero(np.r_[True, target[1:] != target[:-1]]) if len(target) else np.zeros(0, int)
    running = np.cumsum(share)
    running -= np.repeat(running[group] - share[group], np.diff(np.r_[group, len(target)]))
    return first, sizes, source, target, piece, share, length, running


def encode_batch(texts: list[bytes], keys: np.ndarray, vocabulary: Vocabulary) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ids of all texts end to end, ids of each text, and each text's log-probability under the sampler."""
    names: defaultdict[bytes, int] = defaultdict(count().__next__)
    found = [vocabulary.units(b" " + t) for t in texts]
    per_text = np.array([len(x) for x in found], np.int64)
    which = np.fromiter((names[u] for x in found for u in x), np.int64, int(per_text.sum()))
    node_first, sizes, source, target, piece, share, length, running = _forward(list(names), vocabulary)
    cuts = np.searchsorted(target, np.arange(len(node_first) + int(sizes.sum()) + 1)).astype(np.int32)
    text_of = np.repeat(np.arange(len(texts)), per_text)
    end = np.cumsum(sizes[which])
    text_size = np.array([len(t) + 1 for t in texts], np.int64)
    text_start = np.cumsum(text_size) - text_size
    chosen = np.full(int(text_size.sum()) + 1, -1, np.int32)
    with np.errstate(over="ignore"):
        seed = ((keys.astype(np.uint64) + np.uint64(0x632BE59BD9B4E019)) * np.uint64(0xD1342543DE82EF95))[text_of]
    place, node, stop = end - text_start[text_of], node_first[which] + sizes[which], node_first[which]
    while len(node):
        u, e, last = _random(seed, place), cuts[node], cuts[node + 1] - 1
        behind = np.flatnonzero((running[e] <= u) & (e < last))
        while len(behind):
            e[behind] += 1
            now = e[behind]
            behind = behind[(running[now] <= u[behind]) & (now < last[behind])]
        chosen[end] = e
        node, step = source[e], length[e]
        more = np.flatnonzero(node > stop)
        step = step[more]
        node, stop, end, place, seed = node[more], stop[more], end[more] - step, place[more] - step, seed[more]
    there = chosen >= 0
    counts = np.add.reduceat(there[1:].astype(np.int64), text_start) if len(texts) else np.zeros(0, np.int64)
    edge = chosen[there]
    begins = np.cumsum(counts) - counts
    return piece[edge], counts, np.add.reduceat(np.log(share[edge]), begins) if len(texts) else np.zeros(0)


def _loaded(path: str, sharpness: float) -> Vocabulary:
    import sys
    import types

    shelf = sys.modules.setdefault("_piece_shelf", types.ModuleType("_piece_shelf")).__dict__
    if (path, sharpness) not in shelf:
        shelf[path, sharpness] = Vocabulary.load(path, sharpness)
    return shelf[path, sharpness]


ENCODED = "doc_id long, n_tokens long, ids binary, ids_crc32 long, log_prob double, lossless boolean"


def encode(docs: DataFrame, path: str, sharpness: float = SHARPNESS, with_ids: bool = True) -> DataFrame:
    """Sampled ids (uint16, little-endian), their crc32 (as uint32), and whether they decode to the text; docs: doc_id (the row key), text."""
    schema = ENCODED if with_ids else ENCODED.replace("ids binary, ", "")

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary = _loaded(path, sharpness)
        for batch in batches:
            rows, texts, size = [], [], 0
            for k, text in enumerate(batch.column(1)):
                rows.append(k)
                texts.append((text.as_py() or "").encode("utf-8", "replace"))
                size += len(texts[-1])
                if size > BATCH or k + 1 == batch.num_rows:
                    yield out(vocabulary, batch.column(0).take(pa.array(rows)), texts)
                    rows, texts, size = [], [], 0

    def out(vocabulary: Vocabulary, doc_ids: pa.Array, texts: list[bytes]) -> pa.RecordBatch:
        keys = np.array(doc_ids.fill_null(0).to_pylist(), np.int64)
        ids, counts, logs = encode_batch(texts, keys, vocabulary)
        cuts = np.r_[0, np.cumsum(counts)]
        back, at, same = vocabulary.decode(ids), 0, []
        for t, a, b in zip(texts, cuts[:-1], cuts[1:], strict=True):
            n = int(vocabulary.sizes[ids[a:b]].sum())
            same.append(back[at : at + n] == b" " + t)
            at += n
        parts = [ids[a:b] for a, b in zip(cuts[:-1], cuts[1:], strict=True)]
        crc = [zlib.crc32(p.astype("<u4").tobytes()) for p in parts]
        columns = [doc_ids, pa.array(counts), pa.array([p.astype("<u2").tobytes() for p in parts], pa.binary()), pa.array(crc, pa.int64()), pa.array(logs), pa.array(same)]
        names = [x.split()[0] for x in ENCODED.split(", ")]
        return pa.RecordBatch.from_arrays([c for c, n in zip(columns, names, strict=True) if with_ids or n != "ids"], names=[n for n in names if with_ids or n != "ids"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(each, schema)


def decode(encoded: DataFrame, path: str) -> DataFrame:
    """doc_id and text for rows of doc_id and ids."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary = _loaded(path, SHARPNESS)
        for batch in batches:
            texts = [vocabulary.decode(np.frombuffer(x.as_py() or b"", "<u2").astype(np.int64))[1:].decode("utf-8", "replace") for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], names=["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(each, "doc_id long, text string")


def _path() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def op2_piece_sampling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode(read(spark, sf_dir, "documents"), _path(), with_ids=False)
