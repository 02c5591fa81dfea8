"""Language-model scoring with a weighted backoff automaton, spread over the cluster.

The model is of order three: trigrams over bigrams over an add-one unigram model, each smoothed by absolute discounting. The
states of the automaton are the seen histories: two words, one word (the start of a text among them) and the empty history. A
seen n-gram is an arc of its history's state that weighs log10 of its smoothed probability and leads to the longest seen history
that its words end with. Every state has a failure arc to the state of its last word, or to the empty history, that weighs
log10 of ``discount * followers / count``. A text is read from left to right: in its state a token takes the arc, or fails until there is
one (twice at most), and the weights add up to the log-probability. What a token does depends on its state alone, and the
state on the two tokens before, so a chunk's texts are walked together, one step of failing at a time.

The automaton grows with the corpus and fits into no single memory, so each chunk of documents (some MB of text) gets the
states and arcs that it visits, and no others:

1. documents become chunk rows: distinct words as 64-bit hashes, tokens as indexes into them (written once);
2. each chunk sends its distinct words with training counts to shards by hash; a shard adds up, numbers its words, and answers
   each chunk with counts and numbers (4 bytes from here on);
3. each chunk sends its distinct triples (word before, word, word after) with counts as a tree of three levels, cut by the shard of the first
   word. A shard adds up and answers with the counts of triples, the counts and followers of pairs, and those of first words;
4. chunks meet their answers and are walked.

A word or triple is sent once for each chunk however often it occurs. First words with more than ``hot`` tokens (at most 100,000 of
them) are dealt by the pair, pairs of two words that are each more than 1/300 of all tokens by the triple; what shards hold of
those (at most 90,000 pairs) is added up afterwards. Words that collide in 64 bits would be taken for one. Chunks times shards
messages are sent, so ``chunk_bytes`` and ``shard_entries`` should grow with the root of the input beyond some TB.

Edge cases: a null or empty text is the end token only; a null id belongs to the remainder of the empty text; repeated rows
count and score each; without training rows every token is unknown (V = N = 0); an empty table gives an empty result. Other
columns are never looked at.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from itertools import count

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lincompress.llm.common import materialise, read, remainder

MODULUS, HELD, DISCOUNT = 7, 2, 0.75
CHUNK_BYTES, SHARD_ENTRIES = 6 << 20, 1_500_000
HOT_TOKENS, MOST_HOT, MOST_TWICE = 1_000_000, 100_000, 300
#: Stand-ins for the end token and the start of a text; neither can be a word.
END, START = b" ", b"  "


def _pack(x: np.ndarray) -> bytes:
    import zstandard

    return zstandard.ZstdCompressor(level=1).compress(np.ascontiguousarray(x).tobytes())


def _unpack(x: bytes, kind: str) -> np.ndarray:
    import zstandard

    return np.frombuffer(zstandard.ZstdDecompressor().decompress(x), kind)


def _mix(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """64-bit hashes of pairs of 64-bit hashes."""
    with np.errstate(over="ignore"):
        x = a * np.uint64(0x9E3779B97F4A7C15) + (b ^ (b >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(32))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(29))


CHUNK = "chunk long, doc_ids array<long>, held binary, lengths binary, tokens binary, words binary, seen binary, start long, n_words long, n_tokens long"


def chunked(docs: DataFrame, chunk_bytes: int = CHUNK_BYTES) -> DataFrame:
    """Chunk rows of documents; docs: doc_id, text, held. Words are in the order of their hashes; ``start`` is the place of the start."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash
        from pyspark import TaskContext

        next_id = count(TaskContext.get().partitionId() << 32)
        ids: list = []
        held: list[bool] = []
        parts: list[np.ndarray] = []
        size = 0

        def fresh() -> defaultdict:
            d = defaultdict(count().__next__)
            d[END], d[START]
            return d

        words = fresh()

        def row() -> pa.RecordBatch:
            lengths = np.array([len(p) + 1 for p in parts], np.int64)
            tokens = np.zeros(int(lengths.sum()), np.int32)
            ends = np.cumsum(lengths) - 1
            inner = np.ones(len(tokens), bool)
            inner[ends] = False
            tokens[inner] = np.concatenate(parts)
            train = np.repeat(~np.array(held), lengths)
            seen = np.bincount(tokens[train], minlength=len(words))
            seen[1] = int((~np.array(held)).sum())
            hashes = np.frombuffer(b"".join([xxhash.xxh64_digest(w) for w in words]), ">u8").astype("<u8")
            order = np.argsort(hashes)
            place = np.empty(len(order), np.int32)
            place[order] = np.arange(len(order))
            values = [[next(next_id)], [ids], [np.array(held, np.uint8).tobytes()], [_pack(lengths)], [_pack_all(place[tokens])], [_pack_all(np.diff(hashes[order], prepend=np.uint64(0)))], [_pack(seen[order].astype("<i4"))], [int(place[1])], [len(words)], [len(tokens)]]
            kinds = [pa.int64(), pa.list_(pa.int64()), *[pa.binary()] * 5, *[pa.int64()] * 3]
            return pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(values, kinds, strict=True)], names=[x.split()[0] for x in CHUNK.split(", ")])

        for batch in batches:
            for i, text, h in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2).to_pylist(), strict=True):
                data = (text.as_py() or "").encode("utf-8", "replace").lower()
                if parts and size + len(data) > chunk_bytes:
                    yield row()
                    ids, held, parts, size, words = [], [], [], 0, fresh()
                ids.append(i)
                held.append(h)
                split = data.split()
                parts.append(np.fromiter(map(words.__getitem__, split), np.int32, len(split)))
                size += len(data) + 64
        if parts:
            yield row()

    return docs.mapInArrow(each, CHUNK)


def _pack_all(*arrays: np.ndarray) -> bytes:
    """Arrays as one value; bytes of equal weight stand together, which compresses numbers well below their type's range."""
    head = np.array([len(arrays), *map(len, arrays)], "<i8").tobytes()
    columns = [np.ascontiguousarray(x).view(np.uint8).reshape(len(x), x.dtype.itemsize).T.tobytes() for x in arrays]
    return _pack(np.frombuffer(head + b"".join(columns), np.uint8))


def _unpack_all(data: bytes, kinds: list[str]) -> list[np.ndarray]:
    flat, out = _unpack(data, "u1"), []
    sizes, at = np.frombuffer(flat[: 8 * (len(kinds) + 1)].tobytes(), "<i8")[1:], 8 * (len(kinds) + 1)
    for n, kind in zip(sizes.tolist(), kinds, strict=True):
        width = np.dtype(kind).itemsize
        out.append(np.ascontiguousarray(flat[at : at + n * width].reshape(width, n).T).reshape(-1).view(kind))
        at += n * width
    return out


class Grams:
    """A chunk's triples (word before, word, word after) in the order of the words' numbers, cut by shard.

    ``number``: the words' numbers, ascending; ``tokens`` and ``before`` are places in it. ``c3`` and so on are places of distinct triples, ``i3``
    of each token's triple; pairs and first words are runs of them. The word after an end is the start, which is no token.
    """

    def __init__(self, c: dict, number: np.ndarray, hot: np.ndarray, twice: np.ndarray, shards: int):
        (tokens,), self.lengths = _unpack_all(c["tokens"], ["<i4"]), _unpack(c["lengths"], "<i8")
        self.order = np.argsort(number, kind="stable")
        self.number, rank = number[self.order], np.empty(len(number), np.int64)
        rank[self.order] = np.arange(len(number))
        self.tokens, size = rank[tokens], len(number)
        ends = np.cumsum(self.lengths)
        self.begin = ends - self.lengths
        self.before, after = np.empty_like(self.tokens), np.empty_like(self.tokens)
        self.before[1:], after[:-1] = self.tokens[:-1], self.tokens[1:]
        self.before[self.begin], after[ends - 1] = rank[c["start"]], rank[c["start"]]
        codes, self.first, self.i3 = np.unique((self.before * size + self.tokens) * size + after, return_index=True, return_inverse=True)
        pair = codes // size
        new = np.r_[True, pair[1:] != pair[:-1]] if len(pair) else np.zeros(0, bool)
        self.of3 = np.cumsum(new) - 1  # pair of each triple
        pairs = pair[new]
        self.i2 = self.of3[self.i3]
        self.head, self.tail, self.third = pairs // size, pairs % size, codes % size
        held = np.frombuffer(c["held"], np.uint8) == 0
        self.seen = np.bincount(self.i3[np.repeat(held, self.lengths)], minlength=len(codes))
        is_hot, is_twice = np.isin(self.number, hot), np.isin(self.number, twice)
        u = self.number.view(np.uint64)
        a, b = self.head[self.of3], self.tail[self.of3]
        mark = _mix(u[a], np.full(1, 5, np.uint64))
        mark[is_hot[a]] = _mix(u[a], u[b])[is_hot[a]]
        self.twice = is_twice[self.head] & is_twice[self.tail]
        both = self.twice[self.of3]
        mark[both] = _mix(_mix(u[a[both]], u[b[both]]), u[self.third[both]])
        shard = mark % np.uint64(shards)
        self.sent = np.argsort(shard, kind="stable")
        self.cuts = np.searchsorted(shard[self.sent], np.arange(shards + 1).astype(np.uint64))

    def part(self, s: int) -> tuple[np.ndarray, ...]:
        """What goes to a shard: triples, and starts of pairs and of first words among them."""
        which = self.sent[self.cuts[s] : self.cuts[s + 1]]
        pairs, _ = _runs(self.of3[which])
        heads, _ = _runs(self.head[self.of3[which]])
        return which, pairs, heads


def _runs(p: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and lengths of the runs of equal values."""
    starts = np.flatnonzero(np.r_[True, p[1:] != p[:-1]]) if len(p) else np.zeros(0, np.int64)
    return starts, np.diff(np.r_[starts, len(p)])


ASK = "shard long, chunk long, data binary"
ANSWER = "chunk long, shard long, kind int, data binary, head long, tail long, n long, followers long"


def _rows(schema: str, columns: list[list]) -> pa.RecordBatch:
    kinds = {"long": pa.int64(), "int": pa.int32(), "binary": pa.binary()}
    fields = [x.split() for x in schema.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array(v, kinds[k]) for v, (_, k) in zip(columns, fields, strict=True)], names=[n for n, _ in fields])


def _fill(out: list[list], *row) -> None:
    for column, x in zip(out, row, strict=True):
        column.append(x)


def _cuts(hashes: np.ndarray, shards: int) -> np.ndarray:
    """Where the shards begin in ascending hashes: a shard is a range of them."""
    shard = (hashes >> np.uint64(32)) * np.uint64(shards) >> np.uint64(32)
    return np.searchsorted(shard, np.arange(shards + 1).astype(np.uint64))


def _ask_words(chunks: DataFrame, shards: int) -> DataFrame:
    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for c in batch.to_pylist():
                hashes, seen = np.cumsum(_unpack_all(c["words"], ["<u8"])[0]), _unpack(c["seen"], "<i4")
                cuts = _cuts(hashes, shards)
                out: list[list] = [[] for _ in range(3)]
                for s in np.flatnonzero(np.diff(cuts)):
                    part = slice(cuts[s], cuts[s + 1])
                    _fill(out, int(s), c["chunk"], _pack_all(np.diff(hashes[part], prepend=np.uint64(0)), seen[part]))
                yield _rows(ASK, out)

    return chunks.select("chunk", "words", "seen").mapInArrow(each, ASK)


def _count_words(asks: DataFrame, shards: int, hot_from: int) -> DataFrame:
    """Answers (kind 0: counts and numbers), totals (kind 1: tokens in n, distinct in followers), frequent words (kind 2: number in head, n), the number of the start (kind 6). A number is place * shards + shard."""
    start = int(_special()[1])

    def shard(table: pa.Table) -> pa.Table:
        me = table["shard"][0].as_py()
        parts = [(np.cumsum(h), n) for h, n in (_unpack_all(x, ["<u8", "<i4"]) for x in table["data"].to_pylist())]
        keys, inverse = np.unique(np.concatenate([p[0] for p in parts]), return_inverse=True)
        total = np.bincount(inverse, np.concatenate([p[1] for p in parts]).astype(np.float64), len(keys)).astype(np.int64)
        out: list[list] = [[] for _ in range(8)]
        at = 0
        for c, (h, _) in zip(table["chunk"].to_pylist(), parts, strict=True):
            mine = inverse[at : at + len(h)]
            at += len(h)
            _fill(out, c, me, 0, _pack_all(total[mine].astype("<i8"), np.diff(mine, prepend=0).astype("<i4")), None, None, None, None)
        real = keys != np.uint64(start)
        _fill(out, None, me, 1, None, len(keys) * shards, None, int(total[real].sum()), int((total[real] > 0).sum()))
        for k in np.flatnonzero(total > hot_from).tolist():
            _fill(out, None, me, 2, None, k * shards + me, None, int(total[k]), None)
        for k in np.flatnonzero(~real).tolist():
            _fill(out, None, me, 6, None, k * shards + me, None, None, None)
        return pa.Table.from_batches([_rows(ANSWER, out)])

    return asks.groupBy("shard").applyInArrow(shard, ANSWER)


def _special() -> np.ndarray:
    import xxhash

    return np.frombuffer(b"".join(xxhash.xxh64_digest(x) for x in (END, START)), ">u8").astype("<u8")


def _heard(answers: list[dict], shards: int) -> tuple[np.ndarray, np.ndarray]:
    """Training counts and numbers of a chunk's words: answers in the order of shards are in the order of words."""
    counts, number = [], []
    for r in sorted(answers, key=lambda r: r["shard"]):
        n, place = _unpack_all(r["data"], ["<i8", "<i4"])
        counts.append(n)
        number.append(np.cumsum(place, dtype=np.int64) * shards + r["shard"])
    return np.concatenate(counts), np.concatenate(number)


def _send_triples(c: dict, g: Grams, kind: str) -> pa.Table:
    out: list[list] = [[] for _ in range(3)]
    for s in np.flatnonzero(np.diff(g.cuts)):
        which, pairs, heads = g.part(s)
        names = g.number[g.head[g.of3[which[heads]]]]
        _fill(out, int(s), c["chunk"], _pack_all(
            np.diff(names, prepend=0).astype("<i8"), np.diff(heads, prepend=0).astype("<i4"), g.number[g.tail[g.of3[which[pairs]]]].astype(kind), np.diff(pairs, prepend=0).astype("<i4"), g.number[g.third[which]].astype(kind), g.seen[which].astype("<i4")
        ))
    return pa.Table.from_batches([_rows(ASK, out)])


def _repeat(starts: np.ndarray, n: int) -> np.ndarray:
    """For each of n places the run it lies in."""
    mark = np.zeros(n, np.int64)
    mark[starts] = 1
    return np.cumsum(mark) - 1


def _dense(*values: np.ndarray) -> list[np.ndarray]:
    """Values below 2^32 as they are; larger ones as places among the distinct ones."""
    if max((int(v.max()) for v in values if len(v)), default=0) < 1 << 32:
        return [v.astype(np.int64) for v in values]
    names = np.unique(np.concatenate(values))
    return [np.searchsorted(names, v) for v in values]


def _count_triples(asks: DataFrame, start: int, hot: np.ndarray, twice: np.ndarray, kind: str) -> DataFrame:
    """Answers (kind 3: counts of triples; counts and followers of pairs; counts and followers of first words), shares of pairs (kind 4) and of first words (kind 5) that several shards hold."""

    def shard(table: pa.Table) -> pa.Table:
        parts = [(np.cumsum(name), np.cumsum(h), tail, np.cumsum(p), third, n) for name, h, tail, p, third, n in (_unpack_all(x, ["<i8", "<i4", kind, "<i4", kind, "<i4"]) for x in table["data"].to_pylist())]
        heads, tails = [], []
        for name, h, tail, p, third, _ in parts:
            run = _repeat(p, len(third))
            heads.append(name[_repeat(h, len(third))])
            tails.append(tail[run])
        head, tail, third = np.concatenate(heads), np.concatenate(tails), np.concatenate([p[4] for p in parts])
        seen = np.concatenate([p[5] for p in parts]).astype(np.float64)
        names, i1 = np.unique(head, return_inverse=True)
        last = third == start
        tail_id, third_id = _dense(tail, third)
        pairs, at2, i2 = np.unique(i1 << 32 | tail_id, return_index=True, return_inverse=True)
        triples, at3, i3 = np.unique(i2 << 32 | third_id, return_index=True, return_inverse=True)
        n3 = np.bincount(i3, seen, len(triples)).astype(np.int64)
        of3 = triples >> 32
        n2 = np.bincount(of3, n3, len(pairs)).astype(np.int64)
        f2 = np.bincount(of3, (n3 > 0) & ~last[at3], len(pairs)).astype(np.int64)
        of2, own_tail = pairs >> 32, tail[at2]
        shared = np.isin(names, twice)[of2] & np.isin(own_tail, twice)
        n1 = np.bincount(of2, n2 * ~shared, len(names)).astype(np.int64)
        f1 = np.bincount(of2, (n2 > 0) & ~shared, len(names)).astype(np.int64)
        out: list[list] = [[] for _ in range(8)]
        at, me = 0, table["shard"][0].as_py()
        for c, (_, h, _, p, t, _) in zip(table["chunk"].to_pylist(), parts, strict=True):
            mine, of_pairs, of_heads = i3[at : at + len(t)], i2[at + p], i1[at + h]
            at += len(t)
            _fill(out, c, me, 3, _pack_all(n3[mine].astype("<i4"), n2[of_pairs].astype("<i8"), f2[of_pairs].astype("<i8"), n1[of_heads].astype("<i8"), f1[of_heads].astype("<i8")), None, None, None, None)
        for k in np.flatnonzero(shared).tolist():
            _fill(out, None, me, 4, None, int(names[of2[k]]), int(own_tail[k]), int(n2[k]), int(f2[k]))
        for k in np.flatnonzero(np.isin(names, hot)).tolist():
            _fill(out, None, me, 5, None, int(names[k]), None, int(n1[k]), int(f1[k]))
        return pa.Table.from_batches([_rows(ANSWER, out)])

    return asks.groupBy("shard").applyInArrow(shard, ANSWER)


SCORES = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"


class Automaton:
    """The states and arcs that a chunk visits: weights are log10 of probabilities.

    States: the empty history, words (by place in ``Grams.number``) and pairs (by place among the pairs). ``pairs`` and ``heads`` hold (a, b) or a with count
    and followers where several shards hold shares.
    """

    def __init__(self, g: Grams, counts: np.ndarray, answers: list[dict], n: int, v: int, discount: float, pairs: np.ndarray, heads: np.ndarray):
        size = len(g.number)
        self.g, self.counts = g, counts[g.order]
        n3, n2, f2, n1, f1 = (np.zeros(k, np.int64) for k in (len(g.third), len(g.head), len(g.head), size, size))
        for r in answers:
            which, at2, at1 = g.part(r["shard"])
            two, one = g.of3[which[at2]], g.head[g.of3[which[at1]]]
            n3[which], n2[two], f2[two], n1[one], f1[one] = _unpack_all(r["data"], ["<i4", "<i8", "<i8", "<i8", "<i8"])
        if len(heads):
            there = np.isin(g.number, heads[:, 0])
            n1[there], f1[there] = heads[np.searchsorted(heads[:, 0], g.number[there]), 1:].T
        if len(pairs):
            table = {(a, b): (x, y) for a, b, x, y in pairs.tolist()}
            for k in np.flatnonzero(g.twice).tolist():
                n2[k], f2[k] = table[int(g.number[g.head[k]]), int(g.number[g.tail[k]])]
        self.arc3, self.arc2, self.state2, self.state1 = n3 > 0, n2 > 0, n2 > 0, n1 > 0
        one = (self.counts + 1) / (n + v + 1)
        back1 = np.divide(discount * f1, n1, out=np.ones(size), where=self.state1)
        two = np.divide(np.maximum(n2 - discount, 0), n1[g.head], out=np.zeros(len(n2)), where=self.state1[g.head]) + back1[g.head] * one[g.tail]
        back2 = np.divide(discount * f2, n2, out=np.ones(len(n2)), where=self.state2)
        # the pair that a triple ends with is that of the next token
        inner = np.flatnonzero(g.first + 1 < len(g.i2))
        ends = np.zeros(len(n3))
        ends[inner] = two[g.i2[g.first[inner] + 1]]
        three = np.divide(np.maximum(n3 - discount, 0), n2[g.of3], out=np.zeros(len(n3)), where=self.state2[g.of3]) + back2[g.of3] * ends
        with np.errstate(divide="ignore"):
            self.weight1, self.weight2, self.weight3, self.fail1, self.fail2 = (np.log10(x) for x in (one, two, three, back1, back2))

    def walk(self) -> np.ndarray:
        """Log-probability of every token."""
        g = self.g
        out = np.zeros(len(g.tokens))
        later = np.ones(len(out), bool)
        later[g.begin] = False
        here = np.flatnonzero(later)
        state = np.zeros(len(out), np.int8)  # words of the history whose state a token starts from
        state[self.state1[g.before]] = 1
        state[here[self.state2[g.i2[here - 1]]]] = 2
        at = np.flatnonzero(state == 2)
        taken = self.arc3[g.i3[at - 1]]
        out[at[taken]] = self.weight3[g.i3[at[taken] - 1]]
        failed = at[~taken]
        out[failed] += self.fail2[g.i2[failed - 1]]
        state[at[taken]], state[failed] = -1, 1
        at = np.flatnonzero(state == 1)
        taken = self.arc2[g.i2[at]]
        out[at[taken]] += self.weight2[g.i2[at[taken]]]
        failed = at[~taken]
        out[failed] += self.fail1[g.before[failed]]
        state[at[taken]], state[failed] = -1, 0
        at = np.flatnonzero(state == 0)
        out[at] += self.weight1[g.tokens[at]]
        return out


def _scores(c: dict, m: Automaton, n: int, v: int) -> pa.Table:
    g = m.g
    add = lambda x: np.add.reduceat(x, g.begin)
    held, known = np.frombuffer(c["held"], np.uint8) > 0, m.counts[g.tokens]
    columns = [pa.array(c["doc_ids"], pa.int64()), pa.array(held), pa.array(g.lengths), pa.array(add((known > 0).astype(np.int64))), pa.array(np.full(len(held), n, np.int64)), pa.array(add(np.log10((known + 1) / (n + v + 1)))), pa.array(add(m.walk()))]
    return pa.Table.from_arrays(columns, names=[x.split()[0] for x in SCORES.split(", ")])


def score(docs: DataFrame, discount: float = DISCOUNT, chunk_bytes: int = CHUNK_BYTES, shard_entries: int = SHARD_ENTRIES, hot_tokens: int = HOT_TOKENS) -> DataFrame:
    """docs: doc_id, text, held (rows that the model must not learn from)."""
    chunks = materialise(chunked(docs, chunk_bytes), "chunks")
    entries, tokens = (x or 0 for x in chunks.agg(F.sum("n_words"), F.sum("n_tokens")).first())
    word_shards, shards = (max(1, -(-x // shard_entries)) for x in (entries, tokens))
    words = materialise(_count_words(_ask_words(chunks, word_shards), word_shards, max(hot_tokens, tokens // MOST_HOT)), "words")
    totals = words.where("kind = 1").agg(F.sum("n"), F.sum("followers"), F.max("head")).first()
    n, v = totals[0] or 0, totals[1] or 0
    kind = "<u4" if (totals[2] or 0) < 1 << 32 else "<i8"
    frequent = words.where("kind = 2").select("head", "n").collect()
    hot = np.array(sorted(r.head for r in frequent), np.int64)
    twice = np.array(sorted(r.head for r in frequent if r.n > tokens // MOST_TWICE), np.int64)
    starts = words.where("kind = 6").select("head").first()
    start = starts.head if starts else -1
    data = "chunk", "held", "lengths", "tokens", "start"

    def ask(left: pa.Table, right: pa.Table) -> pa.Table:
        for c in left.to_pylist():
            return _send_triples(c, Grams(c, _heard(right.to_pylist(), word_shards)[1], hot, twice, shards), kind)
        return pa.Table.from_batches([_rows(ASK, [[] for _ in range(3)])])

    answers = words.where("kind = 0").select("chunk", "shard", "kind", "data")
    asked = chunks.select(*data).groupBy("chunk").cogroup(answers.groupBy("chunk")).applyInArrow(ask, ASK)
    triples = materialise(_count_triples(asked, start, hot, twice, kind), "triples")
    shares = lambda k: triples.where(F.col("kind") == k).groupBy("head", "tail").agg(F.sum("n").alias("n"), F.sum("followers").alias("followers")).collect()
    pairs = np.array([(r.head, r.tail, r.n, r.followers) for r in shares(4)], np.int64).reshape(-1, 4)
    heads = {r.head: [r.n, r.followers] for r in shares(5)}
    for a, _, count_, _ in pairs.tolist():
        if count_:
            heads[a][0] += count_
            heads[a][1] += 1
    heads = np.array(sorted((a, *x) for a, x in heads.items()), np.int64).reshape(-1, 3)

    def meet(left: pa.Table, right: pa.Table) -> pa.Table:
        for c in left.to_pylist():
            got = right.to_pylist()
            counts, number = _heard([r for r in got if r["kind"] == 0], word_shards)
            g = Grams(c, number, hot, twice, shards)
            return _scores(c, Automaton(g, counts, [r for r in got if r["kind"] == 3], n, v, discount, pairs, heads), n, v)
        return pa.Table.from_arrays([pa.array([], k) for k in (pa.int64(), pa.bool_(), pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.float64())], names=[x.split()[0] for x in SCORES.split(", ")])

    answers = answers.unionAll(triples.where("kind = 3").select("chunk", "shard", "kind", "data"))
    return chunks.select(*data, "doc_ids").groupBy("chunk").cogroup(answers.groupBy("chunk")).applyInArrow(meet, SCORES)


def op8_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    return score(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", (remainder(F.col("doc_id"), MODULUS) == HELD).alias("held")))
