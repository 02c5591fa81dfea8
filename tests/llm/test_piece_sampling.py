import math
import random
from collections import Counter

import numpy as np
import sentencepiece

from lincompress.llm import piece_sampling as ps


def segmentations(word, of):
    if not word:
        yield (), 1.0
    for k in range(1, len(word) + 1):
        if word[:k] in of:
            i, w = of[word[:k]]
            for rest, p in segmentations(word[k:], of):
                yield (i, *rest), w * p


def test_samples_follow_the_lattice():
    pieces = [(1, b" ", 0.3), (2, b"a", 0.5), (3, b"b", 0.4), (4, b"ab", 0.3), (5, b" a", 0.2), (6, b"ba", 0.25), (7, b" ab", 0.05), (8, b"aba", 0.1)]
    v = ps.Vocabulary(pieces, {b: 300 + b for b in range(256)})
    n = 40_000
    ids, counts, logs = ps.encode_batch([b"abab"] * n, np.arange(n), v)
    cuts = np.r_[0, np.cumsum(counts)]
    seen = Counter(tuple(ids[a:b].tolist()) for a, b in zip(cuts[:-1], cuts[1:], strict=True))
    want = dict(segmentations(b" abab", v.of))
    total = sum(want.values())
    assert set(seen) <= set(want)
    for s, w in want.items():
        p = w / total
        assert abs(seen[s] / n - p) < 5 * math.sqrt(p * (1 - p) / n) + 1e-9
    first = tuple(ids[: counts[0]].tolist())
    assert math.isclose(logs[0], math.log(want[first] / total), rel_tol=1e-9)


def test_long_units_take_the_same_law():
    pieces = [(1, b" ", 0.3), (2, b"a", 0.5), (3, b"aa", 0.4)]
    v = ps.Vocabulary(pieces, {b: 300 + b for b in range(256)})
    ids, counts, logs = ps.encode_batch([b"a" * 5000, b"a" * 40, b"q" * 3000], np.array([1, 2, 3]), v)
    assert np.isfinite(logs).all() and v.decode(ids) == b" " + b"a" * 5000 + b" " + b"a" * 40 + b" " + b"q" * 3000
    assert 0.3 < (ids[: counts[0]] == 3).mean() < 0.7


def test_lossless_and_reproducible(spark):
    rnd = random.Random(7)
    odd = "aAzé ß▁日本\U0001f600 \n\t\r<s> </s>[]{}0123,.\x00\x1f́"
    texts = [None, "", " ", "  two  spaces ", "▁", "<0x0A>", "x" * 20_000, "plain words here"] + ["".join(rnd.choices(odd, k=rnd.randrange(80))) for _ in range(200)]
    docs = spark.createDataFrame([(i, t, b"z") for i, t in enumerate(texts)] + [(None, "plain words here", b"z"), (7, texts[7], b"z")], "doc_id long, text string, ids binary")
    path = ps._path()
    rows = ps.encode(docs.repartition(5), path).collect()
    assert all(r.lossless for r in rows)
    again = {r.doc_id: r.ids for r in ps.encode(docs.coalesce(1), path).collect()}
    assert all(again[r.doc_id] == r.ids for r in rows) and len({r.ids for r in rows if r.doc_id == 7}) == 1
    back = {r.doc_id: r.text for r in ps.decode(ps.encode(docs, path), path).collect()}
    assert all(back[i] == (t or "") for i, t in enumerate(texts))
    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    ids = np.frombuffer(again[7], "<u2").tolist()
    assert sp.decode(ids) == texts[7]
    assert ps.encode(docs.limit(0), path).count() == 0
