import math
import random
from collections import Counter, defaultdict

import pytest

from lincompress.llm import lm_scoring


def brute(docs, discount=lm_scoring.DISCOUNT):
    def tokens(text):
        low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
        for c in "\t\n\v\f\r":
            low = low.replace(c, " ")
        return [w for w in low.split(" ") if w] + [None]

    # histories of no, one and two words; the start of a text is a word of a history
    seen, after = Counter(), defaultdict(Counter)
    for _, text, held in docs:
        if not held:
            last = ["<s>"]
            for w in tokens(text):
                seen[w] += 1
                for k in (1, 2):
                    if len(last) >= k:
                        after[tuple(last[-k:])][w] += 1
                last.append(w)
    n, v = sum(seen.values()), len(seen)

    def probability(history, w):
        if not history:
            return (seen[w] + 1) / (n + v + 1)
        less = probability(history[1:], w)
        arcs = after.get(history)
        if not arcs:
            return less
        return max(arcs[w] - discount, 0) / sum(arcs.values()) + discount * len(arcs) / sum(arcs.values()) * less

    out = []
    for i, text, held in docs:
        base = total = 0.0
        last = ["<s>"]
        ts = tokens(text)
        for w in ts:
            base += math.log10(probability((), w))
            total += math.log10(probability(tuple(last[-2:]), w))
            last.append(w)
        out.append((i, held, len(ts), sum(seen[w] > 0 for w in ts), n, base, total))
    return out


@pytest.mark.parametrize("hot", [1_000_000, 3])
def test_equals_brute_force(spark, hot):
    rnd = random.Random(3)
    words = ["the", "The", "of", "ähm", "x y", "rain"] + [f"w{i}" for i in range(60)]
    docs = [(i, " ".join(rnd.choices(words, k=rnd.randrange(40))) + ("\n\t" if i % 2 else ""), i % 5 == 2) for i in range(80)]
    docs += [(100, None, False), (101, "", True), (102, "unseen words only", True), (103, "a b " * 5000, False), (103, "a b " * 5000, False), (None, "the", False)]
    df = spark.createDataFrame([(*d, "x", 3) for d in docs], "doc_id long, text string, held boolean, chunk string, words int").select("doc_id", "text", "held").repartition(4)
    got = lm_scoring.score(df, chunk_bytes=600, shard_entries=50, hot_tokens=hot).collect()
    key = lambda r: (r[0] is None, r[0] or 0, r[2])
    for a, b in zip(sorted(map(tuple, got), key=key), sorted(brute(docs), key=key), strict=True):
        assert a[:5] == b[:5]
        assert a[5:] == pytest.approx(b[5:], rel=1e-9)


def test_empty_and_all_held_out(spark):
    schema = "doc_id long, text string, held boolean"
    assert lm_scoring.score(spark.createDataFrame([], schema)).count() == 0
    row = lm_scoring.score(spark.createDataFrame([(1, "a b", True)], schema)).first()
    assert (row.n_tokens, row.n_known, row.train_tokens, row.base_score, row.score) == (3, 0, 0, 0.0, 0.0)


def test_histories_seen_and_unseen(spark):
    """Every word and the end, after histories of two words, of one, and unseen ones."""
    train = [(i, t, False) for i, t in enumerate(["a b a b c", "a b", "b c a b a", "c", "a b d"])]
    words, histories = ["a", "b", "c", "d"], ["a b", "b", "c a", "x a", "zz yy", ""]
    asks = [(f"{h} {w}".strip(), h, w) for h in histories for w in [*words, ""]]
    held = [(100 + i, t, True) for i, (t, _, _) in enumerate(asks)]
    rows = {r.doc_id: r.score for r in lm_scoring.score(spark.createDataFrame(train + held, "doc_id long, text string, held boolean")).collect()}
    want = {d[0]: d[-1] for d in brute(train + held)}
    assert all(abs(rows[i] - want[i]) < 1e-9 for i in rows)
