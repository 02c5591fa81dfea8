import itertools

import xxhash

from lincompress.llm import simhash


def brute(text, width=3):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    words = low.translate({c: " " for c in range(9, 14)}).split(" ")
    words = [w for w in words if w]
    if not words:
        return 0
    h = [xxhash.xxh64_intdigest(" ".join(words[i : i + width]).encode(), 42) for i in range(max(1, len(words) - width + 1))]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def brute_components(marks):
    name = {d: d for d in marks}
    changed = True
    while changed:
        changed = False
        for a, b in itertools.combinations(marks, 2):
            if bin(marks[a] ^ marks[b]).count("1") <= 2 and name[a] != name[b]:
                low = min(name[a], name[b])
                for d in marks:
                    if name[d] in (name[a], name[b]):
                        name[d] = low
                changed = True
    return name


def test_fingerprints_and_components(spark):
    texts = {1: None, 2: "", 3: "one", 4: "ONE", 5: "a b", 6: "Über straße ÄA b", 7: "a b c d e f g", 8: "a  b\tc d e f g", 9: "x " * 30000, 10: "  q w"}
    docs = spark.createDataFrame([(i, t, "z") for i, t in texts.items()], "doc_id long, text string, fp string")
    rows = {r.doc_id: r for r in simhash.classes(docs).collect()}
    marks = {i: brute(t) for i, t in texts.items()}
    assert {i: r.fp % 2**64 for i, r in rows.items()} == marks
    assert {i: r.component_id for i, r in rows.items()} == brute_components(marks)


def test_links_equal_brute_force(spark):
    import random

    rnd = random.Random(5)
    seeds = [rnd.getrandbits(64) for _ in range(12)] + [0, 2**64 - 1]
    fps = set(seeds)
    for s in seeds:
        for k in range(25):
            x = s
            for b in rnd.sample(range(64), rnd.choice([1, 1, 2, 3, 4, 5])):
                x ^= 1 << b
            fps.add(x)
            if k % 3 == 0:
                s = x
    signed = [x - 2**64 if x >> 63 else x for x in fps]
    df = spark.createDataFrame([(x,) for x in signed], "fp long")
    from lincompress.llm import components

    got = {r.node: r.root for r in components.roots(simhash.links(df)).collect()}
    want = brute_components({x: x % 2**64 for x in signed})
    assert {x: got.get(x, x) for x in signed} == want


def test_empty(spark):
    assert simhash.classes(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_a_full_ball_is_compared_whole():
    import numpy as np

    centre = 0x0F0F_3C3C_55AA_1234
    ball = [centre ^ a ^ b ^ c for a in (0, 1 << 63) for b, c in [(0, 0), *[(1 << i, 0) for i in range(63)], *[(1 << i, 1 << j) for i in range(63) for j in range(i)]]]
    assert len(set(ball)) == 4034
    found = simhash._forest(np.array(ball, np.uint64).view(np.int64))
    assert len(found) == 4033 and all(((a ^ b) & (2**64 - 1)).bit_count() <= 2 for a, b in found)
    apart = np.array([0, 7, 7 << 10, 0b1001 << 40], np.int64)
    assert {frozenset(x) for x in simhash._forest(apart)} == {frozenset((0, 0b1001 << 40))}


def test_repeated_rows(spark):
    docs = spark.createDataFrame([(5, "a b c d"), (5, "a b c d"), (3, "A b C d"), (None, "a b c d"), (9, None), (8, "")], "doc_id long, text string")
    got = sorted((r.doc_id or 0, r.component_id) for r in simhash.classes(docs).collect())
    assert got == [(0, 3), (3, 3), (5, 3), (5, 3), (8, 8), (9, 8)]
