import importlib.util
import itertools
import random

import pytest

from lincompress.llm import line_dedup, near_copies, quality_classifier, quality_rules

SF = "/root/testdata/sf0.01"


def brute_roots(texts, similarity=0.8):
    sets = {}
    for i, t in texts.items():
        w = (t or "").lower().split()
        sets[i] = {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()
    root = {i: i for i in texts}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a, b in itertools.combinations(texts, 2):
        x, y = sets[a], sets[b]
        if (not x and not y) or (x and y and len(x & y) >= similarity * len(x | y)):
            root[max(find(a), find(b))] = min(find(a), find(b))
    return {i: find(i) for i in texts}


def test_near_copies_equal_brute_force(spark):
    rnd = random.Random(11)
    words = [f"w{i}" for i in range(400)]
    texts = {}
    for g in range(25):
        base = rnd.choices(words, k=rnd.randrange(60, 200))
        for c in range(rnd.choice([1, 1, 2, 3, 8])):
            copy = list(base)
            for _ in range(rnd.choice([0, 1, 2, 3]) if c else 0):
                copy[rnd.randrange(len(copy))] = rnd.choice(words)
            texts[len(texts)] = " ".join(copy)
    texts |= {900: None, 901: "", 902: " \n", 903: "one two", 904: "One  two", 905: "one two three", 906: texts[0].upper()}
    docs = spark.createDataFrame([(i, t, "s") for i, t in texts.items()] + [(0, texts[0], "s"), (None, texts[0], "s")], "doc_id long, text string, node string")
    want = {i for i, r in brute_roots(texts).items() if i == r}
    kept = near_copies.stage(spark, docs.repartition(4), SF)
    assert kept.columns == docs.columns
    assert sorted(r.doc_id for r in kept.collect()) == sorted(want)
    assert near_copies.stage(spark, docs.limit(0), SF).count() == 0


def test_quality_stage_takes_effect_and_keeps_columns(spark):
    letters = str.maketrans("0123456789", "abcdefghij")
    head = "subscribe to our letter and read on every day of the year"
    docs = [(i, head + "\n" + " ".join(f"{i}x{k}".translate(letters) for k in range(60)), "h", 7, "e") for i in range(30)]
    docs += [(50, head + " 1\n" + "short text", "h", 7, "e"), (51, None, None, None, None), (52, "a b c " * 40, "h", 1, "e"), (53, docs[0][1], "h", 1, "e"), (53, docs[0][1], "h", 1, "e")]
    df = spark.createDataFrame(docs, "doc_id long, text string, source string, n_chars long, _bad string")
    out = {r.doc_id: r for r in quality_rules.stage(spark, df, SF).collect()}
    assert set(out) == {*range(30), 53} and not any(r.text.startswith("subscribe") for r in out.values())
    assert out[3].n_chars == len(out[3].text) and list(out[3].asDict()) == df.columns
    found = {r.doc_id: r for r in quality_rules.judge(df).collect()}
    assert found[52].base_failed and found[52].n_repeat_words == 120 and found[51].n_words == 0 and found[3].removed_lines == 1
    assert quality_rules.stage(spark, df.limit(0), SF).count() == 0


def test_whole_pipeline(spark):
    if importlib.util.find_spec("corpus_pipeline") is None:
        pytest.skip("no pipeline")
    import corpus_pipeline

    docs, sizes = spark.read.parquet(f"{SF}/documents.parquet"), []
    columns = docs.columns
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = spark.createDataFrame(stage(spark, docs, SF).toPandas(), docs.schema)
        assert docs.columns == columns
        sizes.append(docs.count())
    assert sizes == sorted(sizes, reverse=True) and sizes[-1] > 300
    pieces = corpus_pipeline.run(spark, SF).collect()
    assert {r.doc_id for r in pieces} == {r.doc_id for r in docs.select("doc_id").collect()}


def test_classifier_stage_drops_what_it_rejects(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rejected = {r.doc_id for r in quality_classifier.op9_quality_classifier(spark, SF).collect() if not r.predicted}
    kept = {r.doc_id for r in quality_classifier.stage(spark, docs, SF).select("doc_id").collect()}
    assert kept == {r.doc_id for r in docs.select("doc_id").collect()} - rejected


def test_line_stage(spark):
    text = "\n".join(f"line number {i} of a text that others copy" for i in range(6))
    df = spark.createDataFrame([(1, text, 9, "q"), (2, "own words\n" + text, 9, "q"), (3, text, 9, "q")], "doc_id long, text string, n_chars long, _runs2 string")
    out = {r.doc_id: r for r in line_dedup.stage(spark, df, SF).collect()}
    assert out[1].text == text and out[2].text == "own words" and out[2].n_chars == 9 and 3 not in out


def test_star_families_equal_brute_force(spark):
    """Copies that are similar to a base only, beside texts that share a passage with all others."""
    rnd = random.Random(4)
    texts = []
    for size, copies, changes in ((200, 300, 4), (90, 60, 2), (400, 40, 8)):
        base = [f"b{size}x{i}" for i in range(size)]
        texts.append(" ".join(base))
        for c in range(copies):
            copy = list(base)
            for k in rnd.sample(range(5, size - 5), changes):
                copy[k] = f"c{c}x{k}"
            texts.append(" ".join(copy))
    passage = [f"p{i}" for i in range(40)]
    texts += [" ".join(passage + [f"o{i}x{k}" for k in range(rnd.randrange(10, 30))]) for i in range(60)]
    want = brute_roots(dict(enumerate(texts)))
    docs = spark.createDataFrame([(i, i, t) for i, t in enumerate(texts)], "id long, node long, text string").repartition(4)
    got = {r.id: r.root for r in near_copies.groups(docs).collect()}
    assert got == want and sum(root == want[0] for root in want.values()) == 301
