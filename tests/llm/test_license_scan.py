import random
import re

import pytest

from lincompress.llm import license_scan as ls

SF = "/root/testdata/sf0.01"


def brute(text):
    low = re.sub("[A-Z]", lambda m: m[0].lower(), text or "")
    words = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", low)
    starts, base = [], set()
    for phrase, label in ls.PHRASES:
        p = phrase.split()
        for i in range(len(words)):
            if words[i : i + len(p)] == p:
                starts.append(i)
                base.add(label)
    labels, best = set(base), 0.0
    for label, template, phrase in ls.TEMPLATES:
        t, p = template.split(), phrase.split()
        for at in range(-len(t) + 1, len(words)):
            there = words[max(at, 0) : at + len(t)]
            placed = sum(0 <= at + j < len(words) and words[at + j] == t[j] for j in range(len(t)))
            if placed >= 2:
                best = max(best, placed / len(t))
                if placed / len(t) >= ls.SHARE and any(there[k : k + len(p)] == p for k in range(len(there))):
                    labels.add(label)
    return (len(words), len(starts), min(starts, default=None), max(starts, default=None), ",".join(sorted(base)), ",".join(sorted(labels))), best


def test_equals_brute_force(spark):
    rows = ls.op4_license_scan(spark, SF).collect()
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    assert len(rows) == len(texts)
    labelled = 0
    for r in sorted(rows, key=lambda r: len(texts[r.doc_id]))[:700]:
        want, _ = brute(texts[r.doc_id])
        assert tuple(r)[1:7] == want
        assert 0 <= r.score <= 1
        labelled += r.labels != ""
    assert labelled > 5


def test_small_cases(spark):
    texts = [None, "", "cc by cc BY-ND 4.0 all rights reserved", "CC by", "ALL RIGHTS\nRESERVED.", "é cc by", "* Permission is hereby granted, free of charge,\n * to any person obtaining a copy of this software and its documentation files"]
    docs = spark.createDataFrame([(i, t, "x") for i, t in enumerate(texts)] + [(1, "", "x")], "doc_id long, text string, labels string")
    rows = ls.scan(docs).collect()
    for r in rows:
        assert tuple(r)[1:7] == brute(texts[r.doc_id])[0]
    found = {r.doc_id: r for r in rows}
    assert found[6].labels == "mit" and found[2].labels == "cc-by,reserved" and found[4].score == 1.0
    assert found[0].first_word is None and found[0].score == 0.0
    assert ls.scan(docs.limit(0)).count() == 0


def test_files_with_many_licences(spark):
    """Every template keeps its label and the score is the best share, whatever else the file and the corpus hold."""
    rnd = random.Random(3)
    texts = [" ".join(t for _, t, _ in ls.TEMPLATES), " ".join(t for _, t, _ in reversed(ls.TEMPLATES))]
    texts += [" - ".join(t for _, t, _ in rnd.sample(ls.TEMPLATES, k)) for k in (3, 4, 5, 6) for _ in range(25)]
    texts += [" ".join(rnd.choices(" ".join(t for _, t, _ in ls.TEMPLATES).split(), k=60)) for _ in range(20)]
    texts += [t for label, t, _ in ls.TEMPLATES if "cc-by" in label or "gpl" in label for _ in range(20)]
    rows = ls.scan(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()
    assert len(rows) == len(texts)
    for r in rows:
        want, best = brute(texts[r.doc_id])
        assert tuple(r)[1:7] == want and r.score == pytest.approx(best)
    found = {r.doc_id: r for r in rows}
    assert {label for label, _, _ in ls.TEMPLATES} <= set(found[0].labels.split(","))
