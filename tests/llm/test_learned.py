import zlib

import numpy as np
import pytest

from lincompress.llm import language_id, quality_classifier

SF = "/root/testdata/sf0.01"


def test_language_of_held_out_texts(spark):
    rows = language_id.op7_language_id(spark, SF).collect()
    truth = {r.doc_id: (r.lang, r.text) for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    assert len(rows) == len(truth)
    held = [r for r in rows if r.held_out]
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in rows)
    assert np.mean([r.lang_pred == truth[r.doc_id][0] for r in held]) > 0.97
    assert all(0 <= r.score <= 1 for r in rows)


def plain_bundle(text):
    """Trigram by trigram."""
    s = [-1] + [ord(c) if c.isalpha() else -1 for c in (text or "").lower()] + [-1]
    s = [x for i, x in enumerate(s) if i == 0 or x >= 0 or s[i - 1] >= 0]
    v = {x: language_id.letter_vector(x).astype(float) for x in set(s)}
    out = np.zeros(language_id.SIZE)
    for i in range(len(s) - 2):
        out += np.roll(v[s[i]], 2) * np.roll(v[s[i + 1]], 1) * v[s[i + 2]]
    norm = np.linalg.norm(out)
    return out / norm if norm else out


def test_language_equals_plain_python(spark, monkeypatch):
    rng = np.random.default_rng(3)
    scripts = {"ru": range(0x430, 0x450), "uk": [*range(0x430, 0x446), 0x456, 0x457, 0x454, 0x491], "el": range(0x3B1, 0x3CA), "zh": range(0x4E00, 0x4E30), "fr": [*range(97, 123), 0xE9, 0xE8, 0xE7]}
    rows = []
    for lang, letters in scripts.items():
        weights = rng.dirichlet(np.ones(len(letters)) * 0.5)
        for _ in range(14):
            rows.append((len(rows), " ".join("".join(chr(c) for c in rng.choice(list(letters), rng.integers(1, 8), p=weights)) for _ in range(30)), lang))
    rows += [(900, rows[0][1], "ru"), (900, rows[0][1], "ru"), (901, None, "ru"), (902, "12 !", "fr"), (903, "\u00e9" * 40000 + " a", "fr"), (904, "абв", None)]
    docs = spark.createDataFrame([(*r, "x") for r in rows], "doc_id long, text string, lang string, lang_pred string")
    monkeypatch.setattr(language_id, "CELLS", 1000)
    names, vectors = language_id.profiles(docs.where("doc_id % 3 <> 0"))
    sums = {x: sum(plain_bundle(t) for i, t, lang in rows if lang == x and i % 3) for x in scripts}
    unit = lambda v: v / np.linalg.norm(v)
    mean = np.mean([unit(v) for v in sums.values()], axis=0)
    want = {x: unit(unit(v) - mean) for x, v in sums.items()}
    assert names == sorted(scripts) and np.allclose(vectors, [want[x] for x in names], atol=1e-4)
    got = sorted((r.doc_id, r.lang_pred, r.score) for r in language_id.predict(docs, names, vectors).collect())
    assert len(got) == len(rows)
    for (i, lang, score), (j, text, _) in zip(got, sorted(rows, key=lambda r: r[0]), strict=True):
        cosines = {x: float(plain_bundle(text) @ want[x]) for x in names}
        assert i == j and (lang == "und" if not plain_bundle(text).any() else cosines[lang] > max(cosines.values()) - 1e-4)
        assert abs(score - (0 if lang == "und" else min(max(cosines[lang], 0), 1))) < 1e-3
    held = [(r[2], g[1]) for r, g in zip(sorted(rows, key=lambda r: r[0]), got, strict=True) if r[0] % 3 == 0 and r[0] < 900]
    assert np.mean([a == b for a, b in held]) > 0.9


def test_letters_never_share_a_vector():
    seen = {language_id.letter_vector(c).tobytes() for c in [-1, *range(97, 123), *range(0x400, 0x460), *range(0x4E00, 0x5600)]}
    assert len(seen) == 1 + 26 + 96 + 0x800


def test_language_edges_and_bundles(spark):
    b = language_id.Bundler()
    text = "Aé, b c" * 40
    assert np.allclose(b.bundle([text])[0], plain_bundle(text), atol=1e-5)
    docs = spark.createDataFrame([(1, None), (2, "123 !"), (3, "the cat"), (None, "")], "doc_id long, text string")
    names, vectors = language_id.profiles(spark.createDataFrame([("the cat sat", "en"), ("le chat est", "fr"), ("x", None)], "text string, lang string"))
    got = {r.doc_id: (r.lang_pred, r.score) for r in language_id.predict(docs, names, vectors).collect()}
    assert got[1] == got[2] == got[None] == ("und", 0.0) and got[3][0] == "en"
    names, vectors = language_id.profiles(spark.createDataFrame([], "text string, lang string"))
    assert {r.lang_pred for r in language_id.predict(docs, names, vectors).collect()} == {"und"}
    assert language_id.predict(docs.limit(0), names, vectors).count() == 0


def test_quality_of_held_out_texts(spark):
    rows = {r.doc_id: r for r in quality_classifier.op9_quality_classifier(spark, SF).collect()}
    labels = spark.read.parquet(f"{SF}/labels.parquet").collect()
    assert all(r.held_out == (zlib.crc32(str(i).encode()) % 4 == 2) and 0 <= r.score <= 1 for i, r in rows.items())
    held = [(rows[x.doc_id].predicted, x.quality) for x in labels if rows[x.doc_id].held_out]
    assert np.mean([a == b for a, b in held]) > 0.93


def test_discriminant_equals_formula_and_edges(spark):
    rng = np.random.default_rng(1)
    x = np.vstack([rng.normal(0, 1, (300, 12)), rng.normal(0.7, 2, (200, 12))])
    y = [0] * 300 + [1] * 200
    df = spark.createDataFrame([(r.tolist(), k) for r, k in zip(x, y, strict=True)], "x array<double>, quality int")
    model = quality_classifier.fit(df)
    pooled = np.diag(np.diag(300 * np.cov(x[:300].T, bias=True) + 200 * np.cov(x[300:].T, bias=True)) / 500 + quality_classifier.RIDGE)
    for k, part in ((0, x[:300]), (1, x[300:])):
        cov = 0.9 * np.cov(part.T, bias=True) + 0.1 * pooled + quality_classifier.RIDGE * np.eye(12)
        d = x - part.mean(axis=0)
        want = np.log(len(part) / 500) - 0.5 * (np.linalg.slogdet(cov)[1] + np.einsum("ij,jk,ik->i", d, np.linalg.inv(cov), d))
        assert np.allclose(quality_classifier.densities(model, x, k), want)
    docs = spark.createDataFrame([(1, None), (2, ""), (2, ""), (3, "a b " * 30000)], "doc_id long, text string")
    none = spark.createDataFrame([], "doc_id long, quality int, x int")
    assert [r.score for r in quality_classifier.classify(docs, none).collect()] == [0.5] * 4
    one = spark.createDataFrame([(1, 1), (1, None), (9, 0)], "doc_id long, quality int")
    assert {r.score for r in quality_classifier.classify(docs, one).collect()} == {1.0}
    with pytest.raises(StopIteration):
        next(iter(quality_classifier.classify(docs.limit(0), one).collect()))
