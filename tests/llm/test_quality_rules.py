import re
from collections import defaultdict

from lincompress.llm import quality_rules as q


def brute(rows, min_docs, share, depleted):
    """rows: (doc_id, text, source); the columns of judge without symbols, in order of the rows."""
    space = " \t\n\v\f\r"
    words = lambda t: [w for w in re.split(f"[{space}]+", t) if w]
    normal = lambda x: re.sub("[0-9]", "0", re.sub(f"[{space}]+", " ", x).strip(" ").lower())
    texts, seen = defaultdict(set), defaultdict(set)
    for _, t, h in rows:
        texts[h or ""].add(t or "")
        for x in (t or "").split("\n"):
            if words(x):
                seen[h or "", normal(x)].add(t or "")
    out = []
    for i, t, h in rows:
        t, h = t or "", h or ""
        ws, lines = words(t), t.split("\n")
        limit = max(min_docs, share * len(texts[h]))
        gone = [k for k, x in enumerate(lines) if words(x) and len(seen[h, normal(x)]) > limit]
        removed = sum(len(words(lines[k])) for k in gone)
        grams = defaultdict(list)
        for k in range(len(ws) - 2):
            grams[tuple(ws[k : k + 3])].append(k)
        repeat = len({k + d for v in grams.values() if len(v) > 1 for k in v for d in range(3)})
        real = [x for x in lines if words(x)]
        failed = len(ws) < 50 or 100 * repeat > 50 * len(ws)
        clean = "\n".join(x for k, x in enumerate(lines) if k not in gone) if gone else t
        out.append((i, len(ws), sum(map(len, ws)), sum(c in "#*$%&|<>" for c in t), len(real) - len(set(real)), repeat, failed, len(gone), removed, not failed and removed <= depleted * len(ws), clean))
    return out


COLUMNS = ("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "removed_lines", "removed_words", "kept", "clean_text")


def rows():
    """Lines at the limit (in as many documents) and above it, copies, repeated rows, nulls, empty and very long texts."""
    own = lambda i: " ".join(f"word{i}x{k}" for k in range(60))
    out = []
    for i in range(12):
        head = "Menu  12 | home\n" if i < 4 else "menu 99 | Home \n" if i < 6 else ""
        at_limit = "exactly at the limit\n" if i < 3 else ""
        out.append((i, head + at_limit + own(i) + "\n\n  " + ("all rights" if i < 6 else "else"), "hot" if i != 5 else None))
    out += [(20 + i, "a copied line\n" + own(99), "hot") for i in range(9)]
    out += [(40, None, "hot"), (41, "", None), (42, "Menu 1 | home", "hot"), (42, "Menu 1 | home", "hot"), (None, "é ß 日本\n" * 30, "x"), (43, "long line of words " * 40_000, "x"), (44, "\n".join(["same line here"] * 40), "y")]
    out += [(60 + i, ("Menu 3 | HOME\n" * 9) + " ".join(f"v{i}x{k}" for k in range(5)), "hot") for i in range(3)]
    return out


def result(df):
    return sorted((tuple(r) for r in df.collect()), key=str)


def test_equals_brute_force_both_ways(spark, monkeypatch):
    given = rows()
    df = spark.createDataFrame([(*r, 7, "x") for r in given], "doc_id long, text string, source string, _host long, n_words string").repartition(3)
    want = sorted(brute(given, 3, 0.01, 0.5), key=str)
    assert result(q.judge(df, min_docs=3).select(*COLUMNS)) == want
    monkeypatch.setattr(q.mark_lines, "__defaults__", (0,))
    assert result(q.judge(df, min_docs=3).select(*COLUMNS)) == want


def test_depleted_documents_go(spark):
    body = "\n".join(f"shared footer line number x{'abcdefghij'[k]} of the site" for k in range(9))
    given = [(i, body + "\n" + " ".join(chr(97 + i) + chr(97 + k // 26) + chr(97 + k % 26) for k in range(60 if i < 5 else 200)), "s") for i in range(10)]
    df = spark.createDataFrame(given, "doc_id long, text string, source string")
    got = {r.doc_id: r for r in q.judge(df, min_docs=4).collect()}
    assert [got[i].kept for i in range(10)] == [False] * 5 + [True] * 5 and all(r.removed_lines == 9 and not r.base_failed for r in got.values())
    kept = q.stage(spark, df, "")
    assert {r.doc_id for r in kept.collect()} == set(range(10))  # ten documents are no more than the limit of the query
    assert q.judge(df.limit(0)).count() == 0


def test_no_python_in_the_plan(spark):
    plan = q.judge(spark.createDataFrame(rows(), "doc_id long, text string, source string"), min_docs=3)._jdf.queryExecution().toString()
    assert not re.search("Python|Arrow|Pandas", plan)
