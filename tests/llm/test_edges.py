"""Very long texts, clashing names, and empty tables, for the operators and stages whose own tests lack them."""

import importlib.util
import os

import public_tokenizers
import pytest

from lincompress.llm import license_scan, line_dedup, lm_scoring, near_copies, packing, quality_classifier, quality_rules, simhash

SF = "/root/testdata/sf0.001"
PATH = public_tokenizers.path("word_bpe_49k.json")


def test_license_words_of_a_very_long_text(spark):
    filler = "plain words of a file " * 60_000
    docs = spark.createDataFrame([(1, filler + "all rights reserved " + filler + "CC BY", 2, "x")], "doc_id long, text string, n_words long, score string")
    r = license_scan.scan(docs).first()
    assert (r.n_words, r.n_base, r.first_word, r.last_word, r.base_labels) == (600_005, 2, 300_000, 600_003, "cc-by,reserved")


def test_packing_ignores_clashing_names(spark):
    texts = [(i, f"alpha {i} beta " * (i % 9), "ab"[i % 2]) for i in range(40)]
    plain = spark.createDataFrame(texts, "doc_id long, text string, source string").coalesce(1)
    schema = "doc_id long, text string, source string, ids string, n string, block string, inner string, queue string, length string, offset string"
    other = spark.createDataFrame([(*t, *"abcdefg") for t in texts], schema).coalesce(1)
    assert sorted(packing.pack(plain, PATH).collect()) == sorted(packing.pack(other, PATH).collect())


def test_scores_ignore_clashing_names(spark):
    texts = [(i, f"one two {i % 4} three " * (i % 5), i % 7 == 2) for i in range(30)]
    plain = spark.createDataFrame(texts, "doc_id long, text string, held boolean")
    other = spark.createDataFrame([(*t, "x", 1, None, 2) for t in texts], "doc_id long, text string, held boolean, chunk string, n_words long, kind string, head long")
    assert sorted(lm_scoring.score(plain).collect()) == sorted(lm_scoring.score(other).collect())


def test_fingerprints_ignore_clashing_names(spark):
    texts = [(i, "a b c d e" if i % 2 else f"text {i} of its own") for i in range(9)]
    plain = spark.createDataFrame(texts, "doc_id long, text string")
    other = spark.createDataFrame([(*t, "x", 5, 6) for t in texts], "doc_id long, text string, fingerprint string, node long, component_id long")
    got = simhash.classes(other)
    assert sorted(simhash.classes(plain).collect()) == sorted(got.collect()) and got.columns == simhash.classes(plain).columns


@pytest.mark.parametrize("stage", [quality_rules.stage, quality_classifier.stage, line_dedup.stage, near_copies.stage])
def test_stages_keep_columns_of_any_name(spark, stage):
    """Names that the operators use themselves, and one with a dot, come out as they went in."""
    names = ["doc_id", "text", "source", "_run", "_runs", "_run_id", "_near_id", "_near_text", "_host", "kept", "clean_text", "root", "node", "c3", "a.b", "x", "score"]
    documents = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text", "source")
    rows = [(*r, *[f"{n} of {r.doc_id}" for n in names[3:]]) for r in documents.collect()]
    docs = spark.createDataFrame(rows, ", ".join(f"`{n}` {'long' if n == 'doc_id' else 'string'}" for n in names))
    out = stage(spark, docs, SF)
    assert out.columns == names
    got = out.collect()
    assert got and all(tuple(r)[3:] == tuple(f"{n} of {r[0]}" for n in names[3:]) for r in got)
    alone = {r.doc_id for r in stage(spark, documents, SF).collect()}
    assert {r[0] for r in got} == alone


def test_pipeline_on_empty_tables(spark, tmp_path):
    if importlib.util.find_spec("corpus_pipeline") is None:
        pytest.skip("no pipeline")
    import corpus_pipeline

    for name in sorted(os.listdir(SF)):
        if name in ("documents.parquet", "labels.parquet"):
            spark.read.parquet(f"{SF}/{name}").limit(0).coalesce(1).write.parquet(f"{tmp_path}/{name}")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
    assert quality_classifier.op9_quality_classifier(spark, str(tmp_path)).count() == 0
