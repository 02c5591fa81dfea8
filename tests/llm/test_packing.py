import collections
import zlib

import numpy as np
import public_tokenizers
from tokenizers import Tokenizer

from lincompress.llm import packing

PATH = public_tokenizers.path("word_bpe_49k.json")


def test_whole_and_exact(spark):
    texts = [(1, "Hello  world's <|endoftext|> ΣΑΣ x y z\x1cq", "a"), (2, None, "a"), (3, "", None), (4, "don't I'll é " * 900, "b"), (5, "日本 12345 !!" * 50, "c"), (5, "日本 12345 !!" * 50, "c")]
    texts += [(10 + i, "alpha beta gamma %d " % i * (i % 40), "b" if i % 3 else "a") for i in range(200)]
    docs = spark.createDataFrame(texts, "doc_id long, text string, source string").repartition(5)
    rows = packing.pack(docs, PATH, with_ids=True).collect()
    tok = Tokenizer.from_file(PATH)
    want = collections.Counter()
    for i, t, _ in texts:
        want[i, tuple(tok.encode(t or "", add_special_tokens=False).ids + [1])] += 1
    flat = collections.defaultdict(list)
    for r in rows:
        assert r.ids_crc32 == zlib.crc32(np.array(r.ids, "<u4").tobytes()) and r.length == len(r.ids)
        flat[r.doc_id].append(r)
    for (i, ids), n in want.items():
        covered = collections.Counter()
        for r in flat[i]:
            assert r.doc_tokens == len(ids) and list(ids[r.start : r.start + r.length]) == r.ids
            covered.update(range(r.start, r.start + r.length))
        assert set(covered.values()) == {n} and len(covered) == len(ids)
    seqs = collections.defaultdict(list)
    for r in rows:
        seqs[r.sequence_id].append((r.offset, r.length))
    assert sorted(seqs) == list(range(len(seqs)))
    for k, v in seqs.items():
        at = 0
        for o, n in sorted(v):
            assert o == at
            at += n
        assert at == 2048 or k == len(seqs) - 1


def test_ids_equal_the_tokenizer():
    import random

    tok, encode = Tokenizer.from_file(PATH), packing._encoder(PATH)
    rnd = random.Random(4)
    odd = "aAzZ09.,'!?<|>_ \u00e9\u00c9\u0130\u017f\u00df\u00aa\u00b2\u00bd\u00a0\u0085\x1c\u00ad\u0301\u03a3\u4e00\u2003\ufb01\u212a\U0001f600\u01c5 \n\t"
    texts = ["".join(rnd.choices(odd, k=rnd.randrange(1, 60))) for _ in range(6000)]
    texts += ["it's we'LL they've I'm d'x 'Tis x'", "<|startoftext|>a <|endoftext|>", "\u0130stanbul \u0178 \u01c4 \u0149a"]
    texts += [chr(c) + "a" + chr(c) for c in range(1, 0x250)]
    for t in texts:
        assert np.frombuffer(encode([t])[0], "<u2").tolist() == tok.encode(t, add_special_tokens=False).ids, repr(t)


def test_windows_hold_target_shares(spark):
    rows = [(i, i, "abc"[0 if i % 6 < 3 else 1 if i % 6 < 5 else 2], 300 + i % 7) for i in range(600)]
    lengths = spark.createDataFrame(rows, "row long, doc_id long, source string, n long")
    source = {r[0]: r[2] for r in rows}
    total = collections.Counter()
    for r in rows:
        total[r[2]] += r[3]
    share = {s: n / sum(total.values()) for s, n in total.items()}
    window = collections.defaultdict(collections.Counter)
    for r in packing.schedule(lengths).collect():
        window[r.sequence_id][source[r.row]] += r.size
    run = collections.Counter()
    for k in sorted(window):
        run.update(window[k])
        for s, p in share.items():
            assert abs(run[s] - p * sum(run.values())) <= 2 * packing.QUANTUM
    aimed = collections.defaultdict(collections.Counter)
    for r in packing.schedule(lengths, targets={"a": 1.0, "b": 1.0, "c": 2.0}).collect():
        aimed[r.sequence_id][source[r.row]] += r.size
    first = sum((aimed[k] for k in range(8)), collections.Counter())
    assert abs(first["c"] / sum(first.values()) - 0.5) < 0.05


def test_empty(spark):
    assert packing.pack(spark.createDataFrame([], "doc_id long, text string, source string"), PATH).count() == 0


def test_each_window_holds_the_targets():
    rng = np.random.default_rng(8)
    for power, sizes in ((0.7, [900_000, 40_000, 41_000, 3_000, 700]), (1.0, [5_000, 5_000, 5_000]), (0.5, [123_457]), (1.0, rng.integers(1, 60_000, 300).tolist())):
        weights = [n**power for n in sizes]
        cuts = packing.Cuts(sizes, weights, 2048)
        total = sum(sizes)
        windows = -(-total // 2048)
        c = cuts.at(np.arange(windows + 1))
        got, left = np.diff(c, axis=0), np.array(sizes) - c[:-1]
        assert (got >= 0).all() and (c[-1] == sizes).all() and (got[:-1].sum(axis=1) == 2048).all()
        # windows in which no queue runs dry hold every live queue's share
        for k in range(windows - 1):
            live = left[k] > 0
            want = 2048 * np.array(weights) * live / (np.array(weights) * live).sum()
            if (left[k][live] > want[live] + 2).all():
                assert (abs(got[k] - want) <= 2).all()
        # a cut doesn't depend on what is computed beside it
        some = rng.choice(windows + 1, min(windows, 7), replace=False)
        assert (cuts.at(np.sort(some)) == c[np.sort(some)]).all()


def test_too_many_queues(spark):
    lengths = spark.createDataFrame([(i, i, f"s{i}", 3) for i in range(40)], "row long, doc_id long, source string, n long")
    import pytest

    with pytest.raises(ValueError, match="queues"):
        packing.schedule(lengths, length=64)
    assert packing.schedule(lengths, length=256).groupBy().sum("size").first()[0] == 120


def test_the_pipeline_leaves_no_token_caches_in_workers(spark):
    docs = spark.createDataFrame([(i, f"onlyhere{i} word " * 30, "ab"[i % 2]) for i in range(400)], "doc_id long, text string, source string").repartition(16)
    pieces = packing.stage(spark, docs, "")  # tokens are written, pieces are not made yet

    def left(batches):
        import sys
        import time

        import pyarrow as pa

        for batch in batches:
            time.sleep(0.2)  # so that every worker gets some
            shelf = vars(sys.modules["_token_shelf"]) if "_token_shelf" in sys.modules else {}
            n = sum(b"onlyhere" in k for e in shelf.values() if hasattr(e, "chunks") for k in e.chunks)
            yield pa.RecordBatch.from_arrays([pa.array([n] * batch.num_rows, pa.int64())], names=["n"])

    assert spark.range(0, 48, 1, 48).mapInArrow(left, "n long").groupBy().sum("n").first()[0] == 0
    whole = packing.pack(docs, PATH, power=packing.POWER)
    # places go with tasks, which need not be the same; the ids of a document do
    of = lambda rows: sorted((r.doc_id, r.n) for r in rows.groupBy("doc_id").agg({"length": "sum"}).withColumnRenamed("sum(length)", "n").collect())
    assert of(pieces) == of(whole) and len(of(pieces)) == 400


def test_small_caches_give_the_same_ids():
    encode = packing._encoder(PATH)
    texts = [f"alpha beta{i} Gamma. x{i % 7}" for i in range(300)]
    want = encode(texts)
    packing._forget()
    encoder = encode.__self__
    got = []
    for t in texts:
        got += encode([t], (40, 20))
        assert len(encoder.chunks) <= 40 and len(encoder.words) <= 20
    assert got == want
