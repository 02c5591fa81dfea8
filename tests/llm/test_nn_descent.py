import numpy as np

from lincompress.llm import nn_descent

SF = "/root/testdata/sf0.1"


def exact(ids, x, queries, k=5):
    z = x / np.sqrt((x * x).sum(axis=1, keepdims=True))
    out = {}
    for q in queries:
        i = ids.index(q)
        s = z @ z[i]
        order = sorted((j for j in range(len(ids)) if j != i), key=lambda j: (-s[j], ids[j]))[:k]
        out[q] = [(ids[j], s[j]) for j in order]
    return out


def test_recall_and_scores(spark):
    rows = spark.read.parquet(f"{SF}/embeddings.parquet").collect()
    ids, x = [r.vec_id for r in rows], np.array([r.embedding for r in rows], float)
    want = exact(ids, x, [i for i in ids if i % 50 == 0])
    got = {}
    for r in nn_descent.op3_nn_descent(spark, SF).collect():
        got.setdefault(r.query_id, []).append(r)
    assert set(got) == set(want)
    hits = 0
    for q, found in got.items():
        found.sort(key=lambda r: r.rank)
        assert [r.rank for r in found] == [1, 2, 3, 4, 5]
        assert [(-r.score, r.vec_id) for r in found] == sorted((-r.score, r.vec_id) for r in found)
        for r in found:
            a, b = x[ids.index(q)], x[ids.index(r.vec_id)]
            assert abs(r.score - a @ b / np.sqrt((a @ a) * (b @ b))) < 1e-12
        hits += len({r.vec_id for r in found} & {i for i, _ in want[q]})
    assert hits / (5 * len(want)) >= 0.97


def test_many_blocks_keep_the_recall(spark, monkeypatch):
    monkeypatch.setattr(nn_descent, "BLOCK", 256)
    rng = np.random.default_rng(0)
    x = rng.normal(size=(3000, 24))
    x[1000:1600] = x[7] + 0.05 * rng.normal(size=(600, 24))
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    ids = list(range(len(x)))
    queries = df.where("vec_id % 30 = 0")
    want = exact(ids, x, range(0, 3000, 30))
    got = {}
    for r in nn_descent.nearest(df, queries, beam=128, width=32).collect():
        got.setdefault(r.query_id, set()).add(r.vec_id)
    assert sum(len(got[q] & {i for i, _ in w}) for q, w in want.items()) / (5 * len(want)) >= 0.95


def test_odd_vectors_and_copies(spark):
    nan, inf = float("nan"), float("inf")
    rows = [(i, [1.0, 2.0, 3.0]) for i in range(20)] + [(50, [3.0, 2.0, 1.0]), (100, [1.0, 2.0, 3.0]), (100, [1.0, 2.0, 3.0])]
    rows += [(150, None), (200, [0.0, 0.0, 0.0]), (250, [1.0, None, 2.0]), (300, [nan, 1.0, 1.0]), (350, [inf, 1.0, 1.0]), (400, [1.0]), (None, [1.0, 1.0, 1.0])]
    df = spark.createDataFrame([(*r, "x") for r in rows], "vec_id long, embedding array<double>, node string")
    got = {}
    for r in nn_descent.nearest(df, df.where("vec_id % 50 = 0")).collect():
        got.setdefault(r.query_id, []).append((r.rank, r.vec_id))
    assert {q: [i for _, i in sorted(v)] for q, v in got.items()} == {0: [1, 2, 3, 4, 5], 50: [0, 1, 2, 3, 4], 100: [0, 1, 2, 3, 4]}
    assert nn_descent.nearest(df.limit(0), df).count() == 0
    assert nn_descent.nearest(df.where("vec_id = 50"), df).count() == 0


def test_near_vectors_share_a_block_and_every_node_is_dealt(spark, monkeypatch):
    """Seven of ten nearest neighbours in the node's own block (by hash it would be one of eight); a crowded leaf of like vectors is dealt on."""
    monkeypatch.setattr(nn_descent, "BLOCK", 256)
    rng = np.random.default_rng(1)
    x = rng.normal(size=(40, 16))[np.arange(2000) % 40] + 0.2 * rng.normal(size=(2000, 16))
    x[:1200] = [1.0] * 16 + 1e-9 * rng.normal(size=(1200, 16))  # alike as floats
    x /= np.sqrt((x * x).sum(axis=1, keepdims=True))
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "key long, vector array<float>")
    dealt, blocks = nn_descent.deal(df, 2000, 16)
    rows = dealt.collect()
    assert sorted(r.key for r in rows) == list(range(2000)) and len({r.node for r in rows}) == 2000
    home = {r.key: r.node >> nn_descent.INSIDE for r in rows}
    sizes = np.bincount(list(home.values()), minlength=blocks)
    assert sizes.max() <= 2 * 256 and len(sizes) == blocks
    s = x[1200:] @ x[1200:].T - 2 * np.eye(800)
    near = np.argsort(-s, axis=1)[:, :5] + 1200
    assert np.mean([home[i] == home[j] for i, row in zip(range(1200, 2000), near, strict=True) for j in row]) >= 0.7
