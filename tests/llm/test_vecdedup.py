import numpy as np
import pyarrow.parquet as pq
import pytest

from synthselect.llm import vecdedup


def test_decoder_is_exact_against_all_near_points():
    rng = np.random.default_rng(3)
    x = rng.normal(size=(300, 8)) * 2
    got = vecdedup.decode_e8(x) / 2
    near = np.vstack([np.zeros((1, 8)), vecdedup.shortest_e8() / 2])
    four = near[:, None, :] + near[None, :, :]
    cand = np.unique(four.reshape(-1, 8), axis=0)
    for y, g in zip(x, got):
        best = ((g + cand - y) ** 2).sum(axis=1).min()
        assert ((g - y) ** 2).sum() == pytest.approx(best)
    two = np.rint(2 * got).astype(int)
    assert ((two % 2 == two[:, :1] % 2).all(axis=1)).all() and (two.sum(axis=1) % 4 == 0).all()


def _brute(ids, vecs, labels, least=0.93):
    x = np.array(vecs, np.float64)
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    lab = np.array(labels)
    link = (u @ u.T >= least) & (lab[:, None] == lab[None, :])
    np.fill_diagonal(link, False)
    return link


def _check(spark, ids, vecs, labels):
    df = spark.createDataFrame([(int(i), [float(v) for v in x], int(lab)) for i, x, lab in zip(ids, vecs, labels)], "vec_id long, embedding array<float>, label int")
    got = {r.vec_id: r for r in vecdedup.similar(df).collect()}
    link = _brute(ids, np.array(vecs, np.float32), labels)
    n = np.array([got[i].n_links for i in ids])
    assert (n <= link.sum(axis=1)).all()
    return got, link, n


def test_counts_components_and_recall(spark):
    rng = np.random.default_rng(9)
    base = rng.normal(size=(250, 64))
    base /= np.linalg.norm(base, axis=1, keepdims=True)
    noise = rng.normal(size=(1000, 64))
    noise /= np.linalg.norm(noise, axis=1, keepdims=True)
    of = np.repeat(np.arange(250), 4)
    t = np.tan(np.arccos(rng.uniform(0.93, 1.0, 1000)))[:, None] * 0.95
    vecs = np.vstack([base, base[of] + t * noise, base[:30]])  # 30 exact copies
    labels = np.concatenate([np.arange(250) % 7, of % 7, np.arange(30) % 7])
    got, link, n = _check(spark, np.arange(len(vecs)), vecs, labels)
    assert n.sum() >= 0.9 * link.sum()
    for i in range(30):
        assert got[1250 + i].component_id == got[i].component_id and not got[1250 + i].kept


def test_one_dense_group_counts_every_pair_once(spark, monkeypatch):
    monkeypatch.setattr(vecdedup, "BLOCK", 64)
    rng = np.random.default_rng(1)
    v = np.ones(16) / 4 + rng.normal(size=(300, 16)) * 0.004
    got, link, n = _check(spark, np.arange(300), v, np.zeros(300))
    assert (n == 299).all() and {r.component_id for r in got.values()} == {0}


def test_rows_that_link_with_nothing(spark):
    nan, inf = float("nan"), float("inf")
    rows = [(1, [1.0, 0.0], 1), (2, [1.0, 0.0], None), (3, [1.0, 0.0], None), (4, None, 1), (5, [0.0, 0.0], 1), (6, [0.0, 0.0], 1), (7, [nan, 1.0], 1), (8, [nan, 1.0], 1), (9, [inf, 1.0], 1), (10, [None, 1.0], 1), (11, [], 1), (12, [2.0, 0.0], 1), (13, [1.0, 0.0, 0.0], 1), (14, [1.0, 0.0], 2), (15, [1e300, 0.0], 1), (None, [0.0, 1.0], 1)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int").selectExpr("*", "1 as n_links", "'x' as node")
    got = {r.vec_id: tuple(r)[1:] for r in vecdedup.similar(df).collect()}
    assert len(got) == 16 and got[1] == (2, 1, True) and got[12] == (2, 1, False) and got[15] == (2, 1, False)
    assert all(got[i] == (0, i, True) for i in (2, 3, 4, 5, 6, 7, 8, 9, 10, 11, 13, 14)) and got[None] == (0, None, None)
    assert vecdedup.similar(df.limit(0)).collect() == []


def test_given_table_recall(spark):
    t = pq.read_table("/root/testdata/sf0.01/embeddings.parquet").to_pydict()
    got = {r.vec_id: r for r in vecdedup.op3_vectors(spark, "/root/testdata/sf0.01").collect()}
    link = _brute(t["vec_id"], t["embedding"], t["label"])
    n = np.array([got[i].n_links for i in t["vec_id"]])
    assert (n <= link.sum(axis=1)).all() and n.sum() >= 0.9 * link.sum()
