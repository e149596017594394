import zlib

import numpy as np
import pyarrow.parquet as pq

from synthselect.llm import quality as Q


def test_held_out_accuracy_and_contract(spark):
    d = "/root/testdata/sf0.01"
    got = {r.doc_id: r for r in Q.op10_quality(spark, d).collect()}
    docs, labels = (pq.read_table(f"{d}/{t}.parquet").to_pydict() for t in ("documents", "labels"))
    assert got.keys() == set(docs["doc_id"])
    assert all(r.held_out == (zlib.crc32(str(i).encode()) % 4 == 2) and 0 <= r.score <= 1 and r.predicted == int(r.score >= 0.7) for i, r in got.items())
    y = dict(zip(labels["doc_id"], labels["quality"]))
    held = [i for i in y if got[i].held_out]
    assert np.mean([got[i].predicted == y[i] for i in held]) >= 0.95
    pos, neg = (np.array([got[i].score for i in held if y[i] == k]) for k in (1, 0))
    assert (pos[:, None] > neg[None]).mean() >= 0.97


def _rows(rng, n):
    out = []
    for _ in range(n):
        at = np.unique(rng.integers(0, Q.TERMS, 300)).astype(np.int32)
        out.append((at, rng.integers(1, 5, len(at)).astype(np.float32)))
    return out


def test_votes_equal_a_plain_computation():
    rng = np.random.default_rng(0)
    y = rng.integers(0, 2, 400)
    m = Q.NeighbourVote(_rows(rng, 400), y, dimensions=16, neighbours=7)
    new = Q.matrix(_rows(rng, 20))
    for row, s in zip(m.places(new), m.score(new)):
        sim = m.vectors @ row
        near = np.argsort(-sim)[:7]
        w = np.maximum(sim[near], 0).astype(float) ** Q.POWER
        assert abs(s - (w * y[near]).sum() / w.sum()) < 1e-4


def test_axes_span_the_leading_singular_vectors():
    rng = np.random.default_rng(2)
    topics = [np.unique(rng.integers(0, Q.TERMS, 80)).astype(np.int32) for _ in range(6)]
    rows = []
    for k in range(180):
        at = np.unique(np.concatenate([topics[k % 6], rng.integers(0, Q.TERMS, 10)])).astype(np.int32)
        rows.append((at, rng.integers(1, 5, len(at)).astype(np.float32)))
    m = Q.NeighbourVote(rows, np.arange(180) % 2, dimensions=6)
    x = m._weighted(Q.matrix(rows))
    best = np.linalg.svd(x, compute_uv=False)[:6]
    assert np.allclose(m.axes.T @ m.axes, np.eye(6), atol=1e-4)
    assert ((x @ m.axes) ** 2).sum() >= 0.98 * (best**2).sum()


def test_words_tell_texts_of_one_shape_apart(spark):
    good, bad = "alpha beta gamma delta".split(), "omega sigma kappa theta".split()
    rng = np.random.default_rng(3)
    docs = [(i, " ".join(rng.choice(good if i % 2 else bad, 30))) for i in range(200)]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(200)], "doc_id long, quality int")
    got = {r.doc_id: r.predicted for r in Q.score_documents(df, labels).collect()}
    assert all(got[i] == i % 2 for i in range(200))


def test_one_id_on_many_documents_sends_one(spark):
    docs = spark.range(3000).selectExpr("0L AS doc_id", "concat('some words here number ', id) AS text").union(spark.createDataFrame([(1, "WHAT!! ELSE!!")], "doc_id long, text string"))
    labels = spark.createDataFrame([(0, 1), (0, 1), (1, 0)], "doc_id long, quality int")
    assert len(Q.fit(docs, labels).labels) == 2


def test_held_out_labels_never_matter(spark):
    docs = spark.createDataFrame([(i, ("good words here. " if i % 3 else "BAD!! STUFF!! ") * (i % 7 + 1)) for i in range(80)], "doc_id long, text string")
    held = [i for i in range(80) if zlib.crc32(str(i).encode()) % 4 == 2]
    lab = [(i, int(bool(i % 3))) for i in range(80)]
    flipped = [(i, 1 - q if i in held else q) for i, q in lab]
    a, b = (sorted(Q.score_documents(docs, spark.createDataFrame(x, "doc_id long, quality int")).collect()) for x in (lab, flipped))
    assert a == b


def test_odd_rows(spark):
    docs = spark.createDataFrame([(1, None, 1.0), (2, "", 1.0), (None, "some text here", 1.0), (2, "x" * 300000, 1.0)], "doc_id long, text string, score double")
    labels = spark.createDataFrame([(1, 1), (2, None), (None, 0)], "doc_id long, quality int")
    assert len(Q.score_documents(docs, labels).collect()) == 4
    none = Q.score_documents(docs, labels.limit(0)).collect()
    assert {r.score for r in none} == {0.5} and {r.predicted for r in none} == {0}
    assert Q.score_documents(docs.limit(0), labels).collect() == []
    kept = Q.keep_good(docs, spark.createDataFrame([(1, 1), (2, 1), (3, 1)], "doc_id long, quality int"))
    assert kept.columns == docs.columns and kept.count() == 4


def test_keep_good_on_odd_tables(spark):
    docs = spark.createDataFrame([(None, "plain words of some text", "a"), (1, None, "b"), (1, "plain words of some text", "c"), (2, "", None)], "doc_id long, text string, _q string")
    none = spark.createDataFrame([], "doc_id long, quality int")
    assert Q.keep_good(docs, none).count() == 0  # nothing labelled: every score is 0.5, under the threshold
    labels = spark.createDataFrame([(1, 1), (None, 0), (5, None)], "doc_id long, quality int")
    kept = Q.keep_good(docs, labels)
    assert kept.columns == docs.columns and sorted(map(str, (r._q for r in kept.collect()))) == ["None", "a", "b", "c"]
    assert Q.keep_good(docs.limit(0), labels).count() == 0
