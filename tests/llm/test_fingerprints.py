import hashlib
import re

import pyarrow.parquet as pq

from synthselect.llm import fingerprints as P

SF = "/root/testdata/sf0.001"


def _shingles(t):
    w = [x for x in re.split(r"[ \t\n\x0B\f\r]+", t.lower()) if x]
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def _jaccard(a, b):
    a, b = _shingles(a), _shingles(b)
    return 1.0 if not a and not b else len(a & b) / len(a | b)


def _expected(rows):
    rows = sorted(rows)
    out = {}
    for k, (d, t) in enumerate(rows):
        n = rows[(k + 1) % len(rows)][1]
        cut = len(t) // 4
        out[d] = (len(t), t[: len(t) - cut] + n[:cut], n)
    return out


def test_whole_table_against_brute_force(spark):
    t = pq.read_table(f"{SF}/documents.parquet").to_pydict()
    text = dict(zip(t["doc_id"], t["text"]))
    got = {r.doc_id: r for r in P.op1_minhash(spark, SF).collect()}
    want = _expected(list(text.items()))
    assert got.keys() == want.keys()
    prints = {}
    for d, (n, edited, nxt) in want.items():
        r = got[d]
        assert r.n_chars == n and r.edited_sha256 == hashlib.sha256(edited.encode()).hexdigest(), d
        assert abs(r.near_edited - _jaccard(text[d], edited)) < 0.2 and abs(r.near_next - _jaccard(text[d], nxt)) < 0.2
        assert prints.setdefault(text[d], r.fingerprint) == r.fingerprint and len(r.fingerprint) == 512
    err = [abs(got[d].near_edited - _jaccard(text[d], e)) for d, (_, e, _) in want.items()]
    assert sum(err) / len(err) < 0.03
    assert "Python" not in P.op1_minhash(spark, SF)._jdf.queryExecution().toString() and "Arrow" not in P.op1_minhash(spark, SF)._jdf.queryExecution().toString()


def test_next_row_over_many_ranges(spark, monkeypatch):
    monkeypatch.setattr(P, "RANGE_ROWS", 3)
    ids = [-5, 0, 1, 2, 3, 5, 8, 1000, 1001, 1002, 10**12, 10**12 + 1] + list(range(2000, 2100, 7))
    df = spark.createDataFrame([(i, f"t{i}") for i in ids], "id long, text string").repartition(5)
    got = {r.id: r.next_text for r in P.with_next(df, ["text"], "id", ["text"]).collect()}
    s = sorted(ids)
    assert got == {a: f"t{b}" for a, b in zip(s, s[1:] + s[:1])}


def test_nulls_empties_ties_single_and_no_rows(spark):
    rows = [(None, "before all of them", 0), (1, None, 0), (2, "", 0), (3, "a b c d e f g h", 0), (3, "a b c d e f g h", 0), (4, "wörter \U0001f600 und mehr text hier", 0)]
    df = spark.createDataFrame(rows, "doc_id long, text string, fingerprint int")
    got = P.fingerprints(df).collect()
    assert len(got) == 6
    by = {r.doc_id: r for r in got}
    assert by[1].fingerprint == by[2].fingerprint == "0" * 512 and by[1].near_next == 1.0 and by[2].near_next == 0.0 and by[1].near_edited == 1.0
    assert len({r.fingerprint for r in got if r.doc_id == 3}) == 1
    one = P.fingerprints(df.filter("doc_id = 4")).first()
    assert one.near_next == 1.0 and one.n_chars == 27
    assert P.fingerprints(df.limit(0)).collect() == []
