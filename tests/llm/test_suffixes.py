import hashlib
import random

import pyarrow.parquet as pq
import pytest

from synthselect.llm import suffixes as S


def _brute(rows, length=100):
    """rows: (doc_id, bytes) in order. Result per row."""
    seen = {}
    out = {}
    for d, raw in sorted(rows):
        gone = bytearray(len(raw))
        for i in range(len(raw) - length + 1):
            w = raw[i : i + length]
            if w in seen:
                gone[i : i + length] = b"\1" * length
            else:
                seen[w] = True
        kept = bytes(c for c, g in zip(raw, gone) if not g)
        spans = sum(1 for k, g in enumerate(gone) if g and (k == 0 or not gone[k - 1]))
        out[d] = (len(raw), sum(gone), spans, hashlib.sha256(kept).hexdigest())
    return out


def _run(spark, rows):
    df = spark.createDataFrame([(d, r.decode("utf-8", "strict"), "x") for d, r in rows], "doc_id long, text string, spans string").repartition(3)
    return {r.doc_id: tuple(r)[1:] for r in S.dedup_bytes(df).collect()}


def _texts(seed, n, alphabet="abcdefghij klmno."):
    rng = random.Random(seed)
    mk = lambda k: "".join(rng.choice(alphabet) for _ in range(k))
    passages = [mk(rng.choice([60, 99, 100, 101, 130, 180, 260, 700])) for _ in range(12)]
    docs = []
    for k in range(n):
        parts = []
        for _ in range(rng.randint(0, 6)):
            parts.append(rng.choice(passages) if rng.random() < 0.5 else mk(rng.randint(0, 150)))
        t = "".join(parts)
        if docs and rng.random() < 0.3:
            t = list(rng.choice(docs)[1].decode())
            for _ in range(rng.randint(0, 3)):
                if t:
                    t[rng.randrange(len(t))] = "Z"
            t = "".join(t)
        docs.append((k, t.encode()))
    return docs


def test_random_texts_equal_brute_force(spark):
    rows = _texts(1, 150)
    rows += [(1000, b"a" * 450), (1001, b"ab" * 300), (1002, b"a" * 99), (1003, "é".encode() * 200), (1004, b"x" * 50 + b"a" * 120), (1005, ("yz" + "é" * 60).encode())]
    assert _run(spark, rows) == _brute(rows)


@pytest.mark.parametrize(("many", "kinds", "sifted"), [(2, 3, 400_000), (2, 3, 50), (10**9, 3, 50), (2, 12, 300)])
def test_anchors_of_very_many_kinds_give_the_same(spark, monkeypatch, many, kinds, sifted):
    for name, v in (("MANY", many), ("MOST_KINDS", kinds), ("SIFTED", sifted)):
        monkeypatch.setattr(S, name, v)
    rng = random.Random(8)
    line = "".join(rng.choice("abcdefgh ") for _ in range(130))
    short = line[:50]
    mk = lambda n: "".join(rng.choice("ij") for _ in range(n))
    rows = [(k, ("".join(rng.choice("ijklmnop") for _ in range(80)) + line + "".join(rng.choice("qrstuv") for _ in range(80))).encode()) for k in range(40)]
    rows += [(k + 100, r) for k, r in _texts(2, 40)]
    tails, heads = [mk(60) for _ in range(4)], [mk(60) for _ in range(4)]
    rows += [(k + 200, (mk(30) + rng.choice(heads) + short + rng.choice(tails) + mk(30)).encode()) for k in range(60)]
    assert _run(spark, rows) == _brute(rows)


def test_padding_leaves_its_task_as_one_span(spark):
    rng = random.Random(5)
    text = "".join(rng.choice("abc ") for _ in range(40)) + "=" * 50_000 + "-=" * 20_000
    df = spark.createDataFrame([(1, text), (2, text[:70_000])], "doc_id long, text string").coalesce(1)
    keyed = S._keyed(df)
    rows = S._anchor_rows(keyed, 100, S.np.empty(0, S.np.int64)).collect()
    assert len(rows) < 500 and sum(r.stop >= 0 for r in rows) < 10
    assert S._very_many(keyed, 100).tolist() == []


def test_rows_of_one_id_keep_their_own_spans(spark):
    rng = random.Random(6)
    mk = lambda n: "".join(rng.choice("abcdefgh ") for _ in range(n))
    first, own = mk(150), [mk(266) for _ in range(60)]
    rows = [(1, first)] + [(5, t) for t in own] + [(5, mk(60) + first + mk(56)), (None, mk(200)), (None, first), (None, None), (5, None)]
    got = S.dedup_bytes(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sorted(r.n_removed for r in got) == [0] * 64 + [150, 150]
    assert [r.n_removed for r in got if r.doc_id == 1] == [150]  # a null id comes before all


def test_columns_of_the_caller_stay(spark):
    rng = random.Random(7)
    text = "".join(rng.choice("abcdefgh ") for _ in range(150))
    cols = ["doc_id", "doc", "tie", "spans", "row", "text", "start", "n_chars", "z"]
    df = spark.createDataFrame([(k, "mine", 7, "s", "r", text, 9, 0, "zz") for k in range(2)], "doc_id long, doc string, tie int, spans string, row string, text string, start int, n_chars long, z string")
    got = S.drop_repeats(df)
    assert got.columns == cols and got.dtypes == df.dtypes
    assert sorted(map(tuple, got.collect())) == [(0, "mine", 7, "s", "r", text, 9, 150, "zz"), (1, "mine", 7, "s", "r", "", 9, 0, "zz")]


def test_whole_table_equals_brute_force(spark):
    t = pq.read_table("/root/testdata/sf0.01/documents.parquet").to_pydict()
    rows = [(d, x.encode()) for d, x in zip(t["doc_id"], t["text"])]
    got = {r.doc_id: tuple(r)[1:] for r in S.op9_suffixes(spark, "/root/testdata/sf0.01").collect()}
    assert got == _brute(rows)


def test_parts_of_a_long_text_overlap(spark, monkeypatch):
    monkeypatch.setattr(S, "PART", 400)
    for seed in range(3):
        raw = b"".join(r for _, r in _texts(seed, 30))
        h, at, left, right = S.anchors(raw)
        covered = set()
        for a, x, y in zip(at, left, right):
            covered.update(range(a - x, a + y - 99))
        assert covered == set(range(len(raw) - 99))


def test_maximal_repeats_lists_all_occurrences():
    common = b"r" * 10 + b"q" * 110
    left = [b"abc"[k : k + 1] + b"zz" for k in range(3)] + [b"ayy"]
    right = [common + bytes([k]) for k in (1, 2, 2, 3)]
    got = sorted((b, r, sorted(m)) for b, r, m in S.maximal_repeats(left, right))
    assert (0, 120, [0, 1, 2, 3]) in got and (0, 121, [1, 2]) in got and (1, 120, [0, 3]) in got and len(got) == 3


def test_nulls_ties_repeats_and_no_rows(spark):
    rng = random.Random(3)
    long = "".join(rng.choice("abcdefg ") for _ in range(300))
    rows = [(None, long), (1, None), (2, ""), (3, long), (3, long), (3, long[:150] + "!" * 30), (4, long + "x")]
    df = spark.createDataFrame([(*r, 5) for r in rows], "doc_id long, text string, tie int")
    got = S.dedup_bytes(df).collect()
    assert len(got) == 7
    assert [r.n_removed for r in got if r.doc_id is None] == [0] and {r.n_removed for r in got if r.doc_id in (1, 2)} == {0}
    assert sorted(r.n_removed for r in got if r.doc_id == 3) == [150, 300, 300] and [r.n_removed for r in got if r.doc_id == 4] == [300]
    assert S.dedup_bytes(df.limit(0)).collect() == []
    cut = S.drop_repeats(df.withColumn("n_chars", S.F.lit(0)))
    assert cut.columns == [*df.columns, "n_chars"] and [(r.text, r.n_chars) for r in cut.collect() if r.doc_id == 4] == [("x", 1)]
    assert sorted(str(r.text) for r in cut.collect() if r.doc_id in (1, 2)) == ["", "None"]


def _brute_groups(rows, length):
    """Strings of maximal pairs with all their places."""
    at = {}
    for d, raw in rows:
        for i in range(len(raw) - length + 1):
            at.setdefault(raw[i : i + length], []).append((d, i))
    texts, found = dict(rows), set()
    for places in at.values():
        for n, (d, i) in enumerate(places):
            for e, j in places[n + 1 :]:
                a, b = texts[d], texts[e]
                x, y = 0, length
                while i - x > 0 and j - x > 0 and a[i - x - 1] == b[j - x - 1]:
                    x += 1
                while i + y < len(a) and j + y < len(b) and a[i + y] == b[j + y]:
                    y += 1
                found.add(a[i - x : i + y])
    return {(s, d, k) for s in found for d, raw in rows for k in range(len(raw) - len(s) + 1) if raw[k : k + len(s)] == s}


def test_repeat_groups_equal_brute_force(spark):
    import xxhash

    rows = [(d, r) for d, r in _texts(4, 60) if len(r) < 1000] + [(500, b"a" * 160), (501, b"xy" * 90), (502, b"zz" + b"a" * 130)]
    want = {(xxhash.xxh3_128_hexdigest(s), len(s), d, k) for s, d, k in _brute_groups(rows, 100)}
    df = spark.createDataFrame([(d, r.decode(), "x") for d, r in rows], "doc_id long, text string, repeat string").repartition(3)
    got = S.repeat_groups(df).collect()
    assert {(r.repeat, r.n_bytes, r.doc_id, r.start) for r in got} == want and len(got) == len(want) > 100
    assert all(r.n_occurrences >= 2 for r in got)


def test_repeat_groups_on_odd_rows(spark):
    rng = random.Random(9)
    text = "".join(rng.choice("abc ") for _ in range(140))
    df = spark.createDataFrame([(None, text), (1, None), (1, ""), (2, text + "x"), (2, text + "x")], "doc_id long, text string")
    got = {(r.n_bytes, r.n_occurrences, r.doc_id, r.start) for r in S.repeat_groups(df).collect()}
    assert got == {(140, 2, None, 0), (140, 2, 2, 0)} and S.repeat_groups(df.limit(0)).collect() == []
