import re

import numpy as np
import pyarrow.parquet as pq
import xxhash

from synthselect.llm import simhash


def _brute_fp(text):
    t = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")
    w = re.findall(r"[^\x20\x09-\x0D]+", t)
    if not w:
        return 0
    sh = [" ".join(w[i : i + 4]) for i in range(len(w) - 3)] or [" ".join(w)]
    hs = [xxhash.xxh64_intdigest(s.encode(), 42) for s in sh]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def _brute(rows):
    fps = {d: _brute_fp(t) for d, t in rows}
    ids = sorted(fps)
    root = {d: d for d in ids}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    v = np.array([fps[d] for d in ids], np.uint64)
    for i, d in enumerate(ids):
        for j in np.flatnonzero(np.bitwise_count(v[i] ^ v[i + 1 :]) <= 4):
            a, b = find(d), find(ids[i + 1 + j])
            root[max(a, b)] = min(a, b)
    return {(d, f"{fps[d]:016x}", find(d)) for d in ids}


def test_whole_table_equals_brute_force(spark):
    t = pq.read_table("/root/testdata/sf0.01/documents.parquet").to_pydict()
    got = {tuple(r) for r in simhash.op8_simhash(spark, "/root/testdata/sf0.01").collect()}
    assert got == _brute(zip(t["doc_id"], t["text"]))


def test_every_distance_up_to_four_bits_meets_and_chains_join(spark):
    rng = np.random.default_rng(5)
    base = rng.integers(0, 2**63, 40, dtype=np.uint64)
    vals = []
    for b in base:
        x = b
        for _ in range(6):  # a chain: each link 4 bits
            vals.append(int(x))
            for bit in rng.choice(64, 4, replace=False):
                x = x ^ np.uint64(1 << int(bit))
    v = np.array(vals, np.uint64).astype(np.int64)
    df = spark.createDataFrame([(int(x),) for x in v], "fp long")
    from synthselect.llm import common

    root = {r.id: r.root for r in common.components(simhash.links(df)).collect()}
    for k in range(0, len(v), 6):
        assert len({root.get(int(x), int(x)) for x in v[k : k + 6]}) == 1
    assert len({root.get(int(x), int(x)) for x in v}) == 40


def test_hot_bucket_is_cut_into_blocks(spark, monkeypatch):
    from synthselect.llm import common

    monkeypatch.setattr(simhash, "BLOCK", 8)
    df = spark.createDataFrame([(1 << i,) for i in range(60)] + [(0,)], "fp long")
    got = common.components(simhash.links(df)).collect()
    assert len(got) == 60 and len({r.root for r in got}) == 1


def test_nulls_empties_ties_and_clashing_columns(spark):
    rows = [(1, None, "x"), (2, "", "y"), (3, " \t\n", "z"), (4, "one two", "a"), (4, "one two", "b"), (None, "one TWO", "c"), (7, "a " * 30000, "d")]
    df = spark.createDataFrame(rows, "doc_id long, text string, fingerprint string").withColumn("component_id", df_lit(0))
    got = sorted(simhash.simhash_groups(df).collect(), key=str)
    assert len(got) == 7
    zero = [r for r in got if r.fingerprint == "0" * 16]
    assert sorted(r.doc_id for r in zero) == [1, 2, 3] and {r.component_id for r in zero} == {1}
    assert {r.component_id for r in got if r.doc_id in (4, None)} == {4}
    assert simhash.simhash_groups(df.limit(0)).collect() == []
    kept = simhash.near_dedup(df)
    assert kept.columns == df.columns and sorted(str(r.doc_id) for r in kept.collect()) == ["1", "4", "4", "7", "None"]


def df_lit(x):
    from pyspark.sql import functions as F

    return F.lit(x)


def test_finer_keys_keep_every_link(spark, monkeypatch):
    from synthselect.llm import common

    rng = np.random.default_rng(8)
    base = rng.integers(0, 2**63, 60, dtype=np.uint64)
    vals = list(base)
    for b in base:
        for _ in range(3):
            x = b
            for bit in rng.choice(64, rng.integers(1, 5), replace=False):
                x = x ^ np.uint64(1 << int(bit))
            vals.append(x)
    v = np.unique(np.array(vals, np.uint64))
    near = np.bitwise_count(v[:, None] ^ v[None]) <= 4
    label = np.arange(len(v))
    for _ in range(len(v)):
        label = np.array([label[row].min() for row in near])
    df = spark.createDataFrame([(int(x),) for x in v.astype(np.int64)], "fp long")
    for block in (1, 2048):
        monkeypatch.setattr(simhash, "BLOCK", block)
        root = {r.id: r.root for r in common.components(simhash.links(df)).collect()}
        got = [root.get(int(x), int(x)) for x in v.astype(np.int64)]
        assert len(set(got)) == len(set(label.tolist())) == len(set(zip(got, label.tolist())))
