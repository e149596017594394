import random

import numpy as np

from synthselect.llm import licenses as L
from synthselect.llm.license_texts import TEMPLATES


def _brute(index, text):
    """Templates of which some run of words as long as the template holds 80 % of the shingles."""
    h = index.shingler.hashes(index.shingler.words(text))
    out = set()
    for name, s in zip(index.names, index.sets):
        hit = np.isin(h, s)
        for k in range(max(1, len(h) - len(s) + 1)):
            if len(np.unique(h[k : k + len(s)][hit[k : k + len(s)]])) >= 0.8 * len(s):
                out.add(name)
                break
    return out


def _texts(n=150):
    rng = random.Random(4)
    words = [f"w{k}" for k in range(3000)]
    out = []
    for k in range(n):
        body = [rng.choice(words) for _ in range(rng.randint(0, 400))]
        for name in rng.sample(list(TEMPLATES), rng.randint(0, 2)):
            t = TEMPLATES[name].split()
            for _ in range(len(t) // 60):
                t[rng.randrange(len(t))] = rng.choice(words)
            at = rng.randint(0, len(body))
            body[at:at] = t if rng.random() < 0.8 else t[: int(len(t) * 0.6)]
        out.append(" ".join(body))
    return out


def test_finds_all_that_brute_force_finds():
    index = L.LicenseIndex()
    texts = _texts()
    got = index.scan(texts)
    for t, (_, _, found) in zip(texts, got):
        names = {m[0] for m in found}
        assert _brute(index, t) <= names
        for name, s, e, share in found:
            words = index.shingler.words(t)[s:e]
            mine = index.sets[index.names.index(name)]
            assert len(np.intersect1d(index.shingler.hashes(words), mine)) == round(share * len(mine)) and share >= 0.8


def test_band_settings_meet_the_bound():
    for c in L.LicenseIndex().classes:
        assert 1 - (1 - c.likeness**c.rows) ** c.bands >= 0.999 or c.likeness == 1.0


def test_whole_table_equals_brute_force(spark):
    import pyarrow.parquet as pq

    t = pq.read_table("/root/testdata/sf0.001/documents.parquet").to_pydict()
    index = L.LicenseIndex()
    got = {r.doc_id: set(filter(None, r.licenses.split(","))) for r in L.op5_licenses(spark, "/root/testdata/sf0.001").collect()}
    assert got == {d: _brute(index, x) for d, x in zip(t["doc_id"], t["text"])}
    assert any(got.values())


def test_odd_rows(spark):
    rows = [(1, None), (2, ""), (3, "one two"), (None, TEMPLATES["mit"]), (5, ("word " * 30000) + TEMPLATES["mit-notice"]), (5, TEMPLATES["mit-notice"])]
    df = spark.createDataFrame([(*r, "x") for r in rows], "doc_id long, text string, licenses string")
    got = L.scan_licenses(df).collect()
    assert len(got) == 6 and sorted(r.licenses for r in got) == ["", "", "", "mit", "mit-notice", "mit-notice"]
    assert L.scan_licenses(df.limit(0)).collect() == []


def test_recall_at_the_boundary_is_as_stated():
    rng = random.Random(12)
    index = L.LicenseIndex()
    words = [f"w{k}" for k in range(20000)]
    texts, want = [], []
    for name, own in zip(index.names, index.sets):
        t = index.shingler.words(TEMPLATES[name])
        for trial in range(40):
            w = list(t)
            if trial % 2:  # words all over replaced, as many as the bound allows
                for at in rng.sample(range(len(w)), len(w)):
                    new = w[:at] + [rng.choice(words)] + w[at + 1 :]
                    if len(np.intersect1d(index.shingler.hashes(new), own)) >= 0.8 * len(own):
                        w = new
                    elif len(own) > 100:
                        break
            else:  # the end cut off
                while len(np.intersect1d(index.shingler.hashes(w[:-1]), own)) >= 0.8 * len(own):
                    w.pop()
            before, after = ([rng.choice(words) for _ in range(rng.randint(0, 500))] for _ in range(2))
            texts.append(" ".join(before + w + after))
            want.append(name)
    hit = [name in {m[0] for m in found} for name, (_, _, found) in zip(want, index.scan(texts))]
    assert len(hit) > 1000 and np.mean(hit) >= 0.997


def test_texts_without_a_template_shingle_have_no_candidates():
    index = L.LicenseIndex()
    clean = " ".join(f"w{k}" for k in range(3000))
    whole = [c.hop for c in index.classes]
    (n, cands, found), (m, _, hit) = index.scan([clean, clean + " " + TEMPLATES["mit"]])
    assert cands == 0 and found == [] and n > len(whole) and m > n and hit
