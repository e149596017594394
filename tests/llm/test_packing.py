import zlib

import numpy as np
import pyarrow.parquet as pq
from hypothesis import given, settings
from hypothesis import strategies as st

from synthselect.llm import packing
from synthselect.llm.tokencount import tokenizer_path


def _one_by_one(lengths, gaps):
    """Best fit of descending lengths: (gaps left, lengths left)."""
    gaps, alone = list(gaps), []
    for x in sorted(lengths, reverse=True):
        fit = [g for g in gaps if g >= x]
        if fit:
            gaps.remove(min(fit))
            gaps.append(min(fit) - x)
        else:
            alone.append(x)
    return sorted(g for g in gaps if g), alone


@settings(max_examples=200, deadline=None)
@given(st.lists(st.integers(1, 40), max_size=60), st.lists(st.integers(1, 90), max_size=30), st.integers(1, 7))
def test_a_sweep_is_best_fit(lengths, gaps, block):
    rows = sorted([(-g, packing.GAP, k) for k, g in enumerate(gaps)] + [(-x, packing.PIECE, k) for k, x in enumerate(lengths)])
    sweep, placed = packing.Sweep(0), []
    for k in range(0, len(rows), block):
        placed += list(zip(*sweep.take(*zip(*[(-s, kind, i) for s, kind, i in rows[k : k + block]]))))
    left, alone = _one_by_one(lengths, gaps)
    assert sorted(s for s, _ in sweep.left() + sweep.below()) == left and all(s >= -rows[-1][0] for s, _ in sweep.left()) and sweep.left() == sorted(sweep.left(), key=lambda x: x[0])
    assert [x for _, x in sweep.alone] == alone and len(placed) + len(alone) == len(lengths)
    used = {}
    for piece, seq, gap in placed:
        used[seq] = used.get(seq, gaps[seq])
        assert gap == used[seq] >= lengths[piece]
        used[seq] -= lengths[piece]


@settings(max_examples=200, deadline=None)
@given(st.lists(st.tuples(st.integers(0, 6), st.integers(0, 6)), max_size=12))
def test_ranks_deal_the_nearest_larger_gaps(ranges):
    alone, slots = [a for a, _ in ranges], [s for _, s in ranges]
    rows, taken = packing.deal(alone, slots)
    stack, want = [], []
    for p, (a, s) in enumerate(ranges):
        for r in range(a):
            if stack:
                want.append((p, r, *stack.pop()))
        stack += [(p, k) for k in range(s)][::-1]
    got = [(p, r + k, q, s + k) for p, r, n, q, s in rows.tolist() for k in range(n)]
    assert got == want and sum(taken) == len(want)


def _verify(got, docs):
    from tokenizers import Tokenizer

    lib = Tokenizer.from_file(tokenizer_path("word_bpe_49k.json"))
    ids = {d: [*lib.encode(t or "", add_special_tokens=False).ids, 0] for d, t in docs}
    by_doc, by_seq = {}, {}
    for r in got:
        by_doc.setdefault(r.doc_id, []).append(r)
        by_seq.setdefault(r.sequence_id, []).append(r)
    assert by_doc.keys() == ids.keys()
    for d, rows in by_doc.items():
        rows.sort(key=lambda r: r.piece)
        cut = [ids[d][k : k + 2048] for k in range(0, len(ids[d]), 2048)]
        assert [(r.piece, r.start, r.length, r.ids_crc32) for r in rows] == [(k, 2048 * k, len(c), zlib.crc32(np.array(c, "<u4").tobytes())) for k, c in enumerate(cut)]
    for rows in by_seq.values():
        at = 0
        for r in sorted(rows, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= 2048
    return len(by_seq), sum(r.length for r in got)


def test_whole_table(spark):
    t = pq.read_table("/root/testdata/sf0.01/documents.parquet").to_pydict()
    n, total = _verify(packing.op6_packing(spark, "/root/testdata/sf0.01").collect(), list(zip(t["doc_id"], t["text"])))
    assert n <= -(-total // 2048) + 2


def test_many_ranges_pack_as_well(spark, monkeypatch):
    monkeypatch.setattr(packing, "RANGE_ROWS", 150)
    t = pq.read_table("/root/testdata/sf0.01/documents.parquet").to_pydict()
    n, total = _verify(packing.op6_packing(spark, "/root/testdata/sf0.01").collect(), list(zip(t["doc_id"], t["text"])))
    assert n <= -(-total // 2048) + 2


def test_lengths_of_one_class_and_equal_lengths(spark, monkeypatch):
    monkeypatch.setattr(packing, "RANGE_ROWS", 40)
    rng = np.random.default_rng(4)
    for lengths in ([30] * 500, [700] * 101, [1025] * 9, rng.integers(1, 2049, 300).tolist(), [2048, 1, 2047, 1], rng.integers(1, 300, 400).tolist()):
        df = spark.createDataFrame(list(enumerate(lengths)), "pid long, length long")
        got = packing.place(df).collect()
        assert sorted(r.pid for r in got) == list(range(len(lengths)))
        seqs = {}
        for r in got:
            seqs.setdefault(r.seq, []).append((r.offset, lengths[r.pid]))
        for rows in seqs.values():
            at = 0
            for o, x in sorted(rows):
                assert o == at
                at += x
            assert at <= 2048
        best = len(lengths) and -(-sum(lengths) // 2048)
        bfd = _bfd(lengths)
        assert best <= len(seqs) <= bfd + max(2, bfd // 20), (len(seqs), bfd)


def _bfd(lengths):
    gaps = []
    for x in sorted(lengths, reverse=True):
        fit = [g for g in gaps if g >= x]
        if fit:
            gaps.remove(min(fit))
        gaps.append((min(fit) if fit else 2048) - x)
    return len(gaps)


def test_odd_texts_and_ids(spark):
    docs = [(1, None), (2, ""), (3, "ΑΣ İx\x1cy é é <|endoftext|> ok"), (4, "a " * 5000), (5, "x" * 20000), (6, "It's  a\xa0Ünder_score's 12   done"), (7, "<|startoftext|>")]
    df = spark.createDataFrame([(*d, "z", 3) for d in docs], "doc_id long, text string, piece string, part int")
    _verify(packing.pack(df).collect(), docs)
    twice = packing.pack(df.union(df)).collect()
    assert len(twice) == 2 * len(packing.pack(df).collect())
    assert packing.pack(df.limit(0)).collect() == []
    none = packing.pack(spark.createDataFrame([(None, "a")], "doc_id long, text string")).collect()
    assert len(none) == 1 and none[0].doc_id is None
