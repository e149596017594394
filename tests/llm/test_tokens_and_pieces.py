import hashlib
import random

import pyarrow.parquet as pq
import pytest

from synthselect.llm import merges, pieces, tokencount
from synthselect.llm.tokencount import tokenizer_path

SF = "/root/testdata/sf0.01"


def _odd_texts(seed=3, n=1500):
    rng = random.Random(seed)
    letters = "aaaabcdethein  \n\t'sТ中文é́\x1c\x1f\x85\xa0 \U0001f6420123½²!?<|endoftext|><s>ﬁİΣσς▁\0�"
    out = ["".join(rng.choice(letters) for _ in range(rng.randint(0, 60))) for _ in range(n)]
    out += ["".join(chr(rng.choice([rng.randint(0, 0x2FF), rng.randint(0x300, 0xD7FF), rng.randint(0xE000, 0x1FFFF)])) for _ in range(rng.randint(1, 30))) for _ in range(n)]
    words = "the of and tion ing er in at on ▁ is es re".split()
    out += ["".join(rng.choice(words) for _ in range(rng.randint(1, 40))) for _ in range(n)]
    return out + [" " * k for k in range(70)] + ["a<|endoftext|><|endoftext|> b", "x" * 3000, "ab" * 2000 + " " * 500, "\n" * 50, " a", ""]


@pytest.fixture(scope="module")
def byte_lib():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(tokenizer_path("byte_bpe_50k.json"))


@pytest.fixture(scope="module")
def piece_lib():
    import sentencepiece

    return sentencepiece.SentencePieceProcessor(model_file=tokenizer_path("piece_bpe_32k.model"))


def test_counts_equal_the_library_on_odd_texts(byte_lib):
    texts = _odd_texts()
    c = tokencount.ByteMerges(tokenizer_path("byte_bpe_50k.json"))
    assert c.counts(texts) == [len(e.ids) for e in byte_lib.encode_batch(texts, add_special_tokens=False)]


def test_counts_of_the_whole_table(spark, byte_lib):
    t = pq.read_table(f"{SF}/documents.parquet").to_pydict()
    want = {(d, len(x.encode()), n, n > 1024) for d, x, n in zip(t["doc_id"], t["text"], (len(e.ids) for e in byte_lib.encode_batch(t["text"], add_special_tokens=False)))}
    assert {tuple(r) for r in tokencount.op4_tokens(spark, SF).collect()} == want


def test_pieces_equal_the_library_on_odd_texts(piece_lib):
    texts = _odd_texts(5)
    m = pieces.PieceModel(tokenizer_path("piece_bpe_32k.model"))
    got, want = m.encode(texts), piece_lib.encode(texts, num_threads=1)
    assert got == want
    assert [m.decode(i) for i in got] == [piece_lib.decode(i) for i in want]


def test_pieces_of_the_whole_table_and_odd_rows(spark, piece_lib):
    t = pq.read_table(f"{SF}/documents.parquet").to_pydict()
    sha = lambda x: hashlib.sha256(x.encode()).hexdigest()

    def row(d, x):
        ids = piece_lib.encode(x or "")
        return d, len(ids), sha(",".join(map(str, ids))), sha(piece_lib.decode(ids))

    assert {tuple(r) for r in pieces.op7_pieces(spark, SF).collect()} == {row(*x) for x in zip(t["doc_id"], t["text"])}
    odd = [(k, x) for k, x in enumerate(_odd_texts(9, 200))] + [(None, "a b"), (1, None), (1, None)]
    df = spark.createDataFrame([(*r, 1) for r in odd], "doc_id long, text string, n_tokens int")
    assert sorted(map(str, map(tuple, pieces.encode_documents(df).collect()))) == sorted(str(row(*r)) for r in odd)
    n = tokencount.count_tokens(df).collect()
    assert len(n) == len(odd) and [r.n_tokens for r in n if r.doc_id is None] == [2]
    assert pieces.encode_documents(df.limit(0)).collect() == [] == tokencount.count_tokens(df.limit(0)).collect()


def test_rounds_equal_one_merge_at_a_time():
    rng = random.Random(2)
    for _ in range(60):  # tables with any order of ranks, ties included
        pairs = {}
        for s in range(5, 25):
            pairs.setdefault((rng.randrange(s), rng.randrange(s)), (rng.randrange(12), s))
        table = merges.PairTable(pairs)
        words = [[rng.randrange(5) for _ in range(rng.randint(0, 30))] for _ in range(80)]
        assert merges.merge_words(words, table) == [merges.merge_one(w, table) for w in words]
