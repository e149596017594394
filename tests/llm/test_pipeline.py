import zlib

import numpy as np

import corpus_pipeline
from synthselect.llm import common, quality, secrets
from synthselect.llm.tokencount import tokenizer_path

from . import test_simhash, test_suffixes

SF = "/root/testdata/sf0.01"


def test_each_stage_takes_effect_and_keeps_the_columns(spark):
    docs = common.read(spark, SF, "documents")
    columns, before = docs.columns, docs.count()
    seen = {}
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = common.land(stage(spark, docs, SF), f"t{k}")
        seen[name] = out.count()
        if name != "packing":
            assert out.columns == columns
            if name == "secrets":
                assert out.filter("text like '%[secret]%'").count() > 0 and out.filter("n_chars <> length(text)").count() == 0
            if name == "repeated_passages":
                assert out.selectExpr("sum(n_chars)").first()[0] < docs.selectExpr("sum(n_chars)").first()[0]
        else:
            assert out.select("doc_id").distinct().count() == docs.count()
        docs = out
    assert before > seen["quality"] > seen["near_duplicates"] == seen["repeated_passages"] == seen["secrets"] <= seen["packing"]


def test_run_gives_the_last_stage(spark):
    assert corpus_pipeline.run(spark, SF).columns == ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]


def test_run_equals_brute_force(spark, tmp_path):
    """Every stage anew in plain Python: votes one by one, fingerprints in pairs, all 100-byte windows, all spans, the library's ids."""
    from tokenizers import Tokenizer

    sf = "/root/testdata/sf0.001"
    docs, labels = common.read(spark, sf, "documents"), common.read(spark, sf, "labels")
    model = quality.fit(docs, labels)
    texts = {r.doc_id: r.text for r in docs.collect()}
    texts = {d: t for d, t in texts.items() if model.score(quality.matrix([quality.terms(t)]))[0] >= 0.7}
    fps = {d: test_simhash._brute_fp(t) for d, t in texts.items()}
    low = {d: d for d in fps}
    moved = True
    while moved:
        moved = False
        for a in fps:
            for b in fps:
                if (fps[a] ^ fps[b]).bit_count() <= 4 and low[b] < low[a]:
                    low[a], moved = low[b], True
    texts = {d: t for d, t in texts.items() if low[d] == d}
    seen, cut = set(), {}
    for d in sorted(texts):
        raw = texts[d].encode()
        gone = np.zeros(len(raw), bool)
        for i in range(len(raw) - 99):
            if raw[i : i + 100] in seen:
                gone[i : i + 100] = True
            seen.add(raw[i : i + 100])
        runs = np.split(np.arange(len(raw)), np.flatnonzero(np.diff(gone.astype(int))) + 1)
        cut[d] = "".join(raw[r[0] : r[-1] + 1].decode("utf-8", "ignore") for r in runs if len(r) and not gone[r[0]])
    kept = spark.createDataFrame(list(cut.items()), "doc_id long, text string")
    judge = secrets.train(kept)
    lib = Tokenizer.from_file(tokenizer_path("word_bpe_49k.json"))
    want = {}
    for d, t in cut.items():
        ids = [*lib.encode(secrets.masked(t, secrets.all_spans(t, judge)), add_special_tokens=False).ids, 0]
        want[d] = [zlib.crc32(np.array(ids[k : k + 2048], "<u4").tobytes()) for k in range(0, len(ids), 2048)]
    got = {}
    for r in sorted(corpus_pipeline.run(spark, sf).collect(), key=lambda r: (r.doc_id, r.piece)):
        got.setdefault(r.doc_id, []).append(r.ids_crc32)
    assert got == want and len(got) < docs.count()


def test_odd_tables_run_through(spark, tmp_path):
    good = "plain words of an ordinary text that goes on for a while and says this and that. "
    rows = [(None, good, "en", "s", 0, "x"), (None, None, None, None, None, None), (1, None, "en", "s", 0, "x"), (2, "", "en", "s", 0, "x"), (3, good * 3 + "one", "en", "s", 0, "x"), (3, good * 3 + "one", "en", "s", 0, "x"), (4, good * 2000, "en", "s", 0, "x")]
    cols = "doc_id long, text string, lang string, source string, n_chars long, spans string"
    labels = spark.createDataFrame([(3, 1), (4, 1), (None, 0), (9, None)], "doc_id long, quality int")
    labels.withColumn("toxic", labels.quality).write.parquet(f"{tmp_path}/a/labels.parquet")
    spark.createDataFrame(rows, cols).write.parquet(f"{tmp_path}/a/documents.parquet")
    got = corpus_pipeline.run(spark, f"{tmp_path}/a").collect()
    assert {r.doc_id for r in got} >= {None, 3} and all(r.length <= 2048 for r in got)
    labels.withColumn("toxic", labels.quality).write.parquet(f"{tmp_path}/b/labels.parquet")
    spark.createDataFrame([], cols).write.parquet(f"{tmp_path}/b/documents.parquet")
    assert corpus_pipeline.run(spark, f"{tmp_path}/b").collect() == []
