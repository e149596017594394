"""Work that runs and sizes share: counted, marked and looked up once, with the rows of doing each apart."""

from collections import Counter, defaultdict
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from synthselect.operators import evaluate, lm, scoring, synth
from synthselect.plans import bootstrap

TEXTS = ["the cat saw the dog and the cat ran", "A dog ran\nto the  cat", "", None, "one", "the dog saw a bird, the bird saw the dog " * 3]


@pytest.fixture(scope="module")
def snippets(spark):
    return spark.createDataFrame([(k, t) for k, t in enumerate(TEXTS)], "snippet_id long, text string").withColumn("n_chars", F.coalesce(F.length("text"), F.lit(0)).cast("long")).cache()


def test_sizes_are_trained_in_one_count(snippets):
    docs = snippets.select(F.col("snippet_id").alias("id"), "text")
    got = synth.trained([synth.NGramSynthesizer(3, 2), synth.NGramSynthesizer(100, 4)], docs, 1)
    count = defaultdict(Counter)
    for t in TEXTS:
        w = (t or "").lower().split()
        for u, x in zip(["<s>", *w], w):
            count[u][x] += 1
    for model, vocab, fanout in ((got[0].models[0], 3, 2), (got[1].models[0], 100, 4)):
        best = {u: sorted(c.items(), key=lambda p: (-p[1], p[0]))[:fanout] for u, c in count.items()}
        top = sorted(best, key=lambda u: (-sum(n for _, n in best[u]), u))[:vocab]
        assert model == {u: ([x for x, _ in best[u]], [float(n) for _, n in best[u]]) for u in top}


def test_candidates_stay_in_the_snippets_row(snippets):
    """No shuffle, context words kept, and each text as drawn word by word."""
    model = synth.NGramSynthesizer(4, 3, length=9).train(snippets.select(F.col("snippet_id").alias("id"), "text"), 2)
    made = model.generate(scoring.with_context(snippets), [0, 1], 3)
    assert "context_words" in made.columns and "Exchange" not in made._jdf.queryExecution().executedPlan().toString()
    rows = made.collect()
    assert len(rows) == 6 * len(TEXTS)
    for r in rows:
        rng, w = np.random.default_rng([1, r.snippet_id, r.ckpt, r.draw]), r.q.split()
        assert not w or " ".join(w) in " ".join((TEXTS[r.snippet_id] or "").lower().split())
        u, out, m = w[int(rng.integers(len(w)))] if w else "<s>", [], model.models[r.ckpt]
        for _ in range(9):
            if not (nxt := m.get(u) or m.get("<s>")):
                break
            g = np.log(nxt[1]) / 0.2 - np.log(-np.log(rng.random(len(nxt[1])) + 1e-12))
            out.append(u := nxt[0][int(g.argmax())])
        assert r.s == " ".join(out)


def test_winners_of_all_rules_from_one_marking(spark):
    docs = spark.createDataFrame([(k, " ".join(f"w{(k * j) % 23}" for j in range(60))) for k in range(1, 30)], "snippet_id long, text string").withColumn("n_chars", F.length("text").cast("long"))
    premium = docs.limit(4).select(F.col("snippet_id").alias("id"), F.substring("text", 1, 40).alias("q"), F.substring("text", 41, 80).alias("s"))
    base = bootstrap.Config(unit=2, ckpts=2, draws=2, vocabulary=8, rank=2, width=8, reference="fixed")
    ref = bootstrap.Reference.make(docs, premium, base)
    cfgs = [replace(base, **c) for c in bootstrap.ABLATIONS.values()]
    ready = bootstrap.prepared(docs, cfgs, ref)
    cols = ["iteration", "snippet_id", "ckpt", "draw", "score", "v", "q", "s"]
    asked = bootstrap.prompts_of(docs, base)
    for c in cfgs:
        one = bootstrap.picked(bootstrap.sampled(docs, c), c)
        assert sorted(map(tuple, ready[bootstrap.rule(c)].select(one.columns).collect())) == sorted(map(tuple, one.collect()))
    for c in cfgs[:2]:
        a, b = bootstrap.run(docs, premium, c, ref=ref), bootstrap.run(docs, premium, c, ref=ref, ready=ready[bootstrap.rule(c)], asked=asked)
        assert a.ledger == b.ledger
        assert [sorted(map(tuple, x.select(cols).collect())) for x in a.rounds] == [sorted(map(tuple, x.select(cols).collect())) for x in b.rounds]


def test_items_are_looked_up_once_for_all_sets(spark, monkeypatch):
    kept = spark.createDataFrame([("a", 1, "x y x"), ("a", 2, None), ("b", 1, "y z"), ("c", 3, "")], "cell string, snippet_id long, s string")
    bench = spark.createDataFrame([(1, "x z q", "one"), (2, "", "one"), (3, "Y y\nx", "two")], "item_id long, text string, set string")
    want = {}
    for name in "ab":
        p = lm.perplexity(bench, "item_id", "text", lm.fit(kept.filter(F.col("cell") == name), "snippet_id", "s"))
        for r in bench.join(p.withColumnRenamed("id", "item_id"), "item_id").groupBy("set").agg(F.count("ppl").alias("n"), F.round(F.avg(F.ln("ppl")), 4).alias("m")).collect():
            want[name, r["set"]] = (r.n, r.m)
    for most in (evaluate.MOST_WORDS, 0):
        monkeypatch.setattr(evaluate, "MOST_WORDS", most)
        got = evaluate.lm_proxy_of_each(kept, "cell", "snippet_id", "s", bench, 1, "set").collect()
        assert {(r.cell, r.set): (r.n_items, r.mean_ln_ppl) for r in got} == want
