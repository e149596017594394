"""The loop and the experiment workloads over the given tables, with the SQL of all that hash-placed candidates allow."""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import hash_unit
from ..operators import candidates, categories, evaluate, influence, lm, pool, reference, ridge, scoring, selection, synth
from ..plans import bootstrap
from ..sources import join_sent, land, table
from . import h, query, w
from .methods import _HITS, _NOISE, _SECRET, _grads, _marked
from .solve import elimination

MARKS = scoring.MARKS
#: A reference that any engine can check: adapters of hashed signs over few hashed words.
FIXED = bootstrap.Config(reference="fixed", vocabulary=16, rank=2, width=16)
#: What LowRankBigram.fixed scales its adapters by.
FIXED_SCALE = 0.5
DESCRIPTIONS = 10
EVEN = "cast(substring(source, 4) as int) % 2 = 0"

# ---------------------------------------------------------------- inputs of the loop


@dataclass
class Inputs:
    docs: DataFrame  # the pool without the premium snippets: snippet_id, text, n_chars, lang, source
    premium: DataFrame  # id, q, s, asked
    unit: int
    leaks: object  # benchmark runs, sent
    weights: tuple[float, ...]
    labels: DataFrame  # of the odd sources: what purity is measured by
    whole: DataFrame  # the pool with the premium snippets

    def config(self, **change) -> bootstrap.Config:
        return replace(FIXED, unit=self.unit, weights=self.weights, **change)


def assigned(docs: DataFrame, bench: DataFrame, id_col: str = "snippet_id") -> DataFrame:
    """(id, category_id, similarity): each text's nearest category description."""
    desc = categories.from_descriptions(bench.filter(F.col("item_id") < DESCRIPTIONS), "item_id", "text")
    return categories.assign(categories.hashed_vectors(docs, id_col, "text"), "id", "v", desc).select("id", "category_id", "similarity")


def distilled(seeds: DataFrame) -> DataFrame:
    """(id, q, s, asked): premium samples of seed snippets; hash-placed passages stand for the strong model's answers."""
    made = synth.PassageSynthesizer().generate(seeds, [0], 1)
    return made.select(F.col("snippet_id").alias("id"), "q", "s", F.length("text").alias("asked"))


def quota(unit: int) -> int:
    """Seeds of each category."""
    return -(-unit // DESCRIPTIONS)


def learned_weights(whole: DataFrame, labels: DataFrame, leaks) -> tuple[float, ...]:
    """Ridge weights of the ten marks: an experiment is the candidates of one (lang, source), even sources only."""
    docs = join_sent(whole.filter(EVEN), labels.select(F.col("doc_id").alias("snippet_id"), "quality"), "snippet_id", "inner")
    leaks = scoring.sent_runs(leaks) if isinstance(leaks, DataFrame) else leaks
    if isinstance(leaks, DataFrame):  # too many runs to be sent
        marked = scoring.rule_marks(candidates.multi_checkpoint(scoring.with_context(docs)), leaks)
    else:
        marked = scoring.nested_marks(candidates.placed(docs, [(c, d) for c in range(3) for d in range(4)]), ["lang", "source", "quality"], leaks)
    exps = ridge.experiments(marked, ["lang", "source"], MARKS, "quality")
    return tuple(round(float(x), 6) for x in ridge.fit(land(exps), MARKS).weights)


def inputs(spark: SparkSession, d: str) -> Inputs:
    """Pool: what passes every gate; seeds: quality-1 documents of even sources, so many of each category."""
    raw, bench, labels = (table(spark, d, t) for t in ("documents", "benchmark", "labels"))
    whole = land(pool.build_pool(raw, bench)[0].select("snippet_id", "text", "n_chars", "lang", "source"))
    unit = bootstrap.unit_of(whole.count())
    leaks = scoring.sent_runs(land(pool.benchmark_grams(bench)))
    premium = land(distilled(drawn_seeds(whole, labels, bench, unit)))
    docs = join_sent(whole, premium.select(F.col("id").alias("snippet_id")), "snippet_id", "left_anti")  # its texts aren't landed again
    odd = labels.join(raw.filter(f"not ({EVEN})").select("doc_id"), "doc_id", "left_semi")
    return Inputs(docs, premium, unit, leaks, learned_weights(whole, labels, leaks), odd, whole)


def drawn_seeds(whole: DataFrame, labels: DataFrame, bench: DataFrame, unit: int) -> DataFrame:
    good = join_sent(whole.filter(EVEN), labels.filter("quality = 1").select(F.col("doc_id").alias("snippet_id")), "snippet_id", "left_semi")
    cat = assigned(good, bench).select(F.col("id").alias("snippet_id"), "category_id")
    seeds = land(categories.stratified(cat, "category_id", quota(unit), "snippet_id"))  # of ids: no text is sorted
    return join_sent(whole, seeds, "snippet_id", "inner")


# ---------------------------------------------------------------- the same in SQL

_V, _R, _K = FIXED.vocabulary, FIXED.rank, FIXED.width
_ID = "d.doc_id, d.text, d.n_chars, d.lang, d.source"
_GATES = f"""n AS (SELECT *, len(regexp_extract_all(text, '{_SECRET}')) AS n_sensitive, min(doc_id) OVER (PARTITION BY md5(array_to_string({w("text")}, ' '))) AS first_id FROM ({_NOISE})), hits AS ({_HITS}),
 whole AS MATERIALIZED (SELECT {_ID} FROM n JOIN documents d USING (doc_id) LEFT JOIN hits ON n.doc_id = hits.id WHERE n.n_chars BETWEEN 100 AND 20000 AND NOT (punct_pct > 12 OR distinct_pct < 20 OR repeat_pct > 50) AND n_sensitive = 0 AND n.doc_id = first_id AND hits.id IS NULL),
 unit AS MATERIALIZED (SELECT (count(*) // 18)::BIGINT AS u FROM whole)"""
_ODD_SOURCE = "substr(source, 4)::INT % 2 = 1"


def _cells(src: str, key: str) -> str:
    return f"SELECT id, (hh % 64)::INT AS i, sum(1 - 2 * ((hh >> 16) % 2))::DOUBLE AS x FROM (SELECT id, {h('emb', 't')} AS hh FROM (SELECT {key} AS id, unnest({w('text')}) AS t FROM {src})) GROUP BY 1, 2"


def _assigned(src: str, name: str) -> str:
    return f"""{name}_e AS ({_cells(src, "doc_id")}), {name}_d AS ({_cells("(SELECT * FROM benchmark WHERE item_id < 10)", "item_id")}), {name}_n AS (SELECT id, sqrt(sum(x * x)) AS n FROM {name}_e GROUP BY id), {name}_m AS (SELECT id, sqrt(sum(x * x)) AS n FROM {name}_d GROUP BY id),
 {name}_s AS (SELECT e.id, d.id AS c, sum(e.x * d.x) AS dot FROM {name}_e e JOIN {name}_d d USING (i) GROUP BY 1, 2),
 {name} AS MATERIALIZED (SELECT a.id, b.id AS c, CASE WHEN coalesce(s.dot, 0) = 0 THEN 0.0 ELSE round(s.dot / greatest(a.n * b.n, 1e-300), 6) END::DOUBLE AS similarity FROM {name}_n a CROSS JOIN {name}_m b LEFT JOIN {name}_s s ON s.id = a.id AND s.c = b.id QUALIFY row_number() OVER (PARTITION BY a.id ORDER BY similarity DESC, b.id) = 1)"""


def _cand(src: str, cells: str) -> str:
    at = lambda k: f"{h(k, 'doc_id', 'ckpt', 'draw')} % greatest(1, n_chars - 80)"
    return f"SELECT doc_id AS snippet_id, text, ckpt, draw, substr(text, (1 + {at('q')})::BIGINT, 80) AS q, substr(text, (1 + {at('s')})::BIGINT, 240) AS s FROM {src}, {cells}"


_MULTI = "(SELECT unnest(range(3))::INT AS ckpt) a_, (SELECT unnest(range(4))::INT AS draw) b_"
_ONE = "(SELECT 0 AS ckpt) a_, (SELECT 0 AS draw) b_"
_LAST = "(SELECT 2 AS ckpt) a_, (SELECT unnest(range(12))::INT AS draw) b_"
_BEST = "(SELECT 2 AS ckpt) a_, (SELECT unnest(range(4))::INT AS draw) b_"
_SEEDS = f"""good AS (SELECT * FROM whole WHERE NOT ({_ODD_SOURCE}) AND doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)), {_assigned("good", "cat")},
 seeds AS MATERIALIZED (SELECT good.*, cat.c FROM good JOIN cat ON cat.id = good.doc_id QUALIFY row_number() OVER (PARTITION BY c ORDER BY {h("seed", "doc_id")}, doc_id) <= (SELECT (u + 9) // 10 FROM unit)),
 premium AS MATERIALIZED ({_cand("seeds", _ONE)}), docs AS MATERIALIZED (SELECT * FROM whole WHERE doc_id NOT IN (SELECT doc_id FROM seeds))"""


def _means(marks: list[str]) -> str:
    return ", ".join(f"round(sum({m}) / count({m}), 6) AS {m}" for m in marks)


_LEARNED = f"""exps AS MATERIALIZED (SELECT lang, source, {_means(MARKS)}, round(sum(quality) / count(quality), 6) AS y FROM ({_marked(_cand(f"(SELECT whole.* FROM whole JOIN labels USING (doc_id) WHERE NOT ({_ODD_SOURCE}))", _MULTI))} SELECT * FROM x) x JOIN whole d ON d.doc_id = x.snippet_id JOIN labels USING (doc_id) GROUP BY lang, source),
 {elimination("exps", MARKS, "y", 1.0, "wts")}"""
_IDS = lambda t: f"list_transform({t}, lambda z: ('0x' || substr(md5('ref-' || z), 1, 8))::BIGINT % {_V})"
_SGN = lambda seed, i, j: f"(1 - 2 * ({h(seed, i, j)} % 2))"
_REFERENCE = f"""ids AS (SELECT {_IDS(w("text"))} AS t FROM docs), base AS (SELECT c // {_V} AS u, c % {_V} AS w, count(*) AS c FROM (SELECT unnest(list_transform(range(1, len(t)), lambda k: t[k] * {_V} + t[k + 1])) AS c FROM ids) GROUP BY 1, 2),
 vv AS (SELECT unnest(range({_V})) AS v), rr AS (SELECT unnest(range({_R})) AS k), jj AS (SELECT unnest(range({_K})) AS j), ada AS (SELECT k, v AS w, {_SGN("refA", "k", "v")} AS a FROM rr, vv), adb AS (SELECT v AS u, k, {_SGN("refB", "v", "k")} AS b FROM vv, rr),
 ba AS (SELECT u, w, sum(a * b)::DOUBLE AS ba FROM ada JOIN adb USING (k) GROUP BY 1, 2), lift AS (SELECT u, w, (coalesce(c, 0) + 1) * exp({FIXED_SCALE} * ba) AS e FROM ba LEFT JOIN base USING (u, w)) , prob AS (SELECT u, w, round(1000000 * e / sum(e) OVER (PARTITION BY u))::BIGINT AS p FROM lift),
 tt AS MATERIALIZED (SELECT u, w, j, sum(b * {_SGN("proj", f"k * {_V} + w", "j")} + a * {_SGN("proj", f"{_R * _V} + u * {_R} + k", "j")})::BIGINT AS t FROM ada JOIN adb USING (k), jj GROUP BY 1, 2, 3),
 mean AS (SELECT u, j, sum(p * t)::BIGINT AS m FROM prob JOIN tt USING (u, w) GROUP BY 1, 2), look AS MATERIALIZED (SELECT u * {_V} + w AS c, j, m - 1000000 * t AS g FROM tt JOIN mean USING (u, j))"""


def _gradients(rows: str, name: str, key: str = "snippet_id") -> str:
    """{name}(id, j, g): projected adapter gradients of rows with q and s."""
    t = f"SELECT {key} AS id, {_IDS(w('q'))} AS tq, {_IDS(w('s'))} AS ts FROM {rows}"
    pairs = f"SELECT id, unnest(list_transform(range(greatest(1, len(tq)), len(tq) + len(ts)), lambda k: list_concat(tq, ts)[k] * {_V} + list_concat(tq, ts)[k + 1])) AS c FROM ({t})"
    return f"{name} AS MATERIALIZED (SELECT id, j, sum(g)::BIGINT AS g FROM ({pairs}) JOIN look USING (c) GROUP BY 1, 2)"


_TARGET = _gradients("premium", "pg") + ", aim AS MATERIALIZED (SELECT j, sum(g)::BIGINT AS m FROM pg GROUP BY j), pool_tok AS (SELECT unnest(" + w("text") + ") AS t FROM docs), pool_cnt AS MATERIALIZED (SELECT t, count(*) AS c FROM pool_tok GROUP BY t), pool_size AS MATERIALIZED (SELECT sum(c) AS n, count(*) AS v FROM pool_cnt)"
LOOP = f"WITH {_GATES}, {_SEEDS}, {_LEARNED}, {_REFERENCE}, {_TARGET}"
_WSUM = " + ".join(f"round(w_{m} * 1000000)::BIGINT * {m}" for m in MARKS)
_XSUM = " + ".join(MARKS)


def _scored(src: str, cfg: bootstrap.Config) -> str:
    cells = {"multi": _MULTI, "last": _LAST, "best_of_n": _BEST}[cfg.sampling]
    fold = {"weighted": f"({_WSUM})::BIGINT", "average": f"round(({_XSUM}) / 10.0 * 1000000)::BIGINT", "composite": f"(1 + least(4, (({_XSUM}) - 10) // 10))::BIGINT", "none": h("none", "snippet_id", "ckpt", "draw")}[cfg.aggregate]
    return f"SELECT snippet_id, ckpt, draw, {fold} AS score, q, s FROM ({_marked(_cand(src, cells))} SELECT * FROM x) x, wts"


def rounds_sql(name: str, cfg: bootstrap.Config, sizes: list[int] | None = None) -> str:
    """CTEs {name}p<t> (prompts), {name}a<t> (all candidates), {name}b<t> (winners), {name}k<t> (kept) of each round of a run."""
    out = []
    for t, m in enumerate(sizes or bootstrap.SCHEDULES[cfg.schedule], 1):
        used = "".join(f" AND doc_id NOT IN (SELECT doc_id FROM {name}p{x})" for x in range(1, t))
        out.append(f"{name}p{t} AS MATERIALIZED (SELECT * FROM docs WHERE true{used} ORDER BY {h(f'round{t}', 'doc_id')}, doc_id LIMIT (SELECT {m * cfg.over} * u FROM unit))")
        out.append(f"{name}a{t} AS MATERIALIZED ({_scored(f'{name}p{t}', cfg)})")
        out.append(f"{name}b{t} AS MATERIALIZED (SELECT * FROM {name}a{t} QUALIFY row_number() OVER (PARTITION BY snippet_id ORDER BY score DESC, ckpt, draw) = 1)")
        out.append(_gradients(f"{name}b{t}", f"{name}g{t}"))
        out.append(f"{name}v{t} AS (SELECT id, round(sum(g::DOUBLE * m) / sqrt(sum(g::DOUBLE * g)) / (SELECT sqrt(sum(m::DOUBLE * m)) FROM aim), 6) AS v FROM {name}g{t} JOIN aim USING (j) GROUP BY id)")
        ppl = f"(SELECT round(exp(sum(round(ln((coalesce(c, 0) + 1.0) / (n + v + 1)) * -1000000)::BIGINT) / 1000000.0 / count(*)), 4) FROM (SELECT unnest({w('r.s')}) AS t) LEFT JOIN pool_cnt USING (t), pool_size)"
        order = {"influence": "v_fp DESC NULLS LAST", "random": h(f"keep{t}", "snippet_id"), "score": "score DESC", "low_ppl": "ppl", "high_ppl": "ppl DESC"}[cfg.final]
        extra = f", {ppl} AS ppl" if cfg.final.endswith("ppl") else ""
        rows = f"SELECT {t} AS iteration, r.snippet_id, r.ckpt, r.draw, r.score, x.v, round(x.v * 1000000)::BIGINT AS v_fp, r.q, r.s{extra} FROM {name}b{t} r LEFT JOIN {name}v{t} x ON x.id = r.snippet_id"
        out.append(f"{name}k{t} AS MATERIALIZED (SELECT iteration, snippet_id, ckpt, draw, score, v, q, s FROM ({rows}) ORDER BY {order}, snippet_id LIMIT (SELECT {m} * u FROM unit))")
    return ", ".join(out)


def _kept_sql(name: str, cfg: bootstrap.Config, sizes: list[int] | None = None, cols: str = "iteration, snippet_id, ckpt, draw, score, v, q, s") -> str:
    n = len(sizes or bootstrap.SCHEDULES[cfg.schedule])
    return " UNION ALL ".join(f"SELECT {cols} FROM {name}k{t}" for t in range(1, n + 1))


_ODD_LABELS = f"odd AS MATERIALIZED (SELECT labels.* FROM labels JOIN documents USING (doc_id) WHERE {_ODD_SOURCE})"


def _proxy_sql(rows: str, text: str, order: int = 1) -> str:
    """A scalar: mean ln perplexity of the benchmark items under the counts of `rows`."""
    toks = lambda src, col, key: f"SELECT {key} AS id, unnest(l) AS w, unnest(list_prepend('<s>', l[:-2])) AS u FROM (SELECT {key}, {w(col)} AS l FROM {src}) WHERE len(l) > 0"
    train, items = toks(rows, text, "snippet_id"), toks("benchmark", "text", "item_id")
    key = "w" if order == 1 else "u, w"
    p = "(coalesce(c, 0) + 1.0) / (k.n + k.v + 1)" if order == 1 else "(coalesce(c, 0) + 1.0) / (coalesce(cu, 0) + k.v + 1)"
    more = "" if order == 1 else ", cu AS (SELECT u, sum(c) AS cu FROM c GROUP BY u)"
    join = "" if order == 1 else " LEFT JOIN cu USING (u)"
    return f"""(WITH t AS ({train}), c AS (SELECT {key}, count(*) AS c FROM t GROUP BY {key}), k AS (SELECT sum(c) AS n, count(DISTINCT w) AS v FROM c){more}, i AS ({items}),
 y AS (SELECT id, round(exp(sum(round(ln({p}) * -1000000)::BIGINT) / 1000000.0 / count(*)), 4) AS ppl FROM i LEFT JOIN c USING ({key}){join}, k GROUP BY id) SELECT round(avg(ln(ppl)), 4) FROM y)"""


def _measured_sql(setting: str, rows: str) -> str:
    """One row of measures of kept samples; rows: a CTE or a subquery."""
    return f"""SELECT '{setting}' AS setting, (SELECT count(*) FROM {rows}) AS n_kept, (SELECT round(avg(score), 4) FROM {rows}) AS mean_score, (SELECT round(avg(v), 6) FROM {rows}) AS mean_influence,
 (SELECT count(*) FROM odd WHERE doc_id IN (SELECT snippet_id FROM {rows})) AS n_labelled, (SELECT round(avg(quality::DOUBLE), 6) FROM odd WHERE doc_id IN (SELECT snippet_id FROM {rows})) AS purity, {_proxy_sql(rows, "s")} AS ln_ppl_small, {_proxy_sql(rows, "s", 2)} AS ln_ppl_large"""


MEASURES = ["setting", "n_kept", "mean_score", "mean_influence", "n_labelled", "purity", "ln_ppl_small", "ln_ppl_large"]


#: Runs of a grid that are under way at once.
RUNS = 4


def _grid(spark: SparkSession, d: str, runs: dict[str, Callable[[], DataFrame]], inp: Inputs) -> DataFrame:
    """The same of all runs at once: purity by labels of odd sources, and two targets' perplexities of the benchmark (proxies)."""
    bench = table(spark, d, "benchmark")
    with ThreadPoolExecutor(RUNS) as pool_:  # the small jobs of one run leave cores to others
        made = list(pool_.map(lambda make: make(), runs.values()))
    kept = land(_union([rows.select(F.lit(name).alias("setting"), "snippet_id", "score", "v", "s") for name, rows in zip(runs, made)]))
    n = kept.groupBy("setting").agg(F.count(F.lit(1)).alias("n_kept"), F.round(F.avg("score"), 4).alias("mean_score"), F.round(F.avg("v"), 6).alias("mean_influence"))
    own = kept.select("setting", F.col("snippet_id").alias("doc_id")).distinct().join(inp.labels, "doc_id")
    p = own.groupBy("setting").agg(F.count(F.lit(1)).alias("n_labelled"), F.round(F.avg(F.col("quality").cast("double")), 6).alias("purity"))
    out = n.join(p, "setting", "left").withColumn("n_labelled", F.coalesce("n_labelled", F.lit(0)))
    for order, name in ((1, "ln_ppl_small"), (2, "ln_ppl_large")):
        out = out.join(evaluate.lm_proxy_of_each(kept, "setting", "snippet_id", "s", bench, order).withColumnRenamed("mean_ln_ppl", name), "setting", "left")
    return out.select(*MEASURES)


def _grid_sql(runs: dict[str, tuple[bootstrap.Config, list[int] | None]]) -> str:
    ctes = ", ".join(rounds_sql(f"r{k}_", cfg, sizes) + f", r{k}_ AS MATERIALIZED ({_kept_sql(f'r{k}_', cfg, sizes)})" for k, (cfg, sizes) in enumerate(runs.values()))
    return f"{LOOP}, {_ODD_LABELS}, {ctes} " + " UNION ALL ".join(_measured_sql(name, f"r{k}_") for k, name in enumerate(runs))


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def _run(inp: Inputs, cfg: bootstrap.Config, ref: bootstrap.Reference | None = None, start=None, **more) -> bootstrap.Result:
    return bootstrap.run(inp.docs, inp.premium, cfg, start, leaks=inp.leaks, ref=ref, **more)


# ---------------------------------------------------------------- category-diversified seeds


@query("category_assign_text", "WITH " + _assigned("documents", "cat") + " SELECT id, c::INT AS category_id, similarity FROM cat")
def category_assign_text(spark: SparkSession, d: str) -> DataFrame:
    """Each document's nearest category description, by hashed word vectors."""
    return assigned(table(spark, d, "documents"), table(spark, d, "benchmark"), "doc_id")


@query("seed_categories_text", f"WITH {_GATES}, {_SEEDS} SELECT doc_id AS snippet_id, c::INT AS category_id FROM seeds")
def seed_categories_text(spark: SparkSession, d: str) -> DataFrame:
    """The snippets that the premium set is distilled from: as many of each assigned category."""
    raw, bench, labels = (table(spark, d, t) for t in ("documents", "benchmark", "labels"))
    whole = land(pool.build_pool(raw, bench)[0].select("snippet_id", "text", "n_chars", "lang", "source"))
    return drawn_seeds(whole, labels, bench, bootstrap.unit_of(whole.count())).select("snippet_id", "category_id")


_PLAIN = f"plain AS (SELECT good.*, cat.c FROM good JOIN cat ON cat.id = good.doc_id ORDER BY {h('plain', 'doc_id')}, doc_id LIMIT (SELECT count(*) FROM seeds))"
_COVER = "SELECT '{0}' AS setting, count(*) AS categories, sum(n)::BIGINT AS seeds, round(sum(-n / t * ln(n / t)), 6) AS entropy, round(min(n) / max(n), 6) AS least_to_most FROM (SELECT c, count(*)::DOUBLE AS n, sum(count(*)) OVER () AS t FROM {1} GROUP BY c)"


@query("seeds_grid", f"WITH {_GATES}, {_SEEDS}, {_PLAIN} " + _COVER.format("categories", "seeds") + " UNION ALL " + _COVER.format("plain", "plain"))
def seeds_grid(spark: SparkSession, d: str) -> DataFrame:
    """Seeds by category against as many plain random seeds: how evenly the categories are covered."""
    raw, bench, labels = (table(spark, d, t) for t in ("documents", "benchmark", "labels"))
    whole = land(pool.build_pool(raw, bench)[0].select("snippet_id", "text", "n_chars", "lang", "source"))
    good = whole.filter(EVEN).join(labels.filter("quality = 1").select(F.col("doc_id").alias("snippet_id")), "snippet_id", "left_semi")
    cat = land(assigned(good, bench).select(F.col("id").alias("snippet_id"), F.col("category_id").alias("c")))
    by = land(categories.stratified(cat, "c", quota(bootstrap.unit_of(whole.count())), "snippet_id"))
    out = []
    for name, rows in (("categories", by), ("plain", selection.random_n(cat, by.count(), "plain", "snippet_id"))):
        n = categories.coverage(rows, "c")
        out.append(n.agg(F.count(F.lit(1)).alias("categories"), F.sum("n").alias("seeds"), F.max("entropy").alias("entropy"), F.round(F.min("n") / F.max("n"), 6).alias("least_to_most")).select(F.lit(name).alias("setting"), "*"))
    return _union(out)


# ---------------------------------------------------------------- the loop

_W = {m: f"round(w_{m}, 6) AS w_{m}" for m in MARKS}


@query("ridge_loop_weights", f"WITH {_GATES}, {_LEARNED} SELECT {', '.join(_W.values())} FROM wts")
def ridge_loop_weights(spark: SparkSession, d: str) -> DataFrame:
    """The weights that the loop folds marks by: ridge on the candidates of labelled snippets."""
    raw, bench, labels = (table(spark, d, t) for t in ("documents", "benchmark", "labels"))
    whole = land(pool.build_pool(raw, bench)[0].select("snippet_id", "text", "n_chars", "lang", "source"))
    found = learned_weights(whole, labels, land(pool.benchmark_grams(bench)))
    return spark.createDataFrame([found], ", ".join(f"w_{m} double" for m in MARKS))


@query("grad_adapter_influence", f"{LOOP}, {rounds_sql('r_', FIXED, [6])} SELECT id, v FROM r_v1")
def grad_adapter_influence(spark: SparkSession, d: str) -> DataFrame:
    """Projected adapter gradients of each prompted snippet's winner against the premium mean."""
    inp = inputs(spark, d)
    cfg = inp.config()
    best = bootstrap.picked(bootstrap.sampled(bootstrap.prompted(inp.docs, 12 * inp.unit, 1), cfg), cfg, inp.leaks)
    return bootstrap.ref_scores(best, bootstrap.Reference.make(inp.docs, inp.premium, cfg)).select(F.col("snippet_id").alias("id"), "v")


@query("bootstrap_two_rounds", f"{LOOP}, {rounds_sql('r_', FIXED)} {_kept_sql('r_', FIXED, None, 'iteration, snippet_id, ckpt, draw, score, v')}")
def bootstrap_two_rounds(spark: SparkSession, d: str) -> DataFrame:
    """Two rounds with ridge weights and a reference of fixed adapters, so that any engine can follow."""
    inp = inputs(spark, d)
    return _union(_run(inp, inp.config()).rounds).select("iteration", "snippet_id", "ckpt", "draw", "score", "v")


@query("bootstrap_trained")
def bootstrap_trained(spark: SparkSession, d: str) -> DataFrame:
    """The loop as meant: a trained reference, and an n-gram synthesizer that each round trains on what it kept."""
    inp = inputs(spark, d)
    cfg = replace(inp.config(), reference="trained", vocabulary=64, rank=4, width=64)
    return _union(_run(inp, cfg, None, _enhanced(inp)[1]).rounds).select("iteration", "snippet_id", "ckpt", "draw", "score", "v")


def _enhanced(inp: Inputs, vocab: int = 2000, fanout: int = 16, n_ckpt: int = 3) -> tuple[synth.NGramSynthesizer, synth.NGramSynthesizer]:
    """(original, enhanced) n-gram synthesizers: trained on the pool, then on the premium set."""
    return _enhanced_of(inp, [(vocab, fanout)], n_ckpt)[0]


def _enhanced_of(inp: Inputs, sizes: list[tuple[int, int]], n_ckpt: int = 3) -> list[tuple[synth.NGramSynthesizer, synth.NGramSynthesizer]]:
    """(original, enhanced) of each (vocab, fanout): the words of the pool are counted once for all."""
    base = synth.trained([synth.NGramSynthesizer(v, f) for v, f in sizes], inp.docs.select(F.col("snippet_id").alias("id"), "text"), n_ckpt)
    return list(zip(base, synth.trained(base, inp.premium, n_ckpt, "s", "id", base[0].counts, more=False)))


_SCHEDULES = {name: (replace(FIXED, schedule=name, ckpts=3), None) for name in bootstrap.SCHEDULES}


@query("bootstrap_schedules", _grid_sql(_SCHEDULES))
def bootstrap_schedules(spark: SparkSession, d: str) -> DataFrame:
    """The five schedules, two snippets prompted for each kept: sizes, marks, influence, purity and both proxies."""
    inp = inputs(spark, d)
    ref = bootstrap.Reference.make(inp.docs, inp.premium, inp.config())
    ready = bootstrap.prepared(inp.docs, [inp.config()], ref, inp.leaks)[bootstrap.rule(inp.config())]  # all schedules together prompt nearly all
    return _grid(spark, d, {n: (lambda n=n: _union(_run(inp, inp.config(schedule=n), ref, ready=ready).rounds)) for n in bootstrap.SCHEDULES}, inp)


def _ledger_sql() -> str:
    rows = ["SELECT 0 AS iteration, 'distill' AS stage, 'premium' AS provider, count(*) AS calls, count(*) AS kept, sum(length(text))::BIGINT AS prompt_chars, sum(length(q) + length(s))::BIGINT AS output_chars FROM premium"]
    for t in (1, 2):
        rows.append(f"SELECT {t}, 'sample', 'self', (SELECT count(*) FROM r_a{t}), (SELECT count(*) FROM r_k{t}), (SELECT sum(12 * length(text))::BIGINT FROM r_p{t}), (SELECT sum(length(q) + length(s))::BIGINT FROM r_a{t})")
    return " UNION ALL ".join(rows)


@query("bootstrap_ledger", f"{LOOP}, {rounds_sql('r_', FIXED)} {_ledger_sql()}")
def bootstrap_ledger(spark: SparkSession, d: str) -> DataFrame:
    """Calls and characters of every call, kept or not, and of the premium set."""
    inp = inputs(spark, d)
    return spark.createDataFrame(_run(inp, inp.config()).ledger, bootstrap.LEDGER)


@query("cost_report", f"{LOOP}, {rounds_sql('r_', FIXED)}, l AS ({_ledger_sql()}) SELECT provider, sum(calls)::BIGINT AS calls, sum(kept)::BIGINT AS kept, round(sum(calls) / sum(kept), 4) AS calls_per_kept, round(sum(prompt_chars + output_chars) / sum(kept), 4) AS chars_per_kept, round(sum(kept) / (SELECT sum(kept) FROM l), 6) AS share FROM l GROUP BY provider")
def cost_report(spark: SparkSession, d: str) -> DataFrame:
    """Bought against self-made samples: share, calls and characters for each kept one."""
    led = bootstrap_ledger(spark, d)
    n = led.groupBy("provider").agg(F.sum("calls").alias("calls"), F.sum("kept").alias("kept"), F.sum(F.col("prompt_chars") + F.col("output_chars")).alias("chars"))
    total = led.agg(F.sum("kept").alias("all"))
    return n.crossJoin(F.broadcast(total)).select("provider", "calls", "kept", F.round(F.col("calls") / F.col("kept"), 4).alias("calls_per_kept"), F.round(F.col("chars") / F.col("kept"), 4).alias("chars_per_kept"), F.round(F.col("kept") / F.col("all"), 6).alias("share"))


# ---------------------------------------------------------------- grids

_ABLATIONS = {name: (replace(FIXED, schedule="20-40", **change), None) for name, change in bootstrap.ABLATIONS.items()}


@query("ablation_grid", _grid_sql(_ABLATIONS))
def ablation_grid(spark: SparkSession, d: str) -> DataFrame:
    """The full loop and each part taken out or swapped, for two targets (proxies of order 1 and 2)."""
    inp = inputs(spark, d)
    ref = bootstrap.Reference.make(inp.docs, inp.premium, inp.config())
    cfgs = {n: inp.config(**c) for n, c in bootstrap.ABLATIONS.items()}
    asked = bootstrap.prompts_of(inp.docs, inp.config())  # the same for all
    prompts = join_sent(inp.docs, _union(asked).select("snippet_id"), "snippet_id", "left_semi")
    ready, told = bootstrap.prepared(prompts, list(cfgs.values()), ref, inp.leaks), bootstrap.told_of(inp.docs, inp.premium)
    return _grid(spark, d, {n: (lambda c=c: _union(_run(inp, c, ref, ready=ready[bootstrap.rule(c)], asked=asked, told=told).rounds)) for n, c in cfgs.items()}, inp)


@query("ablation_trained")
def ablation_trained(spark: SparkSession, d: str) -> DataFrame:
    """The three removals with a trained synthesizer, whose checkpoints differ by what they have seen."""
    inp = inputs(spark, d)
    base = replace(inp.config(), reference="trained", vocabulary=64, rank=4, width=64, schedule="20-20")
    start, ref = _enhanced(inp)[1], bootstrap.Reference.make(inp.docs, inp.premium, base)
    names = ("full", "no_multi_ckpt", "no_scoring", "no_influence")
    asked, told = bootstrap.prompts_of(inp.docs, base), bootstrap.told_of(inp.docs, inp.premium)  # the same for all
    return _grid(spark, d, {n: (lambda n=n: _union(_run(inp, replace(base, **bootstrap.ABLATIONS[n]), ref, start, asked=asked, told=told).rounds)) for n in names}, inp)


_STRATEGIES = {name: (replace(FIXED, **change), [4]) for name, change in bootstrap.STRATEGIES.items()}


@query("strategy_grid", _grid_sql(_STRATEGIES))
def strategy_grid(spark: SparkSession, d: str) -> DataFrame:
    """One round from the same prompts by six rules: the full method, two other foldings of marks, random, lowest and
    highest perplexity."""
    inp = inputs(spark, d)
    ref = bootstrap.Reference.make(inp.docs, inp.premium, inp.config())
    pool_lm = lm.fit(inp.docs, "snippet_id", "text")
    cfgs = {n: inp.config(**c) for n, c in bootstrap.STRATEGIES.items()}
    ready = bootstrap.prepared(bootstrap.prompted(inp.docs, 4 * inp.unit * inp.config().over, 1), list(cfgs.values()), ref, inp.leaks)
    return _grid(spark, d, {n: (lambda c=c: bootstrap.one_round(inp.docs, 4 * inp.unit, c, 1, ref, None, inp.leaks, pool_lm, ready[bootstrap.rule(c)])) for n, c in cfgs.items()}, inp)


_SCALE = (1, 2, 4, 6)


def _scaling_sql() -> str:
    parts = [f"s{m} AS MATERIALIZED (SELECT * FROM r_k1 ORDER BY {h('scale', 'snippet_id')}, snippet_id LIMIT (SELECT {m} * u FROM unit))" for m in _SCALE]
    ref = f"plain AS MATERIALIZED (SELECT doc_id AS snippet_id, s FROM (SELECT *, substr(text, (1 + {h('s', 'doc_id', '0', '0')} % greatest(1, n_chars - 80))::BIGINT, 240) AS s FROM docs) ORDER BY {h('plain', 'doc_id')}, doc_id LIMIT (SELECT 4 * u FROM unit))"
    rows = [f"SELECT 'selected' AS setting, {m} AS units, {_proxy_sql(f's{m}', 's')} AS mean_ln_ppl" for m in _SCALE] + [f"SELECT 'reference', 4, {_proxy_sql('plain', 's')}"]
    return f"{LOOP}, {rounds_sql('r_', FIXED, [6])}, {', '.join(parts)}, {ref} " + " UNION ALL ".join(rows)


@query("scaling_curve", _scaling_sql())
def scaling_curve(spark: SparkSession, d: str) -> DataFrame:
    """Nested prefixes of one selected set, and a reference line: as many samples of plain random snippets as at 4 units."""
    inp = inputs(spark, d)
    made = land(bootstrap.one_round(inp.docs, 6 * inp.unit, inp.config(), 1, bootstrap.Reference.make(inp.docs, inp.premium, inp.config()), None, inp.leaks))
    plain = candidates.passages(candidates.grid(selection.random_n(inp.docs, 4 * inp.unit, "plain", "snippet_id"), [0], 1))
    sets = {f"selected|{m}": selection.random_n(made, m * inp.unit, "scale", "snippet_id") for m in _SCALE} | {"reference|4": plain}
    rows = land(_union([part.select(F.lit(name.replace("|", " ")).alias("setting"), "snippet_id", "s") for name, part in sets.items()]))
    got = evaluate.lm_proxy_of_each(rows, "setting", "snippet_id", "s", table(spark, d, "benchmark"))
    return got.select(F.substring_index("setting", " ", 1).alias("setting"), F.substring_index("setting", " ", -1).cast("int").alias("units"), "mean_ln_ppl")


def evaluation_sets(spark: SparkSession, d: str, inp: Inputs | None = None) -> DataFrame:
    """(set, id, text): benchmark items, pool documents of odd sources, assistant turns, page texts."""
    turns = table(spark, d, "conversations").filter("role = 'assistant'").select(F.lit("turns").alias("set"), (F.col("conv_id") * 1000 + F.col("turn")).alias("id"), "text")
    pages = pool.page_text(table(spark, d, "pages")).select(F.lit("pages").alias("set"), F.col("page_id").alias("id"), "text")
    docs = table(spark, d, "documents").filter(f"not ({EVEN})").select(F.lit("documents").alias("set"), F.col("doc_id").alias("id"), "text")
    return table(spark, d, "benchmark").select(F.lit("benchmark").alias("set"), F.col("item_id").alias("id"), "text").union(docs).union(turns).union(pages)


SIZES = (("small", 200, 4), ("middle", 1000, 8), ("large", 4000, 16))


def _steps(inp: Inputs, rounds: bool) -> dict[str, synth.NGramSynthesizer]:
    """Each size's steps: original, enhanced and, if asked for, after each of two rounds."""
    pairs = _enhanced_of(inp, [size[1:] for size in SIZES])
    out = {}
    if rounds:
        cfg = replace(inp.config(), reference="trained", vocabulary=64, rank=4, width=64)
        ref, asked = bootstrap.Reference.make(inp.docs, inp.premium, cfg), bootstrap.prompts_of(inp.docs, cfg)  # the same for all
    for (name, _, _), (base, better) in zip(SIZES, pairs):
        out |= {f"{name} original": base, f"{name} enhanced": better}
        if rounds:
            out |= {f"{name} round{t}": s for t, s in enumerate(_run(inp, cfg, ref, better, asked=asked).synths) if t}
    return out


def _by_sets(spark: SparkSession, d: str, inp: Inputs, rounds: bool) -> DataFrame:
    """All cells at once: (synth, step, set, n_items, mean_ln_ppl)."""
    made, asked = [], land(bootstrap.prompted(inp.docs, 4 * inp.unit, 99))
    for cell, model in _steps(inp, rounds).items():
        rows = bootstrap.final_dataset(model, inp.docs, 4 * inp.unit, inp.config(), asked=asked)
        made.append(rows.select(F.lit(cell).alias("cell"), "snippet_id", "s"))
    sets = evaluation_sets(spark, d).withColumnRenamed("id", "item_id")
    got = evaluate.lm_proxy_of_each(land(_union(made)), "cell", "snippet_id", "s", sets, 1, "set")
    return got.select(F.substring_index("cell", " ", 1).alias("synth"), F.substring_index("cell", " ", -1).alias("step"), "set", "n_items", "mean_ln_ppl")


@query("pilot_grid")
def pilot_grid(spark: SparkSession, d: str) -> DataFrame:
    """Three sizes of the trainable synthesizer, original and enhanced, by the proxy on their final samples."""
    return _by_sets(spark, d, inputs(spark, d), False)


@query("main_grid")
def main_grid(spark: SparkSession, d: str) -> DataFrame:
    """Three sizes of the synthesizer x original, enhanced, first and second round x four evaluation sets."""
    return _by_sets(spark, d, inputs(spark, d), True)


RECIPE_UNITS = {"none": 0, "20k": 2, "75k": 7, "80k": 8, "90k": 9, "this_work": 6}
_COMMON = f"common AS MATERIALIZED (SELECT id, text FROM (SELECT 'c' || (conv_id * 1000 + turn) AS id, text FROM conversations UNION ALL SELECT 'p' || page_id, t FROM page_text) ORDER BY {h('common', 'id')}, id LIMIT (SELECT 11 * u FROM unit))"
_PAGES = """page_text AS (SELECT page_id, trim(regexp_replace(t, '[ \\n\\t\\r]+', ' ', 'g')) AS t FROM (SELECT page_id, replace(replace(replace(replace(replace(t, '&nbsp;', ' '), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&amp;', '&') AS t FROM (SELECT page_id, regexp_replace(regexp_replace(html, '<script[^>]*>[^<]*</script>|<style[^>]*>[^<]*</style>|<!--[^>]*-->', ' ', 'g'), '<[^>]*>', ' ', 'g') AS t FROM pages)))"""


def _staged_sql() -> str:
    rows = []
    for name, m in RECIPE_UNITS.items():
        text = f"SELECT 2 AS e, text FROM common UNION ALL SELECT 3, s FROM (SELECT s, doc_id FROM (SELECT *, substr(text, (1 + {h('s', 'doc_id', '2', '0')} % greatest(1, n_chars - 80))::BIGINT, 240) AS s FROM docs) ORDER BY {h('round99', 'doc_id')}, doc_id LIMIT (SELECT {m} * u FROM unit))"
        rows.append(
            f"""SELECT '{name}' AS recipe, {m} AS units, (WITH t AS (SELECT e, unnest({w("text")}) AS w FROM ({text})), c AS (SELECT w, sum(e) AS c FROM t GROUP BY w), k AS (SELECT sum(c) AS n, count(*) AS v FROM c), i AS (SELECT item_id AS id, unnest({w("text")}) AS w FROM benchmark),
 y AS (SELECT id, round(exp(sum(round(ln((coalesce(c, 0) + 1.0) / (k.n + k.v + 1)) * -1000000)::BIGINT) / 1000000.0 / count(*)), 4) AS ppl FROM i LEFT JOIN c USING (w), k GROUP BY id) SELECT round(avg(ln(ppl)), 4) FROM y) AS mean_ln_ppl"""
        )
    return f"WITH {_GATES}, {_SEEDS}, {_PAGES}, {_COMMON} " + " UNION ALL ".join(rows)


@query("staged_tuning", _staged_sql())
def staged_tuning(spark: SparkSession, d: str) -> DataFrame:
    """A target tuned on common texts for 2 epochs, then on so many synthesized samples for 3: six recipes."""
    raw, bench, labels = (table(spark, d, t) for t in ("documents", "benchmark", "labels"))
    whole = land(pool.build_pool(raw, bench)[0].select("snippet_id", "text", "n_chars", "lang", "source"))
    unit = bootstrap.unit_of(whole.count())
    docs = whole.join(drawn_seeds(whole, labels, bench, unit).select("snippet_id"), "snippet_id", "left_anti")
    turns = table(spark, d, "conversations").select(F.concat(F.lit("c"), (F.col("conv_id") * 1000 + F.col("turn")).cast("string")).alias("id"), "text")
    pages = pool.page_text(table(spark, d, "pages")).select(F.concat(F.lit("p"), F.col("page_id").cast("string")).alias("id"), "text")
    common = land(turns.union(pages).withColumn("_u", hash_unit("common", "id")).orderBy("_u", "id").limit(11 * unit).drop("_u"))
    made = land(bootstrap.final_dataset(None, docs, max(RECIPE_UNITS.values()) * unit, FIXED).select(F.col("snippet_id").alias("id"), F.col("s").alias("text")))
    tokens, items = lm.counted(bench, "item_id", "text"), bench.select(F.col("item_id").alias("id"))
    rows = []
    for name, m in RECIPE_UNITS.items():
        part = selection.random_n(made, m * unit, "round99")
        model = evaluate.staged_fit([(common, 2), (part, 3)])
        rows.append((name, m, lm.perplexity_counted(tokens, items, model).agg(F.round(F.avg(F.ln("ppl")), 4)).first()[0]))
    return spark.createDataFrame(rows, "recipe string, units int, mean_ln_ppl double")


JUDGES = {"lenient": lambda df: scoring.rule_marks(df, context="s"), "strict": lambda df: scoring.rule_marks(df, context="s", target=480, strict=40)}


@query("quality_two_judges")
def quality_two_judges(spark: SparkSession, d: str) -> DataFrame:
    """Kept samples of the trained loop beside conversation pairs, a hundred of each, by two judges on ten aspects."""
    inp = inputs(spark, d)
    cfg = replace(inp.config(), reference="trained", vocabulary=64, rank=4, width=64, schedule="20-20")
    kept = _run(inp, cfg, None, _enhanced(inp)[1]).rounds[-1].select(F.col("snippet_id").alias("id"), "q", "s")
    conv = candidates.from_conversations(table(spark, d, "conversations")).select((F.col("snippet_id") * 100 + F.col("draw")).alias("id"), "q", "s")
    return evaluate.compare_quality({"conversations": conv, "kept": kept}, JUDGES, MARKS)


def _judged_sql() -> str:
    conv = "SELECT conv_id * 100 + turn AS id, text AS q, s FROM (SELECT *, lead(role) OVER win AS r, lead(text) OVER win AS s FROM conversations WINDOW win AS (PARTITION BY conv_id ORDER BY turn)) WHERE role = 'user' AND r = 'assistant'"
    kept = "SELECT snippet_id AS id, q, s FROM r_k1"
    out = []
    for name, rows in (("conversations", conv), ("kept", kept)):
        sample = f"SELECT id, q, s FROM ({rows}) ORDER BY {h('judge', 'id')}, id LIMIT 100"
        for judge in JUDGES:
            marked = _marked(sample, "id", "s", False)
            if judge == "strict":
                marked = marked.replace("(20 * ", "(40 * ").replace("greatest(1, 241)", "greatest(1, 481)")
            out.append(f"SELECT '{name}' AS dataset, '{judge}' AS judge, aspect, round(sum(v) / count(v), 6) AS mean FROM (FROM ({marked} SELECT * FROM x) UNPIVOT (v FOR aspect IN ({', '.join(MARKS)}))) GROUP BY aspect")
    return f"{LOOP}, {rounds_sql('r_', FIXED, [4])} " + " UNION ALL ".join(out)


@query("quality_compare_kept", _judged_sql())
def quality_compare_kept(spark: SparkSession, d: str) -> DataFrame:
    """The same with hash-placed candidates."""
    inp = inputs(spark, d)
    kept = bootstrap.one_round(inp.docs, 4 * inp.unit, inp.config(), 1, bootstrap.Reference.make(inp.docs, inp.premium, inp.config()), None, inp.leaks)
    conv = candidates.from_conversations(table(spark, d, "conversations")).select((F.col("snippet_id") * 100 + F.col("draw")).alias("id"), "q", "s")
    return evaluate.compare_quality({"conversations": conv, "kept": kept.select(F.col("snippet_id").alias("id"), "q", "s")}, JUDGES, MARKS)


# ---------------------------------------------------------------- more targets, sets and costs


@query("final_dataset", f"WITH {_GATES}, {_SEEDS}, asked AS (SELECT * FROM docs ORDER BY {h('round99', 'doc_id')}, doc_id LIMIT (SELECT 4 * u FROM unit)) SELECT snippet_id, md5(q) AS q_digest, md5(s) AS s_digest FROM ({_cand('asked', '(SELECT 2 AS ckpt) a_, (SELECT 0 AS draw) b_')})")
def final_dataset(spark: SparkSession, d: str) -> DataFrame:
    """A target's training set: one draw of the last checkpoint for each of 4 units of snippets."""
    raw, bench, labels = (table(spark, d, t) for t in ("documents", "benchmark", "labels"))
    whole = land(pool.build_pool(raw, bench)[0].select("snippet_id", "text", "n_chars", "lang", "source"))
    unit = bootstrap.unit_of(whole.count())
    docs = whole.join(drawn_seeds(whole, labels, bench, unit).select("snippet_id"), "snippet_id", "left_anti")
    made = bootstrap.final_dataset(None, docs, 4 * unit, FIXED)
    return made.select("snippet_id", F.md5(F.col("q").cast("binary")).alias("q_digest"), F.md5(F.col("s").cast("binary")).alias("s_digest"))


@query("influence_to_items")
def influence_to_items(spark: SparkSession, d: str) -> DataFrame:
    """Benchmark items as the target in place of the premium set, by the trained reference."""
    inp = inputs(spark, d)
    ref = bootstrap.Reference.make(inp.docs, inp.premium, replace(inp.config(), reference="trained", vocabulary=64, rank=4, width=64))
    items = table(spark, d, "benchmark").select(F.col("item_id").alias("id"), F.lit("").alias("q"), F.col("text").alias("s"))
    target = influence.target_sum(ref.gradients(items, "id"))
    rows = inp.docs.select("snippet_id", F.lit("").alias("q"), F.col("text").alias("s"))
    return influence.score(ref.gradients(rows, "snippet_id"), target).select("id", "v")


@query("influence_over_checkpoints")
def influence_over_checkpoints(spark: SparkSession, d: str) -> DataFrame:
    """Influence summed over checkpoints of the reference's training, weighted by its step size."""
    inp = inputs(spark, d)
    v, signs = 64, None
    base = reference.pair_counts(reference.pair_codes(inp.docs, "snippet_id", "text", v), v)
    own = reference.pair_codes(inp.premium, "id", "s", v, "q")
    steps = reference.LowRankBigram.start(base).fit(reference.pair_counts(own, v), keep=(50, 100, 200))
    rows = land(reference.pair_codes(inp.docs.withColumn("q", F.lit("")), "snippet_id", "text", v, "q"))
    scores = []
    for model in steps:
        signs = influence.fast_signs(3, 0, model.width, 64).astype("int64") if signs is None else signs
        scores.append(influence.score(model.per_sample(rows, signs), influence.target_sum(model.per_sample(own, signs))))
    return influence.over_checkpoints(scores, [2.0] * len(scores)).select("id", F.round("v", 6).alias("v"))


_G = "SELECT vec_id AS id, label, generate_subscripts(embedding, 1) - 1 AS i, round(unnest(embedding)::DOUBLE * 1000000)::BIGINT AS g FROM embeddings"


@query("influence_without_self", f"WITH g AS ({_G}), t AS (SELECT i, sum(g)::BIGINT AS m FROM g WHERE id % 10 = 0 GROUP BY i), x AS (SELECT id, g, m - CASE WHEN id % 10 = 0 THEN g ELSE 0 END AS m FROM g JOIN t USING (i)) SELECT id, round(sum(g::DOUBLE * m) / sqrt(sum(g::DOUBLE * g)) / sqrt(sum(m::DOUBLE * m)), 6) AS v FROM x GROUP BY id")
def influence_without_self(spark: SparkSession, d: str) -> DataFrame:
    """Premium rows are compared with the mean of the others."""
    g = _grads(spark, d)
    own = g.filter("id % 10 = 0")
    return influence.score_without_self(g, influence.target_sum(own), own.select("id")).select("id", "v")


_DIST = ", ".join(f"({k})" for k in (8, 32, 256))


@query("projection_distortion", f"""WITH g AS MATERIALIZED ({_G}), t AS MATERIALIZED (SELECT i, sum(g)::BIGINT AS m, count(*) AS n FROM g WHERE id % 10 = 0 GROUP BY i), f AS MATERIALIZED (SELECT id, round(sum(g * m::DOUBLE) / sqrt(sum(g * g)::DOUBLE) / (SELECT sqrt(sum(m::DOUBLE * m)) FROM t), 6) AS v, sqrt(sum((g - floor(m / n)::BIGINT)::DOUBLE * (g - floor(m / n)::BIGINT))) AS d FROM g JOIN t USING (i) GROUP BY id),
 r AS MATERIALIZED (SELECT k, i, j, 1 - 2 * ({h("proj", "i", "j")} % 2) AS s FROM (VALUES {_DIST}) ks(k), (SELECT unnest(range(64)) AS i), (SELECT unnest(range(256)) AS j) WHERE j < k), p AS MATERIALIZED (SELECT k, id, j, sum(g * s)::BIGINT AS g FROM g JOIN r USING (i) GROUP BY 1, 2, 3), pt AS (SELECT k, j, sum(g)::BIGINT AS m FROM p WHERE id % 10 = 0 GROUP BY 1, 2), pm AS (SELECT k, j, sum(floor(m / n)::BIGINT * s)::BIGINT AS c FROM t JOIN r USING (i) GROUP BY 1, 2),
 pn AS (SELECT k, sqrt(sum(m::DOUBLE * m)) AS n FROM pt GROUP BY k), v AS (SELECT k, id, round(sum(g * m::DOUBLE) / sqrt(sum(g::DOUBLE * g)) / max(n), 6) AS w, sqrt(sum((g - c)::DOUBLE * (g - c))) AS e FROM p JOIN pt USING (k, j) JOIN pm USING (k, j) JOIN pn USING (k) GROUP BY 1, 2),
 best AS (SELECT id FROM f ORDER BY v DESC, id LIMIT 50), hit AS (SELECT k, id FROM v QUALIFY row_number() OVER (PARTITION BY k ORDER BY w DESC, id) <= 50) SELECT k::INT AS k, round(avg(abs(v - w)), 4) AS mean_abs_error, round(avg(CASE WHEN d > 0 THEN e / d / sqrt(k) END), 4) AS distance_ratio, (SELECT count(*) FROM hit WHERE hit.k = x.k AND id IN (SELECT id FROM best)) AS top_overlap FROM (SELECT * FROM v JOIN f USING (id)) x GROUP BY k""")
def projection_distortion(spark: SparkSession, d: str) -> DataFrame:
    g = land(_grads(spark, d))
    return influence.distortion(g, g.filter("id % 10 = 0"), 64, [8, 32, 256], 50)


@query("cost_engine")
def cost_engine(spark: SparkSession, d: str) -> DataFrame:
    """Rows, seconds and costly operators of the plan of each stage of one round, run once."""
    inp = inputs(spark, d)
    cfg = inp.config()
    ref = bootstrap.Reference.make(inp.docs, inp.premium, cfg)
    prompts = land(bootstrap.prompted(inp.docs, 4 * inp.unit, 1))
    marked = lambda: scoring.rule_marks(bootstrap.sampled(prompts, cfg), inp.leaks).select("snippet_id", "ckpt", "draw", *MARKS)
    best = bootstrap.picked(bootstrap.sampled(prompts, cfg), cfg, inp.leaks)
    work = {"marks": marked, "gradients": lambda: ref.gradients(best, "snippet_id"), "selection": lambda: bootstrap.ranked(best, 2 * inp.unit, cfg, 1, ref).select("snippet_id", "v")}
    return spark.createDataFrame(evaluate.engine_cost(work), "stage string, rows long, seconds double, exchanges int, broadcasts int, sorts int, scans int, python int, joins int")


# ---------------------------------------------------------------- near duplicates in the pool, prior generators, models

_NEAR = f"""WITH s AS (SELECT doc_id, list_sort(CASE WHEN len(t) >= 5 THEN list_distinct(list_transform(range(1, len(t) - 3), lambda i: array_to_string(t[i:i + 4], ' '))) ELSE [] END) AS g FROM (SELECT doc_id, {w("text")} AS t FROM documents)),
 n AS MATERIALIZED (SELECT min(doc_id) AS id, g, list_transform(g, lambda x: ('0x' || substr(md5('band-' || x), 1, 8))::BIGINT % 2147483647) AS hs FROM s WHERE len(g) > 0 GROUP BY g),
 k AS MATERIALIZED (SELECT id, b, {" || '-' || ".join(f"list_min(list_transform(hs, lambda x: (x * (1000003 * ((b * 2 + {r}) + 1)) + 7919 * (b * 2 + {r})) % 2147483647))::VARCHAR" for r in range(2))} AS key FROM n, (SELECT unnest(range(8)) AS b)),
 m AS (SELECT DISTINCT x.id AS a, y.id AS b FROM k x JOIN k y ON x.b = y.b AND x.key = y.key AND x.id < y.id),
 pairs AS MATERIALIZED (SELECT a, b, (100 * len(list_intersect(x.g, y.g)) // (len(x.g) + len(y.g) - len(list_intersect(x.g, y.g))))::INT AS percent FROM m JOIN n x ON x.id = a JOIN n y ON y.id = b)"""


@query("pool_near_dup_pairs", _NEAR + " SELECT a, b, percent FROM pairs WHERE percent >= 80")
def pool_near_dup_pairs(spark: SparkSession, d: str) -> DataFrame:
    return pool.near_pairs(table(spark, d, "documents"))


@query("pool_near_dup_clusters", _NEAR.replace("WITH s AS", "WITH RECURSIVE s AS", 1) + """, e AS (SELECT a, b FROM pairs WHERE percent >= 80 UNION ALL SELECT b, a FROM pairs WHERE percent >= 80), reach(id, r) AS (SELECT id, id FROM n UNION SELECT reach.id, e.b FROM reach JOIN e ON e.a = reach.r), low AS (SELECT id, min(r) AS cluster_id FROM reach GROUP BY id)
 SELECT s.doc_id AS id, coalesce(low.cluster_id, s.doc_id) AS cluster_id FROM s LEFT JOIN n ON n.g = s.g LEFT JOIN low ON low.id = n.id""")
def pool_near_dup_clusters(spark: SparkSession, d: str) -> DataFrame:
    docs = table(spark, d, "documents")
    return pool.near_clusters(docs, pool.near_pairs(docs))


@query("cand_mean_jaccard")
def cand_mean_jaccard(spark: SparkSession, d: str) -> DataFrame:
    """How alike the candidates of a snippet are."""
    return candidates.mean_jaccard(candidates.multi_checkpoint(table(spark, d, "documents").select(F.col("doc_id").alias("snippet_id"), "text", "n_chars")))


@query("synth_self_bootstrap")
def synth_self_bootstrap(spark: SparkSession, d: str) -> DataFrame:
    """Seed-task bootstrapping from the benchmark items with hash-placed passages: tasks by round."""
    seeds = table(spark, d, "benchmark").select(F.col("item_id").alias("snippet_id"), "text", F.length("text").cast("long").alias("n_chars"))
    return synth.self_bootstrap(seeds, synth.PassageSynthesizer(), 3, 20).groupBy("round").agg(F.count(F.lit(1)).alias("n"))


@query("synth_evolve")
def synth_evolve(spark: SparkSession, d: str) -> DataFrame:
    """Every benchmark item evolved in depth and in breadth."""
    items = table(spark, d, "benchmark").select(F.col("item_id").alias("snippet_id"), "text")
    both = [synth.evolve(items, synth.PassageSynthesizer(), m).select("snippet_id", F.lit(m).alias("mode"), "evolved") for m in ("depth", "breadth")]
    return both[0].union(both[1])


@query("grad_logistic_trained")
def grad_logistic_trained(spark: SparkSession, d: str) -> DataFrame:
    """Influence by the gradients of a trained logistic model of hashed words; target: good documents of even sources."""
    docs = table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id")
    cells = land(reference.HashedLogistic.cells(docs, "doc_id", "text", "quality", 64))
    even = docs.filter(EVEN).select(F.col("doc_id").alias("id"))
    model = reference.HashedLogistic.fit(cells.join(even, "id", "left_semi"), 64)
    g = land(model.per_sample(cells))
    good = docs.filter(f"quality = 1 and {EVEN}").select(F.col("doc_id").alias("id"))
    return influence.score(g, influence.target_sum(g.join(good, "id", "left_semi"))).select("id", "v")
