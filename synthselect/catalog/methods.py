"""The methods, their variants and baselines, and the experiment workloads, over the given tables."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import fp, hash_unit, normalise
from ..operators import candidates, categories, evaluate, influence, lm, pool, reference, ridge, scoring, selection, synth
from ..plans import bootstrap
from ..sources import land, table
from . import five, grams, h, query, w

# ---------------------------------------------------------------- pool

_PUNCT = scoring._PUNCT.replace("'", "''")
_SECRET = scoring.SECRET


def _pct(a: str, b: str) -> str:
    return f"((100 * {a}) // greatest(1, {b}))::INT"




def _punct_n(t: str) -> str:
    return f"(length({t}) - length(translate({t}, '{_PUNCT}', '')))"


_NOISE = f"""SELECT doc_id, n_chars, text, {_pct(_punct_n("text"), "length(text)")} AS punct_pct,
 {_pct(f"len(list_distinct({w('text')}))", f"len({w('text')})")} AS distinct_pct,
 (100 - {_pct("len(list_distinct(string_split(text, chr(10))))", "len(string_split(text, chr(10)))")})::INT AS repeat_pct FROM documents"""


@query("pool_exact_dedup", f"SELECT min(doc_id) AS doc_id FROM documents GROUP BY md5(array_to_string({w('text')}, ' '))")
def pool_exact_dedup(spark: SparkSession, d: str) -> DataFrame:
    return pool.exact_dedup(table(spark, d, "documents")).select("doc_id")


@query("pool_noise_flags", f"SELECT doc_id, punct_pct, distinct_pct, repeat_pct, punct_pct > 12 OR distinct_pct < 20 OR repeat_pct > 50 AS noisy FROM ({_NOISE})")
def pool_noise_flags(spark: SparkSession, d: str) -> DataFrame:
    return pool.noise(table(spark, d, "documents")).select("doc_id", "punct_pct", "distinct_pct", "repeat_pct", pool.is_noisy().alias("noisy"))


@query("pool_length_gate", "SELECT doc_id, n_chars FROM documents WHERE n_chars BETWEEN 100 AND 20000")
def pool_length_gate(spark: SparkSession, d: str) -> DataFrame:
    return pool.length_gate(table(spark, d, "documents"), 100, 20_000).select("doc_id", "n_chars")


@query("pool_sensitive_flags", f"SELECT doc_id, len(regexp_extract_all(text, '{_SECRET}'))::INT AS n_sensitive FROM documents")
def pool_sensitive_flags(spark: SparkSession, d: str) -> DataFrame:
    return pool.sensitive_hits(table(spark, d, "documents")).select("doc_id", "n_sensitive")


@query("pool_license_flags", f"SELECT doc_id, len(regexp_extract_all(lower(text), '{pool.LICENSE}'))::INT AS n_license FROM documents")
def pool_license_flags(spark: SparkSession, d: str) -> DataFrame:
    return pool.license_hits(table(spark, d, "documents")).select("doc_id", "n_license")


_HITS = f"""SELECT id, count(*) AS n_hits FROM (SELECT doc_id AS id, unnest({grams("t", 8)}) AS gram FROM (SELECT doc_id, {w("text")} AS t FROM documents))
 WHERE gram IN (SELECT unnest({grams("t", 8)}) FROM (SELECT {w("text")} AS t FROM benchmark)) GROUP BY id"""


@query("pool_decontaminate", _HITS)
def pool_decontaminate(spark: SparkSession, d: str) -> DataFrame:
    return pool.contaminated(table(spark, d, "documents"), table(spark, d, "benchmark"))


@query(
    "pool_funnel",
    f"""WITH n AS (SELECT *, len(regexp_extract_all(text, '{_SECRET}')) AS n_sensitive, min(doc_id) OVER (PARTITION BY md5(array_to_string({w("text")}, ' '))) AS first_id FROM ({_NOISE})), b AS ({_HITS})
 SELECT CASE WHEN n_chars < 100 OR n_chars > 20000 THEN 'length' WHEN punct_pct > 12 OR distinct_pct < 20 OR repeat_pct > 50 THEN 'noise' WHEN n_sensitive > 0 THEN 'sensitive'
 WHEN doc_id <> first_id THEN 'duplicate' WHEN b.id IS NOT NULL THEN 'benchmark' ELSE 'kept' END AS step, count(*) AS n FROM n LEFT JOIN b ON n.doc_id = b.id GROUP BY 1""",
)
def pool_funnel(spark: SparkSession, d: str) -> DataFrame:
    return pool.funnel(table(spark, d, "documents"), table(spark, d, "benchmark"))


@query(
    "pool_page_text_stats",
    """WITH a AS (SELECT page_id, regexp_replace(html, '<script[^>]*>[^<]*</script>|<style[^>]*>[^<]*</style>|<!--[^>]*-->', ' ', 'g') AS t FROM pages),
 b AS (SELECT page_id, regexp_replace(t, '<[^>]*>', ' ', 'g') AS t FROM a),
 c AS (SELECT page_id, replace(replace(replace(replace(replace(t, '&nbsp;', ' '), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&amp;', '&') AS t FROM b)
 SELECT page_id, length(trim(regexp_replace(t, '[ \\n\\t\\r]+', ' ', 'g')))::INT AS n_chars, md5(trim(regexp_replace(t, '[ \\n\\t\\r]+', ' ', 'g'))) AS digest FROM c""",
)
def pool_page_text_stats(spark: SparkSession, d: str) -> DataFrame:
    return pool.page_text(table(spark, d, "pages")).select("page_id", F.length("text").alias("n_chars"), F.md5(F.col("text").cast("binary")).alias("digest"))


# ---------------------------------------------------------------- categories

_E = "SELECT vec_id, label, generate_subscripts(embedding, 1) - 1 AS i, unnest(embedding)::DOUBLE AS x FROM embeddings"
_PROTO = "SELECT label AS c, i, x AS y FROM e WHERE vec_id IN (SELECT min(vec_id) FROM embeddings GROUP BY label)"
_SIM = f"WITH e AS ({_E}), p AS ({_PROTO}), s AS (SELECT vec_id AS id, c, round(sum(x * y) / sqrt(sum(x * x)) / sqrt(sum(y * y)), 6) AS similarity, round(-sqrt(sum((x - y) * (x - y))), 6) AS near FROM e JOIN p USING (i) GROUP BY 1, 2)"


@query("text_hash_embedding", f"SELECT doc_id AS id, (hh % 64)::INT AS i, sum(1 - 2 * ((hh >> 16) % 2))::BIGINT AS x FROM (SELECT doc_id, {h('emb', 't')} AS hh FROM (SELECT doc_id, unnest({w('text')}) AS t FROM documents)) GROUP BY 1, 2 HAVING sum(1 - 2 * ((hh >> 16) % 2)) <> 0")
def text_hash_embedding(spark: SparkSession, d: str) -> DataFrame:
    return categories.hashed_embedding(table(spark, d, "documents"), "doc_id", "text")


@query("category_assign", _SIM + " SELECT id, c AS category_id, similarity FROM s QUALIFY row_number() OVER (PARTITION BY id ORDER BY similarity DESC, c) = 1")
def category_assign(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "embeddings")
    return categories.assign(e, "vec_id", "embedding", categories.prototypes(e)).select("id", "category_id", "similarity")


@query("category_assign_euclid", _SIM + " SELECT id, c AS category_id, round(near, 3) AS similarity FROM s QUALIFY row_number() OVER (PARTITION BY id ORDER BY near DESC, c) = 1")
def category_assign_euclid(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "embeddings")
    return categories.assign(e, "vec_id", "embedding", categories.prototypes(e), metric="euclidean").select("id", "category_id", F.round("similarity", 3).alias("similarity"))


@query("category_soft_top3", _SIM + " SELECT id, c AS category_id, similarity, row_number() OVER (PARTITION BY id ORDER BY similarity DESC, c)::INT AS place FROM s QUALIFY place <= 3")
def category_soft_top3(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "embeddings")
    return categories.assign(e, "vec_id", "embedding", categories.prototypes(e), m=3)


@query("category_coverage", _SIM + ", a AS (SELECT id, c FROM s QUALIFY row_number() OVER (PARTITION BY id ORDER BY similarity DESC, c) = 1), n AS (SELECT c AS category_id, count(*) AS n, count(*) / sum(count(*)) OVER () AS q FROM a GROUP BY c) SELECT category_id, n, round(q, 6) AS share, round(sum(-q * ln(q)) OVER (), 6) AS entropy FROM n")
def category_coverage(spark: SparkSession, d: str) -> DataFrame:
    return categories.coverage(category_assign(spark, d), "category_id")


@query("category_centroid_assign", f"WITH e AS ({_E}), p AS (SELECT label AS c, i, sum(round(x * 1000000)::BIGINT)::DOUBLE AS y FROM e GROUP BY 1, 2), s AS (SELECT vec_id AS id, c, round(sum(x * y) / sqrt(sum(x * x)) / sqrt(sum(y * y)), 6) AS similarity FROM e JOIN p USING (i) GROUP BY 1, 2) SELECT id, c AS category_id, similarity FROM s QUALIFY row_number() OVER (PARTITION BY id ORDER BY similarity DESC, c) = 1")
def category_centroid_assign(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "embeddings")
    return categories.assign(e, "vec_id", "embedding", categories.centroids(e, 64)).select("id", "category_id", "similarity")


@query("seed_stratified", f"SELECT vec_id AS id, label, row_number() OVER (PARTITION BY label ORDER BY {h('seed', 'vec_id')}, vec_id)::INT AS rank FROM embeddings QUALIFY rank <= 5")
def seed_stratified(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "embeddings").select(F.col("vec_id").alias("id"), "label")
    return categories.stratified(e, "label", 5)


@query("seed_random", f"SELECT vec_id AS id FROM embeddings ORDER BY {h('rand', 'vec_id')}, vec_id LIMIT 50")
def seed_random(spark: SparkSession, d: str) -> DataFrame:
    return selection.random_n(table(spark, d, "embeddings").select(F.col("vec_id").alias("id")), 50)


@query("seed_proportional", f"WITH n AS (SELECT lang, count(*) * 100 // (SELECT count(*) FROM documents) AS quota FROM documents GROUP BY lang) SELECT doc_id AS id, lang FROM documents JOIN n USING (lang) QUALIFY row_number() OVER (PARTITION BY lang ORDER BY {h('seed', 'doc_id')}, doc_id) <= quota")
def seed_proportional(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "documents").select(F.col("doc_id").alias("id"), "lang")
    return categories.proportional(e, "lang", 100).select("id", "lang")


# ---------------------------------------------------------------- candidates and marks


def _cand(cells: str) -> str:
    at = lambda k: f"{h(k, 'doc_id', 'ckpt', 'draw')} % greatest(1, n_chars - 80)"
    return f"SELECT doc_id AS snippet_id, text, ckpt, draw, substr(text, (1 + {at('q')})::BIGINT, 80) AS q, substr(text, (1 + {at('s')})::BIGINT, 240) AS s FROM documents, {cells}"


_MULTI = _cand("(SELECT unnest(range(3))::INT AS ckpt) a, (SELECT unnest(range(4))::INT AS draw) b")
_LAST = _cand("(SELECT 2 AS ckpt) a, (SELECT unnest(range(12))::INT AS draw) b")
_BEST = _cand("(SELECT 2 AS ckpt) a, (SELECT unnest(range(4))::INT AS draw) b")
_SHOW = "SELECT snippet_id, ckpt, draw, md5(q) AS q_digest, md5(s) AS s_digest FROM ({c})"
_SHORT = ["snippet_id", "ckpt", "draw"]


def _snips(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents").select(F.col("doc_id").alias("snippet_id"), "text", "n_chars")


def _fanned(spark: SparkSession, d: str) -> DataFrame:
    """Candidates beside their snippet's words, which are split once."""
    return candidates.multi_checkpoint(scoring.with_context(_snips(spark, d)))


def _digests(df: DataFrame) -> DataFrame:
    return df.select(*_SHORT, F.md5(F.col("q").cast("binary")).alias("q_digest"), F.md5(F.col("s").cast("binary")).alias("s_digest"))


@query("cand_multi_checkpoint", _SHOW.format(c=_MULTI))
def cand_multi_checkpoint(spark: SparkSession, d: str) -> DataFrame:
    return _digests(candidates.multi_checkpoint(_snips(spark, d)))


@query("cand_last_checkpoint", _SHOW.format(c=_LAST))
def cand_last_checkpoint(spark: SparkSession, d: str) -> DataFrame:
    return _digests(candidates.last_checkpoint(_snips(spark, d)))


@query("cand_best_of_n", _SHOW.format(c=_BEST))
def cand_best_of_n(spark: SparkSession, d: str) -> DataFrame:
    return _digests(candidates.best_of_n(_snips(spark, d)))


_CONV = "SELECT conv_id AS snippet_id, turn AS draw, text AS q, s FROM (SELECT *, lead(role) OVER win AS r, lead(text) OVER win AS s FROM conversations WINDOW win AS (PARTITION BY conv_id ORDER BY turn)) WHERE role = 'user' AND r = 'assistant'"


@query("cand_conversation_pairs", f"SELECT snippet_id, draw, md5(q) AS q_digest, md5(s) AS s_digest FROM ({_CONV})")
def cand_conversation_pairs(spark: SparkSession, d: str) -> DataFrame:
    c = candidates.from_conversations(table(spark, d, "conversations"))
    return c.select("snippet_id", "draw", F.md5(F.col("q").cast("binary")).alias("q_digest"), F.md5(F.col("s").cast("binary")).alias("s_digest"))


def _language(t: str) -> str:
    n = [f"len(list_filter({t}, lambda z: z IN ({', '.join(repr(x) for x in ws)})))" for ws in scoring.STOP_WORDS.values()]
    top = f"greatest({', '.join(n)})"
    ties = " + ".join(f"({c} = {top})::INT" for c in n)
    return f"(CASE WHEN {top} = 0 OR {ties} > 1 THEN -1 WHEN {n[0]} = {top} THEN 0 WHEN {n[1]} = {top} THEN 1 WHEN {n[2]} = {top} THEN 2 ELSE 3 END)"


def _marked(cand: str, keys: str = "snippet_id, ckpt, draw", context: str = "text", leak: bool = True) -> str:
    grams_of = f"SELECT unnest({grams('t', 8)}) FROM (SELECT {w('text')} AS t FROM benchmark)"
    x8 = f"(CASE WHEN EXISTS (SELECT 1 FROM leaks WHERE {' AND '.join(f'leaks.{k.strip()} = m.{k.strip()}' for k in keys.split(','))}) THEN 1 ELSE 5 END)::INT" if leak else "5::INT"
    return f"""WITH c AS ({cand}), m AS (SELECT *, {w("q")} AS tq, {w("s")} AS ts, {w(context)} AS tc FROM c){f", leaks AS (SELECT DISTINCT {keys} FROM (SELECT {keys}, unnest({grams('ts', 8)}) AS gram FROM m) WHERE gram IN ({grams_of}))" if leak else ""},
 x AS (SELECT {keys}, q, s, {five("len(list_intersect(tq, ts))", "len(list_distinct(tq))")} AS x1, {five("len(list_distinct(ts))", "len(ts)")} AS x2,
 (5 - least(4, (20 * {_punct_n("s")}) // greatest(1, length(s))))::INT AS x3, {five("length(s)", "241")} AS x4,
 {five("len(list_distinct(string_split(s, chr(10))))", "len(string_split(s, chr(10)))")} AS x5, (5 - least(4, greatest(0, length(s) // greatest(1, len(ts)) - 7)))::INT AS x6,
 {five("len(list_intersect(ts, tc))", "len(list_distinct(ts))")} AS x7, {x8} AS x8, (5 - least(4, 2 * len(regexp_extract_all(s, '{_SECRET}'))))::INT AS x9,
 (CASE WHEN {_language("tq")} = -1 OR {_language("ts")} = -1 THEN 3 WHEN {_language("tq")} = {_language("ts")} THEN 5 ELSE 1 END)::INT AS x10 FROM m)"""


_X = ", ".join(scoring.MARKS)
_SUM = " + ".join(scoring.MARKS)
W10 = list(bootstrap.Config().weights)
_WEIGHTED = " + ".join(f"{wt} * {m}" for wt, m in zip(W10, scoring.MARKS))


def _marks(spark: SparkSession, d: str, cand: DataFrame | None = None) -> DataFrame:
    leaks = pool.benchmark_grams(table(spark, d, "benchmark"))
    return scoring.rule_marks(_fanned(spark, d) if cand is None else cand, leaks)


@query("score_aspects", _marked(_MULTI) + f" SELECT snippet_id, ckpt, draw, {_X} FROM x")
def score_aspects(spark: SparkSession, d: str) -> DataFrame:
    return _marks(spark, d).select(*_SHORT, *scoring.MARKS)


@query("score_aspects_conversations", _marked(_CONV, "snippet_id, draw", "s", False) + f" SELECT snippet_id, draw, {_X} FROM x")
def score_aspects_conversations(spark: SparkSession, d: str) -> DataFrame:
    return scoring.rule_marks(candidates.from_conversations(table(spark, d, "conversations"))).select("snippet_id", "draw", *scoring.MARKS)


@query("score_weighted", _marked(_MULTI) + f" SELECT snippet_id, ckpt, draw, round(({_WEIGHTED}) * 1000000)::BIGINT AS score_fp FROM x")
def score_weighted(spark: SparkSession, d: str) -> DataFrame:
    return scoring.weighted(_marks(spark, d), W10).select(*_SHORT, "score_fp")


@query("score_average", _marked(_MULTI) + f" SELECT snippet_id, ckpt, draw, round(({_SUM}) / 10.0 * 1000000)::BIGINT AS score_fp FROM x")
def score_average(spark: SparkSession, d: str) -> DataFrame:
    return scoring.simple_average(_marks(spark, d)).select(*_SHORT, "score_fp")


@query("score_composite", _marked(_MULTI) + f" SELECT snippet_id, ckpt, draw, (1 + least(4, (({_SUM}) - 10) // 10))::INT AS score FROM x")
def score_composite(spark: SparkSession, d: str) -> DataFrame:
    return scoring.composite(_marks(spark, d)).select(*_SHORT, "score")


_BESTW = _marked(_MULTI) + f", z AS (SELECT snippet_id, ckpt, draw, round(({_WEIGHTED}) * 1000000)::BIGINT AS score_fp FROM x)"


@query("cand_pick_best", _BESTW + " SELECT * FROM z QUALIFY row_number() OVER (PARTITION BY snippet_id ORDER BY score_fp DESC, ckpt, draw) = 1")
def cand_pick_best(spark: SparkSession, d: str) -> DataFrame:
    return candidates.top_m(score_weighted(spark, d), "score_fp").drop("place")


@query("cand_top_m", _BESTW + " SELECT *, row_number() OVER (PARTITION BY snippet_id ORDER BY score_fp DESC, ckpt, draw)::INT AS place FROM z QUALIFY place <= 3")
def cand_top_m(spark: SparkSession, d: str) -> DataFrame:
    return candidates.top_m(score_weighted(spark, d), "score_fp", 3)


@query("cand_search_gain", _BESTW + " SELECT snippet_id, max(score_fp) AS best_all, max(score_fp) FILTER (ckpt = 2) AS best_last, max(score_fp) - max(score_fp) FILTER (ckpt = 2) AS gain FROM z GROUP BY 1")
def cand_search_gain(spark: SparkSession, d: str) -> DataFrame:
    return candidates.search_gain(score_weighted(spark, d), "score_fp", 2)


@query("cand_diversity", f"SELECT snippet_id, count(*) AS n, count(DISTINCT md5(s)) AS n_distinct, round(len(list_distinct(flatten(list({w('s')})))) / greatest(1, sum(len({w('s')}))), 6) AS distinct_1 FROM ({_MULTI}) GROUP BY 1")
def cand_diversity(spark: SparkSession, d: str) -> DataFrame:
    return candidates.diversity(candidates.multi_checkpoint(_snips(spark, d)))


@query("cand_pick_best_conv", _marked(_CONV, "snippet_id, draw", "s", False) + f" SELECT snippet_id, draw, round(({_SUM}) / 10.0 * 1000000)::BIGINT AS score_fp FROM x QUALIFY row_number() OVER (PARTITION BY snippet_id ORDER BY score_fp DESC, draw) = 1")
def cand_pick_best_conv(spark: SparkSession, d: str) -> DataFrame:
    m = scoring.simple_average(scoring.rule_marks(candidates.from_conversations(table(spark, d, "conversations"))))
    return candidates.top_m(m, "score_fp", ties=["draw"]).select("snippet_id", "draw", "score_fp")


@query("cand_nested_longest", f"SELECT snippet_id, ckpt, draw, length(s)::INT AS score FROM ({_MULTI}) QUALIFY row_number() OVER (PARTITION BY snippet_id ORDER BY length(s) DESC, ckpt, draw) = 1")
def cand_nested_longest(spark: SparkSession, d: str) -> DataFrame:
    """The shuffle-free nested form, on the simplest score."""
    return candidates.pick_best_nested(_snips(spark, d), lambda x: F.length(x["s"])).select("snippet_id", "ckpt", "draw", "score")


_LI = "SELECT l_orderkey AS snippet_id, (l_suppkey % 3)::INT AS ckpt, l_linenumber AS draw, l_partkey, (l_quantity * 2 + l_discount * 100 - l_tax * 100)::DOUBLE AS v FROM lineitem"


@query("cand_pick_best_lineitem", f"SELECT snippet_id, ckpt, draw, l_partkey, round(v * 1000000)::BIGINT AS score_fp FROM ({_LI}) QUALIFY row_number() OVER (PARTITION BY snippet_id ORDER BY score_fp DESC, ckpt, draw, l_partkey) = 1")
def cand_pick_best_lineitem(spark: SparkSession, d: str) -> DataFrame:
    li = table(spark, d, "lineitem").select(F.col("l_orderkey").alias("snippet_id"), (F.col("l_suppkey") % 3).cast("int").alias("ckpt"), F.col("l_linenumber").alias("draw"), "l_partkey", fp(F.col("l_quantity") * 2 + F.col("l_discount") * 100 - F.col("l_tax") * 100).alias("score_fp"))
    return candidates.top_m(li, "score_fp", ties=["ckpt", "draw", "l_partkey"]).drop("place")


@query("cand_checkpoint_wins_events", "WITH b AS (SELECT user_id, event_type FROM events QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_type, event_id) = 1) SELECT event_type AS ckpt, count(*) AS wins FROM b GROUP BY 1")
def cand_checkpoint_wins_events(spark: SparkSession, d: str) -> DataFrame:
    best = candidates.top_m(table(spark, d, "events"), "value", by="user_id", ties=["event_type", "event_id"])
    return best.groupBy(F.col("event_type").alias("ckpt")).agg(F.count(F.lit(1)).alias("wins"))


# ---------------------------------------------------------------- ridge

RM = ["x2", "x3", "x5", "x6"]
_DOCQS = "SELECT doc_id AS snippet_id, text, substr(text, 1, 80) AS q, text AS s FROM documents"
_EXP = _marked(_DOCQS, "snippet_id", "q", False) + """, e AS (SELECT lang, source, """ + ", ".join(f"round(sum({m}) / count({m}), 6) AS {m}" for m in RM) + """, round(sum(quality) / count(quality), 6) AS y, count(*) AS n
 FROM x JOIN documents d ON d.doc_id = x.snippet_id JOIN labels USING (doc_id) GROUP BY lang, source)"""


def _labelled_marks(spark: SparkSession, d: str) -> DataFrame:
    docs = table(spark, d, "documents").select(F.col("doc_id").alias("snippet_id"), "lang", "source", F.substring("text", 1, 80).alias("q"), F.col("text").alias("s"))
    return scoring.rule_marks(docs.join(table(spark, d, "labels").withColumnRenamed("doc_id", "snippet_id"), "snippet_id"), context="q")


def _exps(spark: SparkSession, d: str) -> DataFrame:
    return ridge.experiments(_labelled_marks(spark, d), ["lang", "source"], RM, "quality")


@query("ridge_experiments", _EXP + " SELECT * FROM e")
def ridge_experiments(spark: SparkSession, d: str) -> DataFrame:
    return _exps(spark, d)


_I = lambda c: f"round({c} * 1000000)::BIGINT"
_GRAM = ", ".join(f"sum({_I(a)} * {_I(b)})::BIGINT AS g_{a}_{b}" for k, a in enumerate(RM) for b in RM[k:]) + ", " + ", ".join(f"sum({_I(a)} * {_I('y')})::BIGINT AS b_{a}" for a in RM)


@query("ridge_gram", _EXP + f" SELECT {_GRAM}, count(*) AS k FROM e")
def ridge_gram(spark: SparkSession, d: str) -> DataFrame:
    return ridge.gram(_exps(spark, d), RM)


_Z2 = _EXP + ", g AS (SELECT sum(x2 * x2) + 1.0 AS a, sum(x2 * x3) AS b, sum(x3 * x3) + 1.0 AS c, sum(x2 * y) AS p, sum(x3 * y) AS q FROM e)"


@query("ridge_weights_z2", _Z2 + " SELECT round((c * p - b * q) / (a * c - b * b), 6) AS w_x2, round((a * q - b * p) / (a * c - b * b), 6) AS w_x3 FROM g")
def ridge_weights_z2(spark: SparkSession, d: str) -> DataFrame:
    m = ridge.fit(_exps(spark, d), ["x2", "x3"])
    return spark.createDataFrame([tuple(round(float(v), 6) for v in m.weights)], "w_x2 double, w_x3 double")


def _solved(penalty: float, name: str) -> str:
    """CTE {name}: one row of weights, by elimination on the normal equations."""
    from .solve import elimination

    return elimination("e", RM, "y", penalty, name)


_SYS = ", ".join(f"sum({_I(a)} * {_I(b)})::DOUBLE / 1e12 AS g_{a}_{b}" for a in RM for b in RM) + ", " + ", ".join(f"sum({_I(a)} * {_I('y')})::DOUBLE / 1e12 AS b_{a}" for a in RM)
_RESIDUALS = " UNION ALL ".join(f"SELECT '{a}' AS mark, abs(round({' + '.join(f'(g_{a}_{b}' + (' + 1.0' if a == b else '') + f') * w_{b}' for b in RM)} - b_{a}, 6)) AS residual FROM sys, sol" for a in RM)


@query("ridge_residual", _EXP + f", sys AS (SELECT {_SYS} FROM e), {_solved(1.0, 'sol')} {_RESIDUALS}")
def ridge_residual(spark: SparkSession, d: str) -> DataFrame:
    """Residuals of the normal equations at the fitted weights."""
    m = ridge.fit(_exps(spark, d), RM)
    return spark.createDataFrame([(k, abs(round(float(v), 6))) for k, v in zip(RM, m.residual())], "mark string, residual double")


_PEN = (0.1, 1.0, 10.0)


@query("ridge_weights_by_penalty", _EXP + ", " + ", ".join(_solved(p, f"s{k}") for k, p in enumerate(_PEN)) + " " + " UNION ALL ".join(f"SELECT {p}::DOUBLE AS penalty, " + ", ".join(f"round(w_{m}, 6) AS w_{m}" for m in RM) + f" FROM s{k}" for k, p in enumerate(_PEN)))
def ridge_weights_by_penalty(spark: SparkSession, d: str) -> DataFrame:
    e = land(_exps(spark, d))
    rows = [(p, *(round(float(v), 6) for v in ridge.fit(e, RM, p).weights)) for p in _PEN]
    return spark.createDataFrame(rows, "penalty double, " + ", ".join(f"w_{m} double" for m in RM))


def _loo_sql() -> str:
    """Leave-one-out by the hat values; the inverse's columns are solved one by one."""
    from .solve import inverse

    parts = ", ".join(inverse("e", RM, p, f"i{k}") for k, p in enumerate(_PEN))
    rows = []
    for k, p in enumerate(_PEN):
        hat = " + ".join(f"v_{a}_{b} * {a} * {b}" for a in RM for b in RM)
        fit = " + ".join(f"w_{m} * {m}" for m in RM)
        rows.append(f"SELECT {p}::DOUBLE AS penalty, round(avg(r * r), 6) AS loo_mse FROM (SELECT (y - ({fit})) / (1 - ({hat})) AS r FROM e, s{k}, i{k})")
    return _EXP + ", " + ", ".join(_solved(p, f"s{k}") for k, p in enumerate(_PEN)) + f", {parts} " + " UNION ALL ".join(rows)


@query("ridge_loo", _loo_sql())
def ridge_loo(spark: SparkSession, d: str) -> DataFrame:
    return ridge.loo_path(land(_exps(spark, d)), RM, list(_PEN))


@query("ridge_weights")
def ridge_weights(spark: SparkSession, d: str) -> DataFrame:
    """Plain, not negative, with intercept, standardised."""
    e = land(_exps(spark, d))
    ways = {"plain": {}, "nonneg": {"nonneg": True}, "intercept": {"intercept": True}, "standardised": {"intercept": True, "standardise": True}}
    rows = []
    for p in _PEN:
        for name, how in ways.items():
            m = ridge.fit(e, RM, p, **how)
            rows.append((p, name, round(m.intercept, 6), *(round(float(v), 6) for v in m.weights)))
    return spark.createDataFrame(rows, "penalty double, how string, intercept double, " + ", ".join(f"w_{m} double" for m in RM))


@query("ridge_residuals_by_experiment")
def ridge_residuals_by_experiment(spark: SparkSession, d: str) -> DataFrame:
    e = land(_exps(spark, d))
    return ridge.residuals(e, ridge.fit(e, RM), ["lang", "source"])


@query("ridge_rank_correlation")
def ridge_rank_correlation(spark: SparkSession, d: str) -> DataFrame:
    e = land(_exps(spark, d))
    return ridge.rank_correlation(e, ridge.fit(e, RM), ["lang", "source"])


@query("ridge_diagnostics")
def ridge_diagnostics(spark: SparkSession, d: str) -> DataFrame:
    e = _exps(spark, d)
    return ridge.diagnostics(e, ridge.fit(e, RM))


# ---------------------------------------------------------------- influence

_G = "SELECT vec_id AS id, label, generate_subscripts(embedding, 1) - 1 AS i, round(unnest(embedding)::DOUBLE * 1000000)::BIGINT AS g FROM embeddings"
_TARGET = "SELECT i, sum(g)::BIGINT AS m FROM g WHERE id % 10 = 0 GROUP BY i"
_SCORE = f"WITH g AS ({_G}), t AS ({_TARGET}), v AS (SELECT id, round(sum(g * m::DOUBLE) / sqrt(sum(g * g)::DOUBLE) / (SELECT sqrt(sum(m::DOUBLE * m)) FROM t), 6) AS v FROM g JOIN t USING (i) GROUP BY id)"


def _grads(spark: SparkSession, d: str) -> DataFrame:
    return influence.precomputed(table(spark, d, "embeddings"), "vec_id", "embedding")


def _premium(g: DataFrame) -> DataFrame:
    return g.filter("id % 10 = 0")


@query("grad_target_mean", f"WITH g AS ({_G}) SELECT i::INT AS i, m FROM ({_TARGET})")
def grad_target_mean(spark: SparkSession, d: str) -> DataFrame:
    return spark.createDataFrame(list(enumerate(influence.target_sum(_premium(_grads(spark, d))))), "i int, m long")


@query("influence_full", _SCORE + " SELECT id, v FROM v")
def influence_full(spark: SparkSession, d: str) -> DataFrame:
    g = _grads(spark, d)
    return influence.score(g, influence.target_sum(_premium(g))).select("id", "v")


@query("influence_top_n", _SCORE + " SELECT id, v FROM v ORDER BY v DESC, id LIMIT 50")
def influence_top_n(spark: SparkSession, d: str) -> DataFrame:
    g = _grads(spark, d)
    return selection.top_n(influence.score(g, influence.target_sum(_premium(g))), "v_fp", 50).select("id", "v")


@query("influence_dot", f"WITH g AS ({_G}), t AS ({_TARGET}) SELECT id, round(sum(g * m::DOUBLE) / 1000000 / 1000000, 6) AS v FROM g JOIN t USING (i) GROUP BY id")
def influence_dot(spark: SparkSession, d: str) -> DataFrame:
    g = _grads(spark, d)
    return influence.score(g, influence.target_sum(_premium(g)), "dot").select("id", "v")


_SIGN = f"SELECT i, j, 1 - 2 * ({h('proj', 'i', 'j')} % 2) AS s FROM (SELECT unnest(range(64)) AS i), (SELECT unnest(range(32)) AS j)"


@query("influence_projected", f"WITH g0 AS ({_G}), r AS ({_SIGN}), g AS (SELECT id, j AS i, sum(g * s)::BIGINT AS g FROM g0 JOIN r USING (i) GROUP BY 1, 2), t AS ({_TARGET}) SELECT id, round(sum(g * m::DOUBLE) / sqrt(sum(g::DOUBLE * g)) / (SELECT sqrt(sum(m::DOUBLE * m)) FROM t), 6) AS v FROM g JOIN t USING (i) GROUP BY id")
def influence_projected(spark: SparkSession, d: str) -> DataFrame:
    g = influence.project(_grads(spark, d), 64, 32)
    return influence.score(g, influence.target_sum(_premium(g))).select("id", "v")


@query("influence_pairwise_topk", f"WITH g AS ({_G}), n AS (SELECT id, sqrt(sum(g::DOUBLE * g)) AS n FROM g GROUP BY id), p AS (SELECT t.id AS test_id, a.id AS id, round(sum(a.g::DOUBLE * t.g) / max(x.n) / max(y.n), 6) AS v FROM g a JOIN g t ON a.i = t.i AND t.id < 10 JOIN n x ON x.id = a.id JOIN n y ON y.id = t.id GROUP BY 1, 2) SELECT test_id, id, v, row_number() OVER (PARTITION BY test_id ORDER BY v DESC, id)::INT AS rank FROM p QUALIFY rank <= 5")
def influence_pairwise_topk(spark: SparkSession, d: str) -> DataFrame:
    g = _grads(spark, d)
    return influence.pairwise(g, g.filter("id < 10"), 5)


@query("influence_pairwise_searches", f"WITH g AS ({_G}), n AS (SELECT id, sqrt(sum(g::DOUBLE * g)) AS n FROM g GROUP BY id), p AS (SELECT t.id AS test_id, a.id AS id, round(sum(a.g::DOUBLE * t.g) / max(x.n) / max(y.n), 6) AS v FROM g a JOIN g t ON a.i = t.i AND t.id % 20 = 0 JOIN n x ON x.id = a.id JOIN n y ON y.id = t.id GROUP BY 1, 2) SELECT test_id, id, v, row_number() OVER (PARTITION BY test_id ORDER BY v DESC, id)::INT AS rank FROM p QUALIFY rank <= 5")
def influence_pairwise_searches(spark: SparkSession, d: str) -> DataFrame:
    """Every row whose id is divisible by 20 searched against all rows."""
    g = _grads(spark, d)
    return influence.pairwise(g, g.filter("id % 20 = 0"), 5)


@query("influence_by_category", f"WITH g AS ({_G}), t AS (SELECT label AS c, i, sum(g)::BIGINT AS m FROM g WHERE id % 10 = 0 GROUP BY 1, 2), n AS (SELECT c, sqrt(sum(m::DOUBLE * m)) AS n FROM t GROUP BY c), v AS (SELECT id, c, round(sum(g * m::DOUBLE) / sqrt(sum(g::DOUBLE * g)) / max(n), 6) AS v FROM g JOIN t USING (i) JOIN n USING (c) GROUP BY 1, 2) SELECT id, c::INT AS best, v FROM v QUALIFY row_number() OVER (PARTITION BY id ORDER BY v DESC, c) = 1")
def influence_by_category(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "embeddings")
    g = _grads(spark, d)
    lab = e.select(F.col("vec_id").alias("id"), "label").filter("id % 10 = 0")
    rows = _premium(g).join(lab, "id").select("label", F.posexplode("g").alias("i", "x")).groupBy("label", "i").agg(F.sum("x").alias("m")).collect()
    targets: dict[int, list[int]] = {}
    for r in sorted(rows, key=lambda r: (r["label"], r["i"])):
        targets.setdefault(r["label"], []).append(r["m"])
    return influence.score_by_category(g, targets)


_UNI = f"""WITH t AS (SELECT doc_id AS id, ({h("uni", "t")} % 64)::INT AS i FROM (SELECT doc_id, unnest({w("text")}) AS t FROM documents)), n AS (SELECT id, i, count(*) AS c FROM t GROUP BY 1, 2), z AS (SELECT id, sum(c)::BIGINT AS n FROM n GROUP BY 1),
 b AS (SELECT i, (sum(c)::BIGINT * 1000000) // (SELECT sum(c)::BIGINT FROM n) AS base FROM n GROUP BY i), g AS (SELECT z.id, b.i, b.base - (coalesce(n.c, 0) * 1000000) // z.n AS g FROM z CROSS JOIN b LEFT JOIN n ON n.id = z.id AND n.i = b.i)"""


@query("grad_unigram_influence", _UNI + f", t2 AS (SELECT i, sum(g)::BIGINT AS m FROM g JOIN labels ON doc_id = id WHERE quality = 1 AND id % 4 = 0 GROUP BY i) SELECT id, round(sum(g * m::DOUBLE) / sqrt(sum(g::DOUBLE * g)) / (SELECT sqrt(sum(m::DOUBLE * m)) FROM t2), 6) AS v FROM g JOIN t2 USING (i) GROUP BY id")
def grad_unigram_influence(spark: SparkSession, d: str) -> DataFrame:
    g = land(reference.nested(reference.unigram_gradients(table(spark, d, "documents"), "doc_id", "text")))
    good = table(spark, d, "labels").filter("quality = 1 and doc_id % 4 = 0").select(F.col("doc_id").alias("id"))
    v = influence.score(g, influence.target_sum(g.join(good, "id", "left_semi")))
    return v.select("id", "v")


@query("grad_text_logistic", f"WITH t AS (SELECT doc_id AS id, quality AS y, ({h('log', 't')} % 64)::INT AS i FROM (SELECT doc_id, quality, unnest({w('text')}) AS t FROM documents JOIN labels USING (doc_id))), n AS (SELECT id, y, i, count(*) AS c FROM t GROUP BY 1, 2, 3), z AS (SELECT id, sum(c)::BIGINT AS n FROM n GROUP BY 1) SELECT id, i, (1 - 2 * y) * ((c * 1000000) // n) AS g FROM n JOIN z USING (id)")
def grad_text_logistic(spark: SparkSession, d: str) -> DataFrame:
    return reference.logistic_gradients(table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id"), "doc_id", "text", "quality")


@query("grad_lowrank_influence")
def grad_lowrank_influence(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "embeddings")
    model = reference.LowRankSoftmax.start(64, 10).fit(e.filter("vec_id % 10 = 0"), "embedding", "label", epochs=3)
    g = model.per_sample(e, "vec_id", "embedding", "label", influence.signs("proj", model.a.size + model.b.size, 64))
    return influence.score(g, influence.target_sum(_premium(g))).select("id", "v")


@query("grad_bigram_lowrank")
def grad_bigram_lowrank(spark: SparkSession, d: str) -> DataFrame:
    """Whole documents by the low-rank bigram model: base of all texts, adapters trained on good documents of even sources."""
    docs = table(spark, d, "documents")
    good = table(spark, d, "labels").filter("quality = 1").select("doc_id")
    good = docs.filter("cast(substring(source, 4) as int) % 2 = 0").join(good, "doc_id", "left_semi").select(F.col("doc_id").alias("id"))
    pairs = land(reference.pair_codes(docs, "doc_id", "text", 64))
    own = pairs.join(good, "id", "left_semi")
    model = reference.LowRankBigram.start(reference.pair_counts(pairs, 64)).fit(reference.pair_counts(own, 64))
    g = land(model.per_sample(pairs, influence.fast_signs(3, 0, model.width, 64).astype(np.int64)))
    return influence.score(g, influence.target_sum(g.join(good, "id", "left_semi"))).select("id", "v")


# ---------------------------------------------------------------- perplexity and selections

_UPPL = f"""WITH t AS (SELECT doc_id AS id, unnest({w("text")}) AS t FROM documents), c AS (SELECT t, count(*) AS c FROM t GROUP BY t), k AS (SELECT sum(c) AS n, count(*) AS v FROM c),
 p AS (SELECT id, count(*) AS n_tok, round(exp(sum(round(ln((c + 1.0) / (k.n + k.v + 1)) * -1000000)::BIGINT) / 1000000.0 / count(*)), 4) AS ppl FROM t JOIN c USING (t), k GROUP BY id)"""


@query("lm_unigram_ppl", _UPPL + " SELECT id, n_tok, ppl FROM p")
def lm_unigram_ppl(spark: SparkSession, d: str) -> DataFrame:
    return lm.self_perplexity(table(spark, d, "documents"), "doc_id", "text")


@query(
    "lm_bigram_ppl",
    f"""WITH d AS (SELECT doc_id AS id, {w("text")} AS t FROM documents), b AS (SELECT id, unnest(t) AS w, unnest(list_prepend('<s>', t[:-2])) AS u FROM d WHERE len(t) > 0), c AS (SELECT u, w, count(*) AS c FROM b GROUP BY 1, 2), cu AS (SELECT u, count(*) AS cu FROM b GROUP BY 1), k AS (SELECT count(DISTINCT w) AS v FROM b)
 SELECT id, count(*) AS n_tok, round(exp(sum(round(ln((c + 1.0) / (cu + k.v + 1)) * -1000000)::BIGINT) / 1000000.0 / count(*)), 4) AS ppl FROM b JOIN c USING (u, w) JOIN cu USING (u), k GROUP BY id""",
)
def lm_bigram_ppl(spark: SparkSession, d: str) -> DataFrame:
    return lm.self_perplexity(table(spark, d, "documents"), "doc_id", "text", 2)


@query("select_low_ppl", _UPPL + " SELECT id, ppl FROM p ORDER BY ppl, id LIMIT 100")
def select_low_ppl(spark: SparkSession, d: str) -> DataFrame:
    return selection.top_n(lm_unigram_ppl(spark, d), "ppl", 100, ascending=True).select("id", "ppl")


@query("select_high_ppl", _UPPL + " SELECT id, ppl FROM p ORDER BY ppl DESC, id LIMIT 100")
def select_high_ppl(spark: SparkSession, d: str) -> DataFrame:
    return selection.top_n(lm_unigram_ppl(spark, d), "ppl", 100).select("id", "ppl")


@query("select_random", f"SELECT doc_id AS id FROM documents ORDER BY {h('rand', 'doc_id')}, doc_id LIMIT 100")
def select_random(spark: SparkSession, d: str) -> DataFrame:
    return selection.random_n(table(spark, d, "documents").select(F.col("doc_id").alias("id")), 100)


@query("select_overlap", _UPPL + f", a AS (SELECT id FROM p ORDER BY ppl, id LIMIT 100), b AS (SELECT doc_id AS id FROM documents ORDER BY {h('rand', 'doc_id')}, doc_id LIMIT 100), s AS (SELECT count(*) AS k FROM a JOIN b USING (id)) SELECT 100::BIGINT AS n_a, 100::BIGINT AS n_b, k AS shared, round(k / (200 - k), 6) AS jaccard FROM s")
def select_overlap(spark: SparkSession, d: str) -> DataFrame:
    return selection.overlap(select_low_ppl(spark, d), select_random(spark, d))


@query("select_top_n_large", "SELECT l_orderkey, l_linenumber, l_partkey, score FROM (SELECT *, round(l_extendedprice * 100)::BIGINT AS score FROM lineitem) ORDER BY score DESC, l_orderkey * 10 + l_linenumber LIMIT 20000")
def select_top_n_large(spark: SparkSession, d: str) -> DataFrame:
    li = table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.round(F.col("l_extendedprice") * 100).cast("long").alias("score"), (F.col("l_orderkey") * 10 + F.col("l_linenumber")).alias("id"))
    return selection.top_n(li, "score", 20_000).drop("id")


@query("select_ppl_counted", _UPPL + " SELECT id, ppl FROM p ORDER BY ppl, id LIMIT 300")
def select_ppl_counted(spark: SparkSession, d: str) -> DataFrame:
    """Lowest perplexity by counting, on reals."""
    return selection.top_n(lm_unigram_ppl(spark, d), "ppl", 300, ascending=True, small=0).select("id", "ppl")


@query("select_orders_counted", "SELECT o_orderkey, o_custkey FROM orders ORDER BY o_custkey % 5 DESC, o_orderkey LIMIT 700")
def select_orders_counted(spark: SparkSession, d: str) -> DataFrame:
    """Five values only, so the cut falls among ties, which are cut by id the same way."""
    o = table(spark, d, "orders").select("o_orderkey", "o_custkey", (F.col("o_custkey") % 5).alias("mark"))
    return selection.top_n(o, "mark", 700, "o_orderkey", small=50).select("o_orderkey", "o_custkey")


_RANKS = "row_number() OVER (ORDER BY {0} DESC, id)"


@query("select_rank_correlation", _UPPL + ", u AS (SELECT id, ppl, n_tok, " + _RANKS.format("ppl") + " AS a, " + _RANKS.format("n_tok") + " AS b FROM p) SELECT count(*) AS n, round(1 - 6 * sum((a - b) * (a - b))::DOUBLE / (count(*) * (count(*) * count(*) - 1)::DOUBLE), 6) AS spearman FROM u")
def select_rank_correlation(spark: SparkSession, d: str) -> DataFrame:
    """Spearman's correlation of two orders: by perplexity and by length."""
    p = land(lm_unigram_ppl(spark, d))
    return selection.rank_correlation(p.select("id", "ppl"), p.select("id", F.col("n_tok").cast("double").alias("ppl")), "ppl")


# ---------------------------------------------------------------- evaluation

_OUT = "SELECT event_type AS model, user_id AS item_id, count(*) AS n, count(*) FILTER (value >= 50) AS c FROM events GROUP BY 1, 2"


def _outcomes(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "events").groupBy(F.col("event_type").alias("model"), F.col("user_id").alias("item_id")).agg(F.count(F.lit(1)).alias("n"), F.count(F.when(F.col("value") >= 50, 1)).alias("c"))


@query("eval_pass_at_1", f"SELECT model, round(100 * avg(c / n), 4) AS pass_at_k FROM ({_OUT}) GROUP BY 1")
def eval_pass_at_1(spark: SparkSession, d: str) -> DataFrame:
    return evaluate.by_model(_outcomes(spark, d))


@query("eval_pass_at_k", f"SELECT model, round(100 * avg(CASE WHEN n < 3 THEN NULL WHEN n - c < 3 THEN 1.0 ELSE 1 - (n - c) * 1.0 / n * (n - c - 1) / (n - 1) * (n - c - 2) / (n - 2) END), 4) AS pass_at_k FROM ({_OUT}) GROUP BY 1")
def eval_pass_at_k(spark: SparkSession, d: str) -> DataFrame:
    return evaluate.by_model(_outcomes(spark, d), 3)


@query("eval_split_rollup", f"SELECT model, CASE WHEN item_id % 2 = 0 THEN 'full' ELSE 'easy' END AS split, round(100 * avg(c / n), 4) AS pass_at_1, count(*) AS items FROM ({_OUT}) GROUP BY ROLLUP (1, 2)")
def eval_split_rollup(spark: SparkSession, d: str) -> DataFrame:
    return evaluate.by_split(_outcomes(spark, d).withColumn("split", F.when(F.col("item_id") % 2 == 0, "full").otherwise("easy")), ["split"])


#: The outcome log as tables of models: the mean value of each (synth, step, column), in whole hundredths so that none is a tie.
_LOG = "(sum(round(value * 100)::BIGINT)::BIGINT // count(*))::DOUBLE / 100"
_COLUMN4 = f"CASE user_id % 4 {' '.join(f"WHEN {k} THEN '{c}'" for k, c in enumerate(evaluate.COLUMNS))} END"


def _grid4(steps: tuple[str, ...]) -> str:
    step = f"CASE event_id % 4 {' '.join(f"WHEN {k} THEN '{x}'" for k, x in enumerate(steps))} END"
    return f'WITH l AS (SELECT event_type AS synth, {step} AS step, {_COLUMN4} AS "column", {_LOG} AS value FROM events GROUP BY 1, 2, 3)'


def _named(key: str, names: tuple[str, ...]):
    """A name for each residue of a key."""
    return F.array(*[F.lit(x) for x in names])[(F.col(key) % len(names)).cast("int")]


def _means(df: DataFrame, *keys) -> DataFrame:
    """Mean value by keys, in whole hundredths."""
    return df.groupBy(*keys).agg(F.expr("cast(sum(cast(round(value * 100) AS bigint)) div count(1) AS double) / 100").alias("value"))


def _steps(spark: SparkSession, d: str, steps: tuple[str, ...]) -> DataFrame:
    return _means(table(spark, d, "events"), F.col("event_type").alias("synth"), _named("event_id", steps).alias("step"), _named("user_id", evaluate.COLUMNS).alias("column"))


STEPS = ("original", "enhanced", "round1", "round2")
PARTS = ("full", "multi_ckpt", "scoring", "influence")


@query("eval_relative_change", _grid4(STEPS) + ' SELECT l.synth, l.step, l."column", l.value, round(100 * (l.value - b.value) / b.value, 2) AS change FROM l JOIN l b ON b.synth = l.synth AND b."column" = l."column" AND b.step = \'enhanced\'')
def eval_relative_change(spark: SparkSession, d: str) -> DataFrame:
    return evaluate.against(_steps(spark, d, STEPS), ["synth", "column"], "step", "enhanced").select("synth", "step", "column", "value", "change")


_ABL4 = _grid4(PARTS)


@query("eval_ablation_drop", _ABL4 + ' SELECT l.synth, l.step, l."column", l.value, round(100 * (l.value - b.value) / b.value, 2) AS change FROM l JOIN l b ON b.synth = l.synth AND b."column" = l."column" AND b.step = \'full\'')
def eval_ablation_drop(spark: SparkSession, d: str) -> DataFrame:
    return evaluate.against(_steps(spark, d, PARTS), ["synth", "column"], "step", "full").select("synth", "step", "column", "value", "change")


KINDS = ("open", "own", "base")
_TARGET_MODEL = "purchase-own"
_WIDE_COLUMN = f"CASE user_id % 10 {' '.join(f"WHEN {k} THEN '{c}'" for k, c in enumerate(evaluate.WIDE))} END"
_KIND = f"CASE event_id % 3 {' '.join(f"WHEN {k} THEN '{c}'" for k, c in enumerate(KINDS))} END"
_MODELS10 = f"WITH l AS (SELECT event_type || '-' || {_KIND} AS model, {_KIND} AS kind, {_WIDE_COLUMN} AS \"column\", {_LOG} AS value FROM events GROUP BY 1, 2, 3)"
#: The others that a target of ours is compared with are the open ones.
_RIVALS = _MODELS10 + f", r AS (SELECT * FROM l WHERE kind = 'open' OR model = '{_TARGET_MODEL}')"


def _models(spark: SparkSession, d: str, kinds: str = "kind is not null") -> DataFrame:
    kind = _named("event_id", KINDS)
    g = _means(table(spark, d, "events"), F.concat_ws("-", "event_type", kind).alias("model"), kind.alias("kind"), _named("user_id", evaluate.WIDE).alias("column"))
    return g.select("model", "kind", "column", "value").filter(kinds)


@query("eval_model_comparison", _MODELS10 + ' SELECT model, kind, "column", value FROM l')
def eval_model_comparison(spark: SparkSession, d: str) -> DataFrame:
    return _models(spark, d)


@query("eval_vs_best", _RIVALS + " , o AS (SELECT \"column\", max(value) AS best_other FROM r WHERE model <> '" + _TARGET_MODEL + "' GROUP BY 1) SELECT r.\"column\", value AS own, best_other, round(100 * (value - best_other) / best_other, 2) AS change FROM r JOIN o ON o.\"column\" = r.\"column\" WHERE model = '" + _TARGET_MODEL + "'")
def eval_vs_best(spark: SparkSession, d: str) -> DataFrame:
    return evaluate.vs_best(_models(spark, d, f"kind = 'open' or model = '{_TARGET_MODEL}'"), _TARGET_MODEL)


_BENCH = {"lcb": ["lcb_full", "lcb_easy"], "bcb": ["bcb_c_full", "bcb_c_hard", "bcb_i_full", "bcb_i_hard"]}


@query("eval_vs_best_mean", _RIVALS + """, m AS (SELECT split_part("column", '_', 1) AS benchmark, model, avg(value) AS m FROM r GROUP BY 1, 2), o AS (SELECT "column", max(value) AS best FROM r WHERE model <> '""" + _TARGET_MODEL + """' GROUP BY 1),
 c AS (SELECT split_part(r."column", '_', 1) AS benchmark, round(avg(100 * (value - best) / best), 2) AS by_column FROM r JOIN o ON o."column" = r."column" WHERE model = '""" + _TARGET_MODEL + """' GROUP BY 1), b AS (SELECT * FROM m WHERE model <> '""" + _TARGET_MODEL + """' QUALIFY row_number() OVER (PARTITION BY benchmark ORDER BY m DESC, model DESC) = 1)
 SELECT c.benchmark, by_column, round(100 * (m.m - b.m) / b.m, 2) AS by_mean, b.model AS mean_of FROM c JOIN m ON m.benchmark = c.benchmark AND m.model = '""" + _TARGET_MODEL + """' JOIN b ON b.benchmark = c.benchmark WHERE c.benchmark IN ('lcb', 'bcb')""")
def eval_vs_best_mean(spark: SparkSession, d: str) -> DataFrame:
    """The gain over the best open model, by each column's best and by the best mean."""
    return evaluate.vs_best_mean(_models(spark, d, f"kind = 'open' or model = '{_TARGET_MODEL}'"), _TARGET_MODEL, _BENCH)


@query("eval_mark_ranks", _MODELS10 + ' SELECT model, "column", value, dense_rank() OVER (PARTITION BY "column" ORDER BY value DESC)::INT AS rank FROM l WHERE kind IN (\'open\', \'own\') QUALIFY rank <= 2')
def eval_mark_ranks(spark: SparkSession, d: str) -> DataFrame:
    return evaluate.mark_ranks(_models(spark, d, "kind in ('open', 'own')")).select("model", "column", "value", "rank")


@query("eval_ablation_ranks", _ABL4 + ' SELECT synth, step, "column", value, dense_rank() OVER (PARTITION BY synth, "column" ORDER BY value DESC)::INT AS rank FROM l QUALIFY rank <= 2')
def eval_ablation_ranks(spark: SparkSession, d: str) -> DataFrame:
    g = _steps(spark, d, PARTS)
    return evaluate.mark_ranks(g, ["synth", "column"]).select("synth", "step", "column", "value", "rank")


@query("cost_data_sizes", "SELECT step, n AS samples, sum(n) OVER (ORDER BY n)::BIGINT AS so_far FROM (SELECT event_type AS step, count(*) FILTER (value >= 50) AS n FROM events GROUP BY 1)")
def cost_data_sizes(spark: SparkSession, d: str) -> DataFrame:
    """Samples of each step that passed, and all of smaller steps with them."""
    from pyspark.sql import Window

    n = table(spark, d, "events").groupBy(F.col("event_type").alias("step")).agg(F.count(F.when(F.col("value") >= 50, 1)).alias("samples"))
    return n.withColumn("so_far", F.sum("samples").over(Window.orderBy("samples")))


@query("cost_recipe_cube", "SELECT lang AS model, source AS origin, sum(CASE WHEN quality IS NULL THEN n_chars ELSE 0 END)::BIGINT AS common_chars, sum(CASE WHEN quality IS NULL THEN 0 ELSE n_chars END)::BIGINT AS specific_chars FROM documents LEFT JOIN labels USING (doc_id) GROUP BY CUBE (lang, source)")
def cost_recipe_cube(spark: SparkSession, d: str) -> DataFrame:
    """Characters of common (unlabelled) and specific (labelled) texts of each recipe, a language and a source."""
    docs = table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id", "left")
    part = lambda none: F.sum(F.when(F.col("quality").isNull() == F.lit(none), F.col("n_chars")).otherwise(0))
    return docs.cube(F.col("lang").alias("model"), F.col("source").alias("origin")).agg(part(True).alias("common_chars"), part(False).alias("specific_chars"))


_QA = _marked(_CONV, "snippet_id, draw", "s", False)


@query("quality_compare", _QA + ", s AS (SELECT * FROM x ORDER BY " + h("judge", "snippet_id * 100 + draw") + ", snippet_id * 100 + draw LIMIT 100) SELECT aspect, round(sum(v) / count(v), 6) AS mean FROM (FROM s UNPIVOT (v FOR aspect IN (" + _X + "))) GROUP BY 1")
def quality_compare(spark: SparkSession, d: str) -> DataFrame:
    """Marks of a sample of conversation pairs."""
    a = candidates.from_conversations(table(spark, d, "conversations")).withColumn("id", F.col("snippet_id") * 100 + F.col("draw"))
    return evaluate.compare_quality({"a": a}, {"rule": scoring.rule_marks}, scoring.MARKS).select("aspect", "mean")


@query("eval_label_proxy")
def eval_label_proxy(spark: SparkSession, d: str) -> DataFrame:
    """Trained on the even sources, measured on the odd ones."""
    m = land(_labelled_marks(spark, d).select("snippet_id", "source", *RM, F.col("quality").cast("double").alias("y")))
    odd = "cast(substring(source, 4) as int) % 2 = 1"
    return evaluate.label_proxy(m.filter(f"not ({odd})"), m.filter(odd), RM, "y")


@query("synth_prior_prompts", "SELECT doc_id, md5('Take this text as a start and write a problem with its solution: ' || text) AS digest FROM documents")
def synth_prior_prompts(spark: SparkSession, d: str) -> DataFrame:
    return synth.prompts(table(spark, d, "documents"), "snippet", "text").select("doc_id", F.md5(F.col("prompt").cast("binary")).alias("digest"))


@query("synth_novelty", f"SELECT count(DISTINCT md5(array_to_string({w('text')}, ' '))) AS n FROM documents WHERE doc_id % 2 = 1 AND md5(array_to_string({w('text')}, ' ')) NOT IN (SELECT md5(array_to_string({w('text')}, ' ')) FROM documents WHERE doc_id % 2 = 0)")
def synth_novelty(spark: SparkSession, d: str) -> DataFrame:
    docs = table(spark, d, "documents")
    return synth.novel(docs.filter("doc_id % 2 = 1"), docs.filter("doc_id % 2 = 0"), "text").agg(F.count(F.lit(1)).alias("n"))
