"""The snippet pool: cleaning steps from raw documents and pages to snippets, with a report of each gate."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import bound, hash_unit, normalise, shingles, texts, words
from ..sources import MOST_SENT, join_spread, land
from .scoring import SECRET, punctuation, secrets_in, sent_runs, shared_runs, without_punctuation


@dataclass(frozen=True)
class PoolConfig:
    least_chars: int = 100
    most_chars: int = 20_000
    #: In hundredths.
    most_punctuation: int = 12
    least_distinct_words: int = 20
    most_repeated_lines: int = 50
    gram: int = 8
    #: Whole hundredths of likeness from which near duplicates go, the smallest id of a cluster staying; None: they stay.
    near: int | None = None


def page_text(pages: DataFrame) -> DataFrame:
    """(page_id, text): scripts, styles, comments and tags go; the commonest entities become characters."""
    t = F.regexp_replace("html", "<script[^>]*>[^<]*</script>|<style[^>]*>[^<]*</style>|<!--[^>]*-->", " ")
    t = F.regexp_replace(t, "<[^>]*>", " ")
    for entity, c in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&amp;", "&")):
        t = F.replace(t, F.lit(entity), F.lit(c))
    return pages.select("page_id", F.trim(F.regexp_replace(t, "[ \n\t\r]+", " ")).alias("text"))


def noise(df: DataFrame) -> DataFrame:
    """Add punctuation, distinct-word and repeated-line shares in whole hundredths."""
    w, lines = words("text"), F.split("text", "\n")
    pct = lambda a, b: F.floor(100 * a / F.greatest(F.lit(1), b)).cast("int")
    return df.withColumns({"punct_pct": pct(punctuation(F.col("text")), F.length("text")), "distinct_pct": pct(F.size(F.array_distinct(w)), F.size(w)), "repeat_pct": (100 - pct(F.size(F.array_distinct(lines)), F.size(lines))).cast("int")})


def is_noisy(cfg: PoolConfig = PoolConfig()) -> Column:
    return (F.col("punct_pct") > cfg.most_punctuation) | (F.col("distinct_pct") < cfg.least_distinct_words) | (F.col("repeat_pct") > cfg.most_repeated_lines)


def length_gate(df: DataFrame, lo: int, hi: int) -> DataFrame:
    """Pushed down to the scan."""
    return df.filter((F.col("n_chars") >= lo) & (F.col("n_chars") <= hi))


def sensitive_hits(df: DataFrame) -> DataFrame:
    return df.withColumn("n_sensitive", F.regexp_count("text", F.lit(SECRET)).cast("int"))


#: Words of license notices; a screen, the corpus operators tell which license.
LICENSE = r"licensed under|all rights reserved|copyright [(]c[)]|released under the|permission is hereby granted"


def license_hits(df: DataFrame) -> DataFrame:
    return df.withColumn("n_license", F.regexp_count(F.lower("text"), F.lit(LICENSE)).cast("int"))


def sensitive(df: DataFrame, mode: str = "drop") -> DataFrame:
    if mode == "drop":
        return sensitive_hits(df).filter("n_sensitive = 0").drop("n_sensitive")
    return df.withColumn("text", F.regexp_replace("text", SECRET, "[masked]"))


def exact_first(df: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """(id, first_id): the smallest id with the same normalised text; only digests are shuffled."""
    d = df.select(F.col(id_col).alias("id"), F.md5(normalise("text").cast("binary")).alias("digest"))
    low = d.groupBy("digest").agg(F.min("id").alias("first_id"))
    return d.join(low, "digest").select("id", "first_id")


def exact_dedup(df: DataFrame, id_col: str = "doc_id") -> DataFrame:
    keep = exact_first(df, id_col).filter("id = first_id").select(F.col("id").alias(id_col))
    return df.join(keep, id_col, "left_semi")


def benchmark_grams(bench: DataFrame, n: int = 8) -> DataFrame:
    return bench.select(words("text").alias("_t")).select(F.explode(shingles(F.col("_t"), n)).alias("gram")).distinct()


def contaminated(df: DataFrame, bench: DataFrame, id_col: str = "doc_id", n: int = 8) -> DataFrame:
    """(id, n_hits): documents that share runs of n words with the benchmark; its runs are sent to the tasks if few enough."""
    runs = land(benchmark_grams(bench, n))
    hits = shared_runs("_t", runs, n)
    if hits is not None:
        return df.select(F.col(id_col).alias("id"), words("text").alias("_t")).select("id", hits.cast("long").alias("n_hits")).filter("n_hits > 0")
    g = df.select(F.col(id_col).alias("id"), words("text").alias("_t")).select("id", F.explode(shingles(F.col("_t"), n)).alias("gram"))
    return g.join(runs, "gram", "left_semi").groupBy("id").agg(F.count(F.lit(1)).alias("n_hits"))


def _keyed(docs: DataFrame) -> DataFrame:
    """(doc_id, _key): digest of the normalised text, null for null."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = zip(b.column("text").to_pylist(), b.column("_low").to_pylist())
            keys = [None if t is None else hashlib.md5(" ".join(texts.split(t, low)).encode()).hexdigest() for t, low in rows]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(keys, pa.string())], names=["doc_id", "_key"])

    d = docs.select("doc_id", "text", texts.lowered("text").alias("_low"))
    return d.mapInArrow(run, T.StructType([docs.schema["doc_id"], T.StructField("_key", T.StringType())]))


def _told(docs: DataFrame, sent, n: int) -> DataFrame:
    """docs with the columns of noise() and sensitive_hits(), `_key` and `_hit` (1 if the text shares a run with the
    benchmark; null without sent runs), told in one pass over each text."""
    names = ["punct_pct", "distinct_pct", "repeat_pct", "n_sensitive", "_hit"]
    own = docs.columns
    pct = lambda a, b: 100 * a // max(1, b)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = None if sent is None else texts.Runs(sent.value, n)
        for b in batches:
            told, keys = [], []
            for t, low in zip(b.column("text").to_pylist(), b.column("_low").to_pylist()):
                if t is None:
                    told.append((None,) * 5)
                    keys.append(None)
                    continue
                w, lines, raw = texts.split(t, low), t.split("\n"), t.encode()
                hit = 1 if known is not None and known.found(w) else None
                told.append((pct(len(raw) - len(without_punctuation(raw)), len(t)), pct(len(set(w)), len(w)), 100 - pct(len(set(lines)), len(lines)), secrets_in(t, raw), hit))
                keys.append(hashlib.md5(" ".join(w).encode()).hexdigest())
            cols = [pa.array(c, pa.int32()) for c in zip(*told)] or [pa.array([], pa.int32())] * 5
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in own), *cols, pa.array(keys, pa.string())], names=[*own, *names, "_key"])

    kinds = [T.StructField(c, T.IntegerType()) for c in names] + [T.StructField("_key", T.StringType())]
    return docs.withColumn("_low", texts.lowered("text")).mapInArrow(run, T.StructType([*docs.schema.fields, *kinds]))


def gates(docs: DataFrame, bench: DataFrame, cfg: PoolConfig = PoolConfig()) -> DataFrame:
    """docs with `reason`: the first gate that drops the row, or null.

    Texts are read twice (for the digests of copies, then for the gates) and neither landed nor shuffled, unless more than
    MOST_SENT texts have copies.
    """
    sent = sent_runs(land(benchmark_grams(bench, cfg.gram)))
    low = _keyed(docs).groupBy("_key").agg(F.min("doc_id").alias("_low"), F.count(F.lit(1)).alias("_rows"))
    many = land(low.filter("_rows > 1").select("_key", "_low", "_rows"))  # one row for each text that has copies
    if isinstance(sent, DataFrame):
        hit = contaminated(docs, bench, n=cfg.gram).select(F.col("id").alias("doc_id"), F.lit(1).alias("_hit"))
        d = _told(docs, None, cfg.gram).drop("_hit").join(hit, "doc_id", "left")
    else:
        d = _told(docs, sent, cfg.gram)
    if many.count() <= MOST_SENT:
        d = d.join(F.broadcast(many), "_key", "left")
    else:
        d = join_spread(land(d), many, ["_key"], "_rows", docs.count())
    d = d.withColumn("_dup", F.when(F.col("_low") < F.col("doc_id"), 1))
    reason = F.when((F.col("n_chars") < cfg.least_chars) | (F.col("n_chars") > cfg.most_chars), "length").when(is_noisy(cfg), "noise").when(F.col("n_sensitive") > 0, "sensitive").when(F.col("_dup").isNotNull(), "duplicate").when(F.col("_hit").isNotNull(), "benchmark")
    return d.withColumn("reason", reason).drop("_dup", "_hit", "_key", "_low", "_rows")


def build_pool(docs: DataFrame, bench: DataFrame, cfg: PoolConfig = PoolConfig()) -> tuple[DataFrame, DataFrame]:
    """(kept snippets, dropped rows with reason)."""
    g = gates(docs, bench, cfg)
    if cfg.near is not None:
        g = land(g)
        left = g.filter("reason is null")
        c = near_clusters(left, near_pairs(left, least=cfg.near)).filter("id <> cluster_id").select(F.col("id").alias("doc_id"), F.lit(1).alias("_near"))
        g = g.join(c, "doc_id", "left").withColumn("reason", F.when(F.col("_near").isNotNull(), "near_duplicate").otherwise(F.col("reason"))).drop("_near")
    return g.filter("reason is null").select(F.col("doc_id").alias("snippet_id"), *[c for c in docs.columns if c != "doc_id"]), g.filter("reason is not null")


def funnel(docs: DataFrame, bench: DataFrame, cfg: PoolConfig = PoolConfig()) -> DataFrame:
    """(step, dropped): one aggregation."""
    return gates(docs, bench, cfg).groupBy(F.coalesce("reason", F.lit("kept")).alias("step")).agg(F.count(F.lit(1)).alias("n"))


#: The k-th order of shingles is that of (h * 1000003 (k + 1) + 7919 k) mod this prime.
BAND_PRIME = 2_147_483_647


def near_pairs(docs: DataFrame, id_col: str = "doc_id", n: int = 5, bands: int = 8, rows: int = 2, least: int = 80) -> DataFrame:
    """(a, b, percent): texts whose sets of n-word shingles meet in a MinHash band and are `least` percent alike.

    Texts with the same shingles are one node, so copies cost nothing; a node's partners in a band are joined by the
    band's key.  percent: whole hundredths of the Jaccard likeness.  a, b: the smallest ids of their nodes, a < b.

    Only digests and signatures of all texts are shuffled; shingles, as 64-bit hashes, only of texts that have a partner
    whose number of shingles lets them be so much alike.
    """
    t = _shingled(docs, id_col, n)  # empty ones go once they are nodes: a filter here would have the shingles made twice
    hashes = F.transform("grams", lambda g: hash_unit("band", g) % BAND_PRIME)
    low = bound(hashes, lambda hs: F.array(*[F.array_min(F.transform(hs, _mixed(k))) for k in range(bands * rows)]))
    t = t.select("id", _node(), F.size("grams").alias("size"), low.alias("low"))
    t = land(t.groupBy("node").agg(F.min("id").alias("id"), F.min("size").alias("size"), F.min("low").alias("low")).filter("size > 0").drop("node"))
    keys = F.array(*[F.concat_ws("-", F.lit(b), *[F.col("low")[b * rows + r].cast("string") for r in range(rows)]) for b in range(bands)])
    bands_ = t.select("id", "size", F.explode(keys).alias("key"))
    meet = bands_.select(F.col("id").alias("a"), F.col("size").alias("m"), "key").join(bands_.select(F.col("id").alias("b"), F.col("size").alias("n"), "key"), "key")
    meet = land(meet.filter("a < b").filter(100 * F.least("m", "n").cast("long") >= least * F.greatest("m", "n").cast("long")).select("a", "b").distinct())
    paired = meet.select(F.col("a").alias("id")).union(meet.select(F.col("b").alias("id"))).distinct()
    g = land(_shingled(docs.join(paired.withColumnRenamed("id", id_col), id_col, "left_semi"), id_col, n).select("id", F.transform("grams", lambda x: F.xxhash64(x)).alias("grams")))
    both = meet.join(g.select(F.col("id").alias("a"), F.col("grams").alias("_x")), "a").join(g.select(F.col("id").alias("b"), F.col("grams").alias("_y")), "b")
    same = F.size(F.array_intersect("_x", "_y"))
    return both.withColumn("percent", F.floor(100 * same / (F.size("_x") + F.size("_y") - same)).cast("int")).filter(F.col("percent") >= least).select("a", "b", "percent")


def _shingled(docs: DataFrame, id_col: str, n: int) -> DataFrame:
    """(id, grams): the distinct runs of n words of each text, in order."""
    return docs.select(F.col(id_col).alias("id"), words("text").alias("_t")).select("id", F.array_sort(shingles(F.col("_t"), n)).alias("grams"))


def _node() -> Column:
    return F.md5(F.array_join("grams", "|").cast("binary")).alias("node")


def _mixed(k: int):
    return lambda h: (h * (1_000_003 * (k + 1)) + 7919 * k) % BAND_PRIME


def near_clusters(docs: DataFrame, pairs: DataFrame, id_col: str = "doc_id", n: int = 5) -> DataFrame:
    """(id, cluster_id): the smallest id reachable by pairs or equal shingle sets; rounds meet through files.

    Labels travel both ways along links and through their own labels (pointer jumping), so rounds grow with the
    logarithm of a chain's length.
    """
    key = F.when(F.size("grams") > 0, _node()).otherwise(F.concat(F.lit("id"), F.col("id").cast("string")))
    node = land(_shingled(docs, id_col, n).select("id", key.alias("node")))
    node = land(node.join(node.groupBy("node").agg(F.min("id").alias("own")), "node").select("id", "own"))
    label = land(node.select(F.col("own").alias("k")).distinct().withColumn("l", F.col("k")))
    pairs = land(pairs.select("a", "b"))
    links = land(pairs.union(pairs.select("b", "a")))
    while True:
        low = links.join(label.withColumnRenamed("k", "b"), "b").groupBy(F.col("a").alias("k")).agg(F.min("l").alias("m"))
        new = label.join(low, "k", "left").select("k", F.least("l", F.coalesce("m", "l")).alias("l"))
        new = land(new)
        up = new.select(F.col("k").alias("l"), F.col("l").alias("up"))
        new = land(new.join(up, "l").select("k", F.col("up").alias("l")))
        if not label.join(new.withColumnRenamed("l", "n"), "k").filter("l <> n").limit(1).count():
            break
        label = new
    return node.join(label, node.own == label.k).select("id", F.col("l").alias("cluster_id"))
