"""Candidate (q, s) pairs of each snippet from several checkpoints, and picking among them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import hash_unit, words

KEYS = ["snippet_id", "ckpt", "draw"]


def grid(snippets: DataFrame, ckpts: list[int], draws: int) -> DataFrame:
    """Every snippet with every (ckpt, draw): literals exploded in place, no join and no shuffle."""
    cells = F.explode(F.array(*[F.struct(F.lit(c).alias("ckpt"), F.lit(d).alias("draw")) for c in ckpts for d in range(draws)])) if ckpts and draws > 0 else None
    if cells is None:
        return snippets.withColumns({"ckpt": F.lit(0), "draw": F.lit(0)}).limit(0)
    return snippets.withColumn("_c", cells).withColumns({"ckpt": F.col("_c.ckpt"), "draw": F.col("_c.draw")}).drop("_c")


def passages(cells: DataFrame, q_len: int = 80, s_len: int = 240) -> DataFrame:
    """The passage synthesizer: q and s are windows of the snippet, placed by a hash of (snippet, ckpt, draw)."""

    def window(kind: str, n: int) -> Column:
        start = hash_unit(kind, "snippet_id", "ckpt", "draw") % F.greatest(F.lit(1), F.col("n_chars") - 80)
        return F.col("text").substr((start + 1).cast("int"), F.lit(n))

    return cells.withColumns({"q": window("q", q_len), "s": window("s", s_len)})


def placed(snippets: DataFrame, cells: list[tuple[int, int]], q_len: int = 80, s_len: int = 240) -> DataFrame:
    """The same windows in the snippet's row: arrays q and s, one of each (ckpt, draw) in cells."""
    at = F.array(*[F.struct(F.lit(c).alias("ckpt"), F.lit(d).alias("draw")) for c, d in cells])

    def windows(kind: str, n: int) -> Column:
        start = lambda x: hash_unit(kind, "snippet_id", x["ckpt"], x["draw"]) % F.greatest(F.lit(1), F.col("n_chars") - 80)
        return F.transform(at, lambda x: F.substring(F.col("text"), (start(x) + 1).cast("int"), F.lit(n)))

    return snippets.withColumns({"q": windows("q", q_len), "s": windows("s", s_len)})


def multi_checkpoint(snippets: DataFrame, ckpts: int = 3, draws: int = 4) -> DataFrame:
    return passages(grid(snippets, list(range(ckpts)), draws))


def last_checkpoint(snippets: DataFrame, ckpts: int = 3, total: int = 12) -> DataFrame:
    """The ablation: as many draws, all from the last checkpoint."""
    return passages(grid(snippets, [ckpts - 1], total))


def best_of_n(snippets: DataFrame, ckpt: int = 2, n: int = 4) -> DataFrame:
    return passages(grid(snippets, [ckpt], n))


def top_m(df: DataFrame, score: str, m: int = 1, by: str = "snippet_id", ties: list[str] = ["ckpt", "draw"], least: float | None = None, sound: bool = False) -> DataFrame:  # noqa: B006
    """The m best per snippet, ties by checkpoint and draw; partial limits run before the shuffle.

    sound: candidates with an empty q or s, or with q = s, are left out.
    """
    if least is not None:
        df = df.filter(F.col(score) >= least)
    if sound:
        df = df.filter("trim(coalesce(q, '')) <> '' and trim(coalesce(s, '')) <> '' and q <> s")
    w = Window.partitionBy(by).orderBy(F.desc_nulls_last(score), *ties)
    return df.withColumn("place", F.row_number().over(w)).filter(F.col("place") <= m)


def pick_best_nested(snippets: DataFrame, score, ckpts: int = 3, draws: int = 4) -> DataFrame:
    """The same winners without any shuffle: candidates stay an array of the snippet's row.

    score: a function of the candidate's struct (ckpt, draw, q, s) to a column.
    """
    cells = F.array(*[F.struct(F.lit(c).alias("ckpt"), F.lit(d).alias("draw")) for c in range(ckpts) for d in range(draws)])

    def cut(kind: str, x: Column, n: int) -> Column:
        start = hash_unit(kind, "snippet_id", x["ckpt"], x["draw"]) % F.greatest(F.lit(1), F.col("n_chars") - 80)
        return F.substring(F.col("text"), (start + 1).cast("int"), F.lit(n))

    made = F.transform(cells, lambda x: F.struct(x["ckpt"].alias("ckpt"), x["draw"].alias("draw"), cut("q", x, 80).alias("q"), cut("s", x, 240).alias("s")))
    rank = lambda x: F.struct(score(x).alias("score"), (-x["ckpt"]).alias("c"), (-x["draw"]).alias("d"))
    best = snippets.withColumn("_all", made).withColumn("_best", F.array_max(F.transform("_all", rank)))
    return best.select("snippet_id", F.col("_best.score").alias("score"), (-F.col("_best.c")).alias("ckpt"), (-F.col("_best.d")).alias("draw"))


def search_gain(df: DataFrame, score: str, last: int) -> DataFrame:
    """Per snippet: best over all checkpoints, best of the last one, gain."""
    g = df.groupBy("snippet_id").agg(F.max(score).alias("best_all"), F.max(F.when(F.col("ckpt") == last, F.col(score))).alias("best_last"))
    return g.withColumn("gain", F.col("best_all") - F.coalesce("best_last", F.lit(0)))


def diversity(df: DataFrame) -> DataFrame:
    """Per snippet: candidates, distinct solutions, distinct words over words (distinct-1)."""
    g = df.groupBy("snippet_id").agg(F.count(F.lit(1)).alias("n"), F.count_distinct(F.md5(F.col("s").cast("binary"))).alias("n_distinct"), F.sum(F.size(words("s"))).alias("n_words"), F.size(F.array_distinct(F.flatten(F.collect_list(F.array_distinct(words("s")))))).alias("n_vocab"))
    return g.select("snippet_id", "n", "n_distinct", F.round(F.col("n_vocab") / F.greatest(F.lit(1), "n_words"), 6).alias("distinct_1"))


def mean_jaccard(df: DataFrame) -> DataFrame:
    """(snippet_id, n_pairs, mean_jaccard): likeness of the word sets of all pairs of a snippet's candidates, in its own group.

    A snippet has checkpoints x draws candidates, so a group is bounded by the plan, not by the data.
    """
    sets = df.groupBy("snippet_id").agg(F.collect_list(F.array_distinct(words("s"))).alias("_t"))
    pair = lambda a, b: F.struct(F.size(F.array_intersect(a, b)).alias("both"), F.size(F.array_union(a, b)).alias("either"))
    pairs = F.flatten(F.transform("_t", lambda a, i: F.transform(F.slice("_t", i + 2, F.greatest(F.lit(0), F.size("_t") - i - 1)), lambda b: pair(a, b))))
    d = sets.select("snippet_id", F.filter(pairs, lambda p: p["either"] > 0).alias("_p"))
    each = F.aggregate("_p", F.lit(0).cast("long"), lambda s, p: s + F.floor(p["both"] * 1_000_000 / p["either"]))
    return d.select("snippet_id", F.size("_p").alias("n_pairs"), F.round(each / 1e6 / F.greatest(F.lit(1), F.size("_p")), 6).alias("mean_jaccard"))


def from_conversations(conv: DataFrame) -> DataFrame:
    """(snippet_id, draw, q, s): each user turn with the assistant turn that follows; ragged sets."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    nxt = conv.withColumns({"_r": F.lead("role").over(w), "s": F.lead("text").over(w)})
    return nxt.filter("role = 'user' and _r = 'assistant'").select(F.col("conv_id").alias("snippet_id"), F.col("turn").cast("long").alias("draw"), F.col("text").alias("q"), "s")
