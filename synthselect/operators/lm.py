"""Add-one n-gram language models: texts are tokenised once, counts by aggregation, perplexity by joins on the counts."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import words
from ..sources import join_spread, land

START = "<s>"


@dataclass
class NGram:
    """Counts (u, w, c) of an order-1 or order-2 model; V words, N tokens."""

    order: int
    counts: DataFrame
    contexts: DataFrame | None
    vocabulary: int
    tokens: float
    alpha: float = 1.0


def counted(df: DataFrame, id_col: str, text: str, order: int = 1, weight: str | None = None) -> DataFrame:
    """Landed (id, [u,] w, n, [weight]): each document's words, or pairs with the word before, counted in place.

    The words of a text are counted in its own row, so nothing is shuffled here and a common word costs one row a
    document.  weight: a column to carry, for instance training epochs.
    """
    d = df.select(F.col(id_col).alias("id"), words(text).alias("_w"), *([F.col(weight).alias("weight")] if weight else []))
    if order == 1:
        items = F.col("_w")
    else:
        items = F.transform("_w", lambda w, i: F.struct(F.when(i == 0, F.lit(START)).otherwise(F.get(F.col("_w"), i - 1)).alias("u"), w.alias("w")))
    keep = ["weight"] if weight else []
    t = d.select("id", *keep, F.explode(items).alias("t"))
    t = t.groupBy("id", *keep, "t").agg(F.count(F.lit(1)).alias("n"))
    return land(t.select("id", *keep, *([F.col("t").alias("w")] if order == 1 else ["t.u", "t.w"]), "n"))


def fit(df: DataFrame, id_col: str, text: str, order: int = 1, alpha: float = 1.0) -> NGram:
    if order == 1:  # a word's own rows are all that is asked for, so nothing is counted by text
        t = df.select(F.explode(words(text)).alias("w")).withColumn("n", F.lit(1))
        return fit_counted(t, order, alpha)
    return fit_counted(counted(df, id_col, text, order), order, alpha)


def fit_counted(t: DataFrame, order: int = 1, alpha: float = 1.0) -> NGram:
    """t: rows of counted(); with a weight each text counts so many times."""
    n = F.col("n") * F.col("weight") if "weight" in t.columns else F.col("n")
    key = ["w"] if order == 1 else ["u", "w"]
    c = land(t.groupBy(*key).agg(F.sum(n).alias("c"), F.count(F.lit(1)).alias("rows")))
    total = c.agg(F.sum("c"), F.count_distinct("w")).first()
    contexts = None if order == 1 else c.groupBy("u").agg(F.sum("c").alias("cu"), F.sum("rows").alias("rows"))
    return NGram(order, c, contexts, total[1], total[0] or 0, alpha)


def perplexity(df: DataFrame, id_col: str, text: str, lm: NGram) -> DataFrame:
    """(id, n_tok, ppl): exp of the mean negative log-probability; null for no token."""
    return perplexity_counted(counted(df, id_col, text, lm.order), df.select(F.col(id_col).alias("id")), lm)


def perplexity_counted(t: DataFrame, ids: DataFrame, lm: NGram) -> DataFrame:
    """The same from rows of counted() and the ids of all documents.  Hot words are broadcast with their counts."""
    v1 = lm.alpha * (lm.vocabulary + 1)
    total = t.count()
    if lm.order == 1:
        p = join_spread(t, lm.counts, ["w"], "rows", total).withColumn("p", (F.coalesce("c", F.lit(0)) + lm.alpha) / F.lit(lm.tokens + v1))
    else:
        p = join_spread(t, lm.counts, ["u", "w"], "rows", total).drop("rows")
        p = join_spread(p, lm.contexts, ["u"], "rows", total)
        p = p.withColumn("p", (F.coalesce("c", F.lit(0)) + lm.alpha) / (F.coalesce("cu", F.lit(0)) + v1))
    s = p.groupBy("id").agg(F.sum("n").alias("n_tok"), F.sum(F.round(F.ln("p") * -1e6).cast("long") * F.col("n")).alias("nll"))
    return ids.join(s, "id", "left").select("id", F.coalesce("n_tok", F.lit(0)).alias("n_tok"), F.round(F.exp(F.col("nll") / 1e6 / F.col("n_tok")), 4).alias("ppl"))


def self_perplexity(df: DataFrame, id_col: str, text: str, order: int = 1) -> DataFrame:
    """Perplexity of every document under the model of all of them: one tokenisation."""
    t = counted(df, id_col, text, order)
    return perplexity_counted(t, df.select(F.col(id_col).alias("id")), fit_counted(t, order))
