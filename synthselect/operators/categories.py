"""Task categories: hashed text vectors, assignment to the nearest category, balanced seed draws."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import hash_unit, words


def hashed_embedding(df: DataFrame, id_col: str, text: str, d: int = 64, seed: str = "emb") -> DataFrame:
    """(id, i, x): signed feature hashing of words, as counts; rows of zero are left out."""
    tok = df.select(F.col(id_col).alias("id"), F.explode(words(text)).alias("w")).withColumn("h", hash_unit(seed, "w"))
    tok = tok.select("id", (F.col("h") % d).cast("int").alias("i"), (1 - 2 * (F.shiftright("h", 16) % 2)).alias("s"))
    return tok.groupBy("id", "i").agg(F.sum("s").alias("x")).filter("x <> 0")


def hashed_vectors(df: DataFrame, id_col: str, text: str, d: int = 64, seed: str = "emb") -> DataFrame:
    """(id, v array<double>): the same counts as dense vectors, zero for texts without words."""
    cells = hashed_embedding(df, id_col, text, d, seed).groupBy("id").agg(F.map_from_entries(F.collect_list(F.struct("i", F.col("x").cast("double")))).alias("_m"))
    dense = F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda i: F.coalesce(F.try_element_at("_m", i), F.lit(0.0)))
    return df.select(F.col(id_col).alias("id")).join(cells, "id", "left").select("id", F.when(F.col("_m").isNull(), F.array_repeat(F.lit(0.0), d)).otherwise(dense).alias("v"))


def from_descriptions(desc: DataFrame, id_col: str, text: str, d: int = 64, seed: str = "emb") -> list[tuple[int, list[float]]]:
    """Category vectors from a few descriptions, by the same embedding as the snippets'."""
    return [(r["id"], list(r["v"])) for r in hashed_vectors(desc, id_col, text, d, seed).orderBy("id").collect()]


def assign(df: DataFrame, id_col: str, vector: str, prototypes: list[tuple[int, list[float]]], metric: str = "cosine", least: float | None = None, m: int = 1) -> DataFrame:
    """(id, category_id, similarity, place): the m nearest of a few broadcast prototypes, ties to the lowest id.

    Below `least` the category is -1.  No shuffle.
    """
    ids = np.array([c for c, _ in prototypes])
    p = np.array([v for _, v in prototypes], np.float64)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            x = np.array(pdf["v"].tolist(), np.float64)
            if metric == "cosine":
                s = x @ p.T / np.maximum(np.linalg.norm(x, axis=1)[:, None] * np.linalg.norm(p, axis=1)[None], 1e-300)
            elif metric == "dot":
                s = x @ p.T
            else:
                s = -np.sqrt(np.maximum((x**2).sum(1)[:, None] + (p**2).sum(1)[None] - 2 * x @ p.T, 0))
            s = np.round(s, 6)
            order = np.lexsort((np.broadcast_to(ids, s.shape), -s), axis=1)[:, :m]
            for k in range(order.shape[1]):
                at = order[:, k]
                sim = s[np.arange(len(s)), at]
                cat = np.where(sim < least, -1, ids[at]) if least is not None else ids[at]
                yield pd.DataFrame({"id": pdf["id"], "category_id": cat, "similarity": sim, "place": k + 1})

    return df.select(F.col(id_col).alias("id"), F.col(vector).alias("v")).mapInPandas(run, "id long, category_id int, similarity double, place int")


def prototypes(emb: DataFrame) -> list[tuple[int, list[float]]]:
    """The vector with the lowest id of each label (a handful of rows)."""
    low = emb.groupBy("label").agg(F.min_by("embedding", "vec_id").alias("v")).orderBy("label")
    return [(r["label"], list(r["v"])) for r in low.collect()]


def centroids(emb: DataFrame, d: int) -> list[tuple[int, list[float]]]:
    """Mean vector of each label in millionths."""
    rows = emb.select("label", F.posexplode("embedding").alias("i", "x")).groupBy("label", "i").agg(F.sum(F.round(F.col("x").cast("double") * 1e6).cast("long")).alias("s")).collect()
    out: dict[int, list[float]] = {}
    for r in rows:
        out.setdefault(r["label"], [0.0] * d)[r["i"]] = float(r["s"])
    return sorted(out.items())


def stratified(df: DataFrame, category: str, quota: int | Column, id_col: str = "id", seed: str = "seed") -> DataFrame:
    """The first `quota` rows of each category in hash order; partial top-k before the shuffle."""
    w = Window.partitionBy(category).orderBy(hash_unit(seed, id_col), id_col)
    return df.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= quota)


def proportional(df: DataFrame, category: str, n: int, id_col: str = "id", seed: str = "seed") -> DataFrame:
    """n rows (up to rounding down), shares as in the pool."""
    size = df.groupBy(category).agg(F.count(F.lit(1)).alias("_size"))
    total = size.agg(F.sum("_size").alias("_all"))
    quotas = size.crossJoin(F.broadcast(total)).select(category, F.floor(F.col("_size") * n / F.col("_all")).alias("_quota"))
    return stratified(df.join(F.broadcast(quotas), category), category, F.col("_quota"), id_col, seed).drop("_quota")


def coverage(df: DataFrame, category: str) -> DataFrame:
    """(category_id, n, share) of each category, with the entropy of all shares."""
    w = Window.partitionBy()
    n = df.groupBy(F.col(category).alias("category_id")).agg(F.count(F.lit(1)).alias("n"))
    n = n.withColumn("share", F.col("n") / F.sum("n").over(w))
    return n.select("category_id", "n", F.round("share", 6).alias("share"), F.round(F.sum(-F.col("share") * F.ln("share")).over(w), 6).alias("entropy"))
