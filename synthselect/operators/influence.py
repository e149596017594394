"""Gradients, random projection and influence: how much a sample's gradient points the premium set's way.

Everything works on integer vectors (millionths): exact in any engine and under any partitioning.  Scores
over big tables run in numpy over Arrow batches with the one target vector in the closure; the exploded
forms exist for means, which aggregate before they are shuffled.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import UNIT, hash_unit


def precomputed(df: DataFrame, id_col: str, vector: str) -> DataFrame:
    """(id, g array<long>) of a column of ready gradients."""
    return df.select(F.col(id_col).alias("id"), F.transform(vector, lambda x: F.round(x.cast("double") * float(UNIT)).cast("long")).alias("g"))


def signs(seed: str, rows: int, k: int) -> np.ndarray:
    """rows x k matrix of +-1 by md5, the same as hash_unit's lowest bit in any engine."""
    import hashlib

    bit = lambda i, j: int(hashlib.md5(f"{seed}-{i}-{j}".encode()).hexdigest()[:8], 16) & 1
    return np.array([[1 - 2 * bit(i, j) for j in range(k)] for i in range(rows)], np.int64)


def fast_signs(seed: int, lo: int, hi: int, k: int, kind: str = "rademacher") -> np.ndarray:
    """Rows lo..hi of the projection, made anew wherever needed: nothing of D x k is stored or sent.

    kind: rademacher (+-1), gaussian, or sparse (two thirds zeros, scaled by sqrt 3).
    """
    out = np.empty((hi - lo, k))
    for i in range(lo, hi):
        rng = np.random.default_rng([seed, i])
        if kind == "gaussian":
            out[i - lo] = rng.standard_normal(k)
        elif kind == "sparse":
            out[i - lo] = rng.choice([-(3**0.5), 0.0, 0.0, 0.0, 0.0, 3**0.5], k)
        else:
            out[i - lo] = 1 - 2 * rng.integers(0, 2, k)
    return out


def project(grads: DataFrame, width: int, k: int, seed: str = "proj", kind: str = "md5", block: int = 4096) -> DataFrame:
    """(id, g): projected to k numbers inside the tasks; the factor 1/sqrt(k) is dropped, as cosines ignore it.

    kind md5 is exact in integers and checkable; the others are for production widths, block rows at a time.
    """
    if kind == "none":
        return grads

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        exact = signs(seed, width, k) if kind == "md5" else None
        for pdf in batches:
            g = np.array(pdf["g"].tolist(), np.int64).reshape(-1, width)
            if exact is not None:
                p = g @ exact
            else:
                p = np.zeros((len(g), k))
                for lo in range(0, width, block):
                    hi = min(width, lo + block)
                    p += g[:, lo:hi] @ fast_signs(zlib.crc32(seed.encode()), lo, hi, k, kind)
                p = np.rint(p).astype(np.int64)
            yield pd.DataFrame({"id": pdf["id"], "g": list(p)})

    return grads.mapInPandas(run, "id long, g array<long>")


def target_sum(grads: DataFrame) -> list[int]:
    """Component sums (the mean times the count: cosine doesn't care); one short vector to the driver."""
    rows = grads.select(F.posexplode("g").alias("i", "v")).groupBy("i").agg(F.sum(F.col("v").cast("decimal(38,0)")).alias("m")).collect()
    return [int(r["m"]) for r in sorted(rows, key=lambda r: r["i"])]


def score(grads: DataFrame, target: list[int], how: str = "cosine") -> DataFrame:
    """(id, v double rounded to 6 places or null, v_fp long): map-only.  A zero gradient or target gives null."""
    m = np.array(target, np.float64)
    exact = [int(x) for x in target]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        norm = float(sum(x * x for x in exact)) ** 0.5
        for pdf in batches:
            g = np.array(pdf["g"].tolist(), np.float64)
            if not len(g) or not len(m):
                v = np.full(len(pdf), np.nan)
            else:
                dot = g @ m
                own = np.sqrt((g * g).sum(axis=1))
                with np.errstate(invalid="ignore", divide="ignore"):
                    v = dot / own / norm if how == "cosine" else dot / UNIT / UNIT
                if how == "cosine":
                    v[(own == 0) | (norm == 0)] = np.nan
            v = np.round(v, 6)
            yield pd.DataFrame({"id": pdf["id"], "v": v})

    out = grads.mapInPandas(run, "id long, v double").withColumn("v", F.nanvl("v", F.lit(None).cast("double")))
    return out.withColumn("v_fp", F.round(F.col("v") * UNIT).cast("long"))


class Cosine:
    """Influence by cosine in a worker, as score() gives it."""

    def __init__(self, target: list[int]):
        self.m, self.norm = np.array(target, np.float64), float(sum(int(x) * int(x) for x in target)) ** 0.5

    def __call__(self, g: np.ndarray) -> float | None:
        g = np.asarray(g, np.float64)
        own = np.sqrt((g * g).sum()) if len(self.m) else 0
        return float(np.round(g @ self.m / own / self.norm, 6)) if own and self.norm else None


def score_without_self(grads: DataFrame, target: list[int], members: DataFrame) -> DataFrame:
    """(id, v, v_fp) where a member of the target is compared with the target without it; members: (id) of those."""
    m = np.array(target, np.float64)
    own = members.select("id").distinct().withColumn("_in", F.lit(True))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            if len(pdf):
                g = np.array(pdf["g"].tolist(), np.float64)
                t = m[None] - np.where(pdf["_in"].to_numpy(bool)[:, None], g, 0)
                n = np.linalg.norm(g, axis=1) * np.linalg.norm(t, axis=1)
                with np.errstate(invalid="ignore", divide="ignore"):
                    yield pd.DataFrame({"id": pdf["id"], "v": np.round(np.where(n > 0, (g * t).sum(axis=1) / n, np.nan), 6)})

    out = grads.join(own, "id", "left").select("id", "g", F.coalesce("_in", F.lit(False)).alias("_in")).mapInPandas(run, "id long, v double").withColumn("v", F.nanvl("v", F.lit(None).cast("double")))
    return out.withColumn("v_fp", F.round(F.col("v") * UNIT).cast("long"))


def over_checkpoints(scores: list[DataFrame], rates: list[float]) -> DataFrame:
    """(id, v, v_fp): influences at several checkpoints of the reference, summed with their step sizes."""
    total = None
    for s, r in zip(scores, rates):
        part = s.select("id", (F.round(F.col("v") * r * UNIT)).cast("long").alias("v_fp"))
        total = part if total is None else total.union(part)
    return total.groupBy("id").agg(F.sum("v_fp").alias("v_fp")).select("id", (F.col("v_fp") / UNIT).alias("v"), "v_fp")


def score_by_category(grads: DataFrame, targets: dict[int, list[int]], own: str | None = None) -> DataFrame:
    """(id, best, v): the largest cosine to any category's mean (or the row's own category's)."""
    cats = sorted(targets)
    m = np.array([targets[c] for c in cats], np.float64)
    m /= np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-300)
    cols = ["id", "g", *([own] if own else [])]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            g = np.array(pdf["g"].tolist(), np.float64)
            n = np.linalg.norm(g, axis=1, keepdims=True)
            v = np.round((g / np.where(n > 0, n, np.nan)) @ m.T, 6)
            pick = np.searchsorted(cats, pdf[own].to_numpy()) if own else np.nan_to_num(v, nan=-9).argmax(axis=1)
            yield pd.DataFrame({"id": pdf["id"], "best": np.array(cats)[pick], "v": v[np.arange(len(v)), pick]})

    return grads.select(*cols).mapInPandas(run, "id long, best int, v double").withColumn("v", F.nanvl("v", F.lit(None).cast("double")))


def pairwise(grads: DataFrame, tests: DataFrame, top: int, how: str = "cosine", block: int = 4096) -> DataFrame:
    """(test_id, id, v, rank): the `top` most similar samples of each test gradient.

    tests is a stated query set, collected and sent in blocks; each task keeps its own top per test, so at
    most top x tests x tasks rows are shuffled.
    """
    t = tests.orderBy("id").collect()
    w = Window.partitionBy("test_id").orderBy(F.desc("v"), "id")
    out = None
    for lo in range(0, len(t), block):
        ids = np.array([r["id"] for r in t[lo : lo + block]])
        m = np.array([list(r["g"]) for r in t[lo : lo + block]], np.float64)
        if how == "cosine":
            m /= np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-300)

        def run(batches: Iterator[pd.DataFrame], ids=ids, m=m) -> Iterator[pd.DataFrame]:
            for pdf in batches:
                g = np.array(pdf["g"].tolist(), np.float64)
                if how == "cosine":
                    g = g / np.maximum(np.linalg.norm(g, axis=1, keepdims=True), 1e-300)
                v = np.round(g @ m.T, 6)
                own = pdf["id"].to_numpy()
                for k, test in enumerate(ids):
                    best = np.lexsort((own, -v[:, k]))[:top]
                    yield pd.DataFrame({"test_id": test, "id": own[best], "v": v[best, k]})

        part = grads.mapInPandas(run, "test_id long, id long, v double")
        out = part if out is None else out.union(part)
    if out is None:
        return grads.sparkSession.createDataFrame([], "test_id long, id long, v double, rank int")
    return out.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= top)


def distortion(grads: DataFrame, target_rows: DataFrame, width: int, ks: list[int], top: int, seed: str = "proj") -> DataFrame:
    """(k, mean_abs_error, distance_ratio, top_overlap) of projected against full influence.

    The error falls and the overlap rises with k.  distance_ratio: projected over full distance of each row to the
    target's mean, over sqrt(k), as a mean: near one at any k.
    """
    n = target_rows.count()
    mean = [x // max(1, n) for x in target_sum(target_rows)]
    full = score(grads, target_sum(target_rows)).select("id", "v")
    best = full.orderBy(F.desc_nulls_last("v"), "id").limit(top).select("id")

    def far(df: DataFrame, to: list[int], name: str) -> DataFrame:
        m = np.array(to, np.float64)

        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for pdf in batches:
                if len(pdf):
                    yield pd.DataFrame({"id": pdf["id"], "d": np.linalg.norm(np.array(pdf["g"].tolist(), np.float64) - m, axis=1)})

        return df.mapInPandas(run, "id long, d double").withColumnRenamed("d", name)

    out = None
    for k in ks:
        g = project(grads, width, k, seed)
        to = (np.array(mean, np.int64) @ signs(seed, width, k)).tolist()
        p = score(g, target_sum(project(target_rows, width, k, seed))).select("id", F.col("v").alias("w"))
        err = full.join(p, "id").agg(F.round(F.avg(F.abs(F.col("v") - F.col("w"))), 4).alias("mean_abs_error"))
        ratio = far(grads, mean, "d").join(far(g, to, "e"), "id").filter("d > 0").agg(F.round(F.avg(F.col("e") / F.col("d") / k**0.5), 4).alias("distance_ratio"))
        hit = p.orderBy(F.desc_nulls_last("w"), "id").limit(top).join(best, "id").agg(F.count(F.lit(1)).alias("top_overlap"))
        row = err.crossJoin(ratio).crossJoin(hit).select(F.lit(k).alias("k"), "mean_abs_error", "distance_ratio", "top_overlap")  # one row each
        out = row if out is None else out.union(row)
    return out


def plan_order(width: int, k: int, premium: int) -> str:
    """Projection is linear: project the mean, or average projections, whichever is cheaper."""
    return "average_then_project" if width + width * k < premium * width * k else "project_then_average"


def md5_sign(seed: str, i, j):
    """+-1 as a column, the same as signs()."""
    return F.lit(1) - 2 * (hash_unit(seed, i, j) % 2)
