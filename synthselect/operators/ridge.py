"""Learning the weights of marks: ridge regression without intercept on experiments' mean marks."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import UNIT


def experiments(df: DataFrame, groups: list[str], marks: list[str], y: str) -> DataFrame:
    """(groups..., marks' means, y mean, n): from integer sums, so any engine gets the same six decimals."""
    mean = lambda c: F.round(F.sum(F.col(c).cast("long")) / F.count(c), 6)
    return df.groupBy(*groups).agg(*[mean(m).alias(m) for m in marks], mean(y).alias("y"), F.count(F.lit(1)).alias("n"))


def gram(exps: DataFrame, marks: list[str], y: str = "y") -> DataFrame:
    """One row: sums of all products of marks and of marks with y, in squared millionths."""
    whole = lambda c: F.round(F.col(c) * UNIT).cast("long")
    cells = [F.sum(whole(a) * whole(b)).alias(f"g_{a}_{b}") for k, a in enumerate(marks) for b in marks[k:]]
    return exps.agg(*cells, *[F.sum(whole(a) * whole(y)).alias(f"b_{a}") for a in marks], F.count(F.lit(1)).alias("k"))


@dataclass
class Ridge:
    marks: list[str]
    weights: np.ndarray
    gram: np.ndarray
    moment: np.ndarray
    penalty: float
    intercept: float = 0.0

    def residual(self) -> np.ndarray:
        return (self.gram + self.penalty * np.eye(len(self.marks))) @ self.weights - self.moment


def statistics(exps: DataFrame, marks: list[str], y: str = "y") -> tuple[np.ndarray, np.ndarray]:
    row = gram(exps, marks, y).first()
    g = np.zeros((len(marks), len(marks)))
    for i, a in enumerate(marks):
        for j in range(i, len(marks)):
            g[i, j] = g[j, i] = float(row[f"g_{a}_{marks[j]}"] or 0) / UNIT**2
    return g, np.array([float(row[f"b_{a}"] or 0) / UNIT**2 for a in marks])


def fit(exps: DataFrame, marks: list[str], penalty: float = 1.0, y: str = "y", nonneg: bool = False, unit_sum: bool = False, intercept: bool = False, standardise: bool = False) -> Ridge:
    """w = (X'X + penalty I)^-1 X'y: one aggregation row reaches the driver, whatever the number of experiments.

    intercept: marks and y are centred first; standardise: marks are divided by their spread while fitted, and the
    weights given back for the marks as they are.  gram and moment are those of the system that was solved.
    """
    if penalty < 0:
        raise ValueError("the penalty is not negative")
    g, b = statistics(exps, marks, y)
    mean, own = np.zeros(len(marks)), 0.0
    if intercept or standardise:
        row = exps.agg(F.count(F.lit(1)).alias("k"), *[F.avg(m).alias(m) for m in marks], F.avg(y).alias("_y")).first()
        k, centre = row["k"], np.array([row[m] or 0.0 for m in marks])
        spread = np.sqrt(np.maximum(np.diag(g) / max(1, k) - centre**2, 0))
        if intercept:
            mean, own = centre, row["_y"] or 0.0
            g, b = g - k * np.outer(mean, mean), b - k * mean * own
    scale = np.where(spread > 0, spread, 1.0) if standardise else np.ones(len(marks))
    g, b = g / np.outer(scale, scale), b / scale
    a = g + penalty * np.eye(len(marks))
    w = np.linalg.lstsq(a, b, rcond=None)[0] if penalty == 0 else np.linalg.solve(a, b)
    if nonneg:  # coordinate descent on the same normal equations
        w = np.maximum(w, 0)
        for _ in range(500):
            for k in range(len(w)):
                if a[k, k] > 0:
                    w[k] = max(0.0, w[k] + (b[k] - a[k] @ w) / a[k, k])
    solved = Ridge(marks, w, g, b, penalty)
    w = w / scale
    if unit_sum and w.sum():
        w = w / w.sum()
    if not (intercept or standardise or unit_sum):
        return solved
    return Ridge(marks, w, g, b, penalty, float(own - w @ mean))


def loo_path(exps: DataFrame, marks: list[str], penalties: list[float], y: str = "y") -> DataFrame:
    """(penalty, loo_mse): leave-one-out error from the hat values; one map-only pass per penalty."""
    g, b = statistics(exps, marks, y)
    out = None
    for p in penalties:
        inv = np.linalg.inv(g + p * np.eye(len(marks)))
        w = inv @ b
        x = [F.col(m) for m in marks]
        hat = sum(float(inv[i, j]) * x[i] * x[j] for i in range(len(x)) for j in range(len(x)))
        err = (F.col(y) - sum(float(w[i]) * x[i] for i in range(len(x)))) / (1 - hat)
        row = exps.agg(F.round(F.avg(err * err), 6).alias("loo_mse")).select(F.lit(float(p)).alias("penalty"), "loo_mse")
        out = row if out is None else out.union(row)
    return out


def diagnostics(exps: DataFrame, model: Ridge, y: str = "y") -> DataFrame:
    """One row: R^2 and correlation of the fitted score with y."""
    score = sum(float(w) * F.col(m) for w, m in zip(model.weights, model.marks))
    d = exps.withColumn("_s", score).crossJoin(F.broadcast(exps.agg(F.avg(y).alias("_mean"))))
    return d.agg(F.round(1 - F.sum((F.col(y) - F.col("_s")) ** 2) / F.sum((F.col(y) - F.col("_mean")) ** 2), 6).alias("r2"), F.round(F.corr("_s", y), 6).alias("corr"))


def residuals(exps: DataFrame, model: Ridge, keys: list[str], y: str = "y") -> DataFrame:
    """(keys..., y, fitted, residual, rank_y, rank_fitted): one row an experiment."""
    fitted = F.round(sum((float(w) * F.col(m) for w, m in zip(model.weights, model.marks)), F.lit(float(model.intercept))), 6)
    d = exps.select(*keys, y, fitted.alias("fitted")).withColumn("residual", F.round(F.col(y) - F.col("fitted"), 6))
    place = lambda c: F.row_number().over(Window.orderBy(F.desc(c), *keys))  # noqa: E731  a row an experiment, not a document
    return d.withColumns({"rank_y": place(y), "rank_fitted": place("fitted")})


def rank_correlation(exps: DataFrame, model: Ridge, keys: list[str], y: str = "y") -> DataFrame:
    """One row (k, spearman): how well the fitted score orders the experiments."""
    r = residuals(exps, model, keys, y)
    n = F.count(F.lit(1))
    gap = F.col("rank_y") - F.col("rank_fitted")
    return r.agg(n.alias("k"), F.round(F.when(n > 1, 1 - 6 * F.sum(gap * gap) / (n * (n * n - 1))), 6).alias("spearman"))


def fit_mllib(exps: DataFrame, marks: list[str], penalty: float, y: str = "y") -> list[float]:
    """The library's solver as a cross-check: its penalty is scaled by the population spread of y over the count."""
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.regression import LinearRegression

    k, sd = exps.agg(F.count(F.lit(1)), F.stddev_pop(y)).first()
    rows = VectorAssembler(inputCols=marks, outputCol="_v").transform(exps)
    m = LinearRegression(featuresCol="_v", labelCol=y, elasticNetParam=0.0, fitIntercept=False, standardization=False, solver="normal", regParam=penalty * sd / k).fit(rows)
    return list(m.coefficients)
