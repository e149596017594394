"""Keeping n rows: by influence, at random, by perplexity; exact for any n, ties by id."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import hash_unit
from ..sources import land

#: Up to so many rows a heap per task is cheaper than counting; both give the same rows.
SMALL = 2_000


def _bits(x: Column) -> Column:
    """Longs in the order of the doubles: NaN above all, both zeros equal, null for null."""

    @F.pandas_udf("long")
    def run(v: pd.Series) -> pd.Series:
        d = v.to_numpy(np.float64) + 0.0
        b = np.where(np.isnan(d), np.nan, d).view(np.int64)
        return pd.Series(np.where(b < 0, b ^ np.int64(0x7FFFFFFFFFFFFFFF), b))

    return F.when(x.isNotNull(), run(x))


def _key(df: DataFrame, by: str, ascending: bool) -> Column:
    """A long whose order is that of `by`, smallest first to be kept."""
    kind = df.schema[by].dataType
    if isinstance(kind, (T.FloatType, T.DoubleType)):
        key = _bits(F.col(by).cast("double"))
    elif isinstance(kind, (T.ByteType, T.ShortType, T.IntegerType, T.LongType)):
        key = F.col(by).cast("long")
    else:
        raise TypeError(f"top_n selects by integers or reals, {by} is {kind.simpleString()}")
    return key if ascending else F.bitwise_not(key)


def _first(keyed: DataFrame, key: str, n: int) -> tuple[DataFrame, DataFrame, int]:
    """(rows before the cut, rows at it, how many of these belong) of the n smallest keys; keyed holds more than n rows."""
    low, high = keyed.agg(F.min(key), F.max(key)).first()
    at, before, held = low, 0, keyed
    for step in (s for s in (48, 32, 16, 0) if s < (low ^ high).bit_length() or low < 0 <= high):
        counts = held.groupBy(F.shiftright(key, step).alias("bin")).agg(F.count(F.lit(1)).alias("c"))
        run = counts.withColumn("upto", F.sum("c").over(Window.orderBy("bin")))  # at most 2^16 bins, not rows
        hit = run.filter(F.col("upto") + before >= n).orderBy("bin").first()
        before += hit["upto"] - hit["c"]
        at = hit["bin"]
        held = keyed.filter(F.shiftright(key, step) == at)
    return keyed.filter(F.col(key) < at), keyed.filter(F.col(key) == at), n - before


def top_n(df: DataFrame, by: str, n: int, tie: str = "id", ascending: bool = False, small: int | None = None) -> DataFrame:
    """The n rows with the largest (smallest) `by`, nulls last, ties by smallest id; the same rows for any n.

    Up to `small` (SMALL) rows: each task's heap, merged.  Beyond: count rows by the leading bits of an
    order-preserving long of `by`, then by the next bits of those at the cut, down to single values; keep what lies
    before the cut, and of the rows at it the first ids, found the same way.  Nothing is sorted globally, a few numbers
    reach the driver, and df is landed once, as it is read several times.
    """
    if n <= 0:
        return df.limit(0)
    small = SMALL if small is None else small
    key = _key(df, by, ascending)
    order = F.asc_nulls_last(by) if ascending else F.desc_nulls_last(by)
    if n <= small:
        return df.orderBy(order, tie).limit(n)
    keyed = land(df.withColumns({"_key": key, "_tie": _key(df, tie, True)}))
    rows, some = keyed.agg(F.count(F.lit(1)), F.count("_key")).first()
    if n >= rows:
        return keyed.drop("_key", "_tie")
    if n >= some:  # all that have a value, and of the others the first ids
        out, level, left = keyed.filter("_key is not null"), keyed.filter("_key is null"), n - some
        size = rows - some
    else:
        out, level, left = _first(keyed.filter("_key is not null"), "_key", n)
        size = level.count()
    if left >= size:
        out = out.union(level)
    elif left and left <= small:
        out = out.union(level.orderBy(tie).limit(left))
    elif left:
        inner, last, few = _first(level, "_tie", left)
        out = out.union(inner).union(last.limit(few))  # rows of one value and one id
    return out.drop("_key", "_tie")


def random_n(df: DataFrame, n: int, seed: str = "rand", id_col: str = "id") -> DataFrame:
    return top_n(df.withColumn("_u", hash_unit(seed, id_col)), "_u", n, id_col, ascending=True).drop("_u")


def overlap(a: DataFrame, b: DataFrame, id_col: str = "id") -> DataFrame:
    """One row: sizes, shared, Jaccard of two selections."""
    x, y = (d.select(F.col(id_col).alias("id")).distinct() for d in (a, b))
    j = x.withColumn("l", F.lit(1)).join(y.withColumn("r", F.lit(1)), "id", "full_outer")
    n = j.agg(F.count("l").alias("n_a"), F.count("r").alias("n_b"), F.count(F.when(F.col("l").isNotNull() & F.col("r").isNotNull(), 1)).alias("shared"), F.count(F.lit(1)).alias("either"))
    return n.select("n_a", "n_b", "shared", F.round(F.col("shared") / F.col("either"), 6).alias("jaccard"))


def rank_correlation(a: DataFrame, b: DataFrame, by: str, id_col: str = "id") -> DataFrame:
    """One row (n, spearman): of the ids that both selections hold, how alike their orders by `by` are.

    Ranks among the shared ids, ties by id; a selection of n rows is ranked by counting, range by range.
    """
    x = a.select(F.col(id_col).alias("id"), F.col(by).alias("x")).join(b.select(F.col(id_col).alias("id"), F.col(by).alias("y")), "id")
    x = land(x)
    rx, ry = (ranks(x, c, "id").withColumnRenamed("rank", f"r{c}").select("id", f"r{c}") for c in ("x", "y"))
    d = rx.join(ry, "id").agg(F.count(F.lit(1)).alias("n"), F.sum(((F.col("rx") - F.col("ry")) * (F.col("rx") - F.col("ry"))).cast("decimal(38,0)")).alias("d"))
    return d.select("n", F.round(F.when(F.col("n") > 1, 1 - 6 * F.col("d").cast("double") / (F.col("n") * (F.col("n") * F.col("n") - 1).cast("double"))), 6).alias("spearman"))


def ranks(df: DataFrame, by: str, tie: str) -> DataFrame:
    """df with `rank` 1, 2, ... from the largest `by`, ties by id: ranges sorted apart, their counts summed (one a range)."""
    order = [F.desc_nulls_last(by), F.asc(tie)]
    parts = land(df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_at", F.monotonically_increasing_id()))
    part = F.shiftright("_at", 33)
    sizes = parts.groupBy(part.alias("_p")).agg(F.count(F.lit(1)).alias("_n"))
    before = sizes.withColumn("_before", F.coalesce(F.sum("_n").over(Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    place = F.col("_at").bitwiseAND((1 << 33) - 1)
    return parts.withColumn("_p", part).join(F.broadcast(before), "_p").withColumn("rank", F.col("_before") + place + 1).drop("_p", "_n", "_before", "_at")
