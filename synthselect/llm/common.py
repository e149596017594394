"""Shared pieces of the corpus operators: landed tables, run-wise streaming, bucket blocks, components."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Key lists up to so many rows (8 bytes each) are broadcast; longer ones are joined by a shuffle.
MOST_SENT = 500_000
#: A key with more than a share of 1 / SHARES of a table's rows is hot.
SHARES = 2000


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir; where that is unset on one machine (tests), one of this process."""
    d = spark.conf.get("spark.checkpoint.dir", None)
    if not d:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        d = getattr(shared_dir, "own", None) or tempfile.mkdtemp(prefix="synthselect-")
        shared_dir.own = d
    return d.rstrip("/")


#: Folders landed by this process and not deleted yet, oldest first.
LANDED: list[str] = []


def land(df: DataFrame, name: str, *partitions: str) -> DataFrame:
    """Write df to the shared folder and read it back: cuts lineage, survives lost executors.

    The files go when release() says so, at the latest when the driver's JVM ends.  With `partitions` the folder is
    laid out by those columns.
    """
    spark = df.sparkSession
    top = f"{shared_dir(spark)}/synthselect-{uuid.uuid4().hex}"
    path = f"{top}/{name}"
    df.write.partitionBy(*partitions).parquet(path) if partitions else df.write.parquet(path)
    fs, p = _file(spark, top)
    fs.deleteOnExit(p)
    LANDED.append(top)
    return spark.read.schema(df.schema).parquet(path)


def _file(spark: SparkSession, path: str):
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), p


def release(spark: SparkSession, since: int, keep: int = 0) -> None:
    """Delete what was landed after the first `since` folders, but for the last `keep`."""
    for top in LANDED[since : len(LANDED) - keep]:
        fs, p = _file(spark, top)
        fs.delete(p, True)
        LANDED.remove(top)


def join_spread(rows: DataFrame, table: DataFrame, key: str, count: str, total: int, how: str = "inner") -> DataFrame:
    """rows joined with table, which has one row a key with `count`, the rows of that key; `count` is dropped.

    Keys with more than total / SHARES rows, SHARES at most, are broadcast, so none gathers in one task.  how:
    inner or left; keys are not null.
    """
    most = max(1000, total // SHARES)
    hot = table.filter(F.col(count) > most).drop(count)
    rest = table.filter(F.col(count) <= most).drop(count)
    return rows.join(F.broadcast(hot), key).union(rows.join(F.broadcast(hot.select(key)), key, "left_anti").join(rest, key, how))


def sent(keys: DataFrame) -> DataFrame:
    """keys as a side of a join: broadcast after a check of its size."""
    return F.broadcast(keys) if keys.limit(MOST_SENT + 1).count() <= MOST_SENT else keys


def whole_runs(batches: Iterator[pd.DataFrame], keys: list[str], least: int = 50_000) -> Iterator[tuple[pd.DataFrame, np.ndarray]]:
    """Regroup sorted batches so that no run of equal keys is cut: (frame, starts of the runs)."""
    held: list[pd.DataFrame] = []
    n = 0
    for pdf in batches:
        if not len(pdf):
            continue
        held.append(pdf)
        n += len(pdf)
        if n < least:
            continue
        pdf = pd.concat(held, ignore_index=True) if len(held) > 1 else held[0]
        new = _starts(pdf, keys)
        if new[-1] == 0:
            held, n = [pdf], 0  # one run so far: wait for as many rows again
            continue
        cut = new[-1]
        yield pdf.iloc[:cut], new[:-1]
        held = [pdf.iloc[cut:].reset_index(drop=True)]
        n = len(held[0])
    if held:
        pdf = pd.concat(held, ignore_index=True) if len(held) > 1 else held[0]
        yield pdf, _starts(pdf, keys)


def _starts(pdf: pd.DataFrame, keys: list[str]) -> np.ndarray:
    new = np.zeros(len(pdf), bool)
    new[0] = True
    for k in keys:
        v = pdf[k].to_numpy()
        new[1:] |= v[1:] != v[:-1]
    return np.flatnonzero(new)


def pairs_in_runs(starts: np.ndarray, n: int, most: int = 1_000_000) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Row numbers (i < j) of all pairs inside each run, in chunks of about `most` pairs."""
    sizes = np.diff(np.append(starts, n))
    for m in np.unique(sizes[sizes > 1]):
        at = starts[sizes == m]
        if m * m // 2 <= most:
            i, j = np.triu_indices(int(m), 1)
            step = max(1, most // len(i))
            for k in range(0, len(at), step):
                base = at[k : k + step, None]
                yield (base + i).ravel(), (base + j).ravel()
        else:
            rows = max(1, most // int(m))
            for base in at:
                for lo in range(0, int(m), rows):
                    i = np.arange(lo, min(lo + rows, int(m)))
                    ii, jj = np.repeat(i, m), np.tile(np.arange(m), len(i))
                    ok = ii < jj
                    yield base + ii[ok], base + jj[ok]


def stars(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Reduce links a-b to (member, smallest member of its local component), members that are no root."""
    ids, inv = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = inv[: len(a)], inv[len(a) :]
    label = np.arange(len(ids))
    while True:
        lx, ly = label[x], label[y]
        low = np.minimum(lx, ly)
        new = label.copy()
        np.minimum.at(new, lx, low)
        np.minimum.at(new, ly, low)
        while not np.array_equal(up := new[new], new):
            new = up
        if np.array_equal(new, label):
            break
        label = new
    keep = label != np.arange(len(ids))
    return ids[keep], ids[label[keep]]


def in_blocks(rows: DataFrame, key: str, member: str, block: int) -> DataFrame:
    """Add bi, bj, mine and group rows by (key, bi, bj): each pair of a bucket's blocks meets once.

    A bucket of at most `block` rows is one block (0, 0).  A larger one is cut by a hash of `member`; a row of
    block b goes to the block pairs (min(b, j), max(b, j)) for every j.  The block is the same at any size of input.
    """
    hot = rows.groupBy(key).agg(F.count(F.lit(1)).alias("_n")).filter(F.col("_n") > block)
    hot = land(hot.select(key, F.expr(f"cast(ceil(_n / {block}) as long) as _nb")), "hot")
    if hot.limit(1).count():
        rows = rows.join(sent(hot), key, "left").withColumn("_nb", F.coalesce("_nb", F.lit(1)))
        rows = rows.withColumn("mine", F.expr(f"cast(pmod(xxhash64({member}, 7), _nb) as int)"))
        rows = rows.withColumn("_j", F.explode(F.expr("sequence(0, cast(_nb as int) - 1)"))).withColumns({"bi": F.least("mine", "_j"), "bj": F.greatest("mine", "_j")}).drop("_nb", "_j")
    else:
        rows = rows.withColumns({"mine": F.lit(0), "bi": F.lit(0), "bj": F.lit(0)})
    return rows.repartition(key, "bi", "bj").sortWithinPartitions(key, "bi", "bj")


def components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(id, root) of every id that has a smaller one in its component, by alternating star contractions.

    edges: columns a, b (long).  Each round is two aggregations and joins over edges that only get
    fewer or flatter; it is landed, so a lost executor costs at most one round.
    """
    e = edges.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    e = land(e, "edges0")
    seen = None
    for k in range(most_rounds):
        both = e.union(e.select("b", "a"))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        big = both.join(low, "a").filter("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        low = big.groupBy("a").agg(F.min("b").alias("m"))
        small = big.join(low, "a").selectExpr("if(b = m, a, b) as a", "m as b").union(low.select("a", "m")).distinct()
        e = land(small, f"edges{k + 1}")
        now = e.agg(F.count(F.lit(1)), F.sum(F.expr("xxhash64(a, b) % 1000000007"))).first()
        if now[0] == 0 or tuple(now) == seen:
            break
        seen = tuple(now)
    else:
        raise RuntimeError("components did not settle")
    return e.select(F.col("a").alias("id"), F.col("b").alias("root"))
