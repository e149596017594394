"""Sources and sinks: tables of a folder, rounds by iteration, JSON lines of samples."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def views(spark: SparkSession, sf_dir: str, *names: str) -> None:
    """Register tables of the folder as temporary views for SQL users."""
    for n in names:
        table(spark, sf_dir, n).createOrReplaceTempView(n)


def scratch(spark: SparkSession) -> str:
    """A new folder under spark.checkpoint.dir; of this machine only where that is unset on one machine (tests)."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        base = tempfile.gettempdir()
    return f"{base.rstrip('/')}/synthselect-{uuid.uuid4().hex}"


def land(df: DataFrame, path: str | None = None) -> DataFrame:
    """Write as Parquet and read back: stages of a loop meet through files only."""
    own = path is None
    path = path or scratch(df.sparkSession)
    df.write.mode("overwrite").parquet(path)
    if own:  # scratch goes when the driver's JVM ends, at the latest
        fs, p = _file(df.sparkSession, path)
        fs.deleteOnExit(p)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def _file(spark: SparkSession, path: str):
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), p


def drop(df: DataFrame) -> None:
    """Delete the files of a landed frame that nothing reads any more."""
    for top in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if "synthselect-" in top:
            fs, p = _file(df.sparkSession, top)
            fs.delete(p, True)


#: A key with more than a share of 1 / SHARES of a table's rows is hot.
SHARES = 2000


def join_spread(rows: DataFrame, table: DataFrame, keys: list[str], count: str, total: int) -> DataFrame:
    """rows left-joined with table, which has one row a key with `count`, the rows of that key; keys aren't null.

    Keys with more than total / SHARES rows, SHARES at most, are broadcast, so none gathers in one task.
    """
    most = max(1000, total // SHARES)
    hot, rest = table.filter(F.col(count) > most), table.filter(F.col(count) <= most)
    return rows.join(F.broadcast(hot), keys).unionByName(rows.join(F.broadcast(hot.select(*keys)), keys, "left_anti").join(rest, keys, "left"))


#: Rows of a table that is sent to all tasks, if they are so many at most.
MOST_SENT = 1_000_000


def join_sent(rows: DataFrame, table: DataFrame, key: str | list[str], how: str) -> DataFrame:
    """rows joined with a landed table of few short columns: sent to the tasks behind a check of its number, so that no row is
    shuffled; a shuffle beyond it."""
    return rows.join(F.broadcast(table) if table.count() <= MOST_SENT else table, key, how)


def write_round(samples: DataFrame, path: str) -> None:
    """Samples partitioned by iteration; a round overwrites only its own partition."""
    samples.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("iteration").parquet(path)


def read_round(spark: SparkSession, path: str, iteration: int) -> DataFrame:
    return spark.read.parquet(path).filter(F.col("iteration") == iteration)


def exists(spark: SparkSession, path: str) -> bool:
    fs, p = _file(spark, path)
    return fs.exists(p)


def write_jsonl(samples: DataFrame, path: str) -> None:
    """(prompt, q, s) as JSON lines, for trainers outside Spark."""
    samples.select(F.to_json(F.struct(*[c for c in ("prompt", "q", "s") if c in samples.columns])).alias("value")).write.mode("overwrite").text(path)
