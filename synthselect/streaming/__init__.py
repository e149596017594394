"""Candidates that arrive as a stream: best so far, windows, sessions, duplicates, late rows."""

from __future__ import annotations

import json
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources import scratch

#: What events of the tables look like; streams need a schema given.
EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events file as a stream, with a UTC event time t."""
    s = spark.readStream.schema(EVENTS).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return s.withColumn("t", F.col("ts").cast("timestamp"))


def drained(stream: DataFrame, mode: str, batches: list[str] | None = None, state: list[str] | None = None) -> DataFrame:
    """Run the stream over all that is there and give what its sink holds; state and sink in the shared folder.

    Append goes to files.  Update and complete go through foreachBatch, one table per batch; the last value of a key is
    the reader's to pick.  batches, state: lists that get the progress of the batches and the folder of the state.  State has as many partitions as the session shuffles into when the stream first starts.
    """
    base = scratch(stream.sparkSession)
    w = stream.writeStream.option("checkpointLocation", f"{base}/state").trigger(availableNow=True)
    if mode == "append":
        run = w.format("parquet").outputMode("append").option("path", f"{base}/out").start()
    else:
        run = w.outputMode(mode).foreachBatch(lambda df, k: df.withColumn("_batch", F.lit(k)).write.mode("overwrite").parquet(f"{base}/out/b={k}")).start()
    run.awaitTermination()
    if batches is not None:
        batches += [p.json for p in run.recentProgress]
    if state is not None:
        state.append(f"{base}/state")
    return stream.sparkSession.read.parquet(f"{base}/out")


def replayed(spark: SparkSession, parts: list[DataFrame]) -> DataFrame:
    """A stream that sees the parts one after another, a batch each."""
    path = f"{scratch(spark)}/replay"
    for k, p in enumerate(parts):
        p.coalesce(1).write.mode("append").parquet(path)
        if k == 0:
            schema = p.schema
        time.sleep(0.05)  # files are taken in the order of their times
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("latestFirst", "false").parquet(path)


def came(batches: list[str]) -> int:
    """Rows that a stream read, over all batches."""
    return sum(json.loads(b)["numInputRows"] for b in batches)


def waiting(spark: SparkSession, state: str) -> int:
    """Rows counted in windows that are still open: of a stream whose only state is a count a group."""
    return spark.read.format("statestore").load(state).agg(F.sum("value.count")).first()[0] or 0


def latest(df: DataFrame, keys: list[str]) -> DataFrame:
    """Of update-mode batches the last row of each key."""
    cols = [c for c in df.columns if c not in ("_batch", "b", *keys)]
    best = df.groupBy(*keys).agg(F.max_by(F.struct(*cols), "_batch").alias("_r"))
    return best.select(*keys, "_r.*")


def best_so_far(stream: DataFrame, key: str, score: str, carry: list[str]) -> DataFrame:
    """The best candidate of each key as rows come in: an aggregation state of one struct a key."""
    return stream.groupBy(key).agg(F.max(F.struct(score, *carry)).alias("b")).select(key, "b.*")


def best_in_session(stream: DataFrame, key: str, score: str, carry: list[str], time_col: str, gap: str, delay: str) -> DataFrame:
    """The best candidate of each key's session of activity, once the watermark has closed it."""
    g = stream.withWatermark(time_col, delay).groupBy(F.session_window(time_col, gap).alias("win"), key)
    best = g.agg(F.max(F.struct(score, *carry)).alias("b"), F.count(F.lit(1)).alias("n"))
    return best.select(key, F.unix_micros("win.start").alias("start"), "n", "b.*")
