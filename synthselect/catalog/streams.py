"""Streaming queries, each drained and checked against the batch result."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import streaming as S
from ..sources import table
from . import query

_MICROS = "epoch_us(ts)"
#: Append mode emits windows that the watermark has passed: the last event less the delay.
_MARK = "(SELECT max(epoch_us(ts)) - 600000000 FROM events)"


def _us(col: str):
    return F.unix_micros(F.col(col))


@query("stream_best_candidate", "SELECT user_id, value, event_id FROM events QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id DESC) = 1")
def stream_best(spark, d):
    s = S.best_so_far(S.events(spark, d), "user_id", "value", ["event_id"])
    return S.latest(S.drained(s, "update"), ["user_id"])


@query("op_stream_tumbling", f"SELECT ({_MICROS} // 3600000000) * 3600000000 AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2 HAVING start + 3600000000 <= {_MARK}")
def op_tumbling(spark, d):
    s = S.events(spark, d).withWatermark("t", "10 minutes").groupBy(F.window("t", "1 hour").alias("win"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return S.drained(s.select(_us("win.start").alias("start"), "event_type", "n"), "append")


@query("op_stream_sliding", f"SELECT b - k * 1800000000 AS start, count(*) AS n FROM (SELECT ({_MICROS} // 1800000000) * 1800000000 AS b FROM events), (SELECT unnest([0, 1]) AS k) GROUP BY 1 HAVING start + 3600000000 <= {_MARK}")
def op_sliding(spark, d):
    s = S.events(spark, d).withWatermark("t", "10 minutes").groupBy(F.window("t", "1 hour", "30 minutes").alias("win")).agg(F.count(F.lit(1)).alias("n"))
    return S.drained(s.select(_us("win.start").alias("start"), "n"), "append")


@query(
    "op_stream_session",
    f"WITH g AS (SELECT user_id, {_MICROS} AS us, CASE WHEN {_MICROS} - lag({_MICROS}) OVER w < 7200000000 THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY us ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(us) AS start, count(*) AS n FROM s GROUP BY user_id, k HAVING max(us) + 7200000000 <= {_MARK}",
)
def op_session(spark, d):
    s = S.events(spark, d).withWatermark("t", "10 minutes").groupBy(F.session_window("t", "2 hours").alias("win"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return S.drained(s.select("user_id", _us("win.start").alias("start"), "n"), "append")


@query("op_stream_dedup", "SELECT DISTINCT user_id, event_type FROM events")
def op_dedup(spark, d):
    return S.drained(S.events(spark, d).select("user_id", "event_type").dropDuplicates(["user_id", "event_type"]), "append")


@query("op_stream_static_join", "SELECT event_id, c_mktsegment FROM events JOIN customer ON c_custkey = user_id")
def op_static(spark, d):
    c = table(spark, d, "customer")
    return S.drained(S.events(spark, d).join(c, F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment"), "append")


@query("stream_window_scores", "SELECT event_type, sum(round(value * 100)::BIGINT)::BIGINT AS total, count(*) AS n FROM events GROUP BY 1")
def stream_scores(spark, d):
    s = S.events(spark, d).groupBy("event_type").agg(F.sum(F.round(F.col("value") * 100).cast("long")).alias("total"), F.count(F.lit(1)).alias("n"))
    return S.latest(S.drained(s, "update"), ["event_type"])


@query(
    "stream_session_candidates",
    f"WITH g AS (SELECT *, {_MICROS} AS us, CASE WHEN {_MICROS} - lag({_MICROS}) OVER w < 7200000000 THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY us ROWS UNBOUNDED PRECEDING) AS k FROM g), e AS (SELECT user_id, k, min(us) AS start, count(*) AS n, max(us) + 7200000000 AS stop FROM s GROUP BY user_id, k) SELECT e.user_id, start, n, value, event_id FROM e JOIN s USING (user_id, k) WHERE stop <= {_MARK} QUALIFY row_number() OVER (PARTITION BY e.user_id, k ORDER BY value DESC, event_id DESC) = 1",
)
def stream_session_candidates(spark, d):
    return S.drained(S.best_in_session(S.events(spark, d), "user_id", "value", ["event_id"], "t", "2 hours", "10 minutes"), "append")


#: Events held back until the watermark has passed them: every fiftieth of the first half.
_LATE = "event_id % 50 = 7 AND ts < (SELECT min(ts) + (max(ts) - min(ts)) / 2 FROM events)"


@query("op_stream_late_rows", f"WITH a AS (SELECT *, {_LATE} AS late FROM events), win AS (SELECT event_type, ({_MICROS} // 3600000000) * 3600000000 AS start, count(*) AS n FROM a WHERE NOT late GROUP BY 1, 2 HAVING start + 3600000000 <= (SELECT max(epoch_us(ts)) - 600000000 FROM a WHERE NOT late)) SELECT (SELECT count(*) FROM win) AS windows, (SELECT sum(n)::BIGINT FROM win) AS counted, (SELECT count(*) FROM a WHERE late) AS dropped")
def op_late_rows(spark, d):
    """Rows that come after the watermark are dropped, and counted; the windows hold the others."""
    ev = table(spark, d, "events").withColumn("t", F.col("ts").cast("timestamp"))
    lo, hi = ev.agg(F.min(F.unix_micros("t")), F.max(F.unix_micros("t"))).first()
    late = (F.col("event_id") % 50 == 7) & (F.unix_micros("t") * 2 < lo + hi)
    rows = ev.select("event_id", "event_type", "t")
    on_time, held = rows.filter(~late), rows.filter(late)
    last = on_time.orderBy(F.desc("t"), "event_id").limit(1)  # a batch of its own moves the watermark before the late rows come
    told: list[str] = []
    state: list[str] = []
    s = S.replayed(spark, [on_time.join(last.select("event_id"), "event_id", "left_anti"), last, held]).withWatermark("t", "10 minutes")
    g = s.groupBy(F.window("t", "1 hour").alias("win"), "event_type").agg(F.count(F.lit(1)).alias("count"))
    out = S.drained(g.select(_us("win.start").alias("start"), "event_type", F.col("count").alias("n")), "append", told, state)
    # The stream's own metric counts late rows after each task has summed them by window, so rows are told apart by where they went.
    left = S.came(told) - S.waiting(spark, state[0])
    return out.agg(F.count(F.lit(1)).alias("windows"), F.sum("n").alias("counted")).withColumn("dropped", F.lit(left) - F.coalesce("counted", F.lit(0)))
