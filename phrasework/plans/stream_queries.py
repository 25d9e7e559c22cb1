"""Streaming queries over the events table, and their batch twins."""

from __future__ import annotations

from pyspark.sql import functions as F

from phrasework.plans import oracles as O
from phrasework.plans import workloads as W
from phrasework.plans.registry import query
from phrasework.shared import own_path
from phrasework.streaming import windows as S
from phrasework.streaming.windows import read_events, run_to_table


def _window_sizes(window: str, where: str = "") -> str:
    return f"SELECT user_id || '@' || epoch_us({window}) AS string_id, count(*) AS n FROM events {where} GROUP BY 1"


@query(_window_sizes("date_trunc('day', ts)"))
def op_window_tumbling(spark, folder):
    return S.window_counts(W.table(spark, folder, "events"), S.tumbling(), None).select("string_id", "n")


@query("WITH w AS (SELECT user_id, time_bucket(INTERVAL 12 HOUR, ts) AS a FROM events), b AS (SELECT user_id, unnest([a, a - INTERVAL 12 HOUR]) AS a FROM w) SELECT user_id || '@' || epoch_us(a) AS string_id, count(*) AS n FROM b GROUP BY 1")
def op_window_sliding(spark, folder):
    return S.window_counts(W.table(spark, folder, "events"), S.sliding(), None).select("string_id", "n")


@query(
    "WITH g AS (SELECT user_id, ts, event_id, coalesce(ts >= lag(ts) OVER w + INTERVAL 30 MINUTE, true) AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), "
    "k AS (SELECT user_id, ts, sum(CAST(new AS INT)) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM g) SELECT user_id || '@' || epoch_us(min(ts)) AS string_id, count(*) AS n FROM k GROUP BY user_id, s"
)
def op_window_session(spark, folder):
    return S.window_counts(W.table(spark, folder, "events"), S.session(), None).select("string_id", "n")


_SEQUENCE = f"string_agg({O.LETTER}, '' ORDER BY ts, event_id)"
_CLOSED = "(SELECT max(ts) - INTERVAL 1 HOUR FROM events)"
_DAYS = f"SELECT user_id || '@' || epoch_us(date_trunc('day', ts)) AS string_id, {_SEQUENCE} AS text FROM events GROUP BY user_id, date_trunc('day', ts) HAVING date_trunc('day', ts) + INTERVAL 1 DAY <= {_CLOSED}"
_SESSIONS = (
    "WITH g AS (SELECT *, coalesce(ts >= lag(ts) OVER w + INTERVAL 30 MINUTE, true) AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), "
    "k AS (SELECT *, sum(CAST(new AS INT)) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM g) "
    f"SELECT user_id || '@' || epoch_us(min(ts)) AS string_id, {_SEQUENCE} AS text FROM k GROUP BY user_id, s HAVING max(ts) + INTERVAL 30 MINUTE <= {_CLOSED}"
)


def _parsed(strings: str) -> str:
    return f"SELECT string_id, CAST(sum(length) AS BIGINT) AS n, count(*) AS phrases FROM ({O.two_way(strings)}) GROUP BY 1"


@query(_parsed(_DAYS))
def st_window_parse(spark, folder):
    """Daily windows of the stream, parsed once closed; the last day stays open."""
    return run_to_table(S.window_counts(read_events(spark, f"{folder}/events.parquet"), S.tumbling()), "st-window")


@query(_parsed(_SESSIONS))
def st_session_parse(spark, folder):
    return run_to_table(S.window_counts(read_events(spark, f"{folder}/events.parquet"), S.session()), "st-session")


@query("SELECT user_id, count(*) AS n FROM events GROUP BY 1")
def st_incremental_lz77(spark, folder):
    """Online left parse; the last state of each user has taken all its events."""
    rows = run_to_table(S.online_left_parse(read_events(spark, f"{folder}/events.parquet")), "st-online", "update")
    return rows.groupBy("user_id").agg(F.max("n").alias("n"))


_MIDDLE = "(SELECT min(ts) + (max(ts) - min(ts)) / 2 FROM events)"
_FIRST_MARK = f"(SELECT max(ts) - INTERVAL 1 HOUR FROM events WHERE ts >= {_MIDDLE} AND event_id % 2 = 0)"
_LATE = f"ts < {_MIDDLE} AND date_trunc('hour', ts) + INTERVAL 1 HOUR <= {_FIRST_MARK}"
_OPEN = f"date_trunc('hour', ts) + INTERVAL 1 HOUR > {_CLOSED}"


@query(f"SELECT count(*) FILTER (NOT ({_LATE}) AND NOT ({_OPEN})) AS closed, count(*) FILTER ({_OPEN}) AS still_open, count(*) FILTER ({_LATE}) AS late FROM events")
def st_late_data(spark, folder):
    """A stream of three files, the earlier half of the events last: rows that the watermark has passed are dropped.

    Late rows are told by the watermark that held two batches before, so one file stands in between.
    """
    events = W.table(spark, folder, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    ends = events.agg(F.min(F.unix_micros("ts")).alias("a"), F.max(F.unix_micros("ts")).alias("b")).first()
    later, even = F.unix_micros("ts") >= (ends.a + (ends.b - ends.a) / 2 if ends.a is not None else 0), F.col("event_id") % 2 == 0
    path = own_path(spark, "three-files")
    for part in (later & even, later & ~even, ~later):
        events.where(part).coalesce(1).write.mode("append").parquet(path)
    stream = read_events(spark, path).withWatermark("ts", S.WATERMARK)
    kept = run_to_table(stream.groupBy(F.window("ts", "1 hour")).agg(F.count(F.lit(1)).alias("n")), "st-late").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("closed"))
    last = F.unix_micros(F.date_trunc("hour", "ts")) + 3_600_000_000 > (ends.b or 0) - 3_600_000_000
    seen = events.agg(F.count_if(last).alias("still_open"), F.count(F.lit(1)).alias("all"))
    return kept.join(seen).select("closed", "still_open", (F.col("all") - F.col("still_open") - F.col("closed")).alias("late"))


@query("SELECT count(DISTINCT event_id) AS events FROM events")
def st_dedup(spark, folder):
    stream = read_events(spark, f"{folder}/events.parquet")
    # Copies come within an hour of each other; older keys leave the state.
    both = stream.unionByName(read_events(spark, f"{folder}/events.parquet")).withWatermark("ts", S.WATERMARK)
    return run_to_table(both.dropDuplicatesWithinWatermark(["event_id"]).select("event_id"), "st-dedup").agg(F.count(F.lit(1)).alias("events"))


@query("SELECT event_id, c_name FROM events JOIN customer ON user_id = c_custkey")
def st_static_join(spark, folder):
    customers = W.table(spark, folder, "customer").select("c_custkey", "c_name")
    stream = read_events(spark, f"{folder}/events.parquet")
    return run_to_table(stream.join(customers, F.col("user_id") == F.col("c_custkey")).select("event_id", "c_name"), "st-join")
