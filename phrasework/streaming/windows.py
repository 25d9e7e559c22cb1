"""Event streams as symbol sequences, parsed when their window has closed.

A two-way parse needs what comes later, so only closed windows are parsed; the left parse needs
the past alone and also runs online.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from phrasework.operators.parse import counts
from phrasework.shared import own_path

# One letter for each event type.
SYMBOLS = {"signup": "s", "view": "v", "error": "e", "click": "c", "purchase": "p"}
WATERMARK, SESSION_GAP = "1 hour", "30 minutes"


def symbol(event_type: Column) -> Column:
    """The event's letter; ``?`` for an unknown type."""
    found = F.lit("?")
    for name, letter in SYMBOLS.items():
        found = F.when(event_type == name, letter).otherwise(found)
    return found


def read_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """The events table as a stream of its files."""
    schema = spark.read.parquet(path).schema
    reader = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger)
    folder, name = path.rstrip("/").rsplit("/", 1)
    stream = reader.option("pathGlobFilter", name).parquet(folder) if spark.read.parquet(path).inputFiles()[0].rstrip("/").endswith(f"/{name}") else reader.parquet(path)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))  # a watermark needs an instant


def sequences(events: DataFrame, window: Column) -> DataFrame:
    """(user_id, begin, end, text): each user's symbols of a window in time order."""
    letters = F.array_sort(F.collect_list(F.struct("ts", "event_id", symbol(F.col("event_type")).alias("letter"))))
    grouped = events.groupBy(window.alias("w"), "user_id").agg(F.array_join(F.transform(letters, lambda x: x["letter"]), "").alias("text"))
    return grouped.select("user_id", F.col("w.start").alias("begin"), F.col("w.end").alias("end"), "text")


def window_counts(events: DataFrame, window: Column, watermark: str | None = WATERMARK, method: str = "two_way") -> DataFrame:
    """(string_id, n, phrases) of every closed window; batch tables work alike without a watermark."""
    if watermark:
        events = events.withWatermark("ts", watermark)
    rows = sequences(events, window)
    key = F.concat_ws("@", "user_id", F.unix_micros(F.col("begin").cast("timestamp")))
    return counts(rows.select(key.alias("string_id"), "text"), (method,), ("forward",)).select("string_id", "n", "phrases")


def tumbling(length: str = "1 day") -> Column:
    return F.window("ts", length)


def sliding(length: str = "1 day", slide: str = "12 hours") -> Column:
    return F.window("ts", length, slide)


def session(gap: str = SESSION_GAP) -> Column:
    return F.session_window("ts", gap)


ONLINE = "user_id bigint, closed bigint, open_length bigint, n bigint"
#: Characters after which an online parse closes its text and begins a new one.
ONLINE_CHARS = 1 << 16


def online_left_parse(events: DataFrame, most_chars: int = ONLINE_CHARS) -> DataFrame:
    """Phrases closed so far of each user's left parse, updated with every batch of events.

    State is the text so far and the start of the phrase still open; events of a batch are
    taken in time order and later batches follow. After ``most_chars`` characters the open phrase is
    closed and the next event begins a new text, so a user's state and an event's work are bounded.
    """

    def step(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        text, begin, closed, n = state.get if state.exists else ("", 0, 0, 0)
        new = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        for letter in new["letter"]:
            n += 1
            if len(text) >= most_chars:
                text, begin, closed = "", 0, closed + (begin < len(text))
            text += letter
            # The open phrase goes on while it also starts further left; it may overlap itself.
            if begin < len(text) - 1 and text.find(text[begin:], 0, len(text) - 1) >= 0:
                continue
            if begin < len(text) - 1:  # the phrase closed before this letter, which opens the next
                closed, begin = closed + 1, len(text) - 1
            if text.find(letter, 0, len(text) - 1) < 0:
                closed, begin = closed + 1, len(text)
        state.update((text, begin, closed, n))
        yield pd.DataFrame({"user_id": [key[0]], "closed": [closed], "open_length": [len(text) - begin], "n": [n]})

    rows = events.select("user_id", "ts", "event_id", symbol(F.col("event_type")).alias("letter"))
    return rows.groupBy("user_id").applyInPandasWithState(step, ONLINE, "text string, begin int, closed int, n int", "update", "NoTimeout")


def run_to_table(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there, then return its rows."""
    spark = stream.sparkSession
    path = own_path(spark, name)
    if mode == "append":
        query = stream.writeStream.format("parquet").option("checkpointLocation", f"{path}/state").option("path", f"{path}/rows").trigger(availableNow=True).start()
        query.awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{path}/rows")
    parts: list[str] = []

    def keep(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{path}/rows/{number}")
        parts.append(f"{path}/rows/{number}")

    query = stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.parquet(*parts)
