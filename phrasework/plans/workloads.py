"""The strings of each workload, from the given tables."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from phrasework.operators.parse import CHARS_PER_TASK, balanced, distinct_texts
from phrasework.operators.strings import collection, strings
from phrasework.shared import materialize
from phrasework.sources import generators
from phrasework.streaming.windows import symbol

def table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


def benchmark(spark: SparkSession, folder: str) -> DataFrame:
    return strings(table(spark, folder, "benchmark"), "item_id")


def documents(spark: SparkSession, folder: str) -> DataFrame:
    return strings(table(spark, folder, "documents"), "doc_id")


def by_source(spark: SparkSession, folder: str) -> DataFrame:
    return collection(table(spark, folder, "documents"), "source", ["doc_id"]).select("string_id", "text")


def by_lang(spark: SparkSession, folder: str) -> DataFrame:
    return collection(table(spark, folder, "documents"), "lang", ["doc_id"]).select("string_id", "text")


def conversations(spark: SparkSession, folder: str) -> DataFrame:
    return collection(table(spark, folder, "conversations"), "conv_id", ["turn"]).select("string_id", "text")


def pages_by_host(spark: SparkSession, folder: str) -> DataFrame:
    rows = table(spark, folder, "pages").withColumn("host", F.regexp_extract("url", "://([^/?#]*)", 1))
    return collection(rows, "host", ["page_id"], "html").select("string_id", "text")


def events_by_user(spark: SparkSession, folder: str) -> DataFrame:
    rows = table(spark, folder, "events").withColumn("letter", symbol(F.col("event_type")))
    return collection(rows, "user_id", ["ts", "event_id"], "letter", "").select("string_id", "text")


def events_by_day(spark: SparkSession, folder: str) -> DataFrame:
    rows = table(spark, folder, "events").withColumn("letter", symbol(F.col("event_type"))).withColumn("day", F.date_format("ts", "yyyy-MM-dd"))
    return collection(rows, "day", ["ts", "event_id"], "letter", "").select("string_id", "text")


def _flags(spark: SparkSession, folder: str) -> DataFrame:
    rows = table(spark, folder, "lineitem").withColumn("letter", F.translate(F.substring("l_returnflag", 1, 1), "ANR", "anr"))
    return rows.withColumn("letter", F.when(F.col("l_linestatus") == "F", F.upper("letter")).otherwise(F.col("letter")))


def flags_by_supplier(spark: SparkSession, folder: str) -> DataFrame:
    return collection(_flags(spark, folder), "l_suppkey", ["l_orderkey", "l_linenumber", "l_partkey", "l_quantity", "l_extendedprice"], "letter", "").select("string_id", "text")


def flags_by_part(spark: SparkSession, folder: str) -> DataFrame:
    """Return flag and line status of a part's lines, one letter a pair."""
    return collection(_flags(spark, folder), "l_partkey", ["l_orderkey", "l_linenumber", "l_suppkey", "l_quantity", "l_extendedprice"], "letter", "").select("string_id", "text")


def status_by_customer(spark: SparkSession, folder: str) -> DataFrame:
    return collection(table(spark, folder, "orders"), "o_custkey", ["o_orderdate", "o_orderkey"], "o_orderstatus", "").select("string_id", "text")


def status_by_month(spark: SparkSession, folder: str) -> DataFrame:
    rows = table(spark, folder, "orders").withColumn("month", F.date_format("o_orderdate", "yyyy-MM"))
    return collection(rows, "month", ["o_orderdate", "o_orderkey"], "o_orderstatus", "").select("string_id", "text")


def part_names(spark: SparkSession, folder: str) -> DataFrame:
    return strings(table(spark, folder, "part"), "p_partkey", "p_name")


#: Copies of a base string, and rates at which characters change, in the mutated workloads.
COPIES, RATES = 4, (0.00001, 0.0001, 0.001, 0.01)


def bases(spark: SparkSession, folder: str) -> DataFrame:
    """Strings of five kinds of text, whole: prose passages, chats, event days, order histories, return flags."""
    kinds = {"passage": benchmark, "chat": conversations, "day": events_by_day, "orders": status_by_month, "flags": flags_by_supplier}
    parts = [make(spark, folder).select(F.concat(F.lit(f"{kind}:"), "string_id").alias("string_id"), "text") for kind, make in kinds.items()]
    return reduce(DataFrame.unionByName, parts)


def mutated(spark: SparkSession, folder: str, copies: int = COPIES, rates: tuple[float, ...] = RATES) -> DataFrame:
    """Both kinds of mutated copies, at all rates, of every base string."""
    made = generators.mutated_copies(bases(spark, folder), copies, list(rates))
    return made.select(F.concat_ws("-", "string_id", "kind", F.format_string("%.5f", "rate")).alias("string_id"), "text")


def mutated_once(spark: SparkSession, folder: str) -> tuple[DataFrame, DataFrame]:
    """The different texts among the mutated copies, under keys of their own, and (string_id, key) of every copy.

    Equal bases are mutated once, and what several kinds and rates make of a base is one text. Only
    bases are shuffled; the copies stay in the tasks that make them, with the longest noted.
    """
    texts, keys = distinct_texts(materialize(bases(spark, folder), "bases"))
    dealt = balanced(texts, CHARS_PER_TASK // (2 * COPIES * len(RATES)))
    label = lambda m: F.concat_ws("-", m["kind"], F.format_string("%.5f", m["rate"]))
    made = generators.distinct_copies(dealt, COPIES, list(RATES))
    once = made.select(F.concat_ws(" ", "string_id", F.array_join(F.transform("made", label), ",")).alias("string_id"), "text")
    once._longest = COPIES * dealt._longest
    return once, keys


def of_mutated(rows: DataFrame, keys: DataFrame) -> DataFrame:
    """Rows of the texts of :func:`mutated_once` for every mutated copy that has the text."""
    base, made = F.split("string_id", " ")[0], F.split(F.split("string_id", " ")[1], ",")
    each = rows.select(base.alias("key"), F.explode(made).alias("made"), *(c for c in rows.columns if c != "string_id"))
    return keys.join(each, "key").withColumn("string_id", F.concat_ws("-", "string_id", "made")).select(*rows.columns)


def families(spark: SparkSession) -> DataFrame:
    """Generated words up to lengths that every baseline takes in a moment."""
    parts = [generators.fibonacci(spark, 4, 20), generators.thue_morse(spark, 4, 12), generators.run_rich(spark, 6, 14)]
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).select("string_id", "text")
