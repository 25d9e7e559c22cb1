"""Strings as DataFrames: characters, reversal, occurrences, common extensions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from phrasework.operators.batches import map_strings

#: A pattern table of at most this many rows is broadcast.
BROADCAST_PATTERNS = 10_000


def strings(df: DataFrame, id_col: str = "string_id", text_col: str = "text", prefix: str = "") -> DataFrame:
    """STRINGS (string_id, text) of any table with a key and a text."""
    return df.select(F.concat(F.lit(prefix), F.col(id_col).cast("string")).alias("string_id"), F.col(text_col).alias("text"))


def chars(S: DataFrame) -> DataFrame:
    """CHARS: one row a character, ``ch`` its code point; null and empty texts have none."""
    split = F.filter(F.split("text", ""), lambda c: c != "")
    return S.select("string_id", F.posexplode(split).alias("p", "c")).select("string_id", (F.col("p") + 1).cast("bigint").alias("pos"), F.ascii("c").alias("ch"))


def reversed_strings(S: DataFrame) -> DataFrame:
    """Every text read from its end, by code points."""
    return S.select("string_id", F.reverse("text").alias("text"))


def collection(df: DataFrame, key: str, order: list[str], text_col: str = "text", separator: str = "\n", prefix: str = "") -> DataFrame:
    """One string a key: its texts in order, joined; (string_id, text, parts)."""
    parts = F.array_sort(F.collect_list(F.struct(*order, F.col(text_col).alias("part"))))
    return (
        df.where(F.col(text_col).isNotNull())
        .groupBy(F.concat(F.lit(prefix), F.col(key).cast("string")).alias("string_id"))
        .agg(F.array_join(F.transform(parts, lambda x: x["part"]), separator).alias("text"), F.count(F.lit(1)).cast("int").alias("parts"))
    )


def occurrences(S: DataFrame, patterns: DataFrame, broadcast_rows: int = BROADCAST_PATTERNS) -> DataFrame:
    """OCC (string_id, pattern, pos): every place of every pattern, overlapping ones too.

    While the pattern table's checked size allows, one automaton of all patterns is broadcast and
    reads each text once; a larger table meets the texts by an equi-join on the patterns' first
    characters, taken at the shortest pattern's length.
    """
    wanted = patterns.where("pattern <> ''").select("pattern").distinct()
    size = F.length("pattern")
    if wanted.limit(broadcast_rows + 1).count() <= broadcast_rows:
        shared = S.sparkSession.sparkContext.broadcast([r[0] for r in wanted.collect()])
        machine: list = []

        def places(key: str, text: str):
            if not machine:
                machine.append(_automaton(shared.value))
            if machine[0] is not None:
                for end, pattern in machine[0].iter(text):
                    yield key, pattern, end - len(pattern) + 2

        return map_strings(S, "string_id string, pattern string, pos bigint", places)
    head = wanted.agg(F.min(F.length("pattern"))).first()[0]
    starts = F.explode(F.sequence(F.lit(1), F.length("text") - head + 1)).alias("pos")
    grams = S.where(F.length("text") >= head).select("string_id", "text", starts).withColumn("gram", F.substring("text", F.col("pos"), F.lit(head)))
    keyed = wanted.withColumn("gram", F.substring("pattern", 1, head))
    return grams.join(keyed, "gram").where(F.substring("text", F.col("pos"), size) == F.col("pattern")).select("string_id", "pattern", F.col("pos").cast("bigint").alias("pos"))


def _automaton(patterns: list[str]):
    import ahocorasick

    if not patterns:
        return None
    found = ahocorasick.Automaton()
    for pattern in patterns:
        found.add_word(pattern, pattern)
    found.make_automaton()
    return found


def lcp_len(x: Column, y: Column) -> Column:
    """Length of the longest common prefix of two string columns, without a UDF.

    A binary descent: each step compares one pair of substrings of half the length before, so the
    work is proportional to the shorter string.
    """
    both = F.least(F.length(x), F.length(y))
    bits = F.transform(F.sequence(F.lit(0), F.lit(30)), lambda k: F.pow(F.lit(2), F.lit(30) - k).cast("int"))
    steps = F.filter(bits, lambda w: w <= both)
    return F.aggregate(steps, F.lit(0), lambda done, w: F.when((done + w <= both) & (F.substring(x, done + 1, w) == F.substring(y, done + 1, w)), done + w).otherwise(done))


def closer_to(x: Column, y: Column, z: Column) -> Column:
    """Whether x shares a longer prefix with z than y does."""
    return lcp_len(x, z) > lcp_len(y, z)


def lce(S: DataFrame, pairs: DataFrame) -> DataFrame:
    """LCE (string_id, i, j, lce) of given pairs of positions."""
    return pairs.join(S, "string_id").select(
        "string_id", "i", "j", lcp_len(F.col("text").substr(F.col("i").cast("int"), F.length("text")), F.col("text").substr(F.col("j").cast("int"), F.length("text"))).cast("bigint").alias("lce")
    )


def lce_matrix(S: DataFrame) -> DataFrame:
    """LCE of all pairs i < j of each short string, by the next mismatch on each diagonal."""
    c = chars(S)
    a, b = c.select("string_id", F.col("pos").alias("i"), F.col("ch").alias("x")), c.select("string_id", F.col("pos").alias("j"), F.col("ch").alias("y"))
    on = Window.partitionBy("string_id", "gap").orderBy(F.desc("i")).rowsBetween(Window.unboundedPreceding, 0)
    last = Window.partitionBy("string_id")
    rows = a.join(b, "string_id").where("i < j").withColumn("gap", F.col("j") - F.col("i")).withColumn("n", F.max("j").over(last))
    miss = F.min(F.when(F.col("x") != F.col("y"), F.col("i"))).over(on)
    return rows.select("string_id", "i", "j", (F.coalesce(miss, F.col("n") - F.col("gap") + 1) - F.col("i")).alias("lce"))


def space_model(n: Column, words: int, bits: int = 0) -> Column:
    """Bytes of ``words`` 8-byte words and ``bits`` bits a position."""
    return n * F.lit(8 * words) + F.ceil(n * F.lit(bits) / 8)
