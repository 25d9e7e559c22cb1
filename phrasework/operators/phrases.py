"""Parses as data: partition checks, reference graphs, validity, sources, decoding, storage."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from phrasework import schemas
from phrasework.operators.strings import chars
from phrasework.shared import materialize, release

#: Rounds of pointer doubling: enough for chains of 2**40 references.
MAX_ROUNDS = 40
#: Positions in one block of the interval join.
BLOCK = 1 << 12


def check_partition(phrases: DataFrame, S: DataFrame) -> DataFrame:
    """Violations (string_id, phrase_no, problem): gaps, empty phrases, bad or self references, unequal copies."""
    w = Window.partitionBy("string_id").orderBy("start")
    rows = phrases.join(S.select("string_id", "text"), "string_id", "left").withColumn("due", F.coalesce(F.lag(F.col("start") + F.col("length")).over(w), F.lit(1)))
    size = F.length("text")
    own, other = F.substring("text", F.col("start").cast("int"), F.col("length").cast("int")), F.substring("text", F.col("ref").cast("int"), F.col("length").cast("int"))
    problem = (
        F.when(F.col("text").isNull(), "no text")
        .when(F.col("length") < 1, "empty phrase")
        .when(F.col("start") != F.col("due"), "gap or overlap")
        .when(F.col("start") + F.col("length") - 1 > size, "beyond the end")
        .when(F.col("ref").isNull() & ((F.col("length") != 1) | (F.col("literal") != own)), "wrong literal")
        .when(F.col("ref") == F.col("start"), "refers to itself")
        .when((F.col("ref") < 1) | (F.col("ref") + F.col("length") - 1 > size), "reference out of range")
        .when(own != other, "unequal copy")
    )
    found = rows.select("string_id", "phrase_no", problem.alias("problem")).where("problem is not null")
    ends = phrases.groupBy("string_id").agg(F.sum("length").alias("covered"))
    short = S.where("length(text) > 0").join(ends, "string_id", "left").where("covered is null or covered <> length(text)").select("string_id", F.lit(None).cast("int").alias("phrase_no"), F.lit("not covered").alias("problem"))
    return found.unionByName(short)


def reference_graph(phrases: DataFrame) -> DataFrame:
    """REFGRAPH: one row a position, its target or its literal."""
    offset = F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("length") - 1)).alias("k")
    rows = phrases.select("string_id", "start", "ref", "literal", offset)
    return rows.select("string_id", (F.col("start") + F.col("k")).alias("pos"), (F.col("ref") + F.col("k")).alias("target"), F.when(F.col("ref").isNull(), F.col("literal")).alias("literal"))


def square(graph: DataFrame) -> DataFrame:
    """The graph followed twice; rows that end in a literal stay as they are."""
    ahead = graph.select("string_id", F.col("pos").alias("target"), F.col("target").alias("further"), F.col("literal").alias("found"))
    on = graph.join(ahead, ["string_id", "target"], "left")
    return on.select("string_id", "pos", F.when(F.col("target").isNotNull(), F.col("further")).alias("target"), F.coalesce("literal", "found").alias("literal"))


def follow(graph: DataFrame, hops: int) -> DataFrame:
    """The graph after ``hops`` references (1: as it is), by squares of it."""
    if hops < 1:
        raise ValueError("hops must be positive")
    out, power, left = None, graph, hops
    while left:
        if left & 1:
            out = power if out is None else compose(out, power)
        left >>= 1
        if left:
            power = square(power)
    return out


def compose(first: DataFrame, then: DataFrame) -> DataFrame:
    """Follow ``first`` and from where it leads ``then``."""
    ahead = then.select("string_id", F.col("pos").alias("target"), F.col("target").alias("further"), F.col("literal").alias("found"))
    return first.join(ahead, ["string_id", "target"], "left").select("string_id", "pos", F.when(F.col("target").isNotNull(), F.col("further")).alias("target"), F.coalesce("literal", "found").alias("literal"))


def sources(graph: DataFrame) -> DataFrame:
    """SOURCES (string_id, pos, source, literal, hops); source null where the chase never ends.

    Pointer doubling in which settled rows leave: they are written once, when they reach a literal, and
    only open rows are joined and written again. A round looks up where each open row points to among both.
    """
    settled = [graph.where("target is null").select("string_id", "pos", F.col("pos").alias("source"), "literal", F.lit(0).cast("bigint").alias("hops"))]
    first = graph.where("target is not null").select("string_id", "pos", F.col("target").alias("at"), F.lit(1).cast("bigint").alias("hops"))
    open_rows = materialize(first, "open")
    sizes = graph.groupBy("string_id").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0] or 0
    for _ in range(max(1, int(sizes)).bit_length() + 1):
        if open_rows.isEmpty():
            break
        known = reduce(DataFrame.unionByName, settled).select("string_id", F.col("pos").alias("at"), "source", "literal", F.lit(None).cast("bigint").alias("further"), F.col("hops").alias("more"))
        ahead = known.unionByName(open_rows.select("string_id", F.col("pos").alias("at"), F.lit(None).cast("bigint").alias("source"), F.lit(None).cast("string").alias("literal"), F.col("at").alias("further"), F.col("hops").alias("more")))
        moved = materialize(open_rows.join(ahead, ["string_id", "at"], "left").select("string_id", "pos", "source", "literal", "further", (F.col("hops") + F.coalesce("more", F.lit(0))).alias("hops")), "moved")
        settled.append(moved.where("source is not null").select("string_id", "pos", "source", "literal", "hops"))
        before, open_rows = open_rows, materialize(moved.where("source is null and further is not null").select("string_id", "pos", F.col("further").alias("at"), "hops"), "open")
        settled.append(moved.where("source is null and further is null").select("string_id", "pos", F.lit(None).cast("bigint").alias("source"), "literal", "hops"))
        release(before)
    never = open_rows.select("string_id", "pos", F.lit(None).cast("bigint").alias("source"), F.lit(None).cast("string").alias("literal"), F.lit(None).cast("bigint").alias("hops"))
    found = reduce(DataFrame.unionByName, settled).unionByName(never)
    return found.select("string_id", "pos", "source", F.when(F.col("source").isNotNull(), F.col("literal")).alias("literal"), F.when(F.col("source").isNotNull(), F.col("hops")).alias("hops"))


def is_valid(phrases: DataFrame) -> DataFrame:
    """(string_id, valid): whether every position's chain of references ends in a literal."""
    return sources(reference_graph(phrases)).groupBy("string_id").agg((F.count(F.when(F.col("source").isNull(), 1)) == 0).alias("valid"))


def cyclic_positions(graph: DataFrame) -> DataFrame:
    """Positions whose chain never ends."""
    return sources(graph).where("source is null").select("string_id", "pos")


def decode(phrases: DataFrame) -> DataFrame:
    """STRINGS of parses; a parse that does not decode gives a null text."""
    found = sources(reference_graph(phrases))
    text = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("pos", "literal"))), lambda x: x["literal"]), "")
    return found.groupBy("string_id").agg(F.when(F.count(F.when(F.col("source").isNull(), 1)) == 0, text).alias("text"))


def complete_with_literals(prefix: DataFrame, S: DataFrame) -> DataFrame:
    """PHRASES of a partial parse and one literal for each position behind it."""
    ends = prefix.groupBy("string_id").agg(F.max(F.col("start") + F.col("length")).alias("end"), F.max("phrase_no").alias("last"))
    split = F.posexplode(F.filter(F.split("text", ""), lambda c: c != "")).alias("p", "literal")
    rest = S.join(ends, "string_id", "left").select("string_id", "end", "last", split).where("p + 1 >= coalesce(end, 1)")
    rest = rest.select(
        "string_id",
        (F.coalesce("last", F.lit(0)) + F.col("p") + 2 - F.coalesce("end", F.lit(1))).cast("int").alias("phrase_no"),
        (F.col("p") + 1).cast("bigint").alias("start"),
        F.lit(1).cast("bigint").alias("length"),
        F.lit(None).cast("bigint").alias("ref"),
        "literal",
        F.lit("literal").alias("side"),
    )
    return prefix.select(*schemas.names(schemas.PHRASES)).unionByName(rest)


def is_valid_partial(prefix: DataFrame, S: DataFrame) -> DataFrame:
    return is_valid(complete_with_literals(prefix, S))


def source_of(prefix: DataFrame, S: DataFrame) -> DataFrame:
    """SOURCES of a partial parse after completion."""
    return sources(reference_graph(complete_with_literals(prefix, S)))


def source_classes(found: DataFrame) -> DataFrame:
    """(string_id, source, members): positions with one source."""
    return found.where("source is not null").groupBy("string_id", "source").agg(F.sort_array(F.collect_list("pos")).alias("members"))


def can_extend(prefix: DataFrame, S: DataFrame, ref: int, size: int) -> DataFrame:
    """(string_id, valid): may the copy of ``ref`` behind each prefix grow from ``size - 1`` to ``size``?

    It may if the two characters are equal and, the shorter copy being appended, the two
    positions have different sources.
    """
    ends = S.select("string_id", "text").join(prefix.groupBy("string_id").agg(F.max(F.col("start") + F.col("length")).alias("at"), F.max("phrase_no").alias("last")), "string_id", "left")
    ends = ends.select("string_id", "text", F.coalesce("at", F.lit(1)).cast("bigint").alias("at"), F.coalesce("last", F.lit(0)).alias("last"))
    grown = prefix.select(*schemas.names(schemas.PHRASES))
    if size > 1:
        shorter = ends.select("string_id", (F.col("last") + 1).cast("int").alias("phrase_no"), F.col("at").alias("start"), F.lit(size - 1).cast("bigint").alias("length"), F.lit(ref).cast("bigint").alias("ref"), F.lit(None).cast("string").alias("literal"), F.when(F.col("at") > ref, "left").otherwise("right").alias("side"))
        grown = grown.unionByName(shorter)
    found = source_of(grown, S).select("string_id", "pos", "source")
    new, old = (F.col("at") + size - 1).cast("int"), F.lit(ref + size - 1)
    same = F.substring("text", new, F.lit(1)) == F.substring("text", old, F.lit(1))
    a = found.select("string_id", F.col("pos").alias("p"), F.col("source").alias("a"))
    b = found.where(F.col("pos") == ref + size - 1).select("string_id", F.col("source").alias("b"))
    rows = ends.withColumn("p", new).join(a, ["string_id", "p"], "left").join(b, "string_id", "left")
    return rows.select("string_id", F.coalesce(same & (F.col("a") != F.col("b")), F.lit(False)).alias("valid"))


def covering(phrases: DataFrame, positions: DataFrame, block: int = BLOCK) -> DataFrame:
    """Each (string_id, pos) with the phrase that covers it, by an equi-join on blocks of positions."""

    def of(x: Column) -> Column:
        return F.floor(x / block)

    spread = phrases.withColumn("block", F.explode(F.sequence(of(F.col("start")), of(F.col("start") + F.col("length") - 1))))
    asked = positions.select("string_id", "pos", of(F.col("pos")).alias("block"))
    return asked.join(spread, ["string_id", "block"]).where("start <= pos and pos < start + length").drop("block")


def char_at(phrases: DataFrame, positions: DataFrame, max_hops: int = 64) -> DataFrame:
    """(string_id, pos, ch) without decoding the rest: positions hop through covering phrases.

    Chains may be as long as their string; what ``max_hops`` leave open is resolved by pointer
    doubling over the strings concerned. Null only where a chain never ends.
    """
    rows = positions.select("string_id", "pos", F.col("pos").alias("at"), F.lit(None).cast("string").alias("ch"))
    for _ in range(max_hops):
        open_rows = rows.where("ch is null")
        hop = covering(phrases, open_rows.select("string_id", F.col("at").alias("pos")).distinct()).select("string_id", F.col("pos").alias("at"), F.when(F.col("ref").isNotNull(), F.col("ref") + F.col("pos") - F.col("start")).alias("to"), F.col("literal").alias("got"))
        moved = open_rows.drop("ch").join(hop, ["string_id", "at"]).select("string_id", "pos", F.coalesce("to", "at").alias("at"), F.when(F.col("to").isNull(), F.col("got")).alias("ch"))
        rows = materialize(rows.where("ch is not null").unionByName(moved), "hops")
        if rows.where("ch is null").isEmpty():
            return rows.select("string_id", "pos", "ch")
    open_rows = rows.where("ch is null").select("string_id", "pos", "at")
    graph = reference_graph(phrases.join(open_rows.select("string_id").distinct(), "string_id", "left_semi"))
    found = sources(graph).select("string_id", F.col("pos").alias("at"), F.col("literal").alias("ch"))
    return rows.where("ch is not null").select("string_id", "pos", "ch").unionByName(open_rows.join(found, ["string_id", "at"], "left").select("string_id", "pos", "ch"))


def write_phrases(phrases: DataFrame, path: str, fmt: str = "parquet", partition_by: str | None = None) -> None:
    """Store phrases, sorted within files; any built-in format."""
    writer = phrases.sortWithinPartitions("string_id", "phrase_no").write.format(fmt)
    if fmt == "csv":
        writer = writer.option("header", True)
    (writer.partitionBy(partition_by) if partition_by else writer).save(path)


def read_phrases(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    reader = spark.read.format(fmt).schema(schemas.PHRASES)
    return (reader.option("header", True) if fmt == "csv" else reader).load(path)


def nested(phrases: DataFrame) -> DataFrame:
    """One row a string: its phrases as an array of structs."""
    piece = F.struct("phrase_no", "start", "length", "ref", "literal", "side")
    return phrases.groupBy("string_id").agg(F.array_sort(F.collect_list(piece)).alias("phrases"))
