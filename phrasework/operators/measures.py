"""Measures over counts, phrases, traces and reference graphs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from phrasework.operators.parse import best_direction
from phrasework.operators.phrases import reference_graph, sources


def phrase_counts(phrases: DataFrame) -> DataFrame:
    """Phrases, literals and copies of each string, from phrase rows."""
    copy = F.col("ref").isNotNull()
    return phrases.groupBy("string_id").agg(
        F.sum("length").alias("n"), F.count(F.lit(1)).alias("phrases"), F.count(F.when(~copy, 1)).alias("literals"), F.count(F.when(copy, 1)).alias("copies")
    )


def best_counts(counted: DataFrame) -> DataFrame:
    return best_direction(counted).select("string_id", "n", "method", "direction", "phrases")


def table(counted: DataFrame, base: str = "lz77", methods: tuple[str, ...] | None = None) -> DataFrame:
    """One row a string: best counts by method, and each method's ratio to ``base``.

    Ratios of an empty string are null. Without the counted ``methods`` a job finds them first, for
    which all is counted once more.
    """
    wide = best_counts(counted).groupBy("string_id", "n").pivot("method", methods and sorted(methods)).agg(F.first("phrases"))
    others = [c for c in wide.columns if c not in ("string_id", "n", base)]
    return wide.select("*", *(F.round(F.try_divide(c, base), 6).alias(f"{c}_ratio") for c in others))


def winners(counted: DataFrame) -> DataFrame:
    """The methods with the fewest phrases of each string; ties all stay."""
    w = Window.partitionBy("string_id").orderBy("phrases")
    return best_counts(counted).withColumn("place", F.rank().over(w)).where("place = 1").select("string_id", "method", "phrases")


def cost_table(counted: DataFrame, method: str = "two_way", base: str = "lz77", methods: tuple[str, ...] | None = None) -> DataFrame:
    """Per string and method seconds (directions summed) and measured peak bytes (the larger), and both factors of ``method``.

    ``counted`` comes from ``counts(..., memory=True)``. Without the counted ``methods`` a job finds them first, for
    which all is counted once more.
    """
    wide = counted.groupBy("string_id", "n").pivot("method", methods and sorted(methods)).agg(F.sum("seconds").alias("seconds"), F.max("bytes").alias("bytes"))
    return wide.withColumn("time_factor", F.col(f"{method}_seconds") / F.col(f"{base}_seconds")).withColumn("memory_factor", F.col(f"{method}_bytes") / F.col(f"{base}_bytes"))


def factors(counted: DataFrame, method: str = "two_way", base: str = "lz77") -> DataFrame:
    """(string_id, time_factor, memory_factor) of a method against another; without measured bytes the latter is null."""
    return cost_table(counted, method, base).select("string_id", "time_factor", "memory_factor")


def _wide(counted: DataFrame) -> DataFrame:
    pick = lambda m, d: F.max(F.when((F.col("method") == m) & (F.col("direction") == d), F.col("phrases")))
    return counted.groupBy("string_id", "n").agg(*(pick(m, d).alias(f"{m}_{d}") for m in ("two_way", "lz77", "lz_next", "lz_backward", "lex") for d in ("forward", "reverse")))


def bound_report(counted: DataFrame) -> DataFrame:
    """Per string: is two-way at most the left parse of the reverse, in each direction and at best?"""
    w = _wide(counted)
    return w.select(
        "string_id",
        "n",
        ((F.col("two_way_forward") <= F.col("lz77_reverse")) & (F.col("two_way_reverse") <= F.col("lz77_forward"))).alias("bound_holds"),
        (F.least("two_way_forward", "two_way_reverse") <= F.least("lz77_forward", "lz77_reverse")).alias("best_holds"),
    )


def identity_report(counted: DataFrame) -> DataFrame:
    """Per string: backward = left count, right = backward count of the reverse, two-way at most right."""
    w = _wide(counted)
    return w.select(
        "string_id",
        "n",
        (F.col("lz_backward_forward") == F.col("lz77_forward")).alias("backward_is_left"),
        (F.col("lz_next_forward") == F.col("lz_backward_reverse")).alias("right_is_backward_of_reverse"),
        (F.col("two_way_forward") <= F.col("lz_next_forward")).alias("two_way_within_right"),
    )


def relation_report(counted: DataFrame, runs: DataFrame) -> DataFrame:
    """Tiny strings: the smallest parse is within every other, lex within largest-first and twice the runs."""
    forward = counted.where("direction = 'forward'").groupBy("string_id").pivot("method", ["smallest", "two_way", "lz77", "lex", "lcp_first"]).agg(F.first("phrases"))
    return forward.join(runs, "string_id").select(
        "string_id", (F.col("smallest") <= F.least("two_way", "lz77", "lex", "lcp_first")).alias("smallest_within_all"), (F.col("lex") <= F.col("lcp_first")).alias("lex_within_largest_first"), (F.col("lex") <= 2 * (F.col("runs") + 1)).alias("lex_within_runs")
    )


def trace_summary(trace: DataFrame) -> DataFrame:
    """Loop iterations, finds and unions of each string, and the bound on them."""
    return trace.groupBy("string_id").agg(
        F.sum("length").alias("n"),
        F.count(F.lit(1)).alias("phrases"),
        F.sum("candidates").alias("candidates"),
        F.max("candidates").alias("most_candidates"),
        F.sum("finds").alias("finds"),
        F.sum("unions").alias("unions"),
        F.sum(F.col("length") * F.col("candidates")).alias("work_bound"),
        (F.sum("candidates") / F.sum("length")).alias("candidates_per_char"),
    )


def reference_depth(phrases: DataFrame) -> DataFrame:
    """Longest chain of references of each string."""
    return sources(reference_graph(phrases)).groupBy("string_id").agg(F.max("hops").alias("depth"))


def side_mix(phrases: DataFrame) -> DataFrame:
    """Shares of left, right and self-overlapping copies among the phrases of each string."""
    overlap = F.col("ref").isNotNull() & (F.abs(F.col("ref") - F.col("start")) < F.col("length"))
    return phrases.groupBy("string_id").agg(
        F.count(F.when(F.col("side") == "left", 1)).alias("left_refs"), F.count(F.when(F.col("side") == "right", 1)).alias("right_refs"), F.count(F.when(F.col("side") == "literal", 1)).alias("literals"), F.count(F.when(overlap, 1)).alias("overlapping")
    )


def length_profile(phrases: DataFrame) -> DataFrame:
    """Distribution of phrase lengths of each string."""
    return phrases.groupBy("string_id").agg(F.min("length").alias("least"), F.percentile("length", F.lit(0.5)).alias("median"), F.percentile("length", F.lit(0.9)).alias("p90"), F.max("length").alias("most"), F.round(F.avg("length"), 6).alias("mean"))


def length_histogram(phrases: DataFrame) -> DataFrame:
    """Phrases of each string by length, in classes that double: (string_id, at_least, phrases)."""
    size = F.pow(F.lit(2), F.floor(F.log2("length"))).cast("bigint")
    return phrases.groupBy("string_id", size.alias("at_least")).agg(F.count(F.lit(1)).alias("phrases"))


def encoded_bits(counted: DataFrame, sigma: int) -> DataFrame:
    """Two numbers below n for a copy, one letter for a literal."""
    number = F.ceil(F.log2(F.greatest(F.col("n"), F.lit(2))))
    return counted.select("*", (F.col("copies") * 2 * number + F.col("literals") * int(max(1, (sigma - 1).bit_length()))).cast("bigint").alias("bits"))


def gap_indicator(counted: DataFrame, base: str = "smallest") -> DataFrame:
    """z / (b log2(n / b)) of each method, b being the count of ``base``."""
    forward = counted.where("direction = 'forward'")
    b = forward.where(F.col("method") == base).select("string_id", F.col("phrases").alias("b"))
    return forward.where(F.col("method") != base).join(b, "string_id").select("string_id", "method", (F.col("phrases") / (F.col("b") * F.log2(F.greatest(F.col("n") / F.col("b"), F.lit(2.0))))).alias("indicator"))
