"""String families with known parses, and mutated copies, made by column expressions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

# A published expansion of three letters into two; first words of the run-rich family.
EXPANSION = {"a": "101001011001010010110100", "b": "1010010110100", "c": "10100101"}
FIRST_WORDS = ["b", "a", "ac", "ba", "cb"]

#: Multipliers and modulus of the mutation hash, small enough for 64-bit arithmetic in any engine.
HASH_COPY, HASH_POS, HASH_ADD, HASH_MOD = 7919, 104729, 12345, 1_000_003
RATE_SCALE = 1_000_000


def _orders(spark: SparkSession, low: int, high: int) -> DataFrame:
    return spark.range(low, high + 1).select(F.col("id").cast("int").alias("k"))


def fibonacci(spark: SparkSession, low: int = 4, high: int = 20) -> DataFrame:
    """Fibonacci words (string_id, k, text): each is the one before it and the one before that."""
    step = F.aggregate(F.sequence(F.lit(2), F.col("k")), F.struct(F.lit("b").alias("p"), F.lit("a").alias("q")), lambda w, _: F.struct(w["q"].alias("p"), F.concat(w["q"], w["p"]).alias("q")), lambda w: w["q"])
    return _orders(spark, low, high).select(F.concat(F.lit("fib"), "k").alias("string_id"), "k", step.alias("text"))


def thue_morse(spark: SparkSession, low: int = 4, high: int = 14) -> DataFrame:
    """Thue-Morse words (string_id, k, text) of length ``2**(k - 1)``: each followed by its complement."""
    step = F.aggregate(F.sequence(F.lit(2), F.col("k")), F.lit("a"), lambda w, _: F.concat(w, F.translate(w, "ab", "ba")))
    return _orders(spark, low, high).select(F.concat(F.lit("tm"), "k").alias("string_id"), "k", step.alias("text"))


def run_rich(spark: SparkSession, low: int = 6, high: int = 14) -> DataFrame:
    """Words rich in runs: each joins the third and the second word before it, then letters expand."""
    start = F.array(*map(F.lit, FIRST_WORDS))
    grown = F.aggregate(F.sequence(F.lit(6), F.col("k")), start, lambda w, k: F.concat(w, F.array(F.concat(F.element_at(w, -3), F.element_at(w, -2)))))
    word = F.element_at(grown, F.col("k"))
    text = F.array_join(F.transform(F.split(word, ""), lambda c: F.when(c == "a", EXPANSION["a"]).when(c == "b", EXPANSION["b"]).when(c == "c", EXPANSION["c"]).otherwise("")), "")
    return _orders(spark, low, high).select(F.concat(F.lit("rr"), "k").alias("string_id"), "k", text.alias("text"))


#: Characters of mutated copies from which they leave as one batch.
BATCH_CHARS = 1 << 20


def _mutated(text: str, copies: int, rates: list[float], kinds: tuple[int, ...]) -> Iterator[tuple[int, float, str]]:
    """(kind, rate, text) of every kind and rate; which characters change depends on copy, position and rate alone."""
    letters = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4")
    n = len(letters)
    at = np.arange(1, n + 1, dtype=np.int64)
    hashes = [(c * HASH_COPY + at * HASH_POS + HASH_ADD) * 31 % HASH_MOD for c in range(1, copies)]
    for kind in kinds:
        for rate in rates:
            own, out = letters, [letters]
            for h in hashes:
                changed = np.flatnonzero(h * RATE_SCALE < rate * RATE_SCALE * HASH_MOD)
                before = letters if kind == 1 else own
                if len(changed):
                    own = before.copy()
                    own[changed] = letters[h[changed] * 131 % n]
                else:
                    own = before
                out.append(own)
            yield kind, rate, np.concatenate(out[:copies]).tobytes().decode("utf-32-le", "surrogatepass")


def mutated_copies(base: DataFrame, copies: int, rates: list[float], kinds: tuple[int, ...] = (1, 2)) -> DataFrame:
    """Copies of each base string, one after the other, with characters replaced at a rate.

    (string_id, kind, rate, text); copy 0 is the base itself. Kind 1 mutates the base each time,
    kind 2 the copy before. Which characters change, and into which of the base's characters, is
    whole-number arithmetic on copy and position. Null texts give no rows, empty ones empty texts.
    """
    return distinct_copies(base, copies, rates, kinds).select("string_id", F.explode("made").alias("made"), "text").select("string_id", "made.kind", "made.rate", "text")


def distinct_copies(base: DataFrame, copies: int, rates: list[float], kinds: tuple[int, ...] = (1, 2)) -> DataFrame:
    """``mutated_copies`` with each different text of a base once: (string_id, made, text), ``made`` being the
    kinds and rates that give this text. A task holds the different texts of one base at a time."""
    schema = "string_id string, made array<struct<kind: int, rate: double>>, text string"
    made_type = pa.list_(pa.struct([("kind", pa.int32()), ("rate", pa.float64())]))

    def batch_of(rows: list[tuple]) -> pa.RecordBatch:
        keys, made, texts = zip(*rows)
        return pa.RecordBatch.from_arrays([pa.array(keys, pa.string()), pa.array(made, made_type), pa.array(texts, pa.string())], names=["string_id", "made", "text"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, chars = [], 0
        for batch in batches:
            for key, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                if text is None:
                    continue
                found: dict[str, list[dict]] = {}
                for kind, rate, copy in _mutated(text, copies, rates, kinds):
                    found.setdefault(copy, []).append({"kind": kind, "rate": rate})
                rows.extend((key, made, copy) for copy, made in found.items())
                chars += sum(map(len, found))
                if chars >= BATCH_CHARS:
                    yield batch_of(rows)
                    rows, chars = [], 0
        if rows:
            yield batch_of(rows)

    return base.select("string_id", "text").mapInArrow(run, schema)
