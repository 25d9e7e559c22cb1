"""Suffix and factor tables, in kernels for strings of one task and as joins for a huge one."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from phrasework import schemas
from phrasework.kernels import suffix as K
from phrasework.operators.batches import map_strings
from phrasework.operators.strings import chars
from phrasework.shared import materialize

#: Doubling rounds, enough for any string length.
MAX_ROUNDS = 62


def suffix_table(S: DataFrame, tier: str = "kernel", unit: str = "codepoint") -> DataFrame:
    """SUFFIX: rank, position and LCP with the rank above, of every suffix of every string."""
    if tier == "distributed":
        return distributed_suffix_table(S)

    def rows(key: str, text: str):
        index = K.SuffixIndex(K.codes_of(text, unit))
        return zip([key] * index.n, range(1, index.n + 1), (index.sa + 1).tolist(), index.lcp.tolist())

    return map_strings(S, schemas.SUFFIX, rows)


def rank_of(suffixes: DataFrame) -> DataFrame:
    """The inverse suffix array: the same rows keyed by position."""
    return suffixes.select("string_id", "pos", "rank")


def factor_table(S: DataFrame, unit: str = "codepoint", tier: str = "kernel") -> DataFrame:
    """FACTOR: longest earlier and later occurrence of what starts at each position."""
    if tier == "distributed":
        return distributed_factor_table(S)

    def rows(key: str, text: str):
        index = K.SuffixIndex(K.codes_of(text, unit))
        before, after = K.factor(index), K.factor(index, later=True)
        columns = [before[0].tolist(), _refs(before[1]), after[0].tolist(), _refs(after[1])]
        return zip([key] * index.n, range(1, index.n + 1), *columns)

    return map_strings(S, schemas.FACTOR, rows)


def _refs(refs: np.ndarray) -> list[int | None]:
    return [r + 1 if r >= 0 else None for r in refs.tolist()]


def previous_factor(S: DataFrame) -> DataFrame:
    return factor_table(S).select("string_id", "pos", "prev_len", "prev_ref")


def next_factor(S: DataFrame) -> DataFrame:
    return factor_table(S).select("string_id", "pos", "next_len", "next_ref")


def candidates(S: DataFrame, i: int, tie: str = "rightmost") -> DataFrame:
    """CANDIDATES: other positions of each string by LCE with position ``i``, the stream's order."""
    from phrasework.kernels.two_way import ordered, walk

    def rows(key: str, text: str):
        index = K.SuffixIndex(K.codes_of(text))
        if not 1 <= i <= index.n:
            return
        stream = walk(index.sa.tolist(), index.rank.tolist(), index.lcp.tolist(), i - 1, tie == "walk_upper")
        place = 0
        for lce, group in ordered(stream, i - 1, tie):
            for j in group:
                place += 1
                yield key, i, place, j + 1, lce

    return map_strings(S, schemas.CANDIDATES, rows)


def _dense_ranks(rows: DataFrame, keys: list[str]) -> DataFrame:
    """Adds ``rank``: 1 + the number of rows of the string with smaller keys.

    Equal keys are counted first, ahead of any shuffle, so one that a third of all rows share is one
    row. The distinct keys are range-partitioned; each partition adds up its own and one small row a
    partition and string gives the offsets. Ranks come back by an equi-join, which AQE splits at such keys.
    """
    counted = rows.groupBy("string_id", *keys).agg(F.count(F.lit(1)).alias("alike"))
    placed = materialize(counted.repartitionByRange("string_id", *keys).withColumn("part", F.spark_partition_id()), "ranked")
    before = Window.partitionBy("string_id").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = placed.groupBy("string_id", "part").agg(F.sum("alike").alias("size")).withColumn("offset", F.coalesce(F.sum("size").over(before), F.lit(0))).drop("size")
    smaller = Window.partitionBy("string_id", "part").orderBy(*keys).rowsBetween(Window.unboundedPreceding, -1)
    ranks = placed.withColumn("own", F.coalesce(F.sum("alike").over(smaller), F.lit(0))).join(offsets, ["string_id", "part"])
    ranks = ranks.select("string_id", *keys, (F.col("own") + F.col("offset") + 1).alias("rank"))
    return rows.join(ranks, ["string_id", *keys])


def rank_levels(S: DataFrame) -> list[DataFrame]:
    """(string_id, pos, rank) of the substrings of length 1, 2, 4, ... until all ranks differ.

    Each round joins a position with the one ``2**t`` further on, by an equi-join on unique keys.
    """
    characters = materialize(chars(S), "chars")
    levels = [materialize(_dense_ranks(characters.select("string_id", "pos", F.col("ch").cast("bigint").alias("a")), ["a"]).select("string_id", "pos", "rank"), "level")]
    for t in range(MAX_ROUNDS):
        now = levels[-1]
        spread = now.groupBy("string_id").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("rank").alias("d"))
        if spread.where("n <> d").isEmpty():
            return levels
        ahead = now.select("string_id", (F.col("pos") - (1 << t)).alias("pos"), F.col("rank").alias("b"))
        pairs = now.withColumnRenamed("rank", "a").join(ahead, ["string_id", "pos"], "left").withColumn("b", F.coalesce("b", F.lit(0)))
        levels.append(materialize(_dense_ranks(pairs, ["a", "b"]).select("string_id", "pos", "rank"), "level"))
    raise RuntimeError("ranks not settled")


def lce_by_levels(pairs: DataFrame, levels: list[DataFrame]) -> DataFrame:
    """``pairs`` (string_id, pos, j, ...) with ``lce``: a descent over rank levels, two equi-joins each.

    A null ``j`` gives 0.
    """
    n = levels[-1].groupBy("string_id").agg(F.count(F.lit(1)).alias("n"))
    names = pairs.columns
    pairs = pairs.join(n, "string_id").withColumn("lce", F.lit(0).cast("bigint"))
    for t in range(len(levels) - 1, -1, -1):
        level, size = levels[t], 1 << t
        x = level.select("string_id", F.col("pos").alias("x"), F.col("rank").alias("rx"))
        y = level.select("string_id", F.col("pos").alias("y"), F.col("rank").alias("ry"))
        pairs = pairs.withColumn("x", F.col("pos") + F.col("lce")).withColumn("y", F.col("j") + F.col("lce"))
        pairs = pairs.join(x, ["string_id", "x"], "left").join(y, ["string_id", "y"], "left")
        grow = (F.col("rx") == F.col("ry")) & (F.greatest("x", "y") + size <= F.col("n") + 1)
        pairs = pairs.withColumn("lce", F.col("lce") + F.when(grow, size).otherwise(0)).drop("x", "y", "rx", "ry")
        if t % 4 == 0:
            pairs = materialize(pairs, "descent")
    return pairs.select(*names, "lce")


def distributed_suffix_table(S: DataFrame, levels: list[DataFrame] | None = None) -> DataFrame:
    """SUFFIX of huge strings without a kernel: ranks by doubling, LCPs by descent over its levels."""
    levels = levels or rank_levels(S)
    above = levels[-1].select("string_id", (F.col("rank") + 1).alias("rank"), F.col("pos").alias("j"))
    pairs = levels[-1].join(above, ["string_id", "rank"], "left").select("string_id", "rank", "pos", "j")
    return lce_by_levels(pairs, levels).select("string_id", "rank", "pos", F.col("lce").alias("lcp"))


def _nearest_by_rank(ranks: DataFrame, larger: bool, upward: bool, block: int) -> DataFrame:
    """(string_id, pos, j): the nearest suffix in rank order, one way, that starts further right (or left).

    Each block of ranks answers what it can by a stack. What is left over and has an answer at
    all, as the running extreme of later blocks tells, finds the one block that answers it by a
    descent over block maxima and meets that block's staircase: the rows that no row behind them hides.
    """
    sign = 1 if larger else -1
    order = F.col("rank") if not upward else -F.col("rank")
    rows = ranks.select("string_id", "pos", order.alias("at"), F.floor(order / block).alias("block"), (F.col("pos") * sign).alias("value"))

    def inside(key, table):
        at = np.argsort(table.column("at").to_numpy())
        pos, value = table.column("pos").to_numpy()[at].tolist(), table.column("value").to_numpy()[at].tolist()
        stack: list[int] = []
        found: list[int | None] = []
        for k, v in enumerate(value):
            while stack and value[stack[-1]] < v:
                stack.pop()
            found.append(pos[stack[-1]] if stack else None)
            stack.append(k)
        stair = set(stack)
        return pa.table({"string_id": pa.array([key[0].as_py()] * len(pos)), "block": pa.array([key[1].as_py()] * len(pos), pa.int64()), "pos": pos, "value": value, "j": pa.array(found, pa.int64()), "stair": [k in stair for k in range(len(pos))]})

    done = materialize(rows.groupBy("string_id", "block").applyInArrow(inside, "string_id string, block bigint, pos bigint, value bigint, j bigint, stair boolean"), "blocks")
    tops = done.groupBy("string_id", "block").agg(F.max("value").alias("top"))
    before = Window.partitionBy("string_id").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    reach = tops.withColumn("reach", F.max("top").over(before)).select("string_id", "block", "reach")
    open_rows = done.where("j is null").join(reach, ["string_id", "block"]).where("reach > value").select("string_id", "block", "pos", "value")
    target = _nearest_higher_block(open_rows, materialize(tops, "tops"))
    stairs = done.where("stair").select("string_id", "block", F.col("pos").alias("p"), F.col("value").alias("v"))
    answer = target.join(stairs, ["string_id", "block"]).where("v > value").groupBy("string_id", "pos").agg(F.min_by("p", "v").alias("far"))
    return done.join(answer, ["string_id", "pos"], "left").select("string_id", "pos", F.coalesce("j", "far").alias("j"))


def _nearest_higher_block(rows: DataFrame, tops: DataFrame) -> DataFrame:
    """``rows`` (string_id, block, pos, value) with ``block`` moved to the nearest earlier one whose top is above the value.

    A descent over maxima of 1, 2, 4, ... blocks: a step skips that many blocks if none is high enough.
    These tables have a row for each block, so that the joins with them need no shuffle of the rows.
    """
    most = tops.groupBy("string_id").agg((F.max("block") - F.min("block") + 1).alias("n")).agg(F.max("n")).first()[0] or 1
    levels = [tops.select("string_id", "block", "top")]
    for k in range(int(most).bit_length() - 1):
        earlier = levels[-1].select("string_id", (F.col("block") + (1 << k)).alias("block"), F.col("top").alias("before"))
        levels.append(materialize(levels[-1].join(earlier, ["string_id", "block"], "left").select("string_id", "block", F.greatest("top", "before").alias("top")), "maxima"))
    rows = rows.withColumn("block", F.col("block") - 1)
    for k in range(len(levels) - 1, -1, -1):
        rows = rows.join(levels[k], ["string_id", "block"]).withColumn("block", F.when(F.col("top") > F.col("value"), F.col("block")).otherwise(F.col("block") - (1 << k))).drop("top")
    return rows


def distributed_factor_table(S: DataFrame, block: int = 1 << 16) -> DataFrame:
    """FACTOR of huge strings: nearest places along rank order by blocks, lengths by rank levels."""
    levels = rank_levels(S)
    sides = {}
    for name, larger in (("prev", False), ("next", True)):
        both = [lce_by_levels(_nearest_by_rank(levels[-1], larger, upward, block), levels).select("string_id", "pos", F.col("j").alias(f"j{k}"), F.col("lce").alias(f"l{k}")) for k, upward in enumerate((False, True))]
        one = both[0].join(both[1], ["string_id", "pos"])
        size = F.greatest("l0", "l1")
        sides[name] = one.select("string_id", "pos", size.alias(f"{name}_len"), F.when(size > 0, F.when(F.col("l0") >= F.col("l1"), F.col("j0")).otherwise(F.col("j1"))).alias(f"{name}_ref"))
    return sides["prev"].join(sides["next"], ["string_id", "pos"])
