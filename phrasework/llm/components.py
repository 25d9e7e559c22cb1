"""Connected components of an edge table by alternating large-star and small-star joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from phrasework.shared import materialize, release


def _settle(edges: DataFrame) -> DataFrame:
    return edges.where("u <> v").distinct()


def large_star(edges: DataFrame) -> DataFrame:
    """Tie each node's larger neighbours to the smallest node around it."""
    both = edges.select("u", "v").unionAll(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("w")).select("u", F.least("u", "w").alias("w"))
    return _settle(both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("w").alias("v")))


def small_star(edges: DataFrame) -> DataFrame:
    """Tie each node and its smaller neighbours to the smallest of them; edges have u > v."""
    least = edges.groupBy("u").agg(F.min("v").alias("w"))
    moved = edges.join(least, "u").select(F.col("v").alias("u"), F.col("w").alias("v"))
    return _settle(moved.unionAll(least.select("u", F.col("w").alias("v"))))


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, root) for every node of an edge, root being the component's smallest node.

    ``edges`` has comparable columns (u, v); loops, repeats and both orders are welcome, and a
    null end makes no edge. Each round is written to the shared folder and the one before it removed; it
    ends when a round changes nothing. An empty table gives an empty result.
    """
    edges = edges.where("u is not null and v is not null")
    now = materialize(_settle(edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))), "edges")
    mark = None
    for _ in range(max_rounds):
        before, now = now, materialize(small_star(large_star(now)), "edges")
        release(before)
        stars = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")), F.count_distinct("v")).first()
        if tuple(stars) == mark:
            break
        mark = tuple(stars)
    else:
        raise RuntimeError(f"components not settled after {max_rounds} rounds")
    roots = now.select(F.col("u").alias("node"), F.col("v").alias("root"))
    return roots.unionAll(now.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
