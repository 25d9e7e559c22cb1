"""Exact top-k search over 64-bit codes by multi-index hashing.

A code is cut into four segments of 16 bits, each with its own index. A query looks up
segment values at growing radii, one segment after another; after segment j at radius s every
code that is still unseen lies at least ``4 s + j + 1`` bits away, so a query ends once its kth
verified distance is below that. Equal codes are one entry that keeps its k smallest ids, all
that any answer can need. Index shards meet blocks of distinct query codes, and each pair's
best k are merged.
"""

from __future__ import annotations

from functools import lru_cache
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from phrasework.llm.textbytes import U64
from phrasework.shared import materialize, release

BITS, SEGMENTS = 64, 4
WIDTH = BITS // SEGMENTS
#: Codes in an index shard, and distinct query codes in a block.
SHARD, BLOCK = 1 << 17, 1 << 15
#: Parts that the rows of one code are spread over before they meet.
SALTS = 64
#: Query codes searched together inside a task.
TOGETHER = 256


def sign_code(vector: Column) -> Column:
    """Bit i is set where element i of an array column is above zero; null arrays give null.

    Arrays of more than 64 elements are an error: a code has no room for them.
    """
    vector = F.when(F.size(vector) > BITS, F.raise_error(F.lit(f"more than {BITS} elements"))).otherwise(vector)
    bits = F.transform(vector, lambda x, i: F.when(x > 0, F.call_function("shiftleft", F.lit(1).cast("bigint"), i)).otherwise(F.lit(0).cast("bigint")))
    return F.aggregate(bits, F.lit(0).cast("bigint"), lambda a, b: a.bitwiseOR(b))


@lru_cache(maxsize=WIDTH + 1)
def masks(radius: int) -> np.ndarray:
    """All 16-bit values with ``radius`` bits set."""
    return np.array([sum(1 << i for i in c) for c in combinations(range(WIDTH), radius)], np.int64)


def segment(codes: np.ndarray, j: int) -> np.ndarray:
    return ((codes >> U64(WIDTH * j)) & U64((1 << WIDTH) - 1)).astype(np.int64)


class CodeIndex:
    """Per segment: code numbers ordered by the segment's value, and where each value begins."""

    def __init__(self, codes: np.ndarray, weight: np.ndarray):
        self.codes, self.weight = codes, weight
        self.order, self.begin = [], []
        for j in range(SEGMENTS):
            value = segment(codes, j)
            self.order.append(np.argsort(value, kind="stable"))
            self.begin.append(np.searchsorted(value[self.order[j]], np.arange((1 << WIDTH) + 1)))

    def probe(self, queries: np.ndarray, j: int, radius: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(query, code, distance) of codes seen first in segment j at this radius."""
        value = segment(queries, j)[:, None] ^ masks(radius)[None, :]
        begin, end = self.begin[j][value], self.begin[j][value + 1]
        size = (end - begin).ravel()
        at = np.repeat(begin.ravel() - np.concatenate([[0], np.cumsum(size)[:-1]]), size) + np.arange(size.sum())
        q = np.repeat(np.repeat(np.arange(len(queries)), value.shape[1]), size)
        c = self.order[j][at]
        gap = queries[q] ^ self.codes[c]
        first = np.ones(len(gap), bool)
        for other in range(SEGMENTS):
            if other != j:
                d = np.bitwise_count(segment(gap, other))
                first &= d >= radius + (other < j)
        return q[first], c[first], np.bitwise_count(gap[first]).astype(np.int64)

    def search(self, queries: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(query, code, distance) that include the k nearest entries of each query, ties with the kth too."""
        counts = np.zeros((len(queries), BITS + 1), np.int64)
        kept: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        active = np.arange(len(queries))
        kth = np.full(len(queries), BITS)
        for radius in range(WIDTH + 1):
            for j in range(SEGMENTS):
                q, c, d = self.probe(queries[active], j, radius)
                q = active[q]
                np.add.at(counts, (q, d), self.weight[c])
                kept.append((q, c, d))
                reached = np.cumsum(counts[active], axis=1) >= k
                kth[active] = np.where(reached.any(axis=1), reached.argmax(axis=1), BITS)
                active = active[kth[active] >= SEGMENTS * radius + j + 1]
                if not len(active):
                    break
            if not len(active):
                break
            if len(kept) > SEGMENTS:
                kept = [self._needed(kept, kth)]
        return self._needed(kept, kth)

    @staticmethod
    def _needed(kept, kth):
        q, c, d = (np.concatenate(x) for x in zip(*kept))
        near = d <= kth[q]
        return q[near], c[near], d[near]


def _answer(index: CodeIndex, ids: pa.ListArray, queries: np.ndarray, k: int) -> pa.Table:
    starts, values = ids.offsets.to_numpy(), ids.values.to_numpy()
    out: list[tuple[np.ndarray, ...]] = []
    for at in range(0, len(queries), TOGETHER):
        own = queries[at : at + TOGETHER]
        q, c, d = index.search(own, k)
        n = starts[c + 1] - starts[c]
        where = np.repeat(starts[c] - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum())
        q, d, i = np.repeat(q, n), np.repeat(d, n), values[where]
        order = np.lexsort((i, d, q))
        q, d, i = q[order], d[order], i[order]
        place = np.arange(len(q)) - np.searchsorted(q, np.arange(len(own)))[q]
        best = place < k
        out.append((own[q[best]].view(np.int64), d[best], i[best]))
    code, d, i = (np.concatenate(x) for x in zip(*out))
    return pa.table({"query_code": code, "distance": d.astype(np.int32), "neighbor_id": i})


def nearest_codes(rows: DataFrame, queries: DataFrame, k: int = 10, id_col: str = "id", code_col: str = "code") -> DataFrame:
    """The k nearest rows of each query by Hamming distance: (query_id, rank, neighbor_id, distance).

    Both tables have an id and a 64-bit code; equal distances go to the smaller neighbour id, and
    a query that is itself a row finds itself. Rows or queries with a null id or code take no
    part; repeated rows count as often as they stand there. With fewer than k rows all are
    returned; if either table is empty the result is empty.
    """
    real = F.col(id_col).isNotNull() & F.col(code_col).isNotNull()
    rows = rows.where(real).select(F.col(id_col).cast("bigint").alias("id"), F.col(code_col).cast("bigint").alias("code"))
    asked = queries.where(real).select(F.col(id_col).cast("bigint").alias("query_id"), F.col(code_col).cast("bigint").alias("query_code"))

    # Of a code's ids only the k least travel: first of each salted part, then of the code.
    salted = rows.withColumn("salt", F.pmod(F.xxhash64("id"), F.lit(SALTS)))
    for part_of in (["code", "salt"], ["code"]):
        salted = salted.withColumn("place", F.row_number().over(Window.partitionBy(*part_of).orderBy("id"))).where(F.col("place") <= k).drop("place")
    entries = materialize(salted.groupBy("code").agg(F.sort_array(F.collect_list("id")).alias("ids")), "codes")
    distinct = materialize(asked.select("query_code").distinct(), "asked")
    shards = max(1, -(-entries.count() // SHARD))
    blocks = max(1, -(-distinct.count() // BLOCK))

    def every(n: int) -> Column:
        return F.explode(F.sequence(F.lit(0), F.lit(n - 1)))

    def part(code: Column, n: int) -> Column:
        return F.pmod(F.xxhash64(code, F.lit("part")), F.lit(n)).cast("int")

    left = entries.select(part(F.col("code"), shards).alias("shard"), every(blocks).alias("block"), "code", "ids")
    right = distinct.select(every(shards).alias("shard"), part(F.col("query_code"), blocks).alias("block"), "query_code")

    def run(own, ask):
        if not own.num_rows or not ask.num_rows:
            return pa.table({"query_code": pa.array([], pa.int64()), "distance": pa.array([], pa.int32()), "neighbor_id": pa.array([], pa.int64())})
        ids = own.column("ids").combine_chunks()
        ids = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(ids.value_lengths().to_numpy())]).astype(np.int32)), ids.flatten())
        index = CodeIndex(own.column("code").to_numpy().view(U64), np.diff(ids.offsets.to_numpy()).astype(np.int64))
        return _answer(index, ids, ask.column("query_code").to_numpy().view(U64), k)

    found = left.groupBy("shard", "block").cogroup(right.groupBy("shard", "block")).applyInArrow(run, "query_code bigint, distance int, neighbor_id bigint")
    best = Window.partitionBy("query_code").orderBy("distance", "neighbor_id")
    top = materialize(found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k), "top")
    release(entries, distinct)
    return asked.join(top, "query_code").select("query_id", "rank", "neighbor_id", "distance")
