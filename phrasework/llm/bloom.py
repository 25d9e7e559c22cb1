"""A Bloom filter of bounded size over a long column of hashes, built on executors and broadcast.

It only thins out rows ahead of an exact step: a false positive costs a row of shuffle, and a
filter too small for its keys lets more through, never less. The filter consists of blocks; keys
are shuffled by their block, so a task builds whole blocks and each bit reaches the driver once.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from phrasework.llm.textbytes import U64, mix

#: Largest filter: 2**27 bits, 16 MB; a block has 2**20 bits at most.
MAX_LOG2_BITS, MIN_LOG2_BITS, BLOCK_LOG2_BITS, BITS_PER_KEY, PROBES = 27, 16, 20, 16, 4


def _places(keys: np.ndarray, log2_bits: int) -> Iterator[np.ndarray]:
    """Bit of each probe inside the key's block."""
    first = mix(keys.astype(np.int64).view(U64))
    step = mix(first) | U64(1)
    for k in range(PROBES):
        yield (first + step * U64(k)) >> U64(64 - log2_bits)


def build(keys: DataFrame, column: str):
    """Broadcast filter, one row of words a block, of a long column of hashes; nulls are left out."""
    keys = keys.select(F.col(column).alias("key")).where("key is not null")
    log2_bits = int(np.clip(np.ceil(np.log2(max(1, keys.count()) * BITS_PER_KEY)), MIN_LOG2_BITS, MAX_LOG2_BITS))
    within = min(log2_bits, BLOCK_LOG2_BITS)
    blocks = 1 << (log2_bits - within)

    def mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made: dict[int, np.ndarray] = {}
        for batch in batches:
            key = batch.column("key").to_numpy()
            block = key & (blocks - 1)
            for b in np.unique(block).tolist():
                words = made.setdefault(b, np.zeros(1 << (within - 6), U64))
                for at in _places(key[block == b], within):
                    np.bitwise_or.at(words, at >> U64(6), U64(1) << (at & U64(63)))
        for b, words in made.items():
            yield pa.RecordBatch.from_arrays([pa.array([b], pa.int32()), pa.array([words.tobytes()], pa.binary())], names=["block", "words"])

    placed = keys.repartition(blocks, F.col("key").bitwiseAND(F.lit(blocks - 1)))
    table = np.zeros((blocks, 1 << (within - 6)), U64)
    for batch in placed.mapInArrow(mark, "block int, words binary").toArrow().to_batches():
        for b, words in zip(batch.column("block").to_pylist(), batch.column("words").to_pylist()):
            table[b] |= np.frombuffer(words, U64)
    return keys.sparkSession.sparkContext.broadcast(table)


def contains(table: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """Which keys the filter may hold."""
    block = keys.astype(np.int64) & (len(table) - 1)
    found = np.ones(len(keys), bool)
    for at in _places(keys, table.shape[1].bit_length() - 1 + 6):
        found &= (table[block, at >> U64(6)] >> (at & U64(63))) & U64(1) == 1
    return found


def thin(rows: DataFrame, column: str, filter_) -> DataFrame:
    """Rows whose long ``column`` the filter may hold."""

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array(contains(filter_.value, batch.column(column).to_numpy())))

    return rows.mapInArrow(keep, rows.schema)
