"""Sequence packing: first-fit decreasing in randomised groups, on a tournament tree.

Texts become token ids; full sequences are cut off first and what remains of each document
is packed with the remainders of its group. Groups are dealt by a hash, so that their sizes
follow the input and no group grows with it.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from phrasework.llm.textbytes import slices, utf8
from phrasework.shared import materialize

#: Tokens of a sequence, and remainders that one group has on average.
SEQUENCE, GROUP_PIECES = 2048, 8192
END_OF_TEXT = 1
#: Of this length on, a run without a space is left to the slower library, whose time is linear in it.
LONG_RUN = 1 << 15


class TournamentTree:
    """Free space of bins in an array tree; each inner node has the larger of its two children."""

    def __init__(self, bins: int, capacity: int):
        self.base = 1 << max(0, (bins - 1).bit_length())
        self.free = [capacity] * (2 * self.base)

    def first_fit(self, size: int) -> int:
        """Take ``size`` from the leftmost bin that has it and return that bin."""
        free, node, base = self.free, 1, self.base
        while node < base:
            node *= 2
            if free[node] < size:
                node += 1
        left = free[node] = free[node] - size
        place = node - base
        while node > 1:
            left = free[node] if free[node] >= free[node ^ 1] else free[node ^ 1]
            node >>= 1
            if free[node] == left:
                break
            free[node] = left
        return place


def first_fit_decreasing(sizes: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """Bin and offset of each size, larger sizes first and equal ones in their given order."""
    bins, offsets = np.zeros(len(sizes), np.int64), np.zeros(len(sizes), np.int64)
    if not len(sizes):
        return bins, offsets
    tree, used = TournamentTree(len(sizes), capacity), [0] * len(sizes)
    for i in np.argsort(-sizes.astype(np.int64), kind="stable").tolist():
        size = int(sizes[i])
        b = tree.first_fit(size)
        bins[i], offsets[i] = b, used[b]
        used[b] += size
    return bins, offsets


@lru_cache(maxsize=2)
def _exact(json_path: str):
    """The tokenizer; loaded only where a text needs it."""
    from tokenizers import Tokenizer

    return Tokenizer.from_file(json_path)


@lru_cache(maxsize=2)
def _fast(ranks_path: str):
    """A faster reader of the same vocabulary."""
    import base64

    import public_tokenizers
    import tiktoken

    with open(ranks_path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return tiktoken.Encoding("byte_bpe", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


def default_paths() -> tuple[str, str]:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("byte_bpe_50k.tiktoken")


def encode_bytes(text: bytes, json_path: str, ranks_path: str) -> np.ndarray:
    """Token ids of a text as ``tokenizers`` gives them without special tokens.

    The rank table yields the same ids faster; a text with a special token's string, which
    ``tokenizers`` reads as that token, and one with a very long unbroken run go the slow way.
    """
    if b"<|" in text or (len(text) >= LONG_RUN and max(map(len, text.split())) >= LONG_RUN):
        return np.array(_exact(json_path).encode(text.decode(), add_special_tokens=False).ids, "<u4")
    return np.array(_fast(ranks_path).encode_ordinary(text.decode()), "<u4")


PIECES = "id bigint, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint, salt bigint"


def cut_documents(docs: DataFrame, capacity: int = SEQUENCE, paths: tuple[str, str] | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Pieces of each document's ids: whole sequences first, then the remainder.

    ``salt`` deals pieces to groups; it depends on the id and the piece's contents.
    """
    json_path, ranks_path = paths or default_paths()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole):
                raw, at = utf8(batch.column("text"))
                owner, start, length, crc, total, salt = [], [], [], [], [], []
                keys = batch.column("id").to_pylist()
                for i, (a, b) in enumerate(zip(at[:-1], at[1:])):
                    ids = np.append(encode_bytes(raw[a:b].tobytes(), json_path, ranks_path), np.uint32(END_OF_TEXT)).astype("<u4")
                    for s in range(0, len(ids), capacity):
                        part = ids[s : s + capacity]
                        owner.append(keys[i])
                        start.append(s)
                        length.append(len(part))
                        crc.append(zlib.crc32(part.tobytes()))
                        total.append(len(ids))
                        salt.append(zlib.crc32(f"{keys[i]} {s}".encode(), crc[-1]))
                arrays = [pa.array(x, pa.int64()) for x in (owner, start, length, crc, total, salt)]
                yield pa.RecordBatch.from_arrays(arrays, names=[x.split()[0] for x in PIECES.split(", ")])

    rows = docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(run, PIECES)


def pack_pieces(pieces: DataFrame, capacity: int = SEQUENCE, group_pieces: int = GROUP_PIECES) -> DataFrame:
    """Place pieces into sequences: adds ``sequence_id`` and ``offset`` to ``pieces``.

    Whole sequences need no search but go through their group as well, for its numbering. The
    number of groups follows the number of pieces, and a group's sequences are numbered from
    the group's number times 2**32. Equal pieces of repeated rows are counted first and then dealt
    one by one, so that no group holds them all; the result follows from the table's rows alone.
    """
    pieces = materialize(pieces, "pieces")
    groups = max(1, -(-pieces.count() // group_pieces))
    again = F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("alike") - 1)).alias("copy")
    pieces = pieces.groupBy(*pieces.columns).agg(F.count(F.lit(1)).alias("alike")).select(*pieces.columns, again)
    pieces = pieces.withColumn("salt", F.when(F.col("copy") == 0, F.col("salt")).otherwise(F.xxhash64("salt", "copy"))).drop("copy")

    def run(key, table):
        table = table.sort_by([(c, "ascending") for c in ("salt", "start", "length", "ids_crc32", "id")])
        bins, offsets = first_fit_decreasing(table.column("length").to_numpy(), capacity)
        out = table.drop_columns(["pack_group", "salt"])
        return out.append_column("sequence_id", pa.array(bins + (key[0].as_py() << 32))).append_column("offset", pa.array(offsets))

    schema = PIECES.replace(", salt bigint", ", sequence_id bigint, offset bigint")
    return pieces.withColumn("pack_group", F.pmod("salt", F.lit(groups))).groupBy("pack_group").applyInArrow(run, schema)


def pack_documents(docs: DataFrame, capacity: int = SEQUENCE, group_pieces: int = GROUP_PIECES, paths: tuple[str, str] | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Pack all documents into sequences of at most ``capacity`` tokens.

    One row a piece: (id, start, length, ids_crc32, doc_tokens, sequence_id, offset). A
    document is its text's ids and the end id; null and empty texts have the end id alone.
    Null ids and repeated rows stay, each packed on its own; an empty table gives no rows.
    """
    return pack_pieces(cut_documents(docs, capacity, paths, id_col, text_col), capacity, group_pieces)
