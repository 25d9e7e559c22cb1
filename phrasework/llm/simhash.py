"""SimHash near-duplicates: fingerprints, and vantage-point trees over their Hamming space.

Distinct fingerprints are dealt to shards by a tree of vantage points fitted on a bounded sample.
At each node the fingerprints up to the cut plus the radius go inside and those beyond the cut go
outside, so by the triangle inequality both ends of every link meet on one side at least, and only
a band as wide as the radius goes to both. The cut is put where that band is thinnest. Each shard
goes on in the same way by itself, finds all pairs within the radius exactly, and returns only a
spanning forest of them, so a dense group sends no more rows than it has fingerprints.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from phrasework.llm.components import connected_components
from phrasework.llm.textbytes import U64, Words, slices, utf8, xxh64
from phrasework.shared import materialize, release

#: Fingerprints that a shard is meant for, and the largest sample the shard tree is fitted on (8 MB).
SHARD, SAMPLE = 1 << 16, 1 << 20
#: Sampled fingerprints for each shard of the tree, and share of a node's fingerprints that its smaller side has at least.
SAMPLE_PER_SHARD, LEAST_SIDE = 64, 0.3
#: Fingerprints in a leaf of a shard's tree.
LEAF = 48


def _spread() -> np.ndarray:
    """For each byte, a word whose byte b is bit b of it."""
    bits = (np.arange(256)[:, None] >> np.arange(8)) & 1
    return (bits.astype(U64) << (U64(8) * np.arange(8, dtype=U64))).sum(axis=1, dtype=U64)


SPREAD = _spread()


def majority(hashes: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """For rows with ``counts[i]`` consecutive hashes each: bits that over half of them have.

    Bits are counted eight a word, in chunks of at most 255 hashes.
    """
    out = np.zeros(len(counts), U64)
    full = np.flatnonzero(counts)
    if not len(full):
        return out
    sizes = counts[full]
    begin = np.concatenate([[0], np.cumsum(sizes)[:-1]])
    chunks = -(-sizes // 255)
    owner = np.repeat(np.arange(len(full)), chunks)
    first_chunk = np.concatenate([[0], np.cumsum(chunks)[:-1]])
    cut = begin[owner] + 255 * (np.arange(len(owner)) - first_chunk[owner])
    octets = np.ascontiguousarray(hashes).view(np.uint8).reshape(-1, 8)
    fingerprint = np.zeros(len(full), U64)
    for k in range(8):
        lanes = np.add.reduceat(SPREAD[octets[:, k]], cut)
        for b in range(8):
            ones = np.add.reduceat(((lanes >> U64(8 * b)) & U64(255)).astype(np.int64), first_chunk)
            fingerprint |= (2 * ones > sizes).astype(U64) << U64(8 * k + b)
    out[full] = fingerprint
    return out


def text_fingerprints(raw: np.ndarray, at: np.ndarray, shingle: int = 3, seed: int = 42) -> np.ndarray:
    """SimHash of each row of a byte buffer, over XXH64 of its word shingles with repeats."""
    words = Words(raw, at, lower=True)
    counts = np.where(words.counts >= shingle, words.counts - shingle + 1, np.minimum(words.counts, 1))
    row = np.repeat(np.arange(len(counts)), counts)
    base = np.concatenate([[0], np.cumsum(counts)[:-1]]) if len(counts) else np.zeros(0, np.int64)
    first = words.rows[row] + np.arange(len(row)) - base[row]
    last = np.minimum(first + shingle, words.rows[row + 1]) - 1
    if not len(first):
        return np.zeros(len(counts), U64)
    return majority(xxh64(words.padded(), words.starts[first], words.ends[last], seed), counts)


def fingerprints(docs: DataFrame, shingle: int = 3, seed: int = 42, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, fp) of each whole text, ``fp`` being the 64 bits as a signed long; null text: 0."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole):
                got = text_fingerprints(*utf8(batch.column("text")), shingle, seed)
                yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(got.view(np.int64))], names=["id", "fp"])

    return docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).alias("text")).mapInArrow(run, "id bigint, fp bigint")


def distance(a: np.ndarray, b) -> np.ndarray:
    return np.bitwise_count(a ^ b)


def thinnest_cut(d: np.ndarray, radius: int, least_side: float = LEAST_SIDE) -> int:
    """The distance between the sides' quantiles behind which the fewest of ``d`` lie within the radius."""
    low, high = np.quantile(d, (least_side, 1 - least_side), method="lower").astype(int)
    count = np.concatenate([[0], np.cumsum(np.bincount(d, minlength=66 + radius))])
    cuts = np.arange(low, max(low, high - radius) + 1)  # the band counts to the inner side
    return int(cuts[np.argmin(count[cuts + radius + 1] - count[cuts + 1])])


def fit_shards(sample: np.ndarray, depth: int, radius: int = 2) -> list[tuple[int, int]]:
    """Vantage points and cuts of a complete binary tree in heap order, ``2**depth - 1`` of them.

    A node's point is the first of its sample.
    """
    nodes: list[tuple[int, int]] = [(0, 32)] * ((1 << depth) - 1)
    parts = {0: sample}
    for k in range(len(nodes)):
        own = parts.pop(k)
        if len(own):
            d = distance(own, own[0])
            nodes[k] = (int(own[0]), thinnest_cut(d[1:], radius) if len(own) > 1 else 32)
            parts[2 * k + 1], parts[2 * k + 2] = own[d <= nodes[k][1]], own[d > nodes[k][1]]
        else:
            parts[2 * k + 1] = parts[2 * k + 2] = own
    return nodes


def route(points: np.ndarray, nodes: list[tuple[int, int]], depth: int, radius: int) -> list[tuple[int, np.ndarray]]:
    """For each shard the indexes of the points that go there."""
    todo = [(0, np.arange(len(points)))]
    for _ in range(depth):
        below = []
        for k, index in todo:
            d = distance(points[index], U64(nodes[k][0])).astype(np.int64)
            below += [(2 * k + 1, index[d <= nodes[k][1] + radius]), (2 * k + 2, index[d > nodes[k][1]])]
        todo = [x for x in below if len(x[1])]
    return [(k - (1 << depth) + 1, index) for k, index in todo]


def close_pairs(points: np.ndarray, radius: int, leaf: int = LEAF) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """All index pairs of distinct points at most ``radius`` apart, some more than once, found in blocks.

    Where no vantage point divides a set, as in a dense ball, its points are sorted by each of
    ``radius + 1`` bit ranges instead: of two close points one range at least is equal.
    """
    stack = [np.arange(len(points))]
    while stack:
        own = stack.pop()
        if len(own) <= leaf:
            a, b = np.nonzero(np.triu(distance(points[own][:, None], points[own][None, :]) <= radius, 1))
            yield own[a], own[b]
            continue
        for vantage in points[own[[len(own) // 2, 0, -1]]]:
            d = distance(points[own], vantage).astype(np.int64)
            cut = thinnest_cut(d, radius)
            inside, outside = own[d <= cut + radius], own[d > cut]
            if max(len(inside), len(outside)) <= 0.8 * len(own):
                stack += [inside, outside]
                break
        else:
            yield from _close_by_ranges(points, own, radius)


def _close_by_ranges(points: np.ndarray, own: np.ndarray, radius: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    bounds = [64 * k // (radius + 1) for k in range(radius + 2)]
    for low, high in zip(bounds[:-1], bounds[1:]):
        key = (points[own] >> U64(low)) & U64((1 << (high - low)) - 1)
        order = np.argsort(key, kind="stable")
        at, key = own[order], key[order]
        live, step = np.arange(len(at)), 0
        while True:
            step += 1
            live = live[live + step < len(at)]
            live = live[key[live] == key[live + step]]
            if not len(live):
                break
            near = live[distance(points[at[live]], points[at[live + step]]) <= radius]
            yield at[near], at[near + step]


class Forest:
    """Union-find over 0..n-1 with the smaller index as root."""

    def __init__(self, n: int):
        self.up = np.arange(n)

    def roots(self) -> np.ndarray:
        while True:
            above = self.up[self.up]
            if np.array_equal(above, self.up):
                return self.up
            self.up = above

    def merge(self, a: np.ndarray, b: np.ndarray) -> None:
        """Union of pairs: each round hooks the larger root under the smallest it meets."""
        while len(a):
            root = self.roots()
            a, b = root[a], root[b]
            open_ = a != b
            a, b = a[open_], b[open_]
            np.minimum.at(self.up, np.maximum(a, b), np.minimum(a, b))


def shard_forest(points: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Edges (point, root) that connect distinct points within the radius."""
    points = np.sort(points)
    forest = Forest(len(points))
    waiting: list[tuple[np.ndarray, np.ndarray]] = []
    held = 0
    for a, b in close_pairs(points, radius):
        if len(a):
            waiting.append((a, b))
            held += len(a)
        if held > 1 << 18:
            forest.merge(*(np.concatenate(x) for x in zip(*waiting)))
            waiting, held = [], 0
    if waiting:
        forest.merge(*(np.concatenate(x) for x in zip(*waiting)))
    root = forest.roots()
    linked = np.flatnonzero(root != np.arange(len(points)))
    return points[linked], points[root[linked]]


def fingerprint_links(distinct: DataFrame, radius: int = 2, shard: int = SHARD, sample: int = SAMPLE) -> DataFrame:
    """Edges (u, v) between distinct fingerprints ``fp`` that span all links within the radius."""
    n = distinct.count()
    depth = max(0, int(np.ceil(np.log2(max(1, n / shard)))))
    depth = min(depth, int(np.log2(max(1, min(n, sample) // SAMPLE_PER_SHARD))))
    picked = distinct.select("fp").orderBy(F.xxhash64("fp"), "fp").limit(min(sample, SAMPLE_PER_SHARD << depth)).toArrow().column("fp").to_numpy() if depth else np.zeros(0, np.int64)
    nodes = fit_shards(picked.view(U64), depth, radius)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            points = batch.column("fp").to_numpy().view(U64)
            for k, index in route(points, nodes, depth, radius):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(index), k, np.int32)), pa.array(points[index].view(np.int64))], names=["shard", "fp"])

    def link(key, table):
        u, v = shard_forest(table.column("fp").to_numpy().view(U64), radius)
        return pa.table({"u": u.view(np.int64), "v": v.view(np.int64)})

    return distinct.select("fp").mapInArrow(deal, "shard int, fp bigint").groupBy("shard").applyInArrow(link, "u bigint, v bigint")


def near_duplicates(docs: DataFrame, radius: int = 2, shingle: int = 3, seed: int = 42, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Classes of documents whose fingerprints are linked: (id, fp, component_id).

    Two documents are linked if their fingerprints differ in at most ``radius`` bits;
    ``component_id`` is the smallest id that can be reached. Null and wordless texts have
    fingerprint zero and are linked like any other. Repeated rows stay; null ids stay and
    never name a component unless it has no other id. An empty table gives no rows.
    """
    prints = materialize(fingerprints(docs, shingle, seed, id_col, text_col), "fingerprints")
    distinct = materialize(prints.groupBy("fp").agg(F.min("id").alias("least")), "distinct")
    parts = materialize(connected_components(fingerprint_links(distinct, radius)), "components")
    named = parts.join(distinct, parts.node == distinct.fp).groupBy("root").agg(F.min("least").alias("name"))
    of_print = distinct.join(parts.join(named, "root").select(F.col("node").alias("fp"), "name"), "fp", "left").select("fp", F.coalesce("name", "least").alias("component_id"))
    of_print = materialize(of_print, "names")  # a plain table, so that a join with it can split a fingerprint that many share
    release(distinct, parts)
    return prints.join(of_print, "fp").select("id", "fp", "component_id")
