"""Groups of near-duplicate texts for filtering: five-word shingles, similarity of 0.8 or more.

At that similarity 64-bit fingerprints differ in up to 17 bits, where a tree over uniformly
spread fingerprints prunes nothing, so here shards are keyed by shared least shingles instead:
two texts of Jaccard similarity J agree in each of ``ANCHORS`` least shingle hashes with
chance J. Within a shard all pairs of 256-bit SimHashes are compared in blocks and only a
spanning forest of the links leaves it. A shard above ``SHARD`` texts is split, and every pair
of its parts is compared by a task of its own.

The links of 64-bit SimHash fingerprints of three-word shingles, found by the operator's search,
are candidates as well.

All these links are candidates only: two similar texts lie in one component of them, but so may
others. In each component the distinct shingles themselves are compared, and what is merged
has an exact Jaccard similarity of 0.8 or more.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from phrasework.llm import bloom
from phrasework.llm.components import connected_components
from phrasework.llm.simhash import Forest, fingerprint_links, majority, text_fingerprints
from phrasework.llm.substring_dedup import mark_texts, text_keys
from phrasework.llm.textbytes import U64, Words, mix, slices, utf8, xxh64
from phrasework.shared import materialize, release

SHINGLE, ANCHORS, STREAMS = 5, 10, 4
#: Differing bits of 256 at which two texts are candidates; similarity 0.8 differs in 39 on
#: average (deviation 6), in 48 where the texts have only four and five shingles.
RADIUS = 80
#: Least Jaccard similarity of near duplicates, as a fraction of whole numbers.
SIMILAR = (4, 5)
#: Texts of one anchor that a task compares at most, and anchor rows of one task on average.
SHARD, TASK_ROWS = 4096, 1 << 17
#: Shingles of one part of a component, and of one confirming task on average.
PART_SHINGLES = 1 << 21
_SEEDS = mix(np.arange(1, ANCHORS + STREAMS + 1, dtype=U64))


def distinct_shingles(raw: np.ndarray, at: np.ndarray, shingle: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of each row's distinct shingles, row after row, and their number in each row."""
    words = Words(raw, at, lower=True)
    counts = np.where(words.counts >= shingle, words.counts - shingle + 1, np.minimum(words.counts, 1))
    row = np.repeat(np.arange(len(counts)), counts)
    base = np.cumsum(counts) - counts
    first = words.rows[row] + np.arange(len(row)) - base[row]
    last = np.minimum(first + shingle, words.rows[row + 1]) - 1
    hashes = xxh64(words.padded(), words.starts[first], words.ends[last])
    # Each distinct shingle of a row counts once: a word repeated through a text must not decide its bits.
    keep = np.sort(np.unique(mix(hashes + mix(row.astype(U64))), return_index=True)[1])
    return hashes[keep], np.bincount(row[keep], minlength=len(counts))


def sketches(hashes: np.ndarray, counts: np.ndarray) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """Per row of distinct shingles: SimHash words, and least shingle hashes (zero without words)."""
    base = np.cumsum(counts) - counts
    prints = [majority(mix(hashes ^ s), counts) for s in _SEEDS[:STREAMS]]
    full = np.flatnonzero(counts)
    anchors = []
    for s in _SEEDS[STREAMS:]:
        least = np.zeros(len(counts), U64)
        if len(full):
            least[full] = np.minimum.reduceat(mix(hashes ^ s), base[full])
        anchors.append(least)
    return prints, anchors


PRINTS = [f"f{i}" for i in range(STREAMS)]
SKETCH = "id bigint, k1 bigint, k2 bigint, size bigint, fp bigint, " + ", ".join(f"{f} bigint" for f in PRINTS) + ", anchors array<bigint>"


def _sketch(docs: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole):
                raw, at = utf8(batch.column("text"))
                k1, k2 = text_keys(raw, at)
                hashes, counts = distinct_shingles(raw, at)
                prints, anchors = sketches(hashes, counts)
                flat = np.stack(anchors, axis=1).view(np.int64).ravel()
                lists = pa.ListArray.from_arrays(pa.array(np.arange(0, len(flat) + 1, ANCHORS).astype(np.int32)), pa.array(flat))
                yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(k1), pa.array(k2), pa.array(counts.astype(np.int64)), pa.array(text_fingerprints(raw, at).view(np.int64)), *(pa.array(p.view(np.int64)) for p in prints), lists], names=["id", "k1", "k2", "size", "fp", *PRINTS, "anchors"])

    return docs.mapInArrow(run, SKETCH)


def similar(x: np.ndarray, y: np.ndarray) -> bool:
    """Whether two sets, given as arrays of distinct values, have a Jaccard similarity of ``SIMILAR`` or more."""
    both = np.concatenate([x, y])
    both.sort()
    shared = int((both[1:] == both[:-1]).sum())
    return shared * SIMILAR[1] >= (len(both) - shared) * SIMILAR[0]


def link_rows(bucket: np.ndarray, part: np.ndarray, node: np.ndarray, prints: np.ndarray, radius: int, sets: list[np.ndarray] | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Spanning edges of rows linked within a bucket, given rows sorted by bucket.

    In a bucket of two parts only pairs across them are compared. With the rows' shingle
    ``sets`` a pair within the radius is linked only if its sets are similar.
    """
    sizes = None if sets is None else np.array([len(x) for x in sets], np.int64)
    names, dense = np.unique(node, return_inverse=True)
    forest = Forest(len(names))
    new = np.ones(len(bucket), bool)
    new[1:] = bucket[1:] != bucket[:-1]
    first = np.flatnonzero(new)
    end = np.repeat(np.append(first[1:], len(bucket)), np.diff(np.append(first, len(bucket))))
    live = np.arange(len(bucket))
    step = 0
    while True:
        step += 1
        live = live[live + step < end[live]]
        if not len(live):
            break
        for k in range(0, len(live), 1 << 18):
            a = live[k : k + (1 << 18)]
            b = a + step
            if sets is not None:
                root = forest.roots()
                apart = (root[dense[a]] != root[dense[b]]) & (np.minimum(sizes[a], sizes[b]) * SIMILAR[1] >= np.maximum(sizes[a], sizes[b]) * SIMILAR[0])
                a, b = a[apart], b[apart]
            d = np.bitwise_count(prints[0][a] ^ prints[0][b]).astype(np.int16)
            for p in prints[1:]:
                d += np.bitwise_count(p[a] ^ p[b])
            near = (d <= radius) & ((part[a] < 0) | (part[a] != part[b]))
            if sets is not None:
                near[near] = [similar(sets[i], sets[j]) for i, j in zip(a[near].tolist(), b[near].tolist())]
            if near.any():
                forest.merge(dense[a[near]], dense[b[near]])
    root = forest.roots()
    linked = np.flatnonzero(root != np.arange(len(names)))
    return names[linked], names[root[linked]]


def _in_pairs_of_parts(rows: DataFrame) -> DataFrame:
    """Rows once for every ``pair`` of ``parts`` parts that a row's own is in; ``part`` is -1 where nothing is split.

    Within a part all pairs of rows are compared, between two parts those across.
    """
    own = F.pmod(F.xxhash64("node", F.lit("part")), F.col("parts")).cast("int")
    pairs = F.when(F.col("parts") > 1, F.transform(F.sequence(F.lit(0), F.col("parts") - 1), lambda j: F.struct(F.least("own", j).alias("i"), F.greatest("own", j).alias("j"))))
    rows = rows.withColumn("own", own).withColumn("pair", F.explode(F.coalesce(pairs, F.array(F.struct(F.lit(0).alias("i"), F.lit(0).alias("j"))))))
    return rows.withColumn("part", F.when(F.col("pair.i") == F.col("pair.j"), F.lit(-1)).otherwise(F.col("own")))


def print_links(texts: DataFrame, radius: int = 2) -> DataFrame:
    """Edges (u, v) between ``node`` numbers that span all links of 64-bit SimHash fingerprints ``fp`` within the radius.

    The operator's own search, by vantage points over the distinct fingerprints; each stands for its texts by one node.
    """
    first = materialize(texts.groupBy("fp").agg(F.min("node").alias("first")), "prints")
    equal = texts.select("node", "fp").join(first, "fp").where("node <> first").select(F.col("node").alias("u"), F.col("first").alias("v"))
    u, v = (first.select(F.col("fp").alias(k), F.col("first").alias(f"{k}_node")) for k in ("u", "v"))
    close = fingerprint_links(first, radius).join(u, "u").join(v, "v").select(F.col("u_node").alias("u"), F.col("v_node").alias("v"))
    return equal.unionByName(close)


def text_links(texts: DataFrame, radius: int = RADIUS, shard: int = SHARD) -> DataFrame:
    """Edges (u, v) between ``node`` numbers of distinct texts that may be near duplicates.

    An anchor that more than ``shard`` texts share, a boilerplate shingle for instance, is no key by
    itself: its texts are keyed by it together with each of their other anchors. A pair at similarity
    0.8 that shares this anchor has a chance of 0.2**9 to share no other.
    """
    rows = texts.select("node", *PRINTS, "anchors", F.posexplode("anchors").alias("t", "a")).withColumn("anchor", F.xxhash64("t", "a"))
    sizes = materialize(rows.groupBy("anchor").agg(F.count(F.lit(1)).alias("n")).where("n > 1"), "anchors")
    hot = sizes.where(F.col("n") > shard)
    known = bloom.build(sizes, "anchor")
    total = sizes.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    tasks = max(1, -(-total // TASK_ROWS))
    plain = ["node", *PRINTS, "anchor"]
    cold = bloom.thin(rows.select(*plain), "anchor", known).join(sizes.where(F.col("n") <= shard), "anchor").select(*plain, "n")
    if not hot.isEmpty():
        # One hot anchor has over ``shard`` of the rows, so few are hot: a broadcast instead of a shuffle of all rows.
        pairs = rows.join(F.broadcast(hot.select("anchor")), "anchor").select("node", *PRINTS, "anchor", "t", F.posexplode("anchors").alias("t2", "a2")).where("t2 <> t")
        pairs = pairs.withColumn("anchor", F.xxhash64("anchor", "t2", "a2")).select(*plain)
        again = materialize(pairs.groupBy("anchor").agg(F.count(F.lit(1)).alias("n")).where("n > 1"), "pairs")
        cold = cold.unionByName(bloom.thin(pairs, "anchor", bloom.build(again, "anchor")).join(again, "anchor").select(*plain, "n"))
    dealt = (
        cold.withColumn("parts", F.ceil(F.col("n") / shard).cast("int"))
        .transform(_in_pairs_of_parts)
        .select("node", *PRINTS, F.xxhash64("anchor", "pair.i", "pair.j").alias("bucket"), "part")
        .withColumn("task", F.pmod("bucket", F.lit(tasks * 8)))
    )

    def link(key, table):
        bucket = table.column("bucket").to_numpy()
        order = np.argsort(bucket, kind="stable")
        prints = np.stack([table.column(f).to_numpy()[order].view(U64) for f in PRINTS])
        u, v = link_rows(bucket[order], table.column("part").to_numpy()[order], table.column("node").to_numpy()[order], prints, radius)
        return pa.table({"u": u, "v": v})

    return dealt.groupBy("task").applyInArrow(link, "u bigint, v bigint")


def confirmed_links(docs: DataFrame, members: DataFrame, radius: int = RADIUS, shard: int = SHARD, part_shingles: int = PART_SHINGLES) -> DataFrame:
    """Edges (u, v) between ``node`` numbers of similar texts, within components of candidates.

    ``docs`` has (id, text); ``members`` has (root, node, k1, k2, least, size, prints), a row for
    each distinct text of a component. A component too large for a task is split into parts,
    and every pair of parts is compared by a task of its own.
    """
    weight = F.greatest(F.sum("size") / part_shingles, F.count(F.lit(1)) / shard)
    sizes = members.groupBy("root").agg(F.ceil(weight).cast("int").alias("parts"), F.sum("size").alias("shingles"))
    total = sizes.agg(F.coalesce(F.sum(F.col("shingles") * F.greatest("parts", F.lit(1))), F.lit(0))).first()[0]
    tasks = max(1, -(-int(total) // part_shingles))
    filter_ = bloom.build(members, "k1")
    marked, (k1, k2, there, _, _) = mark_texts(docs, "text", filter_)
    asked = members.join(sizes.select("root", "parts"), "root").select("root", "node", F.col("k1").alias(k1), F.col("k2").alias(k2), "least", *PRINTS, "parts")
    texts = marked.where(F.col(there)).join(asked, [k1, k2]).where(F.col("id").eqNullSafe(F.col("least"))).select("root", "node", *PRINTS, "parts", "text")
    plain = ["root", "node", *PRINTS, "parts"]

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole):
                hashes, counts = distinct_shingles(*utf8(batch.column("text")))
                ends = np.concatenate([[0], np.cumsum(counts)]) * 8
                sets = pa.Array.from_buffers(pa.large_binary(), len(counts), [None, pa.py_buffer(ends.astype(np.int64)), pa.py_buffer(hashes)])
                yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in plain), sets.cast(pa.binary())], names=[*plain, "shingles"])

    schema = f"root bigint, node bigint, {', '.join(f'{f} bigint' for f in PRINTS)}, parts int, shingles binary"
    dealt = (
        texts.mapInArrow(cut, schema)
        .transform(_in_pairs_of_parts)
        .select("node", *PRINTS, "shingles", F.xxhash64("root", "pair.i", "pair.j").alias("bucket"), "part")
        .withColumn("task", F.pmod("bucket", F.lit(tasks * 8)))
    )

    def confirm(key, table):
        bucket = table.column("bucket").to_numpy()
        order = np.argsort(bucket, kind="stable")
        prints = np.stack([table.column(f).to_numpy()[order].view(U64) for f in PRINTS])
        held = table.column("shingles")
        sets = [np.frombuffer(held[i].as_buffer(), U64) for i in order.tolist()]
        u, v = link_rows(bucket[order], table.column("part").to_numpy()[order], table.column("node").to_numpy()[order], prints, radius, sets)
        return pa.table({"u": u, "v": v})

    return dealt.groupBy("task").applyInArrow(confirm, "u bigint, v bigint")


def keep_one_of_each(docs: DataFrame, radius: int = RADIUS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with one row left of each group of near-duplicate texts, the one of the smallest id.

    Texts whose distinct shingles have a Jaccard similarity of ``SIMILAR`` or more are near
    duplicates, and a group is what chains of them connect.
    Exact copies, repeated rows among them, count as duplicates, and so do all texts without
    words, null ones included. A null id stays only where its group has no other. Columns are
    as before; an empty table gives no rows.
    """
    rows = docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).alias("text"))
    sketch = ["size", "fp", *PRINTS, "anchors"]
    by_row = _sketch(rows).groupBy("k1", "k2", "id").agg(F.count(F.lit(1)).alias("n"), *(F.first(f).alias(f) for f in sketch))
    lowest = F.min(F.struct(F.col("id").isNull().alias("none"), "id", "n")).alias("low")
    by_text = by_row.groupBy("k1", "k2").agg(lowest, F.sum("n").alias("n"), *(F.first(f).alias(f) for f in sketch))
    by_text = by_text.select("k1", "k2", F.col("low.id").alias("least"), F.col("low.n").alias("same"), "n", *sketch)
    texts = materialize(by_text.withColumn("node", F.monotonically_increasing_id()), "texts")
    maybe = connected_components(print_links(texts).unionByName(text_links(texts, radius)))
    members = materialize(maybe.join(texts.drop("anchors", "fp"), "node"), "members")
    groups = connected_components(confirmed_links(rows, members, radius))
    named = materialize(groups.join(texts.select("node", "least", "k1", "k2"), "node"), "groups")
    chosen = named.groupBy("root").agg(F.min(F.struct(F.col("least").isNull().alias("none"), "least", "node")).alias("best")).select("root", F.col("best.node").alias("best"))
    gone = named.join(chosen, "root").where("node <> best").select("k1", "k2", F.lit(True).alias("gone"), F.lit(None).cast("bigint").alias("keep"), F.lit(0).cast("bigint").alias("same"))
    copied = texts.where("n > 1").select("k1", "k2", "least", "same").join(gone.select("k1", "k2"), ["k1", "k2"], "left_anti").select("k1", "k2", F.lit(False).alias("gone"), F.col("least").alias("keep"), "same")
    decisions = materialize(gone.unionByName(copied), "decisions")
    touched = bloom.build(decisions, "k1")
    marked, (k1, k2, there, keep, same) = mark_texts(docs, text_col, touched)
    names = docs.columns
    known = decisions.select(F.col("k1").alias(k1), F.col("k2").alias(k2), F.col("keep").alias(keep), F.when(~F.col("gone"), F.col("same")).otherwise(-1).alias(same))
    left = F.col(same).isNull() | ((F.col(same) > 0) & F.col(id_col).cast("bigint").eqNullSafe(F.col(keep)))
    some = materialize(marked.where(F.col(there)).join(known, [k1, k2], "left").where(left).drop(there, keep), "kept")
    release(texts, members, named, decisions)
    once = some.where(F.coalesce(F.col(same), F.lit(1)) == 1).select(*names)
    repeated = some.where(F.col(same) > 1).dropDuplicates([k1, k2]).select(*names)
    return marked.where(~F.col(there)).select(*names).unionByName(once).unionByName(repeated)
