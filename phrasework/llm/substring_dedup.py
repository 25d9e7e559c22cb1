"""Repeated word spans by compacting the de Bruijn graph of word windows.

An edge of the graph is a k-mer of ``width`` words, a window. Three steps find where it repeats:

* Edges. In each text, consecutive windows with the same least ``anchor``-word k-mer form a run, a
  stretch without a fork as far as its own text goes. Equal windows have equal anchors, so only
  runs of anchors seen twice matter. Where an anchor has one content, its run is an edge as it
  stands; where it has several the path forks inside, and its windows become edges one by one.
* Compaction. An edge's degrees are counted over all its occurrences. Where an edge has a single
  predecessor that has it as single successor, a join of the degree table with itself says so,
  and the two become one path. Every occurrence of a path's first edge then begins the path.
* Verification. Each occurrence's words are read again at its source coordinates (text, word
  position), and occurrences count only with others of the same path and the same SHA-256 of the
  words themselves. Hashes alone never remove a word.

Window hashes combine halves by a non-linear mix, so word sequences of a regular build (such as
Thue-Morse words) collide no oftener than others.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType, LongType, StructField, StructType

from phrasework.llm import bloom
from phrasework.llm.textbytes import PRIME_5, U64, Words, mix, slices, span_hashes, utf8
from phrasework.shared import materialize, release

WIDTH, ANCHOR = 35, 6
#: Texts that a map task remembers having sent on.
REMEMBERED = 1 << 18
#: Most edges that count as hot, and least runs of one that does.
HOT_EDGES, HOT_RUNS = 100_000, 1024


class Spans:
    """Hashes of word ranges in two independent streams: two overlapping halves of a power of two, mixed."""

    def __init__(self, words: Words):
        groups = words.padded()
        self.levels = [[span_hashes(groups, words.starts, words.ends, seed + 1)] for seed in range(2)]

    def _level(self, stream: int, t: int) -> np.ndarray:
        levels = self.levels[stream]
        while len(levels) <= t:
            below, half = levels[-1], 1 << (len(levels) - 1)
            levels.append(_combined(below[:-half], below[half:], 2 * half))
        return levels[t]

    def of(self, stream: int, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        size = end - start
        out = np.empty(len(start), U64)
        log2 = np.frexp(size.astype(np.float64))[1] - 1
        for t in np.unique(log2).tolist():
            at, level = np.flatnonzero(log2 == t), self._level(stream, t)
            out[at] = _combined(level[start[at]], level[end[at] - (1 << t)], size[at])
        return out


def _combined(a: np.ndarray, b: np.ndarray, size) -> np.ndarray:
    return mix((mix(a + np.asarray(size).astype(U64)) * PRIME_5) ^ b)


def sliding_least(keys: np.ndarray, width: int) -> np.ndarray:
    """Minimum of each ``width`` consecutive keys."""
    size = 1
    while 2 * size <= width:
        keys = np.minimum(keys[:-size], keys[size:])
        size *= 2
    rest = width - size
    return np.minimum(keys[: len(keys) - rest], keys[rest:]) if rest else keys


def runs_of(words: Words, spans: Spans, width: int, anchor: int) -> tuple[np.ndarray, ...]:
    """Runs of a batch: (first window, windows, anchor hash, content hash), in order.

    A run's windows share one place of their least anchor. Anchors compare by their whole hash, ties by
    place, so a text gives the same runs in whatever batch it comes.
    """
    n = len(words)
    last = np.repeat(words.rows[1:], words.counts) - width
    windows = np.flatnonzero(np.arange(n) <= last)
    if not len(windows):
        none = np.zeros(0, np.int64)
        return none, none, none.view(U64), none.view(U64)
    at = np.arange(n - anchor + 1)
    order = spans.of(0, at, at + anchor)
    rank = np.unique(order, return_inverse=True)[1].astype(U64)  # equal hashes stay equal: the first place wins
    place = (sliding_least(rank << U64(32) | at.astype(U64), width - anchor + 1)[windows] & U64((1 << 32) - 1)).astype(np.int64)
    new = np.ones(len(windows), bool)
    new[1:] = (place[1:] != place[:-1]) | (windows[1:] != windows[:-1] + 1)
    first = np.flatnonzero(new)
    count = np.diff(np.append(first, len(windows)))
    start = windows[first]
    return start, count, order[place[first]], spans.of(0, start, start + count - 1 + width)


def text_keys(raw: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """128-bit key of each whole text, as two longs."""
    digest = b"".join(xxhash.xxh3_128_digest(raw[a:b].data) for a, b in zip(at[:-1], at[1:]))
    pair = np.frombuffer(digest, "<i8").reshape(-1, 2)
    return pair[:, 0].copy(), pair[:, 1].copy()


def _lists(offsets: np.ndarray, **columns: np.ndarray) -> pa.Array:
    struct = pa.StructArray.from_arrays([pa.array(v) for v in columns.values()], names=list(columns))
    return pa.ListArray.from_arrays(pa.array(offsets.astype(np.int32)), struct)


SCAN = "id bigint, k1 bigint, k2 bigint, n_words bigint, sha string, runs array<struct<m:bigint,r:bigint,s:int,n:int>>"


def _scan(docs: DataFrame, width: int, anchor: int) -> DataFrame:
    """Each document's key, word count, digest of all its words, and runs."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole):
                raw, at = utf8(batch.column("text"))
                k1, k2 = text_keys(raw, at)
                words = Words(raw, at)
                start, count, m, r = runs_of(words, Spans(words), width, anchor)
                sha = [hashlib.sha256(words.row_bytes(i)).hexdigest() for i in range(len(k1))]
                bounds = np.searchsorted(start, words.rows)
                owner = np.repeat(np.arange(len(k1)), np.diff(bounds))
                runs = _lists(bounds, m=m.view(np.int64), r=r.view(np.int64), s=(start - words.rows[owner]).astype(np.int32), n=count.astype(np.int32))
                arrays = [batch.column("id"), pa.array(k1), pa.array(k2), pa.array(words.counts), pa.array(sha), runs]
                yield pa.RecordBatch.from_arrays(arrays, names=["id", "k1", "k2", "n_words", "sha", "runs"])

    return docs.mapInArrow(run, SCAN)


def _texts(docs: DataFrame, filter_) -> DataFrame:
    """(k1, k2, text) of texts that the filter may hold, about once for each map task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[tuple[int, int]] = set()
        for whole in batches:
            for batch in slices(whole):
                k1, k2 = text_keys(*utf8(batch.column("text")))
                keep = []
                for i in np.flatnonzero(bloom.contains(filter_.value, k1)).tolist():
                    key = (int(k1[i]), int(k2[i]))
                    if key not in seen:
                        keep.append(i)
                        if len(seen) >= REMEMBERED:
                            seen.clear()
                        seen.add(key)
                if keep:
                    keep = pa.array(keep)
                    yield pa.RecordBatch.from_arrays([pa.array(k1).take(keep), pa.array(k2).take(keep), batch.column("text").take(keep)], names=["k1", "k2", "text"])

    return docs.select("text").mapInArrow(run, "k1 bigint, k2 bigint, text string")


def _owners(lists: pa.Array) -> tuple[pa.Array, np.ndarray]:
    """All elements of a list column, and the row each belongs to."""
    return lists.flatten(), np.repeat(np.arange(len(lists)), lists.value_lengths().fill_null(0).to_numpy(zero_copy_only=False))


def _fork_windows(found: DataFrame, width: int, filter_=None) -> DataFrame:
    """Windows of the runs where paths fork, as edges: (w1, w2, place), ``place`` hashing the coordinates.

    With a filter only windows whose ``w1`` it may hold, with neighbours and coordinates instead:
    (w1, p, q, w2, k1, k2, s), ``p`` and ``q`` being the edges one word before and after, 0 for none.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole):
                words = Words(*utf8(batch.column("text")))
                spans = Spans(words)
                flat, owner = _owners(batch.column("asked"))
                s, n = flat.field(0).to_numpy().astype(np.int64), flat.field(1).to_numpy().astype(np.int64)
                pos = np.repeat(s - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum())
                owner = np.repeat(owner, n)
                order = np.lexsort((pos, owner))
                pos, owner = pos[order], owner[order]
                follows = np.zeros(len(pos) + 1, bool)
                follows[1:-1] = (owner[1:] == owner[:-1]) & (pos[1:] == pos[:-1] + 1)
                start = words.rows[owner] + pos
                arrays = {"w1": spans.of(0, start, start + width).view(np.int64)}
                if filter_ is not None:
                    beside = np.concatenate([[0], arrays["w1"], [0]])
                    arrays |= {"p": np.where(follows[:-1], beside[:-2], 0), "q": np.where(follows[1:], beside[2:], 0)}
                    likely = bloom.contains(filter_.value, arrays["w1"])
                    pos, owner, start, arrays = pos[likely], owner[likely], start[likely], {c: v[likely] for c, v in arrays.items()}
                arrays["w2"] = spans.of(1, start, start + width).view(np.int64)
                keys = [batch.column(k).to_numpy()[owner] for k in ("k1", "k2")]
                if filter_ is None:
                    arrays["place"] = mix(keys[0].view(U64) + mix(keys[1].view(U64) + pos.astype(U64))).view(np.int64)
                else:
                    arrays |= {"k1": keys[0], "k2": keys[1], "s": pos.astype(np.int32)}
                for k in range(0, len(start), 1 << 18):
                    yield pa.RecordBatch.from_arrays([pa.array(v[k : k + (1 << 18)]) for v in arrays.values()], names=list(arrays))

    schema = "w1 bigint, w2 bigint, place bigint" if filter_ is None else "w1 bigint, p bigint, q bigint, w2 bigint, k1 bigint, k2 bigint, s int"
    return found.where("size(asked) > 0").select("k1", "k2", "text", "asked").mapInArrow(run, schema)


def _degrees() -> list[Column]:
    """Aggregates over an edge's occurrences that tell a single predecessor or successor; 0 is none."""
    return [f(c).alias(f"{name}_{c}") for c in ("p", "q") for f, name in ((F.min, "least"), (F.max, "most"))]


def _inner(edges: DataFrame, key: list[str]) -> DataFrame:
    """Keys of edges that only continue a path: one predecessor, of which they are the one successor.

    ``edges`` has one row an edge with its key and degrees; neighbours are named by the key's last column.
    """
    last = key[-1]
    one = edges.where("least_p = most_p and least_p <> 0").select(*key, F.col("least_p").alias("p"))
    before = edges.where("least_q = most_q and least_q <> 0").select(F.col(last).alias("p"), F.col("least_q").alias(last)).distinct()
    return one.join(before, ["p", last]).select(*key).distinct()


def _paths(found: DataFrame, width: int) -> DataFrame:
    """Occurrences of compacted paths with the digest of their words: (k1, k2, path, s, n, copies, digest).

    In each text an edge that only continues a path is joined to the one it follows.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole):
                words = Words(*utf8(batch.column("text")))
                parts = []
                for column in ("sure", "hits"):
                    flat, owner = _owners(batch.column(column))
                    s, n, edge, inner, copies = (flat.field(k).to_numpy(zero_copy_only=False) for k in range(5))
                    order = np.lexsort((s, owner))
                    owner, s, n, edge, inner, copies = owner[order], s[order].astype(np.int64), n[order].astype(np.int64), edge[order], inner[order].astype(bool), copies[order]
                    begins = np.ones(len(s), bool)
                    begins[1:] = ~inner[1:] | (owner[1:] != owner[:-1]) | (s[1:] != s[:-1] + n[:-1])
                    first = np.flatnonzero(begins)
                    size = np.add.reduceat(n, first) if len(first) else n[:0]
                    parts.append((owner[first], s[first], size, edge[first], copies[first]))
                owner, s, n, path, copies = (np.concatenate(c) for c in zip(*parts))
                at = words.rows[owner] + s
                digest = [hashlib.sha256(words.text[a:b].data).digest() for a, b in zip(words.starts[at], words.ends[at + n + width - 2])] if len(at) else []
                arrays = [batch.column("k1").to_numpy()[owner], batch.column("k2").to_numpy()[owner], path, s.astype(np.int32), n.astype(np.int32), copies.astype(np.int64)]
                yield pa.RecordBatch.from_arrays([*map(pa.array, arrays), pa.array(digest, pa.binary())], names=["k1", "k2", "path", "s", "n", "copies", "digest"])

    return found.select("k1", "k2", "text", "sure", "hits").mapInArrow(run, "k1 bigint, k2 bigint, path bigint, s int, n int, copies bigint, digest binary")


def _cut(found: DataFrame, width: int) -> DataFrame:
    """Remove the words that verified paths cover: (k1, k2, n_removed, kept, kept_sha)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole):
                words = Words(*utf8(batch.column("text")))
                change = np.zeros(len(words) + 1, np.int64)
                flat, owner = _owners(batch.column("spans"))
                s, n = flat.field(0).to_numpy().astype(np.int64), flat.field(1).to_numpy().astype(np.int64)
                np.add.at(change, words.rows[owner] + s, 1)
                np.add.at(change, words.rows[owner] + s + n - 1 + width, -1)
                gone = np.cumsum(change[:-1]) > 0
                kept_text, removed = [], []
                for i in range(batch.num_rows):
                    a, b = words.rows[i], words.rows[i + 1]
                    left = ~gone[a:b]
                    removed.append(int(b - a - left.sum()))
                    edge = np.flatnonzero(np.diff(np.concatenate([[0], left.view(np.int8), [0]])))
                    spans = [words.text[words.starts[a + x] : words.ends[a + y - 1]].tobytes() for x, y in zip(edge[::2], edge[1::2])]
                    kept_text.append(b" ".join(spans))
                sha = [hashlib.sha256(x).hexdigest() for x in kept_text]
                arrays = [batch.column("k1"), batch.column("k2"), pa.array(removed), pa.array(kept_text, pa.binary()).cast(pa.string()), pa.array(sha)]
                yield pa.RecordBatch.from_arrays(arrays, names=["k1", "k2", "n_removed", "kept", "kept_sha"])

    return found.select("k1", "k2", "text", "spans").mapInArrow(run, "k1 bigint, k2 bigint, n_removed bigint, kept string, kept_sha string")


def _spread_join(rows: DataFrame, known: DataFrame, on: list[str], total: int, spread: list[str]) -> DataFrame:
    """``rows`` with the further columns of ``known``, which has each key ``on`` once and its rows' number ``c``.

    A key of more than a ``HOT_EDGES``th of all ``total`` rows is hot; there are fewer than that many, so
    they are broadcast, and their rows are spread by ``spread`` over the join that the others go through.
    """
    least = max(HOT_RUNS, total // HOT_EDGES)
    further = [c for c in known.columns if c not in (*on, "c")]
    packed = F.struct(F.lit(True).alias("there"), *further)
    hot = known.where(F.col("c") > least).select(*on, packed.alias("hot"))
    cold = known.where(F.col("c") <= least).select(F.col(on[0]).alias("key"), *on[1:], packed.alias("cold"))
    keyed = rows.join(F.broadcast(hot), on, "left").withColumn("key", F.when(F.col("hot").isNotNull(), F.xxhash64(*spread)).otherwise(F.col(on[0])))
    found = keyed.join(cold, ["key", *on[1:]], "left").withColumn("found", F.coalesce("hot", "cold")).where("found is not null")
    return found.select(*rows.columns, *(F.col(f"found.{c}").alias(c) for c in further))


class RepeatedSpans:
    """What the search finds in ``docs`` (columns id, text): ``scan`` by row, ``changed`` by text."""

    def __init__(self, docs: DataFrame, width: int = WIDTH, anchor: int = ANCHOR):
        self.docs = docs
        self.scan = materialize(_scan(docs, width, min(anchor, width)), "runs")
        runs = self.scan.select("k1", "k2", F.expr("inline(transform(runs, (x, i) -> struct(x.m as m, x.r as r, x.s as s, x.n as n, coalesce(get(runs, i - 1).r, 0L) as p, coalesce(get(runs, i + 1).r, 0L) as q)))"))
        repeated = materialize(runs.groupBy("m").agg(F.count(F.lit(1)).alias("c")).where("c > 1").select("m"), "anchors")
        candidates = bloom.thin(runs, "m", bloom.build(repeated, "m"))
        contents = materialize(candidates.groupBy("m", "r").agg(F.count(F.lit(1)).alias("c"), F.min(F.struct("k1", "k2", "s", "n")).alias("one"), *_degrees()), "contents")
        again = contents.where("c > 1")
        again = again.select("m", "r", "c").join(_inner(again, ["m", "r"]).withColumn("inner", F.lit(True)), ["m", "r"], "left")
        whole = _spread_join(candidates, again, ["m", "r"], contents.agg(F.coalesce(F.sum("c"), F.lit(0))).first()[0], ["k1", "s"])
        whole = whole.groupBy("k1", "k2", "s", "n", "r").agg(F.coalesce(F.first("inner"), F.lit(False)).alias("inner"), F.count(F.lit(1)).alias("copies"))
        forks = contents.groupBy("m").agg(F.count(F.lit(1)).alias("ways")).where("ways > 1").select("m")
        asked = contents.join(forks, "m").select("one.*")
        edge = F.struct("s", "n", F.col("r").alias("edge"), "inner", "copies")
        by_text = whole.select("k1", "k2", edge.alias("edge"), F.lit(None).cast("struct<s:int,n:int>").alias("piece")).unionByName(
            asked.select("k1", "k2", F.lit(None).cast("struct<s:int,n:int,edge:bigint,inner:boolean,copies:bigint>").alias("edge"), F.struct("s", "n").alias("piece"))
        )
        by_text = materialize(by_text.groupBy("k1", "k2").agg(F.collect_list("edge").alias("sure"), F.collect_list("piece").alias("asked")), "coordinates")
        self.touched = bloom.build(by_text, "k1")
        texts = _texts(docs, self.touched).groupBy("k1", "k2").agg(F.first("text").alias("text"))
        found = materialize(texts.join(by_text, ["k1", "k2"]), "texts")
        release(repeated, contents, by_text)
        windows = _fork_windows(found, width).groupBy("w1", "w2").agg(F.min("place").alias("a"), F.max("place").alias("b"))
        windows = materialize(windows.where("a <> b").select("w1", "w2"), "windows")
        likely = materialize(_fork_windows(found, width, bloom.build(windows, "w1")).join(windows, ["w1", "w2"]), "edges")
        inner = _inner(likely.groupBy("w2", "w1").agg(*_degrees()), ["w2", "w1"]).withColumn("inner", F.lit(True))
        edge = F.struct("s", F.lit(1).alias("n"), F.col("w1").alias("edge"), F.coalesce("inner", F.lit(False)).alias("inner"), F.lit(1).cast("bigint").alias("copies"))
        hits = likely.join(inner, ["w2", "w1"], "left").groupBy("k1", "k2").agg(F.collect_list(edge).alias("hits"))
        path = ["path", "n", "digest"]
        occurrences = materialize(_paths(found.join(hits, ["k1", "k2"], "left").where("size(sure) > 0 or hits is not null"), width), "paths")
        release(windows, likely)
        verified = occurrences.groupBy(*path).agg(F.sum("copies").alias("c")).where("c > 1").select(*path, "c")
        spans = _spread_join(occurrences, verified, path, occurrences.agg(F.coalesce(F.sum("copies"), F.lit(0))).first()[0], ["k1", "s"]).groupBy("k1", "k2").agg(F.collect_list(F.struct("s", "n")).alias("spans"))
        #: One row for each text that loses words.
        self.changed = materialize(_cut(found.join(spans, ["k1", "k2"]), width), "changed")
        release(found, occurrences)


def _rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).alias("text"))


def removed_spans(docs: DataFrame, width: int = WIDTH, anchor: int = ANCHOR, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """What each document loses: (id, n_words, n_removed, kept_sha256).

    A word goes if a window of ``width`` words covers it whose words also start anywhere else,
    in the same or another document, copies included. Null and empty texts have no words;
    documents shorter than ``width`` lose nothing; null ids and repeated rows stay (a repeated
    row is a copy). An empty table gives no rows.
    """
    found = RepeatedSpans(_rows(docs, id_col, text_col), width, anchor)
    changed = found.changed.select("k1", "k2", "n_removed", "kept_sha")
    return found.scan.join(changed, ["k1", "k2"], "left").select(
        "id", "n_words", F.coalesce("n_removed", F.lit(0)).cast("bigint").alias("n_removed"), F.coalesce("kept_sha", "sha").alias("kept_sha256")
    )


def mark_texts(docs: DataFrame, text_col: str, filter_) -> tuple[DataFrame, list[str]]:
    """``docs`` with its texts' keys and whether the filter may hold them, in new columns.

    Returns five column names that ``docs`` doesn't have, whatever else it has: of the key's
    halves, of the filter's answer, and two to spare.
    """
    names, taken = docs.columns, {c.lower() for c in docs.columns}
    fresh = []
    for name in ("__k1", "__k2", "__there", "__first", "__second"):
        while name in taken:
            name += "_"
        fresh.append(name)
    at = names.index(text_col)

    def mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            k1, k2 = text_keys(*utf8(batch.column(at)))
            there = bloom.contains(filter_.value, k1)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(k1), pa.array(k2), pa.array(there)], names=[*names, *fresh[:3]])

    added = [StructField(n, t) for n, t in zip(fresh, (LongType(), LongType(), BooleanType()))]
    return docs.mapInArrow(mark, StructType([*docs.schema.fields, *added])), fresh


def remove_spans(docs: DataFrame, width: int = WIDTH, anchor: int = ANCHOR, text_col: str = "text") -> DataFrame:
    """``docs`` with repeated spans taken out of ``text_col``; a text that loses nothing stays as it is.

    What is left of a changed text are its kept words joined by one space. All columns and rows
    stay, null texts too.
    """
    found = RepeatedSpans(docs.select(F.lit(None).cast("bigint").alias("id"), F.col(text_col).alias("text")), width, anchor)
    marked, (k1, k2, there, kept, _) = mark_texts(docs, text_col, found.touched)
    changed = found.changed.select(F.col("k1").alias(k1), F.col("k2").alias(k2), F.col("kept").alias(kept))
    some = marked.where(F.col(there)).join(changed, [k1, k2], "left")
    after = some.select(*(F.coalesce(kept, F.col(c)).alias(c) if c == text_col else F.col(c) for c in docs.columns))
    return marked.where(~F.col(there)).select(*docs.columns).unionByName(after)
