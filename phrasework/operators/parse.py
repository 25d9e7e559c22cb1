"""Parses of strings in DataFrames: the two-way parse, its options, and the methods beside it."""

from __future__ import annotations

import time
import tracemalloc
from collections.abc import Callable
from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from phrasework import schemas
from phrasework.kernels import extras, greedy
from phrasework.kernels.suffix import SuffixIndex, codes_of
from phrasework.kernels.two_way import Options, TwoWay
from phrasework.operators import jvm
from phrasework.operators.batches import map_strings

#: Characters that a task parses on average.
CHARS_PER_TASK = 4 << 20
#: Least number of tasks for each core, so that a few long strings rarely share one.
TASKS_PER_CORE = 16

METHODS: dict[str, Callable] = {
    "two_way": lambda codes, index, o: TwoWay(codes, o, index).run().phrases,
    "lz77": lambda codes, index, o: greedy.left_parse(codes, index),
    "lz_next": lambda codes, index, o: greedy.right_parse(codes, index),
    "lz_backward": lambda codes, index, o: greedy.backward_parse(codes),
    "lex": lambda codes, index, o: greedy.lex_parse(codes, index),
    "lcp_first": lambda codes, index, o: extras.largest_first_parse(codes, 2, index),
    "bwt_run": lambda codes, index, o: extras.bwt_run_parse(codes, index),
    "literal": lambda codes, index, o: greedy.literal_parse(codes),
    "smallest": lambda codes, index, o: extras.smallest_parse(codes),
}


def balanced(S: DataFrame, chars_per_task: int = CHARS_PER_TASK, total: int | None = None) -> DataFrame:
    """Strings dealt by a hash of their key to tasks of about ``chars_per_task`` characters each.

    The shuffle moves each text once; one string is never split, so the longest one bounds the
    longest task. Without ``total``, the characters of all strings, one job counts them first, and
    notes the longest string on the frame for :func:`counts`.
    """
    longest = None
    if total is None:
        total, longest = S.agg(F.coalesce(F.sum(F.length("text")), F.lit(0)), F.coalesce(F.max(F.length("text")), F.lit(0))).first()
    tasks = max(-(-int(total) // chars_per_task), TASKS_PER_CORE * S.sparkSession.sparkContext.defaultParallelism)
    dealt = S.repartition(tasks, F.xxhash64("string_id"))
    dealt._longest = longest
    return dealt


def distinct_texts(S: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Texts once each under a key of their own, and (string_id, key) to bring results back."""
    keyed = S.where("text is not null").withColumn("key", F.sha2("text", 256))
    return keyed.groupBy("key").agg(F.first("text").alias("text")).select(F.col("key").alias("string_id"), "text"), keyed.select("string_id", "key")


def _phrase_rows(key: str, text: str, phrases: greedy.Phrases, unit: str):
    raw = text.encode() if unit == "byte" else None
    for k, (start, size, ref) in enumerate(phrases):
        literal = None if ref >= 0 else text[start] if raw is None else f"{raw[start]:02x}"
        side = "literal" if ref < 0 else "left" if ref < start else "right"
        yield key, k + 1, start + 1, size, ref + 1 if ref >= 0 else None, literal, side


def phrases_of(text: str, method: str, options: Options = Options(), direction: str = "forward", unit: str = "codepoint", map_back: bool = True) -> greedy.Phrases:
    """Parse one string in one direction; ``best`` takes the smaller count, forward on a tie."""
    codes = codes_of(text, unit)
    if direction == "best":
        both = [phrases_of(text, method, options, d, unit, map_back) for d in ("forward", "reverse")]
        return min(both, key=len)
    if direction == "reverse":
        codes = codes[::-1].copy()
    elif direction != "forward":
        raise ValueError(f"unknown direction {direction!r}")
    found = METHODS[method](codes, SuffixIndex(codes), options)
    return greedy.map_back(found, len(codes)) if direction == "reverse" and map_back else found


def parse(S: DataFrame, method: str = "two_way", direction: str = "forward", unit: str = "codepoint", map_back: bool = True, collapse: bool = False, **options) -> DataFrame:
    """PHRASES of every string by ``method``; options as in :class:`Options` for the two-way parse.

    A reversed parse is given in the string's own positions unless ``map_back`` is off. With
    ``collapse`` equal texts are parsed once. Null texts give no phrases, empty ones none either.
    """
    chosen = Options(**options)
    if method not in METHODS:
        raise ValueError(f"unknown method {method!r}")

    def rows(key: str, text: str):
        own = text[::-1] if direction == "reverse" and not map_back else text
        return _phrase_rows(key, own, phrases_of(text, method, chosen, direction, unit, map_back), unit)

    if collapse:
        texts, keys = distinct_texts(S)
        found = map_strings(balanced(texts), schemas.PHRASES, rows).withColumnRenamed("string_id", "key")
        return keys.join(found, "key").select(*schemas.names(schemas.PHRASES))
    return map_strings(S, schemas.PHRASES, rows)


def two_way_parse(S: DataFrame, **options) -> DataFrame:
    return parse(S, "two_way", **options)


def lz77_parse(S: DataFrame, **options) -> DataFrame:
    return parse(S, "lz77", **options)


def lz_next_parse(S: DataFrame, **options) -> DataFrame:
    return parse(S, "lz_next", **options)


def lz_backward_parse(S: DataFrame, **options) -> DataFrame:
    return parse(S, "lz_backward", **options)


def lex_parse(S: DataFrame, **options) -> DataFrame:
    return parse(S, "lex", **options)


def lcp_first_parse(S: DataFrame, threshold: int = 2) -> DataFrame:
    return map_strings(S, schemas.PHRASES, lambda key, text: _phrase_rows(key, text, extras.largest_first_parse(codes_of(text), threshold), "codepoint"))


def bwt_run_parse(S: DataFrame) -> DataFrame:
    return parse(S, "bwt_run")


def literal_parse(S: DataFrame) -> DataFrame:
    return parse(S, "literal")


def smallest_parse(S: DataFrame) -> DataFrame:
    return parse(S, "smallest")


def bwt_runs(S: DataFrame) -> DataFrame:
    """(string_id, runs) of the Burrows-Wheeler transform."""
    return map_strings(S, "string_id string, runs bigint", lambda key, text: [(key, extras.bwt_runs(codes_of(text)))])


def _with_positions(S: DataFrame, positions: DataFrame, schema: str, kernel: Callable) -> DataFrame:
    """Rows of ``kernel(string_id, text, 0-based positions)``; strings without a position get an empty set."""
    marked = S.where("text is not null").join(positions.groupBy("string_id").agg(F.collect_set(F.col("pos").cast("string")).alias("at")), "string_id", "left")
    packed = marked.select("string_id", F.concat_ws("\n", F.coalesce(F.array_join("at", ","), F.lit("")), "text").alias("text"))

    def rows(key: str, both: str):
        at, text = both.split("\n", 1)
        return kernel(key, text, {int(p) - 1 for p in at.split(",") if p})

    return map_strings(packed, schema, rows)


def attractor_parse(S: DataFrame, positions: DataFrame) -> DataFrame:
    """PHRASES grown around the attractor of each string, given as rows (string_id, 1-based pos)."""
    return _with_positions(S, positions, schemas.PHRASES, lambda key, text, at: _phrase_rows(key, text, extras.attractor_parse(codes_of(text), at), "codepoint"))


def is_attractor(S: DataFrame, positions: DataFrame) -> DataFrame:
    """(string_id, is_attractor): whether every substring has an occurrence that covers one of the string's positions."""
    return _with_positions(S, positions, "string_id string, is_attractor boolean", lambda key, text, at: [(key, extras.is_attractor(codes_of(text), at))])


def smallest_attractor(S: DataFrame) -> DataFrame:
    """(string_id, pos): a smallest attractor of each string of up to ten characters."""
    return map_strings(S, "string_id string, pos bigint", lambda key, text: [(key, p + 1) for p in sorted(extras.smallest_attractor(codes_of(text)))])


def packed_parse(S: DataFrame, method: str = "two_way") -> DataFrame:
    """(string_id, text, pieces): all phrases of a string of up to ``jvm.ROW_CHARS`` characters in one array, in order."""
    return S.select("string_id", "text", jvm.parse(S.sparkSession, "text", method).alias("pieces"))


def _peak_bytes(codes: np.ndarray, method: str, options: Options) -> int:
    """Most memory that a method, its index included, takes at once, as the allocators report it."""
    tracemalloc.start()
    try:
        METHODS[method](codes, SuffixIndex(codes), options)
        return tracemalloc.get_traced_memory()[1]
    finally:
        tracemalloc.stop()


def counts(S: DataFrame, methods: tuple[str, ...] = ("lz77", "lex", "two_way"), directions: tuple[str, ...] = ("forward", "reverse"), unit: str = "codepoint", memory: bool = False, **options) -> DataFrame:
    """COUNTS by method and direction without phrase rows; one suffix index a direction.

    ``seconds`` holds the method's own processor time with its index. With ``memory`` ``bytes`` holds its measured
    peak beyond the string; else it is null. Under the default rules strings of up to ``jvm.JVM_CHARS`` characters
    are parsed in Spark's own process, and with ``memory`` those of any length, by kernels that take little of it and
    add up their arrays; elsewhere each method runs once more for that, alone and traced.
    """
    if unit == "codepoint" and memory and not options and set(methods) <= set(jvm.LEAN_METHODS):
        found = F.explode(jvm.costs(S.sparkSession, "text", methods, directions)).alias("found")
        fields = ("method", "direction", *schemas.names(schemas.COUNTS)[1:])
        return S.select("string_id", found).select("string_id", *(F.col(f"found.{c}") for c in fields))
    if unit == "codepoint" and not memory and not options and set(methods) <= set(jvm.METHODS):
        found = F.explode(jvm.counts(S.sparkSession, "text", methods, directions)).alias("found")
        fields = ("method", "direction", *schemas.names(schemas.COUNTS)[1:-1])
        fits = F.length("text") <= jvm.JVM_CHARS
        short = S.where(fits).select("string_id", found).select("string_id", *(F.col(f"found.{c}") for c in fields), F.lit(None).cast("bigint").alias("bytes"))
        longest = getattr(S, "_longest", None)
        return short if longest is not None and longest <= jvm.JVM_CHARS else short.unionByName(_worker_counts(S.where(~fits), methods, directions, unit, memory))
    return _worker_counts(S, methods, directions, unit, memory, **options)


def lean_counts(S: DataFrame, methods: tuple[str, ...] = ("lz77", "lex", "two_way"), directions: tuple[str, ...] = ("forward", "reverse")) -> DataFrame:
    """(string_id, method, direction, n, phrases) of long strings in little memory, each direction a task of its own.

    Left and right parses of both directions come from the first direction's suffix order.
    """
    if unknown := set(methods) - set(jvm.LEAN_METHODS):
        raise ValueError(f"no lean form of {sorted(unknown)}")
    asked = {way: [] for way in directions}
    for method in methods:
        for direction in directions:
            asked[directions[0] if method in ("lz77", "lz_next") else direction].append(f"{method}:{direction}")
    ways = F.array(*(F.struct(F.lit(way).alias("way"), F.lit(",".join(items)).alias("wanted")) for way, items in asked.items() if items))
    dealt = S.select("string_id", "text", F.explode(ways).alias("w")).repartition(TASKS_PER_CORE * S.sparkSession.sparkContext.defaultParallelism, "string_id", "w.way")
    found = F.explode(jvm.work(S.sparkSession, "text", F.col("w.way"), F.col("w.wanted"))).alias("found")
    return dealt.select("string_id", found).select("string_id", "found.method", "found.direction", "found.n", "found.phrases")


def _worker_counts(S: DataFrame, methods: tuple[str, ...], directions: tuple[str, ...], unit: str, memory: bool, **options) -> DataFrame:
    """``counts`` by the numpy kernels in Python workers."""
    chosen = Options(**options)
    schema = "string_id string, method string, direction string, " + schemas.COUNTS.split(", ", 1)[1]

    def rows(key: str, text: str):
        forward = codes_of(text, unit)
        for direction in directions:
            codes = forward[::-1].copy() if direction == "reverse" else forward
            began = time.process_time()
            index = SuffixIndex(codes)
            shared = time.process_time() - began
            for method in methods:
                began = time.process_time()
                found = METHODS[method](codes, index, chosen)
                took = time.process_time() - began + shared
                start, _, ref = np.array(found, np.int64).reshape(-1, 3).T
                copies = int((ref >= 0).sum())
                peak = _peak_bytes(codes, method, chosen) if memory else None
                yield key, method, direction, len(codes), len(found), len(found) - copies, copies, int(((ref >= 0) & (ref < start)).sum()), int((ref > start).sum()), took, peak

    return map_strings(S, schema, rows)


def two_way_count(S: DataFrame, **options) -> DataFrame:
    return counts(S, ("two_way",), ("forward",), **options).select("string_id", "phrases")


def two_way_trace(S: DataFrame, **options) -> DataFrame:
    """TRACE: work done for each phrase."""
    chosen = Options(**options)

    def rows(key: str, text: str):
        done = TwoWay(codes_of(text), chosen).run(traced=True)
        for k, ((start, size, _), t) in enumerate(zip(done.phrases, done.traces)):
            yield key, k + 1, start + 1, size, t.candidates, t.groups, t.tests, t.finds, t.unions, t.stop_lce

    return map_strings(S, schemas.TRACE, rows)


def two_way_work(S: DataFrame) -> DataFrame:
    """What :func:`measures.trace_summary` says of each string under the default rules, without a row a phrase.

    Strings of up to ``jvm.LEAN_CHARS`` characters are parsed in little memory in Spark's own process, longer ones traced.
    """
    fits = F.length("text") <= jvm.LEAN_CHARS
    found = F.explode(jvm.work(S.sparkSession, "text", F.lit("forward"), F.lit("two_way:forward"))).alias("w")
    done = S.where(fits).select("string_id", found).where("w.n > 0").select(
        "string_id", "w.n", "w.phrases", "w.candidates", "w.most_candidates", "w.finds", "w.unions", "w.work_bound", (F.col("w.candidates") / F.col("w.n")).alias("candidates_per_char")
    )
    longest = getattr(S, "_longest", None)
    if longest is not None and longest <= jvm.LEAN_CHARS:
        return done
    from phrasework.operators.measures import trace_summary

    return done.unionByName(trace_summary(two_way_trace(S.where(~fits))))


def extension_profile(S: DataFrame, prefix: list[tuple[int, int | None]] | DataFrame) -> DataFrame:
    """(string_id, j, length): longest valid copy of every j behind a prefix of (length, reference or None).

    PHRASES give each string a prefix of its own; behind one that covers its string there is nothing.
    """

    def profile(key: str, text: str, pieces: list[tuple[int, int | None]]):
        state = TwoWay(codes_of(text), replace(Options(), floor=False))
        for size, ref in pieces:
            state.commit(0 if ref is None else size, -1 if ref is None else ref - 1)
        return [(key, j + 1, got) for j, got in enumerate(state.profile())] if state.at < state.n else []

    def rows(key: str, both: str):
        given, text = both.split("\n", 1)
        pieces = [tuple(map(int, p.split(":"))) for p in given.split(",") if p]
        return profile(key, text, [(size, ref or None) for size, ref in pieces])

    schema = "string_id string, j bigint, length bigint"
    if not isinstance(prefix, DataFrame):
        return map_strings(S, schema, lambda key, text: profile(key, text, prefix))
    pieces = F.array_sort(F.collect_list(F.struct("start", F.concat_ws(":", "length", F.coalesce("ref", F.lit(0))).alias("piece"))))
    own = prefix.groupBy("string_id").agg(F.array_join(pieces["piece"], ",").alias("given"))
    return map_strings(S.where("text is not null").join(own, "string_id", "left").select("string_id", F.concat_ws("\n", F.coalesce("given", F.lit("")), "text").alias("text")), schema, rows)


def best_direction(counted: DataFrame) -> DataFrame:
    """The smaller count of each string and method, with its direction; forward on a tie."""
    w = Window.partitionBy("string_id", "method").orderBy("phrases", "direction")
    return counted.withColumn("place", F.row_number().over(w)).where("place = 1").drop("place")
