"""Queries for the worked examples, suffix tables, parses, checks and workloads."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from phrasework import schemas
from phrasework.operators import jvm
from phrasework.operators import measures as M
from phrasework.operators import parse as P
from phrasework.operators import phrases as R
from phrasework.operators import strings as T
from phrasework.operators import suffix_tables as X
from phrasework.operators.jumps import path_members
from phrasework.operators.sharded import two_way_parse_sharded
from phrasework.plans import oracles as O
from phrasework.plans import workloads as W
from phrasework.plans.registry import query
from phrasework.plans.route import KERNEL_CHARS, counts_any_size
from phrasework.shared import materialize
from phrasework.sources import generators


def _one(spark: SparkSession, text: str, key: str = "x") -> DataFrame:
    return spark.range(1).select(F.lit(key).alias("string_id"), F.lit(text).alias("text"))


def _given(spark: SparkSession, text: str, prefix: list[tuple[int, int | None]]) -> DataFrame:
    """PHRASES of hand-made (length, reference or None) pieces of a text."""
    rows, at = [], 1
    for k, (size, ref) in enumerate(prefix):
        side = "literal" if ref is None else "left" if ref < at else "right"
        rows.append(("x", k + 1, at, size, ref, text[at - 1] if ref is None else None, side))
        at += size
    return spark.createDataFrame(rows, schemas.PHRASES)


def _by_text(S: DataFrame, make: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Rows that ``make`` gives of each distinct text, for every string that has it.

    For results that depend on a string's text alone. They are brought back by one join, whose small side
    is what few distinct texts give.
    """
    texts, keys = P.distinct_texts(S)
    return keys.join(make(texts).withColumnRenamed("string_id", "key"), "key").drop("key")


# Worked examples


#: Each different order history of a customer once, under its own text as key.
_HISTORIES = f"SELECT DISTINCT text AS string_id, text FROM ({O.CUSTOMER_STATUS}) WHERE text <> ''"
#: Phrases of the two-way parse that start in the first half of a history, and every position's source behind them.
_HALF = f"SELECT p.* FROM ({O.two_way(_HISTORIES)}) p WHERE 2 * start <= length(string_id)"
_SOURCES = f"""WITH RECURSIVE refs AS (SELECT string_id, CAST(start + k AS BIGINT) AS pos, CAST(ref + k AS BIGINT) AS target FROM ({_HALF}), unnest(range(length)) t(k) WHERE ref > 0),
c(string_id, pos, goal) AS (
  SELECT string_id, CAST(p AS BIGINT), CAST(p AS BIGINT) FROM ({_HISTORIES}), unnest(range(1, length(text) + 1)) t(p)
  UNION ALL
  SELECT c.string_id, c.pos, r.target FROM c JOIN refs r ON r.string_id = c.string_id AND r.pos = c.goal
),
found AS (SELECT string_id, pos, goal AS source FROM c ANTI JOIN refs r ON r.string_id = c.string_id AND r.pos = c.goal)"""


def _of_histories(sql: str) -> str:
    """A query over the different histories, for every customer who has one of them."""
    return f"SELECT h.string_id, q.* EXCLUDE (string_id) FROM ({O.CUSTOMER_STATUS}) h JOIN ({sql}) q ON q.string_id = h.text"


def _half(S: DataFrame) -> DataFrame:
    """PHRASES of the two-way parse that start in the first half of their string."""
    return materialize(P.two_way_parse(S).join(S, "string_id").where("2 * start <= length(text)").drop("text"), "half")


@query(
    _of_histories(f"WITH {O.suffixes(_HISTORIES)} SELECT a.string_id, CAST(a.rank AS INT) AS k, CAST(a.pos AS INT) AS sa, CAST(b.rank AS INT) AS isa, CAST(a.lcp AS INT) AS lcp, CAST(f.prev_len AS INT) AS lpf "
    "FROM suf a JOIN suf b ON b.string_id = a.string_id AND b.pos = a.rank JOIN fac f ON f.string_id = a.string_id AND f.pos = a.rank")
)
def ex_arrays(spark, folder):
    """Suffix array, its inverse, LCP and earlier factors, side by side, of every customer's order history."""

    def make(S: DataFrame) -> DataFrame:
        suf = X.suffix_table(S)
        isa, lpf = X.rank_of(suf), X.previous_factor(S)
        rows = suf.join(isa.select("string_id", F.col("pos").alias("rank"), F.col("rank").alias("isa")), ["string_id", "rank"]).join(lpf.select("string_id", F.col("pos").alias("rank"), "prev_len"), ["string_id", "rank"])
        return rows.select("string_id", *(F.col(a).cast("int").alias(b) for a, b in (("rank", "k"), ("pos", "sa"), ("isa", "isa"), ("lcp", "lcp"), ("prev_len", "lpf"))))

    return _by_text(W.status_by_customer(spark, folder), make)


def _common(x: str, y: str) -> str:
    return f"list_max(list_transform(range(0, least(length({x}), length({y})) + 1), lambda l: CASE WHEN substr({x}, 1, l) = substr({y}, 1, l) THEN l ELSE 0 END))"


@query(
    f"SELECT CAST(a.c_custkey AS VARCHAR) AS string_id, {_common('a.c_name', 'b.c_name')} > {_common('c.c_name', 'b.c_name')} AS closer "
    "FROM customer a JOIN customer b ON b.c_custkey = a.c_custkey + 1 JOIN customer c ON c.c_custkey = a.c_custkey + 2"
)
def ex_similarity(spark, folder):
    """Whether a customer's name shares a longer prefix with the next customer's than the one after that does."""
    own = W.table(spark, folder, "customer").select("c_custkey", "c_name")
    ahead = {k: own.select((F.col("c_custkey") - k).alias("c_custkey"), F.col("c_name").alias(f"name{k}")) for k in (1, 2)}
    rows = own.join(ahead[1], "c_custkey").join(ahead[2], "c_custkey")
    return rows.select(F.col("c_custkey").cast("string").alias("string_id"), T.closer_to(F.col("c_name"), F.col("name2"), F.col("name1")).alias("closer"))


@query(_of_histories(f"WITH {O.factors(_HISTORIES)} SELECT string_id, row_number() OVER (PARTITION BY string_id ORDER BY lce DESC, j DESC) AS ord, j, lce FROM ext WHERE i = 1 AND lce > 0"))
def ex_order_at_first(spark, folder):
    """Places by LCE with the first position of every customer's order history."""
    return _by_text(W.status_by_customer(spark, folder), lambda S: X.candidates(S, 1).select("string_id", "ord", "j", "lce"))


@query("SELECT true AS valid, 'ababbab' AS text, 'abab4ab' AS after_two, 'ababbab' AS after_three")
def ex_valid_parse(spark, folder):
    """All positions after two references, position numbers where no literal is reached yet, and after three."""
    p = _given(spark, "ababbab", [(2, 3), (1, None), (1, None), (3, 2)])

    def after(hops: int, name: str) -> DataFrame:
        shown = F.struct("pos", F.coalesce("literal", F.col("target").cast("string")).alias("c"))
        return R.follow(R.reference_graph(p), hops).agg(F.array_join(F.transform(F.array_sort(F.collect_list(shown)), lambda x: x["c"]), "").alias(name))

    return R.is_valid(p).join(R.decode(p), "string_id").join(after(2, "after_two")).join(after(3, "after_three")).select("valid", "text", "after_two", "after_three")


@query("SELECT * FROM (VALUES (1::BIGINT),(2),(3),(4)) t(pos)")
def ex_invalid_parse(spark, folder):
    return R.cyclic_positions(R.reference_graph(_given(spark, "ababbab", [(2, 3), (2, 1), (1, None), (1, None), (1, None)]))).select("pos")


@query(_of_histories(f"{_SOURCES} SELECT * FROM found"))
def ex_partial_source(spark, folder):
    """The source of every position behind the first half's phrases of every customer's order history."""
    return _by_text(W.status_by_customer(spark, folder), lambda S: R.source_of(_half(S), S).select("string_id", "pos", "source"))


@query(_of_histories(f"SELECT string_id, true AS valid FROM ({_HISTORIES})"))
def ex_partial_valid(spark, folder):
    return _by_text(W.status_by_customer(spark, folder), lambda S: R.is_valid_partial(_half(S), S))


@query(_of_histories(f"{_SOURCES} SELECT string_id, source, string_agg(CAST(pos AS VARCHAR), ',' ORDER BY pos) AS members FROM found GROUP BY ALL"))
def ex_source_classes(spark, folder):
    """Positions of every customer's order history by the source that the first half's phrases give them."""
    members = F.array_join(F.transform("members", lambda x: x.cast("string")), ",").alias("members")
    return _by_text(W.status_by_customer(spark, folder), lambda S: R.source_classes(R.source_of(_half(S), S)).select("string_id", "source", members))


@query("SELECT * FROM (VALUES (3, 1, false), (9, 1, true), (9, 2, true), (9, 3, false), (11, 2, true)) t(ref, size, valid)")
def ex_can_extend(spark, folder):
    prefix, S = _given(spark, "abababaababa", [(5, 3)]), _one(spark, "abababaababa")
    parts = [R.can_extend(prefix, S, ref, size).select(F.lit(ref).alias("ref"), F.lit(size).alias("size"), "valid") for ref, size in ((3, 1), (9, 1), (9, 2), (9, 3), (11, 2))]
    return reduce(DataFrame.unionByName, parts)


@query("SELECT CAST(p AS BIGINT) AS pos, CAST(CASE WHEN p IN (1, 3, 5) THEN 7 WHEN p IN (2, 4) THEN 6 ELSE p END AS BIGINT) AS before, CAST(CASE WHEN p IN (1, 3, 5, 7) THEN 10 WHEN p IN (2, 4, 6) THEN 9 ELSE p END AS BIGINT) AS after FROM range(1, 13) t(p)")
def ex_class_update(spark, folder):
    """Sources before and after one more phrase: the classes of its positions join those they refer to."""
    S = _one(spark, "abababaababa")
    before, after = (R.source_of(_given(spark, "abababaababa", pieces), S).select("pos", F.col("source").alias(name)) for name, pieces in (("before", [(5, 3)]), ("after", [(5, 3), (2, 9)])))
    return before.join(after, "pos")


@query(
    _of_histories(f"SELECT string_id, a.phrases AS lz77, b.phrases AS lz77_reverse, c.phrases AS lex, d.phrases AS two_way FROM ({O.phrase_counts(_HISTORIES, 'prev_len')}) a "
    f"JOIN ({O.phrase_counts(O.reversed_text(_HISTORIES), 'prev_len')}) b USING (string_id) JOIN ({O.phrase_counts(_HISTORIES, 'lcp')}) c USING (string_id) JOIN (SELECT string_id, count(*) AS phrases FROM ({O.two_way(_HISTORIES)}) GROUP BY 1) d USING (string_id)")
)
def ex_third_counts(spark, folder):
    """Counts of the left parse in both directions, the lex parse and the two-way parse of every customer's order history."""
    pick = {"lz77": ("lz77", "forward"), "lz77_reverse": ("lz77", "reverse"), "lex": ("lex", "forward"), "two_way": ("two_way", "forward")}
    wide = [F.max(F.when((F.col("method") == m) & (F.col("direction") == d), F.col("phrases"))).alias(c) for c, (m, d) in pick.items()]
    return _by_text(W.status_by_customer(spark, folder), lambda S: P.counts(S).groupBy("string_id").agg(*wide))


@query(f"SELECT string_id, CAST(length(text) * 41 + ceil(length(text) * 3 / 8) AS BIGINT) AS bytes FROM ({O.PART_NAMES})")
def space_part_names(spark, folder):
    """The paper's layout in bytes: text, five words and three bits a position."""
    return W.part_names(spark, folder).select("string_id", (F.length("text") + T.space_model(F.length("text"), 5, 3)).cast("bigint").alias("bytes"))


@query(_of_histories(O.profile(_HISTORIES, _HALF)))
def ex_extension_profile(spark, folder):
    """Longest valid copy of every place, behind the first half's phrases of every customer's order history."""
    return _by_text(W.status_by_customer(spark, folder), lambda S: P.extension_profile(S, _half(S)))


@query(_of_histories(" UNION ALL ".join(f"SELECT string_id, '{tie}' AS tie, count(*) AS phrases FROM ({O.two_way(_HISTORIES, tie)}) GROUP BY 1" for tie in ("leftmost", "rightmost"))))
def ex_tie_rules(spark, folder):
    """Counts of every customer's order history under two tie rules."""

    def make(S: DataFrame) -> DataFrame:
        return reduce(DataFrame.unionByName, (P.two_way_count(S, tie=t).select("string_id", F.lit(t).alias("tie"), "phrases") for t in ("leftmost", "rightmost")))

    return _by_text(W.status_by_customer(spark, folder), make)


@query(_of_histories(f"SELECT string_id, a.phrases AS lz77, b.phrases AS two_way FROM ({O.phrase_counts(_HISTORIES, 'prev_len')}) a JOIN (SELECT string_id, count(*) AS phrases FROM ({O.two_way(_HISTORIES)}) GROUP BY 1) b USING (string_id)"))
def ex_one_direction_excess(spark, folder):
    """Counts of the left and the two-way parse of every customer's order history, in one direction."""
    wide = [F.max(F.when(F.col("method") == m, F.col("phrases"))).alias(m) for m in ("lz77", "two_way")]
    return _by_text(W.status_by_customer(spark, folder), lambda S: P.counts(S, ("lz77", "two_way"), ("forward",)).groupBy("string_id").agg(*wide))


# Suffix structures


@query(f"WITH {O.suffixes(O.BENCHMARK)} SELECT string_id, rank, pos FROM suf")
def suffix_benchmark(spark, folder):
    return X.suffix_table(W.benchmark(spark, folder)).select("string_id", "rank", "pos")


@query(f"WITH {O.suffixes(O.BENCHMARK)} SELECT string_id, rank, lcp FROM suf")
def lcp_benchmark(spark, folder):
    return X.suffix_table(W.benchmark(spark, folder)).select("string_id", "rank", "lcp")


@query(f"WITH {O.suffixes(O.PART_NAMES)} SELECT string_id, rank, pos, lcp FROM suf")
def suffix_distributed(spark, folder):
    return X.suffix_table(W.part_names(spark, folder), tier="distributed")


@query(f"WITH {O.factors(O.BENCHMARK)} SELECT string_id, pos, prev_len FROM fac")
def lpf_benchmark(spark, folder):
    return X.previous_factor(W.benchmark(spark, folder)).select("string_id", "pos", "prev_len")


@query(f"WITH {O.factors(O.BENCHMARK)} SELECT string_id, pos, next_len FROM fac")
def next_factor_benchmark(spark, folder):
    return X.next_factor(W.benchmark(spark, folder)).select("string_id", "pos", "next_len")


@query(f"WITH {O.factors(O.BENCHMARK)} SELECT string_id, pos, prev_len, next_len FROM fac")
def factors_distributed(spark, folder):
    return X.distributed_factor_table(W.benchmark(spark, folder), block=64).select("string_id", "pos", "prev_len", "next_len")


@query(f"WITH {O.factors(O.BENCHMARK)} SELECT string_id, i, j, lce FROM ext")
def lce_diagonals(spark, folder):
    return T.lce_matrix(W.benchmark(spark, folder))


@query(
    f"WITH {O.factors(O.BENCHMARK)} SELECT string_id, row_number() OVER (PARTITION BY string_id ORDER BY lce DESC, j DESC) AS ord, j, lce "
    "FROM (SELECT string_id, j, lce FROM ext WHERE i = 5 UNION ALL SELECT string_id, i, lce FROM ext WHERE j = 5) WHERE lce > 0"
)
def candidate_order(spark, folder):
    return X.candidates(W.benchmark(spark, folder), 5).select("string_id", "ord", "j", "lce")


# One-sided and suffix-order parses


def _starts(phrases: DataFrame) -> DataFrame:
    return phrases.select("string_id", "start", "length", F.col("ref").isNull().alias("is_literal"))


@query(O.starts(O.BENCHMARK, "prev_len"))
def lz77_benchmark(spark, folder):
    return _starts(P.lz77_parse(W.benchmark(spark, folder)))


@query(O.starts(O.BENCHMARK, "next_len"))
def lz_next_benchmark(spark, folder):
    return _starts(P.lz_next_parse(W.benchmark(spark, folder)))


@query(O.starts(O.BENCHMARK, "lcp"))
def lex_benchmark(spark, folder):
    return _starts(P.lex_parse(W.benchmark(spark, folder)))


@query(O.phrase_counts(O.BENCHMARK, "prev_len"))
def lz_backward_benchmark(spark, folder):
    return M.phrase_counts(P.lz_backward_parse(W.benchmark(spark, folder))).select("string_id", "phrases")


@query(O.starts(O.BENCHMARK, "prev_len").replace(", CAST(greatest(size, 1) AS BIGINT) AS length, size = 0 AS is_literal", "").replace("pos AS start", "pos"))
def lz77_path_distributed(spark, folder):
    jumps = X.previous_factor(W.benchmark(spark, folder)).select("string_id", "pos", F.col("prev_len").alias("jump"))
    return path_members(jumps, block=16)


@query("SELECT CAST(item_id AS VARCHAR) AS string_id, CAST(length(text) AS BIGINT) AS phrases FROM benchmark")
def literal_benchmark(spark, folder):
    return M.phrase_counts(P.literal_parse(W.benchmark(spark, folder))).select("string_id", "phrases")


def _decodes(S: DataFrame, phrases: DataFrame) -> DataFrame:
    return S.join(R.decode(phrases).withColumnRenamed("text", "again"), "string_id", "left").select("string_id", F.length("text").cast("bigint").alias("n"), F.coalesce(F.col("again") == F.col("text"), F.lit(False)).alias("decoded"))


def _two_way_decodes(S: DataFrame) -> DataFrame:
    """``_decodes`` of the two-way parse of texts that are not empty: string by string where all phrases of one may be a row, else over the phrase table."""
    S = S.where(F.length("text") > 0)
    fits = F.length("text") <= jvm.ROW_CHARS
    again = jvm.decode(S.sparkSession, F.col("pieces"))
    rows = P.packed_parse(S.where(fits)).select("string_id", F.length("text").cast("bigint").alias("n"), F.coalesce(again == F.col("text"), F.lit(False)).alias("decoded"))
    long = S.where(~fits)
    return rows if long.isEmpty() else rows.unionByName(_decodes(long, materialize(P.two_way_parse(long), "phrases")))


BENCHMARK_TRUTHS = "SELECT CAST(item_id AS VARCHAR) AS string_id, CAST(length(text) AS BIGINT) AS n, true AS decoded FROM benchmark"


@query(BENCHMARK_TRUTHS)
def lcp_first_benchmark(spark, folder):
    S = W.benchmark(spark, folder)
    return _decodes(S, P.lcp_first_parse(S))


@query(BENCHMARK_TRUTHS)
def bwt_run_benchmark(spark, folder):
    S = W.benchmark(spark, folder)
    return _decodes(S, P.bwt_run_parse(S))


@query("SELECT string_id, true AS smallest_within_all, true AS lex_within_largest_first, true AS lex_within_runs FROM (" + O.PART_NAMES + ") WHERE length(text) <= 10")
def smallest_part_names(spark, folder):
    S = W.part_names(spark, folder).where("length(text) <= 10")
    return _by_text(S, lambda texts: M.relation_report(P.counts(texts, ("smallest", "two_way", "lz77", "lex", "lcp_first"), ("forward",)), P.bwt_runs(texts)))


_SHORT_NAMES = f"SELECT * FROM ({O.PART_NAMES}) WHERE length(text) <= 10"
#: Sizes of smallest attractors by trying all sets of positions as bit masks.
_ATTRACTORS = f"""WITH t AS (SELECT DISTINCT text FROM ({_SHORT_NAMES})),
occ AS (SELECT text, substr(text, CAST(i AS BIGINT), CAST(l AS BIGINT)) AS part, ((1 << CAST(l AS INT)) - 1) << CAST(i - 1 AS INT) AS bits
        FROM t, unnest(range(1, length(text) + 1)) a(i), unnest(range(1, length(text) + 1)) b(l) WHERE i + l <= length(text) + 1),
tried AS (SELECT text, m, part, bool_or(bits & CAST(m AS INT) <> 0) AS covered FROM occ, unnest(range(1, 1 << CAST(length(text) AS INT))) c(m) GROUP BY ALL),
good AS (SELECT text, m FROM tried GROUP BY ALL HAVING bool_and(covered)),
best AS (SELECT text, min(bit_count(CAST(m AS INT))) AS size FROM good GROUP BY 1)"""


@query(f"{_ATTRACTORS} SELECT string_id, CAST(size AS BIGINT) AS size FROM ({_SHORT_NAMES}) JOIN best USING (text)")
def attractor_sizes_part_names(spark, folder):
    texts, keys = P.distinct_texts(W.part_names(spark, folder).where("length(text) <= 10"))
    return keys.join(P.smallest_attractor(texts).withColumnRenamed("string_id", "key"), "key").groupBy("string_id").agg(F.count(F.lit(1)).alias("size"))


@query(f"SELECT string_id, true AS is_attractor, false AS without_last, true AS decoded, true AS copies FROM ({_SHORT_NAMES})")
def attractor_part_names(spark, folder):
    """Parses grown around a smallest attractor: it is one, no smaller part of it is, the parse decodes and copies where a letter repeats."""
    S = W.part_names(spark, folder).where("length(text) <= 10")
    texts, keys = P.distinct_texts(S)
    marks = materialize(P.smallest_attractor(texts), "attractors")
    fewer = marks.withColumn("last", F.max("pos").over(Window.partitionBy("string_id"))).where("pos <> last").drop("last")
    found = materialize(P.attractor_parse(texts, marks), "phrases")
    again = R.decode(found).withColumnRenamed("text", "again")
    checks = P.is_attractor(texts, marks).join(P.is_attractor(texts, fewer).withColumnRenamed("is_attractor", "without_last"), "string_id")
    literals = M.phrase_counts(found).select("string_id", "literals")
    rows = texts.join(again, "string_id").join(checks, "string_id").join(literals, "string_id")
    letters = F.size(F.array_distinct(F.filter(F.split("text", ""), lambda c: c != "")))
    rows = rows.select(F.col("string_id").alias("key"), "is_attractor", "without_last", (F.col("again") == F.col("text")).alias("decoded"), ((F.col("literals") < F.length("text")) | (letters == F.length("text"))).alias("copies"))
    return keys.join(rows, "key").drop("key")


# Two-way parse and its guarantees


@query(f"SELECT string_id, CAST(length(text) AS BIGINT) AS n, true AS decoded FROM ({O.PART_NAMES})")
def two_way_part_names(spark, folder):
    return _by_text(W.part_names(spark, folder), lambda texts: _decodes(texts, P.two_way_parse(texts)))




def _ref() -> Column:
    return F.coalesce("ref", F.lit(0)).cast("bigint").alias("ref")


@query(O.two_way(O.PART_NAMES))
def two_way_phrases_part_names(spark, folder):
    """Every phrase, against trying all references and lengths; reference 0 is a literal."""
    return P.two_way_parse(W.part_names(spark, folder), collapse=True).select("string_id", "start", "length", _ref())


@query(O.two_way(O.CUSTOMER_STATUS))
def two_way_phrases_orders(spark, folder):
    """The same on the repetitive order histories of customers."""
    return P.two_way_parse(W.status_by_customer(spark, folder)).select("string_id", "start", "length", _ref())


@query(" UNION ALL ".join(f"SELECT '{tie}' AS tie, * FROM ({O.two_way(O.PART_NAMES, tie)})" for tie in O.TIE_SCORES))
def two_way_ties_part_names(spark, folder):
    S = W.part_names(spark, folder)
    return reduce(DataFrame.unionByName, (P.two_way_parse(S, tie=tie).select(F.lit(tie).alias("tie"), "string_id", "start", "length", _ref()) for tie in O.TIE_SCORES))


@query(
    f"SELECT string_id, CAST(length(text) AS BIGINT) - start - length + 2 AS start, length, CASE WHEN ref > 0 THEN CAST(length(text) AS BIGINT) - ref - length + 2 ELSE 0 END AS ref "
    f"FROM ({O.two_way(O.reversed_text(O.PART_NAMES))}) JOIN ({O.PART_NAMES}) USING (string_id)"
)
def two_way_reverse_part_names(spark, folder):
    """Parses of the reversed strings, mapped back to the strings' own positions."""
    return P.two_way_parse(W.part_names(spark, folder), direction="reverse").select("string_id", "start", "length", _ref())


@query(O.table(O.PART_NAMES))
def table_part_names(spark, folder):
    """Best counts of both directions and ratios, against brute force."""
    return _by_text(W.part_names(spark, folder), lambda texts: M.table(P.counts(texts)))


@query(
    f"SELECT string_id, method, phrases FROM (SELECT *, rank() OVER (PARTITION BY string_id ORDER BY phrases) AS place FROM (UNPIVOT (SELECT string_id, lz77, lex, two_way FROM ({O.table(O.PART_NAMES)})) ON lz77, lex, two_way INTO NAME method VALUE phrases)) WHERE place = 1"
)
def winners_part_names(spark, folder):
    return _by_text(W.part_names(spark, folder), lambda texts: M.winners(P.counts(texts)))


@query(
    f"WITH p AS ({O.two_way(O.PART_NAMES)}) SELECT string_id, min(length) AS least, quantile_cont(length, 0.5) AS median, quantile_cont(length, 0.9) AS p90, max(length) AS most, round(avg(length), 6) AS mean, "
    "count(*) FILTER (ref > 0 AND ref < start) AS left_refs, count(*) FILTER (ref > start) AS right_refs, count(*) FILTER (ref = 0) AS literals, count(*) FILTER (ref > 0 AND abs(ref - start) < length) AS overlapping FROM p GROUP BY 1"
)
def profile_part_names(spark, folder):
    phrases = materialize(P.two_way_parse(W.part_names(spark, folder), collapse=True), "phrases")
    return M.length_profile(phrases).join(M.side_mix(phrases), "string_id")


@query(f"SELECT string_id, CAST(1 << CAST(floor(log2(length)) AS INT) AS BIGINT) AS at_least, count(*) AS phrases FROM ({O.starts(O.BENCHMARK, 'prev_len')}) GROUP BY ALL")
def length_histogram_benchmark(spark, folder):
    return M.length_histogram(P.lz77_parse(W.benchmark(spark, folder)))


@query("SELECT CAST(item_id AS VARCHAR) AS string_id, CAST(k AS INT) AS most, true AS decoded, true AS within_right FROM benchmark, unnest([1, 2, 8]) t(k)")
def truncated_benchmark(spark, folder):
    """Streams cut short after a few candidates still give parses that decode and keep the right parse's bound."""
    S = W.benchmark(spark, folder)
    right = P.counts(S, ("lz_next",), ("forward",)).select("string_id", F.col("phrases").alias("bound"))

    def cut(most: int) -> DataFrame:
        phrases = materialize(P.two_way_parse(S, max_candidates=most), "phrases")
        rows = _decodes(S, phrases).join(M.phrase_counts(phrases).select("string_id", "phrases"), "string_id").join(right, "string_id")
        return rows.select("string_id", F.lit(most).alias("most"), "decoded", (F.col("phrases") <= F.col("bound")).alias("within_right"))

    return reduce(DataFrame.unionByName, map(cut, (1, 2, 8)))


@query("SELECT CAST(doc_id AS VARCHAR) AS string_id, CAST(length(text) AS BIGINT) AS n, true AS decoded FROM documents WHERE text <> ''")
def two_way_roundtrip_documents(spark, folder):
    return _two_way_decodes(W.documents(spark, folder))


@query("SELECT CAST(page_id AS VARCHAR) AS string_id, CAST(length(html) AS BIGINT) AS n, true AS decoded FROM pages WHERE html <> ''")
def two_way_roundtrip_pages(spark, folder):
    return _two_way_decodes(T.strings(W.table(spark, folder, "pages"), "page_id", "html"))


ALL_METHODS = ("two_way", "lz77", "lz_next", "lz_backward", "lex")


@query("SELECT CAST(doc_id AS VARCHAR) AS string_id, CAST(length(text) AS BIGINT) AS n, true AS bound_holds, true AS best_holds FROM documents WHERE text IS NOT NULL")
def two_way_bound_documents(spark, folder):
    return M.bound_report(P.counts(P.balanced(W.documents(spark, folder)), ("lz77", "two_way")))


@query("SELECT CAST(doc_id AS VARCHAR) AS string_id, CAST(length(text) AS BIGINT) AS n, true AS backward_is_left, true AS right_is_backward_of_reverse, true AS two_way_within_right FROM documents WHERE text IS NOT NULL")
def identity_documents(spark, folder):
    return M.identity_report(P.counts(P.balanced(W.documents(spark, folder)), ALL_METHODS))


@query("SELECT CAST(item_id AS VARCHAR) AS string_id, true AS valid, CAST(0 AS BIGINT) AS problems FROM benchmark")
def validity_benchmark(spark, folder):
    S = W.benchmark(spark, folder)
    phrases = materialize(P.two_way_parse(S), "phrases")
    bad = R.check_partition(phrases, S).groupBy("string_id").agg(F.count(F.lit(1)).alias("bad"))
    return R.is_valid(phrases).join(bad, "string_id", "left").select("string_id", "valid", F.coalesce("bad", F.lit(0)).cast("bigint").alias("problems"))


@query("SELECT source AS string_id, true AS decoded, true AS within_bound FROM documents WHERE text IS NOT NULL GROUP BY 1")
def sharded_bound(spark, folder):
    """Every source's whole text in shards of 16 Ki characters: decodes, at most a phrase a boundary above the right parse."""
    size = 1 << 14
    S = materialize(P.balanced(W.by_source(spark, folder)), "strings")
    phrases = materialize(two_way_parse_sharded(S, size), "phrases")
    right = P.counts(S, ("lz77",), ("reverse",)).select("string_id", F.col("phrases").alias("bound"), F.ceil(F.col("n") / size).alias("shards"))
    sizes = M.phrase_counts(phrases).join(right, "string_id").select("string_id", (F.col("phrases") <= F.col("bound") + F.col("shards") - 1).alias("within_bound"))
    return _decodes(S, phrases).join(sizes, "string_id").select("string_id", "decoded", "within_bound")


@query(
    f"WITH a AS ({O.phrase_counts(O.BENCHMARK, 'prev_len')}), b AS ({O.phrase_counts(O.BENCHMARK, 'next_len')}) "
    "SELECT string_id, least(a.phrases, b.phrases) AS phrases FROM a JOIN b USING (string_id)"
)
def best_direction_benchmark(spark, folder):
    return P.best_direction(P.counts(W.benchmark(spark, folder), ("lz77",))).select("string_id", "phrases")


@query("SELECT rule, true AS decoded, count(*) AS strings FROM benchmark, unnest(['leftmost', 'nearest_left', 'nearest_right', 'rightmost', 'walk_lower', 'walk_upper']) t(rule) GROUP BY 1")
def tie_rules_benchmark(spark, folder):
    S = W.benchmark(spark, folder)
    parts = [_decodes(S, P.two_way_parse(S, tie=t)).agg(F.min("decoded").alias("decoded"), F.count(F.lit(1)).alias("strings")).select(F.lit(t).alias("rule"), "decoded", "strings") for t in ("leftmost", "nearest_left", "nearest_right", "rightmost", "walk_lower", "walk_upper")]
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    return out


@query("SELECT CAST(item_id AS VARCHAR) AS string_id, true AS same_as_exhaustive, true AS same_without_floor, true AS same_with_undo, true AS same_by_size, true AS same_by_graph, true AS left_is_lz77, true AS right_is_lz_next FROM benchmark")
def ablations_benchmark(spark, folder):
    S = W.benchmark(spark, folder)

    def count(name: str, **options) -> DataFrame:
        return P.two_way_count(S, **options).select("string_id", F.col("phrases").alias(name))

    base = count("base")
    for name, options in (("exhaustive", {"search": "exhaustive"}), ("plain", {"floor": False}), ("undo", {"overlay": False}), ("size", {"link": "by_size"}), ("graph", {"validity": "graph"}), ("left", {"sides": "left", "floor": False}), ("right", {"sides": "right"})):
        base = base.join(count(name, **options), "string_id")
    for method in ("lz77", "lz_next"):
        base = base.join(P.counts(S, (method,), ("forward",)).select("string_id", F.col("phrases").alias(method)), "string_id")
    same = {"same_as_exhaustive": "exhaustive", "same_without_floor": "plain", "same_with_undo": "undo", "same_by_size": "size", "same_by_graph": "graph"}
    return base.select("string_id", *((F.col("base") == F.col(c)).alias(n) for n, c in same.items()), (F.col("left") == F.col("lz77")).alias("left_is_lz77"), (F.col("right") == F.col("lz_next")).alias("right_is_lz_next"))


# Workloads


@query("SELECT CAST(k AS INT) AS k, CAST(k AS BIGINT) AS lz77_forward, CAST(k // 2 + 2 AS BIGINT) AS lz77_reverse, CAST(CASE WHEN k % 2 = 1 THEN 4 ELSE k // 2 + 2 END AS BIGINT) AS lex_forward, CAST(5 AS BIGINT) AS two_way_forward FROM range(6, 21) t(k)")
def w_fib_counts(spark, folder):
    S = generators.fibonacci(spark, 6, 20)
    return _family(S, [("lz77", "forward"), ("lz77", "reverse"), ("lex", "forward"), ("two_way", "forward")])


@query("SELECT CAST(k AS INT) AS k, CAST(2 * (k - 1) AS BIGINT) AS lz77_forward, CAST(3 * k // 2 AS BIGINT) AS lex_forward, CAST(k + 2 AS BIGINT) AS two_way_forward FROM range(5, 13) t(k)")
def w_tm_counts(spark, folder):
    return _family(generators.thue_morse(spark, 5, 12), [("lz77", "forward"), ("lex", "forward"), ("two_way", "forward")])


def _family(S: DataFrame, pairs: list[tuple[str, str]]) -> DataFrame:
    counted = P.counts(S.select("string_id", "text"), tuple({m for m, _ in pairs}), tuple({d for _, d in pairs}))
    wide = counted.groupBy("string_id").agg(*(F.max(F.when((F.col("method") == m) & (F.col("direction") == d), F.col("phrases"))).alias(f"{m}_{d}") for m, d in pairs))
    return wide.join(S.select("string_id", "k"), "string_id").drop("string_id")


_RUN_RICH = """WITH RECURSIVE p(k, a, b, c, d, e) AS (SELECT 5, 'b', 'a', 'ac', 'ba', 'cb' UNION ALL SELECT k + 1, b, c, d, e, c || d FROM p WHERE k < 14)
SELECT 'rr' || k AS string_id, replace(replace(replace(replace(replace(replace(e, 'a', 'x'), 'b', 'y'), 'c', 'z'), 'x', '101001011001010010110100'), 'y', '1010010110100'), 'z', '10100101') AS text FROM p WHERE k >= 6"""


@query(
    f"SELECT string_id, CAST(length(text) AS BIGINT) AS n, least(a.phrases, b.phrases) AS lz77, least(c.phrases, d.phrases) AS lex, true AS two_way_within_lz77 FROM ({_RUN_RICH}) "
    f"JOIN ({O.phrase_counts(_RUN_RICH, 'prev_len')}) a USING (string_id) JOIN ({O.phrase_counts(O.reversed_text(_RUN_RICH), 'prev_len')}) b USING (string_id) "
    f"JOIN ({O.phrase_counts(_RUN_RICH, 'lcp')}) c USING (string_id) JOIN ({O.phrase_counts(O.reversed_text(_RUN_RICH), 'lcp')}) d USING (string_id)"
)
def w_runrich_counts(spark, folder):
    wide = M.table(P.counts(generators.run_rich(spark, 6, 14).select("string_id", "text")))
    return wide.select("string_id", "n", "lz77", "lex", (F.col("two_way") <= F.col("lz77")).alias("two_way_within_lz77"))


#: The methods that the tables compare.
METHODS = ("lz77", "lex", "two_way")


@query()
def w_mutated_counts(spark, folder):
    """Counts of the three methods on mutated copies of five kinds of text, at every rate and of both kinds."""
    once, keys = W.mutated_once(spark, folder)
    return W.of_mutated(M.table(P.counts(once, METHODS), methods=METHODS), keys)


def _flags(S: DataFrame) -> DataFrame:
    return M.bound_report(counts_any_size(S, ("lz77", "two_way")))


@query("SELECT source AS string_id, CAST(length(string_agg(text, chr(10))) AS BIGINT) AS n, true AS bound_holds, true AS best_holds FROM documents WHERE text IS NOT NULL GROUP BY 1")
def w_source_counts(spark, folder):
    return _flags(W.by_source(spark, folder))


@query("SELECT lang AS string_id, CAST(length(string_agg(text, chr(10))) AS BIGINT) AS n, true AS bound_holds, true AS best_holds FROM documents WHERE text IS NOT NULL GROUP BY 1")
def w_lang_counts(spark, folder):
    return _flags(W.by_lang(spark, folder))


@query("SELECT CAST(conv_id AS VARCHAR) AS string_id, CAST(length(string_agg(text, chr(10))) AS BIGINT) AS n, true AS bound_holds, true AS best_holds FROM conversations WHERE text IS NOT NULL GROUP BY 1")
def w_conversation_counts(spark, folder):
    return _flags(W.conversations(spark, folder))


@query("SELECT regexp_extract(url, '://([^/?#]*)', 1) AS string_id, CAST(length(string_agg(html, chr(10))) AS BIGINT) AS n, true AS bound_holds, true AS best_holds FROM pages WHERE html IS NOT NULL GROUP BY 1")
def w_pages_counts(spark, folder):
    return _flags(W.pages_by_host(spark, folder))


def _exact(strings: str) -> str:
    """Exact counts of the three walks of short strings, and the two-way parse within its bound."""
    parts = [f"{name} AS ({O.phrase_counts(strings, jump)})" for name, jump in (("a", "prev_len"), ("b", "next_len"), ("c", "lcp"))]
    return f"WITH {', '.join(parts)} SELECT string_id, a.phrases AS lz77, b.phrases AS lz_next, c.phrases AS lex, true AS within_bound FROM a JOIN b USING (string_id) JOIN c USING (string_id)"


def _exact_counts(S: DataFrame) -> DataFrame:
    counted = P.counts(S, ("lz77", "lz_next", "lex", "two_way"), ("forward",))
    pick = {m: F.max(F.when(F.col("method") == m, F.col("phrases"))) for m in ("lz77", "lz_next", "lex", "two_way")}
    return counted.groupBy("string_id").agg(*(v.alias(k) for k, v in pick.items())).select("string_id", "lz77", "lz_next", "lex", (F.col("two_way") <= F.col("lz_next")).alias("within_bound"))


@query(_exact(O.USER_EVENTS))
def w_events_counts(spark, folder):
    return _exact_counts(W.events_by_user(spark, folder))


@query(_exact(O.CUSTOMER_STATUS))
def w_orders_counts(spark, folder):
    return _exact_counts(W.status_by_customer(spark, folder))


@query(_exact(O.PART_FLAGS))
def w_lineitem_counts(spark, folder):
    return _exact_counts(W.flags_by_part(spark, folder))


@query(_exact(O.DAY_EVENTS))
def w_event_days_counts(spark, folder):
    return _exact_counts(W.events_by_day(spark, folder))


_CHATS = "SELECT CAST(conv_id AS VARCHAR) AS string_id, string_agg(text, chr(10)) AS text FROM conversations WHERE text IS NOT NULL GROUP BY 1"
_MONTHS = "SELECT strftime(o_orderdate, '%Y-%m') AS string_id, string_agg(o_orderstatus, '') AS text FROM orders GROUP BY 1"
_SUPPLIERS = "SELECT CAST(l_suppkey AS VARCHAR) AS string_id, string_agg(l_linestatus, '') AS text FROM lineitem GROUP BY 1"
_BASES = " UNION ALL ".join(f"SELECT '{kind}:' || string_id AS string_id, text FROM ({strings})" for kind, strings in (("passage", O.BENCHMARK), ("chat", _CHATS), ("day", O.DAY_EVENTS), ("orders", _MONTHS), ("flags", _SUPPLIERS)))
_MUTATED = f"SELECT string_id || '-' || kind || '-' || rate AS string_id, CAST({W.COPIES} * length(text) AS BIGINT) AS n FROM ({_BASES}), unnest([1, 2]) t(kind), unnest([{', '.join(f"'{r:.5f}'" for r in W.RATES)}]) u(rate)"


@query(f"SELECT string_id, n, true AS bound_holds, true AS best_holds FROM ({_MUTATED})")
def w_mutated_bound(spark, folder):
    once, keys = W.mutated_once(spark, folder)
    return W.of_mutated(M.bound_report(_counted_once(once, ("lz77", "two_way"))), keys)


def _counted_once(once: DataFrame, methods: tuple[str, ...]) -> DataFrame:
    """Counts of what :func:`workloads.mutated_once` gives, whose texts are made in the tasks that parse them while they fit."""
    return P.counts(once, methods) if once._longest <= KERNEL_CHARS else counts_any_size(once, methods)


def _groups(spark: SparkSession, folder: str, copies: bool = True) -> DataFrame:
    groups = {"family": W.families(spark), **({"mutated": W.mutated(spark, folder)} if copies else {}), "source": W.by_source(spark, folder), "conversation": W.conversations(spark, folder), "pages": W.pages_by_host(spark, folder), "events": W.events_by_day(spark, folder)}
    out = None
    for name, S in groups.items():
        part = S.select(F.concat(F.lit(f"{name}:"), "string_id").alias("string_id"), "text")
        out = part if out is None else out.unionByName(part)
    return out


@query()
def table_phrases(spark, folder):
    """Counts of the three methods, best of both directions, ratios, over all workload groups."""
    return M.table(counts_any_size(materialize(_groups(spark, folder), "groups")), methods=METHODS)


@query()
def table_winners(spark, folder):
    """The methods with the fewest phrases of every string of the groups; equal mutated copies are counted once."""
    once, keys = W.mutated_once(spark, folder)
    copies = W.of_mutated(M.winners(_counted_once(once, METHODS)), keys)
    rest = M.winners(counts_any_size(materialize(_groups(spark, folder, copies=False), "groups"), METHODS))
    return rest.unionByName(copies.withColumn("string_id", F.concat(F.lit("mutated:"), "string_id")))


@query(
    "SELECT 'source:' || source AS string_id, CAST(length(string_agg(text, chr(10))) AS BIGINT) AS n, true AS within_lz77, true AS ratio_as_reported FROM documents WHERE text IS NOT NULL GROUP BY 1"
)
def table_claims(spark, folder):
    """On versioned prose the two-way parse beats the left parse of either direction by a few per cent, as reported."""
    rows = M.table(counts_any_size(W.by_source(spark, folder), ("lz77", "two_way")), methods=("lz77", "two_way"))
    return rows.select(F.concat(F.lit("source:"), "string_id").alias("string_id"), "n", (F.col("two_way") <= F.col("lz77")).alias("within_lz77"), F.col("two_way_ratio").between(0.85, 0.99).alias("ratio_as_reported"))


@query()
def table_cost(spark, folder):
    """Seconds and measured peak bytes of each method on each source's text, and both factors against the left parse."""
    return M.cost_table(P.counts(P.balanced(W.by_source(spark, folder)), METHODS, directions=("forward",), memory=True), methods=METHODS)


@query("SELECT count(DISTINCT lang) AS strings, true AS within_four_times, true AS within_twice, true AS bytes_a_char FROM documents WHERE text IS NOT NULL")
def cost_claims(spark, folder):
    """All languages together: at most four times the left parse's time, at most twice its memory, at most 100 bytes a character."""
    methods = ("lz77", "two_way")
    rows = M.cost_table(P.counts(P.balanced(W.by_lang(spark, folder)), methods, directions=("forward",), memory=True), methods=methods)
    return rows.agg(
        F.count(F.lit(1)).alias("strings"),
        (F.sum("two_way_seconds") <= 4 * F.sum("lz77_seconds")).alias("within_four_times"),
        (F.max("memory_factor") <= 2).alias("within_twice"),
        (F.sum("two_way_bytes") <= 100 * F.sum("n")).alias("bytes_a_char"),
    )


@query()
def loop_counts(spark, folder):
    return P.two_way_work(P.balanced(W.by_source(spark, folder)))


@query("SELECT source AS string_id, CAST(length(string_agg(text, chr(10))) AS BIGINT) AS n, true AS loops_far_below_n, true AS finds_within_bound, true AS covered_once FROM documents WHERE text IS NOT NULL GROUP BY 1")
def loop_claims(spark, folder):
    """Candidates of a phrase: on average far below n; finds within the work bound; each copied position merged once."""
    rows = P.two_way_work(P.balanced(W.by_source(spark, folder)))
    return rows.select("string_id", "n", (F.col("candidates") / F.col("phrases") < F.col("n") / 100).alias("loops_far_below_n"), (F.col("finds") <= F.col("work_bound") + F.col("candidates")).alias("finds_within_bound"), (F.col("unions") <= F.col("n")).alias("covered_once"))


@query("SELECT CAST(item_id AS VARCHAR) AS string_id, true AS depth_below_n, CAST(length(text) AS BIGINT) AS n FROM benchmark")
def phrase_profile(spark, folder):
    """Depth of references and the phrases' lengths of whole passages: lengths add up, chains are shorter than the text."""
    phrases = materialize(P.two_way_parse(W.benchmark(spark, folder)), "phrases")
    sizes = M.phrase_counts(phrases).select("string_id", "n")
    return M.length_profile(phrases).join(M.side_mix(phrases), "string_id").join(M.reference_depth(phrases), "string_id").join(sizes, "string_id").select("string_id", (F.col("depth") < F.col("n")).alias("depth_below_n"), "n")


@query("SELECT string_id, method, true AS within_twice_the_logarithm FROM (" + O.PART_NAMES + "), unnest(['two_way', 'lz77', 'lex']) t(method) WHERE length(text) <= 10")
def gap_part_names(spark, folder):
    S = W.part_names(spark, folder).where("length(text) <= 10")
    rows = _by_text(S, lambda texts: M.gap_indicator(P.counts(texts, ("smallest", "two_way", "lz77", "lex"), ("forward",))))
    return rows.select("string_id", "method", (F.col("indicator") <= 2).alias("within_twice_the_logarithm"))
