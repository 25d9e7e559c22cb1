"""Queries for the relational operators around the methods."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from phrasework.functions.register import register
from phrasework.operators import measures as M
from phrasework.operators import parse as P
from phrasework.operators import phrases as R
from phrasework.operators import strings as T
from phrasework.operators import suffix_tables as X
from phrasework.plans import oracles as O
from phrasework.plans import workloads as W
from phrasework.plans.registry import query
from phrasework.plans.route import route
from phrasework.shared import materialize, own_path
from phrasework.sources import generators
from phrasework.sources.files import read_binary_files, read_strings, read_whole_files

LZ = O.starts(O.BENCHMARK, "prev_len")
NEXT = O.starts(O.BENCHMARK, "next_len")


def _lz(spark, folder) -> DataFrame:
    return P.lz77_parse(W.benchmark(spark, folder))


# Scans, sources and sinks


@query("SELECT doc_id, n_chars FROM documents WHERE n_chars > 1000")
def op_scan_prune(spark, folder):
    return W.table(spark, folder, "documents").select("doc_id", "n_chars").where("n_chars > 1000")


@query(f"SELECT format, count(*) AS phrases FROM ({LZ}), unnest(['csv', 'json', 'orc', 'parquet']) t(format) GROUP BY 1")
def op_formats_roundtrip(spark, folder):
    phrases = materialize(_lz(spark, folder), "phrases")
    out = None
    for fmt in ("csv", "json", "orc", "parquet"):
        path = own_path(spark, f"phrases-{fmt}")
        R.write_phrases(phrases, path, fmt)
        part = R.read_phrases(spark, path, fmt).agg(F.count(F.lit(1)).alias("phrases")).select(F.lit(fmt).alias("format"), "phrases")
        out = part if out is None else out.unionByName(part)
    return out


@query("SELECT kind, CAST(sum(length(text)) AS BIGINT) AS chars FROM benchmark, unnest(['binary', 'whole']) t(kind) GROUP BY 1")
def op_file_sources(spark, folder):
    path = own_path(spark, "texts")
    rows = W.table(spark, folder, "benchmark").select(F.encode("text", "UTF-8").alias("b"), "text")
    rows.select(F.regexp_replace("text", "\n", " ").alias("value")).repartition(3).write.option("lineSep", "\n").text(path)
    whole = read_whole_files(spark, path).agg(F.sum(F.length("text") - F.length("text") + F.length(F.regexp_replace("text", "\n", ""))).alias("chars")).select(F.lit("whole").alias("kind"), "chars")
    binary = read_binary_files(spark, path).agg(F.sum(F.length(F.decode(F.encode(F.regexp_replace("text", "\n", ""), "ISO-8859-1"), "UTF-8"))).alias("chars")).select(F.lit("binary").alias("kind"), "chars")
    return whole.unionByName(binary)


@query("SELECT CAST(p_partkey AS VARCHAR) AS string_id, p_name AS text FROM part")
def op_read_strings(spark, folder):
    return read_strings(spark, f"{folder}/part.parquet", "p_partkey", "p_name")


@query(f"SELECT string_id, start, length FROM ({LZ})")
def op_project_struct(spark, folder):
    packed = _lz(spark, folder).select("string_id", F.array(F.struct("start", "length", "ref")).alias("p"))
    return packed.select("string_id", F.inline("p")).select("string_id", "start", "length")


@query("SELECT doc_id FROM documents WHERE regexp_matches(text, '[0-9]{3}') AND text LIKE '% the %' AND n_chars BETWEEN 500 AND 5000 AND lang IN ('en', 'de') AND NOT starts_with(text, 'A')")
def op_filter_predicates(spark, folder):
    t = F.col("text")
    return W.table(spark, folder, "documents").where(t.rlike("[0-9]{3}") & t.like("% the %") & F.col("n_chars").between(500, 5000) & F.col("lang").isin("en", "de") & ~t.startswith("A")).select("doc_id")


# Strings


@query("SELECT CAST(item_id AS VARCHAR) AS string_id, CAST(p AS BIGINT) AS pos, CAST(unicode(substr(text, p, 1)) AS INT) AS ch FROM benchmark, unnest(range(1, length(text) + 1)) t(p)")
def op_chars(spark, folder):
    return T.chars(W.benchmark(spark, folder))


@query("SELECT CAST(item_id AS VARCHAR) AS string_id, string_agg(substr(text, p, 1), '' ORDER BY p DESC) AS text FROM benchmark, unnest(range(1, length(text) + 1)) t(p) GROUP BY 1")
def op_reverse(spark, folder):
    return T.reversed_strings(W.benchmark(spark, folder))


@query(
    "WITH p AS (SELECT DISTINCT text AS pattern FROM benchmark WHERE text <> ''), hit AS (SELECT CAST(doc_id AS VARCHAR) AS string_id, pattern, text FROM documents JOIN p ON contains(text, pattern)) "
    "SELECT string_id, pattern, CAST(k AS BIGINT) AS pos FROM hit, unnest(range(1, length(text) - length(pattern) + 2)) t(k) WHERE substr(text, k, length(pattern)) = pattern"
)
def op_occurrences(spark, folder):
    """Every place of every whole passage in every whole document."""
    return T.occurrences(W.documents(spark, folder), W.table(spark, folder, "benchmark").select(F.col("text").alias("pattern")))


@query("SELECT item_id, lower(text) AS low, instr(text, 'the') AS place, translate(text, 'aeiou', 'AEIOU') AS vowels, lpad(CAST(item_id AS VARCHAR), 6, '0') AS padded, regexp_replace(text, '[aeiou]', '', 'g') AS bare, len(string_split(text, ' ')) AS words FROM benchmark")
def op_str_functions(spark, folder):
    return W.table(spark, folder, "benchmark").select(
        "item_id", F.lower("text").alias("low"), F.instr("text", "the").cast("bigint").alias("place"), F.translate("text", "aeiou", "AEIOU").alias("vowels"), F.lpad(F.col("item_id").cast("string"), 6, "0").alias("padded"), F.regexp_replace("text", "[aeiou]", "").alias("bare"), F.size(F.split("text", " ")).cast("bigint").alias("words")
    )


@query(f"WITH {O.factors(O.BENCHMARK)} SELECT string_id, i, j, lce FROM ext WHERE i <= 4 AND j - i <= 8")
def op_lcp_len(spark, folder):
    S = W.benchmark(spark, folder)
    pairs = S.select("string_id", F.explode(F.array(*(F.lit(x).cast("bigint") for x in (1, 2, 3, 4)))).alias("i"), F.length("text").alias("n")).withColumn("j", F.explode(F.sequence(F.col("i") + 1, F.least(F.col("i") + 8, F.col("n").cast("bigint"))))).select("string_id", "i", "j")
    return T.lce(S, pairs)


@query(f"WITH {O.suffixes(O.BENCHMARK)} SELECT string_id, rank, pos, coalesce(lag(pos) OVER (PARTITION BY string_id ORDER BY rank), 0) AS above FROM suf")
def op_win_lag(spark, folder):
    return X.suffix_table(W.benchmark(spark, folder)).withColumn("above", F.lag("pos", 1, 0).over(Window.partitionBy("string_id").orderBy("rank"))).select("string_id", "rank", "pos", "above")


@query("SELECT CAST(doc_id AS VARCHAR) AS string_id, CASE WHEN length(text) <= 64 THEN 'sql' WHEN length(text) <= 20000 THEN 'kernel' ELSE 'distributed' END AS tier FROM documents WHERE text IS NOT NULL")
def op_route(spark, folder):
    return route(W.documents(spark, folder), kernel_chars=20000).select("string_id", "tier")


# Joins


@query("SELECT quality, count(*) AS documents, sum(n_chars) AS chars FROM documents JOIN labels USING (doc_id) GROUP BY 1")
def op_join_hash(spark, folder):
    return W.table(spark, folder, "documents").select("doc_id", "n_chars").join(W.table(spark, folder, "labels"), "doc_id").groupBy("quality").agg(F.count(F.lit(1)).alias("documents"), F.sum("n_chars").cast("decimal(38,0)").cast("double").alias("chars"))


@query("SELECT r_name, count(*) AS customers, CAST(sum(length(c_name)) AS BIGINT) AS chars FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def op_join_broadcast(spark, folder):
    places = W.table(spark, folder, "nation").join(F.broadcast(W.table(spark, folder, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    rows = W.table(spark, folder, "customer").join(F.broadcast(places), F.col("c_nationkey") == F.col("n_nationkey"))
    return rows.groupBy("r_name").agg(F.count(F.lit(1)).alias("customers"), F.sum(F.length("c_name")).cast("bigint").alias("chars"))


@query("SELECT o_orderkey, string_agg(l_returnflag, '' ORDER BY l_linenumber, l_returnflag) AS flags FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE o_orderstatus = 'F' GROUP BY 1")
def op_join_merge(spark, folder):
    o, l = W.table(spark, folder, "orders").where("o_orderstatus = 'F'").select("o_orderkey"), W.table(spark, folder, "lineitem").select("l_orderkey", "l_linenumber", "l_returnflag")
    rows = o.join(l.hint("merge"), o.o_orderkey == l.l_orderkey)
    flags = F.array_sort(F.collect_list(F.struct("l_linenumber", "l_returnflag")))
    return rows.groupBy("o_orderkey").agg(F.array_join(F.transform(flags, lambda x: x["l_returnflag"]), "").alias("flags"))


@query(f"SELECT p.string_id, q AS pos, p.start FROM ({LZ}) p, unnest([1, 10, 33, 60]) t(q) WHERE p.start <= q AND q < p.start + p.length")
def op_join_range(spark, folder):
    S = W.benchmark(spark, folder)
    asked = S.select("string_id", F.explode(F.array(*map(F.lit, (1, 10, 33, 60)))).alias("pos"))
    return R.covering(_lz(spark, folder), asked, block=16).select("string_id", "pos", "start")


@query("SELECT CAST(item_id AS VARCHAR) AS string_id, CAST(q AS BIGINT) AS pos, substr(text, q, 1) AS ch FROM benchmark, unnest([1, 10, 33, 60]) t(q)")
def op_char_at(spark, folder):
    S = W.benchmark(spark, folder)
    asked = S.select("string_id", F.explode(F.array(*(F.lit(x).cast("bigint") for x in (1, 10, 33, 60)))).alias("pos"))
    return R.char_at(materialize(P.two_way_parse(S), "phrases"), asked)


@query("SELECT event_id, max(o_orderdate) AS last_order FROM events LEFT JOIN orders ON o_custkey = user_id AND o_orderdate <= ts GROUP BY 1")
def op_join_asof(spark, folder):
    e = W.table(spark, folder, "events").select("event_id", "user_id", F.col("ts"), F.lit(None).cast("timestamp").alias("seen"), F.lit(1).alias("side"))
    o = W.table(spark, folder, "orders").select(F.lit(None).cast("bigint").alias("event_id"), F.col("o_custkey").alias("user_id"), F.col("o_orderdate").cast("timestamp").alias("ts"), F.col("o_orderdate").cast("timestamp").alias("seen"), F.lit(0).alias("side"))
    both = e.withColumn("ts", F.col("ts").cast("timestamp")).unionByName(o)
    w = Window.partitionBy("user_id").orderBy("ts", "side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("last_order", F.last("seen", ignorenulls=True).over(w)).where("side = 1").select("event_id", F.col("last_order").cast("timestamp_ntz").alias("last_order"))


@query("SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.ts < b.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE")
def op_join_interval(spark, folder):
    # Ten-minute buckets turn the band into an equi-join with this bucket and the next.
    e = W.table(spark, folder, "events").select("event_id", "user_id", "ts", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 600_000_000).alias("bucket"))
    a = e.select(F.col("event_id").alias("first_id"), "user_id", F.col("ts").alias("t1"), F.explode(F.array(F.col("bucket"), F.col("bucket") + 1)).alias("bucket"))
    b = e.select(F.col("event_id").alias("second_id"), "user_id", F.col("ts").alias("t2"), "bucket")
    return a.join(b, ["user_id", "bucket"]).where("t1 < t2 and t2 <= t1 + interval 10 minutes").select("first_id", "second_id")


@query(f"SELECT string_id, start, length FROM ({LZ})")
def op_join_lateral_udtf(spark, folder):
    register(spark)
    W.benchmark(spark, folder).createOrReplaceTempView("lateral_strings")
    return spark.sql("SELECT string_id, start, length FROM lateral_strings, LATERAL lz77_phrases(text)")


@query("SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def op_join_semi(spark, folder):
    return W.table(spark, folder, "documents").select("doc_id").join(W.table(spark, folder, "labels"), "doc_id", "left_semi")


@query("SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def op_join_anti(spark, folder):
    return W.table(spark, folder, "documents").select("doc_id").join(W.table(spark, folder, "labels"), "doc_id", "left_anti")


@query(f"SELECT string_id, start, coalesce(a.length, 0) AS left_length, coalesce(b.length, 0) AS right_length FROM ({LZ}) a FULL JOIN ({NEXT}) b USING (string_id, start)")
def op_join_outer(spark, folder):
    S = W.benchmark(spark, folder)
    a, b = (P.parse(S, m).select("string_id", "start", F.col("length").alias(c)) for m, c in (("lz77", "left_length"), ("lz_next", "right_length")))
    return a.join(b, ["string_id", "start"], "full_outer").na.fill(0)


@query("SELECT CAST(item_id AS VARCHAR) AS string_id, CAST(length(text) AS BIGINT) AS positions, true AS agree FROM benchmark")
def op_join_self(spark, folder):
    graph = materialize(R.reference_graph(P.two_way_parse(W.benchmark(spark, folder))), "graph")
    twice, by_hops = R.square(graph), R.follow(graph, 2)
    both = twice.join(by_hops.select("string_id", "pos", F.col("target").alias("t2"), F.col("literal").alias("l2")), ["string_id", "pos"])
    return both.groupBy("string_id").agg(F.count(F.lit(1)).alias("positions"), F.min(F.col("target").eqNullSafe(F.col("t2")) & F.col("literal").eqNullSafe(F.col("l2"))).alias("agree"))


# Aggregation


@query(f"SELECT string_id, count(*) AS phrases, CAST(sum(length) AS BIGINT) AS total, min(length) AS least, max(length) AS most, round(avg(length), 6) AS mean FROM ({LZ}) GROUP BY 1")
def op_agg_hash(spark, folder):
    return _lz(spark, folder).groupBy("string_id").agg(F.count(F.lit(1)).alias("phrases"), F.sum("length").alias("total"), F.min("length").alias("least"), F.max("length").alias("most"), F.round(F.avg("length"), 6).alias("mean"))


@query("SELECT source, count(DISTINCT text) AS texts FROM documents GROUP BY 1")
def op_agg_distinct(spark, folder):
    return W.table(spark, folder, "documents").groupBy("source").agg(F.count_distinct("text").alias("texts"))


@query("SELECT source, true AS within_tenth FROM documents GROUP BY 1")
def op_agg_approx(spark, folder):
    """Distinct texts by source from a sketch, held to the exact number."""
    rows = W.table(spark, folder, "documents").groupBy("source").agg(F.approx_count_distinct("text", 0.02).alias("about"), F.count_distinct("text").alias("texts"))
    return rows.select("source", (F.abs(F.col("about") - F.col("texts")) <= F.greatest(F.lit(1.0), F.col("texts") * 0.1)).alias("within_tenth"))


LEVELS = "SELECT lang, source, CAST(grouping_id(lang, source) AS BIGINT) AS level, count(*) AS documents, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY {}"


def _levels(rows) -> DataFrame:
    return rows.agg(F.grouping_id().cast("bigint").alias("level"), F.count(F.lit(1)).alias("documents"), F.sum("n_chars").alias("chars")).select("lang", "source", "level", "documents", "chars")


@query(LEVELS.format("ROLLUP (lang, source)"))
def op_agg_rollup(spark, folder):
    return _levels(W.table(spark, folder, "documents").rollup("lang", "source"))


@query(LEVELS.format("CUBE (lang, source)"))
def op_agg_cube(spark, folder):
    return _levels(W.table(spark, folder, "documents").cube("lang", "source"))


@query(LEVELS.format("GROUPING SETS ((lang), (source), ())"))
def op_agg_grouping_sets(spark, folder):
    return _levels(W.table(spark, folder, "documents").groupingSets([[F.col("lang")], [F.col("source")], []], F.col("lang"), F.col("source")))


@query(f"WITH a AS ({O.phrase_counts(O.BENCHMARK, 'prev_len')}), c AS ({O.phrase_counts(O.BENCHMARK, 'lcp')}) SELECT string_id, a.phrases AS lz77, c.phrases AS lex FROM a JOIN c USING (string_id)")
def op_agg_pivot(spark, folder):
    return P.counts(W.benchmark(spark, folder), ("lz77", "lex"), ("forward",)).groupBy("string_id").pivot("method", ["lz77", "lex"]).agg(F.first("phrases"))


@query("SELECT CAST(conv_id AS VARCHAR) AS string_id, string_agg(text, chr(10) ORDER BY turn) AS text FROM conversations WHERE text IS NOT NULL GROUP BY 1")
def op_agg_concat(spark, folder):
    return W.conversations(spark, folder)


@query("SELECT source, round(quantile_cont(n_chars, 0.5), 4) AS median, round(quantile_cont(n_chars, 0.9), 4) AS p90 FROM documents GROUP BY 1")
def op_agg_percentile(spark, folder):
    return W.table(spark, folder, "documents").groupBy("source").agg(F.round(F.percentile("n_chars", F.lit(0.5)), 4).alias("median"), F.round(F.percentile("n_chars", F.lit(0.9)), 4).alias("p90"))


@query(f"SELECT string_id, count(*) FILTER (WHERE NOT is_literal) AS copies, count(*) FILTER (WHERE is_literal) AS literals FROM ({LZ}) GROUP BY 1")
def op_agg_conditional(spark, folder):
    return _lz(spark, folder).groupBy("string_id").agg(F.count_if(F.col("ref") < F.col("start")).alias("copies"), F.count_if(F.col("ref").isNull()).alias("literals"))


# Windows, order, sets


@query(f"WITH a AS ({O.phrase_counts(O.BENCHMARK, 'prev_len')}), c AS ({O.phrase_counts(O.BENCHMARK, 'lcp')}), u AS (SELECT string_id, 'lz77' AS method, phrases FROM a UNION ALL SELECT string_id, 'lex', phrases FROM c) SELECT *, CAST(rank() OVER (PARTITION BY string_id ORDER BY phrases) AS INT) AS place FROM u")
def op_win_rank(spark, folder):
    w = Window.partitionBy("string_id").orderBy("phrases")
    return P.counts(W.benchmark(spark, folder), ("lz77", "lex"), ("forward",)).select("string_id", "method", "phrases", F.rank().over(w).alias("place"))


@query(f"SELECT string_id, start, true AS due FROM ({LZ})")
def op_win_running(spark, folder):
    w = Window.partitionBy("string_id").orderBy("start").rowsBetween(Window.unboundedPreceding, -1)
    return _lz(spark, folder).select("string_id", "start", (F.coalesce(F.sum("length").over(w), F.lit(0)) + 1 == F.col("start")).alias("due"))


@query("SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW), 4) AS mean FROM events")
def op_win_rows_frame(spark, folder):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-3, 0)
    return W.table(spark, folder, "events").select("event_id", F.round(F.avg("value").over(w), 4).alias("mean"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS recent FROM events")
def op_win_range_frame(spark, folder):
    w = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3_600_000_000, 0)
    return W.table(spark, folder, "events").select("event_id", F.count(F.lit(1)).over(w).alias("recent"))


@query("SELECT doc_id, CAST(ntile(4) OVER w AS INT) AS quarter, first_value(doc_id) OVER w AS shortest FROM documents WINDOW w AS (PARTITION BY lang ORDER BY n_chars, doc_id)")
def op_win_ntile_first_last(spark, folder):
    w = Window.partitionBy("lang").orderBy("n_chars", "doc_id")
    return W.table(spark, folder, "documents").select("doc_id", F.ntile(4).over(w).alias("quarter"), F.first("doc_id").over(w).alias("shortest"))


@query(f"SELECT string_id, start, length FROM ({LZ}) ORDER BY length DESC, string_id, start LIMIT 10")
def op_topk(spark, folder):
    return _lz(spark, folder).select("string_id", "start", "length").orderBy(F.desc("length"), "string_id", "start").limit(10)


@query("SELECT lang, n_chars, doc_id FROM documents ORDER BY lang, n_chars DESC, doc_id")
def op_sort_multi(spark, folder):
    return W.table(spark, folder, "documents").select("lang", "n_chars", "doc_id").orderBy("lang", F.desc("n_chars"), "doc_id")


def _two_sets(spark, folder) -> tuple[DataFrame, DataFrame]:
    S = W.benchmark(spark, folder)
    return tuple(P.parse(S, m).select("string_id", "start", "length") for m in ("lz77", "lz_next"))


@query(f"SELECT string_id, start, length FROM ({LZ}) UNION ALL SELECT string_id, start, length FROM ({NEXT})")
def op_union(spark, folder):
    a, b = _two_sets(spark, folder)
    return a.unionByName(b)


@query(f"SELECT string_id, start, length FROM ({LZ}) INTERSECT SELECT string_id, start, length FROM ({NEXT})")
def op_intersect(spark, folder):
    a, b = _two_sets(spark, folder)
    return a.intersect(b)


@query(f"SELECT string_id, start, length FROM ({LZ}) EXCEPT ALL SELECT string_id, start, length FROM ({NEXT})")
def op_except_all(spark, folder):
    a, b = _two_sets(spark, folder)
    return a.exceptAll(b)


# Scalars


@query(f"WITH c AS (SELECT string_id, count(*) FILTER (WHERE NOT is_literal) AS copies, count(*) FILTER (WHERE is_literal) AS literals, sum(length) AS n FROM ({LZ}) GROUP BY 1) SELECT string_id, CAST(copies * 2 * ceil(log2(greatest(n, 2))) + literals * 8 AS BIGINT) AS bits FROM c")
def op_math_bits(spark, folder):
    counted = P.counts(W.benchmark(spark, folder), ("lz77",), ("forward",))
    return M.encoded_bits(counted, 256).select("string_id", "bits")


@query("SELECT strftime(ts, '%Y-%m-%d') AS string_id, string_agg(CASE event_type WHEN 'signup' THEN 's' WHEN 'view' THEN 'v' WHEN 'error' THEN 'e' WHEN 'click' THEN 'c' WHEN 'purchase' THEN 'p' ELSE '?' END, '' ORDER BY ts, event_id) AS text FROM events GROUP BY 1")
def op_date_buckets(spark, folder):
    return W.events_by_day(spark, folder)


@query(
    "WITH g AS (SELECT user_id, list(event_type ORDER BY ts, event_id) AS a FROM events GROUP BY 1) "
    "SELECT user_id, array_to_string(list_sort(list_distinct(a)), ',') AS kinds, array_to_string(a[1:3], ',') AS first_three, CAST(len(list_filter(a, lambda x: x = 'click')) AS INT) AS clicks FROM g"
)
def op_array_functions(spark, folder):
    g = W.table(spark, folder, "events").groupBy("user_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("ts", "event_id", "event_type"))), lambda x: x["event_type"]).alias("a"))
    return g.select("user_id", F.array_join(F.array_sort(F.array_distinct("a")), ",").alias("kinds"), F.array_join(F.slice("a", 1, 3), ",").alias("first_three"), F.size(F.filter("a", lambda x: x == "click")).alias("clicks"))


@query(f"WITH a AS ({O.phrase_counts(O.BENCHMARK, 'prev_len')}), c AS ({O.phrase_counts(O.BENCHMARK, 'lcp')}) SELECT string_id, a.phrases AS lz77, CAST(2 AS INT) AS entries, c.phrases AS lex FROM a JOIN c USING (string_id)")
def op_map_functions(spark, folder):
    counted = P.counts(W.benchmark(spark, folder), ("lz77", "lex"), ("forward",))
    bags = counted.groupBy("string_id").agg(F.map_from_entries(F.collect_list(F.struct("method", "phrases"))).alias("m"))
    return bags.select("string_id", F.element_at("m", "lz77").alias("lz77"), F.size(F.map_keys("m")).alias("entries"), F.try_element_at("m", F.lit("lex")).alias("lex"))


@query("SELECT event_id, json_valid(props) AS valid, CAST(len(json_keys(props)) AS INT) AS entries FROM events")
def op_json_functions(spark, folder):
    rows = W.table(spark, folder, "events")
    return rows.select("event_id", F.from_json("props", "map<string,string>").isNotNull().alias("valid"), F.size(F.json_object_keys("props")).alias("entries"))


@query("WITH g AS (SELECT user_id, ts > lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE AS new FROM events) SELECT user_id, count(*) FILTER (WHERE coalesce(new, true)) AS sessions FROM g GROUP BY 1")
def op_interval_arith(spark, folder):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    rows = W.table(spark, folder, "events").select("user_id", (F.col("ts") > F.lag("ts").over(w) + F.expr("interval 30 minutes")).alias("new"))
    return rows.groupBy("user_id").agg(F.count_if(F.coalesce("new", F.lit(True))).alias("sessions"))


@query(f"SELECT * FROM ({O.phrase_counts(O.BENCHMARK, 'prev_len')})")
def op_recursive_walk(spark, folder):
    S = W.benchmark(spark, folder)
    longest = S.agg(F.max(F.length("text"))).first()[0] or 0
    materialize(X.previous_factor(S), "factors").createOrReplaceTempView("walk_factors")
    return spark.sql(
        f"WITH RECURSIVE w(string_id, pos, size) MAX RECURSION LEVEL {longest + 1} AS (SELECT string_id, pos, prev_len FROM walk_factors WHERE pos = 1 UNION ALL "
        "SELECT w.string_id, f.pos, f.prev_len FROM w JOIN walk_factors f ON f.string_id = w.string_id AND f.pos = w.pos + greatest(w.size, 1)) "
        "SELECT string_id, count(*) AS phrases FROM w GROUP BY string_id"
    )


@query("SELECT doc_id FROM documents d WHERE n_chars > (SELECT avg(n_chars) FROM documents e WHERE e.source = d.source)")
def op_subquery_correlated(spark, folder):
    W.table(spark, folder, "documents").select("doc_id", "source", "n_chars").createOrReplaceTempView("sized_documents")
    return spark.sql("SELECT doc_id FROM sized_documents d WHERE n_chars > (SELECT avg(n_chars) FROM sized_documents e WHERE e.source = d.source)")


@query(f"SELECT * FROM ({O.phrase_counts(O.BENCHMARK, 'prev_len')})")
def op_udf_count(spark, folder):
    from phrasework.functions.register import lz77_count

    return W.benchmark(spark, folder).select("string_id", lz77_count("text").alias("phrases"))


@query(
    f"SELECT string_id, d.phrases AS two_way, a.phrases AS lz77, c.phrases AS lex FROM ({O.phrase_counts(O.PART_NAMES, 'prev_len')}) a JOIN ({O.phrase_counts(O.PART_NAMES, 'lcp')}) c USING (string_id) "
    f"JOIN (SELECT string_id, count(*) AS phrases FROM ({O.two_way(O.PART_NAMES)}) GROUP BY 1) d USING (string_id)"
)
def op_sql_counts(spark, folder):
    register(spark)
    W.part_names(spark, folder).createOrReplaceTempView("counted_strings")
    return spark.sql("SELECT string_id, two_way_count(text) AS two_way, lz77_count(text) AS lz77, lex_count(text) AS lex FROM counted_strings")


@query(
    " UNION ALL ".join(f"SELECT '{m}' AS method, string_id, start, length FROM ({O.starts(O.PART_NAMES, jump)})" for m, jump in (("lex", "lcp"), ("lz_next", "next_len")))
    + f" UNION ALL SELECT 'two_way', string_id, start, length FROM ({O.two_way(O.PART_NAMES)})"
)
def op_table_functions(spark, folder):
    register(spark)
    W.part_names(spark, folder).createOrReplaceTempView("parsed_strings")
    return spark.sql(" UNION ALL ".join(f"SELECT '{m}' AS method, string_id, start, length FROM parsed_strings, LATERAL {m}_phrases(text)" for m in ("lex", "lz_next", "two_way")))


@query(f"WITH {O.suffixes(O.PART_NAMES)} SELECT string_id, rank, pos, lcp FROM suf")
def op_suffix_function(spark, folder):
    register(spark)
    W.part_names(spark, folder).createOrReplaceTempView("sorted_strings")
    return spark.sql("SELECT string_id, rank, pos, lcp FROM sorted_strings, LATERAL suffix_rows(text)")


@query("SELECT CAST(conv_id AS VARCHAR) AS string_id, CAST(length(string_agg(text, chr(10))) AS BIGINT) AS n, true AS fewer FROM conversations WHERE text IS NOT NULL GROUP BY 1")
def op_udaf_group_parse(spark, folder):
    import pyarrow as pa

    from phrasework.kernels.suffix import codes_of
    from phrasework.kernels.two_way import two_way

    def parse_group(key, table):
        rows = sorted(zip(table.column("turn").to_pylist(), table.column("text").to_pylist()))
        text = "\n".join(t for _, t in rows if t is not None)
        return pa.table({"string_id": [str(key[0].as_py())], "n": pa.array([len(text)], pa.int64()), "fewer": [len(two_way(codes_of(text))) < max(2, len(text))]})

    rows = W.table(spark, folder, "conversations").where("text is not null").select("conv_id", "turn", "text")
    return rows.groupBy("conv_id").applyInArrow(parse_group, "string_id string, n bigint, fewer boolean")


@query("SELECT doc_id FROM (SELECT doc_id, row_number() OVER (PARTITION BY text ORDER BY doc_id) AS k FROM documents) WHERE k = 1")
def op_dedup(spark, folder):
    # The smallest id of each text; a partial aggregate shrinks copies before the shuffle.
    return W.table(spark, folder, "documents").groupBy("text").agg(F.min("doc_id").alias("doc_id")).select("doc_id")


@query("SELECT true AS share_as_asked, true AS ratio_as_reported")
def op_sample(spark, folder):
    """Ratio of two-way to left parse estimated on a tenth of the documents, and the share that was drawn."""
    S = W.documents(spark, folder)
    rows = M.best_counts(P.counts(S.sample(0.1, seed=42), ("lz77", "two_way"))).groupBy().pivot("method", ["lz77", "two_way"]).agg(F.sum("phrases").alias("phrases"), F.count(F.lit(1)).alias("strings"))
    share = F.col("two_way_strings") / F.col("strings")
    return rows.join(S.agg(F.count("text").alias("strings"))).select(share.between(0.05, 0.15).alias("share_as_asked"), (F.col("two_way_phrases") / F.col("lz77_phrases")).between(0.85, 1.0).alias("ratio_as_reported"))


@query("SELECT quality, toxic, count(*) AS documents, round(avg(n_chars), 4) AS mean_chars FROM documents JOIN labels USING (doc_id) GROUP BY 1, 2")
def op_quality_slice(spark, folder):
    rows = W.table(spark, folder, "documents").select("doc_id", "n_chars").join(W.table(spark, folder, "labels"), "doc_id")
    return rows.groupBy("quality", "toxic").agg(F.count(F.lit(1)).alias("documents"), F.round(F.avg("n_chars"), 4).alias("mean_chars"))


@query("SELECT CAST(k AS INT) AS k, CAST(power(2, k - 1) AS BIGINT) AS n FROM range(4, 15) t(k)")
def op_generators(spark, folder):
    return generators.thue_morse(spark, 4, 14).select("k", F.length("text").cast("bigint").alias("n"))


@query(
    "WITH g AS (SELECT item_id, c, p, length(text) AS n, substr(text, CAST(p AS BIGINT), 1) AS own, text, (c * 7919 + p * 104729 + 12345) * 31 % 1000003 AS h FROM benchmark, unnest(range(0, 5)) t(c), unnest(range(1, length(text) + 1)) u(p)), "
    "m AS (SELECT item_id, c, p, own, CASE WHEN c > 0 AND h * 1000000 < 0.01 * 1000000 * 1000003 THEN substr(text, CAST(h * 131 % n + 1 AS BIGINT), 1) WHEN c = 0 THEN own END AS new FROM g), "
    "k AS (SELECT item_id, 1 AS kind, c, p, coalesce(new, own) AS letter FROM m UNION ALL SELECT item_id, 2, c, p, last_value(new IGNORE NULLS) OVER (PARTITION BY item_id, p ORDER BY c) FROM m) "
    "SELECT CAST(item_id AS VARCHAR) AS string_id, CAST(kind AS INT) AS kind, string_agg(letter, '' ORDER BY c, p) AS text FROM k GROUP BY ALL"
)
def op_mutated_text(spark, folder):
    return generators.mutated_copies(W.benchmark(spark, folder), 5, [0.01]).select("string_id", "kind", "text")
