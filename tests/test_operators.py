import json
import random

import pytest

from pyspark.sql import functions as F

from phrasework import schemas
from phrasework.operators import measures as M
from phrasework.operators import parse as P
from phrasework.operators import phrases as R
from phrasework.operators import strings as T
from phrasework.operators import suffix_tables as X
from phrasework.operators.sharded import two_way_parse_sharded
from phrasework.plans import stream_queries  # noqa: F401  registers the streaming queries
from phrasework.plans.route import two_way_any_size
from phrasework.sources import phrasefile


def strings(spark, *rows):
    return spark.createDataFrame(list(rows), schemas.STRINGS)


def test_nulls_empties_and_repeats(spark):
    S = strings(spark, ("n", None), ("e", ""), ("a", "abab"), ("a2", "abab"), ("u", "é😀é😀"))
    for method in ("two_way", "lz77", "lex", "lz_next", "lz_backward", "literal", "bwt_run", "lcp_first"):
        got = {r.string_id: r.text for r in R.decode(P.parse(S, method)).collect()}
        assert got == {"a": "abab", "a2": "abab", "u": "é😀é😀"}, method
    assert {r.string_id: r.phrases for r in P.counts(S, ("lz77",), ("forward",)).collect()} == {"e": 0, "a": 3, "a2": 3, "u": 3}
    assert P.parse(S.limit(0)).count() == 0
    assert {r.string_id for r in P.parse(S, collapse=True).collect()} == {"a", "a2", "u"}


def test_directions_and_units(spark):
    S = strings(spark, ("a", "aaabaa"), ("b", "héé héé"))
    for direction in ("forward", "reverse", "best"):
        phrases = P.parse(S, "two_way", direction=direction)
        assert R.check_partition(phrases, S).count() == 0
        assert {r.string_id: r.text for r in R.decode(phrases).collect()} == {"a": "aaabaa", "b": "héé héé"}
    raw = P.parse(S, "lz77", unit="byte").where("string_id = 'b'").agg({"length": "sum"}).first()[0]
    assert raw == len("héé héé".encode())
    with pytest.raises(ValueError):
        P.parse(S, "other")


def test_partition_problems_are_found(spark):
    S = strings(spark, ("a", "abab"))
    bad = [("a", 1, 1, 2, 3, None, "right"), ("a", 2, 3, 1, 2, None, "left"), ("a", 3, 5, 1, None, "b", "literal")]
    problems = {r.problem for r in R.check_partition(spark.createDataFrame(bad, schemas.PHRASES), S).collect()}
    assert {"unequal copy", "gap or overlap"} <= problems
    assert R.check_partition(spark.createDataFrame([], schemas.PHRASES), S).first().problem == "not covered"


def test_cycles(spark):
    phrases = spark.createDataFrame([("x", 1, 1, 2, 3, None, "right"), ("x", 2, 3, 2, 1, None, "left"), ("x", 3, 5, 1, None, "b", "literal")], schemas.PHRASES)
    assert not R.is_valid(phrases).first().valid
    assert sorted(r.pos for r in R.cyclic_positions(R.reference_graph(phrases)).collect()) == [1, 2, 3, 4]
    assert R.decode(phrases).first().text is None


def test_tiers_agree(spark):
    text = ("the cat sat on the mat and the cat ran " * 6)[:200]
    S = strings(spark, ("a", text), ("b", "banana"))
    kernel = sorted(map(tuple, X.suffix_table(S).collect()))
    assert kernel == sorted(map(tuple, X.suffix_table(S, tier="distributed").collect()))
    plain = {(r.string_id, r.pos): (r.prev_len, r.next_len) for r in X.factor_table(S).collect()}
    assert plain == {(r.string_id, r.pos): (r.prev_len, r.next_len) for r in X.distributed_factor_table(S, block=7).collect()}
    one = P.two_way_parse(S).count()
    assert two_way_parse_sharded(S, 1000).count() == one
    routed = two_way_any_size(S, kernel_chars=50, shard_chars=64)
    assert {r.string_id: r.text for r in R.decode(routed).collect()} == {"a": text, "b": "banana"}


def test_measures(spark):
    S = strings(spark, ("a", "abracadabra" * 3), ("b", "mississippi"))
    counted = P.counts(S, ("lz77", "lex", "two_way", "lz_next", "lz_backward"))
    assert all(r.bound_holds and r.best_holds for r in M.bound_report(counted).collect())
    assert all(r.backward_is_left and r.right_is_backward_of_reverse and r.two_way_within_right for r in M.identity_report(counted).collect())
    assert {"two_way_ratio", "lex_ratio"} <= set(M.table(counted).columns)
    assert M.winners(counted).count() >= 2 and M.factors(counted).count() == 2
    trace = P.two_way_trace(S)
    assert all(r.candidates <= r.work_bound + r.phrases for r in M.trace_summary(trace).collect())
    profile = M.side_mix(P.two_way_parse(S)).collect()
    assert all(r.left_refs + r.right_refs + r.literals > 0 for r in profile)


def test_occurrences_both_ways(spark):
    S = strings(spark, ("a", "abababab"), ("b", "xyz"))
    patterns = spark.createDataFrame([("aba",), ("zz",), ("yz",)], "pattern string")
    want = {("a", "aba", 1), ("a", "aba", 3), ("a", "aba", 5), ("b", "yz", 2)}
    assert {tuple(r) for r in T.occurrences(S, patterns).collect()} == want
    assert {tuple(r) for r in T.occurrences(S, patterns, broadcast_rows=0).collect()} == want


def test_phrasefile_source(spark, tmp_path):
    S = strings(spark, ("a", "abracadabra"))
    path = tmp_path / "p.jsonl"
    row = R.nested(P.two_way_parse(S)).first()
    path.write_text(json.dumps({"string_id": row.string_id, "phrases": [p.asDict() for p in row.phrases]}) + "\n")
    phrasefile.register(spark)
    assert spark.read.format("phrasefile").option("path", str(path)).load().first().text == "abracadabra"


def test_late_rows_and_windows_agree_with_batch(spark, small):
    from phrasework.plans import workloads as W
    from phrasework.plans.registry import QUERIES
    from phrasework.streaming import windows as S

    batch = {(r.string_id, r.n, r.phrases) for r in S.window_counts(W.table(spark, small, "events"), S.tumbling(), None).collect()}
    stream = {(r.string_id, r.n, r.phrases) for r in QUERIES["st_window_parse"](spark, small).collect()}
    assert stream and stream <= batch


def test_online_left_parse(spark, small):
    from phrasework.kernels.greedy import left_parse
    from phrasework.kernels.suffix import codes_of
    from phrasework.plans import workloads as W
    from phrasework.streaming import windows as S

    last = S.run_to_table(S.online_left_parse(S.read_events(spark, f"{small}/events.parquet")), "online", "update").toPandas().sort_values("batch").groupby("user_id").last()
    for r in W.events_by_user(spark, small).collect():
        state = last.loc[int(r.string_id)]
        assert state.closed + (state.open_length > 0) == len(left_parse(codes_of(r.text)))


def test_random_access_through_long_chains(spark):
    """A run is one copy and a literal, so a chain is as long as the run."""
    texts = {"run": "a" * 200, "two": "ab" * 150, "word": "abracadabra"}
    phrases = P.two_way_parse(strings(spark, *texts.items())).cache()
    asked = spark.createDataFrame([(k, p) for k, t in texts.items() for p in {1, 2, len(t) // 2, len(t)}], "string_id string, pos bigint")
    for hops in (0, 3, 64):
        got = {(r.string_id, r.pos): r.ch for r in R.char_at(phrases, asked, hops).collect()}
        assert got == {(r.string_id, r.pos): texts[r.string_id][r.pos - 1] for r in asked.collect()}


def test_growing_a_copy_by_classes(spark):
    S = strings(spark, ("x", "abababaababa"))
    prefix = spark.createDataFrame([("x", 1, 1, 5, 3, None, "right")], schemas.PHRASES)
    profile = {r.j: r.length for r in P.extension_profile(S, [(5, 3)]).collect()}
    for ref in (2, 4, 9, 11):
        grows = [R.can_extend(prefix, S, ref, size).first().valid for size in (1, 2)]
        assert sum(grows) == profile[ref]


def test_distributed_tables_of_skewed_strings(spark):
    """A letter that makes up most of a string, periods, and one string among many short ones."""
    S = strings(spark, ("blanks", " " * 70 + "word" + " " * 50), ("period", "abc" * 40 + "x"), *((f"s{k}", "ab"[k % 2] * (k % 4)) for k in range(30)))
    assert sorted(map(tuple, X.suffix_table(S).collect())) == sorted(map(tuple, X.suffix_table(S, tier="distributed").collect()))
    plain = {(r.string_id, r.pos): (r.prev_len, r.next_len) for r in X.factor_table(S).collect()}
    assert plain == {(r.string_id, r.pos): (r.prev_len, r.next_len) for r in X.distributed_factor_table(S, block=5).collect()}


def test_memory_of_parses_is_linear(spark):
    from phrasework.kernels.suffix import codes_of
    from phrasework.kernels.two_way import Options
    from phrasework.operators.parse import _peak_bytes

    word, before = "a", "b"
    while len(word) < 60_000:
        before, word = word, word + before
    prose = " ".join(r.text for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").orderBy("doc_id").limit(60).collect())
    for text in (word, "a" * 60_000, prose):
        codes = codes_of(text)
        for method in ("two_way", "lz77", "lex"):
            assert _peak_bytes(codes, method, Options()) <= 100 * len(codes) + (1 << 16), (method, text[:20])


def test_attractors_as_rows(spark):
    S = strings(spark, ("x", "abab"), ("y", "aaa"), ("e", ""), ("n", None))
    marks = P.smallest_attractor(S)
    assert {r.string_id: r.is_attractor for r in P.is_attractor(S, marks).collect()} == {"x": True, "y": True, "e": True}
    assert {r.string_id: r.is_attractor for r in P.is_attractor(S, marks.where("string_id = 'y'")).collect()} == {"x": False, "y": True, "e": True}
    assert {r.string_id: r.text for r in R.decode(P.attractor_parse(S, marks)).collect()} == {"x": "abab", "y": "aaa"}


def test_mutated_copies_of_odd_strings(spark):
    from phrasework.sources import generators

    rows = generators.mutated_copies(strings(spark, ("n", None), ("e", ""), ("a", "é😀x" * 50)), 3, [0.0, 1.0]).collect()
    assert {(r.string_id, r.kind, r.rate, len(r.text)) for r in rows} == {(k, kind, rate, n) for k, n in (("e", 0), ("a", 450)) for kind in (1, 2) for rate in (0.0, 1.0)}
    assert all(r.text == "é😀x" * 150 for r in rows if r.string_id == "a" and r.rate == 0)


def test_online_parse_in_bounded_texts(spark, small):
    from phrasework.kernels.greedy import left_parse
    from phrasework.kernels.suffix import codes_of
    from phrasework.plans import workloads as W
    from phrasework.streaming import windows as S

    last = S.run_to_table(S.online_left_parse(S.read_events(spark, f"{small}/events.parquet"), most_chars=7), "online", "update").toPandas().sort_values("batch").groupby("user_id").last()
    for r in W.events_by_user(spark, small).collect():
        parts = [r.text[k : k + 7] for k in range(0, len(r.text), 7)]
        state = last.loc[int(r.string_id)]
        assert state.n == len(r.text) and state.closed + (state.open_length > 0) == sum(len(left_parse(codes_of(t))) for t in parts)


def test_common_prefixes_without_a_udf(spark):
    import random

    rng = random.Random(2)
    pairs = [("".join(rng.choice("ab") for _ in range(rng.randrange(0, 9))), "".join(rng.choice("ab") for _ in range(rng.randrange(0, 9)))) for _ in range(200)] + [("x" * 70, "x" * 64 + "y"), ("é😀", "é😀z")]
    rows = spark.createDataFrame(pairs, "x string, y string").select("x", "y", T.lcp_len(F.col("x"), F.col("y")).alias("k")).collect()
    assert all(r.k == next((i for i, (a, b) in enumerate(zip(r.x, r.y)) if a != b), min(len(r.x), len(r.y))) for r in rows)


def test_counts_of_any_size(spark):
    from phrasework.plans.route import counts_any_size

    S = strings(spark, ("long", ("the cat sat on the mat and the cat ran " * 4)[:140]), ("short", "banana"))
    methods = ("lz77", "lz_next", "lex", "two_way")
    want = {(r.string_id, r.method, r.direction): (r.n, r.phrases) for r in P.counts(S, methods, ("reverse",)).collect()}
    got = {(r.string_id, r.method, r.direction): (r.n, r.phrases) for r in counts_any_size(S, methods, ("reverse",), kernel_chars=50, shard_chars=1000).collect()}
    assert got == want


def test_counts_leave_python(spark):
    """Default counts run in Spark's process and equal the numpy kernels' in both directions, on odd texts too."""
    rng = random.Random(5)
    texts = ["", "a", "a" * 40, "\U0001f600é\U0001f600é", "abc" * 60 + "x" + "abc" * 60] + ["".join(rng.choices("ab中", k=rng.randint(1, 90))) for _ in range(150)]
    S = spark.createDataFrame([(str(k), t) for k, t in enumerate(texts)] + [("null", None)], schemas.STRINGS)
    methods = ("two_way", "lz77", "lz_next", "lz_backward", "lex")
    found = P.counts(P.balanced(S), methods)
    assert "MapInArrow" not in found._jdf.queryExecution().executedPlan().toString()
    want = P._worker_counts(S, methods, ("forward", "reverse"), "codepoint", False)
    rows = lambda df: sorted(map(tuple, df.drop("seconds", "bytes").collect()))
    assert rows(found.select(*want.columns)) == rows(want)
    assert rows(P.counts(S, methods).select(*want.columns)) == rows(want)


def test_lean_counts_equal_the_others(spark):
    """Kernels for long strings count what the default ones count, both directions from one suffix order where that is enough."""
    rng = random.Random(11)
    block = "".join(rng.choices("abcd ", k=900))
    texts = ["", "a", "a" * 400, "\U0001f600é\U0001f600é", "abc" * 60 + "x" + "abc" * 60, "".join(block[:k] for k in range(1, 900, 37)), "z" * 70000 + "y" + "z" * 70000]
    texts += ["".join(rng.choices("ab中", k=rng.randint(1, 200))) for _ in range(150)]
    S = spark.createDataFrame([(str(k), t) for k, t in enumerate(texts)] + [("null", None)], schemas.STRINGS)
    methods = ("two_way", "lz77", "lz_next", "lex")
    rows = lambda df: sorted(map(tuple, df.select("string_id", "method", "direction", "n", "phrases").collect()))
    assert rows(P.lean_counts(S, methods)) == rows(P.counts(P.balanced(S), methods))
    assert rows(P.lean_counts(S, ("lz77",), ("reverse",))) == rows(P.counts(P.balanced(S), ("lz77",), ("reverse",)))


def test_work_of_a_parse_without_its_phrases(spark, small):
    """Sums over the trace, row for row, for strings of many equal places too; queries on sources trace nothing in Python."""
    from phrasework.plans.method_queries import loop_claims, loop_counts

    rng = random.Random(12)
    texts = ["", "a", "a" * 90, "abc" * 60 + "x" + "abc" * 60, "ab" * 99 + "".join(rng.choices("ab", k=300))] + ["".join(rng.choices("ab中", k=rng.randint(1, 200))) for _ in range(60)]
    S = spark.createDataFrame([(str(k), t) for k, t in enumerate(texts)] + [("null", None)], schemas.STRINGS)
    want = M.trace_summary(P.two_way_trace(S))
    found = P.two_way_work(P.balanced(S))
    assert found.columns == want.columns
    assert sorted(map(tuple, found.collect())) == sorted(map(tuple, want.collect()))
    for query in (loop_counts, loop_claims):
        assert "MapInArrow" not in query(spark, small)._jdf.queryExecution().executedPlan().toString()


def test_winners_count_equal_copies_once(spark, small, monkeypatch):
    """The table does not make every mutated copy; each copy still has its row."""
    from phrasework.plans import method_queries
    from phrasework.plans import workloads as W

    copies = {"mutated:" + r.string_id for r in W.mutated(spark, small).select("string_id").collect()}
    monkeypatch.setattr(W, "mutated", lambda *a: pytest.fail("equal copies are counted again"))
    found = [r.string_id for r in method_queries.table_winners(spark, small).collect()]
    assert {key for key in found if key.startswith("mutated:")} == copies


def test_long_strings_take_lean_kernels(spark, monkeypatch):
    """A string above the default kernels' length is counted in one task, without tables of its positions."""
    from phrasework.plans import route

    monkeypatch.setattr(route, "_long_counts", lambda *a: pytest.fail("a distributed walk"))
    monkeypatch.setattr(route, "KERNEL_CHARS", 1000)
    S = spark.createDataFrame([("long", "the cat sat on the mat and the cat ran " * 60), ("short", "banana")], schemas.STRINGS)
    got = {(r.string_id, r.method, r.direction): (r.n, r.phrases) for r in route.counts_any_size(S, kernel_chars=1000).collect()}
    assert got == {(r.string_id, r.method, r.direction): (r.n, r.phrases) for r in P.counts(S).collect()}


def test_counts_do_not_depend_on_length(spark, monkeypatch):
    """However long a string, it is parsed whole: beyond every limit of a kernel it has the counts of the default ones."""
    from phrasework.operators import jvm
    from phrasework.plans import route

    rng = random.Random(23)
    monkeypatch.setattr(jvm, "LEAN_CHARS", 300)
    monkeypatch.setattr(route, "KERNEL_CHARS", 100)
    monkeypatch.setattr("phrasework.operators.sharded.SHARD_CHARS", 64)
    monkeypatch.setattr(route.counts_any_size, "__defaults__", tuple(100 if d == 8 << 20 else d for d in route.counts_any_size.__defaults__))
    texts = ["".join(rng.choices("ab ", k=k)) for k in (40, 200, 900)]
    S = spark.createDataFrame([(str(k), t) for k, t in enumerate(texts)] + [("null", None)], schemas.STRINGS)
    got = {(r.string_id, r.method, r.direction): (r.n, r.phrases) for r in route.counts_any_size(S).collect()}
    assert got == {(r.string_id, r.method, r.direction): (r.n, r.phrases) for r in P.counts(S).collect()}


def test_lean_counts_of_very_many_letters(spark):
    """A long string of more different characters than two bytes tell apart."""
    letters = [chr(c) for c in range(0x10000, 0x10000 + 70_000)]
    S = spark.createDataFrame([("wide", "".join(letters + letters[::-1] + letters[:50_000]))], schemas.STRINGS)
    rows = lambda df: sorted(map(tuple, df.select("string_id", "method", "direction", "n", "phrases").collect()))
    assert rows(P.lean_counts(S)) == rows(P.counts(P.balanced(S)))


def test_roundtrip_of_odd_texts(spark):
    """Whole strings decode in one pass; null and empty texts give no row, as in SQL; a broken parse decodes to nothing."""
    from phrasework.operators import jvm
    from phrasework.plans.method_queries import _two_way_decodes

    texts = ["", "a", "abababababab", "naïve \U0001f600\U0001f600", None]
    S = spark.createDataFrame([(str(k), t) for k, t in enumerate(texts)], schemas.STRINGS)
    found = _two_way_decodes(S)
    assert "MapInArrow" not in found._jdf.queryExecution().executedPlan().toString()
    assert sorted(map(tuple, found.collect())) == [("1", 1, True), ("2", 12, True), ("3", 8, True)]
    packed = P.packed_parse(S).selectExpr("string_id", "posexplode(pieces) as (k, p)").selectExpr("string_id", "k + 1 as phrase_no", "p.*")
    assert sorted(map(tuple, packed.collect()), key=repr) == sorted(map(tuple, P.two_way_parse(S).collect()), key=repr)
    cycle = "array(named_struct('start', 1L, 'length', 1L, 'ref', 2L, 'literal', cast(null as string), 'side', 'right'), named_struct('start', 2L, 'length', 1L, 'ref', 1L, 'literal', cast(null as string), 'side', 'left'))"
    assert spark.range(1).select(F.expr(cycle).alias("pieces")).select(jvm.decode(spark, F.col("pieces")).alias("text")).first().text is None


def test_documents_are_counted_without_workers(spark, small):
    """Both reports on documents have a plan without Python."""
    from phrasework.plans.registry import QUERIES

    for name in ("two_way_bound_documents", "identity_documents"):
        assert "MapInArrow" not in QUERIES[name](spark, small)._jdf.queryExecution().executedPlan().toString(), name


def test_bound_of_documents_counts_what_it_compares(spark, small, monkeypatch):
    """The bound is between two methods; the other three are not counted for it."""
    from phrasework.plans.method_queries import two_way_bound_documents

    asked = []

    def seen(S, methods, *args, original=P.counts, **options):
        asked.append(set(methods))
        return original(S, methods, *args, **options)

    monkeypatch.setattr(P, "counts", seen)
    assert two_way_bound_documents(spark, small).where("bound_holds and best_holds").count() == 200
    assert asked == [{"lz77", "two_way"}]


def test_equal_mutated_copies_are_counted_once(spark, monkeypatch):
    """Equal bases and equal copies are one text; no base is parsed at every rate of both kinds."""
    from phrasework.plans import method_queries as Q
    from phrasework.plans import workloads as W
    from phrasework.sources import generators

    odd = [("n", None), ("e", ""), ("a", "é😀x" * 50), ("a2", "é😀x" * 50), ("b c", "abcab" * 300)]
    bases = strings(spark, *odd)
    monkeypatch.setattr(W, "bases", lambda spark, folder: bases)
    want = {(f"{r.string_id}-{r.kind}-{r.rate:.5f}", r.text) for r in generators.mutated_copies(bases, W.COPIES, list(W.RATES)).collect()}
    once, keys = W.mutated_once(spark, "")
    assert once.count() == once.select("text").distinct().count() < len(want) // 2
    assert set(map(tuple, W.of_mutated(once, keys).collect())) == want
    parsed = []

    def seen(S, *args, original=P.counts, **options):
        parsed.append(S.count())
        return original(S, *args, **options)

    monkeypatch.setattr(P, "counts", seen)
    S = strings(spark, *want)
    rows = lambda df: sorted(map(repr, map(tuple, df.collect())))
    assert rows(Q.w_mutated_counts(spark, "")) == rows(M.table(P._worker_counts(S, Q.METHODS, ("forward", "reverse"), "codepoint", False)))
    assert rows(Q.w_mutated_bound(spark, "")) == sorted(repr((key, len(text), True, True)) for key, text in want)
    assert parsed == [once.count()] * 2


def test_table_claims_count_once(spark, small):
    """A table that is told its methods runs no job of its own; the sources were counted twice for it."""
    from phrasework.plans import method_queries as Q

    jobs = []

    def seen(counted, *args, original=M.table, **options):
        spark.sparkContext.setJobGroup("table", "")
        out = original(counted, *args, **options)
        jobs.append(len(spark.sparkContext.statusTracker().getJobIdsForGroup("table")))
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
        return out

    with pytest.MonkeyPatch.context() as patch:
        patch.setattr(M, "table", seen)
        assert Q.table_claims(spark, small).where("within_lz77").count() == 20
    assert jobs == [0]


def test_table_phrases_name_their_methods(spark, monkeypatch):
    """The table over all groups is told its methods, so that nothing is counted for its columns alone."""
    from phrasework.plans import method_queries as Q

    told = []
    monkeypatch.setattr(Q, "_groups", lambda spark, folder: strings(spark, ("source:a", "abcab" * 9), ("family:b", "")))
    monkeypatch.setattr(M, "table", lambda counted, original=M.table, **options: told.append(options) or original(counted, **options))
    rows = {r.string_id: r for r in Q.table_phrases(spark, "").collect()}
    assert told == [{"methods": ("lz77", "lex", "two_way")}]
    assert rows["family:b"].two_way_ratio is None and rows["source:a"].two_way <= rows["source:a"].lz77


def test_costs_of_strings_of_any_length(spark, small):
    """Measured costs come with the counts of the numpy kernels, without Python, and the table counts once."""
    from phrasework.plans import method_queries as Q

    rng = random.Random(29)
    texts = ["", "a", "a" * 400, "\U0001f600é\U0001f600é", "abc" * 60 + "x" + "abc" * 60] + ["".join(rng.choices("ab中", k=rng.randint(1, 200))) for _ in range(60)]
    S = spark.createDataFrame([(str(k), t) for k, t in enumerate(texts)] + [("null", None)], schemas.STRINGS)
    methods = ("two_way", "lz77", "lz_next", "lex")
    found = P.counts(P.balanced(S), methods, memory=True)
    want = P._worker_counts(S, methods, ("forward", "reverse"), "codepoint", False)
    rows = lambda df: sorted(map(tuple, df.drop("seconds", "bytes").collect()))
    assert found.columns == want.columns and rows(found) == rows(want)
    for r in found.where("n > 100").collect():  # suffix order, LCPs, ranks; links for the two-way parse alone
        assert (14 if r.method == "two_way" else 10) * r.n <= r.bytes <= 16 * r.n + 4096 and r.seconds > 0
    jobs = []

    def seen(counted, *args, original=M.cost_table, **options):
        spark.sparkContext.setJobGroup("costs", "")
        out = original(counted, *args, **options)
        jobs.append(len(spark.sparkContext.statusTracker().getJobIdsForGroup("costs")))
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
        return out

    with pytest.MonkeyPatch.context() as patch:
        patch.setattr(M, "cost_table", seen)
        for query in (Q.table_cost, Q.cost_claims):
            assert "MapInArrow" not in query(spark, small)._jdf.queryExecution().executedPlan().toString()
        assert tuple(Q.cost_claims(spark, small).first()) == (4, True, True, True)
    assert jobs == [0, 0, 0]


def test_lean_counts_of_long_repeats(spark):
    """Common prefixes too long for two bytes are not compared again from there for each phrase."""
    rng = random.Random(31)
    block = "".join(rng.choices("abcd", k=150_000))
    S = spark.createDataFrame([("same", block * 4), ("near", block + "x" + block[:90_000] + "y" + block)], schemas.STRINGS)
    methods = ("lz77", "lz_next", "lex", "two_way")
    rows = lambda df: sorted(map(tuple, df.select("string_id", "method", "direction", "n", "phrases").collect()))
    assert rows(P.lean_counts(S, methods)) == rows(P.counts(P.balanced(S), methods))
    seconds = [r.seconds for r in P.counts(S, methods, ("forward",), memory=True).collect()]
    assert max(seconds) < 2, seconds
