import pytest

import __spark_entry__ as entry
from phrasework.plans.registry import ORACLES, QUERIES

#: Queries whose whole run is long even on the smallest tables; the driver compares them too.
SLOW = {"two_way_roundtrip_documents", "op_recursive_walk"}


@pytest.mark.parametrize("name", sorted(set(ORACLES) - SLOW))
def test_query_equals_sql(name, same):
    same(QUERIES[name], ORACLES[name])


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(ORACLES)))
def test_query_has_rows(name, spark, small):
    assert QUERIES[name](spark, small).count() > 0


def test_entry(spark):
    rows = entry.entry(spark).collect()
    assert rows and all(r.bound_holds for r in rows)
    assert set(QUERIES) <= set(entry.queries()) and set(ORACLES) <= set(entry.oracle_sql())


def test_reported_behaviour(spark, small):
    rows = {r.string_id: r for r in QUERIES["table_phrases"](spark, small).collect()}
    text = [r for k, r in rows.items() if k.startswith("source:")]
    assert all(0.85 < r.two_way_ratio < 0.99 for r in text)
    assert rows["family:fib20"].two_way < rows["family:fib20"].lz77
    assert rows["family:rr14"].lex < rows["family:rr14"].two_way < rows["family:rr14"].lz77
    for kind in (1, 2):  # the order that is reported for mutated copies, at each rate over all bases
        for rate in ("0.00001", "0.00010", "0.00100", "0.01000"):
            some = [r for k, r in rows.items() if k.startswith("mutated:") and k.endswith(f"-{kind}-{rate}")]
            assert some and sum(r.two_way for r in some) < min(sum(r.lz77 for r in some), sum(r.lex for r in some))


def test_approximate_counts(spark, small):
    exact = {r.source: r.texts for r in QUERIES["op_agg_distinct"](spark, small).collect()}
    for r in QUERIES["op_agg_approx"](spark, small).collect():
        assert abs(r.texts - exact[r.source]) <= max(1, 0.1 * exact[r.source])


@pytest.mark.parametrize("name", ["tie_rules_benchmark", "ablations_benchmark"])
def test_whole_benchmark_texts_are_parsed(name, spark, small, monkeypatch):
    from phrasework.operators import parse

    whole = max(len(r.text) for r in spark.read.parquet(f"{small}/benchmark.parquet").collect())
    longest = []
    for f in ("two_way_parse", "two_way_count"):

        def seen(S, *args, original=getattr(parse, f), **options):
            longest.append(max(len(r.text) for r in S.collect()))
            return original(S, *args, **options)

        monkeypatch.setattr(parse, f, seen)
    QUERIES[name](spark, small)
    assert longest and set(longest) == {whole}


@pytest.mark.parametrize("name", ["smallest_part_names", "two_way_part_names", "table_part_names", "winners_part_names", "gap_part_names"])
def test_equal_part_names_are_parsed_once(name, spark, small, tmp_path, monkeypatch):
    from phrasework.operators import parse

    rows = spark.read.parquet(f"{small}/part.parquet").limit(3).select("p_partkey", "p_name").collect()
    many = [(r.p_partkey + 1000 * k, r.p_name) for r in rows for k in range(50)]
    spark.createDataFrame(many, "p_partkey bigint, p_name string").write.parquet(f"{tmp_path}/part.parquet")
    parsed = []
    for f in ("counts", "two_way_parse"):

        def seen(S, *args, original=getattr(parse, f), **options):
            parsed.append(S.count())
            return original(S, *args, **options)

        monkeypatch.setattr(parse, f, seen)
    got = QUERIES[name](spark, str(tmp_path)).collect()
    short = [(key, text) for key, text in many if len(text) <= 10 or name.startswith(("two", "win", "tab"))]
    assert parsed and all(n <= len({text for _, text in short}) for n in parsed)
    assert {r.string_id for r in got} == {str(key) for key, _ in short}


@pytest.mark.parametrize("name", ["ex_arrays", "ex_extension_profile", "ex_one_direction_excess", "ex_order_at_first", "ex_partial_source", "ex_partial_valid", "ex_similarity", "ex_source_classes", "ex_third_counts", "ex_tie_rules"])
def test_worked_examples_read_a_given_table(name, spark, small):
    table, key = ("customer", "c_custkey") if name == "ex_similarity" else ("orders", "o_custkey")
    keys = {str(r[0]) for r in spark.read.parquet(f"{small}/{table}.parquet").select(key).collect()}
    got = {r.string_id for r in QUERIES[name](spark, small).collect()}
    assert len(got) > len(keys) // 2 and got <= keys
