import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from phrasework.kernels import extras as E
from phrasework.kernels.greedy import backward_parse, decode, left_parse, lex_parse, literal_parse, map_back, references, resolve, right_parse
from phrasework.kernels.sources import Overlay, Sources
from phrasework.kernels.suffix import SuffixIndex, codes_of, factor, nearest, rightmost_next
from phrasework.kernels.two_way import TIES, Options, TwoWay, ordered, two_way, walk

words = st.text(alphabet="abc", max_size=24)


def shown(phrases):
    return [(s + 1, n, r + 1) for s, n, r in phrases]


def literals(codes, phrases):
    return {s: int(codes[s]) for s, _, r in phrases if r < 0}


def common(text, i, j):
    k = 0
    while max(i, j) + k < len(text) and text[i + k] == text[j + k]:
        k += 1
    return k


def test_arrays_of_the_worked_example():
    index = SuffixIndex(codes_of("abababaabb"))
    assert (index.sa + 1).tolist() == [7, 5, 3, 1, 8, 10, 6, 4, 2, 9]
    assert (index.rank + 1).tolist() == [4, 9, 3, 8, 2, 7, 1, 5, 10, 6]
    assert index.lcp.tolist() == [0, 1, 3, 5, 2, 0, 1, 2, 4, 1]
    assert factor(index)[0].tolist() == [0, 0, 5, 4, 3, 2, 1, 2, 1, 1]


@given(words)
@settings(max_examples=150, deadline=None)
def test_suffix_order_and_factors(text):
    index = SuffixIndex(codes_of(text))
    n = len(text)
    assert index.sa.tolist() == sorted(range(n), key=lambda i: text[i:])
    for i in range(n):
        assert factor(index)[0][i] == max([common(text, i, j) for j in range(i)], default=0)
        assert factor(index, later=True)[0][i] == max([common(text, i, j) for j in range(i + 1, n)], default=0)
    if n:
        lengths = np.maximum(factor(index, later=True)[0], 1)
        want = [max([j for j in range(n) if common(text, i, j) >= lengths[i] or j == i]) for i in range(n)]
        assert rightmost_next(index, lengths).tolist() == want


@given(words, st.sampled_from(TIES))
@settings(max_examples=100, deadline=None)
def test_candidate_stream_is_complete_and_sorted(text, tie):
    index = SuffixIndex(codes_of(text))
    for i in range(len(text)):
        got = [(lce, j) for lce, group in ordered(walk(index.sa.tolist(), index.rank.tolist(), index.lcp.tolist(), i), i, tie) for j in group]
        assert sorted(got) == sorted((common(text, i, j), j) for j in range(len(text)) if j != i and common(text, i, j))
        assert [x for x, _ in got] == sorted((x for x, _ in got), reverse=True)


def test_nearest_by_jumps_and_by_stack():
    rng = np.random.default_rng(1)
    for order in (rng.permutation(500), np.arange(300), np.arange(300)[::-1], np.append(np.arange(1, 300), 0), np.zeros(0, np.int64)):
        for larger in (False, True):
            value = (-order if larger else order).tolist()
            want = [next((int(order[j]) for j in range(k - 1, -1, -1) if value[j] < value[k]), -1) for k in range(len(order))]
            assert [int(nearest(order, larger)[p]) for p in order] == want
    assert len(left_parse(codes_of("ab" * 3000))) == 3 and len(two_way(codes_of("a" * 3000))) == 2


def test_goldens():
    parse = lambda s, t: shown(two_way(codes_of(s), Options(tie=t)))
    assert parse("abababaababa", "leftmost") == [(1, 5, 3), (6, 2, 9), (8, 3, 10), (11, 1, 0), (12, 1, 0)]
    assert parse("abababaababa", "rightmost") == [(1, 5, 8), (6, 2, 11), (8, 3, 3), (11, 1, 0), (12, 1, 0)]
    assert len(parse("bacaaccba", "leftmost")) == 8 and len(parse("bacaaccba", "rightmost")) == 7
    assert parse("aaabaa", "leftmost") == [(1, 2, 2), (3, 1, 5), (4, 1, 0), (5, 1, 6), (6, 1, 0)]
    state = TwoWay(codes_of("abababaababa"))
    state.commit(5, 2)
    assert state.profile() == [0, 0, 0, 0, 0, 0, 0, 0, 2, 0, 2, 0]


def test_one_direction_excess_stays():
    codes = codes_of("aaabaa")
    assert len(two_way(codes)) == 5 > len(left_parse(codes)) == 4


OPTIONS = [Options(), Options(floor=False), Options(search="exhaustive"), Options(tie="leftmost"), Options(tie="walk_lower", overlay=False), Options(tie="walk_upper"), Options(tie="nearest_right"), Options(tie="nearest_left", link="by_size"), Options(validity="graph", floor=False), Options(sides="left"), Options(sides="right"), Options(max_candidates=1), Options(tie="leftmost", max_candidates=2)]


@given(words)
@settings(max_examples=150, deadline=None)
def test_every_option_decodes_and_keeps_its_bound(text):
    codes = codes_of(text)
    backwards = codes[::-1].copy()
    for o in OPTIONS:
        phrases = two_way(codes, o)
        again = decode(phrases, literals(codes, phrases), len(codes))
        assert again is not None and again.tolist() == codes.tolist()
        assert sum(n for _, n, _ in phrases) == len(codes)
        if o.sides != "left":
            assert len(phrases) <= len(left_parse(backwards)), o
    assert two_way(codes, OPTIONS[0]) == two_way(codes, OPTIONS[1])
    assert len(two_way(codes, OPTIONS[0])) == len(two_way(codes, OPTIONS[2]))
    assert len(two_way(codes, Options(sides="left"))) == len(left_parse(codes))
    assert len(two_way(codes, Options(sides="right"))) == len(right_parse(codes))


@given(words)
@settings(max_examples=100, deadline=None)
def test_prefixes_are_valid_and_classes_are_sources(text):
    codes = codes_of(text)
    state = TwoWay(codes)
    while state.at < state.n:
        graph = TwoWay(codes, Options(validity="graph", floor=False))
        graph.phrases, graph.at = list(state.phrases), state.at
        assert state.profile() == graph.profile()
        state.commit(*state.longest())
        source, _ = resolve(references(state.phrases, state.n))
        assert (source >= 0).all()
        assert [state.sources.source(i) for i in range(state.n)] == source.tolist()


@given(words)
@settings(max_examples=150, deadline=None)
def test_identities(text):
    codes = codes_of(text)
    backwards = codes[::-1].copy()
    assert len(backward_parse(codes)) == len(left_parse(codes))
    assert len(right_parse(codes)) == len(backward_parse(backwards))
    assert len(two_way(codes)) <= len(right_parse(codes))
    for phrases in (left_parse(codes), right_parse(codes), lex_parse(codes), backward_parse(codes), literal_parse(codes), E.largest_first_parse(codes), E.bwt_run_parse(codes)):
        again = decode(phrases, literals(codes, phrases), len(codes))
        assert again is not None and again.tolist() == codes.tolist()
    assert len(lex_parse(codes)) <= len(E.largest_first_parse(codes))
    assert len(E.bwt_run_parse(codes)) <= 2 * E.bwt_runs(codes) + 1


def test_smallest_parse_and_attractor():
    random.seed(2)
    for _ in range(60):
        codes = codes_of("".join(random.choice("ab") for _ in range(random.randrange(1, 8))))
        best = E.smallest_parse(codes)
        assert decode(best, literals(codes, best), len(codes)).tolist() == codes.tolist()
        for phrases in (left_parse(codes), lex_parse(codes), two_way(codes)):
            assert len(best) <= len(phrases)
        marks = E.smallest_attractor(codes)
        assert E.is_attractor(codes, marks) and len(marks) <= len(best)
        grown = E.attractor_parse(codes, marks)
        assert decode(grown, literals(codes, grown), len(codes)).tolist() == codes.tolist()
    with pytest.raises(ValueError):
        E.smallest_parse(codes_of("a" * 11))


def test_families():
    def fib(k):
        a, b = "b", "a"
        for _ in range(k - 1):
            a, b = b, b + a
        return codes_of(b)

    def tm(k):
        s = "a"
        for _ in range(k - 1):
            s += s.translate(str.maketrans("ab", "ba"))
        return codes_of(s)

    for k in range(6, 14):
        assert [len(left_parse(fib(k))), len(left_parse(fib(k)[::-1])), len(two_way(fib(k)))] == [k, k // 2 + 2, 5]
        assert len(lex_parse(fib(k))) == (4 if k % 2 else k // 2 + 2)
    for k in range(5, 11):
        assert [len(left_parse(tm(k))), len(lex_parse(tm(k))), len(two_way(tm(k)))] == [2 * (k - 1), 3 * k // 2, k + 2]
        assert len(two_way(tm(k), Options(tie="leftmost"))) == 2 * (k - 1)


def test_disjoint_sets():
    for link in ("directed", "by_size"):
        s = Sources(6, link)
        s.merge(0, 3)
        s.merge(1, 0)
        s.merge(3, 5)
        assert [s.source(i) for i in range(6)] == [5, 5, 2, 5, 4, 5]
        assert s.add() == 6 and s.source(6) == 6
        over = Overlay(s)
        over.merge(5, 4)
        assert over.source(0) == 4 and s.source(0) == 5
    with pytest.raises(ValueError):
        Sources(1, "other")
    with pytest.raises(ValueError):
        Options(tie="other")


def test_edges_of_text():
    for text in ("", "x", "aaaa", "abc", "\U0001f600a\U0001f600a", "éé", "\n\n"):
        codes = codes_of(text)
        phrases = two_way(codes)
        assert decode(phrases, literals(codes, phrases), len(codes)).tolist() == codes.tolist()
    assert codes_of("é", "byte").tolist() == [0xC3, 0xA9]
    assert map_back([(0, 1, -1), (1, 2, 0)], 3) == [(0, 2, 1), (2, 1, -1)]
    assert decode([(0, 2, 1), (2, 1, 0)], {}, 3) is None


def test_places_tested_together_give_the_same_parse(monkeypatch):
    from phrasework.kernels import sources, two_way as kernel

    rng = random.Random(8)
    for _ in range(150):
        text = "".join(rng.choice("ab" if rng.random() < 0.5 else "abcd") for _ in range(rng.randrange(1, 160)))
        codes = codes_of(text * rng.randrange(1, 4))
        plain = two_way(codes)
        assert plain == TwoWay(codes, Options(floor=False)).run().phrases
        for many, run, cells, cost in ((1, 1, 1 << 22, 64), (2, 4, 3, 1), (3, 64, 1 << 22, 1 << 20)):
            monkeypatch.setattr(kernel, "MANY", many)
            monkeypatch.setattr(sources, "LONG_RUN", run)
            monkeypatch.setattr(sources, "MOST_CELLS", cells)
            monkeypatch.setattr(sources, "STEP_COST", cost)
            assert two_way(codes) == plain
        monkeypatch.undo()
