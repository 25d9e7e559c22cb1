import random
import re

import numpy as np
import pyarrow as pa
import pytest
import sentencepiece
import xxhash

from phrasework.llm import hamming_topk as H
from phrasework.llm import language_id as L
from phrasework.llm import media as A
from phrasework.llm import packing as K
from phrasework.llm import piece_codec as C
from phrasework.llm import simhash as S
from phrasework.llm import substring_dedup as D
from phrasework.llm import toxicity as X
from phrasework.llm.textbytes import U64, Words, slices, span_hashes, utf8, xxh64

WORD = re.compile(r"[^\x20\x09-\x0D]+")
LOWER = {i: i + 32 for i in range(65, 91)}


def odd_texts(n=300, seed=3):
    rng = random.Random(seed)
    return ["".join(rng.choice("ab  \n\tC\xe9\xa0😀") for _ in range(rng.randrange(0, 120))) for _ in range(n)] + ["", None, " ", "a", " a", "x" * 300 + " " + "y" * 77 + " z"]


def test_words_and_hashes_match_plain_python():
    texts = odd_texts()
    words = Words(*utf8(pa.array(texts)), lower=True)
    plain = [WORD.findall((t or "").translate(LOWER)) for t in texts]
    assert words.counts.tolist() == list(map(len, plain))
    assert [words.row_bytes(i) for i in range(len(texts))] == [" ".join(w).encode() for w in plain]
    groups = words.padded()
    assert xxh64(groups, words.starts, words.ends).tolist() == [xxhash.xxh64_intdigest(x, 42) for w in plain for x in w]
    i = np.arange(len(words) - 2)
    spans = [words.text[a:b].tobytes() for a, b in zip(words.starts[i], words.ends[i + 2])]
    assert xxh64(groups, words.starts[i], words.ends[i + 2]).tolist() == [xxhash.xxh64_intdigest(x, 42) for x in spans]
    own = dict(zip(spans, span_hashes(groups, words.starts[i], words.ends[i + 2], 5).tolist()))
    assert len(set(own.values())) == len(own)


def test_slices_keep_all_rows():
    batch = pa.RecordBatch.from_pydict({"text": ["a" * n for n in (5, 0, 100, 3, 3, 3)]})
    assert [t for s in slices(batch, limit=8) for t in s.column("text").to_pylist()] == batch.column("text").to_pylist()
    assert list(slices(batch.slice(0, 0))) == []


def test_fingerprint_bits():
    texts = odd_texts(60) + ["w " * 700]
    got = S.text_fingerprints(*utf8(pa.array(texts)))
    for t, fp in zip(texts, got.tolist()):
        w = WORD.findall((t or "").translate(LOWER))
        shingles = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] or ([" ".join(w)] if w else [])
        h = [xxhash.xxh64_intdigest(x, 42) for x in shingles]
        assert fp == sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


@pytest.mark.parametrize("radius", [0, 2, 5])
def test_vantage_tree_and_shards_find_all_pairs(radius):
    rng = np.random.default_rng(1)
    centres = rng.integers(0, 1 << 63, 40, dtype=np.uint64)
    points = np.unique(np.concatenate([centres, *(centres ^ (U64(1) << rng.integers(0, 64, 40, dtype=np.uint64)) for _ in range(6)), rng.integers(0, 1 << 63, 600, dtype=np.uint64)]))
    want = {(i, j) for i in range(len(points)) for j in np.flatnonzero(np.bitwise_count(points ^ points[i]) <= radius).tolist()}
    got = {(int(q), int(p)) for a, b in S.close_pairs(points, radius, leaf=8) for q, p in zip(a, b)}
    assert got | {(p, q) for q, p in got} | {(i, i) for i in range(len(points))} == want
    dense = np.unique(centres[0] ^ (U64(1) << rng.integers(0, 64, 200, dtype=np.uint64)) ^ (U64(1) << rng.integers(0, 64, 200, dtype=np.uint64)))
    close = {frozenset((int(q), int(p))) for a, b in S.close_pairs(dense, radius, leaf=8) for q, p in zip(a, b)}
    assert close == {frozenset((i, j)) for i in range(len(dense)) for j in np.flatnonzero(np.bitwise_count(dense ^ dense[i]) <= radius).tolist() if i != j}
    nodes = S.fit_shards(points[::3], 3, radius)
    seen, links = np.zeros(len(points), int), set()
    for _, index in S.route(points, nodes, 3, radius):
        seen[index] += 1
        u, v = S.shard_forest(points[index], radius)
        links |= set(zip(u.tolist(), v.tolist()))
    assert (seen >= 1).all()
    forest = S.Forest(len(points))
    where = {int(p): i for i, p in enumerate(points)}
    if links:
        forest.merge(np.array([where[a] for a, _ in links]), np.array([where[b] for _, b in links]))
    full = S.Forest(len(points))
    full.merge(*map(np.array, zip(*want)))
    assert forest.roots().tolist() == full.roots().tolist()


def test_runs_cover_each_window_once_and_match_by_content():
    rng = random.Random(5)
    texts = [" ".join(rng.choice("ab cd ef".split()) for _ in range(rng.randrange(0, 60))) for _ in range(40)]
    words = Words(*utf8(pa.array(texts)))
    start, count, m, r = D.runs_of(words, D.Spans(words), 10, 3)
    windows = np.concatenate([np.arange(s, s + n) for s, n in zip(start, count)])
    want = [words.rows[i] + k for i in range(len(texts)) for k in range(max(0, words.counts[i] - 9))]
    assert windows.tolist() == want
    text = [words.text[a:b].tobytes() for a, b in zip(words.starts, words.ends)]
    anchors: dict = {}
    for s, n, a in zip(start, count, m.tolist()):
        for k in range(s, s + n):
            anchors.setdefault(tuple(text[k : k + 10]), set()).add(a)
    assert all(len(x) == 1 for x in anchors.values())  # equal windows lie in runs of one anchor
    by_content: dict = {}
    for s, n, c in zip(start, count, r.tolist()):
        by_content.setdefault(tuple(text[s : s + n + 9]), set()).add(c)
    assert all(len(x) == 1 for x in by_content.values()) and len(set().union(*by_content.values())) == len(by_content)


def test_g711_tables():
    assert A.MULAW[[0xFF, 0x7F, 0x00, 0x80]].tolist() == [0, 0, -32124, 32124]
    assert A.ALAW[[0xD5, 0x55, 0xAA, 0x2A]].tolist() == [8, -8, 32256, -32256]
    for table in (A.MULAW, A.ALAW):
        assert (table[A.compress(table, table)] == table).all()


def test_adpcm_blocks_side_by_side_equal_one_by_one():
    rng = np.random.default_rng(2)
    blocks = rng.integers(0, 256, (50, 36), dtype=np.uint8)
    together = A.decode_adpcm(blocks)
    for block, got in zip(blocks, together):
        value = int(block[0]) | int(block[1]) << 8
        value -= (value >> 15) << 16
        index, out = min(int(block[2]), 88), [value]
        for byte in block[4:].tolist():
            for code in (byte & 15, byte >> 4):
                step = int(A.STEPS[index])
                change = (step >> 3) + (step if code & 4 else 0) + (step >> 1 if code & 2 else 0) + (step >> 2 if code & 1 else 0)
                value = max(-32768, min(32767, value - change if code & 8 else value + change))
                index = max(0, min(88, index + int(A.INDEX_CHANGE[code])))
                out.append(value)
        assert got.tolist() == out
    tone = (8000 * np.sin(np.arange(2000) / 20)).astype(np.int16)
    again = A.decode_adpcm(A.encode_adpcm(tone)).reshape(-1)[: len(tone)]
    assert np.abs(again[200:].astype(int) - tone[200:]).mean() < 200


def test_wav_round_trips():
    for codec in A.CODECS:
        payload = A.text_payload("héllo".encode() * 40)
        media = A.pack_payload(codec, payload)
        assert A.unpack_payload(media) == payload and A.read_wav(media)[:2] == (codec, 8000)
        assert len(A.decode(media))
    with pytest.raises(ValueError):
        A.read_wav(b"nothing")
    assert A.text_payload(b"") == b"\0" * 64 and len(A.text_payload(b"x" * 64)) == 64
    assert A.resample_double(np.array([0, 100], np.int16)).tolist()[::2] == [0, 100] and len(A.resample_double(np.zeros(0, np.int16))) == 0


def test_first_fit_decreasing_equals_plain_search():
    rng = random.Random(4)
    for _ in range(30):
        sizes = np.array([rng.randrange(1, 100) for _ in range(rng.randrange(0, 60))])
        bins, offsets = K.first_fit_decreasing(sizes, 100)
        free, want = [], {}
        for i in sorted(range(len(sizes)), key=lambda i: -sizes[i]):
            b = next((k for k, f in enumerate(free) if f >= sizes[i]), len(free))
            if b == len(free):
                free.append(100)
            want[i] = (b, 100 - free[b])
            free[b] -= int(sizes[i])
        assert [(int(b), int(o)) for b, o in zip(bins, offsets)] == [want[i] for i in range(len(sizes))]


def test_both_tokenizer_readers_agree():
    paths = K.default_paths()
    exact = K._exact(paths[0])
    for text in ["", " a  b\n\nc", "naïve 😀 12345 don't", "x" * 3000, "<|endoftext|> y", "<|other|>", "tab\tnew\r\n", "日本語 text"]:
        assert K.encode_bytes(text.encode(), *paths).tolist() == exact.encode(text, add_special_tokens=False).ids


def piece_texts():
    rng = random.Random(6)
    return ["".join(rng.choice(list("ab th eion\n\t 12.,é日本梦▁x😀 ")) for _ in range(rng.randrange(0, 80))) for _ in range(400)] + ["", " ", "  a", "a ", "\n", "e" * 300, "the" * 100]


def test_merge_model_equals_sentencepiece():
    raw = C.model_bytes()
    own, reference = C.PieceCodec(raw), sentencepiece.SentencePieceProcessor(model_proto=raw)
    texts = piece_texts()
    got = own.encode(texts)
    assert [x.tolist() for x in got] == reference.encode(texts)
    assert [own.decode(x) for x in got] == [t.replace("▁", " ") for t in texts]


def test_score_model_equals_brute_force():
    raw = C.model_bytes()
    assert C.is_merge_model(raw)
    at = raw.rfind(b"\x18\x02 ")
    own = C.PieceCodec(raw[: at + 1] + b"\x01" + raw[at + 2 :])
    assert own.merges is None
    for word in ("▁there", "▁nation", "sion", "▁inthe"):
        best = [(0.0, ())] + [None] * len(word)
        for end in range(1, len(word) + 1):
            best[end] = max((best[b][0] + own.scores[word[b:end]], (*best[b][1], own.ids[word[b:end]])) for b in range(end) if word[b:end] in own.ids)
        got = np.frombuffer(own.encode_words([word])[word], "<i4")
        assert sum(own.scores[own.pieces[i]] for i in got) == pytest.approx(best[-1][0])


def test_language_forward_sum_equals_all_segmentations():
    lattice = L.Lattice(["▁", "▁a", "a", "b", "ab", "aba", "▁ab"])
    chances = np.random.default_rng(1).random((lattice.unknown + 1, 2))
    names = {p: i for i, p in enumerate(["▁", "▁a", "a", "b", "ab", "aba", "▁ab"])}

    def total(text, k):
        if not text:
            return 1.0
        out = 0.0
        for n in range(1, len(text) + 1):
            piece = text[:n]
            if piece in names:
                out += chances[names[piece], k] * total(text[n:], k)
            elif n == 1:
                out += chances[lattice.unknown, k] * total(text[n:], k)
        return out

    words = ["ab", "abab", "xabax", "bbbaab", "abc" * 6]
    got = L.word_scores(lattice, chances, words)
    for w, row in zip(words, got):
        assert row == pytest.approx([np.log(total("▁" + w, k)) for k in (0, 1)])


def test_chain_marginals_equal_enumeration():
    rng = np.random.default_rng(3)
    field = X.Field(np.zeros(1 << X.LOG2_WEIGHTS, np.float32), rng.normal(size=(2, 2)), rng.normal(size=2), (0.0, 1.0, 0.0))
    rows = [0, 3, 3, 8, 9]
    emission = rng.normal(size=9)
    opens = np.array([0, 3, 8])
    got = field.marginals(emission, opens)[0]
    want = []
    for a, b in zip(rows[:-1], rows[1:]):
        n = b - a
        weights = np.zeros(n)
        norm = 0.0
        for code in range(1 << n) if n else []:
            y = [(code >> i) & 1 for i in range(n)]
            score = field.first[y[0]] + sum(field.moves[y[i - 1], y[i]] for i in range(1, n)) + sum(emission[a + i] * y[i] for i in range(n))
            norm += np.exp(score)
            weights += np.exp(score) * np.array(y)
        want.extend(weights / norm if n else [])
    assert got == pytest.approx(want)
    long = X.chain_messages(rng.random((2, 2, 1000)) + 0.1)
    assert long.shape == (2, 1000) and np.allclose(long.sum(axis=0), 1)


def test_multi_index_search_equals_brute_force():
    rng = np.random.default_rng(7)
    base = rng.integers(0, 1 << 63, 30, dtype=np.uint64)
    codes = np.unique(np.concatenate([rng.integers(0, 1 << 63, 500, dtype=np.uint64), *(base ^ (U64(1) << rng.integers(0, 64, 30, dtype=np.uint64)) for _ in range(4))]))
    weight = rng.integers(1, 4, len(codes))
    queries = np.concatenate([codes[:10], base[:10], rng.integers(0, 1 << 63, 5, dtype=np.uint64)])
    for k in (1, 5, 700, 5000):
        q, c, d = H.CodeIndex(codes, weight).search(queries, k)
        assert len(set(zip(q.tolist(), c.tolist()))) == len(q)
        for i, query in enumerate(queries):
            all_d = np.bitwise_count(codes ^ query).astype(int)
            order = np.argsort(all_d, kind="stable")
            reach = np.searchsorted(np.cumsum(weight[order]), k)
            kth = all_d[order][min(reach, len(codes) - 1)]
            assert sorted(d[q == i].tolist()) == sorted(all_d[all_d <= kth].tolist())


