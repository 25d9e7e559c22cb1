import collections
import hashlib
import re
import zlib

import numpy as np
import pytest
import sentencepiece
import xxhash
from pyspark.sql import functions as F

import __spark_entry__ as entry
from phrasework.llm import hamming_topk, language_id, license_scan, media, near_groups, packing, piece_codec, queries, simhash, substring_dedup, toxicity, url_filter

WORD = re.compile(r"[^\x20\x09-\x0D]+")
LOWER = {i: i + 32 for i in range(65, 91)}
SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, id string, k1 string, fp string, __k1 string, host string, key string"


@pytest.fixture(scope="module")
def documents(spark, small):
    return spark.read.parquet(f"{small}/documents.parquet").orderBy("doc_id").toPandas()


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls in each column, empty and long texts, repeated rows, columns of clashing names."""
    long = " ".join(f"w{i % 97}" for i in range(20000))
    span = " ".join(f"s{i}" for i in range(40))
    rows = [(1, "alpha beta " + span), (1, "alpha beta " + span), (2, span + " omega"), (3, None), (4, ""), (None, "no id here"), (None, None), (5, long), (6, "  \n\t "), (7, "x"), (8, "x")]
    return spark.createDataFrame([(a, t, None, None, None, "i", "k", "f", "d", "h", "y") for a, t in rows], SCHEMA)


def plain_words(text):
    return WORD.findall(text or "")


def plain_spans(rows, width):
    """(n_words, n_removed, kept) of each text by comparing all windows."""
    words = [plain_words(t) for t in rows]
    seen = collections.Counter(tuple(w[i : i + width]) for w in words for i in range(len(w) - width + 1))
    for w in words:
        gone = [False] * len(w)
        for i in range(len(w) - width + 1):
            if seen[tuple(w[i : i + width])] > 1:
                gone[i : i + width] = [True] * width
        yield len(w), sum(gone), " ".join(x for x, g in zip(w, gone) if not g)


def test_every_operator_takes_odd_rows_and_empty_tables(spark, odd):
    field = toxicity.fit(["you scum", "fine day"] * 8, [1, 0] * 8)
    model = language_id.fit({"en": ["the cat and the dog"], "de": ["der hund und die katze"]})
    known = license_scan.known_frame(spark)
    runs = {
        "codec": lambda d: piece_codec.codec_digests(d),
        "spans": lambda d: substring_dedup.removed_spans(d),
        "cut": lambda d: substring_dedup.remove_spans(d),
        "toxic": lambda d: toxicity.score_texts(d, field),
        "clean": lambda d: toxicity.keep_clean(d, field),
        "language": lambda d: language_id.predict(d, model),
        "identified": lambda d: language_id.keep_identified(d, model),
        "near": lambda d: simhash.near_duplicates(d),
        "groups": lambda d: near_groups.keep_one_of_each(d),
        "license": lambda d: license_scan.scan_licenses(d, known),
        "packing": lambda d: packing.pack_documents(d),
        "media": lambda d: media.clip_digests(d),
        "clips": lambda d: media.text_to_clips(d).drop("payload"),
    }
    whole = {"codec", "spans", "cut", "toxic", "language", "near", "license", "media", "clips"}
    for name, run in runs.items():
        rows = run(odd).collect()
        assert len(rows) == odd.count() or name not in whole, name
        assert run(odd.limit(0)).count() == 0, name
    for name in ("cut", "clean", "identified", "groups"):
        assert runs[name](odd).columns == odd.columns


def test_defined_results_of_odd_rows(spark, odd):
    spans = {r.id: r for r in substring_dedup.removed_spans(odd).collect()}
    assert spans[1].n_removed == 42 and spans[2].n_removed == 40 and spans[4].n_words == 0
    assert spans[2].kept_sha256 == hashlib.sha256(b"omega").hexdigest()
    near = simhash.near_duplicates(odd).collect()
    assert {r.component_id for r in near if r.fp == 0} == {3}
    assert sum(r.component_id == 7 for r in near) == 2
    kept = near_groups.keep_one_of_each(odd).collect()
    assert sorted(r.doc_id for r in kept if r.doc_id is not None) == [1, 2, 3, 5, 7] or sorted(r.doc_id for r in kept if r.doc_id is not None) == [1, 3, 5, 7]
    model = language_id.fit({"en": ["the cat and the dog"], "de": ["der hund und die katze"]})
    und = {r.id: (r.lang_pred, r.score) for r in language_id.predict(odd, model).collect()}
    assert und[3] == und[4] == und[6] == ("und", 0.0)
    packed = {r.id: r for r in packing.pack_documents(odd).where("id in (3, 4)").collect()}
    assert packed[3].doc_tokens == packed[4].doc_tokens == 1
    digests = {r.id: r for r in media.clip_digests(odd).collect()}
    assert digests[3].payload_sha256 == hashlib.sha256(b"\0" * 64).hexdigest() == digests[4].payload_sha256


def test_urls(spark, same):
    same(queries.QUERIES["op1_url_filter"], queries.ORACLES["op1_url_filter"])
    urls = ["HTTP://WWW.Example.com/en/x?q#f", "http://a.example.com/en/", "https://net/fr/y", "x.net/fr/", None, "://", "http://ex.net/es", "ftp://example.com", "http://sub.www.example.com/en/", "a://com/ß"]
    pages = spark.createDataFrame([(i, u, "r", "h") for i, u in enumerate(urls)] + [(None, "http://q.com/", "r", "h")], "page_id bigint, url string, rule string, host string")
    rules = url_filter.rules_frame(spark, url_filter.PRODUCTION_RULES)
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in url_filter.filter_urls(pages, rules).collect()}
    assert got[0] == ("www.example.com", "/en/x", "www.example.com/en/", "allow")
    assert got[1] == ("a.example.com", "/en/", "example.com/en/", "block")
    assert got[2] == ("net", "/fr/y", "net/fr/", "block")
    assert got[3] == got[4] == ("", "", None, "allow")
    assert got[6][2:] == (None, "allow") and got[7] == ("example.com", "", None, "allow")
    assert got[8][2] == "www.example.com/en/" and got[None][2] == "com/"
    shuffled = url_filter.filter_urls(pages, rules, broadcast_rules=0).collect()
    assert {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in shuffled} == got
    assert url_filter.filter_urls(pages.limit(0), rules).count() == 0


def test_topk(spark, same):
    same(queries.QUERIES["op2_exact_topk"], queries.ORACLES["op2_exact_topk"])
    rows = spark.createDataFrame([(i, 7 if i % 3 == 0 else i * 1000003) for i in range(400)] + [(None, 7), (900, None)], "id bigint, code bigint")
    asked = rows.where("id % 20 = 0")
    got = collections.defaultdict(list)
    for r in hamming_topk.nearest_codes(rows, asked, k=5).orderBy("query_id", "rank").collect():
        got[r.query_id].append((r.distance, r.neighbor_id))
    plain = [(r.id, r.code) for r in rows.collect() if r.id is not None and r.code is not None]
    for q, code in ((a, c) for a, c in plain if a % 20 == 0):
        assert got[q] == sorted(((c ^ code) & (1 << 64) - 1).bit_count() and (((c ^ code) & (1 << 64) - 1).bit_count(), i) or (0, i) for i, c in plain)[:5]
    assert hamming_topk.nearest_codes(rows.limit(0), asked).count() == 0 and hamming_topk.nearest_codes(rows, asked.limit(0)).count() == 0


def test_pieces_of_whole_texts(spark, small, documents):
    reference = sentencepiece.SentencePieceProcessor(model_file=piece_codec.default_path())
    rows = {r.doc_id: r for r in queries.op3_sentencepiece(spark, small).collect()}
    for d in documents.itertuples():
        ids = reference.encode(d.text)
        assert rows[d.doc_id].n_ids == len(ids) and rows[d.doc_id].ids_crc32 == zlib.crc32(np.array(ids, "<i4").tobytes()) and rows[d.doc_id].round_trip
    docs = spark.read.parquet(f"{small}/documents.parquet").limit(20)
    back = {r.id: r.text for r in piece_codec.decode_ids(piece_codec.encode_texts(docs)).collect()}
    assert all(back[r.doc_id] == r.text for r in docs.collect())


def test_repeated_spans(spark, small, documents):
    rows = {r.doc_id: r for r in queries.op4_substring_dedup(spark, small).collect()}
    for d, (n, gone, kept) in zip(documents.itertuples(), plain_spans(documents.text, 35)):
        assert (rows[d.doc_id].n_words, rows[d.doc_id].n_removed, rows[d.doc_id].kept_sha256) == (n, gone, hashlib.sha256(kept.encode()).hexdigest())


def test_repeated_spans_of_few_words(spark):
    import random

    rng = random.Random(9)
    texts = [" ".join(rng.choice("a b c".split()) for _ in range(rng.randrange(0, 40))) for _ in range(60)] + ["a " * 50, "a " * 12, ""]
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    got = {r.id: (r.n_words, r.n_removed, r.kept_sha256) for r in substring_dedup.removed_spans(rows, width=9, anchor=3).collect()}
    for i, (n, gone, kept) in enumerate(plain_spans(texts, 9)):
        assert got[i] == (n, gone, hashlib.sha256(kept.encode()).hexdigest())
    cut = {r.doc_id: r.text for r in substring_dedup.remove_spans(rows, width=9, anchor=3).collect()}
    for i, (_, gone, kept) in enumerate(plain_spans(texts, 9)):
        assert cut[i] == (kept if gone else texts[i])


def test_repeated_spans_of_regular_words_and_wide_windows(spark):
    """Thue-Morse word orders, whose polynomial hashes collide, periods, and windows of 1,024 words."""
    order = ["x"]
    while len(order) < 2048:
        order += ["y" if w == "x" else "x" for w in order]
    other = ["y" if w == "x" else "x" for w in order]
    period = [f"p{i % 7}" for i in range(3000)]
    long = [f"w{i}" for i in range(1500)]
    texts = [" ".join(t) for t in (order, other, order[100:1200], period, period[3:1500], long, ["head", *long[200:1300], "tail"], long[400:1400] + ["end"])]
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    for width, anchor in ((1024, 6), (64, 6), (35, 6), (4, 6), (1, 6)):
        got = {r.id: (r.n_words, r.n_removed, r.kept_sha256) for r in substring_dedup.removed_spans(rows, width=width, anchor=anchor).collect()}
        for i, (n, gone, kept) in enumerate(plain_spans(texts, width)):
            assert got[i] == (n, gone, hashlib.sha256(kept.encode()).hexdigest()), (width, i)


def test_forks_and_copies_of_spans(spark, monkeypatch):
    """Blocks in many orders: paths that fork at every block end, copies, and blocks that one text repeats."""
    import random

    rng = random.Random(4)
    blocks = [[f"b{k}_{i}" for i in range(rng.randrange(5, 30))] for k in range(12)]
    texts = [" ".join(w for _ in range(rng.randrange(1, 7)) for w in rng.choice(blocks)) for _ in range(80)]
    texts += texts[:10] + ["only words of its own here"]
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    for width, hot in ((8, 1), (20, 1024)):  # edges that count as hot go another way through the join
        monkeypatch.setattr(substring_dedup, "HOT_RUNS", hot)
        got = {r.id: (r.n_removed, r.kept_sha256) for r in substring_dedup.removed_spans(rows, width=width, anchor=3).collect()}
        for i, (_, gone, kept) in enumerate(plain_spans(texts, width)):
            assert got[i] == (gone, hashlib.sha256(kept.encode()).hexdigest()), (width, i)


def crc(doc_id, folds):
    return zlib.crc32(str(doc_id).encode()) % folds


def test_toxicity(spark, small):
    data = "/root/testdata/sf0.01"
    rows = queries.op5_toxicity(spark, data).toPandas().set_index("doc_id")
    assert (rows.held_out == [crc(i, 3) == 1 for i in rows.index]).all() and rows.score.between(0, 1).all()
    assert ((rows.score >= 0.7) == (rows.predicted == 1)).all()
    labels = spark.read.parquet(f"{data}/labels.parquet").toPandas().set_index("doc_id")
    test = labels.join(rows).query("held_out")
    assert test[test.toxic == 1].predicted.mean() >= 0.7 and test[test.toxic == 0].predicted.mean() <= 0.02
    field = toxicity.fit(["a nice day here"] * 30 + ["you utter scum there"] * 30, [0] * 30 + [1] * 30)
    docs = spark.createDataFrame([(1, "well you utter scum ok"), (2, "a nice day")], "doc_id bigint, text string")
    got = {r.id: r for r in toxicity.score_texts(docs, field).collect()}
    assert got[1].score > 0.5 > got[2].score and not got[2].spans
    assert "scum" in ["well you utter scum ok"[s.start : s.end] for s in got[1].spans]
    assert toxicity.fit(["only clean"], [0]).score(np.array([0.9]), np.array([1.0]))[0] < 0.5


def test_language(spark, small):
    rows = queries.op6_language_id(spark, small).toPandas()
    truth = spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "lang").toPandas()
    test = rows.merge(truth, on="doc_id").query("held_out")
    assert (test.held_out == [crc(i, 4) == 2 for i in test.doc_id]).all()
    assert (test.lang_pred == test.lang).mean() >= 0.95 and rows.score.between(0, 1).all()


def test_near_duplicates(spark, small, documents):
    rows = {r.doc_id: (r.fingerprint, r.component_id) for r in queries.op7_simhash_near_dedup(spark, small).collect()}
    prints = {}
    for d in documents.itertuples():
        w = WORD.findall(d.text.translate(LOWER))
        s = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] or ([" ".join(w)] if w else [])
        h = [xxhash.xxh64_intdigest(x, 42) for x in s]
        prints[d.doc_id] = sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))
    group = {i: i for i in prints}
    changed = True
    while changed:
        changed = False
        for i in prints:
            for j in prints:
                if (prints[i] ^ prints[j]).bit_count() <= 2 and group[i] != group[j]:
                    group[i] = group[j] = min(group[i], group[j])
                    changed = True
    assert rows == {i: (f"{prints[i]:016x}", group[i]) for i in prints}


def test_licenses(spark, same):
    same(queries.QUERIES["op8_license_scan"], queries.ORACLES["op8_license_scan"])
    mit = dict(license_scan.KNOWN[::-1])["MIT"]
    wrapped = "Copyright (c) 2020 Some Body\n\n" + license_scan._MIT_GRANT.replace("copies of the", "copies\nof   the").replace("license", "licence").upper()
    docs = spark.createDataFrame([(1, wrapped), (2, "text\n  RELEASED under the MIT licence!\nmore"), (3, mit + " extra"), (4, "(c) only"), (5, None)], "doc_id bigint, text string")
    got = {r.id: (r.license, r.notices, r.license_lines) for r in license_scan.scan_licenses(docs, license_scan.known_frame(spark)).collect()}
    assert got == {1: ("MIT", None, 0), 2: (None, "MIT", 1), 3: (None, None, 0), 4: (None, None, 0), 5: (None, None, 0)}


def test_packing(spark, small, documents):
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(packing.default_paths()[0])
    ids = {d.doc_id: np.array(tokenizer.encode(d.text, add_special_tokens=False).ids + [1], "<u4") for d in documents.itertuples()}
    pieces, sequences = collections.defaultdict(list), collections.defaultdict(list)
    for r in queries.op9_packing(spark, small).collect():
        part = ids[r.doc_id][r.start : r.start + r.length]
        assert zlib.crc32(part.tobytes()) == r.ids_crc32 and r.doc_tokens == len(ids[r.doc_id])
        pieces[r.doc_id].append((r.start, r.length))
        sequences[r.sequence_id].append((r.offset, r.length))
    for spans, end in [(pieces[i], len(ids[i])) for i in ids] + [(s, None) for s in sequences.values()]:
        at = 0
        for begin, length in sorted(spans):
            assert begin == at
            at += length
        assert at == end or (end is None and at <= 2048)
    assert len(sequences) <= -(-sum(map(len, ids.values())) // 2048) + 1


def test_media(spark, small, documents):
    for r in queries.op10_media_columns(spark, small).collect():
        text = documents.text[documents.doc_id == r.doc_id].iloc[0].encode()
        payload = media.text_payload(text)
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(text), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]))
        stored = media.pack_payload(media.codec_of(payload), payload)
        assert (r.media_bytes, r.media_sha256) == (len(stored), hashlib.sha256(stored).hexdigest()) and r.feature.startswith("codec=")


def test_pipeline_stages(spark, small):
    import corpus_pipeline

    docs = spark.read.parquet(f"{small}/documents.parquet")
    columns = docs.columns
    stages = dict(corpus_pipeline.STAGES)
    assert len(stages) == 5
    known = stages["language_id"](spark, docs, small)
    assert known.columns == columns and known.count() >= 0.98 * docs.where("text rlike '[A-Za-z]'").count()
    labels = spark.read.parquet(f"{small}/labels.parquet")
    clean = stages["toxicity"](spark, docs, small)
    assert clean.columns == columns and clean.join(labels.where("toxic = 0"), "doc_id", "left_semi").count() == docs.join(labels.where("toxic = 0"), "doc_id", "left_semi").count()
    kept = stages["simhash_near_dedup"](spark, docs, small)
    before, after = docs.toPandas().set_index("doc_id"), kept.toPandas().set_index("doc_id")
    assert kept.columns == columns and after.index.is_unique and after.text.is_unique
    shingles = {i: {" ".join(w[k : k + 5]) for k in range(max(1, len(w) - 4))} for i, w in ((i, WORD.findall(t.translate(LOWER))) for i, t in before.text.items())}
    similar = lambda i, j: len(shingles[i] & shingles[j]) / max(1, len(shingles[i] | shingles[j]))
    close = [(i, j) for i in shingles for j in shingles if i < j and similar(i, j) >= 0.8]
    assert close and sum(i in after.index and j in after.index for i, j in close) <= 0.02 * len(close)
    for i in set(before.index) - set(after.index):
        assert any(j != i and similar(i, j) >= 0.6 for j in shingles)
    cut = stages["substring_dedup"](spark, kept, small)
    texts = list(after.text)
    want = {i: (k if gone else t) for i, t, (_, gone, k) in zip(after.index, texts, plain_spans(texts, 35))}
    assert cut.columns == columns and {r.doc_id: r.text for r in cut.collect()} == want
    assert cut.where(F.length("text") != F.col("n_chars")).isEmpty()
    packed = stages["packing"](spark, cut, small)
    assert packed.select("doc_id").distinct().count() == cut.count()
    assert entry.queries()["pipeline"](spark, small).count() > 0


def test_rest_does_without_this_subpackage():
    import os
    import subprocess
    import sys
    import tempfile

    root = os.path.dirname(os.path.abspath(entry.__file__))
    with tempfile.TemporaryDirectory() as folder:
        subprocess.run(["cp", "-r", f"{root}/phrasework", f"{root}/__spark_entry__.py", folder], check=True)
        subprocess.run(["rm", "-r", f"{folder}/phrasework/llm"], check=True)
        code = "import __spark_entry__ as e; q = e.queries(); assert q and not [n for n in q if n[:3] == 'op1' or n == 'pipeline']"
        subprocess.run([sys.executable, "-c", code], check=True, cwd=folder)


def test_split_shards_link_the_same_texts(spark, small):
    from phrasework.llm.components import connected_components

    docs = spark.read.parquet(f"{small}/documents.parquet").where("doc_id < 120").select(F.col("doc_id").alias("id"), "text")
    texts = near_groups._sketch(docs).dropDuplicates(["k1", "k2"]).withColumn("node", F.col("id")).cache()
    groups = [{(r.node, r.root) for r in connected_components(near_groups.text_links(texts, shard=n)).collect()} for n in (4096, 2)]
    assert groups[0] and groups[0] == groups[1]


def test_near_groups_at_exactly_the_threshold(spark):
    """Pairs of similarity 40/50, below it 39/51, and pages of one template at 35/55 to each other."""
    texts = []
    for i in range(150):
        base = [f"p{i}w{k}" for k in range(49)]
        texts += [base, base[:44] + [f"n{i}w{k}" for k in range(5)]]
        base = [f"q{i}w{k}" for k in range(49)]
        texts += [base, base[:43] + [f"m{i}w{k}" for k in range(6)]]
    template = [f"t{k}" for k in range(39)]
    texts += [template + [f"page{i}w{k}" for k in range(10)] for i in range(60)]
    shingles = [{tuple(t[k : k + 5]) for k in range(len(t) - 4)} for t in texts]
    gone = {j for i in range(0, 600, 2) for j in (i + 1,) if 5 * len(shingles[i] & shingles[j]) >= 4 * len(shingles[i] | shingles[j])}
    assert len(gone) == 150
    docs = spark.createDataFrame([(i, " ".join(t)) for i, t in enumerate(texts)], "doc_id bigint, text string").repartition(3)
    assert {r.doc_id for r in near_groups.keep_one_of_each(docs).collect()} == set(range(len(texts))) - gone
    rows = docs.withColumnRenamed("doc_id", "id")
    members = near_groups._sketch(rows).drop("anchors").select(F.lit(0).cast("bigint").alias("root"), F.col("id").alias("node"), F.col("id").alias("least"), "*")
    for shard, part_shingles in ((4096, 1 << 21), (100, 1 << 21), (4096, 5000)):
        links = near_groups.confirmed_links(rows, members, shard=shard, part_shingles=part_shingles).collect()
        assert {max(r.u, r.v) for r in links} == gone and all(abs(r.u - r.v) == 1 for r in links)


def test_components_of_chains_and_stars(spark):
    from phrasework.llm.components import connected_components

    pairs = [(i, i + 1) for i in range(40)] + [(100, 100 + i) for i in range(1, 30)] + [(7, 7), (None, 3), (200, 201), (201, 200)]
    got = {r.node: r.root for r in connected_components(spark.createDataFrame(pairs, "u bigint, v bigint")).collect()}
    assert got == {**{i: 0 for i in range(41)}, **{100 + i: 100 for i in range(30)}, 200: 200, 201: 200}
    assert connected_components(spark.createDataFrame([], "u bigint, v bigint")).count() == 0


def test_adjacent_spellings_and_whole_public_texts(spark):
    import os

    rows = spark.createDataFrame([("Favour favour, whilst whilst a sub-licence sub licence!",)], "text string")
    assert rows.select(license_scan.canonical(F.col("text")).alias("t")).first().t == "favor favor while while a sublicense sublicense"
    own = spark.createDataFrame([("House-1", "Do what the house says.\nCopyright 2020 us")], "license string, text string")
    docs = [(1, "DO WHAT THE HOUSE SAYS"), (2, "do what")]
    if os.path.exists("/usr/share/common-licenses/MPL-2.0"):
        with open("/usr/share/common-licenses/MPL-2.0", encoding="utf-8") as f:
            docs.append((3, f.read().upper().replace("\n", "  \n")))
    found = license_scan.scan_licenses(spark.createDataFrame(docs, "doc_id bigint, text string"), license_scan.known_frame(spark, texts=own))
    assert {r.id: r.license for r in found.collect()} == dict([(1, "House-1"), (2, None), (3, "MPL-2.0")][: len(docs)])


def test_spans_are_offsets_into_the_text(spark):
    field = toxicity.fit(["you utter scum"] * 30 + ["fine day outside"] * 30, [1] * 30 + [0] * 30)
    text = "  é fine\t\n day,  utter   SCUM x here "
    row = toxicity.score_texts(spark.createDataFrame([(1, text)], "doc_id bigint, text string"), field, span_at=0.0).first()
    assert [text.encode()[s.start : s.end].decode() for s in row.spans] == plain_words(text)


def test_toxic_chances_segment_by_segment(monkeypatch):
    import random

    import pyarrow as pa

    from phrasework.llm.textbytes import Words, utf8

    rng = random.Random(1)
    texts = [" ".join(rng.choice("fine day you scum trash hello".split()) for _ in range(rng.randrange(0, 90))) for _ in range(40)]
    field = toxicity.fit(texts, [i % 2 for i in range(40)])
    words = Words(*utf8(pa.array(texts)))
    whole = field.toxic_chances(words)
    for size in (1, 7, 100):
        monkeypatch.setattr(toxicity, "SEGMENT", size)
        assert np.allclose(whole, field.toxic_chances(words), atol=1e-12)


def test_language_of_very_long_runs():
    import time

    import pyarrow as pa

    from phrasework.llm.textbytes import utf8

    model = language_id.fit({"en": ["the cat and the dog sat on the mat"] * 3, "de": ["der hund und die katze sassen da"] * 3})
    began = time.monotonic()
    total, n = language_id.batch_scores(model, *utf8(pa.array(["the dog", "x" * 3_000_000 + " the", "", "a b"], pa.large_string())))
    assert time.monotonic() - began < 60 and np.isfinite(total).all() and n.tolist() == [2, 2, 0, 1]
    parts = language_id.batch_scores(model, *utf8(pa.array(["q" * 64 + " " + "q" * 64 + " qq", "q" * 130])))[0]
    assert np.allclose(parts[0], parts[1])


def test_packing_follows_from_the_rows_alone(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text")
    docs = docs.unionByName(docs.limit(5)).unionByName(spark.createDataFrame([(None, "")] * 40, "doc_id bigint, text string"))
    one, other = (sorted(map(repr, packing.pack_documents(docs.repartition(n), group_pieces=64).collect())) for n in (1, 7))
    assert one == other and len(one) >= docs.count()


def test_models_with_other_normalisers_are_refused():
    piece_codec.check_normaliser(b"\x1a\x04\x18\x01\x20\x00")
    for raw in (b"\x1a\x02\x20\x01", b"\x1a\x04\x18\x00\x20\x00", b"\x1a\x05\x12\x01x\x20\x00", b"\x12\x03\xc0\x01\x01\x1a\x02\x20\x00"):
        with pytest.raises(ValueError):
            piece_codec.check_normaliser(raw)


def test_codes_have_room_for_64_elements(spark):
    rows = spark.createDataFrame([([1.0] * 64,), (None,)], "v array<double>")
    assert [r.c for r in rows.select(hamming_topk.sign_code(F.col("v")).alias("c")).collect()] == [-1, None]
    with pytest.raises(Exception, match="more than 64"):
        spark.createDataFrame([([1.0] * 65,)], "v array<double>").select(hamming_topk.sign_code(F.col("v"))).collect()


def test_texts_behind_one_boilerplate_shingle(spark):
    """A shingle that all texts share is no key by itself; near duplicates among them are still found."""
    import random

    rng = random.Random(3)
    texts, groups = [], []
    for k in range(60):
        body = [f"t{k}w{rng.randrange(10**6)}" for _ in range(40)]
        for copy in range(2):
            texts.append(" ".join([*"this is the same boiler plate line for all".split(), *body, *(["more"] if copy else [])]))
            groups.append(k)
    rows = near_groups._sketch(spark.createDataFrame(list(enumerate(texts)), "id bigint, text string")).withColumn("node", F.col("id"))
    links = near_groups.text_links(rows, shard=8).collect()
    up = list(range(len(texts)))
    for r in links:
        a, b = r.u, r.v
        while up[a] != a:
            a = up[a]
        while up[b] != b:
            b = up[b]
        up[max(a, b)] = min(a, b)
    for k in range(60):
        a, b = 2 * k, 2 * k + 1
        while up[a] != a:
            a = up[a]
        while up[b] != b:
            b = up[b]
        assert a == b


def test_near_groups_search_fingerprints(spark):
    fps = [0, 1, 3, 7 << 40, 6 << 40, 0, 1 << 62, 127 << 20]
    rows = spark.createDataFrame(list(enumerate(fps)), "node bigint, fp bigint")
    from phrasework.llm.components import connected_components

    got = {(r.node, r.root) for r in connected_components(near_groups.print_links(rows)).collect()}
    classes = {}
    for node, root in got:
        classes.setdefault(root, set()).add(node)
    # 1 << 62 and 6 << 40 are one and two bits from zero, 127 << 20 is seven.
    assert sorted(map(sorted, classes.values())) == [[0, 1, 2, 3, 4, 5, 6]]
    texts = spark.createDataFrame([(0, "one two three four"), (1, None)], "id bigint, text string")
    prints = {r.id: r.fp for r in simhash.fingerprints(texts, id_col="id").collect()}
    assert {r.id: r.fp for r in near_groups._sketch(texts).collect()} == prints
