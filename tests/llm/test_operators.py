"""The training-data operators against plain versions, on small tables with nulls, empties, ties and repeats."""

from __future__ import annotations

import os
import sys
import time
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

sys.path.insert(0, os.path.dirname(__file__))
import brute  # noqa: E402

from blockflow.llm import fingerprints, htmltext, huffman, licenses, mixing, neardup, packing, quality, tokens, toxicity  # noqa: E402
from blockflow.llm import kernels as K  # noqa: E402
from blockflow.llm.neardup import NearDupConfig, near_duplicates  # noqa: E402
from blockflow.llm.substrings import remove_repeats, suffix_ranks  # noqa: E402
from blockflow.session import materialize  # noqa: E402

tokenizers = pytest.importorskip("tokenizers")
public = pytest.importorskip("public_tokenizers")

SCHEMA = "doc_id long, text string"
BASE = " ".join(f"word{i}" for i in range(120))


def texts():
    near = [BASE.replace(f"word{3 * k} ", f"other{k} ", 1) for k in range(12)]
    far = [" ".join(f"w{(i * 7 + k * 31) % 997}" for i in range(60)) for k in range(8)]
    odd = [None, "", "  \n ", "ab", "é" * 300, "x " * 400, BASE, BASE.upper(), "one two three four", "one two three four five", BASE + "\n" + far[0]]
    return list(enumerate([BASE, *near, *far, *odd]))


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(texts(), SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def test_near_duplicates(docs):
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in near_duplicates(docs).collect()}
    assert got == brute.components(texts())


def test_families_are_not_connected_by_boilerplate(spark):
    # each text has a passage in common with the next one, but no two of them are alike; the last two are near-duplicates
    words = lambda k, n: [f"w{k}x{i}" for i in range(n)]
    chain = [(k, " ".join([*words(k, 40), *words(k + 1, 40)])) for k in range(30)]
    rows = [*chain, (30, " ".join(words(300, 200))), (31, " ".join([*words(300, 190), *words(400, 10)]))]
    texts = spark.createDataFrame(rows, SCHEMA)
    open_ = spark.createDataFrame([(0, k, k, len(t.split()) - 4) for k, t in rows], "hub long, node long, root long, n long")
    for config in (NearDupConfig(), NearDupConfig(signed=3)):
        got = {r.node: r.family for r in neardup._families(open_, texts, config).collect()}
        assert got == {30: 30, 31: 30}
        assert {(min(r), max(r)) for r in neardup._family_links(open_, texts, config).collect()} == {(30, 31)}


def shuffle_files(spark):
    return spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles().mkString("\n").count("/shuffle_")


def test_shuffles_of_finished_steps_go_while_the_job_runs(spark, docs):
    found = near_duplicates(docs)
    until = time.time() + 10
    while shuffle_files(spark) > 20 and time.time() < until:
        time.sleep(0.2)
    assert shuffle_files(spark) <= 20
    assert found.count() == len(texts())


def test_repeats(docs):
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in remove_repeats(docs).collect()}
    assert got == brute.repeats(texts())


def test_repeats_over_several_map_batches(spark, docs):
    got = {r.doc_id: r.n_removed for r in remove_repeats(docs.repartition(9), parts=5).collect()}
    assert got == {k: v[1] for k, v in brute.repeats(texts()).items()}


def test_repeats_of_texts_that_share_a_doc_id(spark):
    period, other = "abcdefgh ijklm\n" * 20, " ".join(f"unique{k * k}" for k in range(60))
    frame = spark.createDataFrame([(1, period), (1, other), (1, other), (2, other)], SCHEMA)
    got = sorted((r.doc_id, r.n_bytes, r.n_removed) for r in remove_repeats(frame).collect())
    assert got == sorted([(1, 300, 285), (1, len(other), 0), (1, len(other), 0), (2, len(other), len(other))])


def test_suffix_ranks_are_the_order_of_cut_suffixes():
    rnd = np.random.default_rng(3)
    for size in (1, 5, 8, 11, 100):
        data = rnd.integers(97, 100, 700).astype(np.uint8)
        data[400:600] = data[100:300]
        cut = [(data.tobytes() + bytes(size))[i : i + size] for i in range(len(data))]
        place = {c: n for n, c in enumerate(sorted(set(cut)))}
        assert suffix_ranks(data, size).tolist() == [place[c] for c in cut]
    assert len(suffix_ranks(np.zeros(0, np.uint8), 100)) == 0


@pytest.mark.parametrize("name", ["word_bpe_49k.json", "byte_bpe_50k.json"])
def test_pieces_give_the_ids_of_whole_texts(name):
    import random

    rnd = random.Random(7)
    alphabet = list("abXY  \n\t.,'!?019éßÉ×÷ŒΣσ  　́<|>") + ["'s", "<|endoftext|>", "日本", "😀", "\r\n"]
    rows = ["".join(rnd.choice(alphabet) for _ in range(rnd.randint(0, 40))) for _ in range(3000)]
    path = public.path(name)
    want = [e.ids for e in tokenizers.Tokenizer.from_file(path).encode_batch(rows, add_special_tokens=False)]
    data, offsets = K.column_bytes(pa.array(rows))
    ids, at = tokens.PieceEncoder(path).encode(data, offsets)
    assert [ids[a:b].tolist() for a, b in zip(at[:-1], at[1:], strict=True)] == want


def test_shards_round_trip(docs):
    path = public.path("word_bpe_49k.json")
    got = {r.doc_id: (r.start, r.n_tokens, r.ids_crc32) for r in huffman.read_shards(*huffman.write_shards(docs, path, 2)).collect()}
    tok, start = tokenizers.Tokenizer.from_file(path), 0
    for i, text in texts():
        ids = np.array([*tok.encode(text or "", add_special_tokens=False).ids, 2], "<u4")
        assert got[i] == (start, len(ids), zlib.crc32(ids.tobytes()))
        start += len(ids)


def test_code_lengths_are_limited_and_complete():
    counts = np.array([1 << k for k in range(30)])
    lengths = huffman.code_lengths(counts, limit=8)
    assert lengths.max() <= 8 and sum(2.0 ** -int(x) for x in lengths) == 1.0
    image = huffman.encode_shard(np.arange(30).repeat(100), np.array([5]), np.array([3000]), 0, lengths, huffman.canonical_codes(lengths), block=64)
    table = huffman.decode_table(lengths)
    assert (huffman.decode_blocks(image, table) == np.arange(30).repeat(100)).all()
    assert (huffman.decode_blocks(image, table, blocks=np.array([46])) == np.arange(30).repeat(100)[46 * 64 :]).all()


def test_packing_holds_every_id_once():
    lengths = np.array([1, 5, 2048, 2049, 5000, 700, 700, 648, 1000, 1048, 3, 3, 2047] * 9)
    sequences = packing.pack(lengths)
    seen = [np.zeros(n, int) for n in lengths]
    for s in sequences:
        assert sum(n for _, _, n in s) <= packing.WINDOW
        for d, start, n in s:
            seen[d][start : start + n] += 1
    assert all((x == 1).all() for x in seen)
    assert len(sequences) <= -(-int(lengths.sum()) // packing.WINDOW) * 1.02 + 1


def test_license_scan(spark):
    rows = [(1, "Licensed under the MIT License."), (2, None), (3, "gnu GENERAL public license; cc by-nc 4.0, mit license"), (4, "nothing here")]
    got = {r.doc_id: r for r in licenses.license_report(spark.createDataFrame(rows, SCHEMA)).collect()}
    assert (got[1].n_words, got[1].n_base, got[1].first_word, got[1].last_word, got[1].labels) == (5, 1, 3, 3, "mit")
    assert (got[2].n_words, got[2].n_base, got[2].first_word, got[2].labels, got[2].score) == (0, 0, None, "", 0.0)
    assert (got[3].n_base, got[3].first_word, got[3].last_word, got[3].base_labels) == (3, 0, 9, "cc-by,gpl,mit")
    assert got[4].labels == "" and len(licenses.signature_rules()) > 300


def test_license_hits_over_many_blocks(spark):
    import random
    import re

    bits = ["licensed under the apache license version 2 0", "under the terms of the gnu general public license v3 or later", "mit license", "plain words", "cc by nc sa", "the", "lgpl", "license gpl"]
    rnd = random.Random(5)
    norm = " " + " ".join(rnd.choice(bits) for _ in range(250)) + " "
    hits = [(r.priority, m.end() - m.start(), -n, m.start(), r.label) for n, r in enumerate(licenses.signature_rules()) if r.keyword in norm for m in re.finditer(r.pattern, norm)]
    want = sorted((a[3], a[1], a[4]) for a in hits if not any(b[3] <= a[3] and b[3] + b[1] >= a[3] + a[1] and b[:3] > a[:3] for b in hits))
    row = licenses.license_report(spark.createDataFrame([(1, norm)], SCHEMA)).first()
    assert len(want) > 128 and sorted((s["start"], s["size"], s["label"]) for s in row.spans) == want


def test_quality_rules(spark, empty):
    junk = [(k, " ".join(f"w{i}###" for i in range(80))) for k in range(5)]
    fine = [(10 + k, ". ".join(f"word{i * k} and more{i}" for i in range(40))) for k in range(40)]
    again = [(60, "a b c d " * 40), (61, None), (62, "x\nx\ny")]
    got = {r.doc_id: r for r in quality.quality_verdicts(spark.createDataFrame(junk + fine + again, SCHEMA), lambda df: materialize(df, "q")).collect()}
    assert not any(got[k].kept for k, _ in junk) and all(got[k].kept for k, _ in fine)
    assert (got[60].n_repeat_words, got[60].base_failed) == (160, True)
    assert (got[61].n_words, got[61].n_dup_lines) == (0, 0) and got[62].n_dup_lines == 1
    assert quality.quality_verdicts(empty, lambda df: materialize(df, "q")).count() == 0


def test_html():
    page = """<html><head><title>t</title></head><body><nav><ul><li>Home</li></ul></nav><div class="cookie-notice">Accept</div>
    <article><h1>A &amp;  title</h1><p>One <b>two</b><br>three<p>Four<ul><li>five</ul><div id="comments">no</div></article>
    <form>Name</form><aside>x</aside><footer>&copy;</footer><script>var a = "</p>";</script>"""
    assert htmltext.main_text(page) == "A & title\n\nOne two three\n\nFour\n\nfive"
    assert htmltext.main_text(None) == htmltext.main_text("") == htmltext.main_text("<nav>a</nav>") == ""
    assert htmltext.main_text("<p>Whole <!-- cut") == "Whole"


def test_toxicity_learns_word_parts(spark):
    rows = [(k, f"plain words number {k} and some more" + (" you zorgling beast" if k % 4 == 0 else "")) for k in range(400)] + [(900, None), (901, "")]
    docs = spark.createDataFrame(rows, SCHEMA)
    labels = spark.createDataFrame([(k, int(k % 4 == 0)) for k in range(0, 400, 3)], "doc_id long, toxic int")
    got = {r.doc_id: r.toxicity for r in toxicity.score(docs, toxicity.fit(docs, labels)).collect()}
    assert all((got[k] >= 0.5) == (k % 4 == 0) for k in range(400)) and got[900] == got[901] < 0.5
    nothing = toxicity.fit(docs, labels.where("doc_id < 0"))
    assert toxicity.score(docs, nothing).where("toxicity > 0.01").count() == 0


def test_fingerprints(docs):
    rows = {r.doc_id: r for r in fingerprints.fingerprint_pairs(docs).collect()}
    want = texts()
    for k, (i, text) in enumerate(want):
        text, after = text or "", want[(k + 1) % len(want)][1] or ""
        assert rows[i].n_chars == len(text)
        cut = len(text) // 2
        import hashlib

        assert rows[i].edited_sha256 == hashlib.sha256((text[: len(text) - cut] + after[:cut]).encode()).hexdigest()
        assert 0 <= rows[i].near_edited <= 1 and 0 <= rows[i].near_next <= 1
        chains = fingerprints.from_text(rows[i].fingerprint)
        assert fingerprints.to_text(chains) == rows[i].fingerprint and fingerprints.likeness(chains, chains) == 1.0
    assert rows[0].fingerprint == next(rows[i].fingerprint for i, t in want if t == BASE and i)


def test_mixing_meets_targets(spark):
    rows = [(k, ("plain text of words " * 20) if k % 5 else ("### $$$ !!! " * 30)) for k in range(200)]
    docs = spark.createDataFrame(rows, SCHEMA)
    labels = spark.createDataFrame([(k, int(k % 5 > 0), 0) for k in range(0, 200, 2)], "doc_id long, quality int, toxic int")
    rated, model, _ = mixing.mix(docs, labels, targets={"q0_t0": 0.5, "q1_t0": 0.5})
    share = [F.sum(F.col("rate") * F.col("n_tokens") * F.get("p", F.lit(d))).alias(f"d{d}") for d in range(len(model.domains))]
    row = rated.agg(F.sum("n_tokens").alias("n"), *share).first()
    assert all(abs(row[f"d{d}"] / row.n - 0.5) < 1e-3 for d in range(2))
    assert rated.where("rate < 0").count() == 0


def test_empty_tables(spark, empty):
    assert near_duplicates(empty).count() == 0
    assert remove_repeats(empty).count() == 0
    assert licenses.license_report(empty).count() == 0
    assert fingerprints.fingerprint_pairs(empty).count() == 0
    path = public.path("byte_bpe_50k.json")
    assert packing.pack_documents(empty, path, 1).count() == 0
    assert huffman.read_shards(*huffman.write_shards(empty, path, 1)).count() == 0


def test_pipeline_stages_keep_columns(spark):
    pipeline = pytest.importorskip("corpus_pipeline")
    d = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{d}/documents.parquet")
    n = docs.count()
    for name, stage in pipeline.STAGES[:-1]:
        docs = materialize(stage(spark, docs.withColumn("clash", F.lit(1)), d), name)
        assert docs.columns == pipeline.COLUMNS
        if name == "near-dedup":
            left = {r.doc_id: r.text for r in docs.collect()}
            assert all(i == c for i, (_, c) in brute.components(left.items()).items())
    assert 0.5 * n < docs.select("doc_id").distinct().count() <= n
    assert pipeline.STAGES[-1][1](spark, docs, d).agg(F.sum("length")).first()[0] > 0


def test_near_dedup_stage_links_from_four_fifths(spark):
    pipeline = pytest.importorskip("corpus_pipeline")
    d = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{d}/documents.parquet")
    two = BASE.replace("word30 ", "other30 ").replace("word60 ", "other60 ")
    three = two.replace("word90 ", "other90 ")
    # shingles in common: 106 of 126, and 101 of 131, which is too few
    extra = [(10_000_001, BASE), (10_000_002, two), (20_000_001, BASE.replace("word", "w")), (20_000_002, three.replace("word", "w"))]
    rows = [(i, t, "en", "s", len(t)) for i, t in extra]
    docs = docs.select(*pipeline.COLUMNS).union(spark.createDataFrame(rows, docs.select(*pipeline.COLUMNS).schema))
    want = {i for i, (_, c) in brute.components([(r.doc_id, r.text) for r in docs.collect()], share=80).items() if i == c}
    got = {r.doc_id for r in pipeline.drop_near_duplicates(spark, docs, d).collect()}
    assert got == want
    assert 10_000_002 not in got and 20_000_002 in got


def test_html_without_marks_is_cut_where_text_surges_and_dives():
    menu = "<div class=x1><ul><li><a href=/>Home</a><li><a href=/n>News</a><li><a href=/a>About us and our work</a><li><a href=/c>Contact</a></ul></div>"
    body = "<div><h2>Title</h2><p>" + "One long sentence of the text. " * 5 + "<ul><li>short<li>items<li>stay<li>here</ul><p>" + "And another <a href=/x>linked</a> paragraph. " * 4 + "</div>"
    want = ["Title", ("One long sentence of the text. " * 5).strip(), "short", "items", "stay", "here", ("And another linked paragraph. " * 4).strip()]
    page = f"<body>{menu}{body}<div class=x2><p>Buy now!</p><p>Only today</p><p>(c) 2020</p></div></body>"
    assert htmltext.main_text(page).split("\n\n") == want
    # a marked page keeps what it marks, however short its lines are
    assert htmltext.main_text(f"<body>{menu}<article><p>Tiny</p></article></body>") == "Tiny"
    # and a page of nothing but short lines is kept whole
    assert htmltext.main_text("<p>Roses<p>are red") == "Roses\n\nare red"


def _distance(members, lift, goal, floor):
    w = members.withColumn("w", mixing._rate(lift, floor))
    row = w.agg(F.sum("n_tokens").alias("n"), *[F.sum(F.col("w") * F.col("n_tokens") * F.get("p", F.lit(d))).alias(f"d{d}") for d in range(len(goal))]).first()
    return sum((g - row[f"d{d}"] / row.n) ** 2 for d, g in enumerate(goal)) ** 0.5


def test_mixing_meets_targets_where_posteriors_overlap(spark, caplog):
    # three domains, a rare one and two that hardly differ
    rows = [(100, [0.5 + 0.02 * (k % 5), 0.49 - 0.02 * (k % 5), 0.01]) for k in range(500)] + [(100, [0.1, 0.1, 0.8])] * 5
    members = spark.createDataFrame(rows, "n_tokens long, p array<double>")
    for floor, goal in ((0.0, [0.5, 0.45, 0.05]), (0.5, [0.53, 0.45, 0.02])):
        lift, left = mixing.fit_rates(members, goal, mixing.MixConfig(floor=floor))
        assert left < 1e-4 and _distance(members, lift, goal, floor) < 1e-4
    assert not caplog.records
    # nothing gives the second domain four fifths: this is said
    lift, left = mixing.fit_rates(members, [0.1, 0.8, 0.1], mixing.MixConfig())
    assert left > 0.1 and "miss the targets" in caplog.text
    assert abs(_distance(members, lift, [0.1, 0.8, 0.1], 0.0) - left) < 1e-9


def test_mixing_tells_long_texts_apart_by_word_counts(spark):
    def text(k, mark):
        # 6000 different words, which fill nearly all buckets, and 2000 times one that is frequent in this domain
        words = [f"w{(k * 7919 + i) % 50021:05d}" for i in range(6000)]
        for i in range(2000):
            words.insert(4 * i, mark)
        return " ".join([*words, "zaaaaa", "zbbbbb"])

    rows = [(k, text(k, "zaaaaa" if k % 2 else "zbbbbb")) for k in range(40)]
    docs = spark.createDataFrame(rows, SCHEMA).repartition(4)
    labels = spark.createDataFrame([(k, k % 2, 0) for k in range(20)], "doc_id long, quality int, toxic int")
    config = mixing.MixConfig()
    model = mixing.fit_domains(docs, mixing.domains_of(labels), config)
    got = {r.doc_id: r.p for r in mixing.posteriors(mixing.features(docs, config), model, config).select("doc_id", "p").collect()}
    assert model.domains == ("q0_t0", "q1_t0")
    assert all(got[k][k % 2] > 0.95 for k in range(20, 40))


def _spellings(pattern):
    """All texts of a pattern of letters, (?:a|b), [ab], [0-9] and ?; one letter stands for [a-z]+."""

    def read(i):
        done, now = [], [""]
        while i < len(pattern) and pattern[i] != ")":
            if pattern[i] == "|":
                done, now, i = done + now, [""], i + 1
                continue
            if pattern.startswith("(?:", i):
                got, i = read(i + 3)
                i += 1
            elif pattern[i] == "[":
                end = pattern.index("]", i)
                held = pattern[i + 1 : end]
                got = [held[0]] if held == "a-z" else [chr(c) for c in range(ord(held[0]), ord(held[2]) + 1)] if held[1] == "-" else list(held)
                i = end + 1 + (pattern[end + 1 : end + 2] == "+")
            else:
                got, i = [pattern[i]], i + 1
            if pattern[i : i + 1] == "?":
                got, i = ["", *got], i + 1
            now = [a + b for a in now for b in got]
        return done + now, i

    return read(0)[0]


def test_license_keywords_let_every_spelling_through(spark):
    rows = [(label, x) for label, _, name in licenses.FAMILIES for x in _spellings(name)]
    docs = spark.createDataFrame([(k, x) for k, (_, x) in enumerate(rows)], SCHEMA)
    hits = {r.doc_id: set(r.labels) for r in licenses.scan(docs).selectExpr("doc_id", "transform(lic_hits, h -> h.label) as labels").collect()}
    assert [rows[k] for k in range(len(rows)) if rows[k][0] not in hits[k]] == []
    for keyword, name in ((k, n) for _, k, n in licenses.FAMILIES):
        assert all(keyword in x for x in _spellings(name))


def test_license_report_of_optional_spellings(spark):
    rows = [(1, "Creative Commons Attribution-Noncommercial-Share Alike 3.0"), (2, "Open Data Commons Database License"), (3, "creative commons attribution no derivatives")]
    got = {r.doc_id: r.labels for r in licenses.license_report(spark.createDataFrame(rows, SCHEMA)).collect()}
    assert got == {1: "cc-by-nc-sa", 2: "odbl", 3: "cc-by-nd"}


def test_html_of_careless_pages():
    assert htmltext.main_text("<html><head><title>x</title><body><p>Hello world</p>") == "Hello world"
    assert htmltext.main_text("<head><meta charset=utf-8>Plain text") == "Plain text"
    assert htmltext.main_text('<p class="a"">Hello</p>') == "Hello"
    assert htmltext.main_text('<div class="it"s">Hello</div>') == "Hello"
    assert htmltext.main_text("<a href=\"foo>Hello</a>") == "Hello"
    import time

    began = time.time()
    assert htmltext.main_text("<div>" * 20_000 + "x" + "</p>" * 20_000) == "x"
    assert time.time() - began < 2


def test_columns_that_clash_are_replaced(spark, docs):
    odd = docs.withColumn("spans", F.lit(1)).withColumn("n_removed", F.lit("x"))
    assert remove_repeats(odd, with_text=True).where("n_removed > 0").count() == sum(v[1] > 0 for v in brute.repeats(texts()).values())
    pages = spark.createDataFrame([(1, None, "a"), (2, "<p>Text</p>", "b")], "page_id long, html string, main_text string")
    assert {r.page_id: r.main_text for r in htmltext.extract(pages).collect()} == {1: "", 2: "Text"}
    model = toxicity.fit(docs, spark.createDataFrame([(0, 1), (1, 0)], "doc_id long, toxic int"))
    scored = toxicity.score(docs.withColumn("toxicity", F.lit("x")).withColumn("tox_text", F.lit(2)), model, keep_text=True)
    assert scored.columns == ["doc_id", "text", "toxicity"] and scored.count() == len(texts())


def test_rows_without_or_with_repeated_doc_ids(spark):
    rows = [(None, BASE), (1, BASE), (1, BASE), (2, "a b c d e f"), (None, None)]
    df = spark.createDataFrame(rows, SCHEMA)
    got = sorted(((r.doc_id, r.component_id, r.kept) for r in near_duplicates(df).collect()), key=str)
    assert got == sorted([(None, None, True), (1, 1, True), (1, 1, True), (2, 2, True), (None, None, True)], key=str)
    packed = packing.pack_documents(df, public.path("byte_bpe_50k.json"), 1).collect()
    assert sum(r.length for r in packed) == sum(r.doc_tokens for r in packed if r.start == 0)


def test_packed_pieces_are_the_tokens_of_the_library(spark, docs):
    path = public.path("byte_bpe_50k.json")
    tok = tokenizers.Tokenizer.from_file(path)
    want = {i: np.array([*tok.encode(t or "", add_special_tokens=False).ids, 1], "<u4") for i, t in texts()}
    places, seen = {}, {i: 0 for i in want}
    for r in packing.pack_documents(docs, path, 1).collect():
        ids = want[r.doc_id]
        assert r.doc_tokens == len(ids) and r.ids_crc32 == zlib.crc32(ids[r.start : r.start + r.length].tobytes())
        seen[r.doc_id] += r.length
        places.setdefault(r.sequence_id, []).append((r.offset, r.length))
    assert all(seen[i] == len(want[i]) for i in want)
    for held in places.values():
        ends = 0
        for offset, length in sorted(held):
            assert offset == ends
            ends += length
        assert ends <= packing.WINDOW


def test_base_columns_of_licenses_and_quality(spark):
    import re

    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text")
    texts_of = {r.doc_id: r.text or "" for r in docs.collect()}
    phrases = {"gnu general public license": "gpl", "apache license": "apache", "cc by": "cc-by", "mit license": "mit"}
    for r in licenses.license_report(docs).collect():
        words = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m.group(0).lower(), texts_of[r.doc_id]))
        places = [(i, label) for phrase, label in phrases.items() for i in range(len(words)) if words[i : i + len(phrase.split())] == phrase.split()]
        starts = [i for i, _ in places]
        assert (r.n_words, r.n_base, r.first_word, r.last_word) == (len(words), len(places), min(starts, default=None), max(starts, default=None))
        assert r.base_labels == ",".join(sorted({x for _, x in places})) and set(r.base_labels.split(",")) <= set(r.labels.split(","))
    for r in quality.quality_verdicts(docs, lambda df: materialize(df, "q")).collect():
        text = texts_of[r.doc_id]
        words = re.findall(r"[^\x20\x09-\x0D]+", text)
        triples = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
        many = {t for t in triples if triples.count(t) > 1} if len(triples) < 3000 else None
        lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        assert (r.n_words, r.word_chars, r.n_symbols) == (len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text)))
        assert r.n_dup_lines == len(lines) - len(set(lines))
        if many is not None:
            assert r.n_repeat_words == len({k for i, t in enumerate(triples) if t in many for k in range(i, i + 3)})
        assert r.base_failed == (len(words) < 50 or 100 * r.n_repeat_words > 50 * len(words)) and not (r.kept and r.base_failed)


def test_pipeline_mixing_moves_domains(spark):
    import corpus_pipeline

    d = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{d}/documents.parquet")
    times = [r["count"] for r in corpus_pipeline.mix_domains(spark, docs, d).groupBy("doc_id").count().collect()]
    # none is left out; with targets near the shares that the domains have, none was read more than twice
    assert len(times) == docs.count() and max(times) >= 3
