"""Whole results of the registered queries against plain versions, on the smallest tables."""

import hashlib
import zlib

import brute
import numpy as np
import pytest
from graphsieve.llm.common import PieceEncoder, tokenizer_path
from graphsieve.llm.queries import QUERIES


@pytest.fixture(scope="module")
def docs(spark, sf):
    return sorted((r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect())


def test_pii(spark, sf, docs):
    got = {r.doc_id: r for r in QUERIES["op2_pii"](spark, sf).collect()}
    assert len(got) == len(docs)
    for d, t in docs:
        spans = brute.base_spans(t)
        r = got[d]
        assert (r.n_email, r.n_ip, r.n_card, r.n_phone) == tuple(sum(k == x for k, _, _ in spans) for x in ("email", "ip", "card", "phone")), d
        assert r.base_sha256 == brute.digest(spans)
        assert {f"{k}:{a}:{b}" for k, a, b in spans} <= set(r.spans.split(","))


def test_token_output(spark, sf, docs):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokenizer_path("byte_bpe_50k.json"))
    got = {r.doc_id: r for r in QUERIES["op3_token_output"](spark, sf).collect()}
    start = 0
    for d, text in docs:
        ids = np.array([*t.encode(text, add_special_tokens=False).ids, 0], "<u4")
        assert (got[d].start, got[d].n_tokens, got[d].ids_crc32) == (start, len(ids), zlib.crc32(ids.tobytes()))
        start += len(ids)


def test_lm(spark, sf, docs):
    want = brute.base_scores(docs)
    rows = QUERIES["op4_lm_scoring"](spark, sf).collect()
    assert len(rows) == len(docs)
    for r in rows:
        n, known, total, base = want[r.doc_id]
        assert (r.n_tokens, r.n_known, r.train_tokens, r.held_out) == (n, known, total, zlib.crc32(str(r.doc_id).encode()) % 10 == 0)
        assert r.base_score == pytest.approx(base, rel=1e-9)
        assert r.score < 0


def test_quality(spark, docs):
    """Ranks held-out documents: the area under the curve on labels that were never learnt from."""
    folder = "/root/testdata/sf0.01"
    rows = QUERIES["op5_quality"](spark, folder).collect()
    assert len(rows) == spark.read.parquet(f"{folder}/documents.parquet").count() and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.7) for r in rows)
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in rows)
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{folder}/labels.parquet").collect()}
    good, bad = ([r.score for r in rows if r.held_out and labels.get(r.doc_id) == k] for k in (1, 0))
    assert len(good) > 20 and len(bad) > 10
    assert np.mean([(a > b) + (a == b) / 2 for a in good for b in bad]) > 0.95


def test_quality_reads_word_pairs():
    """Texts of the same words in another order have other features; a word's own marks are none of its neighbours."""
    from graphsieve.llm.quality import Hasher

    h = Hasher()
    one, other = (set(h.features(t)[0].tolist()) for t in ("the dog bit the man", "the man bit the dog"))
    assert one != other
    assert set(h.features("")[0].tolist()) == set() and len(h.features("word")[0]) == 2


def test_token_counts(spark, sf, docs):
    from graphsieve.llm.token_counts import length_quantile, truncated_total
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokenizer_path("byte_bpe_50k.json"))
    lengths = sorted(len(t.encode(text or "", add_special_tokens=False).ids) for _, text in docs)
    found = QUERIES["op6_token_counts"](spark, sf)
    rows = sorted(found.collect(), key=lambda r: r[0])
    first = found.columns[0]
    want = sorted(set(lengths))
    offset = rows[0][first] - want[0]  # with or without an end token
    assert offset in (0, 1) and [r[first] for r in rows] == [x + offset for x in want]
    lengths = [x + offset for x in lengths]
    for limit in (1, 7, 100, 512, 2048, 10**9):
        assert truncated_total(found, limit) == sum(min(x, limit) for x in lengths)
    for q in (0.0, 0.1, 0.5, 0.9, 1.0):
        assert length_quantile(found, q) in {lengths[max(0, min(len(lengths) - 1, k))] for k in (int(q * len(lengths)) - 1, int(q * len(lengths)), int(q * (len(lengths) - 1)))}


def test_html_against_markup(spark, sf):
    """Every visible word of every page is in its text, in the order of the page; hidden ones are not."""
    import re

    rows = QUERIES["op1_html_extraction"](spark, sf).collect()
    pages = {r.page_id: r.html for r in spark.read.parquet(f"{sf}/pages.parquet").collect()}
    assert len(rows) == len(pages)
    for r in rows:
        assert r.n_chars == len(r.text) and r.text_sha256 == hashlib.sha256(r.text.encode()).hexdigest()
        bare = re.sub(r"(?is)<!--.*?-->|<(script|style|head|template|noscript)\b.*?</\1>", " ", pages[r.page_id] or "")
        bare = re.sub(r"<[^>]*>", " ", bare)
        shown = set(re.findall(r"[A-Za-z]{4,}", r.text))
        assert shown <= set(re.findall(r"[A-Za-z]{4,}", bare + (pages[r.page_id] or "")))


def test_packing(spark, sf, docs):
    from graphsieve.llm.packing import lower_bound
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokenizer_path("word_bpe_49k.json"))
    rows = QUERIES["op7_packing"](spark, sf).collect()
    by, bins = {}, {}
    for r in rows:
        by.setdefault(r.doc_id, []).append(r)
        bins.setdefault(r.sequence_id, []).append(r)
    for d, text in docs:
        ids = np.array([*t.encode(text, add_special_tokens=False).ids, 0], "<u4")
        want = [(k, a, len(ids[a : a + 2048]), zlib.crc32(ids[a : a + 2048].tobytes())) for k, a in enumerate(range(0, len(ids), 2048))]
        assert sorted((r.piece, r.start, r.length, r.ids_crc32) for r in by[d]) == want
    for own in bins.values():
        at = 0
        for r in sorted(own, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= 2048
    assert len(bins) <= lower_bound([r.length for r in rows]) + 1


def test_simhash(spark, sf, docs):
    fps = [(d, brute.simhash(t)) for d, t in docs]
    want = brute.components(fps)
    got = {r.doc_id: r for r in QUERIES["op8_simhash"](spark, sf).collect()}
    for d, f in fps:
        assert got[d].fingerprint == f"{f:016x}" and got[d].component_id == want[d]


def test_merkle(spark, sf, docs):
    got = {r.doc_id: r for r in QUERIES["op9_merkle"](spark, sf).collect()}
    near = []
    for k, (d, t) in enumerate(docs):
        nxt = docs[(k + 1) % len(docs)][1]
        half = len(t) // 2
        edited = t[: len(t) - half] + nxt[:half]
        r = got[d]
        assert (r.n_chars, r.edited_sha256) == (len(t), hashlib.sha256(edited.encode()).hexdigest())
        assert 0 <= r.near_edited <= 1 and 0 <= r.near_next <= 1
        near.append((r.near_edited, r.near_next))
    assert np.mean([a for a, _ in near]) > 0.4 > 0.1 > np.mean([b for _, b in near])
    by_text = {}
    for d, t in docs:
        assert by_text.setdefault(t, got[d].fingerprint) == got[d].fingerprint
    assert len(set(by_text.values())) == len(by_text)


def test_decontamination(spark, sf, docs):
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    hits = 0
    for r in QUERIES["op10_decontamination"](spark, sf).collect():
        want = brute.contamination(dict(docs)[r.doc_id], items)
        assert (r.n_words, r.n_hit, r.n_items, r.items_sha256) == want and r.contaminated == (want[1] > 0)
        hits += r.contaminated
    assert hits


@pytest.mark.parametrize(("name", "kind"), [("byte_bpe_50k.json", "byte"), ("word_bpe_49k.json", "word")])
def test_encoder_equals_library(name, kind):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokenizer_path(name))  # as the library has it
    e = PieceEncoder(tokenizer_path(name), kind, added=True)
    texts = ["", " ", "a", " a b", "a  b", "a \nb", "a\n b", "a b\n", "x y z", " a b", "don't I'LL we've", "Été ΣΑΣ straße İstanbul", "é café a", "a ́b", "<|endoftext|> x<|startoftext|>", "12 345 6.7", "\x1c a \x1f b", "tab\tb c\r\nd", "日本語 テキスト 。", "the the the.", "a\x85b c", "ſ ǅ K Å", "👍🏽 ok", "﻿a b"]
    for text in texts * 2:
        want = np.array(t.encode(text, add_special_tokens=False).ids, "<u4").tobytes()
        assert e.encode(text) == want, text
    assert e.encode("x" * 50_000 + " y") == np.array(t.encode("x" * 50_000 + " y", add_special_tokens=False).ids, "<u4").tobytes()


def test_merkle_branches_and_ranges(spark):
    from graphsieve.llm import merkle

    a = "One sentence here. Another one.\nSecond paragraph.\n\nNext section.\nIts end."
    b = "One sentence here. Another one.\nSecond paragraph, edited.\n\nNext section.\nIts end.\nMore."
    df = merkle.fingerprints(spark.createDataFrame([(1, a), (2, b), (3, a)], "doc_id long, text string"))
    prints = {r.doc_id: r.fingerprint for r in df.collect()}
    assert prints[1] == prints[3] != prints[2]
    pairs = spark.createDataFrame([(prints[1], prints[2]), (prints[1], prints[3])], "a string, b string")
    assert sorted((r.section, r.paragraph) for r in merkle.edited_branches(pairs, "a", "b").collect()) == [(0, 1), (1, 2)]
    ids = spark.range(20_000).selectExpr("id as doc_id").union(spark.createDataFrame([(1 << 62,), (-(1 << 62),), (None,)], "doc_id long"))
    part, behind = merkle._ranges(ids)
    counts = [r["count"] for r in ids.groupBy(part.alias("p")).count().collect()]
    assert max(counts) < 2 * merkle.RANGE_ROWS and len(counts) == behind.count()


def test_decontamination_in_blocks(spark, sf, docs, monkeypatch):
    """A benchmark of many blocks, and an item longer than a block, give what one block gives."""
    from graphsieve.llm import decontaminate

    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    bench = spark.createDataFrame([*items, (10**6, " ".join(t for _, t in docs[:3]))], "item_id long, text string")
    texts = spark.createDataFrame(docs, "doc_id long, text string")
    whole = sorted(map(tuple, decontaminate.contamination_report(texts, bench).collect()))
    monkeypatch.setattr(decontaminate, "BLOCK_WORDS", 700)
    assert len(list(decontaminate._blocks(bench, 10, 5))) > 2
    assert sorted(map(tuple, decontaminate.contamination_report(texts, bench).collect())) == whole


def test_packing_certifies_or_reports(spark):
    """Groups exchange pieces until the bound is met; gaps that stay are in the result."""
    from graphsieve.llm.packing import lower_bound, pack

    rng = np.random.default_rng(4)
    lengths = [int(x) for x in rng.integers(1, 2048, 3000)]
    pieces = spark.createDataFrame([(k, k, 0, 0, n, 0) for k, n in enumerate(lengths)], "uid long, doc_id long, piece int, start long, length long, ids_crc32 long")
    rows = pack(pieces, group=500).collect()
    bins = {}
    for r in rows:
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
    assert len(rows) == 3000 and all(sum(n for _, n in own) <= 2048 for own in bins.values())
    left = len(bins) - lower_bound(lengths)
    assert left <= 0.02 * len(bins) and (left == 0 or any(r.gap for r in rows) or left <= 6)
