"""Stages of the pipeline, one after another over a whole table, each against a plain version on its own input."""

import zlib

import brute
import corpus_pipeline
import numpy as np
from graphsieve.llm.common import materialize, tokenizer_path


def similar_groups(rows):
    """{doc_id: smallest doc_id} by Jaccard similarity of five-word shingles, all against all."""
    sets = {}
    for d, text in rows:
        w = (text or "").lower().split()
        sets[d] = frozenset(tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))) if w else frozenset()
    up = {d: d for d in sets}

    def top(x):
        while up[x] != x:
            x = up[x]
        return x

    ids = sorted(sets)
    for k, a in enumerate(ids):
        for b in ids[k + 1 :]:
            x, y = sets[a], sets[b]
            if x == y or (x and y and len(x & y) * 5 >= 4 * len(x | y)):
                p, q = sorted((top(a), top(b)))
                up[q] = p
    return {d: top(d) for d in ids}


def test_stages(spark, sf):
    from tokenizers import Tokenizer

    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    now = spark.read.parquet(f"{sf}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES:
        given = {r.doc_id: r.text for r in now.collect()}
        now = materialize(stage(spark, now, sf), f"test-{name}")
        got = {r.doc_id: r for r in now.collect()}
        assert given and got
        if name == "near_duplicates":
            groups = similar_groups(list(given.items()))
            assert set(got) == set(groups.values()) and len(got) < len(given)
        if name == "decontamination":
            assert set(got) == {d for d, t in given.items() if not brute.contamination(t, items)[1]} and len(got) < len(given)
        if name == "personal_data":
            assert set(got) == set(given)
            changed = 0
            for d, text in given.items():
                spans = brute.base_spans(text)
                assert all(text[a:b] not in got[d].text for _, a, b in spans)
                assert got[d].n_chars == len(got[d].text)
                changed += bool(spans)
            assert changed
        if name in ("quality", "near_duplicates", "decontamination"):
            assert all(got[d].text == given[d] for d in got)
        if name == "packing":
            t = Tokenizer.from_file(tokenizer_path("word_bpe_49k.json"))
            rows = now.collect()
            for d, text in given.items():
                ids = np.array([*t.encode(text, add_special_tokens=False).ids, 0], "<u4")
                want = [(a, zlib.crc32(ids[a : a + 2048].tobytes())) for a in range(0, len(ids), 2048)]
                assert sorted((r.start, r.ids_crc32) for r in rows if r.doc_id == d) == want
