"""Candidates by SimHash in the near-duplicate stage."""

import numpy as np
from graphsieve.llm import near_copies, simhash


def test_simhash_gives_candidates(spark):
    """Texts without a key in common come together by fingerprints of up to four bits, and only by those."""
    base = 0x0123456789ABCDE
    fps = [base, base ^ 0b1111, base ^ 0b11111 << 40, base]
    single = spark.createDataFrame([(10 + k, fp, [100 + k]) for k, fp in enumerate(fps)], "row long, fp long, keys array<long>")
    got = {tuple(sorted(r)) for r in near_copies.candidates(single).collect()}
    assert got == {(10, 11), (10, 13)}
    same = np.arange(50, dtype=np.uint64)
    found = near_copies.forest([10, 11, 12, 13], [same] * 4, np.arange(4)[:, None], np.array(fps, np.uint64))
    assert {x for pair in found for x in pair} == {10, 11, 13}


def test_sketches_hold_fingerprints(spark):
    texts = ["a b c d e f g", "one two", "", None, "x " * 300 + "y"]
    rows = near_copies._sketches(spark.createDataFrame([(k, k, t) for k, t in enumerate(texts)], "_row long, doc_id long, text string")).collect()
    assert {r.row: r.fp & (1 << 64) - 1 for r in rows} == {k: simhash.fingerprint_of((t or "").encode(), 5) for k, t in enumerate(texts)}
