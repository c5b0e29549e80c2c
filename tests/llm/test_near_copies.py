"""The pipeline's near-duplicate stage against planted copies and plain Jaccard similarity."""

import random

import corpus_pipeline
from graphsieve.llm import near_copies


def jaccard(a, b):
    x, y = ({tuple(t.split()[k : k + 5]) for k in range(len(t.split()) - 4)} for t in (a, b))
    return len(x & y) / len(x | y)


def test_planted_copies(spark, monkeypatch):
    rng = random.Random(3)
    rows, near, far = [], [], []
    for k in range(60):
        text = [f"w{rng.randrange(5000)}" for _ in range(300)]
        other = list(text)
        for p in range(5, 300, 300 // (2 + k % 11)):
            other[p] = "changed"
        rows += [(2 * k, " ".join(text)), (2 * k + 1, " ".join(other))]
        (near if jaccard(rows[-2][1], rows[-1][1]) >= 0.8 else far).append(2 * k + 1)
    assert len(near) > 20 and len(far) > 10
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    want = sorted(d for d, _ in rows if d not in near)
    assert sorted(r.doc_id for r in corpus_pipeline.near_duplicates(spark, docs, "").collect()) == want
    # a chain is one group, whole or in blocks
    base = [f"c{k}" for k in range(100)]
    chain = [(k, " ".join(base[3 * k : 3 * k + 60])) for k in range(13)]
    assert jaccard(chain[0][1], chain[1][1]) >= 0.8 > jaccard(chain[0][1], chain[3][1])
    docs = spark.createDataFrame([*chain, (99, None), (98, " ")], "doc_id long, text string")
    for long in (1000, 4):
        monkeypatch.setattr(near_copies, "LONG", long)
        assert sorted(r.doc_id for r in corpus_pipeline.near_duplicates(spark, docs, "").collect()) == [0, 98]
