"""The span classifier weighs every value of its features."""

import math
import random
from collections import defaultdict

import pytest
from graphsieve.llm import pii


def test_pii_weights_of_all_shapes(spark):
    rng = random.Random(1)
    secrets = ["".join(rng.choice("aA7") * rng.choice((1, 2)) for _ in range(30)) for _ in range(700)]
    docs = spark.createDataFrame([(k, f"the token {s} and mail a{k}@b.com") for k, s in enumerate(secrets)], "doc_id long, text string")
    rows = pii.classify(pii._rows(pii.candidates(docs)))[0].collect()
    assert len({(r.kind, r.f_shape) for r in rows}) > 600
    features = ("f_left", "f_right", "f_size", "f_shape", "f_cue")
    yes, no, models = defaultdict(float), defaultdict(float), defaultdict(lambda: defaultdict(int))
    for r in rows:
        models[r.kind][tuple(r[x] for x in pii.LABELERS)] += 1
        for key in ((r.kind,), *((r.kind, f, r[f]) for f in features)):
            yes[key] += r.soft
            no[key] += 1 - r.soft
    prior = {k: pii.estimate_reliability(sorted((*v, n) for v, n in m.items()))["prior"] for k, m in models.items()}
    for r in rows:
        k, p = (r.kind,), prior[r.kind]
        score = math.log(p / (1 - p)) + sum(math.log((yes[r.kind, f, r[f]] + 0.5) / (yes[k] + 1)) - math.log((no[r.kind, f, r[f]] + 0.5) / (no[k] + 1)) for f in features)
        logit = max(-30, min(30, score))
        assert r.probability == pytest.approx(1 / (1 + math.exp(-logit)), rel=1e-6)
