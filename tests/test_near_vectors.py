"""Neighbours of vectors by blocks against all pairs at once."""

import numpy as np
import pytest
from graphsieve.sources.graphs import near_vectors


@pytest.mark.parametrize("block", [1, 7, 1_000])
def test_blocks(spark, block):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(41, 6)).astype(np.float32)
    x[5], x[9] = 0, x[8]
    rows = [(k * 3, v.tolist()) for k, v in enumerate(x)]
    unit = x.astype(float)
    unit /= np.maximum(np.sqrt((unit * unit).sum(1, keepdims=True)), 1e-300)
    want = {(a * 3, b * 3) for a, b in zip(*np.nonzero(np.round(unit @ unit.T, 9) >= 0.35)) if a < b}
    got = list(map(tuple, near_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<float>"), 0.35, block).collect()))
    assert len(got) == len(set(got)) and set(got) == want and (24, 27) in want


def test_more_vectors_than_one_block_and_none(spark):
    v = spark.createDataFrame([(1, [1.0])], "vec_id long, embedding array<float>")
    assert near_vectors(v.limit(0), 0.35).count() == 0
    # 60,000 vectors were refused
    many = spark.range(60_000).selectExpr("id as vec_id", "array(cast(cos(id) as float), cast(sin(id) as float)) as embedding")
    assert near_vectors(many, 2.0).count() == 0
