"""Two roles of one label that no edge joins: walks keep two vertices of the first, and the answer stays exact."""

import random

import pytest
from graphsieve.operators import walks
from graphsieve.operators.reduce import LabeledGraph, init_candidates, symmetric
from graphsieve.operators.sieve import sieve
from graphsieve.operators.walks import confirmed_pairs
from graphsieve.plans.rules import lone_pair
from graphsieve.plans.template import Template

PATH = Template.build("abcda", [(0, 1), (1, 2), (2, 3), (3, 4)])
KITE = Template.build("abca", [(0, 1), (1, 2), (2, 3), (0, 2)])


def graph(spark, seed, m, n=30):
    rng = random.Random(seed)
    pairs = {tuple(sorted(rng.sample(range(n), 2))) for _ in range(m)}
    v = {k: "abcd"[k % 4] for k in range(n)}
    near = {k: {b if a == k else a for a, b in pairs if k in (a, b)} for k in v}
    return v, near, LabeledGraph(spark.createDataFrame([*v.items()], "vid long, label string"), symmetric(spark.createDataFrame([*pairs], "src long, dst long")))


def brute(t, v, near):
    found = [[]]
    for q in range(t.n):
        found = [[*f, x] for f in found for x in v if v[x] == t.labels[q] and x not in f and all(x in near[f[y]] for y in t.adjacent[q] if y < q)]
    return {(a, b, f[a], f[b]) for f in found for a, b in t.edges}


@pytest.mark.parametrize("t, m", [(PATH, 100), (KITE, 200)])
def test_pairs(spark, t, m):
    v, near, g = graph(spark, 1, m=m)
    want, state = brute(t, v, near), init_candidates(g, t)
    assert lone_pair(t, t.edges) == (0, t.n - 1)
    for freq in ({"c": -1}, {"a": 9, "b": 1}):  # walks from one end, from the middle
        got = {(r.a, r.b, r.u, r.v) if r.a < r.b else (r.b, r.a, r.v, r.u) for r in confirmed_pairs(state, t.edges, freq).collect()}
        assert got == want and want
    edges = {(r.src, r.dst) for r in sieve(g, t, local_below=0).edges.collect()}
    assert edges == {e for _, _, a, b in want for e in ((a, b), (b, a))}


def test_tokens_do_not_multiply(spark, monkeypatch):
    """A hub of 60 vertices on either side: 3,540 matches, but no table of them."""
    one = [(0, k) for k in range(1, 61)] + [(100, k) for k in range(61, 121)] + [(0, 200), (200, 100)]
    v = [(0, "b"), (100, "d"), (200, "c"), *((k, "a") for k in range(1, 121) if k != 100), (300, "a")]
    one = [(a, 300 if b == 100 else b) for a, b in one[:-2]] + one[-2:]
    g = LabeledGraph(spark.createDataFrame(v, "vid long, label string"), symmetric(spark.createDataFrame(one, "src long, dst long")))
    most, old = [], walks.written

    def noted(df, name, **more):
        out = old(df, name, **more)
        most.append(out[1]["rows"])
        return out

    monkeypatch.setattr(walks, "written", noted)
    assert len(sieve(g, PATH, local_below=0).edges.collect()) == 2 * 122
    assert max(most) <= 2 * 122
