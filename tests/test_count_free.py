"""Counts with the test of different vertices taken off afterwards."""

import random

import pytest
from graphsieve.operators import sieve as op
from graphsieve.operators.reduce import LabeledGraph, symmetric
from graphsieve.plans.template import Template

STAR = Template.unlabelled([(0, 1), (0, 2), (0, 3)], "a")
PATH = Template.build("abcab", [(0, 1), (1, 2), (2, 3), (3, 4)])


def graph(spark, labels, n=24, m=70):
    rng = random.Random(11)
    pairs = {tuple(sorted(rng.sample(range(n), 2))) for _ in range(m)}
    v = {k: labels[k % len(labels)] for k in range(n)}
    near = {k: {b if a == k else a for a, b in pairs if k in (a, b)} for k in v}
    return v, near, LabeledGraph(spark.createDataFrame([*v.items()], "vid long, label string"), symmetric(spark.createDataFrame([*pairs], "src long, dst long")))


def brute(t, v, near):
    def go(bound):
        q = len(bound)
        if q == t.n:
            return 1
        return sum(go([*bound, x]) for x in v if v[x] == t.labels[q] and x not in bound and all(x in near[bound[y]] for y in t.adjacent[q] if y < q))

    return go([])


@pytest.mark.parametrize("t", [STAR, PATH])
@pytest.mark.parametrize("free", [True, False])
def test_counts(spark, monkeypatch, t, free):
    v, near, g = graph(spark, sorted(set(t.labels)))
    monkeypatch.setattr(op, "walk_cost", lambda t, f, start, differ=True: (1e9 if differ else 0) if free else (0 if differ else 1))
    for buckets in (1, 3):
        assert op.count_matches(op.sieve(g, t), buckets=buckets).first().n == brute(t, v, near) > 0


def test_pairs_of_one_label_are_not_carried():
    """A nation's orders by customer and by supplier: the plan of the free walk keeps no two orders in a token."""
    from graphsieve.plans.rules import WalkPlan, best_start, walk_cost

    t = Template.build(["order", "cust", "nation", "supplier", "order"], [(0, 1), (1, 2), (2, 3), (3, 4)])
    n = {"order": 22_000, "cust": 18_000, "nation": 25, "supplier": 6_000}
    n |= {k: x for (a, b), x in {("order", "cust"): 4_500, ("cust", "nation"): 18_000, ("nation", "supplier"): 6_000, ("supplier", "order"): 90_000}.items() for k in ((a, b), (b, a))}
    start = best_start(t, t.edges, n, differ=False)
    assert all(len(step.live) <= 1 for step in WalkPlan(t, t.edges, start, n, differ=False).steps)
    assert walk_cost(t, n, start, differ=False) * 10 < walk_cost(t, n, best_start(t, t.edges, n))
