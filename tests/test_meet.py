"""Steps at which tokens meet the paths between their ends, against brute force."""

import random
from itertools import product

from graphsieve.operators.reduce import LabeledGraph
from graphsieve.operators.sieve import count_matches, sieve
from graphsieve.plans import rules
from graphsieve.plans.rules import WalkPlan
from graphsieve.plans.template import Template
from graphsieve.workloads import WORKLOADS

RING = [(0, 1), (1, 2), (2, 3), (0, 3)]


def test_rings_of_dense_graphs_meet():
    t = WORKLOADS["topo_c"][1]
    counts = {x: 20_000 for x in t.labels} | {(a, b): 300_000 for a in t.labels for b in t.labels}
    hops = WalkPlan(t, RING, 0, counts, keep=(0,)).hops
    assert [s.over is not None for s, _ in hops] == [False, False, True]
    assert len(hops[-1][1]) == 1 and hops[-1][1][0].at == hops[-1][0].over


def test_same_answer(spark, monkeypatch):
    monkeypatch.setattr(rules, "MEET_FROM", 0)
    rng = random.Random(7)
    label = {v: "abcd"[v % 4] for v in range(80)}
    pairs = {tuple(sorted(rng.sample(range(80), 2))) for _ in range(1100)}
    both = pairs | {(b, a) for a, b in pairs}
    own = {x: [v for v in label if label[v] == x] for x in "abcd"}
    for labels, edges in (("abcd", RING), ("abcb", RING), ("abcd", [*RING, (0, 2)])):
        t = Template.build(list(labels), edges)
        want = [m for m in product(*(own[x] for x in labels)) if len(set(m)) == 4 and all((m[a], m[b]) in both for a, b in edges)]
        g = LabeledGraph(spark.createDataFrame(list(label.items()), "vid long, label string"), spark.createDataFrame(list(both), "src long, dst long"))
        met = {(m[x], m[y]) for m in want for a, b in edges for x, y in ((a, b), (b, a))}
        for options in ({}, {"starts": "rarest"}, {"starts": "rarest", "how": "none"}):
            s = sieve(g, t, local_below=0, least_gain=0, **options)
            assert want and {tuple(r) for r in s.edges.collect()} == met
        assert count_matches(s).first().n == len(want)


def test_unfolded_tokens_are_told(spark, sf):
    from graphsieve.workloads import graph

    name, t = WORKLOADS["topo_c"]
    told = {}
    for how in ("none", "live"):
        s = sieve(graph(spark, sf, name, t), t, how=how, starts="rarest", least_gain=0, local_below=0, count_tokens=True)
        told[how] = sum(x["tokens"] for x in s.trace if x["stage"] == "cycle")
    assert told["none"] > told["live"] > 0
