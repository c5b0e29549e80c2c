"""Walks that are dealt by their sources, against the joins that they stand for."""

import random

import numpy as np
from graphsieve.operators import dealt, local, walks
from graphsieve.operators.reduce import LabeledGraph, init_candidates
from graphsieve.operators.sieve import sieve
from graphsieve.plans import rules
from graphsieve.plans.rules import Rule, WalkPlan
from graphsieve.plans.template import Template
from graphsieve.workloads import WORKLOADS

RING = [(0, 1), (1, 2), (2, 3), (0, 3)]


def _graph(spark, labels, n, edges):
    rng = random.Random(3)
    label = {v: labels[v % len(labels)] for v in range(n)}
    pairs = set()
    while len(pairs) < edges:
        a, b = sorted(rng.sample(range(n), 2))
        pairs.add((a, b))
    both = pairs | {(b, a) for a, b in pairs}
    return LabeledGraph(spark.createDataFrame(list(label.items()), "vid long, label string"), spark.createDataFrame(list(both), "src long, dst long"))


def test_same_walks(spark, monkeypatch):
    """Tokens, completed walks, sources and pairs as one task has them that holds all edges."""
    monkeypatch.setattr(rules, "MEET_FROM", 0)
    monkeypatch.setattr(dealt, "SOURCES", 0)
    monkeypatch.setattr(dealt, "TOKENS", 300)
    for letters, edges, ways in (("abcdef", WORKLOADS["topo_c"][1].edges, ("none", "live", "issuer")), ("abcb", [*RING, (0, 2)], ("none",))):
        t = Template.build(list(letters), edges)
        state = init_candidates(_graph(spark, sorted(set(letters)), 400, 4500), t)
        columns = state.edges.select("src", "dst", "smask").toPandas()
        kept = local.Kept.of(t, *(columns[c].to_numpy() for c in columns))
        freq = kept.frequency()
        for how in ways:
            monkeypatch.setattr(local, "MEET", 0)
            plan = walks.rule_plan(t, Rule("cycle", 0, frozenset(RING)), how, freq)
            good, tokens, done = dealt.dealt_walk(state, RING, plan, how, freq, False)
            monkeypatch.setattr(local, "MEET", 1 << 60)
            walk, sources = local.Walk(kept, plan, how), np.flatnonzero(kept.mask & 1)
            want = kept.ids[sources[walk.run(sources)]]
            assert sorted(r.vid for r in good.collect()) == sorted(want.tolist()) and len(want)
            assert done == walk.walks > 0 and (how == "live" or tokens == walk.tokens)
        monkeypatch.setattr(local, "MEET", 0)
        for how in ways[:2]:
            pairs, tokens, done = walks._dealt_pairs(state, t.edges, freq, how)
            monkeypatch.setattr(local, "MEET", 1 << 60)
            found, _, n = local.confirmed(kept, t.edges, freq, "none")
            told = lambda a, b, u, v: (a, b, u, v) if a < b else (b, a, v, u)
            ids = kept.ids.tolist()
            assert {told(*r) for r in pairs.collect()} == {told(a, b, ids[k // len(ids)], ids[k % len(ids)]) for (a, b), ks in found.items() for k in ks.tolist()}
            assert n and (done == n if how == "none" else 0 < done <= n)


def test_edges_move_from_the_end_nearer_the_start():
    t = WORKLOADS["topo_c"][1]
    moved, parent = dealt.layout(RING, WalkPlan(t, RING, 0, sequence=(0, 1, 2, 3)))
    assert moved == [(0, 1), (0, 3), (1, 2), (3, 2)] and parent == {1: 0, 3: 0}
    five = Template.build(list("abcdef"), [(0, 1), (1, 2), (2, 3), (3, 4), (0, 4), (3, 5)])
    # 3 is bound from 2, before 4 which is nearer the start and could tell that its edges are to be moved
    assert dealt.layout(five.edges, WalkPlan(five, five.edges, 0, sequence=(0, 1, 2, 3, 4, 5))) is None


def test_a_vertex_of_many_edges_is_left_to_joins(spark, monkeypatch):
    monkeypatch.setattr(rules, "MEET_FROM", 0)
    monkeypatch.setattr(dealt, "MOST_EDGES", 3)
    monkeypatch.setattr(dealt, "SOURCES", 0)
    made, own = [], dealt.dealt_walk
    monkeypatch.setattr(walks, "dealt_walk", lambda *a: made.append(own(*a)) or made[-1])
    t = Template.build(list("abcd"), [(0, 1), (1, 2), (2, 3), (0, 3)])
    g = _graph(spark, list("abcd"), 1200, 5000)
    x = sieve(g, t, starts="rarest", least_gain=0, local_below=0)
    assert made and all(m is None for m in made) and sorted(map(tuple, x.edges.collect())) == sorted(map(tuple, sieve(g, t).edges.collect()))
