"""Cliques by blocks of vertex ranges against brute force."""

import random
from itertools import combinations

import numpy as np
import pytest
from graphsieve.operators import baselines, cliques


def graph(spark, n=60, m=500, hub=True):
    rng = random.Random(4)
    pairs = {tuple(sorted(rng.sample(range(n), 2))) for _ in range(m)} | ({(0, v) for v in range(1, n)} if hub else set())
    move = (3 << 40) - 7
    pairs = {(a + move, b + move) for a, b in pairs}
    return pairs, spark.createDataFrame([*pairs, *((b, a) for a, b in pairs)], "src long, dst long")


@pytest.mark.parametrize("block", [40, 500, 1_000_000])
def test_blocks(spark, block):
    pairs, edges = graph(spark)
    ids = sorted({v for p in pairs for v in p})
    want = [c for c in combinations(ids, 3) if all(p in pairs for p in combinations(c, 2))]
    three = cliques.triangles(edges, block)
    assert sorted(map(tuple, three.collect())) == want
    for k in (4, 5):
        three = cliques.grow(three)
        want = [(*c, v) for c in want for v in ids if v > c[-1] and all((x, v) in pairs for x in c)]
        assert want and sorted(map(tuple, three.collect())) == want


def test_packs(monkeypatch):
    monkeypatch.setattr(cliques, "PACKED", 50)
    rows = np.arange(999).reshape(3, -1) * (1 << 33)
    packs = list(cliques._packed([[c[:7] for c in rows], [c[7:] for c in rows]]))
    told = [(place, *r) for place, cols in cliques._unpacked(packs, 3) for r in zip(*cols)]
    assert sorted(x[1:] for x in told) == sorted(zip(*rows)) and len({x[0] for x in told}) > 100 and 1 < len(packs) < 99


def test_sieve_of_cliques_stores_no_graph(spark, sf):
    from graphsieve import workloads
    from graphsieve.registry import QUERIES

    workloads.forget()
    four = QUERIES["clique4_sieve"](spark, sf).first().n
    assert not any(k[3] == "graph" for k in workloads._made)
    assert four == QUERIES["clique4"](spark, sf).first().n > 0


def test_wedges_stay_in_tasks(spark):
    _, edges = graph(spark)
    for k in (3, 4):
        plan = baselines.clique_grow(edges, k)._jdf.queryExecution().optimizedPlan().toString()
        assert "LeftSemi" not in plan and "Join" not in plan
    assert baselines.clique_grow(edges.limit(0), 4).count() == 0
    assert baselines.clique_grow(edges.filter("src = 0 or dst = 0"), 3).columns == ["c0", "c1", "c2"]


def test_triangle_count_joins_nothing(spark, sf):
    from graphsieve.registry import QUERIES

    out = QUERIES["triangle_count"](spark, sf)
    plan = out._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan and out.columns == ["n"]
    up = spark.read.parquet(f"{sf}/lineitem.parquet").select("l_orderkey", "l_partkey").distinct()
    sets = {}
    for order, part in up.collect():
        sets.setdefault(order, set()).add(part)
    near = {}
    for parts in sets.values():
        for a in parts:
            near.setdefault(a, set()).update(x for x in parts if x > a)
    assert out.first().n == sum(len(near[a] & near.get(b, set())) for a in near for b in near[a])


@pytest.mark.parametrize("k", [3, 4])
def test_sieve_walks_no_wedges(spark, k, monkeypatch):
    from graphsieve.operators import walks
    from graphsieve.operators.reduce import LabeledGraph
    from graphsieve.operators.sieve import count_matches, sieve
    from graphsieve.plans.template import Template
    from pyspark.sql import functions as F

    pairs, edges = graph(spark)
    ids = sorted({v for p in pairs for v in p})
    want = [c for c in combinations(ids, k) if all(p in pairs for p in combinations(c, 2))]
    g = LabeledGraph(edges.select(F.col("src").alias("vid"), F.lit("*").alias("label")).distinct(), edges)
    monkeypatch.setattr(walks, "hop", None)  # the walk's expansion
    t = Template.unlabelled([(a, b) for b in range(k) for a in range(b)])
    s = sieve(g, t, local_below=0, least_gain=0)
    near = {p for c in want for p in combinations(c, 2)}
    assert want and {tuple(r) for r in s.edges.collect()} == near | {(b, a) for a, b in near}
    assert {tuple(r) for r in s.role_map().collect()} == {(v, q) for c in want for v in c for q in range(k)}
    assert count_matches(s, "subgraphs").first().n == len(want)
    assert count_matches(s).first().n == len(want) * (6 if k == 3 else 24)
