"""Roles are taken away by joining one direction of the edges; labels are carried as numbers while edges are picked."""

import random
import re

from graphsieve.operators import reduce
from graphsieve.operators.reduce import State, apply_masks
from graphsieve.plans.template import Template
from graphsieve.sources.graphs import build
from graphsieve.workloads import WORKLOADS

T = Template.build(list("abc"), [(0, 1), (1, 2), (0, 2)])


def test_one_direction_is_joined(spark, monkeypatch):
    rng = random.Random(3)
    pairs = {tuple(sorted(rng.sample(range(60), 2))) for _ in range(400)}
    pairs = [(a, b) for a, b in pairs if a % 3 != b % 3]
    before = {v: 1 << v % 3 for v in range(60)}
    after = {v: m * (rng.random() < 0.6) for v, m in before.items()}
    edges = spark.createDataFrame([(x, y, before[x], before[y]) for a, b in pairs for x, y in ((a, b), (b, a))], "src long, dst long, smask long, dmask long")
    plans, own = {}, reduce.written

    def told(df, name, *args, **more):
        plans[name] = df._jdf.queryExecution().optimizedPlan().toString()
        return own(df, name, *args, **more)

    monkeypatch.setattr(reduce, "written", told)
    for eliminate in ("both", "vertices"):
        masks = spark.createDataFrame([(v, before[v], after[v]) for v in before], "vid long, mask long, new long")
        out, seen = apply_masks(State(T, edges, 2 * len(pairs), borrowed=True), masks, eliminate)
        want = sorted((x, y, after[x], after[y]) for a, b in pairs if after[a] and after[b] for x, y in ((a, b), (b, a)))
        assert want and sorted(map(tuple, out.edges.collect())) == want and out.rows == len(want)
        assert re.search(r"src#\d+L > dst#\d+L", plans["edges"])


def test_labels_are_numbers_in_the_distinct(spark, sf):
    name, t = WORKLOADS["w6"]
    plan = build(spark, sf, name, t).edges._jdf.queryExecution().optimizedPlan().toString()
    grouped = [x for x in plan.splitlines() if "Aggregate [a#" in x]
    assert grouped and len(re.findall(r"THEN 0 WHEN", plan)) >= len(grouped)
