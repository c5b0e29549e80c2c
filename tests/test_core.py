"""Hand fixtures and random graphs against brute force."""

import random
from itertools import permutations

import pytest
from pyspark.sql import functions as F
from graphsieve.operators import baselines, explore, layout, measures
from graphsieve.operators.reduce import LabeledGraph, init_candidates, labelled_edges, neighbourhood_fixpoint, symmetric
from graphsieve.operators.sieve import count_matches, enumerate_matches, has_match, sieve
from graphsieve.operators.walks import hubs_of, rule_plan, walk_sources
from graphsieve.plans.rules import Rule, WalkPlan, cycle_rules, extra_covers, generate, schedule
from graphsieve.plans.template import Template, TemplateProfile
from graphsieve.sources.graphs import dictionary, store


def graph(spark, labels, edges):
    """A written graph: rows from the driver are slow to read again and again."""
    v = spark.createDataFrame([(k, x) for k, x in enumerate(labels)] if not isinstance(labels, dict) else list(labels.items()), "vid long, label string").coalesce(1)
    return store(v, symmetric(spark.createDataFrame([tuple(e) for e in edges], "src long, dst long").coalesce(1)).coalesce(1), "test")


def brute(labels, edges, t):
    labels = dict(enumerate(labels)) if not isinstance(labels, dict) else labels
    es = {(a, b) for a, b in edges} | {(b, a) for a, b in edges}
    return [m for m in permutations(labels, t.n) if all(labels[v] == x for v, x in zip(m, t.labels)) and all((m[a], m[b]) in es for a, b in t.edges)]


def answer(s):
    return {r.vid: tuple(r.roles) for r in s.vertices.collect()}, {(r.src, r.dst) for r in s.edges.collect()}


def exact(ms, t):
    roles = {}
    for m in ms:
        for q, v in enumerate(m):
            roles.setdefault(v, set()).add(q)
    return {v: tuple(sorted(x)) for v, x in roles.items()}, {p for m in ms for a, b in t.edges for p in ((m[a], m[b]), (m[b], m[a]))}


TRI = Template.parse("(a:a)-(b:b)-(c:c), (a)-(c)")
FIXTURES = {
    "unrolled": (TRI, {**dict(enumerate("abcabc")), 10: "a", 11: "b", 12: "c"}, [(0, 1), (1, 2), (2, 3), (3, 4), (4, 5), (5, 0), (10, 11), (11, 12), (12, 10)]),
    "ends_differ": (Template.parse("(a:a)-(b:b)-(c:c)-(d:a)"), dict(enumerate("abc")), [(0, 1), (1, 2), (0, 2)]),
    "joint_cover": (Template.build("dbceaaa", [(0, 1), (0, 2), (0, 3), (1, 4), (2, 5), (3, 6)]), dict(enumerate("dbceaa")), [(0, 1), (0, 2), (0, 3), *((x, y) for x in (1, 2, 3) for y in (4, 5))]),
    "false_edge": (TRI, dict(enumerate("abcabc")), [(0, 1), (1, 2), (0, 2), (3, 4), (4, 5), (3, 5), (0, 4)]),
    "star": (Template.build("xbbb", [(0, 1), (0, 2), (0, 3)]), dict(enumerate("xbb")), [(0, 1), (0, 2)]),
    "hall": (Template.build("xbbbcc", [(0, 1), (0, 2), (0, 3), (2, 4), (3, 5)]), dict(enumerate("xbbbcc")), [(0, 1), (0, 2), (0, 3), (1, 4), (1, 5)]),
    "fold": (Template.build("abcdb", [(0, 1), (1, 2), (2, 3), (3, 4), (4, 0)]), dict(enumerate("abbcd")), [(0, 1), (0, 2), (1, 3), (2, 3), (3, 4), (4, 1)]),
    "tree": (Template.parse("(a:a)-(b:b)-(c:c)-(d:d)"), dict(enumerate("abcdabcdc")), [(0, 1), (1, 2), (2, 3), (4, 5), (5, 6), (7, 8)]),
    "not_induced": (Template.parse("(a:a)-(b:b)-(c:c)"), dict(enumerate("abc")), [(0, 1), (1, 2), (0, 2)]),
}


@pytest.mark.parametrize("name", FIXTURES)
def test_fixtures(spark, name):
    """The single task, and the distributed engine where a fixture tells something of it."""
    t, labels, edges = FIXTURES[name]
    ms = brute(labels, edges, t)
    g = graph(spark, labels, edges)
    for options in ({}, {"starts": "every", "least_gain": 0}, {"how": "none", "least_gain": 0}, *([{"local_below": 0, "least_gain": 0}] if name in ("false_edge", "fold", "star") else [])):
        s = sieve(g, t, **options)
        assert answer(s) == exact(ms, t), options
    assert count_matches(s).first().n == len(ms)
    assert sorted(map(tuple, enumerate_matches(s).collect())) == sorted(ms)
    assert has_match(g, t) == bool(ms)


def test_levels_of_the_neighbourhood_check(spark):
    t, labels, edges = FIXTURES["hall"]
    g = graph(spark, labels, edges)
    kept = {r: neighbourhood_fixpoint(init_candidates(g, t), t, r).counts()[0] for r in ("set", "count", "hall")}
    assert kept == {"set": 6, "count": 6, "hall": 0}
    t, labels, edges = FIXTURES["star"]
    kept = {r: neighbourhood_fixpoint(init_candidates(graph(spark, labels, edges), t), t, r).counts()[0] for r in ("set", "count", "hall")}
    assert kept == {"set": 3, "count": 0, "hall": 0}


def test_rounds_of_a_tree(spark):
    t, labels, edges = FIXTURES["tree"]
    s = sieve(graph(spark, labels, edges), t)
    assert s.trace[0]["rounds"] <= TemplateProfile.of(t).diameter + 1 and len(s.trace) == 1


def test_issuer_tokens_are_refused_where_unsafe(spark):
    t, labels, edges = FIXTURES["fold"]
    s = init_candidates(graph(spark, labels, edges), t)
    with pytest.raises(ValueError):
        walk_sources(s, Rule("cycle", 0, frozenset(t.edges)), "issuer")
    # where labels differ, tokens carry their issuer and last position alone
    plan = rule_plan(TRI, Rule("cycle", 1, frozenset(TRI.edges)), "issuer")
    assert [sorted({*step.live, 1}) for step, _ in plan.hops][0] == sorted({1, plan.hops[0][0].to})


def test_torus_without_cliques(spark):
    edges = []
    for x in range(4):
        for y in range(3):
            at = lambda a, b: a % 4 * 3 + b % 3
            edges += [(at(x, y), at(x + 1, y)), (at(x, y), at(x, y + 1)), (at(x, y), at(x + 1, y + 1))]
    g = graph(spark, "*" * 12, edges)
    assert count_matches(sieve(g, Template.unlabelled([(0, 1), (0, 2), (1, 2)])), "subgraphs").first().n == 28
    two = Template.unlabelled([(0, 1), (0, 2), (1, 2), (0, 3), (1, 3), (2, 3), (0, 4), (1, 4), (2, 4)])
    assert not has_match(g, two)


def test_counting_units(spark):
    k4 = Template.unlabelled([(a, b) for a in range(4) for b in range(a)])
    g = graph(spark, "****", k4.edges)
    s = sieve(g, k4)
    assert count_matches(s).first().n == 24 == len(k4.automorphisms) and count_matches(s, "subgraphs").first().n == 1
    assert baselines.clique_grow(g.edges, 4).count() == 1
    p = Template.parse("(a:*)-(b:*)-(c:*)")
    assert enumerate_matches(sieve(g, p), induced_in=g.edges).count() == 0


def test_variants_of_a_six_clique():
    k6 = Template.build("abcdef", [(a, b) for a in range(6) for b in range(a)])
    assert [len(k6.relaxations(k)) for k in range(5)] == [1, 15, 105, 455, 1365]


def test_exploration_and_revisions(spark):
    k4 = Template.build("opsc", [(a, b) for a in range(4) for b in range(a)])
    labels, edges = dict(enumerate("opsco")), [(0, 1), (0, 2), (1, 2), (0, 3), (3, 4), (1, 4)]
    g = graph(spark, labels, edges)
    r = explore.explore(g, k4)
    assert r.level == 2 and {(x.src, x.dst) for x in r.union_edges().collect()} == {p for a, b in [(0, 1), (0, 2), (1, 2), (0, 3)] for p in ((a, b), (b, a))}
    t, labels, edges = FIXTURES["false_edge"]
    g = graph(spark, {**labels, 6: "d", 7: "d"}, [*edges, (2, 6), (2, 7)])
    path, whole = Template.build("abcd", [(0, 1), (1, 2), (2, 3)]), Template.build("abcd", [(0, 1), (1, 2), (2, 3), (0, 2)])
    steps = [("add", 0, 2), ("remove", 0, 1)]
    answers = {m: [answer(s) for s in explore.run_revisions(g, path, steps, whole, m)] for m in ("independent", "superset", "superset_memo")}
    assert answers["independent"] == answers["superset"] == answers["superset_memo"]
    session = explore.IncrementalSession(g, path, whole)
    assert session.stats()["vertices"] == len(answers["independent"][0][0])
    with pytest.raises(ValueError):
        explore.IncrementalSession(g, path).remove_edge(0, 1)


def test_rules():
    t = Template.build("abcda", [(0, 1), (1, 2), (0, 2), (1, 3), (2, 3), (3, 4)])
    starts = [r.start for r in cycle_rules(TemplateProfile.of(t), True, {"a": 3, "b": 2, "c": 1, "d": 0})]
    assert starts[:3] == [2, 1, 0]  # every role of the first cycle, the rarest label first
    assert [r.start for r in cycle_rules(TemplateProfile.of(t), False, {"a": 3, "b": 2, "c": 1, "d": 0})][0] == 2
    assert len(extra_covers(TemplateProfile.of(t), 3)) <= 3 and all(len(c) < len(t.edges) for c in extra_covers(TemplateProfile.of(t), 3))
    assert Rule("cycle", 1, frozenset([(0, 1), (1, 2), (0, 2)])).sequence() in ((1, 0, 2), (1, 2, 0))
    assert [step.to for step in WalkPlan(TRI, TRI.edges, 0, sequence=(0, 2, 1)).steps][0] == 2
    rules = schedule(generate(t, every_start=False))
    assert [r.kind for r in rules if r.kind == "cycle"] == ["cycle"] * 3
    assert [r.length for r in rules if r.kind != "cover"] == sorted(r.length for r in rules if r.kind != "cover")
    assert generate(Template.parse("(a:a)-(b:b)-(c:c)")) == []
    assert Template.from_json(t.to_json()) == t


def test_degenerate(spark):
    g = graph(spark, {0: "a", 1: None, 2: "b"}, [(0, 0), (0, 1), (0, 2), (2, 0)])
    assert answer(sieve(g, Template.build("a", []))) == ({0: (0,)}, set())
    assert answer(sieve(g, Template.parse("(a:a)-(b:b)"))) == ({0: (0,), 2: (1,)}, {(0, 2), (2, 0)})
    assert answer(sieve(g, Template.parse("(a:a)-(b:z)"))) == ({}, set())
    empty = LabeledGraph(g.vertices.limit(0), g.edges.limit(0))
    assert answer(sieve(empty, TRI)) == ({}, set())


@pytest.mark.parametrize("seed", range(2))
def test_random(spark, seed):
    rnd = random.Random(seed)
    labels = [rnd.choice("abc"[: 1 + seed % 3]) for _ in range(9)]
    edges = [(a, b) for a in range(9) for b in range(a) if rnd.random() < 0.35] or [(0, 1)]
    n = rnd.randint(3, 4)
    tl = [rnd.choice("abc"[: 1 + seed % 3]) for _ in range(n)]
    te = {(rnd.randrange(k), k) for k in range(1, n)} | {(a, b) for b in range(n) for a in range(b) if rnd.random() < 0.4}
    t, g = Template.build(tl, te), graph(spark, labels, edges)
    ms = brute(labels, edges, t)
    s = sieve(g, t)
    assert answer(s) == exact(ms, t)
    assert count_matches(s).first().n == len(ms) and count_matches(s, "subgraphs").first().n * len(t.automorphisms) == len(ms)
    assert baselines.triple_join(g, t).count() == len(ms) == baselines.replicated_enumerate(g, t).count()


def test_layout(spark, tmp_path):
    t, labels, edges = FIXTURES["false_edge"]
    g = graph(spark, labels, edges)
    s = neighbourhood_fixpoint(init_candidates(g, t), t)
    assert s.counts()[1] == s.rows == s.edges.count()
    layout.save(s, f"file://{tmp_path}/s")
    again = layout.consolidate(layout.rebalance(layout.load(spark, f"file://{tmp_path}/s"), 3))
    assert answer(sieve(g, t, state=again)) == answer(sieve(g, t))
    assert {tuple(r) for r in layout.salted_degrees(g.edges, 3).collect()} == {tuple(r) for r in g.edges.groupBy("src").count().collect()}
    pr = measures.precision_recall(s.edges, sieve(g, t).edges, ["src", "dst"])
    assert pr["recall"] == 1 and pr["precision"] == 12 / 14


def test_edges_with_labels_and_directions(spark):
    """Parallel edges, labels and directions against brute force, on both engines."""
    rnd = random.Random(5)
    labels = {k: "abc"[k % 3] for k in range(12)}
    rows = sorted({(rnd.randrange(12), rnd.randrange(12), rnd.choice("xy")) for _ in range(90)})
    v = spark.createDataFrame(list(labels.items()), "vid long, label string")
    g = store(v, labelled_edges(spark.createDataFrame(rows, "src long, dst long, elabel string"), F.col("elabel")), "typed")
    for text in ("(p:a)-[x]->(q:b)-(r:c), (r)->(p)", "(p:a)-[y]-(q:b)-[x]->(r:a)", "(p:a)->(q:a)"):
        t = Template.parse(text)
        assert Template.from_json(t.to_json()) == t
        told = {(a, b): (x, way) for a, b, x, way in t.demands}

        def fits(m, a, b, told=told):
            x, way = told.get((a, b)) or told.get((b, a)) or (None, False)
            there = [(p, q, z) for p, q, z in rows if {p, q} == {m[a], m[b]} and p != q and x in (None, z)]
            p, q = (m[a], m[b]) if (a, b) in told else (m[b], m[a])
            return any(not way or (r[0], r[1]) == (p, q) for r in there)

        ms = [m for m in permutations(labels, t.n) if all(labels[x] == y for x, y in zip(m, t.labels)) and all(fits(m, a, b) for a, b in t.edges)]
        for options in ({}, {"local_below": 0}):
            s = sieve(g, t, **options)
            assert answer(s) == exact(ms, t), (text, options)
        assert sorted(map(tuple, enumerate_matches(s).collect())) == sorted(ms)
    plain = Template.parse("(p:a)-(q:b)")
    assert sieve(g, plain).state.rows == sieve(LabeledGraph(v, symmetric(spark.createDataFrame(rows, "src long, dst long, elabel string"))), plain).state.rows


def test_hub_is_spread(spark):
    """A star's hub: with salts its tokens and edges go to many tasks, and the answer stays."""
    n = 3000
    g = store(spark.range(n + 1).select(F.col("id").alias("vid"), F.when(F.col("id") == 0, "hub").when(F.col("id") % 2 == 0, "b").otherwise("c").alias("label")), symmetric(spark.range(1, n + 1).select(F.lit(0).alias("src"), F.col("id").alias("dst")).unionByName(spark.range(1, n, 2).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst")))), "star")
    t = Template.parse("(c:c)-(h:hub)-(b:b), (c)-(b)")
    plain, salted = sieve(g, t), sieve(g, t, local_below=0, hub_degree=100)
    assert plain.state.rows == salted.state.rows == 3 * n and count_matches(plain).first().n == n // 2
    state = init_candidates(g, t)
    hubs = hubs_of(state, 100, 0)
    assert [r.hub for r in hubs.collect()] == [0] and hubs_of(state) is None
    loads = [r["edges"] for r in layout.partition_loads(layout.spread_hubs(g.edges.select("src", "dst"), 100, 64).filter("src = 0").withColumn("src", F.col("salt").cast("long")), 8).collect()]
    assert len(loads) == 8 and max(loads) < 2 * sorted(loads)[4]


def test_depth_first_in_parts(spark, monkeypatch):
    """Tokens that exceed the cap are walked a part at a time; the answer is the same."""
    import numpy as np
    from graphsieve.operators import local

    rnd = random.Random(2)
    labels = ["abc"[k % 3] for k in range(60)]
    edges = [(a, b) for a in range(60) for b in range(a) if rnd.random() < 0.2]
    t = Template.build("abcab", [(0, 1), (1, 2), (2, 3), (3, 4), (4, 0)])
    pairs = np.array([*edges, *[(b, a) for a, b in edges]])
    found = []
    for cap in (10**6, 50, 1):
        monkeypatch.setattr(local.Walk.__init__, "__defaults__", ("live", False, False, cap))
        kept = local.Kept.of(t, pairs[:, 0], pairs[:, 1], np.array([t.by_label[labels[a]] for a in pairs[:, 0]]))
        local.sieve_kept(kept)
        found.append((kept.s.tolist(), kept.d.tolist(), kept.mask.tolist()))
    assert found[0] == found[1] == found[2] and found[0][0]


def test_dictionary(spark):
    """Every distinct value has its place in sorted order, over many partitions; nulls have none."""
    words = [f"w{k * 7919 % 5000}" for k in range(6000)] + [None]
    got = {r.w: r.place for r in dictionary(spark.createDataFrame([(w,) for w in words], "w string").repartition(13)).collect()}
    assert got == {w: k for k, w in enumerate(sorted({w for w in words if w}))}


def test_exploration_of_six_brands(spark):
    """Variants of a level solved together are those solved one by one."""
    rnd = random.Random(9)
    labels = ["abcdef"[k % 6] for k in range(24)]
    edges = [(a, b) for a in range(24) for b in range(a) if rnd.random() < 0.35]
    g = graph(spark, labels, edges)
    k6 = Template.build("abcdef", [(a, b) for a in range(6) for b in range(a)])
    r = explore.explore(g, k6)
    assert r.level and [x["variants"] for x in r.levels] == [1, 15, 105, 455, 1365, 3003][: r.level + 1]
    assert all(x["matched"] == 0 for x in r.levels[:-1]) and r.levels[-1]["matched"] and r.levels[-1]["reused"]
    want = set()
    for x in k6.relaxations(r.level):
        at = {(a, b) for a, b in edges} | {(b, a) for a, b in edges}
        near = {v: {w for p, w in at if p == v} for v in range(24)}
        partial = [()]
        for q in range(6):
            partial = [(*m, v) for m in partial for v in range(24) if labels[v] == x.labels[q] and v not in m and all(v in near[m[p]] for p in x.adjacent[q] if p < q)]
        want |= exact(partial, x)[1]
    assert {tuple(e) for e in r.union_edges().collect()} == want
