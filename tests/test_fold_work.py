"""Every way of folding is a whole search of its own, and tells its own tokens and completed walks."""

import pytest
from graphsieve import registry
from graphsieve.operators.reduce import LabeledGraph
from graphsieve.operators.sieve import count_matches, sieve
from graphsieve.plans.template import Template
from graphsieve.workloads import WORKLOADS, graph


def test_every_way_confirms(spark, sf, monkeypatch):
    made, own = [], registry.sieve
    monkeypatch.setattr(registry, "sieve", lambda *a, **k: made.append((k["how"], own(*a, **k))) or made[-1][1])
    rows = registry.QUERIES["abl_fold_work"](spark, sf).collect()
    assert [how for how, _ in made] == ["none", "live", "issuer"] * 3
    for r, (_, x) in zip(rows, made):
        assert x.exact and x.trace[-1]["stage"] == "confirm" and r.e_star == x.state.rows == x.edges.count()
        assert (r.tokens, r.walks) == (sum(y.get("tokens", 0) for y in x.trace), sum(y.get("walks", 0) for y in x.trace))
    told = {(r.workload, r.fold): r for r in rows}
    for w in ("w6", "rank_q8", "topo_c"):
        name, t = WORKLOADS[w]
        alone = sieve(graph(spark, sf, name, t), t, how="live", starts="rarest", least_gain=0)
        assert told[w, "live"].tokens == sum(y.get("tokens", 0) for y in alone.trace) and told[w, "live"].e_star == alone.state.rows
    assert told["topo_c", "none"].tokens > told["topo_c", "live"].tokens


@pytest.mark.parametrize("w", ["w2", "w6", "topo_c"])
def test_unfolded_walks_are_the_matches(spark, sf, w):
    """Both engines: confirmation without folding completes a walk for each match, and leaves the same answer."""
    name, t = WORKLOADS[w]
    g = graph(spark, sf, name, t)
    whole = sieve(g, t)
    n, edges = count_matches(whole).first().n, sorted(map(tuple, whole.edges.collect()))
    tokens = set()
    for below in (0, 1_000_000):
        x = sieve(g, t, how="none", starts="rarest", least_gain=0, count_tokens=True, local_below=below)
        assert x.trace[-1]["walks"] == n and sorted(map(tuple, x.edges.collect())) == edges
        tokens.add(tuple(y["tokens"] for y in x.trace if y["stage"] in ("cycle", "path", "cover")))
    assert len(tokens) == 1


def test_walks_that_end_early_are_counted(spark):
    """Rules that leave nothing: hops without tokens count as none."""
    t = Template.build(list("abc"), [(0, 1), (1, 2), (0, 2)])
    v = spark.createDataFrame([(k, "abcabc"[k]) for k in range(6)], "vid long, label string")
    ring = [(k, (k + 1) % 6) for k in range(6)]
    g = LabeledGraph(v, spark.createDataFrame(ring + [(b, a) for a, b in ring], "src long, dst long"))
    for how in ("none", "live", "issuer"):
        x = sieve(g, t, how=how, starts="rarest", least_gain=0, count_tokens=True, local_below=0)
        y = sieve(g, t, how=how, starts="rarest", least_gain=0)
        assert not x.state.rows and sum(r.get("walks", 0) for r in x.trace) == 0
        assert sum(r["tokens"] for r in x.trace) == sum(r["tokens"] for r in y.trace) > 0
