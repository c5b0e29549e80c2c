"""Searches that go on from a stop."""

from graphsieve import registry, workloads
from graphsieve.operators.sieve import rules_of, sieve
from graphsieve.workloads import WORKLOADS, graph


def test_a_stop_goes_on(spark, sf):
    name, t = WORKLOADS["w6"]
    told = lambda s: sorted(map(tuple, s.state.edges.select("src", "dst", "smask", "dmask").collect()))
    for below in (0, 1_000_000):
        start, checked = sieve(graph(spark, sf, name, t), t, max_rules=0, local_below=below).state, []
        state = start
        for k in (1, 2, 3):
            x = sieve(None, t, max_rules=1, state=state, checked=tuple(checked), local_below=below)
            checked, state = [*checked, *rules_of(x.trace)], x.state
            whole = sieve(None, t, max_rules=k, state=start, local_below=below)
            assert len(checked) == k and told(x) == told(whole)
            assert [(a, r.partition(":")[2]) for a, r in rules_of(whole.trace)] == [(a, r.partition(":")[2]) for a, r in checked]
        assert not rules_of(sieve(None, t, max_rules=1, state=state, checked=tuple(checked), local_below=below).trace)


def test_stops_read_the_graph_once(spark, sf, monkeypatch):
    made, own = [], registry.init_candidates
    monkeypatch.setattr(registry, "init_candidates", lambda *a: made.append(1) or own(*a))
    monkeypatch.setattr(registry, "solution", None)  # a second reading
    workloads.forget()
    rows = registry.QUERIES["precision_stages_w6"](spark, sf).collect()
    assert made == [1] and [r.stage for r in rows] == ["0 rules", "1 rules", "2 rules", "3 rules", "confirmed"]
    assert all(r.v_recall == r.e_recall == 1 for r in rows) and rows[-1].e_precision == rows[-1].v_precision == 1
    assert [r.e_precision for r in rows] == sorted(r.e_precision for r in rows)
