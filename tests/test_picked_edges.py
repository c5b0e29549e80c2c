"""Edges picked by a template before they are dealt, against the stored graph's."""

import pytest
from graphsieve.operators.reduce import init_candidates
from graphsieve.sources.graphs import build
from graphsieve.workloads import WORKLOADS, _made, forget, graph


@pytest.mark.parametrize("w", ["w6", "w2", "w5", "topo_c"])
def test_same_candidates(spark, sf, w):
    name, t = WORKLOADS[w]
    told = lambda g: sorted(map(tuple, init_candidates(g, t).edges.select("src", "dst", "smask", "dmask").collect()))
    want = told(build(spark, sf, name))
    assert want and told(build(spark, sf, name, t)) == want


def test_a_template_stores_no_graph(spark, sf):
    name, t = WORKLOADS["w6"]
    forget()
    g = graph(spark, sf, name, t)
    assert not hasattr(g.edges, "_stored_at") and not _made
    whole = graph(spark, sf, name)
    assert graph(spark, sf, name, t) is whole and hasattr(whole.edges, "_stored_at")
