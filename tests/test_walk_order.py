"""Orders of walks by the rows that they are expected to make."""

from graphsieve.plans.rules import Rule, WalkPlan, best_start, cycle_rules
from graphsieve.plans.template import Template, TemplateProfile

#: An order's customer and supplier of one nation: few nations, each of many suppliers and customers.
RING = Template.build(["order", "cust", "nation", "supplier"], [(0, 1), (1, 2), (2, 3), (0, 3)])
_EDGES = {("order", "cust"): 90_000, ("cust", "nation"): 18_000, ("nation", "supplier"): 6_000, ("order", "supplier"): 360_000}
COUNTS = {"order": 90_000, "cust": 18_000, "nation": 25, "supplier": 6_000} | {k: n for (a, b), n in _EDGES.items() for k in ((a, b), (b, a))}


def test_no_pairs_of_a_nation():
    (rule,) = cycle_rules(TemplateProfile.of(RING), False, COUNTS)
    assert rule.start == 2
    hops = WalkPlan(RING, rule.edges, 2, COUNTS, keep=(2,)).hops
    assert [s.to for s, _ in hops] == [1, 0, 3]  # not customers beside suppliers
    # a step extends from the end with few edges to it; the hub is tested
    assert hops[-1][0].at == 0 and [c.at for c in hops[-1][1]] == [2]


def test_every_edge_once_and_labels_alone():
    for start in range(4):
        for counts in (COUNTS, {"order": 9}, None):
            steps = WalkPlan(RING, RING.edges, start, counts).steps
            assert sorted((min(s.at, s.to), max(s.at, s.to)) for s in steps) == sorted(RING.edges)
    assert best_start(RING, RING.edges, {"order": 1, "cust": 2, "nation": 3, "supplier": 4}) == 0
    assert Rule("cycle", 0, frozenset(RING.edges)).sequence() == (0, 1, 2, 3)
