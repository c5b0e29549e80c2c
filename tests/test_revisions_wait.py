"""Revisions of a template that are solved when asked for."""

from graphsieve import registry, workloads
from graphsieve.operators import explore


def test_later_revisions_wait(spark, sf, monkeypatch):
    asked = []
    for what in ("add_edge", "remove_edge"):
        own = getattr(explore.IncrementalSession, what)
        monkeypatch.setattr(explore.IncrementalSession, what, lambda self, a, b, own=own, what=what: asked.append(what) or own(self, a, b))
    workloads.forget()
    registry.QUERIES["incr_superset_0"](spark, sf).collect()
    assert asked == []
    registry.QUERIES["incr_superset_1"](spark, sf).collect()
    assert asked == ["add_edge"]
