"""Candidate roles of vertices, and neighbourhood checks that take them away.

The state is one table of active edges, both ways: ``(src, dst, smask, dmask)``. A mask has a bit for every role that a vertex may still
play. A round sums up every vertex's neighbours (partial sums before the shuffle) and joins the masks that changed back to the edges; what
is written in a round is the changed masks and, if there are any, the edges, and the counts come with the writing.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce
from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphsieve.functions.storage import discard, written
from graphsieve.plans.template import Template


@dataclass
class LabeledGraph:
    """``vertices(vid, label)`` and ``edges(src, dst)``: simple, and each edge both ways.

    Edges may carry ``slabel`` and ``dlabel``, their ends' labels (see ``with_end_labels``): a template's edges are then found by a scan
    without a shuffle. Edges with a label have ``elabel`` and ``forward`` (see ``labelled_edges``), and may be parallel.
    """

    vertices: DataFrame
    edges: DataFrame


def symmetric(pairs: DataFrame, a: str = "src", b: str = "dst") -> DataFrame:
    """Both directions of every edge once; loops and nulls go."""
    one = pairs.select(F.col(a).cast("long").alias("src"), F.col(b).cast("long").alias("dst")).filter("src <> dst")
    return one.unionByName(one.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()


def labelled_edges(pairs: DataFrame, label: Column | None = None, a: str = "src", b: str = "dst") -> DataFrame:
    """Directed edges with labels, both ways: ``forward`` tells the rows that run as given. Parallel edges of other labels stay."""
    one = pairs.select(F.col(a).cast("long").alias("src"), F.col(b).cast("long").alias("dst"), (F.lit(None) if label is None else label).cast("string").alias("elabel")).filter("src <> dst")
    turned = one.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "elabel", F.lit(False).alias("forward"))
    return one.withColumn("forward", F.lit(True)).unionByName(turned).distinct()


def with_end_labels(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """Edges with the labels of both ends; edges of unlabelled or unknown vertices go, as no template can use them."""
    v = vertices.filter(F.col("label").isNotNull())
    return edges.join(v.select(F.col("vid").alias("src"), F.col("label").alias("slabel")), "src").join(v.select(F.col("vid").alias("dst"), F.col("label").alias("dlabel")), "dst")


@dataclass
class State:
    """Active edges with the number of them, and the vertices: derived from the edges where the template has any."""

    template: Template
    edges: DataFrame  # src, dst, smask, dmask (and allow, where the template makes demands on edges)
    rows: int  # directed edges
    alone: DataFrame | None = None  # vid, mask: for templates of a single role
    trace: list = field(default_factory=list)
    borrowed: bool = False  # someone else's tables: not to be freed
    matches: DataFrame | None = None  # of a confirmed clique of one label: c0 < c1 < ..., a row per set of vertices

    @property
    def masks(self) -> DataFrame:
        """``(vid, mask)``."""
        if self.alone is not None:
            return self.alone
        return self.edges.groupBy(F.col("src").alias("vid")).agg(F.max("smask").alias("mask"))

    @property
    def vertices(self) -> DataFrame:
        """``(vid, label, mask)``; a mask tells the label, as its roles have but one."""
        label = reduce(lambda c, x: c.when(F.col("mask").bitwiseAND(F.lit(x[1])) != 0, F.lit(x[0])), self.template.by_label.items(), F)
        return self.masks.select("vid", label.otherwise(F.lit(None)).alias("label"), "mask")

    def counts(self) -> tuple[int, int, int]:
        """Vertices, directed edges, candidate roles."""
        v = self.masks.agg(F.count("*"), F.sum(F.bit_count("mask"))).first()
        return v[0], self.rows, v[1] or 0


def has(mask: str | Column, role: int) -> Column:
    return F.col(mask).bitwiseAND(F.lit(1 << role)) != 0 if isinstance(mask, str) else mask.bitwiseAND(F.lit(1 << role)) != 0


def plays(t: Template, a: int, b: int) -> Column:
    """Whether an edge row may stand for the template's edge from a to b."""
    out = has("smask", a) & has("dmask", b)
    return out & has("allow", t.arcs[a, b]) if t.demands else out


def compatible(t: Template) -> Column:
    """Whether some template edge joins a candidate of the source to one of the target."""
    if t.demands:
        tests = [plays(t, a, b) for a, b in t.arcs]
    else:
        tests = [has("smask", q) & (F.col("dmask").bitwiseAND(F.lit(t.adjmask[q])) != 0) for q in range(t.n) if t.adjmask[q]]
    return reduce(lambda a, b: a | b, tests) if tests else F.lit(False)


def role_mask(t: Template, label: str = "label") -> Column:
    """Candidate roles by label alone."""
    out = F
    for x, mask in t.by_label.items():
        out = out.when(F.col(label) == x, F.lit(mask).cast("long"))
    return out.otherwise(F.lit(0).cast("long"))


def _allowed(t: Template) -> Column:
    """Arcs of the template that a labelled data edge may play."""
    wanted = {(a, b): (x, way) for a, b, x, way in t.demands}
    bits = F.lit(0).cast("long")
    for (a, b), k in t.arcs.items():
        x, way, forward = (*wanted[a, b], True) if (a, b) in wanted else (*wanted[b, a], False) if (b, a) in wanted else (None, False, True)
        ok = F.lit(True)
        if x is not None:
            ok &= F.col("elabel").eqNullSafe(F.lit(x))
        if way:
            ok &= F.col("forward") if forward else ~F.col("forward")
        bits = bits.bitwiseOR(F.when(ok, F.lit(1 << k).cast("long")).otherwise(F.lit(0).cast("long")))
    return bits


def init_candidates(g: LabeledGraph, t: Template) -> State:
    """The edges that some template edge could map to, with both ends' roles by label. Null labels play no role.

    With the ends' labels on the edges this is one scan with a filter on both; without, the labels are joined first.
    """
    labels = list(t.by_label)
    if t.n == 1:
        alone, seen = written(g.vertices.filter(F.col("label").isin(labels)).select("vid", role_mask(t).alias("mask")), "init-vertices")
        return State(t, g.edges.limit(0).select("src", "dst", F.lit(0).cast("long").alias("smask"), F.lit(0).cast("long").alias("dmask")), 0, alone)
    e = g.edges
    if "slabel" not in e.columns:
        e = with_end_labels(e, g.vertices.filter(F.col("label").isin(labels)))
    e = e.filter(F.col("slabel").isin(labels) & F.col("dlabel").isin(labels))
    if t.demands:
        if "forward" not in e.columns:
            raise ValueError("the template makes demands on edges, which have neither label nor direction")
        e = e.withColumn("_allow", _allowed(t)).groupBy("src", "dst", "slabel", "dlabel").agg(F.bit_or("_allow").alias("allow"))
    elif "forward" in e.columns:
        e = e.select("src", "dst", "slabel", "dlabel").distinct()
    more = ["allow"] if t.demands else []
    e = e.select("src", "dst", role_mask(t, "slabel").alias("smask"), role_mask(t, "dlabel").alias("dmask"), *more).filter(compatible(t))
    e, seen = written(e, "init-edges")
    return State(t, e, seen["rows"])


def _needs(t: Template, rule: str) -> dict[int, list[tuple[tuple[int, ...], int]]]:
    """Per role the (subset of neighbour roles of one label, how many distinct neighbours must play one of them), for two or more."""
    out = {}
    for q in range(t.n):
        needs = []
        by: dict[str, list[int]] = {}
        for x in sorted(t.adjacent[q]):
            by.setdefault(t.labels[x], []).append(x)
        for own in by.values():
            if rule == "count" and len(own) > 1:
                needs.append((tuple(own), len(own)))
            if rule == "hall":
                for k in range(2, len(own) + 1):
                    needs += [(s, k) for s in (combinations(own, k) if len(own) <= 6 or k == len(own) else ())]
        out[q] = needs
    return out


def neighbourhood_masks(edges: DataFrame, t: Template, rule: str = "hall", relaxed: bool = False) -> DataFrame:
    """``(vid, mask, new)``: roles whose neighbour requirements hold. ``relaxed``: one neighbour role is enough, but for mandatory edges."""
    if rule not in ("set", "count", "hall"):
        raise ValueError("rule is set, count or hall")
    needs = _needs(t, "set" if relaxed else rule)
    bit = lambda ok, k: F.when(ok, F.lit(1 << k).cast("long")).otherwise(F.lit(0).cast("long"))
    if t.demands:  # neighbours are seen by the arcs that lead to them
        played = reduce(Column.bitwiseOR, [bit(plays(t, a, b), k) for (a, b), k in t.arcs.items()])
        place = lambda q, x: t.arcs[q, x]
    else:
        played, place = F.col("dmask"), lambda q, x: x
    bits = lambda q, xs: sum(1 << place(q, x) for x in xs)
    counted = sorted({bits(q, s) for q, ns in needs.items() for s, _ in ns})
    sums = [F.sum(F.when(F.col("_near").bitwiseAND(F.lit(s)) != 0, 1).otherwise(0)).alias(f"s{s}") for s in counted]
    near = edges.withColumn("_near", played).groupBy("src").agg(F.max("smask").alias("mask"), F.bit_or("_near").alias("near"), *sums)
    new = F.lit(0).cast("long")
    for q in range(t.n):
        must = [x for x in t.adjacent[q] if not relaxed or (min(q, x), max(q, x)) in t.mandatory]
        ok = has("mask", q) & (F.col("near").bitwiseAND(F.lit(bits(q, must))) == F.lit(bits(q, must)))
        if relaxed and t.adjacent[q]:
            ok &= F.col("near").bitwiseAND(F.lit(bits(q, t.adjacent[q]))) != 0
        for s, k in needs[q]:
            ok &= F.col(f"s{bits(q, s)}") >= k
        new = new.bitwiseOR(bit(ok, q))
    return near.select(F.col("src").alias("vid"), "mask", new.alias("new"))


def both_ways(edges: DataFrame) -> DataFrame:
    """``(src, dst, smask, dmask)`` of rows of one direction, which are read once."""
    turned = F.struct(F.col("dst").alias("src"), F.col("src").alias("dst"), F.col("dmask").alias("smask"), F.col("smask").alias("dmask"))
    return edges.select(F.inline(F.array(F.struct("src", "dst", "smask", "dmask"), turned)))


def apply_masks(state: State, masks: DataFrame, eliminate: str = "both") -> tuple[State, dict]:
    """Takes roles away: ``masks(vid, mask, new)`` has a row per vertex. Vertices without a role go, and edges that no template edge can be.

    First the masks that changed are written, with the counts of vertices; only if there are any, the edges.
    """
    t = state.template
    moved = F.col("mask") != F.col("new")
    changed, seen = written(masks, "changed", keep=moved, alive=F.col("new") != 0, moved=moved)
    if not seen["moved"]:
        discard(changed)
        return state, seen
    # demands tell the directions of an edge apart; else one of them is joined, from the end of the later kind, which has more vertices, and made both again
    e = state.edges if t.demands else state.edges.filter("src > dst")
    for end, mask in (("src", "smask"), ("dst", "dmask")):
        e = e.join(changed.select(F.col("vid").alias(end), F.col("new").alias("_new")), end, "left").withColumn(mask, F.coalesce("_new", mask)).drop("_new").filter(f"{mask} <> 0")
    e = e.filter(compatible(t)) if eliminate == "both" else e
    e, kept = written(e.select("src", "dst", "smask", "dmask", "allow") if t.demands else both_ways(e), "edges")
    discard(changed)
    if not state.borrowed:
        discard(state.edges)
    return State(t, e, kept["rows"], None, state.trace), seen


def neighbourhood_fixpoint(state: State, t: Template, rule: str = "hall", eliminate: str = "both", max_rounds: int | None = None, relaxed: bool = False, enough: int | None = None) -> State:
    """Rounds until nothing goes (or no more than ``enough`` edges are left). For trees of unique labels at most the diameter and one more."""
    rounds, messages, alive = 0, 0, None
    while t.n > 1 and state.rows and (max_rounds is None or rounds < max_rounds):
        messages += state.rows
        state, seen = apply_masks(state, neighbourhood_masks(state.edges, t, rule, relaxed), eliminate)
        rounds, alive = rounds + 1, seen["alive"]
        if not seen["moved"] or (enough is not None and state.rows <= enough):
            break
    if alive is None or not state.rows:
        alive = state.counts()[0] if t.n == 1 else 0
    state.trace.append({"stage": "relaxed" if relaxed else "neighbourhood", "rule": rule, "rounds": rounds, "v": alive, "e": state.rows, "messages": messages})
    return state


def relaxed_superset(g: LabeledGraph, t: Template, max_rounds: int | None = None) -> State:
    """Holds the answers of every connected template that edge deletions make of ``t``: each role keeps at least one of its neighbours,
    and all that mandatory edges join it to."""
    return neighbourhood_fixpoint(init_candidates(g, t), t, relaxed=True, max_rounds=max_rounds)
