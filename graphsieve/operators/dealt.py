"""Walks of many short ways, dealt by their sources: a task gets the edges near a share of the sources and walks them on arrays.

Where walks from a start stay near it and make far more tokens than there are edges near all starts, the edges are what is moved: lists of
neighbours, by the vertices that a share of the sources reaches. Each task then walks as ``local`` does, every hop and fold of the plan. Sources are
never parted, so tokens that carry their source fold as they do elsewhere. Where lists would be moved too often, or a vertex has too many edges
for a task, there is no such walk (None), and joins do it.
"""

from __future__ import annotations

from functools import reduce
from math import ceil

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphsieve.functions.storage import written
from graphsieve.operators.local import Walk
from graphsieve.operators.reduce import State, plays
from graphsieve.plans import rules
from graphsieve.plans.rules import WalkPlan, known_pairs
from graphsieve.plans.template import Template

#: Ends that a share's lists hold, the least sources for each share, the most times that an edge may be moved, and the most edges of a vertex.
SHARE, SOURCES, TIMES, MOST_EDGES = 500_000, 10, 12, 2_000
#: Tokens that a task expands at once.
TOKENS = 1_000_000

_ROWS = "a int, b int, u long, v long"
_SOURCE, _COUNTS = -1, -2


class Near:
    """Edges near some sources by the template edge that they may play, as ``Walk`` reads them."""

    def __init__(self, t: Template, edges: dict[tuple[int, int], tuple[np.ndarray, np.ndarray]]):
        self.t, self._steps = t, {}
        self.ids = np.unique(np.concatenate([x for pair in edges.values() for x in pair]))
        for (a, b), (u, v) in edges.items():
            u, v = np.searchsorted(self.ids, u), np.searchsorted(self.ids, v)
            self._add(a, b, u, v)
            self._add(b, a, v, u)

    def _add(self, a: int, b: int, s: np.ndarray, d: np.ndarray) -> None:
        keys = np.sort(s * len(self.ids) + d)
        self._steps[a, b] = keys % len(self.ids), np.searchsorted(keys // len(self.ids), np.arange(len(self.ids) + 1)), keys

    def step(self, a: int, b: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        return self._steps[a, b]


def layout(edges, plan: WalkPlan) -> tuple[list[tuple[int, int]], dict[int, int]] | None:
    """Template edges as they are moved, from the end that is nearer the start; and for each other end that edges are moved from, the role that reaches it.

    None where such a role is bound before all that could reach it: its tokens might be at vertices whose edges were not moved.
    """
    near: dict[int, set[int]] = {}
    for a, b in edges:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    far, todo = {plan.start: 0}, [plan.start]
    for q in todo:
        for x in sorted(near[q] - far.keys()):
            far[x] = far[q] + 1
            todo.append(x)
    place = plan.roles.index
    moved = sorted((min((a, b), key=lambda q: (far[q], place(q))), max((a, b), key=lambda q: (far[q], place(q)))) for a, b in edges)
    parent = {}
    for q in sorted({a for a, _ in moved} - {plan.start}, key=lambda q: far[q]):
        before = [p for p in near[q] if far[p] == far[q] - 1 and place(p) < place(q)]
        if not before:
            return None
        parent[q] = min(before, key=place)
        if parent[q] != plan.start and parent[q] not in parent:
            return None
    return moved, parent


def moved_ends(t: Template, frequency: dict, plan: WalkPlan, moved, parent) -> float:
    """Ends that all lists hold, were no vertex reached twice by a share."""
    n = lambda q: max(1, frequency.get(t.labels[q], 0))
    fan = lambda a, b: frequency.get((t.labels[a], t.labels[b]), 0) / n(a)
    reached = {plan.start: float(n(plan.start))}
    for q, p in parent.items():  # nearer ones come first
        reached[q] = reached[p] * fan(p, q)
    return sum(reached[a] * fan(a, b) for a, b in moved)


def _most_edges(state: State) -> int:
    if not hasattr(state, "_most_edges"):
        state._most_edges = state.edges.groupBy("src").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0] or 0
    return state._most_edges


def _lists(state: State, plan: WalkPlan, moved, parent, shares: int) -> DataFrame:
    """``(share, a, b, u, vs)``: the neighbours in role b of a vertex in role a that a share's sources reach."""
    t = state.template
    own = lambda c: F.pmod(F.xxhash64(c), F.lit(shares)).cast("int")
    reached, out = {}, []
    for a, b in moved:
        lists = state.edges.filter(plays(t, a, b)).groupBy(F.col("src").alias("u")).agg(F.collect_list("dst").alias("vs"))
        if a == plan.start:
            lists = lists.withColumn("share", own("u"))
        else:
            if a not in reached:
                p = parent[a]
                ways = state.edges.filter(plays(t, p, a))
                ways = ways.select(own("src").alias("share"), "dst") if p == plan.start else reached[p].join(ways.withColumnRenamed("src", "u"), "u").select("share", "dst")
                reached[a] = ways.distinct().withColumnRenamed("dst", "u")
            lists = reached[a].join(lists, "u")
        out.append(lists.select("share", F.lit(a).alias("a"), F.lit(b).alias("b"), "u", "vs"))
    return reduce(DataFrame.unionByName, out)


def dealt_walk(state: State, edges, plan: WalkPlan, how: str, frequency: dict | None, record: bool) -> tuple[DataFrame, int, int] | None:
    """Walks of a plan with the number of tokens and of completed walks: ``(vid)`` of the sources that complete, or with ``record`` the pairs ``(a, b, u, v)``
    of ``confirmed_pairs`` (a pair once for each share). None where joins had better do it."""
    t, freq = state.template, frequency or {}
    if not known_pairs(t, freq) or (planned := layout(edges, plan)) is None:
        return None
    moved, parent = planned
    ends, sources = moved_ends(t, freq, plan, moved, parent), freq.get(t.labels[plan.start], 0)
    shares = max(ceil(ends / SHARE), 2 * state.edges.sparkSession.sparkContext.defaultParallelism)
    if ends < rules.MEET_FROM or ends > TIMES * state.rows or sources < SOURCES * shares or _most_edges(state) > MOST_EDGES:
        return None

    def walked(table: pa.Table) -> pa.Table:
        a, b, u = (table[c].to_numpy() for c in ("a", "b", "u"))
        vs = table["vs"].combine_chunks()
        vs = vs.combine_chunks() if isinstance(vs, pa.ChunkedArray) else vs
        long, flat = np.diff(vs.offsets.to_numpy()), vs.flatten().to_numpy()
        a, b, u = np.repeat(a, long), np.repeat(b, long), np.repeat(u, long)
        parts = {}
        for x, y in moved:
            ok = (a == x) & (b == y)
            parts[x, y] = u[ok], flat[ok]
        near = Near(t, parts)
        walk = Walk(near, plan, how, record=record, cap=TOKENS)
        sources = np.searchsorted(near.ids, np.unique(np.concatenate([parts[x, y][0] for x, y in moved if x == plan.start])))
        good = walk.run(sources)
        n = len(near.ids)
        rows = [(x, y, near.ids[(k := np.unique(np.concatenate(found))) // n], near.ids[k % n]) for (x, y), found in walk.pairs.items()] if record else [(_SOURCE, 0, near.ids[sources[good]], near.ids[sources[good]])]
        rows.append((_COUNTS, 0, np.array([walk.tokens]), np.array([walk.walks])))
        column = lambda k: np.concatenate([np.full(len(r[2]), r[k], np.int32) for r in rows])
        return pa.table({"a": column(0), "b": column(1), "u": np.concatenate([r[2] for r in rows]), "v": np.concatenate([r[3] for r in rows])})

    out, _ = written(_lists(state, plan, moved, parent, shares).repartition(shares, "share").groupBy("share").applyInArrow(walked, _ROWS), "dealt")
    tokens, walks = out.filter(F.col("a") == _COUNTS).agg(F.sum("u"), F.sum("v")).first()
    return out.filter(F.col("a") >= 0) if record else out.filter(F.col("a") == _SOURCE).select(F.col("u").alias("vid")), tokens or 0, walks or 0
