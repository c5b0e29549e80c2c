"""Plain ways to the same answers: joins without reduction, a replicated backtracking search, and cliques grown level by level."""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphsieve.operators.cliques import _batches, _by, listed
from graphsieve.operators.reduce import LabeledGraph, with_end_labels
from graphsieve.plans.template import Template

#: Edges that a worker of the replicated search holds.
REPLICATED_EDGES = 2_000_000


def _ends(g: LabeledGraph) -> DataFrame:
    return g.edges if "slabel" in g.edges.columns else with_end_labels(g.edges, g.vertices)


def pair_counts(g: LabeledGraph, t: Template) -> dict[tuple[str, str], int]:
    """Data edges by the labels of their ends, for the template's labels (a row per pair of them)."""
    labels = list(t.by_label)
    rows = _ends(g).filter(F.col("slabel").isin(labels) & F.col("dlabel").isin(labels)).groupBy("slabel", "dlabel").count().collect()
    return {(r[0], r[1]): r[2] for r in rows}


def join_order(g: LabeledGraph, t: Template) -> list[int]:
    """Roles by estimated cost: from the rarest template edge on, always the role that multiplies the rows least (edges per vertex of each bound
    neighbour's label, and the chance that further edges to bound roles exist)."""
    pairs = pair_counts(g, t)
    n = {r[0]: r[1] for r in g.vertices.filter(F.col("label").isin(list(t.by_label))).groupBy("label").count().collect()}
    size = lambda a, b: pairs.get((t.labels[a], t.labels[b]), 0)
    if not t.edges:
        return [0]
    order = list(min(t.edges, key=lambda e: (size(*e), e)))

    def grows(q):
        at, *more = sorted(t.adjacent[q] & set(order), key=lambda x: size(x, q) / max(1, n.get(t.labels[x], 0)))
        out = size(at, q) / max(1, n.get(t.labels[at], 0))
        for x in more:
            out *= size(x, q) / max(1, n.get(t.labels[x], 0) * n.get(t.labels[q], 0))
        return out, q

    while len(order) < t.n:
        order.append(min((q for q in range(t.n) if q not in order and t.adjacent[q] & set(order)), key=grows))
    return order


def _joined(g: LabeledGraph, t: Template, order: list[int], hint: str | None) -> DataFrame:
    v = g.vertices
    out = v.filter(F.col("label") == t.labels[order[0]]).select(F.col("vid").alias(f"r{order[0]}"))
    bound = [order[0]]
    for q in order[1:]:
        at, *more = sorted(t.adjacent[q] & set(bound))
        e = g.edges.select(F.col("src").alias(f"r{at}"), F.col("dst").alias(f"r{q}")).join(v.filter(F.col("label") == t.labels[q]).select(F.col("vid").alias(f"r{q}")), f"r{q}")
        out = out.join(e.hint(hint) if hint else e, f"r{at}")
        for x in bound:
            if t.labels[x] == t.labels[q]:
                out = out.filter(F.col(f"r{x}") != F.col(f"r{q}"))
        for x in more:
            c = g.edges.select(F.col("src").alias(f"r{x}"), F.col("dst").alias(f"r{q}"))
            out = out.join(c.hint(hint) if hint else c, [f"r{x}", f"r{q}"], "left_semi")
        bound.append(q)
    return out.select(*[f"r{q}" for q in range(t.n)])


def triple_join(g: LabeledGraph, t: Template, hint: str | None = None) -> DataFrame:
    """One scan of the edges for each template edge, in the order of an estimated cost, joined as Catalyst likes or by the hinted strategy
    (``shuffle_hash``, ``merge``)."""
    return _joined(g, t, join_order(g, t), hint)


def direct_enumerate(g: LabeledGraph, t: Template) -> DataFrame:
    """Vertex by vertex in the order of the roles as given: no masks, no reduction, no statistics."""
    order = [0]
    while len(order) < t.n:
        order.append(next(x for x in range(t.n) if x not in order and t.adjacent[x] & set(order)))
    return _joined(g, t, order, None)


def shares_of(sizes: dict[tuple[int, int], int], n: int, most: int) -> list[int]:
    """Into how many shares each role's vertices go, so that a cell (one share of every role) gets ``most`` edges or so: always the role is halved that takes most away."""
    shares = [1] * n
    held = lambda s: sum(x / (s[a] * s[b]) for (a, b), x in sizes.items())
    while held(shares) > most:
        shares[min(range(n), key=lambda q: (held([x * (1 + (k == q)) for k, x in enumerate(shares)]), q))] *= 2
    return shares


def replicated_enumerate(g: LabeledGraph, t: Template, most: int = REPLICATED_EDGES) -> DataFrame:
    """Depth-first search from the sources, with no exchange on the way: a worker holds all edges that its search may need.

    Those are all edges of the template's labels, if they are at most ``most``. Of larger graphs the vertices of every role are dealt to shares, and a worker
    holds the edges of one share of every role (a cell): an edge is replicated to all cells that differ only in roles which are not its ends.
    """
    if not t.edges:
        return g.vertices.filter(F.col("label") == t.labels[0]).select(F.col("vid").alias("r0"))
    if t.demands:
        raise ValueError("this baseline does not look at labels and directions of edges")
    pairs = pair_counts(g, t)
    shares = shares_of({(a, b): pairs.get((t.labels[a], t.labels[b]), 0) for a, b in t.edges}, t.n, most)
    width = [int(np.prod(shares[q + 1 :], dtype=np.int64)) for q in range(t.n)]
    cells = int(np.prod(shares, dtype=np.int64))
    e, dealt = _ends(g), []
    for k, (a, b) in enumerate(t.edges):
        share = lambda c, q: F.pmod(F.xxhash64(c, F.lit(q)), F.lit(shares[q])) * F.lit(width[q])
        others = np.zeros(1, np.int64)
        for q in range(t.n):
            if q not in (a, b):
                others = (others[:, None] + np.arange(shares[q]) * width[q]).ravel()
        cell = F.explode(F.transform(F.array(*[F.lit(int(x)) for x in others]), lambda x: x.cast("long") + share("src", a) + share("dst", b)))
        own = e.filter((F.col("slabel") == t.labels[a]) & (F.col("dlabel") == t.labels[b])).select("src", "dst").distinct()
        dealt.append(own.select(cell.alias("place"), F.lit(k).alias("edge"), "src", "dst"))
    order = [0]
    while len(order) < t.n:
        order.append(next(x for x in range(t.n) if x not in order and t.adjacent[x] & set(order)))

    def searched(batches):
        for cell in _by(batches, "place"):
            near: dict = {}
            for k, (a, b) in enumerate(t.edges):
                at = cell["edge"] == k
                for u, v in zip(cell["src"][at].tolist(), cell["dst"][at].tolist()):
                    near.setdefault((a, b), {}).setdefault(u, set()).add(v)
                    near.setdefault((b, a), {}).setdefault(v, set()).add(u)

            def go(bound, near=near):
                if len(bound) == t.n:
                    yield [bound[q] for q in range(t.n)]
                    return
                q = order[len(bound)]
                met = [near.get((x, q), {}).get(bound[x], set()) for x in t.adjacent[q] if x in bound]
                for x in set.intersection(*met) - set(bound.values()):
                    yield from go(bound | {q: x})

            rows = []
            for source in near.get((0, order[1]), {}):
                for m in go({0: source}):
                    rows.append(m)
                    if len(rows) == 50_000:
                        yield from _batches(list(np.array(rows, np.int64).T))
                        rows = []
            if rows:
                yield from _batches(list(np.array(rows, np.int64).T))

    tasks = max(int(e.sparkSession.conf.get("spark.sql.shuffle.partitions")), min(10_000, cells))
    out = reduce(DataFrame.unionByName, dealt).repartition(tasks, "place").sortWithinPartitions("place").mapInArrow(searched, ", ".join(f"c{q} long" for q in range(t.n)))
    return out.select(*[F.col(f"c{q}").alias(f"r{q}") for q in range(t.n)])


def clique_grow(edges: DataFrame, k: int) -> DataFrame:
    """Ordered cliques grown a vertex at a time: rows ``(c0 < c1 < ...)``. Wedges are made and closed within tasks, never shuffled."""
    if k == 2:
        return edges.filter("src < dst").select(F.col("src").alias("c0"), F.col("dst").alias("c1"))
    return listed(edges, k)
