"""Revising a template: incremental sessions on a relaxed superset, a memo of failed rules, and exploration level by level."""

from __future__ import annotations

import json
import time
from dataclasses import dataclass, field
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphsieve.functions.storage import materialize, written
from graphsieve.operators import local
from graphsieve.operators.reduce import LabeledGraph, State, apply_masks, has, relaxed_superset
from graphsieve.operators.sieve import LOCAL_EDGES, Solution, label_frequency, sieve
from graphsieve.operators.walks import walk_sources
from graphsieve.plans.rules import Rule, generate
from graphsieve.plans.template import Template


def scope(superset: State, t: Template, vertices: DataFrame | None = None) -> State:
    """A fresh start for ``t`` inside the superset, or inside given vertices of it (edges always come from the superset)."""
    if vertices is None:
        return State(t, superset.edges, superset.rows, superset.alone, [], borrowed=True)
    keep = vertices.select("vid")
    e = superset.edges.join(keep.withColumnRenamed("vid", "src"), "src", "left_semi").join(keep.withColumnRenamed("vid", "dst"), "dst", "left_semi")
    e, seen = written(e.select(*superset.edges.columns), "scope")
    return State(t, e, seen["rows"], None, [])


class RuleMemo:
    """Sources that fail a rule on the superset. Every later scope is smaller, so they fail there too."""

    def __init__(self):
        self.failed: dict[str, DataFrame] = {}
        self.asked = self.answered = 0

    def lookup(self, signature: str) -> DataFrame | None:
        return self.failed.get(signature)

    def store(self, superset: State, t: Template, rule: Rule) -> DataFrame:
        key = rule.signature(t)
        self.asked += 1
        self.answered += key in self.failed
        if key not in self.failed:
            here = State(t, superset.edges, superset.rows, superset.alone, [], borrowed=True)
            sources = here.masks.filter(has("mask", rule.start)).select("vid")
            self.failed[key] = materialize(sources.join(walk_sources(here, rule), "vid", "left_anti"), "memo")
        return self.failed[key]

    def apply(self, state: State, t: Template, rules: list[Rule]) -> State:
        """Takes the rule's role from sources known to fail."""
        masks = state.masks.withColumn("new", F.col("mask"))
        for r in rules:
            if (bad := self.lookup(r.signature(t))) is not None:
                gone = F.col("new").bitwiseAND(F.bitwise_not(F.lit(1 << r.start).cast("long")))
                masks = masks.join(bad.withColumn("_bad", F.lit(True)), "vid", "left").select("vid", "mask", F.when(F.col("_bad"), gone).otherwise(F.col("new")).alias("new"))
        return apply_masks(state, masks)[0]


class IncrementalSession:
    """Edges of a template are added and deleted; each revision is solved exactly.

    ``whole`` is the template with every edge that may come: its relaxed superset is computed once and holds the answer of every connected
    revision. ``mode``: "independent" starts from the graph each time, "superset" from the superset or the last answer's
    vertices, "superset_memo" also skips sources that are known to fail.
    """

    def __init__(self, g: LabeledGraph, t: Template, whole: Template | None = None, mode: str = "superset_memo", **options):
        if mode not in ("independent", "superset", "superset_memo"):
            raise ValueError("unknown mode")
        self.g, self.t, self.mode, self.memo, self.options = g, t, mode, RuleMemo(), options
        self.whole = whole or t
        self.superset = None if mode == "independent" else relaxed_superset(g, self.whole)
        self.solution = self._solve(None)

    def _solve(self, inside: DataFrame | None) -> Solution:
        if self.superset is None:
            return sieve(self.g, self.t, **self.options)
        start = scope(self.superset, self.t, inside)
        if self.mode == "superset_memo":
            rules = [r for r in generate(self.t, False) if r.kind != "cover"]
            for r in rules:
                self.memo.store(self.superset, self.t, r)
            start = self.memo.apply(start, self.t, rules)
        return sieve(self.g, self.t, state=start, **self.options)

    def add_edge(self, a: int, b: int) -> Solution:
        """Matches of the larger template lie among the last answer's vertices."""
        if (min(a, b), max(a, b)) not in self.whole.edges and self.superset is not None:
            raise ValueError("the session's superset does not know this edge")
        self.t = self.t.with_edge(a, b)
        self.solution = self._solve(self.solution.state.vertices)
        return self.solution

    def remove_edge(self, a: int, b: int) -> Solution:
        """Starts from the superset again; raises if the template falls apart."""
        self.t = self.t.without((a, b))
        self.solution = self._solve(None)
        return self.solution

    def stats(self) -> dict:
        v, e, c = self.solution.state.counts()
        return {"vertices": v, "edges": e, "candidates": c, "labels": label_frequency(self.solution.state)}


class Revisions:
    """Answers of a template and its revisions one after another; a revision is solved once it, or a later one, is asked for."""

    def __init__(self, g: LabeledGraph, t: Template, revisions: list[tuple[str, int, int]], whole: Template, mode: str, **options):
        self.session, self.left = IncrementalSession(g, t, whole, mode, **options), list(revisions)
        self.solved = [self.session.solution]

    def __getitem__(self, k: int) -> Solution:
        while len(self.solved) <= k:
            what, a, b = self.left.pop(0)
            self.solved.append(self.session.add_edge(a, b) if what == "add" else self.session.remove_edge(a, b))
        return self.solved[k]


def run_revisions(g: LabeledGraph, t: Template, revisions: list[tuple[str, int, int]], whole: Template, mode: str, **options) -> list[Solution]:
    all_of = Revisions(g, t, revisions, whole, mode, **options)
    return [all_of[k] for k in range(len(revisions) + 1)]


@dataclass
class ExploreResult:
    level: int | None
    levels: list[dict] = field(default_factory=list)
    found: DataFrame | None = None  # variant, src, dst, smask, dmask of the level's matching variants

    def union(self) -> DataFrame | None:
        return None if self.found is None else self.found.select(F.col("src").alias("vid")).distinct()

    def union_edges(self) -> DataFrame | None:
        return None if self.found is None else self.found.select("src", "dst").distinct()


def explore(g: LabeledGraph, t: Template, max_level: int | None = None, local_below: int = LOCAL_EDGES, tasks: int = 32) -> ExploreResult:
    """Take away 0, 1, 2 ... edges until some variant matches; all variants of that level are solved and united. Variants that are alike up to
    roles of equal labels are solved once.

    One relaxed superset serves all variants, and a rule that fails on it for a vertex is walked once: later variants that have the rule
    take the outcome over. A superset of at most ``local_below`` edges is given to ``tasks`` tasks, among which the variants of a level are dealt, so a
    level is one job; on a larger one every variant is a distributed search.
    """
    superset, out, memo = relaxed_superset(g, t), ExploreResult(None), RuleMemo()
    free = len(t.edges) - len(t.mandatory)
    small = 0 < superset.rows <= local_below
    held = superset.edges.toArrow() if small else None  # at most local_below rows
    for k in range(min(free, free if max_level is None else max_level) + 1):
        variants, began = t.relaxations(k), time.time()
        if not variants:
            break
        distinct = t.relaxations(k, up_to_isomorphism=True)
        if not superset.rows:
            found, stats = None, {"matched": 0, "walked": 0, "reused": 0}
        elif small:
            found, stats = _solve_level(superset, distinct, held, tasks)
        else:
            found, stats = _solve_apart(superset, distinct, memo)
        spent = time.time() - began
        v = 0 if found is None else found.select("src").distinct().count()
        out.levels.append({"level": k, "variants": len(variants), "solved": len(distinct), **stats, "v": v, "seconds": spent, "seconds_each": spent / len(distinct)})
        if stats["matched"]:
            out.level, out.found = k, found
            break
    return out


def _solve_apart(superset: State, variants: list[Template], memo: RuleMemo) -> tuple[DataFrame | None, dict]:
    parts, asked, answered = [], memo.asked, memo.answered
    for i, x in enumerate(variants):
        rules = [r for r in generate(x, False) if r.kind == "cycle" and r.length <= 4]
        for r in rules:
            memo.store(superset, x, r)
        s = sieve(None, x, state=memo.apply(scope(superset, x), x, rules)).state
        if s.rows:
            parts.append(s.edges.select(F.lit(i).alias("variant"), "src", "dst", "smask", "dmask"))
    found = materialize(reduce(DataFrame.unionByName, parts), "explored") if parts else None
    reused = memo.answered - answered
    return found, {"matched": len(parts), "walked": memo.asked - asked - reused, "reused": reused}


def _solve_level(superset: State, variants: list[Template], held, tasks: int) -> tuple[DataFrame | None, dict]:
    """All variants of a level in one job: tasks hold the superset and take their share of the variants."""
    spark = superset.edges.sparkSession
    told = [v.to_json() for v in variants]
    columns = [held[c].to_numpy() for c in ("src", "dst", "smask")] + ([held["allow"].to_numpy()] if superset.template.demands else [None])
    shared = spark.sparkContext.broadcast((columns, told))

    def solved(batches):
        columns, told = shared.value
        memo: dict[str, np.ndarray] = {}
        base = None
        for batch in batches:
            for i in batch["id"].to_pylist():
                x = Template.from_json(told[i])
                base = base or local.Kept.of(x, *columns[:3], columns[3])
                whole, used = base.copy(x), {"walked": 0, "reused": 0}

                def fails(r, x=x, whole=whole, used=used):
                    """Sources that fail a rule on the superset, walked once for all variants of this task."""
                    key = r.signature(x)
                    used["reused" if key in memo else "walked"] += 1
                    if key not in memo:
                        own = whole.copy()
                        sources = np.flatnonzero(own.mask >> r.start & 1)
                        walk = local.Walk(own, local.WalkPlan(x, r.edges, r.start, keep=(r.start,)))
                        memo[key] = sources[~walk.run(sources)]
                    return memo[key]

                kept = whole.copy()
                for r in generate(x, False):
                    if r.kind == "cycle" and r.length <= 4 and len(bad := fails(r)):
                        kept.mask[bad] &= ~(1 << r.start)
                kept.settle()
                local.sieve_kept(kept, switch_below=1 << 62)  # what the short rules left is confirmed at once
                n = len(kept.s)
                yield pa.RecordBatch.from_pydict({
                    "variant": pa.array(np.full(n + 1, i, np.int32)), "src": pa.array([*kept.ids[kept.s].tolist(), None], pa.int64()), "dst": pa.array([*kept.ids[kept.d].tolist(), None], pa.int64()),
                    "smask": pa.array([*kept.mask[kept.s].tolist(), None], pa.int64()), "dmask": pa.array([*kept.mask[kept.d].tolist(), None], pa.int64()),
                    "told": pa.array([None] * n + [json.dumps({"matched": int(n > 0), **used})], pa.string()),
                })

    ids = spark.range(0, len(variants), 1, min(tasks, len(variants)))
    out = materialize(ids.mapInArrow(solved, "variant int, src long, dst long, smask long, dmask long, told string"), "explored")
    stats = F.from_json("told", "matched long, walked long, reused long").alias("x")
    total = out.filter("told is not null").select(stats).agg(*[F.sum(f"x.{c}").alias(c) for c in ("matched", "walked", "reused")]).first()
    shared.unpersist()
    found = out.filter("told is null").drop("told")
    return (found if total.matched else None), total.asDict()
