"""The main loop: reduce a graph to all that takes part in a match, then enumerate, count or rank on what is left."""

from __future__ import annotations

import time
from dataclasses import dataclass
from functools import cached_property, reduce
from math import factorial, prod

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphsieve.operators import local
from graphsieve.operators.reduce import LabeledGraph, State, init_candidates, neighbourhood_fixpoint
from graphsieve.operators.walks import begin, confirm, extend, hop, hubs_of, listed_cliques, rule_check, walk_check
from graphsieve.plans.rules import WalkPlan, best_start, generate, known_pairs, schedule, unchecked, walk_cost
from graphsieve.plans.template import Template, TemplateProfile

#: Directed active edges (32 bytes each) from which on the rest is left to one task.
LOCAL_EDGES = 1_000_000


@dataclass
class Solution:
    template: Template
    state: State
    exact: bool

    @property
    def trace(self) -> list[dict]:
        return self.state.trace

    @property
    def vertices(self) -> DataFrame:
        roles = F.filter(F.array(*[F.when(F.col("mask").bitwiseAND(F.lit(1 << q)) != 0, F.lit(q)) for q in range(self.template.n)]), lambda x: x.isNotNull())
        return self.state.vertices.select("vid", "label", "mask", roles.alias("roles"))

    @property
    def edges(self) -> DataFrame:
        return self.state.edges.select("src", "dst")

    def role_map(self) -> DataFrame:
        return self.vertices.select("vid", F.explode("roles").alias("role"))

    @cached_property
    def frequency(self) -> dict:
        return walk_frequency(self.state)


def label_frequency(state: State) -> dict[str, int]:
    """Vertices left by label: a row per label of the template's, never of the graph."""
    return {r[0]: r[1] for r in state.vertices.groupBy("label").count().collect()}


def walk_frequency(state: State) -> dict:
    """What walks are planned by: vertices left by label, and edges left by the labels of both ends (a row for each two labels of the template's)."""
    named = lambda mask: reduce(lambda c, x: c.when(F.col(mask).bitwiseAND(F.lit(x[1])) != 0, F.lit(x[0])), state.template.by_label.items(), F).alias(mask)
    t = state.template
    pairs = dict.fromkeys(((t.labels[x], t.labels[y]) for a, b in t.edges for x, y in ((a, b), (b, a))), 0)
    pairs |= {(r[0], r[1]): r[2] for r in state.edges.select(named("smask"), named("dmask")).groupBy("smask", "dmask").count().collect()} if pairs else {}
    return label_frequency(state) | pairs


def rules_of(trace: list[dict]) -> list[tuple[str, str]]:
    """The rules that a search has checked: their kind, and the start and edges."""
    return [(x["stage"], x["rule"]) for x in trace if x["stage"] in ("cycle", "path", "cover")]


def sieve(
    g: LabeledGraph | None, t: Template, *, rule: str = "hall", eliminate: str = "both", how: str = "live", policy: str = "type_then_length", starts: str = "all", extra: int = 0, edge_scope: str = "confirmed",
    max_rules: int | None = None, deadline_s: float | None = None, buckets: int = 1, switch_below: int | None = None, least_gain: float = 0.01, local_below: int = LOCAL_EDGES, hub_degree: int | None = None, state: State | None = None, count_tokens: bool = False, checked: tuple = (),
) -> Solution:
    """Reduce ``g`` to the union of all matches of ``t``.

    Neighbourhood checks to a fixpoint, then each rule followed by the fixpoint if it took something, then confirmation. Stopping early
    (``max_rules``, ``deadline_s``, or ``edge_scope="roles"``) leaves a superset: recall stays complete. ``starts``: "all" settles all roles of a
    rule by one walk forward and back; "every" walks a cycle from each of its roles and a path from both ends; "rarest" from one role.
    ``how`` folds tokens on what is read later ("live"), not at all ("none"), or walks cycles and paths in order with tokens of their issuer and last position
    ("issuer"; where that is unsafe, and in confirmation, "live"). ``buckets`` divides the tokens in flight. ``switch_below``: with fewer active edges rules are skipped and confirmation does
    all; so they are after a rule that took less than a share ``least_gain`` of the edges (0: every rule is checked). ``local_below``: with no more active edges the rest is done by one task; 0: never. ``hub_degree``: edges from which on a vertex is spread over tasks.
    ``state``: start from this superset instead of the graph; its tables stay. ``count_tokens``: walks that check one role at a time ("every", "rarest") are counted
    at every hop, so that the trace tells their tokens (those that come, before they are folded) and the walks they completed; it does so without for those of the other kind. ``checked``: rules that made ``state`` what it is, as
    ``rules_of`` its trace tells them; they are left out.
    """
    if starts not in ("all", "every", "rarest") or how not in ("live", "none", "issuer"):
        raise ValueError("starts is all, every or rarest; how is live, none or issuer")
    if how != "live" and starts == "all":
        starts = "every"  # a walk back needs folded tokens
    began = time.time()
    s = init_candidates(g, t) if state is None else State(t, state.edges, state.rows, state.alone, [], borrowed=True)
    options = {"rule": rule, "eliminate": eliminate, "how": how, "policy": policy, "starts": starts, "extra": extra, "edge_scope": edge_scope, "switch_below": switch_below, "least_gain": least_gain, "checked": checked}
    early = max_rules is not None

    def rest(s: State, k: int, skip: tuple = ()) -> Solution:
        left = None if deadline_s is None else deadline_s - (time.time() - began)
        out = local.sieve_here(s, **options, max_rules=None if max_rules is None else max(0, max_rules - k), deadline_s=left, skip=skip)
        out.trace[0].setdefault("started", began)
        return Solution(t, out, edge_scope != "roles" and (TemplateProfile.of(t).local_is_exact or out.trace[-1]["stage"] == "confirm" or not out.rows))

    if 0 < s.rows <= local_below:
        return rest(s, 0)
    at = time.time()
    s = neighbourhood_fixpoint(s, t, rule, eliminate, enough=local_below)
    s.trace[-1] |= {"seconds": time.time() - at, "tokens": 0}
    if 0 < s.rows <= local_below:
        return rest(s, 0)
    if TemplateProfile.of(t).local_is_exact or not s.rows:
        return Solution(t, s, True)
    listed = t.one_label_clique and starts == "all" and not early and deadline_s is None and edge_scope != "roles"
    freq = {} if listed else walk_frequency(s)
    # a walk would write every wedge of a clique of one label; confirmation closes them within tasks
    rules = [] if listed else unchecked(schedule(generate(t, starts == "every", freq, extra), policy, freq, t), checked, starts == "all")
    for k, r in enumerate(rules[:max_rules]):
        if not s.rows or (switch_below is not None and s.rows < switch_below):
            break
        if deadline_s is not None and time.time() - began > deadline_s:
            early = True
            break
        at, before = time.time(), s.rows
        hubs, seen = hubs_of(s) if hub_degree is None else hubs_of(s, hub_degree, 0), {}
        if starts == "all":
            s, took = rule_check(s, r, freq, buckets, hubs, seen)
        else:
            safe = r.kind != "cover" and len({t.labels[q] for q in r.roles}) >= len(r.roles) - (r.kind == "path")
            s, took = walk_check(s, r, how if how != "issuer" or safe else "live", freq, buckets, hubs, seen if count_tokens else None)
        s.trace.append({"stage": r.kind, "rule": f"{r.start}:{sorted(r.edges)}", "rounds": 1, "v": took["alive"], "e": s.rows, "messages": seen.get("tokens", 0), "tokens": seen.get("tokens", 0), "walks": seen.get("walks", 0), "seconds": time.time() - at})
        if took["moved"]:
            at = time.time()
            s = neighbourhood_fixpoint(s, t, rule, eliminate, enough=local_below)
            s.trace[-1] |= {"seconds": time.time() - at, "tokens": 0}
        if 0 < s.rows <= local_below:
            return rest(s, k + 1, tuple(x.signature(t) for x in rules[: k + 1]))
        if not early and before - s.rows < least_gain * before:
            break
    if edge_scope == "roles" or early:
        return Solution(t, s, False)
    at, seen = time.time(), {}
    s = confirm(s, freq, buckets, hubs_of(s) if hub_degree is None else hubs_of(s, hub_degree, 0), seen, "none" if how == "none" else "live")
    s.trace.append({"stage": "confirm", "rule": "full cover", "rounds": 1, "v": seen.get("alive", 0), "e": s.rows, "messages": seen.get("tokens", 0), "tokens": seen.get("tokens", 0), "walks": seen.get("walks", 0), "seconds": time.time() - at})
    return Solution(t, s, True)


def has_match(g: LabeledGraph | None, t: Template, *, local_below: int = LOCAL_EDGES, parts: int = 64, state: State | None = None) -> bool:
    """Whether there is any match, without reducing to all of them: after the neighbourhood checks, walks start from a growing share of the sources
    and end with the first that completes."""
    s = init_candidates(g, t) if state is None else State(t, state.edges, state.rows, state.alone, [], borrowed=True)
    if t.n == 1:
        return not s.masks.isEmpty()
    if s.rows > local_below:
        s = neighbourhood_fixpoint(s, t, enough=local_below)
    if not s.rows:
        return False
    if TemplateProfile.of(t).local_is_exact and s.rows > local_below:
        return True
    if s.rows <= local_below:
        return local.has_match_here(s)
    found, done = Solution(t, s, False), 0
    while done < parts:
        upto = min(parts, max(1, done * 4))
        if not _walked(found, lambda c, a=done, b=upto: F.pmod(F.xxhash64(c), F.lit(parts)).between(a, b - 1)).isEmpty():
            return True
        done = upto
    return False


def _plan(s: Solution, order=(), keep=()) -> WalkPlan:
    t, freq = s.template, s.frequency
    start = best_start(t, t.edges, freq, order) if t.edges else 0
    return WalkPlan(t, t.edges, start, freq, order, keep)


def _walked(s: Solution, sources=None, order=()) -> DataFrame:
    """All positions of all completed walks over the whole template."""
    if s.template.n == 1:
        tokens = begin(s.state, _plan(s))
        return tokens if sources is None else tokens.filter(sources("p0"))
    tokens = None
    for move in _plan(s, order).hops:
        tokens = hop(tokens, s.state, move, sources=sources)
    return tokens


def enumerate_matches(s: Solution, distinct_subgraphs: bool = False, induced_in: DataFrame | None = None, bucket: tuple[int, int] | None = None) -> DataFrame:
    """One row ``(r0, r1, ...)`` per embedding, or per subgraph; ``induced_in``: edges of which a match may have no others among its vertices.

    ``bucket`` (b, of): only walks from that share of the sources, so that a long enumeration can be done and written in parts.
    """
    t = s.template
    share = None if bucket is None else (lambda c: F.pmod(F.xxhash64(c), F.lit(bucket[1])) == bucket[0])
    out = _walked(s, share, t.symmetry_order if distinct_subgraphs else ()).select(*[F.col(f"p{q}").alias(f"r{q}") for q in range(t.n)])
    if induced_in is not None:
        for a in range(t.n):
            for b in range(a + 1, t.n):
                if (a, b) not in t.edges:
                    out = out.join(induced_in.select(F.col("src").alias(f"r{a}"), F.col("dst").alias(f"r{b}")), [f"r{a}", f"r{b}"], "left_anti")
        out = out.select(*[f"r{q}" for q in range(t.n)])
    return out


def _merged(s: Solution, parts: tuple[tuple[int, ...], ...]) -> tuple[Template, DataFrame] | None:
    """The template with the roles of each part made one, and the state's edges with its masks; none where the template's edges join roles of a part."""
    t = s.template
    at = {q: k for k, own in enumerate(parts) for q in own}
    if any(at[a] == at[b] for a, b in t.edges):
        return None
    mask = lambda c: reduce(Column.bitwiseOR, [F.when(F.col(c).bitwiseAND(F.lit(m := sum(1 << q for q in own))) == m, F.lit(1 << k).cast("long")).otherwise(F.lit(0).cast("long")) for k, own in enumerate(parts)]).alias(c)
    return Template.build([t.labels[own[0]] for own in parts], [(at[a], at[b]) for a, b in t.edges]), s.state.edges.select("src", "dst", mask("smask"), mask("dmask"))


def _partitions(t: Template, most: int = 16) -> list[tuple[tuple[int, ...], ...]]:
    """All ways to make roles of one label one, unless they are more than ``most``."""
    out: list[tuple[tuple[int, ...], ...]] = [()]
    for q in range(t.n):
        out = [x for p in out for x in [*((*p[:k], (*own, q), *p[k + 1 :]) for k, own in enumerate(p) if t.labels[own[0]] == t.labels[q] and not any(y in t.adjacent[q] for y in own)), (*p, (q,))]]
        if len(out) > most:
            return []
    return out


def _counted(state: State, plan: WalkPlan, buckets: int) -> DataFrame:
    """One row ``(n)``: walks of a plan; tokens alike in what is read later are one with their number."""
    parts = []
    for b in range(buckets):
        tokens = None
        for move in plan.hops:
            if tokens is None:
                share = None if buckets == 1 else (lambda c, b=b: F.pmod(F.xxhash64(c), F.lit(buckets)) == b)
                wide = hop(None, state, move, sources=share).withColumn("n", F.lit(1).cast("decimal(38,0)"))
            else:
                wide = hop(tokens, state, move)
            step, chords = move
            live = (chords[-1] if chords else step).live
            tokens = wide.groupBy(*[f"p{q}" for q in live]).agg(F.sum("n").cast("decimal(38,0)").alias("n")) if move != plan.hops[-1] else wide
        parts.append(tokens.agg(F.sum("n").cast("decimal(38,0)").alias("n")))
    return reduce(DataFrame.unionByName, parts)


def count_matches(s: Solution, unit: str = "embeddings", buckets: int = 1) -> DataFrame:
    """One row ``(n)``. Tokens carry how many walks they stand for, so matches are counted without being listed; ``buckets`` parts the sources.

    That roles of one label are different vertices keeps both in every token. Where it is cheaper, walks are counted without that test, and those in
    which such roles are the same vertex are counted on templates with these roles made one, and taken off (Moebius inversion over partitions).
    Counts are kept in 38 digits; a total that is no 64-bit integer raises an overflow error.
    """
    t = s.template
    if t.n == 1:
        return begin(s.state, _plan(s)).agg(F.count("*").alias("n"))
    if t.one_label_clique and (s.state.matches is not None or s.state.rows > LOCAL_EDGES):
        each = listed_cliques(s.state) if s.state.matches is None else s.state.matches
        return each.agg((F.count("*") * F.lit(1 if unit == "subgraphs" else factorial(t.n))).alias("n"))
    plan = _plan(s, t.symmetry_order if unit == "subgraphs" else ())
    terms = [(1, s.state, plan)]
    splits = _partitions(t) if unit == "embeddings" and not t.demands else []
    if len(splits) > 1 and known_pairs(t, s.frequency):
        free = []
        for parts in splits:
            merged, edges = _merged(s, parts)
            start = best_start(merged, merged.edges, s.frequency, differ=False)
            sign = prod((-1) ** (len(own) - 1) * factorial(len(own) - 1) for own in parts)
            free.append((sign, State(merged, edges, s.state.rows, borrowed=True), WalkPlan(merged, merged.edges, start, s.frequency, differ=False)))
        if sum(walk_cost(x.template, s.frequency, p.start, differ=False) for _, x, p in free) < walk_cost(t, s.frequency, plan.start):
            terms = free
    counts = [_counted(state, p, buckets).select((F.col("n") * F.lit(sign).cast("decimal(3,0)")).cast("decimal(38,0)").alias("n")) for sign, state, p in terms]
    return reduce(DataFrame.unionByName, counts).agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n"))


def estimate_matches(s: Solution, fraction: float = 0.25, seed: int = 1, buckets: int = 16) -> dict:
    """Embeddings estimated from a hashed share of the start vertices, with a standard error from the buckets' spread."""
    draw = lambda c: F.pmod(F.xxhash64(c, F.lit(seed)), F.lit(1 << 20)) < int(fraction * (1 << 20))
    tokens = _walked(s, draw)
    bucket = F.pmod(F.xxhash64(f"p{_plan(s).start}", F.lit(seed + 1)), F.lit(buckets)).alias("bucket")
    n = {r[0]: r[1] for r in tokens.groupBy(bucket).count().collect()}
    each = [n.get(b, 0) for b in range(buckets)]
    mean = sum(each) / buckets
    spread = (sum((x - mean) ** 2 for x in each) / max(1, buckets - 1) * buckets) ** 0.5
    return {"estimate": sum(each) / fraction, "error": spread / fraction}


def centrality(s: Solution, on: str = "vertex", top: int | None = None) -> DataFrame:
    """Matches through every vertex, (vertex, role) or edge; the commonest ``top``, ties by id."""
    t, m = s.template, enumerate_matches(s)
    if on == "edge":
        items = F.array(*[F.struct(F.least(f"r{a}", f"r{b}").alias("src"), F.greatest(f"r{a}", f"r{b}").alias("dst")) for a, b in t.edges])
        keys = ["src", "dst"]
    else:
        items = F.array(*[F.struct(F.col(f"r{q}").alias("vid"), F.lit(q).alias("role")) for q in range(t.n)])
        keys = ["vid"] if on == "vertex" else ["vid", "role"]
    out = m.select(F.explode(items).alias("x")).select("x.*").groupBy(*keys).agg(F.count("*").alias("n"))
    return out.orderBy(F.desc("n"), *keys).limit(top) if top else out


__all__ = ["LOCAL_EDGES", "Solution", "centrality", "count_matches", "enumerate_matches", "estimate_matches", "extend", "has_match", "label_frequency", "rules_of", "sieve"]
