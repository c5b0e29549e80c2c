"""What is left of a graph, once small, reduced in one task: the same checks on arrays, with walks explored depth first.

A reduced graph often fits one worker many times over, and then each further round costs a job's overhead and little else. From a
checked number of edges on, ``sieve`` hands the active edges to a single task. Tokens are explored depth first: of an expansion that
exceeds ``CAP`` rows a part at a time, so memory follows CAP and the length of the walk, not the number of walks.
"""

from __future__ import annotations

import json
import time
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphsieve.functions.storage import materialize
from graphsieve.operators.reduce import State, _needs
from graphsieve.plans.rules import Rule, WalkPlan, best_start, full_cover, generate, schedule, unchecked
from graphsieve.plans.template import Template, TemplateProfile

#: Tokens that are expanded at once.
CAP = 2_000_000
#: Expansions beyond so many may meet the paths between both ends of a chord instead, of which so many are held at most.
MEET, PATHS = 200_000, 4_000_000


class Kept:
    """Active edges ``s -> d`` (indexes into ``ids``, in order) and the mask of every vertex. ``allow``: arcs that an edge may play."""

    def __init__(self, t: Template, ids: np.ndarray, s: np.ndarray, d: np.ndarray, mask: np.ndarray, allow: np.ndarray | None = None):
        self.t, self.ids, self.s, self.d, self.mask, self.allow = t, ids, s, d, mask, allow
        self._steps: dict = {}

    @classmethod
    def of(cls, t: Template, src: np.ndarray, dst: np.ndarray, smask: np.ndarray, allow: np.ndarray | None = None) -> Kept:
        ids, s = np.unique(src, return_inverse=True)
        at = np.searchsorted(ids, dst)
        fits = (at < len(ids)) & (ids[np.minimum(at, max(0, len(ids) - 1))] == dst) if len(ids) else np.zeros(0, bool)
        s, d, smask = s[fits], at[fits], smask[fits]
        mask = np.zeros(len(ids), np.int64)
        mask[s] = smask
        order = np.lexsort((d, s))
        return cls(t, ids, s[order], d[order], mask, None if allow is None else allow[fits][order])

    def copy(self, t: Template | None = None) -> Kept:
        return Kept(t or self.t, self.ids, self.s, self.d, self.mask.copy(), self.allow)

    @property
    def alive(self) -> int:
        return int((self.mask != 0).sum())

    def plays(self, a: int, b: int) -> np.ndarray:
        ok = (self.mask[self.s] >> a & 1 & self.mask[self.d] >> b) != 0
        return ok & (self.allow >> self.t.arcs[a, b] & 1 != 0) if self.t.demands else ok

    def keep_edges(self, ok: np.ndarray) -> None:
        self.s, self.d = self.s[ok], self.d[ok]
        self.allow = None if self.allow is None else self.allow[ok]
        self._steps = {}

    def settle(self, eliminate: str = "both") -> None:
        """Edges that no template edge can be go, and roles of vertices without edges."""
        if eliminate == "both":
            if self.t.demands:
                ok = np.zeros(len(self.s), bool)
                for a, b in self.t.arcs:
                    ok |= self.plays(a, b)
            else:
                ok, sm, dm = np.zeros(len(self.s), bool), self.mask[self.s], self.mask[self.d]
                for q in range(self.t.n):
                    ok |= (sm >> q & 1 != 0) & (dm & self.t.adjmask[q] != 0)
        else:
            ok = (self.mask[self.s] != 0) & (self.mask[self.d] != 0)
        self.keep_edges(ok)
        there = np.zeros(len(self.ids), bool)
        there[self.s] = True
        self.mask[~there] = 0

    def round(self, rule: str, eliminate: str, relaxed: bool = False) -> bool:
        """One neighbourhood check; whether it took anything."""
        t = self.t
        if not len(self.s):
            moved, self.mask = bool(self.mask.any()), np.zeros_like(self.mask)
            return moved
        first = np.flatnonzero(np.r_[True, self.s[1:] != self.s[:-1]])
        own = self.s[first]
        if t.demands:
            near, place = np.zeros(len(self.s), np.int64), lambda q, x: t.arcs[q, x]
            for (a, b), k in t.arcs.items():
                near |= self.plays(a, b).astype(np.int64) << k
        else:
            near, place = self.mask[self.d], lambda q, x: x
        bits = lambda q, xs: sum(1 << place(q, x) for x in xs)
        seen, mask, new = np.bitwise_or.reduceat(near, first), self.mask[own], np.zeros(len(own), np.int64)
        needs = _needs(t, "set" if relaxed else rule)
        for q in range(t.n):
            must = bits(q, [x for x in t.adjacent[q] if not relaxed or (min(q, x), max(q, x)) in t.mandatory])
            ok = (mask >> q & 1 != 0) & (seen & must == must)
            if relaxed:
                ok &= seen & bits(q, t.adjacent[q]) != 0
            for s, k in needs[q]:
                ok &= np.add.reduceat((near & bits(q, s) != 0).astype(np.int64), first) >= k
            new |= ok.astype(np.int64) << q
        after = np.zeros_like(self.mask)
        after[own] = new
        moved = bool((after != self.mask).any())
        self.mask = after
        if moved:
            self.settle(eliminate)
        return moved

    def fixpoint(self, rule: str = "hall", eliminate: str = "both", max_rounds: int | None = None, relaxed: bool = False) -> tuple[int, int]:
        """Rounds and messages until nothing goes."""
        rounds = messages = 0
        while max_rounds is None or rounds < max_rounds:
            messages += len(self.s)
            rounds += 1
            if not self.round(rule, eliminate, relaxed):
                break
        return rounds, messages

    def frequency(self) -> dict:
        """Vertices by label, and edges by the labels of both ends of template edges."""
        plays = {x: self.mask & m != 0 for x, m in self.t.by_label.items()}
        pairs = {(self.t.labels[x], self.t.labels[y]) for a, b in self.t.edges for x, y in ((a, b), (b, a))}
        return {x: int(m.sum()) for x, m in plays.items()} | {(x, y): int((plays[x][self.s] & plays[y][self.d]).sum()) for x, y in pairs}

    def step(self, a: int, b: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Edges that may play a-b: their targets by source, where each source's begin, and all as sorted pairs."""
        if (a, b) not in self._steps:
            ok = self.plays(a, b)
            s, d = self.s[ok], self.d[ok]
            self._steps[a, b] = d, np.searchsorted(s, np.arange(len(self.ids) + 1)), s * len(self.ids) + d
        return self._steps[a, b]


def _classes(columns: list[np.ndarray], n: int, base: int) -> tuple[np.ndarray, np.ndarray]:
    """First row and class of every distinct combination."""
    if not columns:
        return np.zeros(min(1, n), np.int64), np.zeros(n, np.int64)
    key, size = columns[0], base
    for c in columns[1:]:
        if size > (1 << 62) // max(1, base):
            key = np.unique(key, return_inverse=True)[1]
            size = len(key)
        key, size = key * base + c, size * base
    _, first, which = np.unique(key, return_index=True, return_inverse=True)
    return first, which


class Walk:
    """A walk plan on kept edges: which tokens complete, and on the way back which edges play which template edges.

    ``tokens`` and ``walks`` count the rows of every expansion and of the last, before they are folded; ``first``: stop at the first completed walk.
    """

    def __init__(self, kept: Kept, plan: WalkPlan, how: str = "live", record: bool = False, first: bool = False, cap: int = CAP):
        self.kept, self.plan, self.how, self.first, self.cap = kept, plan, how, first, cap
        self.tokens, self.walks, self.found, self.paths = 0, 0, False, {}
        self.pairs: dict[tuple[int, int], list[np.ndarray]] | None = {} if record else None
        self.lives = [(m[1][-1] if m[1] else m[0]).live for m in plan.hops]

    def run(self, sources: np.ndarray) -> np.ndarray:
        """Which of the sources have a completed walk."""
        return self._complete({self.plan.start: sources}, len(sources), 0)

    def _complete(self, tokens: dict[int, np.ndarray], n: int, k: int) -> np.ndarray:
        if k == len(self.plan.hops) or not n:
            self.found |= bool(n)
            return np.ones(n, bool)
        if self.how == "none":
            rows, which = np.arange(n), None
        else:
            rows, which = _classes([tokens[q] for q in sorted(tokens)], n, len(self.kept.ids))
        good = self._expanded({q: c[rows] for q, c in tokens.items()}, len(rows), k)
        return good if which is None else good[which]

    def _met(self, k: int, n: int, total: int) -> tuple[int, np.ndarray, np.ndarray] | None:
        """The chord to meet at a step, with the sorted ends of the paths from the step's place over its role to the chord's, and that role's vertices; none if these are too many."""
        step, chords = self.plan.hops[k]
        if k not in self.paths:
            found = None
            targets, begins, _ = self.kept.step(step.at, step.to)
            for c in chords:
                ends, starts, _ = self.kept.step(c.to, c.at)
                wide = starts[targets + 1] - starts[targets]
                if found is None or wide.sum() < found[0]:
                    found = int(wide.sum()), c.at, wide, ends, starts
            many, over, wide, ends, starts = found
            self.paths[k] = None
            if many <= min(PATHS, total):
                at = np.repeat(np.arange(len(self.kept.ids)), np.diff(begins))
                spot = np.arange(many) - np.repeat(np.cumsum(wide) - wide, wide) + np.repeat(starts[targets], wide)
                keys = np.repeat(at, wide) * len(self.kept.ids) + ends[spot]
                order = np.argsort(keys, kind="stable")
                self.paths[k] = over, keys[order], np.repeat(targets, wide)[order]
        return self.paths[k] if total > 2 * n else None

    def _expanded(self, tokens: dict[int, np.ndarray], n: int, k: int) -> np.ndarray:
        step, chords = self.plan.hops[k]
        targets, begins, _ = self.kept.step(step.at, step.to)
        at = tokens[step.at]
        low, width = begins[at], begins[at + 1] - begins[at]
        total, cap = int(width.sum()), 4096 if self.first else self.cap
        met = self._met(k, n, total) if chords and total > MEET and not self.first else None
        if met is not None:  # tokens that hold both ends meet the paths over the new role
            over, keys, targets = met
            key = tokens[step.at] * len(self.kept.ids) + tokens[over]
            low = np.searchsorted(keys, key)
            width = np.searchsorted(keys, key, "right") - low
            total, chords_left = int(width.sum()), tuple(c for c in chords if c.at != over)
        else:
            chords_left = chords
        if total > cap and n > 1:  # a part at a time, depth first
            cut = min(max(1, int(np.searchsorted(np.cumsum(width), total // 2))), n - 1)
            left = self._expanded({q: c[:cut] for q, c in tokens.items()}, cut, k)
            if self.first and self.found:
                return np.r_[left, np.zeros(n - cut, bool)]
            return np.r_[left, self._expanded({q: c[cut:] for q, c in tokens.items()}, n - cut, k)]
        row = np.repeat(np.arange(n), width)
        place = np.arange(total) - np.repeat(np.cumsum(width) - width, width) + np.repeat(low, width)
        new = targets[place]
        ok = np.ones(total, bool)
        for x in step.differs:
            ok &= tokens[x][row] != new
        row, new = row[ok], new[ok]
        wide = {q: c[row] for q, c in tokens.items()} | {step.to: new}
        for c in chords_left:
            _, _, sorted_pairs = self.kept.step(c.at, c.to)
            key = wide[c.at] * len(self.kept.ids) + wide[c.to]
            spot = np.searchsorted(sorted_pairs, key)
            ok = spot < len(sorted_pairs)
            ok[ok] = sorted_pairs[spot[ok]] == key[ok]
            row, wide = row[ok], {q: x[ok] for q, x in wide.items()}
        self.tokens += len(row)
        self.walks += len(row) if k == len(self.plan.hops) - 1 else 0
        live = wide.keys() if self.how == "none" else self.lives[k]
        done = self._complete({q: wide[q] for q in live}, len(row), k + 1)
        if self.pairs is not None and done.any():
            for s in (step, *chords):
                key = wide[s.at][done] * len(self.kept.ids) + wide[s.to][done]
                self.pairs.setdefault((s.at, s.to), []).append(np.unique(key))
        good = np.zeros(n, bool)
        good[row[done]] = True
        return good


def confirmed(kept: Kept, edges, frequency: dict, how: str = "live") -> tuple[dict, int, int]:
    """By template edge, the data edges (as pair keys) that play it in a completed walk over all of ``edges``; and the tokens that it took, and completed walks."""
    t = kept.t
    start = best_start(t, edges, frequency)
    walk = Walk(kept, WalkPlan(t, edges, start, frequency), how, record=True)
    walk.run(np.flatnonzero(kept.mask >> start & 1))
    return {k: np.unique(np.concatenate(x)) for k, x in walk.pairs.items()}, walk.tokens, walk.walks


def _roles(kept: Kept, pairs: dict) -> np.ndarray:
    out, n = np.zeros(len(kept.ids), np.int64), len(kept.ids)
    for (a, b), keys in pairs.items():
        out[keys // n] |= 1 << a
        out[keys % n] |= 1 << b
    return out


def check_rule(kept: Kept, rule: Rule, frequency: dict, how: str, all_roles: bool, eliminate: str) -> tuple[int, int]:
    """Takes roles that a rule's walk does not certify: all the rule's roles at once, or the start's alone. Returns the tokens used, and the completed walks."""
    if all_roles:
        pairs, tokens, walks = confirmed(kept, rule.edges, frequency, how)
        inside = sum(1 << q for q in rule.roles)
        new = kept.mask & ~inside | kept.mask & _roles(kept, pairs)
    else:
        from graphsieve.operators.walks import rule_plan

        if how == "issuer" and (rule.kind == "cover" or len({kept.t.labels[q] for q in rule.roles}) < len(rule.roles) - (rule.kind == "path")):
            how = "live"
        walk = Walk(kept, rule_plan(kept.t, rule, how, frequency), how)
        sources = np.flatnonzero(kept.mask >> rule.start & 1)
        new = kept.mask.copy()
        new[sources[~walk.run(sources)]] &= ~(1 << rule.start)
        tokens, walks = walk.tokens, walk.walks
    if (new != kept.mask).any():
        kept.mask = new
        kept.settle(eliminate)
    return tokens, walks


def confirm(kept: Kept, frequency: dict, how: str = "live") -> tuple[int, int]:
    """Leaves the exact answer."""
    pairs, tokens, walks = confirmed(kept, kept.t.edges, frequency, how)
    n = len(kept.ids)
    keys = np.concatenate([np.zeros(0, np.int64), *pairs.values(), *[k % n * n + k // n for k in pairs.values()]])
    kept.mask = _roles(kept, pairs)
    kept.keep_edges(np.isin(kept.s * n + kept.d, keys))
    return tokens, walks


def has_walk(kept: Kept, frequency: dict) -> bool:
    """Whether there is a match at all; stops at the first."""
    t = kept.t
    start = min(range(t.n), key=lambda q: (frequency.get(t.labels[q], 0), q))
    walk = Walk(kept, WalkPlan(t, t.edges, start, frequency), first=True)
    walk.run(np.flatnonzero(kept.mask >> start & 1))
    return walk.found


def sieve_kept(kept: Kept, *, rule: str = "hall", eliminate: str = "both", how: str = "live", policy: str = "type_then_length", starts: str = "all", extra: int = 0, edge_scope: str = "confirmed", max_rules: int | None = None, deadline_s: float | None = None, switch_below: int | None = None, least_gain: float = 0.01, skip: tuple[str, ...] = (), checked: tuple = (), memo: Callable | None = None) -> list[dict]:
    """The whole main loop on kept edges; returns its trace. ``skip``: signatures of rules that were checked before, ``checked``: others as a trace tells them. ``memo``: asked for the sources
    that are known to fail a rule."""
    t, trace = kept.t, []
    began = at = time.time()
    rounds, messages = kept.fixpoint(rule, eliminate)

    def note(stage, name, rounds, messages, tokens=0, walks=0):
        nonlocal at
        trace.append({"stage": stage, "rule": name, "rounds": rounds, "v": kept.alive, "e": len(kept.s), "messages": messages, "tokens": tokens, "walks": walks, "seconds": time.time() - at})
        at = time.time()

    note("neighbourhood", rule, rounds, messages)
    if TemplateProfile.of(t).local_is_exact:
        return trace
    freq = kept.frequency()
    rules = [r for r in unchecked(schedule(generate(t, starts == "every", freq, extra), policy, freq, t), checked, starts == "all") if r.signature(t) not in skip]
    early = max_rules is not None
    for r in rules[:max_rules]:
        if not len(kept.s) or (switch_below is not None and len(kept.s) < switch_below):
            break
        if deadline_s is not None and time.time() - began > deadline_s:
            early = True
            break
        before = int(kept.mask.sum()), len(kept.s)
        if memo is not None and (bad := memo(r)) is not None and len(bad):
            kept.mask[bad] &= ~(1 << r.start)
            kept.settle(eliminate)
        tokens, walks = check_rule(kept, r, freq, how, starts == "all", eliminate)
        note(r.kind, f"{r.start}:{sorted(r.edges)}", 1, tokens, tokens, walks)
        if (int(kept.mask.sum()), len(kept.s)) != before:
            rounds, messages = kept.fixpoint(rule, eliminate)
            note("neighbourhood", rule, rounds, messages)
        if not early and before[1] - len(kept.s) < least_gain * before[1]:
            break
    if edge_scope != "roles" and not early:
        tokens, walks = confirm(kept, freq, "live" if how == "issuer" else how)
        note("confirm", "full cover", 1, tokens, tokens, walks)
    return trace


_ROWS = "src long, dst long, smask long, dmask long, allow long, told string"


def _gathered(batches) -> list[np.ndarray]:
    table = [b for b in batches if b.num_rows]
    names = table[0].schema.names if table else ["src", "dst", "smask", "dmask"]
    return [np.concatenate([b[n].to_numpy(zero_copy_only=False) for b in table]) if table else np.zeros(0, np.int64) for n in names]


def as_rows(kept: Kept, trace: list[dict]):
    """Edges of the answer, and one row with the trace."""
    s, d = kept.s, kept.d
    allow = pa.nulls(len(s), pa.int64()) if kept.allow is None else pa.array(kept.allow)
    yield pa.RecordBatch.from_arrays([pa.array(kept.ids[s]), pa.array(kept.ids[d]), pa.array(kept.mask[s]), pa.array(kept.mask[d]), allow, pa.nulls(len(s), pa.string())], names=["src", "dst", "smask", "dmask", "allow", "told"])
    yield pa.RecordBatch.from_pydict({**{c: pa.nulls(1, pa.int64()) for c in ("src", "dst", "smask", "dmask", "allow")}, "told": pa.array([json.dumps(trace)])})


def sieve_here(state: State, **options) -> State:
    """``sieve_kept`` in one task on a state whose number of edges has been checked, as a written answer with its trace."""
    t = state.template

    def solved(batches):
        kept_columns = _gathered(batches)
        kept = Kept.of(t, *kept_columns[:3], kept_columns[4] if t.demands else None)
        yield from as_rows(kept, sieve_kept(kept, **options))

    out = materialize(state.edges.coalesce(1).mapInArrow(solved, _ROWS), "local")
    trace = json.loads(out.filter(F.col("told").isNotNull()).select("told").first()[0])
    edges: DataFrame = out.filter(F.col("told").isNull()).select("src", "dst", "smask", "dmask", *(["allow"] if t.demands else []))
    return State(t, edges, trace[-1]["e"], None, [*state.trace, *trace])


def has_match_here(state: State) -> bool:
    t = state.template

    def asked(batches):
        columns = _gathered(batches)
        kept = Kept.of(t, *columns[:3], columns[4] if t.demands else None)
        kept.fixpoint()
        yield pa.RecordBatch.from_pydict({"found": pa.array([bool(len(kept.s)) and has_walk(kept, kept.frequency())])})

    return state.edges.coalesce(1).mapInArrow(asked, "found boolean").first()[0]
