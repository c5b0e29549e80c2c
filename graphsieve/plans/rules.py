"""Rules beyond one hop: cycles, paths between equal labels, and covers that walk whole parts of a template."""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass
from itertools import combinations

from graphsieve.plans.template import Template, TemplateProfile


@dataclass(frozen=True)
class Rule:
    """Template edges that a walk from ``start`` must find together."""

    kind: str  # cycle, path or cover
    start: int
    edges: frozenset

    @property
    def length(self) -> int:
        return len(self.edges)

    @property
    def roles(self) -> tuple[int, ...]:
        return tuple(sorted({x for e in self.edges for x in e}))

    def signature(self, t: Template) -> str:
        return f"{self.kind}:{self.start}:{sorted(self.edges)}:{[t.labels[q] for q in self.roles]}:{[d for d in t.demands if tuple(sorted(d[:2])) in self.edges]}"

    def sequence(self) -> tuple[int, ...] | None:
        """Roles of a cycle or path in the order of a walk from ``start``; none for covers."""
        if self.kind == "cover":
            return None
        near: dict[int, list[int]] = {}
        for a, b in sorted(self.edges):
            near.setdefault(a, []).append(b)
            near.setdefault(b, []).append(a)
        out = [self.start]
        while more := [x for x in near[out[-1]] if x not in out]:
            out.append(more[0])
        return tuple(out)


def cycle_rules(profile: TemplateProfile, every_start: bool = True, frequency: dict | None = None) -> list[Rule]:
    """A rule for each cycle: from every role in the order of label frequency, or from that of the rarest label alone."""
    labels, freq = profile.template.labels, frequency or {}
    out = []
    for c in profile.cycles:
        starts = sorted(c, key=lambda q: (freq.get(labels[q], 0), q))
        out += [Rule("cycle", q, profile.edges_of(c)) for q in (starts if every_start else starts[:1])]
    return out


def _shortest_path(t: Template, a: int, b: int, least: int) -> tuple | None:
    """Shortest simple path of at least ``least`` edges."""
    best, todo = None, [(a,)]
    while todo and best is None:
        longer = []
        for p in todo:
            for x in sorted(t.adjacent[p[-1]]):
                if x == b and len(p) >= least:
                    best = best or (*p, x)
                elif x not in p and x != b:
                    longer.append((*p, x))
        todo = longer
    return best


def path_rules(profile: TemplateProfile, skip_covered: bool = True) -> list[Rule]:
    """For every two roles of one label: their shortest path of three or more edges, from both ends; not if one cycle has all its edges."""
    t, out = profile.template, []
    for a, b in combinations(sorted(profile.repeated), 2):
        if t.labels[a] == t.labels[b] and (p := _shortest_path(t, a, b, 3)):
            edges = frozenset((min(x), max(x)) for x in zip(p, p[1:]))
            if not (skip_covered and any(edges <= profile.edges_of(c) for c in profile.cycles)):
                out += [Rule("path", a, edges), Rule("path", b, edges)]
    return out


def _merged(sets: list[frozenset], touch) -> list[frozenset]:
    out: list[frozenset] = []
    for s in sets:
        near = [x for x in out if touch(x, s)]
        out = [x for x in out if x not in near] + [frozenset.union(s, *near)]
    return out


def cycle_covers(profile: TemplateProfile) -> list[frozenset]:
    """Unions of cycles that share edges (of two or more cycles)."""
    sets = [profile.edges_of(c) for c in profile.cycles]
    return [x for x in _merged(sets, lambda a, b: bool(a & b)) if x not in sets]


def path_covers(profile: TemplateProfile, spanning_tree: bool = True) -> list[frozenset]:
    """Unions of paths that share a role; edges that close a cycle are left to other rules if ``spanning_tree``."""
    sets = list(dict.fromkeys(r.edges for r in path_rules(profile, skip_covered=False)))
    roles = lambda s: {x for e in s for x in e}
    out = []
    for s in _merged(sets, lambda a, b: bool(roles(a) & roles(b))):
        if spanning_tree:
            top: dict[int, int] = {}

            def find(x, top=top):
                while top.setdefault(x, x) != x:
                    x = top[x]
                return x

            kept = set()
            for a, b in sorted(s):
                if find(a) != find(b):
                    top[find(a)] = find(b)
                    kept.add((a, b))
            s = frozenset(kept)
        if s not in sets:
            out.append(s)
    return out


def full_cover(t: Template) -> Rule:
    """The rule that leaves no false positive: all edges of the template."""
    return Rule("cover", 0, frozenset(t.edges))


def extra_covers(profile: TemplateProfile, most: int) -> list[frozenset]:
    """Optional further covers: unions of two or three cycles and paths that share a role, the smallest first, ``most`` at most.

    Any such union is a part of the template, so the rule is sound; only the full cover is needed for exactness.
    """
    parts = list(dict.fromkeys([*(profile.edges_of(c) for c in profile.cycles), *(r.edges for r in path_rules(profile))]))
    roles = lambda s: {x for e in s for x in e}
    known, out = {*parts, *cycle_covers(profile), *path_covers(profile), frozenset(profile.template.edges)}, []
    for k in (2, 3):
        for group in combinations(parts, k):
            s = frozenset.union(*group)
            if s not in known and all(any(roles(a) & roles(b) for b in group if b is not a) for a in group):
                known.add(s)
                out.append(s)
    return sorted(out, key=lambda s: (len(s), sorted(s)))[:most]


def generate(t: Template, every_start: bool = True, frequency: dict | None = None, extra: int = 0) -> list[Rule]:
    """Cycle, path and cover rules of a template; none where neighbourhood checks are exact. The full cover is not among them.

    ``extra``: so many optional covers besides the heuristic ones.
    """
    profile = TemplateProfile.of(t)
    if profile.local_is_exact:
        return []
    covers = []
    for s in [*cycle_covers(profile), *path_covers(profile), *extra_covers(profile, extra)]:
        starts = sorted({x for e in s for x in e} & (profile.repeated or {min(min(e) for e in s)})) or [min(min(e) for e in s)]
        covers += [Rule("cover", q, s) for q in (starts if every_start else starts[:1]) if len(s) < len(t.edges)]
    return [*cycle_rules(profile, every_start, frequency), *path_rules(profile), *covers]


def schedule(rules: list[Rule], policy: str = "type_then_length", frequency: dict | None = None, t: Template | None = None) -> list[Rule]:
    """Cheap rules first: paths and cycles by length, then covers; or by length alone, as given, or rare starts first."""
    if policy == "given":
        return list(rules)
    if policy == "length":
        return sorted(rules, key=lambda r: (r.length, r.start))
    if policy == "rarest_first":
        return sorted(rules, key=lambda r: (r.kind == "cover", (frequency or {}).get(t.labels[r.start], 0), r.length, r.start))
    return sorted(rules, key=lambda r: (r.kind == "cover", r.length, r.start, sorted(r.edges)))


def unchecked(rules: list[Rule], checked, all_roles: bool) -> list[Rule]:
    """Rules that are not among those ``checked``, told by kind and ``start:edges``. With ``all_roles`` a rule is the same from whichever start: each one checked takes one of
    its kind and edges off."""
    own = lambda kind, name: (kind, name.partition(":")[2] if all_roles else name)
    left, out = Counter(own(*x) for x in checked), []
    for r in rules:
        key = own(r.kind, f"{r.start}:{sorted(r.edges)}")
        if left[key]:
            left[key] -= 1
        else:
            out.append(r)
    return out


@dataclass(frozen=True)
class Step:
    """Binds role ``to`` over the edge from ``at``, or (``chord``) tests the edge between two bound roles."""

    at: int
    to: int
    chord: bool
    differs: tuple[int, ...]  # bound roles of the same label
    below: tuple[tuple[int, int], ...]  # order tests that become possible
    live: tuple[int, ...]  # roles that are read later
    over: int | None = None  # the chord's role, where tokens had better meet the paths from ``at`` over ``to`` to it


#: Expected rows of an extension from which on tokens may meet paths instead.
MEET_FROM = 5_000_000
#: Up to so many roles every order of a walk is compared; in larger ones the next step is the cheapest.
ALL_ORDERS = 7


class _Costs:
    """Rows that a walk is expected to make: joins of independent ends, folded to the positions that are read later.

    ``frequency`` holds vertices by label and edges by the pair of their ends' labels.
    """

    def __init__(self, t: Template, edges, frequency: dict, order=(), keep=(), differ: bool = True, two: bool = False):
        self.t, self.edges, self.keep, self.two = t, set(edges), set(keep), two
        self.near: dict[int, set[int]] = {}
        for a, b in self.edges:
            self.near.setdefault(a, set()).add(b)
            self.near.setdefault(b, set()).add(a)
        self.n = {q: max(1, frequency.get(t.labels[q], 0)) for q in self.near}
        self.many = {(a, b): frequency.get((t.labels[a], t.labels[b]), 0) for a in self.near for b in self.near[a]}
        self.tested = {q: {x for x in self.near if differ and x != q and t.labels[x] == t.labels[q]} | {x for p in order if q in p for x in p if x != q} for q in self.near}

    def fan(self, a: int, b: int) -> float:
        return self.many[a, b] / self.n[a]

    def paths(self, at: int, to: int, chords: list[int]) -> tuple[float, int] | None:
        """The fewest paths from a step's place over its role to a chord's, with that chord."""
        return min(((self.many[at, to] * self.fan(to, x), x) for x in chords), default=None)

    def over(self, bound: tuple[int, ...], rows: float, to: int) -> int | None:
        """The chord whose paths tokens had better meet: where both are far fewer than the rows of an extension, and these are many."""
        at, *chords = sorted(self.near[to] & set(bound), key=lambda x: (self.fan(x, to), x))
        wide, met = rows * self.fan(at, to), self.paths(at, to, chords)
        return met[1] if len(bound) > 2 and met and wide > MEET_FROM and wide > 2 * (rows + met[0]) else None

    def step(self, bound: tuple[int, ...], rows: float, to: int) -> tuple[float, float]:
        """Rows that the step to a role makes, and those that are left once folded."""
        at, *chords = sorted(self.near[to] & set(bound), key=lambda x: (self.fan(x, to), x))
        wide = rows * self.fan(at, to)
        left = wide
        if self.over(bound, rows, to) is not None:
            wide = rows + self.paths(at, to, chords)[0]
        for x in chords:
            left *= min(1.0, self.fan(x, to) / self.n[to])
        there = {*bound, to}
        live = [q for q in there if q in self.keep or self.near[q] - there or self.tested[q] - there]
        most = 1.0
        for q in live:
            most *= 2 if self.two and q not in self.keep and not self.near[q] - there else self.n[q]
        if len(live) == 2 and tuple(live) in self.many:
            most = min(most, self.many[tuple(live)])
        return wide + left, min(left, most)

    def best(self, start: int) -> tuple[float, tuple[int, ...]]:
        """The cheapest order of the roles from a start, with its cost."""
        found: list = [float("inf"), None]

        def go(bound, rows, cost):
            if found[1] is not None and cost >= found[0]:
                return
            if len(bound) == len(self.near):
                found[:] = cost, bound
                return
            reach = sorted(q for q in self.near if q not in bound and self.near[q] & set(bound))
            if not reach:
                raise ValueError("the edges of a rule hang together")
            steps = sorted((*self.step(bound, rows, q), q) for q in reach)
            for made, left, q in steps if len(self.near) <= ALL_ORDERS else steps[:1]:
                go((*bound, q), left, cost + made)

        go((start,), float(self.n[start]), 0.0)
        return found[0], found[1]


def known_pairs(t: Template, frequency: dict | None) -> bool:
    """Whether edges by their ends' labels are known besides the labels, so that walks can be weighed."""
    return bool(frequency) and all((t.labels[a], t.labels[b]) in frequency for a, b in t.edges)


def lone_pair(t: Template, edges) -> tuple[int, int] | None:
    """The two roles of one label that no edge of the walk joins, if there are just two: one of them is then carried only to differ from the other."""
    pairs = [p for p in combinations(sorted({x for e in edges for x in e}), 2) if t.labels[p[0]] == t.labels[p[1]] and p not in set(edges)]
    return pairs[0] if len(pairs) == 1 else None


def best_start(t: Template, edges, frequency: dict | None, order=(), differ: bool = True, two: bool = False) -> int:
    """The role from which a walk over the edges makes the fewest rows; without counts of edges, the one of the rarest label."""
    freq, roles = frequency or {}, {x for e in edges for x in e}
    rare = lambda q: (freq.get(t.labels[q], 0), q)
    if not known_pairs(t, freq):
        return min(roles, key=rare)
    costs = _Costs(t, edges, freq, order, (), differ, two)
    return min(roles, key=lambda q: (costs.best(q)[0], rare(q)))


def walk_cost(t: Template, frequency: dict, start: int, differ: bool = True) -> float:
    """Expected rows of the cheapest walk over a whole template from a start."""
    return _Costs(t, t.edges, frequency, (), (), differ).best(start)[0]


class WalkPlan:
    """Order of steps for a set of template edges, with the roles that each step must keep.

    Where ``frequency`` holds edges by their ends' labels, the order is that of the fewest expected rows, and a step extends from the end that has the
    fewest edges to it. Else bound roles are tested as soon as they can be: the next role is the one with most bound neighbours, then the
    rarest label. Or roles come in a given ``sequence``. A role is live until its last use: as a place to extend from, as an end of a chord, for a test against an equal label, or of order.
    ``differ``: roles of one label must be different vertices. ``two``: the walk keeps two vertices of a role that is read later only to differ (see ``lone_pair``).
    """

    def __init__(self, t: Template, edges, start: int, frequency: dict | None = None, order: list[tuple[int, int]] = (), keep: tuple[int, ...] = (), sequence: tuple[int, ...] | None = None, differ: bool = True, two: bool = False):
        freq = frequency or {}
        self.start, bound, left, moves = start, [start], set(edges), []
        costs = _Costs(t, edges, freq, order, keep, differ, two) if sequence is None and known_pairs(t, freq) else None
        place = {q: k for k, q in enumerate(sequence if costs is None else costs.best(start)[1])} if costs or sequence else {}
        while left:
            reach = {}
            for a, b in left:
                for x, y in ((a, b), (b, a)):
                    if x in bound and y not in bound:
                        reach.setdefault(y, []).append(x)
            if not reach:
                raise ValueError("the edges of a rule hang together")
            to = min(reach, key=lambda y: (place.get(y, 0), -len(reach[y]), freq.get(t.labels[y], 0), y))
            at, *chords = sorted(reach[to], key=lambda x: (costs.fan(x, to), x) if costs else (-place.get(x, 0), freq.get(t.labels[x], 0), x))
            same = tuple(x for x in bound if differ and t.labels[x] == t.labels[to])
            tests = tuple((i, j) for i, j in order if to in (i, j) and (i in bound or i == to) and (j in bound or j == to))
            moves.append((at, to, False, same, tests))
            moves += [(x, to, True, (), ()) for x in chords]
            bound.append(to)
            left -= {(min(x, to), max(x, to)) for x in reach[to]}
        over, rows = {}, float(costs.n[start]) if costs else 0.0
        for k, to in enumerate(bound[1:] if costs else (), 1):
            over[to] = costs.over(tuple(bound[:k]), rows, to)
            rows = costs.step(tuple(bound[:k]), rows, to)[1]
        steps, later = [], set(keep)
        for at, to, chord, same, tests in reversed(moves):
            steps.append(Step(at, to, chord, same, tests, tuple(sorted(later)), None if chord else over.get(to)))
            later = (later | {at} | ({to} if chord else set()) | set(same) | {x for p in tests for x in p}) - (set() if chord else {to})
        self.steps, self.roles = steps[::-1], bound
        self.first_live = tuple(sorted(later | {start}))
        #: (extension, its chords): what one join and the tests after it do
        self.hops: list[tuple[Step, tuple[Step, ...]]] = []
        for s in self.steps:
            if s.chord:
                first, chords = self.hops[-1]
                self.hops[-1] = (first, (*chords, s))
            else:
                self.hops.append((s, ()))
