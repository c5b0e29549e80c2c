"""Templates: small connected graphs whose roles carry labels."""

from __future__ import annotations

import json
import re
from dataclasses import dataclass, field
from functools import cached_property
from itertools import combinations, permutations

MAX_ROLES = 62


@dataclass(frozen=True)
class Template:
    """Roles 0..n-1 with labels, and edges between them. ``mandatory`` edges survive every relaxation.

    ``demands`` names what a data edge must be beyond its ends: entries (a, b, label or None, directed), of which a directed one wants the
    data edge to run from the vertex of a to that of b. Edges without an entry take any data edge.
    """

    labels: tuple[str, ...]
    edges: tuple[tuple[int, int], ...]
    mandatory: frozenset = field(default_factory=frozenset)
    demands: tuple[tuple[int, int, str | None, bool], ...] = ()

    def __post_init__(self):
        edges = tuple(sorted({(min(a, b), max(a, b)) for a, b in self.edges}))
        object.__setattr__(self, "edges", edges)
        object.__setattr__(self, "labels", tuple(self.labels))
        object.__setattr__(self, "mandatory", frozenset((min(a, b), max(a, b)) for a, b in self.mandatory))
        if not 1 <= self.n <= MAX_ROLES:
            raise ValueError(f"a template has 1 to {MAX_ROLES} roles")
        if any(a == b or not 0 <= a < b < self.n for a, b in edges):
            raise ValueError("an edge joins two different roles of the template")
        object.__setattr__(self, "demands", tuple(d for d in self.demands if (min(d[:2]), max(d[:2])) in set(edges) and (d[2] is not None or d[3])))
        if self.demands and len(edges) > 31:
            raise ValueError("a template with demands on edges has at most 31 edges")

    @classmethod
    def build(cls, labels, edges, mandatory=(), demands=()) -> Template:
        out = cls(tuple(labels), tuple(edges), frozenset(mandatory), tuple(demands))
        if not out.connected:
            raise ValueError("a template is connected; solve components one by one")
        return out

    @classmethod
    def parse(cls, text: str) -> Template:
        """``(a:LabelA)-(b:LabelB)-(c:LabelC), (a)-(c)``: chains of roles; a role's label stands where it is first named.

        ``(a)-[shipped]-(b)`` wants that label of the edge, ``(a)->(b)`` and ``(a)-[shipped]->(b)`` its direction.
        """
        names, labels, edges, demands = {}, [], [], []
        for chain in re.split(r"\s*,\s*(?=\()", text.strip()):
            before = None
            for wanted, arrow, name, label in re.findall(r"(?:-(?:\[([^\]]+)\]-)?(>?)\s*)?\(\s*(\w+)\s*(?::\s*([^)]+?)\s*)?\)", chain):
                if name not in names:
                    if not label:
                        raise ValueError(f"role {name} has no label")
                    names[name] = len(labels)
                    labels.append(label)
                if before is not None:
                    edges.append((before, names[name]))
                    demands.append((before, names[name], wanted or None, bool(arrow)))
                before = names[name]
        return cls.build(labels, edges, demands=demands)

    @classmethod
    def from_json(cls, text: str) -> Template:
        d = json.loads(text)
        demands = [(e["a"], e["b"], e.get("label"), bool(e.get("directed"))) for e in d["edges"]]
        return cls.build([r["label"] for r in sorted(d["roles"], key=lambda r: r["id"])], [(e["a"], e["b"]) for e in d["edges"]], demands=demands)

    def to_json(self) -> str:
        told = {(min(a, b), max(a, b)): {"a": a, "b": b, "label": x, "directed": way} for a, b, x, way in self.demands}
        return json.dumps({"roles": [{"id": k, "label": x} for k, x in enumerate(self.labels)], "edges": [told.get(e, {"a": e[0], "b": e[1]}) for e in self.edges]})

    @classmethod
    def unlabelled(cls, edges, label: str = "*") -> Template:
        return cls.build([label] * (1 + max(max(e) for e in edges)), edges)

    @property
    def n(self) -> int:
        return len(self.labels)

    @cached_property
    def adjacent(self) -> tuple[frozenset, ...]:
        return tuple(frozenset(b if a == q else a for a, b in self.edges if q in (a, b)) for q in range(self.n))

    @cached_property
    def adjmask(self) -> tuple[int, ...]:
        return tuple(sum(1 << x for x in s) for s in self.adjacent)

    @cached_property
    def arcs(self) -> dict[tuple[int, int], int]:
        """Numbers of the template's edges in either direction."""
        return {x: k for k, x in enumerate(x for a, b in self.edges for x in ((a, b), (b, a)))}

    @cached_property
    def by_label(self) -> dict[str, int]:
        out: dict[str, int] = {}
        for k, x in enumerate(self.labels):
            out[x] = out.get(x, 0) | 1 << k
        return out

    def component_of(self, start: int) -> set[int]:
        seen, todo = {start}, [start]
        while todo:
            for x in self.adjacent[todo.pop()] - seen:
                seen.add(x)
                todo.append(x)
        return seen

    def components(self) -> list[set[int]]:
        left, out = set(range(self.n)), []
        while left:
            out.append(self.component_of(min(left)))
            left -= out[-1]
        return out

    @property
    def connected(self) -> bool:
        return len(self.component_of(0)) == self.n

    def with_edge(self, a: int, b: int) -> Template:
        return Template.build(self.labels, [*self.edges, (a, b)], self.mandatory, self.demands)

    def without(self, *edges) -> Template:
        gone = {(min(e), max(e)) for e in edges}
        if gone & self.mandatory:
            raise ValueError("a mandatory edge stays")
        return Template.build(self.labels, [e for e in self.edges if e not in gone], self.mandatory, self.demands)

    def relaxations(self, k: int, up_to_isomorphism: bool = False) -> list[Template]:
        """All connected templates with k of the edges that are not mandatory taken away."""
        out, seen = [], set()
        for gone in combinations([e for e in self.edges if e not in self.mandatory], k):
            t = Template(self.labels, tuple(e for e in self.edges if e not in gone), self.mandatory, self.demands)
            if t.connected:
                key = t.canonical if up_to_isomorphism and not t.demands else t.edges
                if key not in seen:
                    seen.add(key)
                    out.append(t)
        return out

    def _label_permutations(self):
        groups: dict[str, list[int]] = {}
        for k, x in enumerate(self.labels):
            groups.setdefault(x, []).append(k)
        maps = [{}]
        for own in groups.values():
            maps = [m | dict(zip(own, p)) for m in maps for p in permutations(own)]
        return maps

    @cached_property
    def canonical(self):
        return min(tuple(sorted((min(m[a], m[b]), max(m[a], m[b])) for a, b in self.edges)) for m in self._label_permutations())

    @cached_property
    def one_label_clique(self) -> bool:
        """Whether all roles are alike and joined to each other: any order of a match's vertices is a match."""
        return self.n > 2 and not self.demands and len(set(self.labels)) == 1 and len(self.edges) == self.n * (self.n - 1) // 2

    @cached_property
    def automorphisms(self) -> list[dict[int, int]]:
        """Permutations of roles that keep labels and edges, found by extending partial ones."""
        edges, out = set(self.edges), []
        told = {(a, b): (x, way) for a, b, x, way in self.demands} | {(b, a): (x, -way) for a, b, x, way in self.demands}

        def extend(m):
            q = len(m)
            if q == self.n:
                out.append(dict(enumerate(m)))
                return
            for x in range(self.n):
                if x not in m and self.labels[x] == self.labels[q] and all(((min(m[p], x), max(m[p], x)) in edges) == ((p, q) in edges) and told.get((m[p], x)) == told.get((p, q)) for p in range(q)):
                    extend([*m, x])

        extend([])
        return out

    @cached_property
    def symmetry_order(self) -> list[tuple[int, int]]:
        """Pairs (i, j) such that of the embeddings of one subgraph exactly one has vertex i below vertex j for all of them."""
        group, out = self.automorphisms, []
        while len(group) > 1:
            orbits = {q: {m[q] for m in group} for q in range(self.n)}
            q = max(range(self.n), key=lambda q: (len(orbits[q]), -q))
            out += [(q, x) for x in sorted(orbits[q] - {q})]
            group = [m for m in group if m[q] == q]
        return out


class TemplateProfile:
    """What the rules need to know of a template."""

    def __init__(self, t: Template):
        self.template = t
        counts = {x: t.labels.count(x) for x in t.labels}
        self.unique = {q for q in range(t.n) if counts[t.labels[q]] == 1}
        self.repeated = set(range(t.n)) - self.unique
        core, alive = set(range(t.n)), True
        while alive:  # leaves of unique label settle locally, one after another
            leaves = {q for q in core if q in self.unique and len(t.adjacent[q] & core) == 1 and len(core) > 1}
            alive = bool(leaves)
            core -= set(list(leaves)[:1])
        self.core = core
        self.cycles = self._simple_cycles()
        self.cycle_degree = {e: sum(e in self.edges_of(c) for c in self.cycles) for e in t.edges}

    @classmethod
    def of(cls, t: Template) -> TemplateProfile:
        return cls(t)

    @staticmethod
    def edges_of(cycle) -> frozenset:
        return frozenset((min(a, b), max(a, b)) for a, b in zip(cycle, (*cycle[1:], cycle[0])))

    def _simple_cycles(self) -> list[tuple[int, ...]]:
        """Every simple cycle of the core once: from its smallest role, towards the smaller neighbour."""
        t, out = self.template, []

        def go(path):
            for x in sorted(t.adjacent[path[-1]] & self.core):
                if x == path[0] and len(path) > 2 and path[1] < path[-1]:
                    out.append(tuple(path))
                elif x > path[0] and x not in path:
                    go([*path, x])

        for q in sorted(self.core):
            go([q])
        return sorted(out, key=lambda c: (len(c), c))

    @property
    def edge_monocyclic(self) -> bool:
        return max(self.cycle_degree.values(), default=0) <= 1

    @property
    def is_tree(self) -> bool:
        return len(self.template.edges) == self.template.n - 1

    @property
    def local_is_exact(self) -> bool:
        """Neighbourhood checks alone are exact for trees of unique labels."""
        return self.is_tree and not self.repeated

    def distances(self, q: int) -> dict[int, int]:
        seen, frontier = {q: 0}, [q]
        while frontier:
            frontier = [x for f in frontier for x in self.template.adjacent[f] if x not in seen and seen.setdefault(x, seen[f] + 1)]
        return seen

    @property
    def diameter(self) -> int:
        return max(max(self.distances(q).values()) for q in range(self.template.n))
