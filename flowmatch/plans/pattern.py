"""Patterns: small directed query graphs with labels, predicates, times and optional edges."""

from __future__ import annotations

import re
from collections import deque
from dataclasses import dataclass, field, replace
from itertools import permutations


@dataclass(frozen=True)
class QueryVertex:
    name: str
    label: str | None = None  # None: any vertex type


@dataclass(frozen=True)
class QueryEdge:
    """A query edge.  ``labels``: the labels it takes (a trailing '*' makes a prefix), none for any.  ``where``: a SQL predicate on edge columns."""

    name: str
    src: str
    dst: str
    labels: tuple[str, ...] = ()
    where: str | None = None
    time: int | None = None
    directed: bool = True
    optional: bool = False

    def ends(self) -> frozenset[str]:
        return frozenset((self.src, self.dst))


@dataclass(frozen=True)
class Pattern:
    vertices: tuple[QueryVertex, ...]
    edges: tuple[QueryEdge, ...]
    name: str = "pattern"
    _at: dict = field(default_factory=dict, compare=False, repr=False)

    def __post_init__(self):
        names = [v.name for v in self.vertices]
        if len(set(names)) != len(names) or len({e.name for e in self.edges}) != len(self.edges):
            raise ValueError("names of vertices and of edges must be unique")
        if not self.edges or len(self.edges) > 62:
            raise ValueError("a pattern has 1 to 62 edges")
        known = set(names)
        if any(not e.ends() <= known for e in self.edges):
            raise ValueError("an edge names a vertex that the pattern lacks")
        reached, todo = {self.edges[0].src}, [self.edges[0].src]
        while todo:
            v = todo.pop()
            for e in self.edges:
                for w in e.ends() if v in e.ends() else ():
                    if w not in reached:
                        reached.add(w)
                        todo.append(w)
        if reached != known:
            raise ValueError("the pattern must be connected")

    @classmethod
    def of(cls, *edges: QueryEdge, labels: dict[str, str] | None = None, name: str = "pattern") -> Pattern:
        names = list(dict.fromkeys(v for e in edges for v in (e.src, e.dst)))
        return cls(tuple(QueryVertex(n, (labels or {}).get(n)) for n in names), edges, name)

    def vertex(self, name: str) -> QueryVertex:
        return next(v for v in self.vertices if v.name == name)

    def edge(self, name: str) -> QueryEdge:
        return next(e for e in self.edges if e.name == name)

    def bit(self, name: str) -> int:
        """Bit of a query vertex in vertex masks."""
        return next(i for i, v in enumerate(self.vertices) if v.name == name)

    def incident(self, vertex: str) -> list[QueryEdge]:
        return [e for e in self.edges if vertex in e.ends()]

    def timed(self, *times: int) -> Pattern:
        return replace(self, edges=tuple(replace(e, time=t) for e, t in zip(self.edges, times, strict=True)))

    def mandatory(self) -> Pattern:
        kept = [e for e in self.edges if not e.optional]
        names = {n for e in kept for n in e.ends()}
        return Pattern(tuple(v for v in self.vertices if v.name in names), tuple(kept), self.name)


_VERTEX = re.compile(r"\(\s*(\w+)\s*(?::\s*(\w+))?\s*\)")
_EDGE = re.compile(r"(<)?-\[\s*(\w+)?\s*(?::\s*([^\]]+?))?\s*\]-(>)?")


def parse_pattern(text: str, name: str = "pattern") -> Pattern:
    """Chains such as ``(a:User)-[x:click]->(b)<-[y:view|buy]-(c), (a)-[z]-(c)``; without an arrow an edge has no direction."""
    labels: dict[str, str | None] = {}
    edges: list[QueryEdge] = []
    for chain in filter(None, (c.strip() for c in re.split(r",(?![^\[]*\])", text))):
        m = _VERTEX.match(chain)
        if not m:
            raise ValueError(f"no vertex at: {chain!r}")
        at = m.end()
        left = m[1]
        labels[left] = m[2] or labels.get(left)
        while at < len(chain):
            e = _EDGE.match(chain, at)
            v = e and _VERTEX.match(chain, e.end())
            if not v:
                raise ValueError(f"no edge and vertex at: {chain[at:]!r}")
            right = v[1]
            labels[right] = v[2] or labels.get(right)
            a, b = (right, left) if e[1] else (left, right)
            edges.append(QueryEdge(e[2] or f"e{len(edges)}", a, b, tuple(x.strip() for x in (e[3] or "").split("|") if x.strip()), directed=bool(e[1] or e[4])))
            left, at = right, v.end()
    return Pattern(tuple(QueryVertex(n, x) for n, x in labels.items()), tuple(edges), name)


def distances(pattern: Pattern, start: str) -> dict[str, int]:
    far, todo = {start: 0}, deque([start])
    while todo:
        v = todo.popleft()
        for e in pattern.incident(v):
            for w in e.ends():
                if w not in far:
                    far[w] = far[v] + 1
                    todo.append(w)
    return far


def diameter(pattern: Pattern) -> int:
    return max(max(distances(pattern, v.name).values()) for v in pattern.vertices)


def automorphisms(pattern: Pattern) -> list[dict[str, str]]:
    """Maps of the vertices onto themselves that keep labels and edges with their labels and predicates."""
    if len(pattern.vertices) > 9:
        raise ValueError("automorphisms are searched for up to 9 vertices")
    names = [v.name for v in pattern.vertices]
    sign = lambda e, f: (f[e.src], f[e.dst], e.labels, e.where, e.time) if e.directed else (*sorted((f[e.src], f[e.dst])), e.labels, e.where, e.time)
    own = sorted(map(str, (sign(e, {n: n for n in names}) for e in pattern.edges)))
    found = []
    for image in permutations(names):
        f = dict(zip(names, image))
        if all(pattern.vertex(a).label == pattern.vertex(b).label for a, b in f.items()) and sorted(map(str, (sign(e, f) for e in pattern.edges))) == own:
            found.append(f)
    return found


def symmetry_breaking(pattern: Pattern) -> list[tuple[str, str]]:
    """Pairs (a, b): requiring vertex of a < vertex of b leaves one embedding of each orbit."""
    group, pairs = automorphisms(pattern), []
    while len(group) > 1:
        moved = next(v.name for v in pattern.vertices if any(f[v.name] != v.name for f in group))
        pairs += [(moved, other) for other in sorted({f[moved] for f in group} - {moved})]
        group = [f for f in group if f[moved] == moved]
    return pairs
