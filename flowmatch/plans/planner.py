"""From a pattern to a plan: root, query tree, orders, masks, requirements.  All of it on the driver, on small objects."""

from __future__ import annotations

from collections import Counter, deque
from dataclasses import dataclass, field

from flowmatch.plans.pattern import Pattern, QueryEdge


@dataclass(frozen=True)
class Statistics:
    """Row counts that selectivity needs: edges by label, vertices by type."""

    by_label: dict
    by_type: dict
    ends: dict = field(default_factory=dict)  # label: about how many sources and targets; only where "fanout" orders are asked for

    def _of(self, edge: QueryEdge) -> list:
        return [x for x in self.by_label if not edge.labels or any(x == y or y.endswith("*") and str(x).startswith(y[:-1]) for y in edge.labels)]

    def edges(self, edge: QueryEdge) -> int:
        return sum(self.by_label[x] for x in self._of(edge))

    def distinct(self, edge: QueryEdge) -> tuple[int, int]:
        """About how many sources and targets the edges have, at most: vertices may have several labels' edges."""
        own = [self.ends[x] for x in self._of(edge)]
        return max(1, sum(a for a, _ in own)), max(1, sum(b for _, b in own))


def statistics(edges) -> Statistics:
    """One aggregation; the result has a row per label and pair of vertex types."""
    rows = edges.groupBy("label", "src_type", "dst_type").count().collect()
    labels, types = Counter(), Counter()
    for r in rows:
        labels[r.label] += r["count"]
        types[r.src_type] += r["count"]
        types[r.dst_type] += r["count"]
    return Statistics(dict(labels), dict(types))


def fan_statistics(edges) -> Statistics:
    """One aggregation; a row per label, with estimates of its distinct sources and targets."""
    from pyspark.sql import functions as F

    rows = edges.groupBy("label").agg(F.count("*").alias("n"), F.approx_count_distinct("src").alias("a"), F.approx_count_distinct("dst").alias("b")).collect()
    return Statistics({r.label: r.n for r in rows}, {}, {r.label: (r.a, r.b) for r in rows})


@dataclass(frozen=True)
class TreeEdge:
    edge: QueryEdge
    parent: str
    child: str
    level: int

    @property
    def forward(self) -> bool:
        """Whether the parent is the edge's source."""
        return self.edge.src == self.parent


@dataclass(frozen=True)
class QueryTree:
    pattern: Pattern
    root: str
    edges: tuple[TreeEdge, ...]  # in BFS order
    rest: tuple[QueryEdge, ...]  # the others

    @property
    def depth(self) -> int:
        return max((t.level for t in self.edges), default=0)

    def level(self, k: int) -> list[TreeEdge]:
        return [t for t in self.edges if t.level == k]

    def kids(self, vertex: str) -> list[TreeEdge]:
        return [t for t in self.edges if t.parent == vertex]

    def into(self, vertex: str) -> TreeEdge | None:
        return next((t for t in self.edges if t.child == vertex), None)

    def bit(self, t: TreeEdge) -> int:
        """Bit of a tree edge in edge masks: that of its edge among the pattern's."""
        return self.pattern.edges.index(t.edge)


def choose_root(pattern: Pattern, stats: Statistics | None = None, override: str | None = None) -> str:
    """The most selective vertex: the one whose rarest edge is rarest; then the highest degree, then the name."""
    if override:
        return pattern.vertex(override).name
    rank = lambda v: (min(stats.edges(e) for e in pattern.incident(v.name)) if stats else 0, -len(pattern.incident(v.name)), v.name)
    return min(pattern.vertices, key=rank).name


def build_tree(pattern: Pattern, root: str) -> QueryTree:
    """Breadth first, whatever the edges' direction; a self-loop or an edge between seen vertices is no tree edge."""
    seen, todo, found = {root: 0}, deque([root]), []
    while todo:
        v = todo.popleft()
        for e in pattern.incident(v):
            other = e.dst if e.src == v else e.src
            if other not in seen and e.src != e.dst:
                seen[other] = seen[v] + 1
                found.append(TreeEdge(e, v, other, seen[other]))
                todo.append(other)
    used = {t.edge.name for t in found}
    return QueryTree(pattern, root, tuple(found), tuple(e for e in pattern.edges if e.name not in used))


def match_order(tree: QueryTree, strategy: str | list[str] = "bfs", stats: Statistics | None = None) -> list[str]:
    """Names of all edges: "bfs", "selectivity" (the rarest edge that touches what is bound comes next), "fanout" (see there), or a list of one's own."""
    pattern = tree.pattern
    if isinstance(strategy, list):
        if sorted(strategy) != sorted(e.name for e in pattern.edges):
            raise ValueError("an order names every edge once")
        return strategy
    if strategy == "bfs":
        return closed([t.edge.name for t in tree.edges], tree)
    if strategy == "fanout" and stats is not None and stats.ends:
        return fanout_order(pattern, stats)
    if strategy != "selectivity" or stats is None:
        raise ValueError("strategies are 'bfs', and with statistics 'selectivity' and 'fanout'")
    left = list(pattern.edges)
    first = min(left, key=lambda e: (stats.edges(e), e.name))
    order, bound = [], set()
    nxt = first
    while nxt:
        left.remove(nxt)
        order.append(nxt.name)
        bound |= nxt.ends()
        near = [e for e in left if e.ends() & bound]
        nxt = min(near, key=lambda e: (not e.ends() <= bound, stats.edges(e), e.name), default=None)
    return order


def fanout_order(pattern: Pattern, stats: Statistics) -> list[str]:
    """From each first edge on, the edge that leaves the fewest rows comes next; of these orders the one with the fewest rows in all.

    Rare edges alone mislead: two of them that meet at a hub multiply.  A join on a vertex divides by the larger number of
    distinct values on either side.
    """

    def grown(rows: float, domain: dict[str, float], e: QueryEdge) -> tuple[float, dict[str, float]]:
        rows, domain = rows * stats.edges(e), dict(domain)
        for v, n in dict(zip((e.src, e.dst), stats.distinct(e))).items():
            rows /= max(domain[v], n) if v in domain else 1
            domain[v] = min(domain.get(v, n), n)
        return rows, domain

    best = None
    for first in pattern.edges:
        rows, domain = grown(1.0, {}, first)
        order, left, cost = [first.name], [e for e in pattern.edges if e is not first], rows
        while left:
            nxt = min((e for e in left if e.ends() & set(domain)), key=lambda e: (grown(rows, domain, e)[0], e.name))  # noqa: B023
            rows, domain = grown(rows, domain, nxt)
            left.remove(nxt)
            order.append(nxt.name)
            cost += rows
        if best is None or (cost, order) < best:
            best = (cost, order)
    return best[1]


def closed(tree_order: list[str], tree: QueryTree) -> list[str]:
    """The order with every non-tree edge set right after the edge that binds its second end."""
    order, bound, rest = [], set(), list(tree.rest)
    for name in tree_order:
        order.append(name)
        bound |= tree.pattern.edge(name).ends()
        ready = [e for e in rest if e.ends() <= bound]
        order += [e.name for e in ready]
        rest = [e for e in rest if e not in ready]
    return order


def order_from(tree: QueryTree, start: str) -> list[str]:
    """Tree edges in the order of a search that starts at ``start``.

    A tree edge comes first itself, then the path from it up to the root; a non-tree edge's two ends come first, by the
    tree edges into its target and its source, then the path up.  The others follow breadth first.
    """
    edge = tree.pattern.edge(start)
    own = next((t for t in tree.edges if t.edge.name == start), None)
    if own:
        head, at = [own], own.parent
    else:
        head, at = [t for t in (tree.into(edge.dst), tree.into(edge.src)) if t], edge.src
    while t := tree.into(at):
        head.append(t)
        at = t.parent
    return list(dict.fromkeys([*(t.edge.name for t in head), *(t.edge.name for t in tree.edges)]))


def batch_masks(order: list[str], orientation: str = "earlier_old") -> dict[str, set[str]]:
    """For each start, the query edges that may not use an edge of the batch; either way each embedding has one start."""
    if orientation not in ("earlier_old", "later_old"):
        raise ValueError("orientations are 'earlier_old' and 'later_old'")
    return {q: set(order[:i] if orientation == "earlier_old" else order[i + 1 :]) for i, q in enumerate(order)}


@dataclass(frozen=True)
class Requirement:
    """At least ``edges`` edges and ``neighbours`` other ends, out of or into a vertex, that match one of ``of`` (edge names; all: any label)."""

    vertex: str
    out: bool
    of: tuple[str, ...]
    edges: int
    neighbours: int
    total: bool = False


def degree_requirements(pattern: Pattern, profile: str = "injective") -> list[Requirement]:
    """Needs of each query vertex, by direction and rule (edges with the same labels, predicate and far type), and in total.

    They count rule matches, not labels, so any edge rule keeps them sound.  "existence": one is enough, as homomorphism
    may use an edge twice.  "none": no needs.
    """
    if profile == "none":
        return []
    if profile not in ("injective", "existence"):
        raise ValueError("profiles are 'injective', 'existence' and 'none'")
    found = []
    for v in pattern.vertices:
        for out in (True, False):
            own = [e for e in pattern.mandatory().edges if e.directed and (e.src if out else e.dst) == v.name]
            groups: dict[tuple, list[QueryEdge]] = {}
            for e in own:
                groups.setdefault((e.labels, e.where, pattern.vertex(e.dst if out else e.src).label), []).append(e)
            sets = [(tuple(e.name for e in g), False) for g in groups.values()]
            if len(groups) > 1:
                sets.append((tuple(e.name for e in own), True))
            for names, total in sets:
                far = {pattern.edge(n).dst if out else pattern.edge(n).src for n in names}
                n, k = (len(names), len(far)) if profile == "injective" else (1, 1)
                if profile == "injective" or not total:
                    found.append(Requirement(v.name, out, names, n, k, total))
    return found


def temporal_pairs(pattern: Pattern, mode: str = "total") -> list[tuple[str, str]]:
    """Pairs of edges of which the first is earlier: neighbours in time only.  "total": edges of equal time are not compared."""
    timed = sorted((e for e in pattern.edges if e.time is not None), key=lambda e: e.time)
    pairs = {(a.name, b.name) for a in timed for b in timed if a.time < b.time}
    if mode not in ("total", "partial"):
        raise ValueError("modes are 'total' and 'partial'")
    if mode == "partial":  # only edges that share a vertex are ordered
        pairs = {(a, b) for a, b in pairs if pattern.edge(a).ends() & pattern.edge(b).ends()}
    return sorted((a, b) for a, b in pairs if not any((a, c) in pairs and (c, b) in pairs for c in (e.name for e in timed)))


@dataclass(frozen=True)
class Plan:
    pattern: Pattern
    tree: QueryTree
    order: tuple[str, ...]
    profile: str

    def starts(self) -> list[str]:
        """All edges, tree edges first: the total order of the masks."""
        return [*(t.edge.name for t in self.tree.edges), *(e.name for e in self.tree.rest)]


def compile_plan(pattern: Pattern, stats: Statistics | None = None, root: str | None = None, order: str | list[str] = "bfs", profile: str = "injective") -> Plan:
    core = pattern.mandatory()
    tree = build_tree(core, choose_root(core, stats, root))
    return Plan(core, tree, tuple(match_order(tree, order, stats)), profile)


def explain_pattern(plan: Plan) -> list[tuple[str, str, str]]:
    """Rows (what, of, text) of the plan, for people."""
    t = plan.tree
    rows = [("root", t.root, ""), *(("tree", x.edge.name, f"level {x.level}: {x.parent} -> {x.child}" + ("" if x.forward else " (against the edge)")) for x in t.edges)]
    rows += [("other", e.name, f"{e.src} -> {e.dst}") for e in t.rest]
    rows.append(("order", "", ", ".join(plan.order)))
    rows += [("start", s, ", ".join(order_from(t, s))) for s in plan.starts()]
    rows += [("mask", s, ", ".join(sorted(m))) for s, m in batch_masks(plan.starts()).items()]
    rows += [("need", r.vertex, f"{'out' if r.out else 'in'} {r.edges} edges, {r.neighbours} neighbours of {', '.join(r.of)}") for r in degree_requirements(plan.pattern, plan.profile)]
    return rows
