"""The running example as literal rows, and a brute-force matcher for tests."""

from itertools import product

from flowmatch.plans.pattern import Pattern, QueryEdge

TYPES = {0: "A", 1: "A", 8: "A", 2: "B", 3: "B", 4: "C", 6: "D", 7: "E", 5: "F", 9: "F"}
G = [(0, 4, 0), (1, 1, 3), (2, 4, 1), (3, 1, 5), (4, 2, 7), (5, 3, 6), (6, 3, 7), (7, 4, 8), (9, 4, 5)]
T1 = [(10, 2, 6), (11, 0, 2), (12, 0, 5)]
T2_IN, T2_OUT = [(13, 1, 2)], [(6, 3, 7), (3, 1, 5)]
EDGE_SCHEMA = "edge_id long, src long, dst long, src_type string, dst_type string, label string, ts long, weight double"


def rows(triples, types=TYPES, labels=None, ts=None):
    return [(i, s, d, types[s], types[d], (labels or {}).get(i, ""), (ts or {}).get(i, i), 1.0) for i, s, d in triples]


def pattern() -> Pattern:
    pairs = [(0, 1), (2, 0), (0, 5), (1, 3), (1, 4), (2, 6), (2, 5)]
    edges = [QueryEdge(f"q{i}", f"u{a}", f"u{b}") for i, (a, b) in enumerate(pairs)]
    return Pattern.of(*edges, labels={"u0": "A", "u6": "A", "u1": "B", "u2": "C", "u3": "D", "u4": "E", "u5": "F"}, name="running")


def brute(edge_rows, pattern: Pattern, injective=True, pairs=(), within=None):
    """All embeddings as tuples of edge ids in pattern order."""
    found, vertex = [], {v.name: v.label for v in pattern.vertices}
    fits = lambda r, e: (not e.labels or r[5] in e.labels) and (vertex[e.src] in (None, r[3])) and (vertex[e.dst] in (None, r[4]))

    def go(k, bound, used):
        if k == len(pattern.edges):
            ts = {e.name: r[6] for e, r in zip(pattern.edges, used)}
            if all(ts[a] < ts[b] for a, b in pairs) and (within is None or max(ts.values()) - min(ts.values()) <= within):
                found.append(tuple(r[0] for r in used))
            return
        e = pattern.edges[k]
        for r in edge_rows:
            if not fits(r, e):
                continue
            new = dict(bound)
            if any(new.setdefault(n, v) != v for n, v in ((e.src, r[1]), (e.dst, r[2]))):
                continue
            if injective and (len(set(new.values())) < len(new) or any(r[0] == x[0] for x in used)):
                continue
            go(k + 1, new, [*used, r])

    go(0, {}, [])
    return sorted(found)


def simulate(edge_rows, pattern: Pattern):
    """Greatest dual simulation as a set of (query vertex, vid)."""
    vertex = {v.name: v.label for v in pattern.vertices}
    types = {v: t for r in edge_rows for v, t in ((r[1], r[3]), (r[2], r[4]))}
    rel = {(u, v) for u, v in product(vertex, types) if vertex[u] in (None, types[v])}
    while True:
        bad = {
            (u, v) for u, v in rel for e in pattern.edges
            if (e.src == u and not any(r[1] == v and (not e.labels or r[5] in e.labels) and (e.dst, r[2]) in rel for r in edge_rows))
            or (e.dst == u and not any(r[2] == v and (not e.labels or r[5] in e.labels) and (e.src, r[1]) in rel for r in edge_rows))
        }
        if not bad:
            return rel if {u for u, _ in rel} == set(vertex) else set()
        rel -= bad
