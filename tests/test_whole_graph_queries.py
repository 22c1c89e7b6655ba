"""Registered queries that have no SQL, on small fixtures against brute force."""

from itertools import product

from flowmatch import queries as Q
from flowmatch.plans.pattern import diameter
from flowmatch.sources import views as V
from flowmatch.sources.snapshots import DAY, MINUTE
from flowmatch.workloads import PATTERNS
from tests.running import EDGE_SCHEMA


def strong(rows, pattern):
    """(center, qvertex, vid), from the definition."""
    fits = lambda r, e: r[5] in e.labels
    types = {v: t for r in rows for v, t in ((r[1], r[3]), (r[2], r[4]))}
    out = set()
    for center in types:
        ball = {center}
        for _ in range(diameter(pattern)):
            ball |= {b for r in rows for a, b in ((r[1], r[2]), (r[2], r[1])) if a in ball}
        inner = [r for r in rows if r[1] in ball and r[2] in ball]
        rel = {(q.name, v) for q in pattern.vertices for v in ball if types[v] == q.label}
        while True:
            ok = lambda e, r: fits(r, e) and (e.src, r[1]) in rel and (e.dst, r[2]) in rel  # noqa: E731, B023
            new = {(q, v) for q, v in rel if all(any(ok(e, r) and (r[1] if e.src == q else r[2]) == v for r in inner) for e in pattern.edges if q in (e.src, e.dst))}
            if new == rel:
                break
            rel = new
        part = {center} if any(v == center for _, v in rel) and {q for q, _ in rel} == {q.name for q in pattern.vertices} else set()
        used = [r for r in inner if any(ok(e, r) for e in pattern.edges)]
        while part and (more := {b for r in used for a, b in ((r[1], r[2]), (r[2], r[1])) if a in part} - part):
            part |= more
        out |= {(center, q, v) for q, v in rel if v in part}
    return out


def test_strong_simulation_measures_distance_in_the_whole_graph(spark, monkeypatch):
    kind = {1: "customer", 10: "order", 11: "order", 20: "part", 21: "part", 30: "supplier", 31: "supplier"}
    edges = [(1, 10, "PLACED_1-URGENT_F"), (1, 11, "PLACED_1-URGENT_F"), (10, 20, "HAS_RF"), (11, 21, "HAS_RF"), (10, 30, "FROM_AF"), (11, 31, "FROM_AF"), (11, 20, "HAS_AF")]
    rows = [(i, a, b, kind[a], kind[b], x, i, 1.0) for i, (a, b, x) in enumerate(edges)]
    monkeypatch.setattr(V, "commerce", lambda spark, d: spark.createDataFrame(rows, EDGE_SCHEMA))
    got = [(r.center, r.qvertex, r.vid) for r in Q.queries()["strong_sim_v3"](spark, "").collect()]
    assert len(got) == len(set(got)) and set(got) == strong(rows, PATTERNS["trade2"]) and (20, "o", 11) in got


def test_five_clique_keeps_its_wildcards(spark, monkeypatch):
    labels = ["purchase", "click", "view", "error", "signup"]
    kinds = {(0, 1): "purchase", (1, 2): "click", (0, 2): "view", (2, 3): "error", (0, 3): "signup", (1, 3): "view"}
    ends = [(*k, x) for k, x in kinds.items()] + [(a, e, labels[(a + e) % 5]) for a in range(4) for e in (4, 5)] + [(0, 4, "error"), (3, 5, "click")]
    rows = [(i, a, b, "user", "user", x, i, 1.0) for i, (a, b, x) in enumerate(ends)]
    monkeypatch.setitem(V.VIEWS, "v1", lambda spark, d: spark.createDataFrame(rows, EDGE_SCHEMA))
    pattern = PATTERNS["clique5"]
    want = 0
    for chosen in product(range(6), repeat=5):
        at, n = dict(zip("abcde", chosen)), 1
        for e in pattern.edges:
            n *= sum((r[1], r[2]) == (at[e.src], at[e.dst]) and (not e.labels or r[5] in e.labels) for r in rows)
            if not n:
                break
        want += n
    found = Q.queries()
    assert sum(not e.labels for e in pattern.edges) == 5 and found["homo_clique5_count_v1"](spark, "").first().n == want > 0
    assert found["homo_clique5_labelled_count_v1"](spark, "").first().n < want


def test_placeholders_cover_the_whole_table(spark, monkeypatch):
    at = [(1, 0), (1, 5), (2, 70), (1, 200), (1, 900), (1, 901), (1, 902), (2, 1100), (2, 1100)]  # (src, snapshot)
    rows = [(i, s, 9, "user", "resource", "click", k * 10 * MINUTE, 1.0) for i, (s, k) in enumerate(at)]
    monkeypatch.setattr(V, "access", lambda spark, d: spark.createDataFrame(rows, EDGE_SCHEMA))
    life = DAY // (10 * MINUTE)
    for name, reclaim in (("placeholders_reclaim_v2", True), ("placeholders_plain_v2", False)):
        want = {}
        for k in sorted({x for _, b in at for x in (b, b + life)}):
            # What is alive before a snapshot holds its slot through it.
            need = lambda s, j: sum(x == s and b <= j and (not reclaim or b + life >= j and (b == j or b + life > j - 1)) for x, b in at)
            want[k] = sum(max(need(s, j) for j in {b for x, b in at if x == s and b <= k} or {-1}) for s in (1, 2))
        assert {r.snapshot_id: r.slots for r in Q.queries()[name](spark, "").collect()} == want
