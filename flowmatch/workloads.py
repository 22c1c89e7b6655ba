"""Patterns of the experiments on the views, and growth of random patterns from data."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from flowmatch.plans.pattern import Pattern, QueryEdge, parse_pattern

PATTERNS: dict[str, Pattern] = {
    name: parse_pattern(text, name)
    for name, text in {
        "t3_path": "(a)-[x:purchase]->(b)-[y:click]->(c)-[z:view]->(d)",
        "t3_star": "(a)-[x:purchase]->(b),(a)-[y:signup]->(c),(a)-[z:error]->(d)",
        "star2": "(a)-[x:purchase]->(b),(a)-[y:click]->(c)",
        "t2_wild": "(a)-[x:purchase]->(b)-[y]->(c)",
        "t2_undirected": "(a)-[x:purchase]-(b)-[y:signup]->(c)",
        "triangle": "(a)-[x:purchase]->(b)-[y:click]->(c)-[z:view]->(a)",
        "triangle_any": "(a)-[x]->(b)-[y]->(c)-[z]->(a)",
        "triangle_same": "(a)-[x:click]->(b)-[y:click]->(c)-[z:click]->(a)",
        "rectangle": "(a)-[x:purchase]->(b)-[y:click]->(c)-[z:view]->(d)-[w:error]->(a)",
        "dual_triangle": "(a)-[x:purchase]->(b)-[y:click]->(c)-[z:view]->(a),(b)-[p:error]->(d)-[q:signup]->(a)",
        "clique4": "(a)-[x:purchase]->(b)-[y:click]->(c),(a)-[z:view]->(c)-[p:error]->(d),(a)-[q:signup]->(d),(b)-[r]->(d)",
        "clique5": "(a)-[x:purchase]->(b)-[y:click]->(c),(a)-[z:view]->(c)-[p:error]->(d),(a)-[q:signup]->(d),(b)-[r]->(d),(a)-[s]->(e),(b)-[t]->(e),(c)-[u]->(e),(d)-[w]->(e)",
        "clique5_labelled": "(a)-[x:purchase]->(b)-[y:click]->(c),(a)-[z:view]->(c)-[p:error]->(d),(a)-[q:signup]->(d),(b)-[r]->(d),(a)-[s:purchase]->(e),(b)-[t:click]->(e),(c)-[u:view]->(e),(d)-[w:error]->(e)",
        "shared_resource": "(x:user)-[e:error]->(r:resource)<-[p:purchase]-(y:user)-[c:click]->(q:resource)",
        "two_users": "(x)-[a:purchase]->(r)<-[b:purchase]-(y)-[c:error]->(q)<-[d:error]-(x)",
        "t6_trade": "(c:customer)-[p:PLACED_1-URGENT_F]->(o:order)-[h:HAS_RF]->(a:part),(o)-[f:FROM_AF]->(s:supplier)-[b:BASED]->(n:nation)-[r:IN_REGION]->(g:region),(c)-[l:LIVES_BUILDING]->(m:nation)",
        "t6_prefix": "(c:customer)-[p:PLACED_1-URGENT*]->(o:order)-[h:HAS_R*]->(a:part),(o)-[f:FROM_A*]->(s:supplier)-[b:BASED]->(n:nation)-[r:IN_REGION]->(g:region),(c)-[l:LIVES_BUILDING]->(m:nation)",
        "g4_nation": "(c:customer)-[p:PLACED_1-URGENT_F]->(o:order)-[f:FROM_R*]->(s:supplier)-[b:BASED]->(n:nation)<-[l:LIVES_BUILDING]-(c)",
        "trade2": "(c:customer)-[p:PLACED_1-URGENT_F]->(o:order)-[h:HAS_RF]->(a:part),(o)-[f:FROM_AF]->(s:supplier)",
        "triangle_nn": "(a)-[x]->(b)-[y]->(c)-[z]->(a)",
        "rising_path": "(a)-[x:purchase]->(b)-[y:click]->(c)",
        "reply_path": "(a)-[x:user>assistant]->(b)-[y:assistant>user]->(c)-[z:user>assistant]->(d)",
    }.items()
}
# The classes of the experiments on the commerce view: trees of 3, 6, 9 and 12 edges, graphs with cycles of 6, 9 and 12.
_T9 = "(c)-[p:PLACED_1-URGENT_F]->(o)-[h:HAS_RF]->(a),(o)-[f:FROM_AF]->(s)-[b:BASED]->(n)-[r:IN_REGION]->(g),(c)-[l:LIVES_BUILDING]->(m),(o)-[h2:HAS_AF]->(a2),(c)-[p2:PLACED_2-HIGH_F]->(o2)-[h3:HAS_RF]->(a3)"
_G6 = "(c)-[p:PLACED_1-URGENT*]->(o)-[f:FROM_R*]->(s)-[b:BASED]->(n)-[r:IN_REGION]->(g),(c)-[l:LIVES_BUILDING]->(n),(o)-[h:HAS_A*]->(a)"
_G9 = f"{_G6},(c)-[p2:PLACED_2-HIGH*]->(o2)-[f2:FROM_R*]->(s2)-[b2:BASED]->(n2)"
for _name, _text in (
    ("T_3_trade", "(c)-[p:PLACED_1-URGENT_F]->(o)-[h:HAS_RF]->(a),(o)-[f:FROM_AF]->(s)"),
    ("T_6_trade", _T9.split(",(o)-[h2")[0]),
    ("T_9_trade", _T9),
    ("T_12_trade", f"{_T9},(o2)-[f2:FROM_AF]->(s2)-[b2:BASED]->(n2)-[r2:IN_REGION]->(g2)"),
    ("G_6_nation", _G6),
    ("G_9_nation", _G9),
    ("G_12_nation", f"{_G9},(o2)-[h2:HAS_R*]->(a2),(o)-[h3:HAS_R*]->(a3),(n2)-[r2:IN_REGION]->(g)"),
):
    PATTERNS[_name] = parse_pattern(_text, _name)
CLASSES = [n for n in PATTERNS if n[:2] in ("T_", "G_")]

_heavy = [QueryEdge(n, s, d, (x,), "weight > 40") for n, s, d, x in (("a", "c1", "s1", "RF"), ("b", "c1", "s2", "RO"), ("c", "c2", "s1", "AF"), ("d", "c2", "s2", "AO"))]
PATTERNS["rect_flow"] = Pattern.of(*_heavy, name="rect_flow")
PATTERNS["rect_missing"] = Pattern.of(
    QueryEdge("x", "a", "b", ("purchase",)), QueryEdge("y", "b", "c", ("click",)), QueryEdge("z", "c", "a", ("view",), optional=True), QueryEdge("w", "a", "c", ("error",), optional=True), name="rect_missing"
)


def generate(edges: DataFrame, kind: str, size: int, n: int = 3, seed: int = 1, times: bool = False) -> list[Pattern]:
    """Patterns of ``size`` query edges, grown from the data, so that each has an embedding: kind "tree" or "graph".

    Growth starts at the edges that hash lowest; every step attaches the incident edge that hashes lowest and adds one
    vertex, for graphs at every third step one that closes a cycle where there is one.  Each step is one filtered scan.
    """
    if kind not in ("tree", "graph"):
        raise ValueError("kinds are 'tree' and 'graph'")
    h = F.xxhash64("edge_id", F.lit(seed))
    columns = ["edge_id", "src", "dst", "label", "ts"]
    out = []
    for start in edges.where("src <> dst").orderBy(h, "edge_id").limit(n).select(*columns).collect():
        chosen, seen = [start], [start.src, start.dst]
        while len(chosen) < size:
            used = [r.edge_id for r in chosen]
            near = edges.where((F.col("src").isin(seen) | F.col("dst").isin(seen)) & ~F.col("edge_id").isin(used) & (F.col("src") != F.col("dst")))
            both = F.col("src").isin(seen) & F.col("dst").isin(seen)
            new = near.where(~both).orderBy(h, "edge_id").limit(1).select(*columns).collect()
            loop = near.where(both).orderBy(h, "edge_id").limit(1).select(*columns).collect() if kind == "graph" and len(chosen) % 3 == 2 else []
            if not (loop or new):
                break
            row = (loop or new)[0]
            chosen.append(row)
            seen += [v for v in (row.src, row.dst) if v not in seen]
        if len(chosen) == size:
            name = {v: f"u{i}" for i, v in enumerate(seen)}
            order = {r.edge_id: i for i, r in enumerate(sorted(chosen, key=lambda r: (r.ts or 0, r.edge_id)))}
            out.append(Pattern.of(*[QueryEdge(f"q{i}", name[r.src], name[r.dst], (r.label,), time=order[r.edge_id] if times else None) for i, r in enumerate(chosen)], name=f"{kind[0].upper()}_{size}_{len(out)}"))
    return out


def answer_all(edges: DataFrame, patterns: list[Pattern], semantics) -> DataFrame:
    """Several patterns over one graph: (pattern, n) of each.  One pass marks every edge with the matches of all patterns, a mask a
    pattern; each pattern then reads its own."""
    from functools import reduce

    from flowmatch.functions.rules import bit, local_masks
    from flowmatch.operators.enumeration import enumerate_all
    from flowmatch.plans.planner import compile_plan
    from flowmatch.sources.storage import stored

    marked = edges
    for k, p in enumerate(patterns):
        marked = local_masks(marked, p).withColumnRenamed("local_mask", f"mask_{k}")
    shared = stored(marked.where(" or ".join(f"mask_{k} <> 0" for k in range(len(patterns)))).select("edge_id", "src", "dst", "ts", *[f"mask_{k}" for k in range(len(patterns))]), "shared-masks")
    parts = []
    for k, p in enumerate(patterns):
        of = {e.name: shared.where(bit(f"mask_{k}", i)).select("edge_id", "src", "dst", "ts") for i, e in enumerate(p.edges)}
        parts.append(enumerate_all(shared, p, semantics, compile_plan(p, profile=semantics.profile), of=of).agg(F.count("*").alias("n")).select(F.lit(p.name).alias("pattern"), "n"))
    return reduce(lambda a, b: a.unionByName(b), parts)
