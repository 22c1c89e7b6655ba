"""The edge-match index: for every data edge, which query edges it may still serve.

It is kept per vertex: the masks ``deg`` (meets the degree needs of query vertex u), ``top`` (reached from a root
candidate down the query tree), ``sub`` (has the whole subtree of u below it) and ``ok`` (top and sub, and its parent is
ok too), one bit per query vertex.  With ``local_mask`` on the edges these give every edge bit by a narrow expression,
and a tree level costs one aggregation by ``bit_or``, which combines before the shuffle, so hubs cost no more than
others.  All query edges of a level share it.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, Window, functions as F

from flowmatch.functions.rules import Rule, bit, label_rule, local_masks, mask_of
from flowmatch.plans.planner import Plan, QueryTree, TreeEdge, degree_requirements



@dataclass
class Index:
    """``edges``: the graph with local_mask.  ``vertices``: vid, vtype, deg, top, sub, ok.  ``passes``: "fixpoint" or "two_pass"."""

    plan: Plan
    edges: DataFrame
    vertices: DataFrame
    passes: str = "fixpoint"

    def marked(self) -> DataFrame:
        """The edges with reach_mask and live_mask; bit i is query edge i.  Bits of non-tree edges hold the local match alone."""
        return edge_masks(self.edges, self.vertices, self.plan.tree, self.passes)

    def candidates(self, keep=lambda df: df) -> dict[str, DataFrame]:
        """Live edges by query edge, for enumeration; ``keep`` writes the marked edges, so that they are marked once."""
        m = keep(self.marked().where("live_mask <> 0"))
        return {e.name: m.where(bit("live_mask", i)) for i, e in enumerate(self.plan.pattern.edges)}

    def roots(self) -> DataFrame:
        return self.vertices.where(bit("ok", self.plan.pattern.bit(self.plan.tree.root))).select("vid")


def vertex_table(edges: DataFrame) -> DataFrame:
    both = edges.select(F.col("src").alias("vid"), F.col("src_type").alias("vtype")).unionByName(edges.select(F.col("dst").alias("vid"), F.col("dst_type").alias("vtype")))
    return both.groupBy("vid").agg(F.min("vtype").alias("vtype"))


def type_mask(plan: Plan) -> Column:
    return mask_of([(i, F.lit(True) if v.label is None else F.col("vtype") == v.label) for i, v in enumerate(plan.pattern.vertices)])


def _any_bit(names: tuple[str, ...], plan: Plan, of: str = "local_mask") -> Column:
    wanted = sum(1 << i for i, e in enumerate(plan.pattern.edges) if e.name in names)
    return F.col(of).bitwiseAND(F.lit(wanted).cast("bigint")) != 0


def degree_masks(edges: DataFrame, plan: Plan) -> DataFrame:
    """(vid, deg): bit u if the vertex has the edges (f2) and the distinct neighbours (f3) that u needs.

    One aggregation by (vertex, neighbour), one by vertex; vertices without any matching edge have no row.
    """
    needs = degree_requirements(plan.pattern, plan.profile)
    keys = list(dict.fromkeys((r.out, r.of) for r in needs))
    if not keys:
        return edges.select(F.col("src").alias("vid")).unionByName(edges.select(F.col("dst").alias("vid"))).distinct().withColumn("deg", F.lit((1 << len(plan.pattern.vertices)) - 1).cast("bigint"))
    hit = {k: _any_bit(k[1], plan) for k in keys}
    own = lambda out: [(hit[k] if k[0] == out else F.lit(False)).cast("long").alias(f"k{i}") for i, k in enumerate(keys)]
    ends = edges.select(F.col("src").alias("vid"), F.col("dst").alias("far"), *own(True)).unionByName(edges.select(F.col("dst").alias("vid"), F.col("src").alias("far"), *own(False)))
    pairs = ends.groupBy("vid", "far").agg(*[F.sum(f"k{i}").alias(f"k{i}") for i in range(len(keys))])
    per = pairs.groupBy("vid").agg(*[F.sum(f"k{i}").alias(f"k{i}") for i in range(len(keys))], *[F.sum((F.col(f"k{i}") > 0).cast("long")).alias(f"d{i}") for i in range(len(keys))])
    tests = []
    for u, v in enumerate(plan.pattern.vertices):
        own_needs = [(F.col(f"k{(i := keys.index((r.out, r.of)))}") >= r.edges) & (F.col(f"d{i}") >= r.neighbours) for r in needs if r.vertex == v.name]
        tests.append((u, reduce(lambda a, b: a & b, own_needs, F.lit(True))))
    return per.select("vid", mask_of(tests).alias("deg"))


def arcs(edges: DataFrame, tree: QueryTree) -> DataFrame:
    """Edges seen from the parent's end: (edge_id, p, c, m), m the tree edges they may play that way round."""
    out = []
    for forward, (p, c) in ((True, ("src", "dst")), (False, ("dst", "src"))):
        own = sum(1 << tree.bit(t) for t in tree.edges if t.forward == forward or not t.edge.directed)
        if own:
            out.append(edges.select("edge_id", F.col(p).alias("p"), F.col(c).alias("c"), F.col("local_mask").bitwiseAND(F.lit(own).cast("bigint")).alias("m")).where("m <> 0"))
    return reduce(lambda a, b: a.unionByName(b), out)


def _bits(tests: list[tuple[int, Column]]) -> Column:
    return mask_of(tests)


def down(arc: DataFrame, state: DataFrame, level: list[TreeEdge], tree: QueryTree, parent: str, needs_sub: bool = False) -> DataFrame:
    """(vid, got): bits of the level's child vertices that some arc brings: its parent end has ``parent``'s bit, its child end the degree."""
    at = tree.pattern.bit
    a = state.select(F.col("vid").alias("p"), F.col(parent).alias("pm")).where("pm <> 0")
    tests = [(at(t.child), bit("m", tree.bit(t)) & bit("pm", at(t.parent))) for t in level]
    found = arc.where(F.col("m").bitwiseAND(F.lit(sum(1 << tree.bit(t) for t in level)).cast("bigint")) != 0).join(a, "p").select(F.col("c").alias("vid"), _bits(tests).alias("got")).where("got <> 0")
    return found.groupBy("vid").agg(F.bit_or("got").alias("got"))


def up(arc: DataFrame, state: DataFrame, kids: list[TreeEdge], tree: QueryTree) -> DataFrame:
    """(vid, has): bits (of tree edges) for which the vertex has an arc that reaches down to a vertex with the child's subtree."""
    at = tree.pattern.bit
    c = state.select(F.col("vid").alias("c"), F.col("top").alias("ct"), F.col("sub").alias("cs")).where("ct <> 0")
    tests = [(tree.bit(t), bit("m", tree.bit(t)) & bit("ct", at(t.child)) & bit("cs", at(t.child))) for t in kids]
    found = arc.where(F.col("m").bitwiseAND(F.lit(sum(1 << tree.bit(t) for t in kids)).cast("bigint")) != 0).join(c, "c").select(F.col("p").alias("vid"), _bits(tests).alias("has")).where("has <> 0")
    return found.groupBy("vid").agg(F.bit_or("has").alias("has"))


def _with(state: DataFrame, new: DataFrame, column: str, value: Column) -> DataFrame:
    return state.join(new, "vid", "left").withColumn(column, value).drop(*[c for c in new.columns if c != "vid"])


def _got(column: str, keep: Column | None = None) -> Column:
    got = F.coalesce(F.col("got"), F.lit(0)).cast("bigint")
    return F.col(column).bitwiseOR(got if keep is None else got.bitwiseAND(keep))


def leaf_mask(tree: QueryTree) -> int:
    return sum(1 << i for i, v in enumerate(tree.pattern.vertices) if not tree.kids(v.name))


def complete(tree: QueryTree, vertices: list[str], of: str = "has") -> Column:
    """Bits of the vertices all of whose tree edges are in ``of``."""
    tests = []
    for u in vertices:
        need = sum(1 << tree.bit(t) for t in tree.kids(u))
        tests.append((tree.pattern.bit(u), F.coalesce(F.col(of), F.lit(0)).cast("bigint").bitwiseAND(F.lit(need).cast("bigint")) == need))
    return _bits(tests)


def build_index(edges: DataFrame, plan: Plan, rule: Rule = label_rule, passes: str = "fixpoint", keep=lambda df: df) -> Index:
    """From scratch: one pass down, one up, and for "fixpoint" one more down.  ``keep`` cuts lineage between levels where graphs are large."""
    if passes not in ("fixpoint", "two_pass"):
        raise ValueError("passes are 'fixpoint' and 'two_pass'")
    tree, at = plan.tree, plan.pattern.bit
    edges = edges if "local_mask" in edges.columns else local_masks(edges, plan.pattern, rule)
    near = edges.where("local_mask <> 0")
    arc = arcs(near, tree)
    root = 1 << at(tree.root)
    state = vertex_table(near).join(degree_masks(near, plan), "vid", "left").withColumn("deg", F.coalesce("deg", F.lit(0)).cast("bigint").bitwiseAND(type_mask(plan)))
    state = keep(state.withColumn("top", F.col("deg").bitwiseAND(F.lit(root).cast("bigint"))))
    for k in range(1, tree.depth + 1):
        state = keep(_with(state, down(arc, state, tree.level(k), tree, "top"), "top", _got("top", F.col("deg"))))
    state = keep(state.withColumn("sub", F.lit(leaf_mask(tree)).cast("bigint")))
    for k in range(tree.depth, 0, -1):
        kids = tree.level(k)
        state = keep(_with(state, up(arc, state, kids, tree), "sub", F.col("sub").bitwiseOR(complete(tree, sorted({t.parent for t in kids})))))
    state = finish(arc, state, tree, passes, keep)
    return Index(plan, edges, state, passes)


def finish(arc: DataFrame, state: DataFrame, tree: QueryTree, passes: str, keep=lambda df: df) -> DataFrame:
    """The mask ok: top and sub; with "fixpoint", of those the ones whose parent is ok, down to the leaves."""
    both = F.col("top").bitwiseAND(F.col("sub"))
    if passes == "two_pass":
        return state.withColumn("ok", both)
    state = state.withColumn("ok", both.bitwiseAND(F.lit(1 << tree.pattern.bit(tree.root)).cast("bigint")))
    for k in range(1, tree.depth + 1):
        state = keep(_with(state, down(arc, state, tree.level(k), tree, "ok"), "ok", _got("ok", both)))
    return state


def edge_masks(edges: DataFrame, vertices: DataFrame, tree: QueryTree, passes: str) -> DataFrame:
    """reach: local, parent in top, child meets the degree.  live: reach, child has its subtree, and for "fixpoint" the parent is ok."""
    at = tree.pattern.bit
    end = lambda x: vertices.select(F.col("vid").alias(x), F.struct("deg", "top", "sub", "ok").alias(f"{x}_state"))
    rows = edges.join(end("src"), "src", "left").join(end("dst"), "dst", "left")
    reach, live = [], []
    for t in tree.edges:
        i = tree.bit(t)
        ways = []
        for forward in [t.forward] if t.edge.directed else [True, False]:
            p, c = ("src_state", "dst_state") if forward else ("dst_state", "src_state")
            r = bit("local_mask", i) & bit(F.col(f"{p}.top"), at(t.parent)) & bit(F.col(f"{c}.deg"), at(t.child))
            l = r & bit(F.col(f"{c}.sub"), at(t.child))  # noqa: E741
            ways.append((r, l & bit(F.col(f"{p}.ok"), at(t.parent)) if passes == "fixpoint" else l))
        reach.append((i, reduce(lambda a, b: a | b, [w[0] for w in ways])))
        live.append((i, reduce(lambda a, b: a | b, [w[1] for w in ways])))
    others = [(tree.pattern.edges.index(e), bit("local_mask", tree.pattern.edges.index(e))) for e in tree.rest]
    return rows.withColumn("reach_mask", _bits(reach + others)).withColumn("live_mask", _bits(live + others)).drop("src_state", "dst_state")


def index_bits(n_edges: int, n_vertices: int, n_query: int) -> int:
    """Bits of the index: a bit per data edge and tree edge, and a bit per vertex for the roots."""
    return n_edges * (n_query - 1) + n_vertices


def assign_slots(events: DataFrame, reclaim: bool = True) -> DataFrame:
    """Per source vertex and snapshot: live slots before, inserts, and slots in use so far, from rows (src, snapshot, inserts, deletes).

    Freed slots serve from the next snapshot on, so a snapshot needs what is live before it plus its inserts; with
    ``reclaim`` the slots are the peak of that, without it all inserts.
    """
    by = Window.partitionBy("src").orderBy("snapshot")
    so_far = by.rowsBetween(Window.unboundedPreceding, 0)
    before = by.rowsBetween(Window.unboundedPreceding, -1)
    rows = events.groupBy("src", "snapshot").agg(F.sum("inserts").alias("inserts"), F.sum("deletes").alias("deletes"))
    rows = rows.withColumn("live_before", F.coalesce(F.sum(F.col("inserts") - F.col("deletes")).over(before), F.lit(0)))
    if reclaim:
        return rows.withColumn("slots", F.max(F.col("live_before") + F.col("inserts")).over(so_far))
    return rows.withColumn("slots", F.sum("inserts").over(so_far))
