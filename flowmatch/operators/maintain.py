"""Index maintenance by batches: only what a batch can change is computed again.

The strata are deg, top, sub, ok, in that order, each a function of earlier ones and of itself along the acyclic tree.
A batch touches the ends of its edges; a stratum is recomputed for the touched vertices and for those that an arc joins
to a vertex whose bits changed one level before.  Each is recomputed from all arcs it depends on, so no support is
counted twice and inserts and deletes are treated alike; the result equals a rebuild.

Vertices and edges are tables with an overlay.  A batch reads edges by semi-joins with small written sets of ids, writes
the vertices and edges whose bits changed, and no others; a level whose set adds no change passes nothing on.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame, functions as F

from flowmatch.functions.rules import Rule, bit, label_rule, local_masks
from flowmatch.operators import index as ix
from flowmatch.plans.planner import Plan
from flowmatch.sources.storage import DeltaTable, stored

Keep = Callable[[DataFrame], DataFrame]


@dataclass
class LiveIndex:
    """The index under a stream.  ``edges``: those that match some query edge, with local_mask, reach_mask, live_mask and ``born``, the
    batch that brought them; ``vertices``: vid, vtype, deg, top, sub, ok."""

    plan: Plan
    edges: DeltaTable
    vertices: DeltaTable
    passes: str = "fixpoint"
    rule: Rule = label_rule
    work: dict = field(default_factory=dict)  # of the last batch: vertices touched, vertices and edges with new masks

    def live(self, column: str = "live_mask") -> DataFrame:
        return self.edges.view().where(f"{column} <> 0")

    def candidates(self) -> dict[str, DataFrame]:
        rows = self.live()
        return {e.name: rows.where(bit("live_mask", i)) for i, e in enumerate(self.plan.pattern.edges)}

    def roots(self) -> DataFrame:
        return self.vertices.view().where(bit("ok", self.plan.pattern.bit(self.plan.tree.root))).select("vid")


def open_index(edges: DataFrame, plan: Plan, rule: Rule = label_rule, passes: str = "fixpoint", keep: Keep = stored, born: int = -1, share: float = 0.25) -> LiveIndex:
    """From scratch, for the initial graph or at a reset.  A column ``born`` of the edges is kept."""
    return _built(keep(local_masks(edges, plan.pattern, rule).where("local_mask <> 0")), plan, rule, passes, keep, born, share)


def _built(near: DataFrame, plan: Plan, rule: Rule, passes: str, keep: Keep, born: int, share: float) -> LiveIndex:
    """The index of written edges with ``local_mask``."""
    index = ix.build_index(near, plan, rule, passes, keep)
    marked = index.marked()
    marked = marked if "born" in marked.columns else marked.withColumn("born", F.lit(born).cast("long"))
    return LiveIndex(plan, DeltaTable(keep(marked), "edge_id", share=share), DeltaTable(keep(index.vertices), "vid", share=share), passes, rule)


def _union(*sets: DataFrame | None) -> DataFrame:
    return reduce(lambda a, b: a.unionByName(b), [s for s in sets if s is not None]).distinct()


def touched(batch: DataFrame) -> DataFrame:
    return _union(batch.select(F.col("src").alias("vid")), batch.select(F.col("dst").alias("vid")))


def _at(rows: DataFrame, ids: DataFrame, end: str) -> DataFrame:
    return rows.join(ids.select(F.col("vid").alias(end)), end, "left_semi").select(rows.columns)


def _incident(edges: DataFrame, ids: DataFrame) -> DataFrame:
    """Edges with an end among the ids, each once."""
    return _at(edges, ids, "src").unionByName(_at(edges, ids, "dst").join(ids.select(F.col("vid").alias("src")), "src", "left_anti").select(edges.columns))


class _States:
    """Vertex states during a batch: those of the table, under what the batch has changed so far.

    ``new`` holds every changed vertex once, with ``step``, the number of the last change, so a step writes one small table.
    """

    def __init__(self, table: DeltaTable, keep: Keep):
        self.old, self.keep, self.new, self.step = table.view(), keep, None, 0
        self.columns = table.base.columns

    def of(self, ids: DataFrame) -> DataFrame:
        old = self.old.join(ids, "vid", "left_semi")
        if self.new is None:
            return old
        return old.join(self.new.select("vid"), "vid", "left_anti").unionByName(self.new.drop("step").join(ids, "vid", "left_semi"))

    def put(self, rows: DataFrame) -> DataFrame | None:
        """Takes over changed rows; returns their ids, or none if there are no rows."""
        self.step += 1
        rows = rows.select(*self.columns, F.lit(self.step).alias("step"))
        if self.new is not None:
            values = F.struct(*[c for c in self.columns if c != "vid"])
            rows = self.new.unionByName(rows).groupBy("vid").agg(F.max_by(values, "step").alias("x"), F.max("step").alias("step")).select("vid", "x.*", "step")
        self.new = self.keep(rows.select(*self.columns, "step"))
        moved = self.new.where(F.col("step") == self.step).select("vid")
        return None if moved.isEmpty() else moved

    def settle(self, again: DataFrame, got: DataFrame | None, column: str, value: Column) -> DataFrame | None:
        """Recomputes a mask of the given vertices; returns the ids of those that it changes, or none."""
        rows = self.of(again)
        rows = rows if got is None else rows.join(got, "vid", "left")
        return self.put(rows.withColumn("next", value).where(F.col("next") != F.col(column)).withColumn(column, F.col("next")))


def _masked(column: str, bits: int) -> Column:
    return F.col(column).bitwiseAND(F.lit(~bits & ((1 << 62) - 1)).cast("bigint"))


def _bits(n: int) -> Column:
    return F.lit(n).cast("bigint")


def maintain(index: LiveIndex, inserts: DataFrame | None = None, deletes: DataFrame | None = None, batch: int = 0, keep: Keep = stored, cache: bool = True, few: int = 1024) -> LiveIndex:
    """The index after a batch.  ``inserts``: edges; ``deletes``: rows with edge_id.  Edges that match no query edge change nothing.

    A batch that touches over ``few`` vertices and over half of all there were builds the index anew, in fewer steps than it
    takes to find out what it does not change.

    With ``cache`` the edges that the levels read are held in executors' memory, else on their disks, while the batch runs;
    without, each level reads them from the table again.
    """
    plan, tree, at = index.plan, index.plan.tree, index.plan.pattern.bit
    before = index.edges.view()
    columns = before.columns
    fresh = gone = None
    if inserts is not None:
        new = local_masks(inserts, plan.pattern, index.rule).where("local_mask <> 0").withColumn("born", F.lit(batch).cast("long"))
        fresh = keep(new.withColumns({"reach_mask": _bits(0), "live_mask": _bits(0)}).select(columns))
    if deletes is not None:
        gone = keep(before.join(deletes.select("edge_id").distinct(), "edge_id", "left_semi").select(columns))
    changes = [x for x in (fresh, gone) if x is not None]
    hit = keep(_union(*[touched(x) for x in changes])) if changes else None
    n_hit = hit.count() if changes else 0
    if not n_hit:
        return LiveIndex(plan, index.edges, index.vertices, index.passes, index.rule, {"touched": 0, "vertices": 0, "edges": 0})
    edges = before if gone is None else before.join(gone.select("edge_id"), "edge_id", "left_anti").select(columns)
    edges = edges if fresh is None else edges.unionByName(fresh)
    edges = edges.select(*[c for c in columns if c not in ("reach_mask", "live_mask")])
    if n_hit > max(few, (index.vertices.n_base + index.vertices.n_over) // 2):
        out = _built(keep(edges), plan, index.rule, index.passes, keep, batch, index.edges.share)
        out.work = {"touched": n_hit, "vertices": out.vertices.n_base, "edges": out.edges.n_base}
        return out
    if cache:
        edges = edges.persist()
    arc = ix.arcs(edges, tree)
    states = _States(index.vertices, keep)

    def kids_of(ids):
        return _at(arc, ids, "p").select(F.col("c").alias("vid"))

    def parents_of(ids):
        return _at(arc, ids, "c").select(F.col("p").alias("vid"))

    # deg: of the touched vertices only, from all their edges.
    own = _incident(edges, hit)
    old = states.of(hit).select("vid", F.col("vtype").alias("old_type"), "top", "sub", "ok")
    part = hit.join(ix.vertex_table(own), "vid", "left").join(ix.degree_masks(own, plan), "vid", "left").join(old, "vid", "left")
    part = part.withColumn("vtype", F.coalesce("vtype", "old_type")).withColumn("deg", F.coalesce("deg", _bits(0)).bitwiseAND(F.coalesce(ix.type_mask(plan), _bits(0))))
    part = part.fillna(0, ["top", "ok"]).withColumn("sub", F.coalesce("sub", _bits(ix.leaf_mask(tree))))
    states.put(part)

    # top, level by level.
    root = 1 << at(tree.root)
    moved = states.settle(hit, None, "top", _masked("top", root).bitwiseOR(F.col("deg").bitwiseAND(_bits(root))))
    risen = moved
    for k in range(1, tree.depth + 1):
        level = tree.level(k)
        bits = sum(1 << at(t.child) for t in level)
        again = keep(_union(hit, kids_of(moved) if moved is not None else None))
        into = _at(arc, again, "c")
        got = ix.down(into, states.of(into.select(F.col("p").alias("vid"))), level, tree, "top")
        moved = states.settle(again, got, "top", _masked("top", bits).bitwiseOR(F.coalesce("got", _bits(0)).bitwiseAND(F.col("deg")).bitwiseAND(_bits(bits))))
        risen = moved if risen is None else risen if moved is None else risen.unionByName(moved)

    # sub, from the deepest level up; it reads top of the children.
    below = keep(_union(hit, risen))
    for k in range(tree.depth, 0, -1):
        kids = tree.level(k)
        parents = sorted({t.parent for t in kids})
        bits = sum(1 << at(u) for u in parents)
        again = keep(_union(below, parents_of(below)))
        outof = _at(arc, again, "p")
        has = ix.up(outof, states.of(outof.select(F.col("c").alias("vid"))), kids, tree)
        moved = states.settle(again, has, "sub", _masked("sub", bits).bitwiseOR(ix.complete(tree, parents)))
        below = below if moved is None else keep(_union(below, moved))

    # ok, down again.
    both = F.col("top").bitwiseAND(F.col("sub"))
    if index.passes == "two_pass":
        states.settle(below, None, "ok", both)
    else:
        moved = states.settle(below, None, "ok", _masked("ok", root).bitwiseOR(both.bitwiseAND(_bits(root))))
        for k in range(1, tree.depth + 1):
            level = tree.level(k)
            bits = sum(1 << at(t.child) for t in level)
            again = keep(_union(below, kids_of(below if moved is None else _union(below, moved))))
            into = _at(arc, again, "c")
            got = ix.down(into, states.of(into.select(F.col("p").alias("vid"))), level, tree, "ok")
            moved = states.settle(again, got, "ok", _masked("ok", bits).bitwiseOR(F.coalesce("got", _bits(0)).bitwiseAND(both).bitwiseAND(_bits(bits))))

    # Edges at vertices with new states are marked again.
    dirty = keep(_incident(edges, states.new.select("vid")))
    edges.unpersist()
    marked = ix.edge_masks(dirty, states.of(dirty.select(F.explode(F.array("src", "dst")).alias("vid"))), tree, index.passes).select(columns)
    vertices, work = states.new.drop("step"), {"touched": n_hit, "vertices": states.new.count(), "edges": dirty.count()}
    return LiveIndex(plan, index.edges.changed(marked, gone, keep), index.vertices.changed(vertices, None, keep), index.passes, index.rule, work)


def maintain_insert(index: LiveIndex, batch: DataFrame, number: int = 0, keep: Keep = stored) -> LiveIndex:
    return maintain(index, inserts=batch, batch=number, keep=keep)


def maintain_delete(index: LiveIndex, batch: DataFrame, keep: Keep = stored) -> LiveIndex:
    return maintain(index, deletes=batch, keep=keep)


def seed_frontier(batch: DataFrame, plan: Plan, rule: Rule = label_rule) -> DataFrame:
    """(edge_id, bit): the batch's matching pairs, once each."""
    marked = local_masks(batch, plan.pattern, rule)
    bits = F.array(*[F.when(F.getbit("local_mask", F.lit(i)) == 1, F.lit(i)) for i in range(len(plan.pattern.edges))])
    return marked.select("edge_id", F.explode(F.array_compact(bits)).alias("bit"))
