"""The methods compared with, as honest Spark plans under the same output contract."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, functions as F

from flowmatch.functions.rules import Rule, bit, label_rule, local_masks
from flowmatch.operators.enumeration import Chain, Semantics, enumerate_all, live_delta, matches
from flowmatch.operators.maintain import maintain, open_index
from flowmatch.operators.semantics import parallel_collapsed
from flowmatch.plans.pattern import Pattern
from flowmatch.plans.planner import Plan, temporal_pairs
from flowmatch.sources.storage import stored
from flowmatch.sources.views import EDGE

LIST = 4096  # children in a row of a candidate list


def brute_force(edges: DataFrame, pattern: Pattern, semantics: Semantics, rule: Rule = label_rule) -> DataFrame:
    """Self-joins of the raw edges in pattern order, no index."""
    order = [pattern.edges[0].name]
    bound = set(pattern.edges[0].ends())
    left = list(pattern.edges[1:])
    while left:
        e = next(e for e in left if e.ends() & bound)
        left.remove(e)
        order.append(e.name)
        bound |= e.ends()
    chain = Chain(pattern, semantics)
    for name in order:
        chain = chain.extend(matches(edges, pattern.edge(name), pattern, rule), name)
    return chain.result()


def collapse_batch(seen: DataFrame | None, batch: DataFrame) -> DataFrame:
    """The edges of a batch that bring a (src, dst, label) not seen before, the oldest of each."""
    new = parallel_collapsed(batch).drop("multiplicity")
    return new if seen is None else new.join(seen.select("src", "dst", "label"), ["src", "dst", "label"], "left_anti").select(new.columns)


class PairIndex:
    """Pair-level data-centric index: parallel edges are one, and each pair is, per query edge, of state 0 (none), 1 (reached from a
    root) or 2 (reached, with its subtree).

    ``updates`` brings edges one at a time, as published: each explores down and up from its own pair, and is enumerated by
    itself.  ``update`` brings a batch at once, which tells what batching alone is worth.  What comes out are embeddings over
    pairs; ``pair_multiplicity`` counts the edge embeddings each stands for, in which its false reports hide.
    """

    def __init__(self, edges: DataFrame, plan: Plan, semantics: Semantics, rule: Rule = label_rule, keep=stored):
        self.plan, self.semantics, self.rule, self.keep = plan, semantics, rule, keep
        self.raw = keep(edges.select(*EDGE))
        self.index = open_index(parallel_collapsed(self.raw).select(*EDGE), plan, rule, "two_pass", keep)
        self.batch = 0

    def update(self, edges: DataFrame) -> DataFrame:
        """The pair embeddings that the edges bring."""
        self.batch += 1
        new = self.keep(collapse_batch(self.raw, edges.select(*EDGE)).select(*EDGE))
        self.raw = self.keep(self.raw.unionByName(edges.select(*EDGE)))
        self.index = maintain(self.index, inserts=new, batch=self.batch, keep=self.keep)
        rows = self.keep(live_delta(self.index.live(), F.col("born") == self.batch, self.plan, self.semantics, mask="live_mask"))
        many = parallel_collapsed(self.raw).select("edge_id", "multiplicity")
        for e in self.plan.pattern.edges:
            rows = rows.join(many.select(F.col("edge_id").alias(f"e_{e.name}"), F.col("multiplicity").alias(f"m_{e.name}")), f"e_{e.name}")
        names = [f"m_{e.name}" for e in self.plan.pattern.edges]
        return rows.withColumn("pair_multiplicity", reduce(lambda a, b: a * b, [F.col(n) for n in names])).drop(*names, "start")

    def updates(self, edges: DataFrame) -> DataFrame:
        """One edge at a time: a loop over the updates, which is the baseline's definition, for a few hundred of them."""
        out = None
        for r in edges.select("edge_id").orderBy("edge_id").toLocalIterator():
            part = self.keep(self.update(edges.where(F.col("edge_id") == r.edge_id)))
            out = part if out is None else out.unionByName(part)
        return out if out is not None else self.update(edges)

    def states(self) -> DataFrame:
        """(src, dst, label, qedge, state) of the pairs with a state over 0."""
        state = lambda i: F.when(bit("live_mask", i), 2).when(bit("reach_mask", i), 1).otherwise(0)
        each = F.array(*[F.struct(F.lit(e.name).alias("qedge"), state(i).alias("state")) for i, e in enumerate(self.plan.pattern.edges)])
        return self.index.edges.view().select("src", "dst", "label", F.explode(each).alias("x")).select("src", "dst", "label", "x.qedge", "x.state").where("state > 0")


def pair_state(edges: DataFrame, plan: Plan, is_new: Column, semantics: Semantics, rule: Rule = label_rule, batched: bool = True, keep=stored) -> DataFrame:
    """The pair embeddings that the new edges bring to the graph of the old ones."""
    index = PairIndex(edges.where(~is_new), plan, semantics, rule, keep)
    return (index.update if batched else index.updates)(edges.where(is_new))


def audit_context(by_pair: DataFrame, by_event: DataFrame, vertices: list[str]) -> DataFrame:
    """Vertex tuples that the pair index reports and no embedding of events has: temporal context was lost."""
    keys = [f"v_{v}" for v in vertices]
    return by_pair.select(keys).distinct().join(by_event.select(keys), keys, "left_anti")


def delta_wco(edges: DataFrame, pattern: Pattern, is_new: Column | None = None, rule: Rule = label_rule, order: list[str] | None = None) -> DataFrame:
    """Generic join, a vertex at a time, on pairs; then the pairs' parallel edges.  Homomorphism, as it has no injectivity.

    A vertex is proposed by the bound neighbour with the fewest extensions (by row: the smallest list proposes) and every
    other atom intersects by semi-join.  With ``is_new``, one such join for each relation position: the atom itself new,
    those before it new or old, those behind it old.
    """
    names = order or _vertex_order(pattern)

    def atoms(side_of) -> dict[str, DataFrame]:
        return {e.name: matches(side_of(e), e, pattern, rule).select("src", "dst").distinct() for e in pattern.edges}

    def run(of: dict[str, DataFrame], first: str) -> DataFrame:
        e0 = pattern.edge(first)
        rows = of[first].where("src = dst").select(F.col("src").alias(f"v_{e0.src}")) if e0.src == e0.dst else of[first].select(F.col("src").alias(f"v_{e0.src}"), F.col("dst").alias(f"v_{e0.dst}"))
        bound = set(e0.ends())
        rows = _intersect(rows, [e for e in pattern.edges if e.name != first and e.ends() <= bound], of)
        todo = [n for n in names if n not in bound]
        while todo:
            v = next(n for n in todo if any(e.ends() & bound and n in e.ends() for e in pattern.edges))
            todo.remove(v)
            near = [e for e in pattern.edges if v in e.ends() and e.ends() - {v} <= bound and e.src != e.dst]
            sized = rows
            for e in near:
                known = e.src if e.dst == v else e.dst
                n = of[e.name].groupBy(F.col("src" if known == e.src else "dst").alias(f"v_{known}")).agg(F.count("*").alias(f"n_{e.name}"))
                sized = sized.join(n, f"v_{known}")
            least = F.least(*[F.col(f"n_{e.name}") for e in near]) if len(near) > 1 else None
            parts, taken = [], F.lit(False)
            for e in near:
                known, (k, x) = (e.src, ("src", "dst")) if e.dst == v else (e.dst, ("dst", "src"))
                mine = sized if least is None else sized.where((F.col(f"n_{e.name}") == least) & ~taken)
                if least is not None:
                    taken = taken | (F.col(f"n_{e.name}") == least)
                grown = mine.drop(*[f"n_{x.name}" for x in near]).join(of[e.name].select(F.col(k).alias(f"v_{known}"), F.col(x).alias(f"v_{v}")), f"v_{known}")
                parts.append(_intersect(grown, [f for f in near if f.name != e.name], of))
            rows = reduce(lambda a, b: a.unionByName(b), parts)
            bound.add(v)
            rows = _intersect(rows, [e for e in pattern.edges if e.src == e.dst == v], of)
        return rows

    if is_new is None:
        found = run(atoms(lambda e: edges), pattern.edges[0].name)
        sides = [(found, {e.name: edges for e in pattern.edges})]
    else:
        sides = []
        for i, s in enumerate(pattern.edges):
            of_edges = {e.name: edges.where(is_new) if j == i else edges.where(~is_new) if j > i else edges for j, e in enumerate(pattern.edges)}
            sides.append((run(atoms(lambda e, m=of_edges: m[e.name]), s.name), of_edges))
    out = []
    for rows, of_edges in sides:
        for e in pattern.edges:
            full = matches(of_edges[e.name], e, pattern, rule)
            own = full.where("src = dst").select(F.col("src").alias(f"v_{e.src}"), F.col("edge_id").alias(f"e_{e.name}")) if e.src == e.dst else full.select(F.col("src").alias(f"v_{e.src}"), F.col("dst").alias(f"v_{e.dst}"), F.col("edge_id").alias(f"e_{e.name}"))
            rows = rows.join(own, [f"v_{x}" for x in dict.fromkeys((e.src, e.dst))])
        out.append(rows.select(*[f"v_{v.name}" for v in pattern.vertices], *[f"e_{e.name}" for e in pattern.edges]))
    return reduce(lambda a, b: a.unionByName(b), out)


def _vertex_order(pattern: Pattern) -> list[str]:
    return sorted((v.name for v in pattern.vertices), key=lambda n: -len(pattern.incident(n)))


def _intersect(rows: DataFrame, atoms: list, of: dict[str, DataFrame]) -> DataFrame:
    for e in atoms:
        own = of[e.name].where("src = dst").select(F.col("src").alias(f"v_{e.src}")) if e.src == e.dst else of[e.name].select(F.col("src").alias(f"v_{e.src}"), F.col("dst").alias(f"v_{e.dst}"))
        rows = rows.join(own, own.columns, "left_semi")
    return rows


def candidate_store(edges: DataFrame, plan: Plan, rule: Rule = label_rule) -> dict[str, DataFrame]:
    """Query-centric store: per tree edge, a row for each parent match with the list of its children; a hub's list goes on in rows of about ``LIST``."""
    marked = local_masks(edges, plan.pattern, rule)
    out = {}
    for t in plan.tree.edges:
        p, c = ("src", "dst") if t.forward else ("dst", "src")
        own = marked.where(bit("local_mask", plan.tree.bit(t))).select(F.col(p).alias("parent"), F.struct(F.col(c).alias("child"), "edge_id", "ts").alias("x"))
        rows = own.groupBy("parent").agg(F.ceil(F.count("*") / LIST).alias("lists"))
        dealt = own.join(rows, "parent").withColumn("part", F.pmod(F.xxhash64("x.edge_id"), F.col("lists")))
        out[t.edge.name] = dealt.groupBy("parent", "part").agg(F.collect_list("x").alias("children")).select("parent", "children")
    return out


def static_recompute(edges: DataFrame, plan: Plan, semantics: Semantics, rule: Rule = label_rule) -> DataFrame:
    """One snapshot: the store from scratch, then all embeddings from it, no deltas."""
    store = candidate_store(edges, plan, rule)
    of = {}
    for t in plan.tree.edges:
        flat = store[t.edge.name].select("parent", F.inline("children"))
        p, c = ("src", "dst") if t.forward else ("dst", "src")
        of[t.edge.name] = flat.select("edge_id", F.col("parent").alias(p), F.col("child").alias(c), "ts")
    for e in plan.tree.rest:
        of[e.name] = matches(edges, e, plan.pattern, rule)
    return enumerate_all(edges, plan.pattern, semantics, plan, rule, of)


def static_snapshots(edges: DataFrame, plan: Plan, semantics: Semantics, times: list[int], window: int, rule: Rule = label_rule) -> DataFrame:
    """All embeddings of each snapshot of a sliding window, with ``snapshot_id``, the place in ``times``: a store from scratch and no deltas, snapshot by snapshot."""
    parts = []
    for k, now in enumerate(times):
        inside = edges.where((F.col("ts") > now - window) & (F.col("ts") <= now))
        parts.append(static_recompute(inside, plan, semantics, rule).withColumn("snapshot_id", F.lit(k).cast("long")))
    return reduce(lambda a, b: a.unionByName(b), parts)


class MatchStore:
    """Stored partial matches for time-constrained patterns: a table for each prefix of the query edges in time order.

    Edges come in time order, so a new one can only be the last of a prefix: a batch extends the stored prefixes, and those
    that it makes itself, by its edges.  Rows whose first edge has left the window are dropped; the last table's new rows are
    the answers.  The tables are written, so their sum is what the method stores.
    """

    def __init__(self, pattern: Pattern, within: int, rule: Rule = label_rule, keep=stored):
        self.order = sorted(pattern.edges, key=lambda e: e.time)
        bound: set[str] = set()
        for e in self.order:
            if bound and not e.ends() & bound:
                raise ValueError("each edge must touch an earlier one, in time order")
            bound |= e.ends()
        self.pattern, self.within, self.rule, self.keep = pattern, within, rule, keep
        self.semantics = Semantics(pairs=tuple(temporal_pairs(pattern)), within=within)
        self.tables: list[DataFrame | None] = [None] * len(self.order)

    def update(self, batch: DataFrame) -> DataFrame:
        """The embeddings that a batch completes."""
        now = batch.agg(F.max("ts")).first()[0]
        chain, grown = Chain(self.pattern, self.semantics), None
        for i, e in enumerate(self.order):
            start = None
            if i:
                held = self.tables[i - 1]
                start = grown if held is None else held.unionByName(grown.select(held.columns))
            chain = Chain(self.pattern, self.semantics, start, chain.bound, chain.done).extend(matches(batch, e, self.pattern, self.rule), e.name)
            if i:
                self._store(i - 1, grown, now)
            grown = self.keep(chain.rows)
        return chain.semantics.finish(grown)

    def _store(self, i: int, grown: DataFrame, now: int | None) -> None:
        first = F.col(f"t_{self.order[0].name}")
        rows = grown if self.tables[i] is None else self.tables[i].unionByName(grown.select(self.tables[i].columns))
        self.tables[i] = self.keep(rows if now is None else rows.where(first >= now - self.within))

    def stored_rows(self) -> int:
        return sum(t.count() for t in self.tables if t is not None)


def candidate_list(edges: DataFrame, plan: Plan, rule: Rule = label_rule) -> DataFrame:
    """(qvertex, vid): one list for each query vertex, topology lost."""
    marked = local_masks(edges, plan.pattern, rule)
    parts = []
    for i, e in enumerate(plan.pattern.edges):
        own = marked.where(bit("local_mask", i))
        parts += [own.select(F.lit(e.src).alias("qvertex"), F.col("src").alias("vid"), F.lit(f"{i}o").alias("by")), own.select(F.lit(e.dst).alias("qvertex"), F.col("dst").alias("vid"), F.lit(f"{i}i").alias("by"))]
    seen = reduce(lambda a, b: a.unionByName(b), parts).groupBy("qvertex", "vid").agg(F.count_distinct("by").alias("n"))
    need = {v.name: sum((e.src == v.name) + (e.dst == v.name) for e in plan.pattern.edges) for v in plan.pattern.vertices}
    enough = reduce(lambda a, b: a | b, [(F.col("qvertex") == n) & (F.col("n") >= k) for n, k in need.items()])
    return seen.where(enough).select("qvertex", "vid")


def match_matrix(edges: DataFrame, plan: Plan, rule: Rule = label_rule) -> DataFrame:
    """vid and a boolean for each query vertex."""
    names = [v.name for v in plan.pattern.vertices]
    return candidate_list(edges, plan, rule).groupBy("vid").agg(*[F.max(F.col("qvertex") == n).alias(f"is_{n}") for n in names])


def enumerate_from_list(edges: DataFrame, plan: Plan, semantics: Semantics, rule: Rule = label_rule) -> DataFrame:
    """Embeddings from candidate lists: every edge is verified on the graph again."""
    held = candidate_list(edges, plan, rule)
    of = {}
    for e in plan.pattern.edges:
        rows = matches(edges, e, plan.pattern, rule)
        for end, n in (("src", e.src), ("dst", e.dst)):
            rows = rows.join(held.where(F.col("qvertex") == n).select(F.col("vid").alias(end)), end, "left_semi")
        of[e.name] = rows.select("edge_id", "src", "dst", "ts")
    return enumerate_all(edges, plan.pattern, semantics, plan, rule, of)
