"""Embeddings as join chains: static, and by deltas with batch masks.

A row of embeddings has ``v_<name>`` for each query vertex, ``e_<name>`` for each query edge, and ``t_<name>`` for the
edges whose times matter.  A chain binds one query edge after another; ends that are bound already are join keys, so a
cycle closes by an equi-join on both ends that lists every parallel edge.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import Column, DataFrame, functions as F

from flowmatch.functions.rules import Rule, label_rule
from flowmatch.plans.pattern import Pattern, QueryEdge, symmetry_breaking
from flowmatch.plans.planner import Plan, batch_masks, closed, compile_plan, order_from, temporal_pairs


class Expander:
    """How embeddings grow: the user's second function, beside the edge rule.  Every hook has a neutral default.

    ``start`` may change the candidates of the first edge; ``extend_condition`` gives the tests that a newly bound edge makes
    decidable, over columns v_, e_ and (for the edges that ``times`` names) t_; ``finish`` may drop or change whole rows;
    ``reduce`` sees all rows of a result, once.
    """

    profile = "none"  # of the degree filter: "injective", "existence" or "none"

    def times(self, pattern: Pattern) -> set[str]:
        return set()

    def start(self, candidates: DataFrame, edge: QueryEdge) -> DataFrame:
        return candidates

    def extend_condition(self, pattern: Pattern, bound: set[str], done: list[str], edge: QueryEdge, fresh: list[str]) -> list[Column]:
        """``bound`` vertices and ``done`` edges before; ``edge`` is bound now, and the vertices ``fresh`` with it."""
        return []

    def finish(self, rows: DataFrame) -> DataFrame:
        return rows

    def reduce(self, rows: DataFrame) -> DataFrame:
        return rows


@dataclass(frozen=True)
class Semantics(Expander):
    """What makes a row of matching edges an embedding."""

    injective: bool = True
    pairs: tuple[tuple[str, str], ...] = ()  # the first edge is earlier
    strict: bool = True
    within: int | None = None  # microseconds between the first and the last edge, at most
    symmetry: tuple[tuple[str, str], ...] = ()

    @property
    def profile(self) -> str:
        return "injective" if self.injective else "existence"

    def times(self, pattern: Pattern) -> set[str]:
        return {e.name for e in pattern.edges} if self.within is not None else {x for p in self.pairs for x in p}

    def extend_condition(self, pattern: Pattern, bound: set[str], done: list[str], edge: QueryEdge, fresh: list[str]) -> list[Column]:
        p, tests = pattern, []
        v = lambda n: F.col(f"v_{n}")
        t = lambda n: F.col(f"t_{n}")
        after = bound | {edge.src, edge.dst}
        if self.injective:
            for a in fresh:
                others = bound | set(fresh[: fresh.index(a)])
                tests += [v(a) != v(b) for b in sorted(others) if p.vertex(a).label is None or p.vertex(b).label in (None, p.vertex(a).label)]
            tests += [F.col(f"e_{edge.name}") != F.col(f"e_{d}") for d in done if p.edge(d).ends() == edge.ends()]
        tests += [v(a) < v(b) for a, b in self.symmetry if {a, b} <= after and {a, b} & set(fresh)]
        now = [*done, edge.name]
        tests += [t(a) < t(b) if self.strict else t(a) <= t(b) for a, b in self.pairs if edge.name in (a, b) and a in now and b in now]
        if self.within is not None and done:
            tests += [F.abs(t(edge.name) - t(d)) <= self.within for d in done]
        return tests


def isomorphism(pattern: Pattern | None = None, symmetry: bool = False) -> Semantics:
    return Semantics(symmetry=tuple(symmetry_breaking(pattern)) if symmetry else ())


def homomorphism() -> Semantics:
    return Semantics(injective=False)


def temporal(pattern: Pattern, within: int | None = None, strict: bool = True, mode: str = "total") -> Semantics:
    return Semantics(pairs=tuple(temporal_pairs(pattern, mode)), strict=strict, within=within)


def side(edges: DataFrame, edge: QueryEdge, timed: bool) -> DataFrame:
    """Edges as matches of one query edge, under its names; without direction, both ways round."""
    columns = [F.col("edge_id").alias(f"e_{edge.name}"), *([F.col("ts").alias(f"t_{edge.name}")] if timed else [])]
    if edge.src == edge.dst:
        return edges.where("src = dst").select(F.col("src").alias(f"v_{edge.src}"), *columns)
    one = edges.select(F.col("src").alias(f"v_{edge.src}"), F.col("dst").alias(f"v_{edge.dst}"), *columns)
    if edge.directed:
        return one
    return one.unionByName(edges.where("src <> dst").select(F.col("dst").alias(f"v_{edge.src}"), F.col("src").alias(f"v_{edge.dst}"), *columns))


@dataclass(frozen=True)
class Hubs:
    """Vertices whose edges are spread in joins: their edges get one of ``salts`` salts, the rows that bind them all of them."""

    ids: DataFrame  # (hub), written, so that its size is known
    salts: int = 16


def find_hubs(edges: DataFrame, over: int, salts: int = 16, keep=lambda df: df) -> Hubs:
    """Vertices with more than ``over`` edges on either side; there are at most 2 E / ``over``."""
    ends = edges.select(F.col("src").alias("hub")).unionByName(edges.select((-F.col("dst") - 1).alias("hub")))
    many = ends.groupBy("hub").count().where(F.col("count") > over)
    return Hubs(keep(many.select(F.when(F.col("hub") < 0, -F.col("hub") - 1).otherwise(F.col("hub")).alias("hub")).distinct()), salts)


def salted_join(rows: DataFrame, new: DataFrame, keys: list[str], hubs: Hubs) -> DataFrame:
    """``rows.join(new, keys)`` in which no hub of the first key lands in one task."""
    key, n = keys[0], hubs.salts
    is_hub = hubs.ids.select(F.col("hub").alias(key), F.lit(True).alias("is_hub"))
    edge = next(c for c in new.columns if c.startswith("e_"))
    dealt = new.join(is_hub, key, "left").withColumn("salt", F.when(F.col("is_hub"), F.pmod(F.xxhash64(edge), F.lit(n))).otherwise(0).cast("int")).drop("is_hub")
    spread = F.when(F.col("is_hub"), F.sequence(F.lit(0), F.lit(n - 1))).otherwise(F.array(F.lit(0)))
    return rows.join(is_hub, key, "left").withColumn("salt", F.explode(spread)).drop("is_hub").join(dealt, [*keys, "salt"]).drop("salt")


def in_slots(rows: DataFrame, t: str, new: DataFrame, t_new: str, within: int) -> tuple[DataFrame, DataFrame]:
    """Both sides with ``slot``, to join by: rows go to the slot of their time, edges to three, so that what lies ``within`` meets, once.

    Slots are as long as ``within``, so rows meet edges of three slots and not of all times.
    """
    long = max(1, within)
    slot = F.expr(f"`{t_new}` div {long}L")
    return rows.withColumn("slot", F.expr(f"`{t}` div {long}L")), new.withColumn("slot", F.explode(F.array(slot - 1, slot, slot + 1)))


@dataclass
class Chain:
    """A chain under way: the rows so far, and which query vertices and edges they bind."""

    pattern: Pattern
    semantics: Expander
    rows: DataFrame | None = None
    bound: set[str] = field(default_factory=set)
    done: list[str] = field(default_factory=list)
    hubs: Hubs | None = None

    def extend(self, matches: DataFrame, name: str) -> Chain:
        """Joins the matches of one query edge and at once applies every condition that it makes decidable."""
        edge = self.pattern.edge(name)
        timed = name in self.semantics.times(self.pattern)
        new = side(matches if self.rows is not None else self.semantics.start(matches, edge), edge, timed)
        ends = list(dict.fromkeys((edge.src, edge.dst)))
        on = [f"v_{v}" for v in ends if v in self.bound]
        within = getattr(self.semantics, "within", None) if self.rows is not None else None
        if within is not None and timed and self.done:
            old, new = in_slots(self.rows, f"t_{self.done[0]}", new, f"t_{name}", within)
            on = [*on, "slot"]
        else:
            old = self.rows
        rows = new if old is None else salted_join(old, new, on, self.hubs) if self.hubs else old.join(new, on)
        rows = rows.drop("slot")
        tests = self.semantics.extend_condition(self.pattern, self.bound, self.done, edge, [v for v in ends if v not in self.bound])
        if tests:
            rows = rows.where(reduce(lambda a, b: a & b, tests))
        return Chain(self.pattern, self.semantics, rows, self.bound | set(ends), [*self.done, name], self.hubs)

    def result(self) -> DataFrame:
        rows = self.rows.select(*[f"v_{x.name}" for x in self.pattern.vertices if x.name in self.bound], *[f"e_{e.name}" for e in self.pattern.edges if e.name in self.done], *[f"t_{n}" for n in self.done if n in self.semantics.times(self.pattern)])
        return self.semantics.finish(rows)


def matches(edges: DataFrame, edge: QueryEdge, pattern: Pattern, rule: Rule = label_rule) -> DataFrame:
    """The data edges that may play a query edge; the rule reaches the scan as a filter."""
    return edges.where(rule(edge, pattern)).select("edge_id", "src", "dst", "ts")


def enumerate_all(edges: DataFrame, pattern: Pattern, semantics: Expander, plan: Plan | None = None, rule: Rule = label_rule, of: dict[str, DataFrame] | None = None, hubs: Hubs | None = None, limit: int | None = None) -> DataFrame:
    """All embeddings in a graph.  ``of``: candidate edges by query edge, as an index leaves them, instead of the rule; ``limit``: so many at most."""
    plan = plan or compile_plan(pattern)
    chain = Chain(plan.pattern, semantics, hubs=hubs)
    for name in plan.order:
        chain = chain.extend(of[name] if of else matches(edges, plan.pattern.edge(name), pattern, rule), name)
    rows = semantics.reduce(chain.result())
    return rows if limit is None else rows.limit(limit)


def existing(edges: DataFrame, pattern: Pattern, root: str, rule: Rule = label_rule) -> DataFrame:
    """(v_root) of the vertices at which a homomorphic match of a tree pattern hangs: semi-joins from the leaves up, no rows multiply."""
    tree = compile_plan(pattern, root=root).tree
    if tree.rest:
        raise ValueError("only for tree patterns")

    def below(vertex: str) -> DataFrame | None:
        found = None
        for t in tree.kids(vertex):
            own = matches(edges, t.edge, pattern, rule).select(F.col("src" if t.forward else "dst").alias(f"v_{vertex}"), F.col("dst" if t.forward else "src").alias(f"v_{t.child}"))
            deeper = below(t.child)
            own = (own if deeper is None else own.join(deeper, f"v_{t.child}", "left_semi")).select(f"v_{vertex}")
            found = own if found is None else found.join(own, f"v_{vertex}", "left_semi")
        return found

    return below(root).distinct()


def start_order(plan: Plan, start: str) -> list[str]:
    """All edges from a start on, each connected to those before it, cycles closed as soon as they can be."""
    tree_first = order_from(plan.tree, start)
    if start in tree_first:
        order = closed(tree_first, plan.tree)
    else:  # the start is no tree edge: it is bound first
        order = [start, *[n for n in closed(tree_first, plan.tree) if n != start]]
    out, bound, left = [order[0]], set(plan.pattern.edge(order[0]).ends()), order[1:]
    while left:
        nxt = next((n for n in left if plan.pattern.edge(n).ends() <= bound), None) or next(n for n in left if plan.pattern.edge(n).ends() & bound)
        left.remove(nxt)
        out.append(nxt)
        bound |= plan.pattern.edge(nxt).ends()
    return out


def sized_order(pattern: Pattern, start: str, sizes: dict[str, tuple[float, float, float]]) -> list[str]:
    """All edges, each connected to those before it, by which the rows before the last join are fewest, as estimated.

    ``sizes``: of each edge's matches, how many they are, and how many sources and targets they have.  Where several first
    edges do as well, it is ``start``.
    """
    best = None
    for first in [start, *[e.name for e in pattern.edges if e.name != start]]:
        order, bound, rows = [first], set(pattern.edge(first).ends()), sizes[first][0]
        cost = 0.0
        while len(order) < len(pattern.edges):
            cost += rows

            def fan(e: QueryEdge) -> float:
                n, a, b = sizes[e.name]
                return n / ((max(1, a) if e.src in bound else 1) * (max(1, b) if e.dst in bound else 1))  # noqa: B023

            nxt = min((e for e in pattern.edges if e.name not in order and e.ends() & bound), key=fan)
            rows *= fan(nxt)
            order.append(nxt.name)
            bound |= nxt.ends()
        if best is None or cost < best[0]:
            best = (cost, order)
    return best[1]


def delta(all_edges: DataFrame, is_new: Column, plan: Plan, semantics: Expander, rule: Rule = label_rule, orientation: str = "earlier_old", dedup: str = "mask", of: dict[str, DataFrame] | None = None, starts: list[str] | None = None, orders: dict[str, list[str]] | None = None) -> DataFrame:
    """Embeddings that use at least one edge for which ``is_new`` holds, each once; column ``start`` tells by which edge it was found.

    ``all_edges``: the graph with the batch in it (for losses: the graph before the deletes, the dying edges being the new
    ones).  One chain per start edge; masks bar the batch from the edges before it (or behind it).  "none" drops the
    masks and repeats embeddings; "distinct" removes the repeats by a shuffle of all rows.  ``orders``: for each start, the
    order in which its chain is joined, where that need not begin with the start.
    """
    order = plan.starts()
    barred = batch_masks(order, orientation)
    found = []
    for start in starts if starts is not None else order:
        chain = Chain(plan.pattern, semantics)
        for name in orders[start] if orders else start_order(plan, start):
            side_ = of[name] if of else all_edges.where(rule(plan.pattern.edge(name), plan.pattern))
            if name == start:
                side_ = side_.where(is_new)
            elif dedup == "mask" and name in barred[start]:
                side_ = side_.where(~is_new)
            chain = chain.extend(side_.select("edge_id", "src", "dst", "ts"), name)
        found.append(chain.result().withColumn("start", F.lit(start)))
    out = semantics.reduce(reduce(lambda a, b: a.unionByName(b), found))
    return out.dropDuplicates([f"e_{e.name}" for e in plan.pattern.edges]) if dedup == "distinct" else out


def newest(edges: DataFrame, pattern: Pattern, semantics: Expander, batch: Column, plan: Plan | None = None, rule: Rule = label_rule) -> DataFrame:
    """All insert-only deltas of a history in one plan: an embedding is born in the latest batch of its edges, ``snapshot_id``."""
    plan = plan or compile_plan(pattern)
    ids = edges.select("edge_id", batch.alias("b"))
    rows = enumerate_all(edges, pattern, semantics, plan, rule)
    for e in plan.pattern.edges:
        rows = rows.join(ids.select(F.col("edge_id").alias(f"e_{e.name}"), F.col("b").alias(f"b_{e.name}")), f"e_{e.name}")
    names = [f"b_{e.name}" for e in plan.pattern.edges]
    return rows.withColumn("snapshot_id", F.greatest(*names) if len(names) > 1 else F.col(names[0])).drop(*names)


def live_delta(masked: DataFrame, is_new: Column, plan: Plan, semantics: Expander, orientation: str = "earlier_old", dedup: str = "mask", mask: str = "local_mask") -> DataFrame:
    """:func:`delta` on edges with a mask (of local matches, or of live bits), read once per query edge by its bit; starts for which the batch has no edge are left out.

    Under :class:`Semantics`, for which the order does not matter, a batch too large to begin with is joined later.
    """
    names = [e.name for e in plan.pattern.edges]
    counts = []
    for i, n in enumerate(names):
        own = F.getbit(mask, F.lit(i)) == 1
        counts += [F.count(F.when(own & is_new, 1)).alias(f"new_{n}"), F.count(F.when(own, 1)).alias(f"all_{n}"), F.approx_count_distinct(F.when(own, F.col("src"))).alias(f"src_{n}"), F.approx_count_distinct(F.when(own, F.col("dst"))).alias(f"dst_{n}")]
    r = masked.agg(*counts).first()
    starts = [s for s in plan.starts() if r[f"new_{s}"]] or plan.starts()[:1]
    of = {n: masked.where(F.getbit(mask, F.lit(i)) == 1) for i, n in enumerate(names)}
    orders = None
    if type(semantics) is Semantics:
        barred = batch_masks(plan.starts(), orientation) if dedup == "mask" else {}
        size = lambda s, n: r[f"new_{n}"] if n == s else r[f"all_{n}"] - (r[f"new_{n}"] if n in barred.get(s, ()) else 0)
        orders = {s: sized_order(plan.pattern, s, {n: (size(s, n), r[f"src_{n}"], r[f"dst_{n}"]) for n in names}) for s in starts}
    return delta(masked, is_new, plan, semantics, orientation=orientation, dedup=dedup, of=of, starts=starts, orders=orders)


def work_units(marked: DataFrame, is_new: Column, plan: Plan, mask: str = "live_mask") -> DataFrame:
    """(edge_id, start): one unit of enumeration for each new edge and set bit."""
    names = [F.when(F.getbit(mask, F.lit(i)) == 1, F.lit(e.name)) for i, e in enumerate(plan.pattern.edges)]
    return marked.where(is_new).select("edge_id", F.explode(F.array_compact(F.array(*names))).alias("start"))


def apply_delta(current: DataFrame, gained: DataFrame, lost: DataFrame) -> DataFrame:
    """The fold: what was there and is not lost, and what is gained and not lost at once."""
    keys = [c for c in current.columns if c.startswith("e_")]
    both = current.select(current.columns).unionByName(gained.select(current.columns))
    return both.join(lost.select(keys), keys, "left_anti")


def emit(rows: DataFrame, snapshot_id: int | Column, sign: int) -> DataFrame:
    snap = F.lit(snapshot_id).cast("long") if isinstance(snapshot_id, int) else snapshot_id
    return rows.select(snap.alias("snapshot_id"), F.lit(sign).cast("tinyint").alias("sign"), *[c for c in rows.columns if c[:2] in ("v_", "e_")])


def save_embeddings(rows: DataFrame, path: str, mode: str = "append") -> None:
    """Emitted rows to Parquet, a folder for each snapshot and sign."""
    rows.write.mode(mode).partitionBy("snapshot_id", "sign").parquet(path)


def mislabelled(edges: DataFrame, pattern: Pattern, semantics: Expander, max_cost: int) -> DataFrame:
    """Embeddings in which at most ``max_cost`` edges have another label than asked for; column ``cost`` counts them.

    A query edge whose label is missed costs one; end types and predicates still hold.  The cost so far is tested at
    every join.
    """
    plan = compile_plan(pattern, profile=semantics.profile)
    chain, cost = Chain(plan.pattern, semantics), F.lit(0)
    for name in plan.order:
        e = plan.pattern.edge(name)
        anyhow = replace(e, labels=())
        wrong = edges.where(label_rule(anyhow, pattern)).withColumn("miss", F.when(label_rule(e, pattern), 0).otherwise(1))
        chain = chain.extend(wrong.select("edge_id", "src", "dst", "ts"), name)
        chain.rows = chain.rows.join(wrong.select(F.col("edge_id").alias(f"e_{name}"), F.col("miss").alias(f"miss_{name}")), f"e_{name}")
        cost = cost + F.col(f"miss_{name}")
        chain.rows = chain.rows.where(cost <= max_cost)
    return chain.rows.withColumn("cost", cost).select(*[f"v_{v.name}" for v in plan.pattern.vertices], *[f"e_{e.name}" for e in plan.pattern.edges], "cost")


def alternatives(edges: DataFrame, pattern: Pattern, semantics: Semantics, max_missing: int, rule: Rule = label_rule) -> DataFrame:
    """Embeddings that lack at most ``max_missing`` of the optional edges; column ``missing`` counts them.

    The mandatory part is enumerated; each optional edge then either closes (every parallel edge is a row) or is null.
    """
    rows = enumerate_all(edges, pattern.mandatory(), semantics, rule=rule)
    lacking = F.lit(0)
    for e in [x for x in pattern.edges if x.optional]:
        if not e.ends() <= {v.name for v in pattern.mandatory().vertices}:
            raise ValueError("an optional edge joins vertices that mandatory edges bind")
        new = side(matches(edges, e, pattern, rule), e, False)
        rows = rows.join(new, [f"v_{v}" for v in dict.fromkeys((e.src, e.dst))], "left")
        lacking = lacking + F.col(f"e_{e.name}").isNull().cast("int")
        rows = rows.where(lacking <= max_missing)
    return rows.withColumn("missing", lacking)


