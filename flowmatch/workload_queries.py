"""Queries that run the engine over streams, the experiments' classes, the baselines over snapshots, windows of relations, and measures."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from flowmatch import metrics as M, oracle as O
from flowmatch.engine import EngineConfig, MatchEngine
from flowmatch.functions.rules import attribute_rule, label_rule, local_masks, mask_of, python_rule, subset_rule
from flowmatch.operators import baselines as B, graph as G
from flowmatch.operators.enumeration import Expander, Semantics, delta, enumerate_all, existing, find_hubs, homomorphism, isomorphism, mislabelled, temporal
from flowmatch.operators.maintain import seed_frontier
from flowmatch.operators.index import build_index
from flowmatch.operators.semantics import dual_simulation_windows, relation_changes, strong_simulation
from flowmatch.plans.pattern import Pattern, QueryEdge, automorphisms, diameter, parse_pattern, symmetry_breaking
from flowmatch.plans.planner import Plan, batch_masks, build_tree, choose_root, compile_plan, explain_pattern, fan_statistics, order_from, statistics, temporal_pairs
from flowmatch.registry import FOUND, add
from flowmatch.sources import views as V
from flowmatch.sources.snapshots import DAY, HOUR, MINUTE, StreamConfig, insert_delete_events, late_rows, open_stream, resolve_deletes
from flowmatch.sources.storage import TieredStore, shared_dir, stored
from flowmatch.sqlfront import match
from flowmatch.workloads import CLASSES, PATTERNS as P, answer_all, generate

ISO, HOMO = isomorphism(), homomorphism()


def fresh_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"


def named(p: Pattern) -> list[str]:
    return [*[f"v_{x.name}" for x in p.vertices], *[f"e_{e.name}" for e in p.edges]]


def engine(spark: SparkSession, source, p: Pattern, semantics: Expander, config: EngineConfig = EngineConfig()) -> MatchEngine:
    found = MatchEngine(spark, p, semantics, fresh_path(spark, "engine"), config=config)
    found.load_initial(source.initial())
    found.run(source)
    return found


def results(found: MatchEngine, p: Pattern) -> DataFrame:
    rows = found.embeddings()
    if rows is None:  # an empty stream
        rows = found.spark.createDataFrame([], ", ".join(["snapshot_id long", "sign tinyint", *[f"{c} long" for c in named(p)]]))
    return rows.select("snapshot_id", F.col("sign").cast("int").alias("sign"), *named(p))


# --- the method end to end: index upkeep and masked enumeration from live bits, snapshot by snapshot ------------------
def insert_stream(edges: DataFrame, share: float, batches: int):
    n = edges.count()
    first = int(n * share)
    return open_stream(edges, StreamConfig.insert_only(max(1, -(-(n - first) // batches)), first))


def insert_sql(p: Pattern, injective: bool, share: float, batches: int) -> str:
    prefix = f"""with v as materialized ({O.SQL['v1']}), n as (select count(*) as n, floor(count(*) * {share}::double)::bigint as first from v),
      b as (select first, greatest(1, ceil((n - first) / {batches}.0)::bigint) as size from n),
      g as materialized (select v.*, case when seq < first then 0 else (seq - first) // size + 1 end as s from (select *, row_number() over (order by ts, edge_id) - 1 as seq from v) v, b)"""
    born = "greatest(" + ", ".join(f"{e.name}.s" for e in p.edges) + ")"
    return O.embeddings(p, "v1", injective, source="g", prefix=prefix, select=f"{O.columns(p)}, {born} as snapshot_id, 1 as sign", extra=f" and {born} > 0")


for _name, _key, _semantics, _share, _batches in (("stream_insert_t3_v1", "t3_path", ISO, 0.97, 2), ("stream_insert_rectangle_homo_v1", "rectangle", HOMO, 0.892, 1)):
    add(
        _name,
        lambda spark, d, k=_key, s=_semantics, share=_share, n=_batches: results(engine(spark, insert_stream(stored(V.handoff(spark, d)), share, n), P[k], s), P[k]),
        insert_sql(P[_key], _semantics.injective, _share, _batches),
    )


def last_edges(spark: SparkSession, d: str, n: int) -> tuple[DataFrame, int]:
    edges = stored(V.handoff(spark, d))
    return edges, max(0, edges.count() - n)


def _one_by_one(spark: SparkSession, d: str) -> DataFrame:
    edges, first = last_edges(spark, d, 2)
    return results(engine(spark, open_stream(edges, StreamConfig.insert_only(1, first)), P["t3_path"], ISO), P["t3_path"])


_last3 = f"""with v as materialized ({O.SQL['v1']}), g as materialized (select *, greatest(0, seq - greatest(0, n - 2)) as s from (select *, row_number() over (order by ts, edge_id) as seq, count(*) over () as n from v))"""
_t3 = P["t3_path"]
_born3 = "greatest(" + ", ".join(f"{e.name}.s" for e in _t3.edges) + ")"
add("edge_at_a_time_v1", _one_by_one, O.embeddings(_t3, "v1", source="g", prefix=_last3, select=f"{O.columns(_t3)}, {_born3} as snapshot_id, 1 as sign", extra=f" and {_born3} > 0"))


def delete_stream(spark: SparkSession, d: str, snapshots: int = 1):
    events = stored(insert_delete_events(stored(V.commerce(spark, d))))
    n = events.agg(F.max("seq")).first()[0] or 0
    first = int(n * 0.9)
    return open_stream(events, StreamConfig.insert_delete(max(1, -(-(n - first) // snapshots)), first))


_DELETES = f"""with v as materialized ({O.SQL['v3']}), numbered as materialized (select *, row_number() over (order by ts, edge_id) as seq, count(*) over () as n from v),
 cut as materialized (select floor(max(n) * 0.9::double)::bigint as p, greatest(1, max(n) - floor(max(n) * 0.9::double)::bigint) as size from numbered),
 gone as materialized (select (seq * 7919) % p + 1 as victim, (seq - 1 - p) // size + 1 as dies from numbered, cut where seq > p and seq % 10 = 0),
 g as materialized (select numbered.* exclude (n), case when seq <= p then 0 else (seq - 1 - p) // size + 1 end as born, coalesce(dies, 1000000) as dies from numbered cross join cut left join gone on victim = seq where seq <= p or seq % 10 <> 0)"""


def delete_sql(p: Pattern) -> str:
    born, dies = (f"{f}(" + ", ".join(f"{e.name}.{c}" for e in p.edges) + ")" for f, c in (("greatest", "born"), ("least", "dies")))
    e = O.embeddings(p, "v3", source="g", prefix=_DELETES, select=f"{O.columns(p)}, {born} as born, {dies} as dies", extra=f" and {born} <= {dies}")
    return f"with e as ({e}) select * exclude (born, dies), born as snapshot_id, 1 as sign from e where born > 0 union all select * exclude (born, dies), dies, -1 from e where dies < 1000000"


add("stream_insert_delete_t6_v3", lambda spark, d: results(engine(spark, delete_stream(spark, d), P["t6_prefix"], ISO), P["t6_prefix"]), delete_sql(P["t6_prefix"]))


def _bits(spark: SparkSession, d: str) -> DataFrame:
    found = engine(spark, delete_stream(spark, d), P["trade2"], ISO, EngineConfig(root="o"))
    rows = found.index.live()
    each = F.array(*[F.when(F.getbit("live_mask", F.lit(i)) == 1, F.lit(e.name)) for i, e in enumerate(P["trade2"].edges)])
    return rows.select(F.explode(F.array_compact(each)).alias("qedge")).groupBy("qedge").agg(F.count("*").alias("live"))


_kind = "case when label like 'PLACED%' then 'p' when label like 'HAS%' then 'h' else 'f' end"
_P, _H, _F = "label = 'PLACED_1-URGENT_F'", "label = 'HAS_RF'", "label = 'FROM_AF'"
add(
    "maintained_bits_v3",
    _bits,
    f"""{_DELETES}, now as materialized (select * from g where dies = 1000000), o as (select dst as o from now where {_P} intersect select src from now where {_H} intersect select src from now where {_F})
      select {_kind} as qedge, count(*) as live from now where {_P} and dst in (from o) or ({_H} or {_F}) and src in (from o) group by all""",
)


def _resolved(spark: SparkSession, d: str) -> DataFrame:
    edges = V.handoff(spark, d)
    return resolve_deletes(edges, edges.where(F.col("edge_id") % 10 == 0)).select("edge_id")


add("resolve_deletes_v1", _resolved, f"with g as materialized ({O.SQL['v1']}), n as (select src, dst, label, count(*) as n from g where edge_id % 10 = 0 group by all) select edge_id from (select *, row_number() over (partition by src, dst, label order by edge_id) as k from g) join n using (src, dst, label) where k <= n")


def _agree(spark: SparkSession, d: str) -> DataFrame:
    """Rows in which the deltas of both mask orders and of plain distinct differ: none."""
    edges, p = stored(V.handoff(spark, d)), P["triangle"]
    found = [stored(delta(edges, F.col("edge_id") % 3 == 0, compile_plan(p, profile="existence"), HOMO, orientation=o, dedup=how).select(*named(p))) for o, how in (("earlier_old", "mask"), ("later_old", "mask"), ("earlier_old", "distinct"))]
    return spark.createDataFrame([(M.check_equivalence(found[0], x),) for x in found[1:]], "differing long")


add("masks_agree_v1", _agree, "select unnest([0, 0])::bigint as differing")


def _windows(spark: SparkSession, d: str) -> DataFrame:
    source = open_stream(stored(V.access(spark, d)), StreamConfig.sliding(32 * DAY, 16 * DAY))
    return results(engine(spark, source, P["shared_resource"], Semantics(within=DAY)), P["shared_resource"])


_sr = P["shared_resource"]
_sr_ts = ", ".join(f"{e.name}.ts" for e in _sr.edges)
add(
    "stream_window_v2",
    _windows,
    f"""with e as ({O.embeddings(_sr, "v2", True, (), DAY, select=O.columns(_sr) + f", greatest({_sr_ts}) as last_ts, least({_sr_ts}) as first_ts")}),
      life as (select * exclude (last_ts, first_ts), ceil(last_ts / {16 * DAY}.0)::bigint as born, ceil((first_ts + {32 * DAY}) / {16 * DAY}.0)::bigint as dies from e)
      select * exclude (born, dies), born as snapshot_id, 1 as sign from life where born < dies union all select * exclude (born, dies), dies, -1 from life where born < dies""",
)


# --- the programmable surface ----------------------------------------------------------------------------------------
class RisingWeights(Expander):
    """An expander of one's own: weights are not seen, so edges must come with rising ids; of the rows of a first vertex the one of least edge ids stays."""

    profile = "existence"

    def extend_condition(self, pattern: Pattern, bound: set[str], done: list[str], edge: QueryEdge, fresh: list[str]) -> list[Column]:
        return [F.col(f"e_{done[-1]}") < F.col(f"e_{edge.name}")] if done else []

    def finish(self, rows: DataFrame) -> DataFrame:
        return rows.withColumn("span", F.greatest("e_x", "e_y") - F.least("e_x", "e_y"))

    def reduce(self, rows: DataFrame) -> DataFrame:
        return rows.groupBy("v_a").agg(F.min(F.struct("e_x", "e_y", "span")).alias("first")).select("v_a", "first.e_x", "first.e_y", "first.span")


_rp = P["rising_path"]
add(
    "custom_expander_v1",
    lambda spark, d: enumerate_all(V.handoff(spark, d), _rp, RisingWeights(), compile_plan(_rp, root="a", profile="existence")),
    "with r as (" + O.embeddings(_rp, "v1", False, extra=" and x.edge_id < y.edge_id") + ") select v_a, e_x, e_y, e_y - e_x as span from r qualify row_number() over (partition by v_a order by e_x, e_y) = 1",
)
add(
    "python_rule_t2_v1",
    lambda spark, d: enumerate_all(V.handoff(spark, d), _rp, ISO, rule=python_rule(lambda edge, label, weight: label in edge.labels and weight is not None and weight > 50, ["label", "weight"])).select(*named(_rp)),
    O.embeddings(_rp, "v1", extra=" and x.weight > 50 and y.weight > 50"),
)
add(
    "attribute_rule_t2_v1",
    lambda spark, d: enumerate_all(V.handoff(spark, d), _rp, ISO, rule=attribute_rule({"x": F.col("weight") > 50, "y": F.col("edge_id") % 2 == 0})).select(*named(_rp)),
    O.embeddings(_rp, "v1", extra=" and x.weight > 50 and y.edge_id % 2 = 0"),
)
_sub = parse_pattern("(c:customer)-[p:PLACED_1-URGENT_F]->(o:order)-[h:HAS_RF]->(a)", "subset")


def _subset(spark: SparkSession, d: str) -> DataFrame:
    edges = V.commerce(spark, d).withColumns({"src_type": F.concat("src_type", F.lit("|thing")), "dst_type": F.concat(F.lit("thing|"), "dst_type")})
    asked = parse_pattern("(c:customer)-[p:PLACED_1-URGENT_F]->(o:order)-[h:HAS_RF]->(a:thing)", "subset")
    return enumerate_all(edges, asked, HOMO, rule=subset_rule).select(*named(asked))


add("subset_rule_t2_v3", _subset, O.embeddings(_sub, "v3", False))
add("sql_match_t3_v1", lambda spark, d: match(V.handoff(spark, d), "MATCH (a)-[x:purchase]->(b)-[y:click]->(c)-[z:view]->(d) WHERE x.ts < y.ts AND y.ts < z.ts AND x.weight > 10 WITHIN 24 HOURS SEMANTICS iso RETURN x, y, z"), O.embeddings(_t3, "v1", True, (("x", "y"), ("y", "z")), DAY, select="x.edge_id as e_x, y.edge_id as e_y, z.edge_id as e_z", extra=" and x.weight > 10"))


# --- preparation -----------------------------------------------------------------------------------------------------
def roots(spark: SparkSession, d: str) -> DataFrame:
    stats = statistics(V.commerce(spark, d))
    return spark.createDataFrame([(c, choose_root(P[c], stats)) for c in CLASSES], "pattern string, root string")


def _incidence() -> str:
    rows = [f"('{c}', '{v.name}', '{e.labels[0]}', {len(P[c].incident(v.name))})" for c in CLASSES for v in P[c].vertices for e in P[c].incident(v.name)]
    return "(values " + ", ".join(rows) + ") q(pattern, root, label, degree)"


add("selective_root_v3", roots, f"with g as ({O.SQL['v3']}), n as (select label, count(*) as n from g group by label), r as (select pattern, root, any_value(degree) as degree, min(coalesce(n, 0)) as least from {_incidence()} left join n using (label) group by pattern, root) select pattern, root from r qualify row_number() over (partition by pattern order by least, -degree, root) = 1")
add("selective_order_t6_v3", lambda spark, d: enumerate_all(e := stored(V.commerce(spark, d)), P["T_6_trade"], ISO, compile_plan(P["T_6_trade"], s := statistics(e), order="selectivity")).select(*named(P["T_6_trade"])), O.embeddings(P["T_6_trade"], "v3"))
_worked = parse_pattern("(u0)-[a]->(u1)-[d]->(u3),(u2)-[b]->(u0)-[c]->(u5),(u1)-[e]->(u4),(u2)-[f]->(u6),(u2)-[g]->(u5)", "worked")
_tree = build_tree(_worked, "u0")
_ends = {e.name: f"{e.src}{e.dst}" for e in _worked.edges}
# The orders and masks that the worked example has, edges named by their ends.
_ORDERS = {"u0u1": "u0u1 u2u0 u0u5 u1u3 u1u4 u2u6", "u2u0": "u2u0 u0u1 u0u5 u1u3 u1u4 u2u6", "u0u5": "u0u5 u0u1 u2u0 u1u3 u1u4 u2u6", "u1u3": "u1u3 u0u1 u2u0 u0u5 u1u4 u2u6", "u1u4": "u1u4 u0u1 u2u0 u0u5 u1u3 u2u6", "u2u6": "u2u6 u2u0 u0u1 u0u5 u1u3 u1u4", "u2u5": "u0u5 u2u0 u0u1 u1u3 u1u4 u2u6"}
_seven = ["u0u1", "u2u0", "u0u5", "u1u3", "u1u4", "u2u6", "u2u5"]
_LABELS = dict(zip(_seven, ("purchase", "click", "view", "error", "signup", "purchase", "click")))  # the worked example's edges on the handoff view


def _start_orders(spark: SparkSession, d: str) -> DataFrame:
    """The order from each start, and the edges of the view with which it starts."""
    orders = spark.createDataFrame([(_ends[e.name], " ".join(_ends[n] for n in order_from(_tree, e.name)), _LABELS[_ends[e.name]]) for e in _worked.edges], "start string, edges string, label string")
    return V.handoff(spark, d).select("label").join(F.broadcast(orders), "label").groupBy("start", "edges").agg(F.count("*").alias("n"))


_orders_sql = ", ".join(f"('{k}', '{v}', '{_LABELS[k]}')" for k, v in _ORDERS.items())
add("start_orders_worked", _start_orders, f"select start, edges, count(*) as n from (values {_orders_sql}) t(start, edges, label) join ({O.SQL['v1']}) using (label) group by start, edges")
def _masks(spark: SparkSession, d: str) -> DataFrame:
    """What each start bars under both orientations, and how many edges of the batch, every tenth of the view, the mask keeps from there."""
    barred = spark.createDataFrame([(o, s, b, _LABELS[b]) for o in ("earlier_old", "later_old") for s, m in batch_masks(_seven, o).items() for b in sorted(m)], "orientation string, start string, barred string, label string")
    batch = V.handoff(spark, d).where("edge_id % 10 = 0").select("label")
    return batch.join(F.broadcast(barred), "label").groupBy("orientation", "start", "barred").agg(F.count("*").alias("n"))


_seven_sql = ", ".join(f"({k}, '{x}', '{_LABELS[x]}')" for k, x in enumerate(_seven))
add(
    "batch_masks_worked",
    _masks,
    f"""with e as (select * from (values {_seven_sql}) t(k, name, label)), b as (select label, count(*) as n from ({O.SQL['v1']}) where edge_id % 10 = 0 group by label)
      select case when y.k < x.k then 'earlier_old' else 'later_old' end as orientation, x.name as start, y.name as barred, n from e x join e y on x.k <> y.k join b on b.label = y.label""",
)
_FACTS = (("triangle_same", "automorphisms", 3), ("triangle_same", "diameter", 1), ("t3_path", "automorphisms", 1), ("t3_path", "diameter", 3), ("rectangle", "diameter", 2), ("clique5", "diameter", 1), ("worked", "diameter", 4), ("triangle_same", "symmetry pairs", 2), ("shared_resource", "time pairs", 2))


_FACT_VIEW = lambda n: "v2" if n == "shared_resource" else "v1"


def _facts(spark: SparkSession, d: str) -> DataFrame:
    """Facts of patterns, and the edges of the view that fit some edge of theirs."""
    measure = {"automorphisms": lambda p: len(automorphisms(p)), "diameter": diameter, "symmetry pairs": lambda p: len(symmetry_breaking(p)), "time pairs": lambda p: len(temporal_pairs(p.timed(1, 2, 3)))}
    of = {n: _worked if n == "worked" else P[n] for n, _, _ in _FACTS}
    facts = spark.createDataFrame([(n, f, measure[f](of[n])) for n, f, _ in _FACTS], "pattern string, fact string, value int")
    fits = []
    for view in ("v1", "v2"):
        own = [n for n in of if _FACT_VIEW(n) == view]
        rows = V.VIEWS[view](spark, d)
        masks = rows.select(F.explode(F.array_compact(F.array(*[F.when(mask_of([(i, label_rule(e, of[n])) for i, e in enumerate(of[n].edges)]) != 0, F.lit(n)) for n in own]))).alias("pattern"))
        fits.append(masks.groupBy("pattern").agg(F.count("*").alias("n")))
    return facts.join(fits[0].unionByName(fits[1]), "pattern", "left").select("pattern", "fact", "value", F.coalesce("n", F.lit(0)).alias("n"))


def _fits_sql(n: str) -> str:
    labels = {x for e in (_worked if n == "worked" else P[n]).edges for x in e.labels or ("",)}
    where = "" if "" in labels else " where label in (" + ", ".join(f"'{x}'" for x in sorted(labels)) + ")"
    return f"select '{n}' as pattern, count(*) as n from {_FACT_VIEW(n)}{where}"


add(
    "pattern_facts",
    _facts,
    f"with v1 as materialized ({O.SQL['v1']}), v2 as materialized ({O.SQL['v2']}), fits as ({' union all '.join(_fits_sql(n) for n in dict.fromkeys(n for n, _, _ in _FACTS))}) select pattern, fact, value, n from (values "
    + ", ".join(f"('{n}', '{f}', {v})" for n, f, v in _FACTS)
    + ") t(pattern, fact, value) join fits using (pattern)",
)
add("explain_t6_v3", lambda spark, d: spark.createDataFrame(explain_pattern(compile_plan(P["t6_trade"], statistics(V.commerce(spark, d)))), "what string, of string, text string"))
add("frontier_seed_v1", lambda spark, d: seed_frontier(V.handoff(spark, d).where(F.col("edge_id") % 10 == 0), compile_plan(P["t3_path"])), f"select edge_id, case label when 'purchase' then 0 when 'click' then 1 else 2 end as bit from ({O.SQL['v1']}) where edge_id % 10 = 0 and label in ('purchase', 'click', 'view')")


def _grown(spark: SparkSession, d: str) -> DataFrame:
    """Trees grown from the data, and at how many vertices of the first one's kind they hang: one at least."""
    edges = stored(V.commerce(spark, d))
    parts = [existing(edges, p, "u0").agg(F.count("*").alias("vertices")).select(F.lit(p.name).alias("pattern"), "vertices") for p in generate(edges, "tree", 3, 2)]
    return parts[0].unionByName(parts[1])


add("grown_trees_v3", _grown)

# --- the experiments' classes ----------------------------------------------------------------------------------------
_HUBS = ("G_6_nation",)  # breadth first, customers and suppliers of a nation would meet before an order binds them


def class_plan(edges: DataFrame, name: str) -> Plan | None:
    return compile_plan(P[name], fan_statistics(edges), order="fanout") if name in _HUBS else None


def class_rows(spark: SparkSession, d: str, name: str) -> DataFrame:
    """All embeddings.  Line ids take a sort of all lines, so the orders of embeddings are found without them first, and only their lines are numbered."""
    edges, p = V.commerce(spark, d), P[name]
    plan = class_plan(edges, name)
    if plan is None:
        return enumerate_all(edges, p, ISO)
    at = sorted({e.src for e in p.edges if e.labels[0].startswith(("HAS_", "FROM_"))})
    found = enumerate_all(edges, p, ISO, plan).select(F.explode(F.array(*[f"v_{v}" for v in at])).alias("vid")).distinct()
    return enumerate_all(V.commerce(spark, d, stored(found, "orders")), p, ISO, plan)


for _c in CLASSES:
    _short = "".join(_c.lower().split("_")[:2])
    add(f"class_iso_{_short}_v3", lambda spark, d, c=_c: class_rows(spark, d, c).select(*named(P[c])), O.stepwise(P[_c], "v3"))
    add(f"class_homo_{_short}_v3", lambda spark, d, c=_c: enumerate_all(e := V.commerce(spark, d), P[c], HOMO, class_plan(e, c)).agg(F.count("*").alias("n")), O.embeddings(P[_c], "v3", False, select="count(*) as n"))
for _c in ("T_9_trade", "T_12_trade", "G_9_nation", "G_12_nation"):
    _short = "".join(_c.lower().split("_")[:2])
    add(f"wco_{_short}_v3", lambda spark, d, c=_c: B.delta_wco(stored(V.commerce(spark, d)), P[c]).agg(F.count("*").alias("n")), O.embeddings(P[_c], "v3", False, select="count(*) as n"))
add(
    "many_patterns_v1",
    lambda spark, d: answer_all(V.handoff(spark, d), [P[k] for k in ("t3_path", "triangle", "rectangle", "dual_triangle")], HOMO),
    " union all ".join(f"select '{k}' as pattern, n from ({O.embeddings(P[k], 'v1', False, select='count(*) as n')})" for k in ("t3_path", "triangle", "rectangle", "dual_triangle")),
)

# --- variants of matching --------------------------------------------------------------------------------------------
_tri = P["triangle"]
_cost = " + ".join(f"({e.name}.label <> '{e.labels[0]}')::int" for e in _tri.edges)
_any = parse_pattern("(a)-[x]->(b)-[y]->(c)-[z]->(a)")
add("approx_label_cost1_v1", lambda spark, d: mislabelled(V.handoff(spark, d), _tri, ISO, 1).groupBy("cost").agg(F.count("*").alias("n")), f"select cost, count(*) as n from ({O.embeddings(_any, 'v1', select=f'{_cost} as cost')}) where cost <= 1 group by cost")
_path2 = parse_pattern("(a)-[x:purchase]->(b)-[y:click]->(c)")
_hub_sql = f"g as materialized (select edge_id, src, case when edge_id % 7 = 0 then 0 else dst end as dst, label, ts from v where src <> case when edge_id % 7 = 0 then 0 else dst end)"


def _skewed(spark: SparkSession, d: str) -> DataFrame:
    edges = stored(V.with_hub(V.handoff(spark, d)))
    over = max(1, edges.count() // 50)
    return enumerate_all(edges, _path2, HOMO, hubs=find_hubs(edges, over, 8, stored)).agg(F.count("*").alias("n"))


add("skew_hub_count_v1", _skewed, O.embeddings(_path2, "v1", False, source="g", prefix=f"with v as materialized ({O.SQL['v1']}), {_hub_sql}", select="count(*) as n"))
add("existing_t6_v3", lambda spark, d: existing(V.commerce(spark, d), P["T_6_trade"], "o"), f"select distinct v_o from ({O.embeddings(P['T_6_trade'], 'v3', False)})")
add("limited_t3_v1", lambda spark, d: enumerate_all(V.handoff(spark, d), _t3, ISO, limit=10).agg(F.count("*").alias("n")), f"select least(count(*), 10) as n from ({O.embeddings(_t3, 'v1')})")
_reply = P["reply_path"]
add("turns_path_v7", lambda spark, d: enumerate_all(V.turns(spark, d), _reply, ISO).select(*named(_reply)), O.embeddings(_reply, "v7"))
_shared = Pattern.of(QueryEdge("x", "a", "i", ("contains",), "quality = 1 and toxic = 0"), QueryEdge("y", "b", "i", ("contains",), "quality = 1 and toxic = 0"), name="shared_passage")
_passages = f"""select d.doc_id * 1048576 + b.item_id as edge_id, d.doc_id as src, {V.T} + b.item_id as dst, 'contains' as label, quality, toxic from documents d join benchmark b on contains(d.text, b.text) left join labels using (doc_id)
  where len(list_filter(regexp_split_to_array(b.text, '\\s+'), lambda x: x <> '')) > {V.PASSAGE_WORDS}"""
add(
    "attribute_rule_v8",
    lambda spark, d: enumerate_all(V.passages(spark, d), _shared, Semantics(symmetry=tuple(symmetry_breaking(_shared)))).select(*named(_shared)),
    f"with g as materialized ({_passages}) select x.src as v_a, x.dst as v_i, y.src as v_b, x.edge_id as e_x, y.edge_id as e_y from g x join g y on x.dst = y.dst and x.src < y.src where x.quality = 1 and x.toxic = 0 and y.quality = 1 and y.toxic = 0",
)

# --- baselines over streams ------------------------------------------------------------------------------------------
_exist = lambda p: compile_plan(p, profile="existence")


def _pairs_one_by_one(spark: SparkSession, d: str) -> DataFrame:
    edges, first = last_edges(spark, d, 3)
    rows = open_stream(edges, StreamConfig.insert_only(3, first)).events
    index = B.PairIndex(rows.where("snapshot_id = 0"), _exist(_tri), HOMO)
    return index.updates(rows.where("snapshot_id > 0")).select(*[f"v_{v.name}" for v in _tri.vertices], F.col("pair_multiplicity").cast("long").alias("pair_multiplicity"))


# Each update reports the pairs that it brings, weighed by what is there at that moment.
add("pair_edge_at_a_time_v1", _pairs_one_by_one, None)
add(
    "pair_states_v3",
    lambda spark, d: B.PairIndex(V.commerce(spark, d), compile_plan(P["trade2"], root="o"), ISO).states().groupBy("qedge", "state").agg(F.count("*").alias("n")),
    f"""with g as materialized ({O.SQL['v3']}), o as (select dst as o from g where {_P} intersect select src from g where {_H} intersect select src from g where {_F})
      select {_kind} as qedge, 2 as state, count(*) as n from (select distinct src, dst, label from g where {_P} and dst in (from o) or ({_H} or {_F}) and src in (from o)) group by all""",
)


def _static(spark: SparkSession, d: str) -> DataFrame:
    edges = stored(V.access(spark, d))
    first = edges.agg(F.min("ts")).first()[0] or 0
    times = [first + k * DAY for k in range(1, 6)]
    return B.static_snapshots(edges, compile_plan(_sr), ISO, times, DAY).select("snapshot_id", *named(_sr))


_all_in = " and ".join(f"{e.name}.ts > now - {DAY} and {e.name}.ts <= now" for e in _sr.edges)
add(
    "static_snapshots_v2",
    _static,
    f"with e as ({O.embeddings(_sr, 'v2', True, (), DAY, select=O.columns(_sr) + f', greatest({_sr_ts}) as last_ts, least({_sr_ts}) as first_ts')}), t as (select range - 1 as snapshot_id, (select min(epoch_us(ts)) from events) + range * {DAY} as now from range(1, 6)) select snapshot_id, e.* exclude (last_ts, first_ts) from e join t on first_ts > now - {DAY} and last_ts <= now",
)
_timed = _t3.timed(1, 2, 3)


def _match_store(spark: SparkSession, d: str) -> DataFrame:
    edges = stored(V.handoff(spark, d).withColumn("snapshot_id", F.floor(F.col("ts") / (6 * DAY))))
    store, parts = B.MatchStore(_timed, DAY), []
    for r in edges.select("snapshot_id").distinct().orderBy("snapshot_id").collect():  # a row per batch
        parts.append(store.update(edges.where(F.col("snapshot_id") == r.snapshot_id)).withColumn("snapshot_id", F.lit(r.snapshot_id)))
    out = parts[0] if parts else store.update(edges).withColumn("snapshot_id", F.lit(0).cast("long"))
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.select("snapshot_id", *named(_timed))


add("match_store_stream_v1", _match_store, O.embeddings(_timed, "v1", True, temporal_pairs(_timed), DAY, select=f"{O.columns(_timed)}, z.ts // {6 * DAY} as snapshot_id"))

# --- relations on windows --------------------------------------------------------------------------------------------
_win = StreamConfig.sliding(4 * DAY, 2 * DAY)
_rel = f"""with v as materialized ({O.SQL['v2']}), g as materialized (select *, unnest(range(ceil(ts / {2 * DAY}.0)::bigint, ceil((ts + {4 * DAY}) / {2 * DAY}.0)::bigint)) as k from v),
  e as (select k, src as x, dst as r from g where label = 'error'), c as (select k, src as y, dst as q from g where label = 'click'),
  p as materialized (select distinct k, src as y, dst as r from g where label = 'purchase' and (k, dst) in (select k, r from e) and (k, src) in (select k, y from c)),
  rel as materialized (select distinct k as snapshot_id, 'r' as qvertex, r as vid from p union all select distinct k, 'y', y from p union all select distinct k, 'x', x from e where (k, r) in (select k, r from p) union all select distinct k, 'q', q from c where (k, y) in (select k, y from p))"""
add("dual_windows_v2", lambda spark, d: dual_simulation_windows(V.access(spark, d), _sr, _win, keep=stored), f"{_rel} select * from rel")
add(
    "dual_window_changes_v2",
    lambda spark, d: relation_changes(dual_simulation_windows(V.access(spark, d), _sr, _win, keep=stored)),
    f"""{_rel} select snapshot_id, qvertex, vid, 1 as sign from rel where (snapshot_id - 1, qvertex, vid) not in (select snapshot_id, qvertex, vid from rel)
      union all select snapshot_id + 1, qvertex, vid, -1 from rel where (snapshot_id + 1, qvertex, vid) not in (select snapshot_id, qvertex, vid from rel)""",
)


def _strong_window(spark: SparkSession, d: str) -> DataFrame:
    edges = stored(V.access(spark, d))
    end = edges.agg(F.max("ts")).first()[0] or 0
    return strong_simulation(edges.where(F.col("ts") > end - DAY), _sr, keep=stored)


add("strong_window_v2", _strong_window)


# --- measures --------------------------------------------------------------------------------------------------------
_slide = StreamConfig.sliding(DAY, 10 * MINUTE)


def _growth(spark: SparkSession, d: str) -> DataFrame:
    edges = stored(V.access(spark, d))
    low = edges.agg(F.min("ts")).first()[0] or 0
    first = -(-(low + DAY) // (10 * MINUTE))
    rows = [M.placeholder_growth(M.placeholders(M.edge_events(edges, _slide), reclaim), first).withColumn("reclaim", F.lit(reclaim)) for reclaim in (True, False)]
    return rows[0].unionByName(rows[1]).select("reclaim", "slots_start", "slots_end", "growth_pct")


def _growth_sql(reclaim: bool) -> str:
    value = "max(before + i)" if reclaim else "sum(i)"
    return f"""select {str(reclaim).lower()} as reclaim, a as slots_start, b as slots_end, round(100.0::double * (b - a) / a, 1) as growth_pct from (select max(slots) filter (s <= first) as a, max(slots) filter (s <= first + 90) as b from
      (select s, sum(sum(more)) over (order by s) as slots from (select src, s, w - coalesce(lag(w) over (partition by src order by s), 0) as more from (select src, s, {value} over (partition by src order by s) as w from b)) group by s),
      (select ceil((min(ts) + {DAY}) / {10 * MINUTE}.0)::bigint as first from v))"""


add(
    "placeholder_growth_v2",
    _growth,
    f"""with v as materialized ({O.SQL['v2']}), ev as (select src, ceil(ts / {10 * MINUTE}.0)::bigint as s, 1 as i, 0 as x from v union all select src, ceil((ts + {DAY}) / {10 * MINUTE}.0)::bigint, 0, 1 from v),
      t as (select src, s, sum(i) as i, sum(x) as x from ev group by all), b as materialized (select *, coalesce(sum(i - x) over (partition by src order by s rows between unbounded preceding and 1 preceding), 0) as before from t)
      {_growth_sql(True)} union all {_growth_sql(False)}""",
)
add(
    "slot_ids_v2",
    lambda spark, d: G.slot_ids(V.access(spark, d), _slide).groupBy("src").agg(F.count("*").alias("edges"), F.count_distinct("slot").alias("slots"), F.max("slot").alias("highest")),
    f"""with v as materialized ({O.SQL['v2']}), ev as (select src, ceil(ts / {10 * MINUTE}.0)::bigint as s, 1 as i, 0 as x from v union all select src, ceil((ts + {DAY}) / {10 * MINUTE}.0)::bigint, 0, 1 from v),
      t as (select src, s, sum(i) as i, sum(x) as x from ev group by all), b as (select *, coalesce(sum(i - x) over (partition by src order by s rows between unbounded preceding and 1 preceding), 0) as before from t)
      select src, sum(i)::bigint as edges, max(before + i)::bigint as slots, max(before + i)::bigint as highest from b group by src""",
)
_star = compile_plan(P["star2"], root="a", profile="none")
add(
    "traversals_up_v1",
    lambda spark, d: M.bottom_up_traversals(local_masks(V.handoff(spark, d), P["star2"]), _star, F.floor(F.col("edge_id") / 1000).cast("bigint")).select("batch", "visited"),
    f"""with g as materialized (select *, edge_id // 1000 as b from ({O.SQL['v1']}) where label in ('purchase', 'click')), seeds as (select distinct b, dst from g)
      select s.b as batch, count(*) as visited from seeds s join g on g.dst = s.dst and g.b <= s.b group by s.b""",
)
_KINDS = ("bitmap", "pair_state", "query_centric", "match_matrix", "node_list")


def _space(spark: SparkSession, d: str) -> DataFrame:
    from flowmatch.operators.index import vertex_table

    edges = V.handoff(spark, d)
    e, v = edges.count(), vertex_table(edges).count()
    return spark.createDataFrame([(k, M.index_space(k, e, v, 4, 3)) for k in _KINDS], "design string, entries long")


add("index_space_v1", _space, f"with g as ({O.SQL['v1']}), n as (select (select count(*) from g) as e, (select count(*) from (select src from g union select dst from g)) as v) select unnest(['bitmap', 'pair_state', 'query_centric', 'match_matrix', 'node_list']) as design, unnest([e * 3 + v, e * 3 + v, e * 3, v * 4, e * 4]) as entries from n")


def _tiered(spark: SparkSession, d: str) -> DataFrame:
    edges = stored(V.access(spark, d))
    end = (edges.agg(F.min("ts")).first()[0] or 0) + 5 * DAY
    store = TieredStore(spark, fresh_path(spark, "cold"), DAY)
    hot = store.flush(edges.where(F.col("ts") <= end), end)
    return enumerate_all(store.window(hot, end - 3 * DAY, end), _sr, Semantics(within=DAY)).select(*named(_sr))


add("tiered_window_v2", _tiered, f"select e.* exclude (last_ts, first_ts) from ({O.embeddings(_sr, 'v2', True, (), DAY, select=O.columns(_sr) + f', greatest({_sr_ts}) as last_ts, least({_sr_ts}) as first_ts')}) e, (select min(epoch_us(ts)) + {5 * DAY} as until from events) where last_ts <= until and first_ts > until - {3 * DAY}")
add(
    "late_rows_v1",
    lambda spark, d: late_rows(V.handoff(spark, d).withColumn("batch", F.col("edge_id") * 7919 % 10), 6 * HOUR).select("edge_id", "batch", "behind"),
    f"""with g as materialized (select *, edge_id * 7919 % 10 as batch from ({O.SQL['v1']})), t as (select batch, max(max(ts)) over (order by batch rows between unbounded preceding and 1 preceding) as bound from g group by batch)
      select edge_id, batch, bound - ts as behind from g join t using (batch) where bound - ts > {6 * HOUR}""",
)


def _false_candidates(spark: SparkSession, d: str) -> DataFrame:
    """Live edges that are in no embedding, per query edge."""
    p = P["T_6_trade"]
    edges = stored(local_masks(V.commerce(spark, d), p).where("local_mask <> 0"))
    index = build_index(edges, compile_plan(p, root="o"), keep=stored)
    of = index.candidates(stored)
    rows = stored(enumerate_all(edges, p, ISO, index.plan, of=of))
    parts = [of[e.name].join(rows.select(F.col(f"e_{e.name}").alias("edge_id")).distinct(), "edge_id", "left_anti").agg(F.count("*").alias("false_candidates")).select(F.lit(e.name).alias("qedge"), "false_candidates") for e in p.edges]
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return out


def _update_cost(spark: SparkSession, d: str) -> DataFrame:
    """Entries to touch when one part is no candidate any more: in the bitmap, and in the lists of a query-centric store."""
    p, edges = P["trade2"], stored(V.commerce(spark, d))
    plan = compile_plan(p, root="o")
    vertex = edges.where("label = 'HAS_RF'").agg(F.min("dst")).first()[0]
    index = build_index(stored(local_masks(edges, p).where("local_mask <> 0")), plan, keep=stored)
    return spark.createDataFrame([M.update_cost(index, B.candidate_store(edges, plan), vertex)], "bitmap long, lists long")


add("update_cost_v3", _update_cost, f"with g as materialized ({O.SQL['v3']}), v as (select min(dst) as v from g where label = 'HAS_RF') select count(*) as bitmap, count(distinct src) as lists from g, v where label = 'HAS_RF' and dst = v")
# The index of a tree is the full reducer, so only embeddings that are no isomorphism leave false candidates.
_e6 = P["T_6_trade"].edges
add("false_candidates_t6_v3", _false_candidates, f"with h as materialized ({O.embeddings(P['T_6_trade'], 'v3', False)}), i as materialized ({O.embeddings(P['T_6_trade'], 'v3')}) " + " union all ".join(f"select '{e.name}' as qedge, count(*) as false_candidates from (select e_{e.name} from h except select e_{e.name} from i)" for e in _e6))
