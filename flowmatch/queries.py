"""The graph engine's queries, each with the SQL that states its result where SQL can."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from flowmatch import metrics as M, oracle as O
from flowmatch.functions.rules import local_masks
from flowmatch.operators import baselines as B, index as ix
from flowmatch.operators.counting import count_embeddings, count_lost_context
from flowmatch.operators.enumeration import Semantics, alternatives, delta, enumerate_all, homomorphism, isomorphism, live_delta, newest, temporal
from flowmatch.operators.semantics import dual_simulation, parallel_collapsed, strong_simulation
from flowmatch.plans.pattern import Pattern, symmetry_breaking
from flowmatch.plans.planner import compile_plan, degree_requirements, temporal_pairs
from flowmatch.registry import FOUND, Query, add
from flowmatch.sources import views as V
from flowmatch.sources.snapshots import DAY, MINUTE, StreamConfig, counts_by_snapshot, insert_delete_events, sliding_deltas
from flowmatch.sources.storage import stored
from flowmatch.workloads import PATTERNS as P

BATCH = 1000  # events in a batch of the whole history, as the oracle's arithmetic has it


def pattern(name: str, key: str, v: str, semantics: Semantics, **sql) -> None:
    p = P[key]
    add(name, lambda spark, d: _named(enumerate_all(V.VIEWS[v](spark, d), p, semantics), p), O.embeddings(p, v, semantics.injective, semantics.pairs, semantics.within, semantics.symmetry, **sql))


def _named(rows: DataFrame, p: Pattern) -> DataFrame:
    return rows.select(*[f"v_{x.name}" for x in p.vertices], *[f"e_{e.name}" for e in p.edges])


def counted(name: str, key: str, v: str, semantics: Semantics) -> None:
    p = P[key]
    add(name, lambda spark, d: enumerate_all(V.VIEWS[v](spark, d), p, semantics).agg(F.count("*").alias("n")), O.embeddings(p, v, semantics.injective, semantics.pairs, semantics.within, select="count(*) as n"))


# --- static, by semantics --------------------------------------------------------------------------------------------
ISO, HOMO = isomorphism(), homomorphism()
for _name, _key, _v in (("iso_t3_v1", "t3_path", "v1"), ("iso_t6_v3", "t6_trade", "v3"), ("iso_t6_prefix_v3", "t6_prefix", "v3"), ("iso_g4_v3", "g4_nation", "v3"), ("iso_rect_v4", "rect_flow", "v4"), ("iso_trade2_v3", "trade2", "v3")):
    pattern(_name, _key, _v, ISO)
for _name, _key in (("homo_triangle_v1", "triangle"), ("homo_clique4_v1", "clique4"), ("homo_rectangle_v1", "rectangle"), ("homo_dual_triangle_v1", "dual_triangle")):
    pattern(_name, _key, "v1", HOMO)
# The fifth vertex joins the four-cliques edge by edge: written out, as a join reorderer picks the wildcards first.
add(
    "homo_clique5_count_v1",
    lambda spark, d: enumerate_all(V.VIEWS["v1"](spark, d), P["clique5"], HOMO).agg(F.count("*").alias("n")),
    f"""with k4 as materialized ({O.embeddings(P['clique4'], 'v1', False)}), g5 as materialized ({O.SQL['v1']}), a5 as materialized (select v_b, v_c, v_d, dst as v_e from k4 join g5 on src = v_a),
      b5 as materialized (select v_c, v_d, v_e from a5 join g5 on src = v_b and dst = v_e), c5 as materialized (select v_d, v_e from b5 join g5 on src = v_c and dst = v_e) select count(*) as n from c5 join g5 on src = v_d and dst = v_e""",
)
counted("homo_clique5_labelled_count_v1", "clique5_labelled", "v1", HOMO)
counted("iso_t3_star_count_v1", "t3_star", "v1", ISO)
counted("homo_t3_count_v1", "t3_path", "v1", HOMO)
counted("homo_wild_triangle_count_v1", "triangle_any", "v1", HOMO)
add("iso_rect_count_v2", lambda spark, d: count_embeddings(V.access(spark, d), P["two_users"], ISO), O.embeddings(P["two_users"], "v2", True, select="count(*) as n"))
pattern("wildcard_t2_v1", "t2_wild", "v1", ISO)
pattern("symmetry_triangle_v1", "triangle_same", "v1", Semantics(symmetry=tuple(symmetry_breaking(P["triangle_same"]))))
pattern("triangle_nn_v5", "triangle_nn", "v5", Semantics(symmetry=tuple(symmetry_breaking(P["triangle_nn"]))))
_und = "with g as materialized (" + O.SQL["v1"] + "), u as (select edge_id, src, dst, label, ts from g union all select edge_id, dst, src, label, ts from g) "
_x, _y = P["t2_undirected"].edges
add(
    "undirected_t2_v1",
    lambda spark, d: _named(enumerate_all(V.handoff(spark, d), P["t2_undirected"], ISO), P["t2_undirected"]),
    _und + "select x.src as v_a, x.dst as v_b, y.dst as v_c, x.edge_id as e_x, y.edge_id as e_y from u x, g y where x.dst = y.src and x.label = 'purchase' and y.label = 'signup' and x.src <> x.dst and x.src <> y.dst and y.src <> y.dst",
)
add(
    "approx_missing1_v1",
    lambda spark, d: alternatives(V.handoff(spark, d), P["rect_missing"], ISO, 1).select("v_a", "v_b", "v_c", "e_x", "e_y", "e_z", "e_w", "missing"),
    "with g as materialized (" + O.SQL["v1"] + """) select * from (select x.src as v_a, x.dst as v_b, y.dst as v_c, x.edge_id as e_x, y.edge_id as e_y, z.edge_id as e_z, w.edge_id as e_w,
      (z.edge_id is null)::int + (w.edge_id is null)::int as missing from g x join g y on x.dst = y.src and x.label = 'purchase' and y.label = 'click' and x.src <> y.dst and x.src <> x.dst and y.src <> y.dst
      left join g z on z.label = 'view' and z.src = y.dst and z.dst = x.src left join g w on w.label = 'error' and w.src = x.src and w.dst = y.dst) where missing <= 1""",
)

# --- time and windows ------------------------------------------------------------------------------------------------
_timed = P["t3_path"].timed(1, 2, 3)
pattern("timed_t3_v1", "t3_path", "v1", temporal(_timed, DAY))
counted("timed_t3_unbounded_count_v1", "t3_path", "v1", temporal(_timed))
pattern("window_t3_v2", "shared_resource", "v2", Semantics(within=DAY))
pattern("stale_context_v2", "shared_resource", "v2", temporal(P["shared_resource"].timed(1, 2, 3), DAY))
_slide = StreamConfig.sliding(DAY, 10 * MINUTE)
_sr = P["shared_resource"]


def _deltas_sql(stride: int, window: int, tail: str) -> str:
    ts = ", ".join(f"{e.name}.ts" for e in _sr.edges)
    inner = O.embeddings(_sr, "v2", True, (), window, select=O.columns(_sr) + f", greatest({ts}) as last_ts, least({ts}) as first_ts")
    return f"""with e as ({inner}), life as (select *, ceil(last_ts / {stride}.0)::bigint as born, ceil((first_ts + {window}) / {stride}.0)::bigint as dies from e),
      d as (select born as snapshot_id, 1 as sign, * exclude (born, dies, last_ts, first_ts) from life where born < dies union all select dies, -1, * exclude (born, dies, last_ts, first_ts) from life where born < dies) {tail}"""


add("window_delta_24h_10m_v2", lambda spark, d: sliding_deltas(V.access(spark, d), _sr, _slide).select("snapshot_id", "sign", *[f"v_{x.name}" for x in _sr.vertices], *[f"e_{e.name}" for e in _sr.edges]), _deltas_sql(10 * MINUTE, DAY, "select * from d"))
add(
    "window_alive_24h_15m_v2",
    lambda spark, d: counts_by_snapshot(sliding_deltas(V.access(spark, d), _sr, StreamConfig.sliding(DAY, 15 * MINUTE))),
    _deltas_sql(15 * MINUTE, DAY, ", s as (select snapshot_id, count(*) filter (sign > 0) as gained, count(*) filter (sign < 0) as lost from d group by all) select *, (sum(gained - lost) over (order by snapshot_id))::bigint as alive from s"),
)
add(
    "tumbling_day_t3_v2",
    lambda spark, d: enumerate_all(V.access(spark, d), _sr, Semantics(within=DAY)).select(*[F.floor(F.col(f"t_{e.name}") / DAY).alias(f"d_{e.name}") for e in _sr.edges]).where("d_e = d_p and d_p = d_c").groupBy(F.col("d_e").alias("day")).agg(F.count("*").alias("n")),
    O.embeddings(_sr, "v2", select="e.ts // 86400000000 as day, count(*) as n", extra=" and e.ts // 86400000000 = p.ts // 86400000000 and p.ts // 86400000000 = c.ts // 86400000000 group by all"),
)

# --- increments ------------------------------------------------------------------------------------------------------
_b = lambda c="edge_id": F.floor(F.col(c) / BATCH).cast("bigint")


def _born_sql(p: Pattern, injective: bool, select: str | None = None, tail: str = "") -> str:
    born = "greatest(" + ", ".join(f"{e.name}.edge_id" for e in p.edges) + f") // {BATCH}"
    return O.embeddings(p, "v1", injective, select=(select or O.columns(p)) + f", {born} as snapshot_id", extra=tail)


add("delta_pos_triangle_v1", lambda spark, d: newest(V.handoff(spark, d), P["triangle"], HOMO, _b()).select("v_a", "v_b", "v_c", "e_x", "e_y", "e_z", "snapshot_id"), _born_sql(P["triangle"], False))
add("delta_pos_t3_count_v1", lambda spark, d: newest(V.handoff(spark, d), P["t3_path"], ISO, _b()).groupBy("snapshot_id").agg(F.count("*").alias("n")), _born_sql(P["t3_path"], True, "count(*) as n", " group by snapshot_id"))


def _fresh(spark: SparkSession, d: str):
    """Whether an edge lies in the last tenth of the stream."""
    top = V.read(spark, d, "events").agg(F.max("event_id")).first()[0]
    return F.col("edge_id") >= int((top or 0) * 0.9)


def _last_batch(spark: SparkSession, d: str, key: str, semantics: Semantics, **options) -> DataFrame:
    """The delta of the last tenth of the stream, from chains with masks."""
    e = V.handoff(spark, d)
    p = P[key]
    return _named(delta(e, _fresh(spark, d), compile_plan(p, profile=semantics.profile), semantics, **options), p)


def _last_sql(key: str, injective: bool, **options) -> str:
    p = P[key]
    cut = "(select floor(max(event_id) * 0.9::double)::bigint from events)"
    return O.embeddings(p, "v1", injective, extra=" and (" + " or ".join(f"{e.name}.edge_id >= {cut}" for e in p.edges) + ")", **options)


for _o in ("earlier_old", "later_old"):
    add(f"mask_{_o}_v1", lambda spark, d, o=_o: _last_batch(spark, d, "rectangle", HOMO, orientation=o), _last_sql("rectangle", False))
add("dedup_distinct_v1", lambda spark, d: _last_batch(spark, d, "rectangle", HOMO, dedup="distinct"), _last_sql("rectangle", False))
add("delta_t3_count_v1", lambda spark, d: _last_batch(spark, d, "t3_path", ISO).agg(F.count("*").alias("n")), _last_sql("t3_path", True, select="count(*) as n"))


def _avoided(spark: SparkSession, d: str) -> DataFrame:
    return M.duplicates(V.handoff(spark, d), _fresh(spark, d), compile_plan(P["triangle"], profile="existence"), HOMO)


_cut = "(select floor(max(event_id) * 0.9::double)::bigint from events)"
_n_new = " + ".join(f"({e.name}.edge_id >= {_cut})::int" for e in P["triangle"].edges)
add("duplicates_avoided_v1", _avoided, O.embeddings(P["triangle"], "v1", False, select=f"coalesce(sum({_n_new}), 0)::bigint as unmasked, count(*) as masked, (coalesce(sum({_n_new}), 0) - count(*))::bigint as avoided", extra=f" and {_n_new} > 0"))


def _tail(spark: SparkSession, d: str, key: str) -> DataFrame:
    """Insert and delete stream on the commerce view in one batch: what it gains and loses, net."""
    p = P[key]
    plan = compile_plan(p)
    ev = stored(local_masks(insert_delete_events(V.commerce(spark, d)), p).where("local_mask <> 0"), "candidates")
    gone = ev.where("op < 0").select("edge_id", F.lit(True).alias("dies"))
    graph = stored(ev.where("op >= 0").join(gone, "edge_id", "left").withColumn("dies", F.coalesce("dies", F.lit(False))), "graph")
    gained = _named(live_delta(graph.where(~F.col("dies")), F.col("op") > 0, plan, ISO), p).withColumn("sign", F.lit(1))
    lost = _named(live_delta(graph.where("op = 0"), F.col("dies"), plan, ISO), p).withColumn("sign", F.lit(-1))
    return gained.unionByName(lost)


_STREAM = f"""with all_edges as materialized ({O.SQL['v3']}), numbered as materialized (select *, row_number() over (order by ts, edge_id) as seq, count(*) over () as n from all_edges),
 cut as (select floor(max(n) * 0.9::double)::bigint as p from numbered), gone as (select (seq * 7919) % (select p from cut) + 1 as victim from numbered where seq > (select p from cut) and seq % 10 = 0),
 g0 as materialized (select * from numbered where seq <= (select p from cut)),
 g1 as materialized (select * from numbered where seq <= (select p from cut) and seq not in (select victim from gone) or seq > (select p from cut) and seq % 10 <> 0) """


def _tail_sql(key: str) -> str:
    p = P[key]
    s0, s1 = (O.embeddings(p, "v3", source=s) for s in ("g0", "g1"))
    return f"{_STREAM}, s0 as ({s0}), s1 as ({s1}) select *, 1 as sign from (select * from s1 except select * from s0) union all select *, -1 as sign from (select * from s0 except select * from s1)"


add("delta_pos_neg_t6_v3", lambda spark, d: _tail(spark, d, "t6_trade"), _tail_sql("t6_trade"))
add("delta_pos_neg_t6_prefix_v3", lambda spark, d: _tail(spark, d, "t6_prefix"), _tail_sql("t6_prefix"))


def _fold(spark: SparkSession, d: str) -> DataFrame:
    from flowmatch.operators.enumeration import apply_delta

    ev = stored(insert_delete_events(V.commerce(spark, d)).where("op = 0"), "before")
    before = _named(enumerate_all(ev.where("op = 0"), P["t6_trade"], ISO), P["t6_trade"])
    change = _tail(spark, d, "t6_trade")
    return apply_delta(before, change.where("sign > 0"), change.where("sign < 0"))


add("fold_equals_static_v3", _fold, O.embeddings(P["t6_trade"], "v3", source="g1", prefix=_STREAM))

# --- index -----------------------------------------------------------------------------------------------------------
add("local_mask_counts_v1", lambda spark, d: local_masks(V.handoff(spark, d), P["t3_path"]).groupBy("local_mask").agg(F.count("*").alias("n")), f"select (case label when 'purchase' then 1 when 'click' then 2 when 'view' then 4 else 0 end)::bigint as local_mask, count(*) as n from ({O.SQL['v1']}) group by all")


def _index(spark: SparkSession, d: str, key: str = "trade2", v: str = "v3", root: str | None = "o", **options) -> ix.Index:
    p = P[key]
    edges = stored(local_masks(V.VIEWS[v](spark, d), p).where("local_mask <> 0"), "edges")
    return ix.build_index(edges, compile_plan(p, root=root), keep=stored, **options)


_PA, _HA, _FA = ("g.label = 'PLACED_1-URGENT_F'", "g.label = 'HAS_RF'", "g.label = 'FROM_AF'")
_FULL = f"with g as materialized ({O.SQL['v3']}), o as (select dst as o from g where {_PA} intersect select src from g where {_HA} intersect select src from g where {_FA})"
add("root_set_v3", lambda spark, d: _index(spark, d).roots(), f"{_FULL} select o as vid from o")
_kind = "case when label like 'PLACED%' then 'p' when label like 'HAS%' then 'h' else 'f' end as qedge"
add(
    "live_bits_v3",
    lambda spark, d: M.index_quality(_index(spark, d)).select("qedge", "local", "live"),
    f"{_FULL} select {_kind}, count(*) as local, count(*) filter (case when label like 'PLACED%' then dst in (select o from o) else src in (select o from o) end) as live from g where {_PA} or {_HA} or {_FA} group by all",
)
add("top_down_v3", lambda spark, d: _index(spark, d, root="c").vertices.where(F.getbit("top", F.lit(1)) == 1).select("vid"), f"{_FULL} select o as vid from o")
add("bottom_up_v3", lambda spark, d: _index(spark, d, root="c").roots(), f"{_FULL} select distinct src as vid from g where {_PA} and dst in (select o from o)")
_t6 = {"p": ("PLACED_1-URGENT_F", "dst", "src"), "h": ("HAS_RF", "src", "dst"), "f": ("FROM_AF", "src", "dst"), "b": ("BASED", "src", "dst"), "r": ("IN_REGION", "src", "dst"), "l": ("LIVES_BUILDING", "src", "dst")}
add(
    "candidates_per_edge_v3",
    lambda spark, d: M.index_quality(_index(spark, d, "t6_trade", root="o")).select("qedge", "local", "live"),
    # Parent and child of each query edge in the tree from o; the full reducer of that tree, from the leaves up and from the root down.
    f"with g as materialized ({O.SQL['v3']}), "
    + ", ".join(f"{q} as materialized (select edge_id, {a} as pa, {b} as ch from g where label = '{x}')" for q, (x, a, b) in _t6.items())
    + """, s as (select pa as v from b where ch in (select pa from r)), c as (select pa as v from l),
      o as materialized (select pa as v from p where ch in (from c) intersect select pa from h intersect select pa from f where ch in (from s)),
      p1 as materialized (select * from p where pa in (from o) and ch in (from c)), h1 as (select * from h where pa in (from o)), f1 as materialized (select * from f where pa in (from o) and ch in (from s)),
      b1 as materialized (select * from b where pa in (select ch from f1) and ch in (select pa from r)), r1 as (select * from r where pa in (select ch from b1)), l1 as (select * from l where pa in (select ch from p1)) """
    + " union all ".join(f"select '{q}' as qedge, (select count(*) from {q}) as local, (select count(*) from {q}1) as live" for q in _t6),
)
add("indexed_t6_v3", lambda spark, d: _named(enumerate_all(V.commerce(spark, d), P["t6_trade"], ISO, (i := _index(spark, d, "t6_trade", root="o")).plan, of=i.candidates(stored)), P["t6_trade"]), O.embeddings(P["t6_trade"], "v3"))


def _degrees(spark: SparkSession, d: str) -> DataFrame:
    plan = compile_plan(P["t3_star"], root="a")
    return ix.degree_masks(local_masks(V.handoff(spark, d), P["t3_star"]), plan).where(F.getbit("deg", F.lit(0)) == 1).select("vid")


add("degree_filter_v1", _degrees, f"""with g as materialized ({O.SQL['v1']}) select src as vid from g group by src having count(*) filter (label = 'purchase') >= 1 and count(*) filter (label = 'signup') >= 1 and count(*) filter (label = 'error') >= 1
  and count(distinct dst) filter (label in ('purchase', 'signup', 'error')) >= 3""")
add(
    "neighbour_filter_v3",
    lambda spark, d: ix.degree_masks(local_masks(V.commerce(spark, d), P["trade2"]), compile_plan(P["trade2"], root="o")).where(F.getbit("deg", F.lit(1)) == 1).select("vid"),
    f"{_FULL} select o as vid from o",
)
add(
    "index_bits_v1",
    lambda spark, d: V.handoff(spark, d).agg(F.count("*").alias("edges")).crossJoin(ix.vertex_table(V.handoff(spark, d)).agg(F.count("*").alias("vertices"))).withColumn("bits", ix.index_bits(F.col("edges"), F.col("vertices"), len(P["t3_path"].vertices))),
    f"with g as materialized ({O.SQL['v1']}) select (select count(*) from g) as edges, (select count(*) from (select src from g union select dst from g)) as vertices, (select count(*) from g) * 3 + (select count(*) from (select src from g union select dst from g)) as bits",
)

# --- relations -------------------------------------------------------------------------------------------------------
add(
    "dual_sim_tree_v3",
    lambda spark, d: dual_simulation(V.commerce(spark, d), P["trade2"], keep=stored),
    f"""{_FULL} select 'o' as qvertex, o as vid from o union all select distinct 'c', src from g where {_PA} and dst in (select o from o)
      union all select distinct 'a', dst from g where {_HA} and src in (select o from o) union all select distinct 's', dst from g where {_FA} and src in (select o from o)""",
)
_rounds = "".join(
    f""", a{k} as materialized (select vid from a{k - 1} where vid in (select src from g where label = 'purchase' and dst in (from b{k - 1})) and vid in (select dst from g where label = 'view' and src in (from c{k - 1}))),
      b{k} as materialized (select vid from b{k - 1} where vid in (select src from g where label = 'click' and dst in (from c{k - 1})) and vid in (select dst from g where label = 'purchase' and src in (from a{k - 1}))),
      c{k} as materialized (select vid from c{k - 1} where vid in (select src from g where label = 'view' and dst in (from a{k - 1})) and vid in (select dst from g where label = 'click' and src in (from b{k - 1})))"""
    for k in range(1, 9)
)
add(
    "dual_sim_triangle_v1",
    lambda spark, d: dual_simulation(V.handoff(spark, d), P["triangle"], keep=stored),
    f"with g as materialized ({O.SQL['v1']}), a0 as (select src as vid from g union select dst from g), b0 as (from a0), c0 as (from a0) {_rounds} select 'a' as qvertex, vid from a8 union all select 'b', vid from b8 union all select 'c', vid from c8",
)
add("strong_sim_v3", lambda spark, d: strong_simulation(V.commerce(spark, d), P["trade2"], keep=stored), None)

# --- baselines -------------------------------------------------------------------------------------------------------
add("brute_t3_count_v1", lambda spark, d: B.brute_force(V.handoff(spark, d), P["t3_path"], ISO).agg(F.count("*").alias("n")), O.embeddings(P["t3_path"], "v1", select="count(*) as n"))
for _k in ("triangle", "rectangle", "clique4", "dual_triangle"):
    add(f"wco_{_k}_v1", lambda spark, d, k=_k: _named(B.delta_wco(V.handoff(spark, d), P[k]), P[k]), O.embeddings(P[_k], "v1", False))


def _wco_delta(spark: SparkSession, d: str) -> DataFrame:
    return _named(B.delta_wco(V.handoff(spark, d), P["triangle"], _fresh(spark, d)), P["triangle"])


add("wco_delta_triangle_v1", _wco_delta, _last_sql("triangle", False))
add("static_recompute_v2", lambda spark, d: _named(B.static_recompute(V.access(spark, d), compile_plan(_sr), Semantics(within=DAY)), _sr), O.embeddings(_sr, "v2", True, (), DAY))
add("candidate_list_t6_v3", lambda spark, d: _named(B.enumerate_from_list(V.commerce(spark, d), compile_plan(P["t6_trade"]), ISO), P["t6_trade"]), O.embeddings(P["t6_trade"], "v3"))
add("match_matrix_v3", lambda spark, d: B.match_matrix(V.commerce(spark, d), compile_plan(P["trade2"])), f"""{_FULL}, m as (select o as vid, 'o' as q from o union select src, 'c' from g where {_PA} union select dst, 'a' from g where {_HA} union select dst, 's' from g where {_FA})
  select vid, bool_or(q = 'c') as is_c, bool_or(q = 'o') as is_o, bool_or(q = 'a') as is_a, bool_or(q = 's') as is_s from m group by vid""")


def _pair_sql(key: str, injective: bool = False, fresh: str = "edge_id >= " + _cut) -> str:
    p = P[key]
    prefix = f"with g as materialized ({O.SQL['v1']}), p as materialized (select src, dst, label, min(ts) as ts, min(edge_id) as edge_id, count(*) as m, min({fresh}) as fresh from g group by all)"
    at = O.columns(p).split(", ")[: len(p.vertices)]
    return O.embeddings(p, "v1", injective, source="p", prefix=prefix, select=", ".join(at) + ", (" + " * ".join(f"{e.name}.m" for e in p.edges) + ")::bigint as pair_multiplicity", extra=" and (" + " or ".join(f"{e.name}.fresh" for e in p.edges) + ")")


for _k in ("triangle", "rectangle", "clique4", "dual_triangle"):
    add(
        f"pair_state_{_k}_v1",
        lambda spark, d, k=_k: B.pair_state(V.handoff(spark, d), compile_plan(P[k], profile="existence"), _fresh(spark, d), HOMO).select(*[f"v_{v.name}" for v in P[k].vertices], F.col("pair_multiplicity").cast("long").alias("pair_multiplicity")),
        _pair_sql(_k),
    )
add(
    "context_false_positive_v2",
    lambda spark, d: count_lost_context(V.access(spark, d), parallel_collapsed(V.access(spark, d)), _sr, DAY),
    "with a as (" + O.embeddings(_sr, "v2", select="e.src as x, e.dst as r, p.src as y, c.dst as q") + "), t as (" + O.embeddings(_sr, "v2", True, (("e", "p"), ("p", "c")), DAY, select="e.src as x, e.dst as r, p.src as y, c.dst as q") + ") select count(*) as n from (select distinct * from a except select * from t)",
)

# --- measures --------------------------------------------------------------------------------------------------------
_ev = f"select src, ceil(ts / {10 * MINUTE}.0)::bigint as s, 1 as i, 0 as x from v union all select src, ceil((ts + {DAY}) / {10 * MINUTE}.0)::bigint, 0, 1 from v"


def _slots(spark: SparkSession, d: str, reclaim: bool) -> DataFrame:
    return M.placeholders(M.edge_events(V.access(spark, d), _slide), reclaim)


def _slots_3days(spark: SparkSession, d: str, reclaim: bool) -> DataFrame:
    first = V.access(spark, d).agg(F.min(_slide.born())).first()[0] or 0
    return _slots(spark, d, reclaim).where(F.col("snapshot_id") <= first + 432).agg(F.coalesce(F.max("slots"), F.lit(0)).alias("slots"))


def _slots_sql(value: str) -> str:
    return f"""with v as materialized ({O.SQL['v2']}), ev as ({_ev}), s as (select src, s, sum(i) as i, sum(x) as x from ev where s <= (select ceil(min(ts) / {10 * MINUTE}.0)::bigint + 432 from v) group by all),
      r as (select src, {value} as slots from (select *, coalesce(sum(i - x) over (partition by src order by s rows between unbounded preceding and 1 preceding), 0) as before from s) group by src) select coalesce(sum(slots), 0)::bigint as slots from r"""


def _series_sql(value: str) -> str:
    return f"""with v as materialized ({O.SQL['v2']}), ev as ({_ev}), s as (select src, s, sum(i) as i, sum(x) as x from ev group by all),
      b as (select *, coalesce(sum(i - x) over (partition by src order by s rows between unbounded preceding and 1 preceding), 0) as before from s),
      r as (select src, s, {value} over (partition by src order by s) as slots from b), g as (select s, slots - coalesce(lag(slots) over (partition by src order by s), 0) as more from r)
      select s as snapshot_id, (sum(sum(more)) over (order by s))::bigint as slots from g group by s"""


add("placeholders_reclaim_v2", lambda spark, d: _slots(spark, d, True), _series_sql("max(before + i)"))
add("placeholders_plain_v2", lambda spark, d: _slots(spark, d, False), _series_sql("sum(i)"))
add("placeholders_reclaim_3days_v2", lambda spark, d: _slots_3days(spark, d, True), _slots_sql("max(before + i)"))
add("placeholders_plain_3days_v2", lambda spark, d: _slots_3days(spark, d, False), _slots_sql("sum(i)"))
_star = compile_plan(P["star2"], root="a", profile="none")
add(
    "traversals_level1_v1",
    lambda spark, d: M.traversals(local_masks(V.handoff(spark, d), P["star2"]), _star, _b()).select("batch", "visited"),
    f"""with g as materialized (select *, edge_id // {BATCH} as b from ({O.SQL['v1']}) where label in ('purchase', 'click')), seeds as (select distinct b, src from g)
      select s.b as batch, count(*) as visited from seeds s join g on g.src = s.src and g.b <= s.b group by s.b""",
)
def _needs(spark: SparkSession, d: str) -> DataFrame:
    """What each vertex of the star needs, and how many vertices of the view have it."""
    p, keys = P["t3_star"], ["vertex", "outgoing", "edges", "neighbours", "labels"]
    needs = [(r.vertex, r.out, r.edges, r.neighbours, " ".join(p.edge(e).labels[0] for e in r.of)) for r in degree_requirements(p)]
    asked = spark.createDataFrame(needs, "vertex string, outgoing boolean, edges int, neighbours int, labels string")
    rows = V.handoff(spark, d).join(F.broadcast(asked.withColumn("label", F.explode(F.split("labels", " ")))), "label")
    rows = rows.select(*keys, F.when(F.col("outgoing"), F.col("src")).otherwise(F.col("dst")).alias("v"), F.when(F.col("outgoing"), F.col("dst")).otherwise(F.col("src")).alias("far"))
    have = rows.groupBy(*keys, "v").agg(F.count("*").alias("e"), F.count_distinct("far").alias("k")).where("e >= edges and k >= neighbours")
    return asked.join(have.groupBy(*keys).agg(F.count("*").alias("n")), keys, "left").select(*keys, F.coalesce("n", F.lit(0)).alias("n"))


add(
    "needs_t3_star",
    _needs,
    f"""with g as materialized ({O.SQL['v1']}), q as (select * from (values ('a', true, 1, 1, 'purchase'), ('a', true, 1, 1, 'signup'), ('a', true, 1, 1, 'error'), ('a', true, 3, 3, 'purchase signup error'),
      ('b', false, 1, 1, 'purchase'), ('c', false, 1, 1, 'signup'), ('d', false, 1, 1, 'error')) t(vertex, outgoing, edges, neighbours, labels)),
      h as (select q.*, case when outgoing then src else dst end as v from q join g on list_contains(string_split(labels, ' '), label) group by all having count(*) >= any_value(edges) and count(distinct case when outgoing then dst else src end) >= any_value(neighbours))
      select q.*, count(v) as n from q left join h using (vertex, outgoing, edges, neighbours, labels) group by all""",
)


from flowmatch import surface, workload_queries  # noqa: E402,F401  they register theirs


def queries() -> dict[str, Query]:
    return {name: run for name, (run, _) in FOUND.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for name, (_, sql) in FOUND.items() if sql is not None}
