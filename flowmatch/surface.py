"""The operators around the engine, one query per kind, on the graph views and the given tables."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from flowmatch import oracle as O
from flowmatch.operators import graph as G
from flowmatch.operators.enumeration import emit, enumerate_all, isomorphism, save_embeddings
from flowmatch.plans.pattern import parse_pattern
from flowmatch.registry import add
from flowmatch.sources import views as V
from flowmatch.sources.snapshots import DAY, HOUR, late_rows
from flowmatch.sources.storage import shared_dir, stored
from flowmatch.sources.triplets import read_triplets, register_source, write_triplets
from flowmatch.streaming.stars import star_batch
from flowmatch.workloads import PATTERNS as P

_G = f"with g as materialized ({O.SQL['v1']}) "
_A = f"with a as materialized ({O.SQL['v2']}) "
_C = f"with c as materialized ({O.SQL['v3']}) "


def events(spark: SparkSession, d: str) -> DataFrame:
    return V.read(spark, d, "events")


def path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"


# --- sources and sinks -----------------------------------------------------------------------------------------------
add("op_scan", lambda spark, d: events(spark, d).where((F.col("event_type") == "purchase") & (F.col("value") > 50)).select("event_id", "user_id"), "select event_id, user_id from events where event_type = 'purchase' and value > 50")


def _triplet_files(spark: SparkSession, d: str) -> DataFrame:
    where = path(spark, "triplets")
    write_triplets(V.access(spark, d), where)
    return read_triplets(spark, where)


add("op_triplet_files", _triplet_files, _A + "select src, dst, label, ts from a")


def _signed(spark: SparkSession, d: str) -> DataFrame:
    where = path(spark, "signed")
    edges = V.handoff(spark, d)
    sign = F.when(F.col("edge_id") % 10 == 0, -1).otherwise(1)
    edges.select(((F.col("src") + 1) * sign).alias("src"), ((F.col("dst") + 1) * sign).alias("dst"), "label").write.option("sep", " ").csv(where)
    register_source(spark)
    return V.decode_signed(spark.read.format("signed_triplets").load(where)).select(F.col("op").cast("int").alias("op"), "src", "dst", "label")


add("op_signed_source", _signed, _G + "select case when edge_id % 10 = 0 then -1 else 1 end as op, src, dst, label from g")


def _saved(spark: SparkSession, d: str) -> DataFrame:
    where = path(spark, "embeddings")
    save_embeddings(emit(enumerate_all(V.handoff(spark, d), P["triangle"], isomorphism()), 3, 1), where)
    return spark.read.parquet(where).where("snapshot_id = 3 and sign = 1").select("e_x", "e_y", "e_z")


add("op_save_embeddings", _saved, O.embeddings(P["triangle"], "v1", select="x.edge_id as e_x, y.edge_id as e_y, z.edge_id as e_z"))


def _bucketed(spark: SparkSession, d: str) -> DataFrame:
    """Two tables bucketed alike by vertex: their join needs no exchange."""
    names = []
    for key in ("src", "dst"):
        names.append(f"bucketed_{key}_{uuid.uuid4().hex}")
        V.handoff(spark, d).write.bucketBy(4, key).sortBy(key).option("path", path(spark, "bucketed")).saveAsTable(names[-1])
    left, right = (spark.table(n) for n in names)
    return right.join(left, right["dst"] == left["src"]).groupBy(right["dst"].alias("vid")).agg(F.count("*").alias("paths"))


add("op_bucketed_join", _bucketed, _G + "select x.dst as vid, count(*) as paths from g x join g y on x.dst = y.src group by x.dst")


def _json_files(spark: SparkSession, d: str) -> DataFrame:
    where = path(spark, "json")
    events(spark, d).select("event_id", "user_id", "event_type").write.json(where)
    return spark.read.schema("event_id long, user_id long, event_type string").json(where)


add("op_json_files", _json_files, "select event_id, user_id, event_type from events")

# --- rows ------------------------------------------------------------------------------------------------------------
add("op_project", lambda spark, d: V.access(spark, d).selectExpr("edge_id * 2 as twice", "src", "upper(label) as label").withColumnRenamed("src", "user").drop("nothing"), _A + 'select edge_id * 2 as twice, src as user, upper(label) as label from a')
add(
    "op_filter_null",
    lambda spark, d: (x := V.read(spark, d, "documents").select("doc_id").join(V.read(spark, d, "labels"), "doc_id", "left")).select("doc_id", (F.col("quality") == 1).alias("is_good"), F.col("quality").eqNullSafe(1).alias("surely"), F.col("quality").isNull().alias("unknown")).where(F.col("unknown") | (F.col("is_good") & ~F.col("doc_id").between(10, 20))),
    "select doc_id, quality = 1 as is_good, quality is not distinct from 1 as surely, quality is null as unknown from documents left join labels using (doc_id) where quality is null or (quality = 1 and not doc_id between 10 and 20)",
)
add("op_like", lambda spark, d: V.read(spark, d, "part").where(F.col("p_type").isin("ECONOMY", "PROMO") | F.col("p_name").like("%a%") & F.col("p_brand").rlike("#[12]")).select("p_partkey"), "select p_partkey from part where p_type in ('ECONOMY', 'PROMO') or p_name like '%a%' and regexp_matches(p_brand, '#[12]')")

# --- joins -----------------------------------------------------------------------------------------------------------
_orders = lambda spark, d: V.read(spark, d, "orders").select("o_orderkey", "o_custkey")
_customers = lambda spark, d: V.read(spark, d, "customer").select("c_custkey", "c_nationkey")


def _hinted(spark: SparkSession, d: str) -> DataFrame:
    o, c = _orders(spark, d), _customers(spark, d)
    nations = V.read(spark, d, "nation").select("n_nationkey", "n_name")  # 25 rows
    by = {"merge": c.hint("merge"), "shuffle_hash": c.hint("shuffle_hash")}
    parts = [o.join(x, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n")).withColumn("how", F.lit(k)) for k, x in by.items()]
    return parts[0].unionByName(parts[1])


add("op_join", _hinted, "select how, n_name, count(*) as n from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey, (select unnest(['merge', 'shuffle_hash']) as how) group by all")
add("op_left", lambda spark, d: _customers(spark, d).join(_orders(spark, d), F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("orders")), "select c_custkey, count(o_orderkey) as orders from customer left join orders on c_custkey = o_custkey group by c_custkey")
add(
    "op_full",
    lambda spark, d: (h := V.handoff(spark, d).select("src").distinct()).join(V.handoff(spark, d).select("dst").distinct(), F.col("src") == F.col("dst"), "full").select(F.coalesce("src", "dst").alias("vid"), F.col("src").isNotNull().alias("sends"), F.col("dst").isNotNull().alias("receives")),
    _G + "select coalesce(src, dst) as vid, src is not null as sends, dst is not null as receives from (select distinct src from g) full join (select distinct dst from g) on src = dst",
)
add("op_semi", lambda spark, d: _customers(spark, d).join(_orders(spark, d).where("o_orderkey % 3 = 0"), F.col("c_custkey") == F.col("o_custkey"), "left_semi"), "select c_custkey, c_nationkey from customer where c_custkey in (select o_custkey from orders where o_orderkey % 3 = 0)")
add("op_anti", lambda spark, d: _customers(spark, d).join(_orders(spark, d).where("o_orderkey % 3 = 0"), F.col("c_custkey") == F.col("o_custkey"), "left_anti"), "select c_custkey, c_nationkey from customer where not exists (from orders where o_custkey = c_custkey and o_orderkey % 3 = 0)")
add("op_theta", lambda spark, d: (n := V.read(spark, d, "nation")).alias("x").join(F.broadcast(n.alias("y")), F.expr("x.n_nationkey < y.n_nationkey and x.n_regionkey <> y.n_regionkey")).select(F.col("x.n_nationkey").alias("a"), F.col("y.n_nationkey").alias("b")), "select x.n_nationkey as a, y.n_nationkey as b from nation x, nation y where x.n_nationkey < y.n_nationkey and x.n_regionkey <> y.n_regionkey")


def _range_join(spark: SparkSession, d: str) -> DataFrame:
    """Pairs of one user's events within six hours: by user and bucket of time, each left row in the two buckets that its range meets."""
    e = V.access(spark, d).select("edge_id", "src", "ts")
    left = e.select(F.col("edge_id").alias("a"), "src", F.col("ts").alias("t"), F.explode(F.array(F.floor(F.col("ts") / (6 * HOUR)), F.floor(F.col("ts") / (6 * HOUR)) + 1)).alias("bucket"))
    right = e.select(F.col("edge_id").alias("b"), "src", "ts", F.floor(F.col("ts") / (6 * HOUR)).alias("bucket"))
    return left.join(right, ["src", "bucket"]).where((F.col("ts") > F.col("t")) & (F.col("ts") <= F.col("t") + 6 * HOUR)).select("a", "b")


add("op_range_join", _range_join, _A + f"select x.edge_id as a, y.edge_id as b from a x join a y on x.src = y.src and y.ts > x.ts and y.ts <= x.ts + {6 * HOUR}")


def _asof(spark: SparkSession, d: str) -> DataFrame:
    """The latest error of the same user at or before each purchase: one window over both kinds of rows."""
    e = V.access(spark, d).where("label in ('purchase', 'error')").select("edge_id", "src", "label", "ts")
    upto = Window.partitionBy("src").orderBy("ts", F.col("label") == "purchase", "edge_id").rowsBetween(Window.unboundedPreceding, 0)
    latest = F.last(F.when(F.col("label") == "error", F.col("edge_id")), ignorenulls=True).over(upto)
    return e.withColumn("error_id", latest).where("label = 'purchase'").select("edge_id", "error_id")


add("op_asof", _asof, _A + "select p.edge_id, e.edge_id as error_id from (select * from a where label = 'purchase') p asof left join (select * from a where label = 'error') e on p.src = e.src and p.ts >= e.ts")


def _lateral(spark: SparkSession, d: str) -> DataFrame:
    nations, customers = V.read(spark, d, "nation"), V.read(spark, d, "customer")
    ranked = customers.withColumn("rk", F.row_number().over(Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")))
    own = F.array_sort(F.collect_list(F.struct("rk", "c_custkey")))
    best = ranked.where("rk <= 2").groupBy("c_nationkey").agg(own.alias("best"))
    return nations.join(best, nations["n_nationkey"] == best["c_nationkey"]).select("n_nationkey", F.inline("best"))


add("op_lateral", _lateral, "select n_nationkey, rk, c_custkey from nation, lateral (select c_custkey, row_number() over (order by c_acctbal desc, c_custkey) as rk from customer where c_nationkey = n_nationkey) where rk <= 2")

# --- aggregates ------------------------------------------------------------------------------------------------------
add(
    "op_aggregates",
    lambda spark, d: V.access(spark, d).groupBy("label").agg(
        F.count("*").alias("n"), F.sum("src").alias("s"), F.min("edge_id").alias("least"), F.max("edge_id").alias("most"), F.round(F.avg("src"), 4).alias("mean"), F.round(F.stddev("src"), 4).alias("deviation"),
        F.bit_or("src").alias("b_or"), F.bit_and("edge_id").alias("b_and"), F.count_if(F.col("src") > 3).alias("over3"), F.max_by("edge_id", "ts").alias("latest"), F.size(F.collect_set("src")).cast("long").alias("users"), F.percentile("src", 0.5).alias("median"),
    ),
    _A + "select label, count(*) as n, sum(src)::bigint as s, min(edge_id) as least, max(edge_id) as most, round(avg(src), 4) as mean, round(stddev(src), 4) as deviation, bit_or(src) as b_or, bit_and(edge_id) as b_and, count_if(src > 3)::bigint as over3, max_by(edge_id, ts) as latest, count(distinct src) as users, quantile_cont(src, 0.5) as median from a group by label",
)
add("op_distinct", lambda spark, d: V.handoff(spark, d).select("src", "dst").distinct().groupBy("src").agg(F.count_distinct("dst").alias("neighbours")), _G + "select src, count(distinct dst) as neighbours from g group by src")
add("op_drop_duplicates", lambda spark, d: V.handoff(spark, d).groupBy("src", "dst", "label").agg(F.min("edge_id").alias("edge_id")), _G + "select src, dst, label, min(edge_id) as edge_id from g group by all")


def _sketch(spark: SparkSession, d: str) -> DataFrame:
    """Distinct pairs by a HyperLogLog sketch made per day and united: whether it is within a tenth of the truth."""
    e = V.handoff(spark, d).withColumn("day", F.floor(F.col("ts") / DAY))
    united = e.groupBy("day").agg(F.hll_sketch_agg(F.hash("src", "dst")).alias("sketch")).agg(F.hll_sketch_estimate(F.hll_union_agg("sketch")).alias("guess"))
    true = e.select("src", "dst").distinct().agg(F.count("*").alias("n"))
    return united.crossJoin(true).select((F.abs(F.col("guess") - F.col("n")) <= 0.1 * F.col("n")).alias("close"))  # one row each


add("op_sketch", _sketch, "select true as close")
add("op_cube", lambda spark, d: G.label_type_cube(V.commerce(spark, d)), _C + f"select label, case src // {V.T} when 1 then 'customer' when 2 then 'order' when 4 then 'supplier' else 'nation' end as src_type, count(*) as n from c group by cube (label, src_type)")
add("op_rollup", lambda spark, d: V.read(spark, d, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), F.grouping_id().cast("long").alias("gid")), "select o_orderstatus, o_orderpriority, count(*) as n, grouping_id(o_orderstatus, o_orderpriority)::bigint as gid from orders group by rollup (o_orderstatus, o_orderpriority)")
add("op_grouping_sets", lambda spark, d: V.read(spark, d, "lineitem").groupingSets([["l_returnflag"], ["l_linestatus"], []], "l_returnflag", "l_linestatus").agg(F.count("*").alias("n")), "select l_returnflag, l_linestatus, count(*) as n from lineitem group by grouping sets ((l_returnflag), (l_linestatus), ())")
add("op_pivot", lambda spark, d: V.handoff(spark, d).groupBy("src").pivot("label", ["click", "view"]).agg(F.count(F.lit(1))).fillna(0), _G + "select src, count(*) filter (label = 'click') as click, count(*) filter (label = 'view') as view from g group by src")
add("op_unpivot", lambda spark, d: V.read(spark, d, "labels").withColumns({"quality": F.col("quality").cast("long"), "toxic": F.col("toxic").cast("long")}).unpivot("doc_id", ["quality", "toxic"], "mark", "value"), "select doc_id, 'quality' as mark, quality::bigint as value from labels union all select doc_id, 'toxic', toxic from labels")

# --- windows and order -----------------------------------------------------------------------------------------------
_by = lambda: Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
add(
    "op_rank",
    lambda spark, d: V.read(spark, d, "customer").select("c_custkey", F.rank().over(Window.partitionBy("c_nationkey").orderBy("c_mktsegment")).alias("rk"), F.dense_rank().over(Window.partitionBy("c_nationkey").orderBy("c_mktsegment")).alias("dense"), F.ntile(4).over(_by()).alias("quarter"), F.row_number().over(_by()).alias("rn")),
    "select c_custkey, rank() over s as rk, dense_rank() over s as dense, ntile(4) over b as quarter, row_number() over b as rn from customer window s as (partition by c_nationkey order by c_mktsegment), b as (partition by c_nationkey order by c_acctbal desc, c_custkey)",
)
_user = lambda: Window.partitionBy("src").orderBy("ts", "edge_id")
add("op_lag", lambda spark, d: V.access(spark, d).select("edge_id", F.lag("label").over(_user()).alias("before"), F.lead("label", 2).over(_user()).alias("after"), F.first("edge_id").over(_user()).alias("first")), _A + "select edge_id, lag(label) over w as before, lead(label, 2) over w as after, first_value(edge_id) over w as first from a window w as (partition by src order by ts, edge_id)")
add("op_frame_rows", lambda spark, d: V.access(spark, d).select("edge_id", F.count("*").over(_user().rowsBetween(-3, 0)).alias("n"), F.sum("edge_id").over(_user().rowsBetween(-1, 1)).alias("s")), _A + "select edge_id, count(*) over (partition by src order by ts, edge_id rows between 3 preceding and current row) as n, sum(edge_id) over (partition by src order by ts, edge_id rows between 1 preceding and 1 following)::bigint as s from a")
add("op_frame_range", lambda spark, d: V.access(spark, d).select("edge_id", F.count("*").over(Window.partitionBy("src").orderBy("ts").rangeBetween(-DAY, 0)).alias("n")), _A + f"select edge_id, count(*) over (partition by src order by ts range between {DAY} preceding and current row) as n from a")
add("op_topk", lambda spark, d: G.hubs(V.handoff(spark, d), 5), _G + "select vid, count(*) as degree from (select src as vid from g union all select dst from g) group by vid order by degree desc, vid limit 5")
add("op_topk_group", lambda spark, d: V.read(spark, d, "customer").withColumn("rn", F.row_number().over(_by())).where("rn <= 3").select("c_nationkey", "c_custkey", "rn"), "select c_nationkey, c_custkey, row_number() over (partition by c_nationkey order by c_acctbal desc, c_custkey) as rn from customer qualify rn <= 3")

# --- sets ------------------------------------------------------------------------------------------------------------
_sends, _gets = (lambda spark, d: V.handoff(spark, d).select(F.col("src").alias("vid"), "label")), (lambda spark, d: V.handoff(spark, d).select(F.col("dst").alias("vid"), "label"))
add("op_union", lambda spark, d: _sends(spark, d).union(_gets(spark, d)).groupBy("vid").agg(F.count("*").alias("n")), _G + "select vid, count(*) as n from (select src as vid from g union all select dst from g) group by vid")
add("op_intersect", lambda spark, d: _sends(spark, d).where("label = 'view'").intersect(_gets(spark, d).where("label = 'view'")), _G + "select src as vid, label from g where label = 'view' intersect select dst, label from g where label = 'view'")
add("op_intersect_all", lambda spark, d: _sends(spark, d).intersectAll(_gets(spark, d)).groupBy("vid", "label").agg(F.count("*").alias("n")), _G + "select vid, label, count(*) as n from (select src as vid, label from g intersect all select dst, label from g) group by all")
add("op_except_all", lambda spark, d: _sends(spark, d).exceptAll(_gets(spark, d)).groupBy("vid", "label").agg(F.count("*").alias("n")), _G + "select vid, label, count(*) as n from (select src as vid, label from g except all select dst, label from g) group by all")

# --- functions -------------------------------------------------------------------------------------------------------
add(
    "op_string",
    lambda spark, d: V.read(spark, d, "pages").select("page_id", F.regexp_extract("url", "//([^/:]+)", 1).alias("host"), F.size(F.split("url", "/")).cast("long").alias("parts"), F.concat_ws("-", F.lower(F.trim("url")), F.lit("x")).alias("name"), F.substring("url", 1, 8).alias("head"), F.length("html").cast("long").alias("n"), F.levenshtein(F.substring("url", 1, 20), F.lit("https://example.org/")).cast("long").alias("distance")),
    "select page_id, regexp_extract(url, '//([^/:]+)', 1) as host, len(string_split(url, '/'))::bigint as parts, lower(trim(url)) || '-x' as name, substr(url, 1, 8) as head, length(html) as n, levenshtein(substr(url, 1, 20), 'https://example.org/')::bigint as distance from pages",
)
add("op_html_links", lambda spark, d: V.links(spark, d).select("src", "dst", "label", "weight"), """select 'page:' || page_id as src, 'path:' || t as dst, 'links' as label, count(*) as weight from (select page_id, unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) as t from pages) group by all union all select 'page:' || page_id, 'host:' || regexp_extract(url, '//([^/:]+)', 1), 'hosted', 1 from pages""")
add(
    "op_date",
    lambda spark, d: events(spark, d).select("event_id", F.expr("cast(date_trunc('hour', ts) as string)").alias("hour"), F.dayofweek("ts").cast("long").alias("weekday"), V.micros("ts").alias("micros"), F.floor(V.micros("ts") / (10 * 60_000_000)).alias("stride"), F.expr("cast(ts + interval 24 hours as string)").substr(1, 10).alias("tomorrow")),
    "select event_id, strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') as hour, dayofweek(ts) + 1 as weekday, epoch_us(ts) as micros, epoch_us(ts) // 600000000 as stride, strftime(ts + interval 24 hours, '%Y-%m-%d') as tomorrow from events",
)
add(
    "op_bits",
    lambda spark, d: events(spark, d).select("event_id", F.shiftleft("user_id", 3).alias("up"), F.shiftright("event_id", 2).alias("down"), F.col("event_id").bitwiseAND(F.col("user_id")).alias("both"), F.col("event_id").bitwiseOR(F.lit(7)).alias("some"), F.col("event_id").bitwiseXOR(F.col("user_id")).alias("one"), F.bit_count("event_id").cast("long").alias("ones"), F.getbit("event_id", F.lit(3)).cast("long").alias("third"), F.pmod("event_id", F.lit(7)).alias("rest"), F.greatest("event_id", "user_id").alias("most")),
    "select event_id, user_id << 3 as up, event_id >> 2 as down, event_id & user_id as both, event_id | 7 as some, xor(event_id, user_id) as one, bit_count(event_id)::bigint as ones, (event_id >> 3) & 1 as third, event_id % 7 as rest, greatest(event_id, user_id) as most from events",
)
add(
    "op_array",
    lambda spark, d: V.read(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v")).select("vec_id", F.size(F.filter("v", lambda x: x > 0)).cast("long").alias("positive"), F.exists("v", lambda x: x > 2).alias("large"), F.round(F.aggregate("v", F.lit(0.0), lambda a, x: a + x * x), 3).alias("norm2"), F.array_position(F.transform("v", lambda x: x > 0), True).alias("first")),
    "select vec_id, len(list_filter(embedding, lambda x: x > 0))::bigint as positive, list_bool_or(list_transform(embedding, lambda x: x > 2)) as large, round(list_sum(list_transform(embedding::double[], lambda x: x * x)), 3) as norm2, coalesce(list_position(list_transform(embedding, lambda x: x > 0), true), 0)::bigint as first from embeddings",
)
add("op_posexplode", lambda spark, d: V.read(spark, d, "embeddings").select("vec_id", F.posexplode(F.slice("embedding", 1, 2))).select("vec_id", F.col("pos").cast("long").alias("pos"), (F.col("col") > 0).alias("up")), "select vec_id, i - 1 as pos, embedding[i] > 0 as up from embeddings, range(1, 3) t(i)")
add("op_map", lambda spark, d: V.access(spark, d).groupBy("src", "label").agg(F.count("*").alias("n")).groupBy("src").agg(F.map_from_entries(F.collect_list(F.struct("label", "n"))).alias("m")).select("src", F.coalesce(F.element_at("m", "click"), F.lit(0)).alias("clicks"), F.map_contains_key("m", "error").alias("has_error"), F.size(F.map_keys("m")).cast("long").alias("kinds")), _A + "select src, count(*) filter (label = 'click') as clicks, bool_or(label = 'error') as has_error, count(distinct label) as kinds from a group by src")
add("op_json", lambda spark, d: events(spark, d).select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"), F.from_json("props", "k long")["k"].alias("k2"), F.to_json(F.struct("event_id")).alias("text")), """select event_id, json_extract_string(props, '$.k')::bigint as k, json_extract_string(props, '$.k')::bigint as k2, '{"event_id":' || event_id || '}' as text from events""")

# --- windows of streams, as in batch ---------------------------------------------------------------------------------
add("op_tumbling_window", lambda spark, d: events(spark, d).groupBy(F.window(F.col("ts").cast("timestamp"), "1 day").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "event_type", "n"), "select strftime(ts, '%Y-%m-%d') as day, event_type, count(*) as n from events group by all")
add("op_sliding_window", lambda spark, d: events(spark, d).groupBy(F.window(F.col("ts").cast("timestamp"), "2 days", "1 day").alias("w")).agg(F.count("*").alias("n")).select(F.date_format("w.start", "yyyy-MM-dd").alias("start"), "n"), "select strftime(d, '%Y-%m-%d') as start, count(*) as n from (select unnest([date_trunc('day', ts), date_trunc('day', ts) - interval 1 day]) as d from events) group by d")
add(
    "op_session_window",
    lambda spark, d: events(spark, d).groupBy("user_id", F.session_window(F.col("ts").cast("timestamp"), "2 hours")).agg(F.count("*").alias("n"), F.min("event_id").alias("first")).select("user_id", "n", "first"),
    "select user_id, count(*) as n, min(event_id) as first from (select *, sum(fresh) over (partition by user_id order by ts, event_id) as s from (select *, (coalesce(ts - lag(ts) over (partition by user_id order by ts, event_id) >= interval 2 hours, true))::int as fresh from events)) group by user_id, s",
)


def _streamed(spark: SparkSession, d: str, build) -> DataFrame:
    """Runs a streaming query over the events, once, into a table."""
    out = path(spark, "streamed")
    source = path(spark, "stream-source")
    V.access(spark, d).withColumn("at", F.timestamp_micros("ts")).repartitionByRange(3, "ts").write.parquet(source)
    stream = spark.readStream.schema(spark.read.parquet(source).schema).parquet(source)
    build(stream).writeStream.format("parquet").option("path", out).option("checkpointLocation", path(spark, "progress")).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(out)


add("op_stream_dedup", lambda spark, d: _streamed(spark, d, lambda s: s.withWatermark("at", "40 days").dropDuplicatesWithinWatermark(["src", "label"]).select("src", "label")), _A + "select distinct src, label from a")


def _stream_join(s: DataFrame) -> DataFrame:
    left = s.where("label = 'error'").select(F.col("edge_id").alias("e"), F.col("src").alias("eu"), F.col("at").alias("ea")).withWatermark("ea", "40 days")
    right = s.where("label = 'purchase'").select(F.col("edge_id").alias("p"), F.col("src").alias("pu"), F.col("at").alias("pa")).withWatermark("pa", "40 days")
    return left.join(right, F.expr("eu = pu and pa > ea and pa <= ea + interval 6 hours")).select("e", "p")


add("op_stream_join", lambda spark, d: _streamed(spark, d, _stream_join), _A + f"select x.edge_id as e, y.edge_id as p from a x join a y on x.src = y.src and y.ts > x.ts and y.ts <= x.ts + {6 * HOUR} where x.label = 'error' and y.label = 'purchase'")
add("op_stream_static_join", lambda spark, d: _streamed(spark, d, lambda s: s.join(F.broadcast(spark.createDataFrame([("error", 2), ("purchase", 1)], "label string, rank int")), "label").select("edge_id", "rank")), _A + "select edge_id, case label when 'error' then 2 else 1 end as rank from a where label in ('error', 'purchase')")
_star = P["star2"]
add("star_window_v1", lambda spark, d: star_batch(V.handoff(spark, d), _star, 6 * HOUR), O.embeddings(_star, "v1", True, (), 6 * HOUR - 1, select="x.src as v_a, x.dst as v_b, x.edge_id as e_x, y.dst as v_c, y.edge_id as e_y"))
add("op_late_data", lambda spark, d: late_rows(V.access(spark, d).withColumn("batch", F.col("edge_id") * 31 % 8), DAY).groupBy("batch").agg(F.count("*").alias("late")), _A + f", b as (select *, edge_id * 31 % 8 as batch from a), t as (select batch, max(max(ts)) over (order by batch rows between unbounded preceding and 1 preceding) as bound from b group by batch) select batch, count(*) as late from b join t using (batch) where bound - ts > {DAY} group by batch")


# --- user functions --------------------------------------------------------------------------------------------------
def _scalar_udf(spark: SparkSession, d: str) -> DataFrame:
    @F.pandas_udf("long")
    def digits(x: pd.Series) -> pd.Series:
        return x.astype(str).map(lambda t: sum(map(int, t)))

    return events(spark, d).select("event_id", digits("event_id").alias("digits"))


add("op_udf", _scalar_udf, "select event_id, list_sum(list_transform(string_split(event_id::varchar, ''), lambda x: x::bigint))::bigint as digits from events")


def _grouped_udf(spark: SparkSession, d: str) -> DataFrame:
    @F.pandas_udf("long")
    def spread(x: pd.Series) -> int:
        return int(x.max() - x.min())

    return V.access(spark, d).groupBy("label").agg(spread("src").alias("spread"))


add("op_udaf", _grouped_udf, _A + "select label, max(src) - min(src) as spread from a group by label")


def _table_udf(spark: SparkSession, d: str) -> DataFrame:
    @F.udtf(returnType="bit int")
    class SetBits:
        def eval(self, mask: int):
            for i in range(mask.bit_length()):
                if mask >> i & 1:
                    yield (i,)

    spark.udtf.register("set_bits", SetBits)
    events(spark, d).select("event_id").createOrReplaceTempView("ids_with_bits")
    return spark.sql("select event_id, bit from ids_with_bits, lateral set_bits(event_id)")


add("op_udtf", _table_udf, "select event_id, i::int as bit from events, range(0, 40) t(i) where (event_id >> i) & 1 = 1")
add("op_sql_view", lambda spark, d: (V.handoff(spark, d).createOrReplaceTempView("handoff_edges"), spark.sql("select label, count(*) as n from handoff_edges group by label having count(*) > 1"))[1], _G + "select label, count(*) as n from g group by label having count(*) > 1")

# --- graph utilities -------------------------------------------------------------------------------------------------
add("degree_by_label_v1", lambda spark, d: G.degrees(V.handoff(spark, d)), _G + "select vid, label, sum(o)::bigint as out_degree, sum(i)::bigint as in_degree from (select src as vid, label, 1 as o, 0 as i from g union all select dst, label, 0, 1 from g) group by all")
_T7 = f"with g as materialized ({O.SQL['v7']}), b as materialized (select src as a, dst as b from g union select dst, src from g) "
add(
    "khop2_v7",
    lambda spark, d: G.khop(V.turns(spark, d), V.turns(spark, d).select(F.col("src").alias("vid")).distinct(), 2).select("start", "vid", F.col("hops").cast("long").alias("hops")),
    _T7 + ", s as (select distinct src as start from g) select start, vid, min(hops) as hops from (select start, start as vid, 0 as hops from s union all select start, b, 1 from s join b on a = start union all select start, y.b, 2 from s join b x on x.a = start join b y on y.a = x.b) group by all",
)
add("components_v7", lambda spark, d: G.components(V.turns(spark, d)), _T7 + "select vid, min(vid) over (partition by vid // 64) as component from (select src as vid from g union select dst from g)")
add("as_undirected_v1", lambda spark, d: V.as_undirected(V.handoff(spark, d)).select("edge_id", "src", "dst"), _G + "select edge_id, src, dst from g union all select -edge_id - 1, dst, src from g")
add("knn_v5", lambda spark, d: V.neighbours(spark, d).select("src", "dst", "label"), f"select src, dst, label from ({O.SQL['v5']})")
_reach = parse_pattern("(a)-[x]->(b)")
add("corpus_v8", lambda spark, d: V.corpus(spark, d).groupBy("label").agg(F.count("*").alias("n")), f"select 'from' as label, count(*) as n from documents union all select 'in', count(*) from documents union all select 'contains', count(*) from documents d join benchmark b on contains(d.text, b.text) where len(list_filter(regexp_split_to_array(b.text, '\\s+'), lambda x: x <> '')) > {V.PASSAGE_WORDS}")
