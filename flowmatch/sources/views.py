"""Edge views of the given tables.  Every view has the columns of EDGE; ``ts`` is in microseconds since 1970, free of time zones.

Vertex ids are unique across types: ``type code * T + key``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window, functions as F

T = 1 << 40
PASSAGE_WORDS = 5  # words by which a text and a passage meet
EDGE = ["edge_id", "src", "dst", "src_type", "dst_type", "label", "ts", "weight"]


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def micros(ts: str) -> Column:
    return F.expr(f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', {ts})")


def edge(df: DataFrame, edge_id, src, dst, types: tuple[str, str], label, ts=None, weight=None) -> DataFrame:
    c = lambda x: F.col(x) if isinstance(x, str) else x
    return df.select(
        c(edge_id).cast("long").alias("edge_id"), c(src).cast("long").alias("src"), c(dst).cast("long").alias("dst"), F.lit(types[0]).alias("src_type"), F.lit(types[1]).alias("dst_type"),
        c(label).alias("label"), (F.lit(None) if ts is None else ts).cast("long").alias("ts"), (F.lit(None) if weight is None else c(weight)).cast("double").alias("weight"),
    )


def handoff(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User to the next event's user, self-loops left out.

    The next event is found without one global window, whatever the order of ids: events meet their successors within
    blocks of time; a block's last event meets the first of the next block that has any, which is found among the blocks
    of a day, and for a day's last block among the days.
    """
    e = read(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", "value")
    e = e.withColumn("at", micros("ts")).withColumn("block", F.floor(F.col("at") / 600_000_000)).withColumn("day", F.floor(F.col("at") / 86_400_000_000))
    inner = Window.partitionBy("day", "block").orderBy("at", "event_id")
    rows = e.withColumn("next", F.lead("user_id").over(inner))
    heads = e.groupBy("day", "block").agg(F.min_by("user_id", F.struct("at", "event_id")).alias("head"))
    days = heads.groupBy("day").agg(F.min_by("head", "block").alias("first"))
    days = days.select("day", F.lead("first").over(Window.orderBy("day")).alias("next_day"))  # a row per day
    after = heads.withColumn("next_block", F.lead("head").over(Window.partitionBy("day").orderBy("block"))).drop("head").join(days, "day")
    rows = rows.join(after, ["day", "block"]).withColumn("dst", F.coalesce("next", "next_block", "next_day"))
    return edge(rows.where("dst is not null and dst <> user_id"), "event_id", "user_id", "dst", ("user", "user"), "event_type", micros("ts"), "value")


def copies(edges: DataFrame, k: int, parts: int = 32) -> DataFrame:
    """``k`` disjoint copies of a graph whose ids are below 2^32: as dense as the graph itself, for runs at larger sizes."""
    spread = edges.repartition(parts, "edge_id").select("*", F.explode(F.sequence(F.lit(0), F.lit(k - 1))).alias("copy"))
    return spread.withColumns({c: F.col(c) + F.shiftleft(F.col("copy").cast("long"), 32) for c in ("edge_id", "src", "dst")}).drop("copy")


def access(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User to the resource named in the event's properties."""
    e = read(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", "value", "props")
    return edge(e, "event_id", "user_id", F.lit(T) + F.get_json_object("props", "$.k").cast("long"), ("user", "resource"), "event_type", micros("ts"), "value")


def line_ids(spark: SparkSession, sf_dir: str, orders: DataFrame | None = None) -> DataFrame:
    """Lines with their ids; ``orders`` (l_orderkey): only those orders' lines, all of each, so that the ids stay the same."""
    lines = read(spark, sf_dir, "lineitem")
    if orders is not None:
        lines = lines.join(orders, "l_orderkey", "left_semi")
    by = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate")
    return lines.withColumn("line_id", F.col("l_orderkey") * 64 + F.row_number().over(by))


def commerce(spark: SparkSession, sf_dir: str, with_lines: DataFrame | None = None) -> DataFrame:
    """Customers, orders, parts, suppliers, nations, regions; 34 labels.  ``with_lines`` (vid): only these orders have edges to parts and suppliers."""
    vid = lambda code, key: F.lit(T * code) + F.col(key)
    orders = read(spark, sf_dir, "orders")
    numbered = line_ids(spark, sf_dir, None if with_lines is None else with_lines.select((F.col("vid") - 2 * T).alias("l_orderkey")))
    lines = numbered.select("line_id", "l_orderkey", "l_partkey", "l_suppkey", "l_returnflag", "l_linestatus", "l_shipdate")
    flag = F.concat("l_returnflag", "l_linestatus")
    start = F.lit(788918400_000_000)  # 1995-01-01
    parts = [
        edge(orders, F.col("o_orderkey") * 8, vid(1, "o_custkey"), vid(2, "o_orderkey"), ("customer", "order"), F.concat(F.lit("PLACED_"), "o_orderpriority", F.lit("_"), "o_orderstatus"), micros("o_orderdate")),
        edge(lines, F.col("line_id") * 8 + 1, vid(2, "l_orderkey"), vid(3, "l_partkey"), ("order", "part"), F.concat(F.lit("HAS_"), flag), micros("l_shipdate")),
        edge(lines, F.col("line_id") * 8 + 2, vid(2, "l_orderkey"), vid(4, "l_suppkey"), ("order", "supplier"), F.concat(F.lit("FROM_"), flag), micros("l_shipdate")),
        edge(read(spark, sf_dir, "customer"), F.col("c_custkey") * 8 + 3, vid(1, "c_custkey"), vid(5, "c_nationkey"), ("customer", "nation"), F.concat(F.lit("LIVES_"), "c_mktsegment"), start),
        edge(read(spark, sf_dir, "supplier"), F.col("s_suppkey") * 8 + 4, vid(4, "s_suppkey"), vid(5, "s_nationkey"), ("supplier", "nation"), F.lit("BASED"), start),
        edge(read(spark, sf_dir, "nation"), F.col("n_nationkey").cast("long") * 8 + 5, vid(5, "n_nationkey"), vid(6, "n_regionkey"), ("nation", "region"), F.lit("IN_REGION"), start),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def flow(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customer to supplier, one edge per line: a heavy bipartite multigraph."""
    orders = read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    rows = line_ids(spark, sf_dir).select("line_id", "l_orderkey", "l_suppkey", "l_returnflag", "l_linestatus", "l_shipdate", "l_quantity").join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    return edge(rows, "line_id", "o_custkey", F.lit(T) + F.col("l_suppkey"), ("customer", "supplier"), F.concat("l_returnflag", "l_linestatus"), micros("l_shipdate"), "l_quantity")


def neighbours(spark: SparkSession, sf_dir: str, k: int = 10, block: int = 2048) -> DataFrame:
    """Vector to its k nearest by cosine (rounded to 4 places, id breaks ties), block by block; ``k`` up to 15.

    Exact, so every row is a query and the work is square by definition; blocks of vectors meet in tasks of bounded memory
    that keep the best k each, and the best of those are the answer.  Vectors that are null, zero or hold a null or a
    component that is not finite have no neighbours.
    """
    if not 0 < k < 16:
        raise ValueError("k is 1 to 15: an edge id holds four bits of rank")
    v = read(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"), F.col("label").cast("string").alias("label"))
    usable = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("v", lambda x: x != 0)
    v = v.where(F.col("v").isNotNull() & F.coalesce(usable, F.lit(False)))
    n = max(1, -(-v.count() // block))
    part = F.pmod(F.xxhash64("vec_id"), F.lit(n))
    left = v.select(part.alias("a"), F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(n - 1).cast("bigint"))).alias("b"), F.col("vec_id").alias("src"), F.col("v").alias("x"))
    right = v.select(part.alias("b"), F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(n - 1).cast("bigint"))).alias("a"), F.col("vec_id").alias("dst"), F.col("v").alias("x"), F.col("label").alias("name"))

    def best(x, y):
        import numpy as np
        import pyarrow as pa

        if not x.num_rows or not y.num_rows:
            return pa.table({"src": pa.array([], pa.int64()), "dst": pa.array([], pa.int64()), "label": pa.array([], pa.string()), "cos": pa.array([], pa.float64())})
        unit = lambda t: (m := np.array(t.column("x").to_pylist())) / np.linalg.norm(m, axis=1, keepdims=True)
        src, dst, names = x.column("src").to_numpy(), y.column("dst").to_numpy(), y.column("name").to_pylist()
        s = np.round(unit(x) @ unit(y).T, 4)
        s[src[:, None] == dst[None, :]] = -2
        order = np.lexsort((np.broadcast_to(dst, s.shape), -s), axis=1)[:, :k]
        i, j = np.repeat(np.arange(len(src)), order.shape[1]), order.ravel()
        keep = s[i, j] > -2
        i, j = i[keep], j[keep]
        return pa.table({"src": pa.array(src[i]), "dst": pa.array(dst[j]), "label": pa.array([names[q] for q in j], pa.string()), "cos": pa.array(s[i, j])})

    found = left.groupBy("a", "b").cogroup(right.groupBy("a", "b")).applyInArrow(best, "src long, dst long, label string, cos double")
    ranked = found.withColumn("rk", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("cos"), "dst"))).where(F.col("rk") <= k)
    return edge(ranked, F.col("src") * 16 + F.col("rk"), "src", "dst", ("vector", "vector"), "label", None, "cos")


def links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Page to linked path and to host; vertex ids are strings here, columns src, dst, label, weight."""
    pages = read(spark, sf_dir, "pages")
    page = F.concat(F.lit("page:"), "page_id")
    out = pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), 1)).alias("target"))
    linked = out.groupBy("page_id", "target").agg(F.count("*").alias("weight")).select(page.alias("src"), F.concat(F.lit("path:"), "target").alias("dst"), F.lit("links").alias("label"), "weight")
    hosts = pages.select(page.alias("src"), F.concat(F.lit("host:"), F.regexp_extract("url", "//([^/:]+)", 1)).alias("dst"), F.lit("hosted").alias("label"), F.lit(1).cast("bigint").alias("weight"))
    return linked.unionByName(hosts)


def turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Turn to the next turn of a conversation."""
    c = read(spark, sf_dir, "conversations").select("conv_id", "turn", "role")
    by = Window.partitionBy("conv_id").orderBy("turn")
    rows = c.select("conv_id", "turn", "role", F.lead("turn").over(by).alias("next"), F.lead("role").over(by).alias("then")).where("next is not null")
    return edge(rows, F.col("conv_id") * 64 + F.col("turn"), F.col("conv_id") * 64 + F.col("turn"), F.col("conv_id") * 64 + F.col("next"), ("turn", "turn"), F.concat("role", F.lit(">"), "then"), F.col("turn"))


def corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Document to source, to language, and to the benchmark passages of over ``PASSAGE_WORDS`` words that it contains; string vertex ids."""
    docs = read(spark, sf_dir, "documents")
    doc = F.concat(F.lit("doc:"), "doc_id").alias("src")
    # A passage is looked for in the texts that hold its second to sixth word: texts and passages meet by hashed runs of words.
    items = read(spark, sf_dir, "benchmark").select("item_id", F.col("text").alias("passage"))
    runs = F.transform(F.sequence(F.lit(1), F.greatest(F.size("w") - PASSAGE_WORDS + 1, F.lit(1))), lambda k: F.xxhash64(F.concat_ws(" ", F.slice("w", k, PASSAGE_WORDS))))
    words = lambda c: F.filter(F.split(c, r"\s+"), lambda x: x != "")
    inner = items.withColumn("w", words("passage")).where(F.size("w") > PASSAGE_WORDS).withColumn("key", F.xxhash64(F.concat_ws(" ", F.slice("w", 2, PASSAGE_WORDS)))).drop("w")
    texts = docs.select("doc_id", words("text").alias("w"))
    keys = texts.select("doc_id", F.explode(F.array_distinct(runs)).alias("key"))
    asked = keys.join(inner.select("key", "item_id"), "key").select("doc_id", "item_id").distinct()
    held = asked.join(docs.select("doc_id", "text"), "doc_id").join(inner.select("item_id", "passage"), "item_id").where(F.col("text").contains(F.col("passage")))
    return (
        docs.select(doc, F.concat(F.lit("source:"), "source").alias("dst"), F.lit("from").alias("label"))
        .unionByName(docs.select(doc, F.concat(F.lit("lang:"), "lang").alias("dst"), F.lit("in").alias("label")))
        .unionByName(held.select(doc, F.concat(F.lit("item:"), "item_id").alias("dst"), F.lit("contains").alias("label")))
    )


def passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The passages that documents contain, as edges with the documents' labels as attributes (null where there are none); item ids are under 2^20."""
    held = corpus(spark, sf_dir).where("label = 'contains'").select(F.split("src", ":")[1].cast("long").alias("doc"), F.split("dst", ":")[1].cast("long").alias("item"))
    rows = held.join(read(spark, sf_dir, "labels").select(F.col("doc_id").alias("doc"), "quality", "toxic"), "doc", "left")
    return rows.select(
        (F.col("doc") * (1 << 20) + F.col("item")).alias("edge_id"), F.col("doc").alias("src"), (F.lit(T) + F.col("item")).alias("dst"), F.lit("doc").alias("src_type"), F.lit("item").alias("dst_type"),
        F.lit("contains").alias("label"), F.lit(None).cast("long").alias("ts"), F.lit(None).cast("double").alias("weight"), "quality", "toxic",
    )


def with_hub(edges: DataFrame, every: int = 7, hub: int = 0) -> DataFrame:
    """Every ``every``-th edge goes to one vertex: a power law's worst case."""
    return edges.withColumn("dst", F.when(F.col("edge_id") % every == 0, F.lit(hub).cast("long")).otherwise(F.col("dst"))).where("src <> dst")


def as_undirected(edges: DataFrame) -> DataFrame:
    """Both directions of each edge; the reverse one has the negative id less one."""
    back = edges.withColumns({"edge_id": -F.col("edge_id") - 1, "src": F.col("dst"), "dst": F.col("src"), "src_type": F.col("dst_type"), "dst_type": F.col("src_type")})
    return edges.unionByName(back)


def decode_signed(triplets: DataFrame) -> DataFrame:
    """Signed triplets, ids from 1: an insert, or with both ids negative a delete.  Gives op and ids from 0."""
    gone = (F.col("src") < 0) & (F.col("dst") < 0)
    return triplets.withColumn("op", F.when(gone, -1).otherwise(1).cast("tinyint")).withColumn("src", F.abs("src") - 1).withColumn("dst", F.abs("dst") - 1)


VIEWS = {"v1": handoff, "v2": access, "v3": commerce, "v4": flow, "v5": neighbours, "v7": turns}

#: The same views for DuckDB.
_LINE_IDS = """(select *, l_orderkey * 64 + row_number() over (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey, l_quantity,
  l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate) as line_id from lineitem)"""
SQL = {
    "v1": "select event_id as edge_id, user_id as src, lead(user_id) over (order by ts, event_id) as dst, event_type as label, epoch_us(ts) as ts, value as weight from events qualify dst is not null and dst <> src",
    "v2": f"select event_id as edge_id, user_id as src, {T} + cast(json_extract_string(props, '$.k') as bigint) as dst, event_type as label, epoch_us(ts) as ts, value as weight from events",
    "v3": f"""select o_orderkey*8 as edge_id, {T}+o_custkey as src, {2 * T}+o_orderkey as dst, 'PLACED_'||o_orderpriority||'_'||o_orderstatus as label, epoch_us(o_orderdate) as ts from orders
      union all select line_id*8+1, {2 * T}+l_orderkey, {3 * T}+l_partkey, 'HAS_'||l_returnflag||l_linestatus, epoch_us(l_shipdate) from {_LINE_IDS}
      union all select line_id*8+2, {2 * T}+l_orderkey, {4 * T}+l_suppkey, 'FROM_'||l_returnflag||l_linestatus, epoch_us(l_shipdate) from {_LINE_IDS}
      union all select c_custkey*8+3, {T}+c_custkey, {5 * T}+c_nationkey, 'LIVES_'||c_mktsegment, 788918400000000 from customer
      union all select s_suppkey*8+4, {4 * T}+s_suppkey, {5 * T}+s_nationkey, 'BASED', 788918400000000 from supplier
      union all select n_nationkey::bigint*8+5, {5 * T}+n_nationkey, {6 * T}+n_regionkey, 'IN_REGION', 788918400000000 from nation""",
    "v4": f"select line_id as edge_id, o_custkey as src, {T} + l_suppkey as dst, l_returnflag||l_linestatus as label, epoch_us(l_shipdate) as ts, l_quantity as weight from {_LINE_IDS} join orders on l_orderkey = o_orderkey",
    "v5": """select src * 16 + rk as edge_id, src, dst, label from (select a.vec_id as src, b.vec_id as dst, cast(b.label as varchar) as label, row_number() over (partition by a.vec_id order by
      round(list_cosine_similarity(a.embedding::double[], b.embedding::double[]), 4) desc, b.vec_id) as rk from embeddings a join embeddings b on a.vec_id <> b.vec_id) where rk <= 10""",
    "v7": "select conv_id*64+turn as edge_id, conv_id*64+turn as src, lead(conv_id*64+turn) over (partition by conv_id order by turn) as dst, role||'>'||lead(role) over (partition by conv_id order by turn) as label, turn as ts from conversations qualify dst is not null",
}
