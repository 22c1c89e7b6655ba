"""Measures of cost and correctness."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window, functions as F

from flowmatch.functions.rules import bit
from flowmatch.operators import index as ix
from flowmatch.operators.enumeration import Semantics, delta
from flowmatch.operators.index import Index, index_bits
from flowmatch.plans.planner import Plan
from flowmatch.sources.snapshots import StreamConfig


def index_space(kind: str, n_edges: int, n_vertices: int, n_query_vertices: int, n_query_edges: int) -> int:
    """Entries (bits for the bitmaps) by design: "bitmap" and "pair_state", "query_centric", "match_matrix", "node_list", "embedding_store"."""
    return {
        "bitmap": lambda: index_bits(n_edges, n_vertices, n_query_vertices),
        "pair_state": lambda: index_bits(n_edges, n_vertices, n_query_vertices),
        "query_centric": lambda: n_query_edges * n_edges,
        "match_matrix": lambda: n_vertices * n_query_vertices,
        "node_list": lambda: n_edges * n_query_vertices,
        "embedding_store": lambda: n_edges**n_query_vertices,
    }[kind]()


def update_cost(index: Index, store: dict[str, DataFrame], vertex: int) -> tuple[int, int]:
    """Entries touched to drop a vertex's candidacy: in the bitmap its edges' rows, in a query-centric store the lists that hold it."""
    own = index.edges.where((F.col("src") == vertex) | (F.col("dst") == vertex)).count()
    lists = sum(s.where(F.exists("children", lambda c: c["child"] == vertex)).count() for s in store.values())
    return own, lists


def edge_events(edges: DataFrame, config: StreamConfig) -> DataFrame:
    """(src, snapshot, inserts, deletes) of a sliding window: an edge enters when born and leaves when it dies."""
    one = edges.select("src", config.born().alias("snapshot"), F.lit(1).alias("inserts"), F.lit(0).alias("deletes"))
    return one.unionByName(edges.select("src", config.dies().alias("snapshot"), F.lit(0).alias("inserts"), F.lit(1).alias("deletes")))


def placeholders(events: DataFrame, reclaim: bool = True) -> DataFrame:
    """(snapshot_id, slots) of every snapshot with events: edge placeholders allocated by then, summed over source vertices; in between they stay as they are."""
    own = ix.assign_slots(events, reclaim)
    more = F.col("slots") - F.coalesce(F.lag("slots").over(Window.partitionBy("src").orderBy("snapshot")), F.lit(0))
    by_snapshot = own.select("snapshot", more.alias("more")).groupBy(F.col("snapshot").alias("snapshot_id")).agg(F.sum("more").alias("more"))
    return by_snapshot.select("snapshot_id", F.sum("more").over(Window.orderBy("snapshot_id")).cast("long").alias("slots"))  # one row per snapshot


def traversals(edges: DataFrame, plan: Plan, batch: Column, shared: bool = True) -> DataFrame:
    """(batch, level, visited): distinct (edge, query edge) pairs that a batch's frontier reads at each tree level, top down.

    Level 1 reads the candidates of level-1 query edges at the parents that the batch's matching edges have.  Without
    ``shared`` a pair counts once for each update that leads to it.
    """
    tree = plan.tree
    marked = edges.withColumn("batch", batch)
    arc = ix.arcs(marked.where("local_mask <> 0"), tree).join(marked.select("edge_id", "batch"), "edge_id")
    first = sum(1 << tree.bit(t) for t in tree.level(1))
    seeds = arc.where(F.col("m").bitwiseAND(F.lit(first).cast("bigint")) != 0).select("batch", "edge_id", "p").withColumnRenamed("edge_id", "origin")
    seeds = (seeds.select("batch", "p").distinct() if shared else seeds).withColumnRenamed("batch", "now")
    out = None
    for k in range(1, tree.depth + 1):
        level = sum(1 << tree.bit(t) for t in tree.level(k))
        own = arc.where(F.col("m").bitwiseAND(F.lit(level).cast("bigint")) != 0)
        read = own.join(seeds, "p").where("batch <= now").withColumn("pairs", F.bit_count(F.col("m").bitwiseAND(F.lit(level).cast("bigint"))).cast("long"))
        part = read.groupBy(F.col("now").alias("batch")).agg(F.sum("pairs").alias("visited")).withColumn("level", F.lit(k))
        out = part if out is None else out.unionByName(part)
        seeds = read.select("now", F.col("c").alias("p"), *([] if shared else ["origin"]))
        seeds = seeds.distinct()
    return out


def index_quality(index: Index) -> DataFrame:
    """(qedge, local, reach, live): candidates of each query edge after each filter."""
    marked = index.marked()
    rows = []
    for i, e in enumerate(index.plan.pattern.edges):
        rows.append(F.struct(F.lit(e.name).alias("qedge"), *[bit(f"{m}_mask", i).cast("long").alias(m) for m in ("local", "reach", "live")]))
    return marked.select(F.explode(F.array(*rows)).alias("x")).groupBy("x.qedge").agg(*[F.sum(f"x.{m}").alias(m) for m in ("local", "reach", "live")])


def duplicates(edges: DataFrame, is_new: Column, plan: Plan, semantics: Semantics) -> DataFrame:
    """One row: embeddings found without masks, with them, and the repeats that masks avoid."""
    count = lambda d, name: delta(edges, is_new, plan, semantics, dedup=d).agg(F.count("*").alias(name))
    return count("none", "unmasked").crossJoin(count("mask", "masked")).withColumn("avoided", F.col("unmasked") - F.col("masked"))  # one row each


def check_equivalence(a: DataFrame, b: DataFrame) -> int:
    """Rows in which two results differ, repeats counted; 0 if they are equal."""
    b = b.select(a.columns)
    return a.exceptAll(b).count() + b.exceptAll(a).count()


def speedup(runs: DataFrame, base: str) -> DataFrame:
    """From (query, method, seconds or null for a timeout): per method the mean, least and most speed-up over ``base``, also among queries both finish, and timeouts."""
    own = runs.select("query", "method", "seconds")
    ref = own.where(F.col("method") == base).select("query", F.col("seconds").alias("base_s"))
    both = own.join(ref, "query").withColumn("ratio", F.col("base_s") / F.col("seconds"))
    return both.groupBy("method").agg(F.avg("ratio").alias("mean"), F.min("ratio").alias("least"), F.max("ratio").alias("most"), F.count("ratio").alias("finished"), F.sum(F.col("seconds").isNull().cast("long")).alias("timeouts"), F.avg("seconds").alias("seconds"), F.stddev("seconds").alias("deviation"))


def timed(spark: SparkSession, work: Callable[[], DataFrame], timeout_s: float | None = None) -> tuple[float | None, int | None]:
    """Seconds and rows of a plan; (None, None) if it runs out of time, its jobs cancelled by tag."""
    import threading
    import uuid

    tag = f"run-{uuid.uuid4().hex}"
    spark.addTag(tag)
    alarm = threading.Timer(timeout_s, spark.interruptTag, [tag]) if timeout_s else None
    began = time.time()
    try:
        if alarm:
            alarm.start()
        rows = work().count()
        return time.time() - began, rows
    except Exception:
        if timeout_s and time.time() - began >= timeout_s:
            return None, None
        raise
    finally:
        if alarm:
            alarm.cancel()
        spark.removeTag(tag)


def placeholder_growth(series: DataFrame, first: int, snapshots: int = 90) -> DataFrame:
    """One row: slots at snapshot ``first`` and so many snapshots later, and the growth in percent; ``series`` from :func:`placeholders`."""
    at = lambda k: F.max(F.when(F.col("snapshot_id") <= k, F.col("slots")))  # noqa: E731  slots only grow
    row = series.agg(at(first).alias("slots_start"), at(first + snapshots).alias("slots_end"))
    return row.withColumn("growth_pct", F.round(100.0 * (F.col("slots_end") - F.col("slots_start")) / F.col("slots_start"), 1))


def bottom_up_traversals(edges: DataFrame, plan: Plan, batch: Column) -> DataFrame:
    """(batch, level, visited): distinct (edge, query edge) pairs that a batch reads on its way up, from the vertices it touches."""
    tree = plan.tree
    marked = edges.withColumn("batch", batch)
    arc = ix.arcs(marked.where("local_mask <> 0"), tree).join(marked.select("edge_id", "batch"), "edge_id")
    deepest = sum(1 << tree.bit(t) for t in tree.level(tree.depth))
    seeds = arc.where(F.col("m").bitwiseAND(F.lit(deepest).cast("bigint")) != 0).select(F.col("batch").alias("now"), "c").distinct()
    out = None
    for k in range(tree.depth, 0, -1):
        level = F.lit(sum(1 << tree.bit(t) for t in tree.level(k))).cast("bigint")
        read = arc.where(F.col("m").bitwiseAND(level) != 0).join(seeds, "c").where("batch <= now").withColumn("pairs", F.bit_count(F.col("m").bitwiseAND(level)).cast("long"))
        part = read.groupBy(F.col("now").alias("batch")).agg(F.sum("pairs").alias("visited")).withColumn("level", F.lit(k))
        out = part if out is None else out.unionByName(part)
        seeds = read.select("now", F.col("p").alias("c")).distinct()
    return out


def cpu_trace(work: Callable[[], object], every_s: float = 0.5) -> tuple[list[list[float]], object]:
    """Busy share of each core of this machine, sampled while ``work`` runs, and what it returns."""
    import threading

    def read():
        with open("/proc/stat") as f:
            rows = [list(map(int, line.split()[1:])) for line in f if line.startswith("cpu") and line[3] != " "]
        return [(sum(r), r[3] + r[4]) for r in rows]

    samples, stop = [], threading.Event()

    def sample():
        before = read()
        while not stop.wait(every_s):
            now = read()
            samples.append([1 - (b[1] - a[1]) / max(1, b[0] - a[0]) for a, b in zip(before, now)])
            before = now

    thread = threading.Thread(target=sample, daemon=True)
    thread.start()
    try:
        result = work()
    finally:
        stop.set()
        thread.join()
    return samples, result


def tier_overhead(in_memory_s: float, with_tier_s: float) -> float:
    """Percent that the cold tier adds to a run."""
    return 100.0 * (with_tier_s - in_memory_s) / in_memory_s
