"""Graph utilities: degrees, hubs, neighbourhoods, components, label statistics, slots."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, Window, functions as F

from flowmatch.sources.snapshots import StreamConfig
from flowmatch.sources.storage import stored


def degrees(edges: DataFrame) -> DataFrame:
    """(vid, label, out_degree, in_degree) of every vertex and label that it has edges of."""
    one, none = F.lit(1).cast("long"), F.lit(0).cast("long")
    ends = edges.select(F.col("src").alias("vid"), "label", one.alias("o"), none.alias("i")).unionByName(edges.select(F.col("dst").alias("vid"), "label", none.alias("o"), one.alias("i")))
    return ends.groupBy("vid", "label").agg(F.sum("o").alias("out_degree"), F.sum("i").alias("in_degree"))


def hubs(edges: DataFrame, k: int) -> DataFrame:
    """The ``k`` vertices with the most edges; ids break ties."""
    return degrees(edges).groupBy("vid").agg(F.sum(F.col("out_degree") + F.col("in_degree")).alias("degree")).orderBy(F.desc("degree"), "vid").limit(k)


def label_type_cube(edges: DataFrame) -> DataFrame:
    """Edges by label and source type, by each alone, and in all."""
    return edges.cube("label", "src_type").agg(F.count("*").alias("n"))


def khop(edges: DataFrame, starts: DataFrame, hops: int, keep: Callable[[DataFrame], DataFrame] = stored) -> DataFrame:
    """(start, vid, hops): the vertices within so many edges of each start, whatever their direction, and the least number."""
    both = keep(edges.select(F.col("src").alias("a"), F.col("dst").alias("b")).unionByName(edges.select(F.col("dst").alias("a"), F.col("src").alias("b"))).distinct())
    seen = front = starts.select(F.col("vid").alias("start"), "vid", F.lit(0).alias("hops"))
    for k in range(1, hops + 1):
        reached = front.join(both, front["vid"] == both["a"]).select("start", F.col("b").alias("vid")).distinct()
        front = keep(reached.join(seen.select("start", "vid"), ["start", "vid"], "left_anti").withColumn("hops", F.lit(k)))
        seen = seen.unionByName(front)
    return seen


def components(edges: DataFrame, keep: Callable[[DataFrame], DataFrame] = stored) -> DataFrame:
    """(vid, component): the least vertex reachable, for every end of an edge.

    Each round hangs all that a vertex sees on the least of it, so paths halve and rounds grow with the logarithm of the
    longest; every round is written.
    """
    links = keep(edges.select(F.greatest("src", "dst").alias("hi"), F.least("src", "dst").alias("lo")).distinct())
    mark = None
    while True:
        both = links.select(F.col("hi").alias("u"), F.col("lo").alias("v")).unionByName(links.select(F.col("lo").alias("u"), F.col("hi").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        hung = both.join(least, "u").select(F.greatest("v", "m").alias("hi"), F.least("v", "m").alias("lo"))
        links = keep(hung.unionByName(least.select(F.col("u").alias("hi"), F.col("m").alias("lo"))).distinct())
        now = links.agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("hi", "lo")).alias("x")).first()
        if now == mark:
            return links.groupBy(F.col("hi").alias("vid")).agg(F.min("lo").alias("component"))
        mark = now


def slot_ids(edges: DataFrame, config: StreamConfig, keep: Callable[[DataFrame], DataFrame] = stored) -> DataFrame:
    """(edge_id, src, slot): the place of every edge of a sliding window in its source's adjacency, freed places first in, first out.

    A snapshot's inserts take places freed by earlier snapshots and, where these do not suffice, new ones.  Which edges
    reuse a place follows from counts; the n-th of a source to do so follows the n-th to have left, and these links are
    shortened by pointer doubling, so rounds grow with the logarithm of the longest line of owners.
    """
    rows = edges.select("edge_id", "src", config.born().alias("born"), config.dies().alias("dies")).where("born < dies")
    moves = rows.select("src", F.col("born").alias("s"), F.lit(1).alias("i"), F.lit(0).alias("x")).unionByName(rows.select("src", F.col("dies").alias("s"), F.lit(0).alias("i"), F.lit(1).alias("x")))
    by = Window.partitionBy("src").orderBy("s")
    upto, before = by.rowsBetween(Window.unboundedPreceding, 0), by.rowsBetween(Window.unboundedPreceding, -1)
    per = moves.groupBy("src", "s").agg(F.sum("i").alias("i"), F.sum("x").alias("x"))
    per = per.withColumn("need", F.coalesce(F.sum(F.col("i") - F.col("x")).over(before), F.lit(0)) + F.col("i"))
    per = per.withColumn("slots", F.max("need").over(upto)).withColumn("had", F.coalesce(F.max("need").over(before), F.lit(0)))
    per = per.withColumn("new", F.col("slots") - F.col("had")).withColumn("reused_before", F.coalesce(F.sum(F.col("i") - F.col("new")).over(before), F.lit(0)))
    placed = rows.withColumn("k", F.row_number().over(Window.partitionBy("src", "born").orderBy("edge_id"))).join(per.select("src", F.col("s").alias("born"), "i", "new", "had", "reused_before"), ["src", "born"])
    again = F.col("k") <= F.col("i") - F.col("new")
    placed = placed.withColumn("nth", F.when(again, F.col("reused_before") + F.col("k"))).withColumn("slot", F.when(~again, F.col("had") + F.col("k") - (F.col("i") - F.col("new"))))
    left = placed.select(F.col("src").alias("fs"), F.col("edge_id").alias("heir_of"), F.row_number().over(Window.partitionBy("src").orderBy("dies", "edge_id")).alias("fn"))
    now = keep(placed.join(left, (F.col("src") == F.col("fs")) & (F.col("nth") == F.col("fn")), "left").select("edge_id", "src", "slot", "heir_of"))
    while not now.where("slot is null").isEmpty():
        of = now.select(F.col("edge_id").alias("of"), F.col("slot").alias("its"), F.col("heir_of").alias("then"))
        now = keep(now.join(of, F.col("heir_of") == F.col("of"), "left").select("edge_id", "src", F.coalesce("slot", "its").alias("slot"), F.when(F.col("slot").isNull() & F.col("its").isNull(), F.col("then")).alias("heir_of")))
    return now.select("edge_id", "src", F.col("slot").cast("long").alias("slot"))
