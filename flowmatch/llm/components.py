"""Connected components of a distributed edge list."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from flowmatch.llm.common import written


def components(edges: DataFrame) -> DataFrame:
    """From (a, b) to (id, component), one row for every end of an edge; component is the least id reachable.

    Alternating stars: every vertex hangs its larger neighbours on the least vertex it sees, then its smaller ones and
    itself.  Edges never multiply, the number of rounds is logarithmic, and each round is written before the next, so a
    lost executor never recomputes more than a round.  Sums by vertex combine before the shuffle; the joins are plain
    equi-joins, in which adaptive execution splits the keys of hubs.
    """
    e = written(edges.where("a <> b").select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")).distinct(), "links")
    mark = e.agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("hi", "lo")).alias("x")).first()
    while mark.n:
        both = e.select(F.col("hi").alias("u"), F.col("lo").alias("v")).unionByName(e.select(F.col("lo").alias("u"), F.col("hi").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("hi"), F.col("m").alias("lo")).distinct()
        seen = large.groupBy("hi").agg(F.min("lo").alias("m"))
        hung = large.join(seen, "hi").where("lo <> m").select(F.col("lo").alias("hi"), F.col("m").alias("lo"))
        e = written(hung.unionByName(seen.select("hi", F.col("m").alias("lo"))).distinct(), "links")
        before, mark = mark, e.agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("hi", "lo")).alias("x")).first()
        if before == mark:
            break
    return e.select(F.col("hi").alias("id"), F.col("lo").alias("component")).unionByName(e.select(F.col("lo").alias("id"), F.col("lo").alias("component")).distinct())
