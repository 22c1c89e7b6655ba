"""Relation semantics: dual and strong simulation, and their changes between snapshots."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, functions as F

from flowmatch.functions.rules import Rule, bit, label_rule, local_masks, mask_of
from flowmatch.operators.balls import blocks_of, strong_masks
from flowmatch.plans.pattern import Pattern, diameter



def _start(edges: DataFrame, pattern: Pattern, key: list[str]) -> DataFrame:
    ends = edges.select(*key, F.col("src").alias("vid"), F.col("src_type").alias("vtype")).unionByName(edges.select(*key, F.col("dst").alias("vid"), F.col("dst_type").alias("vtype")))
    types = ends.groupBy(*key, "vid").agg(F.min("vtype").alias("vtype"))
    return types.select(*key, "vid", mask_of([(i, F.lit(True) if v.label is None else F.col("vtype") == v.label) for i, v in enumerate(pattern.vertices)]).alias("mask"))


def _round(edges: DataFrame, masks: DataFrame, pattern: Pattern, key: list[str]) -> DataFrame:
    """One step down: a vertex keeps u if for every query edge at u some data edge matches it with the far end in the relation.

    All query vertices and edges share two joins and one aggregation.
    """
    both = edges.join(masks.select(*key, F.col("vid").alias("src"), F.col("mask").alias("sm")), [*key, "src"]).join(masks.select(*key, F.col("vid").alias("dst"), F.col("mask").alias("dm")), [*key, "dst"])
    out = mask_of([(i, bit("local_mask", i) & bit("dm", pattern.bit(e.dst))) for i, e in enumerate(pattern.edges)])
    into = mask_of([(i, bit("local_mask", i) & bit("sm", pattern.bit(e.src))) for i, e in enumerate(pattern.edges)])
    zero = F.lit(0).cast("bigint")
    seen = both.select(*key, F.col("src").alias("vid"), out.alias("o"), zero.alias("n")).unionByName(both.select(*key, F.col("dst").alias("vid"), zero.alias("o"), into.alias("n")))
    got = seen.groupBy(*key, "vid").agg(F.bit_or("o").alias("o"), F.bit_or("n").alias("n"))
    keep = []
    for i, v in enumerate(pattern.vertices):
        need_out = sum(1 << k for k, e in enumerate(pattern.edges) if e.src == v.name)
        need_in = sum(1 << k for k, e in enumerate(pattern.edges) if e.dst == v.name)
        has = lambda c, need: F.coalesce(F.col(c), zero).bitwiseAND(F.lit(need).cast("bigint")) == need
        keep.append((i, has("o", need_out) & has("n", need_in)))
    return masks.join(got, [*key, "vid"], "left").select(*key, "vid", F.col("mask").alias("was"), F.col("mask").bitwiseAND(mask_of(keep)).alias("mask"))


def _fixpoint(edges: DataFrame, masks: DataFrame, pattern: Pattern, key: list[str], keep) -> DataFrame:
    while True:
        new = keep(_round(edges, masks, pattern, key))
        changed = not new.where("was <> mask").isEmpty()
        masks = new.drop("was").where("mask <> 0")
        if not changed:
            return masks


def _whole(masks: DataFrame, pattern: Pattern, key: list[str]) -> DataFrame:
    """Only relations in which every query vertex has a match."""
    full = (1 << len(pattern.vertices)) - 1
    if key:
        return masks.join(masks.groupBy(*key).agg(F.bit_or("mask").alias("all")).where(F.col("all") == full).select(*key), key, "left_semi")
    return masks.crossJoin(F.broadcast(masks.agg(F.bit_or("mask").alias("all")))).where(F.col("all") == full).drop("all")  # one row


def pairs(masks: DataFrame, pattern: Pattern, key: list[str] | None = None) -> DataFrame:
    names = F.array(*[F.when(F.getbit("mask", F.lit(i)) == 1, F.lit(v.name)) for i, v in enumerate(pattern.vertices)])
    return masks.select(*(key or []), F.explode(F.array_compact(names)).alias("qvertex"), "vid")


def simulation_masks(edges: DataFrame, pattern: Pattern, rule: Rule = label_rule, keep=lambda df: df) -> DataFrame:
    edges = keep(local_masks(edges, pattern, rule).where("local_mask <> 0").select("src", "dst", "src_type", "dst_type", "local_mask"))
    return _whole(_fixpoint(edges, _start(edges, pattern, []), pattern, [], keep), pattern, [])


def dual_simulation(edges: DataFrame, pattern: Pattern, rule: Rule = label_rule, keep=lambda df: df) -> DataFrame:
    """The greatest relation (qvertex, vid): each pair has, for every query edge at its vertex, a matching edge to a pair; empty if a query vertex has none."""
    return pairs(simulation_masks(edges, pattern, rule, keep), pattern)


def _grown(start: DataFrame, edges: DataFrame, hops: int, keep) -> DataFrame:
    """(id, w): what lies within so many hops of each id, itself included; of the edges only those at what is reached are joined."""
    found = start.select("id", F.col("id").alias("w")).distinct()
    for _ in range(hops):
        found = keep(found)
        out = edges.select(F.col("src").alias("w"), F.col("dst").alias("to")).join(found, "w")
        into = edges.select(F.col("dst").alias("w"), F.col("src").alias("to")).join(found, "w")
        found = found.unionByName(out.unionByName(into).select("id", F.col("to").alias("w"))).distinct()
    return found


def _near(candidates: DataFrame, edges: DataFrame, hops: int, keep) -> DataFrame:
    """The (center, vid) that are at most so many hops apart, whatever the edges' labels: both sides grow, and meet halfway."""
    half = hops // 2
    one = _grown(candidates.select(F.col("center").alias("id")), edges, half, keep).withColumnRenamed("id", "center")
    two = _grown(candidates.select(F.col("vid").alias("id")), edges, hops - half, keep).withColumnRenamed("id", "vid")
    return candidates.join(keep(one), "center").join(keep(two), ["vid", "w"], "left_semi").select("center", "vid").distinct()


def strong_simulation(edges: DataFrame, pattern: Pattern, rule: Rule = label_rule, keep=lambda df: df, at_once: int = 2_000_000, work: int = 1 << 32) -> DataFrame:
    """(center, qvertex, vid): dual simulation within the ball around each center, as wide as the pattern, held to the center's component.

    A graph of at most ``at_once`` pairs of joined vertices goes whole to blocks of centers, unless its pairs times the words
    of 64 centers are over ``work``; of other graphs, balls are listed.  Both ways are exact.
    """
    dual = keep(simulation_masks(edges, pattern, rule, keep))
    if edges.agg(F.approx_count_distinct(F.struct("src", "dst")).alias("n")).first().n <= 2 * at_once:
        zero = F.lit(0).cast("bigint")
        joined = local_masks(edges.where("src is not null and dst is not null"), pattern, rule)
        joined = keep(joined.groupBy("src", "dst").agg(F.bit_or(F.coalesce("local_mask", zero)).alias("local_mask")))
        n, centers = joined.count(), dual.count()
        if n <= at_once and n * -(-centers // 64) <= work:
            return pairs(strong_masks(joined, dual, pattern, diameter(pattern), blocks_of(centers)), pattern, ["center"])
    return _listed_balls(edges, dual, pattern, rule, keep)


def _listed_balls(edges: DataFrame, dual: DataFrame, pattern: Pattern, rule: Rule, keep) -> DataFrame:
    """Strong simulation from ``dual``, the masks of the whole graph's dual simulation, by rows (center, vid).

    Centers and balls are cut to what dual simulation of the whole graph leaves, as strong simulation lies within it, and to
    what matching edges inside the ball connect with the center: other parts of a ball change nothing there, as the pattern is
    connected.  So a center walks along matching edges; what it reaches in more steps than the ball is wide stays only if all
    edges of the graph make it nearer.
    """
    every = edges.select("src", "dst")
    near = keep(local_masks(edges, pattern, rule).where("local_mask <> 0").select("src", "dst", "src_type", "dst_type", "local_mask"))
    near = keep(near.join(dual.select(F.col("vid").alias("src")), "src", "left_semi").join(dual.select(F.col("vid").alias("dst")), "dst", "left_semi"))
    link = keep(near.select("src", "dst").unionByName(near.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct())
    width, steps = diameter(pattern), 0
    fresh = ball = keep(dual.select(F.col("vid").alias("center"), "vid"))
    while not fresh.isEmpty():
        steps += 1
        fresh = fresh.join(link, fresh["vid"] == link["src"]).select("center", F.col("dst").alias("vid")).distinct().join(ball, ["center", "vid"], "left_anti")
        fresh = keep(fresh if steps <= width else _near(keep(fresh), every, width, keep))
        ball = keep(ball.unionByName(fresh))
    inside = ball.join(dual, "vid").select("center", "vid", "mask")
    own = near.join(inside.select("center", F.col("vid").alias("src")), "src").join(inside.select(F.col("center"), F.col("vid").alias("dst")), ["center", "dst"])
    own = keep(own.select("center", "src", "dst", "local_mask"))
    masks = _whole(_fixpoint(own, inside, pattern, ["center"], keep), pattern, ["center"])
    masks = keep(masks.join(masks.where("center = vid").select("center"), "center", "left_semi"))
    # The component of the center among the edges that the relation uses.
    both = own.join(masks.select("center", F.col("vid").alias("src"), F.col("mask").alias("sm")), ["center", "src"]).join(masks.select("center", F.col("vid").alias("dst"), F.col("mask").alias("dm")), ["center", "dst"])
    used = reduce(lambda a, b: a | b, [bit("local_mask", i) & bit("sm", pattern.bit(e.src)) & bit("dm", pattern.bit(e.dst)) for i, e in enumerate(pattern.edges)])
    step = both.where(used).select("center", "src", "dst")
    step = keep(step.unionByName(step.select("center", F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct())
    seen = masks.where("center = vid").select("center", "vid")
    size = -1
    while size != (n := seen.count()):
        size = n
        seen = keep(seen.unionByName(seen.join(step.withColumnRenamed("src", "vid"), ["center", "vid"]).select("center", F.col("dst").alias("vid"))).distinct())
    return pairs(masks.join(seen, ["center", "vid"], "left_semi"), pattern, ["center"])


def dual_simulation_windows(edges: DataFrame, pattern: Pattern, config, rule: Rule = label_rule, keep=lambda df: df) -> DataFrame:
    """(snapshot_id, qvertex, vid): the dual simulation of every snapshot of a sliding window, all in one fixpoint.

    An edge goes to the window / stride snapshots that see it, and the relation is kept by snapshot, so rounds are shared.
    """
    seen = F.explode(F.sequence(config.born(), config.dies() - 1))
    own = local_masks(edges.where(config.born() < config.dies()), pattern, rule).where("local_mask <> 0")
    own = keep(own.select(seen.alias("snapshot_id"), "src", "dst", "src_type", "dst_type", "local_mask"))
    key = ["snapshot_id"]
    return pairs(_whole(_fixpoint(own, _start(own, pattern, key), pattern, key, keep), pattern, key), pattern, key)


def relation_changes(relation: DataFrame) -> DataFrame:
    """From the relation of each snapshot, the pairs that enter and leave, with sign; before the first and after the last there is none."""
    keys = ["snapshot_id", "qvertex", "vid"]
    plus = relation.join(relation.withColumn("snapshot_id", F.col("snapshot_id") + 1), keys, "left_anti").withColumn("sign", F.lit(1))
    minus = relation.withColumn("snapshot_id", F.col("snapshot_id") + 1).join(relation, keys, "left_anti").withColumn("sign", F.lit(-1))
    return plus.unionByName(minus)


def parallel_collapsed(edges: DataFrame) -> DataFrame:
    """One edge for each (src, dst, label), the oldest: what indexes over vertex pairs see."""
    return edges.groupBy("src", "dst", "label").agg(*[F.min_by(c, "edge_id").alias(c) for c in ("src_type", "dst_type", "ts", "weight")], F.count("*").alias("multiplicity"), F.min("edge_id").alias("edge_id"))


