"""Numbers of embeddings without the embeddings: query vertices are summed out one after another."""

from __future__ import annotations

from functools import reduce
from math import factorial, prod

from pyspark.sql import Column, DataFrame, Window, functions as F

from flowmatch.functions.rules import Rule, label_rule
from flowmatch.operators.enumeration import Semantics, matches, side
from flowmatch.plans.pattern import Pattern
from flowmatch.plans.planner import fan_statistics


def _partitions(items: list[str]) -> list[list[list[str]]]:
    if not items:
        return [[]]
    head, out = items[0], []
    for rest in _partitions(items[1:]):
        out.append([[head], *rest])
        out += [[*rest[:i], [head, *b], *rest[i + 1 :]] for i, b in enumerate(rest)]
    return out


def _summed_out(factors: list[tuple[list[str], DataFrame, float]], domain: dict[str, float]) -> DataFrame:
    """(n): the sum over all vertices of the product of the factors' weights ``n``.

    ``domain`` and the factors' third parts: about how many values a vertex takes and how many rows a factor has.  The vertex
    whose factors' join has the fewest rows goes first: not the hub, at which all pairs of its neighbours would meet.
    """

    def joined(v: str) -> float:
        own = [f for f in factors if v in f[0]]
        seen = [w for vs, _, _ in own for w in vs]
        return prod(size for _, _, size in own) / prod(domain[w] ** (seen.count(w) - 1) for w in set(seen))

    while left := sorted({v for vs, _, _ in factors for v in vs}):
        out = min(left, key=lambda v: (joined(v), v))
        most = joined(out)
        own = [f for f in factors if out in f[0]]
        names, rows, _ = own[0]
        for more, new, _ in own[1:]:
            on = [v for v in names if v in more]
            rows = rows.join(new.withColumnRenamed("n", "m"), on).withColumn("n", F.col("n") * F.col("m")).drop("m")
            names = [*names, *[v for v in more if v not in names]]
        names = [v for v in names if v != out]
        rows = rows.groupBy(*names).agg(F.sum("n").alias("n"))
        factors = [*[f for f in factors if out not in f[0]], (names, rows, min(most, prod(domain[v] for v in names)))]
    return reduce(lambda a, b: a.crossJoin(b.withColumnRenamed("n", "m")).select((F.col("n") * F.col("m")).alias("n")), [rows for _, rows, _ in factors])  # one row each


def count_embeddings(edges: DataFrame, pattern: Pattern, semantics: Semantics = Semantics(), rule: Rule = label_rule) -> DataFrame:
    """(n): as many as :func:`enumerate_all` has rows, for semantics without times and symmetry.

    Homomorphisms are sums of products over pairs of vertices with the numbers of their parallel edges.  The injective ones
    among them follow by inclusion and exclusion over the ways in which vertices may coincide; vertices of different types,
    and without self-loops the ends of an edge, do not.
    """
    if semantics.pairs or semantics.symmetry or semantics.within is not None:
        raise ValueError("times and symmetry take rows")
    pattern = pattern.mandatory()
    if semantics.injective and len({e.ends() for e in pattern.edges}) < len(pattern.edges):
        raise ValueError("for injective counts query edges have different ends")
    names = [v.name for v in pattern.vertices]
    blocks = [[[v] for v in names]]
    if semantics.injective:
        loops = not edges.where("src = dst").isEmpty()
        kind = {v.name: v.label for v in pattern.vertices}
        together = lambda b: len({kind[v] for v in b} - {None}) < 2 and (loops or not any(e.ends() <= set(b) and e.src != e.dst for e in pattern.edges))
        blocks = [p for p in _partitions(names) if all(together(b) for b in p)]
    stats, parts = fan_statistics(edges), []
    for p in blocks:
        to = {v: b[0] for b in p for v in b}
        factors, domain = [], {}
        for e in pattern.edges:
            own = side(matches(edges, e, pattern, rule), e, False).drop(f"e_{e.name}")
            ends = sorted({to[e.src], to[e.dst]})
            if len(ends) == 1 and e.src != e.dst:
                own = own.where(F.col(f"v_{e.src}") == F.col(f"v_{e.dst}")).drop(f"v_{e.dst}")
                own = own.withColumnRenamed(f"v_{e.src}", ends[0])
            else:
                own = own.select(*[F.col(f"v_{v}").alias(to[v]) for v in dict.fromkeys((e.src, e.dst))])
            for v, n in zip((e.src, e.dst), stats.distinct(e)):
                domain[to[v]] = min(domain.get(to[v], n), n)
            factors.append((ends, own.groupBy(*ends).agg(F.count("*").alias("n")), max(1, stats.edges(e))))
        sign = prod((-1) ** (len(b) - 1) * factorial(len(b) - 1) for b in p)
        parts.append(_summed_out(factors, domain).select((F.col("n") * sign).alias("n")))
    every = reduce(lambda a, b: a.unionByName(b), parts)
    return every.agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n"))


def count_lost_context(edges: DataFrame, collapsed: DataFrame, pattern: Pattern, within: int) -> DataFrame:
    """(n): tuples of vertices of the pattern that ``collapsed`` reports and no embedding of ``edges`` with rising times within ``within`` has.

    For patterns x -e-> r <-p- y -c-> q in this order of edges and times.  ``collapsed`` has one edge for each pair and label of
    ``edges``, so the first number is a count over it and the tuples with context are among its tuples.  Of these, (y, r, q)
    stand for spans of time in which an edge at r has context, and x counts by the first of its edges in a span.
    """
    first, second, third = pattern.edges
    (x, r), (y, q) = (first.src, first.dst), (third.src, third.dst)
    if (second.src, second.dst) != (y, r) or len({x, r, y, q}) < 4 or not all(e.directed for e in pattern.edges):
        raise ValueError("the pattern is x -e-> r <-p- y -c-> q")
    if len({e.labels for e in pattern.edges}) < 3 or any(len(e.labels) != 1 or e.labels[0].endswith("*") for e in pattern.edges):
        raise ValueError("the three edges have different labels, one each")  # else a pair of vertices may have several collapsed edges
    own = lambda e: matches(edges, e, pattern).where("ts is not null")
    p, c = own(second).select(F.col("src").alias("y"), F.col("dst").alias("r"), F.col("ts").alias("tp")), own(third).select(F.col("src").alias("y"), F.col("dst").alias("q"), F.col("ts").alias("tc"))
    # Times meet within pieces of the span, so that no vertex's whole history does.
    piece = lambda t: F.floor(F.col(t) / within)
    c = c.select("*", F.explode(F.array(piece("tc"), piece("tc") - 1)).alias("k"))
    spans = p.withColumn("k", piece("tp")).join(c, ["y", "k"]).where((F.col("tp") < F.col("tc")) & (F.col("tc") - F.col("tp") < within) & (F.col("r") != F.col("q")) & (F.col("y") != F.col("r")) & (F.col("y") != F.col("q")))
    spans = spans.groupBy("y", "r", "q").agg(F.array_sort(F.collect_set(F.struct((F.col("tc") - within).alias("lo"), F.col("tp").alias("hi")))).alias("all"))
    return _with_context(spans, own(first).select(F.col("src").alias("x"), F.col("dst").alias("r"), "ts"), within, count_embeddings(collapsed, pattern))


def _merged(spans: str) -> Column:
    """Sorted spans [lo, hi) joined where they overlap or touch."""
    start = F.array().cast("array<struct<lo:bigint,hi:bigint>>")

    def add(acc: Column, s: Column) -> Column:
        last = F.try_element_at(acc, F.lit(-1))
        joined = F.struct(last.lo.alias("lo"), F.greatest(last.hi, s.hi).alias("hi"))
        return F.when(F.size(acc) == 0, F.array(s)).when(last.hi >= s.lo, F.concat(F.slice(acc, 1, F.greatest(F.size(acc) - 1, F.lit(0))), F.array(joined))).otherwise(F.concat(acc, F.array(s)))

    return F.aggregate(spans, start, add)


def _with_context(spans: DataFrame, firsts: DataFrame, within: int, reported: DataFrame) -> DataFrame:
    spans = spans.select("y", "r", "q", _merged("all").alias("all")).select("y", "r", "q", (F.size("all") > 1).alias("several"), F.inline("all"))
    pieces = F.explode(F.sequence(F.floor(F.col("lo") / within), F.floor((F.col("hi") - 1) / within)))
    spans = spans.select("*", pieces.alias("k"))
    before = firsts.withColumn("before", F.lag("ts").over(Window.partitionBy("x", "r").orderBy("ts"))).withColumn("k", F.floor(F.col("ts") / within))
    hits = before.join(spans, ["r", "k"]).where((F.col("ts") >= F.col("lo")) & (F.col("ts") < F.col("hi")) & (F.col("before").isNull() | (F.col("before") < F.col("lo"))) & (F.col("x") != F.col("y")) & (F.col("x") != F.col("r")) & (F.col("x") != F.col("q")))
    once = hits.where("not several").agg(F.count("*").alias("n"))
    again = hits.where("several").select("x", "r", "y", "q").distinct().agg(F.count("*").alias("n"))
    have = once.unionByName(again).agg(F.sum("n").alias("m"))
    return reported.crossJoin(have).select((F.col("n") - F.col("m")).alias("n"))
