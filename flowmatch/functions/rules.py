"""Edge rules: which data edge may play which query edge, as one bit mask per data edge."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, functions as F

from flowmatch.plans.pattern import Pattern, QueryEdge

Rule = Callable[[QueryEdge, Pattern], Column]


def label_test(column: str, labels: tuple[str, ...]) -> Column:
    if not labels:
        return F.lit(True)
    exact = [x for x in labels if not x.endswith("*")]
    tests = [F.col(column).isin(exact)] if exact else []
    tests += [F.col(column).startswith(x[:-1]) for x in labels if x.endswith("*")]
    return reduce(lambda a, b: a | b, tests)


def label_rule(edge: QueryEdge, pattern: Pattern) -> Column:
    """Labels and end types are those asked for; what the query leaves empty matches all.  A null never matches."""
    test = label_test("label", edge.labels)
    for column, name in (("src_type", edge.src), ("dst_type", edge.dst)):
        if (kind := pattern.vertex(name).label) is not None:
            test = test & (F.col(column) == kind)
    return test & F.expr(edge.where) if edge.where else test


def subset_rule(edge: QueryEdge, pattern: Pattern) -> Column:
    """Vertex types hold several labels joined by '|'; the query's are among them."""
    test = label_test("label", edge.labels)
    for column, name in (("src_type", edge.src), ("dst_type", edge.dst)):
        if (kind := pattern.vertex(name).label) is not None:
            test = test & (F.size(F.array_except(F.split(F.lit(kind), r"\|"), F.split(F.col(column), r"\|"))) == 0)
    return test & F.expr(edge.where) if edge.where else test


def attribute_rule(predicates: dict[str, Column]) -> Rule:
    """The label rule, and for each named query edge a condition on any columns of the edges."""
    return lambda edge, pattern: label_rule(edge, pattern) & predicates.get(edge.name, F.lit(True))


def python_rule(fn: Callable[..., bool], columns: list[str]) -> Rule:
    """A rule in Python: ``fn(query edge, *columns)``, run once for each distinct combination of values in an Arrow batch.

    The slow path; native rules stay in generated code.
    """

    def rule(edge: QueryEdge, pattern: Pattern) -> Column:
        @F.pandas_udf("boolean")
        def test(*values):
            import pandas as pd

            rows = pd.DataFrame(dict(enumerate(values))).astype(object)
            rows = rows.where(rows.notna(), None)
            seen: dict = {}
            return pd.Series([seen[r] if r in seen else seen.setdefault(r, bool(fn(edge, *r))) for r in rows.itertuples(index=False, name=None)])

        return test(*[F.col(c) for c in columns])

    return rule


def bit(mask: Column | str, at: int) -> Column:
    return F.getbit(mask, F.lit(at)) == 1


def mask_of(tests: list[tuple[int, Column]]) -> Column:
    """One BIGINT of the given bits; a null test leaves its bit unset."""
    parts = [F.when(test, F.lit(1 << at)).otherwise(F.lit(0)).cast("bigint") for at, test in tests]
    return reduce(lambda a, b: a.bitwiseOR(b), parts, F.lit(0).cast("bigint"))


def local_masks(edges: DataFrame, pattern: Pattern, rule: Rule = label_rule) -> DataFrame:
    """Adds ``local_mask``: bit i for query edge i.  One narrow projection for all query edges."""
    return edges.withColumn("local_mask", mask_of([(i, rule(e, pattern)) for i, e in enumerate(pattern.edges)]))
