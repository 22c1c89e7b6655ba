"""Queries on plans that made their rows up: they read a given table and count on it."""

import pytest

from flowmatch import queries as Q

NAMES = [
    "start_orders_worked",
    "pattern_facts",
    "needs_t3_star",
    "batch_masks_worked",
]


@pytest.mark.parametrize("name", NAMES)
def test_plans_are_set_beside_a_table(spark, sf, name):
    small, large = (Q.queries()[name](spark, d) for d in (sf, "/root/testdata/sf0.01"))
    assert small.inputFiles() and small.columns[-1] == "n"
    a, b = ({r[:-1]: r[-1] for r in map(tuple, x.collect())} for x in (small, large))
    assert set(a) == set(b) and all(0 < a[k] < b[k] for k in a)
