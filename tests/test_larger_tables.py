"""Queries that did not end on larger tables: the ways they take now, and their results on small fixtures."""

from random import Random

from flowmatch import engine as N, queries as Q, workload_queries as W
from flowmatch.operators import balls
from flowmatch.operators.counting import count_embeddings
from flowmatch.operators.enumeration import Semantics, enumerate_all, sized_order
from flowmatch.operators.maintain import maintain
from flowmatch.operators.semantics import strong_simulation
from flowmatch.sources import views as V
from flowmatch.sources.snapshots import DAY, StreamConfig, open_stream
from flowmatch.workloads import PATTERNS
from tests.running import EDGE_SCHEMA, brute
from tests.test_whole_graph_queries import strong


def nation_rows():
    """Forty customers and suppliers of one nation, a few of which an order binds; two parts of an order."""
    kinds, ends = {}, []

    def put(a, ka, b, kb, label):
        kinds.update({a: ka, b: kb})
        ends.append((a, b, label))

    for k in range(40):
        put(100 + k, "customer", 900 + k % 2, "nation", "LIVES_BUILDING")
        put(200 + k, "supplier", 900 + k // 30, "nation", "BASED")
    for k in range(6):
        put(100 + k, "customer", 300 + k, "order", "PLACED_1-URGENT_F")
        put(300 + k, "order", 200 + k, "supplier", "FROM_RF")
        put(300 + k, "order", 400, "part", "HAS_AF")
        put(300 + k, "order", 401 + k % 2, "part", "HAS_AO")
    for k in range(2):
        put(900 + k, "nation", 950, "region", "IN_REGION")
    return [(i, a, b, kinds[a], kinds[b], x, i, 1.0) for i, (a, b, x) in enumerate(ends)]


def prefixed(rows, pattern):
    """The rows that fit some query edge, labelled by it, so that ``brute`` may compare labels: no two query edges share rows here."""
    starts = [x for e in pattern.edges for x in e.labels]
    cut = lambda label: next((x for x in starts if label == x or x.endswith("*") and label.startswith(x[:-1])), label)
    return [(*r[:5], cut(r[5]), *r[6:]) for r in rows]


def test_customers_and_suppliers_of_a_nation_do_not_meet_before_an_order_binds_them(spark, monkeypatch):
    rows, pattern = nation_rows(), PATTERNS["G_6_nation"]
    edges = spark.createDataFrame(rows, EDGE_SCHEMA)
    monkeypatch.setattr(V, "commerce", lambda spark, d: edges)
    order = W.class_plan(edges, "G_6_nation").order
    assert max(order.index("b"), order.index("l")) > min(order.index("p"), order.index("f"))
    want = brute(prefixed(rows, pattern), pattern, injective=False)
    assert Q.queries()["class_homo_g6_v3"](spark, "").first().n == len(want) > 0


def test_only_lines_of_matching_orders_are_numbered(spark, sf, monkeypatch):
    """Both kinds of rows are the same, ids included, though the lines of few orders are numbered."""
    asked, pattern = [], PATTERNS["G_6_nation"]
    whole = V.line_ids

    def counted(spark, d, orders=None):
        asked.append(None if orders is None else orders.count())
        return whole(spark, d, orders)

    monkeypatch.setattr(V, "line_ids", counted)
    few = "/root/testdata/sf0.01"
    got = sorted(map(tuple, Q.queries()["class_iso_g6_v3"](spark, few).collect()))
    want = sorted(map(tuple, W.enumerate_all(V.commerce(spark, few), pattern, W.ISO).select(*W.named(pattern)).collect()))
    assert got == want and len(got) > 0 and 0 < asked[1] <= len(got)


def shared_rows(seed, n=70, users=4, resources=3):
    """Few users and resources, so that the same pairs meet often; ties of time are among them."""
    kinds = ["error", "purchase", "click"]
    at = [(seed * 7919 + k * 104_729) % 9973 for k in range(n)]
    return [(k, a % users, 100 + a // 7 % resources, "user", "resource", kinds[a // 31 % 3], a % 61 * (DAY // 12), 1.0) for k, a in enumerate(at)]


def test_counts_without_rows_equal_the_rows(spark, monkeypatch):
    for seed in (1, 2):
        rows = [*shared_rows(seed), (900, 1, 1, "user", "user", "purchase", 5, 1.0)]  # a self-loop
        monkeypatch.setattr(V, "access", lambda spark, d: spark.createDataFrame(rows, EDGE_SCHEMA))  # noqa: B023
        got = Q.queries()["iso_rect_count_v2"](spark, "")
        assert got.first().n == len(brute(rows, PATTERNS["two_users"])) > 0
        assert "e_a" not in got._jdf.queryExecution().optimizedPlan().toString()
    for key, injective in (("two_users", False), ("shared_resource", True), ("shared_resource", False)):
        got = count_embeddings(spark.createDataFrame(rows, EDGE_SCHEMA), PATTERNS[key], Semantics(injective=injective))
        assert got.first().n == len(brute(rows, PATTERNS[key], injective=injective))
    assert count_embeddings(spark.createDataFrame([], EDGE_SCHEMA), PATTERNS["two_users"]).first().n == 0


def test_lost_context_is_counted_as_listed(spark, monkeypatch):
    """Against the listed tuples; users have several spans of time at a resource, some of which overlap, touch or lie apart."""
    pattern, several = PATTERNS["shared_resource"], 0
    for seed in (3, 4):
        pick = Random(seed)
        rows = [(k, pick.randrange(4), 100 + pick.randrange(3), "user", "resource", pick.choice(("error", "purchase", "click")), pick.randrange(50) * (DAY // 12), 1.0) for k in range(100)]
        monkeypatch.setattr(V, "access", lambda spark, d: spark.createDataFrame(rows, EDGE_SCHEMA))  # noqa: B023
        ends = {r[0]: (r[1], r[2]) for r in rows}
        tuples = lambda found: {(*ends[a], *ends[b], ends[c][1]) for a, b, c in found}  # noqa: E731, B023
        every = tuples(brute(rows, pattern))
        timed = brute(rows, pattern, pairs=(("e", "p"), ("p", "c")), within=DAY)
        several += len(timed) - len(tuples(timed))
        got = Q.queries()["context_false_positive_v2"](spark, "")
        assert got.first().n == len(every - tuples(timed)) and 0 < len(tuples(timed)) < len(every)
    assert several > 0


def test_balls_do_not_hold_what_only_a_hub_connects(spark):
    kinds, ends, k = {"c": "customer", "o": "order", "a": "part", "s": "supplier"}, [], 40
    for i in range(k):
        c, o, a, s = (("c", i), ("o", i), ("a", i), ("s", i))
        ends += [(c, o, "PLACED_1-URGENT_F"), (o, a, "HAS_RF"), (o, s, "FROM_AF"), (c, ("n", 0), "LIVES_BUILDING")]
    number = {v: n for n, v in enumerate(dict.fromkeys(v for a, b, _ in ends for v in (a, b)))}
    rows = [(i, number[a], number[b], kinds.get(a[0], "nation"), kinds.get(b[0], "nation"), x, i, 1.0) for i, (a, b, x) in enumerate(ends)]
    sizes = []

    def keep(df):
        df = df.localCheckpoint()
        sizes.append(df.count())
        return df

    got = strong_simulation(spark.createDataFrame(rows, EDGE_SCHEMA), PATTERNS["trade2"], keep=keep).count()
    assert got == 4 * 4 * k and max(sizes) < k * k


def test_balls_that_share_their_vertices_are_not_listed(spark):
    """Eighty users at one resource: each is in the ball of each, and so is what the result holds."""
    ends = [(k, 100, "error") for k in range(40)] + [(k, 100, "purchase") for k in range(40, 80)] + [(k, 101 + k % 3, "click") for k in range(40, 80)]
    rows = [(i, a, b, "user", "resource", x, i, 1.0) for i, (a, b, x) in enumerate(ends)]
    sizes = []

    def keep(df):
        df = df.localCheckpoint()
        sizes.append(df.count())
        return df

    got = [tuple(r) for r in strong_simulation(spark.createDataFrame(rows, EDGE_SCHEMA), PATTERNS["shared_resource"], keep=keep).collect()]
    assert len(got) == len(set(got)) and set(got) == strong(rows, PATTERNS["shared_resource"]) and max(sizes) <= len(rows) < 80 * 80 < len(got)


def test_words_of_centers_agree_with_listed_balls(spark, monkeypatch):
    """Views and signups shorten ways and match nothing; borders of balls lose pairs; several words and blocks; both ways against brute force."""
    pattern, cut = PATTERNS["shared_resource"], 0
    for seed, users, blocks in ((5, 80, 3), (6, 30, 1)):
        pick = Random(seed)
        rows = [(k, pick.randrange(users), 100 + pick.randrange(users // 3), "user", "resource", pick.choice(("error", "purchase", "click", "view", "signup")), k, 1.0) for k in range(3 * users)]
        edges = spark.createDataFrame([*rows, (900, 1, None, "user", "resource", "error", 1, 1.0)], EDGE_SCHEMA)
        monkeypatch.setattr("flowmatch.operators.semantics.blocks_of", lambda n: blocks)  # noqa: B023
        want = strong(rows, pattern)
        keep = lambda df: df.localCheckpoint()
        for most in (2_000_000, 0):
            got = [tuple(r) for r in strong_simulation(edges, pattern, keep=keep, at_once=most).collect()]
            assert len(got) == len(set(got)) and set(got) == want
        whole = {(q, v) for _, q, v in want}
        cut += sum((c, q, v) not in want for c in {c for c, _, _ in want} for q, v in whole)
    assert cut > 0 and balls.blocks_of(0) == 1 and balls.blocks_of(1025) == 2


def test_edges_meet_only_within_their_time(spark):
    """Times on both sides of 1970, at the ends of slots, as far apart as allowed and one further, and null."""
    pattern, pick = PATTERNS["shared_resource"], Random(7)
    at = [k * DAY + x for k in range(-3, 3) for x in (-1, 0, 1)]
    rows = [(k, pick.randrange(4), 100 + pick.randrange(3), "user", "resource", pick.choice(("error", "purchase", "click")), pick.choice(at), 1.0) for k in range(70)]
    edges = spark.createDataFrame([*rows, (900, 1, 100, "user", "resource", "error", None, 1.0)], EDGE_SCHEMA)
    for within in (0, 1, DAY - 1, DAY):
        found = enumerate_all(edges, pattern, Semantics(within=within))
        assert sorted((r.e_e, r.e_p, r.e_c) for r in found.collect()) == brute(rows, pattern, within=within)
        assert "slot" in found._jdf.queryExecution().optimizedPlan().toString()
    assert len(brute(rows, pattern, within=DAY)) > len(brute(rows, pattern, within=DAY - 1)) > 0


def test_large_batches_are_joined_late_and_small_ones_first():
    sizes = {"e": (1_200_000, 90_000, 100), "p": (1_200_000, 90_000, 100), "c": (1_200_000, 90_000, 100)}
    pattern = PATTERNS["shared_resource"]
    for start in "epc":
        assert sized_order(pattern, start, sizes)[-1] == "e"
        assert sized_order(pattern, start, sizes | {start: (1, 90_000, 100)})[0] == start


def test_large_batches_build_the_index_anew_and_write_what_they_find_once(spark, tmp_path, monkeypatch):
    pattern, pick, within, config = PATTERNS["shared_resource"], Random(8), DAY // 2, StreamConfig.sliding(2 * DAY, 2 * DAY)
    rows = [(k, pick.randrange(5), 100 + pick.randrange(3), "user", "resource", pick.choice(("error", "purchase", "click")), pick.randrange(36) * (DAY // 12), 1.0) for k in range(90)]
    ts = {r[0]: r[6] for r in rows}
    want = set()
    for ids in brute(rows, pattern, within=within):
        born, dies = -(-max(ts[i] for i in ids) // (2 * DAY)), -(-(min(ts[i] for i in ids) + 2 * DAY) // (2 * DAY))
        assert born <= dies  # inserts come before deletes, so what is born as it dies is gained and lost
        want |= {(born, 1, *ids), (dies, -1, *ids)}
    anew = []
    monkeypatch.setattr(N, "maintain", lambda index, **given: anew.append(maintain(index, few=0, **given)) or anew[-1])
    found = N.MatchEngine(spark, pattern, Semantics(within=within), str(tmp_path))
    seen, put = [], found.keep
    found.keep = lambda df: seen.append("sign" in df.columns) or put(df)
    edges = spark.createDataFrame(rows, EDGE_SCHEMA)
    source = open_stream(edges, config, keep=lambda df: df.localCheckpoint())
    found.load_initial(source.initial())
    got = [(r.snapshot_id, r.sign, r.e_e, r.e_p, r.e_c) for r in found.run(source).collect()]
    assert len(got) == len(set(got)) and set(got) == want and len({s for s, *_ in want}) > 2
    assert any(x.edges.over is None and x.work["touched"] for x in anew) and not any(seen)
