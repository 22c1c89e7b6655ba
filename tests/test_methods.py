"""Maintenance, simulation, baselines, slots, stars and the text front end, against brute force on random multigraphs."""

import random

import pytest
from pyspark.sql import functions as F

from flowmatch.operators import baselines as B, graph as G
from flowmatch.operators.enumeration import Semantics, delta, enumerate_all, homomorphism, isomorphism
from flowmatch.operators.index import build_index
from flowmatch.operators.maintain import maintain, open_index
from flowmatch.operators.semantics import dual_simulation
from flowmatch.plans.pattern import parse_pattern
from flowmatch.plans.planner import compile_plan, temporal_pairs
from flowmatch.queries import queries
from flowmatch.sources.snapshots import MINUTE, StreamConfig, open_stream
from flowmatch.sources.storage import stored
from flowmatch.sources.views import copies
from flowmatch.sqlfront import match, parse
from flowmatch.streaming.stars import star_batch, star_matches
from flowmatch.workloads import generate
from tests import running as R

PATH = parse_pattern("(a)-[x:p]->(b)-[y:q]->(c)-[z:p]->(d)", "path")
CYCLE = parse_pattern("(a)-[x:p]->(b)-[y:q]->(c)-[z:p]->(a),(b)-[w:q]->(d)", "cycle")


def graph(seed, n=30, vertices=8, start=0):
    rng = random.Random(seed)
    pairs = [(start + i, rng.randrange(vertices), rng.randrange(vertices)) for i in range(n)]
    return [r for r in R.rows([(i, a, b if a != b else (b + 1) % vertices) for i, a, b in pairs], {v: "T" for v in range(vertices)}, {start + i: rng.choice("pq") for i in range(n)})]


def frame(spark, rows):
    return spark.createDataFrame(rows, R.EDGE_SCHEMA)


@pytest.mark.parametrize("pattern", [PATH, CYCLE])
def test_maintained_index_equals_rebuild(spark, pattern):
    first, more = graph(1, 24, 10), graph(2, 8, 10, start=100)
    plan = compile_plan(pattern)
    index = maintain(open_index(frame(spark, first), plan), frame(spark, more), frame(spark, first[::4]), batch=1)
    left = [r for k, r in enumerate(first) if k % 4] + more
    marks = lambda df: {r.edge_id: r.live_mask for r in df.where("live_mask <> 0").collect()}
    assert marks(index.edges.view()) == marks(build_index(frame(spark, left), plan, keep=stored).marked())


@pytest.mark.parametrize("pattern", [PATH, CYCLE])
@pytest.mark.parametrize("semantics", [isomorphism(), homomorphism()])
def test_enumeration_and_deltas(spark, pattern, semantics):
    rows = graph(3)
    edges = stored(frame(spark, rows))
    keys = [f"e_{e.name}" for e in pattern.edges]
    got = lambda df: sorted(tuple(r) for r in df.select(keys).collect())
    want = R.brute(rows, pattern, semantics.injective)
    assert got(enumerate_all(edges, pattern, semantics)) == want and want
    new = [w for w in want if any(i >= 20 for i in w)]
    assert got(delta(edges, F.col("edge_id") >= 20, compile_plan(pattern, profile=semantics.profile), semantics)) == new


@pytest.mark.parametrize("pattern", [PATH, CYCLE])
def test_dual_simulation(spark, pattern):
    for seed in (3, 4):
        rows = graph(seed, 18)
        assert {(r.qvertex, r.vid) for r in dual_simulation(frame(spark, rows), pattern, keep=stored).collect()} == R.simulate(rows, pattern)


def test_pair_index_one_by_one_and_batched(spark):
    rows = graph(5, 20, 6)
    edges = stored(frame(spark, rows))
    plan = compile_plan(PATH, profile="existence")
    out = {}
    for batched in (True, False):
        found = B.pair_state(edges, plan, F.col("edge_id") >= 18, homomorphism(), batched=batched)
        out[batched] = {tuple(r[f"v_{v.name}"] for v in PATH.vertices) for r in found.collect()}
    label = {r[0]: (r[1], r[2], r[5]) for r in rows}
    old = {label[i] for i in range(18)}
    want = {tuple([label[w[0]][0], *[label[i][1] for i in w]]) for w in R.brute(rows, PATH, False) if any(label[i] not in old for i in w)}
    assert out[True] == out[False] == want


def test_match_store(spark):
    rows = graph(6)
    timed = PATH.timed(1, 2, 3)
    store = B.MatchStore(timed, 12)
    got = [tuple(r) for k in range(0, 30, 10) for r in store.update(frame(spark, rows[k : k + 10])).select("e_x", "e_y", "e_z").collect()]
    assert sorted(got) == R.brute(rows, timed, True, temporal_pairs(timed), 12) and store.stored_rows() < len(rows) ** 2
    with pytest.raises(ValueError):
        B.MatchStore(parse_pattern("(a)-[x:p]->(b)-[y:q]->(c)-[z:p]->(d)").timed(1, 3, 2), 5)


def test_slots(spark):
    rng = random.Random(7)
    rows = [(i, rng.randrange(3), 9, "T", "T", "p", rng.randrange(1, 40) * MINUTE, 1.0) for i in range(60)]
    config = StreamConfig.sliding(10 * MINUTE, 5 * MINUTE)
    got = {r.edge_id: r.slot for r in G.slot_ids(frame(spark, rows), config).collect()}
    life = {r[0]: (r[1], -(-r[6] // config.stride), -(-(r[6] + config.window) // config.stride)) for r in rows}
    want, free, top = {}, {s: [] for s in range(3)}, [0] * 3
    for k in sorted({x for _, b, d in life.values() for x in (b, d)}):
        for i in sorted(i for i, (_, b, _) in life.items() if b == k):
            s = life[i][0]
            if free[s]:
                want[i] = free[s].pop(0)
            else:
                top[s] += 1
                want[i] = top[s]
        for i in sorted(i for i, (_, _, d) in life.items() if d == k):
            free[life[i][0]].append(want[i])
    assert got == want


def test_star_stream(spark, tmp_path):
    star = parse_pattern("(a)-[x:p]->(b),(a)-[y:q]->(c)", "star")
    rows = graph(8, 40, 6)
    edges = frame(spark, rows)
    edges.coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(R.EDGE_SCHEMA).parquet(str(tmp_path / "in"))
    query = star_matches(stream, star, 9).writeStream.format("memory").queryName("stars").outputMode("append").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "cp")).start()
    query.awaitTermination()
    got = sorted(map(tuple, spark.table("stars").collect()))
    assert got == sorted(map(tuple, star_batch(edges, star, 9).collect())) and got


def test_text_front_end(spark):
    found = parse("MATCH (a)-[x:p]->(b)-[y:q]->(c) WHERE x.ts < y.ts AND x.weight > 0 WITHIN 2 minutes SEMANTICS homo RETURN a, y LIMIT 3")
    assert (found.semantics.injective, found.semantics.pairs, found.semantics.within, found.columns, found.limit) == (False, (("x", "y"),), 2 * MINUTE, ("a", "y"), 3)
    rows = match(frame(spark, graph(3)), "match (a)-[x:p]->(b)-[y:q]->(c) return a, y limit 3", view="found_rows")
    assert rows.columns == ["v_a", "e_y"] and spark.sql("select count(*) as n from found_rows").first().n == 3
    for bad in ("(a)-[x]->(b)", "MATCH (a)-[x]->(b) WHERE z.ts < x.ts", "MATCH (a)-[x]->(b) WITHIN 3 moons", "MATCH (a)-[x]->(b) SEMANTICS odd"):
        with pytest.raises(ValueError):
            parse(bad)


def test_grown_patterns_have_embeddings(spark):
    rows = graph(9, 40, 9)
    for kind, size in (("tree", 3), ("graph", 4)):
        grown = generate(frame(spark, rows), kind, size, 2)
        assert grown and all(len(p.edges) == size and R.brute(rows, p) for p in grown)


def test_copies_are_disjoint(spark):
    rows = graph(11, 30)
    one, three = (enumerate_all(e, CYCLE, homomorphism()) for e in (frame(spark, rows), copies(frame(spark, rows), 3, 2)))
    assert three.count() == 3 * one.count() > 0
    assert three.where("v_a >> 32 <> v_d >> 32 or v_a >> 32 <> e_w >> 32").isEmpty()


def test_batches_of_a_stream(spark):
    rows = graph(10, 20)
    source = open_stream(frame(spark, rows), StreamConfig.insert_only(6, 5))
    assert source.initial().count() == 5 and [(k, i.count(), d) for k, i, d in source] == [(1, 6, None), (2, 6, None), (3, 3, None)]
    sliding = open_stream(frame(spark, rows), StreamConfig.sliding(4, 2))
    assert sum(i.count() for _, i, _ in sliding if i) == sum(d.count() for _, _, d in sliding if d) == 20 and sliding.initial().isEmpty()


def test_queries_on_an_empty_table(spark, sf, tmp_path):
    spark.read.parquet(f"{sf}/events.parquet").limit(0).write.parquet(f"{tmp_path}/events.parquet")
    for name in ("delta_t3_count_v1", "mask_earlier_old_v1", "dedup_distinct_v1", "duplicates_avoided_v1", "placeholders_reclaim_3days_v2", "wco_delta_triangle_v1", "timed_t3_v1", "dual_windows_v2", "match_store_stream_v1", "static_snapshots_v2", "op_asof", "late_rows_v1", "slot_ids_v2"):
        queries()[name](spark, str(tmp_path)).collect()


def test_semantics_contain_each_other(spark, sf):
    from flowmatch.sources import views as V

    edges = stored(V.handoff(spark, sf))
    n = [enumerate_all(edges, p, s).count() for p, s in ((PURCHASE.timed(1, 2), Semantics(pairs=(("x", "y"),))), (PURCHASE, isomorphism()), (PURCHASE, homomorphism()))]
    assert 0 < n[0] < n[1] <= n[2]


PURCHASE = parse_pattern("(a)-[x:purchase]->(b)-[y:click]->(c)")
