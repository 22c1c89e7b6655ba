"""The engine on the running example: index bits after each batch, gains and losses, replay, restart, late rows, reset."""

from pyspark.sql import functions as F

from flowmatch.engine import EngineConfig
from flowmatch.operators.enumeration import enumerate_all, isomorphism
from flowmatch.operators.maintain import maintain, open_index
from flowmatch.plans.planner import compile_plan
from flowmatch.streaming.live import EVENT_SCHEMA, LiveMatcher
from tests import running as R
from tests.test_running_example import LIVE, STATES, frame


def bits(index):
    tree = index.plan.tree
    child = {tree.bit(t): t.child[1:] for t in tree.edges}
    rows = index.live().select("edge_id", "live_mask").collect()
    return {r.edge_id: s for r in rows if (s := "".join(sorted(c for i, c in child.items() if r.live_mask >> i & 1)))}


def test_bits_by_maintenance(spark):
    plan = compile_plan(R.pattern(), root="u0")
    index = open_index(frame(spark, R.G), plan)
    assert bits(index) == LIVE["G"][0]
    index = maintain(index, frame(spark, R.T1), batch=1)
    assert bits(index) == LIVE["t1"][0] and index.work["touched"] == 4
    index = maintain(index, frame(spark, R.T2_IN), frame(spark, R.T2_OUT), batch=2)
    assert bits(index) == LIVE["t2"][0]
    again = maintain(index, deletes=spark.createDataFrame([(999,)], "edge_id long"))
    assert again.work == {"touched": 0, "vertices": 0, "edges": 0}


def test_stream_with_replay_restart_late_rows_and_reset(spark, tmp_path):
    events = lambda ins, out=(): spark.createDataFrame([(*r, 1) for r in R.rows(ins)] + [(*r, -1) for r in R.rows(out)], EVENT_SCHEMA)
    where, config = str(tmp_path / "state"), EngineConfig(root="u0", allowed_lateness=5, reset_every=2)
    m = LiveMatcher(spark, R.pattern(), isomorphism(), where, config=config)
    for k, (ins, out) in enumerate([(R.G, ()), (R.T1, ())]):
        m.batch(events(ins, out), k)
    m.batch(events(R.G), 1)  # a replay
    m = LiveMatcher(spark, R.pattern(), isomorphism(), where, config=config)  # a restart
    late = [(14, 4, 1)]  # of time 14, but told as 3
    rows = [(*r, 1) for r in R.rows(R.T2_IN)] + [(*r, -1) for r in R.rows(R.T2_OUT)] + [(*r, 1) for r in R.rows(late, ts={14: 3})]
    m.batch(spark.createDataFrame(rows, EVENT_SCHEMA), 2)
    got = {(r.snapshot_id, r.sign): r["count"] for r in m.embeddings().groupBy("snapshot_id", "sign").count().collect()}
    assert got == {(0, 1): 2, (1, 1): 2, (2, 1): 2, (2, -1): 4}
    assert [r.edge_id for r in m.late().collect()] == [14] and m.commits.ids() == [0, 1, 2]
    none = enumerate_all(frame(spark, STATES["G"]).where("false"), R.pattern(), isomorphism(), m.plan)
    now = m.current(none.select([c for c in m.embeddings().columns if c[:2] in ("v_", "e_")]))
    want = enumerate_all(frame(spark, STATES["t2"]), R.pattern(), isomorphism(), m.plan)
    keys = [f"e_{e.name}" for e in R.pattern().edges]
    assert sorted(map(tuple, now.select(keys).collect())) == sorted(map(tuple, want.select(keys).collect())) == R.brute(R.rows(STATES["t2"]), R.pattern())


def test_micro_batches_from_files(spark, tmp_path):
    spark.createDataFrame([(*r, 1) for r in R.rows(R.G)], EVENT_SCHEMA).coalesce(1).write.parquet(str(tmp_path / "in"))
    m = LiveMatcher(spark, R.pattern(), isomorphism(), str(tmp_path / "state"), config=EngineConfig(root="u0"))
    stream = spark.readStream.schema(EVENT_SCHEMA).parquet(str(tmp_path / "in"))
    m.start(stream, str(tmp_path / "progress")).awaitTermination()
    assert m.embeddings().where(F.col("sign") > 0).count() == 2
