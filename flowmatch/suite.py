"""Runs of the experiments: query sets by method, with timeouts; sweeps over batch size and cores; a report.

``python -m flowmatch.suite SF_DIR`` runs the set of :data:`flowmatch.workloads.CLASSES` and prints a table;
``python -m flowmatch.suite SF_DIR cores K`` times one class on ``local[K]`` and prints seconds, for :func:`sweep_cores`;
with ``static`` for ``cores``, three patterns without a stream on ten disjoint copies of the handoff view.
"""

from __future__ import annotations

import os
import subprocess
import sys
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, functions as F

from flowmatch import metrics as M
from flowmatch.engine import EngineConfig, MatchEngine
from flowmatch.operators.baselines import PairIndex
from flowmatch.operators.enumeration import Expander, enumerate_all, homomorphism, isomorphism
from flowmatch.plans.pattern import Pattern
from flowmatch.plans.planner import compile_plan
from flowmatch.sources import views as V
from flowmatch.sources.snapshots import StreamConfig, open_stream
from flowmatch.sources.storage import shared_dir, stored

RUNS = "query string, kind string, method string, seconds double, rows long"


def engine_run(edges: DataFrame, pattern: Pattern, semantics: Expander, config: StreamConfig, tag: str = "run", options: EngineConfig = EngineConfig()) -> tuple[MatchEngine, list[float], int]:
    """A stream through the engine: it, the seconds of each snapshot, and the gains and losses."""
    import uuid

    spark = edges.sparkSession
    source = open_stream(edges, config)
    engine = MatchEngine(spark, pattern, semantics, f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}", config=options)
    engine.load_initial(source.initial())
    seconds, rows = [], 0
    for batch_id, inserts, deletes in source:
        began = time.time()
        rows += engine.apply(batch_id, inserts, deletes).count()
        seconds.append(time.time() - began)
    return engine, seconds, rows


def methods(spark: SparkSession, edges: DataFrame, pattern: Pattern, semantics: Expander, config: StreamConfig) -> dict[str, Callable[[], DataFrame]]:
    """The engine, and the pair-level index with batched updates, over the same stream."""
    source = open_stream(edges, config)
    plan = compile_plan(pattern, profile=semantics.profile)

    def engine():
        import uuid

        e = MatchEngine(spark, pattern, semantics, f"{shared_dir(spark)}/suite-{uuid.uuid4().hex}")
        e.load_initial(source.initial())
        return e.run(source)

    def pairs():
        index, out = PairIndex(source.initial(), plan, semantics), None
        for _, inserts, _ in source:
            part = stored(index.update(inserts))
            out = part if out is None else out.unionByName(part)
        return out

    return {"engine": engine, "pair_index": pairs}


def run_suite(spark: SparkSession, edges: DataFrame, patterns: list[Pattern], semantics: Expander, config: StreamConfig, timeout_s: float | None = 120) -> DataFrame:
    """A row per query and method; seconds are null where time ran out, as such runs are counted but not averaged."""
    rows = []
    for p in patterns:
        for name, work in methods(spark, edges, p, semantics, config).items():
            seconds, n = M.timed(spark, work, timeout_s)
            rows.append((p.name, p.name.rsplit("_", 1)[0], name, seconds, n))
    return spark.createDataFrame(rows, RUNS)


def report(runs: DataFrame) -> DataFrame:
    """Per class and method: mean and deviation of the finished runs, and timeouts."""
    return runs.groupBy("kind", "method").agg(F.avg("seconds").alias("mean_s"), F.stddev("seconds").alias("deviation_s"), F.count_if(F.col("seconds").isNull()).alias("timeouts"), F.count("*").alias("queries"))


def sweep_batch_size(edges: DataFrame, pattern: Pattern, semantics: Expander, initial: int, sizes: list[int]) -> list[tuple[int, float, int]]:
    """(batch size, seconds a thousand updates, embeddings) of one stream cut in different ways."""
    out = []
    for size in sizes:
        _, seconds, rows = engine_run(edges, pattern, semantics, StreamConfig.insert_only(size, initial))
        updates = edges.count() - initial
        out.append((size, 1000 * sum(seconds) / max(1, updates), rows))
    return out


def sweep_cores(sf_dir: str, cores: list[int], kind: str = "cores") -> list[tuple[int, float]]:
    """(cores, seconds) of one class, or with ``kind`` "static" of patterns without a stream, each in a session of its own."""
    out = []
    for k in cores:
        ran = subprocess.run([sys.executable, "-m", "flowmatch.suite", sf_dir, kind, str(k)], capture_output=True, text=True, check=True)
        out.append((k, float(ran.stdout.strip().splitlines()[-1])))
    return out


def session(cores: int | str = 8) -> SparkSession:
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    os.environ["PYTHONPATH"] = os.pathsep.join([root, os.environ.get("PYTHONPATH", "")])
    spark = SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "8g").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def main(args: list[str]) -> None:
    from flowmatch.workloads import CLASSES, PATTERNS

    sf_dir = args[0]
    if args[1:2] == ["cores"]:
        spark = session(args[2])
        edges = stored(V.commerce(spark, sf_dir))
        began = time.time()
        engine_run(edges, PATTERNS["t6_prefix"], isomorphism(), StreamConfig.insert_only(16_384, int(edges.count() * 0.892)))
        print(time.time() - began)
        return
    if args[1:2] == ["static"]:
        spark = session(args[2])
        edges = stored(V.copies(V.handoff(spark, sf_dir), 10))
        work = lambda: [enumerate_all(edges, PATTERNS[p], homomorphism()).count() for p in ("triangle", "clique4", "dual_triangle")]
        work()  # compiles
        began = time.time()
        work()
        print(time.time() - began)
        return
    spark = session()
    edges = stored(V.commerce(spark, sf_dir))
    n = edges.count()
    config = StreamConfig.insert_only(max(1, int(n * 0.036) + 1), int(n * 0.892))
    for semantics, label in ((isomorphism(), "isomorphism"), (homomorphism(), "homomorphism")):
        runs = stored(run_suite(spark, edges, [PATTERNS[c] for c in CLASSES], semantics, config))
        print(label, n, "edges")
        for r in runs.orderBy("query", "method").collect():
            print("  ", r.query, r.method, None if r.seconds is None else round(r.seconds, 2), r.rows)
        for r in M.speedup(runs, "pair_index").collect():
            print("   speed-up over pair_index:", r.asDict())


if __name__ == "__main__":
    main(sys.argv[1:])
