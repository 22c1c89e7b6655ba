"""Snapshots: how a stream of edges becomes batches of inserts and deletes."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window, functions as F

from flowmatch.operators.enumeration import Semantics, enumerate_all
from flowmatch.plans.pattern import Pattern
from flowmatch.plans.planner import Plan
from flowmatch.sources.storage import stored

MINUTE = 60_000_000
HOUR, DAY = 60 * MINUTE, 1440 * MINUTE


@dataclass(frozen=True)
class StreamConfig:
    """kind: "insert_only", "insert_delete", "sliding" or "tumbling"; times in microseconds."""

    kind: str
    batch_size: int = 16_384
    initial: int = 0  # rows before the first batch
    window: int = DAY
    stride: int = 10 * MINUTE

    @classmethod
    def insert_only(cls, batch_size: int = 16_384, initial: int = 0) -> StreamConfig:
        return cls("insert_only", batch_size, initial)

    @classmethod
    def insert_delete(cls, batch_size: int = 16_384, initial: int = 0) -> StreamConfig:
        return cls("insert_delete", batch_size, initial)

    @classmethod
    def sliding(cls, window: int = DAY, stride: int = 10 * MINUTE) -> StreamConfig:
        if window % stride:
            raise ValueError("the window must be a multiple of the stride")
        return cls("sliding", window=window, stride=stride)

    @classmethod
    def tumbling(cls, window: int = DAY) -> StreamConfig:
        return cls("tumbling", window=window, stride=window)

    def batch(self, seq: str = "seq") -> Column:
        """Snapshot of a row by its number (from 0): 0 is the initial graph, batches follow."""
        return F.when(F.col(seq) < self.initial, F.lit(0)).otherwise(F.floor((F.col(seq) - self.initial) / self.batch_size) + 1).cast("bigint")

    def born(self, ts: str = "ts") -> Column:
        """First snapshot k, at time k * stride, that sees an edge of this time."""
        return F.ceil(F.col(ts) / self.stride).cast("bigint")

    def dies(self, ts: str = "ts") -> Column:
        """First snapshot that no longer does: an edge is seen at T if T - window < ts <= T."""
        return F.ceil((F.col(ts) + self.window) / self.stride).cast("bigint")


def numbered(edges: DataFrame) -> DataFrame:
    """Adds ``seq`` from 1 in the order of (ts, edge_id), without a window over all rows.

    Counts by (day, time, id range) give prefix sums within days, days among each other; rows are numbered only within a
    time and id range.  Nothing depends on how rows are partitioned.
    """
    rows = edges.withColumn("day", F.floor(F.col("ts") / DAY)).withColumn("span", F.floor(F.col("edge_id") / 65_536))
    counts = rows.groupBy("day", "ts", "span").agg(F.count("*").alias("c"))
    within = counts.withColumn("before", F.sum("c").over(Window.partitionBy("day").orderBy("ts", "span")) - F.col("c")).drop("c")
    days = counts.groupBy("day").agg(F.sum("c").alias("c"))
    days = days.select("day", (F.sum("c").over(Window.orderBy("day")) - F.col("c")).alias("start"))  # one row per day
    nth = F.row_number().over(Window.partitionBy("day", "ts", "span").orderBy("edge_id"))
    return rows.withColumn("nth", nth).join(within, ["day", "ts", "span"]).join(days, "day").withColumn("seq", (F.col("start") + F.col("before") + F.col("nth")).cast("bigint")).drop("day", "span", "nth", "before", "start")


def insert_delete_events(edges: DataFrame, prefix: float = 0.9, every: int = 10) -> DataFrame:
    """The insert-and-delete stream: the first rows are the initial graph; of the later ones every tenth deletes a prefix edge, picked by arithmetic, and does not enter itself.

    Columns of the edges and seq, op (+1, -1; 0 for the initial graph).
    """
    rows = stored(numbered(edges), "stream")
    n = rows.agg(F.max("seq")).first()[0] or 0
    p = int(n * prefix)
    kinds = rows.withColumn("op", F.when(F.col("seq") <= p, 0).when(F.col("seq") % every == 0, -1).otherwise(1))
    gone = kinds.where("op = -1").select((F.col("seq") * 7919 % p + 1).alias("victim"), F.col("seq").alias("at")) if p else kinds.where("false").select(F.col("seq").alias("victim"), F.col("seq").alias("at"))
    deletes = kinds.where("op = 0").join(gone, F.col("seq") == F.col("victim")).withColumn("seq", F.col("at")).withColumn("op", F.lit(-1)).drop("victim", "at")
    return kinds.where("op >= 0").unionByName(deletes)


def resolve_deletes(graph: DataFrame, deletes: DataFrame, policy: str = "oldest") -> DataFrame:
    """Edge ids for deletes that name (src, dst, label) only: the n-th such delete takes the n-th oldest (or newest) parallel edge, or "all"."""
    keys = ["src", "dst", "label"]
    if policy == "all":
        return graph.join(deletes.select(*keys).distinct(), keys, "left_semi").select("edge_id", *keys)
    if policy not in ("oldest", "newest"):
        raise ValueError("policies are 'oldest', 'newest' and 'all'")
    order = F.col("edge_id") if policy == "oldest" else F.desc("edge_id")
    mine = graph.withColumn("k", F.row_number().over(Window.partitionBy(*keys).orderBy(order)))
    asked = deletes.groupBy(*keys).agg(F.count("*").alias("n"))
    return mine.join(asked, keys).where("k <= n").select("edge_id", *keys)


class BatchSource:
    """Snapshots (id, inserts, deletes) of a table with columns snapshot_id and op; snapshots without rows of a kind have None for it.

    ``initial``: the rows before the first snapshot.
    """

    def __init__(self, events: DataFrame, first: int = 1):
        self.events, self.first = events, first

    def initial(self) -> DataFrame:
        return self.events.where(F.col("snapshot_id") < self.first)

    def __iter__(self) -> Iterator[tuple[int, DataFrame | None, DataFrame | None]]:
        kinds = self.events.where(F.col("snapshot_id") >= self.first).groupBy("snapshot_id").agg(F.max(F.col("op") >= 0).alias("i"), F.max(F.col("op") < 0).alias("d"))
        for r in kinds.orderBy("snapshot_id").collect():  # a row per snapshot
            own = self.events.where(F.col("snapshot_id") == r.snapshot_id)  # prunes partitions where the table is partitioned by it
            yield r.snapshot_id, own.where("op >= 0") if r.i else None, own.where("op < 0") if r.d else None


def open_stream(edges: DataFrame, config: StreamConfig, keep=stored) -> BatchSource:
    """The batches of a stream over a table of edges, by the kind of ``config``.

    Insert-only: in the order of (ts, edge_id), ``batch_size`` edges a batch after ``initial`` ones.  Insert-and-delete: the
    same over rows that have ``seq`` and ``op`` (0 for the initial graph).  Sliding and tumbling: an edge is inserted in the
    first snapshot that sees it and deleted in the first that no longer does.
    """
    if config.kind == "insert_only":
        rows = numbered(edges).withColumn("seq", F.col("seq") - 1)
        return BatchSource(keep(rows.withColumn("snapshot_id", config.batch()).withColumn("op", F.lit(1)).drop("seq")))
    if config.kind == "insert_delete":
        later = F.floor((F.col("seq") - 1 - config.initial) / config.batch_size) + 1
        return BatchSource(keep(edges.withColumn("snapshot_id", F.when(F.col("op") == 0, 0).otherwise(later).cast("bigint")).drop("seq")))
    born, dies = config.born(), config.dies()
    moves = F.explode(F.array(F.struct(born.alias("snapshot_id"), F.lit(1).alias("op")), F.struct(dies.alias("snapshot_id"), F.lit(-1).alias("op"))))
    rows = edges.where(born < dies).select("*", moves.alias("move")).select(*edges.columns, "move.snapshot_id", "move.op")
    low = rows.agg(F.min("snapshot_id")).first()[0]
    return BatchSource(keep(rows), low if low is not None else 0)


def late_rows(arrivals: DataFrame, allowed: int, batch: str = "batch", ts: str = "ts") -> DataFrame:
    """The arrivals whose time lies over ``allowed`` behind the latest of earlier batches, with ``behind``: by how much.

    Latest times are taken per batch and then over batches, one row each, so no window runs over the arrivals.
    """
    tops = arrivals.groupBy(batch).agg(F.max(ts).alias("top"))
    bound = tops.select(F.col(batch).alias("b"), F.max("top").over(Window.orderBy(batch).rowsBetween(Window.unboundedPreceding, -1)).alias("bound"))
    rows = arrivals.join(bound, F.col(batch) == F.col("b")).withColumn("behind", F.col("bound") - F.col(ts))
    return rows.where(F.col("behind") > allowed).drop("b", "bound")


def sliding_deltas(edges: DataFrame, pattern: Pattern, config: StreamConfig, semantics: Semantics = Semantics(), plan: Plan | None = None) -> DataFrame:
    """All gains and losses of all snapshots of a sliding window, from one time-bounded join.

    An embedding is seen from the first snapshot at or after its last edge until the first at or after first edge plus
    window; it is ever seen if these differ.
    """
    bounded = Semantics(semantics.injective, semantics.pairs, semantics.strict, config.window, semantics.symmetry)
    rows = enumerate_all(edges, pattern, bounded, plan)
    times = [f"t_{e.name}" for e in pattern.edges]
    first, last = (F.least(*times), F.greatest(*times)) if len(times) > 1 else (F.col(times[0]), F.col(times[0]))
    alive = rows.withColumn("first_ts", first).withColumn("last_ts", last)
    alive = alive.withColumn("born", config.born("last_ts")).withColumn("dies", config.dies("first_ts")).where("born < dies")
    keys = [c for c in rows.columns if c[:2] in ("v_", "e_")]
    return alive.select(*keys, F.explode(F.array(F.struct(F.col("born").alias("snapshot_id"), F.lit(1).alias("sign")), F.struct(F.col("dies").alias("snapshot_id"), F.lit(-1).alias("sign")))).alias("x")).select("x.snapshot_id", "x.sign", *keys)


def counts_by_snapshot(deltas: DataFrame) -> DataFrame:
    """snapshot_id, gained, lost, and how many are alive after it."""
    sums = deltas.groupBy("snapshot_id").agg(F.sum((F.col("sign") > 0).cast("long")).alias("gained"), F.sum((F.col("sign") < 0).cast("long")).alias("lost"))
    return sums.withColumn("alive", F.sum(F.col("gained") - F.col("lost")).over(Window.orderBy("snapshot_id")))  # a row per snapshot
