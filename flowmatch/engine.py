"""The engine: a pattern, an expander, an edge rule and a stream go in; what each snapshot gains and loses comes out.

A snapshot runs as published: inserts enter the graph, the index is brought up to date, embeddings that use a new edge are
enumerated from live bits; then embeddings that use a dying edge are enumerated from the index that still has it, the
edges leave, and the index is brought up to date again.  Batch masks make every embedding come out once.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, functions as F

from flowmatch.functions.rules import Rule, label_rule
from flowmatch.operators.enumeration import Expander, apply_delta, emit, live_delta
from flowmatch.operators.maintain import LiveIndex, maintain, open_index
from flowmatch.plans.pattern import Pattern
from flowmatch.plans.planner import Statistics, compile_plan
from flowmatch.sources.storage import Commits, DeltaTable, delete, fs_path, keeper, opened
from flowmatch.sources.views import EDGE


@dataclass(frozen=True)
class EngineConfig:
    """What a user may override.  ``filter_profile``: "auto" takes the expander's.  ``root``, ``order``: of the query tree and the matching
    order.  ``passes``: "fixpoint" or "two_pass".  ``orientation``, ``dedup``: of the batch masks.  ``net``: an embedding gained
    and lost in one snapshot is left out.  ``reset_every``: the index is built anew every so many snapshots.
    ``overlay``: share of a table that its overlay of changes may reach.  ``allowed_lateness``: microseconds that an insert
    may lie behind the latest time of earlier snapshots; later ones go to the side output."""

    filter_profile: str = "auto"
    root: str | None = None
    order: str | list[str] = "bfs"
    passes: str = "fixpoint"
    orientation: str = "earlier_old"
    dedup: str = "mask"
    net: bool = False
    reset_every: int | None = None
    overlay: float = 0.25
    allowed_lateness: int | None = None


class MatchEngine:
    """State lives under ``path``; an engine opened on a path with commits goes on from the last one."""

    def __init__(self, spark: SparkSession, pattern: Pattern, semantics: Expander, path: str, rule: Rule = label_rule, config: EngineConfig = EngineConfig(), stats: Statistics | None = None):
        self.spark, self.semantics, self.rule, self.config, self.path = spark, semantics, rule, config, path.rstrip("/")
        profile = semantics.profile if config.filter_profile == "auto" else config.filter_profile
        self.plan = compile_plan(pattern, stats, config.root, config.order, profile)
        self.commits, self.keep = Commits(spark, f"{self.path}/commits"), keeper(f"{self.path}/tables")
        self.index: LiveIndex | None = None
        self.since_reset, self.latest, self.work = 0, None, {}
        if done := self.commits.ids():
            self._open(self.commits.read(done[-1]))

    def _open(self, commit: dict) -> None:
        self.index = LiveIndex(self.plan, DeltaTable.at(self.spark, commit["edges"]), DeltaTable.at(self.spark, commit["vertices"]), self.config.passes, self.rule)
        self.since_reset, self.latest = commit["since_reset"], commit["latest"]

    def load_initial(self, edges: DataFrame, batch_id: int = -1) -> None:
        """The graph before the first snapshot; nothing is enumerated.  Without it the stream starts from the empty graph."""
        if self.commits.ids():
            return
        self.index = open_index(edges.select(*EDGE), self.plan, self.rule, self.config.passes, self.keep, share=self.config.overlay)
        self._commit(batch_id)

    def _commit(self, batch_id: int) -> None:
        done = self.commits.ids()
        self.commits.write(batch_id, {"edges": self.index.edges.pointer(), "vertices": self.index.vertices.pointer(), "since_reset": self.since_reset, "latest": self.latest})
        # Tables that neither this commit nor the one before points to have no reader left.
        used = {p for b in [batch_id, *done[-1:]] for t in ("edges", "vertices") for p in (self.commits.read(b)[t]["base"], self.commits.read(b)[t]["over"])}
        fs, folder = fs_path(self.spark, f"{self.path}/tables")
        for s in fs.listStatus(folder):
            name = s.getPath().getName()
            if not any(u and u.endswith("/" + name) for u in used):
                delete(self.spark, f"{self.path}/tables/{name}")

    def apply_inserts(self, edges: DataFrame, batch_id: int) -> DataFrame:
        """Adds the edges and brings the index up to date; the embeddings gained, lazily."""
        self.index = maintain(self.index, inserts=edges, batch=batch_id, keep=self.keep)
        self.work = {"inserts": self.index.work}
        return emit(live_delta(self.index.live(), F.col("born") == batch_id, self.plan, self.semantics, self.config.orientation, self.config.dedup, "live_mask"), batch_id, 1)

    def apply_deletes(self, gone: DataFrame, batch_id: int, keep: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
        """The embeddings lost, written by ``keep`` from the index that still has the edges; then removes these and brings the index up to date."""
        ids = self.keep(gone.select("edge_id").distinct())
        dying = self.index.live().join(ids.withColumn("dies", F.lit(True)), "edge_id", "left").withColumn("dies", F.coalesce("dies", F.lit(False)))
        lost = (keep or self.keep)(emit(live_delta(dying, F.col("dies"), self.plan, self.semantics, self.config.orientation, self.config.dedup, "live_mask"), batch_id, -1))
        self.index = maintain(self.index, deletes=ids, batch=batch_id, keep=self.keep)
        self.work |= {"deletes": self.index.work}
        return lost

    def apply(self, batch_id: int, inserts: DataFrame | None = None, deletes: DataFrame | None = None) -> DataFrame:
        """One snapshot: its gains and losses, written under its id.  A snapshot that is committed already changes nothing."""
        out = f"{self.path}/embeddings/{batch_id}"
        if batch_id in self.commits.ids():
            return opened(self.spark, out)
        if self.index is None:
            self.index = open_index((inserts if inserts is not None else deletes).select(*EDGE).limit(0), self.plan, self.rule, self.config.passes, self.keep, share=self.config.overlay)
        delete(self.spark, out)  # of a try that was not committed
        net = self.config.net and inserts is not None and deletes is not None

        def put(rows: DataFrame) -> DataFrame:
            """Written once, where they stay, unless gains and losses are to be offset first."""
            if net:
                return self.keep(rows)
            rows.write.mode("append").parquet(out)
            return opened(self.spark, out, rows.schema)

        self.work, gained = {}, None
        if inserts is not None:
            rows = gained = put(self.apply_inserts(self._in_time(inserts.select(*EDGE), batch_id), batch_id))
        if deletes is not None:
            rows = self.apply_deletes(deletes, batch_id, put)
        if net:
            rows = gained.unionByName(rows)
            keys = [c for c in rows.columns if c.startswith("e_")]
            rows = rows.join(rows.groupBy(*keys).agg(F.sum("sign").alias("net")).where("net <> 0").drop("net"), keys, "left_semi")
            rows.write.parquet(out)
        self.since_reset += 1
        if self.config.reset_every and self.since_reset >= self.config.reset_every:
            self.reset()
        self._commit(batch_id)
        return opened(self.spark, out, rows.schema)

    def _in_time(self, inserts: DataFrame, batch_id: int) -> DataFrame:
        """Inserts that are not too late; the others go to the side output ``late``."""
        if self.config.allowed_lateness is None:
            return inserts
        bound = None if self.latest is None else self.latest - self.config.allowed_lateness
        newest = inserts.agg(F.max("ts")).first()[0]
        self.latest = max((x for x in (self.latest, newest) if x is not None), default=None)
        if bound is None:
            return inserts
        inserts.where(F.col("ts") < bound).write.mode("overwrite").parquet(f"{self.path}/late/{batch_id}")
        return inserts.where(F.coalesce(F.col("ts") >= bound, F.lit(True)))

    def reset(self) -> None:
        """Drops the index and its overlays and builds it from the edges."""
        edges = self.index.edges.view().drop("local_mask", "reach_mask", "live_mask")
        self.index = open_index(edges, self.plan, self.rule, self.config.passes, self.keep, share=self.config.overlay)
        self.since_reset = 0

    def run(self, source: Iterable[tuple[int, DataFrame | None, DataFrame | None]], most: int | None = None) -> DataFrame | None:
        """Applies the snapshots of a source, ``most`` of them at most; returns all gains and losses so far."""
        for k, (batch_id, inserts, deletes) in enumerate(source):
            if most is not None and k >= most:
                break
            self.apply(batch_id, inserts, deletes)
        return self.embeddings()

    def embeddings(self) -> DataFrame | None:
        """All gains and losses so far."""
        done = [b for b in self.commits.ids() if fs_path(self.spark, f"{self.path}/embeddings/{b}")[0].exists(fs_path(self.spark, f"{self.path}/embeddings/{b}")[1])]
        return self.spark.read.parquet(*[f"{self.path}/embeddings/{b}" for b in done]) if done else None

    def current(self, before: DataFrame) -> DataFrame:
        """The embeddings after the last snapshot, from those before the first: the fold of all gains and losses."""
        every = self.embeddings()
        return before if every is None else apply_delta(before, every.where("sign > 0"), every.where("sign < 0"))

    def late(self) -> DataFrame | None:
        fs, p = fs_path(self.spark, f"{self.path}/late")
        return self.spark.read.parquet(f"{self.path}/late/*") if fs.exists(p) else None
