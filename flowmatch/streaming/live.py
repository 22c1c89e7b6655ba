"""The live engine: Structured Streaming micro-batches through the same engine as batch mode.

A micro-batch of edge events (columns of EDGE and ``op``: 1 insert, -1 delete) is one snapshot: its inserts come before
its deletes, so an edge of both is born and dies in it.  The engine's commit is written last, under the batch id, so a
replayed batch changes nothing, and a query started again on the same path goes on.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from flowmatch.engine import MatchEngine
from flowmatch.sources.storage import keeper

EVENT_SCHEMA = "edge_id long, src long, dst long, src_type string, dst_type string, label string, ts long, weight double, op tinyint"


class LiveMatcher(MatchEngine):
    def batch(self, events: DataFrame, batch_id: int) -> None:
        if batch_id in self.commits.ids():
            return
        events = keeper(f"{self.path}/tables")(events)  # read once, however many plans follow
        kinds = events.agg(F.coalesce(F.bool_or(F.col("op") < 0), F.lit(False)).alias("deletes")).first()
        self.apply(batch_id, events.where("op > 0"), events.where("op < 0") if kinds.deletes else None)

    def start(self, stream: DataFrame, checkpoint: str, **trigger):
        """A streaming query over events; one pass over what is there unless a trigger is given."""
        return stream.writeStream.foreachBatch(self.batch).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()
