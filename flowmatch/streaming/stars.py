"""Star patterns without joins: all edges of a star share their center, so a keyed state of the center's recent edges finds every embedding.

For patterns such as ``(a)-[x]->(b), (a)-[y]->(c)``: the state of a center holds, per query edge, the edges that may play
it, within ``window`` of the newest.  A new edge is matched with what is there, and only embeddings that use it come out.
"""

from __future__ import annotations

from itertools import product

from pyspark.sql import DataFrame, functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from flowmatch.functions.rules import Rule, label_rule, local_masks
from flowmatch.plans.pattern import Pattern


def center_of(pattern: Pattern) -> str:
    """The source that all edges of a star share."""
    centers = {e.src for e in pattern.edges}
    if len(centers) != 1 or any(e.dst in centers for e in pattern.edges) or len({e.dst for e in pattern.edges}) != len(pattern.edges):
        raise ValueError("not a star of outgoing edges with distinct ends")
    return centers.pop()


def star_matches(events: DataFrame, pattern: Pattern, window: int, rule: Rule = label_rule) -> DataFrame:
    """Streaming inserts (columns of EDGE) to embeddings: v_<center>, and v_ and e_ of every edge; distinct ends, all edges within ``window``."""
    center, edges = center_of(pattern), pattern.edges
    near = local_masks(events, pattern, rule).where("local_mask <> 0").select("edge_id", "src", "dst", "ts", "local_mask")
    out = ", ".join([f"v_{center} long", *[f"v_{e.dst} long, e_{e.name} long" for e in edges]])
    names = [f"v_{center}", *[c for e in edges for c in (f"v_{e.dst}", f"e_{e.name}")]]

    def step(key, batches, state):
        import pandas as pd

        held = [tuple(x) for x in zip(*state.get)] if state.exists else []
        rows = []
        for frame in batches:
            for r in frame.sort_values(["ts", "edge_id"]).itertuples():
                held = [h for h in held if h[2] > r.ts - window]
                new = (int(r.edge_id), int(r.dst), int(r.ts), int(r.local_mask))
                held.append(new)
                for i in range(len(edges)):
                    if not new[3] >> i & 1:
                        continue
                    # The new edge plays edge i; earlier places take older edges only, so it is found once.
                    options = [[new] if j == i else [h for h in held if h[3] >> j & 1 and (j > i or h is not new)] for j in range(len(edges))]
                    for pick in product(*options):
                        if len({h[1] for h in pick} | {key[0]}) == len(edges) + 1 and len({h[0] for h in pick}) == len(edges):
                            rows.append([key[0], *[x for h in pick for x in (h[1], h[0])]])
        state.update(tuple(list(x) for x in zip(*held)))
        yield pd.DataFrame(rows, columns=names, dtype="int64")

    held_type = "ids array<long>, ends array<long>, times array<long>, masks array<long>"
    return near.groupBy("src").applyInPandasWithState(step, out, held_type, "append", GroupStateTimeout.NoTimeout)


def star_batch(edges: DataFrame, pattern: Pattern, window: int, rule: Rule = label_rule) -> DataFrame:
    """The same result for a table, as a plan of joins."""
    from flowmatch.operators.enumeration import Semantics, enumerate_all

    rows = enumerate_all(edges, pattern, Semantics(within=window - 1), rule=rule)
    center = center_of(pattern)
    return rows.select(f"v_{center}", *[F.col(c) for e in pattern.edges for c in (f"v_{e.dst}", f"e_{e.name}")])
