"""Strong simulation for 64 centers at a time: a word for each vertex says for which of them it is in the ball, or in the relation.

Balls that share most of their vertices are never listed, only what remains of them.  A block of centers needs the whole
graph at one place, so this is for graphs of a bounded number of vertex pairs; Spark deals blocks to tasks.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame, functions as F

from flowmatch.plans.pattern import Pattern

BLOCK = 1024  # centers, about
SLICE = 16_384  # vertices whose rows leave together


def solver(pattern: Pattern, width: int, slice_: int = SLICE) -> Callable[..., Iterator[tuple]]:
    """The work on one block, as a function that holds nothing of this package, so that workers need not import it."""
    import numpy as np

    ends, size = [(pattern.bit(e.src), pattern.bit(e.dst)) for e in pattern.edges], len(pattern.vertices)

    def gather(to, frm, n: int):
        """x -> for each of ``n`` vertices, the bits of x at any ``frm`` whose ``to`` it is."""
        order = np.argsort(to, kind="stable")
        at, frm = to[order], frm[order]
        first = np.flatnonzero(np.diff(at, prepend=-1))

        def gathered(x):
            out = np.zeros(n, np.uint64)
            if len(first):
                out[at[first]] = np.bitwise_or.reduceat(x[frm], first)
            return out

        return gathered

    def relations(centers, vid, mask, src, dst, bits):
        """(center, vid, mask) in slices.  ``mask``: of the dual simulation, by ``vid``; ``bits``: the query edges that match between ``src`` and ``dst``."""
        ids = np.unique(np.concatenate([src, dst, vid]))
        a, b = np.searchsorted(ids, src), np.searchsorted(ids, dst)
        near = gather(np.concatenate([a, b]), np.concatenate([b, a]), len(ids))
        order = np.argsort(vid)
        vid, mask = vid[order], mask[order]
        n, place = len(vid), np.searchsorted(ids, vid)
        own = np.full(len(ids), -1)
        own[place] = np.arange(n)
        a, b = own[a], own[b]
        may = [(mask >> i & 1).astype(bool) for i in range(size)]
        steps = []  # by query edge: its ends, and what of a word at one end reaches the other
        for i, (s, d) in enumerate(ends):
            fits = (bits >> i & 1).astype(bool) & (a >= 0) & (b >= 0)
            fits[fits] = may[s][a[fits]] & may[d][b[fits]]
            steps.append((s, d, gather(b[fits], a[fits], n), gather(a[fits], b[fits], n)))
        for k in range(0, len(centers), 64):
            some = centers[k : k + 64]
            mine, one = np.searchsorted(vid, some), np.uint64(1) << np.arange(len(some), dtype=np.uint64)
            ball = np.zeros(len(ids), np.uint64)
            ball[place[mine]] = one
            for _ in range(width):
                ball |= near(ball)
            rel = [np.where(m, ball[place], np.uint64(0)) for m in may]
            changed = True
            while changed:
                changed = False
                for s, d, down, up in steps:
                    for u, new in ((s, rel[s] & up(rel[d])), (d, rel[d] & down(rel[s]))):
                        if not np.array_equal(new, rel[u]):
                            rel[u] &= new
                            changed = True
            part = np.zeros(n, np.uint64)
            part[mine] = np.bitwise_or.reduce(rel)[mine] & one
            before = None
            while before is None or not np.array_equal(before, part):
                before = part.copy()
                for s, d, down, up in steps:
                    part |= down(part & rel[s]) & rel[d]
                    part |= up(part & rel[d]) & rel[s]
            rows = np.flatnonzero(part)
            for j in range(0, len(rows), slice_):
                at = rows[j : j + slice_]
                out = np.zeros((len(at), 64), np.uint8 if len(rel) <= 8 else np.int64)
                for u, r in enumerate(rel):
                    word = (r[at] & part[at]).astype("<u8").view(np.uint8).reshape(-1, 8)
                    out |= np.unpackbits(word, axis=1, bitorder="little").astype(out.dtype) << u
                v, c = np.nonzero(out)
                yield some[c], vid[at[v]], out[v, c].astype(np.int64)

    return relations


def blocks_of(centers: int) -> int:
    return max(1, -(-centers // BLOCK))


def strong_masks(pairs: DataFrame, dual: DataFrame, pattern: Pattern, width: int, blocks: int) -> DataFrame:
    """(center, vid, mask).  ``pairs``: src, dst and local_mask of all joined vertices, each pair once; ``dual``: vid and mask of the dual simulation."""
    solve = solver(pattern, width)
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("block")
    none = F.lit(0).cast("bigint")
    rows = (
        pairs.select(every, F.lit(0).alias("kind"), F.col("src").alias("x"), F.col("dst").alias("y"), F.col("local_mask").alias("mask"))
        .unionByName(dual.select(every, F.lit(1).alias("kind"), F.col("vid").alias("x"), none.alias("y"), "mask"))
        .unionByName(dual.select(F.pmod(F.xxhash64("vid"), F.lit(blocks)).cast("int").alias("block"), F.lit(2).alias("kind"), F.col("vid").alias("x"), none.alias("y"), "mask"))
    )

    def answered(batches):
        import numpy as np
        import pyarrow as pa

        def result(parts):
            kind, x, y, mask = (np.concatenate([p[i] for p in parts]) for i in range(4))
            edge, vertex = kind == 0, kind == 1
            for columns in solve(x[kind == 2], x[vertex], mask[vertex], x[edge], y[edge], mask[edge]):
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["center", "vid", "mask"])

        at, parts = None, []
        for batch in batches:
            block, *columns = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(5))
            cuts = [0, *(np.flatnonzero(np.diff(block)) + 1), len(block)]
            for lo, hi in zip(cuts, cuts[1:]):
                if lo == hi:
                    continue
                if parts and block[lo] != at:
                    yield from result(parts)
                    parts = []
                at = block[lo]
                parts.append([c[lo:hi].copy() for c in columns])
        if parts:
            yield from result(parts)

    return rows.repartition(blocks, "block").sortWithinPartitions("block").mapInArrow(answered, "center long, vid long, mask long")
