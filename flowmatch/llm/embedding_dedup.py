"""Embedding near-duplicates by sorted projection passes.

A pass gives every vector a key of ``depth`` random hash bits (signs of random projections) and sorts all vectors by it,
lexicographically: a range-partitioned sort of keys and digests alone, so that equal keys never crowd into one task.
From its rank a vector gets a tile of ``TILE`` rows and a block of ``SPAN`` tiles.  Compared are

* neighbours in the order: vectors of the same tile or of adjacent ones, across the borders of blocks and of hash
  buckets alike, so every vector meets at least ``TILE`` neighbours on each side;
* vectors that share the first ``b`` bits, however far apart they stand.  ``b`` grows with the number of vectors so that
  a run of unrelated ones stays near ``WINDOW`` rows, and the number of passes grows with ``b`` so that a pair at the
  threshold shares them in no pass with a chance under ``MISS``.

A block is compared in one task, with the tile that follows it; a run of near copies that goes on over many blocks is
compared block by block, each pair of blocks in a task of its own.  So memory is bounded and nothing is left out.

Pairs are compared as matrix products in double precision and never become rows: a task returns, per vector, how many
others it links to and a root of its links' spanning forest.  A pair counts in the first pass that compares it, which
both vectors' tiles and leading bits in every pass tell.  The passes' forests are united by connected components.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
from pyspark.sql import DataFrame, Window, functions as F, types as T

from flowmatch.llm.common import dropped, mapped, written
from flowmatch.llm.components import components

COSINE, WINDOW, MISS, LEAST_BITS, MOST_BITS, FINER, SEED = 0.95, 256, 0.002, 6, 30, 24, 17
TILE, SPAN, ROWS_PER_PART = 128, 16, 200_000
LO, HI, OWN, NEXT = 0, 1, 2, 3  # roles of a row in a task: of the first or the second of two blocks; of the block; of the tile behind it


def layout(n: int, cosine: float = COSINE) -> tuple[int, int, int]:
    """Leading bits that make two vectors meet, bits of a whole key, and number of passes, for ``n`` vectors."""
    bits = min(MOST_BITS, max(LEAST_BITS, math.ceil(math.log2(max(2, n) / WINDOW))))
    agree = (1 - math.acos(cosine) / math.pi) ** bits
    return bits, bits + FINER, math.ceil(math.log(MISS) / math.log(1 - agree))


def _planes(dim: int, bits: int, passes: int) -> np.ndarray:
    return np.random.default_rng(SEED + dim).standard_normal((dim, bits * passes))


def _unit(rows: np.ndarray) -> np.ndarray:
    scaled = rows / np.abs(rows).max(axis=1, keepdims=True)
    return scaled / np.linalg.norm(scaled, axis=1, keepdims=True)


def hashed(vectors: DataFrame, depth: int, passes: int, id_col: str, vec_col: str) -> DataFrame:
    """(id, same: digest of the vector, v: the vector as it came, keys: of each pass); for a vector that cannot link, nulls."""
    rows = vectors.select(F.col(id_col).alias("id"), F.col(vec_col).alias("v"))
    kind = rows.schema["v"].dataType.elementType
    kind = kind if isinstance(kind, (T.FloatType, T.DoubleType)) else T.DoubleType()
    rows = rows.withColumn("v", F.col("v").cast(T.ArrayType(kind)))
    schema = T.StructType([T.StructField("id", rows.schema["id"].dataType), T.StructField("same", T.BinaryType()), T.StructField("v", T.ArrayType(kind)), T.StructField("keys", T.ArrayType(T.LongType()))])
    weight = 1 << np.arange(depth - 1, -1, -1, dtype=np.int64)

    def run(batches):
        import pyarrow as pa

        planes: dict[int, np.ndarray] = {}
        for b in batches:
            same, own, keys = [None] * len(b), [None] * len(b), [None] * len(b)
            by_dim: dict[int, list] = {}
            for i, x in enumerate(b.column(1)):
                if not x.is_valid or not len(x) or x.values.null_count:
                    continue
                raw = x.values.to_numpy(zero_copy_only=False)
                if np.isfinite(raw).all() and raw.any():
                    by_dim.setdefault(len(raw), []).append((i, raw + raw.dtype.type(0)))
            for dim, of in by_dim.items():
                if dim not in planes:
                    planes[dim] = _planes(dim, depth, passes)
                for k in range(0, len(of), 1024):
                    part = of[k : k + 1024]
                    u = _unit(np.array([y for _, y in part], dtype=np.float64))
                    made = ((u @ planes[dim] > 0).reshape(len(u), passes, depth) * weight).sum(axis=2)
                    for (i, y), row in zip(part, made):
                        same[i], own[i], keys[i] = hashlib.blake2b(y.tobytes(), digest_size=16).digest(), y, row
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(same, pa.binary()), pa.array(own, b.column(1).type), pa.array(keys, pa.list_(pa.int64()))], names=schema.names)

    return mapped(rows, run, schema)


def ordered(reps: DataFrame, n: int, bits: int, depth: int, passes: int) -> DataFrame:
    """(same, pass, tile, block, cell) from the ``n`` rows' (same, keys): where each stands in the order of each pass.

    The order is a range-partitioned sort; a row's rank is its place in its partition and the rows of those before.
    """
    rows = reps.select("same", F.posexplode("keys").alias("pass", "key"))
    parts = max(1, n * passes // ROWS_PER_PART)
    laid = rows.repartitionByRange(parts, "pass", "key", "same").sortWithinPartitions("pass", "key", "same")
    laid = written(laid.select("same", "pass", F.shiftright("key", depth - bits).cast("int").alias("cell"), F.monotonically_increasing_id().alias("at")), "order")
    part = F.shiftright("at", 33)
    counts = laid.groupBy(part.alias("part")).agg(F.count("*").alias("c"))
    starts = counts.select("part", (F.sum("c").over(Window.orderBy("part")) - F.col("c")).alias("start"))  # a row per partition
    rank = F.col("start") + F.col("at").bitwiseAND(F.lit((1 << 33) - 1)) - F.col("pass").cast("long") * n
    placed = laid.withColumn("part", part).join(starts, "part").withColumn("rank", rank)
    return placed.select("same", "pass", "cell", F.floor(F.col("rank") / TILE).cast("int").alias("tile"), F.floor(F.col("rank") / (TILE * SPAN)).cast("int").alias("block"))


def _forest(n: int, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Least row of each row's component under the links i-j."""
    root = np.arange(n)
    while True:
        low = np.minimum(root[i], root[j])
        new = root.copy()
        np.minimum.at(new, i, low)
        np.minimum.at(new, j, low)
        new = new[new]
        if (new == root).all():
            return root
        root = new


def _list_column(table, name: str, rows=None) -> np.ndarray:
    column = table.column(name).combine_chunks()
    flat = column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1)
    return flat if rows is None else flat[rows]


def window_links(table, cosine: float = COSINE):
    """Of one block and the tile behind it, or of one run in two blocks: per row with links its id, their weight, and the id of its root."""
    import pyarrow as pa

    n = table.num_rows
    table = table.sort_by("id")
    role, number = table.column("role").to_numpy(), table.column("pass")[0].as_py()
    ids, weight = table.column("id").combine_chunks(), table.column("c").to_numpy()
    tiles, cells = _list_column(table, "tiles"), _list_column(table, "cells")
    links, found = np.zeros(n, dtype=np.int64), []
    sizes = table.column("v").combine_chunks().value_lengths().to_numpy()
    for k in np.unique(sizes).tolist():
        at = np.flatnonzero(sizes == k)
        v = _unit(_list_column(table.take(pa.array(at)), "v").astype(np.float64))
        pairs = []
        for a, b in ((OWN, OWN), (OWN, NEXT), (LO, HI)):
            x, y = np.flatnonzero(role[at] == a), np.flatnonzero(role[at] == b)
            if len(x) and len(y):
                close = v[x] @ v[y].T >= cosine
                i, j = np.nonzero(np.triu(close, 1) if a == b else close)
                pairs.append((at[x[i]], at[y[j]], a, b))
        for i, j, a, b in pairs:
            near = np.abs(tiles[i, number] - tiles[j, number]) <= 1
            same = cells[i, number] == cells[j, number]
            fresh = near | same if a == b else near if b == NEXT else same & ~near
            for p in range(number):
                fresh &= (np.abs(tiles[i, p] - tiles[j, p]) > 1) & (cells[i, p] != cells[j, p])
            found.append((i[fresh], j[fresh]))
    i, j = (np.concatenate(x) for x in zip(*found)) if found else (np.zeros(0, dtype=np.int64),) * 2
    np.add.at(links, i, weight[j])
    np.add.at(links, j, weight[i])
    linked = np.flatnonzero(links)
    root = _forest(n, i, j)
    return pa.table([ids.take(pa.array(linked)), pa.array(links[linked]), ids.take(pa.array(root[linked]))], names=["id", "links", "root"])


def near_duplicates(vectors: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", cosine: float = COSINE) -> DataFrame:
    """One row per vector: id, n_links (other rows linked directly), component_id (least id reachable), kept, n_copies.

    Equal vectors collapse first and link to each other.  Vectors that are null, empty, zero, or hold a null or a
    component that is not finite link with nothing.  Vectors of different length do not link.  Rows that repeat an id
    with other components are vectors of their own that share the id's component.  An empty table gives no rows; columns
    besides the two named are not read.
    """
    bits, depth, passes = layout(vectors.count(), cosine)
    sig = written(hashed(vectors, depth, passes, id_col, vec_col), "projections")
    some = sig.where("same is not null")
    reps = written(some.groupBy("same").agg(F.min("id").alias("id"), F.count("*").alias("c"), F.first("v").alias("v"), F.first("keys").alias("keys")).where("id is not null"), "vectors")
    placed = written(ordered(reps, reps.count(), bits, depth, passes), "places")
    by_pass = placed.groupBy("same").agg(F.sort_array(F.collect_list(F.struct("pass", "tile", "cell"))).alias("at"))  # one entry a pass
    rows = written(reps.select("same", "id", "c", "v").join(by_pass, "same").select("id", "c", "v", F.col("at.tile").alias("tiles"), F.col("at.cell").alias("cells")), "placed-vectors")
    # Runs of one cell that go on from a block into later ones.
    ends = placed.groupBy("pass", "block").agg(F.min("cell").alias("first"), F.max("cell").alias("last"))
    behind = ends.select(F.col("pass").alias("p"), F.col("block").alias("hi"), "first")
    runs = written(ends.select("pass", F.col("block").alias("lo"), F.col("last").alias("cell")).join(behind, (F.col("pass") == F.col("p")) & (F.col("cell") == F.col("first")) & (F.col("hi") > F.col("lo"))).select("pass", "lo", "hi", "cell"), "runs")
    spread = rows.select("*", F.posexplode(F.arrays_zip("tiles", "cells")).alias("pass", "x")).select("id", "c", "v", "tiles", "cells", "pass", F.col("x.tiles").alias("tile"), F.col("x.cells").alias("cell"))
    spread = spread.withColumn("block", F.floor(F.col("tile") / SPAN).cast("int"))
    block = F.struct(F.col("block").alias("lo"), F.col("block").alias("hi"), F.lit(OWN).alias("role"))
    before = F.struct((F.col("block") - 1).alias("lo"), (F.col("block") - 1).alias("hi"), F.lit(NEXT).alias("role"))
    leads = (F.col("tile") % SPAN == 0) & (F.col("block") > 0)
    near = spread.select("*", F.explode(F.when(leads, F.array(block, before)).otherwise(F.array(block))).alias("to"))
    held = near.select("pass", "to.lo", "to.hi", "to.role", "id", "c", "v", "tiles", "cells")
    if not runs.isEmpty():
        for side, role in (("lo", LO), ("hi", HI)):
            own = runs.withColumnsRenamed({"pass": "p", "cell": "x"})
            far = spread.join(own, (F.col("pass") == F.col("p")) & (F.col("cell") == F.col("x")) & (F.col("block") == F.col(side)))
            held = held.unionByName(far.select("pass", "lo", "hi", F.lit(role).alias("role"), "id", "c", "v", "tiles", "cells"))
    kind = reps.schema["id"].dataType
    schema = T.StructType([T.StructField("id", kind), T.StructField("links", T.LongType()), T.StructField("root", kind)])
    limit = cosine

    def run(table):
        return window_links(table, limit)

    found = written(held.groupBy("pass", "lo", "hi").applyInArrow(run, schema), "window-links")
    dropped(placed, rows, runs)
    label = components(found.select(F.col("id").alias("a"), F.col("root").alias("b")))
    links = found.groupBy("id").agg(F.sum("links").alias("links"))
    named = reps.select("same", "id", "c").join(links, "id", "left").join(label, "id", "left")
    named = named.select(F.col("same").alias("s"), "c", (F.coalesce("links", F.lit(0)) + F.col("c") - 1).alias("n_links"), F.coalesce("component", "id").alias("component_id"))
    out = sig.select("id", "same").join(named, F.col("same") == F.col("s"), "left")
    return out.select(
        F.col("id").alias(id_col), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", "id").alias("component_id"),
        F.coalesce(F.coalesce("component_id", "id") == F.col("id"), F.lit(True)).alias("kept"), F.coalesce("c", F.lit(1)).cast("long").alias("n_copies"),
    )
