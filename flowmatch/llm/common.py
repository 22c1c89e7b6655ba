"""What the operators of this subpackage share: table access, written intermediates, folds, bounded samples, lean workers."""

from __future__ import annotations

import atexit
import re
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession, functions as F, types as T

#: Words of the contracts: runs of anything but ASCII white space.  ``bytes.split()`` splits UTF-8 at exactly these bytes.
WORD = r"[^\x20\x09-\x0D]+"

#: Bytes of texts that a worker holds as Python objects at once; a longer text is held alone.
PIECE = 4 << 20
BATCH_BYTES = 8 << 20

_own_dir: str | None = None
_scratch: list[list[tuple[SparkSession, str]]] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder every executor and the driver see: ``spark.checkpoint.dir``.  Only a local session may do without; it gets a fresh folder."""
    global _own_dir
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if _own_dir is None:
        _own_dir = tempfile.mkdtemp(prefix="shared-")
        atexit.register(shutil.rmtree, _own_dir, ignore_errors=True)
    return _own_dir


def written(df: DataFrame, tag: str) -> DataFrame:
    """Cuts lineage: ``df`` as a Parquet table in the shared folder, read back with its own schema.

    A lost executor costs nothing but the tasks that ran on it.  The folder is named by ``tag`` and a random suffix;
    :func:`dropped` or :func:`scratch` delete it, else the cluster's own routine does, as for checkpoint files.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    if _scratch:
        _scratch[-1].append((spark, path))
    out = spark.read.schema(df.schema).parquet(path)
    out.written_at = path
    return out


def _delete(spark: SparkSession, path: str) -> None:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def dropped(*tables: DataFrame) -> None:
    """Deletes what :func:`written` wrote, for tables of which no later result reads."""
    for df in tables:
        _delete(df.sparkSession, df.written_at)


@contextmanager
def scratch() -> Iterator[list]:
    """Deletes all that is :func:`written` inside, at its end, but the tables put into the list it gives."""
    made, kept = [], []
    _scratch.append(made)
    try:
        yield kept
    finally:
        _scratch.pop()
        left = {df.written_at for df in kept}
        for spark, path in made:
            if path not in left:
                _delete(spark, path)
            elif _scratch:
                _scratch[-1].append((spark, path))


def trim() -> None:
    """Gives memory that this process has freed back to the system."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    give_back = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if give_back:
        give_back(0)


def lean(run: Callable) -> Callable:
    """For ``mapInArrow``: a worker is used for many tasks, and at the end of each keeps no memory that the task freed."""

    def wrapped(batches):
        yield from run(batches)
        trim()

    return wrapped


def mapped(rows: DataFrame, run: Callable, schema: T.StructType) -> DataFrame:
    """``rows.mapInArrow``, lean, with Arrow batches of ``BATCH_BYTES`` where the session leaves their size at the default.

    Spark's own bound of 64 MB a batch is held several times over by each running task, outside the heap.
    """
    conf, key = rows.sparkSession.conf, "spark.sql.execution.arrow.maxBytesPerBatch"
    if conf.isModifiable(key) and conf.get(key).rstrip("b") == str(64 << 20):
        conf.set(key, f"{BATCH_BYTES}b")
    return rows.mapInArrow(lean(run), schema)


def pieces(batches, column: int, limit: int = PIECE):
    """The record batches, cut so that the texts of ``column`` in each have about ``limit`` bytes; a longer text comes alone."""
    import numpy as np
    import pyarrow.compute as pc

    for b in batches:
        size = pc.fill_null(pc.binary_length(b.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
        upto = np.cumsum(size)
        start = 0
        while start < len(size):
            before = int(upto[start - 1]) if start else 0
            end = max(start + 1, int(np.searchsorted(upto, before + limit, side="right")))
            yield b.slice(start, end - start)
            start = end


#: Ids that a broadcast may hold (8 MB of longs); more ids are joined by shuffle.
BROADCAST_IDS = 1_000_000


def by_ids(df: DataFrame, ids: DataFrame, on: Column, how: str) -> DataFrame:
    """Semi or anti join of ``df`` with a written list of ids: wide rows stay where they are if the list is of a checked size, else both sides are shuffled."""
    return df.join(F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids, on, how)


def fold(doc_id: Column, n: int) -> Column:
    """crc32 of the id as text, modulo n; a null id counts as the empty text."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % n


def unit(*parts: Column) -> Column:
    """A uniform number in (0, 1) from the MD5 of the parts joined by ':'; DuckDB's md5() gives the same one."""
    text = F.concat_ws(":", *[F.coalesce(p.cast("string"), F.lit("")) for p in parts])
    return (F.conv(F.substring(F.md5(text.cast("binary")), 1, 12), 16, 10).cast("bigint") + F.lit(0.5)) / F.lit(float(1 << 48))


def first_by_hash(ids: DataFrame, key: str, n: int, seed: int = 0) -> DataFrame:
    """At most ``n`` rows, those whose key hashes lowest: bounded, the same on every run, a top-n with no full sort."""
    return ids.orderBy(F.xxhash64(F.col(key), F.lit(seed)), F.col(key)).limit(n)


def arrow_type(kind: T.DataType):
    from pyspark.sql.pandas.types import to_arrow_type

    return to_arrow_type(kind)


def text_bytes(column) -> list[bytes]:
    """An Arrow string column as UTF-8 bytes, null as empty, without building Python strings."""
    import pyarrow as pa

    return [x or b"" for x in column.cast(pa.large_binary()).to_pylist()]
