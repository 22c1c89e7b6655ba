"""Written state: tables in the shared folder that the session names, tables with an overlay of changes, commits that replay safely, a cold tier."""

from __future__ import annotations

import json
import re
import tempfile
import uuid
from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession, functions as F, types as T

_own: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``, which driver and executors share; only a local session may do without and gets a folder of its own."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not _own:
        _own.append(tempfile.mkdtemp(prefix="flowmatch-"))
    return _own[0]


def stored(df: DataFrame, tag: str = "table", folder: str | None = None) -> DataFrame:
    """``df`` written as Parquet to the shared folder, and read again: what follows recomputes nothing and survives lost executors."""
    path = f"{folder or shared_dir(df.sparkSession)}/{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return opened(df.sparkSession, path, df.schema)


def opened(spark: SparkSession, path: str, schema: T.StructType | None = None) -> DataFrame:
    out = (spark.read.schema(schema) if schema else spark.read).parquet(path)
    out.stored_at = path
    return out


def keeper(folder: str) -> Callable[[DataFrame], DataFrame]:
    return partial(stored, folder=folder)


def fs_path(spark: SparkSession, path: str):
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()), p


def delete(spark: SparkSession, path: str) -> None:
    fs, p = fs_path(spark, path)
    fs.delete(p, True)


class DeltaTable:
    """Rows with a key, as a written base and a small written overlay of new, changed and removed rows.

    A change costs as much as the overlay; the base stays where it is.  Readers leave out of the base what the overlay
    names, by an anti-join whose small side Catalyst knows the size of.  An overlay of over ``share`` of the base is
    folded into a new base.
    """

    def __init__(self, base: DataFrame, key: str, over: DataFrame | None = None, n_base: int | None = None, n_over: int = 0, share: float = 0.25):
        self.base, self.key, self.over, self.n_over, self.share = base, key, over, n_over, share
        self.n_base = base.count() if n_base is None else n_base

    def view(self) -> DataFrame:
        if self.over is None:
            return self.base
        rest = self.base.join(self.over.select(self.key), self.key, "left_anti").select(self.base.columns)
        return rest.unionByName(self.over.where("not gone").drop("gone"))

    def changed(self, rows: DataFrame | None, gone: DataFrame | None, keep: Callable[[DataFrame], DataFrame]) -> DeltaTable:
        """With ``rows`` new or in place of their keys' own, and without the keys of ``gone``."""
        parts = []
        if rows is not None:
            parts.append(rows.select(self.base.columns).withColumn("gone", F.lit(False)))
        if gone is not None:
            parts.append(gone.select(*[F.col(c) if c == self.key else F.lit(None).cast(self.base.schema[c].dataType).alias(c) for c in self.base.columns], F.lit(True).alias("gone")))
        new = parts[0] if len(parts) == 1 else parts[0].join(parts[1].select(self.key), self.key, "left_anti").unionByName(parts[1])
        if self.over is not None:
            new = keep(new)
            new = self.over.join(new.select(self.key), self.key, "left_anti").unionByName(new)
        over = keep(new)
        out = DeltaTable(self.base, self.key, over, self.n_base, over.count(), self.share)
        if out.n_over > max(1024, self.share * self.n_base):
            return DeltaTable(keep(out.view()), self.key, share=self.share)
        return out

    def pointer(self) -> dict:
        return {"key": self.key, "base": self.base.stored_at, "over": self.over.stored_at if self.over is not None else None, "n_base": self.n_base, "n_over": self.n_over, "share": self.share}

    @classmethod
    def at(cls, spark: SparkSession, pointer: dict) -> DeltaTable:
        base = opened(spark, pointer["base"])
        over = opened(spark, pointer["over"]) if pointer["over"] else None
        return cls(base, pointer["key"], over, pointer["n_base"], pointer["n_over"], pointer["share"])


class Commits:
    """One small file per batch, written last: a batch counts once its file is there, so replaying it changes nothing."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")

    def ids(self) -> list[int]:
        fs, p = fs_path(self.spark, self.path)
        return sorted(int(s.getPath().getName()) for s in fs.listStatus(p) if s.getPath().getName().lstrip("-").isdigit()) if fs.exists(p) else []

    def read(self, batch_id: int) -> dict:
        fs, p = fs_path(self.spark, f"{self.path}/{batch_id}")
        stream = fs.open(p)
        try:
            return json.loads(stream.readUTF())
        finally:
            stream.close()

    def write(self, batch_id: int, what: dict) -> None:
        fs, half = fs_path(self.spark, f"{self.path}/{batch_id}.part")
        stream = fs.create(half, True)
        stream.writeUTF(json.dumps(what))
        stream.close()
        fs.rename(half, fs_path(self.spark, f"{self.path}/{batch_id}")[1])


class TieredStore:
    """Edges younger than the hot window stay cached; older ones go to Parquet by day, with their masks, and are pruned by day when read."""

    def __init__(self, spark: SparkSession, path: str, hot_window: int, day: int = 86_400_000_000):
        self.spark, self.path, self.hot_window, self.day = spark, path, hot_window, day
        self.flushed = False

    def flush(self, edges: DataFrame, now: int) -> DataFrame:
        """Appends what has left the hot window to the cold tier; returns the hot rest, cached where memory and disk allow."""
        cut = now - self.hot_window
        edges.where(F.col("ts") <= cut).withColumn("day", F.floor(F.col("ts") / self.day)).write.mode("append").partitionBy("day").parquet(self.path)
        self.flushed = True
        return edges.where(F.col("ts") > cut).persist()

    def window(self, hot: DataFrame, start: int, end: int) -> DataFrame:
        """All edges with start < ts <= end, from both tiers; only the days that the window meets are read."""
        rows = hot
        if self.flushed:
            cold = self.spark.read.schema(T.StructType([*hot.schema.fields, T.StructField("day", T.LongType())])).parquet(self.path)
            rows = cold.where((F.col("day") >= start // self.day) & (F.col("day") <= end // self.day)).select(hot.columns).unionByName(hot)
        return rows.where((F.col("ts") > start) & (F.col("ts") <= end))

    def bytes(self) -> int:
        fs, p = fs_path(self.spark, self.path)
        return fs.getContentSummary(p).getLength() if self.flushed else 0
