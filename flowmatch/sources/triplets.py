"""Triplet files: ``src dst label [ts]`` lines, and a data source for signed ones, in which negative ids mean a delete."""

from __future__ import annotations

import glob
import os

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "src long, dst long, label string, ts long"


def write_triplets(edges: DataFrame, path: str) -> None:
    edges.select("src", "dst", "label", "ts").write.option("sep", " ").csv(path)


def read_triplets(spark: SparkSession, path: str) -> DataFrame:
    """By Spark's own reader, in parallel and from any store; lines that are no triplet stop the read."""
    return spark.read.schema(SCHEMA).option("sep", " ").option("mode", "FAILFAST").csv(path)


class _File(InputPartition):
    def __init__(self, path: str):
        self.path = path


class _Reader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path.removeprefix("file://").removeprefix("file:")

    def partitions(self) -> list[_File]:
        names = sorted(glob.glob(f"{self.path}/part-*")) if os.path.isdir(self.path) else [self.path]
        return [_File(n) for n in names] or [_File("")]

    def read(self, partition: _File):
        if not partition.path:
            return
        with open(partition.path, encoding="utf-8") as lines:
            for line in lines:
                src, dst, label = line.split()
                yield int(src), int(dst), label


class SignedTriplets(DataSource):
    """``src dst label`` lines with ids from 1, negative for deletes, from files that all executors see; a task per file."""

    @classmethod
    def name(cls) -> str:
        return "signed_triplets"

    def schema(self) -> str:
        return "src long, dst long, label string"

    def reader(self, schema) -> _Reader:
        return _Reader(self.options["path"])


def register_source(spark: SparkSession) -> None:
    spark.dataSource.register(SignedTriplets)
