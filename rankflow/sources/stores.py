"""Versions of snapshots and ranks as Parquet folders.

A version is written beside its place and renamed into it, so readers see all of
it or nothing, and writing a version that is there already changes nothing:
repeated micro-batches are harmless. Ranks are partitioned by block, so a reader
of few blocks prunes the rest.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from ..operators.blocks import by_hash
from ..operators.graph import Graph


class VersionStore:
    def __init__(self, spark: SparkSession, folder: str, blocks: int = 8):
        self.spark, self.folder, self.blocks = spark, folder.rstrip("/"), blocks
        jvm = spark.sparkContext._jvm
        self._path = jvm.org.apache.hadoop.fs.Path
        self._fs = self._path(self.folder).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())

    def versions(self, kind: str) -> list[int]:
        place = self._path(f"{self.folder}/{kind}")
        if not self._fs.exists(place):
            return []
        names = [f.getPath().getName() for f in self._fs.listStatus(place)]
        return sorted(int(n[2:]) for n in names if n.startswith("v="))

    def latest(self, kind: str) -> int | None:
        found = self.versions(kind)
        return found[-1] if found else None

    def put(self, kind: str, version: int, df: DataFrame, key: str) -> bool:
        """Whether this call wrote the version."""
        if version in self.versions(kind):
            return False
        own = f"{self.folder}/.tmp-{uuid.uuid4().hex}"
        df.withColumn("block", by_hash(key, self.blocks)).write.partitionBy("block").parquet(own)
        place = self._path(f"{self.folder}/{kind}/v={version}")
        self._fs.mkdirs(self._path(f"{self.folder}/{kind}"))
        done = self._fs.rename(self._path(own), place)
        if not done:
            self._fs.delete(self._path(own), True)
        return bool(done)

    def get(self, kind: str, version: int) -> DataFrame:
        return self.spark.read.parquet(f"{self.folder}/{kind}/v={version}")

    def put_graph(self, version: int, graph: Graph) -> bool:
        self.put("vertices", version, graph.vertices, "vid")
        return self.put("edges", version, graph.edges, "dst")

    def graph(self, version: int) -> Graph:
        return Graph(self.get("edges", version).select("src", "dst"), self.get("vertices", version).select("vid"))

    def put_ranks(self, version: int, ranks: DataFrame) -> bool:
        return self.put("ranks", version, ranks.select("vid", "rank"), "vid")

    def ranks(self, version: int) -> DataFrame:
        return self.get("ranks", version).select("vid", "rank")
