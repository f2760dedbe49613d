"""Directed graphs as edge sets, and graphs whose edges come in an order."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

#: Rows of a batch that is sent to all edges.
SENT_ROWS = 500_000


@dataclass
class Graph:
    """edges (src, dst), a set; vertices (vid), a superset of their ends. With
    ``self_loops`` each vertex links to itself, so none is without a link out and
    a vertex's own state reaches it in the same join as its neighbours'."""

    edges: DataFrame
    vertices: DataFrame
    self_loops: bool = True
    _links: DataFrame | None = None
    _n: int | None = None
    _n_links: int | None = None

    @staticmethod
    def build(edges: DataFrame, vertices: DataFrame | None = None, undirected: bool = False, self_loops: bool = True) -> Graph:
        """From any (src, dst) rows. Rows with a null end are no edges; repeated
        rows count once."""
        rows = edges.select(F.col("src").cast("long"), F.col("dst").cast("long")).dropna()
        ends = rows.select(F.explode(F.array("src", "dst")).alias("vid"))
        vids = (ends if vertices is None else ends.unionAll(vertices.select(F.col("vid").cast("long")))).dropna().distinct()
        if undirected and self_loops:  # each pair once, then both ways
            pairs = rows.where("src <> dst").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).distinct()
            loops = vids.select(F.col("vid").alias("src"), F.col("vid").alias("dst"))
            return Graph(pairs.unionAll(pairs.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).unionAll(loops), vids)
        if undirected:
            rows = rows.unionAll(rows.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
        if self_loops:
            rows = rows.unionAll(vids.select(F.col("vid").alias("src"), F.col("vid").alias("dst")))
        return Graph(rows.distinct(), vids, self_loops)

    @property
    def n(self) -> int:
        if self._n is None:
            self._n = self.vertices.count()
        return self._n

    @property
    def n_links(self) -> int:
        if self._n_links is None:
            self._n_links = self.links().count()
        return self._n_links

    def out_degrees(self) -> DataFrame:
        return self.edges.groupBy(F.col("src").alias("vid")).agg(F.count("*").alias("degree"))

    def links(self) -> DataFrame:
        """(src, dst, w = 1 / out-degree), dealt by src once and kept for all
        passes: a pass then moves only partial sums by dst."""
        if self._links is None:
            degree = W.partitionBy("src")
            parts = int(self.edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
            self._links = self.edges.repartition(parts, "src").select("src", "dst", (F.lit(1.0) / F.count("*").over(degree)).alias("w")).persist(StorageLevel.MEMORY_AND_DISK)
        return self._links

    def release(self) -> None:
        if self._links is not None:
            self._links.unpersist()
            self._links = None

    def apply(self, batch: DataFrame, size: int | None = None) -> Graph:
        """The next snapshot: deletions go, insertions come, an edge in both
        stays. Self-loops are never deleted; the vertex set does not change. size: rows
        of the batch, if known; to a small one the edges come unmoved."""
        gone = batch.where("op = '-' and src <> dst").select("src", "dst")
        come = batch.where("op = '+'").select("src", "dst")
        left = self.edges.join(gone, ["src", "dst"], "left_anti")
        known = come.join(self.vertices.withColumnRenamed("vid", "src"), "src", "left_semi").join(self.vertices.withColumnRenamed("vid", "dst"), "dst", "left_semi").select("src", "dst")
        if size is not None and size <= SENT_ROWS:
            left, new = self.edges.join(F.broadcast(gone), ["src", "dst"], "left_anti"), known.distinct()
            there = left.join(F.broadcast(new), ["src", "dst"], "left_semi")
            return Graph(left.unionAll(new.join(there, ["src", "dst"], "left_anti")), self.vertices, self.self_loops, _n=self._n)
        return Graph(left.unionAll(known).distinct(), self.vertices, self.self_loops, _n=self._n)

    def profile(self) -> DataFrame:
        """One row: vertices, edges, average degree."""
        if self.self_loops:
            both = self.edges.agg(F.count("*").alias("edges"), F.count(F.when(F.col("src") == F.col("dst"), 1)).alias("vertices"))
            return both.select("vertices", "edges", F.round(F.col("edges") / F.col("vertices"), 6).alias("degree"))
        return self.edges.agg(F.count("*").alias("edges")).crossJoin(self.vertices.agg(F.count("*").alias("vertices"))).select("vertices", "edges", F.round(F.col("edges") / F.col("vertices"), 6).alias("degree"))


@dataclass
class TemporalGraph:
    """rows (seq, src, dst): edge insertions in a total order, repeats kept."""

    rows: DataFrame
    vertices: DataFrame
    undirected: bool = False
    _total: int | None = None

    @property
    def total(self) -> int:
        if self._total is None:
            self._total = self.rows.count()
        return self._total

    def prefix(self, fraction: float) -> Graph:
        """The graph of the first ``fraction`` of the rows, all vertices there."""
        stop = int(self.total * fraction)
        return Graph.build(self.rows.where(F.col("seq") < stop), self.vertices, self.undirected)

    def slice(self, start: int, size: int) -> DataFrame:
        """The insertions of rows start to start + size, as a batch."""
        some = self.rows.where((F.col("seq") >= start) & (F.col("seq") < start + size)).select("src", "dst")
        if self.undirected:
            some = some.unionAll(some.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
        return some.distinct().withColumn("op", F.lit("+"))

    def whole(self) -> Graph:
        return self.prefix(1.0)


def ordered(rows: DataFrame, order: list[str], parts: int | None = None) -> DataFrame:
    """``rows`` with seq, a dense 0-based position in ``order``, without bringing
    all rows to one task: ranges, counts of ranges, offsets."""
    from ..storage import cut

    spark = rows.sparkSession
    n = parts or int(spark.conf.get("spark.sql.shuffle.partitions"))
    placed = cut(rows.repartitionByRange(n, *order).sortWithinPartitions(*order).withColumn("_at", F.monotonically_increasing_id()))
    part = F.shiftright("_at", 33)
    sizes = sorted((r[0], r[1]) for r in placed.groupBy(part).count().collect())  # a row for each range
    base, total = [], 0
    for p, size in sizes:
        base.append((int(p), total))
        total += size
    bases = F.broadcast(spark.createDataFrame(base, "_part long, _base long"))
    return placed.withColumn("_part", part).join(bases, "_part").withColumn("seq", F.col("_base") + F.col("_at").bitwiseAND(F.lit((1 << 33) - 1))).drop("_part", "_base", "_at")
