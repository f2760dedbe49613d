"""Blocks of vertices: the steps of an in-place pass, the units of work that
workers take."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .graph import Graph, ordered


def by_id(vid: Column | str, blocks: int) -> Column:
    """Round-robin by id: the same block for a vertex in any engine."""
    return F.pmod(F.col(vid) if isinstance(vid, str) else vid, F.lit(blocks)).cast("long")


def by_hash(vid: Column | str, blocks: int) -> Column:
    """Spread whatever the ids are."""
    return F.pmod(F.xxhash64(vid), F.lit(blocks))


def by_size(graph: Graph, size: int = 2048) -> DataFrame:
    """(vid, block): ``size`` consecutive vertices each."""
    return ordered(graph.vertices, ["vid"]).select("vid", F.expr(f"seq div {size}").alias("block"))


def by_edges(graph: Graph, blocks: int, parts: int = 64) -> DataFrame:
    """(vid, block): consecutive vertices, about equally many links into each
    block. The running sum is taken in ranges of ids and then over the ranges."""
    degree = graph.edges.groupBy(F.col("dst").alias("vid")).agg(F.count("*").alias("degree"))
    rows = graph.vertices.join(degree, "vid", "left").select("vid", F.coalesce("degree", F.lit(0)).alias("degree"))
    lo, hi = rows.agg(F.min("vid"), F.max("vid")).first()
    if lo is None:
        return rows.select("vid", F.lit(0).cast("long").alias("block"))
    part = F.expr(f"(vid - {lo}) div {max(1, -(-(hi - lo + 1) // parts))}")
    rows = rows.withColumn("part", part)
    sums = rows.groupBy("part").agg(F.sum("degree").alias("sum"))  # at most ``parts`` rows
    total = F.sum("sum").over(W.partitionBy())
    bases = sums.select("part", F.coalesce(F.sum("sum").over(W.orderBy("part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("base"), total.alias("total"))
    near = F.coalesce(F.sum("degree").over(W.partitionBy("part").orderBy("vid").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    return rows.withColumn("near", near).join(F.broadcast(bases), "part").select("vid", F.least(F.expr(f"((base + near) * {blocks}) div greatest(total, 1)"), F.lit(blocks - 1)).cast("long").alias("block"))
