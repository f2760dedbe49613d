"""Edge lists from text, and snapshots and ranks kept by version."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.graph import Graph, TemporalGraph, ordered


def edge_rows(spark: SparkSession, path: str, comments: str = "#%", temporal: bool = False) -> DataFrame:
    """(src, dst[, ts]) of a text file of pairs: blanks, tabs, commas or
    semicolons between, comment lines dropped. Lines that hold no pair of whole
    numbers are dropped, and so is the size line of a matrix file, which is the
    first line without a comment after one that starts with %%."""
    lines = spark.read.text(path).where(~F.col("value").rlike(rf"^\s*[{comments}]"))
    parts = F.split(F.trim("value"), r"[\s,;]+")
    rows = lines.select(F.try_element_at(parts, F.lit(1)).try_cast("long").alias("src"), F.try_element_at(parts, F.lit(2)).try_cast("long").alias("dst"), F.try_element_at(parts, F.lit(3)).alias("third"))
    head = spark.read.text(path).limit(1).collect()  # one line
    if head and head[0][0].startswith("%%"):
        first = lines.limit(1).collect()
        if first:
            sizes = [int(x) for x in first[0][0].split()[:3] if x.isdigit()]
            if len(sizes) == 3:
                rows = rows.where(~((F.col("src") == sizes[0]) & (F.col("dst") == sizes[1]) & (F.col("third") == str(sizes[2]))))
    rows = rows.where("src is not null and dst is not null")
    return rows.select("src", "dst", F.col("third").try_cast("long").alias("ts")) if temporal else rows.select("src", "dst")


def edge_list(spark: SparkSession, path: str, undirected: bool = False, temporal: bool = False) -> Graph | TemporalGraph:
    rows = edge_rows(spark, path, temporal=temporal)
    if not temporal:
        return Graph.build(rows, undirected=undirected)
    seq = ordered(rows, ["ts", "src", "dst"]).select("seq", "src", "dst")
    return TemporalGraph(seq, seq.select(F.explode(F.array("src", "dst")).alias("vid")).distinct(), undirected)
