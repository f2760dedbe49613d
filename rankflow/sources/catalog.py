"""Graphs built from the given tables. Vertex ids are arithmetic or hashes of
names, so any engine builds the same graph without a global numbering."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..operators.graph import Graph, TemporalGraph, ordered

GRID_WIDTH = 100
NEIGHBOURS = 8
#: Vectors compared against all others at once.
VECTOR_BLOCK = 512


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def name_id(name: Column) -> Column:
    """60 bits of the md5 of a name."""
    return F.conv(F.substring(F.md5(name), 1, 15), 16, 10).cast("long")


def trade(spark: SparkSession, sf_dir: str) -> Graph:
    """Customers and the suppliers of their orders: dense, like a social network."""
    lines, orders = table(spark, sf_dir, "lineitem"), table(spark, sf_dir, "orders")
    pairs = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select((F.col("o_custkey") * 2).alias("src"), (F.col("l_suppkey") * 2 + 1).alias("dst"))
    return Graph.build(pairs, _parties(spark, sf_dir), undirected=True)


def _parties(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "customer").select((F.col("c_custkey") * 2).alias("vid")).unionAll(table(spark, sf_dir, "supplier").select((F.col("s_suppkey") * 2 + 1).alias("vid")))


def catalog(spark: SparkSession, sf_dir: str) -> Graph:
    """Parts and their suppliers: dense, a second instance."""
    pairs = table(spark, sf_dir, "lineitem").select((F.col("l_partkey") * 2).alias("src"), (F.col("l_suppkey") * 2 + 1).alias("dst"))
    vids = table(spark, sf_dir, "part").select((F.col("p_partkey") * 2).alias("vid")).unionAll(table(spark, sf_dir, "supplier").select((F.col("s_suppkey") * 2 + 1).alias("vid")))
    return Graph.build(pairs, vids, undirected=True)


def web(spark: SparkSession, sf_dir: str) -> Graph:
    """Pages, the targets they link to, and their hosts."""
    pages = table(spark, sf_dir, "pages").select("url", "html")
    page = name_id(F.concat(F.lit("page "), F.col("url")))
    targets = pages.select(page.alias("src"), F.explode(F.regexp_extract_all("html", F.lit(r'href="([^"]*)"'), 1)).alias("t")).select("src", name_id(F.concat(F.lit("target "), F.col("t"))).alias("dst"))
    host = name_id(F.concat(F.lit("host "), F.regexp_extract("url", r"^[a-z]+://([^/]*)", 1)))
    hosts = pages.select(host.alias("src"), page.alias("dst"))
    both = hosts.unionAll(hosts.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    return Graph.build(targets.unionAll(both), pages.select(page.alias("vid")))


def geo(spark: SparkSession, sf_dir: str) -> Graph:
    """Regions, nations, customers and suppliers: a tree, like a road network."""

    def edge(name: str, child: str, kind: int, parent: str, above: int) -> DataFrame:
        return table(spark, sf_dir, name).select((F.col(child).cast("long") * 4 + kind).alias("src"), (F.col(parent).cast("long") * 4 + above).alias("dst"))

    rows = edge("nation", "n_nationkey", 1, "n_regionkey", 0).unionAll(edge("customer", "c_custkey", 2, "c_nationkey", 1)).unionAll(edge("supplier", "s_suppkey", 3, "s_nationkey", 1))
    return Graph.build(rows, table(spark, sf_dir, "region").select((F.col("r_regionkey").cast("long") * 4).alias("vid")), undirected=True)


def chain(spark: SparkSession, sf_dir: str) -> Graph:
    """Consecutive orders of a customer: many short paths."""
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    follow = F.lead("o_orderkey").over(W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey"))
    return Graph.build(orders.select(F.col("o_orderkey").alias("src"), follow.alias("dst")), orders.select(F.col("o_orderkey").alias("vid")), undirected=True)


def turns(spark: SparkSession, sf_dir: str) -> Graph:
    """A turn of a conversation and the one that follows it: directed paths."""
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", (F.col("conv_id") * 16 + F.col("turn")).alias("vid"))
    follow = F.lead("vid").over(W.partitionBy("conv_id").orderBy("turn"))
    return Graph.build(rows.select(F.col("vid").alias("src"), follow.alias("dst")), rows.select("vid"))


def line(spark: SparkSession, sf_dir: str) -> Graph:
    """Orders with neighbouring keys: one long path."""
    keys = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("vid"))
    rows = keys.select(F.col("vid").alias("src"), (F.col("vid") + 1).alias("dst")).join(keys.select(F.col("vid").alias("dst")), "dst", "left_semi")
    return Graph.build(rows, keys, undirected=True)


def grid(spark: SparkSession, sf_dir: str, width: int = GRID_WIDTH) -> Graph:
    """Orders on a grid ``width`` wide: like a road network in two dimensions."""
    keys = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("vid"))
    right = keys.where(F.col("vid") % width != width - 1).select(F.col("vid").alias("src"), (F.col("vid") + 1).alias("dst"))
    down = keys.select(F.col("vid").alias("src"), (F.col("vid") + width).alias("dst"))
    return Graph.build(right.unionAll(down).join(keys.select(F.col("vid").alias("dst")), "dst", "left_semi"), keys, undirected=True)


def knn(spark: SparkSession, sf_dir: str, k: int = NEIGHBOURS) -> Graph:
    """Each vector and its k nearest by cosine (rounded to 9 digits, ties by id).
    Blocks of vectors meet all rows, and keep k of each block, so what moves is k
    rows a vector and block; exact, and so for tables of this size."""
    import numpy as np
    import pandas as pd

    rows = table(spark, sf_dir, "embeddings").select("vec_id", "embedding").where("embedding is not null")
    held = rows.withColumn("block", F.expr(f"vec_id div {VECTOR_BLOCK}"))
    blocks = held.select("block").distinct().withColumnRenamed("block", "other")
    n = blocks.count()
    left = held.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(max(0, n - 1))))).withColumn("side", F.lit(0))
    right = held.withColumn("other", F.col("block")).withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(max(0, n - 1))))).withColumn("side", F.lit(1))

    def best(pdf: pd.DataFrame) -> pd.DataFrame:
        x, y = pdf[pdf.side == 0], pdf[pdf.side == 1]
        if not len(x) or not len(y):
            return pd.DataFrame({"src": [], "dst": [], "cosine": []})
        a, b = np.array(x.embedding.tolist(), np.float64), np.array(y.embedding.tolist(), np.float64)
        a /= np.linalg.norm(a, axis=1, keepdims=True)
        b /= np.linalg.norm(b, axis=1, keepdims=True)
        cos = np.round(a @ b.T, 9)
        ids, own = y.vec_id.to_numpy(), x.vec_id.to_numpy()
        cos[own[:, None] == ids[None]] = -np.inf
        order = np.lexsort((np.broadcast_to(ids, cos.shape), -cos), axis=1)[:, : k + 1]
        out = pd.DataFrame({"src": np.repeat(own, order.shape[1]), "dst": ids[order].ravel(), "cosine": np.take_along_axis(cos, order, 1).ravel()})
        return out[np.isfinite(out.cosine)]

    near = left.unionByName(right).groupBy("block", "other").applyInPandas(best, "src long, dst long, cosine double")
    top = near.withColumn("r", F.row_number().over(W.partitionBy("src").orderBy(F.desc("cosine"), "dst"))).where(F.col("r") <= k)
    return Graph.build(top.select("src", "dst"), rows.select(F.col("vec_id").alias("vid")))


def handoff(spark: SparkSession, sf_dir: str) -> TemporalGraph:
    """Successive users of the same type of event, in time order."""
    events = table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type")
    w = W.partitionBy("event_type").orderBy("ts", "event_id")
    rows = events.select("ts", "event_id", F.col("user_id").alias("src"), F.lead("user_id").over(w).alias("dst")).where("dst is not null")
    return TemporalGraph(ordered(rows, ["ts", "event_id"]).select("seq", "src", "dst"), events.select(F.col("user_id").alias("vid")).distinct())


def purchases(spark: SparkSession, sf_dir: str) -> TemporalGraph:
    """Order lines in the order of their dates, between customers and suppliers."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    rows = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select("o_orderdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", (F.col("o_custkey") * 2).alias("src"), (F.col("l_suppkey") * 2 + 1).alias("dst"))
    return TemporalGraph(ordered(rows, ["o_orderdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]).select("seq", "src", "dst"), _parties(spark, sf_dir), undirected=True)


GRAPHS: dict[str, Callable[[SparkSession, str], Graph]] = {f.__name__: f for f in (trade, catalog, web, geo, chain, line, grid, turns, knn)}
TEMPORAL: dict[str, Callable[[SparkSession, str], TemporalGraph]] = {f.__name__: f for f in (handoff, purchases)}


def build(name: str, spark: SparkSession, sf_dir: str) -> Graph:
    """A graph by name; of a temporal one, all its edges."""
    return GRAPHS[name](spark, sf_dir) if name in GRAPHS else TEMPORAL[name](spark, sf_dir).whole()
