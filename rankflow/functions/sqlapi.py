"""The SQL surface: views of graphs, batches and ranks, and calls by name."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..operators import methods
from ..operators.graph import Graph
from ..params import Params
from . import udfs


def register(spark: SparkSession, graphs: dict[str, Graph]) -> None:
    """Views graph_<name>_edges and graph_<name>_vertices, and the functions."""
    for name, g in graphs.items():
        g.edges.createOrReplaceTempView(f"graph_{name}_edges")
        g.vertices.createOrReplaceTempView(f"graph_{name}_vertices")
    udfs.register(spark)


def publish(ranks: DataFrame, method: str, version: int) -> str:
    """View ranks_<method>_t<version>."""
    name = f"ranks_{method}_t{version}"
    ranks.createOrReplaceTempView(name)
    return name


def call(spark: SparkSession, method: str, edges: str, version: int = 0, before: str | None = None, batch: str | None = None, prev_edges: str | None = None, **changes) -> DataFrame:
    """Runs a method on views and publishes its ranks. ``edges`` is the current
    snapshot (src, dst), ``prev_edges`` the one before, ``before`` earlier ranks,
    ``batch`` the changes."""
    cur = Graph.build(spark.table(edges))
    prev = Graph.build(spark.table(prev_edges)) if prev_edges else cur
    ranks = spark.table(before) if before else methods.uniform(cur)
    changed = spark.table(batch) if batch else spark.createDataFrame([], "src long, dst long, op string")
    run = methods.run(method, prev, cur, changed, ranks, Params(**changes))
    publish(run.ranks, method, version)
    return run.ranks


def reach_sql(spark: SparkSession, marks: str, edges: str, max_depth: int) -> DataFrame:
    """Vertices within ``max_depth`` links of the marks by a recursive query. Spark
    recursion cannot drop repeats on the way, so the depth is bounded; the loop in
    ``marking.reach`` has no such bound."""
    return spark.sql(
        f"""WITH RECURSIVE walk(vid, depth) AS (
          SELECT vid, 0 FROM {marks} UNION ALL SELECT e.dst, depth + 1 FROM walk JOIN {edges} e ON e.src = walk.vid WHERE depth < {max_depth} AND e.src <> e.dst
        ) SELECT DISTINCT vid FROM walk"""
    )
