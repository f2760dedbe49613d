"""Beyond a fixed vertex set and plain links: growth, weights, preferences,
missing links out, and sampled walks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import cut
from .graph import Graph


def rescale_for_vertices(ranks: DataFrame, added: DataFrame, removed: DataFrame) -> DataFrame:
    """Start ranks after vertices came and went: survivors keep their share scaled
    to the new number, newcomers get 1 / n, and all sum to one."""
    left = ranks.select("vid", "rank").join(removed.select("vid"), "vid", "left_anti")
    come = added.select("vid").distinct().join(left.select("vid"), "vid", "left_anti")
    old_n = ranks.count()
    new_n = left.count() + come.count()
    rows = left.select("vid", (F.col("rank") * (old_n / new_n)).alias("rank")).unionAll(come.select("vid", F.lit(1.0 / new_n).alias("rank")))
    total = rows.agg(F.sum("rank").alias("t"))
    return rows.crossJoin(F.broadcast(total)).select("vid", (F.col("rank") / F.col("t")).alias("rank"))


def general_ranks(edges: DataFrame, vertices: DataFrame, alpha: float = 0.85, passes: int = 50, prefer: DataFrame | None = None, every: int = 5) -> DataFrame:
    """Ranks over weighted edges (src, dst, weight) without self-loops: what
    vertices without links out hold goes where jumps go, to all vertices or, by
    their weights, to those in ``prefer`` (vid, weight). (vid, rank)."""
    total_out = edges.groupBy("src").agg(F.sum("weight").alias("out"))
    links = edges.join(total_out, "src").select("src", "dst", (F.col("weight") / F.col("out")).alias("w")).persist()
    n = vertices.count()
    if prefer is None:
        base = vertices.select("vid", F.lit(1.0 / n).alias("jump"))
    else:
        whole = prefer.agg(F.sum("weight")).first()[0]
        base = vertices.join(prefer.select("vid", "weight"), "vid", "left").select("vid", (F.coalesce("weight", F.lit(0.0)) / whole).alias("jump"))
    base = cut(base)
    state = base.select("vid", F.col("jump").alias("rank"))
    for p in range(passes):
        mass = links.join(state, links["src"] == state["vid"]).groupBy(F.col("dst").alias("vid")).agg(F.sum(F.col("rank") * F.col("w")).alias("mass"))
        kept = mass.agg(F.sum("mass").alias("kept"))  # one row; what it lacks to one was without links
        state = base.join(mass, "vid", "left").crossJoin(F.broadcast(kept)).select("vid", (F.col("jump") * (1 - alpha + alpha * (1 - F.coalesce("kept", F.lit(0.0)))) + alpha * F.coalesce("mass", F.lit(0.0))).alias("rank"))
        if (p + 1) % every == 0 or p + 1 == passes:
            state = cut(state)
        else:
            state = cut(state) if p == 0 else state
    links.unpersist()
    return state


def monte_carlo_ranks(graph: Graph, walks_per_vertex: int = 32, seed: int = 1, alpha: float = 0.85, most_hops: int = 60) -> DataFrame:
    """Ranks estimated from walks that stop with probability 1 - alpha a step, a
    join for each hop. Choices are hashes, so runs agree; the error falls with the
    root of the number of walks."""
    degree = graph.out_degrees()
    numbered = _numbered(graph)
    at = cut(graph.vertices.withColumn("walk", F.explode(F.sequence(F.lit(1), F.lit(walks_per_vertex)))).select(F.xxhash64("vid", "walk").alias("walk"), "vid"))
    ended = []

    def unit(*cols):
        return F.pmod(F.xxhash64(*cols), F.lit(1 << 30)) / F.lit(float(1 << 30))

    for hop in range(most_hops):
        stops = unit("walk", F.lit(hop), F.lit(seed)) >= alpha
        ended.append(at.where(stops).groupBy("vid").count())
        going = at.where(~stops).join(degree, "vid").withColumn("i", F.pmod(F.xxhash64("walk", F.lit(hop), F.lit(seed + 7)), F.col("degree")))
        at = cut(going.join(numbered, (going["vid"] == numbered["src"]) & (going["i"] == numbered["i"])).select("walk", F.col("dst").alias("vid")))
        if at.isEmpty():
            break
    ended.append(at.groupBy("vid").count())
    every = ended[0]
    for e in ended[1:]:
        every = every.unionAll(e)
    total = graph.n * walks_per_vertex
    return graph.vertices.join(every.groupBy("vid").agg(F.sum("count").alias("c")), "vid", "left").select("vid", (F.coalesce("c", F.lit(0)) / total).alias("rank"))


def _numbered(graph: Graph) -> DataFrame:
    from pyspark.sql import Window as W

    return cut(graph.edges.withColumn("i", F.row_number().over(W.partitionBy("src").orderBy("dst")).cast("long") - 1))


def salted_pull(links: DataFrame, state: DataFrame, hub_degree: int, salts: int) -> DataFrame:
    """(vid, mass): a pull in which vertices with more than ``hub_degree`` links
    out spread theirs over ``salts`` tasks; only their rows of the state repeat."""
    hubs = links.groupBy("src").agg(F.count("*").alias("d")).where(F.col("d") > hub_degree).select("src", F.lit(True).alias("hub"))
    spread = links.join(hubs, "src", "left").withColumn("salt", F.when(F.col("hub"), F.pmod(F.xxhash64("dst"), F.lit(salts))).otherwise(F.lit(0)))
    copies = state.select(F.col("vid").alias("src"), "rank").join(hubs, "src", "left").withColumn("salt", F.explode(F.when(F.col("hub"), F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(0)))))
    return spread.select("src", F.col("salt").cast("long").alias("salt"), "dst", "w").join(copies.select("src", F.col("salt").cast("long").alias("salt"), "rank"), ["src", "salt"]).groupBy(F.col("dst").alias("vid")).agg(F.sum(F.col("rank") * F.col("w")).alias("mass"))
