"""One pass, or one step of an in-place pass, as one join and one aggregate.

A vertex links to itself, so its own old state arrives along its loop with its
neighbours' and the aggregate by target yields all of the next state. Marks of
the step before travel in the same rows: a vertex is marked when some
in-neighbour's last change exceeds the frontier tolerance.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _gathered(links: DataFrame, state: DataFrame, frontier_tol: float | None) -> DataFrame:
    loop = F.col("src") == F.col("dst")
    moved = F.abs(F.col("rank") - F.col("prev_rank")) > frontier_tol if frontier_tol is not None else F.lit(False)
    own = [F.max(F.when(loop, F.col("rank"))).alias("own"), F.bool_or(loop & F.col("affected")).alias("was")]
    if "open" in state.columns:
        own += [F.bool_or(loop & F.col("open")).alias("was_open"), F.bool_or(loop & F.col("processed")).alias("just")]
    # the state is hashed by partition: the links are neither moved nor sorted, and
    # no vector as large as the graph is ever broadcast
    return (
        links.join(state.hint("shuffle_hash"), links["src"] == state["vid"])
        .groupBy(F.col("dst").alias("vid"))
        .agg(*own, F.sum(F.col("rank") * F.col("w")).alias("mass"), F.bool_or(moved).alias("mark"), F.count("*").alias("links_in"))
    )


def _pull(alpha: float, n: int) -> Column:
    return F.lit((1.0 - alpha) / n) + F.lit(alpha) * F.col("mass")


def superstep(links: DataFrame, state: DataFrame, alpha: float, n: int, frontier_tol: float | None) -> DataFrame:
    """The next state (vid, rank, prev_rank, affected, links_in) of a two-buffer
    pass. frontier_tol None: no marks."""
    g = _gathered(links, state, frontier_tol).withColumn("affected", F.col("was") | F.col("mark"))
    return g.select("vid", F.when(F.col("affected"), _pull(alpha, n)).otherwise(F.col("own")).alias("rank"), F.col("own").alias("prev_rank"), "affected", "links_in")


def block_step(links: DataFrame, state: DataFrame, block: Column, alpha: float, n: int, tol: float, frontier_tol: float | None, close_rule: str, flag_rule: str) -> DataFrame:
    """The next state of one step of an in-place pass: where ``block`` holds and
    the vertex is affected, its rank is renewed from the freshest ranks. Marks of
    the step before count first; a mark re-opens only vertices that were not
    themselves processed in that step."""
    g = _gathered(links, state, frontier_tol).withColumn("affected", F.col("was") | F.col("mark"))
    fresh = F.col("mark") & ~F.col("just") if close_rule == "marks" else F.col("mark") & ~F.col("was")
    g = g.withColumn("opened", F.col("was_open") | fresh).withColumn("now", block & F.col("affected"))
    g = g.withColumn("rank", F.when(F.col("now"), _pull(alpha, n)).otherwise(F.col("own")))
    large = F.abs(F.col("rank") - F.col("own")) > tol
    stays = large if flag_rule == "reopen" else large & F.col("opened")
    return g.select("vid", "rank", F.col("own").alias("prev_rank"), "affected", F.when(F.col("now"), stays).otherwise(F.col("opened")).alias("open"), F.col("now").alias("processed"), "links_in")
