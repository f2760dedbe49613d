"""The form of the in-place methods for large clusters: a task owns a block.

A pass joins the links into a block with the ranks of their sources, hands each
block to one task as arrays, and the task sweeps its vertices several times,
with its own freshest ranks and the other blocks' ranks of the pass before. One
shuffle a pass moves ranks; links stay where they are. The fixed point is that of
the other methods; only the way to it differs.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..params import Params, Pass, RankRun
from ..storage import cut
from .blocks import by_hash
from .graph import Graph


def _sweeper(alpha: float, base: float, sweeps: int, tol: float, only_affected: bool):
    def sweep(key: tuple, links: pd.DataFrame) -> pd.DataFrame:
        links = links.sort_values("dst", kind="stable")
        dst, src, w = links["dst"].to_numpy(), links["src"].to_numpy(), links["w"].to_numpy()
        rank = links["rank"].to_numpy().copy()
        vids, first = np.unique(dst, return_index=True)
        count = np.diff(np.append(first, len(dst)))
        # where a link's source lies in this block, its rank follows the sweeps
        at = np.minimum(np.searchsorted(vids, src), len(vids) - 1)
        own = vids[at] == src
        loop = src == dst
        old = np.empty(len(vids))
        old[np.searchsorted(vids, dst[loop])] = rank[loop]
        flags = np.ones(len(vids), bool)
        if only_affected:
            flags[:] = False
            flags[np.searchsorted(vids, dst[loop])] = links["affected"].to_numpy()[loop]
            marked = np.add.reduceat(links["moved"].to_numpy().astype(np.int64), first) > 0
            flags |= marked
        now = old.copy()
        for _ in range(sweeps):
            rank[own] = now[at[own]]
            new = np.where(flags, base + alpha * np.add.reduceat(rank * w, first), now)
            moved = np.abs(new - now).max() if len(new) else 0.0
            now = new
            if moved <= tol / 10:
                break
        return pd.DataFrame({"vid": vids, "rank": now, "prev_rank": old, "affected": flags, "links_in": count})

    return sweep


def local_async(cur: Graph, state: DataFrame, params: Params = Params(), frontier_tol: float | None = None, sweeps: int = 4) -> RankRun:
    """``state`` is (vid, rank, affected); frontier_tol None: all are affected."""
    params = params.for_size(cur.n)
    base = (1.0 - params.alpha) / cur.n
    links = cur.links().withColumn("block", by_hash("dst", params.blocks)).repartition(params.blocks, "block").persist()
    state = cut(state.select("vid", "rank", F.col("rank").alias("prev_rank"), "affected", F.lit(0).cast("long").alias("links_in")))
    schema = "vid long, rank double, prev_rank double, affected boolean, links_in long"
    trace: list[Pass] = []
    converged = False
    limit = params.fixed_passes or params.max_passes
    sweep = _sweeper(params.alpha, base, sweeps, params.tol, frontier_tol is not None)
    while len(trace) < limit and not converged:
        moved = F.abs(F.col("rank") - F.col("prev_rank")) > (frontier_tol if frontier_tol is not None else float("inf"))
        seen = state.select(F.col("vid").alias("src"), "rank", "affected", moved.alias("moved"))
        state = cut(links.join(seen, "src").groupBy("block").applyInPandas(sweep, schema))
        row = state.agg(F.sum(F.col("affected").cast("long")), F.sum(F.when(F.col("affected"), F.col("links_in")).otherwise(0)), F.max(F.abs(F.col("rank") - F.col("prev_rank")))).first()
        trace.append(Pass(len(trace) + 1, row[0] or 0, row[1] or 0, row[2] or 0.0))
        converged = params.fixed_passes is None and trace[-1].max_delta <= params.tol
    links.unpersist()
    return RankRun(state.select("vid", "rank"), state, len(trace), converged, trace)
