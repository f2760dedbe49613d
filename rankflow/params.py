"""Parameters and results that all methods share."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame


@dataclass(frozen=True)
class Params:
    """alpha: damping; tol: stop when no rank changes by more; frontier_tol: a
    change above it marks out-neighbours (tol / 1000 unless given); max_passes:
    cap; fixed_passes: run exactly so many passes, without a stop test; blocks:
    steps of a pass of the in-place methods; close_rule: 'marks' (a mark re-opens
    a vertex) or 'delta' (only if it was not affected before); flag_rule:
    'reopen', 'latched' or 'literal'; checkpoint_every: passes between cuts of
    the lineage; plan: 'fused' (passes over all links), 'pruned' (over regions
    around the affected vertices), 'local' (over regions, or a whole graph, that one
    task solves; an error if too large) or 'auto' (for methods that start with part
    of the vertices: by the size of the region; 'fused' for the others); tol_scale: 'absolute', or
    '1/n' to multiply tolerances by the mean rank, for graphs whose mean rank is
    below the tolerance."""

    alpha: float = 0.85
    tol: float = 1e-10
    frontier_tol: float | None = None
    max_passes: int = 500
    fixed_passes: int | None = None
    blocks: int = 8
    close_rule: str = "marks"
    flag_rule: str = "reopen"
    checkpoint_every: int = 6
    plan: str = "auto"
    tol_scale: str = "absolute"

    def __post_init__(self):
        if not 0 <= self.alpha < 1:
            raise ValueError("alpha must be in [0, 1)")
        if self.close_rule not in ("marks", "delta"):
            raise ValueError("close_rule is 'marks' or 'delta'")
        if self.flag_rule not in ("reopen", "latched", "literal"):
            raise ValueError("flag_rule is 'reopen', 'latched' or 'literal'")
        if self.plan not in ("fused", "pruned", "local", "auto"):
            raise ValueError("plan is 'fused', 'pruned', 'local' or 'auto'")
        if self.tol_scale not in ("absolute", "1/n"):
            raise ValueError("tol_scale is 'absolute' or '1/n'")

    @property
    def frontier(self) -> float:
        return self.tol / 1000 if self.frontier_tol is None else self.frontier_tol

    def for_size(self, n: int) -> Params:
        """With tolerances for a graph of n vertices."""
        if self.tol_scale == "absolute":
            return self
        return replace(self, tol=self.tol / n, frontier_tol=self.frontier / n, tol_scale="absolute")


@dataclass(frozen=True)
class Pass:
    """What one pass did: affected vertices, links read into them, the largest
    change, and open vertices (in-place methods; -1 otherwise)."""

    number: int
    active: int
    edges_read: int
    max_delta: float
    open: int = -1


@dataclass
class RankRun:
    """ranks (vid, rank), the last state, how many passes, whether the stop test
    ended the run, and the trace."""

    ranks: DataFrame
    state: DataFrame
    passes: int
    converged: bool
    trace: list[Pass] = field(default_factory=list)

    @property
    def edges_read(self) -> int:
        return sum(p.edges_read for p in self.trace)

    def trace_frame(self) -> DataFrame:
        rows = [(p.number, p.active, p.edges_read, p.max_delta, p.open) for p in self.trace]
        return self.ranks.sparkSession.createDataFrame(rows, "pass int, active long, edges_read long, max_delta double, open long")
