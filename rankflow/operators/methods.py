"""The methods: from scratch, warm start, reach and frontier, each with two
buffers and a stop test for every pass (``*_sync``) or in place, block by block,
with open flags (``*_async``)."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from ..params import Params, Pass, RankRun
from ..storage import cut
from . import marking, region
from .blocks import by_id
from .graph import Graph
from .kernel import block_step, superstep

#: 'auto' runs a region apart below this share of all vertices.
REGION_BELOW = 0.25


def uniform(graph: Graph) -> DataFrame:
    """(vid, rank): the ranks that a run from scratch starts with."""
    return graph.vertices.select("vid", F.lit(1.0 / graph.n).alias("rank"))


def _start(cur: Graph, ranks: DataFrame, affected: DataFrame | None) -> DataFrame:
    """First state. Vertices without an earlier rank start at 1 / n. A graph needs its
    self-loops: a vertex's own state comes along its loop."""
    if not cur.self_loops:
        raise ValueError("ranks need a graph with self-loops; general_ranks takes any")
    rows = cur.vertices.join(ranks.select("vid", "rank"), "vid", "left").select("vid", F.coalesce("rank", F.lit(1.0 / cur.n)).alias("rank"))
    rows = rows.withColumn("prev_rank", F.col("rank"))
    if affected is None:
        return rows.withColumn("affected", F.lit(True))
    return rows.join(affected.select("vid").distinct().withColumn("_m", F.lit(True)), "vid", "left").withColumn("affected", F.coalesce("_m", F.lit(False))).drop("_m")


def _watch(state: DataFrame, opened: bool = False) -> tuple[DataFrame, Observation]:
    """Counts a pass while its rows go by, without a job of their own."""
    seen = Observation()
    links_in = F.when(F.col("affected"), F.col("links_in")).otherwise(0)
    facts = [
        F.coalesce(F.sum(F.col("affected").cast("long")), F.lit(0)).alias("active"),
        F.coalesce(F.sum(links_in), F.lit(0)).cast("long").alias("edges_read"),
        F.coalesce(F.max(F.abs(F.col("rank") - F.col("prev_rank"))), F.lit(0.0)).alias("max_delta"),
    ]
    if opened:
        facts.append(F.coalesce(F.sum(F.col("open").cast("long")), F.lit(0)).alias("open"))
    return state.observe(seen, *facts), seen


def _pass(number: int, seen: Observation) -> Pass:
    got = seen.get
    return Pass(number, got["active"], got["edges_read"], got["max_delta"], got.get("open", -1))


def _passes_sync(links: DataFrame, state: DataFrame, others: DataFrame | None, params: Params, n: int, frontier_tol: float | None, most: int) -> tuple[DataFrame, list[Pass], bool]:
    """At most ``most`` passes, until no rank changes by more than the tolerance.
    Several passes make one job, counted by observations; if one before the last of a
    job ends the run, that job is done again up to it. ``others`` are vertices that
    links come from but that do not change."""
    trace: list[Pass] = []

    def step(s: DataFrame) -> DataFrame:
        return superstep(links, s if others is None else s.unionByName(others), params.alpha, n, frontier_tol)

    while len(trace) < most:
        count = min(params.checkpoint_every, most - len(trace))
        now, seen = state, []
        for _ in range(count):
            now, one = _watch(step(now))
            seen.append(one)
        now = cut(now)
        done = [_pass(len(trace) + 1 + i, one) for i, one in enumerate(seen)]
        stop = next((i for i, p in enumerate(done) if p.max_delta <= params.tol), None) if params.fixed_passes is None else None
        if stop is not None:
            if stop < count - 1:
                now = state
                for _ in range(stop + 1):
                    now = step(now)
                now = cut(now)
            return now, trace + done[: stop + 1], True
        trace += done
        state = now
    return state, trace, False


def _passes_async(links: DataFrame, state: DataFrame, others: DataFrame | None, params: Params, n: int, frontier_tol: float | None, most: int) -> tuple[DataFrame, list[Pass], bool]:
    """The same of ``blocks`` steps, each with the freshest ranks, until no vertex is
    open. The steps of a pass and the marks of its last step make one job."""
    trace: list[Pass] = []

    def step(s: DataFrame, block: Column) -> DataFrame:
        every = s if others is None else s.unionByName(others)
        return block_step(links, every, block, params.alpha, n, params.tol, frontier_tol, params.close_rule, params.flag_rule)

    while len(trace) < most:
        now, seen = state, []
        for b in range(params.blocks):
            now = step(now, by_id("vid", params.blocks) == b)
            counted = Observation()
            did = F.col("processed")
            now = now.observe(
                counted,
                F.coalesce(F.sum(did.cast("long")), F.lit(0)).alias("active"),
                F.coalesce(F.sum(F.when(did, F.col("links_in")).otherwise(0)), F.lit(0)).cast("long").alias("edges_read"),
                F.coalesce(F.max(F.abs(F.col("rank") - F.col("prev_rank"))), F.lit(0.0)).alias("max_delta"),
            )
            seen.append(counted)
        flushed, last = _watch(step(now, F.lit(False)), opened=True)
        state = cut(flushed)
        got = [s.get for s in seen]
        trace.append(Pass(len(trace) + 1, sum(g["active"] for g in got), sum(g["edges_read"] for g in got), max(g["max_delta"] for g in got), last.get["open"]))
        if params.fixed_passes is None and trace[-1].open == 0:
            return state, trace, True
    return state, trace, False


def _whole(cur: Graph, params: Params) -> bool:
    """Whether one task solves the whole graph, larger than a region may be."""
    return params.plan == "local" and region.LOCAL_LINKS < cur.n_links <= region.WHOLE_LINKS


def _run(cur: Graph, state: DataFrame, params: Params, frontier_tol: float | None, in_place: bool, some: bool, reach: bool = False) -> RankRun:
    """A run over the plan that ``params`` names; ``some``: it starts with part of
    the vertices; reach: see ``region.solved_whole``, which then runs. See ``region``
    for runs over regions."""
    params = params.for_size(cur.n)
    links, n = cur.links(), cur.n
    passes = _passes_async if in_place else _passes_sync
    state = cut(state)
    trace: list[Pass] = []
    over, limit = False, params.fixed_passes or params.max_passes
    # a pass in place moves marks by a step a block, a pass of two buffers by one
    reach_of_pass = params.blocks + 1 if in_place else 1
    hops = max(region.HOPS, 2 * reach_of_pass) if frontier_tol is not None else 0
    plan = params.plan if some or params.plan == "local" else "fused"
    while plan != "fused" and len(trace) < limit and not over:
        left = limit - len(trace)
        if _whole(cur, params):
            state, trace, over = region.solved_whole(cur.edges, state, cur.n_links, left, params, n, frontier_tol, in_place, reach)
            break
        if plan in ("auto", "local") and cur.n_links <= region.LOCAL_LINKS:
            near, into = None, links.withColumn("depth", F.lit(-1))  # all of it, without a rim
        elif some:
            core = state.where("affected").select("vid")
            if plan == "auto" and core.count() > max(REGION_BELOW * n, region.FEW_VERTICES):
                break
            near, size = region.around(links, core, hops)
            if plan == "auto" and size > max(REGION_BELOW * n, region.FEW_VERTICES):
                break
            into = region.links_into(links, near, size)
        else:
            raise ValueError(f"a graph of {cur.n_links} links is too large for one task")
        rows = region.with_sources(into, state)
        fits = plan != "pruned"
        if fits and near is not None:
            rows, n_links = region.counted(rows)
            fits = n_links <= region.LOCAL_LINKS
            if not fits and plan == "local":
                raise ValueError(f"a region of {n_links} links is too large for one task")
        if fits:
            part, done, over = region.solved(rows, left, params, n, frontier_tol, hops, in_place)
            if not done and not over:  # the rim moved within the first pass
                hops *= 2
        else:
            ends = near.select("vid")
            own = cut(into.select("src", "dst", "w"))
            mine = state.join(ends, "vid", "left_semi")
            others = cut(state.join(own.select(F.col("src").alias("vid")).distinct().join(ends, "vid", "left_anti"), "vid", "left_semi"))
            part, done, over = passes(own, cut(mine), others, params, n, frontier_tol, min(left, hops // reach_of_pass) if hops else left)
        state = cut(region.merged(state, part))
        trace += [replace(p, number=len(trace) + p.number) for p in done]
    if len(trace) < limit and not over:
        state, done, over = passes(links, state, None, params, n, frontier_tol, limit - len(trace))
        trace += [replace(p, number=len(trace) + p.number) for p in done]
    return RankRun(state.select("vid", "rank"), state, len(trace), over, trace)


def _run_sync(cur: Graph, state: DataFrame, params: Params, frontier_tol: float | None, some: bool = False, reach: bool = False) -> RankRun:
    return _run(cur, state.withColumn("links_in", F.lit(0).cast("long")), params, frontier_tol, False, some, reach)


def _run_async(cur: Graph, state: DataFrame, params: Params, frontier_tol: float | None, opened: Column, some: bool = False, reach: bool = False) -> RankRun:
    rows = state.withColumn("open", opened).withColumn("processed", F.lit(False)).withColumn("links_in", F.lit(0).cast("long"))
    return _run(cur, rows, params, frontier_tol, True, some, reach)


def _all_open(params: Params) -> Column:
    return F.lit(params.flag_rule != "literal")


def cold_sync(cur: Graph, params: Params = Params()) -> RankRun:
    return _run_sync(cur, _start(cur, uniform(cur), None), params, None)


def cold_async(cur: Graph, params: Params = Params()) -> RankRun:
    return _run_async(cur, _start(cur, uniform(cur), None), params, None, _all_open(params))


def warm_sync(cur: Graph, prev_ranks: DataFrame, params: Params = Params()) -> RankRun:
    return _run_sync(cur, _start(cur, prev_ranks, None), params, None)


def warm_async(cur: Graph, prev_ranks: DataFrame, params: Params = Params()) -> RankRun:
    return _run_async(cur, _start(cur, prev_ranks, None), params, None, _all_open(params))


def reach_sync(prev: Graph, cur: Graph, batch: DataFrame, prev_ranks: DataFrame, params: Params = Params()) -> RankRun:
    whole = _whole(cur, params)  # the task then finds what the marks reach
    marks = marking.initial(prev, cur, batch)
    return _run_sync(cur, _start(cur, prev_ranks, marks if whole else marking.reach_from(cur, marks)), params, None, True, whole)


def reach_async(prev: Graph, cur: Graph, batch: DataFrame, prev_ranks: DataFrame, params: Params = Params(), lost: list[set[int]] | None = None) -> RankRun:
    """``lost``: chunks of the changes' sources whose marking fails, by round; others
    do them again (``marking.initial_with_help``)."""
    marks, _ = marking.initial_with_help(prev, cur, batch, lost)
    whole = _whole(cur, params)
    return _run_async(cur, _start(cur, prev_ranks, marks if whole else marking.reach_from(cur, marks)), params, None, F.col("affected") & _all_open(params), True, whole)


def frontier_sync(prev: Graph, cur: Graph, batch: DataFrame, prev_ranks: DataFrame, params: Params = Params(), expand: bool = True) -> RankRun:
    """expand=False never marks beyond the first marks: a negative control."""
    state = _start(cur, prev_ranks, marking.initial(prev, cur, batch))
    return _run_sync(cur, state, params, params.for_size(cur.n).frontier if expand else None, True)


def frontier_async(prev: Graph, cur: Graph, batch: DataFrame, prev_ranks: DataFrame, params: Params = Params(), lost: list[set[int]] | None = None) -> RankRun:
    """``lost`` as in ``reach_async``."""
    marks, _ = marking.initial_with_help(prev, cur, batch, lost)
    return _run_async(cur, _start(cur, prev_ranks, marks), params, params.for_size(cur.n).frontier, F.col("affected") & _all_open(params), True)


def reference(cur: Graph, max_passes: int = 500, plan: str = "fused") -> RankRun:
    """Ground truth: from scratch, to a tolerance that only bit-equal passes meet."""
    return cold_sync(cur, Params(tol=1e-100, max_passes=max_passes, checkpoint_every=20, plan=plan))


def no_barrier_only(cur: Graph, params: Params = Params()) -> RankRun:
    """A negative control: two buffers whose barrier is merely dropped. Even
    blocks of a pass read the buffer that odd blocks have already swapped, so
    ranks of different passes mix."""
    params = params.for_size(cur.n)
    links, n = cur.links(), cur.n
    state = cut(_start(cur, uniform(cur), None))
    passes = params.fixed_passes or 20
    for p in range(passes):
        ahead = by_id("vid", 2) == p % 2
        # readers see the newer buffer of half of the vertices, the older of the rest
        mixed = state.withColumn("seen", F.when(ahead, F.col("rank")).otherwise(F.col("prev_rank")))
        loop = F.col("src") == F.col("dst")
        g = links.join(mixed, links["src"] == mixed["vid"]).groupBy(F.col("dst").alias("vid")).agg(F.sum(F.col("seen") * F.col("w")).alias("mass"), F.max(F.when(loop, F.col("rank"))).alias("own"))
        state = g.select("vid", (F.lit((1 - params.alpha) / n) + params.alpha * F.col("mass")).alias("rank"), F.col("own").alias("prev_rank"))
        if (p + 1) % params.checkpoint_every == 0:
            state = cut(state)
    return RankRun(state.select("vid", "rank"), state, passes, False)


#: name: (needs a previous snapshot, run of (prev, cur, batch, prev ranks, params))
METHODS: dict[str, Callable[[Graph, Graph, DataFrame, DataFrame, Params], RankRun]] = {
    "cold_sync": lambda prev, cur, batch, ranks, p: cold_sync(cur, p),
    "cold_async": lambda prev, cur, batch, ranks, p: cold_async(cur, p),
    "warm_sync": lambda prev, cur, batch, ranks, p: warm_sync(cur, ranks, p),
    "warm_async": lambda prev, cur, batch, ranks, p: warm_async(cur, ranks, p),
    "reach_sync": reach_sync,
    "reach_async": reach_async,
    "frontier_sync": frontier_sync,
    "frontier_async": frontier_async,
}
MAIN = ("cold_sync", "cold_async", "warm_sync", "warm_async", "frontier_sync", "frontier_async")


def run(name: str, prev: Graph, cur: Graph, batch: DataFrame, prev_ranks: DataFrame, params: Params = Params(), **changes) -> RankRun:
    return METHODS[name](prev, cur, batch, prev_ranks, replace(params, **changes))
