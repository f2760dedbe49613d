"""The experiments, on the graphs of the given tables."""

from __future__ import annotations

import time
from collections.abc import Iterable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession

from ..operators import batches, measures, methods, region
from ..operators.graph import Graph, TemporalGraph
from ..params import Params, RankRun
from ..sources import catalog
from . import faults

ROW = "graph string, method string, fraction double, batch_no int, passes int, converged boolean, edges_read long, affected long, error double, seconds double"


def _plan(graph: Graph) -> str:
    """For ranks that are only compared with."""
    return "local" if graph.n_links <= region.LOCAL_LINKS else "auto"


def timed(make) -> tuple[RankRun, float]:
    """A run and its seconds: marking and stop tests count, reading does not."""
    began = time.perf_counter()
    run = make()
    return run, time.perf_counter() - began


def _row(graph: str, method: str, fraction: float, number: int, run: RankRun, seconds: float, truth: DataFrame | None) -> tuple:
    return (graph, method, fraction, number, run.passes, run.converged, run.edges_read, run.trace[-1].active if run.trace else 0, measures.error(run, truth) if truth is not None else None, seconds)


def random_batches(spark: SparkSession, sf_dir: str, graphs: Iterable[str], fractions: Iterable[float], names: Iterable[str] = methods.MAIN, repeats: int = 1, params: Params = Params(), with_error: bool = True, truth_passes: int = 500) -> DataFrame:
    """Random mixed batches of each size on each graph, each method on each."""
    rows = []
    for g in graphs:
        prev = catalog.build(g, spark, sf_dir)
        before = methods.cold_sync(prev, replace(params, plan=_plan(prev))).ranks
        for fraction in fractions:
            for number in range(repeats):
                batch = batches.random(prev, fraction, seed=number + 1).persist()
                cur = prev.apply(batch)
                cur.links().count()
                truth = methods.reference(cur, truth_passes, _plan(cur)).ranks if with_error else None
                for name in names:
                    run, seconds = timed(lambda: methods.run(name, prev, cur, batch, before, params))
                    rows.append(_row(g, name, fraction, number, run, seconds, truth))
                cur.release()
                batch.unpersist()
        prev.release()
    return spark.createDataFrame(rows, ROW)


def replay(spark: SparkSession, name: str, graph: TemporalGraph, fraction: float, names: Iterable[str], load: float = 0.9, most: int | None = None, params: Params = Params(), with_error: bool = False, truth_passes: int = 500) -> DataFrame:
    """Loads a share of a temporal graph and then applies slices of its rows, one
    batch after the other; each method goes on from its own ranks."""
    total = graph.total
    size, at, number, rows = max(1, int(total * fraction)), int(total * load), 0, []
    prev = graph.prefix(load)
    first = methods.cold_sync(prev, replace(params, plan=_plan(prev))).ranks
    own = {m: first for m in names}
    while at < total and (most is None or number < most):
        batch = batches.normalised(prev, graph.slice(at, size)).persist()
        cur = prev.apply(batch)
        cur.links().count()
        truth = methods.reference(cur, truth_passes, _plan(cur)).ranks if with_error else None
        for m in names:
            run, seconds = timed(lambda: methods.run(m, prev, cur, batch, own[m], params))
            own[m] = run.ranks
            rows.append(_row(name, m, fraction, number, run, seconds, truth))
        prev.release()
        prev, at, number = cur, at + size, number + 1
    return spark.createDataFrame(rows, ROW)


def round_trip(prev: Graph, fraction: float, name: str, seed: int = 1, params: Params = Params(), before: DataFrame | None = None) -> float:
    """Deletes a batch, updates, inserts it again, updates: largest difference to
    the ranks before."""
    before = methods.cold_sync(prev, replace(params, plan=_plan(prev))).ranks if before is None else before
    gone = batches.random(prev, fraction, seed, mix="del").persist()
    cur = prev.apply(gone)
    there = methods.run(name, prev, cur, gone, before, params).ranks
    back = batches.invert(gone)
    again = cur.apply(back)
    out = measures.linf(methods.run(name, cur, again, back, there, params).ranks, before)
    cur.release()
    again.release()
    gone.unpersist()
    return out


def tolerance_sweep(prev: Graph, cur: Graph, batch: DataFrame, before: DataFrame, truth: DataFrame, factors: Iterable[float], params: Params = Params()) -> list[tuple]:
    """(factor, passes, affected, edges read, error) of frontier runs whose
    frontier tolerance is a factor of the tolerance."""
    out = []
    for f in factors:
        run = methods.run("frontier_sync", prev, cur, batch, before, params, frontier_tol=params.tol * f)
        out.append((f, run.passes, run.trace[-1].active, run.edges_read, measures.error(run, truth)))
    return out


Costs = list[dict[int, tuple[int, int]]]


def delays(barrier: Costs, free: Costs, units: Iterable[int], chances: Iterable[float], workers: int = 64) -> list[tuple]:
    """(units of a sleep, probability, sleeps with barriers, time with, time without,
    ratio). ``barrier`` is the work of the run of two buffers, ``free`` of that in
    place, which takes other passes."""
    out = []
    for u in units:
        for p in chances:
            sim = faults.Simulator(workers=workers, delay_p=p, delay_units=u)
            a, b = sim.play(barrier, True), sim.play(free, False)
            out.append((u, p, a.sleeps, a.units, b.units, round(a.units / max(1, b.units), 6)))
    return out


def crashes(barrier: Costs, free: Costs, counts: Iterable[int], workers: int = 64) -> list[tuple]:
    """(crashed workers, whether barriers let it finish, time without barriers,
    speed relative to no crash). A crashed worker's last block is done again."""
    base = faults.Simulator(workers=workers).play(free, False).units
    out = []
    for c in counts:
        sim = faults.Simulator(workers=workers, crashes=c)
        b = sim.play(free, False)
        out.append((c, sim.play(barrier, True).finished, b.units, round(base / max(1, b.units), 6)))
    return out


def scaling(barrier: Costs, free: Costs, workers: Iterable[int]) -> list[tuple]:
    """(workers, speed-up with barriers, without) against one worker."""
    one = faults.Simulator(workers=1)
    a, b = one.play(barrier, True).units, one.play(free, False).units
    return [(w, round(a / max(1, faults.Simulator(workers=w).play(barrier, True).units), 6), round(b / max(1, faults.Simulator(workers=w).play(free, False).units), 6)) for w in workers]
