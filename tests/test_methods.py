"""Ranks against closed forms, a dense computation, and each other."""

from dataclasses import astuple, replace

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from rankflow.operators import batches, blocks, marking, measures, methods
from rankflow.operators.graph import Graph
from rankflow.params import Params
from rankflow.plans import faults, registry, replays


def graph(spark, pairs, undirected=False, loops=True):
    return Graph.build(spark.createDataFrame(pairs, "src long, dst long"), undirected=undirected, self_loops=loops)


def dense(edges, vids, alpha=0.85, passes=300):
    at = {v: i for i, v in enumerate(vids)}
    a = np.zeros((len(vids), len(vids)))
    for s, t in edges:
        a[at[t], at[s]] = 1
    a /= a.sum(axis=0, keepdims=True)
    r = np.full(len(vids), 1 / len(vids))
    for _ in range(passes):
        r = (1 - alpha) / len(vids) + alpha * a @ r
    return dict(zip(vids, r))


def ranks(run):
    return {r.vid: r.rank for r in run.ranks.collect()}


def spread(a, b):
    assert a.keys() == b.keys()
    return max(abs(a[k] - b[k]) for k in a)


@pytest.fixture(scope="module")
def random_graph(spark):
    rng = np.random.default_rng(3)
    pairs = {(int(a), int(b)) for a, b in rng.integers(0, 60, (150, 2)) if a != b}
    return graph(spark, sorted(pairs))


@pytest.fixture(scope="module")
def change(random_graph):
    batch = batches.random(random_graph, 0.05, 4).persist()
    cur = random_graph.apply(batch)
    return random_graph, Graph(methods.cut(cur.edges), methods.cut(cur.vertices)), batch, methods.cold_sync(random_graph, Params(tol=1e-9)).ranks


def truth_of(g):
    return dense([tuple(e) for e in g.edges.collect()], sorted(v.vid for v in g.vertices.collect()))


@pytest.mark.parametrize("pairs", [[(0, 1), (1, 2), (2, 3), (3, 0)], [(a, b) for a in range(4) for b in range(4) if a != b], [(0, 1), (1, 0)]])
def test_regular_graphs_have_equal_ranks(spark, pairs):
    got = ranks(methods.cold_sync(graph(spark, pairs)))
    assert all(abs(r - 1 / len(got)) < 1e-9 for r in got.values())


def test_one_vertex(spark):
    got = ranks(methods.cold_sync(graph(spark, [(7, 7)])))
    assert got.keys() == {7} and abs(got[7] - 1) < 1e-12


@pytest.mark.parametrize("name", methods.METHODS)
def test_every_method_reaches_the_dense_ranks(change, name):
    prev, cur, batch, before = change
    run = methods.run(name, prev, cur, batch, before, Params(tol=1e-7, blocks=2))
    assert run.converged
    assert spread(ranks(run), truth_of(cur)) < 1e-6


def same_run(a, b):
    assert (a.passes, a.converged) == (b.passes, b.converged)
    assert [p[:3] + p[4:] for p in map(astuple, a.trace)] == [p[:3] + p[4:] for p in map(astuple, b.trace)]
    assert spread(ranks(a), ranks(b)) < 1e-15


@pytest.mark.parametrize("name,plan", [("frontier_sync", "pruned"), ("frontier_sync", "auto"), ("frontier_async", "auto"), ("frontier_async", "pruned"), ("reach_sync", "auto"), ("reach_async", "local"), ("warm_sync", "local"), ("cold_async", "local")])
def test_plans_agree(change, name, plan):
    prev, cur, batch, before = change
    a, b = (methods.run(name, prev, cur, batch, before, Params(fixed_passes=5, blocks=3, plan=p, checkpoint_every=2)) for p in ("fused", plan))
    same_run(a, b)


@pytest.mark.parametrize("name", ["frontier_sync", "frontier_async"])
def test_regions_grow_with_the_frontier(spark, monkeypatch, name):
    """A long path, with regions of so few hops that their rims move."""
    prev = graph(spark, [(i, i + 1) for i in range(60)], undirected=True)
    prev = Graph(methods.cut(prev.edges), methods.cut(prev.vertices))
    batch = spark.createDataFrame([(30, 31, "-"), (3, 40, "+")], batches.EMPTY)
    cur = prev.apply(batch)
    before = methods.cold_sync(prev, Params(plan="local")).ranks
    whole = methods.run(name, prev, cur, batch, before, Params(tol=1e-6, blocks=2, plan="local"))
    monkeypatch.setattr(methods.region, "HOPS", 3)
    monkeypatch.setattr(methods.region, "FEW_VERTICES", 10**6)
    monkeypatch.setattr(Graph, "n_links", property(lambda g: methods.region.LOCAL_LINKS + 1))
    same_run(whole, methods.run(name, prev, cur, batch, before, Params(tol=1e-6, blocks=2, plan="auto")))


def test_graphs_without_loops_are_refused(spark):
    g = graph(spark, [(1, 2), (2, 3), (3, 1), (4, 1)], loops=False)
    with pytest.raises(ValueError):
        methods.cold_sync(g)


def test_reach_contracts_two_way_links(spark):
    rng = np.random.default_rng(8)
    pairs = {(i, i + 1) for i in range(40)} | {(i + 1, i) for i in range(40) if i % 9} | {(int(a), int(b)) for a, b in rng.integers(50, 90, (40, 2)) if a != b} | {(40, 50)}
    g = graph(spark, sorted(pairs))
    for heads in ([0], [20], [55, 70], [999]):
        seen, last = set(heads), set(heads)
        while last:
            last = {b for a, b in pairs if a in last} - seen
            seen |= last
        marks = spark.createDataFrame([(h,) for h in heads], "vid long")
        assert {r.vid for r in marking.reach_from(g, marks).collect()} == seen
    depth = {r.vid: r.depth for r in marking.reach_from(g, spark.createDataFrame([(0,)], "vid long"), 3).collect()}
    assert depth == {0: 0, 1: 1, 2: 2, 3: 3}


def test_lost_marking_is_helped(change):
    prev, cur, batch, before = change
    a = methods.frontier_async(prev, cur, batch, before, Params(fixed_passes=3, blocks=2))
    b = methods.frontier_async(prev, cur, batch, before, Params(fixed_passes=3, blocks=2), lost=[set(range(12)), {3, 5}])
    same_run(a, b)


def test_empty_batch_changes_no_bit(change):
    prev, _, _, before = change
    old = {r.vid: r.rank for r in before.collect()}
    for name in ("frontier_sync", "frontier_async", "reach_sync", "reach_async"):
        assert ranks(methods.run(name, prev, prev, batches.empty(prev), before, Params(blocks=2))) == old


def test_async_with_one_block_follows_sync(change):
    _, cur, _, _ = change
    a = methods.cold_sync(cur, Params(fixed_passes=5))
    b = methods.cold_async(cur, Params(fixed_passes=5, blocks=1))
    assert spread(ranks(a), ranks(b)) < 1e-15


def test_stop_in_the_middle_of_a_job_gives_that_pass(change):
    _, cur, _, _ = change
    one, many = (methods.cold_sync(cur, Params(tol=1e-4, checkpoint_every=c)) for c in (1, 7))
    assert one.passes == many.passes and spread(ranks(one), ranks(many)) == 0


def test_cap_is_reported(change):
    run = methods.cold_sync(change[1], Params(max_passes=3))
    assert not run.converged and run.passes == 3


def test_mass_and_floor(change):
    _, cur, _, _ = change
    run = methods.cold_sync(cur, Params(fixed_passes=12))
    assert abs(measures.mass(run.ranks) - 1) < 1e-9
    assert min(ranks(run).values()) >= 0.15 / cur.n - 1e-12


def test_frontier_lies_between_initial_and_reach(change):
    prev, cur, batch, before = change
    first = {r.vid for r in marking.initial(prev, cur, batch).collect()}
    reach = {r.vid for r in marking.reach(prev, cur, batch).collect()}
    run = methods.run("frontier_sync", prev, cur, batch, before)
    seen = {r.vid for r in run.state.where("affected").collect()}
    assert first <= seen <= reach
    assert all(a.active <= b.active for a, b in zip(run.trace, run.trace[1:]))


def test_negative_controls(spark, sf):
    prev, cur, batch = registry.changed(spark, sf, "line", 1e-2)
    before = methods.cold_sync(prev).ranks
    truth = methods.reference(cur, 110).ranks
    on = measures.error(methods.frontier_sync(prev, cur, batch, before), truth)
    off = measures.error(methods.frontier_sync(prev, cur, batch, before, expand=False), truth)
    assert on < 1e-9 < off
    assert methods.cold_async(cur, Params(blocks=2, flag_rule="literal")).passes == 1


def test_batch_algebra(change):
    prev, cur, batch, _ = change
    edges = lambda g: {tuple(e) for e in g.edges.collect()}
    assert edges(prev.apply(batches.diff(prev, cur))) == edges(cur)
    assert edges(cur.apply(batches.invert(batch))) == edges(prev)
    assert edges(prev.apply(batch.unionAll(batch))) == edges(cur)
    loops = prev.vertices.select(F.col("vid").alias("src"), F.col("vid").alias("dst"), F.lit("-").alias("op"))
    assert edges(prev.apply(loops)) == edges(prev)


def test_insertion_wins_and_nothing_happens_for_effectless_rows(spark):
    g = graph(spark, [(1, 2), (2, 3)])
    b = spark.createDataFrame([(1, 2, "-"), (1, 2, "+"), (9, 1, "+"), (3, 1, "-"), (3, 1, "+"), (2, 3, "+")], batches.EMPTY)
    assert {tuple(e) for e in g.apply(b).edges.collect()} == {(1, 2), (2, 3), (3, 1), (1, 1), (2, 2), (3, 3)}
    assert {tuple(r) for r in batches.normalised(g, b.where("src <> 9")).collect()} == {(3, 1, "+")}


def test_bernoulli_batches_follow_the_fraction(random_graph):
    rows = batches.bernoulli(random_graph, 0.4, 2).collect()
    gone = [r for r in rows if r.op == "-"]
    assert 0.08 < len(gone) / random_graph.edges.count() < 0.35
    assert 0.05 < sum(r.op == "+" for r in rows) / random_graph.edges.count() < 0.35
    assert {r.op for r in batches.bernoulli(random_graph, 0.4, 2, "ins").collect()} == {"+"}
    assert all(r.src != r.dst for r in rows)


@pytest.mark.parametrize("mix", ["both", "del", "ins"])
def test_large_batches_are_the_rows_of_the_order(random_graph, monkeypatch, mix):
    """Before, a batch of more changes than a limit was another draw, of about the size."""
    small = sorted(map(tuple, batches.random(random_graph, 0.3, 2, mix).collect()))
    for limit in ("MOST_EXACT", "RANKED_AT_ONCE"):
        monkeypatch.setattr(batches, limit, 5, raising=False)
    assert sorted(map(tuple, batches.random(random_graph, 0.3, 2, mix).collect())) == small
    k, known = batches.size_of(random_graph, 0.3), {tuple(e) for e in random_graph.edges.collect()}
    gone, come = ([r for r in small if r[2] == op] for op in "-+")
    assert len(gone) == {"both": k, "del": 2 * k, "ins": 0}[mix] and {r[:2] for r in gone} <= known
    assert (len(come) > 0) == (mix != "del") and not {r[:2] for r in come} & known


@pytest.mark.parametrize("mix", ["both", "del"])
def test_batches_of_experiments_are_the_random_ones_a_task_each(spark, random_graph, mix):
    """Before, each was made by jobs of its own, and rows of changes were dealt by their
    number, so that all small batches went to one task."""
    fractions = [1e-8, 1e-3, 0.02, 0.1, 0.5]
    specs, same, batch_of = replays._batches(random_graph, fractions, 2, mix)
    assert sorted(f for some in same.values() for f in some) == fractions and len(specs) == 2 * len(same)
    for _, spec in specs.iterrows():
        want = batches.random(random_graph, spec["fraction"], int(spec["batch_no"]) + 1, mix)
        assert sorted(batch_of(spec.to_frame().T).itertuples(index=False, name=None)) == sorted(map(tuple, want.collect()))
    from pyspark import TaskContext

    where = replays._tasks(spark, specs, lambda spec: [(int(spec["task"].iloc[0]), TaskContext.get().partitionId())], "task int, part int")
    assert len({r.part for r in where.collect()}) == len(specs)


def test_low_hashes_that_are_too_few_are_not_all(random_graph, monkeypatch):
    some = random_graph.vertices.withColumn("h", F.md5(F.col("vid").cast("string")))
    first = [tuple(r) for r in batches._firsts(some, ["h", "vid"], 20).orderBy("seq").collect()]
    monkeypatch.setattr(batches, "RANKED_AT_ONCE", 5)
    for of in (1, random_graph.n, 10**9):
        assert [tuple(r) for r in batches._firsts(some, ["h", "vid"], 20, lambda: of).orderBy("seq").collect()] == first


def test_small_batches_leave_the_edges_where_they_are(spark, random_graph):
    """Before, a batch of a few rows dealt all edges twice."""
    b = batches.random(random_graph, 0.1, 3).unionAll(spark.createDataFrame([(1, 1, "-"), (99, 1, "+"), (5, 5, "+")], batches.EMPTY))
    b = methods.cut(b.unionAll(b).unionAll(random_graph.edges.limit(3).withColumn("op", F.lit("+"))))
    slow, fast = random_graph.apply(b).edges, random_graph.apply(b, b.count()).edges
    assert sorted(map(tuple, fast.collect())) == sorted(map(tuple, slow.collect()))
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        joins = [x.apply(b, size).edges._jdf.queryExecution().executedPlan().toString().count("BroadcastHashJoin") for x, size in ((random_graph, None), (random_graph, 9))]
        assert joins[0] == 0 and joins[1] >= 2
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_nulls_and_repeats_in_edges(spark):
    g = graph(spark, [(1, 2), (1, 2), (None, 3), (4, None)])
    assert {tuple(e) for e in g.edges.collect()} == {(1, 2), (1, 1), (2, 2)}


def test_empty_graph(spark):
    g = graph(spark, [])
    assert g.n == 0 and g.profile().count() == 1


def test_blocks_share_links(random_graph):
    rows = blocks.by_edges(random_graph, 4).join(random_graph.edges, F.col("dst") == F.col("vid")).groupBy("block").count().collect()
    total = sum(r["count"] for r in rows)
    assert len(rows) == 4 and max(r["count"] for r in rows) < total / 4 + 30


def test_help_marks_what_one_round_would(change):
    prev, cur, batch, _ = change
    marks, ledger = marking.initial_with_help(prev, cur, batch, [{0, 1, 2}, {1}], chunks=4)
    assert {r.vid for r in marks.collect()} == {r.vid for r in marking.initial(prev, cur, batch).collect()}
    assert ledger.count() == batch.select("src").distinct().count()


def test_example_of_fourteen_vertices(spark):
    prev, cur, batch = registry.example(spark)
    marks = marking.initial(prev, cur, batch)
    assert {r.vid for r in marks.collect()} == {8, 9, 11}
    state = marks.select("vid", F.lit(0.5).alias("rank"), F.lit(0.1).alias("prev_rank"))
    assert {r.vid for r in marking.expand(state, cur.edges, registry.FRONTIER_TOL).collect()} == {10, 12}


def test_lost_and_late_blocks_still_converge(change):
    prev, cur, batch, before = change
    run = faults.run_with_losses(prev, cur, batch, before, {1: {0, 1}, 2: {1}}, {3: {0}}, Params(tol=1e-7, blocks=2, max_passes=120))
    assert run.converged and spread(ranks(run), truth_of(cur)) < 1e-6


def test_simulated_clock():
    costs = [{b: (10, 1) for b in range(8)}] * 3
    none = faults.Simulator(workers=4)
    assert none.play(costs, True).units == none.play(costs, False).units == 3 * 2 * 11
    assert none.play(costs, True).wait_share == 0
    crashed = faults.Simulator(workers=4, crashes=2, crash_spread=1)
    assert not crashed.play(costs, True).finished
    assert crashed.play(costs, False).finished and crashed.play(costs, False).units > none.play(costs, False).units
    slow = faults.Simulator(workers=4, delay_p=0.05, delay_units=100)
    assert slow.play(costs, True).units >= slow.play(costs, False).units
    with pytest.raises(ValueError):
        faults.Simulator(workers=2, crashes=2)
    fixed, pooled = faults.static_schedule([{0: (100, 1), 4: (100, 1), 1: (1, 1)}] * 2, 4)
    assert fixed.units > pooled.units


def test_parameters_are_checked():
    for bad in ({"alpha": 1.0}, {"close_rule": "x"}, {"flag_rule": "x"}, {"plan": "x"}, {"tol_scale": "x"}):
        with pytest.raises(ValueError):
            Params(**bad)
    assert Params(tol=1e-6, tol_scale="1/n").for_size(10).tol == 1e-7


def test_one_shuffle_a_pass_and_links_stay(spark, random_graph):
    from rankflow.operators.kernel import superstep

    spark.conf.set("spark.sql.adaptive.enabled", "false")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        links = random_graph.links()
        links.count()
        first = superstep(links, methods.cut(methods._start(random_graph, methods.uniform(random_graph), None).repartition(4, "vid")), 0.85, random_graph.n, 1e-13)
        plan = superstep(links, first, 0.85, random_graph.n, 1e-13)._jdf.queryExecution().executedPlan().toString()
        outside = plan.split("InMemoryTableScan")[0]
        assert outside.count("Exchange") <= 1, outside
    finally:
        spark.conf.unset("spark.sql.adaptive.enabled")
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


@pytest.mark.parametrize("name", methods.METHODS)
def test_replayed_runs_equal_the_methods(change, name):
    prev, cur, batch, before = change
    params = Params(tol=1e-7, blocks=3)
    a, b = replays.Held.of(prev), replays.Held.of(cur)
    old = {r.vid: r.rank for r in before.collect()}
    found, trace, over = replays.run(name, a, b, batch.toPandas(), np.array([old[v] for v in a.vids]), params)
    run = methods.run(name, prev, cur, batch, before, replace(params, plan="local"))
    assert run.converged == over and [p.active for p in run.trace] == [t[0] for t in trace] and run.edges_read == sum(t[1] for t in trace)
    assert spread(dict(zip(b.vids.tolist(), found.tolist())), ranks(run)) < 1e-15
    assert (a.apply(batch.toPandas()).keys == b.keys).all()


def test_workloads_keep_within_the_bar(spark, sf):
    prev = registry.graph(spark, sf, "web")
    rows = replays.random_batches(prev, [1e-8, 1e-6, 1e-2], repeats=1).collect()
    assert len(rows) == 3 * 6 and all(r.converged and r.error < 1e-9 for r in rows)
    assert all(r.difference < 1e-9 for r in replays.round_trips(prev, [1e-2]).collect())
    temporal = registry.catalog.handoff(spark, sf)
    rows = replays.replay(temporal, 1e-2).collect()
    assert {r.batch_no for r in rows} == set(range(-(-(temporal.total - int(temporal.total * 0.9)) // max(1, int(temporal.total * 1e-2)))))
    assert all(r.converged and r.error < 2e-9 for r in rows)


def test_reference_and_batches_of_arrays():
    rng = np.random.default_rng(5)
    for n, m in ((1, 0), (4, 5), (60, 200)):
        vids = np.sort(rng.choice(10_000, n, False))
        ends = [np.concatenate([rng.integers(0, n, m), np.arange(n)]) for _ in range(2)]
        held = replays.Held(vids, np.empty(0, np.int64)).with_edges(vids[ends[0]], vids[ends[1]])
        held = held.with_edges(vids, vids)
        none = pd.DataFrame({"src": [], "dst": [], "op": []})
        for passes in (1, 2, 151, 152, 500):
            slow = replays.run("cold_sync", held, held, none, np.empty(0), Params(tol=1e-100, max_passes=passes))[0]
            assert (replays.truth(held, passes) == slow).all()
        for k in (0, 1, 50):
            batch = pd.DataFrame({"src": vids[rng.integers(0, n, k)], "dst": vids[rng.integers(0, n, k)], "op": rng.choice(["+", "-"], k)})
            key, plus = held.key(batch["src"].to_numpy(), batch["dst"].to_numpy()), (batch["op"] == "+").to_numpy()
            assert sorted((set(held.keys) - set(key[~plus])) | set(key[plus])) == held.apply(batch).keys.tolist()


@pytest.mark.parametrize("name", methods.METHODS)
def test_whole_graphs_over_the_limit_of_regions(spark, change, monkeypatch, name):
    """Before, plan='local' refused a graph of more links than a region's limit."""
    prev, cur, batch, before = change
    params = Params(tol=1e-7, blocks=3, plan="local")
    small = methods.run(name, prev, cur, batch, before, params)
    monkeypatch.setattr(methods.region, "LOCAL_LINKS", 10)
    for chunk, most in ((7, 0), (1 << 21, 10**6)):
        monkeypatch.setattr(methods.region, "CHUNK", chunk)
        monkeypatch.setattr(methods.region, "SORTED_LINKS", most)
        large = methods.run(name, prev, cur, batch, before, params)
        assert large.trace == small.trace and large.converged == small.converged
        assert sorted(map(tuple, large.state.collect())) == sorted(map(tuple, small.state.select(*large.state.columns).collect()))


def test_losses_in_one_task_are_those_of_steps(change, monkeypatch):
    """Before, a run that loses blocks took a job a pass, whatever the graph."""
    prev, cur, batch, before = change
    run = lambda: faults.run_with_losses(prev, cur, batch, before, {1: {0, 1}, 2: {1}}, {3: {0}}, Params(tol=1e-5, blocks=3, max_passes=20))
    one = run()
    monkeypatch.setattr(methods.region, "WHOLE_LINKS", 0)
    steps = run()
    assert (one.passes, one.converged) == (steps.passes, steps.converged)
    assert [(p.active, p.edges_read, p.open) for p in one.trace[:3]] == [(p.active, p.edges_read, p.open) for p in steps.trace[:3]]
    assert spread(ranks(one), ranks(steps)) < 1e-12


@pytest.mark.parametrize("in_place", [False, True])
def test_whole_graphs_as_arrays(monkeypatch, in_place):
    """The lean form of a whole graph gives the passes and ranks of a region's."""
    region = methods.region
    rng = np.random.default_rng(5)
    vids = np.sort(rng.choice(1000, 80, False))
    keys = np.unique(np.concatenate([rng.integers(0, 6400, 200), np.arange(80) * 81]))
    src, dst = keys // 80, keys % 80
    w, start, marks = 1.0 / np.bincount(src)[src], rng.random(80) / 80, rng.random(80) < 0.1
    off = np.zeros(len(src), bool)
    solve = region.solve_async if in_place else region.solve_sync
    for chunk, most in ((7, 0), (7, 10**6), (1 << 21, 10**6)):
        monkeypatch.setattr(region, "CHUNK", chunk)
        monkeypatch.setattr(region, "SORTED_LINKS", most)
        for tol in (None, 1e-6):
            a = region.Region([vids[src], vids[dst], w, np.full(len(src), -1), start[src], start[src], marks[src], marks[src], off], 0)
            b = region.Whole(vids, dst * 80 + src).start(start, marks, marks)
            params = Params(tol=1e-4, blocks=3)
            assert solve(a, 50, params, 80, tol) == solve(b, 50, params, 80, tol)
            assert np.array_equal(a.rank, b.rank) and np.array_equal(a.affected, b.affected)
        seen = marks.copy()
        for _ in range(80):
            seen[dst[seen[src]]] = True
        assert np.array_equal(region.Whole(vids, dst * 80 + src).reached(marks), seen)
    held = replays.Held(vids, src * 80 + dst)
    true = dense(list(zip(src.tolist(), dst.tolist())), list(range(80)), passes=500)
    assert np.abs(replays.truth(held) - np.array([true[i] for i in range(80)])).max() < 1e-12
    none = pd.DataFrame({"src": [], "dst": [], "op": []})
    got = replays.run("cold_async" if in_place else "cold_sync", held, held, none, np.empty(0), Params(tol=1e-12, blocks=3))
    assert got[2] and np.abs(got[0] - replays.truth(held)).max() < 1e-9
