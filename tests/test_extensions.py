"""The block-owning form, general ranks, growth, walks and salting."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from rankflow.operators import batches, extensions, local, marking, measures, methods
from rankflow.operators.graph import Graph
from rankflow.params import Params


@pytest.fixture(scope="module")
def g(spark):
    rng = np.random.default_rng(5)
    pairs = sorted({(int(a), int(b)) for a, b in rng.integers(0, 50, (160, 2)) if a != b})
    return Graph.build(spark.createDataFrame(pairs, "src long, dst long"))


def test_block_tasks_reach_the_same_ranks(g):
    truth = methods.cold_sync(g, Params(tol=1e-10))
    run = local.local_async(g, methods.uniform(g).withColumn("affected", F.lit(True)), Params(tol=1e-8, blocks=2))
    assert run.converged and measures.error(run, truth.ranks) < 1e-7
    assert run.passes < truth.passes


def test_block_tasks_follow_the_frontier(g):
    before = methods.cold_sync(g).ranks
    batch = batches.random(g, 0.03, 2).persist()
    cur = g.apply(batch)
    start = methods._start(cur, before, marking.initial(g, cur, batch))
    run = local.local_async(cur, start, Params(tol=1e-8, blocks=2), frontier_tol=1e-11)
    assert measures.error(run, methods.cold_sync(cur).ranks) < 1e-7


def test_general_ranks_keep_their_mass_without_loops(spark):
    edges = spark.createDataFrame([(1, 2, 3.0), (1, 3, 1.0), (2, 3, 1.0)], "src long, dst long, weight double")
    vertices = spark.createDataFrame([(i,) for i in (1, 2, 3, 4)], "vid long")
    got = {r.vid: r.rank for r in extensions.general_ranks(edges, vertices).collect()}
    assert abs(sum(got.values()) - 1) < 1e-12
    a = np.array([[0, 0, 0.25, 0.25], [0.75, 0, 0.25, 0.25], [0.25, 1, 0.25, 0.25], [0, 0, 0.25, 0.25]])
    a[0, 2] = a[1, 2] = a[2, 2] = a[3, 2] = 0.25
    r = np.full(4, 0.25)
    for _ in range(50):
        r = 0.15 / 4 + 0.85 * a @ r
    assert max(abs(got[i + 1] - r[i]) for i in range(4)) < 1e-9
    mine = extensions.general_ranks(edges, vertices, prefer=spark.createDataFrame([(4, 2.0)], "vid long, weight double"))
    assert abs({r.vid: r.rank for r in mine.collect()}[4] - 1) < 1e-12


def test_growth_keeps_the_sum(spark, g):
    ranks = methods.cold_sync(g).ranks
    new = extensions.rescale_for_vertices(ranks, spark.createDataFrame([(1000,)], "vid long"), ranks.limit(3))
    assert new.count() == ranks.count() - 2 and abs(measures.mass(new) - 1) < 1e-12


def test_walks_come_near(g):
    near = measures.norms(extensions.monte_carlo_ranks(g, 60, most_hops=8), methods.cold_sync(g).ranks).first()
    assert near.l1 < 0.4


def test_salting_changes_no_sum(g):
    state = methods.uniform(g)
    got = {r.vid: r.mass for r in extensions.salted_pull(g.links(), state, 3, 4).collect()}
    want = {r.vid: r.mass for r in g.links().join(state, F.col("src") == F.col("vid")).groupBy(F.col("dst").alias("vid")).agg(F.sum(F.col("rank") * F.col("w")).alias("mass")).collect()}
    assert got.keys() == want.keys() and max(abs(got[v] - want[v]) for v in want) < 1e-12
