"""All queries by name, and the SQL that checks them."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import relational as rel
from ..functions import sqlapi, udfs
from ..operators import batches, blocks, marking, measures, methods, region
from ..operators.graph import Graph, ordered
from ..params import Params
from ..sources import catalog
from ..sources.stores import VersionStore
from ..storage import cut, fresh_path
from ..streaming import maintain
from . import faults, replays, workloads
from . import oracles as o

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

#: Passes of runs that are compared with SQL value by value.
PASSES = 12
BEFORE_PASSES = 20
ASYNC_PASSES, BLOCKS = 4, 4
FRACTION = 1e-3
FRONTIER_TOL = Params().frontier


#: Sizes of random batches, as shares of all links.
SIZES = [10.0**-k for k in range(8, 0, -1)]


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


# Runs that several queries start from are made once a session and table folder.
_made: dict[tuple, object] = {}


def once(spark: SparkSession, sf_dir: str, what: str, make: Callable[[], object]) -> object:
    key = (spark.sparkContext.applicationId, sf_dir, what)
    if key not in _made:
        _made[key] = make()
    return _made[key]


def from_tables(name: str) -> None:
    """From now on the query starts from the tables themselves, not from graphs or
    ranks that earlier queries of the session made."""
    made = QUERIES[name]

    def run(s: SparkSession, d: str) -> DataFrame:
        held = dict(_made)
        _made.clear()
        try:
            return made(s, d)
        finally:
            _made.update(held)

    QUERIES[name] = run


def graph(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    def make() -> Graph:
        g = catalog.build(name, spark, sf_dir)
        edges, n_links = region.counted(g.edges)
        # each vertex has its loop, and no other edge is one
        vertices, n = region.counted(edges.where("src = dst").select(F.col("src").alias("vid")))
        return Graph(edges, vertices, _n=n, _n_links=n_links)

    return once(spark, sf_dir, f"graph {name}", make)


def before(spark: SparkSession, sf_dir: str, name: str, passes: int | None = BEFORE_PASSES) -> DataFrame:
    g = graph(spark, sf_dir, name)
    return once(spark, sf_dir, f"before {name} {passes}", lambda: methods.cold_sync(g, Params(fixed_passes=passes, plan=whole_plan(g))).ranks)


def changed(spark: SparkSession, sf_dir: str, name: str, fraction: float = FRACTION) -> tuple[Graph, Graph, DataFrame]:
    def make() -> tuple[Graph, Graph, DataFrame]:
        prev = graph(spark, sf_dir, name)
        batch, size = region.counted(batches.random(prev, fraction, 1))
        cur = prev.apply(batch, size)
        edges, n_links = region.counted(cur.edges)
        return prev, Graph(edges, prev.vertices, _n=prev.n, _n_links=n_links), batch

    return once(spark, sf_dir, f"changed {name} {fraction}", make)


def whole_plan(g: Graph) -> str:
    """For runs of all vertices of which only results are told."""
    return "local" if g.n_links <= region.WHOLE_LINKS else "auto"


def settled(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Ranks of a graph to the tolerance: what methods that update ranks start from."""
    g = graph(spark, sf_dir, name)
    return once(spark, sf_dir, f"settled {name}", lambda: methods.cold_sync(g, Params(plan=whole_plan(g))).ranks)


def truth(s: SparkSession, d: str, name: str = "web", after: bool = True) -> DataFrame:
    """Reference ranks of a graph, after its batch or before."""
    g = changed(s, d, name)[1] if after else graph(s, d, name)
    return once(s, d, f"truth {name} {after}", lambda: methods.reference(g, plan=whole_plan(g)).ranks)


def before_ctes(name: str, passes: int | None = BEFORE_PASSES) -> list[str]:
    run = o.sync_cte("r0", "g", None, None, None, passes or 500, None if passes else 1e-10)
    return [o.graph_ctes(name), o.links_cte("g"), run, "before AS MATERIALIZED (SELECT vid, rank FROM " + o.last("r0") + " z)"]


def changed_ctes(name: str, fraction: float = FRACTION, passes: int | None = BEFORE_PASSES) -> list[str]:
    return [*before_ctes(name, passes), o.batch_ctes(fraction), o.applied_ctes(), o.links_cte("h"), o.marks_cte()]


def _pico(ranks: DataFrame) -> DataFrame:
    return ranks.select("vid", rel.pico().alias("rank_pico"))


# ---- graphs -----------------------------------------------------------------

for _g in catalog.GRAPHS:
    query(f"graph_{_g}_edges", o.with_([o.graph_ctes(_g)], "SELECT src, dst FROM g_e"))(lambda s, d, g=_g: catalog.build(g, s, d).edges)
for _g in catalog.TEMPORAL:
    query(f"graph_{_g}_temporal", f"SELECT seq, src, dst FROM ({o.ROWS[_g][0]})")(lambda s, d, g=_g: catalog.TEMPORAL[g](s, d).rows)


@query("graph_profile", " UNION ALL ".join(f"SELECT * FROM ({o.with_([o.graph_ctes(g)], f'''SELECT '{g}' AS graph, (SELECT count(*) FROM g_v) AS vertices, count(*) AS edges, round(count(*) / (SELECT count(*) FROM g_v), 6) AS degree FROM g_e''')})" for g in catalog.GRAPHS))
def graph_profile(s: SparkSession, d: str) -> DataFrame:
    rows = []
    for g in catalog.GRAPHS:  # one after the other, and none is kept
        rows.append((g, *catalog.build(g, s, d).profile().first()))
    return s.createDataFrame(rows, "graph string, vertices long, edges long, degree double")


@query("degree_histogram", o.with_([o.graph_ctes("trade")], "SELECT degree, count(*) AS vertices FROM (SELECT src, count(*) AS degree FROM g_e GROUP BY src) GROUP BY degree"))
def degree_histogram(s: SparkSession, d: str) -> DataFrame:
    return graph(s, d, "trade").out_degrees().groupBy("degree").agg(F.count("*").alias("vertices"))


@query("links_weighted", o.with_([o.graph_ctes("geo"), o.links_cte("g")], "SELECT src, dst, CAST(round(w * 1e12) AS BIGINT) AS w_pico FROM g_l"))
def links_weighted(s: SparkSession, d: str) -> DataFrame:
    return graph(s, d, "geo").links().select("src", "dst", rel.pico("w").alias("w_pico"))


@query("block_assign", "SELECT vid, (row_number() OVER (ORDER BY vid) - 1) // 2048 AS block FROM (SELECT o_orderkey AS vid FROM orders)")
def block_assign(s: SparkSession, d: str) -> DataFrame:
    return blocks.by_size(graph(s, d, "line"), 2048)


@query(
    "block_assign_by_edges",
    o.with_(
        [o.graph_ctes("trade")],
        """SELECT vid, CAST(least((before * 8) // greatest(total, 1), 7) AS BIGINT) AS block FROM (
          SELECT vid, coalesce(sum(c) OVER (ORDER BY vid ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before, sum(c) OVER () AS total
          FROM (SELECT vid, count(dst) AS c FROM g_v LEFT JOIN g_e ON dst = vid GROUP BY vid))""",
    ),
)
def block_assign_by_edges(s: SparkSession, d: str) -> DataFrame:
    return blocks.by_edges(graph(s, d, "trade"), 8)


# ---- batches ----------------------------------------------------------------

for _mix, _n in (("del", "del"), ("ins", "ins"), ("both", "mixed")):
    query(f"batch_random_{_n}", o.with_([o.graph_ctes("trade"), o.batch_ctes(FRACTION, 3, _mix)], "SELECT src, dst, op FROM b"))(lambda s, d, m=_mix: batches.random(graph(s, d, "trade"), FRACTION, 3, m))

_APPLIED = [o.graph_ctes("line"), o.batch_ctes(FRACTION), o.applied_ctes()]


@query("batch_apply", o.with_(_APPLIED, "SELECT src, dst FROM h_e"))
def batch_apply(s: SparkSession, d: str) -> DataFrame:
    return changed(s, d, "line")[1].edges


@query("batch_diff", o.with_(_APPLIED, "SELECT src, dst, '-' AS op FROM g_e ANTI JOIN h_e USING (src, dst) UNION ALL SELECT src, dst, '+' FROM h_e ANTI JOIN g_e USING (src, dst)"))
def batch_diff(s: SparkSession, d: str) -> DataFrame:
    prev, cur, _ = changed(s, d, "line")
    return batches.diff(prev, cur)


@query("batch_invert", o.with_(_APPLIED, "SELECT src, dst, CASE WHEN op = '+' THEN '-' ELSE '+' END AS op FROM b"))
def batch_invert(s: SparkSession, d: str) -> DataFrame:
    return batches.invert(changed(s, d, "line")[2])


@query("batch_normalised", o.with_([o.graph_ctes("line"), o.batch_ctes(FRACTION)], "SELECT src, dst, op FROM b"))
def batch_normalised(s: SparkSession, d: str) -> DataFrame:
    """Repeats, self-loops and changes without effect leave no trace."""
    prev, _, batch = changed(s, d, "line")
    noise = prev.edges.withColumn("op", F.lit("+")).join(batch.select("src", "dst"), ["src", "dst"], "left_anti").unionAll(batch).unionAll(batch).unionAll(prev.vertices.select(F.col("vid").alias("src"), F.col("vid").alias("dst"), F.lit("-").alias("op")))
    return batches.normalised(prev, noise.where("not (op = '+' and src = dst)"))


_HANDOFF = f"t AS MATERIALIZED ({o.ROWS['handoff'][0]})"


@query("temporal_prefix", o.with_([_HANDOFF], f"SELECT src, dst FROM t WHERE seq < (SELECT CAST(floor(count(*) * 0.9) AS BIGINT) FROM t) UNION SELECT vid, vid FROM ({o.ROWS['handoff'][1]})"))
def temporal_prefix(s: SparkSession, d: str) -> DataFrame:
    return catalog.handoff(s, d).prefix(0.9).edges


@query("temporal_slice", o.with_([_HANDOFF], "SELECT DISTINCT src, dst, '+' AS op FROM t WHERE seq >= 100 AND seq < 300"))
def temporal_slice(s: SparkSession, d: str) -> DataFrame:
    return catalog.handoff(s, d).slice(100, 200)


@query("temporal_batches_sizes", o.with_([_HANDOFF], "SELECT seq // 500 AS batch, count(*) AS inserts, count(DISTINCT (src, dst)) AS pairs FROM t GROUP BY 1"))
def temporal_batches_sizes(s: SparkSession, d: str) -> DataFrame:
    return catalog.handoff(s, d).rows.groupBy(F.expr("seq div 500").alias("batch")).agg(F.count("*").alias("inserts"), F.countDistinct("src", "dst").alias("pairs"))


# ---- marking ----------------------------------------------------------------


@query("mark_initial", o.with_([*_APPLIED, o.marks_cte()], "SELECT vid FROM m"))
def mark_initial(s: SparkSession, d: str) -> DataFrame:
    return marking.initial(*changed(s, d, "line"))


#: The worked example of fourteen vertices; only its facts are known, the rest of
#: its edges is a ring.
EXAMPLE_OLD = [(7, 8), (10, 11), (8, 10), (9, 12), (11, 12), (1, 2), (2, 3), (3, 4), (4, 5), (5, 6), (6, 13), (13, 14), (14, 1)]


def example(s: SparkSession) -> tuple[Graph, Graph, DataFrame]:
    old = s.createDataFrame(EXAMPLE_OLD, "src long, dst long")
    prev = Graph.build(old, self_loops=False)
    batch = s.createDataFrame([(10, 11, "-"), (7, 9, "+")], batches.EMPTY)
    return prev, prev.apply(batch), batch


_GRID = [o.graph_ctes("grid"), o.batch_ctes(FRACTION), o.applied_ctes(), o.marks_cte()]


@query("mark_initial_example14", o.with_(_GRID, "SELECT vid FROM m"))
def mark_initial_example14(s: SparkSession, d: str) -> DataFrame:
    """The first step of the worked example, on the grid of the orders."""
    return marking.initial(*changed(s, d, "grid"))


@query("mark_expand_example14", o.with_(_GRID, "SELECT DISTINCT dst AS vid FROM h_e WHERE src IN (SELECT vid FROM m)"))
def mark_expand_example14(s: SparkSession, d: str) -> DataFrame:
    """Its second step: all that was marked at first has moved."""
    prev, cur, batch = changed(s, d, "grid")
    state = marking.initial(prev, cur, batch).select("vid", F.lit(0.5).alias("rank"), F.lit(0.1).alias("prev_rank"))
    return marking.expand(state, cur.edges, FRONTIER_TOL)


@query("mark_reach", o.with_([o.graph_ctes("chain"), o.batch_ctes(FRACTION), o.applied_ctes(), o.marks_cte(), o.reach_cte()], "SELECT vid FROM reached"))
def mark_reach(s: SparkSession, d: str) -> DataFrame:
    return marking.reach(*changed(s, d, "chain")).select("vid")


@query("mark_reach_sql", o.with_([o.graph_ctes("turns"), o.batch_ctes(FRACTION), o.applied_ctes(), o.marks_cte(), o.reach_cte()], "SELECT vid FROM reached"))
def mark_reach_sql(s: SparkSession, d: str) -> DataFrame:
    prev, cur, batch = changed(s, d, "turns")
    tag = uuid.uuid4().hex[:8]
    marking.initial(prev, cur, batch).createOrReplaceTempView(f"marks_{tag}")
    cur.edges.createOrReplaceTempView(f"edges_{tag}")
    return sqlapi.reach_sql(s, f"marks_{tag}", f"edges_{tag}", 40)


@query(
    "mark_frontier_growth",
    o.with_([*changed_ctes("grid"), o.sync_cte("r", "h", "before", "m", FRONTIER_TOL, PASSES)], "SELECT CAST(p AS INT) AS pass, count(*) FILTER (aff) AS active, CAST(coalesce(sum(lin) FILTER (aff), 0) AS BIGINT) AS edges_read FROM r WHERE p > 0 GROUP BY p"),
)
def mark_frontier_growth(s: SparkSession, d: str) -> DataFrame:
    run = methods.run("frontier_sync", *changed(s, d, "grid"), before(s, d, "grid"), Params(fixed_passes=PASSES))
    return run.trace_frame().select("pass", "active", "edges_read")


@query(
    "mark_quality",
    o.with_(
        [*changed_ctes("line"), o.sync_cte("r1", "h", None, None, None, BEFORE_PASSES), o.sync_cte("r", "h", "before", "m", FRONTIER_TOL, PASSES),
         "moved AS (SELECT a.vid FROM before a JOIN (SELECT * FROM r1 WHERE p = 20) b ON a.vid = b.vid WHERE abs(a.rank - b.rank) > 1e-8)",
         f"marked AS (SELECT vid FROM r WHERE p = {PASSES} AND aff)"],
        "SELECT (SELECT count(*) FROM marked) AS marked, (SELECT count(*) FROM moved) AS moved, (SELECT count(*) FROM marked JOIN moved USING (vid)) AS both",
    ),
)
def mark_quality(s: SparkSession, d: str) -> DataFrame:
    prev, cur, batch = changed(s, d, "line")
    run = methods.run("frontier_sync", prev, cur, batch, before(s, d, "line"), Params(fixed_passes=PASSES))
    after = methods.cold_sync(cur, Params(fixed_passes=BEFORE_PASSES)).ranks
    return measures.mark_quality(run.state.where("affected"), before(s, d, "line"), after, 1e-8).select("marked", "moved", "both")


@query("mark_with_help_ledger", o.with_([o.graph_ctes("line"), o.batch_ctes(FRACTION)], "SELECT DISTINCT src, CAST(CASE WHEN src % 16 IN (3, 5) THEN 3 WHEN src % 16 IN (1, 2) THEN 2 ELSE 1 END AS INT) AS attempts FROM b"))
def mark_with_help_ledger(s: SparkSession, d: str) -> DataFrame:
    return marking.initial_with_help(*changed(s, d, "line"), lost=[{1, 2, 3, 5}, {3, 5}])[1]


# ---- methods ----------------------------------------------------------------

_DYNAMIC = {"warm_sync": None, "warm_async": None, "reach_sync": "reached", "reach_async": "reached", "frontier_sync": "m", "frontier_async": "m"}


def _method_sql(method: str, name: str) -> str:
    ctes = changed_ctes(name)
    if method.startswith("reach"):
        ctes.append(o.reach_cte())
    ranks = None if method.startswith("cold") else "before"
    tol = FRONTIER_TOL if method.startswith("frontier") else None
    if method.endswith("_sync"):
        ctes.append(o.sync_cte("r", "h", ranks, _DYNAMIC.get(method), tol, PASSES))
        return o.with_(ctes, f"SELECT vid, {o.pico()} AS rank_pico FROM r WHERE p = {PASSES}")
    ctes.append(o.async_cte("r", "h", ranks, _DYNAMIC.get(method), tol, ASYNC_PASSES, BLOCKS))
    return o.with_(ctes, f"SELECT vid, {o.pico()} AS rank_pico FROM r WHERE i = {ASYNC_PASSES * (BLOCKS + 1)}")


def _method(s: SparkSession, d: str, method: str, name: str, plan: str = "auto") -> DataFrame:
    params = Params(fixed_passes=PASSES, plan=plan) if method.endswith("_sync") else Params(fixed_passes=ASYNC_PASSES, blocks=BLOCKS, plan=plan)
    return _pico(methods.run(method, *changed(s, d, name), before(s, d, name), params).ranks)


for _m in methods.METHODS:
    for _g in ("line", "trade", "web"):
        query(f"{_m}_{_g}", _method_sql(_m, _g))(lambda s, d, m=_m, g=_g: _method(s, d, m, g))

def _conv_sql(method: str, name: str) -> str:
    ctes = changed_ctes(name, passes=None)
    if method.startswith("reach"):
        ctes.append(o.reach_cte())
    ranks = None if method.startswith("cold") else "before"
    tol = FRONTIER_TOL if method.startswith("frontier") else None
    if method.endswith("_sync"):
        ctes.append(o.sync_cte("r", "h", ranks, _DYNAMIC.get(method), tol, 500, 1e-10))
        return o.with_(ctes, f"SELECT vid, CAST(p AS INT) AS passes, {o.pico()} AS rank_pico FROM {o.last('r')} z")
    ctes.append(o.async_cte("r", "h", ranks, _DYNAMIC.get(method), tol, 500, 2, until_closed=True))
    return o.with_(ctes, f"SELECT vid, CAST(i // 3 AS INT) AS passes, {o.pico()} AS rank_pico FROM {o.last('r', 'i')} z")


def _converged(s: SparkSession, d: str, method: str, name: str) -> DataFrame:
    """A run to its tolerance from ranks that are at theirs."""
    prev, cur, batch = changed(s, d, name)
    ranks = None if method.startswith("cold") else settled(s, d, name)
    run = methods.run(method, prev, cur, batch, ranks, Params(blocks=2, plan=whole_plan(cur)))
    return _pico(run.ranks).withColumn("passes", F.lit(run.passes))


for _m in methods.METHODS:
    for _g in ("line", "trade", "web"):
        query(f"{_m}_{_g}_conv", _conv_sql(_m, _g))(lambda s, d, m=_m, g=_g: _converged(s, d, m, g))
query("frontier_sync_grid_conv", _conv_sql("frontier_sync", "grid"))(lambda s, d: _converged(s, d, "frontier_sync", "grid"))

for _rule in ("literal", "latched"):
    query(f"cold_async_web_{_rule}", o.with_([*changed_ctes("web"), o.async_cte("r", "h", None, None, None, 6, 2, flag_rule=_rule, until_closed=True)], f"SELECT CAST(i // 3 AS INT) AS passes, count(*) FILTER (open) AS open FROM {o.last('r', 'i')} z GROUP BY i"))(
        lambda s, d, r=_rule: (lambda run: run.state.agg(F.count(F.when(F.col("open"), 1)).alias("open")).withColumn("passes", F.lit(run.passes)))(methods.run("cold_async", *changed(s, d, "web"), before(s, d, "web"), Params(blocks=2, flag_rule=r, max_passes=6)))
    )


@query("frontier_async_web_delta", o.with_([*changed_ctes("web"), o.async_cte("r", "h", "before", "m", FRONTIER_TOL, ASYNC_PASSES, BLOCKS, close_rule="delta")], f"SELECT vid, {o.pico()} AS rank_pico, open FROM r WHERE i = {ASYNC_PASSES * (BLOCKS + 1)}"))
def frontier_async_web_delta(s: SparkSession, d: str) -> DataFrame:
    run = methods.run("frontier_async", *changed(s, d, "web"), before(s, d, "web"), Params(fixed_passes=ASYNC_PASSES, blocks=BLOCKS, close_rule="delta"))
    return run.state.select("vid", rel.pico().alias("rank_pico"), "open")


@query("reference_web", o.with_([o.graph_ctes("web"), o.links_cte("g"), o.sync_cte("r", "g", None, None, None, 120)], f"SELECT vid, {o.pico()} AS rank_pico FROM r WHERE p = 120"))
def reference_web(s: SparkSession, d: str) -> DataFrame:
    return _pico(methods.reference(graph(s, d, "web"), 120).ranks)


@query("frontier_sync_expand_off", o.with_([*changed_ctes("line"), o.sync_cte("r", "h", "before", "m", None, PASSES)], f"SELECT vid, {o.pico()} AS rank_pico FROM r WHERE p = {PASSES}"))
def frontier_sync_expand_off(s: SparkSession, d: str) -> DataFrame:
    return _pico(methods.frontier_sync(*changed(s, d, "line"), before(s, d, "line"), Params(fixed_passes=PASSES), expand=False).ranks)


for _m, _plan in (("frontier_sync", "pruned"), ("frontier_sync", "fused"), ("frontier_async", "fused"), ("cold_async", "local")):
    query(f"{_m}_{_plan}", _method_sql(_m, "line"))(lambda s, d, m=_m, p=_plan: _method(s, d, m, "line", p))


_SWEEP = (1.0, 0.1, 0.001)


@query(
    "frontier_sync_ft_sweep",
    o.with_(
        [*changed_ctes("grid"), *(o.sync_cte(f"f{i}", "h", "before", "m", 1e-10 * f, PASSES) for i, f in enumerate(_SWEEP))],
        " UNION ALL ".join(f"SELECT CAST({f!r} AS DOUBLE) AS factor, count(*) FILTER (aff) AS affected, (SELECT CAST(sum(lin) FILTER (aff) AS BIGINT) FROM f{i}) AS edges_read FROM f{i} WHERE p = {PASSES}" for i, f in enumerate(_SWEEP)),
    ),
)
def frontier_sync_ft_sweep(s: SparkSession, d: str) -> DataFrame:
    rows = []
    for f in _SWEEP:
        run = methods.run("frontier_sync", *changed(s, d, "grid"), before(s, d, "grid"), Params(fixed_passes=PASSES, frontier_tol=1e-10 * f))
        rows.append((f, run.trace[-1].active, run.edges_read))
    return s.createDataFrame(rows, "factor double, affected long, edges_read long")


@query("no_barrier_only_web")
def no_barrier_only_web(s: SparkSession, d: str) -> DataFrame:
    """Error of the negative control against the reference."""
    g = graph(s, d, "web")
    run = methods.no_barrier_only(g, Params(fixed_passes=30))
    return measures.norms(run.ranks, truth(s, d, after=False))


# ---- measures ---------------------------------------------------------------

_TWO = [*changed_ctes("trade"), o.sync_cte("r", "h", "before", None, None, PASSES), f"after AS MATERIALIZED (SELECT vid, rank FROM r WHERE p = {PASSES})"]


def after(s: SparkSession, d: str) -> DataFrame:
    return once(s, d, "after trade", lambda: methods.run("warm_sync", *changed(s, d, "trade"), before(s, d, "trade"), Params(fixed_passes=PASSES)).ranks)


@query("error_linf", o.with_(_TWO, f"SELECT {o.pico('max(abs(a.rank - b.rank))')} AS error_pico FROM before a JOIN after b USING (vid)"))
def error_linf(s: SparkSession, d: str) -> DataFrame:
    return measures.norms(before(s, d, "trade"), after(s, d)).select(rel.pico("linf").alias("error_pico"))


@query("norms_compare", o.with_(_TWO, f"SELECT {o.pico('max(d)')} AS linf, {o.pico('sum(d)')} AS l1, {o.pico('sqrt(sum(d * d))')} AS l2 FROM (SELECT abs(a.rank - b.rank) AS d FROM before a JOIN after b USING (vid))"))
def norms_compare(s: SparkSession, d: str) -> DataFrame:
    return measures.norms(before(s, d, "trade"), after(s, d)).select(*(rel.pico(c).alias(c) for c in ("linf", "l1", "l2")))


@query("mass_check", " UNION ALL ".join(f"SELECT * FROM ({o.with_(before_ctes(g), f'''SELECT '{g}' AS graph, CAST(round(sum(rank) * 1e9) AS BIGINT) AS mass_nano FROM before''')})" for g in ("line", "trade", "web")))
def mass_check(s: SparkSession, d: str) -> DataFrame:
    return s.createDataFrame([(g, round(measures.mass(before(s, d, g)) * 1e9)) for g in ("line", "trade", "web")], "graph string, mass_nano long")


@query("geomean_speedup", "WITH t AS (SELECT l_returnflag AS method, CAST(l_linenumber AS DOUBLE) AS fraction, l_quantity AS seconds FROM lineitem), m AS (SELECT method, fraction, exp(avg(ln(seconds))) AS g FROM t GROUP BY 1, 2) SELECT a.method, a.fraction, round(a.g, 6) AS geomean, round(b.g / a.g, 6) AS speedup FROM m a JOIN m b ON b.fraction = a.fraction AND b.method = 'A'")
def geomean_speedup(s: SparkSession, d: str) -> DataFrame:
    times = catalog.table(s, d, "lineitem").select(F.col("l_returnflag").alias("method"), F.col("l_linenumber").cast("double").alias("fraction"), F.lit("g").alias("graph"), F.col("l_quantity").alias("seconds"))
    return measures.speedups(times, "A").select("method", "fraction", F.round("geomean", 6).alias("geomean"), F.round("speedup", 6).alias("speedup"))


@query("work_trace", o.with_([*changed_ctes("line"), o.async_cte("r", "h", "before", "m", FRONTIER_TOL, ASYNC_PASSES, BLOCKS)], f"SELECT CAST((i - 1) // {BLOCKS + 1} + 1 AS INT) AS pass, count(*) FILTER (just) AS active, CAST(coalesce(sum(lin) FILTER (just), 0) AS BIGINT) AS edges_read, count(*) FILTER (open AND i % {BLOCKS + 1} = 0) AS open FROM r WHERE i > 0 GROUP BY 1"))
def work_trace(s: SparkSession, d: str) -> DataFrame:
    run = methods.run("frontier_async", *changed(s, d, "line"), before(s, d, "line"), Params(fixed_passes=ASYNC_PASSES, blocks=BLOCKS))
    return run.trace_frame().select("pass", "active", "edges_read", "open")


@query("topk_overlap", o.with_(_TWO, "SELECT 50 AS k, count(*) AS shared FROM (SELECT vid FROM before ORDER BY round(rank, 12) DESC, vid LIMIT 50) JOIN (SELECT vid FROM after ORDER BY round(rank, 12) DESC, vid LIMIT 50) USING (vid)"))
def topk_overlap(s: SparkSession, d: str) -> DataFrame:
    return measures.topk_overlap(before(s, d, "trade"), after(s, d), 50)


@query("flag_block_rollup", o.with_([*changed_ctes("line"), o.async_cte("r", "h", "before", "m", FRONTIER_TOL, ASYNC_PASSES, BLOCKS)], f"SELECT vid % {BLOCKS} AS block, bool_or(open) AS open, count(*) FILTER (open) AS n FROM r WHERE i = {ASYNC_PASSES * (BLOCKS + 1)} GROUP BY 1"))
def flag_block_rollup(s: SparkSession, d: str) -> DataFrame:
    run = methods.run("frontier_async", *changed(s, d, "line"), before(s, d, "line"), Params(fixed_passes=ASYNC_PASSES, blocks=BLOCKS))
    return run.state.groupBy(blocks.by_id("vid", BLOCKS).alias("block")).agg(F.bool_or("open").alias("open"), F.count(F.when(F.col("open"), 1)).alias("n"))


# ---- workloads --------------------------------------------------------------


def _counts(rows: DataFrame) -> DataFrame:
    return rows.select("fraction", "batch_no", "method", "passes", "converged", "edges_read", "affected", (F.col("error") < 1e-9).alias("within_1e_9"))


# every batch of the last tenth, all six methods, each from its own ranks
for _g in catalog.TEMPORAL:
    for _f, _name in ((1e-3, "1e_3"), (1e-4, "1e_4")):
        query(f"w1_replay_{_g}_{_name}")(lambda s, d, g=_g, f=_f: _counts(replays.replay(catalog.TEMPORAL[g](s, d), f)))


def _random_runs(s: SparkSession, d: str, name: str) -> DataFrame:
    return once(s, d, f"random {name}", lambda: cut(replays.random_batches(graph(s, d, name), SIZES)))


# all sizes, two batches each, all six methods, against a reference of 500 passes
for _g in catalog.GRAPHS:
    query(f"w2_random_{_g}")(lambda s, d, g=_g: _counts(_random_runs(s, d, g)))


@query("w3_error_curve")
def w3_error_curve(s: SparkSession, d: str) -> DataFrame:
    """Largest error of each method at each size over all graphs, in 1e-12, and mean
    passes and links read."""
    every = None
    for g in catalog.GRAPHS:
        rows = _random_runs(s, d, g)
        every = rows if every is None else every.unionAll(rows)
    return every.groupBy("method", "fraction").agg(F.max(F.round(F.col("error") * 1e12)).cast("long").alias("error_pico"), F.round(F.avg("passes"), 3).alias("passes"), F.round(F.avg("edges_read"), 3).alias("edges_read"))


@query("w4_stability")
def w4_stability(s: SparkSession, d: str) -> DataFrame:
    """A batch goes and comes again: all sizes, graphs and methods."""
    every = None
    for g in catalog.GRAPHS:
        rows = replays.round_trips(graph(s, d, g), SIZES).select(F.lit(g).alias("graph"), "fraction", "method", (F.col("difference") < 1e-9).alias("within_1e_9"))
        every = rows if every is None else every.unionAll(rows)
    return every


def _costs(s: SparkSession, d: str, name: str, n_blocks: int = 256) -> tuple[list[dict], list[dict]]:
    """Work of the two frontier methods by pass and block, of two buffers and in place."""
    return once(s, d, f"costs {name} {n_blocks}", lambda: replays.frontier_costs(*changed(s, d, name), n_blocks))


CLOCKED = ("grid", "trade", "web")


def _clocked(s: SparkSession, d: str, rows, schema: str) -> DataFrame:
    made = [(g, *r) for g in CLOCKED for r in rows(*_costs(s, d, g))]
    return s.createDataFrame(made, "graph string, " + schema)


@query("w5_scaling")
def w5_scaling(s: SparkSession, d: str) -> DataFrame:
    return _clocked(s, d, lambda a, b: workloads.scaling(a, b, (1, 2, 4, 8, 16, 32, 64)), "workers int, barrier double, barrier_free double")


@query("w6_delay_sim")
def w6_delay_sim(s: SparkSession, d: str) -> DataFrame:
    return _clocked(s, d, lambda a, b: workloads.delays(a, b, (5_000, 10_000, 20_000), (1e-5, 1e-4, 1e-3)), "sleep_units long, chance double, sleeps long, barrier_units long, free_units long, ratio double")


@query("w7_crash_sim")
def w7_crash_sim(s: SparkSession, d: str) -> DataFrame:
    return _clocked(s, d, lambda a, b: workloads.crashes(a, b, (0, 1, 2, 4, 8, 16, 32, 48, 56)), "crashed int, barrier_finished boolean, free_units long, relative_speed double")


_WAIT = [4**k for k in range(1, 8)]


@query(
    "w8_chunk_costs",
    " UNION ALL ".join(
        f"SELECT * FROM ({o.with_([o.graph_ctes(g)], f'''SELECT '{g}' AS graph, c AS chunk, count(*) AS blocks, CAST(max(cost) AS BIGINT) AS largest, CAST(sum(cost) AS BIGINT) AS total FROM (SELECT c, pos // c AS block, sum(k + 1) AS cost FROM (SELECT row_number() OVER (ORDER BY vid) - 1 AS pos, k FROM (SELECT dst AS vid, count(*) AS k FROM g_e GROUP BY dst)) x, (SELECT unnest({_WAIT}) AS c) y GROUP BY 1, 2) GROUP BY c''')})"
        for g in ("trade", "web", "chain")
    ),
)
def w8_chunk_costs(s: SparkSession, d: str) -> DataFrame:
    """What a pass from scratch costs by chunk size: blocks, the largest and all."""
    rows = [(g, size, len(c), max(c), sum(c)) for g, size, c in _chunks(s, d)]
    return s.createDataFrame(rows, "graph string, chunk int, blocks long, largest long, total long")


def _chunks(s: SparkSession, d: str) -> list[tuple[str, int, list[int]]]:
    def make() -> list:
        out = []
        for name in ("trade", "web", "chain"):
            g = graph(s, d, name)
            into = g.edges.groupBy(F.col("dst").alias("vid")).agg((F.count("*") + 1).alias("cost"))
            placed = cut(ordered(into, ["vid"]))
            for size in _WAIT:
                rows = placed.groupBy(F.expr(f"seq div {size}").alias("block")).agg(F.sum("cost").alias("cost")).orderBy("block").collect()
                out.append((name, size, [r["cost"] for r in rows]))
        return out

    return once(s, d, "chunks", make)


@query("w8_wait_share")
def w8_wait_share(s: SparkSession, d: str) -> DataFrame:
    """Share of time that 64 workers wait at barriers, by chunk size."""
    rows = [(g, size, round(faults.Simulator(workers=64).play([{b: (x, 0) for b, x in enumerate(c)}] * 4, True).wait_share, 6)) for g, size, c in _chunks(s, d)]
    return s.createDataFrame(rows, "graph string, chunk int, wait_share double")


@query("w9_tolerance_sweep")
def w9_tolerance_sweep(s: SparkSession, d: str) -> DataFrame:
    rows = []
    for g in ("web", "grid"):
        prev, cur, batch = changed(s, d, g)
        rows += [(g, f, p, a, e, err < 1e-9) for f, p, a, e, err in workloads.tolerance_sweep(prev, cur, batch, settled(s, d, g), truth(s, d, g), (1.0, 0.1, 0.01, 0.001, 0.0001, 0.0))]
    return s.createDataFrame(rows, "graph string, factor double, passes int, affected long, edges_read long, within_1e_9 boolean")


@query(
    "w10_reach_vs_warm",
    " UNION ALL ".join(
        f"SELECT * FROM ({o.with_([o.graph_ctes(g), o.batch_ctes(FRACTION), o.applied_ctes(), o.marks_cte(), o.reach_cte()], f'''SELECT '{g}' AS graph, (SELECT count(*) FROM reached) AS reached, (SELECT count(*) FROM h_v) AS vertices, (SELECT count(*) FROM h_e WHERE dst IN (SELECT vid FROM reached)) AS reach_links, (SELECT count(*) FROM h_e) AS warm_links''')})"
        for g in ("chain", "turns", "web")
    ),
)
def w10_reach_vs_warm(s: SparkSession, d: str) -> DataFrame:
    """Links a pass: reach against warm start."""
    out = None
    for name in ("chain", "turns", "web"):
        prev, cur, batch = changed(s, d, name)
        seen = marking.reach(prev, cur, batch).select(F.col("vid").alias("dst"), F.lit(1).alias("r"))
        links = cur.edges.join(seen, "dst", "left").agg(F.count("r").alias("reach_links"), F.count("*").alias("warm_links"))
        row = links.crossJoin(seen.agg(F.count("*").alias("reached"))).select(F.lit(name).alias("graph"), "reached", F.lit(cur.n).cast("long").alias("vertices"), "reach_links", "warm_links")
        out = row if out is None else out.unionAll(row)
    return out


@query("w11_fixed_vs_pooled")
def w11_fixed_vs_pooled(s: SparkSession, d: str) -> DataFrame:
    """The earlier schedule, in which workers own blocks, against the pool, in place."""
    rows = []
    for g in CLOCKED:
        _, in_place = once(s, d, f"whole costs {g}", lambda g=g: replays.whole_costs(graph(s, d, g), 64, 8))
        fixed, pooled = faults.static_schedule(in_place, 8)
        rows += [(g, "fixed", fixed.units), (g, "pooled", pooled.units)]
    return s.createDataFrame(rows, "graph string, schedule string, units long")


_EXAMPLE = [
    f"g_v AS MATERIALIZED (SELECT CAST(unnest(range(1, 15)) AS BIGINT) AS vid), g_p AS MATERIALIZED (SELECT CAST(s AS BIGINT) AS src, CAST(t AS BIGINT) AS dst FROM (VALUES {', '.join(map(str, EXAMPLE_OLD))}) v(s, t)), g_e AS MATERIALIZED (SELECT src, dst FROM g_p UNION SELECT vid, vid FROM g_v)",
    "b AS (SELECT * FROM (VALUES (10::BIGINT, 11::BIGINT, '-'), (7::BIGINT, 9::BIGINT, '+')) v(src, dst, op))",
]


@query(
    "w12_example_ranks",
    o.with_([*_EXAMPLE, o.applied_ctes(), o.links_cte("g"), o.links_cte("h"), o.sync_cte("r0", "g", None, None, None, 500, 1e-10), "before AS MATERIALIZED (SELECT vid, rank FROM " + o.last("r0") + " z)", o.marks_cte(), o.sync_cte("r", "h", "before", "m", FRONTIER_TOL, 500, 1e-10)], f"SELECT vid, CAST(p AS INT) AS passes, aff AS affected, {o.pico()} AS rank_pico FROM {o.last('r')} z"),
)
def w12_example_ranks(s: SparkSession, d: str) -> DataFrame:
    """The example of fourteen vertices, with loops, taken through to its ranks."""
    prev = Graph.build(s.createDataFrame(EXAMPLE_OLD, "src long, dst long"))
    batch = s.createDataFrame([(10, 11, "-"), (7, 9, "+")], batches.EMPTY)
    run = methods.frontier_sync(prev, prev.apply(batch), batch, methods.cold_sync(prev, Params(plan="local")).ranks)
    return run.state.select("vid", F.lit(run.passes).alias("passes"), "affected", rel.pico().alias("rank_pico"))


@query("lost_blocks")
def lost_blocks(s: SparkSession, d: str) -> DataFrame:
    """An in-place run that loses blocks and finishes others late still ends
    within the error bar."""
    prev, cur, batch = changed(s, d, "web")
    run = faults.run_with_losses(prev, cur, batch, settled(s, d, "web"), {1: {0, 1}, 2: {1}, 4: {2}}, {3: {0}}, Params(blocks=3, max_passes=150))
    return s.createDataFrame([(run.converged, measures.error(run, truth(s, d)) < 1e-9)], "converged boolean, within_1e_9 boolean")


# ---- relational -------------------------------------------------------------

_BY_NAME = "who AS MATERIALIZED (SELECT b.vid, b.rank, 'customer' AS kind, c_name AS name, c_nationkey AS nationkey, c_mktsegment AS segment FROM before b JOIN customer ON c_custkey * 2 = vid UNION ALL SELECT b.vid, b.rank, 'supplier', s_name, s_nationkey, NULL FROM before b JOIN supplier ON s_suppkey * 2 + 1 = vid)"
_WHO = [*before_ctes("trade"), _BY_NAME]


def who(s: SparkSession, d: str) -> DataFrame:
    return rel.named(before(s, d, "trade"), catalog.table(s, d, "customer"), catalog.table(s, d, "supplier"))


def nations(s: SparkSession, d: str) -> DataFrame:
    return catalog.table(s, d, "nation").join(catalog.table(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_nationkey").alias("nationkey"), F.col("n_name").alias("nation"), F.col("r_name").alias("region"))


_NATIONS = "geo AS (SELECT n_nationkey AS nationkey, n_name AS nation, r_name AS region FROM nation JOIN region ON n_regionkey = r_regionkey)"


@query("rank_topk", o.with_(before_ctes("trade"), f"SELECT vid, {o.pico()} AS rank_pico FROM before ORDER BY 2 DESC, 1 LIMIT 100"))
def rank_topk(s: SparkSession, d: str) -> DataFrame:
    return rel.topk(before(s, d, "trade"), 100)


@query("rank_topk_per_kind", o.with_(_WHO, f"SELECT kind, CAST(place AS INT) AS place, vid, rank_pico FROM (SELECT kind, vid, {o.pico()} AS rank_pico, row_number() OVER (PARTITION BY kind ORDER BY {o.pico()} DESC, vid) AS place FROM who) WHERE place <= 20"))
def rank_topk_per_kind(s: SparkSession, d: str) -> DataFrame:
    return rel.topk_by(who(s, d), "kind", 20)


@query("rank_movers", o.with_(_TWO, f"SELECT vid, {o.pico('a.rank')} AS before_pico, {o.pico('b.rank')} AS after_pico, {o.pico('b.rank')} - {o.pico('a.rank')} AS change_pico FROM before a JOIN after b USING (vid) ORDER BY abs({o.pico('b.rank')} - {o.pico('a.rank')}) DESC, vid LIMIT 50"))
def rank_movers(s: SparkSession, d: str) -> DataFrame:
    return rel.movers(before(s, d, "trade"), after(s, d), 50)


_SUM = f"CAST(sum({o.pico()}) AS BIGINT) AS mass_pico, count(*) AS n"


@query("rank_rollup_geo", o.with_([*_WHO, _NATIONS], f"SELECT region, nation, {_SUM} FROM who JOIN geo USING (nationkey) GROUP BY ROLLUP (region, nation)"))
def rank_rollup_geo(s: SparkSession, d: str) -> DataFrame:
    return who(s, d).join(F.broadcast(nations(s, d)), "nationkey").rollup("region", "nation").agg(F.sum(rel.pico()).alias("mass_pico"), F.count("*").alias("n"))


@query("rank_cube", o.with_([*_WHO, _NATIONS], f"SELECT region, kind, {_SUM} FROM who JOIN geo USING (nationkey) GROUP BY CUBE (region, kind)"))
def rank_cube(s: SparkSession, d: str) -> DataFrame:
    return who(s, d).join(F.broadcast(nations(s, d)), "nationkey").cube("region", "kind").agg(F.sum(rel.pico()).alias("mass_pico"), F.count("*").alias("n"))


@query("rank_grouping_sets", o.with_([*_WHO, _NATIONS], f"SELECT region, segment, {_SUM} FROM who JOIN geo USING (nationkey) GROUP BY GROUPING SETS ((region), (segment), ())"))
def rank_grouping_sets(s: SparkSession, d: str) -> DataFrame:
    rows = who(s, d).join(F.broadcast(nations(s, d)), "nationkey").withColumn("pico", rel.pico())
    return rows.groupingSets([["region"], ["segment"], []], "region", "segment").agg(F.sum("pico").alias("mass_pico"), F.count("*").alias("n"))


@query("rank_pivot", o.with_([*_WHO, _NATIONS], f"SELECT region, CAST(coalesce(sum({o.pico()}) FILTER (kind = 'customer'), 0) AS BIGINT) AS customer, CAST(coalesce(sum({o.pico()}) FILTER (kind = 'supplier'), 0) AS BIGINT) AS supplier FROM who JOIN geo USING (nationkey) GROUP BY region"))
def rank_pivot(s: SparkSession, d: str) -> DataFrame:
    rows = who(s, d).join(F.broadcast(nations(s, d)), "nationkey").withColumn("pico", rel.pico())
    return rows.groupBy("region").pivot("kind", ["customer", "supplier"]).agg(F.coalesce(F.sum("pico"), F.lit(0)))


@query(
    "rank_window_suite",
    o.with_(_WHO, f"""SELECT vid, CAST(rank() OVER w AS INT) AS rk, CAST(dense_rank() OVER w AS INT) AS dr, CAST(ntile(4) OVER (PARTITION BY kind ORDER BY p DESC, vid) AS INT) AS quarter,
      round(percent_rank() OVER w, 9) AS pr, round(cume_dist() OVER w, 9) AS cd, lag(p) OVER (PARTITION BY kind ORDER BY vid) AS lag_pico,
      CAST(sum(p) OVER (PARTITION BY kind ORDER BY vid ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS moving FROM (SELECT vid, kind, {o.pico()} AS p FROM who) WINDOW w AS (PARTITION BY kind ORDER BY p DESC)"""),
)
def rank_window_suite(s: SparkSession, d: str) -> DataFrame:
    w = W.partitionBy("kind").orderBy(F.desc("p"))
    by_vid = W.partitionBy("kind").orderBy("vid")
    rows = who(s, d).select("vid", "kind", rel.pico().alias("p"))
    return rows.select(
        "vid", F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(W.partitionBy("kind").orderBy(F.desc("p"), "vid")).alias("quarter"),
        F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"), F.lag("p").over(by_vid).alias("lag_pico"), F.sum("p").over(by_vid.rowsBetween(-2, 0)).alias("moving"),
    )


@query(
    "rank_asof_events",
    o.with_(
        [*before_ctes("handoff"), f"v AS MATERIALIZED (SELECT o_custkey % 150 AS user_id, o_orderdate AS ts, max(o_totalprice) AS price FROM orders GROUP BY 1, 2)"],
        f"SELECT e.event_id, {o.pico('b.rank')} AS rank_pico, v.price AS last_price FROM events e JOIN before b ON b.vid = e.user_id ASOF LEFT JOIN v ON v.user_id = e.user_id AND v.ts <= e.ts",
    ),
)
def rank_asof_events(s: SparkSession, d: str) -> DataFrame:
    """Each event with its user's rank and the last order price known at its time."""
    events = catalog.table(s, d, "events").select("event_id", "user_id", "ts")
    prices = catalog.table(s, d, "orders").groupBy((F.col("o_custkey") % 150).alias("user_id"), F.col("o_orderdate").alias("ts")).agg(F.max("o_totalprice").alias("last_price"))
    known = rel.as_of(events, prices, "ts", ["user_id"], "last_price")
    return known.join(before(s, d, "handoff").withColumnRenamed("vid", "user_id"), "user_id").select("event_id", rel.pico().alias("rank_pico"), "last_price")


@query("rank_range_join", o.with_(before_ctes("trade"), f"SELECT s_suppkey, count(*) AS n FROM (SELECT {o.pico()} AS p FROM before) JOIN (SELECT s_suppkey, {o.pico()} AS lo, {o.pico()} + 1000000 AS hi FROM supplier JOIN before ON vid = s_suppkey * 2 + 1) ON p >= lo AND p < hi GROUP BY 1"))
def rank_range_join(s: SparkSession, d: str) -> DataFrame:
    p = before(s, d, "trade").select("vid", rel.pico().alias("p"))
    spans = p.where("vid % 2 = 1").select(F.expr("(vid - 1) div 2").alias("s_suppkey"), F.col("p").alias("lo"), (F.col("p") + 1_000_000).alias("hi"))
    return rel.range_join(p.select("p"), spans, "p", "lo", "hi", 1_000_000).groupBy("s_suppkey").agg(F.count("*").alias("n"))


for _k, _sql in {"union": "UNION", "intersect": "INTERSECT", "except": "EXCEPT"}.items():
    query(f"edges_{_k}", o.with_(_APPLIED, f"SELECT src, dst FROM g_e {_sql} SELECT src, dst FROM h_e"))(
        lambda s, d, k=_k: (lambda a, b: {"union": a.union(b).distinct(), "intersect": a.intersect(b), "except": a.exceptAll(b)}[k])(changed(s, d, "line")[0].edges.select("src", "dst"), changed(s, d, "line")[1].edges.select("src", "dst"))
    )
for _k, _how in {"semi": "SEMI", "anti": "ANTI"}.items():
    query(f"edges_{_k}", o.with_([*_APPLIED, o.marks_cte()], f"SELECT src, dst FROM h_e {_how} JOIN m ON vid = dst"))(lambda s, d, k=_k: changed(s, d, "line")[1].edges.join(mark_initial(s, d).withColumnRenamed("vid", "dst"), "dst", f"left_{k}").select("src", "dst"))


@query("rank_versions_full_outer", o.with_(_TWO, f"SELECT vid, {o.pico('a.rank')} AS x, {o.pico('b.rank')} AS y FROM before a FULL JOIN (SELECT vid + 2 AS vid, rank FROM after) b USING (vid)"))
def rank_versions_full_outer(s: SparkSession, d: str) -> DataFrame:
    # ids of the second version are moved, so that both sides have rows of their own
    a, b = before(s, d, "trade"), after(s, d).withColumn("vid", F.col("vid") + 2)
    return a.select("vid", rel.pico().alias("x")).join(b.select("vid", rel.pico().alias("y")), "vid", "full")


@query("theta_rank", o.with_(_WHO, f"SELECT s.vid, count(*) AS n FROM (SELECT vid, {o.pico()} AS p FROM who WHERE kind = 'supplier') s JOIN (SELECT {o.pico()} AS p FROM who WHERE segment = 'BUILDING' OR kind = 'supplier') c ON c.p < s.p GROUP BY 1"))
def theta_rank(s: SparkSession, d: str) -> DataFrame:
    """How many suppliers, and customers of one segment, rank below each supplier: an
    inequality join, as running counts over one order of both sides."""
    rows = who(s, d).select("vid", "kind", "segment", rel.pico().alias("p"))
    points = rows.where("segment = 'BUILDING' or kind = 'supplier'").select("p")
    return rel.below(points, rows.where("kind = 'supplier'").select("vid", "p"), "p").where("n > 0").select("vid", "n")


@query("approx_hosts")
def approx_hosts(s: SparkSession, d: str) -> DataFrame:
    return catalog.table(s, d, "pages").agg(F.approx_count_distinct(F.parse_url("url", F.lit("HOST")), 0.01).alias("hosts"))


@query("percentiles", o.with_(_WHO, f"SELECT kind, CAST(quantile_disc({o.pico()}, 0.5) AS BIGINT) AS median, round(stddev_samp({o.pico()}), 3) AS sd, max_by(vid, {o.pico()} * 100000 + vid) AS top FROM who GROUP BY kind"))
def percentiles(s: SparkSession, d: str) -> DataFrame:
    rows = who(s, d).select("kind", "vid", rel.pico().alias("p"))
    return rows.groupBy("kind").agg(F.expr("percentile_disc(0.5) within group (order by p)").cast("long").alias("median"), F.round(F.stddev_samp("p"), 3).alias("sd"), F.max_by("vid", F.col("p") * 100000 + F.col("vid")).alias("top"))


@query("json_props", "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")
def json_props(s: SparkSession, d: str) -> DataFrame:
    return catalog.table(s, d, "events").groupBy(F.get_json_object("props", "$.k").cast("long").alias("k")).agg(F.count("*").alias("n"))


@query("url_parts", "SELECT regexp_extract(url, '^[a-z]+://([^/]*)', 1) AS host, count(*) AS pages, CAST(sum(len(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1))) AS BIGINT) AS links FROM pages GROUP BY 1")
def url_parts(s: SparkSession, d: str) -> DataFrame:
    return catalog.table(s, d, "pages").groupBy(F.regexp_extract("url", r"^[a-z]+://([^/]*)", 1).alias("host")).agg(F.count("*").alias("pages"), F.sum(F.size(F.regexp_extract_all("html", F.lit(r'href="([^"]*)"'), 1))).cast("long").alias("links"))


@query("array_cosine", "SELECT a.vec_id, round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 6) AS cosine FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def array_cosine(s: SparkSession, d: str) -> DataFrame:
    e = catalog.table(s, d, "embeddings").select("vec_id", "embedding")
    follow = e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("other"))
    return e.join(follow, "vec_id").select("vec_id", F.round(udfs.cosine("embedding", "other"), 6).alias("cosine"))


@query("udf_suite", "SELECT l_returnflag, round(exp(avg(ln(l_quantity))), 9) AS built_in, round(exp(avg(ln(l_quantity))), 9) AS udf FROM lineitem GROUP BY 1")
def udf_suite(s: SparkSession, d: str) -> DataFrame:
    rows = catalog.table(s, d, "lineitem").select("l_returnflag", "l_quantity")
    a = rows.groupBy("l_returnflag").agg(F.round(measures.geomean("l_quantity"), 9).alias("built_in"))
    return a.join(rows.groupBy("l_returnflag").agg(F.round(udfs.geomean_udf("l_quantity"), 9).alias("udf")), "l_returnflag")


@query("udtf_ring", "SELECT CAST(h AS INT) AS hop, (n_nationkey + h) % 25 AS vid, n_nationkey FROM (SELECT n_nationkey, unnest(range(1, 4)) AS h FROM nation)")
def udtf_ring(s: SparkSession, d: str) -> DataFrame:
    udfs.register(s)
    catalog.table(s, d, "nation").createOrReplaceTempView("rank_nation")
    return s.sql("SELECT r.hop, r.vid, n_nationkey FROM rank_nation, LATERAL ring(CAST(n_nationkey AS BIGINT), 3, 25) r")


@query("udtf_neighbors", o.with_([o.graph_ctes("turns"), "near AS (SELECT vid, 0 AS hop, vid AS other FROM g_v UNION SELECT vid, hop + 1, dst FROM near JOIN g_e ON src = other WHERE hop < 3 AND src <> dst)"], "SELECT vid, CAST(min(hop) AS INT) AS hop, other FROM near GROUP BY vid, other HAVING min(hop) > 0"))
def udtf_neighbors(s: SparkSession, d: str) -> DataFrame:
    g = graph(s, d, "turns")
    return udfs.neighbours(g.edges, g.vertices, 3)


@query("sql_surface", o.with_([*before_ctes("geo", PASSES)], f"SELECT vid, {o.pico()} AS rank_pico FROM before WHERE vid >= 0"))
def sql_surface(s: SparkSession, d: str) -> DataFrame:
    sqlapi.register(s, {"geo": graph(s, d, "geo")})
    sqlapi.call(s, "cold_sync", "graph_geo_edges", version=7, fixed_passes=PASSES)
    return s.sql("SELECT vid, CAST(round(rank * 1e12) AS BIGINT) AS rank_pico FROM ranks_cold_sync_t7 WHERE vid >= :first", args={"first": 0})


# ---- streaming --------------------------------------------------------------


def _drain(s: SparkSession, stream: DataFrame, mode: str = "append") -> DataFrame:
    return maintain.drained(stream, mode)


@query("stream_handoff_edges", f"SELECT src, dst, count(*) AS n FROM ({o.ROWS['handoff'][0]}) GROUP BY 1, 2")
def stream_handoff_edges(s: SparkSession, d: str) -> DataFrame:
    return _drain(s, maintain.handoffs(maintain.event_stream(s, d))).groupBy("src", "dst").agg(F.count("*").alias("n"))


@query("stream_tumbling", "SELECT time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01') AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_tumbling(s: SparkSession, d: str) -> DataFrame:
    return _drain(s, maintain.tumbling(maintain.event_stream(s, d), "1 day"), "complete").select(F.col("window.start").alias("start"), "event_type", "n")


@query("stream_sliding", "SELECT start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01'), time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') - INTERVAL 6 HOUR]) AS start FROM events) GROUP BY 1")
def stream_sliding(s: SparkSession, d: str) -> DataFrame:
    return _drain(s, maintain.sliding(maintain.event_stream(s, d), "12 hours", "6 hours"), "complete").select(F.col("window.start").alias("start"), "n")


@query(
    "stream_session",
    """SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM (
      SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 2 HOUR OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts) IS NULL THEN 1 ELSE 0 END AS fresh FROM events)) GROUP BY user_id, k""",
)
def stream_session(s: SparkSession, d: str) -> DataFrame:
    return _drain(s, maintain.sessions(maintain.event_stream(s, d), "2 hours"), "complete").select("user_id", F.col("session_window.start").alias("start"), "n")


@query("stream_dedup", "SELECT event_type, count(DISTINCT event_id) AS n FROM events GROUP BY 1")
def stream_dedup(s: SparkSession, d: str) -> DataFrame:
    stream = maintain.event_stream(s, d)
    return _drain(s, maintain.once(stream.unionAll(stream)).select("event_type")).groupBy("event_type").agg(F.count("*").alias("n"))


@query("stream_interval_join", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 30 MINUTE")
def stream_interval_join(s: SparkSession, d: str) -> DataFrame:
    def side(kind: str, tag: str) -> DataFrame:
        return maintain.event_stream(s, d).where(F.col("event_type") == kind).withWatermark("ts", "1 hour").select(F.col("event_id").alias(tag), F.col("ts").alias(f"ts_{tag}"), F.col("user_id").alias(f"user_{tag}"))

    a, b = side("click", "a"), side("purchase", "b")
    joined = a.join(b, F.expr("user_a = user_b AND ts_b > ts_a AND ts_b <= ts_a + INTERVAL 30 MINUTES"))
    return _drain(s, joined).select("a", "b")


@query("stream_static_join", o.with_(before_ctes("handoff"), f"SELECT event_id, {o.pico()} AS rank_pico FROM events JOIN before ON vid = user_id"))
def stream_static_join(s: SparkSession, d: str) -> DataFrame:
    joined = maintain.with_ranks(maintain.event_stream(s, d), before(s, d, "handoff"))
    return _drain(s, joined.select("event_id", rel.pico().alias("rank_pico")))


@query("stream_update_mode", "SELECT event_type, count(*) AS n, CAST(max(user_id) AS BIGINT) AS top FROM events GROUP BY 1")
def stream_update_mode(s: SparkSession, d: str) -> DataFrame:
    """Counts in update mode, the last row of each key."""
    rows = maintain.event_stream(s, d).groupBy("event_type").agg(F.count("*").alias("n"), F.max("user_id").alias("top"))
    return _drain(s, rows, "update").groupBy("event_type").agg(F.max("n").alias("n"), F.max("top").alias("top"))


@query(
    "stream_link_expiry",
    """WITH t AS (SELECT ts, src, dst FROM (SELECT ts, user_id AS src, lead(user_id) OVER (PARTITION BY event_type ORDER BY ts, event_id) AS dst FROM events) WHERE dst IS NOT NULL
    ), g AS (SELECT *, coalesce(ts - lag(ts) OVER (PARTITION BY src, dst ORDER BY ts) >= INTERVAL 2 DAY, false) AS gap FROM t
    ), k AS (SELECT *, count(*) FILTER (gap) OVER (PARTITION BY src, dst ORDER BY ts ROWS UNBOUNDED PRECEDING) AS part FROM g
    ), p AS (SELECT src, dst, part, count(*) AS n, max(ts) AS last FROM k GROUP BY 1, 2, 3
    ), e AS (SELECT *, part < max(part) OVER (PARTITION BY src, dst) OR last + INTERVAL 2 DAY < (SELECT max(ts) FROM t) - INTERVAL 1 HOUR AS expired FROM p)
    SELECT src, dst, CAST(sum(n) AS BIGINT) AS n, count(*) AS expired FROM e WHERE expired GROUP BY 1, 2""",
)
def stream_link_expiry(s: SparkSession, d: str) -> DataFrame:
    """How often each link expired, unused for two days of event time, and its uses."""
    events = catalog.table(s, d, "events")
    nxt = F.lead("user_id").over(W.partitionBy("event_type").orderBy("ts", "event_id"))
    folder = fresh_path(s, "handoffs")
    events.select("ts", F.col("user_id").alias("src"), nxt.alias("dst")).where("dst is not null").write.parquet(folder)
    stream = s.readStream.schema("ts timestamp, src long, dst long").parquet(folder).withWatermark("ts", "1 hour")
    told = _drain(s, maintain.active_links(stream, "2 days"))
    return told.where("expired").groupBy("src", "dst").agg(F.sum("n").alias("n"), F.count("*").alias("expired"))


@query("stream_rank_maintain")
def stream_rank_maintain(s: SparkSession, d: str) -> DataFrame:
    """Ranks maintained over micro-batches against a run on the last snapshot."""
    temporal = catalog.handoff(s, d)
    start = temporal.prefix(0.9)
    store = VersionStore(s, fresh_path(s, "ranks"), 2)
    keeper = maintain.Maintainer(store, start)
    at, size = int(temporal.total * 0.9), max(1, temporal.total // 20)
    for i in range(2):
        keeper.on_batch(temporal.slice(at + i * size, size), i)
        keeper.on_batch(temporal.slice(at + i * size, size), i)  # a repeat changes nothing
    last = store.graph(store.latest("edges"))
    near = measures.norms(store.ranks(store.latest("ranks")), methods.cold_sync(last, Params(plan=whole_plan(last))).ranks)
    return near.select(F.lit(store.latest("ranks")).alias("version"), (F.col("linf") < 1e-9).alias("within_1e_9"))


# ---- the form for large clusters, and extensions ------------------------------


@query("local_async_web")
def local_async_web(s: SparkSession, d: str) -> DataFrame:
    """Block-owning tasks reach the reference ranks."""
    from ..operators import local

    g = graph(s, d, "web")
    run = local.local_async(g, methods.uniform(g).withColumn("affected", F.lit(True)), Params(blocks=4))
    near = measures.norms(run.ranks, truth(s, d, after=False))
    return near.select(F.lit(run.converged).alias("converged"), (F.col("linf") < 1e-9).alias("within_1e_9"))


_WEIGHTED = "SELECT o_custkey * 2 AS src, l_suppkey * 2 + 1 AS dst, sum(l_quantity) AS weight FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2"


@query(
    "general_ranks_trade",
    o.with_(
        [f"e AS MATERIALIZED ({_WEIGHTED})", "l AS MATERIALIZED (SELECT src, dst, weight / sum(weight) OVER (PARTITION BY src) AS w FROM e)", f"v AS MATERIALIZED ({o._PARTIES})", "n AS MATERIALIZED (SELECT CAST(count(*) AS DOUBLE) AS n FROM v)",
         """r(p, vid, rank) AS (SELECT 0, vid, 1 / n FROM v, n UNION ALL
           SELECT p + 1, vid, 1 / n * (1 - 0.85 + 0.85 * (1 - sum(mass) OVER ())) + 0.85 * mass FROM (
             SELECT max(p) AS p, vid, coalesce(sum(mass), 0) AS mass FROM (
               SELECT p, dst AS vid, rank * w AS mass FROM r JOIN l ON l.src = r.vid WHERE p < 10 UNION ALL SELECT p, vid, 0 FROM r WHERE p < 10) GROUP BY vid), n)"""],
        f"SELECT vid, {o.pico()} AS rank_pico FROM r WHERE p = 10",
    ),
)
def general_ranks_trade(s: SparkSession, d: str) -> DataFrame:
    """Weighted edges, and suppliers without links out."""
    from ..operators import extensions

    lines, orders = catalog.table(s, d, "lineitem"), catalog.table(s, d, "orders")
    edges = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).groupBy((F.col("o_custkey") * 2).alias("src"), (F.col("l_suppkey") * 2 + 1).alias("dst")).agg(F.sum("l_quantity").alias("weight"))
    return _pico(extensions.general_ranks(edges, catalog._parties(s, d), passes=10))


@query("rescale_vertices", o.with_([*before_ctes("web"), "k AS (SELECT vid, rank FROM before WHERE vid % 5 <> 0), c AS (SELECT count(*) AS old FROM before), m AS (SELECT count(*) + 2 AS new FROM k), z AS (SELECT vid, rank * (old / new) AS rank FROM k, c, m UNION ALL SELECT x, 1.0 / new FROM (VALUES (-1), (-2)) t(x), m)"], f"SELECT vid, {o.pico('rank / sum(rank) OVER ()')} AS rank_pico FROM z"))
def rescale_vertices(s: SparkSession, d: str) -> DataFrame:
    from ..operators import extensions

    ranks = before(s, d, "web")
    return _pico(extensions.rescale_for_vertices(ranks, s.createDataFrame([(-1,), (-2,)], "vid long"), ranks.where("vid % 5 = 0")))


@query("salted_pull_trade", o.with_(before_ctes("trade"), f"SELECT dst AS vid, {o.pico('sum(rank * w)')} AS mass_pico FROM before JOIN g_l ON src = vid GROUP BY dst"))
def salted_pull_trade(s: SparkSession, d: str) -> DataFrame:
    from ..operators import extensions

    return extensions.salted_pull(graph(s, d, "trade").links(), before(s, d, "trade"), 100, 4).select("vid", rel.pico("mass").alias("mass_pico"))


@query("monte_carlo_web")
def monte_carlo_web(s: SparkSession, d: str) -> DataFrame:
    """How near sampled walks come."""
    from ..operators import extensions

    near = measures.norms(extensions.monte_carlo_ranks(graph(s, d, "web"), 16, most_hops=25), truth(s, d, after=False))
    return near.select((F.col("l1") < 0.5).alias("near"))


for _n in ("batch_diff", "batch_invert", "batch_random_ins", "batch_random_mixed", "block_assign_by_edges", "edges_except", "edges_intersect", "edges_union", "mark_expand_example14", "mark_initial_example14", "rank_range_join", "rank_topk"):
    from_tables(_n)
