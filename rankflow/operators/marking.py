"""Which vertices a batch affects: at first, by reach, and by helping rounds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import cut
from .components import components
from .graph import Graph


def sources(batch: DataFrame) -> DataFrame:
    """Sources of the changes, once each."""
    return batch.select("src").distinct()


def initial(prev: Graph, cur: Graph, batch: DataFrame) -> DataFrame:
    """(vid): out-neighbours of each source of a change, in either snapshot."""
    heads = sources(batch)
    return prev.edges.join(heads, "src", "left_semi").select("dst").unionAll(cur.edges.join(heads, "src", "left_semi").select("dst")).select(F.col("dst").alias("vid")).distinct()


def initial_with_help(prev: Graph, cur: Graph, batch: DataFrame, lost: list[set[int]] | None = None, chunks: int = 16) -> tuple[DataFrame, DataFrame]:
    """(marks, ledger) when workers may lose chunks of the sources: each round
    takes the sources that the ledger does not show as done; marks are a set, so
    doing one again changes nothing. ``lost`` names the chunks lost in each
    round; ledger is (src, attempts)."""
    heads = cut(sources(batch).withColumn("chunk", F.pmod("src", F.lit(chunks))))
    marks, ledger, turn = None, None, 0
    lost = lost or []
    while True:
        left = heads if ledger is None else heads.join(ledger.select("src"), "src", "left_anti")
        gone = sorted(lost[turn]) if turn < len(lost) else []
        done = left.where(~F.col("chunk").isin(gone)) if gone else left
        some = initial(prev, cur, done.select("src"))
        marks = some if marks is None else marks.unionAll(some).distinct()
        turn += 1
        now = done.select("src", F.lit(turn).alias("attempts"))
        ledger = now if ledger is None else ledger.unionAll(now)
        if not gone:
            return marks, ledger


def expand(state: DataFrame, links: DataFrame, frontier_tol: float) -> DataFrame:
    """(vid): out-neighbours of vertices whose last change exceeds the tolerance."""
    moved = state.where(F.abs(F.col("rank") - F.col("prev_rank")) > frontier_tol).select(F.col("vid").alias("src"))
    return links.join(moved, "src", "left_semi").select(F.col("dst").alias("vid")).distinct()


def reach(prev: Graph, cur: Graph, batch: DataFrame, max_depth: int | None = None) -> DataFrame:
    """(vid): all that the initial marks reach in the new snapshot, or, with
    ``max_depth``, (vid, depth) of what lies within so many links."""
    return reach_from(cur, initial(prev, cur, batch), max_depth)


def reach_from(cur: Graph, marks: DataFrame, max_depth: int | None = None) -> DataFrame:
    """The same from any marks. Vertices that link to each other both ways reach the
    same, so their components are contracted first, in rounds that grow with the
    logarithm of a path; only one-way links are then followed hop by hop, several
    hops a job."""
    if max_depth is not None:
        return _within(cur, marks, max_depth)
    links = cur.edges.where("src <> dst")
    both = links.where("src < dst").join(links.select(F.col("dst").alias("src"), F.col("src").alias("dst")), ["src", "dst"], "left_semi")
    home = cut(components(both))

    def contracted(rows: DataFrame, end: str) -> DataFrame:
        return rows.join(home.select(F.col("vid").alias(end), "component"), end, "left").withColumn(end, F.coalesce("component", end)).drop("component")

    one_way = cut(contracted(contracted(links, "src"), "dst").where("src <> dst").distinct())
    heads = contracted(marks.select("vid"), "vid").distinct()
    found = _closed(one_way, heads)
    # every vertex of a reached component, and reached vertices without one
    inside = home.join(found.withColumnRenamed("vid", "component"), "component", "left_semi").select("vid")
    return inside.unionAll(found).distinct()


def _closed(links: DataFrame, heads: DataFrame, hops: int = 8) -> DataFrame:
    """(vid): ``heads`` and all that they reach, ``hops`` hops a job. A round goes on
    only from what the round before found."""
    ends = links.select(F.explode(F.array("src", "dst")).alias("src")).distinct()
    looped = cut(links.select("src", "dst").unionAll(ends.select("src", F.col("src").alias("dst"))))  # keeps what was reached
    seen = last = cut(heads)
    while True:
        found = last
        for _ in range(hops):
            found = looped.join(found.withColumnRenamed("vid", "src"), "src", "left_semi").select(F.col("dst").alias("vid")).distinct()
        last = cut(found.join(seen, "vid", "left_anti"))
        if last.isEmpty():
            return seen
        seen = cut(seen.unionAll(last))


def _within(cur: Graph, marks: DataFrame, hops: int) -> DataFrame:
    """(vid, depth) of all within ``hops`` links of the marks."""
    links = cur.edges if cur.self_loops else cur.edges.unionAll(cur.vertices.select(F.col("vid").alias("src"), F.col("vid").alias("dst")))
    near = marks.select("vid", F.lit(0).alias("depth"))
    for hop in range(hops):
        far = F.col("depth") + (F.col("src") != F.col("dst")).cast("int")
        near = links.join(near, links["src"] == near["vid"]).groupBy(F.col("dst").alias("vid")).agg(F.min(far).alias("depth"))
        if hop % 8 == 7:
            near = cut(near)
    return near
