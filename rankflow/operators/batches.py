"""Batches of edge changes (src, dst, op): '-' deletes, '+' inserts."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .graph import Graph, ordered

EMPTY = "src long, dst long, op string"


def empty(graph: Graph) -> DataFrame:
    return graph.edges.sparkSession.createDataFrame([], EMPTY)


def size_of(graph: Graph, fraction: float, n_links: int | None = None) -> int:
    """Edges of each kind in a batch of ``fraction`` of all edges (``n_links``, else
    counted), loops included: half are deletions and half insertions, one of each at least."""
    return max(1, int((graph.edges.count() if n_links is None else n_links) * fraction / 2))


def _mark(*parts: Column | str) -> Column:
    return F.md5(F.concat_ws("-", *[F.lit(p) if isinstance(p, str) else p.cast("string") for p in parts]))


#: Rows of an order that one task ranks; more are placed by ranges, the same rows.
RANKED_AT_ONCE = 250_000


def _firsts(rows: DataFrame, order: list[str], k: int, of: Callable[[], int] | None = None) -> DataFrame:
    """The first k rows in ``order``, with their 0-based places (seq). of: about how many
    rows there are where the order starts with a hash: then only those with low hashes
    are sorted, unless they turn out to be fewer than k."""
    if k <= RANKED_AT_ONCE:
        return rows.orderBy(*order).limit(k).withColumn("seq", F.row_number().over(W.orderBy(*order)) - 1)
    if of and (share := (k + 6 * k**0.5) / max(1, of())) < 1:
        low = ordered(rows.where(F.col(order[0]) < f"{int(share * 16**8):08x}"), order)
        if low.count() >= k:
            return low.where(F.col("seq") < k)
    return ordered(rows, order).where(F.col("seq") < k)


def _gone(graph: Graph, k: int, seed: int) -> DataFrame:
    some = graph.edges.where("src <> dst").withColumn("h", _mark("d", F.col("src"), F.col("dst"), str(seed)))
    return _firsts(some, ["h", "src", "dst"], k, lambda: some.count()).select("src", "dst", F.lit("-").alias("op"), "seq", F.lit(-1).cast("long").alias("i"))


def _come(graph: Graph, k: int, seed: int) -> DataFrame:
    def firsts(side: str) -> DataFrame:
        hashed = graph.vertices.withColumn("h", _mark(side, F.col("vid"), str(seed)))
        return _firsts(hashed, ["h", "vid"], 4 * k, lambda: graph.n).select(F.col("seq").cast("long").alias("i"), F.col("vid").alias(side))

    pairs = firsts("src").join(firsts("dst"), "i").where("src <> dst")
    free = pairs.join(graph.edges, ["src", "dst"], "left_anti")
    return _firsts(free, ["i"], k).select("src", "dst", F.lit("+").alias("op"), "seq", "i")


def deletions(graph: Graph, k: int, seed: int) -> DataFrame:
    """k edges that are no loops, first in the order of a hash (a top-k, not a
    sort of all edges)."""
    return _gone(graph, k, seed).select("src", "dst", "op")


def insertions(graph: Graph, k: int, seed: int) -> DataFrame:
    """Up to k pairs without an edge: the vertices first by one hash meet those
    first by another, place by place. Only 4 k vertices are ever ranked."""
    return _come(graph, k, seed).select("src", "dst", "op")


#: Changes of each kind in a random batch, as multiples of its size.
MIXES = {"both": (1, 1), "del": (2, 0), "ins": (0, 2)}


def nested(graph: Graph, k: int, seed: int, mix: str = "both") -> DataFrame:
    """The random batch of size k, with the place (seq) of each change among those of
    its kind and, of an insertion, of its vertices in their orders (i): the batch of any
    smaller size is ``nested_rows`` of it."""
    kinds = [make(graph, k * times, seed) for make, times in zip((_gone, _come), MIXES[mix]) if times]
    return kinds[0] if len(kinds) == 1 else kinds[0].unionAll(kinds[1])


def nested_rows(rows, k: int, mix: str = "both"):
    """Which rows (a table of arrays) of a ``nested`` batch are those of size k."""
    most = (rows["op"] == "-") * (MIXES[mix][0] * k) + (rows["op"] == "+") * (MIXES[mix][1] * k)
    return (rows["seq"] < most) & (rows["i"] < 4 * most)


def random(graph: Graph, fraction: float, seed: int = 1, mix: str = "both") -> DataFrame:
    """A random batch of exactly the size of ``fraction``, whatever that is. mix:
    'both', 'del' or 'ins'."""
    return nested(graph, size_of(graph, fraction), seed, mix).select("src", "dst", "op")


def bernoulli(graph: Graph, fraction: float, seed: int = 1, mix: str = "both") -> DataFrame:
    """A batch of the size of ``fraction`` in expectation only, without a task that ranks
    anything: each edge is drawn by its hash and goes; another draw of as many gives
    as many pairs of vertices, each end uniform by the hash of the drawn edge and the
    vertices' places in an order. Pairs that are there already, or equal, fall out."""
    ends = {"both": (0.5, 0.5), "del": (1.0, 0.0), "ins": (0.0, 1.0)}[mix]

    def drawn(salt: int, share: float) -> DataFrame:
        unit = F.pmod(F.xxhash64("src", "dst", F.lit(seed + salt)), F.lit(1 << 30)) / F.lit(float(1 << 30))
        return graph.edges.where(unit < fraction * share)

    out = None
    if ends[0]:
        out = drawn(0, ends[0]).where("src <> dst").withColumn("op", F.lit("-"))
    if ends[1]:
        placed = ordered(graph.vertices, ["vid"]).select(F.col("seq").alias("place"), "vid")

        def place(salt: int) -> Column:
            return F.pmod(F.xxhash64("src", "dst", F.lit(seed + salt)), F.lit(max(1, graph.n)))

        pairs = drawn(1, ends[1]).select(place(2).alias("i"), place(3).alias("j"))
        first = pairs.join(placed.select(F.col("place").alias("i"), F.col("vid").alias("src")), "i")
        both = first.join(placed.select(F.col("place").alias("j"), F.col("vid").alias("dst")), "j").select("src", "dst").where("src <> dst").distinct()
        come = both.join(graph.edges, ["src", "dst"], "left_anti").withColumn("op", F.lit("+"))
        out = come if out is None else out.unionAll(come)
    return out


def normalised(graph: Graph, batch: DataFrame) -> DataFrame:
    """Only changes that have an effect, once each: deletions of edges there are,
    insertions of edges there are not; of an edge in both, the insertion wins."""
    rows = batch.where("src <> dst").select("src", "dst", "op").distinct()
    come = rows.where("op = '+'")
    new = come.join(graph.edges, ["src", "dst"], "left_anti")
    gone = rows.where("op = '-'").join(come.select("src", "dst"), ["src", "dst"], "left_anti").join(graph.edges, ["src", "dst"], "left_semi")
    return gone.select("src", "dst", "op").unionAll(new.select("src", "dst", "op"))


def diff(before: Graph, after: Graph) -> DataFrame:
    """The batch that leads from one snapshot to the next."""
    gone = before.edges.join(after.edges, ["src", "dst"], "left_anti").withColumn("op", F.lit("-"))
    come = after.edges.join(before.edges, ["src", "dst"], "left_anti").withColumn("op", F.lit("+"))
    return gone.unionAll(come)


def invert(batch: DataFrame) -> DataFrame:
    return batch.select("src", "dst", F.when(F.col("op") == "+", "-").otherwise("+").alias("op"))
