"""What users ask of ranks and edges: tops, movers, roll-ups, versions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def pico(rank: str | Column = "rank") -> Column:
    """Ranks as whole numbers of 1e-12, for comparison across engines."""
    return F.round((F.col(rank) if isinstance(rank, str) else rank) * 1e12).cast("long")


def named(ranks: DataFrame, customer: DataFrame, supplier: DataFrame) -> DataFrame:
    """Ranks of customers (even ids) and suppliers (odd ids) with what is known of
    them: vid, rank, kind, name, nationkey, segment."""
    c = customer.select((F.col("c_custkey") * 2).alias("vid"), F.lit("customer").alias("kind"), F.col("c_name").alias("name"), F.col("c_nationkey").alias("nationkey"), F.col("c_mktsegment").alias("segment"))
    s = supplier.select((F.col("s_suppkey") * 2 + 1).alias("vid"), F.lit("supplier").alias("kind"), F.col("s_name").alias("name"), F.col("s_nationkey").alias("nationkey"), F.lit(None).cast("string").alias("segment"))
    return ranks.select("vid", "rank").join(c.unionAll(s), "vid")


def topk(ranks: DataFrame, k: int) -> DataFrame:
    return ranks.select("vid", pico().alias("rank_pico")).orderBy(F.desc("rank_pico"), "vid").limit(k)


def topk_by(ranks: DataFrame, by: str, k: int) -> DataFrame:
    """The k first of each group; a rank-limit window keeps k rows a task and
    group before the shuffle."""
    w = W.partitionBy(by).orderBy(F.desc("rank_pico"), "vid")
    return ranks.withColumn("rank_pico", pico()).withColumn("place", F.row_number().over(w)).where(F.col("place") <= k).select(by, "place", "vid", "rank_pico")


def movers(before: DataFrame, after: DataFrame, k: int) -> DataFrame:
    """The k largest changes between two versions."""
    both = before.select("vid", pico().alias("x")).join(after.select("vid", pico().alias("y")), "vid", "full").na.fill(0)
    return both.select("vid", F.col("x").alias("before_pico"), F.col("y").alias("after_pico"), (F.col("y") - F.col("x")).alias("change_pico")).orderBy(F.desc(F.abs("change_pico")), "vid").limit(k)


def as_of(rows: DataFrame, versions: DataFrame, ts: str, by: list[str], value: str) -> DataFrame:
    """``rows`` with the last ``value`` of ``versions`` at or before their time:
    union, then the last value in time order of each key."""
    cols = [*by, ts]
    left = rows.select("*", F.lit(None).cast(dict(versions.dtypes)[value]).alias(value), F.lit(1).alias("_side"))
    right = versions.select(*cols, value)
    for c in rows.columns:
        if c not in cols:
            right = right.withColumn(c, F.lit(None).cast(dict(rows.dtypes)[c]))
    right = right.withColumn("_side", F.lit(0)).select(*left.columns)
    w = W.partitionBy(*by).orderBy(ts, "_side").rowsBetween(W.unboundedPreceding, W.currentRow)
    return left.unionAll(right).withColumn(value, F.last(value, ignorenulls=True).over(w)).where("_side = 1").drop("_side")


def range_join(points: DataFrame, spans: DataFrame, at: str, lo: str, hi: str, width: int) -> DataFrame:
    """Points inside [lo, hi): both sides fall into buckets ``width`` wide and join
    on the bucket, so no pair outside one is ever compared."""
    p = points.withColumn("_b", F.floor(F.col(at) / width))
    s = spans.withColumn("_b", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor((F.col(hi) - 1) / width))))
    return p.join(s, "_b").where((F.col(at) >= F.col(lo)) & (F.col(at) < F.col(hi))).drop("_b")


def below(points: DataFrame, marks: DataFrame, at: str, width: int = 1 << 20) -> DataFrame:
    """``marks`` with n, how many ``points`` lie strictly below each: an inequality
    join as running counts, by ranges of ``width`` and inside each, so that neither
    pairs nor an order of all rows in one task come up."""
    rows = marks.withColumn("_own", F.lit(0)).unionByName(points.withColumn("_own", F.lit(1)), allowMissingColumns=True)
    rows = rows.withColumn("_range", F.floor(F.col(at) / width))
    inside = W.partitionBy("_range").orderBy(at).rangeBetween(W.unboundedPreceding, -1)
    sums = rows.groupBy("_range").agg(F.sum("_own").alias("_sum"))  # a row a range
    before = sums.select("_range", F.coalesce(F.sum("_sum").over(W.orderBy("_range").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    near = rows.withColumn("n", F.coalesce(F.sum("_own").over(inside), F.lit(0))).where("_own = 0")
    return near.join(before, "_range").withColumn("n", F.col("n") + F.col("_before")).drop("_own", "_range", "_before")
