"""Accuracy and cost measures of rank runs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..params import RankRun


def compared(a: DataFrame, b: DataFrame) -> DataFrame:
    """(vid, x, y): two rank versions side by side, 0 where a vertex is missing."""
    return a.select("vid", F.col("rank").alias("x")).join(b.select("vid", F.col("rank").alias("y")), "vid", "full").na.fill(0.0, ["x", "y"])


def norms(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: linf, l1 and l2 of the difference."""
    d = F.abs(F.col("x") - F.col("y"))
    return compared(a, b).agg(F.coalesce(F.max(d), F.lit(0.0)).alias("linf"), F.coalesce(F.sum(d), F.lit(0.0)).alias("l1"), F.coalesce(F.sqrt(F.sum(d * d)), F.lit(0.0)).alias("l2"))


def linf(a: DataFrame, b: DataFrame) -> float:
    return norms(a, b).first()["linf"]


def error(run: RankRun | DataFrame, truth: DataFrame) -> float:
    """Largest difference from the reference ranks of the same snapshot."""
    return linf(run.ranks if isinstance(run, RankRun) else run, truth)


def mass(ranks: DataFrame) -> float:
    """Sum of all ranks: 1 where no vertex is without a link out."""
    return ranks.agg(F.coalesce(F.sum("rank"), F.lit(0.0))).first()[0]


def geomean(column: str | Column) -> Column:
    return F.exp(F.avg(F.log(column)))


def speedups(times: DataFrame, base: str) -> DataFrame:
    """(method, fraction, geomean, speedup) of rows (graph, method, fraction,
    seconds): the ratio of geometric means over graphs to those of ``base``."""
    means = times.groupBy("method", "fraction").agg(geomean("seconds").alias("geomean"))
    own = means.where(F.col("method") == base).select("fraction", F.col("geomean").alias("base"))
    return means.join(own, "fraction").select("method", "fraction", "geomean", (F.col("base") / F.col("geomean")).alias("speedup"))


def mark_quality(affected: DataFrame, before: DataFrame, after: DataFrame, tol: float) -> DataFrame:
    """One row: marked, moved (reference rank differs by more than tol), both,
    precision and recall of the marks."""
    moved = compared(before, after).where(F.abs(F.col("x") - F.col("y")) > tol).select("vid", F.lit(1).alias("m"))
    rows = affected.select("vid", F.lit(1).alias("a")).join(moved, "vid", "full")
    got = rows.agg(F.count("a").alias("marked"), F.count("m").alias("moved"), F.count(F.when(F.col("a").isNotNull() & F.col("m").isNotNull(), 1)).alias("both"))
    return got.withColumn("precision", F.col("both") / F.greatest("marked", F.lit(1))).withColumn("recall", F.when(F.col("moved") == 0, F.lit(1.0)).otherwise(F.col("both") / F.col("moved")))


def topk_overlap(a: DataFrame, b: DataFrame, k: int) -> DataFrame:
    """One row: how many of the k most important vertices two versions share."""

    def top(x: DataFrame) -> DataFrame:
        return x.orderBy(F.desc(F.round("rank", 12)), "vid").limit(k).select("vid")

    return top(a).join(top(b), "vid").agg(F.count("*").alias("shared")).select(F.lit(k).alias("k"), "shared")


def stage_totals(spark: SparkSession, after: int = -1) -> dict[str, int]:
    """Tasks and bytes shuffled and spilled of the stages numbered above ``after``, and
    the last number. The session's status store keeps so many stages (a thousand by
    default); of a run with more only those count."""
    jvm, store = spark.sparkContext._jvm, spark.sparkContext._jsc.sc().statusStore()
    none = spark.sparkContext._gateway.new_array(jvm.double, 0)
    stages = store.stageList(None, False, False, none, jvm.java.util.ArrayList())
    out = {"last_stage": after, "tasks": 0, "shuffle_bytes": 0, "spilled_bytes": 0}
    for i in range(stages.size()):
        stage = stages.apply(i)
        if stage.stageId() > after:
            out["last_stage"] = max(out["last_stage"], stage.stageId())
            out["tasks"] += stage.numCompleteTasks()
            out["shuffle_bytes"] += stage.shuffleWriteBytes()
            out["spilled_bytes"] += stage.diskBytesSpilled()
    return out
