"""Functions that SQL users register: an aggregate, a vector function and two
table functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.DoubleType())
def geomean_udf(x: pd.Series) -> float:
    """Geometric mean as a grouped aggregate."""
    return float(np.exp(np.log(x).mean())) if len(x) else float("nan")


def cosine(a: str | Column, b: str | Column) -> Column:
    """Cosine of two arrays, in doubles, without leaving the JVM."""

    def dot(x: str | Column, y: str | Column) -> Column:
        return F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)

    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


@F.udtf(returnType=T.StructType([T.StructField("hop", T.IntegerType()), T.StructField("vid", T.LongType())]))
class Ring:
    """Vertices of a ring of ``size`` at most ``hops`` steps after one: a table
    function for examples and tests of lateral joins."""

    def eval(self, vid: int, hops: int, size: int) -> Iterator[tuple[int, int]]:
        for h in range(1, hops + 1):
            yield h, (vid + h) % size


def neighbours(edges: DataFrame, start: DataFrame, hops: int) -> DataFrame:
    """(vid, hop, other): vertices within ``hops`` links of each start, at their
    least distance. One join a hop, of the vertices found in the hop before."""
    found = start.select("vid", F.lit(0).alias("hop"), F.col("vid").alias("other"))
    last = found
    for h in range(1, hops + 1):
        step = last.join(edges, last["other"] == edges["src"]).select("vid", F.lit(h).alias("hop"), F.col("dst").alias("other")).distinct()
        last = step.join(found.select("vid", "other"), ["vid", "other"], "left_anti").select("vid", "hop", "other")
        found = found.unionAll(last)
    return found.where("hop > 0")


def register(spark: SparkSession) -> None:
    spark.udf.register("geomean", geomean_udf)
    spark.udtf.register("ring", Ring)
