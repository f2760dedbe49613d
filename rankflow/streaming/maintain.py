"""Ranks kept current on a stream of edge changes: a micro-batch is a batch."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators import batches, methods
from ..operators.graph import Graph
from ..params import Params
from ..sources.stores import VersionStore
from ..storage import fresh_path

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, sf_dir: str, per_trigger: int | None = None) -> DataFrame:
    """The events, of one file or a folder of files, all of them in one micro-batch; or
    ``per_trigger`` files at once, if they come in time order."""
    stream = spark.readStream.schema(EVENTS)
    if per_trigger is not None:
        stream = stream.option("maxFilesPerTrigger", per_trigger)
    return stream.parquet(f"{sf_dir}/events*.parquet")  # a pattern: a plain path must be a folder's


class Maintainer:
    """Applies micro-batches of changes (src, dst, op) in order, each once: the
    version of the ranks is the number of the micro-batch, and a version that the
    store already has is skipped."""

    def __init__(self, store: VersionStore, start: Graph, method: str = "frontier_sync", params: Params = Params()):
        self.store, self.method, self.params = store, method, params
        if store.latest("ranks") is None:
            store.put_graph(0, start)
            store.put_ranks(0, methods.cold_sync(start, params).ranks)

    def on_batch(self, changes: DataFrame, batch_id: int) -> None:
        version = batch_id + 1
        at = self.store.latest("ranks")
        if version <= at:
            return
        prev = self.store.graph(at)
        batch = batches.normalised(prev, changes.select("src", "dst", "op")).persist()
        cur = prev.apply(batch)
        run = methods.run(self.method, prev, cur, batch, self.store.ranks(at), self.params)
        self.store.put_graph(version, cur)
        self.store.put_ranks(version, run.ranks)  # last: a version is there when its ranks are
        cur.release()
        batch.unpersist()


def handoffs(events: DataFrame) -> DataFrame:
    """(event_type, src, dst, event_id) of successive users of each type, in the
    order that events arrive (files in time order). State: the last user."""
    schema = "event_type string, src long, dst long, event_id long"

    def pair(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        before = state.get[0] if state.exists else None
        users = rows["user_id"].tolist()
        src = [before, *users[:-1]]
        state.update((users[-1],))
        out = pd.DataFrame({"event_type": key[0], "src": src, "dst": users, "event_id": rows["event_id"].tolist()})
        yield out[out["src"].notna()].astype({"src": "int64"})

    return events.groupBy("event_type").applyInPandasWithState(pair, schema, "last long", "append", GroupStateTimeout.NoTimeout)


def active_links(events: DataFrame, idle: str) -> DataFrame:
    """(src, dst, n, expired) of successive users of each type, where a link without
    use for ``idle`` of event time expires: its row is told once more, with expired,
    and its count starts anew. State: count and last use of each link."""
    schema = "src long, dst long, n long, expired boolean"
    wait = int(pd.Timedelta(idle).total_seconds() * 1000)

    def follow(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        def row(n: int, expired: bool) -> pd.DataFrame:
            return pd.DataFrame({"src": [key[0]], "dst": [key[1]], "n": [n], "expired": [expired]})

        if state.hasTimedOut:
            n, _ = state.get
            state.remove()
            yield row(n, True)
            return
        n, last = state.get if state.exists else (0, None)
        for t in sorted(int(x.timestamp() * 1000) for f in frames for x in f["ts"]):
            if last is not None and t - last >= wait:
                yield row(n, True)
                n = 0
            n, last = n + 1, t if last is None else max(last, t)
        state.update((n, last))
        state.setTimeoutTimestamp(max(last + wait, state.getCurrentWatermarkMs() + 1))
        yield row(n, False)

    return events.groupBy("src", "dst").applyInPandasWithState(follow, schema, "n long, last long", "append", GroupStateTimeout.EventTimeTimeout)


def with_ranks(events: DataFrame, ranks: DataFrame) -> DataFrame:
    """Events with their users' ranks: a stream against a table."""
    return events.join(ranks.select(F.col("vid").alias("user_id"), "rank"), "user_id")


def on_time(changes: DataFrame, delay: str) -> DataFrame:
    """Changes (src, dst, op, ts) that count: insertions always; deletions only if they
    come within ``delay`` of the latest change seen before their micro-batch, as a later
    one may follow an insertion that it must not undo."""
    gone = changes.where("op = '-'").select("src", "dst", "op", "ts").withWatermark("ts", delay).dropDuplicatesWithinWatermark(["src", "dst", "op", "ts"])
    return changes.where("op = '+'").select("src", "dst", "op", "ts").unionByName(gone)


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """All that a stream has now, run to its end into files of the shared folder; no row
    comes to the driver. Of mode 'complete' the last micro-batch's rows, of the others
    those of all."""
    spark = stream.sparkSession
    folder = fresh_path(spark, "drained")
    writer = stream.writeStream.option("checkpointLocation", fresh_path(spark, "progress")).outputMode(mode).trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").option("path", folder).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(folder)
    done: list[str] = []

    def keep(rows: DataFrame, number: int) -> None:
        place = f"{folder}/{number}"
        rows.write.mode("overwrite").parquet(place)  # a repeat changes nothing
        if place not in done:
            done.append(place)

    writer.foreachBatch(keep).start().awaitTermination()
    read = spark.read.schema(stream.schema)
    if not done:
        return spark.createDataFrame([], stream.schema)
    return read.parquet(done[-1]) if mode == "complete" else read.parquet(*done)


def tumbling(events: DataFrame, width: str) -> DataFrame:
    return events.withWatermark("ts", "1 hour").groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n"))


def sliding(events: DataFrame, width: str, slide: str) -> DataFrame:
    return events.withWatermark("ts", "1 hour").groupBy(F.window("ts", width, slide)).agg(F.count("*").alias("n"), F.approx_count_distinct("user_id", 0.01).alias("users"))


def sessions(events: DataFrame, gap: str) -> DataFrame:
    return events.withWatermark("ts", "1 hour").groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))


def once(events: DataFrame) -> DataFrame:
    return events.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"])
