"""Helpers that the training-data operators share.

Intermediate tables go to the shared folder that the session names in
``spark.checkpoint.dir``; a private folder is made only where it is unset.
"""

from __future__ import annotations

import atexit
import os
import shutil
import tempfile
import uuid
from urllib.parse import urlparse

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Words of the contracts: runs of anything but ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"

#: More chunk bounds than this are never gathered on the driver.
MAX_CHUNKS = 65_536


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that the driver and all executors share. Without the setting, a
    private one where the driver is the only machine; an error on a cluster."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not (spark.sparkContext.master or "").split("[")[0] == "local":
            raise RuntimeError("spark.checkpoint.dir must name a folder that all machines share")
        own = tempfile.mkdtemp(prefix="shared-")
        atexit.register(shutil.rmtree, own, True)
        found = "file://" + own
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def _drop(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    except Exception:  # the session may have ended before the interpreter does
        pass


def fresh_path(spark: SparkSession, label: str) -> str:
    """A new path in the shared folder, removed when the driver program ends."""
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    atexit.register(_drop, spark, path)
    return path


def staged(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` to the shared folder and return the written table: cuts the
    lineage, survives lost executors, and is computed once."""
    path = fresh_path(df.sparkSession, label)
    df.write.parquet(path)
    table = df.sparkSession.read.schema(df.schema).parquet(path)
    table._staged_at = path
    return table


def forget(*tables: DataFrame) -> None:
    """Removes the files of tables made by ``staged`` that nothing reads any more."""
    for df in tables:
        path = getattr(df, "_staged_at", None)
        if path:
            _drop(df.sparkSession, path)


def free_names(df: DataFrame, *wanted: str) -> list[str]:
    """Column names that ``df`` does not have, whatever their case."""
    taken = {c.lower() for c in df.columns}
    out = []
    for name in wanted:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out


def shuffle_parts(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def word_count(text: Column) -> Column:
    """Words of ``text`` as a long; null counts as empty."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def global_rank(df: DataFrame, order: list[Column], rank: str, label: str) -> DataFrame:
    """``df`` (staged) with a dense 0-based position in ``order``: one range
    shuffle, then per-partition counts (as many rows as partitions) as offsets.
    Ties get different positions, fixed once the table is written."""
    spark = df.sparkSession
    kept = staged(
        df.repartitionByRange(shuffle_parts(spark), *order)
        .sortWithinPartitions(*order)
        .withColumn("_place", F.monotonically_increasing_id()),
        label,
    )
    part = F.shiftright("_place", 33)
    sizes = sorted((r[0], r[1]) for r in kept.groupBy(part.alias("p")).count().collect())
    base, total = [], 0
    for p, n in sizes:
        base.append((int(p), total))
        total += n
    bases = spark.createDataFrame(base, "_part long, _base long")
    return (
        kept.withColumn("_part", part)
        .join(F.broadcast(bases), "_part")
        .withColumn(rank, F.col("_base") + F.col("_place").bitwiseAND(F.lit((1 << 33) - 1)))
        .drop("_part", "_base", "_place")
    )


def chunk_bounds(ids: DataFrame, key: str, rows: int) -> np.ndarray:
    """Largest key of each of about ``count/rows`` contiguous key ranges,
    ascending; at most MAX_CHUNKS of them whatever the table's size."""
    n = ids.count()
    parts = max(1, min(MAX_CHUNKS, -(-n // rows)))
    got = (
        ids.select(key)
        .repartitionByRange(parts, key)
        .groupBy(F.spark_partition_id().alias("p"))
        .agg(F.max(key).alias("top"))
        .select("top")
        .collect()
    )
    return np.array(sorted(r[0] for r in got if r[0] is not None), dtype=np.int64)


def chunk_of(key: Column, bounds: np.ndarray) -> Column:
    """The contiguous range that ``key`` falls in; null keys go to the first."""

    @F.arrow_udf("long")
    def place(keys: pa.Array) -> pa.Array:
        values = keys.fill_null(np.iinfo(np.int64).min).to_numpy(zero_copy_only=False)
        return pa.array(np.minimum(np.searchsorted(bounds, values), max(0, len(bounds) - 1)), pa.int64())

    return place(key)


def local_path(uri: str) -> str | None:
    """The path of a file: URI on a shared mount, else None."""
    parsed = urlparse(uri)
    return parsed.path if parsed.scheme in ("", "file") else None


class FileOut:
    """A file that readers see whole or not at all, also when two attempts of one
    task write it: written beside its place and moved there when closed."""

    def __init__(self, uri: str):
        path = local_path(uri)
        self.store = None
        if path is None:
            from pyarrow import fs

            self.store, path = fs.FileSystem.from_uri(uri)
        self.path, self.own = path, f"{path}.{uuid.uuid4().hex}"
        if self.store is None:
            os.makedirs(os.path.dirname(path), exist_ok=True)
        self.out = open(self.own, "wb") if self.store is None else self.store.open_output_stream(self.own)

    def write(self, data: bytes) -> None:
        self.out.write(data)

    def close(self) -> None:
        self.out.close()
        if self.store is None:
            os.replace(self.own, self.path)
        else:
            self.store.move(self.own, self.path)


def put_bytes(uri: str, data: bytes) -> None:
    out = FileOut(uri)
    out.write(data)
    out.close()


def map_file(uri: str, dtype: str) -> np.ndarray:
    """A flat file as an array: memory-mapped on a shared mount, read whole
    from other stores."""
    path = local_path(uri)
    if path is None:
        from pyarrow import fs

        store, at = fs.FileSystem.from_uri(uri)
        with store.open_input_file(at) as src:
            return np.frombuffer(src.read(), dtype=dtype)
    if os.path.getsize(path) == 0:
        return np.empty(0, dtype=dtype)
    return np.memmap(path, dtype=dtype, mode="r")


#: What empties each operator's tables in this worker process.
_tables: dict[str, list] = {}


def held_by(owner: str, empty) -> None:
    _tables.setdefault(owner, []).append(empty)


def only(owner: str) -> None:
    """Called where a task of ``owner`` begins: a worker process outlives its
    stage, so the tables of other operators go, and their memory with them."""
    others = [e for name, several in _tables.items() if name != owner for e in several]
    for empty in others:
        empty()
    pa.default_memory_pool().release_unused()


#: Longer keys of a table are never kept, so that its bytes are bounded too.
MOST_KEY = 256


class Kept(dict):
    """Results of ``make`` by key, of at most twice ``size`` keys of ``MOST_KEY``
    characters or bytes: when one generation is full, only what is asked for again
    moves to the next."""

    def __init__(self, make, size: int = 150_000):
        self.make, self.size, self.old = make, size, {}

    def empty(self) -> None:
        self.clear()
        self.old = {}

    def __missing__(self, key):
        if len(key) > MOST_KEY:
            return self.make(key)
        got = self.old.get(key, self)
        if got is self:
            got = self.make(key)
        if len(self) >= self.size:
            self.old = dict(self)
            self.clear()
        self[key] = got
        return got


def spliced(flat: np.ndarray, first: np.ndarray, size: np.ndarray, which: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The runs of ``flat`` (by their first places and sizes) that ``which`` lists,
    one after the other, and where each begins (one more than there are)."""
    n = size[which]
    ends = np.cumsum(n)
    total = int(ends[-1]) if len(ends) else 0
    at = np.arange(total) + np.repeat(first[which] - (ends - n), n)
    return flat[at], np.concatenate([[0], ends])


def texts_of(column: pa.ChunkedArray | pa.Array) -> list[str]:
    return ["" if x is None else x for x in column.to_pylist()]
