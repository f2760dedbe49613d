"""Shards by extendible hashing: a directory indexed by hash-prefix bits, where
only buckets above the byte limit split on another bit.

A document's bucket is the shortest prefix of its hash whose documents together
fit the limit. Documents larger than the limit each are a shard of their own,
outside the directory. Buckets that still exceed the limit when all bits are
used (rows that repeat one id) are marked, not cut.

The directory grows by ``STEP_BITS`` levels a round, and a round only looks at
documents of buckets that are still too large, so its work shrinks to nothing.
Directories are broadcast up to ``FEW_CELLS`` cells and joined by hash beyond.

Null texts have no bytes; a null id hashes as an empty one. Texts count whole,
however long. Rows that repeat an id share a shard unless they differ in being
larger than the limit: the large ones of an id are one shard, of their bytes
together. There are no ties: a row has one bucket. An empty table has no shards.
Other columns are never looked at, whatever their names.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import free_names, staged

HASH_BITS = 60
STEP_BITS = 6
LIMIT = 4 << 20
#: Cells of a directory that is broadcast: under a megabyte.
FEW_CELLS = 8_192


def _hash60():
    return F.conv(F.substring(F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))), 1, HASH_BITS // 4), 16, 10).cast("long")


def assign_shards(docs: DataFrame, limit: int = LIMIT) -> DataFrame:
    """doc_id, n_bytes, depth, prefix (the first ``depth`` bits of the hash),
    shard (its name), shard_bytes, fits (whether the shard is within the limit)."""
    n_bytes = F.coalesce(F.octet_length("text"), F.lit(0)).cast("long")
    rows = staged(docs.select("doc_id", n_bytes.alias("n_bytes")).withColumn("hash", _hash60()), "bytes")
    large = rows.where(F.col("n_bytes") > limit).select("doc_id", "n_bytes", F.lit(HASH_BITS).alias("depth"), F.col("hash").alias("prefix"), F.lit("single").alias("kind"), F.sum("n_bytes").over(W.partitionBy("hash")).alias("shard_bytes"))
    # bytes by hash prefix, one row a prefix: small next to the documents
    left = rows.where(F.col("n_bytes") <= limit)
    leaves: list[tuple[int, DataFrame]] = []
    depth = 0

    def sized(cells: DataFrame, n: int) -> DataFrame:
        return F.broadcast(cells) if n <= FEW_CELLS else cells.hint("shuffle_hash")

    while True:
        top = min(depth + STEP_BITS, HASH_BITS)
        cells = staged(left.groupBy(F.shiftright("hash", HASH_BITS - top).alias("cell")).agg(F.sum("n_bytes").alias("bytes")), "cells")
        n = cells.count()
        levels = F.explode(F.sequence(F.lit(depth), F.lit(top)))
        spread = cells.select("bytes", "cell", levels.alias("depth")).withColumn("prefix", F.expr(f"shiftright(cell, {top} - depth)"))
        sums = spread.groupBy("depth", "prefix").agg(F.sum("bytes").alias("shard_bytes"))
        fitting = sums.where((F.col("shard_bytes") <= limit) | (F.col("depth") == HASH_BITS))
        # of the fitting prefixes of a cell the shortest is its bucket
        home = spread.select("cell", "depth", "prefix").join(fitting.hint("merge"), ["depth", "prefix"]).groupBy("cell").agg(F.min(F.struct("depth", "prefix", "shard_bytes")).alias("b"))
        home = staged(home.select(F.col("cell"), "b.*"), "directory")
        leaves.append((top, sized(home, n)))
        if top == HASH_BITS:
            break
        open_cells = cells.join(home.hint("merge"), "cell", "left_anti").select("cell")
        if open_cells.isEmpty():
            break
        left = staged(left.withColumn("cell", F.shiftright("hash", HASH_BITS - top)).join(sized(open_cells, n), "cell", "left_semi").drop("cell"), "oversized")
        depth = top + 1 if top + 1 <= HASH_BITS else top
    small = rows.where(F.col("n_bytes") <= limit)
    placed = []
    for top, leaf in leaves:  # each round's rows join on their own prefix length
        placed.append(small.withColumn("cell", F.shiftright("hash", HASH_BITS - top)).join(leaf, "cell").select("doc_id", "n_bytes", "depth", "prefix", F.lit("bucket").alias("kind"), "shard_bytes"))
    every = reduce(DataFrame.unionAll, [*placed, large])
    name = F.concat_ws("-", "kind", F.lpad(F.col("depth").cast("string"), 2, "0"), F.lpad(F.lower(F.hex("prefix")), 15, "0"))
    return every.select("doc_id", "n_bytes", F.col("depth").cast("int").alias("depth"), "prefix", name.alias("shard"), "shard_bytes", (F.col("shard_bytes") <= limit).alias("fits"))


def write_shards(docs: DataFrame, path: str, limit: int = LIMIT) -> None:
    """Writes ``docs`` to one folder a shard, each row once. Rows are dealt by shard,
    so each shard's file is written whole by one task. The folders' column is named
    shard, with an underscore after it if ``docs`` has such a column."""
    own_id, own_size, shard = free_names(docs, "id_", "large_", "shard")
    # rows of one id and kind of size have one shard
    homes = assign_shards(docs, limit).select(F.col("doc_id").alias(own_id), (F.col("n_bytes") > limit).alias(own_size), F.col("shard").alias(shard)).distinct()
    large = F.coalesce(F.octet_length("text"), F.lit(0)) > limit
    joined = docs.join(homes, docs["doc_id"].eqNullSafe(F.col(own_id)) & (large == F.col(own_size))).select(*[docs[c] for c in docs.columns], shard)
    joined.repartition(shard).write.partitionBy(shard).parquet(path)


def shards_sql(documents: str = "documents", limit: int = LIMIT) -> str:
    """The same by DuckDB, from all prefixes at once."""
    return f"""
WITH rows AS (
  SELECT doc_id, CAST(coalesce(octet_length(encode(text)), 0) AS BIGINT) AS n_bytes,
         CAST(('0x' || substr(md5(coalesce(CAST(doc_id AS VARCHAR), '')), 1, {HASH_BITS // 4})) AS BIGINT) AS hash FROM {documents}
), small AS (SELECT * FROM rows WHERE n_bytes <= {limit}
), depths AS (SELECT CAST(unnest(range({HASH_BITS + 1})) AS INT) AS depth
), sums AS (
  SELECT depth, hash >> ({HASH_BITS} - depth) AS prefix, CAST(sum(n_bytes) AS BIGINT) AS shard_bytes FROM small, depths GROUP BY 1, 2
), homes AS (
  SELECT hash, min(depth) AS depth FROM (SELECT DISTINCT hash FROM small) h, depths JOIN sums USING (depth)
  WHERE prefix = hash >> ({HASH_BITS} - depth) AND (shard_bytes <= {limit} OR depth = {HASH_BITS}) GROUP BY hash
), placed AS (
  SELECT doc_id, n_bytes, h.depth, s.prefix, 'bucket' AS kind, shard_bytes FROM small JOIN homes h USING (hash) JOIN sums s ON s.depth = h.depth AND s.prefix = hash >> ({HASH_BITS} - h.depth)
  UNION ALL SELECT doc_id, n_bytes, {HASH_BITS}, hash, 'single', CAST(sum(n_bytes) OVER (PARTITION BY hash) AS BIGINT) FROM rows WHERE n_bytes > {limit}
)
SELECT doc_id, n_bytes, depth, prefix, kind || '-' || lpad(CAST(depth AS VARCHAR), 2, '0') || '-' || lpad(format('{{:x}}', prefix), 15, '0') AS shard,
       shard_bytes, shard_bytes <= {limit} AS fits FROM placed
"""
