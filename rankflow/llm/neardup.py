"""Near duplicates by MinHash: many universal hash minima with banding,
signature verification, exact confirmation on full shingle sets, and connected
components by alternating large-star and small-star.

Words are runs of anything but ASCII white space, A-Z lower-cased. A document's
set holds its distinct runs of five words; with fewer words the whole sequence
is its one member; without words (or with a null text) the set is empty and is
linked with nothing. Repeated ids keep a row each and share their component: the
texts of one id are linked through it, whatever they are. Null ids are linked with
nothing. Texts count whole, however long. Of ties (equal texts) the least doc_id
is kept. An empty table gives no rows. Other columns are never looked at, whatever
their names.

How the work stays bounded under large groups of copies:

* documents with equal sets form a class before any search; a class is one row;
* a small bucket of the banding gives all its pairs, a bounded number a row;
* a larger bucket that fits a block of bounded size is tested by one task, which
  returns only links that connect components;
* in buckets of several blocks, two turns test members only against one pivot of
  each bucket, so a group of m near copies costs m tests and not m * m / 2.
  Members already connected need no further test. Those outside a bucket's
  commonest component are then tested against all of the bucket, one pair of
  blocks a task. No pair of a bucket that could connect two components is left
  untested.

The banding misses a pair at the similarity threshold s with probability
(1 - s ** rows) ** bands: 2.7e-7 at 0.85 with 32 bands of 6 rows, 2.5e-7 at 0.8
with 50 (32 would miss 6e-5 there).
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Kept, forget, free_names, held_by, only, shuffle_parts, staged

BANDS, ROWS = 32, 6
#: Bands for a similarity under 0.85, 0.8 at the least.
MORE_BANDS = 50
WORDS = 5
#: Per cent of similarity from which on the stage takes documents for copies.
STAGE_PERCENT = 80
#: Signature agreement under which a pair is not worth its full sets: the estimate
#: is 9 standard deviations above it at true similarity 0.85 (192 minima) and 8 at
#: 0.8 (300 minima).
LEAST_AGREED = 0.6
#: Rows of a bucket that gives all its pairs.
SMALL = 24
PIVOT_TURNS = 2
#: Shingles of a block of a large bucket.
BLOCK_SHINGLES = 400_000
#: Bits of one of Spark's bitmaps, and bits for each id looked for.
MAP_BITS, ID_BITS = 32_768, 16

_LOWER = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))
_MIX = np.uint64(0x9E3779B97F4A7C15)


#: 64-bit hashes of the words of a worker's batches.
_words = Kept(xxhash.xxh3_64_intdigest, 80_000)
held_by("near", _words.empty)


def shingles(text: str | None, words: int = WORDS) -> np.ndarray:
    """Sorted distinct 64-bit hashes of a text's shingles."""
    if not text:
        return np.empty(0, np.uint64)
    raw = text.encode("utf-8", "surrogatepass").translate(_LOWER)
    tokens = raw.split()  # bytes split at exactly the six ASCII white space bytes
    if not tokens:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(_words.__getitem__, tokens), np.uint64, len(tokens))
    width = min(words, len(h))
    n = len(h) - width + 1
    out = np.full(n, width if width < words else 0, np.uint64)
    for i in range(width):
        out = (out ^ h[i : i + n]) * _MIX
        out ^= out >> np.uint64(29)
    return np.unique(out)


def _universal(count: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(seed)
    return (rng.integers(0, 1 << 32, count, dtype=np.uint32) | np.uint32(1))[:, None], rng.integers(0, 1 << 32, count, dtype=np.uint32)[:, None]


def minima(sets: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The least value of each universal hash over a set (not empty)."""
    x = (sets >> np.uint64(32)).astype(np.uint32)
    out = np.full(len(a), 0xFFFFFFFF, np.uint32)
    for lo in range(0, len(x), 1024):
        part = x[None, lo : lo + 1024]
        out = np.minimum(out, (a * part + b).min(axis=1))
    return out


def digest_of(s: np.ndarray) -> bytes:
    return xxhash.xxh3_128_digest(s.tobytes())


def signatures(docs: DataFrame, bands: int = BANDS, rows: int = ROWS, words: int = WORDS, seed: int = 11) -> DataFrame:
    """doc_id, n_shingles, digest (of the set), keys (a bucket for each band) and
    agreed (the low byte of each minimum); the last three null for empty sets."""
    schema = "doc_id long, n_shingles long, digest binary, keys array<long>, agreed binary"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        only("near")
        a, b = _universal(bands * rows, seed)
        for whole in batches:
            for lo in range(0, whole.num_rows, 256):
                batch = whole.slice(lo, 256)
                n, digest, keys, agreed = [], [], [], []
                for text in batch.column(1).to_pylist():
                    s = shingles(text, words)
                    n.append(len(s))
                    if not len(s):
                        digest.append(None), keys.append(None), agreed.append(None)
                        continue
                    m = minima(s, a, b)
                    digest.append(digest_of(s))
                    k = np.zeros(bands, np.uint64)
                    for r in range(rows):
                        k = (k ^ m[r::rows].astype(np.uint64)) * _MIX
                        k ^= k >> np.uint64(31)
                    keys.append(k.view(np.int64))
                    agreed.append(m.astype(np.uint8).tobytes())
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(digest, pa.binary()), pa.array(keys, pa.list_(pa.int64())), pa.array(agreed, pa.binary())], names=["doc_id", "n_shingles", "digest", "keys", "agreed"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, schema)


def _listed(sets: list[np.ndarray]) -> pa.ListArray:
    """Sets of unsigned hashes as an array of signed lists."""
    ends = np.cumsum([0, *map(len, sets)])
    flat = np.concatenate(sets) if sets else np.empty(0, np.uint64)
    return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(flat.view(np.int64)))


def _sets_of(column: pa.ListArray) -> list[np.ndarray]:
    flat, ends = column.values.to_numpy(), column.offsets.to_numpy()
    return [flat[i:j] for i, j in zip(ends[:-1], ends[1:])]


def shingle_sets(docs: DataFrame, words: int = WORDS) -> DataFrame:
    """doc_id, digest and hashes of the set of each row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        only("near")
        for whole in batches:
            for lo in range(0, whole.num_rows, 128):
                batch = whole.slice(lo, 128)
                sets = [shingles(t, words) for t in batch.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(map(digest_of, sets), pa.binary()), _listed(sets)], names=["doc_id", "digest", "set"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, digest binary, set array<long>")


def _perhaps_among(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """doc_id and text of all rows whose id is among ``ids`` (doc_id), and of few others
    (1 in ``ID_BITS``). Each id marks a bit by its hash; only these bits are sent to all
    tasks, so that no text moves, however many ids there are."""
    size = MAP_BITS * max(1, -(-ids.count() * ID_BITS // MAP_BITS))
    at = F.pmod(F.xxhash64("doc_id"), F.lit(size).cast("long"))
    place, bit = F.floor(at / MAP_BITS).alias("place"), (at % MAP_BITS).alias("bit")
    maps = ids.select(place, bit).groupBy("place").agg(F.bitmap_construct_agg("bit").alias("map"))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).select("doc_id", "text", place, bit)
    byte = F.conv(F.hex(F.expr("substring(map, int(bit div 8) + 1, 1)")), 16, 10).cast("int")
    marked = byte.bitwiseAND(F.expr("shiftleft(1, int(bit % 8))")) != 0
    return rows.join(F.broadcast(maps), "place").where(marked).select("doc_id", "text")


def _agree(a: Column, b: Column) -> Column:
    """Share of equal signature bytes."""

    @F.arrow_udf("double")
    def share(x: pa.Array, y: pa.Array) -> pa.Array:
        n = len(x)
        if not n:
            return pa.array([], pa.float64())
        left = np.frombuffer(b"".join(x.to_pylist()), np.uint8).reshape(n, -1)
        right = np.frombuffer(b"".join(y.to_pylist()), np.uint8).reshape(n, -1)
        return pa.array((left == right).mean(axis=1))

    return share(a, b)


def _confirmed(a: Column, b: Column, percent: int) -> Column:
    """Whether two full sets reach the similarity, in whole numbers and without
    leaving the JVM."""
    both = F.size(F.array_intersect(a, b)).cast("long")
    return 100 * both >= percent * (F.size(a) + F.size(b) - both)


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """vertex and component (its least reachable vertex) of the vertices of
    undirected ``edges`` (u, v), by alternating large-star and small-star. Each
    step is an aggregate and a join on the vertex; edges are staged each round."""
    now = staged(edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u <> v").distinct(), "stars")
    before = None
    for _ in range(max_rounds):
        both = now.unionAll(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.col("u"), F.min("v")).alias("m"))
        # large star: neighbours above a vertex move to its least neighbour
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        # small star: a vertex and its neighbours below move to the least of them
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionAll(low.select("u", F.col("m").alias("v"))).distinct()
        old, now = now, staged(small, "stars")
        forget(old)
        mark = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if tuple(mark) == before:
            break
        before = tuple(mark)
    else:
        raise RuntimeError("components did not settle")
    tops = now.select(F.col("v").alias("vertex")).distinct()
    return now.select(F.col("u").alias("vertex"), F.col("v").alias("component")).unionAll(tops.select("vertex", F.col("vertex").alias("component")))


def near_components(docs: DataFrame, percent: int = 85, bands: int | None = None, rows: int = ROWS, words: int = WORDS) -> DataFrame:
    """doc_id, n_shingles, component_id (least doc_id reachable over links) and
    kept (whether that is the document itself), one row for each row of ``docs``.

    Rows with a null doc_id are their own component with a null id and are kept.
    """
    spark = docs.sparkSession
    bands = bands or (BANDS if percent >= 85 else MORE_BANDS)
    signed = staged(signatures(docs, bands, rows, words), "signatures")
    some = F.col("digest").isNotNull() & F.col("doc_id").isNotNull()
    # a class has a number of its own: one id may stand for several sets. Its keys move
    # once, with its digest, and are kept with it
    of_set = F.min_by(F.struct("n_shingles", "keys", "agreed"), "doc_id").alias("of_set")
    reps = signed.where(some).groupBy("digest").agg(F.min("doc_id").alias("rep"), of_set).select("digest", "rep", "of_set.*")
    reps = staged(reps.withColumn("vertex", F.monotonically_increasing_id()), "classes")
    marked = staged(signed.select("doc_id", "n_shingles", "digest"), "rows")
    forget(signed)
    classes = reps.select("digest", "rep", "vertex")
    links = staged(_links_of_ids(marked.where(some).join(classes, "digest")), "links")
    member = reps.select(F.posexplode("keys").alias("band", "key"), F.col("vertex").alias("doc_id"), "n_shingles")
    filled = member.groupBy("band", "key").agg(F.count("*").alias("n"), F.sum("n_shingles").alias("size")).where("n > 1")
    member = member.drop("n_shingles")
    member = staged(member.join(filled, ["band", "key"]), "buckets")
    if member.isEmpty():
        return _with_components(marked, classes, None if links.isEmpty() else _labels([links]))

    wanted = member.select(F.col("doc_id").alias("vertex")).distinct()
    wanted = staged(reps.join(wanted, "vertex").select("vertex", F.col("rep").alias("doc_id"), "digest", "n_shingles", "agreed"), "wanted")
    # from here on doc_id is the number of a class
    # an id and a digest name one class, and what the join deals by them needs no other deal
    known = staged(
        shingle_sets(_perhaps_among(docs, wanted.select("doc_id")), words)
        .join(wanted, ["doc_id", "digest"]).dropDuplicates(["doc_id", "digest"])
        .select(F.col("vertex").alias("doc_id"), "set", "n_shingles", "agreed"),
        "sets",
    )
    light = known.select("doc_id", "n_shingles", "agreed")
    heavy = known.select("doc_id", "set")

    def linked(pairs: DataFrame) -> DataFrame:
        """The pairs (a, b) that pass size, signature and full-set tests."""
        sized = pairs.join(_named(light, "a"), "a").join(_named(light, "b"), "b")
        fits = sized.where(100 * F.least("n_a", "n_b") >= percent * F.greatest("n_a", "n_b"))
        likely = fits.where(_agree(F.col("s_a"), F.col("s_b")) >= LEAST_AGREED).select("a", "b")
        full = likely.join(heavy.select(F.col("doc_id").alias("a"), F.col("set").alias("x")), "a").join(heavy.select(F.col("doc_id").alias("b"), F.col("set").alias("y")), "b")
        return full.where(_confirmed(F.col("x"), F.col("y"), percent)).select("a", "b")

    def rows_of(some: DataFrame) -> DataFrame:
        return some.select("band", "key", "doc_id")

    small, one_block = F.col("n") <= SMALL, F.col("size") <= BLOCK_SHINGLES
    found = [links, staged(linked(_pairs(rows_of(member.where(small))).distinct()), "links")]
    medium, giant = rows_of(member.where(~small & one_block)), rows_of(member.where(~small & ~one_block))
    found.append(staged(_block_links(medium.withColumn("component", F.col("doc_id")), known, percent), "links"))
    if not giant.isEmpty():
        label = _labels(found)
        for turn in range(PIVOT_TURNS):
            rows = _open_buckets(giant, label)
            pivot = rows.groupBy("band", "key").agg(F.min_by(F.struct("doc_id", "component"), F.xxhash64("doc_id", "band", F.lit(turn))).alias("p"))
            pairs = rows.join(pivot, ["band", "key"]).where("component <> p.component").select(F.least("doc_id", "p.doc_id").alias("a"), F.greatest("doc_id", "p.doc_id").alias("b"))
            found.append(staged(linked(pairs.distinct()), "links"))
            label = _labels(found)
        found.append(staged(_block_links(_open_buckets(giant, label), known, percent), "links"))
    return _with_components(marked, classes, _labels(found))


def _links_of_ids(own: DataFrame) -> DataFrame:
    """Links (a, b) between the classes of each id that has several."""
    ends = own.groupBy("doc_id").agg(F.min("vertex").alias("a"), F.max("vertex").alias("last")).where("a <> last").select("doc_id", "a")
    return own.select("doc_id", F.col("vertex").alias("b")).join(ends, "doc_id").where("a <> b").select("a", "b").distinct()


def _labels(links: list[DataFrame]) -> DataFrame:
    """vertex and component of all that ``links`` (a, b) connect."""
    return staged(components(reduce(DataFrame.unionAll, links).select(F.col("a").alias("u"), F.col("b").alias("v"))), "labels")


def _named(light: DataFrame, end: str) -> DataFrame:
    return light.select(F.col("doc_id").alias(end), F.col("n_shingles").alias(f"n_{end}"), F.col("agreed").alias(f"s_{end}"))


def _open_buckets(member: DataFrame, label: DataFrame) -> DataFrame:
    """Rows of the buckets that hold more than one component."""
    rows = member.join(label.withColumnRenamed("vertex", "doc_id"), "doc_id", "left").withColumn("component", F.coalesce("component", "doc_id"))
    mixed = rows.groupBy("band", "key").agg(F.min("component").alias("lo"), F.max("component").alias("hi")).where("lo <> hi").select("band", "key")
    return rows.join(mixed, ["band", "key"])


def _pairs(rows: DataFrame) -> DataFrame:
    """All pairs of small buckets."""
    one = rows.select("band", "key", F.col("doc_id").alias("a"))
    two = rows.select("band", "key", F.col("doc_id").alias("b"))
    return one.join(two, ["band", "key"]).where("a < b").select("a", "b")


def _block_links(rows: DataFrame, known: DataFrame, percent: int) -> DataFrame:
    """Links (a, b) that connect components of a bucket: rows outside its
    commonest component against all its rows, block by block."""
    sized = rows.join(known.select("doc_id", "n_shingles"), "doc_id")
    parts = sized.groupBy("band", "key", "component").agg(F.count("*").alias("c"), F.sum("n_shingles").alias("size"))
    bucket = parts.groupBy("band", "key").agg(F.max_by("component", F.struct("c", F.negative("component"))).alias("major"), F.max(F.struct("c", F.negative("component"), "size"))["size"].alias("most"), F.sum("size").alias("size"))
    blocks = bucket.select(
        "band", "key", "major",
        F.expr(f"int(size div {BLOCK_SHINGLES}) = 0").alias("single"),
        F.expr(f"int((size - most) div {BLOCK_SHINGLES}) + 1").alias("minors"),
        F.expr(f"int(most div {BLOCK_SHINGLES}) + 1").alias("majors"),
    )
    placed = sized.join(blocks, ["band", "key"]).withColumn("minor", F.col("component") != F.col("major"))
    at = F.xxhash64("doc_id")
    i, j = F.pmod(at, F.col("minors")).cast("int"), F.pmod(at, F.col("majors")).cast("int")
    others = F.sequence(F.lit(0), F.col("minors") - 1)
    group = F.struct(F.lit(0).alias("kind"), F.lit(0).alias("x"), F.lit(0).alias("y"))

    def cell(kind: int, x: Column, y: Column) -> Column:
        return F.struct(F.lit(kind).alias("kind"), x.cast("int").alias("x"), y.cast("int").alias("y"))

    homes = (
        F.when(F.col("single"), F.array(group))
        .when(F.col("minor"), F.concat(F.transform(others, lambda o: cell(1, F.least(i, o), F.greatest(i, o))), F.transform(F.sequence(F.lit(0), F.col("majors") - 1), lambda o: cell(2, i, o))))
        .otherwise(F.transform(others, lambda o: cell(2, o, j)))
    )
    spread = placed.select("band", "key", "doc_id", "component", "minor", F.explode(homes).alias("g")).select("band", "key", "g.kind", "g.x", "g.y", "doc_id", "component", "minor")
    full = spread.join(known.select("doc_id", "set"), "doc_id")
    by = ["band", "key", "kind", "x", "y"]
    dealt = full.select(*by, "doc_id", "component", "minor", "set").repartition(shuffle_parts(rows.sparkSession), *by).sortWithinPartitions(*by)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []
        for whole in batches:
            for lo in range(0, whole.num_rows, 256):
                part = whole.slice(lo, 256)
                for row in zip(*(c.to_pylist() for c in part.columns[:-1]), _sets_of(part.columns[-1])):
                    if row[:5] != now:
                        if len(held) > 1:
                            yield _tested(held, percent)
                        now, held = row[:5], []
                    held.append(row[5:])
        if len(held) > 1:
            yield _tested(held, percent)

    return dealt.mapInArrow(run, "a long, b long").distinct()


def _tested(held: list[tuple[int, int, bool, np.ndarray]], percent: int) -> pa.RecordBatch:
    """Links between components of one block pair, no more than connect them."""
    sets = [h[3] for h in held]
    sizes = np.array([len(s) for s in sets])
    starts = np.concatenate([[0], np.cumsum(sizes)])
    _, flat = np.unique(np.concatenate(sets), return_inverse=True)
    mark = np.zeros(int(flat.max()) + 1, np.int32)
    root: dict[int, int] = {}

    def top(c: int) -> int:
        while root.get(c, c) != c:
            root[c] = root.get(root[c], root[c])
            c = root[c]
        return c

    a, b = [], []
    for i, (doc, own, minor, _) in enumerate(held):
        if not minor:
            continue
        mine = flat[starts[i] : starts[i + 1]]
        mark[mine] = 1
        inter = np.add.reduceat(mark[flat], starts[:-1])
        mark[mine] = 0
        for k in np.flatnonzero(100 * inter >= percent * (sizes + sizes[i] - inter)).tolist():
            p, q = top(own), top(held[k][1])
            if p != q:
                root[max(p, q)] = min(p, q)
                a.append(min(doc, held[k][0])), b.append(max(doc, held[k][0]))
    return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])


def _with_components(marked: DataFrame, classes: DataFrame, label: DataFrame | None) -> DataFrame:
    """Components by their least id; a row without a set takes what its id has."""
    own = classes
    if label is not None:
        own = own.join(label, "vertex", "left").withColumn("component", F.coalesce("component", "vertex"))
        own = own.join(own.groupBy("component").agg(F.min("rep").alias("least")), "component")
    else:
        own = own.withColumn("least", F.col("rep"))
    rows = marked.select("doc_id", "n_shingles", "digest").join(own.select("digest", "least"), "digest", "left")
    bare = rows.where("digest is null and doc_id is not null").select("doc_id").distinct()
    theirs = rows.join(bare, "doc_id", "left_semi").where("digest is not null").groupBy("doc_id").agg(F.min("least").alias("of_id"))
    rows = rows.join(theirs, "doc_id", "left")
    found = F.when(F.col("doc_id").isNotNull(), F.coalesce("least", "of_id", "doc_id"))
    return rows.select("doc_id", "n_shingles", found.alias("component_id")).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def one_of_each_group(docs: DataFrame, percent: int = STAGE_PERCENT) -> DataFrame:
    """One row of each group of near copies, the first by doc_id, and all rows
    without words. Rows count one by one: those that repeat a doc_id, or have
    none, are copies only where their texts are."""
    (row,) = free_names(docs, "row_")
    rows = staged(docs.withColumn(row, F.monotonically_increasing_id()), "rows")
    found = staged(near_components(rows.select(F.col(row).alias("doc_id"), "text"), percent).select(F.col("doc_id").alias(row), "component_id", "kept"), "groups")
    several = found.where("not kept").select("component_id").distinct()
    member = found.join(several, "component_id").select(row, "component_id").join(rows.select(row, F.col("doc_id").alias("id")), row)
    order = F.struct(F.col("id").isNull().alias("last"), "id", row)
    first = member.groupBy("component_id").agg(F.min(order)[row].alias("first"))
    gone = member.join(first, "component_id").where(F.col(row) != F.col("first")).select(row)
    return rows.join(gone, row, "left_anti").select(*[rows[c] for c in docs.columns])


def near_components_sql(documents: str = "documents", percent: int = 85) -> str:
    """The same by DuckDB, from all pairs that share a shingle."""
    return rf"""
WITH RECURSIVE words AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM {documents}
), runs AS (
  SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < {WORDS} THEN [array_to_string(w, ' ')]
         ELSE list_distinct(list_transform(range(1, len(w) - {WORDS} + 2), lambda i: array_to_string(list_slice(w, i, i + {WORDS - 1}), ' '))) END AS s FROM words
), sizes AS (SELECT doc_id, CAST(len(s) AS BIGINT) AS n FROM runs
), members AS (SELECT doc_id, unnest(s) AS g FROM runs
), shared AS (
  SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM members x JOIN members y ON x.g = y.g AND x.doc_id < y.doc_id GROUP BY 1, 2
), links AS (
  SELECT a, b FROM shared JOIN sizes p ON p.doc_id = a JOIN sizes q ON q.doc_id = b WHERE 100 * c >= {percent} * (p.n + q.n - c)
), ways AS (SELECT a AS u, b AS v FROM links UNION ALL SELECT b, a FROM links
), reach(u, v) AS (SELECT doc_id, doc_id FROM sizes UNION SELECT reach.u, ways.v FROM reach JOIN ways ON reach.v = ways.u)
SELECT s.doc_id, s.n AS n_shingles, r.v AS component_id, s.doc_id = r.v AS kept
FROM sizes s JOIN (SELECT u, min(v) AS v FROM reach GROUP BY u) r ON r.u = s.doc_id
"""
