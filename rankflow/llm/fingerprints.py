"""SimHash fingerprints of documents and search within a Hamming radius.

A text's terms are its runs of three words (all words, if fewer), weighted by
how often they occur. The hash of each term votes on 64 signed bits; a bit of
the fingerprint is set where the votes for it win. An empty text has fingerprint
zero. The likeness of two fingerprints is one less the share of unequal bits.

``within_radius`` finds all pairs at most ``radius`` bits apart: the bits are
cut into radius + 3 blocks, and for each choice of three blocks a table keyed
by them holds every fingerprint. Two fingerprints within the radius differ in
at most ``radius`` blocks, so some table has them under one key. A key under
which many fingerprints lie is cut further: among the rest of their bits, in
radius + 1 parts, two within the radius agree in one part at least, so tables of
the key and one more part hold all that is to be found, and so on.

Null texts are empty. Null keys order before all others. Repeated keys keep a
row each, ordered by text (ties are equal rows). Texts count whole, however long.
Equal texts and repeated rows have equal fingerprints. An empty table gives no
rows. Other columns are never looked at, whatever their names.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import reduce
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Kept, chunk_bounds, chunk_of, held_by, only, shuffle_parts, staged

BITS = 64
TERM_WORDS = 3
ROWS_PER_CHUNK = 1_000
_MIX = np.uint64(0x9E3779B97F4A7C15)
NULL_KEY = -(1 << 63)


#: 64-bit hashes of the words of a worker's batches.
_words = Kept(xxhash.xxh3_64_intdigest)
held_by("prints", _words.empty)


def fingerprint(text: str | None) -> int:
    """The 64-bit SimHash of a whole text."""
    tokens = (text or "").encode("utf-8", "surrogatepass").split()
    if not tokens:
        return 0
    h = np.fromiter(map(_words.__getitem__, tokens), np.uint64, len(tokens))
    width = min(TERM_WORDS, len(h))
    n = len(h) - width + 1
    terms = np.full(n, width, np.uint64)
    for i in range(width):
        terms = (terms ^ h[i : i + n]) * _MIX
        terms ^= terms >> np.uint64(32)
    votes = np.zeros(BITS, np.int64)
    for lo in range(0, n, 255):  # so many one-bit votes fit a byte
        part = terms[lo : lo + 255]
        votes += np.add.reduce(np.unpackbits(part.view(np.uint8).reshape(len(part), 8), axis=1), axis=0, dtype=np.uint8)
    return int(np.packbits(2 * votes > n).view(np.uint64)[0])


def likeness(a: int, b: int) -> float:
    return 1.0 - (a ^ b).bit_count() / BITS


def edited_pairs(docs: DataFrame, rows_per_chunk: int = ROWS_PER_CHUNK) -> DataFrame:
    """Fingerprints of every text and of its edited text: the last half of its
    code points gives way to the first as many of the next document, in
    descending order of doc_id; after the last comes the first.

    Rows are dealt into contiguous key ranges; the last row of each range goes
    to the following range as well, so each text moves once and a task holds
    two texts at a time.
    """
    rows = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(NULL_KEY)).alias("key"), F.col("text").cast("string").alias("text"))
    bounds = chunk_bounds(rows, "key", rows_per_chunk)
    parts = max(1, len(bounds))
    tops = set(bounds.tolist())

    @F.arrow_udf("array<long>")
    def homes(chunk: pa.Array, key: pa.Array) -> pa.Array:
        return pa.array([[c, -1 - (c + 1) % parts] if k in tops else [c] for c, k in zip(chunk.to_pylist(), key.to_pylist())], pa.list_(pa.int64()))

    dealt = (
        rows.withColumn("home", F.explode(homes(chunk_of(F.col("key"), bounds), F.col("key"))))
        .withColumn("carried", F.col("home") < 0)
        .withColumn("chunk", F.when(F.col("carried"), -1 - F.col("home")).otherwise(F.col("home")))
        .select("chunk", "carried", "key", "text")
        .repartition(parts, "chunk")
        .sortWithinPartitions("chunk", F.desc("carried"), "key", "text")
    )
    schema = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        only("prints")
        before, before_print = "", 0
        for whole in batches:
            for lo in range(0, whole.num_rows, 256):
                b = whole.slice(lo, 256)
                out: list[tuple] = []
                for carried, key, text in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), b.column(3).to_pylist()):
                    text = text or ""
                    own = fingerprint(text)
                    if not carried:
                        half = len(text) // 2
                        edited = text[: len(text) - half] + before[:half]
                        other = own if edited == text else fingerprint(edited)
                        sha = hashlib.sha256(edited.encode("utf-8", "surrogatepass")).hexdigest()
                        out.append((None if key == NULL_KEY else key, len(text), sha, f"{own:016x}", f"{other:016x}", likeness(own, other), likeness(own, before_print)))
                    before, before_print = text, own
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()))], names=["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"])

    return dealt.mapInArrow(run, schema)


def document_fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id and fingerprint (hexadecimal) of every text, without a shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([f"{fingerprint(t):016x}" for t in b.column(1).to_pylist()], pa.string())], names=["doc_id", "fingerprint"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, fingerprint string")


#: Fingerprints under one key that are compared pair by pair.
FEW_UNDER_KEY = 256
#: Keys of the last level have 50 bits, so at most 2 ** 14 fingerprints are under one.
MOST_LEVELS = 4


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _parts(mask: int, count: int) -> list[int]:
    """The bits that ``mask`` lacks, cut into ``count`` runs, each a mask."""
    rest = [i for i in range(BITS) if not mask >> i & 1]
    edges = [len(rest) * i // count for i in range(count + 1)]
    return [sum(1 << b for b in rest[edges[i] : edges[i + 1]]) for i in range(count)]


def _under_keys(keyed: DataFrame, radius: int, few: int) -> DataFrame:
    """From (mask, key, bits), dealt by mask and key: links (a, b, apart) of keys with
    at most ``few`` fingerprints, and the rows of all other keys (apart null: a is
    the mask, b the bits)."""
    parts = shuffle_parts(keyed.sparkSession)
    dealt = keyed.repartition(parts, "mask", "key").sortWithinPartitions("mask", "key", "bits")

    def links(bits: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        found = []
        for lo in range(0, len(bits), 256):
            apart = np.bitwise_count((bits[lo : lo + 256, None] ^ bits[None]).view(np.uint64))
            i, j = np.nonzero(np.triu(apart <= radius, lo + 1))
            found.append((bits[lo + i], bits[j], apart[i, j].astype(np.int32)))
        return tuple(np.concatenate(c) for c in zip(*found))

    def out(a: np.ndarray, b: np.ndarray, apart: np.ndarray | None) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.nulls(len(a), pa.int32()) if apart is None else pa.array(apart, pa.int32())], names=["a", "b", "apart"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # the fingerprints under the last key may go on in the next batch
        now, held, over = None, np.empty(0, np.int64), False

        def closed() -> Iterator[pa.RecordBatch]:
            if over:
                yield out(np.full(len(held), now[0]), held, None)
            elif len(held) > 1:
                yield out(*links(held))

        for batch in batches:
            mask, key, bits = (c.to_numpy() for c in batch.columns)
            if not len(mask):
                continue
            starts = np.flatnonzero(np.concatenate([[True], (mask[1:] != mask[:-1]) | (key[1:] != key[:-1])]))
            ends = np.append(starts[1:], len(mask))
            several = (ends - starts > 1) | (starts == 0) | (ends == len(mask))  # a lone one inside has no partner
            for lo, hi in zip(starts[several].tolist(), ends[several].tolist()):
                if (mask[lo], key[lo]) != now:
                    yield from closed()
                    now, held, over = (mask[lo], key[lo]), np.empty(0, np.int64), False
                held = np.concatenate([held, bits[lo:hi]])
                if len(held) > few:
                    over = True
                if over:  # rows of a hot key go by, at most a batch is held
                    yield out(np.full(len(held), now[0]), held, None)
                    held = np.empty(0, np.int64)
        yield from closed()

    return dealt.select("mask", "key", "bits").mapInArrow(run, "a long, b long, apart int")


def within_radius(prints: DataFrame, radius: int = 3, few: int = FEW_UNDER_KEY) -> tuple[DataFrame, DataFrame]:
    """(members, pairs) of fingerprints: members gives each doc_id its class, the
    least doc_id with that fingerprint; pairs (a, b, bits) links the classes of
    unequal fingerprints at most ``radius`` bits apart. Copies stay classes and
    are not expanded into pairs. Rows without a fingerprint are left out; a class
    of rows without ids has a null class id."""
    blocks = radius + 3
    edges = [BITS * i // blocks for i in range(blocks + 1)]
    masks = [sum(((1 << edges[i + 1]) - (1 << edges[i])) for i in chosen) for chosen in combinations(range(blocks), 3)]
    hi, lo = (F.conv(F.substring("fingerprint", at, 8), 16, 10).cast("long") for at in (1, 9))
    classes = staged(prints.where("fingerprint is not null").groupBy("fingerprint").agg(F.min("doc_id").alias("class_id")).withColumn("bits", F.shiftleft(hi, 32).bitwiseOR(lo)), "classes")

    def keyed(rows: DataFrame, chosen: Column) -> DataFrame:
        made = rows.withColumn("mask", F.explode(chosen))
        return made.select("mask", F.col("bits").bitwiseAND(F.col("mask")).alias("key"), "bits")

    tables = keyed(classes.select("bits"), F.array(*[F.lit(_signed(m)).cast("long") for m in masks]))
    found = []
    for level in range(MOST_LEVELS):
        # the last level compares whatever is left; keys have most of the bits by then
        got = staged(_under_keys(tables, radius, few if level + 1 < MOST_LEVELS else 1 << 62), "links")
        found.append(got.where("apart is not null"))
        hot = got.where("apart is null").select(F.col("a").alias("mask"), F.col("b").alias("bits"))
        used = [r[0] for r in hot.select("mask").distinct().collect()]  # a number that the radius and the level bound
        if not used:
            break
        finer = F.create_map(*[x for m in used for x in (F.lit(m).cast("long"), F.array(*[F.lit(_signed(m & (1 << 64) - 1 | p)).cast("long") for p in _parts(m & (1 << 64) - 1, radius + 1)]))])
        tables = keyed(hot.select("bits", finer[F.col("mask")].alias("finer")), F.col("finer")).distinct()
    pairs = reduce(DataFrame.unionAll, found).distinct()
    own = classes.select("bits", "class_id")
    named = pairs.join(own.select(F.col("bits").alias("a"), F.col("class_id").alias("x")), "a").join(own.select(F.col("bits").alias("b"), F.col("class_id").alias("y")), "b")
    x, y = (F.coalesce(c, F.lit(NULL_KEY)) for c in ("x", "y"))
    pairs = named.select(F.nullif(F.least(x, y), F.lit(NULL_KEY)).alias("a"), F.greatest(x, y).alias("b"), F.col("apart").alias("bits"))
    members = prints.join(classes.select("fingerprint", "class_id"), "fingerprint").select("doc_id", "class_id")
    return members, pairs


def near_fingerprints(docs: DataFrame, radius: int = 3) -> DataFrame:
    """doc_id, class_id (least doc_id with the same fingerprint) and n_links (other
    classes within ``radius`` bits) of every row of ``docs``."""
    prints = staged(document_fingerprints(docs), "prints")
    members, pairs = within_radius(prints, radius)
    ends = pairs.select("a").unionAll(pairs.select(F.col("b").alias("a"))).groupBy("a").agg(F.count("*").alias("n"))
    return members.join(ends, F.col("class_id").eqNullSafe(F.col("a")), "left").select("doc_id", "class_id", F.coalesce("n", F.lit(0)).cast("long").alias("n_links"))
