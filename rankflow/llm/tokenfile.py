"""Token files: flat unsigned ids plus 64-bit document offsets.

Format of one chunk ``c`` in a folder (little-endian, no headers):

* ``c.ids``      ids of all its documents in key order, each document's ids
                 followed by the end id; two bytes each if the vocabulary has at
                 most 65,536 ids, else four
* ``c.offsets``  n + 1 64-bit offsets into ``c.ids``, in ids
* ``c.keys``     n 64-bit document keys

Chunks are contiguous key ranges in ascending order. The manifest (a Parquet
table: chunk, n_docs, n_tokens, start) holds each chunk's base, the prefix sum
of the sizes before it, so any document is found by one binary search and one
slice, memory-mapped where files lie on a mount. Files are written as their
documents go by, so a task holds a batch of texts, however large its chunk.

Null texts are empty; null keys sort first and are stored as the smallest
64-bit integer. Texts count whole, however long. Repeated keys keep all their
rows, ordered by text (ties are equal rows), in one chunk. An empty table gives
an empty manifest. Other columns are never looked at, whatever their names.
"""

from __future__ import annotations

import json
import sys
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import FileOut, Kept, chunk_bounds, chunk_of, fresh_path, held_by, map_file, only, spliced, staged, texts_of

#: Other white space than space and line end, and the mark put between cuts.
OTHER_BLANKS = "[\x00\t\x0b-\r\x1c-\x1f\x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]"
KEPT_UNITS = 400_000
#: Texts that are encoded together.
TOGETHER, MOST_CHARS = 4_000, 1 << 25
NULL_KEY = -(1 << 63)
#: Fixed value: the pattern of byte-level BPE's units.
UNIT = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
ROWS_PER_CHUNK = 4_000


class ByteEncoder:
    """The tokenizers library's ids of whole texts.

    Byte-level BPE splits a text into units by a pattern, and a new unit always
    starts at a single space or line end between other characters. So the texts
    of a batch are cut there and each different cut is split into units once;
    the library's model gives the ids of each different unit, of which many are
    kept from batch to batch. Texts with other white space, with white space next
    to white space or at an edge, or with an added token, go to the library whole.
    """

    def __init__(self, file: str):
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(file)
        self.dtype = dtype_of(self.library.get_vocab_size())
        self.code = "I" if self.dtype == "<u4" else "H"
        before = self.library.pre_tokenizer
        shape = json.loads(before.__getstate__()) if before is not None else {}
        self.whole_only = not (self.library.normalizer is None and shape.get("type") == "ByteLevel" and shape["use_regex"] and not shape["add_prefix_space"])
        self.added = [t.content for t in self.library.get_added_tokens_decoder().values()]
        self.units = regex.compile("\x00|" + UNIT.replace(r"[^\s", r"[^\x00\s"))
        printable = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174]
        rest = [b for b in range(256) if b not in printable]
        self.shown = {b: chr(256 + i) for i, b in enumerate(rest)}  # the model's alphabet has no blanks
        self.unit = Kept(self._unit, KEPT_UNITS)

    def _unit(self, unit: str) -> bytes:
        if unit == "\x00":
            return b""
        text = unit.replace(" ", self.shown[32]) if unit.isascii() and unit.isprintable() else unit.encode("utf-8", "surrogatepass").decode("latin-1").translate(self.shown)
        ids = array(self.code, [t.id for t in self.library.model.tokenize(text)])
        if sys.byteorder == "big":
            ids.byteswap()
        return ids.tobytes()

    def whole(self, text: str) -> bytes:
        return np.array(self.library.encode(text, add_special_tokens=False).ids, dtype=self.dtype).tobytes()

    def _plain(self, texts: list[str]) -> list[bool]:
        if self.whole_only:
            return [False] * len(texts)
        other = pc.match_substring_regex(pa.array(texts, pa.large_string()), OTHER_BLANKS).to_pylist()
        return [
            0 < len(t) < MOST_CHARS and not o and "  " not in t and " \n" not in t and "\n " not in t and "\n\n" not in t and t[0] not in " \n" and t[-1] not in " \n" and not any(a in t for a in self.added)
            for t, o in zip(texts, other)
        ]

    def encode(self, texts: list[str]) -> list[bytes]:
        """The bytes of the ids of each text."""
        out: list[bytes] = []
        lo = n = 0
        for hi, t in enumerate(texts):
            n += len(t)
            if n >= MOST_CHARS:
                out += self._together(texts[lo : hi + 1])
                lo, n = hi + 1, 0
        return out + self._together(texts[lo:])

    def _together(self, texts: list[str]) -> list[bytes]:
        if not texts:
            return []
        plain = self._plain(texts)
        out = [b"" if p or not t else self.whole(t) for t, p in zip(texts, plain)]
        some = [k for k, p in enumerate(plain) if p]
        if not some:
            return out
        # a cut keeps its space; a mark that such texts do not hold parts the cuts
        marked = pa.array([texts[k].replace("\n", "\x00\n\x00").replace(" ", "\x00 ") for k in some], pa.large_string())
        lists = pc.split_pattern(marked, "\x00")
        cuts = lists.values.dictionary_encode()
        all_cuts = pa.ListArray.from_arrays(pa.array([0, len(cuts.dictionary)], pa.int32()), cuts.dictionary.cast(pa.string()))
        units = pa.array(self.units.findall(pc.binary_join(all_cuts, "\x00")[0].as_py()), pa.large_string()).dictionary_encode()
        ids = list(map(self.unit.__getitem__, units.dictionary.to_pylist()))
        known = np.frombuffer(b"".join(ids), self.dtype)
        size = np.fromiter(map(len, ids), np.int64, len(ids)) // known.itemsize
        which = units.indices.to_numpy()
        flat, begins = spliced(known, np.cumsum(size) - size, size, which)
        edges = np.flatnonzero(which == units.dictionary.index("\x00").as_py())
        first = begins[np.concatenate([[0], edges + 1])]
        last = begins[np.concatenate([edges, [len(which)]])]
        flat, begins = spliced(flat, first, last - first, cuts.indices.to_numpy())
        bounds = begins[lists.offsets.to_numpy()]
        data, width = flat.tobytes(), flat.itemsize
        for k, i, j in zip(some, bounds[:-1].tolist(), bounds[1:].tolist()):
            out[k] = data[i * width : j * width]
        return out


def dtype_of(n_ids: int) -> str:
    """Two bytes an id if they suffice, else four."""
    return "<u4" if n_ids > 1 << 16 else "<u2"


_encoders: dict[str, ByteEncoder] = {}
held_by("tokens", _encoders.clear)


def encoder(file: str) -> ByteEncoder:
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    if file not in _encoders:
        _encoders[file] = ByteEncoder(file)
    return _encoders[file]


def write_token_files(docs: DataFrame, tokenizer: str, end_id: int, folder: str, key: str = "doc_id", text: str = "text", rows_per_chunk: int = ROWS_PER_CHUNK) -> DataFrame:
    """Write ``docs`` as token files into ``folder`` (on storage that executors
    share) and return the manifest. Text moves once, into key ranges; each
    chunk is written whole by one task, so a lost task only repeats its own."""
    rows = docs.select(F.col(key).cast("long").alias("_key"), F.col(text).alias("_text"))
    bounds = chunk_bounds(rows, "_key", rows_per_chunk)
    placed = rows.withColumn("_chunk", chunk_of(F.col("_key"), bounds))
    dealt = placed.repartition(max(1, len(bounds)), "_chunk").sortWithinPartitions("_chunk", "_key", "_text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        only("tokens")
        use = encoder(tokenizer)
        end = np.array([end_id], dtype=use.dtype).tobytes()
        width = len(end)
        now, files, n_docs, at = None, [], 0, 0

        def begin(chunk: int) -> list[FileOut]:
            opened = [FileOut(f"{folder}/{chunk:08d}.{kind}") for kind in ("ids", "offsets", "keys")]
            opened[1].write(bytes(8))
            return opened

        def put(some: list[list[bytes]]) -> None:
            for f, parts in zip(files, some):
                f.write(b"".join(parts))
                parts.clear()

        def close() -> pa.RecordBatch:
            for f in files:
                f.close()
            return pa.RecordBatch.from_arrays([pa.array([now], pa.int64()), pa.array([n_docs], pa.int64()), pa.array([at], pa.int64())], names=["chunk", "n_docs", "n_tokens"])

        for whole in batches:
            for lo in range(0, whole.num_rows, TOGETHER):
                b = whole.slice(lo, TOGETHER)
                some: list[list[bytes]] = [[], [], []]
                for k, c, ids in zip(b.column(0).to_pylist(), b.column(2).to_pylist(), use.encode(texts_of(b.column(1)))):
                    if c != now:
                        if now is not None:
                            put(some)
                            yield close()
                        now, files, n_docs, at = c, begin(c), 0, 0
                    n_docs, at = n_docs + 1, at + len(ids) // width + 1
                    some[0] += (ids, end)
                    some[1].append(at.to_bytes(8, "little"))
                    some[2].append((NULL_KEY if k is None else k).to_bytes(8, "little", signed=True))
                put(some)
        if now is not None:
            yield close()

    sizes = staged(dealt.mapInArrow(run, "chunk long, n_docs long, n_tokens long"), "manifest")
    before = W.orderBy("chunk").rowsBetween(W.unboundedPreceding, -1)  # a row a chunk, at most MAX_CHUNKS
    return sizes.withColumn("start", F.coalesce(F.sum("n_tokens").over(before), F.lit(0)))


def read_token_files(manifest: DataFrame, folder: str, dtype: str, parts: int) -> DataFrame:
    """doc_id, start, n_tokens and the bytes of the ids of every document, from
    the memory-mapped files of each chunk of ``manifest``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for c, base in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                name = f"{folder}/{c:08d}"
                ids, at, keys = map_file(f"{name}.ids", dtype), map_file(f"{name}.offsets", "<i8"), map_file(f"{name}.keys", "<i8")
                for lo in range(0, len(keys), 256):
                    hi = min(lo + 256, len(keys))
                    yield pa.RecordBatch.from_arrays(
                        [
                            pa.array(keys[lo:hi], pa.int64(), mask=keys[lo:hi] == NULL_KEY),
                            pa.array(base + at[lo:hi], pa.int64()),
                            pa.array(at[lo + 1 : hi + 1] - at[lo:hi], pa.int64()),
                            pa.array([ids[at[i] : at[i + 1]].astype("<u4").tobytes() for i in range(lo, hi)], pa.binary()),
                        ],
                        names=["doc_id", "start", "n_tokens", "ids"],
                    )

    return manifest.select("chunk", "start").repartition(max(1, parts), "chunk").mapInArrow(run, "doc_id long, start long, n_tokens long, ids binary")


def ids_checksum(read: DataFrame) -> DataFrame:
    """Replaces the ids with their crc32 as little-endian 32-bit integers."""
    return read.select("doc_id", "start", "n_tokens", F.crc32("ids").alias("ids_crc32"))


def token_file_digests(docs: DataFrame, tokenizer: str, end_id: int = 0, rows_per_chunk: int = ROWS_PER_CHUNK) -> DataFrame:
    """Writes ``docs`` to files in the shared folder and checks what they hold."""
    spark: SparkSession = docs.sparkSession
    folder = fresh_path(spark, "tokens")
    manifest = write_token_files(docs, tokenizer, end_id, folder, rows_per_chunk=rows_per_chunk)
    from tokenizers import Tokenizer

    dtype = dtype_of(Tokenizer.from_file(tokenizer).get_vocab_size())
    return ids_checksum(read_token_files(manifest, folder, dtype, int(spark.conf.get("spark.sql.shuffle.partitions"))))
