"""Sub-word pieces: encode and decode with a SentencePiece merge-type model.

Instead of replaying merges over a whole text, each prefix of a text keeps the
one piece that its encoding ends with. A piece that an automaton finds ending
at a position belongs there if it is itself reachable by merging and may follow
the piece that ends where it starts, which a test of the two pieces alone
settles. The ids are then read off from the end backwards.

A text is cut first where no piece can span: before a space mark that follows
another character, and around characters that occur in no longer piece. Cuts
repeat within a corpus, so their results are kept in a table bounded in keys and,
as long cuts are never kept, in bytes.

Nulls encode as empty; an empty text has no ids and decodes to an empty text.
Texts count whole, however long. Repeated rows give repeated results. Of pieces
with equal scores the leftmost pair merges first, as in the library. An empty
table gives no rows. Other columns pass through ``encode_pieces`` and
``decode_pieces``; one named like the new column is replaced.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import ahocorasick
import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql.types import ArrayType, IntegerType, StringType, StructField, StructType

from .common import Kept, held_by, only, spliced, texts_of

SPACE = "▁"
#: Cuts of a generation that one Python worker keeps.
KEPT_CUTS = 150_000
KEPT_UNITS = 250_000
#: Size of the texts that are encoded together, and the length from which one goes alone.
TOGETHER_CHARS, MOST_CHARS = 1 << 21, 1 << 20
SPLICED = 256
#: Marks that usually end a word.
MARKS = ".,;:!?)\"'*$%&#"
KEPT_PAIRS = 400_000


class PieceCodec:
    """Ids of a merge-type SentencePiece model without its encoder."""

    def __init__(self, model_file: str):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=model_file)
        n = sp.get_piece_size()
        self.pieces = [sp.id_to_piece(i) for i in range(n)]
        self.special = {i for i in range(n) if sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i)}
        self.byte_of = {i: int(self.pieces[i][3:5], 16) for i in range(n) if sp.is_byte(i)}
        self.byte_id = {b: i for i, b in self.byte_of.items()}
        self.unknown = sp.unk_id()
        self.id_of = {p: i for i, p in enumerate(self.pieces) if i not in self.special and i not in self.byte_of}
        self.score = {p: sp.get_score(i) for p, i in self.id_of.items()}
        self.spans_space = any(SPACE in p[1:] and p.strip(SPACE) and SPACE in p.lstrip(SPACE) for p in self.id_of)
        joined = {c for p in self.id_of if len(p) > 1 for c in p}
        self.newline_alone = "\n" not in joined
        self.inside = {p[i : i + 2].replace(SPACE, " ") for p in self.id_of for i in range(len(p) - 1)}
        self.found = ahocorasick.Automaton()
        for p in self.id_of:
            if len(p) > 1:
                self.found.add_word(p, p)
        self.found.make_automaton()
        self.reachable: dict[str, bool] = {}
        self.fits: dict[tuple[str, str], bool] = {}
        self.unit = Kept(self._unit, KEPT_UNITS)
        self.bare = Kept(self.known, 20_000)
        self.spaced = Kept(lambda word: self.known(" " + word), KEPT_CUTS)

    def merged(self, text: str) -> list[str]:
        """Pieces of a short string by merging its best neighbours."""
        parts, score = list(text), self.score
        while len(parts) > 1:
            best, at = None, -1
            for i in range(len(parts) - 1):
                s = score.get(parts[i] + parts[i + 1])
                if s is not None and (best is None or s > best):
                    best, at = s, i
            if at < 0:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts

    def _whole(self, piece: str) -> bool:
        got = self.reachable.get(piece)
        if got is None:
            got = self.reachable[piece] = self.merged(piece) == [piece]
        return got

    def _fit(self, left: str, right: str) -> bool:
        key = (left, right)
        got = self.fits.get(key)
        if got is None:
            if len(self.fits) >= KEPT_PAIRS:
                self.fits.clear()
            got = self.fits[key] = self._whole(right) and self.merged(left + right) == [left, right]
        return got

    def split(self, cut: str) -> list[str]:
        """Pieces of a cut: unique last piece of every prefix, then backwards.
        The automaton tells longer pieces first; a prefix that none of them
        ends takes its last character."""
        n, fits = len(cut), self.fits
        last = [""] * (n + 1)
        done = 0
        for end, piece in self.found.iter(cut):
            i = end + 1
            if last[i]:
                continue
            while done < end:
                done += 1
                if not last[done]:
                    last[done] = cut[done - 1]
            j = i - len(piece)
            if j:
                ok = fits.get((last[j], piece))
                if ok is None:
                    ok = self._fit(last[j], piece)
            else:
                ok = self._whole(piece)
            if ok:
                last[i] = piece
        for i in range(done + 1, n + 1):
            if not last[i]:
                last[i] = cut[i - 1]
        out, i = [], n
        while i:
            out.append(last[i])
            i -= len(last[i])
        return out[::-1]

    def ids_of(self, pieces: list[str]) -> list[int]:
        ids = []
        for p in pieces:
            i = self.id_of.get(p)
            if i is not None:
                ids.append(i)
            elif self.byte_id:
                ids.extend(self.byte_id[b] for b in p.encode("utf-8", "surrogatepass"))
            else:
                ids.append(self.unknown)
        return ids

    def raw(self, ids: list[int]) -> bytes:
        """Bytes of ids before the leading space mark goes: valid UTF-8 from
        whole pieces, what the byte pieces hold otherwise."""
        return b"".join(
            bytes([self.byte_of[i]]) if i in self.byte_of else b"" if i in self.special and i != self.unknown else " ⁇ ".encode() if i == self.unknown else self.pieces[i].replace(SPACE, " ").encode()
            for i in ids
        )

    def _unit(self, unit: str) -> bytes:
        ids = self.ids_of(self.split(unit.replace(" ", SPACE)))
        return b"%b %b" % (",".join(map(str, ids)).encode(), self.raw(ids))

    def known(self, cut: str) -> bytes:
        """The listed ids of a cut, a blank, and its bytes, as one object, since many
        are kept. Space marks are blanks in cuts. The marks at its end go apart if the
        characters they part stand side by side in no piece."""
        word = cut.rstrip(MARKS)
        n = len(word)
        if not 0 < n < len(cut) or cut[n - 1 : n + 1] in self.inside:
            return self.unit[cut]
        (a, _, x), (b, _, y) = self.unit[word].partition(b" "), self.unit[cut[n:]].partition(b" ")
        return b"%b,%b %b%b" % (a, b, x, y)

    def parts(self, text: str) -> list[bytes]:
        """What is known of each cut of a text that is not empty."""
        if self.spans_space:
            return [self.bare[" " + text.replace(SPACE, " ")]]
        out: list[bytes] = []
        for k, line in enumerate(text.split("\n") if self.newline_alone else [text]):
            if k:
                out.append(self.bare["\n"])
            line = line.replace(SPACE, " ") if SPACE in line else line
            words = line.split(" ")
            if line and "  " not in line and line[0] != " " and line[-1] != " ":
                if k:
                    out.append(self.bare[words[0]])
                    del words[0]
                out.extend(map(self.spaced.__getitem__, words))
                continue
            run = 0 if k else 1
            for i, w in enumerate(words):
                run += i > 0
                if w:
                    out.append(self.bare[" " * run + w])
                    run = 0
            if run:
                out.append(self.bare[" " * run])
        return out

    def encode(self, text: str | None) -> list[int]:
        ids: list[int] = []
        for got in self.parts(text) if text else ():
            ids.extend(map(int, got.partition(b" ")[0].split(b",")))
        return ids

    def decode(self, ids: list[int]) -> str:
        """Text of any ids; byte pieces that form no character become U+FFFD,
        and the space that encoding put first goes."""
        shown = self.shown(self.raw(ids))
        return shown[1:] if ids and self.pieces[ids[0]].startswith(SPACE) and shown.startswith(" ") else shown

    @staticmethod
    def shown(raw: bytes) -> str:
        try:
            return raw.decode()
        except UnicodeDecodeError:
            out, i = [], 0
            while i < len(raw):
                b = raw[i]
                size = 1 if b < 0x80 else 2 if b >> 5 == 6 else 3 if b >> 4 == 14 else 4 if b >> 3 == 30 else 1
                try:
                    out.append(raw[i : i + size].decode())
                    i += size
                except UnicodeDecodeError:
                    out.append("�")
                    i += 1
            return "".join(out)

    @staticmethod
    def _digest(n: int, listed: bytes, raw: bytes) -> tuple[int, str, str]:
        shown = PieceCodec.shown(raw)
        return n, hashlib.sha256(listed).hexdigest(), hashlib.sha256((shown[1:] if shown.startswith(" ") else shown).encode()).hexdigest()

    def digest(self, text: str | None) -> tuple[int, str, str]:
        """Number of ids, and the digests of the listed ids and the decoded text."""
        got = [g.partition(b" ") for g in self.parts(text)] if text else []
        return self._digest(sum(g[0].count(b",") + 1 for g in got), b",".join(g[0] for g in got), b"".join(g[2] for g in got))

    def digests(self, texts: list[str]) -> list[tuple[int, str, str]]:
        out: list = []
        lo = n = 0
        for hi, t in enumerate(texts):
            n += len(t)
            if n >= TOGETHER_CHARS:
                out += self._together(texts[lo : hi + 1])
                lo, n = hi + 1, 0
        return out + self._together(texts[lo:])

    def _together(self, texts: list[str]) -> list[tuple[int, str, str]]:
        """The same of many texts: different cuts are looked up once, and their
        ids and bytes put together by array operations. Texts with other runs of
        blanks than single spaces between words go one by one."""
        plain = [
            0 < len(t) < MOST_CHARS and not (self.spans_space or not self.newline_alone or "\0" in t or SPACE in t or "  " in t or " \n" in t or "\n " in t or "\n\n" in t or t[0] in " \n" or t[-1] in " \n")
            for t in texts
        ]
        out: list = [None if p else self.digest(t) for t, p in zip(texts, plain)]
        some = [k for k, p in enumerate(plain) if p]
        if not some:
            return out
        marked = pa.array([" " + texts[k].replace("\n", "\0\n\0").replace(" ", "\0 ") for k in some], pa.large_string())
        lists = pc.split_pattern(marked, "\0")
        cuts = lists.values.dictionary_encode()
        got = [self.known(cut).partition(b" ") for cut in cuts.dictionary.to_pylist()]
        which, bounds = cuts.indices.to_numpy(), lists.offsets.to_numpy()
        count = np.concatenate([[0], np.cumsum(np.fromiter((g[0].count(b",") + 1 for g in got), np.int64, len(got))[which])])[bounds]
        sides = []
        for values in ([g[0] + b"," for g in got], [g[2] for g in got]):
            size = np.fromiter(map(len, values), np.int64, len(values))
            sides.append((np.frombuffer(b"".join(values), np.uint8), np.cumsum(size) - size, size))
        for lo in range(0, len(some), SPLICED):
            near = bounds[lo : lo + SPLICED + 1]
            parts = [spliced(*side, which[near[0] : near[-1]]) for side in sides]
            (listed, at), (raw, to) = ((flat.tobytes(), begins[near - near[0]].tolist()) for flat, begins in parts)
            for i, k in enumerate(some[lo : lo + SPLICED]):
                out[k] = self._digest(int(count[lo + i + 1] - count[lo + i]), listed[at[i] : at[i + 1] - 1], raw[to[i] : to[i + 1]])
        return out


_codecs: dict[str, PieceCodec] = {}
held_by("pieces", _codecs.clear)


def codec(model_file: str) -> PieceCodec:
    """The codec of a worker process, made once."""
    if model_file not in _codecs:
        _codecs[model_file] = PieceCodec(model_file)
    return _codecs[model_file]


def encode_pieces(docs: DataFrame, model_file: str, text: str = "text", ids: str = "ids") -> DataFrame:
    """``docs`` with an array of ids; a column of that name is replaced."""
    kept = docs.drop(ids)
    at = kept.columns.index(text)
    schema = StructType([*kept.schema.fields, StructField(ids, ArrayType(IntegerType()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        only("pieces")
        use = codec(model_file)
        for b in batches:
            made = pa.array([use.encode(t) for t in texts_of(b.column(at))], pa.list_(pa.int32()))
            yield pa.RecordBatch.from_arrays([*b.columns, made], names=[*b.schema.names, ids])

    return kept.mapInArrow(run, schema)


def decode_pieces(encoded: DataFrame, model_file: str, ids: str = "ids", text: str = "decoded") -> DataFrame:
    """``encoded`` with the text of each array of ids."""
    kept = encoded.drop(text)
    at = kept.columns.index(ids)
    schema = StructType([*kept.schema.fields, StructField(text, StringType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        only("pieces")
        use = codec(model_file)
        for b in batches:
            made = pa.array([use.decode(x or []) for x in b.column(at).to_pylist()], pa.string())
            yield pa.RecordBatch.from_arrays([*b.columns, made], names=[*b.schema.names, text])

    return kept.mapInArrow(run, schema)


def spans(texts: pa.Array) -> list[tuple[int, int]]:
    """(first, number) of rows that hold some ``TOGETHER_CHARS`` bytes each."""
    upto = np.cumsum(pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False), dtype=np.int64)
    first = np.flatnonzero(np.diff(upto // TOGETHER_CHARS, prepend=-1))
    return list(zip(first.tolist(), np.diff(first, append=len(upto)).tolist()))


def piece_digests(docs: DataFrame, model_file: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256 and decoded_sha256 of every whole text, in
    one pass and without a shuffle. Repeated rows give repeated results."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        only("pieces")
        use = codec(model_file)
        for b in batches:
            for lo, n in spans(b.column(1)):
                part = b.slice(lo, n)
                made = use.digests(texts_of(part.column(1)))
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), pa.array([m[0] for m in made], pa.int64()), pa.array([m[1] for m in made]), pa.array([m[2] for m in made])],
                    names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"],
                )

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
