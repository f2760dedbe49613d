"""FLAC streams in binary columns: encode bytes as 8-bit samples, decode Rice
residuals and linear predictors, verify checksums, cut PCM blocks at seekable
sample offsets.

The decoder reads mono or multi-channel streams of 4 to 24 bits with constant,
verbatim, fixed and LPC subframes, both Rice codings, escaped partitions and
channel decorrelation. Mono frames of one Rice partition, which the encoder
writes, take a fast path that decodes all frames of a batch in step; all others
are read one after another. A header's CRC-8, a frame's CRC-16, the block and
frame sizes that STREAMINFO promises and the stream's MD5 are always verified; a
stream that fails, in whatever way, raises ``FlacError``. A span of samples is
read from the frames that hold it alone, found by the seek table.

Encoding pads UTF-8 bytes with spaces to a positive multiple of 192, so null
and empty texts give one block of 192 samples, and an empty table no rows.
Samples are bytes less 128. Texts count whole, however long; repeated rows and
equal texts give equal streams. Of predictors that cost the same the lowest order
is taken. Other columns pass through; those named like new ones are replaced.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType, LongType, StructField, StructType

#: Samples of a full block; the last block of a stream may be shorter.
BLOCK = 1152
UNIT = 192
RATE = 8000


class FlacError(ValueError):
    """A stream that is not what its checksums or its format say."""


def _crc_table(poly: int, bits: int, width: int) -> np.ndarray:
    """Remainders of all ``width``-bit words by a polynomial of ``bits`` bits."""
    top, mask = 1 << (bits - 1), (1 << bits) - 1
    crc = np.arange(1 << width, dtype=np.uint32) << (bits - width)
    for _ in range(width):
        crc = np.where(crc & top, (crc << 1) ^ poly, crc << 1) & mask
    return crc


_CRC8 = _crc_table(0x07, 8, 8)
_CRC8_LIST = _CRC8.tolist()
_CRC16 = _crc_table(0x8005, 16, 16).astype(np.uint16)


def crc8(data: bytes) -> int:
    crc = 0
    for b in data:
        crc = _CRC8_LIST[crc ^ b]
    return crc


def crc16_each(frames: list[bytes]) -> np.ndarray:
    """CRC-16 of many byte strings at once; zeros in front change nothing."""
    out = np.zeros(len(frames), np.uint16)
    order = np.argsort([len(f) for f in frames], kind="stable")
    for lo in range(0, len(order), 256):
        some = order[lo : lo + 256]
        width = (max(len(frames[i]) for i in some) + 1) // 2 * 2
        words = np.frombuffer(b"".join(frames[i].rjust(width, b"\0") for i in some), ">u2").reshape(len(some), -1).T.astype(np.uint16, order="C")
        crc = np.zeros(len(some), np.uint16)
        for w in words:
            crc = _CRC16[crc ^ w]
        out[some] = crc
    return out


def _coded_number(n: int) -> bytes:
    """A frame number in the extended UTF-8 code of frame headers."""
    if n < 0x80:
        return bytes([n])
    tail = []
    lead = 0x3F
    while n > lead:
        tail.append(0x80 | n & 0x3F)
        n >>= 6
        lead >>= 1
    return bytes([(~(2 * lead + 1)) & 0xFF | n, *reversed(tail)])


def _frame_header(n: int, number: int) -> bytes:
    size, extra = (3, b"") if n == BLOCK else (6, bytes([n - 1])) if n <= 256 else (7, struct.pack(">H", n - 1))
    head = bytes([0xFF, 0xF8, size << 4 | 4, 1 << 1]) + _coded_number(number) + extra
    return head + bytes([crc8(head)])


def _encode_lanes(x: np.ndarray) -> list[bytes]:
    """Subframes of equally long 8-bit blocks (a row each)."""
    lanes, n = x.shape
    out: list[bytes | None] = [None] * lanes
    wide = x.astype(np.int16)
    res = {0: wide, 1: np.diff(wide, axis=1), 2: np.diff(wide, n=2, axis=1)}
    cost = np.stack([np.abs(r).sum(axis=1, dtype=np.int64) for r in res.values()])
    best = cost.argmin(axis=0)
    flat = (x == x[:, :1]).all(axis=1)
    for i in np.flatnonzero(flat):
        out[i] = bytes([0, int(x[i, 0]) & 0xFF])
    for order, r in res.items():
        mine = np.flatnonzero((best == order) & ~flat)
        if not len(mine):
            continue
        u = r[mine].astype(np.int32)
        u = (u << 1) ^ (u >> 31)
        mean = u.mean(axis=1) * 0.69
        k = np.clip(np.floor(np.log2(np.maximum(mean, 1))), 0, 14).astype(np.int32)[:, None]
        q = u >> k
        length = q + 1 + k
        lead = 8 + 8 * order + 2 + 4 + 4
        ends = np.cumsum(length, axis=1, dtype=np.int64) + lead
        total = (ends[:, -1] + 7) // 8 * 8
        raw = total >= 8 + 8 * n
        for i in mine[raw]:
            out[i] = b"\x02" + x[i].tobytes()
        if raw.all():
            continue
        keep = ~raw
        mine, u, k, q, length, ends, total = mine[keep], u[keep], k[keep], q[keep], length[keep], ends[keep], total[keep]
        base = np.concatenate([[0], np.cumsum(total)])
        bits = np.zeros(base[-1], np.uint8)
        stop = (ends - length + q + base[:-1, None]).astype(np.int64)
        bits[stop.ravel()] = 1
        for deep in np.unique(k):
            at = np.flatnonzero(k[:, 0] == deep)
            s, v = stop[at], u[at]
            for j in range(int(deep)):
                bits[(s + (1 + j)).ravel()] = ((v >> (int(deep) - 1 - j)) & 1).ravel()
        front = np.zeros((len(mine), lead), np.uint8)
        kind = 0b001000 | order
        for j in range(6):
            front[:, 1 + j] = (kind >> (5 - j)) & 1
        for o in range(order):
            sample = x[mine, o].astype(np.int16) & 0xFF
            for j in range(8):
                front[:, 8 + 8 * o + j] = (sample >> (7 - j)) & 1
        for j in range(4):
            front[:, lead - 4 + j] = (k[:, 0] >> (3 - j)) & 1
        bits[(base[:-1, None] + np.arange(lead)).ravel()] = front.ravel()
        packed = np.packbits(bits).tobytes()
        for lane, lo, hi in zip(mine.tolist(), (base[:-1] // 8).tolist(), (base[1:] // 8).tolist()):
            out[lane] = packed[lo:hi]
    return out


def padded(text: str | None) -> bytes:
    raw = (text or "").encode("utf-8", "surrogatepass")
    return raw.ljust(max(UNIT, -(-len(raw) // UNIT) * UNIT), b" ")


def encode_streams(payloads: list[bytes]) -> list[bytes]:
    """A FLAC stream of each payload (whose length is a multiple of 192)."""
    blocks: dict[int, list[tuple[int, int]]] = defaultdict(list)
    data = [np.frombuffer(p, np.uint8) ^ np.uint8(0x80) for p in payloads]
    for i, d in enumerate(data):
        for lo in range(0, len(d), BLOCK):
            blocks[min(BLOCK, len(d) - lo)].append((i, lo))
    bodies: dict[tuple[int, int], bytes] = {}
    for n, at in blocks.items():
        for lo in range(0, len(at), 512):
            some = at[lo : lo + 512]
            x = np.stack([data[i][p : p + n] for i, p in some]).view(np.int8)
            for (i, p), sub in zip(some, _encode_lanes(x)):
                bodies[i, p] = _frame_header(n, p // BLOCK) + sub
    keys = list(bodies)
    frames = {key: bodies[key] + struct.pack(">H", c) for key, c in zip(keys, crc16_each([bodies[key] for key in keys]).tolist())}
    out = []
    for i, d in enumerate(data):
        starts = range(0, len(d), BLOCK)
        mine = [frames[i, p] for p in starts]
        sizes = [len(f) for f in mine]
        fields = (RATE << 44) | (0 << 41) | (7 << 36) | len(d)
        info = struct.pack(">HH", BLOCK, BLOCK) + max(0, min(sizes)).to_bytes(3, "big") + max(sizes).to_bytes(3, "big") + fields.to_bytes(8, "big") + hashlib.md5(d.tobytes()).digest()
        points, at = [], 0
        for p, size in zip(starts, sizes):
            points.append(struct.pack(">QQH", p, at, min(BLOCK, len(d) - p)))
            at += size
        table = b"".join(points)
        out.append(b"fLaC" + b"\x00" + len(info).to_bytes(3, "big") + info + b"\x83" + len(table).to_bytes(3, "big") + table + b"".join(mine))
    return out


class _Bits:
    """Bits of a byte string, most significant first."""

    #: Bytes of which the set bits are listed at once.
    WINDOW = 1 << 14

    def __init__(self, data: bytes, at: int = 0):
        self.data, self.at = data, at * 8
        self.lo = self.hi = 0
        self.ones: list[int] = []
        self.next = 0

    def take(self, n: int) -> int:
        lo, hi = self.at // 8, (self.at + n + 7) // 8
        if hi > len(self.data):
            raise FlacError("the stream ends inside a frame")
        value = int.from_bytes(self.data[lo:hi], "big") >> (hi * 8 - self.at - n) & ((1 << n) - 1)
        self.at += n
        return value

    def signed(self, n: int) -> int:
        v = self.take(n)
        return v - (1 << n) if n and v >> (n - 1) else v

    def unary(self) -> int:
        """Unset bits before the next set one."""
        start = at = self.at
        while True:
            if not self.lo <= at < self.hi:
                first = at // 8
                if first >= len(self.data):
                    raise FlacError("the stream ends inside a frame")
                part = np.frombuffer(self.data, np.uint8, min(self.WINDOW, len(self.data) - first), first)
                self.lo, self.hi, self.next = first * 8, (first + len(part)) * 8, 0
                self.ones = (np.flatnonzero(np.unpackbits(part)) + self.lo).tolist()
            ones, i = self.ones, self.next
            while i < len(ones) and ones[i] < at:
                i += 1
            self.next = i
            if i < len(ones):
                self.at = ones[i] + 1
                return ones[i] - start
            at = self.hi


#: Fixed values of the format: predictor weights, newest sample first.
FIXED = {0: (), 1: (1,), 2: (2, -1), 3: (3, -3, 1), 4: (4, -6, 4, -1)}


def _residual(bits: _Bits, n: int, order: int) -> list[int]:
    method, parts = bits.take(2), 1 << bits.take(4)
    if method > 1 or n % parts or n // parts < order:
        raise FlacError("a residual's coding is not known")
    width, out = 4 + method, []
    for p in range(parts):
        k = bits.take(width)
        count = n // parts - (order if p == 0 else 0)
        if k == (1 << width) - 1:
            raw = bits.take(5)
            out += [bits.signed(raw) for _ in range(count)]
            continue
        for _ in range(count):
            u = bits.unary() << k | bits.take(k)
            out.append(u >> 1 ^ -(u & 1))
    return out


def _subframe(bits: _Bits, n: int, bps: int) -> list[int]:
    if bits.take(1):
        raise FlacError("a subframe starts with a set bit")
    kind = bits.take(6)
    wasted = bits.unary() + 1 if bits.take(1) else 0
    bps -= wasted
    if kind == 0:
        out = [bits.signed(bps)] * n
    elif kind == 1:
        out = [bits.signed(bps) for _ in range(n)]
    elif 8 <= kind <= 12 or kind >= 32:
        order = kind - 8 if kind < 32 else kind - 31
        out = [bits.signed(bps) for _ in range(order)]
        if kind >= 32:
            precision = bits.take(4) + 1
            shift = bits.signed(5)
            weights = [bits.signed(precision) for _ in range(order)]
        else:
            weights, shift = FIXED[order], 0
        for r in _residual(bits, n, order):
            out.append(r + (sum(w * s for w, s in zip(weights, reversed(out[-order:] if order else []))) >> shift))
    else:
        raise FlacError("a subframe's kind is reserved")
    return [s << wasted for s in out]


def _parse_header(data: bytes, at: int, info: dict) -> tuple[int, int, int, int]:
    """(first byte after the header, samples, channel code, bits a sample)."""
    if len(data) < at + 6 or data[at] != 0xFF or data[at + 1] & 0xFE != 0xF8:
        raise FlacError("no frame where one should start")
    size, rate = data[at + 2] >> 4, data[at + 2] & 15
    channels, depth = data[at + 3] >> 4, data[at + 3] >> 1 & 7
    p, lead = at + 4, data[at + 4]
    p += 1 if lead < 0x80 else 8 - (~lead & 0xFF).bit_length()
    if size == 6:
        n, p = data[p] + 1, p + 1
    elif size == 7:
        n, p = struct.unpack(">H", data[p : p + 2])[0] + 1, p + 2
    elif size == 1:
        n = 192
    elif 2 <= size <= 5:
        n = 576 << (size - 2)
    elif size >= 8:
        n = 256 << (size - 8)
    else:
        raise FlacError("a block size is reserved")
    p += 1 if rate == 12 else 2 if rate in (13, 14) else 0
    if crc8(data[at:p]) != data[p]:
        raise FlacError("a frame header's CRC-8 is wrong")
    if channels > 10 or depth in (3, 7):
        raise FlacError("a frame's channels or sample size are reserved")
    if n > info["most"] or not info["most"]:
        raise FlacError("a block is larger than STREAMINFO says")
    return p + 1, n, channels, {0: info["bps"], 1: 8, 2: 12, 4: 16, 5: 20, 6: 24}[depth]


def _slow_frame(data: bytes, at: int, info: dict) -> tuple[np.ndarray, int]:
    """Samples (channels by n) of a frame and the byte after it."""
    p, n, code, bps = _parse_header(data, at, info)
    bits = _Bits(data, p)
    if code < 8:
        chans = [_subframe(bits, n, bps) for _ in range(code + 1)]
    else:
        chans = [_subframe(bits, n, bps + (code == 9)), _subframe(bits, n, bps + (code != 9))]
    end = -(-bits.at // 8)
    if len(data) < end + 2 or crc16_each([data[at:end]])[0] != struct.unpack(">H", data[end : end + 2])[0]:
        raise FlacError("a frame's CRC-16 is wrong")
    x = np.array(chans, np.int64)
    if code == 8:
        x[1] = x[0] - x[1]
    elif code == 9:
        x[0] = x[0] + x[1]
    elif code == 10:
        mid = x[0] << 1 | x[1] & 1
        x = np.stack([mid + x[1] >> 1, mid - x[1] >> 1])
    return x, end + 2


def _decode_lanes(subs: list[bytes], n: int) -> np.ndarray:
    """Samples of fixed subframes with one Rice partition each, in step."""
    order = subs[0][0] >> 1 & 7
    lead = 8 + 8 * order + 10
    sizes = np.array([len(s) for s in subs], np.int64)
    base = np.concatenate([[0], np.cumsum(sizes)])
    raw = np.frombuffer(b"".join(subs), np.uint8)
    bits = np.unpackbits(raw)
    ones = np.flatnonzero(bits).astype(np.int32)
    if len(bits) >= 1 << 31:
        raise FlacError("a batch is too large")
    nth = np.cumsum(bits, dtype=np.int32)
    nth -= bits  # ones before each bit
    warm = np.stack([raw[base[:-1] + 1 + o].view(np.int8) for o in range(order)], axis=1).astype(np.int32) if order else np.zeros((len(subs), 0), np.int32)
    start = base[:-1] * 8 + lead - 4
    k = (bits[start[:, None] + np.arange(4)] * np.array([8, 4, 2, 1], np.uint8)).sum(axis=1).astype(np.int32)
    at = (start + 4).astype(np.int32)
    count = n - order
    stop = np.empty((count, len(subs)), np.int32)
    begin = np.empty((count, len(subs)), np.int32)
    step = 1 + k
    limit = np.int32(len(bits) - 1)
    for j in range(count):
        begin[j] = at
        s = ones[np.minimum(nth[np.minimum(at, limit)], len(ones) - 1)]
        stop[j] = s
        at = s + step
    if (at > base[1:] * 8).any():
        raise FlacError("a residual runs over its frame")
    u = (stop - begin) << k
    for deep in np.unique(k):
        mine = np.flatnonzero(k == deep)
        low = np.zeros((count, len(mine)), np.int32)
        s = stop[:, mine]
        for j in range(int(deep)):
            low = low << 1 | bits[s + (1 + j)]
        u[:, mine] |= low
    r = (u >> 1) ^ -(u & 1)
    if order == 0:
        return r.T
    if order == 1:
        return np.concatenate([warm.T, r]).cumsum(axis=0).T
    first = np.concatenate([(warm[:, 1] - warm[:, 0])[None], r]).cumsum(axis=0)
    return np.concatenate([warm[:, 0][None], first]).cumsum(axis=0).T


def _read_head(data: bytes) -> tuple[dict, int, list[tuple[int, int, int]]]:
    if data[:4] != b"fLaC":
        raise FlacError("the stream's mark is missing")
    at, info, points, last = 4, None, [], False
    while not last:
        if len(data) < at + 4:
            raise FlacError("the stream ends inside its metadata")
        last, kind, size = data[at] >> 7, data[at] & 0x7F, int.from_bytes(data[at + 1 : at + 4], "big")
        body = data[at + 4 : at + 4 + size]
        if kind == 0:
            if len(body) < 34:
                raise FlacError("STREAMINFO is cut short")
            fields = int.from_bytes(body[10:18], "big")
            least, most = struct.unpack(">HH", body[:4])
            info = {"least": least, "most": most, "frames": (int.from_bytes(body[4:7], "big"), int.from_bytes(body[7:10], "big")), "bps": (fields >> 36 & 31) + 1, "channels": (fields >> 41 & 7) + 1, "total": fields & (1 << 36) - 1, "md5": body[18:34]}
        elif kind == 3:
            points = [p for p in struct.iter_unpack(">QQH", body) if p[0] != (1 << 64) - 1]
        at += 4 + size
    if info is None:
        raise FlacError("the stream has no STREAMINFO")
    return info, at, points


def _promised(info: dict, blocks: list[int], frames: list[int]) -> None:
    """Holds the sizes of all blocks and frames of a stream against STREAMINFO."""
    if any(n < info["least"] for n in blocks[:-1]):
        raise FlacError("a block is smaller than STREAMINFO says")
    least, most = info["frames"]
    if frames and (least and min(frames) != least or most and max(frames) != most):
        raise FlacError("the sizes of frames are not what STREAMINFO says")


def decode_streams(streams: list[bytes], spans: list[tuple[int, int]] | None = None) -> list[tuple[np.ndarray, np.ndarray]]:
    """For each stream its samples (n by channels) and the sample offset at
    which each frame starts. The seek table, where it is whole, tells where
    frames lie; otherwise they are read one after another. With ``spans`` (first
    and end of the wanted samples) only frames that hold some of them are read,
    and only what those frames promise is verified."""
    try:
        return _decoded(streams, spans)
    except FlacError:
        raise
    except (IndexError, KeyError, ValueError, OverflowError, MemoryError, struct.error) as e:
        raise FlacError(f"the stream is damaged: {e}") from e


def _decoded(streams: list[bytes], spans: list[tuple[int, int]] | None) -> list[tuple[np.ndarray, np.ndarray]]:
    heads = [_read_head(s) for s in streams]
    parts: list[dict[int, np.ndarray]] = [{} for _ in streams]
    lanes: dict[tuple[int, int], list[tuple[int, int, bytes]]] = defaultdict(list)
    checks: list[bytes] = []
    wanted: list[int] = []
    for i, (data, (info, at, points)) in enumerate(zip(streams, heads)):
        lo_sample, hi_sample = spans[i] if spans else (0, info["total"] or 1 << 62)
        whole = bool(points) and sum(p[2] for p in points) == info["total"] and info["channels"] == 1 and info["bps"] == 8
        blocks: list[int] = []
        frames: list[int] = []
        if whole:
            ends = [p[1] for p in points[1:]] + [len(data) - at]
            for (sample, offset, n), end in zip(points, ends):
                if sample + n <= lo_sample or sample >= hi_sample:
                    continue
                lo, hi = at + offset, at + end
                body, count, code, bps = _parse_header(data, lo, info)
                if count != n or code or bps != 8 or hi - 2 <= body:
                    raise FlacError("a seek point and its frame disagree")
                blocks.append(n), frames.append(hi - lo)
                checks.append(data[lo : hi - 2])
                wanted.append(data[hi - 2] << 8 | data[hi - 1])
                sub = data[body : hi - 2]
                kind = sub[0]
                if kind == 2 and len(sub) == 1 + n:
                    parts[i][sample] = np.frombuffer(sub, np.int8, n, 1)[None]
                elif kind == 0 and len(sub) == 2:
                    parts[i][sample] = np.full((1, n), np.frombuffer(sub, np.int8, 1, 1)[0])
                elif kind in (16, 18, 20) and not ((sub[1 + (kind >> 1 & 7)] & 0xFC)):
                    lanes[n, kind].append((i, sample, sub))
                else:
                    parts[i][sample] = np.array([_subframe(_Bits(sub), n, 8)], np.int16)
        else:
            near = [p for p in points if p[0] <= lo_sample] if spans else []
            sample, at = (near[-1][0], at + near[-1][1]) if near else (0, at)
            while at < len(data) and sample < hi_sample:
                first = at
                x, at = _slow_frame(data, at, info)
                blocks.append(x.shape[1]), frames.append(at - first)
                if sample + x.shape[1] > lo_sample:
                    parts[i][sample] = x
                sample += x.shape[1]
        if not spans:
            _promised(info, blocks, frames)
    if checks and (crc16_each(checks) != np.array(wanted, np.uint16)).any():
        raise FlacError("a frame's CRC-16 is wrong")
    for (n, _), some in lanes.items():
        for lo in range(0, len(some), 512):
            group = some[lo : lo + 512]
            for (i, sample, _), x in zip(group, _decode_lanes([g[2] for g in group], n)):
                parts[i][sample] = x[None].astype(np.int16)
    out = []
    for i, ((info, _, _), got) in enumerate(zip(heads, parts)):
        at = sorted(got)
        x = np.concatenate([got[p] for p in at], axis=1) if at else np.zeros((info["channels"], 0), np.int16)
        if spans:
            lo, hi = spans[i]
            first = at[0] if at else lo
            out.append((x.T[max(0, lo - first) : max(0, hi - first)], np.array(at, np.int64)))
            continue
        if info["total"] and x.shape[1] != info["total"]:
            raise FlacError("the stream has too few samples")
        size = -(-info["bps"] // 8)
        flat = x.T.astype("<i4").reshape(-1, 1).view(np.uint8).reshape(-1, 4)[:, :size] if size > 1 else x.T.astype(np.int8)
        if any(info["md5"]) and hashlib.md5(np.ascontiguousarray(flat).tobytes()).digest() != info["md5"]:
            raise FlacError("the stream's MD5 is wrong")
        out.append((x.T, np.array(at, np.int64)))
    return out


def features(samples: np.ndarray) -> str:
    """Mean, root mean square and sign changes of mono samples."""
    x = samples.astype(np.int64)
    n = max(1, len(x))
    changes = int(((x[1:] >= 0) != (x[:-1] >= 0)).sum())
    return f"n={len(x)};mean={x.sum() / n:.4f};rms={(int((x * x).sum()) / n) ** 0.5:.4f};crossings={changes}"


def encode_column(docs: DataFrame, text: str = "text", media: str = "media") -> DataFrame:
    """``docs`` with each text's FLAC stream in place of the text, and n_bytes."""
    kept = docs.drop(media, "n_bytes")
    at = kept.columns.index(text)
    names = [c for c in kept.columns if c != text]
    schema = StructType([*kept.select(*names).schema.fields, StructField("n_bytes", LongType()), StructField(media, BinaryType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for lo in range(0, whole.num_rows, 128):
                b = whole.slice(lo, 128)
                texts = b.column(at).to_pylist()
                n = pa.array([len((t or "").encode("utf-8", "surrogatepass")) for t in texts], pa.int64())
                made = pa.array(encode_streams([padded(t) for t in texts]), pa.binary())
                yield pa.RecordBatch.from_arrays([*(c for k, c in enumerate(b.columns) if k != at), n, made], names=schema.names)

    return kept.mapInArrow(run, schema)


def pcm_blocks(stored: DataFrame, key: str = "doc_id", media: str = "media") -> DataFrame:
    """key, block, sample_offset, n_samples, channels and pcm (samples of one
    byte each if they fit, else of four, little-endian) of every stored stream:
    the blocks from any sample on are a filter on sample_offset."""
    schema = f"`{key}` {dict(stored.dtypes)[key]}, block int, sample_offset long, n_samples int, channels int, pcm binary"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for lo in range(0, whole.num_rows, 64):
                b = whole.slice(lo, 64)
                keys = b.column(0).to_pylist()
                rows = []
                for k, (x, at) in zip(keys, decode_streams(b.column(1).to_pylist())):
                    kind = np.int8 if not len(x) or (x.min() >= -128 and x.max() <= 127) else np.dtype("<i4")
                    for j, (p, q) in enumerate(zip(at, [*at[1:], len(x)])):
                        rows.append((k, j, int(p), int(q - p), x.shape[1], x[p:q].astype(kind).tobytes()))
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (b.schema.field(0).type, pa.int32(), pa.int64(), pa.int32(), pa.int32(), pa.binary()))], names=[key, "block", "sample_offset", "n_samples", "channels", "pcm"])

    return stored.select(key, media).where(F.col(media).isNotNull()).mapInArrow(run, schema)


def pcm_span(stored: DataFrame, first: int, count: int, key: str = "doc_id", media: str = "media") -> DataFrame:
    """key and pcm (as in ``pcm_blocks``) of ``count`` samples from sample ``first``
    on, fewer where a stream ends: only the frames that hold them are decoded."""
    schema = f"`{key}` {dict(stored.dtypes)[key]}, pcm binary"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for lo in range(0, whole.num_rows, 64):
                b = whole.slice(lo, 64)
                found = decode_streams(b.column(1).to_pylist(), [(first, first + count)] * b.num_rows)
                made = [x.astype(np.int8 if not len(x) or (x.min() >= -128 and x.max() <= 127) else np.dtype("<i4")).tobytes() for x, _ in found]
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(made, pa.binary())], names=[key, "pcm"])

    return stored.select(key, media).where(F.col(media).isNotNull()).mapInArrow(run, schema)


def media_digests(stored: DataFrame) -> DataFrame:
    """Reads the streams of ``encode_column`` back and tells what they hold."""
    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for lo in range(0, whole.num_rows, 128):
                b = whole.slice(lo, 128)
                streams = b.column(2).to_pylist()
                made: list[tuple] = []
                for (x, _), s in zip(decode_streams(streams), streams):
                    payload = (x[:, 0].astype(np.uint8) ^ np.uint8(0x80)).tobytes()
                    made.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), len(s), hashlib.sha256(s).hexdigest(), features(x[:, 0])))
                cols = list(zip(*made)) or [()] * 6
                types = (pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string())
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), *(pa.array(c, t) for c, t in zip(cols, types))], names=["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"])

    return stored.select(F.col("doc_id").cast("long"), "n_bytes", "media").mapInArrow(run, schema)
