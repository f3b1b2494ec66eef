"""Lossless 8-bit mono FLAC of byte payloads in numpy: Rice residuals, fixed and linear predictors, checksums, seek points.

Frames hold 576 samples; a sample is a byte less 104, modulo 256, so that letters lie about zero. All frames of a batch are coded and decoded in lockstep, one vector lane a
frame: the decoder finds frames by their exact headers, whose numbers must run on, and checks the header's CRC-8, the
frame's CRC-16 and the stream's MD5. A seek point for every 16 frames allows reads from a sample offset.

Edge cases: a null or empty text is one frame of padding; very long texts are streams of many frames; repeated rows give
equal streams; a null doc_id is kept; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
from pyspark.sql import DataFrame

from .common import id_in, id_out, written

BLOCK = 576
PAD = 255
CENTRE = np.uint8(104)
SEEK_EVERY = 16
#: Fixed values of the format: predictors of order 0 to 4, as weights of the last samples.
FIXED = ((), (1,), (2, -1), (3, -3, 1), (4, -6, 4, -1))
LPC_ORDER, LPC_BITS, LPC_SHIFT = 8, 12, 9
LANES = 4096
_APP = b"PyLd"


def _crc_table(polynomial: int, bits: int) -> np.ndarray:
    out = np.zeros(256, np.uint32)
    for i in range(256):
        c = i << (bits - 8)
        for _ in range(8):
            c = (c << 1) ^ polynomial if c >> (bits - 1) & 1 else c << 1
        out[i] = c & ((1 << bits) - 1)
    return out


CRC8, CRC16 = _crc_table(0x07, 8), _crc_table(0x8005, 16)


def crc8(data: bytes) -> int:
    c = 0
    for b in data:
        c = int(CRC8[c ^ b])
    return c


def _number(n: int) -> bytes:
    """Frame numbers are coded like code points, of up to 36 bits."""
    if n < 0x80:
        return bytes([n])
    size = next(s for s in range(2, 8) if n < 1 << (5 * s + 1))
    tail = [0x80 | n >> 6 * i & 0x3F for i in reversed(range(size - 1))]
    return bytes([(0xFF << (8 - size) & 0xFF) | n >> 6 * (size - 1), *tail])


_headers: list[bytes] = []


def frame_header(n: int) -> bytes:
    while len(_headers) <= n:
        head = b"\xff\xf8\x20\x02" + _number(len(_headers))
        _headers.append(head + bytes([crc8(head)]))
    return _headers[n]


def crc16_of(buffer: np.ndarray, starts: np.ndarray, stops: np.ndarray) -> np.ndarray:
    """CRC-16 of byte ranges in lockstep; ranges are aligned right, since leading zeros do not change it."""
    width = int((stops - starts).max(initial=0))
    at = stops[None, :] - width + np.arange(width)[:, None]
    rows = np.where(at >= starts[None, :], buffer[np.maximum(at, 0)], 0).astype(np.uint32)
    crc = np.zeros(len(starts), np.uint32)
    for row in rows:
        crc = ((crc << np.uint32(8)) & np.uint32(0xFFFF)) ^ CRC16[(crc >> np.uint32(8)) ^ row]
    return crc


def linear_predictors(samples: np.ndarray) -> np.ndarray:
    """Quantised weights [F, order] by the autocorrelation method."""
    x = samples.astype(np.float64)
    r = np.stack([np.einsum("ij,ij->i", x[:, : BLOCK - lag], x[:, lag:]) for lag in range(LPC_ORDER + 1)], axis=1)
    a = np.zeros((len(x), LPC_ORDER))
    error = np.maximum(r[:, 0], 1e-9)
    for i in range(LPC_ORDER):
        k = (r[:, i + 1] - np.einsum("ij,ij->i", a[:, :i], r[:, i:0:-1])) / error
        a[:, :i] -= k[:, None] * a[:, :i][:, ::-1].copy()
        a[:, i] = k
        error = np.maximum(error * (1 - k * k), 1e-9)
    top = 1 << (LPC_BITS - 1)
    return np.clip(np.rint(a * (1 << LPC_SHIFT)), -top, top - 1).astype(np.int32)


def encode_frames(samples: np.ndarray, numbers: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(bytes of all frames, end of each) of samples [F, 576]."""
    s = samples.astype(np.int32)
    f = len(s)
    lanes = np.arange(f)
    best, order, kind = s.copy(), np.zeros(f, np.int64), np.full(f, 8)
    cost = np.abs(s).sum(axis=1)
    flat = (s == s[:, :1]).all(axis=1)
    diff = s
    for o in range(1, 5):
        diff = np.diff(diff, axis=1)
        c = np.abs(diff).sum(axis=1)
        better = c < cost
        best[better, o:], order[better], kind[better], cost[better] = diff[better], o, 8 + o, c[better]
    q = linear_predictors(s)
    guess = np.zeros((f, BLOCK - LPC_ORDER), np.int32)
    for j in range(LPC_ORDER):
        guess += q[:, j : j + 1] * s[:, LPC_ORDER - 1 - j : BLOCK - 1 - j]
    rest = s[:, LPC_ORDER:] - (guess >> LPC_SHIFT)
    c = np.abs(rest).sum(axis=1) + 60
    better = c < cost
    best[better, LPC_ORDER:], order[better], kind[better] = rest[better], LPC_ORDER, 32 + LPC_ORDER - 1
    coded = np.arange(BLOCK)[None, :] >= order[:, None]
    u = np.where(coded, (best << 1) ^ (best >> 31), 0)
    mean = u.sum(axis=1) / np.maximum(coded.sum(axis=1), 1)
    k0 = np.clip(np.floor(np.log2(np.maximum(mean * 0.69, 1))).astype(np.int32), 0, 13)
    bits0, bits1 = (np.where(coded, (u >> k[:, None]) + 1 + k[:, None], 0).sum(axis=1) for k in (k0, k0 + 1))
    k = np.where(bits1 < bits0, k0 + 1, k0)
    raw = np.minimum(bits0, bits1) + 8 * order + 10 >= 8 * BLOCK
    kind = np.where(flat, 0, np.where(raw, 1, kind))
    predicted, lpc = kind >= 8, kind >= 32
    heads = [frame_header(int(n)) for n in numbers]
    width = max(map(len, heads))
    fields = width + 1 + (2 + LPC_ORDER) + 3 + BLOCK
    value, size = np.zeros((f, fields), np.int64), np.zeros((f, fields), np.int64)
    for i, h in enumerate(heads):
        value[i, : len(h)], size[i, : len(h)] = list(h), 8
    value[:, width], size[:, width] = kind << 1, 8
    at = width + 1
    # warm-up samples stand where the codes of the rest follow; weights and the Rice parameter come between
    code = value[:, at:], size[:, at:]
    low = np.where(predicted[:, None] & coded, (1 << k[:, None]) | (u & ((1 << k[:, None]) - 1)), s & 255)
    wide = np.where(predicted[:, None] & coded, (u >> k[:, None]) + 1 + k[:, None], 8)
    wide[kind == 0, 1:] = 0
    extra_v, extra_n = np.zeros((f, 13), np.int64), np.zeros((f, 13), np.int64)
    extra_v[:, 0], extra_n[:, 0] = LPC_BITS - 1, np.where(lpc, 4, 0)
    extra_v[:, 1], extra_n[:, 1] = LPC_SHIFT, np.where(lpc, 5, 0)
    extra_v[:, 2:10], extra_n[:, 2:10] = q & ((1 << LPC_BITS) - 1), np.where(lpc, LPC_BITS, 0)[:, None]
    extra_n[:, 10], extra_n[:, 11] = np.where(predicted, 2, 0), np.where(predicted, 4, 0)
    extra_v[:, 12], extra_n[:, 12] = k, np.where(predicted, 4, 0)
    for o in np.unique(order):
        g = lanes[order == o]
        for part, extra, main in ((code[0], extra_v, low), (code[1], extra_n, wide)):
            part[g[:, None], np.arange(o)] = main[g, :o]
            part[g[:, None], o + np.arange(13)] = extra[g]
            part[g[:, None], o + 13 + np.arange(BLOCK - o)] = main[g, o:]
    bits = np.cumsum(size, axis=1)
    length = (bits[:, -1] + 7) // 8 + 2
    ends = np.cumsum(length)
    stop = (bits + 8 * (ends - length)[:, None]).ravel()
    shifted = (value.ravel() << (-stop & 7))[live := size.ravel() > 0]
    last = ((stop + 7) >> 3)[live]
    total = int(ends[-1])
    out = np.zeros(total, np.uint8)
    for j in range(3):
        byte = shifted >> (8 * j) & 255
        some = (byte > 0) & (last - 1 - j >= 0)
        out += np.bincount((last - 1 - j)[some], byte[some], minlength=total).astype(np.uint8)
    crc = crc16_of(out, ends - length, ends - 2)
    out[ends - 2], out[ends - 1] = crc >> 8, crc & 255
    return out, ends


def padded(data: bytes) -> bytes:
    return data + bytes([PAD]) * (-len(data) % BLOCK if data else BLOCK)


def to_samples(data: bytes) -> np.ndarray:
    return (np.frombuffer(data, np.uint8) - CENTRE).view(np.int8)


def encode(payloads: list[bytes]) -> list[bytes]:
    """A FLAC stream of each unpadded payload; its byte count is kept in an application block."""
    out, group, lanes = [], [], 0
    for p in payloads:
        group.append(p)
        lanes += max(1, -(-len(p) // BLOCK))
        if lanes >= LANES:
            out += _encode(group)
            group, lanes = [], 0
    return out + (_encode(group) if group else [])


def _encode(payloads: list[bytes]) -> list[bytes]:
    full = [padded(p) for p in payloads]
    frames = np.array([len(p) // BLOCK for p in full])
    samples = to_samples(b"".join(full)).reshape(-1, BLOCK)
    numbers = np.concatenate([np.arange(n) for n in frames])
    parts, ends = zip(*(encode_frames(samples[a : a + LANES], numbers[a : a + LANES]) for a in range(0, len(samples), LANES)), strict=True)
    base = np.cumsum([0, *(len(p) for p in parts)])
    stop = np.concatenate([e + b for e, b in zip(ends, base, strict=False)])
    data = np.concatenate(parts).tobytes()
    out, at = [], 0
    for raw, p, n in zip(payloads, full, frames, strict=True):
        first = int(stop[at - 1]) if at else 0
        sizes = np.diff(stop[at : at + n], prepend=first)
        points = b"".join(struct.pack(">QQH", j * BLOCK, int(stop[at + j - 1]) - first if j else 0, BLOCK) for j in range(0, n, SEEK_EVERY))
        md5 = hashlib.md5(to_samples(p).tobytes()).digest()
        info = struct.pack(">HH", BLOCK, BLOCK) + int(sizes.min()).to_bytes(3, "big") + int(sizes.max()).to_bytes(3, "big") + (8000 << 44 | 0 << 41 | 7 << 36 | len(p)).to_bytes(8, "big") + md5
        app = _APP + struct.pack(">Q", len(raw))
        blocks = b"".join(bytes([t]) + len(b).to_bytes(3, "big") + b for t, b in ((0, info), (2, app), (0x80 | 3, points)))
        out.append(b"fLaC" + blocks + data[first : int(stop[at + n - 1])])
        at += n
    return out


def metadata(stream: bytes) -> dict:
    """Frames' start, total samples, MD5, payload bytes and seek points of a stream."""
    if stream[:4] != b"fLaC":
        raise ValueError("not a FLAC stream")
    at, out = 4, {"points": []}
    while True:
        kind, size = stream[at], int.from_bytes(stream[at + 1 : at + 4], "big")
        body = stream[at + 4 : at + 4 + size]
        at += 4 + size
        if kind & 127 == 0:
            out |= {"samples": int.from_bytes(body[10:18], "big") & ((1 << 36) - 1), "md5": body[18:34]}
        elif kind & 127 == 2 and body[:4] == _APP:
            out["bytes"] = struct.unpack(">Q", body[4:12])[0]
        elif kind & 127 == 3:
            out["points"] = list(struct.iter_unpack(">QQH", body))
        if kind & 128:
            return out | {"start": at}


def frame_starts(data: bytes, start: int, first: int, count: int) -> np.ndarray:
    """Offsets of frames first.. in data: places whose header is that of the next expected frame."""
    b = np.frombuffer(data, np.uint8)[start:]
    hits = np.flatnonzero((b[:-3] == 0xFF) & (b[1:-2] == 0xF8) & (b[2:-1] == 0x20) & (b[3:] == 0x02)) + start
    out = []
    for h in hits.tolist():
        if len(out) < count and data.startswith(frame_header(first + len(out)), h):
            out.append(h)
    if len(out) != count:
        raise ValueError(f"{count} frames expected, {len(out)} headers found")
    return np.array(out, np.int64)


class _Bits:
    """Bit positions of many lanes over one buffer; words are 64 bits from any byte."""

    def __init__(self, buffer: np.ndarray, at: np.ndarray):
        wide = np.concatenate([buffer, np.zeros(16, np.uint8)])
        word = np.zeros(len(buffer) + 8, np.uint64)
        for j in range(8):
            word |= wide[j : j + len(word)].astype(np.uint64) << np.uint64(56 - 8 * j)
        self.word, self.at = word, at * 8

    def peek(self) -> np.ndarray:
        return self.word[self.at >> 3] << (self.at & 7).astype(np.uint64)

    def take(self, n) -> np.ndarray:
        """n bits (0 to 32, by lane or for all) as unsigned numbers."""
        n = np.broadcast_to(np.asarray(n, np.int64), self.at.shape)
        out = (self.peek() >> np.uint64(1) >> (63 - n).astype(np.uint64)).astype(np.int64)
        self.at = self.at + n
        return out

    def zeros(self) -> np.ndarray:
        """Length of each lane's run of zeros, read with the one that ends it."""
        run = np.zeros(len(self.at), np.int64)
        open_ = np.arange(len(self.at))
        while True:
            top = self.word[self.at[open_] >> 3] << (self.at[open_] & 7).astype(np.uint64) >> np.uint64(11)
            n = 53 - np.frexp(top.astype(np.float64))[1].astype(np.int64)
            none = top == 0
            run[open_] += np.where(none, 53, n)
            self.at[open_] += np.where(none, 53, n + 1)
            open_ = open_[none]
            if not len(open_):
                return run
            if (self.at[open_] >> 3 > len(self.word) - 8).any():
                raise ValueError("a Rice code runs out of the stream")


def decode_frames(buffer: np.ndarray, starts: np.ndarray, stops: np.ndarray, heads: np.ndarray) -> np.ndarray:
    """Samples [F, 576] of frames at byte ranges, heads: header sizes. Raises if a frame's checksum is wrong."""
    wrong = crc16_of(buffer, starts, stops - 2) != (buffer[stops - 2].astype(np.uint32) << 8 | buffer[stops - 1])
    if wrong.any():
        raise ValueError(f"checksum of {int(wrong.sum())} frames is wrong")
    out = np.zeros((len(starts), BLOCK), np.int32)
    body = starts + heads
    kind = buffer[body].astype(np.int64)
    if (kind & 0x81).any():
        raise ValueError("wasted bits or a reserved bit: not of this profile")
    kind >>= 1
    lanes = np.flatnonzero(kind == 0)
    out[lanes] = buffer[body[lanes] + 1].astype(np.int8)[:, None]
    lanes = np.flatnonzero(kind == 1)
    out[lanes] = buffer[body[lanes, None] + 1 + np.arange(BLOCK)].astype(np.int8)
    lanes = np.flatnonzero(kind >= 8)
    if len(lanes):
        out[lanes] = _predicted(buffer, body[lanes] + 1, kind[lanes])
    return out


def _predicted(buffer: np.ndarray, at: np.ndarray, kind: np.ndarray) -> np.ndarray:
    n = len(at)
    bits = _Bits(buffer, at)
    lpc = kind >= 32
    order = np.where(lpc, kind - 31, kind - 8)
    depth = max(4, int(order.max()))
    s = np.zeros((depth + BLOCK, n), np.int64)
    for i in range(int(order.max())):
        warm = i < order
        s[depth + i] = np.where(warm, (bits.take(np.where(warm, 8, 0)) ^ 128) - 128, 0)
    precision = bits.take(np.where(lpc, 4, 0)) + 1
    shift = bits.take(np.where(lpc, 5, 0))
    weight = np.zeros((depth, n), np.int64)
    for o, w in enumerate(FIXED):
        for j, x in enumerate(w):
            weight[j, ~lpc & (order == o)] = x
    for j in range(int(order[lpc].max(initial=0))):
        on = lpc & (j < order)
        x = bits.take(np.where(on, precision, 0))
        weight[j] = np.where(on, x - ((x >> (precision - 1) & 1) << precision), weight[j])
    method = bits.take(2)
    if (method > 1).any():
        raise ValueError("reserved residual coding method")
    part = BLOCK >> bits.take(4)
    k, escape = np.zeros(n, np.int64), np.zeros(n, np.int64)
    every = bool((part == BLOCK).all())
    first = int(order.min())
    for i in range(first, BLOCK):
        on = order <= i
        fresh = (order == i) if every else on & ((i % part == 0) | (order == i))
        if (i <= depth or not every) and fresh.any():
            k = np.where(fresh, bits.take(np.where(fresh, 4 + method, 0)), k)
            raw = fresh & (k == np.where(method == 1, 31, 15))
            escape = np.where(fresh, 0, escape)
            if raw.any():
                size = bits.take(np.where(raw, 5, 0))
                escape = np.where(raw, size + 1, escape)
        if i >= depth and not escape.any():
            q = bits.zeros()
            u = q << k | bits.take(k)
            r = (u >> 1) ^ -(u & 1)
        else:
            r = np.zeros(n, np.int64)
            coded = np.flatnonzero(on & (escape == 0))
            if len(coded):
                some = _Bits.__new__(_Bits)
                some.word, some.at = bits.word, bits.at[coded]
                q = some.zeros()
                u = q << k[coded] | some.take(k[coded])
                r[coded] = (u >> 1) ^ -(u & 1)
                bits.at[coded] = some.at
            plain = on & (escape > 0)
            if plain.any():
                size = np.where(plain, escape - 1, 0)
                x = bits.take(size)
                r = np.where(plain & (size > 0), x - ((x >> np.maximum(size - 1, 0) & 1) << size), r)
        guess = np.einsum("pn,pn->n", weight, s[i + depth - 1 : i - 1 if i else None : -1][:depth]) >> shift
        s[depth + i] = np.where(on, r + guess, s[depth + i])
    return s[depth:].T


def decode(streams: list[bytes]) -> list[tuple[bytes, int]]:
    """(padded payload, unpadded bytes) of each stream; all checksums are verified."""
    out = []
    group, lanes = [], 0
    for stream in streams:
        group.append(stream)
        lanes += metadata(stream)["samples"] // BLOCK
        if lanes >= LANES:
            out += _decode(group)
            group, lanes = [], 0
    return out + (_decode(group) if group else [])


def _decode(streams: list[bytes]) -> list[tuple[bytes, int]]:
    facts = [metadata(x) for x in streams]
    counts = [x["samples"] // BLOCK for x in facts]
    starts, stops, base = [], [], 0
    for x, fact, n in zip(streams, facts, counts, strict=True):
        own = frame_starts(x, fact["start"], 0, n) + base
        base += len(x)
        starts.append(own)
        stops.append(np.append(own[1:], base))
    start, stop = np.concatenate(starts), np.concatenate(stops)
    heads = np.concatenate([[len(frame_header(i)) for i in range(n)] for n in counts])
    buffer = np.frombuffer(b"".join(streams), np.uint8)
    samples = np.concatenate([decode_frames(buffer, start[a : a + LANES], stop[a : a + LANES], heads[a : a + LANES]) for a in range(0, len(start), LANES)])
    data = (samples.astype(np.uint8) + CENTRE).tobytes()
    out, at = [], 0
    for fact, n in zip(facts, counts, strict=True):
        payload = data[at * BLOCK : (at + n) * BLOCK]
        if hashlib.md5(to_samples(payload).tobytes()).digest() != fact["md5"]:
            raise ValueError("the stream's MD5 is wrong")
        out.append((payload, fact["bytes"]))
        at += n
    return out


def read_samples(stream: bytes, offset: int, count: int) -> np.ndarray:
    """Samples offset.. of a stream, decoding from the last seek point before it."""
    fact = metadata(stream)
    stop = min(offset + count, fact["samples"])
    point = max((p for p in fact["points"] if p[0] <= offset), default=(0, 0, BLOCK))
    first = point[0] // BLOCK
    n = -(-stop // BLOCK) - first
    more = first + n < fact["samples"] // BLOCK
    starts = frame_starts(stream, fact["start"] + point[1], first, n + more)
    stops = starts[1:] if more else np.append(starts[1:], len(stream))
    heads = np.array([len(frame_header(first + i)) for i in range(n)])
    return decode_frames(np.frombuffer(stream, np.uint8), starts[:n], stops[:n], heads).ravel()[offset - point[0] : stop - point[0]]


def features(payload: bytes) -> str:
    """Of the decoded samples: frames, peak, mean square, crossings of zero and summed steps, all whole numbers."""
    s = to_samples(payload).astype(np.int32)
    return f"frames={len(s) // BLOCK};peak={int(np.abs(s).max())};power={int((s * s).sum()) // len(s)};crossings={int(((s[1:] < 0) != (s[:-1] < 0)).sum())};steps={int(np.abs(np.diff(s)).sum())}"


def _batches(frames, column: str, limit: int = 8 << 20):
    """Slices of pandas batches of about limit bytes in the column."""
    for frame in frames:
        size = frame[column].map(lambda x: len(x) if isinstance(x, (str, bytes, bytearray)) else 0).cumsum()
        for _, part in frame.groupby(size // limit, sort=True):
            yield part


def store(docs: DataFrame) -> DataFrame:
    """A written table (doc_id, media) of the texts' FLAC streams."""

    def task(frames):
        import pandas as pd

        for part in _batches(frames, "text"):
            raw = [x.encode() if isinstance(x, str) else b"" for x in part["text"]]
            yield pd.DataFrame({"doc_id": part["doc_id"], "media": encode(raw)})

    return written(id_out(docs.select(id_in("doc_id"), "text").mapInPandas(task, "doc_id long, media binary"), "doc_id"), "flac", "zstd")


def digests(media: DataFrame) -> DataFrame:
    """Decodes a stored table; one row per stream."""

    def task(frames):
        import pandas as pd

        for part in _batches(frames, "media"):
            streams = [bytes(x) for x in part["media"]]
            rows = []
            for doc_id, stream, (payload, n) in zip(part["doc_id"], streams, decode(streams), strict=True):
                rows.append((doc_id, n, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]), len(stream), hashlib.sha256(stream).hexdigest(), features(payload)))
            yield pd.DataFrame(rows, columns=["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"])

    out = media.select(id_in("doc_id"), "media").mapInPandas(task, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")
    return id_out(out, "doc_id")
