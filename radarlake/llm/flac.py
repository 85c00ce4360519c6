"""FLAC: frames of Rice coded residuals over linear predictors, checked and decoded to seekable PCM blocks.

Two decoders share the format. `decode_stream` reads any stream bit by bit (all
subframe kinds, 4 to 32 bits, stereo decorrelation, wasted bits, escaped partitions).
`decode_many` takes all frames of many streams at once, one numpy lane a frame, for
mono streams of 8-bit samples whose seek table names every frame, as `encode_many`
writes them; other streams, legal ones with escaped or wide residual codes among them, go
to the first. Every frame's header and footer checksum
and the stream's MD5 are verified; a mismatch raises ValueError.

As media columns of texts: UTF-8 bytes, zero bytes up to a positive multiple of 64,
are 8-bit samples (byte minus 128). Null text is empty text: 64 zero bytes. Null and
repeated ids are rows like any other. What is stored is a table of media columns in the
shared folder; `write_pcm` writes its samples as blocks with offsets to seek by.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from radarlake.llm.common import binary_array, chunks, partitions, stored

BLOCK = 512
RATE = 8000
LPC_ORDER, LPC_BITS = 4, 12
_FIXED = np.array([[0, 0, 0, 0], [1, 0, 0, 0], [2, -1, 0, 0], [3, -3, 1, 0], [4, -6, 4, -1]], np.int64)


def _crc_table(poly: int, bits: int) -> np.ndarray:
    out = []
    for b in range(256):
        c = b << (bits - 8)
        for _ in range(8):
            c = (c << 1) ^ (poly if c >> (bits - 1) & 1 else 0)
        out.append(c & ((1 << bits) - 1))
    return np.array(out, np.uint32)


_CRC8, _CRC16 = _crc_table(0x07, 8), _crc_table(0x8005, 16)


def _crc_lanes(data: np.ndarray, start: np.ndarray, size: np.ndarray, table: np.ndarray, bits: int) -> np.ndarray:
    """Checksums of many byte ranges at once, the longest first inside."""
    order = np.argsort(-size, kind="stable")
    at, left = start[order], size[order]
    crc = np.zeros(len(start), np.uint32)
    active = len(start) - np.searchsorted(left[::-1], np.arange(int(left[0]) if len(left) else 0), "right")
    for j, m in enumerate(active.tolist()):
        c = crc[:m]
        crc[:m] = ((c << np.uint32(8)) & np.uint32((1 << bits) - 1)) ^ table[(c >> np.uint32(bits - 8)) ^ data[at[:m] + j]]
    out = np.empty_like(crc)
    out[order] = crc
    return out


def _utf8_number(n: int) -> bytes:
    if n < 0x80:
        return bytes([n])
    k = next(k for k in range(2, 8) if n < 1 << (5 * k + 1))
    tail = [0x80 | (n >> (6 * i) & 0x3F) for i in range(k - 2, -1, -1)]
    return bytes([(0xFF00 >> k & 0xFF) | (n >> (6 * (k - 1))), *tail])


# --- encoding ---------------------------------------------------------------------


def _put(words: np.ndarray, at: np.ndarray, value: np.ndarray, bits: np.ndarray) -> None:
    """Adds values of up to 57 bits at bit positions of a zeroed array of 64-bit words, high bit first."""
    value, bits, at = value.astype(np.uint64), bits.astype(np.uint64), at.astype(np.uint64)
    word, inside = (at >> np.uint64(6)).astype(np.int64), at & np.uint64(63)
    top = (value << np.uint64(1)) << (np.uint64(63) - bits)
    np.add.at(words, word, top >> inside)
    low = np.flatnonzero(inside + bits > 64)
    np.add.at(words, word[low] + 1, top[low] << (np.uint64(64) - inside[low]))


def _predictors(x: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Quantised linear predictors of each row by the autocorrelation method, and their shifts."""
    f = x.astype(np.float32)
    r = np.stack([np.einsum("ij,ij->i", f[:, k:], f[:, : f.shape[1] - k]) for k in range(LPC_ORDER + 1)]).astype(np.float64)
    a = np.zeros((LPC_ORDER, len(x)))
    err = r[0] * (1 + 1e-9) + 1e-9
    for i in range(LPC_ORDER):
        k = (r[i + 1] - (a[:i] * r[i:0:-1]).sum(0)) / err
        a[:i], a[i] = a[:i] - k * a[:i][::-1], k
        err = np.maximum(err * (1 - k * k), 1e-9)
    _, e = np.frexp(np.abs(a).max(0))
    shift = np.clip(LPC_BITS - 1 - e, 0, 15)
    q = np.clip(np.rint(a * 2.0**shift), -(1 << (LPC_BITS - 1)), (1 << (LPC_BITS - 1)) - 1).astype(np.int64)
    return q.T, shift.astype(np.int64)


def _residual(x: np.ndarray, q: np.ndarray, shift: np.ndarray, order: int) -> np.ndarray:
    pred = np.zeros_like(x)
    for j in range(order):
        pred[:, j + 1 :] += q[:, j : j + 1] * x[:, : x.shape[1] - j - 1]
    return x - (pred >> shift[:, None])


def encode_many(data: np.ndarray, offsets: np.ndarray, block: int = BLOCK) -> tuple[np.ndarray, np.ndarray]:
    """Streams of many rows of 8-bit samples (as bytes, plus 128); sizes must be positive multiples of 64."""
    sizes = np.diff(offsets)
    per = -(-sizes // block)
    first = np.concatenate([[0], np.cumsum(per)])
    row = np.repeat(np.arange(len(sizes)), per)
    number = np.arange(first[-1]) - first[row]
    begin = offsets[row] + number * block
    n = np.minimum(offsets[row + 1] - begin, block)
    total = len(row)
    column = np.arange(block)
    inside = column < n[:, None]
    x = np.where(inside, data[np.minimum(begin[:, None] + column, len(data) - 1)].astype(np.int32) - 128, 0)

    # candidates: fixed predictors of order 0 and 1 and a fitted one; the least estimated bits win
    parts = np.where((n == block) & (block % 4 == 0), 4, 1)
    lpc, shift = _predictors(x, n)
    best = np.full(total, np.iinfo(np.int64).max)
    u, order, q, s, is_lpc = np.zeros_like(x), np.zeros(total, np.int64), np.zeros((total, LPC_ORDER), np.int64), np.zeros(total, np.int64), np.zeros(total, bool)
    for kind, o in (("fixed", 0), ("fixed", 1), ("lpc", LPC_ORDER)):
        coefficients, sh = (lpc, shift) if kind == "lpc" else (np.broadcast_to(_FIXED[o], (total, 4)), np.zeros(total, np.int64))
        r = _residual(x, coefficients.astype(np.int32), sh.astype(np.int32), o)
        z = (r << 1) ^ (r >> 31)
        z[:, :o] = 0
        z *= inside
        mean = z.sum(1) / np.maximum(n - o, 1)
        k = np.maximum(np.frexp(mean * 0.7)[1], 0).astype(np.int32)
        bits = 8 * o + (n - o) * (k + 1) + (z >> k[:, None]).sum(1) + (kind == "lpc") * (9 + LPC_BITS * o)
        won = bits < best
        best = np.where(won, bits, best)
        u[won], order[won], s[won], is_lpc[won] = z[won], o, sh[won], kind == "lpc"
        q[won] = coefficients[won]
    constant = (x == x[:, :1]).sum(1) >= n
    constant &= ((x == x[:, :1]) | ~inside).all(1)
    verbatim = ~constant & (best + 10 + 4 * parts >= 8 * n)
    rice = ~constant & ~verbatim

    # Rice parameters by partition, from the mean
    # u is zero outside and before the first residual
    quarters = u.reshape(total, 4, block // 4).sum(2) if block % 4 == 0 else np.zeros((total, 4), np.int64)
    sums = np.where(parts[:, None] == 4, quarters, u.sum(1)[:, None])
    counts = np.where(parts[:, None] == 4, block // 4, n[:, None]) - np.where(np.arange(4) < np.where(parts == 4, 1, 4)[:, None], order[:, None], 0)
    k = np.clip(np.frexp(sums / np.maximum(counts, 1) * 0.7)[1], 0, 14).astype(np.int64)
    ks = k[:, :1].astype(np.int32).repeat(block, 1)
    if (parts == 4).any():
        ks[parts == 4] = k[parts == 4].astype(np.int32).repeat(block // 4, 1)
    raw = (column < order[:, None]) | verbatim[:, None]
    length = np.where(inside, np.where(raw, 8, (u >> ks) + 1 + ks), 0)
    length[constant] = 0
    length[constant, 0] = 8
    extra = np.zeros_like(length)
    residual_at = np.where(rice, order, 0)
    lead = np.where(is_lpc, 9 + LPC_BITS * order, 0) + 6 + 4
    extra[np.flatnonzero(rice), residual_at[rice]] = lead[rice]
    four = np.flatnonzero(rice & (parts == 4))
    for p in range(1, 4):
        extra[four, p * block // 4] += 4
    place = np.cumsum(length + extra, 1)
    bits = place[:, -1].copy()
    place -= length

    # headers: sync and fixed blocks, size in 16 bits (or 8), rate from the stream, mono, 8 bits
    numbers = [_utf8_number(i) for i in range(int(per.max(initial=0)))]
    heads = [b"\xff\xf8\x70\x02" + numbers[i] + int(m - 1).to_bytes(2, "big") for i, m in zip(number.tolist(), n.tolist(), strict=True)]
    head_size = np.array([len(h) for h in heads], np.int64)
    head_at = np.concatenate([[0], np.cumsum(head_size)])
    head_bytes = np.frombuffer(b"".join(heads), np.uint8)
    crc8 = _crc_lanes(head_bytes, head_at[:-1], head_size, _CRC8, 8)
    frame = head_size + 2 + (bits + 7) // 8 + 2  # header, its checksum, subframe byte, subframe, checksum
    start = np.concatenate([[0], np.cumsum(frame)])
    words = np.zeros(int(start[-1]) // 8 + 2, np.uint64)
    body = (start[:-1] + head_size + 2) * 8
    keep = inside & (length > 0)
    value = np.where(raw | constant[:, None], (x & 0xFF), (1 << ks) | (u & ((1 << ks) - 1)))
    width = np.where(raw | constant[:, None], 8, ks + 1)
    at = body[:, None] + place + np.where(raw | constant[:, None], 0, u >> ks)
    _put(words, at[keep], value[keep], width[keep])
    r = np.flatnonzero(rice)
    here = body[r] + place[r, residual_at[r]] - 10
    _put(words, here, np.where(parts[r] == 4, 2, 0) << 4 | k[r, 0], np.full(len(r), 10))
    for p in range(1, 4):
        _put(words, body[four] + place[four, p * block // 4] - 4, k[four, p], np.full(len(four), 4))
    fitted = np.flatnonzero(rice & is_lpc)
    here = body[fitted] + 8 * order[fitted]
    _put(words, here, (LPC_BITS - 1) << 5 | s[fitted], np.full(len(fitted), 9))
    for j in range(LPC_ORDER):
        _put(words, here + 9 + LPC_BITS * j, q[fitted, j] & ((1 << LPC_BITS) - 1), np.full(len(fitted), LPC_BITS))
    out = words.byteswap().view(np.uint8)[: start[-1]].copy()
    at = np.repeat(start[:-1] - head_at[:-1], head_size) + np.arange(head_at[-1])
    out[at] = head_bytes
    out[start[:-1] + head_size] = crc8
    kind = np.where(constant, 0, np.where(verbatim, 1, np.where(is_lpc, 31 + order, 8 + order)))
    out[start[:-1] + head_size + 1] = kind << 1
    crc16 = _crc_lanes(out, start[:-1], frame - 2, _CRC16, 16)
    out[start[1:] - 2], out[start[1:] - 1] = crc16 >> 8, crc16 & 0xFF

    # streams: marker, STREAMINFO, a seek point for every frame, the frames
    pieces, ends = [], [0]
    signed = data ^ 0x80
    for i in range(len(sizes)):
        a, b = first[i], first[i + 1]
        points = np.zeros((b - a, 18), np.uint8)
        points[:, :8] = (number[a:b].astype(">u8") * block).astype(">u8").view(np.uint8).reshape(-1, 8)
        points[:, 8:16] = (start[a:b] - start[a]).astype(">u8").view(np.uint8).reshape(-1, 8)
        points[:, 16:] = n[a:b].astype(">u2").view(np.uint8).reshape(-1, 2)
        info = (RATE << 44 | 0 << 41 | 7 << 36 | int(sizes[i])).to_bytes(8, "big")
        spans = frame[a:b]
        head = b"fLaC\x00\x00\x00\x22" + block.to_bytes(2, "big") * 2 + int(spans.min()).to_bytes(3, "big") + int(spans.max()).to_bytes(3, "big")
        head += info + hashlib.md5(signed[offsets[i] : offsets[i + 1]]).digest() + b"\x83" + points.size.to_bytes(3, "big")
        pieces += [np.frombuffer(head, np.uint8), points.reshape(-1), out[start[a] : start[b]]]
        ends.append(ends[-1] + len(head) + points.size + int(start[b] - start[a]))
    return np.concatenate([np.zeros(0, np.uint8), *pieces]), np.array(ends, np.int64)


# --- decoding ---------------------------------------------------------------------


class Stream:
    """The metadata of one stream: sizes, MD5, seek points as (sample, offset, samples), and where the frames start."""

    def __init__(self, raw: bytes):
        if raw[:4] != b"fLaC":
            raise ValueError("not a FLAC stream")
        at, last, self.points = 4, False, None
        while not last:
            last, kind, size = raw[at] >> 7, raw[at] & 0x7F, int.from_bytes(raw[at + 1 : at + 4], "big")
            body = raw[at + 4 : at + 4 + size]
            if kind == 0:
                packed = int.from_bytes(body[10:18], "big")
                self.rate, self.channels, self.bits, self.samples = packed >> 44, (packed >> 41 & 7) + 1, (packed >> 36 & 31) + 1, packed & ((1 << 36) - 1)
                self.md5, self.block = body[18:34], int.from_bytes(body[2:4], "big")
            elif kind == 3:
                table = np.frombuffer(body, [("sample", ">u8"), ("offset", ">u8"), ("samples", ">u2")])
                self.points = table[table["sample"] != 0xFFFFFFFFFFFFFFFF]
            at += 4 + size
        self.frames = at

    def whole(self) -> bool:
        """Whether the seek table names every frame."""
        p = self.points
        if p is None or not len(p) or p["sample"][0] or p["offset"][0]:
            return False
        ends = p["sample"].astype(np.int64) + p["samples"]
        return bool((ends[:-1] == p["sample"][1:]).all() and ends[-1] == self.samples)


class _Bits:
    def __init__(self, raw: bytes, at: int):
        self.raw, self.at = raw, at * 8

    def read(self, n: int) -> int:
        a, b = self.at >> 3, (self.at + n + 7) >> 3
        value = int.from_bytes(self.raw[a:b], "big") >> (b * 8 - self.at - n) & ((1 << n) - 1)
        self.at += n
        return value

    def signed(self, n: int) -> int:
        value = self.read(n)
        return value - (1 << n) if n and value >> (n - 1) else value

    def unary(self) -> int:
        n = 0
        while not self.read(1):
            n += 1
            if self.at > 8 * len(self.raw):
                raise ValueError("the stream is cut off")
        return n


def _subframe(bits: _Bits, n: int, size: int) -> list[int]:
    if bits.read(1):
        raise ValueError("a subframe must start with a zero bit")
    kind = bits.read(6)
    wasted = bits.unary() + 1 if bits.read(1) else 0
    size -= wasted
    if kind == 0:
        out = [bits.signed(size)] * n
    elif kind == 1:
        out = [bits.signed(size) for _ in range(n)]
    elif 8 <= kind <= 12 or kind >= 32:
        order = kind - 8 if kind < 32 else kind - 31
        out = [bits.signed(size) for _ in range(order)]
        shift, coefficients = 0, _FIXED[order][:order].tolist() if kind < 32 else []
        if kind >= 32:
            precision, shift = bits.read(4) + 1, bits.signed(5)
            coefficients = [bits.signed(precision) for _ in range(order)]
        method, partition = bits.read(2), bits.read(4)
        if method > 1:
            raise ValueError("an unknown residual code")
        wide = 5 if method else 4
        for p in range(1 << partition):
            count = (n >> partition) - (order if p == 0 else 0)
            k = bits.read(wide)
            if k == (1 << wide) - 1:
                k = bits.read(5)
                rest = [bits.signed(k) for _ in range(count)]
            else:
                rest = []
                for _ in range(count):
                    u = bits.unary() << k | bits.read(k)
                    rest.append(u >> 1 ^ -(u & 1))
            for r in rest:
                out.append(r + (sum(c * out[-1 - j] for j, c in enumerate(coefficients)) >> shift))
    else:
        raise ValueError("a reserved subframe")
    return [x << wasted for x in out] if wasted else out


def _crc(data: bytes, table: np.ndarray, bits: int) -> int:
    return int(_crc_lanes(np.frombuffer(data, np.uint8), np.zeros(1, np.int64), np.array([len(data)]), table, bits)[0])


def decode_frame(raw: bytes, at: int, stream: Stream) -> tuple[np.ndarray, int]:
    """Samples (channels, n) of the frame at a byte position, both checksums verified, and the position after it."""
    bits = _Bits(raw, at)
    if bits.read(15) != 0x7FFC:
        raise ValueError("no frame starts here")
    bits.read(1)
    size_code, rate_code, channel, bps_code = bits.read(4), bits.read(4), bits.read(4), bits.read(3)
    bits.read(1)
    lead = bits.read(8)
    for _ in range(max(0, 8 - (lead ^ 0xFF).bit_length() - 1)):
        bits.read(8)
    n = 192 if size_code == 1 else 576 << (size_code - 2) if 2 <= size_code <= 5 else bits.read(8) + 1 if size_code == 6 else bits.read(16) + 1 if size_code == 7 else 256 << (size_code - 8)
    if rate_code >= 12:
        bits.read(8 if rate_code == 12 else 16)
    size = {0: stream.bits, 1: 8, 2: 12, 4: 16, 5: 20, 6: 24, 7: 32}[bps_code]
    if _crc(raw[at : bits.at >> 3], _CRC8, 8) != bits.read(8):
        raise ValueError("a frame header fails its checksum")
    if channel < 8:
        out = np.array([_subframe(bits, n, size) for _ in range(channel + 1)], np.int64)
    else:
        a = np.array(_subframe(bits, n, size + (channel == 9)), np.int64)
        b = np.array(_subframe(bits, n, size + (channel != 9)), np.int64)
        if channel == 8:
            out = np.stack([a, a - b])
        elif channel == 9:
            out = np.stack([a + b, b])
        else:
            mid = (a << 1) | (b & 1)
            out = np.stack([(mid + b) >> 1, (mid - b) >> 1])
    end = (bits.at + 7) >> 3
    if _crc(raw[at:end], _CRC16, 16) != int.from_bytes(raw[end : end + 2], "big"):
        raise ValueError("a frame fails its checksum")
    return out, end + 2


def decode_stream(raw: bytes) -> np.ndarray:
    """Samples (channels, n) of a whole stream."""
    stream, out = Stream(raw), []
    at, got = stream.frames, 0
    while at < len(raw) and (not stream.samples or got < stream.samples):
        samples, at = decode_frame(raw, at, stream)
        out.append(samples)
        got += samples.shape[1]
    whole = np.concatenate(out, 1) if out else np.zeros((stream.channels, 0), np.int64)
    if stream.samples and got != stream.samples:
        raise ValueError("the stream is cut off")
    width = -(-stream.bits // 8)
    packed = whole.T.astype("<i8").tobytes()
    sound = np.frombuffer(packed, np.uint8).reshape(-1, 8)[:, :width].tobytes()
    if any(stream.md5) and hashlib.md5(sound).digest() != stream.md5:
        raise ValueError("the samples fail the stream's MD5")
    return whole


class _Lanes:
    """A bit reader for many positions of one buffer."""

    def __init__(self, data: np.ndarray):
        self.data = np.concatenate([data, np.zeros(16, np.uint8)])
        n = len(data) + 8
        self.window = np.zeros(n, np.uint64)
        for k in range(8):
            self.window |= self.data[k : k + n].astype(np.uint64) << np.uint64(56 - 8 * k)

    def look(self, at: np.ndarray) -> np.ndarray:
        return self.window[at >> 3] << (at & 7).astype(np.uint64)

    def read(self, at: np.ndarray, n) -> np.ndarray:
        n = np.broadcast_to(np.asarray(n, np.uint64), at.shape)
        return ((self.look(at) >> np.uint64(1)) >> (np.uint64(63) - n)).astype(np.int64)

    def rice(self, at: np.ndarray, k: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Codes with parameters k, and the positions after them."""
        w = self.look(at)
        top = (w >> np.uint64(11)).astype(np.float64).view(np.int64)
        q = 1075 - (top >> 52)
        if int(q.max(initial=0)) + int(k.max(initial=0)) > 54:
            q = np.zeros_like(at)
            open_ = np.arange(len(at))
            while len(open_):
                w = self.look(at[open_] + q[open_]) >> np.uint64(16)
                e = w.astype(np.float64).view(np.int64) >> 52
                none = w == 0
                q[open_] += np.where(none, 48, 1070 - e)
                open_ = open_[none]
                if len(open_) and int((at[open_] + q[open_]).max()) > 8 * (len(self.window) - 1):
                    raise ValueError("the stream is cut off")
            at = at + q + 1
            return q << k | self.read(at, k), at + k
        rest = (w << (q + 1).astype(np.uint64)) >> np.uint64(1) >> (63 - k).astype(np.uint64)
        return q << k | rest.astype(np.int64), at + q + 1 + k


def _signed(x: np.ndarray, n) -> np.ndarray:
    return x - (x >> (np.asarray(n) - 1) << np.asarray(n))


class _OtherProfile(ValueError):
    """A legal stream that is not as `encode_many` writes them."""


def decode_many(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Bytes (samples plus 128) of many mono 8-bit streams and their offsets, everything verified."""
    raw = data.tobytes()
    cuts = list(zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True))
    streams = [Stream(raw[a:b]) for a, b in cuts]
    try:
        return _decode_lanes(raw, data, offsets, streams)
    except _OtherProfile:
        rows = []
        for s, (a, b) in zip(streams, cuts, strict=True):
            if s.channels != 1 or s.bits != 8:
                raise ValueError("only mono streams of 8 bits are bytes; decode_stream reads others") from None
            rows.append((decode_stream(raw[a:b])[0] + 128).astype(np.uint8))
        return np.concatenate([np.zeros(0, np.uint8), *rows]), np.concatenate([[0], np.cumsum([len(x) for x in rows])]).astype(np.int64)


def _decode_lanes(raw: bytes, data: np.ndarray, offsets: np.ndarray, streams: list[Stream]) -> tuple[np.ndarray, np.ndarray]:
    if any(s.channels != 1 or s.bits != 8 or not s.whole() for s in streams):
        raise _OtherProfile("another kind of stream")
    if not streams:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    out_at = np.concatenate([[0], np.cumsum([s.samples for s in streams])]).astype(np.int64)
    start = np.concatenate([s.points["offset"].astype(np.int64) + s.frames + a for s, a in zip(streams, offsets[:-1].tolist(), strict=True)])
    end = np.concatenate([np.append(start[1:], 0)[:0], start[1:], [offsets[-1]]])
    per = [len(s.points) for s in streams]
    last = np.cumsum(per) - 1
    end[last] = offsets[1:]
    n = np.concatenate([s.points["samples"].astype(np.int64) for s in streams])
    to = np.concatenate([s.points["sample"].astype(np.int64) + a for s, a in zip(streams, out_at[:-1].tolist(), strict=True)])
    crc = _crc_lanes(data, start, end - start - 2, _CRC16, 16)
    if (crc != (data[end - 2].astype(np.uint32) << 8 | data[end - 1])).any():
        raise ValueError("a frame fails its checksum")
    lead = data[start + 4]
    more = np.where(lead < 0x80, 0, 8 - np.frexp((lead ^ 0xFF).astype(np.float64))[1] - 1)
    plain = (data[start] == 0xFF) & (data[start + 1] == 0xF8) & (data[start + 2] == 0x70) & (data[start + 3] == 0x02)
    head = 5 + more + 2
    if not plain.all():
        raise _OtherProfile("a frame header does not fit its seek table")
    size = (data[start + head - 2].astype(np.int64) << 8 | data[start + head - 1]) + 1
    if (size != n).any() or (_crc_lanes(data, start, head, _CRC8, 8) != data[start + head]).any():
        raise ValueError("a frame header fails its checksum")
    kind = data[start + head + 1] >> 1
    if (data[start + head + 1] & 0x81).any():
        raise _OtherProfile("a subframe header is out of this profile")
    body = start + head + 2
    out = np.zeros(int(out_at[-1]), np.uint8)
    for k in (0, 1):
        for i in np.flatnonzero(kind == k).tolist():
            out[to[i] : to[i] + n[i]] = data[body[i]] ^ 0x80 if k == 0 else data[body[i] : body[i] + n[i]] ^ 0x80
    coded = np.flatnonzero(kind > 1)
    if len(coded):
        coded = coded[np.argsort(-n[coded], kind="stable")]
        samples = _residual_lanes(_Lanes(data), body[coded] * 8, n[coded], kind[coded].astype(np.int64))
        length = n[coded]
        at = np.repeat(to[coded], length) + np.arange(length.sum()) - np.repeat(np.cumsum(length) - length, length)
        out[at] = (samples.T[np.arange(samples.shape[0]) < length[:, None]] + 128).astype(np.uint8)
    signed = out ^ 0x80
    for i, s in enumerate(streams):
        if any(s.md5) and hashlib.md5(signed[out_at[i] : out_at[i + 1]]).digest() != s.md5:
            raise ValueError("the samples fail the stream's MD5")
    return out, out_at


def _residual_lanes(bits: _Lanes, at: np.ndarray, n: np.ndarray, kind: np.ndarray) -> np.ndarray:
    """Samples (time, lane) of fixed and fitted subframes; lanes stand by falling length."""
    fitted = kind >= 32
    order = np.where(fitted, kind - 31, kind - 8)
    if ((order > 4) & ~fitted).any() or (order < 0).any():
        raise ValueError("a reserved subframe")
    deep = int(order.max())
    out = np.zeros((int(n[0]) + deep, len(n)), np.int64)  # `deep` rows of history in front
    for i in range(deep):
        here = np.flatnonzero(order > i)
        out[deep + i, here] = _signed(bits.read(at[here], 8), 8)
        at[here] += 8
    q, shift = np.zeros((max(deep, 4), len(n)), np.int64), np.zeros(len(n), np.int64)
    q[:4] = _FIXED[np.where(fitted, 0, order)].T
    f = np.flatnonzero(fitted)
    precision = bits.read(at[f], 4) + 1
    shift[f] = _signed(bits.read(at[f] + 4, 5), 5)
    at[f] += 9
    for j in range(deep):
        here, p = f[order[f] > j], precision[order[f] > j]
        q[j, here] = _signed(bits.read(at[here], p), p)
        at[here] += p
    if bits.read(at, 2).any():
        raise _OtherProfile("a residual code out of this profile")
    parts = n >> bits.read(at + 2, 4)
    at += 6
    k = np.zeros(len(n), np.int64)
    active = len(n) - np.searchsorted(n[::-1], np.arange(int(n[0])), "right")
    borders = {0, *(int(b) for p in np.unique(parts) for b in range(0, int(n[0]), int(p)))}
    lowest = int(order.min())
    for i in range(lowest, int(n[0])):
        m = int(active[i])
        if i in borders or i <= deep:
            fresh = np.flatnonzero((i % parts[:m] == 0) & (order[:m] <= i) | (order[:m] == i))
            k[fresh] = bits.read(at[fresh], 4)
            at[fresh] += 4
            if (k[fresh] == 15).any():
                raise _OtherProfile("an escaped partition out of this profile")
        if i < deep:
            lanes = np.flatnonzero(order[:m] <= i)
            u, at[lanes] = bits.rice(at[lanes], k[lanes])
        else:
            lanes = slice(0, m)
            u, at[:m] = bits.rice(at[:m], k[:m])
        pred = np.zeros(m if i >= deep else len(lanes), np.int64)
        for j in range(deep):
            pred += q[j, lanes] * out[deep + i - 1 - j, lanes]
        out[deep + i, lanes] = (u >> 1 ^ -(u & 1)) + (pred >> shift[lanes])
    return out[deep:]


# --- columns ----------------------------------------------------------------------


def _padded(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    size = np.diff(offsets)
    full = np.maximum(-(-size // 64), 1) * 64
    at = np.concatenate([[0], np.cumsum(full)])
    out = np.zeros(int(at[-1]), np.uint8)
    out[np.arange(len(data)) + np.repeat(at[:-1] - offsets[:-1], size)] = data
    return out, at


def _encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for rows, data, offsets in chunks(batches, "text", 1 << 20):
        media, at = encode_many(*_padded(data, offsets))
        yield pa.RecordBatch.from_arrays([rows.column(rows.schema.get_field_index("doc_id")), pa.array(np.diff(offsets)), binary_array(media, at)], names=["doc_id", "n_bytes", "media"])


def encode(docs: DataFrame) -> DataFrame:
    """Media rows (doc_id, n_bytes, media) of texts."""
    return docs.select("doc_id", "text").mapInArrow(_encode, "doc_id long, n_bytes long, media binary")


def _media(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
    for rows, media, offsets in chunks(batches, "media", 1 << 20):
        yield rows, media, offsets, *decode_many(media, offsets)


def _features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for rows, media, offsets, pcm, at in _media(batches):
        x = pcm.astype(np.float64) - 128
        lengths = np.diff(at)
        cross = np.zeros(len(x))
        cross[1:] = (x[1:] < 0) != (x[:-1] < 0)
        cross[at[:-1]] = 0
        total = lambda v: np.add.reduceat(v, at[:-1]) / lengths
        mean, power, crossings = total(x), total(x * x), total(cross)
        peak = np.maximum.reduceat(np.abs(x), at[:-1])
        feature = [f"samples={n};mean={m:.4f};rms={p**0.5:.4f};peak={k:.0f};crossings={c:.4f}" for n, m, p, k, c in zip(lengths.tolist(), mean.tolist(), power.tolist(), peak.tolist(), crossings.tolist(), strict=True)]
        sound, stored = memoryview(pcm), memoryview(np.ascontiguousarray(media))
        pairs, kept = list(zip(at[:-1].tolist(), at[1:].tolist(), strict=True)), list(zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True))
        get = lambda n: rows.column(rows.schema.get_field_index(n))
        yield pa.RecordBatch.from_arrays(
            [
                get("doc_id"), get("n_bytes"), pa.array(lengths),
                pa.array([hashlib.sha256(sound[a:b]).hexdigest() for a, b in pairs]), pa.array([zlib.crc32(sound[b - 64 : b]) for _, b in pairs], pa.int64()),
                pa.array(np.diff(offsets)), pa.array([hashlib.sha256(stored[a:b]).hexdigest() for a, b in kept]), pa.array(feature),
            ],
            names=["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"],
        )


def features(media: DataFrame) -> DataFrame:
    """Decodes media rows and describes the samples."""
    return media.mapInArrow(_features, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")


def pcm_blocks(media: DataFrame, block: int = 4096) -> DataFrame:
    """PCM of media rows in blocks with the number of the first sample, so that a reader can seek by (doc_id, sample_offset)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, _, _, pcm, at in _media(batches):
            doc, first, parts = [], [], []
            for d, a, b in zip(rows.column(rows.schema.get_field_index("doc_id")).to_pylist(), at[:-1].tolist(), at[1:].tolist(), strict=True):
                for k in range(a, b, block):
                    doc.append(d)
                    first.append(k - a)
                    parts.append((pcm[k : min(k + block, b)] ^ 0x80).tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(doc, pa.int64()), pa.array(first, pa.int64()), pa.array([len(p) for p in parts], pa.int64()), pa.array(parts, pa.binary())], names=["doc_id", "sample_offset", "samples", "pcm"])

    return media.select("doc_id", "media").mapInArrow(run, "doc_id long, sample_offset long, samples long, pcm binary")


def write_pcm(media: DataFrame, path: str, block: int = 4096) -> str:
    """Writes the blocks of media rows to Parquet files sorted by document and offset, so that a reader opens the row groups of its samples alone."""
    blocks = pcm_blocks(media, block)
    parts = partitions(media.sparkSession)
    blocks.repartitionByRange(parts, "doc_id", "sample_offset").sortWithinPartitions("doc_id", "sample_offset").write.mode("overwrite").option("compression", "zstd").parquet(path)
    return path


def seek(blocks: DataFrame, doc_id: int, first: int, count: int) -> DataFrame:
    """The samples [first, first + count) of a document, as parts (sample_offset, pcm) of its blocks in any order; the condition is pushed to the files' statistics."""
    last = first + count
    held = blocks.filter((F.col("doc_id") == doc_id) & (F.col("sample_offset") < last) & (F.col("sample_offset") + F.col("samples") > first))
    begin = F.greatest(F.lit(first), F.col("sample_offset"))
    end = F.least(F.lit(last), F.col("sample_offset") + F.col("samples"))
    return held.select("doc_id", begin.alias("sample_offset"), F.substring("pcm", (begin - F.col("sample_offset") + 1).cast("int"), (end - begin).cast("int")).alias("pcm"))


def round_trip(docs: DataFrame) -> DataFrame:
    """Texts stored as media and read back: sizes, digests and features per document."""
    return features(stored(encode(docs), "media"))
