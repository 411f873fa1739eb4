"""FLAC media columns: Rice residuals and linear predictors, frame checksums, PCM blocks at seekable sample offsets.

Two decoders read the same format. `decode_stream` walks any mono or stereo FLAC stream, frame by frame (all
subframe kinds, partitioned and escaped Rice residuals, wasted bits, side channels). `decode_many` reads mono
streams of one fixed block size, thousands of frames at a time in numpy: it finds the frames by sync code,
header checksum and frame number, takes one residual of every frame in each step, and then holds each frame's
end against the next one's start and each frame's CRC-16 against the stored one; a stream that isn't of that
kind goes to `decode_stream`.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifscan.llm.common import in_arrow

BLOCK = 192
RATE = 8000
#: Frames that are worked on at once; bounds memory whatever the texts' lengths.
CHUNK = 4096
#: Frames between two seek points.
SEEK_EVERY = 64


def crc_table(poly: int, bits: int) -> np.ndarray:
    top, mask, out = 1 << (bits - 1), (1 << bits) - 1, []
    for byte in range(256):
        r = byte << (bits - 8)
        for _ in range(8):
            r = ((r << 1) ^ (poly if r & top else 0)) & mask
        out.append(r)
    return np.array(out, np.uint16)


CRC8, CRC16 = crc_table(0x07, 8), crc_table(0x8005, 16)
_CRC8, _CRC16 = CRC8.tolist(), CRC16.tolist()


def crc_rows(data: np.ndarray, start: np.ndarray, end: np.ndarray, bits: int) -> np.ndarray:
    """The checksum of data[start:end] of each row. Both start from 0, so leading zeros change nothing and rows are aligned at their ends."""
    n = int((end - start).max(initial=0))
    at = end[None, :] - n + np.arange(n)[:, None]
    rows = np.where(at >= start[None, :], data[np.maximum(at, 0)], 0).astype(np.uint16)
    crc = np.zeros(len(start), np.uint16)
    for row in rows:
        crc = CRC8[crc ^ row] if bits == 8 else (crc << np.uint16(8)) ^ CRC16[(crc >> np.uint16(8)) ^ row]
    return crc


def coded_number(n: int) -> bytes:
    """A frame number as the header has it: like UTF-8, up to 36 bits."""
    if n < 0x80:
        return bytes([n])
    tail = []
    while n >= 1 << (6 - len(tail)):
        tail.append(0x80 | n & 0x3F)
        n >>= 6
    return bytes([(0xFF << (7 - len(tail))) & 0xFF | n, *reversed(tail)])


def _put(bits: np.ndarray, at: np.ndarray, value: np.ndarray | int, width: int) -> None:
    for j in range(width):
        bits[at + j] = (value >> (width - 1 - j)) & 1


def _lpc(x: np.ndarray, order: int, shift: int) -> np.ndarray:
    """Quantised predictor coefficients of each row (Levinson-Durbin on the autocorrelation), for x[i-1], x[i-2], ..."""
    f = x.astype(np.float64)
    r = np.stack([np.einsum("ij,ij->i", f[:, : f.shape[1] - k], f[:, k:]) for k in range(order + 1)], 1)
    r[:, 0] = r[:, 0] * 1.0001 + 1e-3
    a, err = np.zeros((len(x), order)), r[:, 0].copy()
    for i in range(order):
        k = (r[:, i + 1] - np.einsum("ij,ij->i", a[:, :i], r[:, i:0:-1])) / err
        a[:, :i], a[:, i] = a[:, :i] - k[:, None] * a[:, :i][:, ::-1], k
        err *= np.maximum(1 - k * k, 1e-9)
    return np.clip(np.rint(a * (1 << shift)), -128, 127).astype(np.int32)


def encode_frames(x: np.ndarray, number: np.ndarray, lpc_order: int = 2, shift: int = 6) -> tuple[np.ndarray, np.ndarray]:
    """Frames of 8-bit mono blocks: x (frames, samples) signed; number: each frame's number. All frames' bytes, and each one's length."""
    n, size = x.shape
    x = x.astype(np.int32)
    # the residuals of each predictor; a frame takes the one with the least sum
    kinds, residuals = [], []
    r = x
    for order in range(5):
        kinds.append(8 + order)
        residuals.append(r)
        r = r[:, 1:] - r[:, :-1]
    coef = None
    if lpc_order:
        coef = _lpc(x, lpc_order, shift)
        guess = sum(coef[:, j : j + 1] * x[:, lpc_order - 1 - j : size - 1 - j] for j in range(lpc_order)) >> shift
        kinds.append(31 + lpc_order)
        residuals.append(x[:, lpc_order:] - guess)
    cost = np.stack([np.abs(r[:, max(0, 4 - (size - r.shape[1])) :]).sum(1) for r in residuals], 1)
    best = cost.argmin(1)
    kind, k, width = np.empty(n, np.int64), np.zeros(n, np.int64), np.full(n, 8 * size, np.int64)
    coded: list[np.ndarray | None] = [None] * len(kinds)
    for c, (kd, r) in enumerate(zip(kinds, residuals, strict=True)):
        of = np.flatnonzero(best == c)
        if not len(of):
            continue
        u = r[of]
        u = (u << 1) ^ (u >> 31)
        total, m = u.sum(1, dtype=np.int64), u.shape[1]
        tries = np.stack([m * (j + 1) + np.maximum(total - m * ((1 << j) - 1) // 2, 0) / (1 << j) for j in range(13)], 1)
        k[of] = tries.argmin(1)
        kind[of] = kd
        order = size - m
        width[of] = 8 * order + (9 + 8 * order if kd >= 32 else 0) + 10 + (u >> k[of][:, None]).sum(1) + m * (k[of] + 1)
        coded[c] = u
    kind[width >= 8 * size] = 1
    constant = (x == x[:, :1]).all(1)
    kind[constant] = 0
    width = np.where(kind == 0, 8, np.where(kind == 1, 8 * size, width))
    heads = [b"\xff\xf8" + bytes([0x10 if size == 192 else 0x70, 0x02]) + coded_number(int(i)) + (b"" if size == 192 else struct.pack(">H", size - 1)) for i in number]
    head_len = np.fromiter(map(len, heads), np.int64, n)
    length = head_len + 2 + (width + 7) // 8 + 2
    end = np.cumsum(length)
    start = end - length
    body = start + head_len + 2  # behind CRC-8 and the subframe's header byte
    bits = np.zeros(8 * int(end[-1] if n else 0), np.uint8)
    for c, u in enumerate(coded):
        if u is None:
            continue
        kd, m = kinds[c], u.shape[1]
        of = np.flatnonzero(best == c)
        keep = kind[of] == kd
        of, u, order = of[keep], u[keep], size - m
        if not len(of):
            continue
        at = 8 * body[of]
        for j in range(order):
            _put(bits, at, x[of, j] & 0xFF, 8)
            at = at + 8
        if kd >= 32:
            _put(bits, at, 7, 4)
            _put(bits, at + 4, shift, 5)
            at = at + 9
            for j in range(order):
                _put(bits, at, coef[of, j] & 0xFF, 8)
                at = at + 8
        _put(bits, at + 6, k[of], 4)
        at = at + 10
        for kk in np.unique(k[of]):
            sub = np.flatnonzero(k[of] == kk)
            v = u[sub]
            q = v >> kk
            stop = at[sub][:, None] + np.cumsum(q + (1 + kk), 1) - (1 + kk)
            bits[stop] = 1
            for j in range(kk):
                bits[stop + (j + 1)] = (v >> (kk - 1 - j)) & 1
    out = np.packbits(bits)
    of = np.flatnonzero(kind == 1)
    out[body[of][:, None] + np.arange(size)] = x[of] & 0xFF
    of = np.flatnonzero(kind == 0)
    out[body[of]] = x[of, 0] & 0xFF
    for ln in np.unique(head_len):
        of = np.flatnonzero(head_len == ln)
        rows = np.frombuffer(b"".join(heads[i] for i in of), np.uint8).reshape(len(of), ln)
        out[start[of][:, None] + np.arange(ln)] = rows
    out[start + head_len] = crc_rows(out, start, start + head_len, 8)
    out[start + head_len + 1] = kind << 1
    crc = crc_rows(out, start, end - 2, 16)
    out[end - 2], out[end - 1] = crc >> 8, crc & 0xFF
    return out, length


def head(n_samples: int, pcm_md5: bytes, lengths: np.ndarray, size: int = BLOCK, every: int = SEEK_EVERY) -> bytes:
    """The marker, STREAMINFO and a SEEKTABLE with a point for each `every` frames."""
    info = struct.pack(">HH", size, size) + int(lengths.min()).to_bytes(3) + int(lengths.max()).to_bytes(3)
    info += (RATE << 44 | 0 << 41 | 7 << 36 | n_samples).to_bytes(8) + pcm_md5
    before = np.cumsum(lengths) - lengths
    points = b"".join(struct.pack(">QQH", i * size, int(before[i]), size) for i in range(0, len(lengths), every))
    return b"fLaC\x00" + len(info).to_bytes(3) + info + b"\x83" + len(points).to_bytes(3) + points


def encode_many(payloads: list[bytes], lpc_order: int = 2) -> list[bytes]:
    """A mono 8-bit FLAC stream of each payload; a payload is a positive multiple of BLOCK bytes, each one a sample less 128."""
    counts = np.array([len(p) // BLOCK for p in payloads], np.int64)
    pcm = (np.frombuffer(b"".join(payloads), np.uint8) ^ 0x80).view(np.int8).reshape(-1, BLOCK)
    number = np.arange(len(pcm)) - np.repeat(np.cumsum(counts) - counts, counts)
    parts = [encode_frames(pcm[i : i + CHUNK], number[i : i + CHUNK], lpc_order) for i in range(0, len(pcm), CHUNK)]
    data, lengths = b"".join(p[0].tobytes() for p in parts), np.concatenate([p[1] for p in parts])
    out, f, b = [], 0, 0
    for c in counts.tolist():
        ln = lengths[f : f + c]
        total = int(ln.sum())
        out.append(head(c * BLOCK, hashlib.md5(pcm[f : f + c].tobytes()).digest(), ln) + data[b : b + total])
        f, b = f + c, b + total
    return out


class Damaged(ValueError):
    """A stream that breaks the format or a checksum."""


def metadata(stream: bytes) -> dict:
    """STREAMINFO, the seek points (sample, byte, samples) and where the frames begin."""
    if stream[:4] != b"fLaC":
        raise Damaged("no FLAC marker")
    at, out, last = 4, {"seek": []}, False
    while not last:
        if at + 4 > len(stream):
            raise Damaged("metadata is cut off")
        last, kind, n = stream[at] >> 7, stream[at] & 0x7F, int.from_bytes(stream[at + 1 : at + 4])
        data = stream[at + 4 : at + 4 + n]
        if kind == 0:
            packed = int.from_bytes(data[10:18])
            out |= {"min_block": int.from_bytes(data[:2]), "max_block": int.from_bytes(data[2:4]), "rate": packed >> 44, "channels": (packed >> 41 & 7) + 1, "bits": (packed >> 36 & 31) + 1, "samples": packed & (1 << 36) - 1, "md5": data[18:34]}
        elif kind == 3:
            out["seek"] = [p for p in struct.iter_unpack(">QQH", data[: n // 18 * 18]) if p[0] != (1 << 64) - 1]
        at += 4 + n
    if "rate" not in out:
        raise Damaged("no STREAMINFO")
    return out | {"first": at}


class _Bits:
    def __init__(self, data: bytes, at: int):
        self.data, self.at = data, 8 * at

    def take(self, n: int) -> int:
        if not n:
            return 0
        a, b = self.at >> 3, (self.at + n + 7) >> 3
        if b > len(self.data):
            raise Damaged("a frame is cut off")
        v = int.from_bytes(self.data[a:b]) >> (8 * b - self.at - n) & (1 << n) - 1
        self.at += n
        return v

    def signed(self, n: int) -> int:
        v = self.take(n)
        return v - (1 << n) if n and v >> (n - 1) else v

    def unary(self) -> int:
        n = 0
        while not self.take(1):
            n += 1
        return n


def _residual(b: _Bits, size: int, order: int) -> list[int]:
    method, parts = b.take(2), b.take(4)
    if method > 1 or size >> parts < order or size % (1 << parts):
        raise Damaged("bad residual coding")
    wide, out = 5 if method else 4, []
    for i in range(1 << parts):
        k, n = b.take(wide), (size >> parts) - (order if i == 0 else 0)
        if k == (1 << wide) - 1:
            raw = b.take(5)
            out += [b.signed(raw) for _ in range(n)]
        else:
            for _ in range(n):
                u = b.unary() << k | b.take(k)
                out.append(u >> 1 ^ -(u & 1))
    return out


def _subframe(b: _Bits, size: int, bits: int) -> list[int]:
    b.take(1)
    kind, wasted = b.take(6), 0
    if b.take(1):
        wasted = b.unary() + 1
        bits -= wasted
    if kind == 0:
        out = [b.signed(bits)] * size
    elif kind == 1:
        out = [b.signed(bits) for _ in range(size)]
    elif 8 <= kind <= 12 or kind >= 32:
        order = kind - 8 if kind < 32 else kind - 31
        out = [b.signed(bits) for _ in range(order)]
        if kind < 32:
            coef, shift = [(), (1,), (2, -1), (3, -3, 1), (4, -6, 4, -1)][order], 0
        else:
            precision, shift = b.take(4) + 1, b.signed(5)
            coef = [b.signed(precision) for _ in range(order)]
        for r in _residual(b, size, order):
            out.append(r + (sum(c * out[-1 - j] for j, c in enumerate(coef)) >> shift))
    else:
        raise Damaged("unknown subframe")
    return [v << wasted for v in out] if wasted else out


def _frame(stream: bytes, at: int, info: dict) -> tuple[list[list[int]], int, int]:
    """The channels of the frame at a byte, its first sample and where it ends; both checksums hold."""
    b = _Bits(stream, at)
    if b.take(15) != 0x7FFC:
        raise Damaged("no sync code")
    variable, size, rate, channels, bits = b.take(1), b.take(4), b.take(4), b.take(4), b.take(3)
    b.take(1)
    lead = b.take(8)
    more = 0 if lead < 0x80 else 8 - (~lead & 0xFF).bit_length() - 1
    number = lead if not more else lead & ((1 << (6 - more)) - 1)
    for _ in range(more):
        number = number << 6 | b.take(8) & 0x3F
    size = 192 if size == 1 else 576 << (size - 2) if 2 <= size <= 5 else b.take(8) + 1 if size == 6 else b.take(16) + 1 if size == 7 else 256 << (size - 8)
    b.take({12: 8, 13: 16, 14: 16}.get(rate, 0))
    crc = 0
    for v in stream[at : b.at >> 3]:
        crc = _CRC8[crc ^ v]
    if crc != b.take(8):
        raise Damaged("header checksum differs")
    bits = {0: info["bits"], 1: 8, 2: 12, 4: 16, 5: 20, 6: 24, 7: 32}[bits]
    if channels < 8:
        out = [_subframe(b, size, bits) for _ in range(channels + 1)]
    else:
        l, r = (_subframe(b, size, bits + (channels == (9, 8, 10)[0] and i == 0 or channels in (8, 10) and i == 1)) for i in range(2))
        if channels == 8:
            out = [l, [a - s for a, s in zip(l, r, strict=True)]]
        elif channels == 9:
            out = [[s + a for s, a in zip(l, r, strict=True)], r]
        else:
            mid = [m << 1 | s & 1 for m, s in zip(l, r, strict=True)]
            out = [[(m + s) >> 1 for m, s in zip(mid, r, strict=True)], [(m - s) >> 1 for m, s in zip(mid, r, strict=True)]]
    end, crc = (b.at + 7) >> 3, 0
    for v in stream[at:end]:
        crc = (crc << 8 & 0xFFFF) ^ _CRC16[crc >> 8 ^ v]
    if crc != int.from_bytes(stream[end : end + 2]):
        raise Damaged("frame checksum differs")
    return out, number if variable else number * info["min_block"], end + 2


def decode_stream(stream: bytes, start: int = 0, count: int | None = None) -> Iterator[tuple[int, int, list[list[int]]]]:
    """(first sample, byte of the frame, channels) of the frames that hold the samples from start on; the seek table says where to begin."""
    info = metadata(stream)
    at = info["first"] + max([p[1] for p in info["seek"] if p[0] <= start], default=0)
    last = info["samples"] or 1 << 62
    last = last if count is None else min(last, start + count)
    while at < len(stream):
        pcm, first, end = _frame(stream, at, info)
        if first >= last:
            return
        if first + len(pcm[0]) > start:
            yield first, at, pcm
        at = end


def read_samples(stream: bytes, start: int, count: int) -> list[list[int]]:
    """Samples start to start + count of each channel."""
    out: list[list[int]] = []
    for first, _, pcm in decode_stream(stream, start, count):
        out = out or [[] for _ in pcm]
        for o, c in zip(out, pcm, strict=True):
            o += c[max(0, start - first) : max(0, start + count - first)]
    return out


def _decode_frames(data: np.ndarray, start: np.ndarray, end: np.ndarray, body: np.ndarray, size: int) -> np.ndarray | None:
    """PCM (frames, size) of 8-bit mono frames; None if one isn't plain or doesn't end where the next begins."""
    kind = (data[body] >> 1).astype(np.int64)
    if (data[body] & 0x81).any():
        return None
    x, stop, body = np.empty((len(start), size), np.int32), 8 * (end - 2), 8 * (body + 1)
    signed = data.view(np.int8)
    lo, hi = int(start[0]), int(end[-1])
    part = np.concatenate([data[lo:hi], np.zeros(8, np.uint8)])
    bits = np.unpackbits(part)
    following = np.where(bits, np.arange(len(bits), dtype=np.int32), np.int32(len(bits) - 1))
    following = np.minimum.accumulate(following[::-1])[::-1]
    wide = part.astype(np.uint64)
    window = (wide[:-3] << np.uint64(24)) | (wide[1:-2] << np.uint64(16)) | (wide[2:-1] << np.uint64(8)) | wide[3:]

    def peek(at: np.ndarray, n: np.ndarray | int) -> np.ndarray:
        return (((window[at >> 3] << (at & 7).astype(np.uint64)) & np.uint64(0xFFFFFFFF)) >> (np.uint64(32) - np.asarray(n).astype(np.uint64))).astype(np.int64)

    for kd in np.unique(kind):
        of = np.flatnonzero(kind == kd)
        at = body[of] // 8
        if kd <= 1:
            x[of] = signed[at][:, None] if kd == 0 else signed[at[:, None] + np.arange(size)]
            used = body[of] + (8 if kd == 0 else 8 * size)
        elif 8 <= kd <= 12 or kd >= 32:
            order = int(kd - 8 if kd < 32 else kd - 31)
            warm = signed[at[:, None] + np.arange(order)].astype(np.int32)
            pos = body[of] + 8 * order - 8 * lo
            if kd >= 32:
                precision, shift = peek(pos, 4) + 1, peek(pos + 4, 5)
                if (precision != precision[0]).any() or (shift > 15).any():
                    return None
                pos = pos + 9
                coef = np.stack([peek(pos + j * precision, precision) for j in range(order)], 1)
                coef = np.where(coef >= 1 << (precision[:, None] - 1), coef - (1 << precision[:, None]), coef)
                pos = pos + order * precision
            if peek(pos, 6).any():
                return None
            k = peek(pos + 6, 4)
            if (k == 15).any():
                return None
            pos, r = pos + 10, np.empty((size - order, len(of)), np.int32)
            k64, k1, down = k.astype(np.uint64), k + 1, np.uint64(32) - k.astype(np.uint64)
            last = len(bits) - 64
            for i in range(size - order):
                one = following[np.minimum(pos, last)]
                q = one - pos
                pos = one.astype(np.int64) + k1
                at_k = one + 1
                rest = ((window[at_k >> 3] << (at_k & 7).astype(np.uint64)) & np.uint64(0xFFFFFFFF)) >> down
                u = (q << k) | rest.astype(np.int64)
                r[i] = (u >> 1) ^ -(u & 1)
            res, used = r.T, pos + 8 * lo
            if kd < 32:
                seq = res
                for j in range(order - 1, -1, -1):
                    seq = np.cumsum(np.concatenate([np.diff(warm[:, : j + 1], n=j, axis=1), seq], 1), 1, dtype=np.int32)
                x[of] = seq
            else:
                y = np.empty((size, len(of)), np.int64)
                y[:order] = warm.T
                for i in range(order, size):
                    y[i] = r[i - order] + (sum(coef[:, j] * y[i - 1 - j] for j in range(order)) >> shift)
                x[of] = y.T
        else:
            return None
        if (-(-used // 8) != stop[of] // 8).any():
            return None
    return x


def decode_many(streams: list[bytes]) -> list[np.ndarray]:
    """The PCM samples of mono streams; every frame's checksums and the stream's MD5 hold, else Damaged is raised."""
    infos = [metadata(s) for s in streams]
    plain = [i for i, m in enumerate(infos) if m["channels"] == 1 and m["bits"] == 8 and m["min_block"] == m["max_block"] == BLOCK and m["samples"] % BLOCK == 0 and m["samples"]]
    out: list[np.ndarray | None] = [None] * len(streams)
    if plain:
        data = np.frombuffer(b"".join(streams[i][infos[i]["first"] :] for i in plain) + bytes(16), np.uint8)
        ends = np.cumsum([len(streams[i]) - infos[i]["first"] for i in plain])
        begins = np.concatenate([[0], ends[:-1]])
        frames = np.array([infos[i]["samples"] // BLOCK for i in plain], np.int64)
        firsts = np.cumsum(frames) - frames
        at = np.flatnonzero((data[:-3] == 0xFF) & (data[1:-2] == 0xF8) & (data[2:-1] == 0x10) & (data[3:] == 0x02))
        lead = data[at + 4].astype(np.int64)
        more = np.select([lead < 0x80, lead < 0xE0, lead < 0xF0, lead < 0xF8, lead < 0xFC, lead < 0xFE], [0, 1, 2, 3, 4, 5], 6)
        number = np.where(more == 0, lead, lead & ((1 << np.maximum(6 - more, 0)) - 1))
        for j in range(int(more.max(initial=0))):
            number = np.where(more > j, number << 6 | data[np.minimum(at + 5 + j, len(data) - 1)] & 0x3F, number)
        crc_at = np.minimum(at + 5 + more, len(data) - 1)
        good = crc_rows(data, at, crc_at, 8) == data[crc_at]
        of = np.searchsorted(ends, at, "right")
        at, number, body, of = at[good], number[good], crc_at[good] + 1, of[good]
        want = firsts[np.minimum(of, len(firsts) - 1)] + number
        # one candidate for each frame, in order: else the slow way
        ok = len(at) == int(frames.sum()) and (want == np.arange(len(at))).all() and (of < len(firsts)).all() and (number < frames[of]).all() and (at[firsts] == begins).all()
        if ok:
            end = np.append(at[1:], ends[-1])
            ok = (crc_rows_in_chunks(data, at, end - 2) == (data[end - 2].astype(np.uint16) << 8 | data[end - 1])).all()
            pcm = np.empty((len(at), BLOCK), np.int8)
            for c in range(0, len(at), CHUNK) if ok else ():
                x = _decode_frames(data, at[c : c + CHUNK], end[c : c + CHUNK], body[c : c + CHUNK], BLOCK)
                if x is None:
                    ok = False
                    break
                pcm[c : c + CHUNK] = x
        if ok:
            for i, f, c in zip(plain, firsts.tolist(), frames.tolist(), strict=True):
                out[i] = pcm[f : f + c].reshape(-1)
    for i, stream in enumerate(streams):
        if out[i] is None:
            samples = [v for _, _, pcm in decode_stream(stream) for v in (pcm[0] if len(pcm) == 1 else np.stack(pcm, 1).reshape(-1).tolist())]
            out[i] = np.array(samples, np.int8 if infos[i]["bits"] <= 8 else np.int16 if infos[i]["bits"] <= 16 else np.int32)
        if out[i].dtype == np.int8 and infos[i]["md5"] != bytes(16) and hashlib.md5(out[i].tobytes()).digest() != infos[i]["md5"]:
            raise Damaged("MD5 of the samples differs")
    return out


def crc_rows_in_chunks(data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    return np.concatenate([crc_rows(data, start[c : c + CHUNK], end[c : c + CHUNK], 16) for c in range(0, len(start), CHUNK)])


def _features(pcm: np.ndarray) -> str:
    """Level and shape of the samples: frames, mean, root of the mean square, crossings of the mean, steps."""
    x = pcm.astype(np.int32)
    crossings = int((np.diff((x >= x.mean()).view(np.int8)) != 0).sum())
    return f"frames={len(x) // BLOCK};mean={x.mean():.4f};rms={np.sqrt((x * x).mean()):.4f};crossings={crossings};step={np.abs(np.diff(x)).mean():.4f};peak={int(np.abs(x).max())}"


def _batches(texts: list[bytes], most: int = CHUNK * BLOCK) -> Iterator[list[bytes]]:
    now, n = [], 0
    for t in texts:
        now.append(t)
        n += max(len(t), BLOCK)
        if n >= most:
            yield now
            now, n = [], 0
    if now:
        yield now


def to_media(docs: DataFrame, with_media: bool = False, lpc_order: int = 2) -> DataFrame:
    """Stores every whole text as a FLAC stream, reads it back and describes both.

    The text in UTF-8 (null: empty), filled up with bytes 32 to a positive multiple of 192, is the payload; each
    byte less 128 is a sample. with_media adds the stored stream as column media. Repeated rows give repeated
    rows; other columns aren't read. Runs where the rows are, a bounded number of frames at a time.
    """
    fields = [("doc_id", pa.int64(), "long"), ("n_bytes", pa.int64(), "long"), ("payload_bytes", pa.int64(), "long"), ("payload_sha256", pa.string(), "string"), ("tail_crc32", pa.int64(), "long"), ("media_bytes", pa.int64(), "long"), ("media_sha256", pa.string(), "string"), ("feature", pa.string(), "string")]
    if with_media:
        fields.append(("media", pa.binary(), "binary"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 256):
                batch = whole.slice(at, 256)
                texts = [(t or "").encode() for t in batch.column(1).to_pylist()]
                columns: list[list] = [[] for _ in fields[1:]]
                for group in _batches(texts):
                    streams = encode_many([t + b" " * (-len(t) % BLOCK if t else BLOCK) for t in group], lpc_order)
                    for text, stream, pcm in zip(group, streams, decode_many(streams), strict=True):
                        payload = (pcm.view(np.uint8) ^ 0x80).tobytes()
                        row = [len(text), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), len(stream), hashlib.sha256(stream).hexdigest(), _features(pcm), stream]
                        for c, v in zip(columns, row, strict=False):
                            c.append(v)
                yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, f[1]) for c, f in zip(columns, fields[1:], strict=True))], [f[0] for f in fields])

    return in_arrow(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")), run, ", ".join(f"{n} {s}" for n, _, s in fields))


def pcm_blocks(media: DataFrame, id_col: str = "doc_id", media_col: str = "media") -> DataFrame:
    """A row for each frame of each stream: id, block, sample_offset, byte_offset, n_samples, channels, pcm (binary, 32-bit little endian, interleaved).

    A null stream gives no rows. A damaged one gives a last row with the reason in error and no pcm, behind its good frames.
    """
    names = [id_col, "block", "sample_offset", "byte_offset", "n_samples", "channels", "pcm", "error"]
    kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.binary(), pa.string()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for key, stream in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                if not stream.is_valid:
                    continue
                rows, block = [], 0
                try:
                    for first, byte, pcm in decode_stream(stream.as_py()):
                        rows.append((key, block, first, byte, len(pcm[0]), len(pcm), np.array(pcm, "<i4").T.tobytes(), None))
                        block += 1
                        if len(rows) == CHUNK:
                            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names)
                            rows = []
                except Damaged as e:
                    rows.append((key, block, None, None, 0, 0, None, str(e)))
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names)

    return in_arrow(media.select(F.col(id_col).cast("long"), F.col(media_col).cast("binary")), run, f"`{id_col}` long, block int, sample_offset long, byte_offset long, n_samples int, channels int, pcm binary, error string")
