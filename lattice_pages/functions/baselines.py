"""Published codecs to compare with, re-implemented from their public descriptions.

Every one takes one page of 64-bit words and gives bytes that decode without any other
state. They make no claim about the speed of the originals.
"""

from __future__ import annotations

import math
import struct
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

from lattice_pages.functions import admission
from lattice_pages.functions.bits import Reader, Writer, bit_length, canonical, code_lengths, read_varint, unzigzag, varint, zigzag
from lattice_pages.functions.rawlane import read_raw, xor_fields

_M64 = (1 << 64) - 1


class _Out:
    """Scalar bit output, packed at once."""

    def __init__(self) -> None:
        self.v: list[int] = []
        self.w: list[int] = []

    def put(self, value: int, width: int) -> None:
        self.v.append(value & _M64)
        self.w.append(width)

    def gamma(self, v: int) -> None:
        n = v.bit_length()
        self.put(0, n - 1)
        self.put(v, n)

    def bytes(self) -> bytes:
        w = Writer()
        if self.v:
            w.array(np.array(self.v, np.uint64), np.array(self.w))
        return w.bytes()


def _unsigned(words: np.ndarray) -> list[int]:
    return np.asarray(words, np.int64).view(np.uint64).tolist()


def _signed(values: list[int]) -> np.ndarray:
    return np.array(values, np.uint64).view(np.int64)


# ---------------------------------------------------------------- XOR of words


def _xors(words: np.ndarray) -> np.ndarray:
    w = np.asarray(words, np.int64).view(np.uint64)
    return w[1:] ^ w[:-1]


def gorilla_encode(words: np.ndarray) -> bytes:
    """XORs under a reusable window, with a 5 + 6 bit header for a new one."""
    out = Writer()
    if len(words):
        out.put(int(words[0]), 64)
        out.array(*xor_fields(_xors(words), 31, 5))
    return varint(len(words)) + out.bytes()


def gorilla_decode(data: bytes) -> np.ndarray:
    n, at = read_varint(data, 0)
    return read_raw(n, Reader(data[at:]), 5).view(np.int64)


#: The rounded leading-zero counts.
_LEADS = (0, 8, 12, 16, 18, 20, 22, 24)


def chimp_encode(words: np.ndarray) -> bytes:
    out = Writer()
    if len(words):
        out.put(int(words[0]), 64)
        x = _xors(words)
        k = np.searchsorted(_LEADS, 64 - bit_length(x), side="right") - 1
        lead, tail = np.array(_LEADS)[k], bit_length(x & (~x + np.uint64(1))) - 1
        same, short = x == 0, tail > 6
        known = ~same & ~short  # leaves its count of leading zeros for the next one
        again = known & np.concatenate([[False], known[:-1] & (k[1:] == k[:-1])])[: len(x)]
        n = np.where(short, 64 - lead - np.maximum(tail, 0), 64 - lead)
        flag = np.where(same, 0, np.where(short, 1, np.where(again, 2, 3)))
        head = np.where(same | again, 0, 3)
        values = np.stack([flag, k, n - 1, np.where(short, x >> np.maximum(tail, 0).astype(np.uint64), x).view(np.int64)], axis=1).view(np.uint64)
        out.array(values, np.stack([np.full(len(x), 2), head, np.where(short & ~same, 6, 0), np.where(same, 0, n)], axis=1))
    return varint(len(words)) + out.bytes()


def chimp_decode(data: bytes) -> np.ndarray:
    n, at = read_varint(data, 0)
    r = Reader(data[at:])
    out = np.zeros(n, np.uint64)
    if not n:
        return out.view(np.int64)
    out[0] = r.get(64)
    bits, i, last = r.bits.tolist(), 64, None
    which, places, sizes, shifts = [], [], [], []
    for j in range(1, n):
        flag, i = 2 * bits[i] + bits[i + 1], i + 2
        if not flag:
            last = None
            continue
        shift = 0
        if flag == 2:
            size = 64 - last
        else:
            lead, i = _LEADS[4 * bits[i] + 2 * bits[i + 1] + bits[i + 2]], i + 3
            size = 64 - lead
            last = lead
            if flag == 1:
                r.at = i
                size, i, last = r.get(6) + 1, i + 6, None
                shift = 64 - lead - size
        which.append(j)
        places.append(i)
        sizes.append(size)
        shifts.append(shift)
        i += size
    if which:
        out[which] = r.fields(np.array(places), np.array(sizes)) << np.array(shifts).astype(np.uint64)
    return np.bitwise_xor.accumulate(out).view(np.int64)


def _scales(x: np.ndarray) -> np.ndarray:
    """The lowest scale that rebuilds each value exactly, or -1."""
    _, ok = admission.scale_matrix(x)
    return np.where(ok.any(axis=0), ok.argmax(axis=0), -1)


def _restore(erased: np.ndarray, s: np.ndarray) -> np.ndarray:
    """The words with scales s that lie next above erased words in magnitude."""
    e = erased.view(np.float64)
    with np.errstate(all="ignore"):
        m = np.ceil(np.abs(e) * admission.POWERS[s]) / admission.POWERS[s]
    return np.copysign(m, e).view(np.uint64)


def _erase(w: np.ndarray, s: np.ndarray) -> np.ndarray:
    """Clears the longest mantissa suffix that ``_restore`` brings back."""
    lo, hi = np.zeros(len(w), np.uint64), np.full(len(w), 52, np.uint64)
    for _ in range(6):  # 52 < 2^6
        k = (lo + hi + np.uint64(1)) // np.uint64(2)
        good = _restore(w >> k << k, s) == w
        lo, hi = np.where(good, k, lo), np.where(good | (lo >= hi), hi, k - np.uint64(1))
    return w >> lo << lo


def erase_encode(words: np.ndarray, reuse: bool = False) -> bytes:
    w = np.asarray(words, np.int64).view(np.uint64)
    out = Writer()
    if len(w):
        s = _scales(w.view(np.float64))
        few = (s >= 0) & (s <= 17)
        e = np.where(few, _erase(w, np.where(few, s, 0)), w)
        s = np.where(e != w, s, 31)
        same = np.concatenate([[False], s[1:] == s[:-1]]) & reuse
        values, widths = np.zeros((len(w), 6), np.uint64), np.zeros((len(w), 6), np.int64)
        values[:, 0], widths[:, 0] = same, int(reuse)
        values[:, 1], widths[:, 1] = s, np.where(same, 0, 5)
        values[0, 2], widths[0, 2] = e[0], 64
        values[1:, 2:], widths[1:, 2:] = xor_fields(e[1:] ^ e[:-1], 31, 5)
        out.array(values, widths)
    return varint(len(words)) + bytes([reuse]) + out.bytes()


def erase_decode(data: bytes) -> np.ndarray:
    n, at = read_varint(data, 0)
    reuse, r = data[at], Reader(data[at + 1 :])
    x, s = np.zeros(n, np.uint64), 31
    bits, i, size, tail, scales = r.bits.tolist(), 0, None, None, []
    which, places, sizes, shifts = [], [], [], []
    for j in range(n):
        if reuse:
            i += 1
        if not (reuse and bits[i - 1]):
            s = 16 * bits[i] + 8 * bits[i + 1] + 4 * bits[i + 2] + 2 * bits[i + 3] + bits[i + 4]
            i += 5
        scales.append(s)
        if not j:
            r.at = i
            x[0], i = r.get(64), i + 64
            continue
        if not bits[i]:
            i += 1
            continue
        if bits[i + 1]:
            r.at = i + 2
            lead = r.get(5)
            size = r.get(6) + 1
            tail = 64 - lead - size
            i += 11
        i += 2
        which.append(j)
        places.append(i)
        sizes.append(size)
        shifts.append(tail)
        i += size
    if which:
        x[which] = r.fields(np.array(places), np.array(sizes)) << np.array(shifts).astype(np.uint64)
    x, s = np.bitwise_xor.accumulate(x), np.array(scales, np.int64)
    kept = s == 31
    return np.where(kept, x, _restore(x, np.where(kept, 0, s))).view(np.int64)


# ---------------------------------------------------------------- decimal integers


def _raws(words: np.ndarray, at: np.ndarray) -> bytes:
    return varint(len(at)) + b"".join(varint(int(d)) for d in np.diff(at, prepend=0)) + words[at].astype("<i8").tobytes()


def _read_raws(data: bytes, at: int) -> tuple[np.ndarray, np.ndarray, int]:
    n, at = read_varint(data, at)
    gaps = []
    for _ in range(n):
        g, at = read_varint(data, at)
        gaps.append(g)
    return np.cumsum(np.array(gaps, np.int64)), np.frombuffer(data, "<i8", n, at), at + 8 * n


def frame_of_reference_encode(words: np.ndarray) -> bytes:
    """One decimal exponent per page, integers against their minimum, exceptions aside."""
    words = np.asarray(words, np.int64)
    x, best = words.view(np.float64), None
    for s, q, ok in zip(admission.SCALES, *admission.scale_matrix(x)):
        low = int(q[ok].min()) if ok.any() else 0
        width = int(int(q[ok].max()) - low).bit_length() if ok.any() else 0
        bits = width * len(x) + int((~ok).sum()) * 80
        if width <= 63 and (best is None or bits < best[0]):
            best = (bits, s, q, ok, low, width)
    if best is None:
        best = (0, 0, np.zeros(len(x), np.int64), np.zeros(len(x), bool), 0, 0)
    _, s, q, ok, low, width = best
    out = Writer()
    out.array(np.where(ok, q - np.int64(low), 0).view(np.uint64), width)
    return varint(len(x)) + bytes([s, width]) + int(low).to_bytes(8, "little", signed=True) + _raws(words, np.flatnonzero(~ok)) + out.bytes()


def frame_of_reference_decode(data: bytes) -> np.ndarray:
    n, at = read_varint(data, 0)
    s, width, low = data[at], data[at + 1], int.from_bytes(data[at + 2 : at + 10], "little", signed=True)
    where, raw, at = _read_raws(data, at + 10)
    q = Reader(data[at:]).array(np.full(n, width)).view(np.int64) + np.int64(low)
    out = admission.rebuild_exact(q, s).view(np.int64).copy()
    out[where] = raw
    return out


def decimal_neighbor_encode(words: np.ndarray) -> bytes:
    """Each value at its own scale against its neighbour, realigned where the scales differ."""
    x = np.asarray(words, np.int64).view(np.float64)
    q, ok = admission.scale_matrix(x)
    out, last, prev = _Out(), 0, 0
    scales = np.where(ok.any(axis=0), ok.argmax(axis=0), -1)
    own = q[np.maximum(scales, 0), np.arange(len(x))]
    for s, c, w in zip(scales.tolist(), own.tolist(), _unsigned(words)):
        if s < 0 or abs(c) >= 1 << 60:
            out.put(0b11, 2)
            out.put(w, 64)
            continue
        if s == last:
            out.put(0, 1)
        else:
            out.put(0b10, 2)
            out.put(s, 5)
        base = prev * 10 ** (s - last) if s >= last else round(prev / 10 ** (last - s))
        d = c - base
        z = 2 * d if d >= 0 else -2 * d - 1
        n = z.bit_length()
        out.put(n, 7)
        if n > 64:
            out.put(z >> 64, n - 64)
        out.put(z, min(n, 64))
        last, prev = s, c
    return varint(len(x)) + out.bytes()


def decimal_neighbor_decode(data: bytes) -> np.ndarray:
    n, at = read_varint(data, 0)
    r, last, prev = Reader(data[at:]), 0, 0
    q, scales, whole = np.zeros(n, np.int64), np.zeros(n, np.int64), {}
    for i in range(n):
        s = last
        if r.get(1):
            if r.get(1):
                whole[i] = r.get(64)
                continue
            s = r.get(5)
        base = prev * 10 ** (s - last) if s >= last else round(prev / 10 ** (last - s))
        z = r.get(r.get(7))
        prev, last = base + (z >> 1 if z & 1 == 0 else -(z + 1 >> 1)), s
        q[i], scales[i] = prev, s
    out = (q.astype(np.float64) / admission.POWERS[scales]).view(np.int64)
    out[list(whole)] = _signed(list(whole.values()))
    return out


def bitplane_encode(words: np.ndarray) -> bytes:
    """Deltas at one scale, ZigZag, transposed to bit planes; empty planes cost a bit, sparse ones positions."""
    words = np.asarray(words, np.int64)
    x = words.view(np.float64)
    scales = _scales(x)
    s = int(scales.max(initial=0))
    q, ok = (m[s] for m in admission.scale_matrix(x))
    if ok.mean() < 0.5 if len(ok) else True:
        s, q, ok = 31, words, np.ones(len(words), bool)
    q = np.where(ok, q, 0)
    with np.errstate(over="ignore"):
        z = zigzag(np.diff(q, prepend=np.int64(0)))
    out, n = Writer(), len(words)
    step = max(1, (n - 1).bit_length())
    for p in range(63, -1, -1):
        plane = (z >> np.uint64(p)) & np.uint64(1)
        ones = np.flatnonzero(plane)
        if not len(ones):
            out.put(0, 1)
        elif (len(ones) + 1) * step < n:
            out.put(0b10, 2)
            out.put(len(ones), step)
            out.array(ones.astype(np.uint64), step)
        else:
            out.put(0b11, 2)
            out.array(plane, 1)
    return varint(n) + bytes([s]) + _raws(words, np.flatnonzero(~ok)) + out.bytes()


def bitplane_decode(data: bytes) -> np.ndarray:
    n, at = read_varint(data, 0)
    s = data[at]
    where, raw, at = _read_raws(data, at + 1)
    r, z, step = Reader(data[at:]), np.zeros(n, np.uint64), max(1, (n - 1).bit_length())
    for p in range(63, -1, -1):
        if r.get(1):
            if r.get(1):
                plane = r.flags(n)
            else:
                plane = np.zeros(n, bool)
                plane[r.array(np.full(r.get(step), step)).astype(np.int64)] = True
            z |= plane.astype(np.uint64) << np.uint64(p)
    with np.errstate(over="ignore"):
        q = np.cumsum(unzigzag(z))
    out = q.copy() if s == 31 else admission.rebuild_exact(q, s).view(np.int64).copy()
    out[where] = raw
    return out


# ---------------------------------------------------------------- general byte codecs


def _bytes_codec(name: str, level: int | None = None) -> tuple[Callable, Callable]:
    def encode(words: np.ndarray) -> bytes:
        raw = np.asarray(words, "<i8").tobytes()
        return varint(len(raw)) + bytes(pa.Codec(name, compression_level=level).compress(raw, asbytes=True)) if raw else varint(0)

    def decode(data: bytes) -> np.ndarray:
        n, at = read_varint(data, 0)
        return np.frombuffer(pa.Codec(name).decompress(data[at:], n, asbytes=True) if n else b"", "<i8").astype(np.int64)

    return encode, decode


# ---------------------------------------------------------------- error-bounded


def _quantised(x: np.ndarray, eps: float) -> tuple[np.ndarray, np.ndarray]:
    """(index on a grid of 2 eps, whether it meets the bound)."""
    step = 2 * eps
    with np.errstate(all="ignore"):
        q = np.rint(x / step)
        fits = np.isfinite(q) & (np.abs(q) < 2.0**52)
        i = np.where(fits, q, 0).astype(np.int64)
        ok = fits & (np.abs(x - i * step) <= eps)
    return np.where(ok, i, 0), ok


def _huffman_write(symbols: np.ndarray, out: Writer) -> bytes:
    s, n = np.unique(symbols, return_counts=True)
    lengths = code_lengths(dict(zip(s.tolist(), n.tolist())))
    codes = canonical(lengths)
    pairs = np.array([codes[v] for v in s.tolist()], np.uint64).reshape(-1, 2)[np.searchsorted(s, symbols)]
    out.array(pairs[:, 0], pairs[:, 1].astype(np.int64))
    return varint(len(lengths)) + b"".join(varint(v) + bytes([k]) for v, k in sorted(lengths.items()))


def _huffman_read(data: bytes, at: int) -> tuple[dict, int]:
    n, at = read_varint(data, at)
    lengths = {}
    for _ in range(n):
        v, at = read_varint(data, at)
        lengths[v] = data[at]
        at += 1
    return {(k, code): v for v, (code, k) in canonical(lengths).items()}, at


def _huffman_get(table: dict, r: Reader, count: int) -> list[int]:
    """The next ``count`` symbols."""
    flat = {1 << n | code: v for (n, code), v in table.items()}  # a leading one keeps the length
    bits, i, got = r.bits[r.at :].tolist(), 0, []
    for _ in range(count):
        code = 1
        while code not in flat:
            code = 2 * code + bits[i]
            i += 1
        got.append(flat[code])
    r.at += i
    return got


def previous_quantiser_encode(words: np.ndarray, eps: float) -> bytes:
    """Difference to the previous rebuilt value on a grid of 2 eps, Elias gamma; raw words escape."""
    out, prev, step = _Out(), 0.0, 2 * eps
    for w, x in zip(_unsigned(words), np.asarray(words, np.int64).view(np.float64).tolist()):
        d = (x - prev) / step if x == x and abs(x) != float("inf") else float("nan")
        q = round(d) if abs(d) < 2.0**50 else None
        y = prev + q * step if q is not None else None
        if y is None or not abs(x - y) <= eps:
            out.gamma(1)
            out.put(w, 64)
            if x == x and abs(x) != float("inf"):
                prev = x
            continue
        out.gamma(2 + (2 * q if q >= 0 else -2 * q - 1))
        prev = y
    return varint(len(words)) + np.float64(eps).tobytes() + out.bytes()


def previous_quantiser_decode(data: bytes) -> np.ndarray:
    n, at = read_varint(data, 0)
    step = 2 * float(np.frombuffer(data, "<f8", 1, at)[0])
    r, got, whole, prev = Reader(data[at + 8 :]), np.zeros(n), {}, 0.0
    bits, i = r.bits.tolist(), 0
    for j in range(n):
        start = i
        while not bits[i]:
            i += 1
        size = i - start + 1
        r.at = i
        z = r.get(size) - 2
        i += size
        if z < 0:
            r.at = i
            whole[j] = r.get(64)
            i += 64
            x = struct.unpack("<d", struct.pack("<Q", whole[j]))[0]
            prev = x if math.isfinite(x) else prev
        else:
            prev = prev + (z >> 1 if z & 1 == 0 else -(z + 1 >> 1)) * step
            got[j] = prev
    out = got.view(np.int64)
    out[list(whole)] = _signed(list(whole.values()))
    return out


def _within(x: np.ndarray, eps: float) -> tuple[list[int], list[int]]:
    """The least and the greatest rank of the doubles y with ``abs(x - y) <= eps``, as that is computed.

    A rank numbers the doubles in their order. The computed distance never falls on the way away
    from x, so the ranks between are all near enough. Not finite: an empty range.
    """
    fine = np.isfinite(x)
    v = np.where(fine, x, 0.0)
    here, ends = _rank(v), []
    with np.errstate(all="ignore"):
        margin = 4 * np.spacing(np.maximum(np.abs(v), eps))
        for sign in (-1, 1):
            at = lambda steps, i=slice(None): _unrank(here[i] + sign * steps.view(np.int64))  # noqa: B023, E731
            last = (_TOP - sign * here).view(np.uint64)  # steps to the largest finite double, modulo 2^64
            far = [sign * (_rank(np.clip(v + sign * (eps + m), -_MAX, _MAX)) - here) for m in (-margin, margin)]
            lo, hi = (np.where(f > 0, f, 0).view(np.uint64) for f in far)
            lo = np.where(np.abs(v - at(lo)) <= eps, lo, np.uint64(0))  # lo is near enough, hi is not
            hi = np.where((hi <= lo) | (np.abs(v - at(hi)) <= eps), last + np.uint64(1), hi)
            open_ = np.flatnonzero(hi - lo > 1)
            while len(open_):
                mid = lo[open_] + (hi[open_] - lo[open_]) // np.uint64(2)
                near = np.abs(v[open_] - at(mid, open_)) <= eps
                lo[open_[near]], hi[open_[~near]] = mid[near], mid[~near]
                open_ = open_[hi[open_] - lo[open_] > 1]
            ends.append(here + sign * lo.view(np.int64))
    return np.where(fine, ends[0], 1).tolist(), np.where(fine, ends[1], 0).tolist()


_TOP = np.int64(0x7FEFFFFFFFFFFFFF)
_MAX = float(np.finfo(np.float64).max)


def _rank(x: np.ndarray) -> np.ndarray:
    w = x.view(np.int64)
    return np.where(w >= 0, w, -(w & np.int64(0x7FFFFFFFFFFFFFFF)))


def _unrank(r: np.ndarray) -> np.ndarray:
    return np.copysign(np.abs(r).view(np.float64), np.where(r < 0, -1.0, 1.0))


def bounded_xor_encode(words: np.ndarray, eps: float) -> bytes:
    """Within the bound, the word that shares the longest prefix and suffix with the one before; XOR codes."""
    got, prev, half = [], None, (1 << 63) - 1
    low, high = _within(np.asarray(words, np.int64).view(np.float64), eps)
    for w, a, b in zip(_unsigned(words), low, high):
        best = w
        if prev is not None and a <= b:
            differ = w ^ prev
            c = prev  # keep 64 - k bits of w, take the rest from the word before; k falls to each bit that differs
            while True:
                rank = c if c <= half else -(c & half)
                if a <= rank <= b:
                    best = c
                    break
                if not differ:
                    break
                top = 1 << differ.bit_length() - 1
                c ^= top
                differ ^= top
        got.append(best)
        prev = best
    return gorilla_encode(_signed(got))


def block_predictor_encode(words: np.ndarray, eps: float) -> bytes:
    """Hold or line prediction on the grid, whichever is cheaper, linear quantiser codes, Huffman, byte codec."""
    words = np.asarray(words, np.int64)
    q, ok = _quantised(words.view(np.float64), eps)
    best = None
    for order in (1, 2):
        d = np.diff(q, n=1, prepend=0)
        d = np.diff(d, prepend=0) if order == 2 else d
        z = np.minimum(zigzag(d), np.uint64(65535))
        out = Writer()
        table = _huffman_write(z.astype(np.int64), out)
        big = np.flatnonzero(z == 65535)
        out.array(d[big].view(np.uint64), 64)
        data = bytes([order]) + table + out.bytes()
        if best is None or len(data) < len(best):
            best = data
    raw = _raws(words, np.flatnonzero(~ok)) + best
    return varint(len(words)) + np.float64(eps).tobytes() + varint(len(raw)) + bytes(pa.Codec("zstd", compression_level=3).compress(raw, asbytes=True))


def block_predictor_decode(data: bytes) -> np.ndarray:
    n, at = read_varint(data, 0)
    step = 2 * float(np.frombuffer(data, "<f8", 1, at)[0])
    size, at = read_varint(data, at + 8)
    data = pa.Codec("zstd").decompress(data[at:], size, asbytes=True)
    where, raw, at = _read_raws(data, 0)
    order = data[at]
    table, at = _huffman_read(data, at + 1)
    r = Reader(data[at:])
    z = np.array(_huffman_get(table, r, n), np.uint64)
    d = unzigzag(z)
    big = np.flatnonzero(z == 65535)
    d[big] = r.array(np.full(len(big), 64)).view(np.int64)
    q = np.cumsum(np.cumsum(d)) if order == 2 else np.cumsum(d)
    out = (q * step).view(np.int64).copy()
    out[where] = raw
    return out


def hybrid_entropy_encode(words: np.ndarray, eps: float) -> bytes:
    """Grid differences: Huffman over bit lengths, then the bits themselves."""
    words = np.asarray(words, np.int64)
    q, ok = _quantised(words.view(np.float64), eps)
    z = zigzag(np.diff(q, prepend=0))
    n = bit_length(z)
    out = Writer()
    table = _huffman_write(n, out)
    out.array(z, np.maximum(n - 1, 0))  # the first digit follows from the length
    return varint(len(words)) + np.float64(eps).tobytes() + _raws(words, np.flatnonzero(~ok)) + table + out.bytes()


def hybrid_entropy_decode(data: bytes) -> np.ndarray:
    n, at = read_varint(data, 0)
    step = 2 * float(np.frombuffer(data, "<f8", 1, at)[0])
    where, raw, at = _read_raws(data, at + 8)
    table, at = _huffman_read(data, at)
    r = Reader(data[at:])
    length = np.array(_huffman_get(table, r, n), np.int64)
    z = r.array(np.maximum(length - 1, 0)) | np.where(length > 0, np.uint64(1) << np.maximum(length - 1, 0).astype(np.uint64), np.uint64(0))
    out = (np.cumsum(unzigzag(z)) * step).view(np.int64).copy()
    out[where] = raw
    return out


def forecast_pack_encode(words: np.ndarray, eps: float) -> bytes:
    """Grid values, line forecast, ZigZag, packed in groups of 8 at one width each."""
    words = np.asarray(words, np.int64)
    q, ok = _quantised(words.view(np.float64), eps)
    z = zigzag(np.diff(q, n=2, prepend=[0, 0])) if len(q) else np.zeros(0, np.uint64)
    pad = np.concatenate([z, np.zeros(-len(z) % 8, np.uint64)]).reshape(-1, 8)
    w = bit_length(pad).max(axis=1) if len(pad) else np.zeros(0, np.int64)
    out = Writer()
    out.array(w.astype(np.uint64), 7)
    out.array(pad, np.repeat(w, 8).reshape(-1, 8))
    return varint(len(words)) + np.float64(eps).tobytes() + _raws(words, np.flatnonzero(~ok)) + out.bytes()


def forecast_pack_decode(data: bytes) -> np.ndarray:
    n, at = read_varint(data, 0)
    step = 2 * float(np.frombuffer(data, "<f8", 1, at)[0])
    where, raw, at = _read_raws(data, at + 8)
    r, k = Reader(data[at:]), -(-n // 8)
    w = r.array(np.full(k, 7)).astype(np.int64)
    z = r.array(np.repeat(w, 8))[:n]
    out = (np.cumsum(np.cumsum(unzigzag(z))) * step).view(np.int64).copy()
    out[where] = raw
    return out


@dataclass(frozen=True)
class Codec:
    name: str
    encode: Callable
    decode: Callable
    bounded: bool = False

    def encode_page(self, words: np.ndarray, eps: float = 1e-3) -> bytes:
        return self.encode(words, eps) if self.bounded else self.encode(words)

    def decode_page(self, data: bytes) -> np.ndarray:
        return self.decode(data)


def _plain(words: np.ndarray) -> bytes:
    return np.asarray(words, "<i8").tobytes()


CODECS = {
    c.name: c
    for c in (
        Codec("gorilla", gorilla_encode, gorilla_decode),
        Codec("chimp", chimp_encode, chimp_decode),
        Codec("erase_xor", erase_encode, erase_decode),
        Codec("erase_xor_plus", lambda w: erase_encode(w, True), erase_decode),
        Codec("alp", frame_of_reference_encode, frame_of_reference_decode),
        Codec("decimal_neighbor", decimal_neighbor_encode, decimal_neighbor_decode),
        Codec("falcon", bitplane_encode, bitplane_decode),
        Codec("snappy", *_bytes_codec("snappy")),
        Codec("lz4", *_bytes_codec("lz4_raw")),
        Codec("zstd3", *_bytes_codec("zstd", 3)),
        Codec("plain", _plain, lambda d: np.frombuffer(d, "<i8").astype(np.int64)),
        Codec("serf_qt", previous_quantiser_encode, previous_quantiser_decode, True),
        Codec("serf_xor", bounded_xor_encode, gorilla_decode, True),
        Codec("sz2", block_predictor_encode, block_predictor_decode, True),
        Codec("machete", hybrid_entropy_encode, hybrid_entropy_decode, True),
        Codec("sprintz_xff", forecast_pack_encode, forecast_pack_decode, True),
    )
}


def get(name: str) -> Codec:
    return CODECS[name]
