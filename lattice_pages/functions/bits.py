"""Bit strings in numpy: values of mixed widths, universal codes, canonical prefix codes."""

from __future__ import annotations

import numpy as np

U = np.uint64


def bit_length(v: np.ndarray) -> np.ndarray:
    """Binary digits of unsigned 64-bit values; 0 for 0. Exact at every size."""
    v = np.asarray(v, U)
    if v.size and v.max() < 1 << 53:  # exact as doubles
        return np.frexp(v.astype(np.float64))[1].astype(np.int64)
    high = v >> U(32)
    return np.where(high > 0, np.frexp(high.astype(np.float64))[1] + 32, np.frexp((v & U(0xFFFFFFFF)).astype(np.float64))[1]).astype(np.int64)


def zigzag(r: np.ndarray) -> np.ndarray:
    """Signed residuals (taken modulo 2^64) to unsigned, small magnitudes first."""
    r = np.asarray(r, np.int64)
    return ((r << 1) ^ (r >> 63)).view(U)


def unzigzag(z: np.ndarray) -> np.ndarray:
    z = np.asarray(z, U)
    return ((z >> U(1)) ^ (U(0) - (z & U(1)))).view(np.int64)


class Writer:
    """Collects fields, most significant bit first; ``bytes()`` pads the last byte with zeros."""

    def __init__(self) -> None:
        self.values: list[np.ndarray] = []
        self.widths: list[np.ndarray] = []
        self.single: tuple[list[int], list[int]] = ([], [])  # fields put one by one, not yet among the others
        self.bits = 0

    def put(self, value: int, width: int) -> None:
        self.single[0].append(value & 0xFFFFFFFFFFFFFFFF)
        self.single[1].append(width)
        self.bits += width

    def _settle(self) -> None:
        if self.single[0]:
            self.values.append(np.array(self.single[0], U))
            self.widths.append(np.array(self.single[1], np.int64))
            self.single = ([], [])

    def extend(self, other: Writer) -> None:
        self._settle()
        other._settle()
        self.values += other.values
        self.widths += other.widths
        self.bits += other.bits

    def array(self, values: np.ndarray, widths: np.ndarray | int) -> None:
        self._settle()
        w = np.broadcast_to(np.asarray(widths, np.int64), np.shape(values)).ravel()
        self.values.append(np.asarray(values, U).ravel())
        self.widths.append(w)
        self.bits += int(w.sum())

    def gamma(self, values: np.ndarray) -> None:
        """Elias gamma codes of values >= 1."""
        n = bit_length(values)
        two = np.stack([np.zeros(len(n), U), np.asarray(values, U)], axis=1)
        self.array(two, np.stack([n - 1, n], axis=1))

    def bytes(self) -> bytes:
        self._settle()
        if not self.values:
            return b""
        v, w = np.concatenate(self.values), np.concatenate(self.widths)
        of = np.repeat(np.arange(len(v)), w)
        if not len(of):
            return b""
        ends = np.cumsum(w)
        left = (ends[of] - 1 - np.arange(len(of))).astype(U)
        return np.packbits(((v[of] >> left) & U(1)).astype(np.uint8)).tobytes()


class Reader:
    """Reads what ``Writer`` wrote; raises ``ValueError`` beyond the end."""

    def __init__(self, data: bytes) -> None:
        self.data = bytes(data)
        self.bits = np.unpackbits(np.frombuffer(data, np.uint8))
        self.at = 0
        self.ones: np.ndarray | None = None

    def _need(self, n: int) -> None:
        if n < 0 or self.at + n > len(self.bits):
            raise ValueError("the bit string ends early")

    def get(self, width: int) -> int:
        self._need(width)
        end = self.at + width
        out = int.from_bytes(self.data[self.at >> 3 : (end + 7) >> 3]) >> (-end & 7) & ((1 << width) - 1)
        self.at = end
        return out

    def fields(self, at: np.ndarray, widths: np.ndarray) -> np.ndarray:
        """Fields of 0 to 64 bits at any places; the reader stays where it is."""
        at, w = np.asarray(at, np.int64), np.asarray(widths, np.int64)
        if len(at) and (int((at + w).max()) > len(self.bits) or int(w.min()) < 0):
            raise ValueError("the bit string ends early")
        padded = np.frombuffer(self.data + bytes(9), np.uint8)
        nine = padded[(at >> 3)[:, None] + np.arange(9)]
        skip = (at & 7).astype(U)
        first = np.ascontiguousarray(nine[:, :8]).view(">u8")[:, 0].astype(U)
        got = first << skip | nine[:, 8].astype(U) >> (U(8) - skip)
        return np.where(w > 0, got >> (64 - np.maximum(w, 1)).astype(U), U(0))

    def array(self, widths: np.ndarray) -> np.ndarray:
        w = np.asarray(widths, np.int64)
        total = int(w.sum())
        self._need(total)
        out = np.zeros(len(w), U)
        if total:
            some = np.flatnonzero(w)
            starts = np.concatenate([[0], np.cumsum(w[some])[:-1]])
            ends = np.repeat(np.cumsum(w[some]), w[some])
            place = (ends - 1 - np.arange(total)).astype(U)
            out[some] = np.add.reduceat(self.bits[self.at : self.at + total].astype(U) << place, starts)
        self.at += total
        return out

    def flags(self, n: int) -> np.ndarray:
        self._need(n)
        out = self.bits[self.at : self.at + n].astype(bool)
        self.at += n
        return out

    def unary(self) -> int:
        """Zeros before the next one."""
        if self.ones is None:
            self.ones = np.flatnonzero(self.bits)
        k = int(np.searchsorted(self.ones, self.at))
        if k == len(self.ones):
            raise ValueError("the bit string ends early")
        n = int(self.ones[k]) - self.at
        self.at += n + 1
        return n

    def gamma(self) -> int:
        n = self.unary()
        return (1 << n) | self.get(n)


def varint(n: int) -> bytes:
    out = bytearray()
    while n > 0x7F:
        out.append(n & 0x7F | 0x80)
        n >>= 7
    out.append(n)
    return bytes(out)


def read_varint(data: bytes, at: int) -> tuple[int, int]:
    n = shift = 0
    while True:
        if at >= len(data) or shift > 63:
            raise ValueError("bad length")
        b = data[at]
        n |= (b & 0x7F) << shift
        at, shift = at + 1, shift + 7
        if b < 0x80:
            return n, at


def code_lengths(counts: dict[int, int]) -> dict[int, int]:
    """Huffman code lengths of the symbols; one symbol alone gets length 1."""
    import heapq

    symbols = sorted(s for s, n in counts.items() if n)
    heap = [(counts[s], s, i) for i, s in enumerate(symbols)]
    if len(heap) == 1:
        return {symbols[0]: 1}
    parent = [0] * max(2 * len(heap) - 1, 0)
    heapq.heapify(heap)
    node = len(heap)
    while len(heap) > 1:
        a, b = heapq.heappop(heap), heapq.heappop(heap)
        parent[a[2]] = parent[b[2]] = node
        heapq.heappush(heap, (a[0] + b[0], min(a[1], b[1]), node))
        node += 1
    depth = [0] * len(parent)
    for i in range(len(parent) - 2, -1, -1):  # a parent comes after its children
        depth[i] = depth[parent[i]] + 1
    return {s: depth[i] for i, s in enumerate(symbols)}


def canonical(lengths: dict[int, int]) -> dict[int, tuple[int, int]]:
    """symbol -> (code, length), codes in order of (length, symbol)."""
    out, code, last = {}, 0, 0
    for s, n in sorted(lengths.items(), key=lambda x: (x[1], x[0])):
        code <<= n - last
        out[s] = (code, n)
        code, last = code + 1, n
    return out
