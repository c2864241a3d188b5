"""The raw lane: whole 64-bit words, XORed with their predecessor under a reusable window."""

from __future__ import annotations

import numpy as np

from lattice_pages.functions.bits import Reader, Writer, bit_length


def windows(x: np.ndarray, lead_cap: int = 64) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(whether it sets the window, leading zeros, trailing zeros of the window) for XORs, none of them zero.

    Only the choice of the window goes value by value; a window stays until an XOR does not fit.
    """
    lead, tail = np.minimum(64 - bit_length(x), lead_cap), bit_length(x & (~x + np.uint64(1))) - 1
    at, a, b = [], 65, 65
    for i, (c, d) in enumerate(zip(lead.tolist(), tail.tolist())):
        if c < a or d < b:
            a, b = c, d
            at.append(i)
    fresh = np.zeros(len(x), bool)
    fresh[at] = True
    times = np.diff([*at, len(x)])
    return fresh, np.repeat(lead[at], times), np.repeat(tail[at], times)


def raw_bits(words: np.ndarray) -> int:
    if not len(words):
        return 0
    w = words.view(np.uint64)
    x = w[1:] ^ w[:-1]
    some = x[x > 0]
    fresh, lead, tail = windows(some)
    return 64 + len(x) + len(some) + 12 * int(fresh.sum()) + int((64 - lead - tail).sum())


def raw_bits_least(words: np.ndarray) -> int:
    """A lower bound of ``raw_bits`` in array arithmetic: every window as tight as its word."""
    if not len(words):
        return 0
    w = words.view(np.uint64)
    x = w[1:] ^ w[:-1]
    x = x[x > 0]
    return 64 + (len(w) - 1 - len(x)) + int((2 + bit_length(x) - bit_length(x & (~x + np.uint64(1))) + 1).sum())


def xor_fields(x: np.ndarray, lead_cap: int, lead_bits: int) -> tuple[np.ndarray, np.ndarray]:
    """(values, widths) of the four fields of every XOR: flag, leading zeros, length - 1, payload; unused ones have no width."""
    values, widths = np.zeros((len(x), 4), np.uint64), np.zeros((len(x), 4), np.int64)
    widths[:, 0] = 1
    at = np.flatnonzero(x)
    fresh, lead, tail = windows(x[at], lead_cap)
    n = 64 - lead - tail
    values[at, 0], widths[at, 0] = 2 + fresh, 2
    values[at, 1], widths[at, 1] = lead, lead_bits * fresh
    values[at, 2], widths[at, 2] = n - 1, 6 * fresh
    values[at, 3], widths[at, 3] = x[at] >> tail.astype(np.uint64), n
    return values, widths


def write_raw(words: np.ndarray, out: Writer) -> None:
    words = words.view(np.uint64)
    if not len(words):
        return
    out.put(int(words[0]), 64)
    out.array(*xor_fields(words[1:] ^ words[:-1], 64, 6))


def read_raw(n: int, r: Reader, lead_bits: int = 6) -> np.ndarray:
    """The words; the reader stands behind them afterwards."""
    out = np.zeros(n, np.uint64)
    if not n:
        return out
    out[0] = r.get(64)
    bits, i, size, tail = r.bits[r.at :].tolist(), 0, None, None
    base, head = r.at, lead_bits + 6
    which, at, sizes, tails = [], [], [], []
    try:
        for k in range(1, n):
            if not bits[i]:
                i += 1
                continue
            if bits[i + 1]:
                r.at = base + i + 2
                lead = r.get(lead_bits)
                size = r.get(6) + 1
                tail = 64 - lead - size
                if tail < 0:
                    raise ValueError("bad window")
                i += 2 + head
            elif size is None:
                raise ValueError("a window is reused before it is set")
            else:
                i += 2
            which.append(k)
            at.append(i)
            sizes.append(size)
            tails.append(tail)
            i += size
    except IndexError:
        raise ValueError("the bit string ends early") from None
    if i > len(bits):
        raise ValueError("the bit string ends early")
    if which:
        out[which] = r.fields(np.array(at) + base, np.array(sizes)) << np.array(tails).astype(np.uint64)
    r.at = base + i
    return np.bitwise_xor.accumulate(out)
