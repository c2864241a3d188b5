"""Which values may become integers: the decoder's own arithmetic decides.

Exact mode divides an integer by a power of ten and compares all 64 bits; bounded mode
rounds a product and a sum, in that order, and compares with the bound.
"""

from __future__ import annotations

import functools
import math

import numpy as np

SCALES = range(19)
#: Powers of ten up to 10^18 are exact (to 10^22) as doubles.
POWERS = np.array([float(10**s) for s in SCALES])
#: The divisor alphabet of the bounded profile.
DIVISORS = (1, 2, 4, 5, 8, 10, 20, 25, 40, 50, 100, 125, 200, 250, 500, 1000, 2000, 2500, 5000, 10**4, 5 * 10**4, 10**5, 10**6, 10**7, 10**8)
_LIMIT = 2.0**63


def rebuild_exact(q: np.ndarray, s: int) -> np.ndarray:
    return q.astype(np.float64) / POWERS[s]


def narrowed(x: np.ndarray) -> np.ndarray:
    """Doubles rounded to binary32, as zero-extended words."""
    with np.errstate(all="ignore"):
        return x.astype(np.float32).view(np.uint32).astype(np.int64)


def exact_index(x: np.ndarray, s: int, narrow: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """(q, admitted) at scale s; q is 0 where the value is not admitted. ``narrow``: rounded to binary32 all bits agree."""
    with np.errstate(all="ignore"):
        y = np.rint(x * POWERS[s])
        fits = np.isfinite(y) & (y >= -_LIMIT) & (y < _LIMIT)
        q = np.where(fits, y, 0).astype(np.int64)
        back = rebuild_exact(q, s)
        ok = fits & (narrowed(back) == narrowed(x) if narrow else back.view(np.int64) == x.view(np.int64))
    return np.where(ok, q, 0), ok


def scale_matrix(x: np.ndarray, narrow: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """(q, admitted) for all 19 scales, one row a scale; not to be written to, as the last page's are kept for the next codec."""
    return _matrix(np.ascontiguousarray(x).tobytes(), narrow)


@functools.lru_cache(maxsize=1)
def _matrix(values: bytes, narrow: bool) -> tuple[np.ndarray, np.ndarray]:
    x = np.frombuffer(values)
    both = [exact_index(x, s, narrow) for s in SCALES]
    q, ok = np.stack([q for q, _ in both]), np.stack([ok for _, ok in both])
    q.flags.writeable = ok.flags.writeable = False
    return q, ok


def error_steps(eps: float) -> list[float]:
    if not (eps > 0 and math.isfinite(eps)):
        raise ValueError("the bound must be positive and finite")
    return [math.nextafter(k * eps, 0.0) for k in (2.0, 1.5, 1.0)]


def frame_origin(x: np.ndarray) -> float | None:
    """The first finite value that is not zero."""
    at = np.flatnonzero(np.isfinite(x) & (x != 0))
    return float(x[at[0]]) if len(at) else None


def rebuild_bounded(q: np.ndarray, origin: float, step: float, narrow: bool = False) -> np.ndarray:
    with np.errstate(all="ignore"):
        product = q.astype(np.float64) * step
        return (origin + product).astype(np.float32).astype(np.float64) if narrow else origin + product


def bounded_index(x: np.ndarray, origin: float, step: float, eps: float, narrow: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """(q, admitted): of the nearest index and its neighbours, the one of least error, then least magnitude."""
    with np.errstate(all="ignore"):
        near = np.rint((x.astype(np.longdouble) - np.longdouble(origin)) / np.longdouble(step))
        fits = np.isfinite(near) & (np.abs(near) < np.longdouble(2.0**62))
        center = np.where(fits, near, 0).astype(np.int64)
        best_q, best_e = np.zeros(len(x), np.int64), np.full(len(x), np.inf)
        for move in (0, -1, 1):
            q = center + move
            y = rebuild_bounded(q, origin, step, narrow)
            e = np.where(fits & np.isfinite(y) & np.isfinite(x), np.abs(x - y), np.inf)
            better = (e < best_e) | ((e == best_e) & ((np.abs(q) < np.abs(best_q)) | ((np.abs(q) == np.abs(best_q)) & (q < best_q))))
            best_q, best_e = np.where(better, q, best_q), np.where(better, e, best_e)
        ok = best_e <= eps
    return np.where(ok, best_q, 0), ok


def checked_affine(z: int, d: int, r: int) -> int:
    """d z + r in exact arithmetic; raises where it leaves 64 bits."""
    q = int(d) * int(z) + int(r)
    if not -(1 << 63) <= q < 1 << 63:
        raise OverflowError("a coordinate leaves 64 bits")
    return q


def restore_affine(z: np.ndarray, d: int, r: int) -> np.ndarray:
    """Vector form: an exact bound check first, plain arithmetic after it."""
    if len(z):
        checked_affine(int(z.min()), d, r)
        checked_affine(int(z.max()), d, r)
    return z * np.int64(d) + np.int64(r)


def affine_candidates(q: np.ndarray, window: int = 16, keep: int = 8) -> list[tuple[int, int]]:
    """(d, r): divisors from GCDs of adjacent differences in windows, each with its fullest residue."""
    if len(q) < 3:
        return []
    diff = np.abs(np.diff(q))
    diff = diff[: len(diff) // window * window].reshape(-1, window) if len(diff) >= window else diff[None, :]
    g, n = np.unique(np.gcd.reduce(diff, axis=1), return_counts=True)
    order = [(int(n[i]), int(g[i])) for i in range(len(g)) if 2 <= g[i] <= 10**8]
    out = []
    for _, d in sorted(order, key=lambda t: (-t[0], t[1]))[:keep]:
        r, m = np.unique(np.mod(q, d), return_counts=True)
        out.append((d, int(r[m.argmax()])))
    return out
