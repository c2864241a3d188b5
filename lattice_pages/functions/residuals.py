"""Residual blocks: predictors, block forms and their costs, writing and reading.

All arithmetic on coordinates is modulo 2^64, which is a bijection on signed 64-bit
integers: no coordinate can overflow its residual.
"""

from __future__ import annotations

import numpy as np

from lattice_pages.functions.bits import Reader, Writer, bit_length, unzigzag, zigzag

BLOCK = 16
#: hold, line, parabola, rounded half slope, rounded mean
PREDICTORS = 5
PATCH, SPLIT, RICE = 0, 1, 2
RICE_MAX = 20
_W = np.arange(65)
#: Cost of the extension of a residual of length l (row) in a block of base width w (column).
_EXTRA = np.array([[(2 * int(a - w).bit_length() - 1 + a - w) if a > w else 0 for w in range(65)] for a in range(65)], np.int64)

_EXTRA_F = _EXTRA.astype(np.float64)


def predictions(u: np.ndarray, p: int) -> np.ndarray:
    """Prediction of every coordinate after the first from those before it."""
    u1 = u[:-1]
    if p == 0 or len(u) < 3:
        return u1.copy()
    u2 = np.concatenate([u[:1], u[:-2]])  # too little history: hold
    with np.errstate(over="ignore"):
        if p == 1:
            got = 2 * u1 - u2
        elif p == 2:
            u3 = np.concatenate([u[:1], u[:1], u[:-3]]) if len(u) > 3 else np.concatenate([u[:1], u[:1]])[: len(u1)]
            got = 3 * u1 - 3 * u2 + u3
            got[:2] = u1[:2]
        elif p == 3:
            got = u1 + ((u1 - u2) >> 1)
        else:
            got = u2 + ((u1 - u2) >> 1)
        got[0] = u1[0]
    return got


def predict_next(u: list[int], p: int) -> int:
    """The same for one value, from the list of those before it."""
    m = (1 << 64) - 1
    sign = lambda v: (v & m) - (1 << 64) if v & (1 << 63) else v & m
    if p == 0 or len(u) < 2 or (p == 2 and len(u) < 3):
        return u[-1]
    u1, u2 = u[-1], u[-2]
    if p == 1:
        return sign(2 * u1 - u2)
    if p == 2:
        return sign(3 * u1 - 3 * u2 + u[-3])
    if p == 3:
        return sign(u1 + (sign(u1 - u2) >> 1))
    return sign(u2 + (sign(u1 - u2) >> 1))


def residuals(u: np.ndarray, p: int = 0) -> np.ndarray:
    with np.errstate(over="ignore"):
        return u[1:] - predictions(u, p)


def _blocks(v: np.ndarray, block: int) -> tuple[np.ndarray, np.ndarray]:
    """(padded matrix, rows' sizes); padding is zero."""
    n = len(v)
    k = -(-n // block)
    out = np.zeros(k * block, v.dtype)
    out[:n] = v
    size = np.full(k, block)
    if n % block:
        size[-1] = n % block
    return out.reshape(k, block), size


def _shape(z: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(residuals of each length, residuals longer than each width) of every block; widths up to the longest residual."""
    k, b = z.shape
    lens = bit_length(z)
    top = int(lens.max(initial=0)) + 1  # wider bases cannot occur
    flat = (np.arange(k)[:, None] * top + lens).ravel()
    counts = np.bincount(flat, minlength=k * top).reshape(k, top)
    counts[:, 0] -= b - size  # padding counted as zeros
    return counts, size[:, None] - np.cumsum(counts, axis=1)


def _patch(counts: np.ndarray, above: np.ndarray, size: np.ndarray) -> np.ndarray:
    top = counts.shape[1]
    extra = (counts.astype(np.float64) @ _EXTRA_F[:top, :top]).astype(np.int64)  # small integers: exact
    ok = counts > 0
    ok[:, 0] = True
    return np.where(ok, size[:, None] * (_W[:top] + (above > 0)) + extra, 1 << 40)


def _split(counts: np.ndarray, above: np.ndarray, size: np.ndarray) -> np.ndarray:
    w = _W[: counts.shape[1]]
    longest = (above > 0).sum(axis=1)
    return np.where(above > 0, size[:, None] * (w + 1) + 7 + above * (longest[:, None] - w), 1 << 40)


def _rice(z: np.ndarray, size: np.ndarray, top: int) -> np.ndarray:
    out = np.empty((len(z), min(RICE_MAX + 1, top)), np.int64)
    for k in range(out.shape[1]):
        high = z >> np.uint64(k)
        if top - k > 31:
            high = np.minimum(high, np.uint64(1 << 30))
        out[:, k] = high.sum(axis=1).view(np.int64) + size * (1 + k) + 5
    return out


def _wide(cost: np.ndarray, n: int = 65) -> np.ndarray:
    out = np.full((len(cost), n), 1 << 40)
    out[:, : cost.shape[1]] = cost
    return out


def patch_costs(z: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Bits of each block (row) at each base width 0..64, without header symbols.

    Only widths that occur in the block, and 0, are admissible; others cost 2^40.
    """
    return _wide(_patch(*_shape(z, size), size))


def split_costs(z: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Low planes of w bits for all, a bitmap, and high parts of one common width for the rest."""
    return _wide(_split(*_shape(z, size), size))


def rice_costs(z: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Rice parameters 0..20; those far from the mean cannot win and are costed all the same."""
    return _rice(z, size, RICE_MAX + 33)


def best_widths(z: np.ndarray, size: np.ndarray, width_cost: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(width, bits with the width symbol and the patch flag) of each block; least cost, then least width."""
    cost = _patch(*_shape(z, size), size)
    return _least(cost + width_cost[: cost.shape[1]] + 1)


def _least(cost: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    k = cost.argmin(axis=1)
    return k, cost[np.arange(len(k)), k]


def write_patch(z: np.ndarray, size: np.ndarray, w: np.ndarray, out: Writer) -> np.ndarray:
    """Payload of patch blocks: all base bits, then bitmaps, then extensions; returns the patch flags."""
    live = np.arange(z.shape[1])[None, :] < size[:, None]
    lens = bit_length(z)
    wide = (lens > w[:, None]) & live
    flags = wide.any(axis=1)
    ww = np.broadcast_to(w[:, None], z.shape)
    low = np.where(ww >= 64, z, z & ((np.uint64(1) << np.minimum(ww, 63).astype(np.uint64)) - np.uint64(1)))
    out.array(low[live], ww[live])
    marked = live & flags[:, None]
    out.array(wide[marked].astype(np.uint64), 1)
    if wide.any():
        more = (lens - ww)[wide]
        out.gamma(more.astype(np.uint64))
        high = z[wide] >> np.minimum(ww[wide], 63).astype(np.uint64)
        out.array(high, more)
    return flags


def read_patch(size: np.ndarray, w: np.ndarray, flags: np.ndarray, r: Reader) -> np.ndarray:
    """The residuals (ZigZag, flat) of patch blocks."""
    width = np.repeat(w, size)
    z = r.array(width)
    marked = np.repeat(flags, size)
    wide = np.zeros(len(z), bool)
    wide[marked] = r.flags(int(marked.sum()))
    at = np.flatnonzero(wide)
    if len(at):
        more = np.array([r.gamma() for _ in at], np.int64)
        if (width[at] + more > 64).any():
            raise ValueError("an extension leaves 64 bits")
        z[at] |= r.array(more) << width[at].astype(np.uint64)
    return z


def choose_upper(u: np.ndarray, block: int, width_cost: np.ndarray, use_predictors: bool = True, use_split: bool = True, use_rice: bool = True, use_gcd: bool = True) -> dict[str, np.ndarray]:
    """Cheapest (predictor, divisor, form, parameter) of every block of one lane; of equal ones the first.

    All predictors are costed in one matrix; divided residuals only where there is a divisor.
    """
    preds = PREDICTORS if use_predictors else 1
    each = [_blocks(residuals(u, p), block) for p in range(preds)]
    r, k = np.concatenate([e[0] for e in each]), len(each[0][1])
    size = np.tile(each[0][1], preds)
    none = 1 << 60
    costs, params = np.full((2, 3, preds * k), none), np.zeros((2, 3, preds * k), np.int64)

    def fill(which: int, at: np.ndarray | slice, z: np.ndarray, size: np.ndarray, extra: np.ndarray | int) -> None:
        counts, above = _shape(z, size)
        top = counts.shape[1]
        forms = [(PATCH, _patch(counts, above, size) + width_cost[:top] + 1)]
        if use_split:
            forms.append((SPLIT, _split(counts, above, size) + width_cost[:top]))
        if use_rice:  # a residual of l digits costs 2^(l - 1 - RICE_MAX) bits or more
            longest = (above > 0).sum(axis=1)
            open_ = (longest <= RICE_MAX + 1) | (1 << np.maximum(longest - 1 - RICE_MAX, 0) <= forms[0][1].min(axis=1))
            rice = np.full((len(z), min(RICE_MAX + 1, top)), 1 << 40)
            rice[open_] = _rice(z[open_], size[open_], top)
            forms.append((RICE, rice))
        for form, cost in forms:
            params[which, form, at], c = _least(cost)
            costs[which, form, at] = c + extra

    z = zigzag(r)
    fill(0, slice(None), z, size, 6)
    d = np.ones(len(r), np.int64)
    if use_gcd:
        g = np.gcd.reduce(np.where(r == np.int64(-(1 << 63)), 1, r), axis=1)
        at = np.flatnonzero(g > 1)
        if len(at):
            d[at] = g[at]
            divided = zigzag(r[at] // g[at, None])
            fill(1, at, divided, size[at], 6 + 2 * bit_length(g[at].astype(np.uint64)) - 1)
    # order of preference: predictor, undivided before divided, form
    table = costs.reshape(2, 3, preds, k).transpose(2, 0, 1, 3).reshape(6 * preds, k)
    win = table.argmin(axis=0)
    p, which, form = win // 6, win % 6 // 3, win % 3
    row = p * k + np.arange(k)
    chosen = z[row]
    if which.any():
        mine = np.flatnonzero(which)
        chosen[mine] = divided[np.searchsorted(at, row[mine])]
    return {"p": p, "d": np.where(which > 0, d[row], 1), "form": form, "param": params[which, form, row], "bits": table[win, np.arange(k)], "z": chosen, "size": size[:k]}


def write_upper_block(z: np.ndarray, form: int, param: int, out: Writer) -> None:
    if form == PATCH:
        write_patch(z[None, :], np.array([len(z)]), np.array([param]), out)
    elif form == SPLIT:
        lens = bit_length(z)
        h = int(lens.max()) - param
        wide = lens > param
        out.put(h, 7)
        out.array(z & np.uint64((1 << param) - 1), param)
        out.array(wide.astype(np.uint64), 1)
        out.array(z[wide] >> np.uint64(param), h)
    else:
        high = z >> np.uint64(param)
        if int(high.max(initial=0)) <= 64:
            low = z & np.uint64((1 << param) - 1)
            wide = np.stack([high.astype(np.int64), np.ones(len(z), np.int64), np.full(len(z), param)], axis=1)
            out.array(np.stack([np.zeros(len(z), np.uint64), np.ones(len(z), np.uint64), low], axis=1), wide)
            return
        for v in z.tolist():
            high = v >> param
            out.array(np.zeros(high // 64 + 1, np.uint64), np.array([64] * (high // 64) + [high % 64]))
            out.put(1, 1)
            out.put(v & ((1 << param) - 1), param)


def read_upper_block(n: int, form: int, param: int, flag: bool, r: Reader) -> np.ndarray:
    if form == PATCH:
        return read_patch(np.array([n]), np.array([param]), np.array([flag]), r)
    if form == SPLIT:
        h = r.get(7)
        if h + param > 64:
            raise ValueError("a high part leaves 64 bits")
        z = r.array(np.full(n, param))
        wide = r.flags(n)
        z[wide] |= r.array(np.full(int(wide.sum()), h)) << np.uint64(param)
        return z
    return np.array([(r.unary() << param) | r.get(param) for _ in range(n)], np.uint64)


__all__ = ["BLOCK", "PATCH", "PREDICTORS", "RICE", "SPLIT", "best_widths", "choose_upper", "predict_next", "predictions", "read_patch", "read_upper_block", "residuals", "unzigzag", "write_patch", "write_upper_block", "zigzag"]
