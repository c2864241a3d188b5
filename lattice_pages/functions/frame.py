"""The frame of one page: self-contained bytes, and their strict reader.

A frame is ``varint(len(meta)) meta payload``. The metadata holds the magic of the
contract, geometry, descriptors, the width code, the route and all block headers; the
payload holds residuals and raw words. Everything is length-delimited, and what does
not add up raises ``PageFormatError``.
"""

from __future__ import annotations

import struct

import numpy as np

from lattice_pages.functions import admission
from lattice_pages.functions.bits import Reader, Writer, bit_length, canonical, code_lengths, read_varint, unzigzag, varint, zigzag
from lattice_pages.functions.rawlane import read_raw, write_raw
from lattice_pages.functions.residuals import PATCH, RICE, SPLIT, _blocks, best_widths, choose_upper, predict_next, read_patch, read_upper_block, write_patch, write_upper_block
from lattice_pages.plans.planner import RAW, Plan, lane_residuals, plan_page
from lattice_pages.plans.profiles import Profile

MAGIC = {"exact": b"LX", "bounded": b"LB", "exact32": b"Lx", "bounded32": b"Lb", "exact_integer": b"LI"}
VERSION = 1
PARTS = ("framing", "route", "predictor", "patch", "residual", "exception", "raw")
_UPPER, _RESET, _ANCHOR, _PLAINQ, _WHOLE = 1, 2, 4, 8, 16


class PageFormatError(ValueError):
    """Bytes that are no valid frame of the contract that was asked for."""


def _route(plan: Plan, n: int) -> tuple[bytes, bool]:
    """(route bytes, whether one lane covers all)."""
    sizes = [len(a) for a in plan.used]
    if len(sizes) == 1 and sizes[0] == n:
        return b"", True
    if not sizes:
        return b"", False
    first = int(np.argmax(sizes))
    out = Writer()
    out.array((plan.route == first).astype(np.uint64), 1)
    symbols = {lane: i for i, lane in enumerate([k for k in range(len(sizes)) if k != first] + [RAW])}
    rest = plan.route[plan.route != first]
    out.array(np.array([symbols[k] for k in rest.tolist()], np.uint64), max(0, (len(sizes) - 1).bit_length()))
    return out.bytes(), False


def encode_page(words: np.ndarray, p: Profile, plan: Plan | None = None) -> tuple[bytes, bytes, dict[str, int]]:
    """(meta, payload, bits by part) of one page."""
    words = np.ascontiguousarray(words, np.int64)
    n = len(words)
    plan = plan or plan_page(words, p)
    bits = dict.fromkeys(PARTS, 0)
    route, whole = _route(plan, n)
    width = np.full(65, 7)
    lanes = []
    for c, at in zip(plan.lanes, plan.used):
        u = c.u[at]
        if p.upper:
            lanes.append((u, choose_upper(u, p.block, width, p.use_predictors, p.use_split, p.use_rice, p.use_gcd) if len(u) > 1 else None))
        else:
            z, size = _blocks(zigzag(lane_residuals(u, at, p)), p.block) if len(u) > 1 else (None, None)
            lanes.append((u, (z, size)))

    def widths() -> dict[int, int]:
        counts: dict[int, int] = {}
        for _, got in lanes:
            ws = got["param"][got["form"] != RICE] if p.upper and got else best_widths(*got, width)[0] if not p.upper and got[0] is not None else []
            for w in np.asarray(ws).tolist():
                counts[w] = counts.get(w, 0) + 1
        return counts

    counts = widths()
    lengths = code_lengths(counts) if counts else {}
    if lengths and p.learn_width:  # one reselection among the widths that have a code
        width = np.full(65, 1 << 20)
        for w, k in lengths.items():
            width[w] = k
        width[0] = min(width[0], max(lengths.values()) + 3)
        if p.upper:
            lanes = [(u, choose_upper(u, p.block, width, p.use_predictors, p.use_split, p.use_rice, p.use_gcd) if len(u) > 1 else None) for u, _ in lanes]
        counts = widths()
        lengths = code_lengths(counts) if counts else {}
    codes = canonical(lengths)

    payload, headers = Writer(), []
    for u, got in lanes:
        head = Writer()
        if p.upper and got is not None:
            for b in range(len(got["p"])):
                m, form, param, d = int(got["size"][b]), int(got["form"][b]), int(got["param"][b]), int(got["d"][b])
                z = got["z"][b, :m]
                head.put(int(got["p"][b]), 3)
                head.put(form, 2)
                head.put(int(d > 1), 1)
                if d > 1:
                    head.gamma(np.array([d], np.uint64))
                before = head.bits
                if form == RICE:
                    head.put(param, 5)
                else:
                    head.put(*codes[param])
                if form == PATCH:
                    flag = bool((z >> np.uint64(min(param, 63)) > 0).any()) if param < 64 else False
                    head.put(int(flag), 1)
                bits["predictor"] += head.bits - before
                at = payload.bits
                write_upper_block(z, form, param, payload)
                bits["residual"] += payload.bits - at
        elif not p.upper and got[0] is not None:
            z, size = got
            w, _ = best_widths(z, size, width)
            part = Writer()
            flags = write_patch(z, size, w, part)
            base = int((w * size).sum())
            marks = int(size[flags].sum())
            live = np.arange(z.shape[1])[None, :] < size[:, None]
            lens = bit_length(z)
            more = np.where(live, np.maximum(lens - w[:, None], 0), 0)
            ext = int(more.sum())
            bits["residual"] += base
            bits["exception"] += ext
            bits["patch"] += part.bits - base - ext
            assert part.bits >= base + ext + marks
            payload.extend(part)
            code = np.array([codes[k] for k in w.tolist()], np.int64)
            head.array(np.stack([code[:, 0].astype(np.uint64), flags.astype(np.uint64)], axis=1), np.stack([code[:, 1], np.ones(len(code), np.int64)], axis=1))
        headers.append(head)
        bits["predictor"] += head.bits if not p.upper else 0
    raw = np.flatnonzero(plan.route == RAW)
    before = payload.bits
    write_raw(words[raw], payload)
    bits["raw"] = payload.bits - before
    body = payload.bytes()

    flags = p.upper * _UPPER | (not p.persist) * _RESET | (not p.predict) * _ANCHOR | (not p.factor) * _PLAINQ | whole * _WHOLE
    meta = bytearray(MAGIC[p.contract] + bytes([VERSION, flags]) + varint(n) + varint(p.block))
    if p.bounded:
        meta += struct.pack("<ddB", p.eps, plan.origin, plan.step)
    first = int(np.argmax([len(a) for a in plan.used])) if plan.lanes else 0
    meta.append(len(plan.lanes) | first << 3)
    framing = len(meta)
    for c in plan.lanes:
        if p.bounded:
            meta.append(admission.DIVISORS.index(c.desc[0]))
        else:
            meta.append(c.desc[0])
            if p.upper:
                meta += varint(c.desc[1]) + varint(c.desc[2])
    meta += varint(len(route)) + route
    bits["route"] = 8 * (len(meta) - framing)
    at = len(meta)
    meta += varint(len(lengths)) + b"".join(bytes([w, k]) for w, k in sorted(lengths.items()))
    for (u, _), head in zip(lanes, headers):
        data = head.bytes()
        if len(u):
            meta += varint(int(zigzag(u[:1])[0]))
        meta += varint(len(data)) + data
    bits["predictor"] = 8 * (len(meta) - at)
    meta += varint(len(body))
    size = 8 * (len(meta) + len(body) + len(varint(len(meta))))
    bits["framing"] = size - sum(bits[k] for k in PARTS[1:])
    return bytes(meta), body, bits


def _read_route(data: bytes, n: int, lanes: int, whole: bool) -> np.ndarray | tuple[np.ndarray, np.ndarray]:
    """The whole route, or (mask of the primary lane, symbols of the others)."""
    if whole:
        if lanes != 1 or data:
            raise PageFormatError("route and lane count disagree")
        return np.zeros(n, np.int64)
    if not lanes:
        if data:
            raise PageFormatError("route without lanes")
        return np.full(n, RAW)
    r = Reader(data)
    first = r.flags(n)
    k = max(0, (lanes - 1).bit_length())
    symbols = r.array(np.full(int((~first).sum()), k)).astype(np.int64)
    if (symbols >= lanes).any():
        raise PageFormatError("illegal route symbol")
    if len(r.bits) - r.at >= 8 or r.bits[r.at :].any():
        raise PageFormatError("route too long")
    return first, symbols


def decode_page(meta: bytes, payload: bytes, contract: str | None = None) -> np.ndarray:
    """The words of a page; nothing is searched or tested for membership."""
    try:
        return _decode(meta, payload, contract)
    except PageFormatError:
        raise
    except (ValueError, IndexError, KeyError, struct.error, OverflowError) as e:
        raise PageFormatError(str(e)) from e


def _decode(meta: bytes, payload: bytes, contract: str | None) -> np.ndarray:
    kind = {m: k for k, m in MAGIC.items()}.get(bytes(meta[:2]))
    if kind is None or (contract is not None and kind != contract):
        raise PageFormatError("wrong magic")
    if meta[2] != VERSION or meta[3] >= 32:
        raise PageFormatError("unknown version or flags")
    flags = meta[3]
    n, at = read_varint(meta, 4)
    block, at = read_varint(meta, at)
    if not block or n > 1 << 24:
        raise PageFormatError("bad geometry")
    eps = origin = step = None
    lossy, narrow = kind.startswith("bounded"), kind.endswith("32")
    if lossy:
        eps, origin, step = struct.unpack_from("<ddB", meta, at)
        at += 17
    k, primary, at = meta[at] & 7, meta[at] >> 3, at + 1
    if k > 4 or primary >= max(k, 1):
        raise PageFormatError("too many lanes")
    descs = []
    for _ in range(k):
        if lossy:
            descs.append((admission.DIVISORS[meta[at]],))
            at += 1
        else:
            s, at = meta[at], at + 1
            d, r = 1, 0
            if flags & _UPPER:
                d, at = read_varint(meta, at)
                r, at = read_varint(meta, at)
            if s > 18 or d < 1 or r >= d:
                raise PageFormatError("illegal descriptor")
            descs.append((s, d, r))
    size, at = read_varint(meta, at)
    got = _read_route(meta[at : at + size], n, k, bool(flags & _WHOLE))
    at += size
    count, at = read_varint(meta, at)
    lengths = {}
    for _ in range(count):
        lengths[meta[at]] = meta[at + 1]
        at += 2
    decode = {(length, code): w for w, (code, length) in canonical(lengths).items()}
    anchors, heads, counts = [], [], None
    if isinstance(got, tuple):
        first, symbols = got
        others = [x for x in range(k) if x != primary] + [RAW]
        route = np.full(n, primary)
        route[~first] = np.array(others)[symbols]
    else:
        route = got
    counts = [int((route == j).sum()) for j in range(k)]
    for j in range(k):
        if not counts[j]:
            raise PageFormatError("empty lane")
        a, at = read_varint(meta, at)
        anchors.append(int(unzigzag(np.array([a], np.uint64))[0]))
        size, at = read_varint(meta, at)
        heads.append(bytes(meta[at : at + size]))
        if at + size > len(meta):
            raise PageFormatError("header beyond the metadata")
        at += size
    size, at = read_varint(meta, at)
    if at != len(meta) or size != len(payload):
        raise PageFormatError("lengths do not add up")
    body = Reader(payload)
    out = np.zeros(n, np.int64)
    for j in range(k):
        where = np.flatnonzero(route == j)
        u = _read_lane(anchors[j], where, heads[j], body, block, flags, decode)
        if lossy:
            q = u if flags & _PLAINQ else admission.restore_affine(u, descs[j][0], 0)
            x = admission.rebuild_bounded(q, origin, admission.error_steps(eps)[step])
        else:
            s, d, r = descs[j]
            q = admission.restore_affine(u, d, r)
            x = None if kind == "exact_integer" else admission.rebuild_exact(q, s)
        out[where] = q if x is None else admission.narrowed(x) if narrow else x.view(np.int64)
    raw = np.flatnonzero(route == RAW)
    out[raw] = read_raw(len(raw), body).view(np.int64)
    if len(body.bits) - body.at >= 8 or body.bits[body.at :].any():
        raise PageFormatError("payload too long")
    return out


def _read_lane(anchor: int, where: np.ndarray, head: bytes, body: Reader, block: int, flags: int, decode: dict) -> np.ndarray:
    n = len(where)
    u = np.zeros(n, np.int64)
    u[0] = anchor
    if n == 1:
        return u
    blocks = -(-(n - 1) // block)
    size = np.full(blocks, block)
    if (n - 1) % block:
        size[-1] = (n - 1) % block
    h = Reader(head)

    def symbol() -> int:
        code = length = 0
        while (length, code) not in decode:
            code, length = 2 * code + h.get(1), length + 1
            if length > 64:
                raise PageFormatError("illegal width symbol")
        return decode[(length, code)]

    if flags & _UPPER:
        values = [anchor]
        for m in size.tolist():
            p, form, divided = h.get(3), h.get(2), h.get(1)
            if p > 4 or form > RICE:
                raise PageFormatError("illegal block symbol")
            d = h.gamma() if divided else 1
            param = h.get(5) if form == RICE else symbol()
            flag = bool(h.get(1)) if form == PATCH else False
            r = unzigzag(read_upper_block(m, form, param, flag, body))
            for v in r.tolist():
                x = (predict_next(values[-3:] if len(values) > 3 else values, p) + v * d) & 0xFFFFFFFFFFFFFFFF
                values.append(x - (1 << 64) if x >> 63 else x)
        return np.array(values, np.int64)
    bits, i, w, patched = h.bits.tolist(), 0, [], []
    for _ in range(blocks):
        code = length = 0
        while (length, code) not in decode:
            code, length, i = 2 * code + bits[i], length + 1, i + 1
        w.append(decode[(length, code)])
        patched.append(bits[i])
        i += 1
    w, patched = np.array(w), np.array(patched, bool)
    r = unzigzag(read_patch(size, w, patched, body))
    with np.errstate(over="ignore"):
        if flags & _ANCHOR:
            u[1:] = anchor + r
        elif flags & _RESET:
            fresh = np.concatenate([[True], np.diff(where) != 1])
            base = np.concatenate([[np.int64(anchor)], r])
            start = np.flatnonzero(fresh)
            total = np.cumsum(base)
            seg = np.repeat(start, np.diff(np.concatenate([start, [n]])))
            u = total - total[seg] + base[seg] + np.where(seg > 0, np.int64(anchor), np.int64(0))
        else:
            u[1:] = anchor + np.cumsum(r)
    return u


def frame(meta: bytes, payload: bytes) -> bytes:
    return varint(len(meta)) + meta + payload


def split_frame(data: bytes) -> tuple[bytes, bytes]:
    try:
        n, at = read_varint(data, 0)
    except ValueError as e:
        raise PageFormatError(str(e)) from e
    if at + n > len(data):
        raise PageFormatError("metadata beyond the frame")
    return data[at : at + n], data[at + n :]


__all__ = ["MAGIC", "PARTS", "PageFormatError", "SPLIT", "decode_page", "encode_page", "frame", "split_frame"]
