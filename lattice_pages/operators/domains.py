"""Page measures that look inside a plan: bits by prediction domain, lanes, invariants."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from lattice_pages.functions import admission
from lattice_pages.functions.bits import bit_length, zigzag
from lattice_pages.functions.frame import PARTS, decode_page, encode_page, frame
from lattice_pages.operators.codec import words_of
from lattice_pages.operators.pages import FEW_PAGES, grouped
from lattice_pages.plans.planner import RAW, plan_page
from lattice_pages.plans.profiles import PAGE, Profile, profile

DOMAINS = ("word_xor", "erased_xor", "adjacent_decimal", "one_integer_stream", "routed_lanes", "normalised_lanes")


def each_page(df: DataFrame, make: Callable[[np.ndarray], dict], ddl: str, page_size: int = PAGE) -> DataFrame:
    """``stream_id, page_no`` and what ``make`` gives for the words of every page; one exchange."""
    value = "word" if "word" in df.columns else "value"
    names = [c.split()[0] for c in ddl.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []

        def done() -> pa.RecordBatch:
            got = make(np.concatenate(held))
            return pa.RecordBatch.from_arrays([pa.array([now[0]]), pa.array([now[1]]), *(pa.array([got[n]]) for n in names)], ["stream_id", "page_no", *names])

        for b in batches:
            if not b.num_rows:
                continue
            stream, page, (w, valid) = b.column("stream_id").to_numpy(zero_copy_only=False), b.column("ord").to_numpy(zero_copy_only=False) // page_size, words_of(b.column(value))
            if valid is not None:
                raise ValueError("page measures take values without nulls")
            cuts = [0, *(np.flatnonzero((stream[1:] != stream[:-1]) | (page[1:] != page[:-1])) + 1).tolist(), len(page)]
            for a, z in zip(cuts, cuts[1:]):
                if (stream[a], int(page[a])) != now:
                    if held:
                        yield done()
                    now, held = (stream[a], int(page[a])), []
                held.append(w[a:z])
        if held:
            yield done()

    return grouped(df.select("stream_id", "ord", value), page_size, FEW_PAGES).mapInArrow(run, f"stream_id string, page_no long, {ddl}")


def _xor_bits(words: np.ndarray) -> int:
    """Digits of successive XORs from their first set bit to their last."""
    w = words.view(np.uint64)
    x = w[1:] ^ w[:-1]
    x = x[x > 0]
    return int((bit_length(x) - bit_length(x & (~x + np.uint64(1))) + 1).sum())


def erased(words: np.ndarray, scale: np.ndarray) -> np.ndarray:
    """Words with as many low bits cleared as the value's decimals can restore; others as they are."""
    x = words.view(np.float64)
    best = words.copy()
    with np.errstate(all="ignore"):
        p = admission.POWERS[np.maximum(scale, 0)]
        open_ = scale >= 0
        for k in range(1, 53):
            cut = words & ~np.int64((1 << k) - 1)
            v = cut.view(np.float64)
            back = np.copysign(np.ceil(np.abs(v) * p) / p, x)
            good = open_ & (back.view(np.int64) == words)
            best = np.where(good, cut, best)
    return best


def domain_bits(words: np.ndarray) -> dict[str, int]:
    """Residual digits of one page in six representations, all starting afresh; values without a scale cost 64 bits.

    Coordinates are numbers here, as in the cost layer: a negative zero has scale 0 and coordinate 0.
    """
    x = words.view(np.float64) + 0.0  # no negative zeros
    q, ok = admission.scale_matrix(x)
    scale = np.where(ok.any(axis=0), ok.argmax(axis=0), -1)
    rest = 64 * int((scale < 0).sum())
    cost = lambda r: int(bit_length(zigzag(r)).sum())
    out = {"word_xor": _xor_bits(words), "erased_xor": _xor_bits(erased(words, scale))}
    good = np.flatnonzero(scale >= 0)
    adjacent = one = routed = normal = rest
    if len(good):
        s = scale[good]
        pair = np.maximum(s[1:], s[:-1])
        with np.errstate(over="ignore"):
            at = lambda i, k: np.rint(x[i] * admission.POWERS[k]).astype(np.int64)
            adjacent += cost(at(good[1:], pair) - at(good[:-1], pair))
            one += cost(np.diff(at(good, s.max())))
            for k in np.unique(s):
                r = np.diff(q[k][good[s == k]])
                routed += cost(r)
                g = int(np.gcd.reduce(r[r != np.int64(-(1 << 63))])) if len(r) else 0
                normal += cost(r // g if g > 1 else r)
    return out | {"adjacent_decimal": adjacent, "one_integer_stream": one, "routed_lanes": routed, "normalised_lanes": normal, "n": len(words)}


def by_domain(df: DataFrame, page_size: int = PAGE) -> DataFrame:
    return each_page(df, domain_bits, ", ".join(f"{d} long" for d in DOMAINS) + ", n long", page_size)


def lane_stats(df: DataFrame, profile_name: str | Profile = "exact_fast", eps: float | None = None, page_size: int = PAGE) -> DataFrame:
    """Lanes of each page's plan, values in its largest lane and in the raw lane, and bits of entropy of its route."""
    p = profile(profile_name, eps)

    def make(words: np.ndarray) -> dict:
        plan = plan_page(words, p)
        n = np.array([len(a) for a in plan.used] + [int((plan.route == RAW).sum())])
        share = n[n > 0] / n.sum()
        return {"n": len(words), "lanes": len(plan.lanes), "largest": int(max(n[:-1], default=0)), "raw": int(n[-1]), "entropy": float(-(share * np.log2(share)).sum() + 0.0)}

    return each_page(df, make, "n long, lanes long, largest long, raw long, entropy double", page_size)


def invariants(df: DataFrame, page_size: int = PAGE) -> DataFrame:
    """Pages that break a rule: lossless frames, bit parts that add up, affine coordinates that come back, factoring without error."""
    fast, upper, full, plain = (profile(n) for n in ("exact_fast", "exact_upper", "bounded", "bounded_no_factor"))

    def make(words: np.ndarray) -> dict:
        bad = {"lossless": 0, "parts": 0, "affine": 0, "factor": 0}
        for p in (fast, upper):
            plan = plan_page(words, p)
            meta, body, bits = encode_page(words, p, plan)
            bad["lossless"] |= int((decode_page(meta, body) != words).any())
            bad["parts"] |= int(sum(bits[k] for k in PARTS) != 8 * len(frame(meta, body)))
            for c in plan.lanes:
                s, d, r = c.desc
                q = admission.restore_affine(c.u[c.ok], d, r)
                same = admission.rebuild_exact(q, s).view(np.int64) == words[c.ok]
                whole = np.diff(q) == d * np.diff(c.u[c.ok])  # differences divide by the step
                bad["affine"] |= int(not (same.all() and whole.all()))
        x = words.view(np.float64)
        a, b = (decode_page(*encode_page(words, p)[:2]).view(np.float64) for p in (full, plain))
        fine = np.isfinite(x)
        with np.errstate(all="ignore"):
            bad["factor"] = int((np.abs(a - x)[fine] > full.eps).any() or (np.abs(b - x)[fine] > full.eps).any() or (a.view(np.int64)[~fine] != words[~fine]).any())
        return bad

    return each_page(df, make, "lossless long, parts long, affine long, factor long", page_size)
