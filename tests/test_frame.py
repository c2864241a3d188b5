import numpy as np
import pytest

from lattice_pages.functions import admission, bits, frame
from lattice_pages.plans.planner import RAW, plan_page
from lattice_pages.plans.profiles import ABLATIONS, BOUNDED, EXACT_FAST, EXACT_UPPER, profile

R = np.random.default_rng(11)
SPECIAL = np.array([0x8000000000000000, 0x7FF0000000000000, 0xFFF0000000000000, 0x7FF8000000000123, 1, 0x7FEFFFFFFFFFFFFF], np.uint64).view(np.float64)


def streams():
    smooth = np.cumsum(R.integers(-3, 4, 600)) / 10 + 20
    mixed = np.round(smooth, 1)
    mixed[::37] = R.integers(0, 10**6, len(mixed[::37])) / 1e5
    special = np.round(R.normal(size=300), 2)
    special[::17] = np.resize(SPECIAL, len(special[::17]))
    wide = np.array([9.2e18, -9.2e18, 1.0, 2.0, -(2.0**63), 1e300, 5e-324] * 9)
    return {"smooth": smooth, "mixed": mixed, "special": special, "wide": wide, "noise": R.normal(size=200), "steps": 50.0 * np.arange(500) + 4, "minutes": np.repeat(np.arange(100) * 60.0, 3), "constant": np.full(100, 7.25), "zeros": np.zeros(40), "one": np.array([3.14]), "none": np.zeros(0), "tail": np.round(R.normal(size=1025), 3), "jumps": np.where(R.random(512) < 0.02, 1e9, 1.0) * np.round(R.random(512), 1)}


@pytest.mark.parametrize("name", list(streams()))
@pytest.mark.parametrize("p", [EXACT_FAST, EXACT_UPPER, *(ABLATIONS[a] for a in ABLATIONS if not ABLATIONS[a].bounded)], ids=lambda p: repr(hash(p)))
def test_exact_round_trip(name, p):
    w = streams()[name].view(np.int64)
    meta, payload, parts = frame.encode_page(w, p)
    data = frame.frame(meta, payload)
    assert (frame.decode_page(*frame.split_frame(data), "exact") == w).all()
    assert sum(parts.values()) == 8 * len(data) and min(parts.values()) >= 0


@pytest.mark.parametrize("name", list(streams()))
@pytest.mark.parametrize("eps", [1e-1, 1e-2, 1e-3, 1e-6])
@pytest.mark.parametrize("factor", [True, False])
def test_bound(name, eps, factor):
    x = streams()[name]
    p = profile("bounded", eps=eps, factor=factor)
    plan = plan_page(x.view(np.int64), p)
    meta, payload, _ = frame.encode_page(x.view(np.int64), p, plan)
    y = frame.decode_page(meta, payload, "bounded").view(np.float64)
    ok = np.isfinite(x)
    with np.errstate(all="ignore"):
        assert (np.abs(x[ok] - y[ok]) <= eps).all()
    raw = plan.route == RAW
    assert (x.view(np.int64)[raw] == y.view(np.int64)[raw]).all() and (x.view(np.int64)[~ok] == y.view(np.int64)[~ok]).all()


def test_contracts_and_damage():
    w = streams()["mixed"].view(np.int64)
    meta, payload, _ = frame.encode_page(w, EXACT_FAST)
    with pytest.raises(frame.PageFormatError):
        frame.decode_page(meta, payload, "bounded")
    bad = [(b"XX" + meta[2:], payload), (meta[:-1], payload), (meta, payload[:-1]), (meta, payload + b"\0"), (meta[:2] + b"\x09" + meta[3:], payload), (meta[:3] + b"\xff" + meta[4:], payload), (b"", b"")]
    for m, p in bad:
        with pytest.raises(frame.PageFormatError):
            frame.decode_page(m, p)
    for i in range(len(meta)):  # damage never hangs or crashes otherwise
        try:
            frame.decode_page(meta[:i] + bytes([meta[i] ^ 0x41]) + meta[i + 1 :], payload)
        except frame.PageFormatError:
            pass


def test_planner_rules():
    for name, x in streams().items():
        w = x.view(np.int64)
        for p in (EXACT_FAST, EXACT_UPPER):
            plan = plan_page(w, p)
            assert len(plan.lanes) <= p.max_lanes and (plan.route < len(plan.lanes)).all()
            from dataclasses import replace

            assert plan.bits <= plan_page(w, replace(p, max_lanes=1)).bits + 64, name
    fast = {n: sum(map(len, frame.encode_page(x.view(np.int64), EXACT_FAST)[:2])) for n, x in streams().items()}
    one = {n: sum(map(len, frame.encode_page(x.view(np.int64), ABLATIONS["one_lane"])[:2])) for n, x in streams().items()}
    assert fast["mixed"] < 0.85 * one["mixed"]
    upper = sum(map(len, frame.encode_page(streams()["steps"].view(np.int64), EXACT_UPPER)[:2]))
    assert upper < fast["steps"]


def test_admission():
    x = np.array([12.4, 1234.5, 1234.56789, -0.0, np.nan, np.inf, 0.1 + 0.2, 9.3e18])
    q, ok = admission.scale_matrix(x)
    assert [int(np.argmax(ok[:, i])) if ok[:, i].any() else None for i in range(len(x))] == [1, 1, 5, None, None, None, 17, None]
    assert admission.checked_affine(2**62 // 5, 5, 3) == 2**62 // 5 * 5 + 3
    with pytest.raises(OverflowError):
        admission.checked_affine(2**62, 5, 3)
    assert len(admission.DIVISORS) == 25 and admission.affine_candidates(50 * np.arange(100) + 7)[0] == (50, 7)


def test_bit_codes():
    v = np.concatenate([R.integers(0, 2**63, 200, dtype=np.uint64), np.array([0, 1, 2**64 - 1, 2**63], np.uint64)])
    assert bits.bit_length(v).tolist() == [int(x).bit_length() for x in v]
    r = v.view(np.int64)
    assert (bits.unzigzag(bits.zigzag(r)) == r).all()
    out = bits.Writer()
    n = bits.bit_length(v)
    out.array(v, n)
    out.gamma(v[v > 0])
    back = bits.Reader(out.bytes())
    assert (back.array(n) == v).all() and [back.gamma() for _ in range(int((v > 0).sum()))] == v[v > 0].tolist()
    codes = bits.canonical(bits.code_lengths({3: 10, 4: 1, 9: 5, 0: 1}))
    assert sum(2.0**-k for _, k in codes.values()) == 1.0
