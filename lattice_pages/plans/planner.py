"""Page planning: which lanes, which route for each value, by the full encoded cost."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from lattice_pages.functions import admission
from lattice_pages.functions.bits import code_lengths, zigzag
from lattice_pages.functions.rawlane import raw_bits, raw_bits_least
from lattice_pages.functions.residuals import _blocks, best_widths, choose_upper, predictions, residuals
from lattice_pages.plans.profiles import Profile

#: Provisional bits of a width symbol, before the page's own code is learned.
PROVISIONAL = 7
RAW = -1


@dataclass
class Candidate:
    """One possible lane: its descriptor, the values it admits and their coordinates."""

    desc: tuple[int, ...]  # exact: (scale, divisor, residue); bounded: (divisor,)
    ok: np.ndarray
    u: np.ndarray
    bits: int  # of the descriptor

    def order(self) -> tuple:
        return self.desc


@dataclass
class Plan:
    lanes: list[Candidate]
    route: np.ndarray  # lane number, or RAW
    bits: int
    step: int = 0  # bounded: which of the three steps
    origin: float = 0.0
    used: list[np.ndarray] = field(default_factory=list)  # positions of each lane


def lane_residuals(u: np.ndarray, at: np.ndarray, p: Profile) -> np.ndarray:
    """Hold residuals of a lane under the profile's history rule."""
    if not p.predict:
        with np.errstate(over="ignore"):
            return u[1:] - u[0]
    if not p.persist:
        before = np.where(np.diff(at) == 1, u[:-1], u[0])
        with np.errstate(over="ignore"):
            return u[1:] - before
    return residuals(u)


def route_bits(n: int, sizes: list[int], n_raw: int) -> int:
    """Bits of the route: none for one lane that covers all, else a bitmap and codes for the others."""
    if not sizes or (len(sizes) == 1 and not n_raw):
        return 0
    others = len(sizes)  # the other lanes and the raw lane
    return n + (n - max(sizes)) * max(0, (others - 1).bit_length())


class PageCost:
    """Costs of lanes and raw sets of one page, remembered by what they hold."""

    def __init__(self, words: np.ndarray, p: Profile) -> None:
        self.words, self.p = words, p
        self.width = np.full(65, PROVISIONAL)
        self.lanes: dict = {}
        self.raws: dict = {}

    def learn(self, plan: Plan) -> None:
        """Replace provisional width costs by the code lengths of the plan's own widths."""
        counts: dict[int, int] = {}
        for lane, at in zip(plan.lanes, plan.used):
            if len(at) > 1:
                for w in self.widths(lane, at).tolist():
                    counts[w] = counts.get(w, 0) + 1
        lengths = code_lengths(counts) if counts else {}
        self.width = np.full(65, max(lengths.values(), default=1) + 3)
        for w, n in lengths.items():
            self.width[w] = n
        self.lanes = {}

    def widths(self, lane: Candidate, at: np.ndarray) -> np.ndarray:
        if self.p.upper:
            got = choose_upper(lane.u[at], self.p.block, self.width, self.p.use_predictors, self.p.use_split, self.p.use_rice, self.p.use_gcd)
            return got["param"][got["form"] != 2]
        z, size = _blocks(zigzag(lane_residuals(lane.u[at], at, self.p)), self.p.block)
        return best_widths(z, size, self.width)[0]

    def lane(self, lane: Candidate, at: np.ndarray) -> int:
        key = (lane.desc, at.tobytes())
        got = self.lanes.get(key)
        if got is None:
            got = lane.bits + 16
            if len(at):
                u = lane.u[at]
                anchor = int(zigzag(u[:1])[0])
                got += 8 * max(1, -(-anchor.bit_length() // 7))
                if len(at) > 1:
                    if self.p.upper:
                        c = choose_upper(u, self.p.block, self.width, self.p.use_predictors, self.p.use_split, self.p.use_rice, self.p.use_gcd)
                        got += int(c["bits"].sum())
                    else:
                        z, size = _blocks(zigzag(lane_residuals(u, at, self.p)), self.p.block)
                        got += int(best_widths(z, size, self.width)[1].sum())
            self.lanes[key] = got
        return got

    def raw(self, at: np.ndarray) -> int:
        key = at.tobytes()
        if key not in self.raws:
            self.raws[key] = raw_bits(self.words[at])
        return self.raws[key]

    def plan(self, lanes: list[Candidate], route: np.ndarray, under: int | None = None) -> Plan | None:
        """The plan and its cost; None as soon as a lower bound shows that it reaches ``under``."""
        used = [np.flatnonzero(route == k) for k in range(len(lanes))]
        raw = np.flatnonzero(route == RAW)
        bits = route_bits(len(route), [len(a) for a in used], len(raw))
        if under is not None and len(raw) > 4:
            least = bits + raw_bits_least(self.words[raw])
            if least >= under:
                return None
        rest = least - bits if under is not None and len(raw) > 4 else 0
        pairs = list(zip(lanes, used))
        for c, a in sorted(pairs, key=lambda x: (x[0].desc, x[1].tobytes()) not in self.lanes):  # known costs first
            bits += self.lane(c, a)
            if under is not None and bits + rest >= under:
                return None
        return Plan(lanes, route, bits + self.raw(raw), used=used)


def assign(lanes: list[Candidate], n: int, p: Profile) -> tuple[list[Candidate], np.ndarray]:
    """Refit: every value goes to the first lane in the profile's order that admits it."""
    route = np.full(n, RAW)
    ranked = sorted(lanes, key=(lambda c: -c.desc[0]) if p.bounded else Candidate.order)
    for k in range(len(ranked) - 1, -1, -1):
        route[ranked[k].ok] = k
    if p.bounded:  # by frequency, ties to the larger divisor
        sizes = [int((route == k).sum()) for k in range(len(ranked))]
        order = sorted(range(len(ranked)), key=lambda k: (-sizes[k], -ranked[k].desc[0]))
        new = np.full(n, RAW)
        for i, k in enumerate(order):
            new[route == k] = i
        return [ranked[k] for k in order], new
    return ranked, route


def greedy(cost: PageCost, singles: list[Candidate], more: list[Candidate], p: Profile) -> Plan:
    """The best one-lane plan (ties: the first candidate), then insertions while the cost falls strictly."""
    n = len(cost.words)
    best, rank = None, -1
    for k, c in sorted(enumerate(singles), key=lambda x: (-int(x[1].ok.sum()), x[0])):
        got = cost.plan(*assign([c], n, p), None if best is None else best.bits + 1)
        if got is not None and (best is None or (got.bits, k) < (best.bits, rank)):
            best, rank = got, k
    none = cost.plan([], np.full(n, RAW), None if best is None else best.bits + 1)
    if none is not None and (best is None or none.bits <= best.bits):
        best = none
    while best.lanes and len(best.lanes) < p.max_lanes:
        step = best
        have = {c.desc for c in best.lanes}
        for c in more:
            if c.desc in have:
                continue
            got = cost.plan(*assign([*best.lanes, c], n, p), step.bits)
            if got is not None and all(len(a) for a in got.used) and got.bits * (1 + p.alpha) < step.bits:
                step = got
        if step is best:
            break
        best = step
    return best


def exact_candidates(x: np.ndarray, p: Profile) -> tuple[list[Candidate], list[Candidate]]:
    """(scale lanes, affine lanes). A scale that admits what a lower one does is dominated."""
    q, ok = admission.scale_matrix(x, p.domain == "binary32")
    scales, affine = [], []
    seen: list[np.ndarray] = []
    for s in admission.SCALES:
        if not ok[s].any() or any(not (ok[s] & ~m).any() for m in seen):
            continue
        seen.append(ok[s])
        scales.append(Candidate((s, 1, 0), ok[s], q[s], 5 + (16 if p.use_affine else 0)))
        if p.use_affine:
            for d, r in admission.affine_candidates(q[s][ok[s]]):
                fits = ok[s] & (np.mod(q[s], d) == r)
                z = np.where(fits, (q[s] - r) // d, 0)
                affine.append(Candidate((s, d, r), fits, z, 5 + 8 * (-(-d.bit_length() // 7) + max(1, -(-r.bit_length() // 7)))))
    return scales, affine


def integer_candidates(words: np.ndarray, p: Profile) -> tuple[list[Candidate], list[Candidate]]:
    """The lane of all integers, and affine lanes of those that a step divides."""
    every = np.ones(len(words), bool)
    affine = []
    if p.use_affine:
        for d, r in admission.affine_candidates(words):
            fits = np.mod(words, d) == r
            affine.append(Candidate((0, d, r), fits, np.where(fits, (words - np.where(fits, r, 0)) // d, 0), 5 + 8 * (-(-d.bit_length() // 7) + max(1, -(-r.bit_length() // 7)))))
    return [Candidate((0, 1, 0), every, words, 5 + (16 if p.use_affine else 0))], affine


def plan_page(words: np.ndarray, p: Profile) -> Plan:
    """The plan of one page of 64-bit words."""
    x = p.values(words)
    cost = PageCost(words, p)
    if not p.bounded:
        if p.domain == "integer":  # words are coordinates already
            scales, affine = integer_candidates(words, p)
        else:
            scales, affine = exact_candidates(x, p)
        singles = more = [*scales, *affine]
        best = greedy(cost, singles, more, p)
        if best.lanes and p.learn_width:
            cost.learn(best)
            again = greedy(cost, singles, more, p)
            best = again if again.bits <= cost.plan(best.lanes, best.route).bits else cost.plan(best.lanes, best.route)
        return best
    origin = admission.frame_origin(x)
    if origin is None:
        return cost.plan([], np.full(len(words), RAW))
    best = None
    for k, step in enumerate(admission.error_steps(p.eps)):
        q, ok = admission.bounded_index(x, origin, step, p.eps, p.domain == "binary32")
        if not ok.any():
            continue
        lanes = []
        for d in admission.DIVISORS:
            fits = ok & (q % d == 0)
            if fits.any():
                lanes.append(Candidate((d,), fits, np.where(fits, q // d if p.factor else q, 0), 5))
        sizes = {c.desc: int(c.ok.sum()) for c in lanes}
        total = int(ok.sum())
        full = [c for c in lanes if sizes[c.desc] == total]
        # a part that divides saves about log2(d) bits a value and costs a bitmap; of equal parts the largest divisor is enough
        partial = [c for i, c in enumerate(lanes) if sizes[c.desc] < total and sizes[c.desc] * np.log2(c.desc[0]) > len(words) and not any(sizes[o.desc] == sizes[c.desc] and o.desc[0] % c.desc[0] == 0 for o in lanes[i + 1 :])]
        cost.lanes = {}  # coordinates belong to this step
        got = greedy(cost, full, partial, p)
        if p.learn_width and got.lanes:
            was = cost.width
            cost.learn(got)
            got2 = greedy(cost, full, partial, p)
            got = got2 if got2.bits <= got.bits else cost.plan(got.lanes, got.route)
            cost.width = was
        got.step, got.origin = k, origin
        if best is None or got.bits < best.bits:
            best = got
    return best if best is not None else cost.plan([], np.full(len(words), RAW))


__all__ = ["Candidate", "PageCost", "Plan", "RAW", "assign", "exact_candidates", "greedy", "lane_residuals", "plan_page", "predictions", "route_bits"]
