"""The cost layer as relational algebra: one text for Spark and for DuckDB.

``E`` spells the few functions that differ. On the Spark side a stream is a view whose
ordinals come from a range partitioning; in DuckDB it is a subquery with a window.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from lattice_pages.functions.admission import DIVISORS, SCALES, error_steps
from lattice_pages.plans.profiles import PAGE
from lattice_pages.plans.streams import BY_NAME, duck_sql

BLOCK = 16


@dataclass(frozen=True)
class E:
    """An engine's spelling."""

    spark: bool

    def rint(self, x: str) -> str:
        return f"rint({x})" if self.spark else f"round_even({x}, 0)"

    def int(self, x: str) -> str:
        return f"CAST({x} AS BIGINT)"

    def idiv(self, a: str, b: str) -> str:
        return f"({a} div {b})" if self.spark else f"({a} // {b})"

    def stream(self, name: str) -> str:
        return f"s_{name}" if self.spark else f"({duck_sql(BY_NAME[name])})"

    def min_by(self, a: str, b: str) -> str:
        return f"min_by({a}, {b})" if self.spark else f"arg_min({a}, {b})"

    def explode(self, n: int, name: str) -> str:
        """A table of 0..n-1."""
        return f"(SELECT explode(sequence(0, {n - 1})) AS {name})" if self.spark else f"(SELECT unnest(range({n})) AS {name})"

    def bit_or(self, x: str) -> str:
        return f"bit_or({x})"


SPARK, DUCK = E(True), E(False)


def zz(r: str) -> str:
    return f"(CASE WHEN {r} >= 0 THEN 2 * {r} ELSE -2 * {r} - 1 END)"


def blen(v: str) -> str:
    return f"(CASE WHEN {v} = 0 THEN 0 ELSE length(bin({v})) END)"


def p10(s: int) -> str:
    return f"1e{s}"


def admits(e: E, x: str, s: int) -> str:
    y = e.rint(f"{x} * {p10(s)}")
    return f"(abs({y}) < 9.2e18 AND {y} / {p10(s)} = {x})"


def min_scale(e: E, x: str) -> str:
    return "(CASE " + " ".join(f"WHEN {admits(e, x, s)} THEN {s}" for s in SCALES) + " END)"


def at_scale(e: E, x: str, s: str, top: int = 9) -> str:
    """The coordinate of x at the scale in column s, 0..top."""
    return "(CASE " + " ".join(f"WHEN {s} = {k} THEN {e.int(e.rint(f'{x} * {p10(k)}'))}" for k in range(top + 1)) + " END)"


def pages(e: E, name: str, page: int = PAGE) -> str:
    return f"SELECT {e.idiv('ord', str(page))} AS page_no, ord % {page} AS pos, value FROM {e.stream(name)} t"


def one_lane(e: E, name: str, page: int = PAGE) -> str:
    """Every value at its page's widest scale; r: hold residual (null at the anchor)."""
    return f"""SELECT page_no, pos, s, q, q - lag(q) OVER (PARTITION BY page_no ORDER BY pos) AS r FROM (
      SELECT page_no, pos, s, {at_scale(e, 'value', 's')} AS q FROM (
        SELECT page_no, pos, value, max({min_scale(e, 'value')}) OVER (PARTITION BY page_no) AS s FROM ({pages(e, name, page)}) a) b) c"""


def routed(e: E, name: str, page: int = PAGE) -> str:
    """Every value at its lowest scale, against the last of the same scale."""
    return f"""SELECT page_no, pos, s, q, q - lag(q) OVER (PARTITION BY page_no, s ORDER BY pos) AS r FROM (
      SELECT page_no, pos, s, {at_scale(e, 'value', 's')} AS q FROM (
        SELECT page_no, pos, value, {min_scale(e, 'value')} AS s FROM ({pages(e, name, page)}) a) b) c WHERE s <= 9"""


def lens(e: E, rows: str, block: int = BLOCK) -> str:
    """z and its length, with block numbers along the lane."""
    return f"""SELECT page_no, s, {e.idiv('j', str(block))} AS block, j, z, {blen('z')} AS l FROM (
      SELECT page_no, s, {zz('r')} AS z, row_number() OVER (PARTITION BY page_no, s ORDER BY pos) - 1 AS j FROM ({rows}) x WHERE r IS NOT NULL) y"""


def gamma(v: str) -> str:
    return f"(2 * {blen(v)} - 1)"


def block_costs(e: E, rows: str, block: int = BLOCK, width_bits: int = 7) -> str:
    """page_no, s, block, w, bits: the cheapest admissible width of each block."""
    base = lens(e, rows, block)
    widths = f"SELECT DISTINCT page_no, s, block, l AS w FROM ({base}) a UNION SELECT DISTINCT page_no, s, block, 0 AS w FROM ({base}) b"
    cost = f"""SELECT a.page_no, a.s, a.block, w.w, {width_bits} + 1 + count(*) * w.w + max(CASE WHEN l > w.w THEN 1 ELSE 0 END) * count(*)
      + sum(CASE WHEN l > w.w THEN {gamma('(l - w.w)')} + l - w.w ELSE 0 END) AS bits
      FROM ({base}) a JOIN ({widths}) w ON a.page_no = w.page_no AND a.s = w.s AND a.block = w.block GROUP BY a.page_no, a.s, a.block, w.w"""
    return f"SELECT page_no, s, block, CAST(w AS BIGINT) AS w, CAST(bits AS BIGINT) AS bits FROM (SELECT *, row_number() OVER (PARTITION BY page_no, s, block ORDER BY bits, w) AS n FROM ({cost}) c) d WHERE n = 1"


def bounded_q(e: E, name: str, eps: float, k: int) -> str:
    """page_no, pos, value, q (null if not admitted) for the k-th step."""
    d = f"{error_steps(eps)[k]!r}"
    d = d if "e" in d else d + "e0"
    bound = f"{eps!r}" if "e" in f"{eps!r}" else f"{eps!r}e0"
    origin = f"SELECT page_no, {e.min_by('value', 'pos')} AS o FROM ({pages(e, name)}) a WHERE value <> 0 GROUP BY page_no"
    c = f"SELECT p.page_no, p.pos, p.value, g.o, {e.int(e.rint(f'(p.value - g.o) / {d}'))} AS c FROM ({pages(e, name)}) p JOIN ({origin}) g ON p.page_no = g.page_no"
    err = lambda q: f"abs(value - (o + CAST({q} AS DOUBLE) * {d}))"
    f = f"SELECT page_no, pos, value, c, {err('c')} AS e0, {err('(c - 1)')} AS e1, {err('(c + 1)')} AS e2 FROM ({c}) x"
    # least error, then least magnitude
    pick = "CASE WHEN least(e0, e1, e2) = e0 THEN c WHEN e1 < e2 OR (e1 = e2 AND abs(c - 1) <= abs(c + 1)) THEN c - 1 ELSE c + 1 END"
    return f"SELECT page_no, pos, value, CASE WHEN least(e0, e1, e2) <= {bound} THEN {pick} END AS q FROM ({f}) y"


def predictor_costs(e: E, name: str) -> str:
    """page_no, block, p: the cheapest predictor of each block at fixed width = its longest residual."""
    lag = lambda k: f"lag(q, {k}) OVER (PARTITION BY page_no ORDER BY pos)"
    base = f"SELECT page_no, pos, q, {lag(1)} AS u1, {lag(2)} AS u2, {lag(3)} AS u3 FROM (SELECT page_no, pos, q FROM ({one_lane(e, name)}) a) b"
    half = e.int("floor((u1 - u2) / 2.0)")
    preds = ["u1", "coalesce(2 * u1 - u2, u1)", "coalesce(3 * u1 - 3 * u2 + u3, u1)", f"coalesce(u1 + {half}, u1)", f"coalesce(u2 + {half}, u1)"]
    union = " UNION ALL ".join(f"SELECT page_no, {e.idiv('(pos - 1)', str(BLOCK))} AS block, {i} AS p, {blen(zz(f'(q - {x})'))} AS l FROM ({base}) b WHERE u1 IS NOT NULL" for i, x in enumerate(preds))
    cost = f"SELECT page_no, block, p, count(*) * max(l) AS bits FROM ({union}) u GROUP BY page_no, block, p"
    return f"SELECT page_no, block, CAST(p AS BIGINT) AS p, CAST(bits AS BIGINT) AS bits FROM (SELECT *, row_number() OVER (PARTITION BY page_no, block ORDER BY bits, p) AS n FROM ({cost}) c) d WHERE n = 1"


def rice_costs(e: E, rows: str) -> str:
    shift = "shiftright(z, k)" if e.spark else "(z >> k)"
    cost = f"SELECT page_no, s, block, k, 5 + sum({shift}) + count(*) * (1 + k) AS bits FROM ({lens(e, rows)}) a CROSS JOIN {e.explode(21, 'k')} b GROUP BY page_no, s, block, k"
    return f"SELECT page_no, s, block, CAST(k AS BIGINT) AS k, CAST(bits AS BIGINT) AS bits FROM (SELECT *, row_number() OVER (PARTITION BY page_no, s, block ORDER BY bits, k) AS n FROM ({cost}) c) d WHERE n = 1"


def split_costs(e: E, rows: str) -> str:
    top = f"SELECT *, max(l) OVER (PARTITION BY page_no, s, block) AS t FROM ({lens(e, rows)}) a"
    cost = f"SELECT page_no, s, block, w, 7 + count(*) * (w + 1) + sum(CASE WHEN l > w THEN 1 ELSE 0 END) * (max(t) - w) AS bits FROM ({top}) a CROSS JOIN {e.explode(64, 'w')} b WHERE w < t GROUP BY page_no, s, block, w"
    return f"SELECT page_no, s, block, CAST(w AS BIGINT) AS w, CAST(bits AS BIGINT) AS bits FROM (SELECT *, row_number() OVER (PARTITION BY page_no, s, block ORDER BY bits, w) AS n FROM ({cost}) c) d WHERE n = 1"


def mixed(e: E, name: str, rate_inv: int, burst: bool) -> str:
    """Coarse values with fine exceptions: one position in ``rate_inv``, spread or in bursts."""
    q = e.int(e.rint("100 * value"))
    hit = f"ord % {PAGE} < {math.floor(PAGE / rate_inv)}" if burst else f"ord % {rate_inv} = 0"
    fine = f"CAST({q} * 10000 + (ord * 7919 + 13) % 9999 + 1 AS DOUBLE) / 1e6"
    return f"SELECT ord, CASE WHEN {hit} THEN {fine} ELSE CAST({q} AS DOUBLE) / 1e2 END AS value FROM {e.stream(name)} t"


def mixed_routes(e: E, name: str, rate_inv: int, burst: bool) -> str:
    rows = f"SELECT {e.idiv('ord', str(PAGE))} AS page_no, ord % {PAGE} AS pos, value FROM ({mixed(e, name, rate_inv, burst)}) m"
    sc = f"SELECT page_no, pos, {min_scale(e, 'value')} AS s, value FROM ({rows}) a"
    two = f"SELECT page_no, pos, CASE WHEN s <= 2 THEN 2 ELSE 6 END AS s, value FROM ({sc}) b"
    q = f"SELECT page_no, pos, s, {at_scale(e, 'value', 's')} AS q FROM ({two}) c"
    r = f"SELECT s, q - lag(q) OVER (PARTITION BY page_no, s ORDER BY pos) AS r FROM ({q}) d"
    return f"SELECT {rate_inv} AS one_in, {'true' if burst else 'false'} AS burst, CAST(s AS BIGINT) AS lane, count(*) AS n, CAST(sum({blen(zz('r'))}) AS BIGINT) AS bits FROM ({r}) f GROUP BY s"


def retained(e: E, name: str, pct: int) -> str:
    kept = f"SELECT row_number() OVER (PARTITION BY {e.idiv('ord', str(PAGE))} ORDER BY ord) AS k, {e.idiv('ord', str(PAGE))} AS page_no, {e.int(e.rint('value * 100'))} AS q FROM {e.stream(name)} t WHERE (ord * 2654435761) % 1000 < {10 * pct}"
    r = f"SELECT q - lag(q) OVER (PARTITION BY page_no ORDER BY k) AS r FROM ({kept}) a"
    return f"SELECT {pct} AS pct, count(*) AS n, CAST(sum({blen(zz('r'))}) AS BIGINT) AS bits FROM ({r}) b"


def permuted(e: E, name: str, pct: int) -> str:
    page = e.idiv("ord", str(PAGE))
    base = f"SELECT ord, {page} AS page_no, {e.int(e.rint('value * 100'))} AS q, (ord * 2654435761) % 1000 < {10 * pct} AS moved FROM {e.stream(name)} t"
    a = f"SELECT ord, page_no, row_number() OVER (PARTITION BY page_no ORDER BY ord) AS k FROM ({base}) b WHERE moved"
    c = f"SELECT q, page_no, row_number() OVER (PARTITION BY page_no ORDER BY (ord * 40503) % 65536, ord) AS k FROM ({base}) b WHERE moved"
    rows = f"SELECT a.ord, a.page_no, c.q FROM ({a}) a JOIN ({c}) c ON a.page_no = c.page_no AND a.k = c.k UNION ALL SELECT ord, page_no, q FROM ({base}) b WHERE NOT moved"
    r = f"SELECT q, q - lag(q) OVER (PARTITION BY page_no ORDER BY ord) AS r FROM ({rows}) d"
    return f"SELECT {pct} AS pct, count(*) AS n, CAST(sum(q) AS BIGINT) AS total, CAST(sum({blen(zz('r'))}) AS BIGINT) AS bits FROM ({r}) f"


def structure(e: E, name: str, page: int, block: int) -> str:
    return f"SELECT {page} AS page, {block} AS block, count(*) AS blocks, CAST(sum(bits) AS BIGINT) AS bits FROM ({block_costs(e, one_lane(e, name, page), block)}) a"


def divisor_cover(e: E, name: str, eps: float) -> str:
    values = ", ".join(f"({d})" for d in DIVISORS)
    table = f"(SELECT col1 AS d FROM VALUES {values})" if e.spark else f"(SELECT col0 AS d FROM (VALUES {values}) v)"
    return f"SELECT CAST(d AS BIGINT) AS d, count(*) AS n, CAST(sum(CASE WHEN q % d = 0 THEN 1 ELSE 0 END) AS BIGINT) AS covered FROM ({bounded_q(e, name, eps, 0)}) a CROSS JOIN {table} t WHERE q IS NOT NULL GROUP BY d"
