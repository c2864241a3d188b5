"""Personal data: high-recall candidates, boosted trees, calibrated thresholds.

Base rules (emails, ip addresses, card and phone numbers) are exact and always stay.
Beside them, generators propose further spans, which may overlap the base and each
other: numbers glued to other numbers, phone numbers without a plus, cards with other
separators, written-out email addresses, ip addresses within longer runs. Gradient boosted trees
score each candidate from its format and its context; a threshold per kind, calibrated
on held-out rows for ``PRECISION``, decides; the best-scoring spans that touch no base
span and no better span are added.

The trees are trained here, on candidates from a synthetic text of ``TRAIN_TEXTS``
lines with known answers (a bounded sample, made from a seed), in numpy.

Defined results: a null text counts as empty and has no span; repeated rows give
repeated results; an empty table gives an empty table. Whole texts are read. ``detect``
reads only the id and text columns; ``redact`` keeps all columns as they are.
"""

from __future__ import annotations

import hashlib
import random
import re
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from lattice_pages.session import sparing

KINDS = ("email", "ip", "card", "phone")
PRECISION = 0.995
TRAIN_TEXTS = 6000
Span = tuple[str, int, int]

# The base patterns.
_HOST = re.compile(r"@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_IP = re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
_CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_DIGIT = re.compile(r"[0-9]")


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c)
        total += d if i % 2 == 0 else (2 * d if d < 5 else 2 * d - 9)
    return total % 10 == 0


def _digits(text: str) -> str:
    return "".join(c for c in text if "0" <= c <= "9")


def _octet(part: str) -> bool:
    """At most 255; of any length, as zeros may lead."""
    part = part.lstrip("0")
    return len(part) <= 3 and int(part or "0") <= 255


def _emails(text: str) -> Iterator[Span]:
    """Leftmost non-overlapping emails, found from their @: linear in the text."""
    at, free = text.find("@"), 0
    while at >= 0:
        start = at
        while start > free and text[start - 1] in _LOCAL:
            start -= 1
        if start < at and (m := _HOST.match(text, at)):
            yield "email", start, m.end()
            free = m.end()
        at = text.find("@", max(at + 1, free))


def base_spans(text: str) -> list[Span]:
    """The base spans, by kind as listed, then by start."""
    got = list(_emails(text))
    if _DIGIT.search(text):
        got += [("ip", m.start(), m.end()) for m in _IP.finditer(text) if all(_octet(p) for p in m.group().split("."))]
        got += [("card", m.start(), m.end()) for m in _CARD.finditer(text) if 16 <= len(d := _digits(m.group())) <= 19 and luhn(d)]
        if "+" in text:
            got += [("phone", m.start(), m.end()) for m in _PHONE.finditer(text) if 8 <= len(_digits(m.group())) <= 15]
    return got


# ---------------------------------------------------------------- candidates

_CAND_CARD = re.compile(r"(?<![0-9])(?=([0-9]{4}(?:[ ./_\xa0-]?[0-9]{4}){3}(?:[0-9]{1,3})?|[0-9]{4}[ .-]?[0-9]{6}[ .-]?[0-9]{5})(?![0-9]))")
_CAND_PHONE = re.compile(r"(?<![0-9+])(?=(\+[0-9]{1,3}[ .-]?\(?[0-9]{2,4}\)?[ .-]?[0-9]{3,4}[ .-]?[0-9]{3,4}|\(?[0-9]{3}\)?[ .-]?[0-9]{3}[ .-][0-9]{4})(?![0-9]))")
_CAND_IP = re.compile(r"(?<![0-9.])(?=([0-9]{1,3}(?:\.[0-9]{1,3}){3})(?![0-9]))")
_CAND_EMAIL = re.compile(r"[\w.+%-]{1,64} ?(?:\(at\)|\[at\]|\{at\}| at ) ?[A-Za-z0-9-]{1,63}(?: ?(?:\(dot\)|\[dot\]|\{dot\}| dot |\.) ?[A-Za-z0-9-]{2,63})+", re.I)
_OBFUSCATED = ("(at)", "[at]", "{at}", " dot ", "(dot)", "[dot]")
_WORDS = {"card": ("card", "visa", "master", "pay", "credit", "karte", "carte", "tarjeta"), "phone": ("call", "phone", "tel", "mobile", "fax", "contact", "anruf", "appel", "llam"), "ip": ("ip", "host", "server", "address", "ping", "login"), "email": ("mail", "write", "contact", "reach")}
_AGAINST = ("version", "v.", "isbn", "order", "invoice", "ref", "id", "section", "page", "price", "total", "build", "release", "serial", "no.", "#", "$", "€", "=")


def candidates(text: str) -> list[Span]:
    """High-recall proposals of every kind; they may overlap."""
    got: list[Span] = []
    if _DIGIT.search(text):
        for kind, pattern in (("card", _CAND_CARD), ("phone", _CAND_PHONE), ("ip", _CAND_IP)):
            got += [(kind, m.start(1), m.end(1)) for m in pattern.finditer(text)]
    low = text.lower() if "(" in text or "[" in text or "{" in text or " dot " in text else ""
    if any(m in low for m in _OBFUSCATED):
        got += [("email", m.start(), m.end()) for m in _CAND_EMAIL.finditer(text)]
    return got


def features(text: str, span: Span) -> list[float]:
    """Format and context of a candidate."""
    kind, a, b = span
    s, left, right = text[a:b], text[max(0, a - 24) : a], text[b : b + 16]
    digits, low = _digits(s), left.lower()
    groups = re.findall("[0-9]+", s)
    before, after = left[-1:], right[:1]
    return [
        KINDS.index(kind), len(s), len(digits), float(bool(digits) and luhn(digits)), len(groups),
        max(map(len, groups), default=0), min(map(len, groups), default=0),
        len({c for c in s if not c.isalnum()}), float("+" in s), float("(" in s and ")" in s), s.count("."), s.count("-"), s.count(" "),
        float(kind == "ip" and all(int(g) <= 255 and (len(g) == 1 or g[0] != "0") for g in groups)),
        float(before.isalpha() or before == "_"), float(before.isdigit()), float(before in ".-/:=#$+" and before != ""), float(after.isalpha() or after == "_"), float(after in "-/:%" and after != ""),
        float(after == "." and right[1:2].isdigit()), float(bool(re.search(r"[0-9][ .()-]*$", left))), float(bool(re.match(r"[ .()-]*[0-9]", right))),
        float(any(w in low for w in _WORDS[kind])), float(any(w in low for w in _AGAINST)),
        float(digits[:1] in "3456") if digits else 0.0, float(bool(re.search(r"[\[({](at|dot)[\])}]", s, re.I))),
    ]


# ---------------------------------------------------------------- boosted trees


@dataclass
class Trees:
    """Depth-limited regression trees for log-odds, as flat arrays (one row a tree)."""

    base: float
    depth: int
    feature: np.ndarray
    cut: np.ndarray
    leaf: np.ndarray

    def score(self, x: np.ndarray) -> np.ndarray:
        z = np.full(len(x), self.base)
        for f, c, leaf in zip(self.feature, self.cut, self.leaf):
            at = np.zeros(len(x), np.int64)
            for _ in range(self.depth):
                at = 2 * at + 1 + (x[np.arange(len(x)), f[at]] > c[at])
            z += leaf[at - (2**self.depth - 1)]
        return 1 / (1 + np.exp(-z))


def boost(x: np.ndarray, y: np.ndarray, rounds: int = 50, depth: int = 3, rate: float = 0.3, ridge: float = 1.0) -> Trees:
    """Second-order boosting with exact splits on at most 32 cuts a feature."""
    base = float(np.log((y.mean() + 1e-6) / (1 - y.mean() + 1e-6)))
    cuts = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, 33)[1:-1])) for j in range(x.shape[1])]
    over = [(j, c, x[:, j] > c) for j, cs in enumerate(cuts) for c in cs if 0 < (x[:, j] > c).sum() < len(x)]
    masks = np.array([m for _, _, m in over], np.float64)
    z = np.full(len(x), base)
    out = []
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-z))
        g, h = p - y, p * (1 - p)
        f, c = np.zeros(2**depth - 1, np.int64), np.full(2**depth - 1, np.inf)
        at = np.zeros(len(x), np.int64)
        for node in range(2**depth - 1):
            own = at == node
            if own.any():
                right_g, right_h = np.einsum("ij,j->i", masks, g * own), np.einsum("ij,j->i", masks, h * own)
                all_g, all_h = (g * own).sum(), (h * own).sum()
                gain = right_g**2 / (right_h + ridge) + (all_g - right_g) ** 2 / (all_h - right_h + ridge) - all_g**2 / (all_h + ridge)
                k = int(gain.argmax())
                if gain[k] > 1e-6:
                    f[node], c[node] = over[k][0], over[k][1]
            at = np.where(own, 2 * node + 1 + (x[:, f[node]] > c[node]), at)
        at -= 2**depth - 1
        leaf = np.array([-rate * g[at == i].sum() / (h[at == i].sum() + ridge) for i in range(2**depth)])
        z += leaf[at]
        out.append((f, c, leaf))
    return Trees(base, depth, *(np.array(a) for a in zip(*out)))


def synthetic(n: int = TRAIN_TEXTS, seed: int = 7) -> list[tuple[str, list[Span]]]:
    """Lines with known personal data among look-alikes."""
    r = random.Random(seed)
    d = lambda k: "".join(r.choice("0123456789") for _ in range(k))
    word = lambda: "".join(r.choice("etaoinshrdlu") for _ in range(r.randint(2, 9)))

    def card(good: bool) -> str:
        while True:
            s = r.choice("3456") + d(15)
            if luhn(s) == good:
                sep = r.choice(["", "", " ", "-", ".", "/"])
                return sep.join(s[i : i + 4] for i in range(0, 16, 4))

    def phone() -> str:
        a, b, c = r.choice("23456789") + d(2), r.choice("23456789") + d(2), d(4)
        cc = r.choice(["+1 ", "+44 ", "+49 ", "+33-", "+1-"])
        return r.choice([f"{cc}({a}) {b}-{c}", f"{cc}{a} {b} {c}", f"({a}) {b}-{c}", f"{a}-{b}-{c}", f"{a}.{b}.{c}"])

    def ip(good: bool) -> str:
        return ".".join(str(r.randint(1, 255) if good else r.randint(256, 999)) for _ in range(4))

    def email() -> str:
        return f"{word()}{r.choice(['(at)', '[at]', ' (at) ', ' [at] '])}{word()}{r.choice(['.', '(dot)', ' [dot] '])}{r.choice(['com', 'org', 'net'])}"

    good = [("card", lambda: card(True)), ("phone", phone), ("ip", lambda: ip(True)), ("email", email)]
    bad = [lambda: card(False), lambda: f"version {r.randint(1, 9)}.{d(1)}.{d(2)}.{d(1)}", lambda: "v." + ip(True), lambda: ip(False), lambda: f"ISBN 978-{d(1)}-{d(4)}-{d(4)}-{d(1)}", lambda: f"order #{d(3)}-{d(3)}-{d(4)}", lambda: f"id={d(3)} {d(3)} {d(4)}", lambda: f"{d(16)}", lambda: f"x{d(3)}-{d(3)}-{d(4)}", lambda: f"{ip(True)}.{d(2)}", lambda: f"20{d(2)}-{d(2)}-{d(2)} {d(2)}:{d(2)}", lambda: f"${d(3)} {d(3)} {d(4)}", lambda: f"build {d(3)}.{d(3)}.{d(4)}", lambda: f"{d(4)}/{d(4)}/{d(4)}/{d(4)}", lambda: f"{d(30)}", lambda: f"look at {word()} dot {word()}"]
    lead = {"card": ["card", "visa", "pay with", ""], "phone": ["call", "phone", "tel", ""], "ip": ["host", "server", ""], "email": ["mail", "write to", ""]}
    out = []
    for _ in range(n):
        parts, spans = [word() for _ in range(r.randint(2, 6))], []
        text = " ".join(parts) + " "
        for _ in range(r.randint(1, 3)):
            if r.random() < 0.5:
                kind, make = r.choice(good)
                if cue := r.choice(lead[kind]):
                    text += cue + " "
                s = make()
                spans.append((kind, len(text), len(text) + len(s)))
                text += s
            else:
                text += r.choice(bad)()
            text += r.choice([" ", " ", ", ", ". "]) + (word() + " " if r.random() < 0.7 else "")
        out.append((text, spans))
    return out


@dataclass
class Model:
    trees: Trees
    thresholds: dict[str, float]


@lru_cache(maxsize=1)
def model() -> Model:
    """Train and calibrate; the same at every call."""
    x, y, hold = [], [], []
    for i, (text, spans) in enumerate(synthetic()):
        for c in candidates(text):
            x.append(features(text, c))
            y.append(float(c in spans))
            hold.append(i % 4 == 3)
    x, y, hold = np.array(x), np.array(y), np.array(hold)
    trees = boost(x[~hold], y[~hold])
    p, kinds = trees.score(x[hold]), x[hold][:, 0]
    thresholds = {}
    for k, kind in enumerate(KINDS):
        own = kinds == k
        order = np.argsort(-p[own])
        hits, score = y[hold][own][order], p[own][order]
        precise = np.flatnonzero(np.cumsum(hits) / np.arange(1, len(hits) + 1) >= PRECISION)
        thresholds[kind] = max(0.5, float(score[precise[-1]])) if len(precise) else 1.1
    return Model(trees, thresholds)


# ---------------------------------------------------------------- detection


def all_spans(texts: list[str], m: Model) -> list[tuple[list[Span], list[Span]]]:
    """(base spans, all spans) of each text; candidates of all texts are scored at once."""
    base = [base_spans(t) for t in texts]
    which, cand, rows = [], [], []
    for i, t in enumerate(texts):
        taken = sorted((a, b) for _, a, b in base[i])
        for c in candidates(t):
            if not _touches(taken, c):
                which.append(i)
                cand.append(c)
                rows.append(features(t, c))
    extra: dict[int, list[tuple[float, Span]]] = {}
    if rows:
        for i, c, p in zip(which, cand, m.trees.score(np.array(rows)).tolist()):
            if p >= m.thresholds[c[0]]:
                extra.setdefault(i, []).append((-p, c))
    out = []
    for i, b in enumerate(base):
        spans, kept = list(b), []
        for _, c in sorted(extra.get(i, [])):
            if not _touches(kept, c):
                kept = sorted([*kept, c[1:]])
                spans.append(c)
        out.append((b, sorted(spans, key=lambda s: (KINDS.index(s[0]), s[1], s[2]))))
    return out


def _touches(spans: list[tuple[int, int]], c: Span) -> bool:
    from bisect import bisect_left

    k = bisect_left(spans, (c[2], -1))
    return any(b > c[1] for _, b in spans[max(0, k - 4) : k])


def _joined(spans: list[Span]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in spans)


def detect(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", fitted: Model | None = None) -> DataFrame:
    """Counts of base spans, their digest and all spans of every document; map-only."""
    kind = docs.schema[id_col].dataType.simpleString()
    m = fitted or model()
    names = [id_col, *(f"n_{k}" for k in KINDS), "base_sha256", "spans"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = all_spans([t.as_py() or "" for t in b.column(1)], m)
            counts = [pa.array([sum(s[0] == k for s in base) for base, _ in got], pa.int64()) for k in KINDS]
            shas = pa.array([hashlib.sha256(_joined(base).encode()).hexdigest() for base, _ in got], pa.string())
            yield pa.RecordBatch.from_arrays([b.column(0), *counts, shas, pa.array([_joined(s) for _, s in got], pa.string())], names)

    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, " + ", ".join(f"n_{k} long" for k in KINDS) + ", base_sha256 string, spans string")


def replace(text: str, spans: list[Span]) -> str:
    """The text with each (merged) span replaced by its kind in brackets."""
    out, at = [], 0
    for kind, a, b in sorted(spans, key=lambda s: (s[1], -s[2])):
        if a >= at:
            out += [text[at:a], f"[{kind.upper()}]"]
        at = max(at, b)
    return "".join(out) + text[at:]


def redact(docs: DataFrame, text_col: str = "text", length_col: str | None = None, fitted: Model | None = None) -> DataFrame:
    """All rows and columns, personal data in the text replaced; map-only."""
    m = fitted or model()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            i = b.schema.get_field_index(text_col)
            texts = b.column(i).to_pylist()
            new = [t if t is None else replace(t, spans) if spans else t for t, (_, spans) in zip(texts, all_spans([t or "" for t in texts], m))]
            cols = list(b.columns)
            cols[i] = pa.array(new, b.schema.field(i).type)
            if length_col is not None:
                j = b.schema.get_field_index(length_col)
                cols[j] = pa.array([len(n) if n is not None and n != t else c for n, t, c in zip(new, texts, cols[j].to_pylist())], b.schema.field(j).type)
            yield pa.RecordBatch.from_arrays(cols, b.schema.names)

    return docs.mapInArrow(sparing(run), docs.schema)
