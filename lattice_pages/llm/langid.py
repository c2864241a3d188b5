"""Language identification: averaged hashed subword embeddings and a linear softmax.

A text's features are its words (letter runs, lower case) and their character n-grams
with word-boundary marks, hashed into ``BUCKETS``. Their embeddings are averaged and a
linear layer with softmax gives the language. Training is plain stochastic gradient
descent in numpy on a bounded sample: at most ``PER_LANGUAGE`` rows of each label, each
a window of ``WINDOW`` characters at a hashed place. Prediction reads whole texts. As
the model is linear up to the softmax, every bucket is reduced to one score per
language, and a bounded cache holds the summed scores of each white-space chunk.

Calibration on rows kept out of the training: a temperature that minimises the log
loss, and the rejection threshold, below which lie at most ``REJECT_SHARE`` of the rows.

Defined results: a null text, or one without any letter, is ``und`` with score 0; without any
labelled row everything is ``und``; repeated rows get equal results; an empty table
gives an empty table. Only the named columns are read, so other columns cannot clash.
"""

from __future__ import annotations

import re
import sys
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from lattice_pages.session import sparing

BUCKETS = 1 << 15
DIM = 16
GRAMS = (2, 3, 4)
PER_LANGUAGE = 1000
WINDOW = 1500
REJECT_SHARE = 0.001
UNKNOWN = "und"

#: ``\w`` also takes numeric signs (fractions, superscripts, Roman-numeral characters): no letters.
_SIGNS = "".join(c for c in map(chr, range(sys.maxunicode + 1)) if c.isalnum() and not c.isalpha() and not c.isdecimal())
_LETTERS = re.compile(rf"[^\W\d_{_SIGNS}]+")


_ASCII = re.compile(r"[a-z]+")


def letters(low: str) -> list[str]:
    """The letter runs of a lower-case text."""
    return (_ASCII if low.isascii() else _LETTERS).findall(low)


def features(chunks: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of all features of the chunks, and how many each chunk has.

    A chunk is its words, marked at both ends; features are the whole and its byte
    n-grams. All chunks are hashed in one pass over one buffer.
    """
    runs = [letters(c.lower()) for c in chunks]
    units = [f"<{'><'.join(r)}>".encode() if r else b"" for r in runs]
    sizes = np.fromiter(map(len, units), np.int64, len(units))
    data = np.frombuffer(b"".join(units) + b"\0" * max(GRAMS), np.uint8).astype(np.uint64)
    n = len(data) - max(GRAMS)
    ends = np.cumsum(sizes)
    own = np.repeat(np.arange(len(units)), sizes)
    room = np.repeat(ends, sizes) - np.arange(n)
    places, at = [np.fromiter((zlib.crc32(u) % BUCKETS for u in units if u), np.int64)], [np.flatnonzero(sizes)]
    word = data[:n].copy()
    for k in range(1, max(GRAMS)):
        word |= data[k : n + k] << np.uint64(8 * k)
        if k + 1 in GRAMS:
            ok = np.flatnonzero(room > k)
            mixed = (word[ok] + np.uint64((k + 1) << 40)) * np.uint64(0x9E3779B97F4A7C15)
            places.append((mixed >> np.uint64(49)).astype(np.int64) % BUCKETS)
            at.append(own[ok])
    flat, of = np.concatenate(places), np.concatenate(at)
    order = np.argsort(of, kind="stable")
    return flat[order], np.bincount(of, minlength=len(units))


@dataclass
class Model:
    languages: list[str]
    scores: np.ndarray  # bucket -> one score per language
    bias: np.ndarray
    temperature: float
    threshold: float

    def probabilities(self, sums: np.ndarray, counts: np.ndarray) -> np.ndarray:
        z = (sums / np.maximum(counts, 1)[:, None] + self.bias) / self.temperature
        z = np.exp(z - z.max(axis=1, keepdims=True))
        return z / z.sum(axis=1, keepdims=True)


def train(rows: list[tuple[str, str]], epochs: int = 6, rate: float = 0.5, seed: int = 1, reject_share: float = REJECT_SHARE) -> Model:
    """Fit on (language, text) rows; every fifth row is for calibration only."""
    languages = sorted({lang for lang, _ in rows})
    rows = sorted((r for r in rows if _LETTERS.search(r[1])), key=lambda r: zlib.crc32(r[1].encode()))
    y = np.array([languages.index(lang) for lang, _ in rows], np.int64)
    bags = [features(text.split())[0] for _, text in rows]
    unique = [(u, (n / n.sum())[:, None]) for u, n in (np.unique(b, return_counts=True) for b in bags)]
    hold = np.arange(len(rows)) % 5 == 4
    r = np.random.default_rng(seed)
    e = (r.random((BUCKETS, DIM)) - 0.5) / DIM
    w, b = np.zeros((DIM, len(languages))), np.zeros(len(languages))
    own = np.flatnonzero(~hold)
    for epoch in range(epochs):
        lr = rate * (1 - epoch / epochs)
        for i in r.permutation(own):
            bag, share = unique[i]
            h = (e[bag] * share).sum(axis=0)
            z = np.einsum("i,ij->j", h, w) + b
            p = np.exp(z - z.max())
            p /= p.sum()
            p[y[i]] -= 1
            back = np.einsum("ij,j->i", w, p)
            w -= lr * np.outer(h, p)
            b -= lr * 0.1 * p
            e[bag] -= lr * share * back
    m = Model(languages, np.einsum("ij,jk->ik", e, w).astype(np.float32), b, 1.0, 0.0)
    at = np.flatnonzero(hold) if hold.any() else own
    if len(at):
        sums, counts = np.stack([m.scores[bags[i]].sum(axis=0, dtype=float) for i in at]), np.array([len(bags[i]) for i in at])

        def loss(t: float) -> float:
            m.temperature = t
            return -float(np.log(m.probabilities(sums, counts)[np.arange(len(at)), y[at]] + 1e-12).mean())

        m.temperature = min((0.25, 0.35, 0.5, 0.7, 1.0, 1.4, 2.0, 3.0), key=loss)
        m.threshold = float(min(0.9, np.quantile(m.probabilities(sums, counts).max(axis=1), reject_share, method="lower") * 0.95))
    return m


class Scorer:
    """Sums of bucket scores, by chunk, with a bounded cache."""

    ENTRIES = 300_000
    #: Code points of new chunks that are hashed in one pass; its arrays take many times that.
    PASS = 1 << 16

    def __init__(self, model: Model) -> None:
        self.model = model
        self.wide = len(model.languages) + 1
        self.reset()

    def reset(self) -> None:
        self.at: dict[str, int] = {}
        self.rows = np.zeros((1 << 14, self.wide))

    def learn(self, chunks: list[str]) -> None:
        """Add the sums of new chunks, in passes of bounded size."""
        first, size = 0, 0
        for i, c in enumerate(chunks):
            if size and size + len(c) > self.PASS:
                self._learn(chunks[first:i])
                first, size = i, 0
            size += len(c)
        self._learn(chunks[first:])

    def _learn(self, chunks: list[str]) -> None:
        flat, counts = features(chunks)
        n = len(self.at)
        while n + len(chunks) > len(self.rows):
            self.rows = np.concatenate([self.rows, np.zeros_like(self.rows)])
        self.at.update(zip(chunks, range(n, n + len(chunks))))
        some = np.flatnonzero(counts)
        self.rows[n + np.arange(len(chunks)), -1] = counts
        if len(some):
            starts = np.concatenate([[0], np.cumsum(counts[some])[:-1]])
            self.rows[n + some, :-1] = np.add.reduceat(self.model.scores[flat].astype(float), starts, axis=0)

    def texts(self, texts: list[str]) -> np.ndarray:
        """A row for each text: summed scores by language, then the number of features."""
        out = np.zeros((len(texts), self.wide))
        if not len(self.model.languages):
            return out
        for a in range(0, len(texts), 256):
            part = [t.split() for t in texts[a : a + 256]]
            if len(self.at) > self.ENTRIES:
                self.reset()
            new = [c for c in set().union(*part) if c not in self.at]
            if new:
                self.learn(new)
            for i, chunks in enumerate(part):
                if chunks:
                    places = np.fromiter(map(self.at.__getitem__, chunks), np.int64, len(chunks))
                    out[a + i] = self.rows.take(places, axis=0).sum(axis=0)
        return out


def sample(docs: DataFrame, where: Column, id_col: str = "doc_id", text_col: str = "text", label_col: str = "lang", per_language: int = PER_LANGUAGE) -> list[tuple[str, str]]:
    """(label, text window) of at most ``per_language`` hashed rows of each label."""
    rows = docs.filter(where & F.col(label_col).isNotNull() & F.col(text_col).isNotNull())
    n = {r[0]: r[1] for r in rows.groupBy(label_col).agg(F.count(F.lit(1))).collect()}  # one row per label
    if not n:
        return []
    draw = F.pmod(F.xxhash64(F.lit("draw"), id_col), F.lit(1_000_000))
    keep = F.lit(False)
    for label, count in sorted(n.items()):
        keep = keep | ((F.col(label_col) == label) & (draw < int(1_000_000 * min(1.0, 1.3 * per_language / count)) + 1))
    start = F.pmod(F.xxhash64(F.lit("place"), id_col), F.greatest(F.length(text_col) - WINDOW, F.lit(1))).cast("int") + 1
    rows = rows.filter(keep).select(F.col(label_col).alias("lang"), F.col(text_col).substr(start, F.lit(WINDOW)).alias("text"), draw.alias("draw"), F.col(id_col).alias("id"))
    first = Window.partitionBy("lang").orderBy("draw", "id", "text")
    rows = rows.withColumn("n", F.row_number().over(first)).filter(F.col("n") <= per_language)
    return sorted((r.lang, r.text) for r in rows.select("lang", "text").collect())


def fit(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "lang", folds: int = 5, held_out: int = 0) -> Model:
    """Train on labelled rows outside the held-out fold ``crc32(id) mod folds``."""
    fold = F.crc32(F.col(id_col).cast("string")) % folds
    return train(sample(docs, fold != held_out, id_col, text_col, label_col))


def predict(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id, lang_pred, score, accepted`` for every row; map-only, whole texts."""
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(model)
        for b in batches:
            sums = scorer.texts([t.as_py() or "" for t in b.column(1)])
            known = (sums[:, -1] > 0) & (len(model.languages) > 0)
            lang, score = np.full(len(sums), UNKNOWN, object), np.zeros(len(sums))
            if known.any():
                p = model.probabilities(sums[known, :-1], sums[known, -1])
                lang[known], score[known] = np.array(model.languages, object)[p.argmax(axis=1)], p.max(axis=1)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(lang, pa.string()), pa.array(score), pa.array(known & (score >= model.threshold))], [id_col, "lang_pred", "score", "accepted"])

    return docs.select(id_col, text_col).mapInArrow(sparing(run), f"`{id_col}` {kind}, lang_pred string, score double, accepted boolean")


def identify(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "lang") -> DataFrame:
    """``id, held_out, lang_pred, score, accepted`` by a model fitted on the labelled rows."""
    got = predict(docs, fit(docs, id_col, text_col, label_col), id_col, text_col)
    return got.select(id_col, F.coalesce(F.crc32(F.col(id_col).cast("string")) % 5 == 0, F.lit(False)).alias("held_out"), "lang_pred", "score", "accepted")


def keep_accepted(docs: DataFrame, model: Model, text_col: str = "text") -> DataFrame:
    """The rows whose language is accepted, all columns as they are; map-only."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(model)
        for b in batches:
            sums = scorer.texts([t.as_py() or "" for t in b.column(b.schema.get_field_index(text_col))])
            ok = sums[:, -1] > 0
            if len(model.languages) and ok.any():
                ok[ok] = model.probabilities(sums[ok, :-1], sums[ok, -1]).max(axis=1) >= model.threshold
            yield b.filter(pa.array(ok))

    return docs.mapInArrow(sparing(run), docs.schema)
