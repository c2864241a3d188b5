"""Near copies: SimHash anchor points and a set join propose, exact similarity of word shingles decides.

Two texts link if the Jaccard similarity of their sets of ``words``-word shingles (64-bit
hashes, ASCII case and blanks folded) is ``least`` or more; one row of each connected
component stays. Texts with equal sets are one node from the start. Under any fixed order
of the shingles, two linked sets of ``n`` shingles share one of their first
``n - ceil(least n) + 1``, so only those are exchanged, and a pair is a candidate only if
its sizes and the places of the shared shingle still allow the similarity. The order puts
shingles that a sample of the texts shows often last, by their count; the sample decides
the order and thereby the work, never the result.

Candidates are found twice. First the SimHash operator (``simhash.links``: anchor points from
a perfect Hamming code on six views) proposes pairs of nodes whose fingerprints, of the
same shingles, differ in few bits, and every node meets the least and the greatest node of
each of its buckets; verified pairs become components. SimHash alone would miss most pairs at 0.8 to
0.9, and its pairs may be less alike than that, so neither way stands alone. Then all pairs of a bucket that lie
in different components meet, so a large group of near copies is not paired within
itself. Every candidate is verified on the whole sets, unless its sketches rule it out: a
sketch has the parity of the shingles that fall on each of 512 bits, so two sketches differ
in at most as many bits as the sets differ in shingles, and more bits than the similarity
allows shingles prove that it is not reached.

Defined results: null and empty texts and texts without words are copies of each other;
shorter texts than a shingle are one shingle. The row kept has the least id of its group
(null ids last); of repeated ids with different texts in different groups each stays, and
rows equal in id and text stay once. An empty table gives an empty table.
"""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from lattice_pages.llm import simhash
from lattice_pages.llm.components import components
from lattice_pages.session import BATCH_BYTES, bound_batches, drop_path, materialize, release, sparing  # noqa: F401

WORDS = 5
LEAST = Fraction(4, 5)
SEED = 42
#: One text in so many is read for the order; shingles seen this often in them go last.
SAMPLE = 8
OFTEN = 3
MOST_OFTEN = 100_000
#: Row keys up to this number are broadcast.
BROADCAST = 1_000_000
#: Rows of an Arrow batch: sets are longer than their texts, so its bytes alone do not bound what a task holds.
BATCH = 500
_ROW = ["_row_a", "_row_b"]
#: Whether more rows than one have the key.
_AGAIN = "_row_again"
#: 64-bit words of a sketch.
LANES = 8
_SKETCH = "struct<" + ",".join(f"b{i}:bigint" for i in range(LANES)) + ">"


def shingles(text: str | None, words: int = WORDS) -> np.ndarray:
    """The distinct shingles as sorted unsigned hashes."""
    import xxhash

    h = xxhash.xxh64_intdigest
    w = (text or "").encode("utf-8").lower().split()  # bytes: A-Z and ASCII blanks only
    if not w:
        return np.empty(0, np.uint64)
    line = b" ".join(w)
    if len(w) <= words:
        return np.array([h(line, SEED)], np.uint64)
    ends = np.cumsum(np.fromiter(map(len, w), np.int64, len(w)) + 1) - 1
    starts = [0, *(ends[:-words] + 1).tolist()]
    return np.unique(np.array([h(line[a:b], SEED) for a, b in zip(starts, ends[words - 1 :].tolist())], np.uint64))


def set_key(s: np.ndarray) -> int:
    import xxhash

    return int(np.uint64(xxhash.xxh64_intdigest(s.tobytes(), SEED)).astype(np.int64)) if len(s) else 0


def similar(a: np.ndarray, b: np.ndarray, least: Fraction = LEAST) -> bool:
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both * least.denominator >= least.numerator * (len(a) + len(b) - both)


def sketch(s: np.ndarray) -> np.ndarray:
    """The parity of the shingles on each of ``64 LANES`` bits, as signed words."""
    odd = np.bincount((s % np.uint64(64 * LANES)).astype(np.int64), minlength=64 * LANES) & 1
    return np.packbits(odd.astype(np.uint8)).view(np.int64)


def prefix(s: np.ndarray, often: np.ndarray, counts: np.ndarray, least: Fraction = LEAST) -> np.ndarray:
    """The shingles to exchange, in order: rare ones by hash, then often seen ones by count."""
    n = len(s)
    take = n + least.numerator * -n // least.denominator + 1 if n else 0
    if not take:
        return s
    rank = np.zeros(n, np.int64)
    if len(often):
        at = np.minimum(np.searchsorted(often, s), len(often) - 1)
        rank = np.where(often[at] == s, counts[at], 0)
    return s[np.lexsort((s, rank))[:take]]


# ---------------------------------------------------------------- passes over the texts


def _rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Rows with a key of 96 bits over id and text."""
    return docs.withColumn(_ROW[0], F.xxhash64(id_col, text_col)).withColumn(_ROW[1], F.hash(F.lit("row"), id_col, text_col))


def _keys(rows: DataFrame, id_col: str, text_col: str, words: int) -> DataFrame:
    kind = rows.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            node, n, bits, fp = np.empty(len(b), np.int64), np.empty(len(b), np.int32), np.empty((len(b), LANES), np.int64), np.empty(len(b), np.uint64)
            for i, t in enumerate(b.column(3)):
                s = shingles(t.as_py(), words)
                node[i], n[i], bits[i], fp[i] = set_key(s), len(s), sketch(s), simhash.bit_majority(s)
            lanes = pa.StructArray.from_arrays([pa.array(bits[:, k].copy()) for k in range(LANES)], [f"b{k}" for k in range(LANES)])
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), pa.array(node), pa.array(n), lanes, pa.array(fp.view(np.int64))], ["id", *_ROW, "node", "n", "bits", "fp"])

    return rows.select(id_col, *_ROW, text_col).mapInArrow(sparing(run), f"id {kind}, {_ROW[0]} long, {_ROW[1]} int, node long, n int, bits {_SKETCH}, fp long")


def _order(rows: DataFrame, text_col: str, words: int) -> tuple[np.ndarray, np.ndarray]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for t in b.column(0):
                yield pa.RecordBatch.from_arrays([pa.array(shingles(t.as_py(), words).view(np.int64))], ["s"])

    sample = rows.select(text_col).filter(F.pmod(F.xxhash64(text_col), F.lit(SAMPLE)) == 0).distinct()
    seen = sample.mapInArrow(sparing(run), "s long").groupBy("s").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") >= OFTEN).orderBy(F.desc("n"), "s").limit(MOST_OFTEN).toPandas()
    s, n = seen["s"].to_numpy(np.int64).view(np.uint64), seen["n"].to_numpy(np.int64)
    at = np.argsort(s)
    return s[at], n[at]


def _prefixes(rows: DataFrame, text_col: str, words: int, least: Fraction) -> DataFrame:
    shared = rows.sparkSession.sparkContext.broadcast(_order(rows, text_col, words))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        often, counts = shared.value
        for b in batches:
            parts = []
            for t in b.column(0):
                s = shingles(t.as_py(), words)
                p = prefix(s, often, counts, least)
                parts.append((p, np.full(len(p), set_key(s)), np.full(len(p), len(s), np.int32), np.arange(len(p), dtype=np.int32)))
            s, node, n, pos = (np.concatenate(x) for x in zip(*parts)) if parts else (np.empty(0, np.uint64), np.empty(0, np.int64), np.empty(0, np.int32), np.empty(0, np.int32))
            yield pa.RecordBatch.from_arrays([pa.array(s.view(np.int64)), pa.array(node), pa.array(n), pa.array(pos)], ["s", "node", "n", "pos"])

    return rows.select(text_col).mapInArrow(sparing(run), "s long, node long, n int, pos int")


def _held(df: DataFrame, n: int) -> DataFrame:
    return F.broadcast(df) if n <= BROADCAST else df


# ---------------------------------------------------------------- candidates and their check


def _possible(na: str, pa_: str, nb: str, pb: str, least: Fraction) -> str:
    """Sizes, and places of the first shared shingle, that allow the similarity."""
    p, q = least.numerator, least.denominator
    return f"least({na}, {nb}) * {q}L >= greatest({na}, {nb}) * {p}L AND least({na} - {pa_}, {nb} - {pb}) * {p + q}L >= ({na} + {nb}) * {p}L"


def _bits_allow(na: str, a: str, nb: str, b: str, least: Fraction) -> str:
    """Sketches that differ in no more bits than the similarity allows shingles."""
    p, q = least.numerator, least.denominator
    differ = " + ".join(f"bit_count({a}.b{i} ^ {b}.b{i})" for i in range(LANES))
    return f"({differ}) * {p + q}L <= ({na} + {nb}) * {q - p}L"


def _anchored(first: DataFrame) -> DataFrame:
    """Pairs ``a < b`` of nodes that span the links of the SimHash operator."""
    nodes = first.select("node", "fp")
    homes = materialize(nodes.groupBy("fp").agg(F.min("node").alias("rep")), "similar-fingerprints")
    equal = nodes.join(homes, "fp").select(F.col("rep").alias("a"), F.col("node").alias("b"))
    links = materialize(simhash.links(homes), "similar-anchored")
    for e in "ab":
        links = links.join(homes.select(F.col("fp").alias(e), F.col("rep").alias("r" + e)), e)
    near = links.select(F.least("ra", "rb").alias("a"), F.greatest("ra", "rb").alias("b"))
    return equal.unionByName(near).filter("a < b")


def _near(pairs: DataFrame, first: DataFrame, least: Fraction) -> DataFrame:
    """The pairs that sizes and sketches of their nodes leave."""
    for e in "ab":
        pairs = pairs.join(first.select(F.col("node").alias(e), F.col("n").alias("n" + e), F.col("bits").alias("bits" + e)), e)
    return pairs.filter(_bits_allow("na", "bitsa", "nb", "bitsb", least)).select("a", "b")


def _verified(pairs: DataFrame, rows: DataFrame, first: DataFrame, text_col: str, words: int, least: Fraction) -> DataFrame:
    """The pairs ``a, b`` of nodes whose whole sets are similar."""
    need = materialize(pairs.select(F.col("a").alias("node")).union(pairs.select("b")).distinct().join(first.select("node", *_ROW, _AGAIN), "node"), "similar-need")

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([shingles(t.as_py(), words).tobytes() for t in b.column(2)], pa.binary())], ["node", _AGAIN, "words"])

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ok = [similar(np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64), least) for x, y in zip(b.column(2), b.column(3))]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1)], ["a", "b"]).filter(pa.array(ok, pa.bool_()))

    n, repeats = need.agg(F.count(F.lit(1)), F.count_if(_AGAIN)).first()
    chosen = rows.select(*_ROW, text_col).join(_held(need, n), _ROW).select("node", _AGAIN, text_col)
    made = materialize(chosen.mapInArrow(sparing(sets), f"node long, {_AGAIN} boolean, words binary"), "similar-sets")
    known = made
    if repeats:  # only sets of rows that stand there again can repeat
        known = made.filter(f"NOT {_AGAIN}").union(made.filter(_AGAIN).dropDuplicates(["node"]))
    both = pairs.join(known.select(F.col("node").alias("a"), F.col("words").alias("wa")), "a").join(known.select(F.col("node").alias("b"), F.col("words").alias("wb")), "b")
    links = materialize(both.select("a", "b", "wa", "wb").mapInArrow(sparing(check), "a long, b long"), "similar-links")
    for done in (need, made, pairs):
        drop_path(rows.sparkSession, done)
    return links


@contextmanager
def _small_batches(spark: SparkSession) -> Iterator[None]:
    arrow = "spark.sql.execution.arrow.max"
    was = {k: spark.conf.get(arrow + k) for k in ("RecordsPerBatch", "BytesPerBatch")}
    spark.conf.set(arrow + "RecordsPerBatch", str(BATCH))
    bound_batches(spark)
    try:
        yield
    finally:
        for k, v in was.items():
            spark.conf.set(arrow + k, v)


def similar_components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = WORDS, least: Fraction = LEAST) -> DataFrame:
    """``id``, the row key and ``component`` of every row."""
    with _small_batches(docs.sparkSession):
        return _components(docs, id_col, text_col, words, least)


def _components(docs: DataFrame, id_col: str, text_col: str, words: int, least: Fraction) -> DataFrame:
    rows = _rows(docs, id_col, text_col)
    keys = materialize(_keys(rows, id_col, text_col, words), "similar-keys")
    known = keys.groupBy("node", *_ROW).agg(F.min("n").alias("n"), F.min("bits").alias("bits"), F.min("fp").alias("fp"), (F.count(F.lit(1)) > 1).alias(_AGAIN))
    first = materialize(known.groupBy("node").agg(F.min(F.struct(*_ROW, "n", "bits", "fp", _AGAIN)).alias("r")).select("node", "r.*"), "similar-first")
    copies = materialize(keys.select(*_ROW).distinct().join(first.select(*_ROW), _ROW, "left_anti"), "similar-copies")
    ones = rows.join(_held(copies, copies.count()), _ROW, "left_anti")
    anchored = materialize(_anchored(first), "similar-anchored-pairs")
    release(docs.sparkSession)
    bucket = Window.partitionBy("s")
    here = F.struct("node", "n", "pos")
    met = _prefixes(ones, text_col, words, least).withColumn("lo", F.min(here).over(bucket)).withColumn("hi", F.max(here).over(bucket)).filter("lo.node < hi.node")
    met = materialize(met, "similar-buckets")
    ends = [met.filter(f"{a} < {b} AND {_possible('n', 'pos', f'{end}.n', f'{end}.pos', least)}").select(F.expr(a).alias("a"), F.expr(b).alias("b")) for end, a, b in (("lo", "lo.node", "node"), ("hi", "node", "hi.node"))]
    proposed = ends[0].unionByName(ends[1]).unionByName(anchored).distinct()
    proposed = materialize(_near(proposed, first, least), "similar-pairs")
    release(docs.sparkSession)
    links = _verified(proposed, rows, first, text_col, words, least)
    part = components(links, name="similar-part")
    release(docs.sparkSession)
    left = met.select("s", "node", "n", "pos").distinct().join(part, "node", "left").select("s", "node", "n", "pos", F.coalesce("root", "node").alias("root"))
    left = left.withColumn("lo", F.min("root").over(bucket)).withColumn("hi", F.max("root").over(bucket)).filter("lo < hi").drop("lo", "hi")
    left = materialize(left.join(first.select("node", "bits"), "node"), "similar-left")
    drop_path(docs.sparkSession, met)
    release(docs.sparkSession)
    x, y = (left.select("s", *[F.col(c).alias(c + e) for c in ("node", "n", "pos", "root", "bits")]) for e in "xy")
    pairs = x.join(y, "s").filter(f"nodex < nodey AND rootx <> rooty AND {_possible('nx', 'posx', 'ny', 'posy', least)} AND {_bits_allow('nx', 'bitsx', 'ny', 'bitsy', least)}").select(F.col("nodex").alias("a"), F.col("nodey").alias("b")).distinct()
    pairs = materialize(pairs, "similar-pairs")
    drop_path(docs.sparkSession, left)
    release(docs.sparkSession)
    more = _verified(pairs, rows, first, text_col, words, least)
    drop_path(docs.sparkSession, first)
    cc = components(links.unionByName(more), name="similar-cc")
    return keys.join(cc, "node", "left").select("id", *_ROW, F.coalesce("root", "node").alias("component"))


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = WORDS, least: Fraction = LEAST) -> DataFrame:
    """One row of each component stays: the one with the least id."""
    found = similar_components(docs, id_col, text_col, words, least)
    found = found.groupBy("component", *_ROW).agg(F.min("id").alias("id"), (F.count(F.lit(1)) > 1).alias(_AGAIN))
    stay = found.groupBy("component").agg(F.min(F.struct(F.col("id").isNull().alias("none"), "id", *_ROW, _AGAIN)).alias("r")).select(*[f"r.{c}" for c in (*_ROW, _AGAIN)])
    stay = materialize(stay, "similar-stay")
    rows, n = _rows(docs, id_col, text_col), stay.count()
    if n > BROADCAST:  # the join brings equal keys together already
        kept = rows.join(stay.select(*_ROW), _ROW, "left_semi").dropDuplicates(_ROW)
        return kept.select(*docs.columns)
    once, again = (rows.join(_held(stay.filter(c).select(*_ROW), n), _ROW, "left_semi") for c in (f"NOT {_AGAIN}", _AGAIN))
    return once.union(again.dropDuplicates(_ROW)).select(*docs.columns)
