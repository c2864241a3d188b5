"""SimHash near-duplicates by anchor-point covering.

Fingerprints of 64 bits link at ``THRESHOLD`` (4) or fewer differing bits. The bits are
cut into six blocks; each of six views joins three blocks, and for every way four errors
can fall on the blocks some view holds at most one of them (checked when the module is
loaded). Within a view the anchors are the codewords of the perfect Hamming code on 31
bits (covering radius 1) times the view's spare bits. A fingerprint's home anchor is
the codeword within the radius; it is replicated to every anchor that is home to some
word within one bit of it, 16 to 18 anchors a view. So for any linked pair, one view
puts the one fingerprint at the home anchor of the other, where they are compared by
exact distance: no linked pair is missed, and there are about 2^32 anchors a view.

Within an anchor only a spanning set of true links is emitted, never all pairs. An
anchor that is home to more than ``HOME_BLOCK`` fingerprints is split: its home rows are
dealt into blocks and its visiting rows go to each block. Components are found on
distinct fingerprints, so exact copies never meet as pairs.

Defined results: null or empty texts, and texts without words, have fingerprint zero and
link like any other; repeated rows share their component; an empty table gives an empty
table; only the id and text columns are read, so other columns cannot clash. A row with
a null id takes part but never names a component unless no other row can.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lattice_pages.llm.components import components
from lattice_pages.session import materialize

THRESHOLD = 4
SHINGLE = 4
SEED = 42
HOME_BLOCK = 4096
#: Block widths, and the three blocks of each view.
BLOCKS = (11, 11, 11, 11, 10, 10)
VIEWS = ((0, 1, 2), (0, 1, 3), (0, 4, 5), (1, 4, 5), (2, 3, 4), (2, 3, 5))


def views_cover(views: tuple, blocks: int = len(BLOCKS), errors: int = THRESHOLD, within: int = 1) -> bool:
    """Whether each way to spread the errors leaves some view with at most ``within``."""
    spreads = (c for c in itertools.product(range(errors + 1), repeat=blocks) if sum(c) == errors)
    return all(any(sum(c[i] for i in v) <= within for v in views) for c in spreads)


# ---------------------------------------------------------------- fingerprints


def bit_majority(hashes: np.ndarray) -> int:
    """Bits set in over half of the unsigned 64-bit hashes."""
    n = len(hashes)
    if not n:
        return 0
    if n < 255:
        counts = np.unpackbits(hashes.astype(">u8").view(np.uint8).reshape(n, 8), axis=1).sum(axis=0, dtype=np.int64)
        set_bits = np.packbits(2 * counts > n)
        return int.from_bytes(set_bits.tobytes(), "big")
    lanes = np.zeros(-(-n // 255) * 255, np.uint64)
    lanes[:n] = hashes
    lanes = lanes.reshape(-1, 255)
    out = 0
    ones = np.uint64(0x0101010101010101)
    for shift in range(8):  # eight byte counters at once; 255 rows cannot overflow one
        sums = ((lanes >> np.uint64(shift)) & ones).sum(axis=1, dtype=np.uint64)
        counts = sums.astype("<u8").view(np.uint8).reshape(-1, 8).sum(axis=0, dtype=np.int64)
        for byte in np.flatnonzero(2 * counts > n):
            out |= 1 << (8 * int(byte) + shift)
    return out


def fingerprint(text: str | None) -> int:
    import xxhash

    h = xxhash.xxh64_intdigest
    words = (text or "").encode("utf-8").lower().split()  # bytes: A-Z and ASCII blanks only
    if not words:
        return 0
    if len(words) <= SHINGLE:
        return h(b" ".join(words), SEED)
    line = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = [0, *(ends[: -SHINGLE] + 1).tolist()]
    got = [h(line[a:b], SEED) for a, b in zip(starts, ends[SHINGLE - 1 :].tolist())]
    return bit_majority(np.array(got, np.uint64))


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id, fp``: the fingerprint as a signed long; map-only."""
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = np.array([fingerprint(t.as_py()) for t in b.column(1)], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(got)], [id_col, "fp"])

    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, fp long")


# ---------------------------------------------------------------- anchors


def _view_bits() -> list[list[int]]:
    first = np.concatenate([[0], np.cumsum(BLOCKS)])
    return [[p for i in v for p in range(first[i], first[i + 1])] for v in VIEWS]


VIEW_BITS = _view_bits()
#: For syndrome s, masks of the two flips that lead to each other codeword at distance 2.
_PAIRS = np.array([[(1 << q) | (1 << (q ^ s)) for q in range(1, 32) if q < q ^ s and q ^ s] if s else [0] * 15 for s in range(32)], np.uint64)
_CHECKS = [sum(1 << q for q in range(1, 32) if q >> j & 1) for j in range(5)]


def _anchors(fp: np.ndarray, homes_only: bool = False) -> Iterator[tuple[np.ndarray, np.ndarray, bool]]:
    """(keys, row numbers, is home) of the anchors of unsigned fingerprints."""
    rows = np.arange(len(fp))
    one = np.uint64(1)
    for v, bits in enumerate(VIEW_BITS):
        word, spare = np.zeros(len(fp), np.uint64), np.zeros(len(fp), np.uint64)
        for at, p in enumerate(bits):
            bit = (fp >> np.uint64(p)) & one
            if at < 31:
                word |= bit << np.uint64(at + 1)
            else:
                spare |= bit << np.uint64(at - 31)
        syndrome = np.zeros(len(fp), np.uint64)
        for j, mask in enumerate(_CHECKS):
            x = word & np.uint64(mask)
            for s in (32, 16, 8, 4, 2, 1):
                x ^= x >> np.uint64(s)
            syndrome |= (x & one) << np.uint64(j)
        flip = np.where(syndrome > 0, one << syndrome, np.uint64(0))
        key = lambda w, sp, v=v: (np.uint64(v) << np.uint64(40)) | (sp << np.uint64(32)) | w
        home = word ^ flip
        yield key(home, spare), rows, True
        if homes_only:
            continue
        for extra in range(len(bits) - 31):
            yield key(home, spare ^ np.uint64(1 << extra)), rows, False
        off = np.flatnonzero(syndrome)
        masks = _PAIRS[syndrome[off].astype(np.int64)]
        for k in range(15):
            yield key(word[off] ^ masks[:, k], spare[off]), rows[off], False


def _to_anchors(homes_only: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            signed = b.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
            for key, rows, home in _anchors(signed.view(np.uint64), homes_only):
                yield pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), pa.array(signed[rows]), pa.array(np.full(len(rows), home))], ["anchor", "fp", "home"])

    return run


def _distance(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.bitwise_count(a ^ b)


class _Linker:
    """Reads rows sorted by (anchor, block, home first) and finds spanning links."""

    SMALL = 16
    FLUSH = 1 << 18

    def __init__(self) -> None:
        self.parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        self.held = 0
        self.giant = None  # (group, home fps, labels) of a group larger than the buffer

    def add(self, group: np.ndarray, fp: np.ndarray, home: np.ndarray) -> np.ndarray:
        self.parts.append((group, fp, home))
        self.held += len(fp)
        return self.flush(False) if self.held >= self.FLUSH else np.empty((0, 2), np.uint64)

    def flush(self, last: bool) -> np.ndarray:
        if not self.parts:
            return np.empty((0, 2), np.uint64)
        group, fp, home = (np.concatenate(x) for x in zip(*self.parts))
        cut = len(fp) if last else int(np.argmax((group == group[-1]).all(axis=1)))
        out = []
        if cut == 0 and not last:  # the buffer is one group: keep its home rows, drop the rest once compared
            if self.giant is None or self.giant[0] != tuple(group[0]):
                self.giant = (tuple(group[0]), fp[home], np.arange(int(home.sum())))
            out.append(self._visit(fp))
            self.parts, self.held = [], 0
            return np.concatenate(out)
        if self.giant is not None:
            mine = (group[:cut] == np.array(self.giant[0])).all(axis=1)
            if mine.any():
                out.append(self._visit(fp[:cut][mine]))
            keep = np.flatnonzero(~mine)
            done = (group[:cut][keep], fp[:cut][keep], home[:cut][keep])
            if cut < len(fp) or last:
                self.giant = None
        else:
            done = (group[:cut], fp[:cut], home[:cut])
        out.append(self._groups(*done))
        self.parts = [(group[cut:], fp[cut:], home[cut:])] if cut < len(fp) else []
        self.held = len(fp) - cut
        return np.concatenate(out)

    def _groups(self, group: np.ndarray, fp: np.ndarray, home: np.ndarray) -> np.ndarray:
        n = len(fp)
        if n < 2:
            return np.empty((0, 2), np.uint64)
        starts = np.concatenate([[0], np.flatnonzero((group[1:] != group[:-1]).any(axis=1)) + 1])
        sizes = np.diff(np.concatenate([starts, [n]]))
        out = []
        small = np.repeat((sizes > 1) & (sizes <= self.SMALL), sizes)
        at = np.flatnonzero(small)
        if len(at):
            no = np.repeat(np.arange(len(starts)), sizes)
            for s in range(1, self.SMALL):
                i = at[at + s < n]
                i = i[no[i] == no[i + s]]
                if not len(i):
                    break
                i = i[home[i] & (_distance(fp[i], fp[i + s]) <= THRESHOLD)]
                out.append(np.stack([fp[i], fp[i + s]], axis=1))
        for k in np.flatnonzero(sizes > self.SMALL):
            own = slice(starts[k], starts[k] + sizes[k])
            self.giant = (None, fp[own][home[own]], np.arange(int(home[own].sum())))
            out.append(self._visit(fp[own]))
            self.giant = None
        return np.concatenate(out) if out else np.empty((0, 2), np.uint64)

    def _visit(self, fp: np.ndarray) -> np.ndarray:
        """Links of the visiting rows to the home rows: one for each local component they touch."""
        _, homes, labels = self.giant
        got: list[tuple] = []
        if not len(homes):
            return np.empty((0, 2), np.uint64)
        step = max(1, (1 << 22) // len(homes))
        for a in range(0, len(fp), step):
            part = fp[a : a + step]
            near = _distance(homes[:, None], part[None, :]) <= THRESHOLD
            for j in np.flatnonzero(near.sum(axis=0) > 0):
                hit = np.flatnonzero(near[:, j])
                roots, first = np.unique(labels[hit], return_index=True)
                got += [(part[j], homes[hit[i]]) for i in first]
                if len(roots) > 1:
                    labels[np.isin(labels, roots)] = roots[0]
        out = np.array(got, np.uint64).reshape(-1, 2)
        return out[out[:, 0] != out[:, 1]]


def _link(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    linker = _Linker()

    def batch(e: np.ndarray) -> pa.RecordBatch:
        e = np.unique(np.sort(e, axis=1), axis=0).view(np.int64)
        return pa.RecordBatch.from_arrays([pa.array(e[:, 0].copy()), pa.array(e[:, 1].copy())], ["a", "b"])

    for b in batches:
        anchor, block, fp, home = (b.column(i).to_numpy(zero_copy_only=False) for i in range(4))
        got = linker.add(np.stack([anchor, block.astype(np.int64)], axis=1), fp.astype(np.int64).view(np.uint64), home.astype(bool))
        if len(got):
            yield batch(got)
    got = linker.flush(True)
    if len(got):
        yield batch(got)


def links(nodes: DataFrame, home_block: int = HOME_BLOCK) -> DataFrame:
    """``a, b``: true links that span every component of the distinct fingerprints ``fp``."""
    homes = nodes.select("fp").mapInArrow(_to_anchors(True), "anchor long, fp long, home boolean")
    hot = materialize(homes.groupBy("anchor").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > home_block).select("anchor", F.ceil(F.col("n") / home_block).cast("int").alias("blocks")), "hot-anchors")
    rows = nodes.select("fp").mapInArrow(_to_anchors(False), "anchor long, fp long, home boolean")
    n_hot = hot.limit(100_001).count()
    if n_hot:
        rows = rows.join(F.broadcast(hot) if n_hot <= 100_000 else hot, "anchor", "left")
        own = F.pmod(F.xxhash64("fp"), F.col("blocks")).cast("int")
        every = F.sequence(F.lit(0), F.col("blocks") - 1)
        # home rows compare in their own block; every row visits all blocks
        rows = rows.withColumn("block", F.explode(F.when(F.col("blocks").isNull(), F.array(F.lit(0))).otherwise(every))).withColumn("home", F.col("home") & (F.col("blocks").isNull() | (own == F.col("block"))))
    else:
        rows = rows.withColumn("block", F.lit(0))
    rows = rows.select("anchor", "block", "fp", "home").repartition("anchor", "block").sortWithinPartitions("anchor", "block", F.desc("home"))
    return rows.mapInArrow(_link, "a long, b long").distinct()


def near_components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: its id, ``fingerprint`` (16 hex digits), ``component_id``."""
    fps = materialize(fingerprints(docs, id_col, text_col), "simhash")
    nodes = materialize(fps.groupBy("fp").agg(F.min(id_col).alias("rep")), "simhash-nodes")
    cc = components(links(nodes), name="simhash-cc")
    owner = nodes.join(cc.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "rep", F.coalesce("root", "fp").alias("root"))
    named = owner.groupBy("root").agg(F.min("rep").alias("component_id"))
    owner = owner.join(named, "root").select("fp", "component_id")
    return fps.join(owner, "fp").select(id_col, F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The documents that give their component its id: one stays of each group.

    Rows that repeat an id are copies of each other and stay once; rows without an id stay.
    """
    first = near_components(docs, id_col, text_col).filter(F.col(id_col) == F.col("component_id")).select(id_col).distinct()
    kept = docs.join(first, id_col, "left_semi").dropDuplicates([id_col])
    return kept.unionByName(docs.filter(F.col(id_col).isNull()))


if not views_cover(VIEWS):
    raise AssertionError("the views miss a spread of errors")
