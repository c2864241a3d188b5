"""Sequence packing as a cutting-stock problem solved by column generation.

Documents longer than a sequence are cut at every ``capacity`` tokens; the remainders
are packed. The driver sees only the histogram of remainder lengths, at most
``capacity`` rows whatever the input. Lengths are put into classes (exact up to 255,
then steps of at most 1/128 of the length, rounded up). A linear program chooses how often to use each
pattern, a multiset of classes that fits one sequence: a simplex basis holds the
current patterns, and a knapsack dynamic program over the capacity prices new ones from
the duals. The solution is rounded down and what is left (less than one sequence for each
basis column) is packed best-fit decreasing. Documents are ranked within their class,
and the ranks are dealt to the pattern slots.

Ranks come in two steps (rank within class and bucket, offset of the bucket), so a
class with any share of the rows is no single task's work.

Defined results: a null text counts as empty; every document ends with ``end_id``, so
an empty one is a piece of one token; repeated rows are packed once each; an empty table gives
an empty table. Only the id and text columns are read, so other columns cannot clash.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from lattice_pages.session import materialize, sparing

CAPACITY = 2048
#: The linear program ends when its value is within this share of a lower bound.
GAP = 0.001
#: Least pivot of the simplex, and updates of its inverse before it is computed anew.
PIVOT, REFRESH = 1e-7, 100
#: Rows of one class and bucket that are ranked together, at about this many.
BUCKET_ROWS = 50_000
#: A number of each piece, fixed when the pieces are written.
PLACE = "_place"


def pieces(docs: DataFrame, vocab_path: str, end_id: int = 1, capacity: int = CAPACITY, id_col: str = "doc_id", text_col: str = "text", keep_ids: bool = False) -> DataFrame:
    """One row per piece: id, start, length, ids_crc32, doc_tokens (and ``ids``); map-only."""
    kind = docs.schema[id_col].dataType.simpleString()
    names = [id_col, "start", "length", "ids_crc32", "doc_tokens", *["ids"] * keep_ids]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from lattice_pages.llm.byteids import ByteIds

        coder = ByteIds(vocab_path)
        end = int(end_id).to_bytes(4, "little")
        for b in batches:
            at, rows = [], []
            for i, text in enumerate(b.column(1)):
                raw = coder.ids(text.as_py() or "") + end
                n = len(raw) // 4
                for s in range(0, n, capacity):
                    part = raw[4 * s : 4 * (s + capacity)]
                    at.append(i)
                    rows.append((s, len(part) // 4, zlib.crc32(part), n, part))
            columns = [b.column(0).take(pa.array(at, pa.int64()))] + [pa.array([r[k] for r in rows], pa.int64()) for k in range(4)]
            yield pa.RecordBatch.from_arrays(columns + [pa.array([r[4] for r in rows], pa.binary())] * keep_ids, names)

    return docs.select(id_col, text_col).mapInArrow(sparing(run), f"`{id_col}` {kind}, start long, length long, ids_crc32 long, doc_tokens long" + ", ids binary" * keep_ids)


# ---------------------------------------------------------------- lengths and patterns


def class_of(length: np.ndarray) -> np.ndarray:
    """The class that holds a length: the least grid length not below it."""
    n = np.asarray(length, np.int64)
    step = np.int64(1) << np.maximum(0, np.frexp(n.astype(float))[1] - 8)
    return -(-n // step) * step


def knapsack(sizes: np.ndarray, worth: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """(best worth within each capacity, last item taken or -1), items without limit."""
    best, last = np.zeros(capacity + 1), np.full(capacity + 1, -1)
    fits = np.searchsorted(sizes, np.arange(capacity + 1), side="right")
    for w in range(1, capacity + 1):
        best[w] = best[w - 1]
        k = fits[w]
        if k:
            got = best[w - sizes[:k]] + worth[:k]
            i = int(got.argmax())
            if got[i] > best[w] + 1e-12:
                best[w], last[w] = got[i], i
    return best, last


def _taken(last: np.ndarray, sizes: np.ndarray, w: int, m: int) -> np.ndarray:
    """The item counts behind ``best[w]``."""
    column = np.zeros(m)
    while w > 0:
        if last[w] < 0:
            w -= 1
        else:
            column[last[w]] += 1
            w -= int(sizes[last[w]])
    return column


def _greedy_basis(sizes: np.ndarray, demand: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """A first basis: fill sequences from the largest size down until a size runs out, again and again.

    Column k holds no size that ran out before size k, so the matrix is triangular in that order.
    """
    m = len(sizes)
    left, x, basis = demand.copy(), np.zeros(m), np.diag((capacity // sizes).astype(float))
    open_ = np.ones(m, bool)
    while open_.any():
        column, space = np.zeros(m), capacity
        for i in np.flatnonzero(open_)[::-1].tolist():
            n = space // int(sizes[i])
            if n:
                n = min(n, max(1, int(left[i])))
                column[i], space = n, space - n * int(sizes[i])
        used = column > 0
        times = np.where(used, left / np.where(used, column, 1), np.inf)
        r = int(times.argmin())
        basis[:, r], x[r] = column, times[r]
        left = left - times[r] * column
        open_[r] = False
        open_ &= left > 1e-9  # others that ran out at once keep a column of their own, used zero times
    return basis, x


def _inverse(matrix: np.ndarray) -> np.ndarray:
    """Gauss-Jordan elimination with row pivots, in element-wise arithmetic.

    The driver's process may have started a JVM after a threaded linear-algebra library was
    used, and such a library can then hang; so nothing here calls one (``einsum`` does not).
    """
    m = len(matrix)
    work = np.concatenate([matrix, np.eye(m)], axis=1)
    for k in range(m):
        r = k + int(np.abs(work[k:, k]).argmax())
        if r != k:
            work[[k, r]] = work[[r, k]]
        work[k] /= work[k, k]
        factor = work[:, k].copy()
        factor[k] = 0
        at = np.flatnonzero(factor)
        work[at] -= factor[at, None] * work[k]
    return work[:, m:]


def column_generation(sizes: np.ndarray, demand: np.ndarray, capacity: int, gap: float = GAP, rounds: int = 600) -> tuple[np.ndarray, np.ndarray, float]:
    """Patterns (columns), how often to use each (fractional), and a lower bound on the value.

    Minimises the number of sequences that cover ``demand`` items of each size. A column
    with a negative entry is the surplus of that size and costs nothing.
    """
    m = len(sizes)
    basis, x = _greedy_basis(sizes, demand, capacity)
    inverse, cost = _inverse(basis), np.ones(m)
    bound = float((sizes * demand).sum() / capacity)
    since = 0

    def enter(column: np.ndarray, price: float) -> None:
        nonlocal x, inverse, since
        d = np.einsum("ij,j->i", inverse, column)
        ratio = np.where(d > PIVOT, x / np.where(d > PIVOT, d, 1), np.inf)
        if not np.isfinite(ratio.min()):
            return
        tied = np.flatnonzero(ratio <= ratio.min() * (1 + 1e-12) + 1e-12)
        r = int(tied[d[tied].argmax()])  # of equal ratios the firmest pivot
        step = ratio[r]
        x = np.maximum(x - step * d, 0)
        x[r] = step
        pivot = inverse[r] / d[r]
        inverse -= d[:, None] * pivot
        inverse[r] = pivot
        basis[:, r], cost[r] = column, price
        since += 1
        if since == REFRESH:  # rounding errors of the updates would add up
            inverse, since = _inverse(basis), 0
            x = np.maximum(np.einsum("ij,j->i", inverse, demand), 0)

    def duals() -> np.ndarray:
        return np.einsum("i,ij->j", cost, inverse)

    for _ in range(rounds):
        if (cost * x).sum() <= bound * (1 + gap):
            break
        y = duals()
        low = int(y.argmin())
        if y[low] < -1e-9:
            surplus = np.zeros(m)
            surplus[low] = -1
            enter(surplus, 0.0)
            continue
        best, last = knapsack(sizes, y, capacity)
        if best[capacity] <= 1 + 1e-9:
            bound = max(bound, float((cost * x).sum()))
            break
        bound = max(bound, float((y * demand).sum() / best[capacity]))
        forced = best[capacity - sizes] + y  # the best pattern that has a given item
        for i in np.argsort(-forced)[:32]:
            if forced[i] < 1 + (best[capacity] - 1) / 2:
                break
            column = _taken(last, sizes, int(capacity - sizes[i]), m)
            column[i] += 1
            if (duals() * column).sum() > 1 + 1e-7:
                enter(column, 1.0)
    return basis, x, bound


@dataclass
class Plan:
    """Slots sorted by (class, lo): ranks lo..hi-1 of a class go to these sequences."""

    klass: np.ndarray
    lo: np.ndarray
    hi: np.ndarray
    first: np.ndarray  # the sequence of rank lo
    each: np.ndarray  # ranks of this class in one sequence
    slot: np.ndarray  # the first of them stands at this slot
    sequences: int
    bound: float


def plan(counts: dict[int, int], capacity: int = CAPACITY, gap: float = GAP) -> Plan:
    """Deal ``counts`` (class -> rows) to sequences."""
    rows: list[tuple[int, int, int, int, int, int]] = []
    used = dict.fromkeys(counts, 0)
    at = 0

    def deal(pattern: list[tuple[int, int]], times: int) -> None:
        nonlocal at
        slot = 0
        for size, n in pattern:
            lo = used[size]
            hi = min(counts[size], lo + n * times)
            if hi > lo:
                rows.append((size, lo, hi, at, n, slot))
            used[size] = hi
            slot += n
        at += times

    bound = 0.0
    if counts.get(capacity):
        deal([(capacity, 1)], counts[capacity])
        bound += counts[capacity]
    sizes = np.array(sorted(s for s, n in counts.items() if n and s < capacity), np.int64)
    if len(sizes):
        demand = np.array([counts[s] for s in sizes.tolist()], float)
        basis, x, least = column_generation(sizes, demand, capacity, gap)
        bound += least
        for p in np.argsort(-x):
            times = int(x[p] + 1e-9)
            if times and basis[:, p].min() >= 0:
                deal([(int(sizes[i]), int(basis[i, p])) for i in np.flatnonzero(basis[:, p])[::-1]], times)
        room: list[list] = []  # best fit decreasing over what is left
        by_space: dict[int, list[int]] = {}
        for s in sizes[::-1].tolist():
            for _ in range(counts[s] - used[s]):
                space = next((w for w in range(s, capacity + 1) if by_space.get(w)), None)
                if space is None:
                    room.append([])
                    k, space = len(room) - 1, capacity
                else:
                    k = by_space[space].pop()
                room[k].append(s)
                by_space.setdefault(space - s, []).append(k)
        for items in room:
            deal([(s, items.count(s)) for s in sorted(set(items), reverse=True)], 1)
    rows.sort()
    cols = np.array(rows, np.int64).reshape(-1, 6).T
    return Plan(*cols, sequences=at, bound=bound)


# ---------------------------------------------------------------- assignment


def _placer(p: Plan):
    width = int(max(p.hi.max(initial=0), 1)) + 1
    starts = p.klass * width + p.lo

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            i = b.schema.get_field_index("klass")
            klass, rank = (b.column(k).to_numpy(zero_copy_only=False).astype(np.int64) for k in (i, i + 1))
            s = np.searchsorted(starts, klass * width + rank, side="right") - 1
            k = rank - p.lo[s]
            yield pa.RecordBatch.from_arrays([*b.columns[:i], pa.array(p.first[s] + k // p.each[s]), pa.array(p.slot[s] + k % p.each[s])], [*b.schema.names[:i], "sequence_id", "slot"])

    return run


def pack_pieces(parts: DataFrame, capacity: int = CAPACITY, id_col: str = "doc_id") -> DataFrame:
    """Adds ``sequence_id`` and ``offset`` to (materialized) pieces."""
    columns = parts.columns
    if PLACE not in columns:
        parts = parts.withColumn(PLACE, F.monotonically_increasing_id())
    bits = F.length(F.bin("length"))
    step = F.expr("cast(shiftleft(1L, cast(greatest(0, length(bin(length)) - 8) as int)) as bigint)")
    parts = parts.withColumn("klass", F.when(bits > 0, F.ceil(F.col("length") / step).cast("long") * step))
    counts = {r[0]: r[1] for r in parts.groupBy("klass").agg(F.count(F.lit(1))).collect()}  # at most `capacity` rows
    p = plan(counts, capacity)
    buckets = max(64, sum(counts.values()) // BUCKET_ROWS)
    parts = parts.withColumn("bucket", F.pmod(F.xxhash64(id_col, "start", "ids_crc32"), F.lit(buckets)))
    # only rows that repeat an id and text very often can fill a bucket: they are dealt by their place
    crowded = materialize(parts.groupBy("klass", "bucket").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > 4 * BUCKET_ROWS).select("klass", "bucket", F.lit(True).alias("crowded")), "crowded")
    if not crowded.isEmpty():
        spread = F.when(F.col("crowded"), F.pmod(F.xxhash64(PLACE), F.lit(buckets)) * buckets).otherwise(0)
        parts = parts.join(crowded, ["klass", "bucket"], "left").withColumn("bucket", F.col("bucket") + spread).drop("crowded")
    own = Window.partitionBy("klass", "bucket").orderBy(id_col, "start", "ids_crc32")
    ranked = parts.withColumn("own", F.row_number().over(own).cast("long") - 1)
    sizes = parts.groupBy("klass", "bucket").agg(F.count(F.lit(1)).alias("n"))
    before = Window.partitionBy("klass").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sizes.select("klass", "bucket", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    ranked = ranked.join(offsets, ["klass", "bucket"])
    fields = [c for c in columns if c != PLACE]
    placed = ranked.select(*fields, "klass", (F.col("own") + F.col("base")).alias("rank"))
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in placed.schema.fields[: len(fields)])
    placed = placed.mapInArrow(_placer(p), schema + ", sequence_id long, slot long")
    inside = Window.partitionBy("sequence_id").orderBy("slot").rowsBetween(Window.unboundedPreceding, -1)
    return placed.select(*fields, "sequence_id", F.coalesce(F.sum("length").over(inside), F.lit(0)).alias("offset"))


def pack(docs: DataFrame, vocab_path: str, end_id: int = 1, capacity: int = CAPACITY, id_col: str = "doc_id", text_col: str = "text", keep_ids: bool = False) -> DataFrame:
    """Pieces of all documents with the sequence and offset each one stands at."""
    made = pieces(docs, vocab_path, end_id, capacity, id_col, text_col, keep_ids).withColumn(PLACE, F.monotonically_increasing_id())
    return pack_pieces(materialize(made, "pieces"), capacity, id_col)


def sequences(packed: DataFrame, capacity: int = CAPACITY, pad_id: int = 0) -> DataFrame:
    """``sequence_id, ids, used``: the sequences themselves, padded unless ``used`` is a power of two.

    Needs pieces with ``ids``; a sequence holds at most ``capacity`` tokens, so groups are small.
    """
    got = packed.groupBy("sequence_id").agg(F.array_sort(F.collect_list(F.struct("offset", "ids"))).alias("p"), F.sum("length").alias("used"))
    body = F.aggregate("p", F.lit(b""), lambda acc, x: F.concat(acc, x["ids"]))
    pad = F.when(F.bit_count("used") == 1, 0).otherwise(capacity - F.col("used")).cast("int")
    fill = F.unhex(F.repeat(F.lit(int(pad_id).to_bytes(4, "little").hex()), pad))
    return got.select("sequence_id", F.concat(body, fill).alias("ids"), "used")
