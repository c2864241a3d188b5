"""Approximate nearest neighbours by shifted space-filling curves.

Vectors are projected by random rotations, shifted, and put in order along Hilbert
curves, one curve for each rotation and shift. The orders are made by range
partitioning in Spark; a row's position on a curve is its place within its partition
plus the rows before it, ties going to the smaller id. A query meets the rows within
``window`` positions on every curve. There it sees sketches of them (a byte a component), so
that what is exchanged for a row and curve is an eighth of the vector. The rows that the
sketches cannot tell from the nearest merge over the curves, and those that stay in
question are measured exactly, in double precision on the original vectors.

The window is one number for all curves. If none is given it is calibrated: the true
neighbours of ``CALIBRATE`` hashed rows are found by one pass over all rows, and the
window is the least that reaches the share ``TARGET`` of them on some curve. So vectors of low
intrinsic dimension get short windows; noise gets long ones, as no index can do much there
(the README has the figures). ``exact=True`` compares all rows in blocks instead.

Equal vectors form a class: one row stands for it on the curves, and its 11 smallest
ids stand for its members, which is all that any list of 10 can show. Blocks have
equal sizes by construction and positions are distinct, so no region is too dense for a
task and no block holds more than a bounded number of queries.

Defined results: vectors that are null, zero, hold null or non-finite components, or
have another length than most, and rows without an id, take no part; repeated rows
(same id and vector) count once; an empty table gives an empty table. Only the id and
vector columns are read, so other columns cannot clash.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from lattice_pages.session import materialize

CURVES = 48
AXES, BITS = 15, 4
SEED = 5
#: Least rows of a block; a block also holds four windows at least.
BLOCK = 4096
#: A sketch is off by about scale * sqrt(dim / 12); rows this many times as far apart are told apart.
MARGIN = 2.5
#: Rows whose true neighbours set the window, and the share of these it must reach.
CALIBRATE, TARGET = 256, 0.925


def hilbert(points: np.ndarray, bits: int) -> np.ndarray:
    """Positions on the Hilbert curve of integer points (rows), axes * bits <= 63."""
    x = np.ascontiguousarray(points.astype(np.uint64).T)
    n = len(x)
    top = 1 << (bits - 1)
    q = top
    while q > 1:  # undo the rotations and reflections of each level
        low = np.uint64(q - 1)
        for i in range(n):
            set_ = (x[i] & np.uint64(q)) > 0
            swap = np.where(set_, np.uint64(0), (x[0] ^ x[i]) & low)
            x[0] = np.where(set_, x[0] ^ low, x[0] ^ swap)
            x[i] ^= swap
        q >>= 1
    for i in range(1, n):  # Gray decode
        x[i] ^= x[i - 1]
    flip = np.zeros_like(x[0])
    q = top
    while q > 1:
        flip = np.where((x[n - 1] & np.uint64(q)) > 0, flip ^ np.uint64(q - 1), flip)
        q >>= 1
    x ^= flip
    key = np.zeros(x.shape[1], np.uint64)
    for level in range(bits - 1, -1, -1):
        for i in range(n):
            key = (key << np.uint64(1)) | ((x[i] >> np.uint64(level)) & np.uint64(1))
    return key.astype(np.int64)


def _orthogonal(rows: np.ndarray) -> np.ndarray:
    """The rows made orthonormal, as columns; element-wise arithmetic only."""
    out: list[np.ndarray] = []
    for v in rows:
        for _ in range(2):
            for u in out:
                v = v - (u * v).sum() * u
        out.append(v / np.sqrt((v**2).sum()))
    return np.stack(out, axis=1)


def curve_keys(vectors: np.ndarray, curve: int, center: np.ndarray, scale: np.ndarray, seed: int = SEED) -> np.ndarray:
    """Keys of vectors on one curve: rotate, put most of the range in a box, shift, index."""
    r = np.random.default_rng([seed, curve])
    dim = vectors.shape[1]
    axes = min(AXES, dim)
    turn = _orthogonal(r.normal(size=(axes, dim)))
    shift = r.random(axes)
    half = 3.5 * np.sqrt((turn**2 * (scale**2)[:, None]).sum(axis=0)) + 1e-300
    place = (np.einsum("ij,jk->ik", vectors - center, turn) / half + 1) / 2
    cells = (np.clip(place, 0, 1) + shift) / 2 * (1 << BITS)
    return hilbert(np.clip(cells, 0, (1 << BITS) - 1).astype(np.int64), BITS)


def clean(rows: DataFrame, id_col: str, vec_col: str) -> DataFrame:
    """``id, v`` (doubles as bytes), ``size`` and a 128-bit class of each usable vector; map-only."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        for b in batches:
            out = []
            for i, v in zip(b.column(0).to_pylist(), b.column(1)):
                values = v.values
                if i is None or not v.is_valid or values is None or not len(values) or values.null_count:
                    continue
                x = values.to_numpy(zero_copy_only=False).astype(np.float64) + 0.0  # -0.0 becomes 0.0
                if np.isfinite(x).all() and x.any():
                    raw = x.astype("<f8").tobytes()
                    h = xxhash.xxh3_128_intdigest(raw)
                    out.append((i, raw, len(x), (h >> 65), h & ((1 << 63) - 1)))
            cols = list(zip(*out)) or [[]] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.binary(), pa.int32(), pa.int64(), pa.int64()))], ["id", "v", "size", "c1", "c2"])

    return rows.select(F.col(id_col).cast("long"), F.col(vec_col)).mapInArrow(run, "id long, v binary, size int, c1 long, c2 long")


def _matrix(column: pa.Array, dim: int) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), "<f8").reshape(-1, dim)


def _order(reps: DataFrame, curves: int, dim: int, center: np.ndarray, scale: np.ndarray) -> DataFrame:
    """``curve, rep, pos``: every row's position on every curve."""

    def keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = _matrix(b.column(1), dim)
            for c in range(curves if len(x) else 0):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(x), c, np.int32)), pa.array(curve_keys(x, c, center, scale)), b.column(0)], ["curve", "key", "rep"])

    def number(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, seen = TaskContext.get().partitionId(), np.zeros(curves, np.int64)
        for b in batches:
            c = b.column(0).to_numpy(zero_copy_only=False)
            own = np.empty(len(c), np.int64)
            for k in np.unique(c):
                at = np.flatnonzero(c == k)
                own[at] = seen[k] + np.arange(len(at))
                seen[k] += len(at)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array(np.full(len(c), part, np.int32)), pa.array(own)], ["curve", "rep", "part", "own"])

    rows = reps.select("rep", "v").mapInArrow(keys, "curve int, key long, rep long").repartitionByRange("curve", "key", "rep").sortWithinPartitions("curve", "key", "rep")
    rows = materialize(rows.mapInArrow(number, "curve int, rep long, part int, own long"), "curves")
    sizes = rows.groupBy("curve", "part").agg(F.count(F.lit(1)).alias("n"))  # a row for each curve and partition
    before = Window.partitionBy("curve").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    base = sizes.select("curve", "part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    return rows.join(base, ["curve", "part"]).select("curve", "rep", (F.col("own") + F.col("base")).alias("pos"))


def sketch(x: np.ndarray, center: np.ndarray) -> list[bytes]:
    """A byte a component, relative to the vector's largest one, then the scale as a float."""
    y = x - center
    scale = (np.abs(y).max(axis=1) / 127 + 1e-30).astype("<f4")
    code = np.clip(np.rint(y / scale[:, None]), -128, 127).astype(np.int8).view(np.uint8)
    return [r.tobytes() for r in np.concatenate([code, scale.view(np.uint8).reshape(-1, 4)], axis=1)]


def unsketch(data: list[bytes], dim: int) -> tuple[np.ndarray, np.ndarray]:
    """(approximate rows, scales)."""
    raw = np.frombuffer(b"".join(data), np.uint8).reshape(len(data), -1)
    scale = np.ascontiguousarray(raw[:, -4:]).view("<f4").astype(np.float64)
    return raw[:, :dim].view(np.int8) * scale, scale[:, 0]


def _sketches(dim: int, center: np.ndarray):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(sketch(_matrix(b.column(1), dim), center), pa.binary())], ["rep", "x"])

    return run


def _compare(dim: int, center: np.ndarray, window: int, keep: int):
    """Rows sorted by (curve, block, queries first, pos): the rows of each query's window that may be among its ``keep`` nearest."""

    def near(group: list[tuple]) -> Iterator[pa.RecordBatch]:
        is_q, rep, pos, data = (np.concatenate(c) for c in zip(*group))
        nq = int(is_q.sum())
        if not nq or nq == len(is_q):
            return
        q = np.frombuffer(b"".join(data[:nq]), "<f8").reshape(nq, dim) - center
        rows, scale = unsketch(data[nq:].tolist(), dim)
        norms, off = np.einsum("ij,ij->i", rows, rows), MARGIN * np.sqrt(dim / 12) * scale
        ids, place = rep[nq:], pos[nq:]
        lo, hi = np.searchsorted(place, pos[:nq] - window), np.searchsorted(place, pos[:nq] + window, side="right")
        got = []
        for i in np.flatnonzero(hi > lo).tolist():
            part = slice(lo[i], hi[i])
            d = np.sqrt(np.maximum(norms[part] - 2 * np.einsum("ij,j->i", rows[part], q[i]) + (q[i] ** 2).sum(), 0))
            most = np.partition(d + off[part], keep - 1)[keep - 1] if len(d) > keep else np.inf
            k = np.flatnonzero(d - off[part] <= most)
            k = k[ids[part][k] != rep[i]]
            got.append((np.full(len(k), rep[i]), ids[part][k], d[k], off[part][k]))
        if got:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*got)], ["q", "rep", "d", "off"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []
        for b in batches:
            if not b.num_rows:
                continue
            curve, block, is_q, rep, pos = (b.column(i).to_numpy(zero_copy_only=False) for i in range(5))
            data = np.array(b.column(5).to_pylist(), object)
            cuts = [0, *(np.flatnonzero((curve[1:] != curve[:-1]) | (block[1:] != block[:-1])) + 1).tolist(), len(curve)]
            for a, z in zip(cuts, cuts[1:]):
                if (curve[a], block[a]) != now:
                    if held:
                        yield from near(held)
                    now, held = (curve[a], block[a]), []
                held.append((is_q[a:z], rep[a:z], pos[a:z], data[a:z]))
        if held:
            yield from near(held)

    return run


def _brute(asked: np.ndarray, keep: int):
    """Each asked vector's nearest rows of a task, exactly, a block of rows at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best_d, best_i = np.empty((len(asked), 0)), np.empty((len(asked), 0), np.int64)
        for b in batches:
            if not b.num_rows:
                continue
            x, ids = _matrix(b.column(1), asked.shape[1]), b.column(0).to_numpy(zero_copy_only=False)
            d = np.stack([np.sqrt(((x - v) ** 2).sum(axis=1)) for v in asked])
            best_d, best_i = np.concatenate([best_d, d], axis=1), np.concatenate([best_i, np.broadcast_to(ids, d.shape)], axis=1)
            order = np.lexsort((best_i, best_d), axis=1)[:, :keep]
            best_d, best_i = np.take_along_axis(best_d, order, 1), np.take_along_axis(best_i, order, 1)
        n = best_d.shape[1]
        yield pa.RecordBatch.from_arrays([pa.array(np.repeat(np.arange(len(asked)), n)), pa.array(best_i.ravel()), pa.array(best_d.ravel())], ["s", "rep", "d"])

    return run


def calibrate(reps: DataFrame, order: DataFrame, dim: int, k: int, sample: int = CALIBRATE, target: float = TARGET) -> int:
    """The least window that holds the share ``target`` of the sample's true neighbours on some curve."""
    chosen = reps.select("rep", "v").orderBy(F.xxhash64(F.lit("calibrate"), "rep"), "rep").limit(sample).collect()  # at most `sample` rows
    asked = np.frombuffer(b"".join(bytes(r.v) for r in chosen), "<f8").reshape(len(chosen), dim)
    parts = reps.select("rep", "v").mapInArrow(_brute(asked, k + 1), "s long, rep long, d double")
    first = Window.partitionBy("s").orderBy("d", "rep")
    true = parts.withColumn("n", F.row_number().over(first)).filter(F.col("n") <= k + 1).select("s", "rep").collect()  # sample * (k + 1) rows
    pairs = [(chosen[r.s].rep, r.rep) for r in true if chosen[r.s].rep != r.rep]
    if not pairs:
        return 1
    ids = sorted({i for p in pairs for i in p})
    wanted = order.sparkSession.createDataFrame([(i,) for i in ids], "rep long")
    spots = order.join(F.broadcast(wanted), "rep").select("curve", "rep", "pos").toPandas()  # curves * sample * (k + 1) rows
    curves = int(spots["curve"].max()) + 1
    place = np.zeros((curves, len(ids)), np.int64)
    place[spots["curve"].to_numpy(), np.searchsorted(ids, spots["rep"].to_numpy())] = spots["pos"].to_numpy()
    a, b = (np.searchsorted(ids, [p[i] for p in pairs]) for i in range(2))
    gap = np.abs(place[:, a] - place[:, b]).min(axis=0)
    return max(1, int(np.quantile(gap, target, method="higher")))


def _curve_candidates(reps: DataFrame, askers: DataFrame, dim: int, k: int, curves: int, window: int | None) -> DataFrame:
    """``q, rep``: for every asking row the rows of its windows that may be among its nearest."""
    n, (center, scale) = _moments(reps, dim)
    order = materialize(_order(reps, curves, dim, center, scale), "order")
    reach = max(k + 1, calibrate(reps, order, dim, k) if window is None else window)  # so that k rows are always found
    block = max(BLOCK, 4 * reach)
    spots = order.join(askers, "rep").select("curve", "rep", "pos", F.explode(F.sequence(F.floor(F.greatest(F.col("pos") - reach, F.lit(0)) / block), F.floor(F.least(F.col("pos") + reach, F.lit(n - 1)) / block))).alias("block"))
    spots = spots.join(reps.select("rep", F.col("v").alias("x")), "rep").select("curve", "block", F.lit(1).alias("is_q"), "rep", "pos", "x")
    short = reps.select("rep", "v").mapInArrow(_sketches(dim, center), "rep long, x binary")
    own = order.select("curve", "rep", "pos", F.floor(F.col("pos") / block).alias("block")).join(short, "rep").select("curve", "block", F.lit(0).alias("is_q"), "rep", "pos", "x")
    both = own.unionByName(spots).repartition("curve", "block").sortWithinPartitions("curve", "block", F.desc("is_q"), "pos")
    seen = both.mapInArrow(_compare(dim, center, reach, k + 1), "q long, rep long, d double, off double")
    seen = seen.repartition("q").groupBy("q", "rep").agg(F.min("d").alias("d"), F.min("off").alias("off"))
    seen = seen.withColumn("n", F.row_number().over(Window.partitionBy("q").orderBy(F.col("d") + F.col("off"), "rep")))
    most = F.max(F.when(F.col("n") <= k + 1, F.col("d") + F.col("off"))).over(Window.partitionBy("q"))
    return seen.withColumn("most", most).filter(F.col("d") - F.col("off") <= F.col("most")).select("q", "rep")


def _exact(dim: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            d = np.sqrt(((_matrix(b.column(3), dim) - _matrix(b.column(2), dim)) ** 2).sum(axis=1)) if b.num_rows else np.empty(0)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(d)], ["q", "rep", "d"])

    return run


def search(rows: DataFrame, is_query: Column, k: int = 10, id_col: str = "vec_id", vec_col: str = "embedding", curves: int = CURVES, window: int | None = None, exact: bool = False) -> DataFrame:
    """``query_id, rank, vec_id, score``: the ``k`` nearest rows found for every query row.

    ``is_query`` is a condition on the column ``id``, which holds the id of a row. A query's own
    class is always a candidate. ``exact`` takes every row as a candidate of every query.
    """
    good = materialize(clean(rows, id_col, vec_col), "vectors")
    size = good.groupBy("size").count().orderBy(F.desc("count"), "size").first()
    spark = rows.sparkSession
    if size is None:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    dim = size[0]
    good = good.filter(F.col("size") == dim).select("id", "c1", "c2", "v")
    members = Window.partitionBy("c1", "c2").orderBy("id")
    top = good.dropDuplicates(["c1", "c2", "id"])
    top = top.withColumn("n", F.row_number().over(members)).filter(F.col("n") <= k + 1)
    top = materialize(top, "members")
    reps = top.filter("n = 1").select(F.col("id").alias("rep"), "c1", "c2", "v")
    asked = good.filter(is_query).select("id", "c1", "c2").distinct()
    asked = materialize(asked.join(reps.select("rep", "c1", "c2"), ["c1", "c2"]).select(F.col("id").alias("query_id"), "rep"), "asked")
    askers = asked.select("rep").distinct()
    if exact:
        near = _all_pairs(reps, askers, dim, k)
    else:
        pairs = _curve_candidates(reps, askers, dim, k, curves, window)
        pairs = pairs.unionByName(askers.select(F.col("rep").alias("q"), "rep"))
        pairs = pairs.join(reps.select(F.col("rep").alias("q"), F.col("v").alias("vq")), "q").join(reps.select("rep", "v"), "rep")
        near = pairs.select("q", "rep", "vq", "v").mapInArrow(_exact(dim), "q long, rep long, d double")
    near = materialize(near, "near")
    found = near.join(reps.select("rep", "c1", "c2"), "rep").join(top.select("c1", "c2", F.col("id").alias("vec_id")), ["c1", "c2"])
    found = asked.join(found.select(F.col("q").alias("rep"), "vec_id", "d"), "rep").filter("vec_id <> query_id")
    ranked = found.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy("d", "vec_id"))).filter(F.col("rank") <= k)
    return ranked.select("query_id", "rank", "vec_id", F.col("d").alias("score"))


def _all_pairs(reps: DataFrame, askers: DataFrame, dim: int, k: int, block: int = 2048) -> DataFrame:
    """The exact way: every block of queries meets every block of rows."""
    at = lambda c: F.pmod(F.xxhash64(c), F.lit(max(1, -(-reps.count() // block)))).cast("int")
    spread = reps.select("rep", "v", at("rep").alias("part"))
    groups = askers.join(reps.select("rep", "v"), "rep").select(F.col("rep").alias("q"), F.col("v").alias("vq"))
    blocks = spread.select("part").distinct()
    both = groups.crossJoin(F.broadcast(blocks)).select("part", F.lit(1).alias("is_q"), F.col("q").alias("rep"), F.col("vq").alias("v"))
    both = both.unionByName(spread.select("part", F.lit(0).alias("is_q"), "rep", "v")).repartition("part").sortWithinPartitions("part", F.asc("is_q"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, ids, x = None, np.empty(0, np.int64), np.empty((0, dim))
        for b in batches:
            part, is_q, rep = (b.column(i).to_numpy(zero_copy_only=False) for i in range(3))
            v = _matrix(b.column(3), dim)
            got: list[tuple] = []
            for p in np.unique(part):
                if p != now:
                    now, ids, x = p, np.empty(0, np.int64), np.empty((0, dim))
                mine = part == p
                own = mine & (is_q == 0)
                ids, x = np.concatenate([ids, rep[own]]), np.concatenate([x, v[own]])
                for i in np.flatnonzero(mine & (is_q == 1)).tolist():
                    d = np.sqrt(((x - v[i]) ** 2).sum(axis=1))
                    o = np.lexsort((ids, d))[: k + 1]
                    got.append((np.full(len(o), rep[i]), ids[o], d[o]))
            if got:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*got)], ["q", "rep", "d"])

    first = Window.partitionBy("q").orderBy("d", "rep")
    seen = both.mapInArrow(run, "q long, rep long, d double")
    return seen.withColumn("n", F.row_number().over(first)).filter(F.col("n") <= k + 1).select("q", "rep", "d")


def _moments(reps: DataFrame, dim: int) -> tuple[int, tuple[np.ndarray, np.ndarray]]:
    """Rows, and the mean and deviation of each component, over all rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, s, s2 = 0, np.zeros(dim), np.zeros(dim)
        for b in batches:
            x = _matrix(b.column(0), dim)
            n, s, s2 = n + len(x), s + x.sum(axis=0), s2 + (x**2).sum(axis=0)
        yield pa.RecordBatch.from_arrays([pa.array([n]), pa.array([s.tolist()]), pa.array([s2.tolist()])], ["n", "s", "s2"])

    parts = reps.select("v").mapInArrow(run, "n long, s array<double>, s2 array<double>")
    sums = parts.select("n", F.posexplode(F.arrays_zip("s", "s2")).alias("i", "x")).groupBy("i").agg(F.sum("n").alias("n"), F.sum("x.s").alias("s"), F.sum("x.s2").alias("s2")).collect()  # one row a component
    n = sums[0].n
    mean = np.array([r.s for r in sorted(sums)]) / n
    dev = np.sqrt(np.maximum(np.array([r.s2 for r in sorted(sums)]) / n - mean**2, 0))
    return n, (mean, dev)
