"""Encode streams to page groups, decode them, store and load them.

Encoding is one exchange (rows of a page group meet) and one Arrow pass, or two around the JVM's
kernels (exact profiles on doubles); decoding and recompressing are map-only. A group's bytes depend on its values alone, so they are
the same at any parallelism.
"""

from __future__ import annotations

import itertools
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lattice_pages.functions.bits import read_varint, varint
from lattice_pages.functions.frame import MAGIC as MAGICS
from lattice_pages.functions.frame import PARTS, PageFormatError, decode_page, encode_page
from lattice_pages.jvm import udf
from lattice_pages.operators.pages import GROUP_PAGES, grouped, keep_tails
from lattice_pages.plans.profiles import PAGE, Profile, profile
from lattice_pages.session import bound_batches

GROUP_DDL = (
    "stream_id string, group_no long, profile string, n_pages int, first_ord long, n long, "
    "min_ts long, max_ts long, min_value double, max_value double, "
    "directory array<struct<page_no:long,n:int,meta:int,payload:int,min_ts:long,max_ts:long,min_value:double,max_value:double,n_special:int,n_null:int,n_nan:int,sum_value:double>>, "
    "ts binary, valid binary, payload binary, raw_bytes long, coded_bytes long, bits array<long>"
)
_DIRECTORY = pa.list_(pa.struct([("page_no", pa.int64()), ("n", pa.int32()), ("meta", pa.int32()), ("payload", pa.int32()), ("min_ts", pa.int64()), ("max_ts", pa.int64()), ("min_value", pa.float64()), ("max_value", pa.float64()), ("n_special", pa.int32()), ("n_null", pa.int32()), ("n_nan", pa.int32()), ("sum_value", pa.float64())]))
_GROUP = pa.schema([("stream_id", pa.string()), ("group_no", pa.int64()), ("profile", pa.string()), ("n_pages", pa.int32()), ("first_ord", pa.int64()), ("n", pa.int64()), ("min_ts", pa.int64()), ("max_ts", pa.int64()), ("min_value", pa.float64()), ("max_value", pa.float64()), ("directory", _DIRECTORY), ("ts", pa.binary()), ("valid", pa.binary()), ("payload", pa.binary()), ("raw_bytes", pa.int64()), ("coded_bytes", pa.int64()), ("bits", pa.list_(pa.int64()))])
MAGIC = b"LG"


def _zstd(data: bytes, level: int) -> bytes:
    return bytes(pa.Codec("zstd", compression_level=level).compress(data, asbytes=True))


def pack_group(pages: list[tuple[bytes, bytes]], p: Profile) -> bytes:
    """Magic, directory and pages; metadata compressed together, or everything for the dense profile."""
    head = MAGIC + bytes([int(p.upper)]) + varint(len(pages))
    for meta, payload in pages:
        head += varint(len(meta)) + varint(len(payload))
    metas, bodies = b"".join(m for m, _ in pages), b"".join(b for _, b in pages)
    packed = metas + bodies if p.upper else metas
    z = _zstd(packed, p.zstd)
    return head + varint(len(packed)) + varint(len(z)) + z + (b"" if p.upper else bodies)


def unpack_group(data: bytes, wanted: set[int] | None = None) -> list[tuple[bytes, bytes] | None]:
    """(meta, payload) of each page; pages outside ``wanted`` are None and not copied."""
    try:
        if data[:2] != MAGIC:
            raise PageFormatError("not a page group")
        upper = data[2]
        n, at = read_varint(data, 3)
        sizes = []
        for _ in range(n):
            m, at = read_varint(data, at)
            b, at = read_varint(data, at)
            sizes.append((m, b))
        full, at = read_varint(data, at)
        size, at = read_varint(data, at)
        packed = bytes(pa.Codec("zstd").decompress(data[at : at + size], full, asbytes=True))
    except PageFormatError:
        raise
    except (ValueError, IndexError, OSError, pa.ArrowException) as e:
        raise PageFormatError(str(e)) from e
    n_meta = sum(m for m, _ in sizes)
    body = packed[n_meta:] if upper else data[at + size :]
    if len(packed) < n_meta or sum(b for _, b in sizes) != len(body):
        raise PageFormatError("the directory does not add up")
    out, i, j = [], 0, 0
    for k, (m, b) in enumerate(sizes):
        out.append((packed[i : i + m], body[j : j + b]) if wanted is None or k in wanted else None)
        i, j = i + m, j + b
    return out


def _pack_ts(ts: np.ndarray | None) -> bytes | None:
    if ts is None:
        return None
    return varint(len(ts)) + _zstd(np.diff(ts, prepend=0).astype("<i8").tobytes(), 3)


def unpack_ts(data: bytes | None, n: int) -> np.ndarray | None:
    if data is None:
        return None
    k, at = read_varint(data, 0)
    return np.cumsum(np.frombuffer(pa.Codec("zstd").decompress(data[at:], 8 * k, asbytes=True), "<i8"))


def words_of(column: pa.Array, domain: str = "binary64") -> tuple[np.ndarray, np.ndarray | None]:
    """(words, validity or None): the bits of a column. A null has the word before it, which costs little."""
    valid = None
    if column.null_count:
        valid = column.is_valid().to_numpy(zero_copy_only=False)
        column = column.fill_null(0)
    v = np.ascontiguousarray(column.to_numpy(zero_copy_only=False))
    if v.dtype == np.float32:
        v = v.view(np.uint32).astype(np.int64) if domain == "binary32" else v.astype(np.float64)
    elif domain == "integer" or v.dtype == np.int64:
        v = v.astype(np.int64)
    elif domain == "binary32":
        v = v.astype(np.float32).view(np.uint32).astype(np.int64)
    return v.view(np.int64), valid


def carried(words: np.ndarray, valid: np.ndarray | None) -> np.ndarray:
    """Words with each null replaced by the valid word before it (zero before the first)."""
    if valid is None or valid.all():
        return words
    at = np.maximum.accumulate(np.where(valid, np.arange(len(words)), -1))
    return np.where(at >= 0, words[np.maximum(at, 0)], 0)


def encode_group(stream: str, group_no: int, first_ord: int, words: np.ndarray, ts: np.ndarray | None, p: Profile, page_size: int, valid: np.ndarray | None = None, coded: list[bytes] | None = None) -> dict:
    """One group row; ``coded``: its pages as the JVM made them."""
    pages, directory, parts = [], [], np.zeros(len(PARTS), np.int64)
    valid = None if valid is None or valid.all() else valid
    words = carried(words, valid)
    x = p.values(words)
    for a in range(0, len(words), page_size):
        w, v = words[a : a + page_size], x[a : a + page_size]
        if coded is None:
            meta, payload, bits = encode_page(w, p)
        else:
            meta, payload, own = udf.unpack(coded[a // page_size])[:3]
            bits = dict(zip(PARTS, own.tolist()))
        v = v if valid is None else v[valid[a : a + page_size]]
        fine = v[~np.isnan(v)]  # statistics are over numbers, infinities among them
        total = math.fsum(fine) if np.isfinite(fine).all() else float(fine.sum())
        t = ts[a : a + page_size] if ts is not None else None
        directory.append({"page_no": (first_ord + a) // page_size, "n": len(w), "meta": len(meta), "payload": len(payload), "min_ts": None if t is None else int(t.min()), "max_ts": None if t is None else int(t.max()), "min_value": float(fine.min()) if len(fine) else None, "max_value": float(fine.max()) if len(fine) else None, "n_special": int((~np.isfinite(v)).sum()), "n_null": len(w) - len(v), "n_nan": len(v) - len(fine), "sum_value": total if len(fine) else None})
        pages.append((meta, payload))
        parts += [bits[k] for k in PARTS]
    data = pack_group(pages, p)
    low = [d["min_value"] for d in directory if d["min_value"] is not None]
    high = [d["max_value"] for d in directory if d["max_value"] is not None]
    return {"stream_id": stream, "group_no": group_no, "profile": p.name, "n_pages": len(pages), "first_ord": first_ord, "n": len(words), "min_ts": None if ts is None else int(ts.min()), "max_ts": None if ts is None else int(ts.max()), "min_value": min(low, default=None), "max_value": max(high, default=None), "directory": directory, "ts": _pack_ts(ts), "valid": None if valid is None else np.packbits(valid).tobytes(), "payload": data, "raw_bytes": p.word_bytes * len(words), "coded_bytes": len(data) + (0 if valid is None else -(-len(words) // 8)), "bits": parts.tolist()}


def encode(df: DataFrame, profile_name: str | Profile = "exact_fast", eps: float | None = None, page_size: int = PAGE, group_pages: int = GROUP_PAGES, tail: str = "keep", **overrides) -> DataFrame:
    """Group rows of the streams in ``df`` (``stream_id, ord, value`` [, ``word``] [, ``ts``]).

    A ``float`` column makes binary32 pages unless a domain is given. Nulls of the value are kept by
    validity bits beside the pages; a null ordinal, or a null in a given ``ts``, is refused.
    """
    value = "word" if "word" in df.columns else "value"
    if df.schema[value].dataType.simpleString() == "float":
        overrides.setdefault("domain", "binary32")
    p = profile(profile_name, eps, **overrides)
    cols = ["stream_id", "ord", value, *["ts"] * ("ts" in df.columns)]
    rows = grouped(keep_tails(df.select(*cols), tail, page_size), page_size, group_pages)

    def runs(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
        """(stream, group, first ordinal, words, times or None, validity) of every group."""
        held: list[tuple] = []
        now = None

        def done() -> tuple:
            o, v = np.concatenate([h[0] for h in held]), np.concatenate([h[1] for h in held])
            if (np.diff(o) != 1).any():
                raise ValueError(f"ordinals of {now} are not dense")
            t = np.concatenate([h[3] for h in held]) if len(held[0]) > 3 else None
            return now[0], now[1], int(o[0]), v, t, np.concatenate([h[2] for h in held])

        for b in batches:
            if not b.num_rows:
                continue
            cells = {n: b.column(n) for n in b.schema.names}
            stream, group = cells["stream_id"].to_numpy(zero_copy_only=False), cells["group_no"].to_numpy(zero_copy_only=False)
            if cells["ord"].null_count or ("ts" in cells and cells["ts"].null_count):
                raise ValueError("ordinals and given times must not be null")
            words, valid = words_of(cells[value], p.domain)
            data = [cells["ord"].to_numpy(zero_copy_only=False), words, np.ones(len(words), bool) if valid is None else valid, *([cells["ts"].to_numpy(zero_copy_only=False)] if "ts" in cells else [])]
            cuts = [0, *(np.flatnonzero((stream[1:] != stream[:-1]) | (group[1:] != group[:-1])) + 1).tolist(), len(stream)]
            for a, z in zip(cuts, cuts[1:]):
                if (stream[a], group[a]) != now:
                    if held:
                        yield done()
                    held, now = [], (stream[a], int(group[a]))
                held.append(tuple(d[a:z] for d in data))
        if held:
            yield done()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for stream, group, first, words, ts, valid in runs(batches):
            yield pa.RecordBatch.from_pylist([encode_group(stream, group, first, words, ts, p, page_size, valid)], _GROUP)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for stream, group, first, words, ts, valid in runs(batches):
            words = carried(words, valid)
            pages = range(0, len(words), page_size)
            split = lambda a: [None if a is None else a[i : i + page_size].tobytes() for i in pages]
            columns = [[stream] * len(pages), [group] * len(pages), [first] * len(pages), split(words), split(ts), split(valid)]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (pa.string(), pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.binary()))], ["stream_id", "group_no", "first_ord", "words", "ts", "valid"])

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = (r for b in batches for r in b.to_pylist())
        for (stream, group, first), pages in itertools.groupby(rows, key=lambda r: (r["stream_id"], r["group_no"], r["first_ord"])):
            pages = list(pages)
            whole = lambda name, kind: None if pages[0][name] is None else np.frombuffer(b"".join(r[name] for r in pages), kind)  # noqa: B023, E731
            yield pa.RecordBatch.from_pylist([encode_group(stream, group, first, whole("words", np.int64), whole("ts", np.int64), p, page_size, whole("valid", bool), [r["coded"] for r in pages])], _GROUP)

    if not udf.covers(p):
        return rows.mapInArrow(run, GROUP_DDL)
    bound_batches(df.sparkSession)  # a row is a page here
    pages = rows.mapInArrow(cut, "stream_id string, group_no long, first_ord long, words binary, ts binary, valid binary")
    return pages.withColumn("coded", udf.coded(df.sparkSession, "words", udf.spec(p))).mapInArrow(gather, GROUP_DDL)


ROW_DDL = "stream_id string, ord long, ts long, word long, value double"
#: What a decoder reads of a group.
NEEDED = ("stream_id", "first_ord", "n", "profile", "directory", "ts", "valid", "payload")


def _values(words: np.ndarray, meta: bytes) -> np.ndarray:
    kind = bytes(meta[:2])
    if kind == MAGICS["exact_integer"]:
        return words.astype(np.float64)
    return words.astype(np.uint32).view(np.float32).astype(np.float64) if kind in (MAGICS["exact32"], MAGICS["bounded32"]) else words.view(np.float64)


def decoder(keep=None, contract: str | None = None, on_corrupt: str = "fail"):
    """An Arrow function from group rows to value rows; ``keep(page)`` prunes pages by their directory entry.

    ``on_corrupt``: 'fail', 'skip' (bad pages are left out) or 'report' (a bad page gives one row,
    its first ordinal, without value and with the ``error``).
    """
    names = ["stream_id", "ord", "ts", "word", "value", *["error"] * (on_corrupt == "report")]

    def bad(g: dict, starts: np.ndarray, pages: list[int], error: str) -> Iterator[pa.RecordBatch]:
        if on_corrupt == "report" and pages:
            k = len(pages)
            yield pa.RecordBatch.from_arrays([pa.array([g["stream_id"]] * k), pa.array([int(g["first_ord"] + starts[i]) for i in pages], pa.int64()), pa.nulls(k, pa.int64()), pa.nulls(k, pa.int64()), pa.nulls(k, pa.float64()), pa.array([error] * k)], names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for g in b.to_pylist():
                hit = {i for i, d in enumerate(g["directory"]) if keep is None or keep(d)}
                if not hit:
                    continue
                starts = np.cumsum([0, *(d["n"] for d in g["directory"])])
                ts = unpack_ts(g["ts"], g["n"])
                valid = None if g["valid"] is None else np.unpackbits(np.frombuffer(g["valid"], np.uint8), count=g["n"]).astype(bool)
                try:
                    pages = unpack_group(g["payload"], hit)
                    if len(pages) != len(g["directory"]):
                        raise PageFormatError("the group and its directory disagree")
                except PageFormatError as e:
                    if on_corrupt == "fail":
                        raise
                    yield from bad(g, starts, sorted(hit), str(e))
                    continue
                for i, page in enumerate(pages):
                    if page is None:
                        continue
                    try:
                        w = decode_page(*page, contract)
                        if len(w) != g["directory"][i]["n"]:
                            raise PageFormatError("the page and its directory disagree")
                    except PageFormatError as e:
                        if on_corrupt == "fail":
                            raise
                        yield from bad(g, starts, [i], str(e))
                        continue
                    o = g["first_ord"] + starts[i] + np.arange(len(w))
                    t = pa.nulls(len(w), pa.int64()) if ts is None else pa.array(ts[starts[i] : starts[i + 1]])
                    gone = None if valid is None else ~valid[starts[i] : starts[i + 1]]
                    columns = [pa.array([g["stream_id"]] * len(w)), pa.array(o), t, pa.array(w, mask=gone), pa.array(_values(w, page[0]), mask=gone, from_pandas=False)]
                    yield pa.RecordBatch.from_arrays(columns + [pa.nulls(len(w), pa.string())] * (on_corrupt == "report"), names)

    return run


def decode(enc: DataFrame, on_corrupt: str = "fail", contract: str | None = None) -> DataFrame:
    """Value rows of group rows; map-only. ``on_corrupt``: 'fail', 'skip' or 'report' (adds ``error``)."""
    if on_corrupt not in ("fail", "skip", "report"):
        raise ValueError("on_corrupt is 'fail', 'skip' or 'report'")
    return enc.select(*NEEDED).mapInArrow(decoder(contract=contract, on_corrupt=on_corrupt), ROW_DDL + ", error string" * (on_corrupt == "report"))


#: Column types that are integers on the inside: how to get the integer, and how to get the value back.
def to_words(df: DataFrame, col: str = "value") -> DataFrame:
    """``word`` from an integer, decimal (18 digits), date, timestamp or boolean column ``col``, for the domain ``integer``."""
    kind, c = df.schema[col].dataType, F.col(col)
    name = kind.typeName()
    if name == "decimal":
        if kind.precision > 18:
            raise ValueError("decimals of more than 18 digits are no 64-bit integers")
        word = (c.cast("decimal(38,18)") * F.lit(10**kind.scale)).cast("decimal(38,0)").cast("long") if kind.scale == 0 else F.regexp_replace(c.cast("string"), r"\.", "").cast("long")
    elif name == "date":
        word = F.unix_date(c).cast("long")
    elif name == "timestamp":
        word = F.unix_micros(c)
    elif name == "timestamp_ntz":
        word = F.expr(f"timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', `{col}`)")
    elif name in ("byte", "short", "integer", "long", "boolean"):
        word = c.cast("long")
    else:
        raise ValueError(f"{name} is no integer type")
    return df.withColumn("word", word).drop(col)


def from_words(df: DataFrame, kind: str, col: str = "value") -> DataFrame:
    """The column that ``to_words`` took: ``kind`` is its type, as in DDL."""
    w = F.col("word")
    if kind.startswith("decimal"):
        scale = int(kind.rstrip(")").split(",")[1]) if "," in kind else 0
        value = F.expr(f"cast(cast(word as decimal(20,0)) * cast('{10.0 ** -scale:.{scale}f}' as decimal({max(scale, 1)},{scale})) as {kind})") if scale else w.cast(kind)
    elif kind == "date":
        value = F.date_from_unix_date(w.cast("int"))
    elif kind == "timestamp":
        value = F.timestamp_micros(w)
    elif kind == "timestamp_ntz":
        value = F.expr("timestampadd(MICROSECOND, word, timestamp_ntz'1970-01-01 00:00:00')")
    else:
        value = w.cast(kind)
    return df.drop(col).withColumn(col, value)


def recompress(enc: DataFrame, profile_name: str | Profile = "exact_upper", **overrides) -> DataFrame:
    """Decode and encode each group again, in place: no exchange, groups stay what they are."""
    p = profile(profile_name, None, **overrides)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for g in b.to_pylist():
                words = np.concatenate([decode_page(*x) for x in unpack_group(g["payload"])])
                size = max(d["n"] for d in g["directory"])
                valid = None if g["valid"] is None else np.unpackbits(np.frombuffer(g["valid"], np.uint8), count=g["n"]).astype(bool)
                yield pa.RecordBatch.from_pylist([encode_group(g["stream_id"], g["group_no"], g["first_ord"], words, unpack_ts(g["ts"], g["n"]), p, size, valid)], _GROUP)

    return enc.mapInArrow(run, GROUP_DDL)


def page_info(enc: DataFrame) -> DataFrame:
    """One row per page from the directory alone: nothing is decoded."""
    return enc.select("stream_id", "group_no", "profile", F.explode("directory").alias("d")).select("stream_id", "group_no", "profile", "d.*")


def save(enc: DataFrame, path: str, mode: str = "errorifexists") -> None:
    """Store group rows; the payload is not compressed a second time, so file sizes are honest."""
    enc.write.mode(mode).option("compression", "none").parquet(path)


def load(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(GROUP_DDL).parquet(path)
