"""Any page codec over streams: sizes, round trips, throughput."""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lattice_pages.functions import baselines
from lattice_pages.functions.bits import varint
from lattice_pages.functions.frame import decode_page, encode_page, frame, split_frame
from lattice_pages.jvm import udf
from lattice_pages.operators.codec import words_of
from lattice_pages.operators.pages import FEW_PAGES, grouped, keep_tails
from lattice_pages.plans.profiles import PAGE, Profile, profile
from lattice_pages.session import bound_batches

PAGES_DDL = "stream_id string, codec string, page_no long, n int, raw_bytes long, coded_bytes long, encode_s double, decode_s double, mismatches long, violations long, max_error double, data binary"


def page_codec(name: str | Profile, eps: float):
    """(encode, decode, bounded) of a profile, an ablation or a baseline, on one page."""
    if isinstance(name, str) and name in baselines.CODECS:
        c = baselines.get(name)
        return (lambda w: c.encode_page(w, eps)), c.decode_page, c.bounded
    p = profile(name)
    p = profile(p, eps=eps) if p.bounded else p
    return (lambda w: frame(*encode_page(w, p)[:2])), (lambda d: decode_page(*split_frame(d))), p.bounded


def run_pages(df: DataFrame, codecs: list[str | Profile], eps: float = 1e-3, page_size: int = PAGE, tail: str = "keep", keep_data: bool = False) -> DataFrame:
    """Every codec on every page of the streams: one row for each, verified in place.

    Pages are independent and self-contained for all codecs; times cover encode and decode
    alone. Input: ``stream_id, ord, value`` or ``word``.
    """
    names = [c if isinstance(c, str) else c.name for c in codecs]
    java = {i: p for i, c in enumerate(codecs) if not (isinstance(c, str) and c in baselines.CODECS) and udf.covers(p := profile(c))}
    schema = pa.schema([("stream_id", pa.string()), ("codec", pa.string()), ("page_no", pa.int64()), ("n", pa.int32()), ("raw_bytes", pa.int64()), ("coded_bytes", pa.int64()), ("encode_s", pa.float64()), ("decode_s", pa.float64()), ("mismatches", pa.int64()), ("violations", pa.int64()), ("max_error", pa.float64()), ("data", pa.binary())])

    def measure(stream: str, page_no: int, words: np.ndarray, row: dict) -> Iterator[dict]:
        x = words.view(np.float64)
        fine = np.isfinite(x)
        for i, (name, codec) in enumerate(zip(names, codecs)):
            got = {"stream_id": stream, "codec": name, "page_no": page_no, "n": len(words), "raw_bytes": 8 * len(words), "violations": 0, "max_error": 0.0}
            if i in java:
                meta, payload, _, encode_s, decode_s, different = udf.unpack(row[f"coded{i}"])
                data = frame(meta, payload) if keep_data or different else None
                if different:  # the strict reader tells by how much
                    with np.errstate(all="ignore"):
                        got["max_error"] = float(np.abs(x - decode_page(*split_frame(data)).view(np.float64))[fine].max(initial=0.0))
                yield {**got, "coded_bytes": len(varint(len(meta))) + len(meta) + len(payload), "encode_s": encode_s, "decode_s": decode_s, "mismatches": different, "data": data if keep_data else None}
                continue
            encode, decode, bounded = page_codec(codec, eps)
            t0 = time.perf_counter()
            data = encode(words)
            t1 = time.perf_counter()
            back = decode(data)
            t2 = time.perf_counter()
            with np.errstate(all="ignore"):
                error = np.abs(x - back.view(np.float64))[fine]
            bad = int((~(error <= eps)).sum() + (back[~fine] != words[~fine]).sum()) if bounded else 0
            yield {**got, "coded_bytes": len(data), "encode_s": t1 - t0, "decode_s": t2 - t1, "mismatches": int((back != words).sum()), "violations": bad, "max_error": float(error.max()) if len(error) else 0.0, "data": data if keep_data else None}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = [m for r in b.to_pylist() for m in measure(r["stream_id"], r["page_no"], np.frombuffer(r["words"], np.int64), r)]
            if out:
                yield pa.RecordBatch.from_pylist(out, schema)

    bound_batches(df.sparkSession)  # a row is a page here
    pages = cut_pages(df, page_size, tail)
    return pages.withColumns({f"coded{i}": udf.coded(df.sparkSession, "words", udf.spec(p, True)) for i, p in java.items()}).mapInArrow(run, PAGES_DDL)


def cut_pages(df: DataFrame, page_size: int = PAGE, tail: str = "keep") -> DataFrame:
    """``stream_id, page_no, words`` (binary) of the streams, after one exchange."""
    value = "word" if "word" in df.columns else "value"
    rows = grouped(keep_tails(df.select("stream_id", "ord", value), tail, page_size), page_size, FEW_PAGES)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []
        names = ["stream_id", "page_no", "words"]
        for b in batches:
            if not b.num_rows:
                continue
            stream, o, (v, valid) = b.column("stream_id").to_numpy(zero_copy_only=False), b.column("ord").to_numpy(zero_copy_only=False), words_of(b.column(value))
            if valid is not None:
                raise ValueError("comparisons take values without nulls")
            page = o // page_size
            cuts = [0, *(np.flatnonzero((stream[1:] != stream[:-1]) | (page[1:] != page[:-1])) + 1).tolist(), len(o)]
            done = []
            for a, z in zip(cuts, cuts[1:]):
                key = (stream[a], int(page[a]))
                if key != now:
                    if held:
                        done.append((*now, b"".join(held)))
                    now, held = key, []
                held.append(v[a:z].tobytes())
            if done:
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*done)], names)
        if held:
            yield pa.RecordBatch.from_arrays([pa.array([x]) for x in (*now, b"".join(held))], names)

    return rows.mapInArrow(run, "stream_id string, page_no long, words binary")


def run_settings(df: DataFrame, settings: list[tuple[int, Profile]]) -> DataFrame:
    """Exact profiles at several page sizes, verified: ``setting`` (its place), ``stream_id``, ``n``, ``raw_bytes``, ``coded_bytes``, ``mismatches`` of every page.

    Page sizes that divide a larger one share its exchange; pages are cut and coded in the JVM.
    """
    spark, out = df.sparkSession, None
    families: dict[int, list[int]] = {}
    for k in sorted(range(len(settings)), key=lambda k: -settings[k][0]):
        size = settings[k][0]
        families.setdefault(next((top for top in families if top % size == 0), size), []).append(k)
    for top, own in families.items():
        kinds = F.array(*[F.struct(F.lit(k).alias("setting"), F.lit(8 * settings[k][0]).alias("step"), udf.spec(settings[k][1], True).alias("spec")) for k in own])
        rows = cut_pages(df, top).select("stream_id", "words", F.explode(kinds).alias("s")).select("stream_id", "words", "s.*")
        rows = rows.withColumn("i", F.explode(F.expr("sequence(0, (length(words) - 1) div step)")))
        pages = rows.select("setting", "stream_id", F.expr("substring(words, cast(i * step + 1 as int), step)").alias("words"), "spec")
        coded = pages.select("setting", "stream_id", (F.length("words") / 8).cast("long").alias("n"), udf.coded(spark, "words", F.col("spec")).alias("coded"))
        number = lambda at: F.conv(F.hex(F.substring("coded", 8 * at + 1, 8)), 16, 10).cast("long")
        sizes = F.length("coded") - udf.HEAD + F.ceil(F.length(F.bin(number(10))) / 7)
        one = coded.select("setting", "stream_id", "n", (8 * F.col("n")).alias("raw_bytes"), sizes.cast("long").alias("coded_bytes"), number(2).alias("mismatches"))
        out = one if out is None else out.unionByName(one)
    return out


def decode_pages(pages: DataFrame, page_size: int = PAGE, eps: float = 1e-3) -> DataFrame:
    """``stream_id, codec, ord, word, value`` of pages that kept their data."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for r in b.to_pylist():
                w = page_codec(r["codec"], eps)[1](r["data"])
                n = len(w)
                yield pa.RecordBatch.from_arrays([pa.array([r["stream_id"]] * n), pa.array([r["codec"]] * n), pa.array(r["page_no"] * page_size + np.arange(n)), pa.array(w), pa.array(w.view(np.float64))], ["stream_id", "codec", "ord", "word", "value"])

    return pages.select("stream_id", "codec", "page_no", "data").mapInArrow(run, "stream_id string, codec string, ord long, word long, value double")


def summary(pages: DataFrame, *by: str) -> DataFrame:
    """Pooled ratio, throughput in MB of raw data a second of one core, and failures."""
    by = by or ("stream_id", "codec")
    return pages.groupBy(*by).agg(
        F.sum("n").alias("n"), F.sum("raw_bytes").alias("raw_bytes"), F.sum("coded_bytes").alias("coded_bytes"), (F.sum("raw_bytes") / F.sum("coded_bytes")).alias("ratio"),
        (F.sum("raw_bytes") / 1e6 / F.sum("encode_s")).alias("encode_mb_s"), (F.sum("raw_bytes") / 1e6 / F.sum("decode_s")).alias("decode_mb_s"),
        F.sum("mismatches").alias("mismatches"), F.sum("violations").alias("violations"), F.max("max_error").alias("max_error"),
    )
