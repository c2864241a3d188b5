"""The codec's SQL surface: Arrow functions on pages, and plain SQL functions that Catalyst inlines."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from lattice_pages.functions.frame import decode_page, encode_page, frame, split_frame
from lattice_pages.plans.costsql import SPARK, blen, min_scale, zz
from lattice_pages.plans.profiles import profile


@F.pandas_udf(T.LongType())
def float64_word(x: pd.Series) -> pd.Series:
    return pd.Series(np.ascontiguousarray(x.to_numpy(np.float64)).view(np.int64))


@F.pandas_udf(T.DoubleType())
def word_float64(w: pd.Series) -> pd.Series:
    return pd.Series(np.ascontiguousarray(w.to_numpy(np.int64)).view(np.float64))


@F.pandas_udf(T.BinaryType())
def lattice_encode_page(words: pd.Series, name: pd.Series, eps: pd.Series) -> pd.Series:
    def one(w, n, e):
        p = profile(n)
        return frame(*encode_page(np.asarray(w, np.int64), profile(p, eps=e) if p.bounded else p)[:2])

    return pd.Series([None if w is None else one(w, n, e) for w, n, e in zip(words, name, eps)])


@F.pandas_udf(T.ArrayType(T.LongType()))
def lattice_decode_page(data: pd.Series) -> pd.Series:
    return pd.Series([None if d is None else decode_page(*split_frame(d)) for d in data])


@F.pandas_udf(T.StructType([T.StructField("contract", T.StringType()), T.StructField("n", T.LongType()), T.StructField("lanes", T.IntegerType()), T.StructField("bytes", T.LongType())]))
def lattice_page_info(data: pd.Series) -> pd.DataFrame:
    """From the header alone: no payload is decoded."""
    from lattice_pages.functions.bits import read_varint
    from lattice_pages.functions.frame import MAGIC

    rows = []
    for d in data:
        meta, _ = split_frame(d)
        n, at = read_varint(meta, 4)
        _, at = read_varint(meta, at)
        kind = {v: k for k, v in MAGIC.items()}[meta[:2]]
        rows.append((kind, n, meta[at + (17 if kind == "bounded" else 0)] & 7, len(d)))
    return pd.DataFrame(rows, columns=["contract", "n", "lanes", "bytes"])


def register(spark: SparkSession) -> None:
    for name, f in (("float64_word", float64_word), ("word_float64", word_float64), ("lattice_encode_page", lattice_encode_page), ("lattice_decode_page", lattice_decode_page), ("lattice_page_info", lattice_page_info)):
        spark.udf.register(name, f)
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION zigzag(r BIGINT) RETURNS BIGINT RETURN {zz('r')}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION bit_len(v BIGINT) RETURNS INT RETURN {blen('v')}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION min_scale(x DOUBLE) RETURNS INT RETURN {min_scale(SPARK, 'x')}")
