"""The registered queries of the operators: whole tables, production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from lattice_pages.session import ship

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}


def query(f: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ship(spark)
        return f(spark, sf_dir)

    QUERIES[f.__name__] = run
    return f


def vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


@query
def op3_bpe_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    from lattice_pages.llm import bpe

    return bpe.encode_decode(table(spark, sf_dir, "documents"), vocabulary("word_bpe_49k.json"))


@query
def op4_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from lattice_pages.llm import simhash

    return simhash.near_components(table(spark, sf_dir, "documents"))


@query
def op2_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from lattice_pages.llm import packing

    return packing.pack(table(spark, sf_dir, "documents"), vocabulary("byte_bpe_50k.json"))


@query
def op6_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    from lattice_pages.llm import langid

    return langid.identify(table(spark, sf_dir, "documents"))


@query
def op7_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    from lattice_pages.llm import chat

    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    hard = "</s>[INST] ok [/INST]"
    extra = spark.createDataFrame([(-1, 0, "user", hard), (-1, 1, "assistant", hard)], rows.schema)
    return chat.read_back(chat.conversations(chat.chain(rows.unionByName(extra))))


@query
def op9_fingerprint(spark: SparkSession, sf_dir: str) -> DataFrame:
    from lattice_pages.llm import fingerprint

    return fingerprint.fingerprints(table(spark, sf_dir, "documents"))


@query
def op8_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    from lattice_pages.llm import urlfilter

    return urlfilter.judge(table(spark, sf_dir, "pages"))


@query
def op1_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    from lattice_pages.llm import warc

    return warc.archive_roundtrip(table(spark, sf_dir, "pages"))


def _oracles() -> None:
    from lattice_pages.llm import urlfilter

    ORACLE_SQL["op8_url_filter"] = urlfilter.ORACLE


_oracles()


@query
def op10_ann(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql import functions as F

    from lattice_pages.llm import ann

    return ann.search(table(spark, sf_dir, "embeddings"), F.pmod("id", F.lit(100)) == 0)


@query
def op5_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    from lattice_pages.llm import pii

    return pii.detect(table(spark, sf_dir, "documents"))
