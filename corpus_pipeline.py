"""A pipeline over ``documents``: language, near copies, personal data, packing.

Each stage takes (spark, docs, sf_dir), works on all rows its predecessor kept, and its
decisions take effect. ``run`` writes each stage's rows as Parquet to shared storage and
reads them again as the next one's input.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from lattice_pages.llm import langid, packing, pii, similar
from lattice_pages.llm.queries import vocabulary
from lattice_pages.session import bound_batches, materialize, release, ship

#: SQL cannot express the stages (trained models, tokenizers): tests use brute force.
ORACLE_SQL = None


def _ready(spark: SparkSession) -> None:
    ship(spark)
    bound_batches(spark)
    release(spark)  # a stage does not begin with what the driver kept of the one before


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language the model rejects go."""
    _ready(spark)
    return langid.keep_accepted(docs, langid.fit(docs))


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays: five-word shingles, similarity 0.8.

    SimHash anchor points and a set join propose pairs; the exact similarity decides.
    """
    _ready(spark)
    return similar.keep_one(docs)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data in the texts is replaced by its kind."""
    _ready(spark)
    return pii.redact(docs, length_col="n_chars" if "n_chars" in docs.columns else None)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the documents, each with the sequence and offset it stands at."""
    _ready(spark)
    return packing.pack(docs, vocabulary("byte_bpe_50k.json"))


STAGES = [("language", language), ("near_copies", near_copies), ("personal_data", personal_data), ("packing", pack)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
