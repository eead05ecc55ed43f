"""A training corpus from `documents`: language ID, near-duplicates, secrets, mixing, packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; it is written
and read again before the next one. All but the last return the columns of
documents.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import wraps

from pyspark.sql import DataFrame, SparkSession, functions as F

from sketchinit.llm import langid, mixing, packing, secrets, simhash
from sketchinit.llm.memory import short_batches
from sketchinit.plans.storage import stash

Stage = Callable[[SparkSession, DataFrame, str], DataFrame]


def in_short_batches(stage: Stage) -> Stage:
    """The stage, with short batches to Python: executors and their workers stay up from one stage to the next, and keep what they once took."""

    @wraps(stage)
    def run(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        short_batches(spark)
        return stage(spark, docs, sf_dir)

    return run


@in_short_batches
def languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents without a recognised language; fills `lang` where it is null."""
    model = langid.fit(docs)
    seen = langid.predict(docs, model, prefix="_")
    kept = seen.where(F.col("_lang_pred") != "und").withColumn("lang", F.coalesce("lang", "_lang_pred"))
    return kept.select(*docs.columns)


@in_short_batches
def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document of the smallest id of each group of near-duplicates: fingerprints link texts, and an exact check and search follow (similarity of 0.8 or more)."""
    return simhash.dedup(docs)


@in_short_batches
def without_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Masks secrets in the texts; n_chars follows."""
    return secrets.redact(docs).withColumn("n_chars", F.char_length("text").cast("long")).select(*docs.columns)


@in_short_batches
def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as its source's target asks."""
    return mixing.mix(docs)


@in_short_batches
def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents with their token ids and places in sequences."""
    return packing.pack(docs, packing.public_tokenizer(), payload="ids")


STAGES = [
    ("language_id", languages),
    ("near_duplicates", near_duplicates),
    ("secret_scans", without_secrets),
    ("mixing", mixed),
    ("packing", packed),
]

#: No stage has a SQL form; each is tested against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; the last stage's rows."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = stash(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
