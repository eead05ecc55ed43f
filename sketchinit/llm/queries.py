"""The thin queries of the ten operators; each derives the agreed digest columns from its operator's results."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from . import cotrain, langid, media, mixing, packing, secrets, simhash, sketches, suffixes, surrogates


def _documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def op1_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(_documents(spark, sf_dir), packing.public_tokenizer(), payload="crc32")


def op2_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    return cotrain.score(_documents(spark, sf_dir), labels)


def op3_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = simhash.groups(_documents(spark, sf_dir), words=3, tau=3)
    return g.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def op4_suffixes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffixes.remove_repeats(_documents(spark, sf_dir)).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")


def _joined(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def op5_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = secrets.scan(_documents(spark, sf_dir))
    count = lambda kind: F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    base = F.filter("spans", lambda s: s["kind"] != "entropy")
    return found.select("doc_id", count("assign"), count("access"), count("hex"), F.sha2(_joined(base), 256).alias("base_sha256"), _joined(F.col("spans")).alias("spans"))


def op6_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.plan(_documents(spark, sf_dir)).select("doc_id", "size", "source_size", "target", "taken", "source")


def op7_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return surrogates.replace(_documents(spark, sf_dir)).select("doc_id", "text", "n_entities", "entities")


def op8_langid(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _documents(spark, sf_dir).select("doc_id", "text", "lang")
    out = langid.predict(docs.select("doc_id", "text"), langid.fit(docs))
    held = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2
    return out.select("doc_id", held.alias("held_out"), "lang_pred", "score", "ambiguous")


def op9_sketches(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = sketches.edited_pairs(_documents(spark, sf_dir))
    return p.select(
        "doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"),
        sketches.as_text(F.col("sketch")).alias("fingerprint"), sketches.as_text(F.col("edited_sketch")).alias("edited_fingerprint"),
        sketches.jaccard(F.col("sketch"), F.col("edited_sketch")).alias("near_edited"), sketches.jaccard(F.col("sketch"), F.col("next_sketch")).alias("near_next"),
    )


def op10_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    read = media.clips(media.store(_documents(spark, sf_dir)))
    clip = F.transform("clips", lambda c: F.concat_ws("-", F.format_number(c["start_s"], 2), F.format_number(c["end_s"], 2), F.format_number(c["mean"], 3)))
    return read.select("doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", F.array_join(clip, ",").alias("feature"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    ops = (op1_packing, op2_quality, op3_simhash, op4_suffixes, op5_secrets, op6_mixing, op7_surrogates, op8_langid, op9_sketches, op10_media)
    return {f.__name__: f for f in ops} | {"pipeline": pipeline}


def oracle_sql() -> dict[str, str]:
    """No operator of this list has a SQL form; each is tested against a brute-force version."""
    return {}
