"""Contract queries of the ten operators: thin digests of what each operator returns."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, language_id, line_dedup, mixing, near_dedup, quality_rules, secret_scan, spot_signatures, suffix_dedup, toxicity
from .common import documents, written


def op9_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_dedup.near_components(spark, documents(spark, sf_dir))
    return found.select("doc_id", "n_shingles", "component_id", F.col("doc_id").eqNullSafe(F.col("component_id")).alias("kept"))


def _id_hash(n: int):
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % n


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = quality_rules.judge(spark, documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "rule")


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    held_out = F.coalesce(_id_hash(3) == 1, F.lit(False))
    model = language_id.fit(spark, docs, ~held_out)
    return language_id.identify(docs, model).select("doc_id", held_out.alias("held_out"), "lang_pred", "score", "rejected")


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = line_dedup.dedup_lines(spark, documents(spark, sf_dir))
    return found.select("doc_id", "n_lines", "n_removed", "n_runs", F.sha2(F.col("text").cast("binary"), 256).alias("kept_sha256"))


def op4_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = secret_scan.scan(spark, documents(spark, sf_dir))
    counts = [F.size(k).cast("long").alias(f"n_{k}") for k in ("assign", "access", "hex", "random")]
    return found.select("doc_id", *counts, F.sha2(secret_scan.joined("base").cast("binary"), 256).alias("base_sha256"), secret_scan.joined("all").alias("spans"), secret_scan.verdicts().alias("tested"))


def op5_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = suffix_dedup.dedup_substrings(spark, documents(spark, sf_dir))
    return found.select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    held_out = F.coalesce(_id_hash(5) == 0, F.lit(False))
    lexicon = toxicity.fit(spark, docs, spark.read.parquet(f"{sf_dir}/labels.parquet"), ~held_out)
    return toxicity.score(docs, lexicon).select("doc_id", held_out.alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op7_spot_signatures(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The contract's pairs, and ``near_id``: the least id of the documents that a chain of near fingerprints leads to."""
    d = spot_signatures.with_next(documents(spark, sf_dir)).withColumn("edited", spot_signatures.edited())
    d = d.withColumn("es", spot_signatures.fingerprint(F.col("edited")))
    d = d.select(
        "doc_id",
        F.col("n").alias("n_chars"),
        F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"),
        "s",
        spot_signatures.printed(F.col("es")).alias("edited_fingerprint"),
        spot_signatures.likeness(F.col("s"), F.col("es")).alias("near_edited"),
        spot_signatures.likeness(F.col("s"), F.col("next_s")).alias("near_next"),
    )
    d = written(spark, d.withColumns({"f1": F.xxhash64("s"), "f2": F.xxhash64(F.lit(7), F.col("s"))}), "fingerprints")
    near = spot_signatures.near_classes(spark, d)
    out = d.join(near, ["f1", "f2"]).withColumn("fingerprint", spot_signatures.printed(F.col("s")))
    return out.select("doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next", "near_id")


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(spark, documents(spark, sf_dir)).select("doc_id", "size", "source_size", "target", "taken")


def op10_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    coded = bpe.encode_decode(documents(spark, sf_dir))
    return coded.select("doc_id", "n_tokens", F.sha2("ids", 256).alias("ids_sha256"), F.sha2(F.col("decoded").cast("binary"), 256).alias("decoded_sha256"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_quality_rules": op1_quality_rules,
    "op2_language_id": op2_language_id,
    "op3_line_dedup": op3_line_dedup,
    "op4_secret_scan": op4_secret_scan,
    "op5_suffix_dedup": op5_suffix_dedup,
    "op6_toxicity": op6_toxicity,
    "op7_spot_signatures": op7_spot_signatures,
    "op8_mixing": op8_mixing,
    "op9_near_duplicates": op9_near_duplicates,
    "op10_bpe": op10_bpe,
}

ORACLE_SQL: dict[str, str] = {
    "op3_line_dedup": f"WITH {line_dedup.oracle()} SELECT doc_id, n_lines, n_removed, n_runs, sha256(kept) AS kept_sha256 FROM line_dedup",
    "op9_near_duplicates": near_dedup.oracle(),
}
