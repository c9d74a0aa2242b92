"""A training-data pipeline of five corpus operators, each applied to what the one before it kept.

Every stage takes (spark, docs, sf_dir); all but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relpress.llm import bpe, language_id, line_dedup, mixing, near_dedup
from relpress.llm.common import WORD, col, documents, free_name, written


def identify_languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language is recognised; the model learns from documents of the stage with a known language."""
    model = language_id.fit(spark, docs, F.lit(True))
    return language_id.accepted(docs, model)


def dedup_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts less their later copies of line runs; documents of which no word is left go."""
    found = line_dedup.dedup_lines(spark, docs).select(*[col(c) for c in docs.columns]).where(F.col("text").rlike(WORD))
    return found.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in docs.columns else found


def dedup_near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies (likeness 0.8 on five-word shingles)."""
    found = near_dedup.near_components(spark, docs, percent=80)
    name = free_name(docs, "kept_id")
    kept = found.where(F.col("doc_id").eqNullSafe(F.col("component_id"))).select(F.col("doc_id").alias(name)).distinct()
    return docs.join(kept, F.col("doc_id").eqNullSafe(F.col(name)), "left_semi")


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents repeated as often as the mix takes them; those it leaves out go."""
    taken = mixing.mix(spark, docs).groupBy(F.col("doc_id").alias("mixed_id")).agg(F.max("copies").cast("int").alias("copies")).where("copies > 0")
    row = docs.select(F.struct(*[col(c) for c in docs.columns]).alias("row"))
    both = row.join(taken, F.col("row.doc_id").eqNullSafe(F.col("mixed_id")))
    each = both.select("row", F.explode(F.sequence(F.lit(1), F.col("copies"))).alias("copy"))
    return each.select(*[F.col("row").getField(c).alias(c) for c in docs.columns])


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every document (little-endian unsigned 32-bit), with a check that they decode to its text."""
    coded = bpe.encode_decode(docs)
    return coded.select("doc_id", "n_tokens", "ids", F.sha2(F.col("decoded").cast("binary"), 256).alias("decoded_sha256"))


STAGES = [
    ("language identification", identify_languages),
    ("line deduplication", dedup_lines),
    ("near deduplication", dedup_near),
    ("source mixing", mix_sources),
    ("token encoding", encode),
]

#: Learned, iterated and seeded stages are beyond SQL; tests hold the rows against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for i, (_, stage) in enumerate(STAGES):
        docs = written(spark, stage(spark, docs, sf_dir), f"stage{i}")
    return docs
