"""Corpus pipeline: quality rules, near-duplicates, repeated passages, mixing, tokens.

Each stage takes (spark, docs, sf_dir) and works on all that its predecessor kept; each is
written as Parquet and read again before the next. All but the last return the columns of
documents.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rasterchain.llm.common import checkpoint, ensure_checkpoint_dir
from rasterchain.llm.mixing import sampled
from rasterchain.llm.quality import measured, ruled
from rasterchain.llm.sentencepiece_codec import model_bytes, token_digests
from rasterchain.llm.simhash import simhash_groups
from rasterchain.llm.suffix_dedup import remove_repeats


def _wrapped(docs: DataFrame, *needed: str) -> DataFrame:
    """The whole row beside the columns that an operator reads, so that no other name can clash with its own."""
    return docs.select(F.struct(*[F.col(c) for c in docs.columns]).alias("_row"), *needed)


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the base rules and the fences of their language and source."""
    measures = measured(_wrapped(docs, "text", "lang", "source")).drop("text")
    return ruled(measures).where("kept").select("_row.*")


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates stays: the one with the smallest id.

    A row with a null id stays only if its whole group has none. Of rows with one id, the
    least hash of the text decides; of rows that repeat id and text, one stays.
    """
    # ordered as the groups' smallest ids are: rows without an id come last
    key = F.struct(F.col("doc_id").isNull().alias("z"), F.col("doc_id").alias("d"), F.xxhash64("text").alias("t"))
    keyed = docs.select(F.struct(*[F.col(c) for c in docs.columns]).alias("_row"), "text", key.alias("_key"))
    named = checkpoint(simhash_groups(keyed, id_col="_key").where(F.col("_key") == F.col("component_id")).groupBy(F.col("_key").alias("_of")).agg(F.count("*").alias("_n")))
    kept = keyed.join(named, F.col("_key") == F.col("_of"))
    several = kept.where("_n > 1").withColumn("_h", F.xxhash64("_row"))
    least = several.groupBy("_key").agg(F.min_by("_row", "_h").alias("_row"))
    return kept.where("_n = 1").select("_row.*").unionByName(least.select("_row.*"))


def passage_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the strings of 200 bytes that also start elsewhere; n_chars is counted anew."""
    rest = [c for c in docs.columns if c not in ("doc_id", "text", "n_chars")]
    cut = remove_repeats(docs, carry=tuple(rest)).withColumnRenamed("kept_text", "text")
    return cut.withColumn("n_chars", F.length("text").cast("long")).select(*docs.columns)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it."""
    return sampled(_wrapped(docs, "doc_id", "text", "source")).select("_row.*")


def token_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Digests of the token ids and of the decoded text of every row of the mix."""
    return token_digests(docs, model_bytes())


STAGES = [
    ("quality rules", quality_stage),
    ("SimHash near-dedup", near_duplicate_stage),
    ("suffix-array dedup", passage_stage),
    ("mixing to target weights", mixing_stage),
    ("SentencePiece encoding and decoding", token_stage),
]

#: Fingerprints and token ids have no SQL; the stages are tested against brute force.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on documents; each stage is written to the shared folder and read again.

    What a stage wrote is removed once its successor is written; what the last one reads stays, as its result is lazy.
    """
    ensure_checkpoint_dir(spark)
    base = f"{spark.sparkContext.getCheckpointDir()}/pipeline-{uuid.uuid4().hex}"
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs.write.parquet(f"{base}/{k}")
            docs = spark.read.parquet(f"{base}/{k}")
            if k:
                _removed(spark, f"{base}/{k - 1}")
    return docs


def _removed(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)
