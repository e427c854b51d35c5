"""A training-corpus pipeline of five operators; each stage is written to shared storage and read again by the next.

A document that the quality scorer rejects goes; of equal texts the smallest id
stays; of near-duplicates the smallest id stays; sources are mixed to their
targets, a document that is taken several times being there as often; texts are
encoded. Rows that repeat an id with an equal text are one document. An empty
table gives an empty result.
"""

from __future__ import annotations

import uuid

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from vtask.llm import byte_bpe, exact_dedup, mixing, near_text, quality
from vtask.llm.common import drop_folder, parts_for, settle, shared_dir, text_bytes


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality.QualityModel(docs).keep(docs)


def exact_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    src = exact_dedup.normal_texts(docs)
    owners = exact_dedup.text_owners(src, parts_for(spark, text_bytes(docs, "text"), 16 << 20))
    keys = owners.select(F.col("keep_id").alias("__id"), F.col("text_sha256").alias("__sha"))
    marked = docs.withColumn("__key", F.sha2(exact_dedup.normal_text("text").cast("binary"), 256))
    stay = marked.join(keys, (F.col("__key") == F.col("__sha")) & F.col("doc_id").eqNullSafe(F.col("__id")), "left_semi")
    one = Window.partitionBy("__key", "doc_id").orderBy("__key")
    return stay.withColumn("__n", F.row_number().over(one)).filter("__n = 1").select(*docs.columns)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Five words and a similarity of 0.8, verified: the links of op 2's trees, and those that no radius can reach."""
    return near_text.first_of_near_copies(docs)


def mix_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    cols = docs.columns
    # rows that repeat an id have different texts here
    h = F.xxhash64("text")
    tie = F.shiftleft(F.pmod(h, F.lit(1 << 16)), 33) + F.pmod(F.shiftright(h, 16), F.lit(1 << 33))
    rows = docs.select(F.struct(*cols).alias("__row"), F.col("doc_id").alias("id"), "source", mixing.word_count("text").alias("size"), tie.alias("tie"))
    plan = mixing.mix_plan(settle(rows.select("id", "source", "size", "tie")))
    taken = mixing.apply_plan(rows, plan).filter("times > 0")
    return taken.withColumn("__copy", F.explode(F.sequence(F.lit(1), F.col("times").cast("int")))).select("__row.*")


def encode_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    file = public_tokenizers.path("byte_bpe_50k.tiktoken")
    coded = byte_bpe.decode(byte_bpe.encode(docs, file, public_tokenizers.PATTERN), file)
    return coded.select("doc_id", "n_tokens", "ids", F.sha2("ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


STAGES = [
    ("quality classifier", quality_stage),
    ("exact dedup", exact_stage),
    ("SimHash near-dedup", near_stage),
    ("mixing sources to target weights", mix_stage),
    ("byte-level BPE encoding and decoding", encode_stage),
]

#: Fingerprints, seeded choices and byte-pair merges are not to be had in SQL; tests hold run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, place = spark.read.parquet(f"{sf_dir}/documents.parquet"), f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    for k, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{place}/{k}")
        docs = spark.read.parquet(f"{place}/{k}")
        if k:  # nothing reads the stage before any more
            drop_folder(spark, f"{place}/{k - 1}")
    return docs
