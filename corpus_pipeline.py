"""The corpus pipeline: each stage is one operator at work on all that the stage before it kept."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spanweave.llm import bpe, exact_dedup, mixing, quality, simhash
from spanweave.llm.queries import TARGETS, vocabulary
from spanweave.llm.shared import shared_dir, stash, table


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go. Null texts are judged as empty ones; rows are judged one by one, repeated or not; no rows give no rows."""
    return quality.keep_good(docs, table(spark, sf_dir, "labels"))


def exact_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the row with the least doc_id stays, one row if it is repeated; null texts are empty ones; an id with two texts loses neither to the other."""
    return exact_dedup.drop_exact(docs)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of documents linked by a similarity of 0.8 or more over five-word shingles, the row with the least doc_id stays; rows are told by id and text, null
    ids come last, and texts without words are alike."""
    return simhash.drop_near(docs)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, in the order in which their sources are mixed to the target weights. Files are no order: the last stage names each document's place."""
    return mixing.mixed(docs, TARGETS)


def encoding_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts, digests of ids and decoded texts, and `mix_position`, the document's place in the mix, which follows from ids and sources. Null texts have no tokens;
    rows that share an id share its first place."""
    places = mixing.schedule(docs, TARGETS).groupBy(F.col("doc_id").alias("_id")).agg(F.min("position").alias("mix_position"))
    digests = bpe.encoding_digests(docs, vocabulary())
    return digests.join(stash(places).hint("merge"), F.col("doc_id").eqNullSafe(F.col("_id")), "left").drop("_id")


STAGES = [
    ("quality classifier", quality_stage),
    ("exact dedup", exact_stage),
    ("SimHash near-dedup", near_stage),
    ("mixing sources to target weights", mixing_stage),
    ("BPE encoding and decoding", encoding_stage),
]

#: The classifier is trained and the encoder is no SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents, each written as Parquet and read again as the next one's input."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        path = f"{shared_dir(spark).rstrip('/')}/pipeline-{uuid.uuid4().hex}"
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return STAGES[-1][1](spark, docs, sf_dir)
