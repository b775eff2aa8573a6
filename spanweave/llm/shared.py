"""Helpers that several operators of this subpackage use."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: White space of the text contracts: blank, tab, line feed, vertical tab, form feed, carriage return.
SPACE_CLASS = r"[\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables; the path may be in any store that Spark reads."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def texts(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, text) alone, so that further columns of any name cannot clash; a null text becomes empty."""
    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))


def shared_dir(spark: SparkSession) -> str:
    """The folder that every executor sees; set here only where the session names none (tests in local mode)."""
    set_dir = spark.conf.get("spark.checkpoint.dir", None)
    if not set_dir:
        found = spark.sparkContext._jsc.sc().getCheckpointDir()
        set_dir = found.get() if found.isDefined() else None
    if not set_dir:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        set_dir = os.path.join(tempfile.gettempdir(), "spanweave-checkpoints")
        spark.sparkContext.setCheckpointDir(set_dir)
    return set_dir


def stash(df: DataFrame, partitions: int | None = None, codec: str | None = None) -> DataFrame:
    """Write `df` as Parquet in the shared folder and read it back: the lineage ends there and a lost
    executor costs nothing that was finished before. `codec` names another compression than the session's."""
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/stash-{uuid.uuid4().hex}"
    (df if partitions is None else df.coalesce(partitions)).write.parquet(path, compression=codec)
    return spark.read.schema(df.schema).parquet(path)
