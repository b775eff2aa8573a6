"""Materialised frames: where iterations cut their lineage."""

from __future__ import annotations

import os
import tempfile
import uuid
import weakref

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors see, as the session names it; set here only where it names none (local mode)."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        found = spark.sparkContext._jsc.sc().getCheckpointDir()
        named = found.get() if found.isDefined() else None
    if not named:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        named = os.path.join(tempfile.gettempdir(), "spanweave-checkpoints")
        spark.sparkContext.setCheckpointDir(named)
    return named.rstrip("/")


#: Bytes of a row group: what one task wrote is read by many.
ROW_GROUP = 8 << 20


def stash(df: DataFrame) -> DataFrame:
    """`df`, written as Parquet to the shared folder and read back: later rounds restart from there, not from the input."""
    path = f"{shared_dir(df.sparkSession)}/stash-{uuid.uuid4().hex}"
    df.write.option("parquet.block.size", ROW_GROUP).parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    _folders[id(out)] = path, weakref.ref(out, lambda _, key=id(out): _folders.pop(key, None))
    return out


#: Folder of each frame that is alive, by the frame's identity.
_folders: dict[int, tuple[str, weakref.ref]] = {}


def discard(df: DataFrame) -> None:
    """Delete the folder behind a frame that `stash` returned. Only for frames that nothing reads any more: call it once what came of them is written."""
    found = _folders.pop(id(df), None)
    if found is not None:
        spark = df.sparkSession
        path = spark._jvm.org.apache.hadoop.fs.Path(found[0])
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
