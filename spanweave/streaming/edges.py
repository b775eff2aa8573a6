"""Edges as a stream: sources, watermarks, windows, and components kept up to date. Everything else in this library is batch."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from spanweave.operators.bridges import find_bridges
from spanweave.operators.components import connected_components
from spanweave.schema import vertex
from spanweave.store import shared_dir

EVENTS = T.StructType([T.StructField("event_id", T.LongType()), T.StructField("user_id", T.LongType()), T.StructField("event_type", T.StringType()), T.StructField("ts", T.TimestampNTZType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType())])


def event_stream(spark: SparkSession, folder: str, schema: T.StructType | None = None, files: int = 1) -> DataFrame:
    """Events of Parquet files that appear in a folder, `files` a micro-batch."""
    rows = spark.readStream.schema(schema or EVENTS).option("maxFilesPerTrigger", files).parquet(folder)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))  # watermarks take no zoneless times


def edge_stream(events: DataFrame, delay: str = "1 day", words: list[str] | None = None) -> DataFrame:
    """(ts, src, dst): user and event type; an event id counts once, late rows beyond the watermark are dropped (`late_rows` counts them). A batch has no late rows. With `words` a type's number is its
    place in that list and another word is an error; without, it is the word's CRC, which two words may share."""
    rows = events.withWatermark("ts", delay) if events.isStreaming else events
    if "event_id" in events.columns:
        rows = rows.dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else rows.dropDuplicates(["event_id"])
    token = F.crc32("event_type")
    if words is not None:
        place = F.array_position(F.array(*(F.lit(w) for w in words)), F.col("event_type"))
        token = F.when(place == 0, F.raise_error(F.concat(F.lit("no such word: "), F.col("event_type")))).otherwise(place)
    return rows.select("ts", vertex("user", "user_id").alias("src"), vertex("token", token).alias("dst"))


def late_rows(run) -> int:
    """Rows that a stream's stateful operators dropped because they came behind the watermark, over the progress reports it still holds."""
    return sum(op["numRowsDroppedByWatermark"] for report in run.recentProgress for op in report["stateOperators"])


def tumbling(events: DataFrame, length: str = "1 day", delay: str | None = "1 day") -> DataFrame:
    """(start, events) by fixed windows; with a batch input the same, without a watermark."""
    rows = events.withWatermark("ts", delay) if delay and events.isStreaming else events
    return rows.groupBy(F.window("ts", length)).agg(F.count(F.lit(1)).alias("events")).select(F.col("window.start").alias("start"), "events")


def sliding(events: DataFrame, length: str = "1 day", step: str = "6 hours", delay: str | None = "1 day") -> DataFrame:
    rows = events.withWatermark("ts", delay) if delay and events.isStreaming else events
    return rows.groupBy(F.window("ts", length, step)).agg(F.count(F.lit(1)).alias("events")).select(F.col("window.start").alias("start"), "events")


def sessions(events: DataFrame, gap: str = "1 hour", delay: str | None = "1 day") -> DataFrame:
    """(user_id, start, events): runs of a user's events with no gap that long."""
    rows = events.withWatermark("ts", delay) if delay and events.isStreaming else events
    return rows.groupBy("user_id", F.session_window("ts", gap)).agg(F.count(F.lit(1)).alias("events")).select("user_id", F.col("session_window.start").alias("start"), "events")


class ComponentKeeper:
    """Labels of an insert-only edge stream: each micro-batch's edges are joined with the labels they touch, and only those components change. What it holds is a version a
    micro-batch in `folder`, complete once its edges are written, and the edges of each batch beside it: a keeper made on the same folder goes on from the last complete
    version, and a batch that is played again changes nothing. Labels are written whole for every batch that brings an edge, edges once."""

    def __init__(self, spark: SparkSession, folder: str | None = None):
        self.spark, self.folder = spark, folder or f"{shared_dir(spark)}/keeper-{uuid.uuid4().hex}"
        files = self._path("edges").getFileSystem(spark._jsc.hadoopConfiguration())
        found = files.globStatus(self._path("edges/batch=*/_SUCCESS")) or []
        self.version = max((int(f.getPath().getParent().getName().split("=")[1]) for f in found), default=None)
        if self.version is None:
            self._write(spark.createDataFrame([], "v long, comp long"), "labels", -1)
            self._write(spark.createDataFrame([], "comp long"), "touched", -1)
            self._write(spark.createDataFrame([], "src long, dst long"), "edges", -1)
            self.version = -1

    def _path(self, name: str):
        return self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.folder}/{name}")

    def _write(self, df: DataFrame, what: str, version: int) -> None:
        df.write.mode("overwrite").parquet(f"{self.folder}/{what}/batch={version}")

    def _drop(self, version: int) -> None:
        for what in ("labels", "touched"):
            path = self._path(f"{what}/batch={version}")
            path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)

    @property
    def labels(self) -> DataFrame:
        return self.spark.read.schema("v long, comp long").parquet(f"{self.folder}/labels/batch={self.version}")

    @property
    def touched(self) -> DataFrame:
        """Components that the last batch with an edge changed."""
        return self.spark.read.schema("comp long").parquet(f"{self.folder}/touched/batch={self.version}")

    @property
    def edges(self) -> DataFrame:
        rows = self.spark.read.schema("src long, dst long, batch long").option("basePath", f"{self.folder}/edges").parquet(f"{self.folder}/edges")
        return rows.filter(F.col("batch") <= self.version).select("src", "dst").distinct()

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id <= self.version:
            return
        fresh = batch.select("src", "dst").filter("src <> dst").distinct().persist()
        try:
            if fresh.isEmpty():
                return
            seen = fresh.select(F.explode(F.array("src", "dst")).alias("v")).distinct()
            labels = self.labels
            held = seen.join(labels, "v", "left").select("v", F.coalesce("comp", "v").alias("comp"))
            spokes = held.filter("v <> comp").select(F.col("v").alias("src"), F.col("comp").alias("dst"))
            moved = connected_components(fresh.unionByName(spokes))
            renamed = held.join(moved, "v").select(held["comp"].alias("old"), moved["comp"].alias("new")).distinct()
            kept = labels.join(renamed, labels["comp"] == F.col("old"), "left").select("v", F.coalesce("new", "comp").alias("comp"))
            added = moved.join(labels.select("v"), "v", "left_anti").select("v", "comp")
            self._write(kept.unionByName(added), "labels", batch_id)
            self._write(moved.select("comp").distinct(), "touched", batch_id)
            self._write(fresh, "edges", batch_id)  # last: it makes the version complete
            before, self.version = self.version, batch_id
            self._drop(before)
        finally:
            fresh.unpersist()

    def bridges(self) -> DataFrame:
        """Bridges of the components that the last batch touched."""
        inside = self.labels.join(self.touched, "comp", "left_semi").select(F.col("v").alias("src"))
        return find_bridges(self.edges.join(inside, "src", "left_semi").select("src", "dst"), method="interval")


def keep_components(edges: DataFrame, checkpoint: str, keeper: ComponentKeeper):
    """Run an edge stream to its present end through a keeper."""
    return edges.writeStream.foreachBatch(keeper).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def last_events(events: DataFrame) -> DataFrame:
    """(user_id, last_type, event_type, ts): every event with the type of the user's event before it, across micro-batches; one row of state a user. Events of a
    micro-batch are taken by time, then by type; needs the RocksDB state store (`spark.sql.streaming.stateStore.providerClass`)."""
    import pandas as pd
    from pyspark.sql.streaming import StatefulProcessor

    class Last(StatefulProcessor):
        def init(self, handle) -> None:
            self.state = handle.getValueState("last", "event_type string")

        def handleInputRows(self, key, rows, timerValues):  # noqa: N802, N803
            table = pd.concat(list(rows)).sort_values(["ts", "event_type"])
            known = self.state.get()[0] if self.state.exists() else None
            before = [known, *table["event_type"].tolist()[:-1]]
            self.state.update((table["event_type"].iat[-1],))
            yield pd.DataFrame({"user_id": key[0], "last_type": before, "event_type": table["event_type"].tolist(), "ts": table["ts"].tolist()})

        def close(self) -> None:
            pass

    rows = events.select("user_id", "event_type", "ts")
    return rows.groupBy("user_id").transformWithStateInPandas(Last(), "user_id long, last_type string, event_type string, ts timestamp", "Append", "None")
