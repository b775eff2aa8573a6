"""Sources and sinks: tables with pruned columns, edge lists in several formats, results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from spanweave.schema import EDGES


def read_table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    """One of the given tables, only the columns that are needed: the scan reads no others."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", **options) -> DataFrame:
    """(src, dst) from CSV, JSON, ORC or Parquet files, under the fixed schema: nothing is inferred."""
    if fmt not in ("csv", "json", "orc", "parquet"):
        raise ValueError(f"unknown format {fmt}")
    return spark.read.schema(EDGES).options(**options).format(fmt).load(path)


def from_rows(spark: SparkSession, pairs) -> DataFrame:
    """An edge frame of given pairs, as they are."""
    return spark.createDataFrame([(int(a), int(b)) for a, b in pairs], EDGES)


def write_result(df: DataFrame, path: str | None = None, fmt: str = "parquet", partition_by: list[str] | None = None, table: str | None = None, buckets: tuple[int, str] | None = None, mode: str = "errorifexists") -> None:
    """A distributed write: to files, or to a table bucketed and sorted by a column, which later joins on it need not shuffle.
    fmt "noop" computes everything and stores nothing (for timing)."""
    writer = df.write.mode("overwrite" if fmt == "noop" else mode)
    if table:
        if buckets:
            writer = writer.bucketBy(buckets[0], buckets[1]).sortBy(buckets[1])
        writer.format(fmt).saveAsTable(table)
        return
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    writer.format(fmt).save(path) if path else writer.format(fmt).save()
