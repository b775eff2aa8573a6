"""Global order without a single task: dense positions and prefix sums in two passes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from spanweave.ledger import settle


def _ranged(df: DataFrame, order: list[str]) -> DataFrame:
    """Range-partitioned by `order`, the partition's number in `_part`; written, since ranges are sampled and must stay as they are."""
    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return settle(df.repartitionByRange(n, *order).withColumn("_part", F.spark_partition_id()), "ranges")


def dense_positions(df: DataFrame, order: list[str], name: str = "pos") -> DataFrame:
    """`df` with `name` = 1..n in the order of the columns `order`; rows that tie in all of them are placed in any order among themselves.

    Ranges of the order are ranked apart and shifted by the rows before them: one row a range is gathered."""
    ranged = _ranged(df, order)
    before = _offsets(ranged.groupBy("_part").agg(F.count(F.lit(1)).alias("_n")), [], "_n")
    local = F.row_number().over(Window.partitionBy("_part").orderBy(*order))
    return ranged.withColumn(name, local).join(F.broadcast(before), "_part").withColumn(name, (F.col(name) + F.col("_before")).cast("long")).drop("_part", "_before")


def prefix_sums(df: DataFrame, group: list[str], order: list[str], weight: str, name: str = "before") -> DataFrame:
    """`df` with `name`: the sum of `weight` over the rows of its group that come earlier. `group` and `order` together must be unique.

    A group may be far larger than a task: it is cut into ranges, and their sums, one row a range and group, are added up first."""
    ranged = _ranged(df, [*group, *order])
    before = _offsets(ranged.groupBy(*group, "_part").agg(F.sum(weight).alias("_n")), group, "_n")
    local = F.sum(weight).over(Window.partitionBy(*group, "_part").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1))
    return ranged.withColumn(name, F.coalesce(local, F.lit(0))).join(before, [*group, "_part"]).withColumn(name, (F.col(name) + F.col("_before")).cast("long")).drop("_part", "_before")


def _offsets(parts: DataFrame, group: list[str], n: str) -> DataFrame:
    over = Window.partitionBy(*group, F.lit(0)).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    return parts.select(*group, "_part", F.coalesce(F.sum(n).over(over), F.lit(0)).alias("_before"))
