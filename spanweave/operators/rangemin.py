"""Batched range minima over a sequence (pos, val), positions 1..n."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from spanweave.ledger import settle
from spanweave.operators.pointers import hop


def block_length(n: int) -> int:
    """The binary logarithm of the length, rounded up, at least 1."""
    return max(1, (n - 1).bit_length()) if n > 1 else 1


def range_min(arr: DataFrame, queries: DataFrame, method: str = "block", route: str = "auto", report: dict | None = None) -> DataFrame:
    """(qid, min_value) of queries (qid, lo, hi), lo <= hi, ends included.

    block: minima of blocks of log n positions, minima from each position to its block's ends, and a doubling table over the block minima: n + q rows. Ranges of at least a block's length take that
    way; shorter ones, which touch at most two blocks, look at their positions (route="auto"). route="long" insists on long ranges. sparse_table: doubling table over all positions, n log n rows. naive: a
    join by range, for tests. `report` receives how many rows were stored."""
    report = report if report is not None else {}
    if method == "naive":
        hit = queries.join(arr, (F.col("pos") >= F.col("lo")) & (F.col("pos") <= F.col("hi")))
        return hit.groupBy("qid").agg(F.min("val").alias("min_value"))
    if method == "sparse_table":
        table, top = _doubling_table(arr, report)
        return _by_table(table, top, queries)
    n = arr.agg(F.coalesce(F.max("pos"), F.lit(0))).first()[0]
    t = block_length(n)
    blocked = arr.select("pos", "val", F.ceil(F.col("pos") / t).cast("long").alias("block"))
    over = Window.partitionBy("block").orderBy("pos")  # at most t rows a block
    ends = blocked.select("pos", F.min("val").over(over.rowsBetween(Window.unboundedPreceding, 0)).alias("left"), F.min("val").over(over.rowsBetween(0, Window.unboundedFollowing)).alias("right"))
    ends = settle(ends, "range minimum", 0)
    minima = blocked.groupBy(F.col("block").alias("pos")).agg(F.min("val").alias("val"))
    table, top = _doubling_table(minima, report)
    report["rows_stored"] = report.get("rows_stored", 0) + 2 * n
    asked = queries.select("qid", "lo", "hi")
    long = asked.filter(F.col("hi") - F.col("lo") >= t)
    short = asked.filter(F.col("hi") - F.col("lo") < t)
    if route == "long":
        if not short.isEmpty():
            raise ValueError(f"a range is shorter than {t}")
        short = None
    first, last = F.ceil(F.col("lo") / t).cast("long") + 1, F.floor(F.col("hi") / t).cast("long")
    inner = long.select("qid", first.alias("lo"), last.alias("hi")).filter("lo <= hi")
    middle = _by_table(table, top, inner).select("qid", F.col("min_value").alias("m"))
    at = hop(hop(long, ends, "lo", {"_r": "right"}, name="pos"), ends, "hi", {"_l": "left"}, name="pos")
    out = at.join(middle, "qid", "left").select("qid", F.least("_r", "_l", "m").alias("min_value"))
    if short is None:
        return out
    touched = short.withColumn("block", F.explode(F.sequence(F.ceil(F.col("lo") / t).cast("long"), F.ceil(F.col("hi") / t).cast("long"))))
    near = touched.join(blocked, "block").filter("pos between lo and hi").groupBy("qid").agg(F.min("val").alias("min_value"))
    return out.unionByName(near)


def _doubling_table(arr: DataFrame, report: dict) -> tuple[DataFrame, int]:
    """(j, pos, m): minima of 2**j positions from pos on. Up to LOCAL positions one task fills it, beyond that every level is a join of the one before with itself."""
    n = arr.agg(F.coalesce(F.max("pos"), F.lit(0))).first()[0]
    if n <= LOCAL:
        report["rows_stored"] = report.get("rows_stored", 0) + sum(max(0, n - (1 << j) + 1) for j in range(max(1, n).bit_length()))
        table = arr.groupBy(F.lit(0).alias("all")).applyInPandas(_local_table, "j int, pos long, m long")
        return settle(table, "range table"), max(1, n).bit_length() - 1
    level, out, j = arr.select("pos", F.col("val").alias("m")), None, 0
    stored = 0
    while True:
        level = settle(level, "range table", j)
        stored += max(0, n - (1 << j) + 1)
        row = level.select(F.lit(j).alias("j"), "pos", "m")
        out = row if out is None else out.unionByName(row)
        if 1 << (j + 1) > max(1, n):
            break
        ahead = level.select((F.col("pos") - (1 << j)).alias("pos"), F.col("m").alias("_m"))
        level, j = level.join(ahead, "pos").select("pos", F.least("m", "_m").alias("m")), j + 1
    report["rows_stored"] = report.get("rows_stored", 0) + stored
    return out, j


#: Positions whose table one task makes.
LOCAL = 100_000


def _local_table(pdf: pd.DataFrame) -> pd.DataFrame:
    pdf = pdf.sort_values("pos")
    pos, row = pdf["pos"].to_numpy(), pdf["val"].to_numpy(dtype=np.int64)
    parts, j = [], 0
    while len(row):
        parts.append(pd.DataFrame({"j": np.full(len(row), j, np.int32), "pos": pos[: len(row)], "m": row}))
        row = np.minimum(row[: -(1 << j)], row[1 << j :]) if len(row) > 1 << j else row[:0]
        j += 1
    return pd.concat(parts)


def _by_table(table: DataFrame, top: int, queries: DataFrame) -> DataFrame:
    """Two looks a query: the power of two that fits, from its start and up to its end."""
    j = F.floor(F.log2((F.col("hi") - F.col("lo") + 1).cast("double"))).cast("int")
    asked = queries.select("qid", "lo", "hi", j.alias("j"))
    starts = asked.select("qid", "j", F.explode(F.array(F.col("lo"), F.expr("hi - shiftleft(CAST(1 AS BIGINT), j) + 1"))).alias("pos"))
    return starts.join(table, ["j", "pos"]).groupBy("qid").agg(F.min("m").alias("min_value"))
