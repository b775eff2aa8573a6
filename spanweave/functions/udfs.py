"""Functions for SQL and DataFrames that need Python: Arrow batches or whole tables, bounded groups only."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.StringType())
def xor_edges(edges: pd.Series) -> str:
    """Symmetric difference of edge lists, each a string of blank-separated edges: what remains of two cycles put together. A grouped aggregate for small groups."""
    left: set[str] = set()
    for row in edges:
        left ^= set(row.split())
    return " ".join(sorted(left))


@F.udtf(returnType=T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType())]))
class BridgesOf:
    """bridges_of(TABLE(...) WITH SINGLE PARTITION) of (src, dst) rows: one task, refused beyond LIMIT edges."""

    LIMIT = 200_000

    def __init__(self):
        self.edges: set[tuple[int, int]] = set()

    def eval(self, row):
        a, b = row["src"], row["dst"]
        if a is not None and b is not None and a != b:
            self.edges.add((min(a, b), max(a, b)))
        if len(self.edges) > self.LIMIT:
            raise ValueError(f"more than {self.LIMIT} edges for one task")

    def terminate(self):
        from spanweave.operators.bridges import solve_low_points

        for src, dst, bridge, _, _ in solve_low_points(sorted(self.edges)):
            if bridge:
                yield src, dst


def register_functions(spark: SparkSession) -> None:
    spark.udf.register("xor_edges", xor_edges)
    spark.udtf.register("bridges_of", BridgesOf)
