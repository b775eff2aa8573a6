"""The SQL surface: results as temporary views."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from spanweave.operators.blocks import color_blocks, cut_vertices
from spanweave.operators.bridges import Prepared, find_bridges


def register(spark: SparkSession, edges: DataFrame, prefix: str, method: str = "interval", **options) -> Prepared:
    """Views {prefix}_edges, _forest, _tour, _bridges, _blocks, _cut_vertices of a graph, over one shared tree phase."""
    ready = Prepared(edges, **options)
    colors = color_blocks(edges, method=method, ready=ready)
    views = {"edges": ready.graph, "forest": ready.parents, "tour": ready.tour, "bridges": find_bridges(edges, method=method, ready=ready), "blocks": colors, "cut_vertices": cut_vertices(colors)}
    for name, df in views.items():
        df.createOrReplaceTempView(f"{prefix}_{name}")
    return ready
