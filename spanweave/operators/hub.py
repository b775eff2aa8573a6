"""The hub reduction: connectivity answered by blocks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanweave.graphs import canonical
from spanweave.ledger import settle
from spanweave.operators.blocks import color_blocks, is_biconnected
from spanweave.schema import KIND_BITS, KINDS

#: The hub's id: above every other kind's.
HUB = KINDS["hub"] << KIND_BITS


def add_hub(edges: DataFrame, vertices: DataFrame | None = None) -> DataFrame:
    """The graph and a new vertex next to every other one: diameter 2, one block a component."""
    every = edges.select(F.explode(F.array("src", "dst")).alias("v"))
    every = (every if vertices is None else every.unionByName(vertices.select("v"))).distinct()
    return canonical(edges.select("src", "dst").unionByName(every.select(F.col("v").alias("src"), F.lit(HUB).alias("dst"))))


def components_via_hub(edges: DataFrame, vertices: DataFrame | None = None, **options) -> DataFrame:
    """(v, comp): components read off the colours of the hub's edges, named by their least id."""
    colors = color_blocks(add_hub(edges, vertices), **options).filter(F.col("dst") == HUB)
    least = colors.groupBy("block_src", "block_dst").agg(F.min("src").alias("comp"))
    return colors.join(least, ["block_src", "block_dst"]).select(F.col("src").alias("v"), "comp")


def one_or_two_cycles(edges: DataFrame, **options) -> int:
    """1 if a graph that is one cycle or two is one, 2 if two: whether the graph with a hub is biconnected."""
    return 1 if is_biconnected(add_hub(settle(canonical(edges), "normalise")), **options) else 2
