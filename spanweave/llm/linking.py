"""Connected components of links between keys, for duplicate classes.

Alternating star operations: every vertex hands the least vertex it knows to its larger neighbours, then to its smaller ones, until all
vertices point at the least of their component. Least neighbours come from combinable aggregates, never from gathered neighbour lists,
so a vertex with very many links is no hot group.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanweave.llm.shared import stash


def _large_star(links: DataFrame) -> DataFrame:
    both = links.select("u", "v").unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
    # Written first: a join of two plain shuffles can be split where one vertex has very many links.
    least = stash(both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")))
    return both.filter("v > u").join(least.hint("merge"), "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()


def _small_star(links: DataFrame) -> DataFrame:
    """Links come as u > v."""
    least = links.groupBy("u").agg(F.min("v").alias("m"))
    moved = links.join(least, "u")
    return moved.filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select("u", F.col("m").alias("v"))).distinct()


def components(links: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(key, component) for every key on a link, the component named by its least key. `links` has u, v; loops and repeated
    links are harmless. No links, no rows."""
    ordered = links.filter("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    now, mark = stash(ordered), None
    for _ in range(max_rounds):
        # A fixed point of both stars is a forest of depth one; sums of hashes tell whether the set of links is still the same.
        seen = tuple(now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        if seen == mark:
            roots = now.select(F.col("v").alias("key"), F.col("v").alias("component")).distinct()
            return now.select(F.col("u").alias("key"), F.col("v").alias("component")).unionByName(roots)
        mark, now = seen, stash(_small_star(_large_star(now)))
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
