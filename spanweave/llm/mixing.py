"""Mixing sources to target weights: Pfair scheduling of source blocks.

A source is cut into blocks of equal size. With share w of the slots, its i-th block may not start before slot floor((i-1)/w)
and must be placed by slot ceil(i/w); earliest deadline first then keeps every source within one block of its share at all
times. Shares are whole numbers out of a whole total, so the schedule repeats after `total` slots and one such round is all that is ever
computed: its length depends on the weights and the number of sources, not on the data. A block's place on this clock follows from its number alone. When a source
has run dry its slots fall away and later blocks move up; the others keep their order, and at the end of each round they stand at their shares again.
"""

from __future__ import annotations

import heapq
from fractions import Fraction
from math import gcd, lcm

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from spanweave.llm.shared import stash

#: Slots of a round up to which target weights are kept exactly; finer ones are rounded to so many parts (more, if there are more sources).
RESOLUTION = 1_000_000
#: Hexadecimal digits of the digest that split a source for ranking, and parts that the clock is cut into: 4096 each.
DIGITS, PARTS = 3, 4096


def one_round(shares: dict[str, int]) -> list[tuple[str, int, int]]:
    """The round of sum(shares) slots: (source, release, deadline) of the block in every slot, by earliest deadline first; ties by name.

    Block i of a source with share a of q is released at floor((i-1) q / a) and due by ceil(i q / a)."""
    q = sum(shares.values())
    waiting = sorted(((i - 1) * q // a, -(-i * q // a), s) for s, a in shares.items() for i in range(1, a + 1))
    waiting.reverse()
    ready: list[tuple[int, str, int]] = []
    out = []
    for slot in range(q):
        while waiting and waiting[-1][0] <= slot:
            release, due, source = waiting.pop()
            heapq.heappush(ready, (due, source, release))
        due, source, release = heapq.heappop(ready)
        if due <= slot:
            raise AssertionError("a deadline was missed")
        out.append((source, release, due))
    return out


def whole_weights(sources: list[str], targets: dict[str, float] | None, resolution: int = RESOLUTION) -> dict[str, int]:
    """Targets as whole shares of a round, in lowest terms. Sources without a target, and all where none are given, count 1 part in the number of sources;
    targets that are not positive count as much as the smallest of the others."""
    even = Fraction(1, max(1, len(sources)))
    wanted = {s: Fraction(str(targets[s])) if s in (targets or {}) else even for s in sources}
    smallest = min((w for w in wanted.values() if w > 0), default=even)
    wanted = {s: w if w > 0 else smallest for s, w in wanted.items()}
    total, unit = sum(wanted.values()), lcm(*(w.denominator for w in wanted.values()))
    parts = {s: int(w * unit) for s, w in wanted.items()}
    size = max(resolution, len(parts))
    if sum(parts.values()) // (gcd(*parts.values()) or 1) > size:
        parts = {s: max(1, round(w / total * size)) for s, w in wanted.items()}
    common = gcd(*parts.values()) or 1
    return {s: n // common for s, n in parts.items()}


def ranked(docs: DataFrame, doc_id: Column, source: Column) -> DataFrame:
    """doc_id, source, rank (from 0, by MD5 of the id, then id: a fixed shuffle), without ever bringing a source together.

    The digest's first digits split each source evenly; ranks are local, and one row a part holds what lies before it."""
    digest = F.md5(F.coalesce(doc_id.cast("string"), F.lit("")))
    rows = docs.select(doc_id.cast("long").alias("doc_id"), F.coalesce(source, F.lit("")).alias("source"), digest.alias("digest"), F.substring(digest, 1, DIGITS).alias("part"))
    before = rows.groupBy("source", "part").agg(F.count(F.lit(1)).alias("n"))
    before = before.select("source", "part", F.sum("n").over(Window.partitionBy("source").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)).alias("before"))
    local = F.row_number().over(Window.partitionBy("source", "part").orderBy("digest", "doc_id")) - 1
    return rows.select("doc_id", "source", "part", local.alias("local")).join(before, ["source", "part"]).select("doc_id", "source", (F.col("local") + F.coalesce("before", F.lit(0))).cast("long").alias("rank"))


_PLAN = T.StructType([T.StructField("source", T.StringType())] + [T.StructField(n, T.LongType()) for n in ("turn", "share", "offset", "release", "due")])


def schedule(docs: DataFrame, targets: dict[str, float] | None = None, block: int = 16, doc_id: str = "doc_id", source: str = "source") -> DataFrame:
    """One row per row of `docs`: doc_id, source, block (of its source), clock, release, deadline, slot, position.

    `targets` are the wanted shares by source (default: all equal). Blocks hold `block` documents, a source's last one the rest. `clock` is the block's slot as long as no
    source has run dry, with release <= clock < deadline; `slot` counts the blocks before it. Documents are placed once each; rows ordered by `position` are the mix. A null source
    is the source "", null ids are ids like any other. Repeated rows get a place each. An empty table gives no rows; other columns are ignored.
    The driver holds the names of the sources and one round of the plan."""
    spark = docs.sparkSession
    places = stash(ranked(docs, F.col(doc_id), F.col(source)))
    counts = {r["source"]: r["n"] for r in places.groupBy("source").agg(F.count(F.lit(1)).alias("n")).collect()}
    shares = whole_weights(sorted(counts), targets) if counts else {}
    turn, rows, size = dict.fromkeys(shares, 0), [], sum(shares.values())
    for offset, (name, release, due) in enumerate(one_round(shares)):
        rows.append((name, turn[name], shares[name], offset, release, due))
        turn[name] += 1
    plan = stash(spark.createDataFrame(rows, _PLAN))
    number = F.floor(F.col("rank") / block).cast("long")
    turns = places.withColumn("block", number).join(plan.select("source", "share").filter("share > 0").distinct(), "source")
    turns = turns.withColumn("turn", F.col("block") % F.col("share")).join(plan.drop("share"), ["source", "turn"])
    base = F.floor(F.col("block") / F.col("share")).cast("long") * size
    # The last tick of the clock, cut into PARTS stretches: slots are ranks inside a stretch plus the blocks before it.
    last = max((-(-n // block) // shares[s] + 1) * size for s, n in counts.items()) if counts else 1
    clock = base + F.col("offset")
    ticked = turns.select("doc_id", "source", "rank", "block", clock.alias("clock"), (base + F.col("release")).alias("release"), (base + F.col("due")).alias("deadline"), F.floor(clock / -(-last // PARTS)).cast("int").alias("part"))
    ticked = stash(ticked)
    firsts = ticked.filter(F.col("rank") % block == 0).groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    before = firsts.select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    slot = F.col("before") + F.dense_rank().over(Window.partitionBy("part").orderBy("clock")) - 1
    placed = ticked.join(F.broadcast(before), "part").withColumn("slot", slot.cast("long"))  # PARTS rows at most
    return placed.select("doc_id", "source", "block", "clock", "release", "deadline", "slot", (F.col("slot") * block + F.col("rank") % block).alias("position"))


def mixed(docs: DataFrame, targets: dict[str, float] | None = None, block: int = 16, position: str | None = None) -> DataFrame:
    """`docs`, all rows and columns, in the order of the mix: partitions are ranges of positions, sorted within; `position` names a further column for the place.

    Rows that repeat an id, null ids included, stand together at the first place of that id. An empty table gives no rows; columns of any name stand."""
    inner = [f"_c{i}" for i in range(len(docs.columns))]
    places = stash(schedule(docs, targets, block).groupBy(F.col("doc_id").alias("_id")).agg(F.min("position").alias("_place")))
    parts = max(2, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    key = F.col(inner[docs.columns.index("doc_id")]).cast("long")
    whole = docs.toDF(*inner).join(places.hint("merge"), key.eqNullSafe(F.col("_id")), "left").drop("_id")
    ordered = whole.repartitionByRange(parts, "_place").sortWithinPartitions("_place")
    out = [F.col(i).alias(n) for i, n in zip(inner, docs.columns, strict=True)]
    return ordered.select(*out, *([F.col("_place").alias(position)] if position else []))
