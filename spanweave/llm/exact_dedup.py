"""Exact deduplication by 128-bit content hash, verified by comparing bytes inside every group.

DataFrame functions only. Three passes over the texts: hash groups are counted over narrow rows with map-side
combining; the texts of groups with two rows or more are compared as `min(body) = max(body)`, which combines
before it shuffles and so never gathers a group of copies in one task; the result is a join of narrow rows,
whose large partitions Spark splits at run time. Joins are merge joins at every size: what is shuffled then grows with
the input alone, and nothing is broadcast that grows with it.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spanweave.llm.shared import SPACE_CLASS, stash, texts


def normalised(text: Column) -> Column:
    """Each run of white space replaced by one blank."""
    return F.regexp_replace(text, SPACE_CLASS, " ")


def content_digest(body: Column) -> Column:
    """128-bit digest of the UTF-8 bytes."""
    return F.unhex(F.md5(body))


def exact_groups(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", digest: Callable[[Column], Column] = content_digest) -> DataFrame:
    """One row per row of `docs`: doc_id, keep_id, group_size, kept, text_sha256.

    Null texts are empty texts, and all empty texts form one group. Texts that share a digest but not their bytes
    are told apart. A null doc_id never is the smallest unless its whole group has none. Rows that repeat an id
    with the same text share its fate. An empty table gives an empty result; other columns are ignored.
    """
    rows = texts(docs, doc_id, text).select("doc_id", normalised(F.col("text")).alias("body")).withColumn("digest", digest(F.col("body")))
    groups = stash(rows.groupBy("digest").agg(F.min("doc_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size")).filter("group_size > 1"))
    # Grouped by an expression and not by the join's own key: Spark then combines before the shuffle and can split a hot digest's join.
    compared = rows.join(groups.hint("merge"), "digest").groupBy(F.hex("digest").alias("_hex")).agg(F.min("body").alias("low"), F.max("body").alias("high"))
    doubtful = stash(compared.filter("low <> high").select(F.unhex("_hex").alias("in_doubt")))
    narrow = rows.withColumn("text_sha256", F.sha2("body", 256))
    result = ["doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256"]
    if doubtful.isEmpty():
        return _placed(narrow.drop("body"), groups).select(*result)
    clear = _placed(narrow.join(doubtful, F.col("digest") == F.col("in_doubt"), "left_anti").drop("body"), groups)
    unclear = narrow.join(doubtful, F.col("digest") == F.col("in_doubt"), "left_semi")
    by_bytes = stash(unclear.groupBy("body").agg(F.min("doc_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size")))
    return clear.select(*result).unionByName(unclear.join(by_bytes, "body").select(*result))


def _placed(narrow: DataFrame, groups: DataFrame) -> DataFrame:
    return narrow.join(groups.hint("merge"), "digest", "left").select(
        "doc_id", "text_sha256", F.when(F.col("group_size").isNull(), F.col("doc_id")).otherwise(F.col("keep_id")).alias("keep_id"), F.coalesce("group_size", F.lit(1)).cast("long").alias("group_size")
    )


def drop_exact(docs: DataFrame) -> DataFrame:
    """The rows of `docs` that stay, all columns.

    Of equal texts one row stays, that with the least doc_id, and rows are told by id and text: an id that carries two texts keeps both, if each is the least of its own. Of several
    rows with that id and text (repeated rows, or null ids where no other are) one stays, the least by its other columns. Null texts are empty texts; an empty table gives no rows.
    Columns of any name stand; those that cannot be ordered (maps) do not decide between repeated rows."""
    inner = [f"_c{i}" for i in range(len(docs.columns))]
    plain = docs.toDF(*inner)
    key, body = (F.col(inner[docs.columns.index(c)]) for c in ("doc_id", "text"))
    sha = F.unhex(F.sha2(normalised(F.coalesce(body, F.lit(""))), 256))
    fates = exact_groups(docs).select("doc_id", F.unhex("text_sha256").alias("sha"), "kept")
    fates = stash(fates.groupBy("doc_id", "sha").agg(F.max("kept").alias("kept"), F.count(F.lit(1)).alias("times")).filter("not kept or times > 1"))
    marked = plain.withColumn("_id", key.cast("long")).withColumn("_sha", sha)
    marked = marked.join(fates.hint("merge"), F.col("_id").eqNullSafe(F.col("doc_id")) & (F.col("_sha") == F.col("sha")), "left")
    alone = marked.filter("kept is null").select(*inner)
    again = marked.filter("kept")
    orderable = [c for c, f in zip(inner, docs.schema.fields, strict=True) if "map<" not in f.dataType.simpleString() and "variant" not in f.dataType.simpleString()]
    least = again.groupBy("_id", "_sha").agg(F.min_by(F.struct(*inner), F.struct(*orderable)).alias("r")).select("r.*")
    return alone.unionByName(least).toDF(*docs.columns)


ORACLE = r"""
WITH d AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS body FROM documents)
SELECT doc_id, min(doc_id) OVER (PARTITION BY body) AS keep_id, count(*) OVER (PARTITION BY body) AS group_size,
       doc_id = min(doc_id) OVER (PARTITION BY body) AS kept, sha256(body) AS text_sha256
FROM d
"""
