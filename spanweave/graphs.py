"""Graphs built from the given tables: edge frames (src, dst), src < dst, distinct; and the builders they are made of."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from spanweave.schema import vertex
from spanweave.sources.tables import read_table


def canonical(edges: DataFrame, multiplicity: bool = False) -> DataFrame:
    """Least end first, loops dropped, each edge once; with `multiplicity` the count of parallel edges is kept."""
    one = edges.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).filter("src <> dst")
    return one.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("times")) if multiplicity else one.distinct()


def drop_loops(edges: DataFrame) -> DataFrame:
    return edges.filter("src <> dst")


def induced(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """Edges with both ends among `vertices` (v)."""
    return edges.join(vertices.select(F.col("v").alias("src")), "src", "left_semi").join(vertices.select(F.col("v").alias("dst")), "dst", "left_semi").select("src", "dst")


def bipartite(df: DataFrame, left: tuple[str, Column | str], right: tuple[str, Column | str], where: Column | str | None = None) -> DataFrame:
    """An edge for each distinct pair of (kind, key)."""
    df = df.filter(where) if where is not None else df
    return canonical(df.select(vertex(*left).alias("src"), vertex(*right).alias("dst")).filter("src is not null and dst is not null"))


def chain(df: DataFrame, part: str, order: str, v: str = "v") -> DataFrame:
    """Consecutive rows of a part, by `order`."""
    return canonical(df.select(F.col(v).alias("src"), F.lead(v).over(Window.partitionBy(part).orderBy(order)).alias("dst")).filter("dst is not null"))


def ring(df: DataFrame, part: str, order: str, through: str | None = None, v: str = "v") -> DataFrame:
    """Rows of a part in a ring by `order`; with `through` the ring closes through that vertex. A ring of two, or of one through a vertex, is a single edge."""
    over = Window.partitionBy(part).orderBy(order)
    links = df.select(F.col(v).alias("src"), F.lead(v).over(over).alias("dst")).filter("dst is not null")
    ends = df.groupBy(part).agg(F.min_by(v, order).alias("a"), F.max_by(v, order).alias("b"), *([F.first(through).alias("t")] if through else []))
    closing = ends.select(F.col("a").alias("src"), F.col("t").alias("dst")).unionByName(ends.select(F.col("b").alias("src"), F.col("t").alias("dst"))) if through else ends.select(F.col("a").alias("src"), F.col("b").alias("dst"))
    return canonical(links.unionByName(closing))


def shared_token(df: DataFrame, key: Column, tokens: Column) -> DataFrame:
    """(id, token) for tokens of two ids or more; `tokens` is an array. A token that very many share costs a partial count a task."""
    pairs = df.select(key.alias("id"), F.explode(tokens).alias("token")).distinct()
    often = pairs.groupBy("token").agg(F.count(F.lit(1)).alias("n")).filter("n > 1").select("token")
    return pairs.join(often, "token", "left_semi").select("id", "token")


def interned(pairs: DataFrame, kind: str = "token") -> DataFrame:
    """Edges of (id, token): tokens numbered by their order, never by a hash alone."""
    from spanweave.operators.positions import dense_positions

    words = dense_positions(pairs.select("token").distinct(), ["token"], "number")
    return canonical(pairs.join(words, "token").select(F.col("id").alias("src"), vertex(kind, "number").alias("dst")))


def knn(df: DataFrame, k: int = 1, rows: int = 5000) -> DataFrame:
    """Mutual k nearest neighbours of (v, x: array of float) by cosine; every pair is compared, so refused beyond `rows` rows."""
    if df.limit(rows + 1).count() > rows:
        raise ValueError(f"more than {rows} rows: pairs are compared one by one")
    norm = F.sqrt(F.aggregate("x", F.lit(0.0), lambda a, b: a + b.cast("double") * b.cast("double")))
    unit = df.select("v", F.transform("x", lambda e: e.cast("double") / norm).alias("x"))
    other = unit.select(F.col("v").alias("w"), F.col("x").alias("y"))
    dot = F.aggregate(F.zip_with("x", "y", lambda a, b: a * b), F.lit(0.0), lambda a, b: a + b)
    near = unit.join(F.broadcast(other), F.col("v") != F.col("w")).select("v", "w", dot.alias("s"))
    near = near.withColumn("r", F.row_number().over(Window.partitionBy("v").orderBy(F.desc("s"), "w"))).filter(F.col("r") <= k)
    back = near.select(F.col("w").alias("v"), F.col("v").alias("w"))
    return canonical(near.select("v", "w").join(back, ["v", "w"]).select(F.col("v").alias("src"), F.col("w").alias("dst")))


# ---- the workload graphs
def trade_sparse(spark: SparkSession, sf_dir: str, cut: int = 49) -> DataFrame:
    rows = read_table(spark, sf_dir, "lineitem", ["l_partkey", "l_suppkey", "l_quantity", "l_returnflag"])
    return bipartite(rows, ("part", "l_partkey"), ("supplier", "l_suppkey"), (F.col("l_quantity") >= cut) & (F.col("l_returnflag") == "R"))


def order_part(spark: SparkSession, sf_dir: str, cut: int = 46) -> DataFrame:
    rows = read_table(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_quantity"])
    return bipartite(rows, ("order", "l_orderkey"), ("part", "l_partkey"), F.col("l_quantity") >= cut)


def part_supp(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bipartite(read_table(spark, sf_dir, "lineitem", ["l_partkey", "l_suppkey"]), ("part", "l_partkey"), ("supplier", "l_suppkey"))


def ring_cactus(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = read_table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"]).select("o_custkey", "o_orderkey", vertex("order", "o_orderkey").alias("v"), vertex("customer", "o_custkey").alias("hub"))
    customers = read_table(spark, sf_dir, "customer", ["c_custkey", "c_nationkey"]).select("c_nationkey", "c_custkey", vertex("customer", "c_custkey").alias("v"), vertex("nation", "c_nationkey").alias("hub"))
    nations = read_table(spark, sf_dir, "nation", ["n_nationkey", "n_regionkey"]).select(vertex("nation", "n_nationkey").alias("src"), vertex("region", "n_regionkey").alias("dst"))
    regions = read_table(spark, sf_dir, "region", ["r_regionkey"]).select(F.lit(0).alias("all"), "r_regionkey", vertex("region", "r_regionkey").alias("v"))
    return canonical(ring(orders, "o_custkey", "o_orderkey", "hub").unionByName(ring(customers, "c_nationkey", "c_custkey", "hub")).unionByName(nations).unionByName(ring(regions, "all", "r_regionkey")))


def fk_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    link = lambda t, a, ka, b, kb: read_table(spark, sf_dir, t, [ka, kb]).select(vertex(a, ka).alias("src"), vertex(b, kb).alias("dst"))
    parts = [link("orders", "order", "o_orderkey", "customer", "o_custkey"), link("customer", "customer", "c_custkey", "nation", "c_nationkey"), link("nation", "nation", "n_nationkey", "region", "n_regionkey"), link("supplier", "supplier", "s_suppkey", "nation", "s_nationkey")]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return canonical(out)


def rings(spark: SparkSession, sf_dir: str, count: int = 1, below: int | None = None) -> DataFrame:
    """The parts in `count` rings of equal length by key; keys are dense from 0. `below` takes the first keys only (a parameter of the diameter series)."""
    parts = read_table(spark, sf_dir, "part", ["p_partkey"])
    parts = parts.filter(F.col("p_partkey") < below) if below else parts
    n = parts.count()
    length = n // count
    start = (F.col("p_partkey") / length).cast("long") * length
    nxt = start + (F.col("p_partkey") - start + 1) % length
    return canonical(parts.filter(F.col("p_partkey") < length * count).select(vertex("part", "p_partkey").alias("src"), vertex("part", nxt).alias("dst")))


def hubbed(edges: DataFrame) -> DataFrame:
    from spanweave.operators.hub import add_hub

    return add_hub(edges)


def user_type(spark: SparkSession, sf_dir: str) -> DataFrame:
    return interned_pairs(read_table(spark, sf_dir, "events", ["user_id", "event_type"]), "user", "user_id", "event_type")


def interned_pairs(df: DataFrame, kind: str, key: str, word: str) -> DataFrame:
    return interned(df.select(vertex(kind, key).alias("id"), F.col(word).alias("token")).filter("id is not null and token is not null").distinct())


def turn_id() -> Column:
    return F.col("conv_id") * (1 << 24) + F.col("turn")


def chains(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = read_table(spark, sf_dir, "conversations", ["conv_id", "turn"]).select("conv_id", "turn", vertex("turn", turn_id()).alias("v"))
    return chain(turns, "conv_id", "turn")


def line_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, token): documents and the trimmed lines of 20 characters or more that they share with another one."""
    docs = read_table(spark, sf_dir, "documents", ["doc_id", "text"])
    lines = F.filter(F.transform(F.split("text", "\n"), lambda x: F.trim(x)), lambda x: F.length(x) >= 20)
    return shared_token(docs, vertex("document", "doc_id"), lines)


def line_share(spark: SparkSession, sf_dir: str) -> DataFrame:
    return interned(line_pairs(spark, sf_dir))


def link_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = read_table(spark, sf_dir, "pages", ["page_id", "html"])
    return pages.select(vertex("page", "page_id").alias("id"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("token")).distinct()


def links(spark: SparkSession, sf_dir: str) -> DataFrame:
    return interned(link_pairs(spark, sf_dir))


def broom(spark: SparkSession, sf_dir: str, k: int, w: int) -> DataFrame:
    """A chain of the first k parts, all others hung on its vertex w: the tree as (v, parent)."""
    parts = read_table(spark, sf_dir, "part", ["p_partkey"])
    up = F.when(F.col("p_partkey") == 0, F.col("p_partkey")).when(F.col("p_partkey") < k, F.col("p_partkey") - 1).otherwise(F.lit(w))
    return parts.select(vertex("part", "p_partkey").alias("v"), vertex("part", up).alias("parent"))
