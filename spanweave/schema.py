"""Schemas of the frames that operators exchange, and the encoding of vertex ids."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Entity kinds of vertex ids. Fixed values.
KINDS = {"region": 1, "nation": 2, "customer": 3, "supplier": 4, "part": 5, "order": 6, "user": 7, "document": 8, "vector": 9, "page": 10, "turn": 11, "token": 12, "hub": 63}
KIND_BITS = 56


def _long(*names: str) -> T.StructType:
    return T.StructType([T.StructField(n, T.LongType()) for n in names])


EDGES = _long("src", "dst")
VERTICES = _long("v")
PARENTS = T.StructType([*_long("v", "parent", "root").fields, T.StructField("depth", T.IntegerType())])
PAIRS = _long("qid", "u", "v")
LCAS = _long("qid", "u", "v", "lca", "child_u", "child_v")
PATHS = _long("qid", "pos", "v")
TOUR = _long("root", "pos", "v")
SPANS = _long("v", "first", "last")
RANGES = _long("qid", "lo", "hi")


class Failed(RuntimeError):
    """A randomised step gave up within its budget. Results are exact otherwise."""


def vertex(kind: str, key: Column | str) -> Column:
    """The id of an entity: kind in the upper bits, key in the lower ones, so ids order by (kind, key)."""
    key = F.col(key) if isinstance(key, str) else key
    return key.cast("long") + F.lit(KINDS[kind] << KIND_BITS)


def vertex_sql(kind: str, key: str) -> str:
    return f"(CAST({key} AS BIGINT) + {KINDS[kind] << KIND_BITS})"


def conform(df: DataFrame, schema: T.StructType) -> DataFrame:
    """`df` with exactly the columns of `schema`, cast; an error where one is missing."""
    missing = [f.name for f in schema if f.name not in df.columns]
    if missing:
        raise ValueError(f"columns {missing} are missing from {df.columns}")
    return df.select(*(F.col(f.name).cast(f.dataType) for f in schema))
