"""Vertex ids: tagged integers for tables' keys, and collision-free numbers for any other key."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tidegraph.operators.primitives import global_index

KINDS = {"order": 0, "part": 1, "supplier": 2, "customer": 3, "nation": 4, "region": 5, "event": 6, "other": 7}


def tag(key: Column, kind: str) -> Column:
    return key.cast("long") * 8 + KINDS[kind]


def encode_ids(edges: DataFrame, a: str = "u", b: str = "v") -> tuple[DataFrame, DataFrame]:
    """Edges over any keys -> (edges u, v over 0..n-1, dictionary id, key). Ids are sorted ranks, so two keys never share one."""
    keys = edges.select(F.col(a).alias("key")).union(edges.select(F.col(b).alias("key"))).where("key is not null").distinct()
    dictionary = global_index(keys, "key", name="id").select("id", "key")
    pairs = edges.select(F.col(a).alias("_a"), F.col(b).alias("_b"))
    left, right = (dictionary.select(F.col("id").alias(n), F.col("key").alias(f"_{n}")) for n in "uv")
    coded = pairs.join(left, F.col("_a") == F.col("_u")).select("u", "_b").join(right, F.col("_b") == F.col("_v")).select("u", "v")
    return coded, dictionary
