"""Joins whose one side is small or whose keys are hot: checked broadcasts, and salts for what is beyond them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tidegraph.functions.session import cut

MOST_BROADCAST = 50_000  # rows of a broadcast side


def attach(rows: DataFrame, params: DataFrame, on: dict[str, str], how: str = "inner", most: int = MOST_BROADCAST, salts: int = 64) -> DataFrame:
    """rows with the columns of params, whose keys are unique; on: column of rows -> column of params, null equals null.

    params (a written table) is counted: up to `most` rows it is broadcast and rows stay where they are. Beyond, its rows are
    sent `salts` times and rows are dealt over the salts, so a key of a third of all rows is spread over that many tasks.
    """
    same: Column = F.lit(True)
    for a, b in on.items():
        same = same & F.col(a).eqNullSafe(F.col(b))
    if params.count() <= most:
        return rows.join(F.broadcast(params), same, how).drop(*on.values())
    dealt = rows.withColumn("_salt", F.pmod(F.monotonically_increasing_id(), F.lit(salts)).cast("int"))
    copies = params.withColumn("_salt2", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return dealt.join(copies, same & (F.col("_salt") == F.col("_salt2")), how).drop("_salt", "_salt2", *on.values())


def spread(many: DataFrame, few: DataFrame, keys: list[str], limit: int = 4000, most: int = 500_000) -> tuple[DataFrame, DataFrame]:
    """Both sides of an equi join on keys with a column _salt to be added to its keys.

    A key with more than `limit` rows in `many` has these dealt over rows / limit salts, and its rows in `few` repeated for each. Keys
    like that are a limit-th of the rows at most; their list is broadcast up to `most` rows, else joined.
    """
    hot = cut(many.groupBy(*keys).agg(F.count("*").alias("_n")).where(F.col("_n") > limit).select(*keys, F.ceil(F.col("_n") / limit).cast("int").alias("_n")))
    n = hot.count()
    if not n:
        return many.withColumn("_salt", F.lit(0)), few.withColumn("_salt", F.lit(0))
    hot = F.broadcast(hot) if n <= most else hot
    others = [c for c in many.columns if c not in keys]
    dealt = many.join(hot, keys, "left").withColumn("_salt", F.coalesce(F.pmod(F.xxhash64(*others), F.col("_n")), F.lit(0)).cast("int")).drop("_n")
    copies = few.join(hot, keys, "left").withColumn("_salt", F.explode(F.sequence(F.lit(0), F.coalesce("_n", F.lit(1)) - 1))).drop("_n")
    return dealt, copies
