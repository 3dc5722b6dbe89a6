"""Sequence and graph primitives: prefix sums, predecessor, dedupe, contraction, degrees, writes by key.

Graphs are arcs(src, dst): symmetric, loop-free, distinct. All are plain DataFrame plans. A prefix over a whole
table runs in two passes (totals by range partition, then local scans with an offset), because an
un-partitioned window is one task.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tidegraph.functions.session import cut

OPS = {"sum": F.sum, "min": F.min, "max": F.max, "count": F.count}


def sort_tuples(df: DataFrame, *cols) -> DataFrame:
    return df.orderBy(*cols)


def filter_tuples(df: DataFrame, predicate: Column | str) -> DataFrame:
    return df.where(predicate)


def _ranged(df: DataFrame, order: list[str], parts: int | None) -> DataFrame:
    """Rows dealt into ranges of the order, with the range's number; cut, so bounds are drawn once."""
    n = parts or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return cut(df.repartitionByRange(n, *order).withColumn("_part", F.spark_partition_id()))


def prefix(df: DataFrame, order: str | list[str], value: str, op: str = "sum", exclusive: bool = True, name: str = "prefix", parts: int | None = None) -> DataFrame:
    """Adds the op over all earlier rows (and the row's own value unless exclusive), in a total order."""
    order = [order] if isinstance(order, str) else order
    rows = _ranged(df, order, parts)
    f = OPS[op]
    merge = F.sum if op in ("sum", "count") else f
    totals = rows.groupBy("_part").agg(f(value).alias("_t"))
    before = totals.select("_part", merge("_t").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)).alias("_b"))  # a row a partition
    local = f(value).over(Window.partitionBy("_part").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1 if exclusive else 0))
    out = rows.withColumn("_l", local).join(F.broadcast(before), "_part")
    if op in ("sum", "count"):
        both = F.coalesce("_l", F.lit(0)) + F.coalesce("_b", F.lit(0))
    else:
        both = (F.least if op == "min" else F.greatest)("_l", "_b")
    return out.withColumn(name, both).drop("_part", "_l", "_b")


def reduce_all(df: DataFrame, value: str, op: str = "sum", name: str = "total") -> DataFrame:
    return df.agg(OPS[op](value).alias(name))


def global_index(df: DataFrame, order: str | list[str], name: str = "index", parts: int | None = None) -> DataFrame:
    """Dense 0-based position in a total order."""
    return prefix(df.withColumn("_one", F.lit(1)), order, "_one", "count", True, name, parts).drop("_one")


def filter_compact(df: DataFrame, predicate: Column | str, order: str | list[str], name: str = "index") -> DataFrame:
    return global_index(df.where(predicate), order, name)


def predecessor(df: DataFrame, key: str, order: str | list[str], flag: str, payload: str, name: str = "before") -> DataFrame:
    """Payload of the nearest earlier row of the key whose flag is 1: an as-of look-up."""
    order = [order] if isinstance(order, str) else order
    w = Window.partitionBy(key).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    return df.withColumn(name, F.last(F.when(F.col(flag) == 1, F.col(payload)), ignorenulls=True).over(w))


def dedupe_sorted(df: DataFrame, cols: list[str]) -> DataFrame:
    return df.select(*cols).distinct()


def latest_version(df: DataFrame, key: str, version: Column | str, value: str) -> DataFrame:
    version = F.col(version) if isinstance(version, str) else version
    return df.groupBy(key).agg(F.max_by(value, version).alias(value))


def scan(df: DataFrame, order: str | list[str], value: str, op: str = "sum", name: str = "prefix") -> tuple[DataFrame, DataFrame]:
    return prefix(df, order, value, op, True, name), reduce_all(df, value, op)


def multiprefix(df: DataFrame, key: str | list[str], order: str | list[str], value: str, op: str = "sum", exclusive: bool = True, name: str = "prefix") -> DataFrame:
    """An independent scan for each key; a list of keys makes many multiprefixes one."""
    keys, order = ([x] if isinstance(x, str) else x for x in (key, order))
    w = Window.partitionBy(*keys).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1 if exclusive else 0)
    out = OPS[op](value).over(w)
    return df.withColumn(name, F.coalesce(out, F.lit(0)) if op in ("sum", "count") else out)


def dedupe_first(df: DataFrame, key: str | list[str], order: str | list[str]) -> DataFrame:
    """First row of each key: those whose exclusive count by key is 0."""
    return multiprefix(df.withColumn("_one", F.lit(1)), key, order, "_one", "count", True, "_seen").where("_seen = 0").drop("_one", "_seen")


def symmetrize(edges: DataFrame, a: str = "u", b: str = "v") -> DataFrame:
    """arcs: both directions, loops and nulls dropped, distinct."""
    e = edges.select(F.col(a).cast("long").alias("src"), F.col(b).cast("long").alias("dst")).where("src <> dst")
    return e.unionByName(e.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()


def to_adjacency(arcs: DataFrame) -> DataFrame:
    """Sorted neighbour arrays; only for vertices of bounded degree."""
    return arcs.groupBy("src").agg(F.sort_array(F.collect_list("dst")).alias("nbrs"))


def contract(arcs: DataFrame, moves: DataFrame) -> DataFrame:
    """Renames both ends by moves(old, new), one step, and drops loops and duplicates."""
    a = moves.select(F.col("old").alias("_o1"), F.col("new").alias("_n1"))
    b = moves.select(F.col("old").alias("_o2"), F.col("new").alias("_n2"))
    out = arcs.join(a, F.col("src") == F.col("_o1"), "left").join(b, F.col("dst") == F.col("_o2"), "left")
    return out.select(F.coalesce("_n1", "src").alias("src"), F.coalesce("_n2", "dst").alias("dst")).where("src <> dst").distinct()


def apply_moves(members: DataFrame, moves: DataFrame) -> DataFrame:
    """members(orig, rep) after one simultaneous step of moves."""
    return members.join(moves, F.col("rep") == F.col("old"), "left").select("orig", F.coalesce("new", "rep").alias("rep"))


def compose_moves(maps: list[DataFrame]) -> DataFrame | None:
    """One map for a sequence of simultaneous maps, newest first, so sizes grow only towards the start.

    Each product enters the next step twice, so each is cut: plans stay of one size however many maps there are.
    """
    later = None
    for moves in reversed(maps):
        moves = moves.select("old", "new")
        if later is None:
            later = moves
            continue
        f = later.select(F.col("old").alias("_o"), F.col("new").alias("_n"))
        now = moves.join(f, F.col("new") == F.col("_o"), "left").select("old", F.coalesce("_n", "new").alias("new"))
        later = cut(now.unionByName(later.join(moves.select("old"), "old", "left_anti")))
    return later


def degrees(arcs: DataFrame) -> DataFrame:
    return arcs.groupBy("src").agg(F.count("*").alias("degree"))


def with_levels(arcs: DataFrame, verts: DataFrame) -> DataFrame:
    """arcs with level and active flag of both ends."""
    s = verts.select(F.col("vid").alias("src"), F.col("level").alias("sl"), F.col("active").alias("sa"))
    d = verts.select(F.col("vid").alias("dst"), F.col("level").alias("dl"), F.col("active").alias("da"))
    return arcs.join(s, "src").join(d, "dst").select("src", "dst", "sl", "sa", "dl", "da")


def level_degrees(arcs: DataFrame, verts: DataFrame) -> DataFrame:
    d = verts.select(F.col("vid").alias("dst"), F.col("level").alias("nbr_level"))
    return arcs.join(d, "dst").groupBy(F.col("src").alias("vid"), "nbr_level").agg(F.count("*").alias("cnt"))


def degree_array_map(arcs: DataFrame, verts: DataFrame) -> DataFrame:
    return level_degrees(arcs, verts).groupBy("vid").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("nbr_level", "cnt")))).alias("degrees"))


def induced_degree(arcs: DataFrame, verts: DataFrame, level: int) -> DataFrame:
    """Degrees in the subgraph of the vertices of at least this level."""
    high = verts.where(F.col("level") >= level).select("vid")
    inner = arcs.join(high.withColumnRenamed("vid", "src"), "src", "left_semi").join(high.withColumnRenamed("vid", "dst"), "dst", "left_semi")
    return high.join(degrees(inner), F.col("vid") == F.col("src"), "left").select("vid", F.coalesce("degree", F.lit(0)).alias("degree"))


def neighbor_agg(arcs: DataFrame, values: DataFrame, agg: Column, name: str = "out") -> DataFrame:
    """agg over columns of values(vid, ...) at each vertex's neighbours."""
    return arcs.join(values, F.col("dst") == F.col("vid")).groupBy("src").agg(agg.alias(name))


def combine_write(df: DataFrame, cell: str, value: str, op: str = "sum", name: str = "value") -> DataFrame:
    """Concurrent writes into cells, combined by op; `arbitrary` takes the least, which is one of them and repeatable."""
    f = F.min if op == "arbitrary" else OPS[op]
    return df.groupBy(cell).agg(f(value).alias(name))


def union_edges(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.unionByName(b).distinct()


def minus_edges(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.subtract(b)


def common_edges(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.intersect(b)


def first_k_neighbors(arcs: DataFrame, k: int) -> DataFrame:
    return arcs.withColumn("_r", F.row_number().over(Window.partitionBy("src").orderBy("dst"))).where(F.col("_r") <= k).drop("_r")


def all_of(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)
