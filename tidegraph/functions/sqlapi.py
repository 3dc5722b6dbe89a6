"""SQL surface: views over a result, link queries."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tidegraph.operators.connect import EngineConfig, connected_components


def register_views(spark: SparkSession, edges: DataFrame, labels: DataFrame) -> None:
    edges.createOrReplaceTempView("edges")
    labels.createOrReplaceTempView("labels")


def sql_components(spark: SparkSession, view: str, cfg: EngineConfig = EngineConfig()) -> DataFrame:
    """labels for a view with columns u, v."""
    return connected_components(spark.table(view), cfg=cfg).labels


def connected(labels: DataFrame, pairs: DataFrame) -> DataFrame:
    """pairs(a, b) with same: whether they are in one component (null if either is unknown)."""
    x, y = (labels.select(F.col("vertex").alias(c), F.col("component").alias(f"_{c}")) for c in "ab")
    return pairs.join(x, "a", "left").join(y, "b", "left").select("a", "b", (F.col("_a") == F.col("_b")).alias("same"))


def component_of(labels: DataFrame, vertices: DataFrame) -> DataFrame:
    return vertices.join(labels, "vertex", "left")


def members_of(labels: DataFrame, vertices: DataFrame) -> DataFrame:
    wanted = vertices.join(labels, "vertex").select(F.col("vertex").alias("of"), "component")
    return wanted.join(labels, "component").select("of", "vertex")


def top_components(labels: DataFrame, k: int) -> DataFrame:
    return labels.groupBy("component").agg(F.count("*").alias("size")).orderBy(F.desc("size"), "component").limit(k)


def component_members(labels: DataFrame, most: int = 1000) -> DataFrame:
    """Arrays of members; components over `most` are given as null and not gathered."""
    sizes = labels.groupBy("component").agg(F.count("*").alias("size"))
    small = labels.join(sizes.where(F.col("size") <= most), "component").groupBy("component").agg(F.sort_array(F.collect_list("vertex")).alias("members"))
    return sizes.join(small, "component", "left")


def component_rollup(labels: DataFrame, attributes: DataFrame, dims: list[str], how: str = "rollup") -> DataFrame:
    """Vertices and components by attributes(vertex, dims...), as rollup or cube."""
    j = attributes.join(labels, "vertex")
    return getattr(j, how)(*dims).agg(F.count("*").alias("vertices"), F.count_distinct("component").alias("components"))


def numbered(labels: DataFrame) -> DataFrame:
    return labels.withColumn("rank", F.row_number().over(Window.partitionBy("component").orderBy("vertex")))


def component_grouping_sets(labels: DataFrame, attributes: DataFrame, sets: list[list[str]]) -> DataFrame:
    """Vertices and components by any sets of attributes(vertex, ...)."""
    dims = list(dict.fromkeys(x for s in sets for x in s))
    return attributes.join(labels, "vertex").groupingSets([[F.col(x) for x in s] for s in sets], *dims).agg(F.count("*").alias("vertices"), F.count_distinct("component").alias("components"))


def approx_components(labels: DataFrame, rsd: float = 0.05) -> DataFrame:
    """The number of components by a sketch of bounded size."""
    return labels.agg(F.approx_count_distinct("component", rsd).alias("components"))


def two_hop_size_estimate(arcs: DataFrame, shares: tuple[float, ...] = (0.5, 0.9, 0.99)) -> DataFrame:
    """Quantiles of the wedges at a vertex, before a linking step: how large the two-hop join would be."""
    deg = arcs.groupBy("src").agg(F.count("*").alias("degree"))
    return deg.agg(F.percentile_approx(F.col("degree") * F.col("degree"), list(shares), 10_000).alias("wedges"))


def register_path_vertices(spark: SparkSession) -> None:
    """SQL table function path_vertices(n): 0 .. n - 1."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="vid long")
    class PathVertices:
        def eval(self, n: int):
            for i in range(n):
                yield (i,)

    spark.udtf.register("path_vertices", PathVertices)
