"""The lower bound's reduction: cut a cycle graph by coins, solve the pieces, contract them, and repeat."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tidegraph.functions.coins import coin01
from tidegraph.functions.session import cut
from tidegraph.operators.connect import connected_components
from tidegraph.operators.primitives import contract, symmetrize


def kept_edges(edges: DataFrame, n: int, d_prime: int, seed: int, kind: str = "xx") -> DataFrame:
    """Each edge goes with probability min(1, 2 ln n / D'), by a coin on its two ends in order (any ids)."""
    p = min(1.0, 2 * math.log(max(n, 2)) / d_prime)
    if kind == "md5":
        key = F.concat_ws("-", F.least("u", "v").cast("string"), F.greatest("u", "v").cast("string"))
    else:
        key = F.xxhash64(F.least("u", "v"), F.greatest("u", "v"))
    return edges.where(coin01(key, seed, "cycle", kind=kind) >= p)


def shrink_cycles_once(edges: DataFrame, d_prime: int, seed: int = 0, solver=connected_components, kind: str = "xx") -> tuple[DataFrame, DataFrame, dict]:
    """(edges after contraction, moves, stats). Edges u, v of disjoint cycles."""
    arcs = symmetrize(edges)
    n, m = arcs.select("src").distinct().count(), edges.count()
    rest = cut(kept_edges(edges, n, d_prime, seed, kind))
    labels = solver(rest).labels
    moves = cut(labels.where("vertex <> component").select(F.col("vertex").alias("old"), F.col("component").alias("new")))
    out = cut(contract(arcs, moves).where("src < dst").select(F.col("src").alias("u"), F.col("dst").alias("v")))
    longest = labels.groupBy("component").count().agg(F.max("count")).first()[0] or 1
    removed = m - rest.count()
    return out, moves, {"n": n, "m": m, "removed": removed, "bound": 4 * m * math.log(max(n, 2)) / d_prime, "longest": longest - 1, "d_prime": d_prime, "edges_after": out.count()}


def one_or_two_cycles(edges: DataFrame, d_prime: int | None = None, seed: int = 0, finish: int = 2000, most: int = 60) -> tuple[int, list[dict]]:
    """Number of cycles. A cycle that shrinks to one vertex leaves no arc, so vertices are counted and not arcs."""
    everyone = cut(symmetrize(edges).select(F.col("src").alias("vid")).distinct())
    n = everyone.count()
    d = d_prime or max(8, int(math.log(max(n, 2)) ** 2))
    trace, vertices = [], everyone
    for i in range(most):
        if edges.count() <= finish:
            return connected_components(edges, vertices).labels.select("component").distinct().count(), trace
        edges, moves, stats = shrink_cycles_once(edges, d, seed + i)
        vertices = cut(vertices.join(moves.select(F.col("old").alias("vid")), "vid", "left_anti"))
        trace.append(stats)
    raise RuntimeError(f"no end after {most} passes: {trace[-1]}")
