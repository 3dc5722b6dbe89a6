"""Constant-factor vertex shrink with high probability: pick, untangle, merge stars, thin, merge lone picks.

Every decision reads the frozen input of its step, and the two kinds of moves touch disjoint vertices, so
one simultaneous map results. Only the pick and the contraction touch arcs; all between is vertex-sized.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tidegraph.functions.coins import coin01
from tidegraph.functions.session import cut
from tidegraph.operators.primitives import contract


def split_isolated(vertices: DataFrame, arcs: DataFrame) -> DataFrame:
    """Vertices (vid) that no arc touches."""
    return vertices.join(arcs.select(F.col("src").alias("vid")).distinct(), "vid", "left_anti")


def pick_min_neighbor(arcs: DataFrame, *salt, order: str = "id") -> DataFrame:
    """One pick a vertex: its least neighbour by id, or by a salted hash of it (hash).

    Any total order of the vertices will do. The hash of a long is one to one, so it has no ties; unlike ids it makes many
    local minima where ids rise along paths, so that stars and not only thinned lone picks merge.
    """
    if order not in ("id", "hash"):
        raise ValueError(f"unknown order: {order}")
    least = F.min("dst") if order == "id" else F.min_by("dst", F.xxhash64("dst", *[F.lit(s) for s in salt]))
    return arcs.groupBy(F.col("src").alias("tail")).agg(least.alias("head"))


def break_mutual(picks: DataFrame) -> DataFrame:
    """Of two vertices that pick each other only the lesser keeps its pick; what is left is a forest."""
    back = picks.select(F.col("tail").alias("head"), F.col("head").alias("tail"))
    return picks.join(back.where("tail > head"), ["tail", "head"], "left_anti")


def _centers(picks: DataFrame) -> DataFrame:
    return picks.groupBy("head").agg(F.count("*").alias("c")).where("c > 1").select("head")


def cut_hub_out(picks: DataFrame) -> DataFrame:
    """A vertex that two or more picks point at loses its own."""
    return picks.join(_centers(picks).withColumnRenamed("head", "tail"), "tail", "left_anti")


def merge_stars(picks: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(moves into the centres, picks that neither moved nor point at what moved)."""
    centers = _centers(picks)
    star = picks.join(centers, "head", "left_semi")
    rest = picks.join(centers, "head", "left_anti").join(star.select(F.col("tail").alias("head")), "head", "left_anti")
    return star.select(F.col("tail").alias("old"), F.col("head").alias("new")), rest.select("tail", "head")


def thin(picks: DataFrame, *salt, keep: float = 1 / 3, kind: str = "xx") -> DataFrame:
    return picks.where(coin01(F.col("tail"), *salt, "thin", kind=kind) < keep)


def merge_isolated(picks: DataFrame, isolated: str = "both_ends") -> DataFrame:
    """Moves along picks that touch no other pick (tail_only: whose tail no other pick touches)."""
    ends = picks.select(F.col("tail").alias("v")).unionByName(picks.select(F.col("head").alias("v")))
    busy = ends.groupBy("v").agg(F.count("*").alias("c")).where("c > 1").select("v")
    out = picks.join(busy.withColumnRenamed("v", "tail"), "tail", "left_anti")
    if isolated == "both_ends":
        out = out.join(busy.withColumnRenamed("v", "head"), "head", "left_anti")
    elif isolated != "tail_only":
        raise ValueError(f"unknown: {isolated}")
    return out.select(F.col("tail").alias("old"), F.col("head").alias("new"))


def random_mate_moves(arcs: DataFrame, *salt, kind: str = "xx") -> DataFrame:
    """Tails move to their least head neighbour; shrinks by a constant factor in expectation only."""
    heads = lambda c: coin01(F.col(c), *salt, "mate", kind=kind) < 0.5
    return arcs.where(~heads("src") & heads("dst")).groupBy(F.col("src").alias("old")).agg(F.min("dst").alias("new"))


@dataclass
class Pass:
    number: int
    vertices: int
    arcs: int
    moved: int
    arcs_after: int

    @property
    def ratio(self) -> float:
        return (self.vertices - self.moved) / max(1, self.vertices)


def shrink_moves(arcs: DataFrame, *salt, kind: str = "xx", isolated: str = "both_ends", picks: DataFrame | None = None) -> DataFrame:
    """picks: those of pick_min_neighbor, where they are at hand."""
    picks = cut(cut_hub_out(break_mutual(picks if picks is not None else cut(pick_min_neighbor(arcs)))))
    stars, rest = merge_stars(picks)
    lone = merge_isolated(thin(rest, *salt, kind=kind), isolated)
    return stars.unionByName(lone)


def shrink_once(arcs: DataFrame, *salt, kind: str = "xx", isolated: str = "both_ends", method: str = "picks", picks: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """(contracted arcs, moves). method: picks, or random_mate for the in-expectation baseline."""
    moves = cut(shrink_moves(arcs, *salt, kind=kind, isolated=isolated, picks=picks) if method == "picks" else random_mate_moves(arcs, *salt, kind=kind))
    return cut(contract(arcs, moves)), moves


@dataclass
class Shrunk:
    arcs: DataFrame
    maps: list[DataFrame] = field(default_factory=list)
    passes: list[Pass] = field(default_factory=list)


def shrink_until(arcs: DataFrame, target: float, seed: int = 0, kind: str = "xx", method: str = "picks", stop_arcs: int = 0, most: int = 200, order: str = "hash") -> Shrunk:
    """Passes until at most target vertices (of those that have arcs) or stop_arcs arcs are left.

    Each such vertex has one pick, so the picks count the vertices without a shuffle of their own.
    """
    out = Shrunk(arcs)
    for i in range(most):
        m = out.arcs.count()
        picks = cut(pick_min_neighbor(out.arcs, seed, i, order=order)) if m > stop_arcs else None
        n = picks.count() if picks is not None else 0
        if out.passes:
            out.passes[-1].arcs_after = m
        if m == 0 or n <= target or m <= stop_arcs:
            return out
        out.arcs, moves = shrink_once(out.arcs, seed, i, kind=kind, method=method, picks=picks)
        out.maps.append(moves)
        out.passes.append(Pass(i, n, m, moves.count(), 0))
    raise RuntimeError(f"no end after {most} shrink passes: {out.passes[-3:]}")


