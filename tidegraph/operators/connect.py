"""Connected components in optimal space: shrink the vertex set by a polylogarithmic factor, then run levels on the rest."""

from __future__ import annotations

import math
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tidegraph.functions.session import cut
from tidegraph.operators.baselines import local_finish
from tidegraph.operators.levels import ComponentsResult, LevelConfig, budgeted_components, canonical, init_state, run
from tidegraph.operators.primitives import compose_moves, symmetrize
from tidegraph.operators.shrink import shrink_until


@dataclass(frozen=True)
class EngineConfig:
    levels: LevelConfig = field(default_factory=LevelConfig)
    shrink: str = "auto"  # auto, never, random_mate
    shrink_to: float | None = None  # vertices left before levels start; default n ln^-alpha n
    local_finish_arcs: int | None = None  # a remainder of so many arcs at most is finished in one task; default n^local_exponent
    local_exponent: float = 0.5  # one machine's space as a power of the number of vertices
    seed: int = 0


def needs_shrink(n: int, m: int, space: float | None = None, alpha: float = 5.0) -> bool:
    """False where the graph is dense enough, or the space large enough, for levels to start at once."""
    log = math.log(max(n, 3)) ** alpha
    return not (m >= n * log or (space is not None and space >= m + n * log))


def connected_components(edges: DataFrame, vertices: DataFrame | None = None, cfg: EngineConfig = EngineConfig()) -> ComponentsResult:
    """labels(vertex, component = least id) for edges(u, v) and optional vertices(vid)."""
    arcs = cut(symmetrize(edges))
    ids = arcs.select(F.col("src").alias("vid"))
    everyone = cut((ids if vertices is None else ids.unionByName(vertices.select(F.col("vid").cast("long").alias("vid")))).distinct())
    n, m = everyone.count(), arcs.count()
    small = cfg.local_finish_arcs if cfg.local_finish_arcs is not None else int(n**cfg.local_exponent)
    trace, maps = [], []
    if m > small and cfg.shrink != "never" and needs_shrink(n, m // 2, cfg.levels.space, cfg.levels.alpha):
        target = cfg.shrink_to if cfg.shrink_to is not None else n / math.log(max(n, 3)) ** cfg.levels.alpha
        out = shrink_until(arcs, max(target, 1), cfg.seed, method="random_mate" if cfg.shrink == "random_mate" else "picks", stop_arcs=small)
        arcs, maps = out.arcs, out.maps
        trace += [p.__dict__ | {"ratio": p.ratio, "phase": "shrink"} for p in out.passes]
        m = arcs.count()
    if m == 0:
        return ComponentsResult(canonical(everyone, compose_moves(maps), None), trace)
    if m <= small:
        return ComponentsResult(canonical(everyone, compose_moves(maps), local_finish(arcs)), trace)
    state = run(init_state(edges, None, replace(cfg.levels, n_for_rate=cfg.levels.n_for_rate or n), arcs=arcs))
    mu = state.arcs.groupBy(F.col("src").alias("vid")).agg(F.least(F.min("dst"), F.col("src")).alias("mu"))
    for d in state.done:
        mu = mu.unionByName(d.select("vid", "mu"))
    return ComponentsResult(canonical(everyone, compose_moves([*maps, *state.log]), mu), [*trace, *state.trace], state)


def boosted_components(edges: DataFrame, copies: int = 3, cfg: LevelConfig = LevelConfig()) -> ComponentsResult:
    """Independent copies of the graph in one run: a copy's number is part of every key, so each draws its own coins.

    A copy whose components have all retired is out of the loop; the run goes on until the slowest is done or raises at the cap. All must agree: any
    answer is exact, so a difference is an error. Ids times copies must fit 62 bits.
    """
    both = edges.select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v"))
    many = both.withColumn("_c", F.explode(F.sequence(F.lit(0), F.lit(copies - 1)))).select((F.col("u") * copies + F.col("_c")).alias("u"), (F.col("v") * copies + F.col("_c")).alias("v"))
    out = budgeted_components(many, cfg=cfg)
    each = out.labels.select(F.expr(f"(vertex - pmod(vertex, {copies})) div {copies}").alias("vertex"), F.expr(f"(component - pmod(component, {copies})) div {copies}").alias("component"))
    labels = cut(each.groupBy("vertex").agg(F.min("component").alias("component"), F.max("component").alias("_x"), F.count("*").alias("_n")))
    if not labels.where((F.col("component") != F.col("_x")) | (F.col("_n") != copies)).isEmpty():
        raise RuntimeError(f"{copies} copies do not agree")
    return ComponentsResult(labels.select("vertex", "component"), out.trace, out.state)
