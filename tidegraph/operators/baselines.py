"""The algorithms the method is compared with. Those known only by their bounds follow the published literature:
hook-and-contract (conditional and star hooking) and random mate; their constants are this engine's choice.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tidegraph.functions.coins import coin01
from tidegraph.functions.session import cut
from tidegraph.operators.levels import ComponentsResult, all_cliques, canonical
from tidegraph.operators.primitives import compose_moves, contract, degrees, symmetrize
from tidegraph.operators.shrink import random_mate_moves, shrink_until


def _start(edges: DataFrame, vertices: DataFrame | None) -> tuple[DataFrame, DataFrame]:
    arcs = cut(symmetrize(edges))
    ids = arcs.select(F.col("src").alias("vid"))
    return arcs, cut((ids if vertices is None else ids.unionByName(vertices.select(F.col("vid").cast("long").alias("vid")))).distinct())


def _mu(arcs: DataFrame) -> DataFrame:
    return arcs.groupBy(F.col("src").alias("vid")).agg(F.least(F.min("dst"), F.col("src")).alias("mu"))


def exponentiation_components(edges: DataFrame, vertices: DataFrame | None = None, max_arcs: int = 50_000_000) -> ComponentsResult:
    """Joins every vertex to its whole two-hop set until cliques are left: log D steps, up to n^2 space. Raises past max_arcs."""
    arcs, everyone = _start(edges, vertices)
    trace = [{"iteration": 0, "edges": arcs.count() // 2}]
    while not all_cliques(arcs):
        load = degrees(arcs).agg(F.sum(F.col("degree") * F.col("degree"))).first()[0]
        if load > 40 * max_arcs:
            raise MemoryError(f"{load} two-hop pairs")
        hop = arcs.select(F.col("src").alias("w"), F.col("dst").alias("v"))
        wide = arcs.select(F.col("src").alias("w2"), F.col("dst").alias("u"))
        two = hop.join(wide, F.col("w") == F.col("w2")).where("v <> u").select(F.col("v").alias("src"), F.col("u").alias("dst"))
        arcs = cut(arcs.unionByName(two).distinct())
        trace.append({"iteration": len(trace), "edges": arcs.count() // 2})
        if 2 * trace[-1]["edges"] > max_arcs:
            raise MemoryError(f"{trace[-1]['edges']} edges after {len(trace) - 1} steps")
    return ComponentsResult(canonical(everyone, None, _mu(arcs)), trace)


def matrix_squaring_components(edges: DataFrame, vertices: DataFrame | None = None, max_entries: int = 50_000_000) -> ComponentsResult:
    """Squares the boolean matrix with its diagonal until it stands still. For small graphs."""
    arcs, everyone = _start(edges, vertices)
    cells = cut(arcs.unionByName(everyone.select(F.col("vid").alias("src"), F.col("vid").alias("dst"))))
    trace, n = [], cells.count()
    while True:
        if n > max_entries:
            raise MemoryError(f"{n} matrix entries")
        right = cells.select(F.col("src").alias("k"), F.col("dst").alias("j"))
        nxt = cut(cells.join(right, F.col("dst") == F.col("k")).select("src", F.col("j").alias("dst")).distinct())
        m = nxt.count()
        trace.append({"iteration": len(trace) + 1, "entries": m})
        if m == n:
            break
        cells, n = nxt, m
    return ComponentsResult(cells.groupBy(F.col("src").alias("vertex")).agg(F.min("dst").alias("component")), trace)


def uniform_degree_components(edges: DataFrame, vertices: DataFrame | None = None, d0: int = 4, rate: float = 3.0, seed: int = 0, max_phases: int = 60) -> ComponentsResult:
    """One global degree target d a phase: link two hops until every vertex has d neighbours or its whole
    component, draw leaders at rate ln n / d, contract the others into a leader beside them, square d."""
    from pyspark.sql import Window

    arcs, everyone = _start(edges, vertices)
    n, d, log, trace = everyone.count(), d0, [], []
    for phase in range(max_phases):
        steps = 0
        while True:
            if all_cliques(arcs):
                return ComponentsResult(canonical(everyone, compose_moves(log), _mu(arcs)), trace)
            deg = cut(degrees(arcs))
            low = deg.where(F.col("degree") < d).select(F.col("src").alias("v"), (d - F.col("degree")).alias("room"))
            lists = arcs.select(F.col("src").alias("w"), F.col("dst").alias("u")).withColumn("r", F.row_number().over(Window.partitionBy("w").orderBy("u"))).where(F.col("r") <= d + 1).drop("r")
            hop = arcs.select(F.col("src").alias("v"), F.col("dst").alias("w")).join(low, "v")
            new = hop.join(lists, "w").where("u <> v").select("v", "u", "room").distinct().join(arcs.select(F.col("src").alias("v"), F.col("dst").alias("u")), ["v", "u"], "left_anti")
            new = cut(new.withColumn("r", F.row_number().over(Window.partitionBy("v").orderBy("u"))).where("r <= room"))
            if new.isEmpty():
                break
            steps += 1
            arcs = cut(symmetrize(arcs.unionByName(new.select(F.col("v").alias("src"), F.col("u").alias("dst"))), "src", "dst"))
        p = min(1.0, rate * math.log(max(n, 2)) / d)
        leader = lambda c: coin01(F.col(c), seed, phase, "uniform") < p
        full = degrees(arcs).where(F.col("degree") >= d).select("src")
        moves = cut(arcs.where(~leader("src") & leader("dst")).join(full, "src", "left_semi").groupBy(F.col("src").alias("old")).agg(F.min("dst").alias("new")))
        log.append(moves)
        arcs = cut(contract(arcs, moves))
        trace.append({"iteration": phase + 1, "d": d, "steps": steps, "moved": moves.count(), "edges": arcs.count() // 2})
        d = min(d * d, 1 << 20)
    raise RuntimeError(f"no end after {max_phases} phases: {trace[-2:]}")


class Forest:
    """Union-find over numpy arrays on one machine, fed in chunks: it holds the vertices seen, not the pairs."""

    def __init__(self) -> None:
        self.ids, self.parent = np.zeros(0, np.int64), np.zeros(0, np.int64)

    def add(self, a: np.ndarray, b: np.ndarray) -> None:
        own, inverse = np.unique(np.concatenate([a, b]), return_inverse=True)
        fresh = own
        if len(self.ids):
            at = np.minimum(np.searchsorted(self.ids, own), len(self.ids) - 1)
            fresh = own[self.ids[at] != own]
        if len(fresh):  # positions move up by the number of new lesser ids; fresh ids are their own parents
            moved = np.arange(len(self.ids)) + np.searchsorted(fresh, self.ids)
            parent = np.arange(len(self.ids) + len(fresh))
            parent[moved] = moved[self.parent]
            ids = np.empty(len(parent), np.int64)
            ids[moved] = self.ids
            ids[np.arange(len(fresh)) + np.searchsorted(self.ids, fresh)] = fresh
            self.ids, self.parent = ids, parent
        parent, at = self.parent, np.searchsorted(self.ids, own)  # sorted look-ups; the pairs' own are by position
        x, y = at[inverse[: len(a)]], at[inverse[len(a) :]]
        while True:  # hook the greater root on the lesser, then jump: sequential in effect, vectorised in form
            x, y = self.root(x), self.root(y)
            open_ = x != y
            if not open_.any():
                return
            x, y = x[open_], y[open_]
            np.minimum.at(parent, np.maximum(x, y), np.minimum(x, y))

    def root(self, x: np.ndarray) -> np.ndarray:
        """Of each position, whose path is halved on the way."""
        while True:
            up = self.parent[x]
            far = self.parent[up]
            if (far == up).all():
                return up
            self.parent[x] = far
            x = far

    def labels(self) -> pd.DataFrame:
        while True:
            up = self.parent[self.parent]
            if (up == self.parent).all():
                return pd.DataFrame({"vid": self.ids, "mu": self.ids[up] if len(up) else self.ids})
            self.parent = up


def local_labels(pairs, chunk: int = 4_000_000) -> pd.DataFrame:
    """Least vertex of each one's component, from an iterable of (a, b) arrays."""
    forest, held, n = Forest(), [], 0
    for a, b in pairs:
        held, n = [*held, (a, b)], n + len(a)
        if n >= chunk:
            forest.add(*(np.concatenate(x) for x in zip(*held, strict=True)))
            held, n = [], 0
    if n:
        forest.add(*(np.concatenate(x) for x in zip(*held, strict=True)))
    return forest.labels()


def local_finish(arcs: DataFrame) -> DataFrame:
    """(vid, mu) for a remainder whose vertices are known to fit one task."""

    def run(frames):
        out = local_labels((f["src"].to_numpy(), f["dst"].to_numpy()) for f in frames)
        for at in range(0, len(out), 1_000_000):
            yield out.iloc[at : at + 1_000_000]

    return arcs.where("src < dst").coalesce(1).mapInPandas(run, "vid long, mu long")


def local_components(edges: DataFrame, vertices: DataFrame | None = None, max_arcs: int = 20_000_000) -> ComponentsResult:
    """The sequential yardstick: one task holds two numbers a vertex, however many edges there are. A graph of more than max_arcs
    vertices, which do not fit one task, is shrunk to so many first."""
    pairs = cut(edges.select(F.least("u", "v").cast("long").alias("src"), F.greatest("u", "v").cast("long").alias("dst")).where("u is not null and v is not null and src <> dst"))
    ids = pairs.select(F.col("src").alias("vid")).unionByName(pairs.select(F.col("dst").alias("vid")))
    everyone = cut((ids if vertices is None else ids.unionByName(vertices.select(F.col("vid").cast("long").alias("vid")))).distinct())
    if everyone.count() <= max_arcs:
        return ComponentsResult(canonical(everyone, None, local_finish(pairs)), [])
    out = shrink_until(cut(symmetrize(pairs, "src", "dst")), max_arcs)
    return ComponentsResult(canonical(everyone, compose_moves(out.maps), local_finish(out.arcs)), [p.__dict__ | {"ratio": p.ratio} for p in out.passes])


def hook_contract_components(edges: DataFrame, vertices: DataFrame | None = None, variant: str = "conditional", local_arcs: int = 0, max_rounds: int = 200) -> ComponentsResult:
    """Roots hook on lesser neighbours and pointers jump; then the forest is contracted.

    conditional: every root hooks on its least neighbour if that is lesser, trees are flattened
    fully before contracting. star: one jump a round; roots that stand still hook on any neighbour tree.
    local_arcs: a remainder of at most so many arcs is finished in one task.
    """
    arcs, everyone = _start(edges, vertices)
    log, trace = [], []
    for i in range(max_rounds):
        m = arcs.count()
        if m == 0:
            return ComponentsResult(canonical(everyone, compose_moves(log), None), trace)
        if m <= local_arcs:
            return ComponentsResult(canonical(everyone, compose_moves(log), local_finish(arcs)), trace)
        least = arcs.groupBy(F.col("src").alias("old")).agg(F.min("dst").alias("new"))
        hooks = least.where("new < old")
        if variant == "star":  # local minima that nobody hooked on would stand still: they hook upwards
            still = least.where("new > old").join(hooks.select(F.col("new").alias("old")).distinct(), "old", "left_anti")
            hooks = hooks.unionByName(still)
        elif variant != "conditional":
            raise ValueError(f"unknown variant: {variant}")
        hooks, jumps = cut(hooks), 0
        while variant == "conditional" or jumps == 0:
            up = hooks.select(F.col("old").alias("_o"), F.col("new").alias("_n"))
            nxt = cut(hooks.join(up, F.col("new") == F.col("_o"), "left").select("old", F.coalesce("_n", "new").alias("new"), F.col("_n").isNotNull().alias("_moved")))
            hooks, jumps = nxt.select("old", "new"), jumps + 1
            if nxt.where("_moved").isEmpty():
                break
        log.append(hooks)
        arcs = cut(contract(arcs, hooks))
        trace.append({"iteration": i + 1, "edges": m // 2, "jumps": jumps})
    raise RuntimeError(f"no end after {max_rounds} rounds")


def random_mate_components(edges: DataFrame, vertices: DataFrame | None = None, seed: int = 0, bounded: bool = False, max_rounds: int = 400) -> ComponentsResult:
    """Tails join a head beside them. bounded: of each round's joins only a third, drawn by coin, take place."""
    arcs, everyone = _start(edges, vertices)
    log, trace = [], []
    for i in range(max_rounds):
        m = arcs.count()
        trace.append({"iteration": i, "edges": m // 2})
        if m == 0:
            return ComponentsResult(canonical(everyone, compose_moves(log), None), trace)
        moves = random_mate_moves(arcs, seed, i)
        log.append(cut(moves.where(coin01(F.col("old"), seed, i, "bound") < 1 / 3) if bounded else moves))  # cut: later rounds and the composition read it
        arcs = cut(contract(arcs, log[-1]))
    raise RuntimeError(f"no end after {max_rounds} rounds")


def shrink_only_components(edges: DataFrame, vertices: DataFrame | None = None, seed: int = 0, method: str = "picks", kind: str = "xx", local_arcs: int = 0) -> ComponentsResult:
    """Shrink passes until no arc is left: the O(log n)-round family."""
    arcs, everyone = _start(edges, vertices)
    out = shrink_until(arcs, 0, seed, kind, method, local_arcs)
    final = local_finish(out.arcs) if local_arcs else None
    return ComponentsResult(canonical(everyone, compose_moves(out.maps), final), [p.__dict__ | {"ratio": p.ratio} for p in out.passes])


def label_flood_components(edges: DataFrame, vertices: DataFrame | None = None, max_rounds: int = 20_000) -> ComponentsResult:
    """Each vertex takes the least label around it, until none changes: D rounds."""
    arcs, everyone = _start(edges, vertices)
    labels, rounds = cut(everyone.select("vid", F.col("vid").alias("mu"))), 0
    while rounds < max_rounds:
        seen = arcs.join(labels, F.col("dst") == F.col("vid")).groupBy("src").agg(F.min("mu").alias("m"))
        nxt = cut(labels.join(seen, F.col("vid") == F.col("src"), "left").select("vid", F.least("mu", "m").alias("mu"), (F.col("m") < F.col("mu")).alias("_c")))
        rounds += 1
        labels = nxt.select("vid", "mu")
        if nxt.where("_c").isEmpty():
            return ComponentsResult(labels.select(F.col("vid").alias("vertex"), F.col("mu").alias("component")), [{"iteration": rounds, "edges": arcs.count() // 2}])
    raise RuntimeError(f"no end after {rounds} rounds")
