"""Cost and accuracy measures, bounds, and audits of a run."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tidegraph.functions.session import cut
from tidegraph.operators import packed
from tidegraph.operators.levels import ComponentsResult, State
from tidegraph.operators.primitives import degrees, symmetrize, with_levels


def graph_stats(edges: DataFrame) -> DataFrame:
    deg = degrees(symmetrize(edges))
    return deg.agg(F.count("*").alias("n"), (F.sum("degree") / 2).cast("long").alias("m"), F.max("degree").alias("max_degree"))


def degree_histogram(edges: DataFrame) -> DataFrame:
    return degrees(symmetrize(edges)).groupBy("degree").agg(F.count("*").alias("vertices"))


def component_sizes(labels: DataFrame) -> DataFrame:
    return labels.groupBy("component").agg(F.count("*").alias("size"))


def size_histogram(labels: DataFrame) -> DataFrame:
    return component_sizes(labels).groupBy("size").agg(F.count("*").alias("components"))


def partition_equal(a: DataFrame, b: DataFrame) -> bool:
    """Same sets, whatever their names."""
    j = a.select("vertex", F.col("component").alias("x")).join(b.select("vertex", F.col("component").alias("y")), "vertex", "full_outer")
    pairs = cut(j.select("x", "y").distinct())
    if not pairs.where("x is null or y is null").isEmpty():
        return False
    n = pairs.count()
    return n == pairs.select("x").distinct().count() == pairs.select("y").distinct().count()


def diameters(edges: DataFrame, max_rounds: int = 10_000) -> DataFrame:
    """Exact diameter of each component, by all-pairs frontiers: for graphs of small components."""
    arcs = cut(symmetrize(edges))
    dist = cut(arcs.select(F.col("src").alias("s")).distinct().select("s", F.col("s").alias("t"), F.lit(0).alias("d")))
    frontier, step = dist, 0
    while step < max_rounds:
        step += 1
        reach = frontier.join(arcs, F.col("t") == F.col("src")).select("s", F.col("dst").alias("t")).distinct()
        frontier = cut(reach.join(dist.select("s", "t"), ["s", "t"], "left_anti").withColumn("d", F.lit(step)))
        if frontier.isEmpty():
            break
        dist = cut(dist.unionByName(frontier))
    far = dist.groupBy("s").agg(F.max("d").alias("ecc"), F.min("t").alias("component"))
    return far.groupBy("component").agg(F.max("ecc").alias("diameter"))


def iteration_bound(n: int, diameter: int, beta0: float, max_level: int) -> float:
    """Iterations: four for each of L + 4 log2 D super-iterations, and O(L) more."""
    return 4 * (max_level + 4 * math.log2(max(diameter, 2))) + 8 * (max_level + 1)


def level_bound(n: int, beta0: float) -> float:
    return math.log(max(math.log(max(n, 3)) / math.log(beta0), 1)) / math.log(1.25)


def level_census(result: ComponentsResult, space: float) -> dict:
    return {"max_level": max((t.get("max_level", 0) for t in result.trace), default=0), "peak_sum_sq_budget": max((t.get("sum_sq_budget", 0) for t in result.trace), default=0), "peak_potential": max((t.get("potential", 0) for t in result.trace), default=0), "space": space, "unled": sum(t.get("unled", 0) for t in result.trace)}


def wedge_load(state: State) -> DataFrame:
    """Two-hop candidates of each active vertex that still has room, against its squared capacity. The others link nothing, so nothing is promised for them."""
    leveled = cut(with_levels(state.arcs, state.verts))
    d = leveled.where("sa").groupBy("src", "sl").agg(F.count_if(F.col("dl") >= F.col("sl")).alias("d")).where(F.col("d") < state.cap(F.col("sl"))).select("src")
    own = leveled.where("sl = dl")
    deg = own.groupBy(F.col("src").alias("w")).agg(F.count("*").alias("k"))
    load = own.join(d, "src", "left_semi").join(deg, F.col("dst") == F.col("w")).groupBy("src", "sl").agg(F.sum(F.least(F.col("k"), state.cap(F.col("sl")) + 1)).alias("candidates"))
    return load.select("src", "candidates", (state.cap(F.col("sl")) * (state.cap(F.col("sl")) + 1)).alias("bound"))


def thin_survival_rate(picks: DataFrame, seed: int = 0) -> float:
    """Share of picks on paths that are alone after thinning (4/27 or more expected)."""
    from tidegraph.operators.shrink import merge_isolated, thin

    return merge_isolated(thin(picks, seed)).count() / max(1, picks.count())


def level_catchup(state: State) -> int:
    """Violations of: after one more iteration each vertex's level is at least its neighbours' old ones. Levels follow renames."""
    old = cut(with_levels(state.arcs, state.verts).select("src", "dl"))
    from tidegraph.operators.levels import step

    after = step(state)
    maps = after.log[len(state.log) :]
    where = old.withColumn("now", F.col("src"))
    for m in maps:
        where = where.join(m.select(F.col("old").alias("_o"), F.col("new").alias("_n")), F.col("now") == F.col("_o"), "left").select("src", "dl", F.coalesce("_n", "now").alias("now"))
    return where.join(after.verts, F.col("now") == F.col("vid")).where("level < dl").count()


def reached(trace: list[dict], n: int, beta0: float, exponent: float = 1.25) -> list[dict]:
    """By level: n_i, the vertices that reached it over the run; the budgets that promotions granted; and whether the level
    thinned out as the space bound asks (n_i below n_(i-1) / budget_(i-1)^0.25)."""
    up: dict[int, int] = {}
    for t in trace:
        for level, k in t.get("promoted", {}).items():
            up[level + 1] = up.get(level + 1, 0) + k
    rows, before = [], n
    for level in range(1, max(up, default=0) + 1):
        beta = beta0 ** (exponent**level)
        rows.append({"level": level, "reached": up.get(level, 0), "granted": beta * up.get(level, 0), "thinned": up.get(level, 0) < before * (beta0 ** (exponent ** (level - 1))) ** -0.25})
        before = up.get(level, 0)
    return rows


def load(arcs: DataFrame, parts: int) -> DataFrame:
    """Of an exchange by vertex over `parts` partitions: rows, rows of the largest key and of the largest partition."""
    deg = degrees(arcs)
    size = deg.groupBy(F.pmod(F.hash("src"), F.lit(parts)).alias("p")).agg(F.sum("degree").alias("rows"), F.max("degree").alias("key"))
    return size.agg(F.sum("rows").alias("rows"), F.max("key").alias("largest_key"), F.max("rows").alias("largest_partition"))


def followed(pairs: DataFrame, maps: list[DataFrame], ends: tuple[str, ...]) -> DataFrame:
    """pairs with each end replaced by the vertex that stands for it after the maps, applied oldest first."""
    for m in maps:
        for c in ends:
            pairs = pairs.join(m.select(F.col("old").alias("_o"), F.col("new").alias("_n")), F.col(c) == F.col("_o"), "left").withColumn(c, F.coalesce("_n", c)).drop("_o", "_n")
        pairs = cut(pairs)
    return pairs


def stand_ins(path: list[int], maps: list[DataFrame]) -> list[int]:
    """followed for a few vertices at hand: a filtered read of each map, nothing is joined or written."""
    now = list(path)
    for m in maps:
        moved = {x["old"]: x["new"] for x in m.where(F.col("old").isin(sorted(set(now)))).collect()}  # a row a vertex of the path at most
        now = [moved.get(v, v) for v in now]
    return now


def two_hop_progress(state: State, steps: int = 4) -> dict:
    """Pairs at distance two now, looked at again after `steps` iterations: each is at distance one or less, or both levels have risen."""
    from tidegraph.operators.levels import step

    arcs = state.arcs
    hop = arcs.select(F.col("src").alias("w"), F.col("dst").alias("a")).join(arcs.select(F.col("src").alias("w"), F.col("dst").alias("b")), "w").where("a < b").select("a", "b").distinct()
    far = hop.join(arcs.select(F.col("src").alias("a"), F.col("dst").alias("b")), ["a", "b"], "left_anti")
    old = state.verts.select(F.col("vid").alias("_v"), F.col("level").alias("_l"))
    pairs = cut(far.join(old.withColumnsRenamed({"_v": "a", "_l": "la"}), "a").join(old.withColumnsRenamed({"_v": "b", "_l": "lb"}), "b"))
    after = state
    for _ in range(steps):
        after = step(after)
    pairs = followed(pairs, after.log[len(state.log) :], ("a", "b"))
    now = after.verts.select(F.col("vid").alias("_v"), F.col("level").alias("_l"))
    pairs = pairs.join(now.withColumnsRenamed({"_v": "a", "_l": "na"}), "a", "left").join(now.withColumnsRenamed({"_v": "b", "_l": "nb"}), "b", "left")
    near = after.arcs.select(F.col("src").alias("a"), F.col("dst").alias("b"), F.lit(True).alias("near"))
    pairs = pairs.join(near, ["a", "b"], "left")
    ok = (F.col("a") == F.col("b")) | F.col("near") | ((F.col("na") > F.col("la")) & (F.col("nb") > F.col("lb")))
    row = pairs.agg(F.count("*").alias("n"), F.count_if(F.coalesce(F.col("a") == F.col("b"), F.lit(False)) | F.col("near")).alias("near"), F.count_if(~F.coalesce(ok, F.lit(False))).alias("bad")).first()
    return {"pairs": row["n"], "near": row["near"], "violations": row["bad"]}


def monotone_audit(state: State) -> dict:
    """One iteration: arcs whose ends are afterwards neither one vertex nor neighbours, and vertices whose stand-in is on a lower level."""
    from tidegraph.operators.levels import step

    after = step(state)
    maps = after.log[len(state.log) :]
    arcs = followed(state.arcs.where("src < dst"), maps, ("src", "dst")).where("src <> dst")
    apart = arcs.join(after.arcs, ["src", "dst"], "left_anti").count()
    old = followed(state.verts.select("vid", F.col("level").alias("was")), maps, ("vid",))
    lower = old.join(after.verts, "vid").where("level < was").count()
    return {"apart": apart, "lower": lower}


def mask_of(images: list[int], rose: list[bool], adjacent: set[tuple[int, int]]) -> list[int] | None:
    """Which images stay on the path: ends stay, none twice, neighbours on the path are adjacent, and an image whose level did not rise has one
    dropped within two places. None where there is no such choice by dropping what a shortcut passes over."""
    n = len(images)
    keep = [1] * n
    last = {v: i for i, v in enumerate(images)}
    i = 0
    while i < n:  # a vertex met again: all in between goes, and it stays once (at the path's end if it stands there)
        j = last[images[i]]
        if j > i:
            for k in range(i + 1, j + 1):
                keep[k] = 0
            if j == n - 1:
                keep[j], keep[i] = 1, 0 if i else 1
        i = j + 1
    inside = lambda k: 0 <= k < n
    for i in range(n):
        if keep[i] and not rose[i] and all(keep[k] for k in (i - 2, i - 1, i + 1, i + 2) if inside(k)):
            for drop in (i + 1, i - 1):
                a, b = drop - 1, drop + 1
                if inside(a) and inside(b) and keep[drop] and keep[a] and keep[b] and (images[a], images[b]) in adjacent:
                    keep[drop] = 0
                    break
            else:
                if n > 3:
                    return None
    kept = [images[k] for k in range(n) if keep[k]]
    return keep if all((a, b) in adjacent for a, b in zip(kept, kept[1:], strict=False)) else None


def hand_on(coins: list[float], keep: list[int]) -> list[float]:
    """Coins of the kept: a quarter of what each dropped one has goes to each of the nearest two kept on either side."""
    out = [c if k else 0.0 for c, k in zip(coins, keep, strict=True)]
    for i, k in enumerate(keep):
        if not k:
            for own in ([j for j in range(i - 1, -1, -1) if keep[j]][:2], [j for j in range(i + 1, len(keep)) if keep[j]][:2]):
                for j in own:
                    out[j] += coins[i] / 4
    return [c for c, k in zip(out, keep, strict=True) if k]


def coin_audit(state: State, path: list[int], most: int = 12) -> list[dict]:
    """The coin argument on one path, by super-iterations of four: its length, all coins, the least of coin / 1.25^(r - level), and whether a mask was found.

    Only this path's vertices are gathered; the loop is distributed.
    """
    from tidegraph.operators.levels import forget, step

    given, coins, rows, r = state, [1.0] * len(path), [], 0
    levels = {x["vid"]: x["level"] for x in state.verts.where(F.col("vid").isin(path)).collect()}
    rows.append({"r": 0, "vertices": len(path), "coins": sum(coins), "least": 1.0, "masked": True})
    while len(path) > 3 and r < most:
        before = len(state.log)
        for _ in range(4):
            state = forget(state, step(state)) if state is not given else step(state)
        r += 1
        images = stand_ins(path, state.log[before:])
        own = sorted(set(images))
        now = {x["vid"]: x["level"] for x in state.verts.where(F.col("vid").isin(own)).collect()}
        arcs = packed.among(state.packed, own) if state.packed is not None else state.arcs.where(F.col("src").isin(own) & F.col("dst").isin(own))
        near = {(x["src"], x["dst"]) for x in arcs.collect()}
        if images[0] == images[-1]:
            break
        rose = [now.get(b, 0) > levels.get(a, 0) for a, b in zip(path, images, strict=True)]
        keep = mask_of(images, rose, near)
        if keep is None:
            rows.append({"r": r, "vertices": len(path), "coins": sum(coins), "least": 0.0, "masked": False})
            break
        coins = hand_on(coins, keep)
        path = [v for v, k in zip(images, keep, strict=True) if k]
        levels = {v: now.get(v, 0) for v in path}
        rows.append({"r": r, "vertices": len(path), "coins": sum(coins), "least": min(c / 1.25 ** (r - levels[v]) for c, v in zip(coins, path, strict=True)), "masked": True})
    return rows


def primitive_costs(trace: list[dict]) -> list[dict]:
    """Work and depth by iteration from what it did: rows that go into each primitive, and the primitives in sequence.

    Linking: degree count, list cut, wedge, two dedupes, symmetrize (6); lifting: best neighbour, one contraction (2), if any vertex moved; leaders: count,
    spread, coin, two-hop search of two steps, contraction (6), if any is saturated.
    """
    out = []
    for t in trace:
        arcs = 2 * t["linked"]
        work, depth = 6 * arcs, 6
        if t["lifted"]:
            work, depth = work + 2 * arcs + t["lifted"], depth + 2
        else:
            work, depth = work + arcs, depth + 1
        if t["saturated"]:
            work, depth = work + 6 * arcs + t["saturated"], depth + 6
        else:
            work, depth = work + arcs, depth + 1
        out.append({"iteration": t["iteration"], "work": work, "depth": depth})
    return out
