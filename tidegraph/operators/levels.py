"""Components by levels and budgets: link two hops within budget, lift to the highest neighbour, contract into leaders.

A vertex of level i has budget beta0 ** (1.25 ** i); its integer part is the capacity used both for
linking and for saturation. Each iteration keeps arcs symmetric, loop-free and distinct, and joins only
vertices of one component, so when every component is a clique the answer is exact whatever the coins
were. Coins are hashes of (vertex, seed, iteration), one-step maps go to a log that is composed at the end.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field, replace

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tidegraph.functions.coins import coin01
from tidegraph.functions.keyed import spread
from tidegraph.functions.session import cut, dropped
from tidegraph.operators import packed
from tidegraph.operators.primitives import compose_moves, symmetrize, with_levels


@dataclass(frozen=True)
class LevelConfig:
    beta0: float | None = None
    space: float | None = None
    alpha: float = 5.0
    exponent: float = 1.25
    leader_rate: float = 3.0
    rule: str = "exact"  # exact, mpc, skip_lifted
    pick: str = "min_id"  # min_id, hash
    saturate_at_least: bool = True
    retire_cliques: bool = True
    max_iterations: int = 120
    seed: int = 0
    coin: str = "xx"
    trace: bool = False
    n_for_rate: int | None = None


@dataclass(frozen=True)
class SpaceBudget:
    n: int
    m: int
    space: float
    beta0: float


def plan_budget(n: int, m: int, cfg: LevelConfig = LevelConfig()) -> SpaceBudget:
    """Total space and first budget sqrt(space / n); budgets below 2 would never grow.

    The space is m + n ln^alpha n, but at least n (rate ln n)^4: from a first budget of (rate ln n)^2 on, a leader's squared
    budget b^2.5 is paid for by the b / (rate ln n) vertices that join it. That is what `alpha large enough` means at finite n.
    """
    log = math.log(max(n, 3))
    space = cfg.space or m + n * max(log**cfg.alpha, (cfg.leader_rate * log) ** 4)
    beta0 = cfg.beta0 if cfg.beta0 is not None else max(2.0, math.sqrt(space / max(n, 1)))
    if beta0 < 2:
        raise ValueError("the first budget must be 2 or more")
    return SpaceBudget(n, m, space, beta0)


@dataclass
class State:
    arcs: DataFrame
    verts: DataFrame  # vid, level, active
    budget: SpaceBudget
    cfg: LevelConfig
    iteration: int = 0
    log: list[DataFrame] = field(default_factory=list)
    done: list[DataFrame] = field(default_factory=list)  # vid, mu of finished cliques
    trace: list[dict] = field(default_factory=list)
    leveled: DataFrame | None = None  # arcs with level and active flag of both ends, where a step left them
    packed: packed.Packed | None = None  # the same graph as packed lists, which the frames above then read

    @property
    def seen(self) -> DataFrame:
        return self.leveled if self.leveled is not None else with_levels(self.arcs, self.verts)

    def beta(self, level: Column) -> Column:
        return F.pow(F.lit(float(self.budget.beta0)), F.pow(F.lit(self.cfg.exponent), level))

    def cap(self, level: Column) -> Column:
        return F.floor(F.least(self.beta(level), F.lit(1e15))).cast("long")


def init_state(edges: DataFrame, vertices: DataFrame | None = None, cfg: LevelConfig = LevelConfig(), arcs: DataFrame | None = None) -> State:
    """Level 0 and active everywhere. vertices (vid) may add isolated ones."""
    arcs = arcs if arcs is not None else cut(symmetrize(edges))
    ids = arcs.select(F.col("src").alias("vid"))
    ids = (ids if vertices is None else ids.unionByName(vertices.select(F.col("vid").cast("long").alias("vid")))).distinct()
    verts = cut(ids.select("vid", F.lit(0).alias("level"), F.lit(True).alias("active")))
    return State(arcs, verts, plan_budget(verts.count(), arcs.count() // 2, cfg), cfg)


def clique_components(arcs: DataFrame) -> DataFrame:
    """mu (least id of a closed neighbourhood), size, is_clique. A group is a finished clique if every member sees
    exactly the others: all arcs of its members stay inside it and each has size - 1 of them."""
    mu = arcs.groupBy(F.col("src").alias("vid")).agg(F.least(F.min("dst"), F.col("src")).alias("mu"), F.count("*").alias("deg"))
    far = mu.select(F.col("vid").alias("dst"), F.col("mu").alias("mu2"))
    same = arcs.join(mu, F.col("src") == F.col("vid")).join(far, "dst").groupBy("vid", "mu", "deg").agg(F.min(F.col("mu") == F.col("mu2")).alias("inside"))
    groups = same.groupBy("mu").agg(F.count("*").alias("size"), F.min("inside").alias("inside"), F.min("deg").alias("lo"), F.max("deg").alias("hi"))
    return groups.select("mu", "size", (F.col("inside") & (F.col("lo") == F.col("size") - 1) & (F.col("hi") == F.col("size") - 1)).alias("is_clique"))


def all_cliques(arcs: DataFrame) -> bool:
    """The same test by one minimum and one count: every vertex shares its mu with exactly its neighbours."""
    mu = arcs.groupBy(F.col("src").alias("vid")).agg(F.least(F.min("dst"), F.col("src")).alias("mu"), F.count("*").alias("deg"))
    return mu.groupBy("mu").agg(F.count("*").alias("k"), F.sum("deg").alias("d"), F.max("deg").alias("hi")).where("d <> k * (k - 1) or hi <> k - 1").isEmpty()


def degree_at_or_above(leveled: DataFrame) -> DataFrame:
    return leveled.groupBy("src").agg(F.count_if(F.col("dl") >= F.col("sl")).alias("d"))


def same_level_two_hop(leveled: DataFrame) -> DataFrame:
    """(v, u): u shares a neighbour with v, all three on one level; without v and its neighbours.

    A vertex with one neighbour of its level (lone) has each candidate through that one only and no arc to any, so its pairs need no
    dedupe and no look-up, and are not shuffled; such pairs are all but a few where hubs have leaves. Hubs are dealt over salts.
    """
    own = leveled.where("sl = dl").select("src", "dst")
    lone = own.groupBy("src").agg(F.count("*").alias("k")).where("k = 1").select(F.col("src").alias("dst"), F.lit(True).alias("lone"))
    own = cut(own.join(lone, "dst", "left").select("src", "dst", F.coalesce("lone", F.lit(False)).alias("lone")))
    a = own.select(F.col("src").alias("w"), F.col("dst").alias("v"), F.col("lone").alias("vlone"))
    b = own.select(F.col("src").alias("w"), F.col("dst").alias("u"), F.col("lone").alias("ulone"))
    a, b = spread(a, b, ["w"])
    wedge = a.join(b, ["w", "_salt"]).where("v <> u")
    once = wedge.where("vlone or ulone").select("v", "u")
    again = wedge.where("not vlone and not ulone").select("v", "u").distinct()
    return once.unionByName(again.join(leveled.select(F.col("src").alias("v"), F.col("dst").alias("u")), ["v", "u"], "left_anti"))


def _order(state: State, col: str = "u") -> list:
    return [F.col(col)] if state.cfg.pick == "min_id" else [F.xxhash64(F.col(col), F.lit(state.cfg.seed), F.lit(state.iteration)), F.col(col)]


LARGE = 1_000_000  # arcs from which hubs are looked for
PACKED = 250_000  # ids that a vertex's candidates may be in one row; beyond, each is a row of its own
ENDS = ("src", "dst", "sl", "sa", "dl", "da")


def link_two_hops(state: State, leveled: DataFrame | None = None) -> DataFrame:
    """arcs with each active vertex filled up to its capacity from its two-hop set."""
    return link_leveled(state, leveled if leveled is not None else cut(state.seen)).select("src", "dst")


def link_leveled(state: State, leveled: DataFrame) -> DataFrame:
    """The same on arcs that carry the levels of their ends, which the new arcs get too.

    Middle lists are cut at capacity + 1 before the wedge join: a full list alone fills v, as at most d_v
    of it are neighbours and one is v. So wedges stay within the sum of squared capacities. On large graphs the cut has a
    literal bound too (that of the highest level), so a hub's list is cut before it is shuffled, and the wedges at a hub are dealt over salts.
    """
    cfg = state.cfg
    if cfg.rule not in ("exact", "mpc", "skip_lifted"):
        raise ValueError(f"unknown rule: {cfg.rule}")
    exact, large = cfg.rule == "exact", 2 * state.budget.m > LARGE
    room = leveled.groupBy(F.col("src").alias("v"), F.col("sl").alias("vl"), F.col("sa").alias("va")).agg(F.count_if(F.col("dl") >= F.col("sl")).alias("d"), F.count_if(F.col("dl") == F.col("sl")).alias("same"), F.max("dl").alias("top"))
    room = room.where("va").withColumn("room", state.cap(F.col("vl")) - F.col("d")).where("room > 0" + (" and top <= vl" if cfg.rule == "skip_lifted" else "")).select("v", "vl", "room", "same")
    top, widest = 0, 0
    if exact or large:
        top = leveled.agg(F.max("sl")).first()[0] or 0
    if exact:
        room = cut(room)
        widest = room.agg(F.max("same")).first()[0] or 0
    most = int(min(state.budget.beta0 ** (cfg.exponent**top), 2**31 - 2)) + 1
    # w's neighbours as seen from w: those on w's level (exact), or on at least v's level (others)
    lists = (leveled.where("sl = dl") if exact else leveled).select(F.col("src").alias("w"), F.col("dst").alias("u"), F.col("dl").alias("ul"), F.col("da").alias("ua"))
    lists = lists.withColumn("_r", F.row_number().over(Window.partitionBy("w", *([] if exact else ["ul"])).orderBy(*_order(state))))
    if large:
        lists = lists.where(F.col("_r") <= most)
    lists = lists.where(F.col("_r") <= state.cap(F.col("ul")) + 1).drop("_r")
    hops = leveled.where("sl = dl" if exact else "dl >= sl").select(F.col("src").alias("v"), F.col("dst").alias("w")).join(room.drop("same"), "v")
    packed = exact and widest * most <= PACKED
    if packed:
        lists = lists.groupBy("w").agg(F.collect_list("u").alias("us"), F.collect_list(F.when(~F.col("ua"), F.col("u"))).alias("off"))
    on = ["w"]
    if large:
        hops, lists = spread(cut(hops), cut(lists), ["w"])
        on = ["w", "_salt"]
    if packed:
        new = picked_of_lists(state, hops.join(lists, on))
    else:
        wedge = hops.join(lists, on).where("u <> v" + (" and ul = vl" if exact else " and ul >= vl")).select("v", "u", "vl", "ul", "ua", "room").distinct()
        new = wedge.join(leveled.select(F.col("src").alias("v"), F.col("dst").alias("u")), ["v", "u"], "left_anti")
        new = new.withColumn("_r", F.row_number().over(Window.partitionBy("v").orderBy(*_order(state)))).where("_r <= room")
    return leveled.select(*ENDS).unionByName(both_ways(new))


def picked_of_lists(state: State, seen: DataFrame) -> DataFrame:
    """New (v, u, vl, ul, ua) from a row for each v and middle w with w's list: one array for each v instead of a row for each wedge. The
    middles are all of v's neighbours on its level, so no look-up of arcs is needed."""
    of = seen.groupBy("v", "vl", "room").agg(F.flatten(F.collect_list("us")).alias("us"), F.array_distinct(F.flatten(F.collect_list("off"))).alias("off"), F.collect_list("w").alias("ws"))
    free = F.array_except("us", F.array_append("ws", F.col("v")))  # without repeats
    if state.cfg.pick == "min_id":
        first = F.sort_array(free)
    else:
        keyed = F.sort_array(F.transform(free, lambda u: F.struct(F.xxhash64(u, F.lit(state.cfg.seed), F.lit(state.iteration)).alias("h"), u.alias("u"))))
        first = F.transform(keyed, lambda x: x["u"])
    of = of.select("v", "vl", "off", F.slice(first, F.lit(1), F.least(F.col("room"), F.lit(2**31 - 2)).cast("int")).alias("us"))
    return of.select("v", "vl", "off", F.explode("us").alias("u")).select("v", "u", "vl", F.col("vl").alias("ul"), (~F.array_contains("off", F.col("u"))).alias("ua"))


def both_ways(new: DataFrame) -> DataFrame:
    """Arcs with levels for new links (v, u), which may be there from either end: deduped as pairs, one row for both directions. None is an arc yet."""
    up = F.col("v") < F.col("u")
    ends = {"a": ("v", "u"), "b": ("u", "v"), "al": ("vl", "ul"), "bl": ("ul", "vl"), "aa": ("va", "ua"), "ba": ("ua", "va")}
    pairs = new.withColumn("va", F.lit(True)).select(*[F.when(up, F.col(x)).otherwise(F.col(y)).alias(name) for name, (x, y) in ends.items()]).distinct()
    way = lambda x, y: F.struct(F.col(x).alias("src"), F.col(y).alias("dst"), F.col(f"{x}l").alias("sl"), F.col(f"{x}a").alias("sa"), F.col(f"{y}l").alias("dl"), F.col(f"{y}a").alias("da"))
    return pairs.select(F.inline(F.array(way("a", "b"), way("b", "a")))).select(*ENDS)


def best_neighbor(leveled: DataFrame) -> DataFrame:
    """(v, own level, h, h_level): the neighbour of highest level, the least id of equals."""
    best = leveled.groupBy("src", "sl").agg(F.max(F.struct(F.col("dl").alias("l"), (-F.col("dst")).alias("i"))).alias("b"))
    return best.select(F.col("src").alias("v"), "sl", (-F.col("b.i")).alias("h"), F.col("b.l").alias("h_level"))


def lift_moves(leveled: DataFrame) -> DataFrame:
    """Every vertex below some neighbour moves to the best one; only up-arcs take part in the aggregate."""
    return best_neighbor(leveled.where("dl > sl")).select(F.col("v").alias("old"), F.col("h").alias("new"))


def renamed(leveled: DataFrame, changes: DataFrame) -> DataFrame:
    """Contraction of arcs with levels: changes(old, new, level, active), one step; a vertex that stays but changes has itself as new."""
    out = leveled
    for end, level, active in (("src", "sl", "sa"), ("dst", "dl", "da")):
        own = changes.select(F.col("old").alias("_o"), F.col("new").alias("_n"), F.col("level").alias("_l"), F.col("active").alias("_a"))
        out = out.join(own, F.col(end) == F.col("_o"), "left").withColumns({end: F.coalesce("_n", end), level: F.coalesce("_l", level), active: F.coalesce("_a", active)}).drop("_o", "_n", "_l", "_a")
    return out.where("src <> dst").select(*ENDS).distinct()


def lift_leveled(leveled: DataFrame) -> tuple[DataFrame, DataFrame | None]:
    """(arcs with levels, moves or None). A vertex that moves and is moved to stays as an inactive one."""
    best = leveled.where("dl > sl").groupBy("src").agg(F.max(F.struct(F.col("dl").alias("l"), (-F.col("dst")).alias("i"), F.col("da").alias("a"))).alias("b"))
    moves = cut(best.select(F.col("src").alias("old"), (-F.col("b.i")).alias("new"), F.col("b.l").alias("level"), F.col("b.a").alias("active")))
    if moves.isEmpty():
        return leveled, None
    gone = moves.select(F.col("old").alias("_g"))
    changes = moves.join(gone, F.col("new") == F.col("_g"), "left").select("old", "new", "level", (F.col("active") & F.col("_g").isNull()).alias("active"))
    return cut(renamed(leveled, changes)), moves.select("old", "new")


def advanced(verts: DataFrame, leveled: DataFrame, lifted: DataFrame | None, changes: DataFrame | None) -> DataFrame:
    """verts after a step: lifted ones are inactive and go when no arc is left; contracted ones go; leaders rise."""
    out = verts
    if lifted is not None:
        out = out.join(lifted.select(F.col("old").alias("_o")), F.col("vid") == F.col("_o"), "left").select("vid", "level", (F.col("active") & F.col("_o").isNull()).alias("active"))
    if changes is not None:
        out = out.join(changes.where("old <> new").select(F.col("old").alias("vid")), "vid", "left_anti")
        out = out.join(changes.where("old = new").select(F.col("old").alias("vid"), F.col("level").alias("_l")), "vid", "left").select("vid", F.coalesce("_l", "level").alias("level"), "active")
    return drop_isolated_inactive(out, leveled)


def lift_to_higher_level(state: State) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(arcs, verts, moves): one direct rename each, chains are left for the next iteration."""
    leveled, moves = lift_leveled(cut(state.seen))
    moves_or_none = moves if moves is not None else state.arcs.select(F.col("src").alias("old"), F.col("dst").alias("new")).limit(0)
    return leveled.select("src", "dst"), cut(advanced(state.verts, leveled, moves, None)), moves_or_none


def drop_isolated_inactive(verts: DataFrame, arcs: DataFrame) -> DataFrame:
    touched = arcs.select(F.col("src").alias("vid")).distinct().withColumn("_t", F.lit(True))
    return verts.join(touched, "vid", "left").where("active or _t").select("vid", "level", "active")


def saturated_direct(state: State, leveled: DataFrame) -> DataFrame:
    """(v, level): active with at least capacity active neighbours of its level."""
    full = F.col("c") >= state.cap(F.col("sl")) if state.cfg.saturate_at_least else F.col("c") > state.beta(F.col("sl"))
    return leveled.where("sa and da and sl = dl").groupBy("src", "sl").agg(F.count("*").alias("c")).where(full).select(F.col("src").alias("v"), F.col("sl").alias("level"))


def saturated_spread(leveled: DataFrame, direct: DataFrame) -> DataFrame:
    """direct, and active vertices with a direct one of their level beside them (one step)."""
    seen = leveled.where("sa and sl = dl").join(direct.select(F.col("v").alias("dst")), "dst", "left_semi").select(F.col("src").alias("v"), F.col("sl").alias("level"))
    return direct.unionByName(seen).distinct()


def draw_leaders(state: State, saturated: DataFrame) -> DataFrame:
    n = state.cfg.n_for_rate or state.budget.n
    p = F.least(F.lit(1.0), F.lit(state.cfg.leader_rate * math.log(max(n, 2))) / state.beta(F.col("level")))
    return saturated.where(coin01(F.col("v"), state.cfg.seed, state.iteration, "leader", kind=state.cfg.coin) < p)


def leader_within_two_hops(leveled: DataFrame, leaders: DataFrame) -> DataFrame:
    """(v, leader, hops): least leader among same-level neighbours, else among theirs."""
    own = leveled.where("sl = dl").select("src", "dst")
    one = own.join(leaders.select(F.col("v").alias("dst")), "dst", "left_semi").groupBy("src").agg(F.min("dst").alias("pick"))
    two = own.join(one.select(F.col("src").alias("dst"), F.col("pick")), "dst").groupBy("src").agg(F.min("pick").alias("pick2"))
    out = two.join(one, "src", "full_outer").select(F.col("src").alias("v"), F.coalesce("pick", "pick2").alias("leader"), F.when(F.col("pick").isNotNull(), 1).otherwise(2).alias("hops"))
    return out.where("v <> leader")


def contract_leveled(state: State, leveled: DataFrame) -> tuple[DataFrame, DataFrame | None, dict]:
    """(arcs with levels, changes or None, counters): promotion and moves are decided on the state as it was and applied together.

    promoted: leaders by the level they leave. A saturated vertex without a leader in reach (unled) keeps its place and draws again.
    """
    direct = cut(saturated_direct(state, leveled))
    if direct.isEmpty():
        return leveled, None, {"saturated": 0, "leaders": 0, "unled": 0, "contracted": 0, "two_hop": 0, "promoted": {}}
    sat = saturated_spread(leveled, direct)
    drawn = draw_leaders(state, sat).select("v", F.lit(True).alias("leader"))
    sat = cut(sat.join(drawn, "v", "left").withColumn("leader", F.coalesce("leader", F.lit(False))))
    leaders = sat.where("leader").select("v", "level")
    found = leader_within_two_hops(leveled, leaders).join(sat.where("not leader").select("v", "level"), "v")
    changes = cut(found.select(F.col("v").alias("old"), F.col("leader").alias("new"), (F.col("level") + 1).alias("level"), F.lit(True).alias("active"), "hops").unionByName(leaders.select(F.col("v").alias("old"), F.col("v").alias("new"), (F.col("level") + 1).alias("level"), F.lit(True).alias("active"), F.lit(0).alias("hops"))))
    n_sat = sat.count()
    rows = changes.groupBy("level", "hops").count().collect()
    led, up = sum(r["count"] for r in rows), {r["level"] - 1: r["count"] for r in rows if r["hops"] == 0}
    seen = {"saturated": n_sat, "leaders": sum(up.values()), "unled": n_sat - led, "contracted": led - sum(up.values()), "two_hop": sum(r["count"] for r in rows if r["hops"] == 2), "promoted": up}
    return cut(renamed(leveled, changes)), changes, seen


def contract_saturated(state: State) -> tuple[DataFrame, DataFrame, DataFrame | None, dict]:
    """(arcs, verts, moves, counters)."""
    leveled, changes, seen = contract_leveled(state, cut(state.seen))
    if changes is None:
        return state.arcs, state.verts, None, seen
    return leveled.select("src", "dst"), cut(advanced(state.verts, leveled, None, changes)), changes.where("old <> new").select("old", "new"), seen


WIDEST = 20_000_000  # vertices up to which a vertex's list is one row; beyond, steps work by rows


def packable(state: State) -> bool:
    return state.cfg.rule == "exact" and state.cfg.pick == "min_id" and state.cfg.coin == "xx" and state.budget.n <= WIDEST


def known_of(state: State) -> dict:
    """Capacities, budgets and leader rates by level, and the salt of the coins."""
    def beta(level: int) -> float:
        try:
            return float(state.budget.beta0) ** (state.cfg.exponent**level)
        except OverflowError:
            return math.inf

    betas = np.array([beta(i) for i in range(packed.LEVELS)])
    rate = state.cfg.leader_rate * math.log(max(state.cfg.n_for_rate or state.budget.n, 2))
    return {"beta": betas, "cap": np.floor(np.minimum(betas, 1e15)).astype(np.int64), "rate": np.minimum(1.0, rate / betas), "at_least": state.cfg.saturate_at_least, "seed": state.cfg.seed, "iteration": state.iteration}


def pack(state: State) -> packed.Packed:
    if state.packed is not None:
        return state.packed
    far = state.verts.select(F.col("vid").alias("dst"), F.col("level").alias("dl"), F.col("active").alias("da"))
    arcs = state.leveled if state.leveled is not None else state.arcs.join(far, "dst")
    parts = int(arcs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return packed.packed_of(arcs, state.verts, max(parts, -(-2 * state.budget.m // packed.ARCS_A_PART)), known_of(state))


def repacked(state: State, graph: packed.Packed) -> State:
    leveled = packed.leveled_of(graph.rows)
    return replace(state, packed=graph, leveled=leveled, arcs=leveled.select("src", "dst"), verts=packed.verts_of(graph.rows))


def forget(old: State, new: State) -> State:
    """Deletes the packed lists of a state that was replaced by new."""
    if old.packed is not None and new.packed is not None and old.packed.rows is not new.packed.rows:
        dropped(old.packed.rows)
    return new


def retire(state: State) -> State:
    """Moves finished cliques out of the loop, so a component costs by its own diameter. The log says in which iteration."""
    if packable(state):
        given = pack(state)
        graph, gone = packed.retired(given, known_of(state))
        if gone is not None and state.packed is None:
            dropped(given.rows)
        state = repacked(state, graph)
        return state if gone is None else replace(state, done=[*state.done, gone.withColumn("iteration", F.lit(state.iteration))])
    return retire_by_rows(state)


def retire_by_rows(state: State) -> State:
    mu = state.arcs.groupBy(F.col("src").alias("vid")).agg(F.least(F.min("dst"), F.col("src")).alias("mu"))
    done = cut(mu.join(clique_components(state.arcs).where("is_clique").select("mu"), "mu", "left_semi").select("vid", "mu", F.lit(state.iteration).alias("iteration")))
    if done.isEmpty():
        return state
    keep = done.select(F.col("vid").alias("src"))
    leveled = cut(state.seen.join(keep, "src", "left_anti").select(*ENDS))
    return replace(state, arcs=leveled.select("src", "dst"), leveled=leveled, verts=state.verts.join(done.select("vid"), "vid", "left_anti"), done=[*state.done, done])


def remaining_budget(state: State) -> DataFrame:
    """Per vertex max(0, budget - degree) if active, else 0."""
    left = F.when(F.col("active"), F.greatest(F.lit(0.0), state.beta(F.col("level")) - F.coalesce("deg", F.lit(0)))).otherwise(F.lit(0.0))
    if state.packed is not None:
        return packed.degrees_of(state.packed).select("vid", "level", left.alias("remaining"))
    deg = state.arcs.groupBy(F.col("src").alias("vid")).agg(F.count("*").alias("deg"))
    return state.verts.join(deg, "vid", "left").select("vid", "level", left.alias("remaining"))


def measured(state: State) -> dict:
    m = state.packed.n[packed.GROWN] // 2 if state.packed is not None else state.arcs.count() // 2
    left = remaining_budget(state).agg(F.count("*"), F.sum("remaining"), F.max("level")).first()
    b = state.beta(F.col("level"))
    active, sq = state.verts.where("active").agg(F.count("*"), F.sum(b * b)).first()
    return {"iteration": state.iteration, "super_iteration": -(-state.iteration // 4), "edges": m, "vertices": left[0], "active": active, "max_level": left[2] or 0, "remaining_budget": left[1] or 0.0, "potential": m + (left[1] or 0.0), "sum_sq_budget": sq or 0.0}


@dataclass
class ComponentsResult:
    labels: DataFrame  # vertex, component (least id)
    trace: list[dict]
    state: State | None = None


def step(state: State) -> State:
    """One iteration: link, lift, contract."""
    if not packable(state):
        return step_by_rows(state)
    state = replace(state, iteration=state.iteration + 1)
    given = pack(state)
    graph, log, seen = packed.iterate(given, known_of(state))
    if state.packed is None:
        dropped(given.rows)
    state = repacked(replace(state, log=[*state.log, *log]), graph)
    return replace(state, trace=[*state.trace, (measured(state) if state.cfg.trace else {"iteration": state.iteration}) | seen])


def step_by_rows(state: State) -> State:
    """The same with arcs as rows, for graphs whose lists may be too wide and for the other rules and picks."""
    state = replace(state, iteration=state.iteration + 1, packed=None)
    before = state.leveled if state.leveled is not None else cut(state.seen)
    leveled = cut(link_leveled(state, before))
    linked = leveled.count() // 2
    leveled, lifted = lift_leveled(leveled)
    leveled, changes, seen = contract_leveled(state, leveled)
    log = [m for m in (lifted, changes.where("old <> new").select("old", "new") if seen["contracted"] else None) if m is not None]
    verts = cut(advanced(state.verts, leveled, lifted, changes))
    seen |= {"linked": linked, "lifted": lifted.count() if lifted is not None else 0, "edges": leveled.count() // 2}
    state = replace(state, arcs=leveled.select("src", "dst"), leveled=leveled, verts=verts, log=[*state.log, *log])
    return replace(state, trace=[*state.trace, (measured(state) if state.cfg.trace else {"iteration": state.iteration}) | seen])


def run(state: State) -> State:
    """Iterates until every component is a clique; raises instead of returning partial labels."""
    while True:
        if state.cfg.retire_cliques:
            state = forget(state, retire(state))
            if not state.packed.n[packed.GROWN] if state.packed is not None else state.arcs.isEmpty():
                return state
        elif all_cliques(state.arcs):
            return state
        if state.iteration >= state.cfg.max_iterations:
            raise RuntimeError(f"no end after {state.iteration} iterations: {state.trace[-2:]}")
        state = forget(state, step(state))


def canonical(vertices: DataFrame, moves: DataFrame | None, final: DataFrame | None) -> DataFrame:
    """labels(vertex, component): through moves to a last vertex, through final(vid, mu) to its group, then the group's least original id."""
    out = vertices.select(F.col("vid").alias("vertex"), F.col("vid").alias("rep"))
    if moves is not None:
        out = out.join(moves, F.col("rep") == F.col("old"), "left").select("vertex", F.coalesce("new", "rep").alias("rep"))
    if final is not None:
        out = out.join(final, F.col("rep") == F.col("vid"), "left").select("vertex", F.coalesce("mu", "rep").alias("rep"))
    least = out.groupBy("rep").agg(F.min("vertex").alias("component"))
    return out.join(least, "rep").select("vertex", "component")


def unfold(vertices: DataFrame, state: State) -> DataFrame:
    mu = state.arcs.groupBy(F.col("src").alias("vid")).agg(F.least(F.min("dst"), F.col("src")).alias("mu"))
    for d in state.done:
        mu = mu.unionByName(d.select("vid", "mu"))
    return canonical(vertices, compose_moves(state.log), mu)


def finishes(vertices: DataFrame, state: State) -> DataFrame:
    """component, iteration: the iteration after which each component was a clique (0: from the start). Needs retire_cliques; isolated vertices are left out."""
    when = state.done[0].select("vid", "iteration") if state.done else None
    for d in state.done[1:]:
        when = when.unionByName(d.select("vid", "iteration"))
    labels = unfold(vertices, state)
    moves = compose_moves(state.log)
    reps = vertices.select(F.col("vid").alias("vertex"), F.col("vid").alias("rep"))
    if moves is not None:
        reps = reps.join(moves, F.col("rep") == F.col("old"), "left").select("vertex", F.coalesce("new", "rep").alias("rep"))
    out = reps.join(labels, "vertex").join(when, F.col("rep") == F.col("vid"), "left")
    # a component that contracted to one vertex has no arc left to be seen: it was done when its last move was made, the run's last iteration at most
    return out.groupBy("component").agg(F.coalesce(F.max("iteration"), F.lit(state.iteration)).alias("iteration"), F.count("*").alias("size"))


def budgeted_components(edges: DataFrame, vertices: DataFrame | None = None, cfg: LevelConfig = LevelConfig()) -> ComponentsResult:
    state = init_state(edges, vertices, cfg)
    everyone = state.verts.select("vid")
    state = run(state)
    return ComponentsResult(unfold(everyone, state), state.trace, state)
