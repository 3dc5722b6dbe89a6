"""Registered graph queries: (spark, sf_dir) -> DataFrame, and the SQL that gives the same rows."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tidegraph.functions import sqlapi
from tidegraph.functions.ids import encode_ids, tag
from tidegraph.functions.session import cut
from tidegraph.operators import baselines as B
from tidegraph.operators import cycles, levels, measures, shrink
from tidegraph.operators import primitives as P
from tidegraph.operators.connect import EngineConfig, boosted_components, connected_components
from tidegraph.operators.levels import LevelConfig
from tidegraph.plans import graphs as G
from tidegraph.plans import oracles as O

Query = Callable[[SparkSession, str], DataFrame]
_found: dict[str, Query] = {}
_sql: dict[str, str] = {}


def add(name: str, run: Query, sql: str | None) -> None:
    _found[name] = run
    if sql:
        _sql[name] = sql


def labels_of(edges: DataFrame, cfg: EngineConfig = EngineConfig(), vertices: DataFrame | None = None) -> DataFrame:
    return connected_components(edges, vertices, cfg).labels


# ---- components of the graphs ------------------------------------------------------------------
for name, build, sql in (
    ("geo_forest", G.geo_forest, O.GEO), ("part_supplier", G.part_supplier, O.PART_SUPPLIER), ("customer_supplier", G.customer_supplier, O.CUSTOMER_SUPPLIER),
    ("order_part", G.order_part, O.order_part()), ("user_paths", G.user_paths, O.USER_PATHS), ("conversations", G.conversation_turns, O.CONVERSATIONS),
    ("document_copies", G.document_copies, O.COPIES), ("document_lines", G.document_lines, O.LINES), ("user_user", G.user_user, O.USER_USER), ("caterpillar", G.caterpillar, O.CATERPILLAR),
    ("embedding_knn1", G.embedding_neighbors, O.KNN1), ("user_cliques", G.user_cliques, O.CLIQUES), ("cooccurrence", G.cooccurrence_chain, O.COOCCUR),
):
    add(f"cc_{name}", lambda s, d, build=build: labels_of(build(s, d)), O.components(sql))
for q in (1, 2, 3, 5, 8):
    add(f"cc_order_part_q{q}", lambda s, d, q=q: labels_of(G.order_part(s, d, q)), O.components(O.order_part(q)))
for rings, name in ((1, "one_cycle"), (2, "two_cycles")):
    add(f"cc_{name}", lambda s, d, rings=rings: labels_of(G.event_ring(s, d, rings)), O.rings(rings))
    add(f"cycles_{name}", lambda s, d, rings=rings: s.createDataFrame([(cycles.one_or_two_cycles(G.event_ring(s, d, rings), 256)[0],)], "cycles long"), f"SELECT CAST({rings} AS BIGINT) AS cycles")


def orders_as_vertices(s: SparkSession, d: str) -> DataFrame:
    return G.table(s, d, "orders").select(tag(F.col("o_orderkey"), "order").alias("vid"))


add("cc_with_isolated", lambda s, d: labels_of(G.order_part(s, d, 2), vertices=orders_as_vertices(s, d)), O.components(O.order_part(2), "SELECT CAST(o_orderkey AS BIGINT) * 8 FROM orders"))


def page_links(s: SparkSession, d: str) -> DataFrame:
    edges, names = encode_ids(G.page_links(s, d))
    labels = labels_of(edges)
    a, b = (names.select(F.col("id").alias(f"_{c}"), F.col("key").alias(c)) for c in ("name", "component_name"))
    return labels.join(a, F.col("vertex") == F.col("_name")).join(b, F.col("component") == F.col("_component_name")).select("name", "component_name")


add("cc_page_links", page_links, O.PAGE_COMPONENTS)

# ---- variants of the method, and the baselines, on one graph ----------------------------------
Q3 = O.components(O.order_part(3))
WHOLE = O.components(O.order_part())


def q3(s: SparkSession, d: str) -> DataFrame:
    return G.order_part(s, d, 3)


BASE = LevelConfig()
for name, cfg in (
    ("paper_budget", BASE), ("beta2", replace(BASE, beta0=2)), ("beta4", replace(BASE, beta0=4)), ("beta8", replace(BASE, beta0=8)), ("beta32", replace(BASE, beta0=32)),
    ("rule_mpc", replace(BASE, beta0=4, rule="mpc")), ("rule_skip_lifted", replace(BASE, beta0=4, rule="skip_lifted")), ("retire_off", replace(BASE, beta0=8, retire_cliques=False)), ("hashed_pick", replace(BASE, beta0=8, pick="hash")),
):
    add(f"cc_levels_{name}", lambda s, d, cfg=cfg: levels.budgeted_components(q3(s, d), cfg=cfg).labels, Q3)
add("cc_levels_order_part_q5", lambda s, d: levels.budgeted_components(G.order_part(s, d, 5), cfg=replace(BASE, beta0=32)).labels, O.components(O.order_part(5)))
add("cc_levels_user_paths", lambda s, d: levels.budgeted_components(G.user_paths(s, d), cfg=replace(BASE, beta0=32)).labels, O.components(O.USER_PATHS))
add("cc_levels_geo_forest", lambda s, d: levels.budgeted_components(G.geo_forest(s, d), cfg=replace(BASE, beta0=32)).labels, O.components(O.GEO))
add("cc_shrink_only", lambda s, d: B.shrink_only_components(G.order_part(s, d)).labels, WHOLE)
add("cc_shrink_then_levels", lambda s, d: connected_components(G.order_part(s, d, 5), cfg=EngineConfig(local_finish_arcs=0, shrink_to=1000, levels=replace(BASE, beta0=8))).labels, O.components(O.order_part(5)))
add("cc_boosted", lambda s, d: boosted_components(q3(s, d), 3, replace(BASE, beta0=32)).labels, Q3)
add("cc_global_path", lambda s, d: labels_of(G.global_path(s, d)), "SELECT i AS vertex, CAST(0 AS BIGINT) AS component FROM range(0, (SELECT count(*) FROM events)) t(i)")
add("cc_similarity", lambda s, d: labels_of(G.similarity_edges(s, d)), O.components(O.SIMILAR))
add("base_exponentiation", lambda s, d: B.exponentiation_components(q3(s, d)).labels, Q3)
add("base_uniform_degree", lambda s, d: B.uniform_degree_components(q3(s, d)).labels, Q3)
add("base_matrix_squaring", lambda s, d: B.matrix_squaring_components(q3(s, d)).labels, Q3)
add("base_hook_contract_conditional", lambda s, d: B.hook_contract_components(G.order_part(s, d)).labels, WHOLE)
add("base_hook_contract_star", lambda s, d: B.hook_contract_components(G.order_part(s, d), variant="star").labels, WHOLE)
add("base_random_mate", lambda s, d: B.random_mate_components(q3(s, d)).labels, Q3)
add("base_random_mate_bounded", lambda s, d: B.random_mate_components(q3(s, d), bounded=True).labels, Q3)
add("base_random_mate_shrink", lambda s, d: connected_components(G.order_part(s, d), cfg=EngineConfig(shrink="random_mate")).labels, WHOLE)
add("base_label_flood", lambda s, d: B.label_flood_components(G.order_part(s, d)).labels, WHOLE)
add("base_local", lambda s, d: B.local_components(G.order_part(s, d)).labels, WHOLE)


# ---- single steps on the geography forest with preset levels -----------------------------------
def preset(s: SparkSession, d: str, beta0: float = 4.0) -> levels.State:
    state = levels.init_state(G.geo_forest(s, d), cfg=LevelConfig(beta0=beta0, coin="md5", leader_rate=0.3))
    state.verts = cut(state.verts.select("vid", (F.floor(F.col("vid") / 8) % 3).cast("int").alias("level"), "active"))
    return state


def leveled(state: levels.State) -> DataFrame:
    return P.with_levels(state.arcs, state.verts)


def sat(state: levels.State, spread: bool = True) -> DataFrame:
    lv = cut(leveled(state))
    direct = levels.saturated_direct(state, lv)
    return levels.saturated_spread(lv, direct) if spread else direct


def step_leaders(s, d):
    state = preset(s, d, 2.0)
    return levels.draw_leaders(state, sat(state))


def step_two_hops(s, d):
    state = preset(s, d, 2.0)
    return levels.leader_within_two_hops(leveled(state), levels.draw_leaders(state, sat(state)))


add("step_init", lambda s, d: levels.init_state(G.geo_forest(s, d)).verts, O.graph(O.GEO) + "SELECT DISTINCT src AS vid, CAST(0 AS INTEGER) AS level, TRUE AS active FROM arcs")
add("step_h_candidates", lambda s, d: levels.same_level_two_hop(leveled(preset(s, d))), O.graph(O.GEO) + "SELECT DISTINCT a.dst AS v, b.dst AS u FROM lev a JOIN lev b ON a.src = b.src AND a.dst <> b.dst WHERE a.sl = a.dl AND b.sl = b.dl AND NOT EXISTS (SELECT 1 FROM arcs x WHERE x.src = a.dst AND x.dst = b.dst)")
add("step_degree_at_or_above", lambda s, d: levels.degree_at_or_above(leveled(preset(s, d))), O.graph(O.GEO) + "SELECT src, count(*) FILTER (dl >= sl) AS d FROM lev GROUP BY src")
add("step_link_first_iteration", lambda s, d: levels.link_two_hops(levels.init_state(G.geo_forest(s, d), cfg=LevelConfig(beta0=4))), O.LINK)
add("step_lift_preset_levels", lambda s, d: levels.lift_moves(leveled(preset(s, d))), O.graph(O.GEO) + "SELECT src AS old, arg_min(dst, (-dl, dst)) AS new FROM lev WHERE dl > sl GROUP BY src")
add("step_saturated", lambda s, d: sat(preset(s, d), False), O.SATURATED + "SELECT v, level FROM direct")
add("step_saturated_spread", lambda s, d: sat(preset(s, d)), O.SATURATED + "SELECT v, level FROM spread")
add("step_leader_coin_md5", step_leaders, O.LEADERS + "SELECT v, level FROM leaders")
add("step_leader_two_hops", step_two_hops, O.LEADERS + O.TWO_HOPS)
add("step_contract", lambda s, d: P.contract(P.symmetrize(G.geo_forest(s, d)), levels.lift_moves(leveled(preset(s, d)))), O.graph(O.GEO) + ", mv AS (SELECT src AS old, arg_min(dst, (-dl, dst)) AS new FROM lev WHERE dl > sl GROUP BY src) SELECT DISTINCT coalesce(x.new, src) AS src, coalesce(y.new, dst) AS dst FROM arcs LEFT JOIN mv x ON x.old = src LEFT JOIN mv y ON y.old = dst WHERE coalesce(x.new, src) <> coalesce(y.new, dst)")
add("step_clique_test", lambda s, d: levels.clique_components(P.symmetrize(q3(s, d))).where("is_clique").select("mu", "size"), O.CLIQUE_TEST)


def chain(s: SparkSession, times: int) -> DataFrame:
    """Three vertices on levels 0, 1, 2 in a row, lifted `times` times: members of each vertex that is left."""
    arcs = cut(P.symmetrize(s.createDataFrame([(1, 2), (2, 3)], "u long, v long")))
    verts = cut(s.createDataFrame([(1, 0, True), (2, 1, True), (3, 2, True)], "vid long, level int, active boolean"))
    state = levels.State(arcs, verts, levels.plan_budget(3, 2, LevelConfig(beta0=4)), LevelConfig(beta0=4))
    members = verts.select(F.col("vid").alias("orig"), F.col("vid").alias("rep"))
    for _ in range(times):
        arcs, verts, moves = levels.lift_to_higher_level(state)
        members = cut(P.apply_moves(members, moves))
        state = replace(state, arcs=arcs, verts=verts)
    return members


add("step_lift_chain_1", lambda s, d: chain(s, 1), "SELECT * FROM (VALUES (1::BIGINT, 2::BIGINT), (2, 3), (3, 3)) t(orig, rep)")
add("step_lift_chain_2", lambda s, d: chain(s, 2), "SELECT * FROM (VALUES (1::BIGINT, 3::BIGINT), (2, 3), (3, 3)) t(orig, rep)")


def picks(s: SparkSession, d: str) -> DataFrame:
    return shrink.pick_min_neighbor(P.symmetrize(G.order_part(s, d, 5)))


def untangled(s: SparkSession, d: str) -> DataFrame:
    return cut(shrink.cut_hub_out(shrink.break_mutual(cut(picks(s, d)))))


add("shrink_pick_min", picks, O.PICKS + "SELECT tail, head FROM p1")
add("shrink_break_mutual", lambda s, d: shrink.break_mutual(picks(s, d)), O.PICKS + "SELECT tail, head FROM p2")
add("shrink_cut_hub_out", untangled, O.PICKS + "SELECT tail, head FROM p3")
add("shrink_merge_stars", lambda s, d: shrink.merge_stars(untangled(s, d))[0], O.PICKS + "SELECT tail AS old, head AS new FROM star")
add("shrink_thin_md5", lambda s, d: shrink.thin(shrink.merge_stars(untangled(s, d))[1], 0, kind="md5"), O.PICKS + "SELECT tail, head FROM thin")
add("shrink_isolated", lambda s, d: shrink.merge_isolated(shrink.thin(shrink.merge_stars(untangled(s, d))[1], 0, kind="md5")), O.PICKS + "SELECT tail AS old, head AS new FROM lone")
add("shrink_once_md5", lambda s, d: shrink.shrink_once(cut(P.symmetrize(G.order_part(s, d, 5))), 0, kind="md5")[0], O.PICKS + ", mv AS (SELECT tail AS old, head AS new FROM star UNION ALL SELECT tail, head FROM lone) SELECT DISTINCT coalesce(x.new, src) AS src, coalesce(y.new, dst) AS dst FROM arcs LEFT JOIN mv x ON x.old = src LEFT JOIN mv y ON y.old = dst WHERE coalesce(x.new, src) <> coalesce(y.new, dst)")
add("cycle_cut_md5", lambda s, d: cycles.kept_edges(G.event_ring(s, d), T(s, d, "events").count(), 64, 0, "md5"), O.CYCLE_CUT)
add("cycle_contract", lambda s, d: s.createDataFrame([(cycles.shrink_cycles_once(G.event_ring(s, d), 64, kind="md5")[2]["edges_after"],)], "edges long"), O.CYCLE_CONTRACT)

# ---- primitives ---------------------------------------------------------------------------------
T = G.table
add("prim_sort", lambda s, d: P.sort_tuples(T(s, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey"), "l_orderkey", "l_linenumber"), "SELECT l_orderkey, l_linenumber, l_partkey FROM lineitem ORDER BY 1, 2")
add("prim_filter_compact", lambda s, d: P.filter_compact(T(s, d, "orders").select("o_orderkey", "o_custkey"), F.col("o_custkey") % 3 == 0, "o_orderkey"), "SELECT o_orderkey, o_custkey, row_number() OVER (ORDER BY o_orderkey) - 1 AS index FROM orders WHERE o_custkey % 3 = 0")
for op in ("sum", "min", "max", "count"):
    agg = f"CAST(coalesce({op}(o_custkey) OVER (ORDER BY o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT)" if op in ("sum", "count") else f"{op}(o_custkey) OVER (ORDER BY o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)"
    add(f"prim_prefix_{op}", lambda s, d, op=op: P.prefix(T(s, d, "orders").select("o_orderkey", "o_custkey"), "o_orderkey", "o_custkey", op), f"SELECT o_orderkey, o_custkey, {agg} AS prefix FROM orders")
add("prim_predecessor", lambda s, d: P.predecessor(T(s, d, "events").select("event_id", "user_id", "ts", (F.col("event_id") % 3 == 0).cast("int").alias("flag")), "user_id", ["ts", "event_id"], "flag", "event_id").select("event_id", "before"), "SELECT event_id, last_value(CASE WHEN event_id % 3 = 0 THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS before FROM events")
add("prim_dedupe_sorted", lambda s, d: P.dedupe_sorted(T(s, d, "lineitem"), ["l_partkey", "l_suppkey"]), "SELECT DISTINCT l_partkey, l_suppkey FROM lineitem")
add("prim_latest_version", lambda s, d: P.latest_version(T(s, d, "events"), "user_id", F.struct("ts", "event_id"), "event_id"), "SELECT user_id, arg_max(event_id, (ts, event_id)) AS event_id FROM events GROUP BY user_id")
add("prim_scan_total", lambda s, d: P.scan(T(s, d, "orders"), "o_orderkey", "o_custkey")[1], "SELECT CAST(sum(o_custkey) AS BIGINT) AS total FROM orders")
add("prim_multiprefix", lambda s, d: P.multiprefix(T(s, d, "events").select("user_id", "event_id", "ts"), "user_id", ["ts", "event_id"], "event_id").select("event_id", "prefix"), "SELECT event_id, CAST(coalesce(sum(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS prefix FROM events")
add("prim_dedupe_first", lambda s, d: P.dedupe_first(T(s, d, "events").select("user_id", "event_id", "ts"), "user_id", ["ts", "event_id"]).select("user_id", "event_id"), "SELECT user_id, event_id FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS r FROM events) WHERE r = 1")
add("prim_symmetrize", lambda s, d: P.symmetrize(G.geo_forest(s, d)), O.graph(O.GEO) + "SELECT src, dst FROM arcs")
add("prim_adjacency", lambda s, d: P.to_adjacency(P.symmetrize(q3(s, d))).select("src", F.array_join(F.transform("nbrs", lambda x: x.cast("string")), ",").alias("nbrs")), O.graph(O.order_part(3)) + "SELECT src, string_agg(CAST(dst AS VARCHAR), ',' ORDER BY dst) AS nbrs FROM arcs GROUP BY src")
add("prim_degrees", lambda s, d: P.degrees(P.symmetrize(G.geo_forest(s, d))), O.graph(O.GEO) + "SELECT src, count(*) AS degree FROM arcs GROUP BY src")
add("prim_level_degrees", lambda s, d: (lambda st: P.level_degrees(st.arcs, st.verts))(preset(s, d)), O.graph(O.GEO) + "SELECT src AS vid, dl AS nbr_level, count(*) AS cnt FROM lev GROUP BY 1, 2")
add("prim_induced_degree", lambda s, d: (lambda st: P.induced_degree(st.arcs, st.verts, 1))(preset(s, d)), O.graph(O.GEO) + "SELECT vid, count(*) FILTER (l.dl >= 1) AS degree FROM verts LEFT JOIN lev l ON l.src = vid WHERE level >= 1 GROUP BY vid")
add("prim_neighbor_agg", lambda s, d: (lambda st: P.neighbor_agg(st.arcs, st.verts, F.sum("level")))(preset(s, d)), O.graph(O.GEO) + "SELECT src, CAST(sum(dl) AS BIGINT) AS out FROM lev GROUP BY src")
add("prim_combine_write", lambda s, d: P.combine_write(T(s, d, "events"), "user_id", "event_id", "arbitrary"), "SELECT user_id, min(event_id) AS value FROM events GROUP BY user_id")
add("prim_first_k_neighbors", lambda s, d: P.first_k_neighbors(P.symmetrize(G.geo_forest(s, d)), 3), O.graph(O.GEO) + "SELECT src, dst FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY dst) AS r FROM arcs) WHERE r <= 3")


def composed(s: SparkSession, d: str) -> DataFrame:
    ids = T(s, d, "orders").select(F.col("o_orderkey").cast("long").alias("id"))
    halve = lambda times: ids.select(F.floor(F.col("id") / 2**times).alias("old")).where("old > 0").distinct().select("old", F.floor(F.col("old") / 2).alias("new"))
    return P.compose_moves([halve(0), halve(1), halve(2)]).join(ids, F.col("old") == F.col("id"), "left_semi")


add("prim_compose_moves", composed, "SELECT DISTINCT CAST(o_orderkey AS BIGINT) AS old, CAST(o_orderkey AS BIGINT) // 8 AS new FROM orders WHERE o_orderkey > 0")
add("prim_degree_array", lambda s, d: (lambda st: P.degree_array_map(st.arcs, st.verts).select("vid", F.to_json("degrees").alias("degrees")))(preset(s, d)), O.graph(O.GEO) + "SELECT vid, '{' || string_agg('\"' || dl || '\":' || c, ',' ORDER BY dl) || '}' AS degrees FROM (SELECT src AS vid, dl, count(*) AS c FROM lev GROUP BY ALL) GROUP BY vid")
add("prim_many_multiprefix", lambda s, d: P.multiprefix(T(s, d, "events").select("user_id", "event_type", "event_id", "ts"), ["user_id", "event_type"], ["ts", "event_id"], "event_id", "count").select("event_id", "prefix"), "SELECT event_id, count(event_id) OVER (PARTITION BY user_id, event_type ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS prefix FROM events")

# ---- measures -----------------------------------------------------------------------------------
add("meas_graph_stats", lambda s, d: measures.graph_stats(G.part_supplier(s, d)), O.graph(O.PART_SUPPLIER) + ", g AS (SELECT src, count(*) AS c FROM arcs GROUP BY src) SELECT count(*) AS n, CAST(sum(c) // 2 AS BIGINT) AS m, max(c) AS max_degree FROM g")
add("meas_degree_histogram", lambda s, d: measures.degree_histogram(G.part_supplier(s, d)), O.graph(O.PART_SUPPLIER) + ", g AS (SELECT src, count(*) AS degree FROM arcs GROUP BY src) SELECT degree, count(*) AS vertices FROM g GROUP BY degree")
add("meas_diameter", lambda s, d: measures.diameters(G.order_part(s, d, 2)), O.DIAMETER)
add("meas_component_sizes", lambda s, d: measures.component_sizes(labels_of(G.order_part(s, d, 5))), O.components(O.order_part(5), outer="SELECT component, count(*) AS size FROM (%s) GROUP BY component"))
add("meas_size_histogram", lambda s, d: measures.size_histogram(labels_of(G.order_part(s, d, 5))), O.components(O.order_part(5), outer="SELECT size, count(*) AS components FROM (SELECT component, count(*) AS size FROM (%s) GROUP BY component) GROUP BY size"))
add("meas_remaining_budget0", lambda s, d: levels.remaining_budget(levels.init_state(G.geo_forest(s, d), cfg=LevelConfig(beta0=4))), O.graph(O.GEO) + "SELECT src AS vid, CAST(0 AS INTEGER) AS level, greatest(0.0::DOUBLE, 4.0::DOUBLE - count(*)) AS remaining FROM arcs GROUP BY src")
add("meas_wedge_load", lambda s, d: measures.wedge_load(preset(s, d)).where("candidates > bound"), "SELECT CAST(0 AS BIGINT) AS src, CAST(0 AS BIGINT) AS candidates, CAST(0 AS BIGINT) AS bound WHERE FALSE")


def bounds_levels(s: SparkSession, d: str) -> DataFrame:
    """Iterations and levels of one run against their bounds, which take the graph's measured diameter."""
    edges = q3(s, d)
    r = levels.budgeted_components(edges, cfg=replace(BASE, beta0=8.0, trace=True))
    n, top = r.state.budget.n, max(t["max_level"] for t in r.trace)
    wide = measures.diameters(edges).agg(F.max("diameter")).first()[0]
    return s.createDataFrame([(wide, len(r.trace) <= measures.iteration_bound(n, wide, 8.0, top), top <= 1 + measures.level_bound(n, 8.0), sum(t["unled"] for t in r.trace))], "diameter int, iterations_ok boolean, levels_ok boolean, unled long")


def space_of(r: levels.ComponentsResult) -> tuple:
    census = measures.level_census(r, r.state.budget.space)
    return census["peak_sum_sq_budget"] <= 1.01 * census["space"], census["peak_potential"] <= 2 * census["space"], census["unled"] == 0


def bounds_space(s: SparkSession, d: str) -> DataFrame:
    r = levels.budgeted_components(G.geo_forest(s, d), cfg=LevelConfig(trace=True))
    return s.createDataFrame([space_of(r)], "squares_ok boolean, potential_ok boolean, led boolean")


def bounds_census(s: SparkSession, d: str) -> DataFrame:
    """Where vertices saturate and contract: the sum of squared budgets, potential, budgets granted, and each level's thinning, on order-part with q <= 5.
    The rate of 0.5 makes the least first budget of the space bound, (0.5 ln n)^2, small enough for a graph of this size."""
    cfg = LevelConfig(alpha=3.0, leader_rate=0.5, trace=True)
    r = levels.budgeted_components(G.order_part(s, d, 5), cfg=cfg)
    squares, potential, _ = space_of(r)
    rows = measures.reached(r.trace, r.state.budget.n, r.state.budget.beta0)
    granted = sum(x["granted"] for x in rows)
    contracted = sum(t["contracted"] for t in r.trace)
    return s.createDataFrame([(squares, potential, granted <= r.state.budget.space, all(x["thinned"] for x in rows), bool(rows) and contracted > 0)], "squares_ok boolean, potential_ok boolean, granted_ok boolean, thinned boolean, happened boolean")


def costs(s: SparkSession, d: str) -> DataFrame:
    """Work and depth of a run against (m + n)(log D + levels) and the iterations, with the constants of this engine's primitives."""
    edges = q3(s, d)
    r = levels.budgeted_components(edges, cfg=replace(BASE, beta0=8.0, trace=True))
    rows = measures.primitive_costs(r.trace)
    top = max(t["max_level"] for t in r.trace)
    peak = max(2 * t["linked"] + t["vertices"] for t in r.trace)
    return s.createDataFrame([(sum(x["depth"] for x in rows) <= 14 * len(rows), sum(x["work"] for x in rows) <= 15 * peak * measures.iteration_bound(r.state.budget.n, 32, 8.0, top))], "depth_ok boolean, work_ok boolean")


def diameter_sweep(s: SparkSession, d: str) -> DataFrame:
    """Paths of 8 to 1,024 edges as one graph: each component's last iteration against the bound for its own diameter."""
    lengths = [2**k for k in range(3, 11)]
    edges = G.path_family(s, lengths)
    state = levels.init_state(edges, cfg=replace(BASE, beta0=32.0))
    everyone = state.verts.select("vid")
    state = levels.run(state)
    rows = sorted((r["size"] - 1, r["iteration"]) for r in levels.finishes(everyone, state).collect())
    top = max((max(t["promoted"], default=-1) + 1 for t in state.trace), default=0)
    later = all(a[1] <= b[1] for a, b in zip(rows, rows[1:], strict=False))
    return s.createDataFrame([(n, it <= measures.iteration_bound(0, n, 32.0, top), later) for n, it in rows], "diameter long, within boolean, monotone boolean")


def key_load(s: SparkSession, d: str) -> DataFrame:
    return measures.load(P.symmetrize(G.part_supplier(s, d)), 8).select("rows", "largest_key", (F.col("largest_partition") >= F.col("largest_key")).alias("holds_key"))


def audit_two_hops(s: SparkSession, d: str) -> DataFrame:
    out = measures.two_hop_progress(levels.init_state(G.user_paths(s, d), cfg=replace(BASE, beta0=4.0)))
    return s.createDataFrame([(out["pairs"], out["violations"])], "pairs long, violations long")


def audit_monotone(s: SparkSession, d: str) -> DataFrame:
    out = measures.monotone_audit(levels.step(levels.init_state(q3(s, d), cfg=replace(BASE, beta0=4.0))))
    return s.createDataFrame([(out["apart"], out["lower"])], "apart long, lower long")


def compare_baselines(s: SparkSession, d: str) -> DataFrame:
    """Iterations and peak edges of the methods on the conversations' paths; every one's labels are held against the first's."""
    edges = cut(G.conversation_turns(s, d))
    m = edges.count()
    runs = {
        "levels": lambda: levels.budgeted_components(edges, cfg=replace(BASE, beta0=8.0)), "uniform_degree": lambda: B.uniform_degree_components(edges), "squaring": lambda: B.matrix_squaring_components(edges),
        "hook_conditional": lambda: B.hook_contract_components(edges), "hook_star": lambda: B.hook_contract_components(edges, variant="star"), "random_mate": lambda: B.random_mate_components(edges), "shrink_only": lambda: B.shrink_only_components(edges),
    }
    rows, first = [], None
    for name, run in runs.items():
        r = run()
        first = first if first is not None else cut(r.labels)
        peak = max((int(t.get("edges", t.get("arcs", 0) // 2)) for t in r.trace), default=m)
        rows.append((name, measures.partition_equal(first, r.labels), len(r.trace) >= 1, peak <= (m if name in ("hook_conditional", "hook_star", "random_mate", "shrink_only") else 10 * m)))
    return s.createDataFrame(rows, "method string, same boolean, ran boolean, space_ok boolean")


def shrink_seeds(s: SparkSession, d: str) -> DataFrame:
    """One shrink pass over three seeds: the share of vertices left against the proven one; arcs never grow."""
    rows = []
    for name, edges in (("geo_forest", G.geo_forest(s, d)), ("document_lines", G.document_lines(s, d))):
        arcs = cut(P.symmetrize(edges))
        n, m = P.degrees(arcs).count(), arcs.count()
        for seed in range(3):
            out, moves = shrink.shrink_once(arcs, seed, 0, picks=cut(shrink.pick_min_neighbor(arcs, seed, 0, order="hash")))
            rows.append((name, seed, (n - moves.count()) / n <= 323 / 324, out.count() <= m))
    return s.createDataFrame(rows, "graph string, seed long, vertices_ok boolean, arcs_ok boolean")


def bounds_shrink(s: SparkSession, d: str) -> DataFrame:
    arcs = cut(P.symmetrize(G.order_part(s, d, 5)))
    passes = shrink.shrink_until(arcs, 1000).passes
    return s.createDataFrame([(all(p.ratio <= 323 / 324 for p in passes), all(p.arcs_after <= p.arcs for p in passes))], "vertices_ok boolean, arcs_ok boolean")


def bounds_cycles(s: SparkSession, d: str, d_prime: int = 256) -> DataFrame:
    _, _, st = cycles.shrink_cycles_once(G.event_ring(s, d), d_prime)
    return s.createDataFrame([(st["removed"] <= st["bound"], st["longest"] <= d_prime, st["edges_after"] == st["removed"])], "removed_ok boolean, pieces_ok boolean, contracted_ok boolean")


def audit_catchup(s: SparkSession, d: str) -> DataFrame:
    state = levels.step(levels.init_state(q3(s, d), cfg=replace(BASE, beta0=2.0)))
    return s.createDataFrame([(measures.level_catchup(state),)], "violations long")


def audit_path(s: SparkSession, d: str) -> DataFrame:
    """Coins along the events of the user who has most of them (ties: the least user), in the graph of all users' events."""
    events = T(s, d, "events")
    user = events.groupBy("user_id").count().orderBy(F.desc("count"), "user_id").first()["user_id"]
    path = [r["v"] for r in events.where(F.col("user_id") == user).orderBy("ts", "event_id").select(tag(F.col("event_id"), "event").alias("v")).collect()]
    rows = measures.coin_audit(levels.init_state(G.user_paths(s, d), cfg=replace(BASE, beta0=8.0)), path)
    return s.createDataFrame([(len(path) - 1, all(r["masked"] for r in rows), all(r["coins"] <= len(path) + 1e-9 for r in rows), all(r["least"] >= 1 - 1e-9 for r in rows), all(a["vertices"] >= b["vertices"] for a, b in zip(rows, rows[1:], strict=False)))], "diameter long, masked boolean, coins_ok boolean, least_ok boolean, never_longer boolean")


def compare_methods(s: SparkSession, d: str) -> DataFrame:
    """Iterations and peak edges of the method and two baselines on one long path, and whether they are as the bounds say."""
    n = 200
    path = cut(s.range(n).select(F.col("id").alias("u"), (F.col("id") + 1).alias("v")))
    runs = {"levels": levels.budgeted_components(path, cfg=LevelConfig(beta0=8.0, trace=True)), "exponentiation": B.exponentiation_components(path), "label_flood": B.label_flood_components(path)}
    most = {"levels": (measures.iteration_bound(n, n, 8.0, 8), n * n / 8), "exponentiation": (math.ceil(math.log2(n)), n * (n + 1) // 2), "label_flood": (n + 1, n)}
    rows = [(k, n, int(r.trace[-1]["iteration"]) <= most[k][0], max((int(t.get("edges", 0)) for t in r.trace), default=0) <= most[k][1]) for k, r in runs.items()]
    return s.createDataFrame(rows, "method string, diameter long, iterations_ok boolean, space_ok boolean")


TRUE2 = "SELECT TRUE AS {}, TRUE AS {}"
add("meas_bounds_levels", bounds_levels, f"SELECT CAST(max(diameter) AS INTEGER) AS diameter, TRUE AS iterations_ok, TRUE AS levels_ok, CAST(0 AS BIGINT) AS unled FROM ({O.DIAMETER.replace(O.order_part(2), O.order_part(3))})")
add("meas_bounds_space", bounds_space, TRUE2.format("squares_ok", "potential_ok") + ", TRUE AS led")
add("meas_bounds_census", bounds_census, TRUE2.format("squares_ok", "potential_ok") + ", TRUE AS granted_ok, TRUE AS thinned, TRUE AS happened")
add("meas_bounds_shrink", bounds_shrink, TRUE2.format("vertices_ok", "arcs_ok"))
for d_prime in (64, 256, 1024):
    add("meas_bounds_cycles" + ("" if d_prime == 256 else f"_{d_prime}"), lambda s, d, k=d_prime: bounds_cycles(s, d, k), TRUE2.format("removed_ok", "pieces_ok") + ", TRUE AS contracted_ok")
add("meas_sum_sq_budget0", lambda s, d: (lambda st: st.verts.agg(F.sum(st.beta(F.col("level")) ** 2).alias("squares")))(levels.init_state(G.geo_forest(s, d), cfg=LevelConfig(beta0=4))), O.graph(O.GEO) + "SELECT CAST(16 * count(*) AS DOUBLE) AS squares FROM verts")
add("meas_key_load", key_load, O.graph(O.PART_SUPPLIER) + "SELECT count(*) AS rows, (SELECT max(c) FROM (SELECT count(*) AS c FROM arcs GROUP BY src)) AS largest_key, TRUE AS holds_key FROM arcs")
add("meas_work_depth", costs, TRUE2.format("depth_ok", "work_ok"))
add("meas_iterations_by_diameter", diameter_sweep, "SELECT CAST(1 << k AS BIGINT) AS diameter, TRUE AS within, TRUE AS monotone FROM range(3, 11) t(k)")
add("meas_shrink_seeds", shrink_seeds, "SELECT g AS graph, s AS seed, TRUE AS vertices_ok, TRUE AS arcs_ok FROM (VALUES ('geo_forest'), ('document_lines')) t(g), range(3) r(s)")
add("meas_level_catchup", audit_catchup, "SELECT CAST(0 AS BIGINT) AS violations")
add("meas_monotone", audit_monotone, "SELECT CAST(0 AS BIGINT) AS apart, CAST(0 AS BIGINT) AS lower")
add("meas_two_hop_progress", audit_two_hops, f"WITH arcs AS (SELECT u AS src, v AS dst FROM ({O.USER_PATHS}) UNION SELECT v, u FROM ({O.USER_PATHS})) SELECT count(*) AS pairs, CAST(0 AS BIGINT) AS violations FROM arcs a JOIN arcs b ON a.src = b.src AND a.dst < b.dst")
add("meas_path_audit", audit_path, "SELECT max(c) - 1 AS diameter, TRUE AS masked, TRUE AS coins_ok, TRUE AS least_ok, TRUE AS never_longer FROM (SELECT count(*) AS c FROM events GROUP BY user_id)")
add("meas_compare_methods", compare_methods, "SELECT m AS method, CAST(200 AS BIGINT) AS diameter, TRUE AS iterations_ok, TRUE AS space_ok FROM (VALUES ('levels'), ('exponentiation'), ('label_flood')) t(m)")
add("meas_compare_baselines", compare_baselines, "SELECT m AS method, TRUE AS same, TRUE AS ran, TRUE AS space_ok FROM (VALUES ('levels'), ('uniform_degree'), ('squaring'), ('hook_conditional'), ('hook_star'), ('random_mate'), ('shrink_only')) t(m)")


# ---- around the method --------------------------------------------------------------------------
def geo_labels(s: SparkSession, d: str) -> DataFrame:
    return labels_of(G.geo_forest(s, d))


def customers(s: SparkSession, d: str) -> DataFrame:
    return T(s, d, "customer").select(tag(F.col("c_custkey"), "customer").alias("vertex"), F.col("c_nationkey").alias("nation"), F.col("c_mktsegment").alias("segment"))


def approximate(labels: DataFrame) -> DataFrame:
    exact = labels.select("component").distinct().count()
    return sqlapi.approx_components(labels).select((F.abs(F.col("components") - exact) <= 0.15 * exact).alias("near"))


for how in ("rollup", "cube"):
    add(f"op_{how}_components", lambda s, d, how=how: sqlapi.component_rollup(geo_labels(s, d), customers(s, d), ["nation", "segment"], how), f"SELECT c_nationkey AS nation, c_mktsegment AS segment, count(*) AS vertices, count(DISTINCT n_regionkey) AS components FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY {how.upper()} (c_nationkey, c_mktsegment)")
add("op_grouping_sets", lambda s, d: sqlapi.component_grouping_sets(geo_labels(s, d), customers(s, d), [["nation"], ["segment"], []]), "SELECT c_nationkey AS nation, c_mktsegment AS segment, count(*) AS vertices, count(DISTINCT n_regionkey) AS components FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY GROUPING SETS ((c_nationkey), (c_mktsegment), ())")
add("op_similarity_edges", lambda s, d: G.similarity_edges(s, d), O.SIMILAR)
add("op_json_edges", lambda s, d: G.json_key_edges(s, d), "SELECT CAST(event_id AS BIGINT) * 8 + 6 AS u, CAST(json_extract_string(props, '$.k') AS BIGINT) * 8 + 7 AS v FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL")
add("op_edges_asof", lambda s, d: G.edges_asof(s, d, "2024-01-15 00:00:00"), O.USER_PATHS.replace("FROM events)", "FROM events WHERE ts <= TIMESTAMP '2024-01-15 00:00:00')"))
add("op_approx_components", lambda s, d: approximate(cut(labels_of(q3(s, d)))), "SELECT TRUE AS near")
add("op_topk_components", lambda s, d: sqlapi.top_components(labels_of(G.order_part(s, d, 5)), 10), O.components(O.order_part(5), outer="SELECT component, count(*) AS size FROM (%s) GROUP BY component ORDER BY size DESC, component LIMIT 10"))
add("op_same_component_pairs", lambda s, d: sqlapi.connected(geo_labels(s, d), T(s, d, "customer").select(tag(F.col("c_custkey"), "customer").alias("a"), tag(F.col("c_custkey") % 25, "nation").alias("b"))), "SELECT CAST(c_custkey AS BIGINT) * 8 + 3 AS a, CAST(c_custkey AS BIGINT) % 25 * 8 + 4 AS b, x.n_regionkey = y.n_regionkey AS same FROM customer JOIN nation x ON c_nationkey = x.n_nationkey JOIN nation y ON c_custkey % 25 = y.n_nationkey")
add("op_cooccurrence", lambda s, d: G.cooccurrence(s, d), O.COOCCUR)
add("op_asof", lambda s, d: P.predecessor(T(s, d, "events").select("event_id", "user_id", "ts", F.lit(1).alias("flag")), "user_id", ["ts", "event_id"], "flag", "event_id").select("event_id", "before"), "SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM events")
add("op_semi_anti", lambda s, d: shrink.split_isolated(orders_as_vertices(s, d), P.symmetrize(G.order_part(s, d, 2))), "SELECT CAST(o_orderkey AS BIGINT) * 8 AS vid FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem WHERE l_quantity <= 2)")
add("op_setops", lambda s, d: P.minus_edges(G.order_part(s, d, 3), G.order_part(s, d, 2)), f"SELECT u, v FROM ({O.order_part(3)}) EXCEPT SELECT u, v FROM ({O.order_part(2)})")
add("op_common_edges", lambda s, d: P.common_edges(G.order_part(s, d, 3), G.order_part(s, d, 2)), f"SELECT u, v FROM ({O.order_part(3)}) INTERSECT SELECT u, v FROM ({O.order_part(2)})")
add("op_edges_by_month", lambda s, d: T(s, d, "events").groupBy(F.date_format("ts", "yyyy-MM").alias("month")).agg(F.count("*").alias("events"), F.count_distinct("user_id").alias("users")), "SELECT strftime(ts, '%Y-%m') AS month, count(*) AS events, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
add("op_component_ranks", lambda s, d: sqlapi.numbered(labels_of(G.order_part(s, d, 2))).withColumn("rank", F.col("rank").cast("long")), O.components(O.order_part(2), outer="SELECT vertex, component, row_number() OVER (PARTITION BY component ORDER BY vertex) AS rank FROM (%s)"))


def stream_batches(s: SparkSession, d: str) -> DataFrame:
    """The same components from three batches of edges, the second delivered twice."""
    import uuid

    from tidegraph.functions.session import shared_dir
    from tidegraph.streaming.incremental import IncrementalComponents

    inc = IncrementalComponents(s, f"{shared_dir(s).rstrip('/')}/stream-{uuid.uuid4().hex}")
    edges = q3(s, d)
    for b in (0, 1, 1, 2):
        inc.add(edges.where(F.pmod(F.xxhash64("u", "v"), F.lit(3)) == b), b)
    return inc.labels()


def window_components(s: SparkSession, d: str) -> DataFrame:
    """Users of each hour of events, joined to components of all hours (a user links the hours in which it acts)."""
    from tidegraph.streaming.incremental import windowed_edges

    return labels_of(windowed_edges(T(s, d, "events")).select("u", "v"))


add("stream_incremental_components", stream_batches, Q3)
add("stream_window_components", window_components, O.components("SELECT DISTINCT -(epoch_us(time_bucket(INTERVAL 1 HOUR, ts))) - 1 AS u, CAST(user_id AS BIGINT) AS v FROM events"))


def queries() -> dict[str, Query]:
    return dict(_found)


def oracle_sql() -> dict[str, str]:
    return dict(_sql)
