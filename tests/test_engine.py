"""The registered queries against their SQL, and what SQL cannot say: traps, odd inputs, streams."""

import duckdb
import pytest

from tidegraph.functions.ids import encode_ids
from tidegraph.operators import baselines, levels, measures, shrink
from tidegraph.operators import primitives as P
from tidegraph.operators.connect import EngineConfig, connected_components
from tidegraph.operators.levels import LevelConfig
from tidegraph.plans import graphs, queries

DATA = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
QUICK = ["cc_conversations", "cc_order_part_q3", "cc_with_isolated", "cc_document_copies", "base_local", "base_hook_contract_star", "step_h_candidates", "step_link_first_iteration", "step_saturated_spread", "step_leader_two_hops", "step_lift_chain_1", "step_lift_chain_2", "step_clique_test", "shrink_once_md5", "prim_prefix_sum", "prim_predecessor", "prim_compose_moves", "meas_diameter", "op_rollup_components"]


def plain(rows, columns):
    return sorted((tuple(None if r[c] is None else float(r[c]) if isinstance(r[c], float) else r[c] for c in columns) for r in rows), key=str)


@pytest.mark.parametrize("name", QUICK)
def test_query_equals_sql(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{DATA}/{t}.parquet')")
    want = con.execute(queries.oracle_sql()[name])
    columns = [x[0] for x in want.description]
    rows = [dict(zip(columns, r, strict=True)) for r in want.fetchall()]
    got = queries.queries()[name](spark, DATA)
    assert sorted(got.columns) == sorted(columns)
    assert plain([r.asDict() for r in got.collect()], columns) == plain(rows, columns)


def labels(result):
    return {r["vertex"]: r["component"] for r in result.labels.collect()}


def test_odd_inputs(spark):
    edges = spark.createDataFrame([(5, 5), (1, 2), (2, 1), (1, 2), (-7, 2), (2**55, 2**55 + 1), (None, 3)], "u long, v long")
    ids = spark.createDataFrame([(99,), (5,)], "vid long")
    want = {5: 5, 99: 99, 1: -7, 2: -7, -7: -7, 2**55: 2**55, 2**55 + 1: 2**55}
    for result in (connected_components(edges, ids), connected_components(edges, ids, EngineConfig(local_finish_arcs=0)), baselines.hook_contract_components(edges, ids)):
        assert labels(result) == want
    assert labels(connected_components(edges.limit(0))) == {}


def test_regular_graph_at_capacity_halts_only_with_at_least(spark):
    ring = graphs.circulant(spark, 24, 4)
    done = levels.budgeted_components(ring, cfg=LevelConfig(beta0=4, leader_rate=0.3))
    assert set(labels(done).values()) == {0}
    with pytest.raises(RuntimeError):
        levels.budgeted_components(ring, cfg=LevelConfig(beta0=4, saturate_at_least=False, max_iterations=2))


def test_small_budgets_are_refused():
    with pytest.raises(ValueError):
        levels.plan_budget(10, 5, LevelConfig(beta0=1.0))


def test_invariants_after_each_step(spark):
    edges = graphs.order_part(spark, DATA, 2)
    want = labels(baselines.local_components(edges))
    state = levels.init_state(edges, cfg=LevelConfig(beta0=2, leader_rate=0.3))
    everyone = state.verts.select("vid")
    for _ in range(2):
        state = levels.step(state)
        back = state.arcs.selectExpr("dst AS src", "src AS dst")
        assert state.arcs.subtract(back).isEmpty() and state.arcs.where("src = dst").isEmpty() and state.arcs.count() == state.arcs.distinct().count()
        now = levels.canonical(everyone, P.compose_moves(state.log), baselines.local_finish(state.arcs))
        assert {r["vertex"]: r["component"] for r in now.collect()} == want


def test_thinning_leaves_enough_lone_picks(spark):
    path = spark.range(5000).selectExpr("id AS tail", "id + 1 AS head")
    assert measures.thin_survival_rate(path) > 4 / 27 - 0.02


def test_shrink_never_adds_arcs(spark):
    arcs = P.symmetrize(graphs.order_part(spark, DATA, 5))
    out = shrink.shrink_until(arcs, 200)
    assert all(p.arcs_after <= p.arcs and p.ratio <= 323 / 324 for p in out.passes)


def test_string_ids(spark):
    coded, names = encode_ids(spark.createDataFrame([("b", "a"), ("c", "d"), ("a", None)], "u string, v string"))
    assert {r["key"]: r["id"] for r in names.collect()} == {"a": 0, "b": 1, "c": 2, "d": 3}
    assert sorted(map(tuple, coded.collect())) == [(1, 0), (2, 3)]


def test_partition_equality(spark):
    a = spark.createDataFrame([(1, 1), (2, 1), (3, 3)], "vertex long, component long")
    b = spark.createDataFrame([(1, 9), (2, 9), (3, 4)], "vertex long, component long")
    c = spark.createDataFrame([(1, 9), (2, 4), (3, 4)], "vertex long, component long")
    assert measures.partition_equal(a, b) and not measures.partition_equal(a, c)
