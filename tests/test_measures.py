"""Measures that can fail, and traces that show each step of the loop at work."""

import pytest

from tidegraph.operators import baselines, levels, measures
from tidegraph.operators import primitives as P
from tidegraph.operators.connect import EngineConfig, boosted_components, connected_components
from tidegraph.operators.levels import LevelConfig
from tidegraph.plans import graphs
from tidegraph.streaming import incremental

DATA = "/root/testdata/sf0.001"


def labels(df):
    return {r["vertex"]: r["component"] for r in df.collect()}


def test_every_step_of_the_loop_happens(spark):
    edges = graphs.order_part(spark, DATA, 8)
    want = labels(baselines.local_components(edges).labels)
    out = levels.budgeted_components(edges, cfg=LevelConfig(beta0=4, leader_rate=0.3, trace=True))
    assert labels(out.labels) == want
    total = {k: sum(t[k] for t in out.trace) for k in ("saturated", "leaders", "lifted", "contracted", "two_hop")}
    assert all(total.values()), total
    assert max(t["max_level"] for t in out.trace) >= 2
    both = connected_components(edges, cfg=EngineConfig(local_finish_arcs=0, shrink_to=300, levels=LevelConfig(beta0=4, leader_rate=0.3)))
    assert labels(both.labels) == want
    assert any(t.get("phase") == "shrink" for t in both.trace) and any("linked" in t for t in both.trace)


def test_composition_stays_of_one_size(spark):
    ids = spark.range(64)
    halve = ids.where("id > 0").selectExpr("id AS old", "id div 2 AS new")
    sizes = {k: P.compose_moves([halve] * k)._jdf.queryExecution().analyzed().collectLeaves().size() for k in (3, 6, 12)}
    assert len(set(sizes.values())) == 1


def test_first_budget_covers_the_rate():
    for n in (100, 10**4, 10**9):
        b = levels.plan_budget(n, 3 * n)
        assert b.beta0 >= (3 * __import__("math").log(n)) ** 2 * (1 - 1e-9) and b.space >= n * b.beta0**2 * (1 - 1e-9)


def test_masks_and_coins():
    near = {(a, b) for a in range(9) for b in range(9) if 0 < abs(a - b) <= 2}
    keep = measures.mask_of(list(range(8)), [False] * 8, near)
    kept = [i for i in range(8) if keep[i]]
    assert keep[0] == keep[-1] == 1 and all((a, b) in near for a, b in zip(kept, kept[1:], strict=False))
    assert all(0 in [keep[k] for k in (i - 2, i - 1, i + 1, i + 2) if 0 <= k < 8] for i in kept)
    coins = measures.hand_on([1.0] * 8, keep)
    assert sum(coins) <= 8 and min(coins) >= 1.25
    assert measures.mask_of([1, 2, 3, 4, 5], [False] * 5, {(a, a + 1) for a in range(9)}) is None
    assert measures.mask_of([1, 2, 1, 4, 5], [True] * 5, {(1, 4), (4, 5)}) == [1, 0, 0, 1, 1]


def test_boosted_copies_agree(spark):
    edges = graphs.order_part(spark, DATA, 2)
    assert labels(boosted_components(edges, 2, LevelConfig(beta0=32)).labels) == labels(baselines.local_components(edges).labels)


def test_labels_grow_by_batches_and_replays_change_nothing(spark, tmp_path):
    inc = incremental.IncrementalComponents(spark, str(tmp_path / "inc"))
    batches = [[(1, 2), (3, 4)], [(2, 3), (9, 9), (None, 5)], [(10, 9)], [(10, 9)]]
    for n, (b, e) in enumerate(zip((0, 1, 2, 2), batches, strict=True)):
        inc.add(spark.createDataFrame(e, "u long, v long"), b)
        assert n or labels(inc.labels()) == {1: 1, 2: 1, 3: 3, 4: 3}
    assert labels(inc.labels()) == {1: 1, 2: 1, 3: 1, 4: 1, 5: 5, 9: 9, 10: 9}


def test_sessions_and_windows(spark):
    import datetime as dt

    at = lambda m: dt.datetime(2024, 1, 1) + dt.timedelta(minutes=m)
    e = spark.createDataFrame([(at(0), 1), (at(5), 1), (at(70), 1), (at(6), 2), (at(71), 2)], "ts timestamp_ntz, user_id long")
    s = {(r["user_id"], r["events"]) for r in incremental.session_edges(e.withColumn("ts", e["ts"].cast("timestamp"))).collect()}
    assert s == {(1, 2), (1, 1), (2, 1)}
    w = incremental.windowed_edges(e.withColumn("ts", e["ts"].cast("timestamp"))).collect()
    assert len({r["u"] for r in w}) == 2 and len(w) == 4
    assert len(incremental.windowed_edges(e.withColumn("ts", e["ts"].cast("timestamp")), slide="30 minutes").collect()) > 4
    met = incremental.meeting_edges(e.withColumn("k", e["user_id"] * 0), e.withColumn("k", e["user_id"] * 0), "k").collect()
    assert sorted(map(tuple, met)) == [(1, 2), (1, 2)]


@pytest.mark.parametrize("ids", [(1, 2), (2**61, 2**61 + 7)])
def test_the_cycle_coin_takes_any_ids(spark, ids):
    from tidegraph.operators.cycles import kept_edges

    e = spark.createDataFrame([ids], "u long, v long")
    for kind in ("xx", "md5"):
        assert kept_edges(e, 100, 10**9, 0, kind).count() == 1
