"""Iterations over packed lists against the same by rows."""

import random

import numpy as np
import pytest

from tidegraph.functions.coins import coin01
from tidegraph.operators import baselines, levels, packed
from tidegraph.operators.levels import LevelConfig
from tidegraph.plans import graphs

DATA = "/root/testdata/sf0.001"


def rows(df, *columns):
    return sorted(map(tuple, df.select(*columns).collect()))


def same_run(state, times):
    a = b = state
    total = {}
    for _ in range(times):
        x, y = levels.retire(a), levels.retire_by_rows(b)
        assert [rows(d, "vid", "mu", "iteration") for d in x.done] == [rows(d, "vid", "mu", "iteration") for d in y.done]
        a, b = levels.step(x), levels.step_by_rows(y)
        assert rows(a.leveled, *levels.ENDS) == rows(b.leveled, *levels.ENDS)
        assert rows(a.verts, "vid", "level", "active") == rows(b.verts, "vid", "level", "active")
        assert [rows(m, "old", "new") for m in a.log] == [rows(m, "old", "new") for m in b.log]
        assert [{k: pytest.approx(v) if isinstance(v, float) else v for k, v in t.items()} for t in b.trace] == a.trace  # sums of doubles in another order
        for k, v in a.trace[-1].items():
            total[k] = total.get(k, 0) + (v if isinstance(v, (int, float)) else 0)
    return total


def test_packed_iterations_are_those_by_rows(spark, monkeypatch):
    monkeypatch.setattr(packed, "WEDGES", 500)
    total = same_run(levels.init_state(graphs.order_part(spark, DATA, 8), cfg=LevelConfig(beta0=4, leader_rate=0.3, trace=True)), 4)
    assert all(total[k] for k in ("saturated", "leaders", "lifted", "contracted", "two_hop")), total


def test_packed_iterations_from_mixed_levels(spark):
    rng = random.Random(5)
    arcs = {p for _ in range(260) for a, b in [rng.sample(range(-60, 60), 2)] for p in ((a, b), (b, a))}
    arcs |= {(a, b) for s in (1 << 60, 500) for a in range(s, s + 5) for b in range(s, s + 5) if a != b}
    edges = spark.createDataFrame(sorted(arcs), "src long, dst long")
    verts = spark.createDataFrame([(v, rng.choice([0, 0, 1, 2]), rng.random() < 0.8) for v in sorted({a for a, _ in arcs} | {7000})], "vid long, level int, active boolean")
    for at_least in (True, False):
        cfg = LevelConfig(beta0=3, leader_rate=0.4, saturate_at_least=at_least, trace=True)
        same_run(levels.State(edges, verts, levels.plan_budget(130, 280, cfg), cfg), 2)


def test_coins_are_those_of_the_engine(spark):
    ids = [0, 1, -5, 2**61, 123456789]
    df = spark.createDataFrame([(i,) for i in ids], "v long")
    for salt in ((0, 1, "leader"), (12345678, 17, "a longer salt than eight")):
        want = [r["c"] for r in df.select(coin01(df["v"], *salt).alias("c")).collect()]
        assert packed.coins(np.array(ids), *salt).tolist() == want


@pytest.mark.parametrize("cfg", [LevelConfig(beta0=8), LevelConfig(beta0=8, retire_cliques=False)])
def test_a_step_reads_no_table_of_arcs_but_its_own(spark, cfg, monkeypatch):
    monkeypatch.setattr(levels, "step_by_rows", None)
    edges = graphs.user_paths(spark, DATA).limit(300)
    want = {r["vertex"]: r["component"] for r in baselines.local_components(edges).labels.collect()}
    assert {r["vertex"]: r["component"] for r in levels.budgeted_components(edges, cfg=cfg).labels.collect()} == want
