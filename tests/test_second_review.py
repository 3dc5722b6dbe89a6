"""What the second review found in the graph queries: each test fails on the code as it was then."""

import random
from dataclasses import replace
from datetime import datetime, timedelta

from tidegraph.operators import baselines, levels, measures
from tidegraph.plans import graphs
from tidegraph.plans import queries as graph_queries


def components_of(pairs):
    least = {v: v for p in pairs for v in p}
    moved = True
    while moved:
        moved = False
        for a, b in pairs:
            low = min(least[a], least[b])
            moved |= least[a] != low or least[b] != low
            least[a] = least[b] = low
    return least


def test_dense_events_link_by_chains(spark, tmp_path, monkeypatch):
    start = datetime(2024, 1, 1)
    seconds = [0.1 * i for i in range(300)] + [100, 160, 160, 220.000001, 300, 330, 360, 361]
    users = [i % 150 for i in range(300)] + [200, 201, 202, 203, 204, None, 205, 205]
    rows = [(i, start + timedelta(seconds=t), u) for i, (t, u) in enumerate(zip(seconds, users, strict=True))] + [(999, None, 7)]
    spark.createDataFrame(rows, "event_id long, ts timestamp, user_id long").write.parquet(f"{tmp_path}/events.parquet")
    all_pairs = {(r["u"], r["v"]) for r in graphs.cooccurrence(spark, str(tmp_path)).collect()}
    got = {r["vertex"]: r["component"] for r in graph_queries.queries()["cc_cooccurrence"](spark, str(tmp_path)).collect()}
    assert got == components_of(all_pairs)
    monkeypatch.setattr(graph_queries, "labels_of", lambda edges: edges)
    assert graph_queries.queries()["cc_cooccurrence"](spark, str(tmp_path)).count() < len(rows) < len(all_pairs)


def test_local_components_take_graphs_beyond_the_bound(spark):
    pairs = [(i, i + 1) for i in range(60) if i % 7] + [(100, 3), (100, 100), (-5, 59)]
    edges = spark.createDataFrame([*pairs, (None, 4)], "u long, v long")
    want = components_of([p for p in pairs if p[0] != p[1]])
    for most in (20, 100):  # arcs: above both; vertices: above one
        assert {r["vertex"]: r["component"] for r in baselines.local_components(edges, max_arcs=most).labels.collect()} == want


def test_leaves_at_a_hub_are_paired_without_a_shuffle(spark):
    arcs = [(0, i) for i in range(1, 30)] + [(40, 1), (40, 2), (2, 3)]
    rows = [(a, b, 0, True, 0, True) for p in arcs for a, b in (p, p[::-1])] + [(50, 1, 1, True, 0, True), (1, 50, 0, True, 1, True)]
    leveled = spark.createDataFrame(rows, "src long, dst long, sl int, sa boolean, dl int, da boolean")
    near = {}
    for a, b in arcs:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    want = sorted((v, u) for v in near for u in {x for w in near[v] for x in near[w]} - near[v] - {v})
    out = levels.same_level_two_hop(leveled)
    assert sorted(map(tuple, out.collect())) == want
    plan = out._jdf.queryExecution().optimizedPlan().toString()
    assert plan.lstrip().startswith("Union")


def test_candidates_in_arrays_link_as_single_rows_do(spark, monkeypatch):
    rng = random.Random(3)
    arcs = {p for _ in range(150) for a, b in [rng.sample(range(70), 2)] for p in ((a, b), (b, a))}
    level, active = {v: rng.choice([0, 0, 0, 1]) for v in range(70)}, {v: rng.random() < 0.8 for v in range(70)}
    edges = spark.createDataFrame(sorted(arcs), "src long, dst long")
    verts = spark.createDataFrame([(v, level[v], active[v]) for v in {a for a, _ in arcs}], "vid long, level int, active boolean")
    grouped = []
    whole = levels.picked_of_lists
    monkeypatch.setattr(levels, "picked_of_lists", lambda *x: grouped.append(1) or whole(*x))
    for pick in ("min_id", "hash"):
        cfg = levels.LevelConfig(beta0=5, pick=pick)
        state = levels.State(edges, verts, levels.plan_budget(70, 150, cfg), cfg, iteration=2)
        found = []
        for most, large in ((10**6, 10**6), (0, 10**6), (10**6, 0)):
            monkeypatch.setattr(levels, "PACKED", most)
            monkeypatch.setattr(levels, "LARGE", large)
            found.append(sorted(map(tuple, levels.link_leveled(state, state.seen).collect())))
        assert found[0] == found[1] == found[2] and len(found[0]) == len({x[:2] for x in found[0]}) > len(arcs)
        assert all(x[2:] == (level[x[0]], active[x[0]], level[x[1]], active[x[1]]) for x in found[0])
    assert len(grouped) == 4


def test_a_path_is_followed_without_written_tables(spark, monkeypatch):
    maps = [spark.createDataFrame(m, "old long, new long") for m in ([(1, 2), (4, 5)], [(2, 9), (5, 4)], [(7, 8)])]
    monkeypatch.setattr(measures, "cut", None)
    assert measures.stand_ins([1, 2, 3, 4, 1], maps) == [9, 9, 3, 4, 9]
    arcs = spark.createDataFrame([(a, b) for i in range(4) for a, b in ((i, i + 1), (i + 1, i))], "src long, dst long")
    verts = spark.createDataFrame([(v, 0, True) for v in range(5)], "vid long, level int, active boolean")
    cfg = levels.LevelConfig(beta0=8)
    state = levels.State(arcs, verts, levels.plan_budget(5, 4, cfg), cfg)
    monkeypatch.setattr(levels, "step", lambda s: replace(s, log=[*s.log, *maps]))
    assert [r["vertices"] for r in measures.coin_audit(state, list(range(5)), most=1)][0] == 5
