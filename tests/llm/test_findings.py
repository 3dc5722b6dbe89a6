"""What the first review found: each test fails on the code as it was then."""

import pytest
from pyspark.sql import functions as F

from tidegraph.llm import queries, robust_quality
from tidegraph.operators import levels
from tidegraph.plans import graphs
from tidegraph.plans import queries as graph_queries


def test_outliers_near_the_limit(spark, tmp_path):
    symbols = {1000: 25, 1001: 40, 1002: 45, 1003: 55, 1004: 68, 1005: 70}  # of 500 characters
    rows = [(i, with_symbols(i, symbols.get(i, 0)), "en", "a") for i in [*range(120), *symbols]]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r["doc_id"]: r for r in queries.op1_robust_quality(spark, str(tmp_path)).collect()}
    limit = robust_quality.chi2_quantile(1 - 1e-4, 4)
    assert 23 < limit < 24
    for i, n in symbols.items():
        assert abs(got[i]["distance2"] - n / 500 / 0.06**2) < 1e-6
        assert got[i]["kept"] == (n / 500 / 0.06**2 <= limit)
    assert [got[i]["kept"] for i in symbols] == [True, True, False, False, False, False]
    assert all(got[i]["kept"] for i in range(120))


@pytest.mark.parametrize("name", ["base_label_flood", "cc_shrink_only"])
def test_baselines_take_the_whole_graph(spark, name):
    data = "/root/testdata/sf0.001"
    edges = graphs.order_part(spark, data)
    ids = edges.select(F.col("u").alias("vertex")).union(edges.select("v")).distinct()
    got = graph_queries.queries()[name](spark, data)
    assert sorted(r["vertex"] for r in got.select("vertex").collect()) == sorted(r["vertex"] for r in ids.collect())


def test_methods_are_compared_on_one_graph(spark, monkeypatch):
    seen = []

    def run(edges, **_):
        seen.append(sorted(map(tuple, edges.collect())))
        return levels.ComponentsResult(None, [{"iteration": 1, "edges": len(seen[-1])}])

    monkeypatch.setattr(graph_queries.levels, "budgeted_components", run)
    monkeypatch.setattr(graph_queries.B, "exponentiation_components", run)
    monkeypatch.setattr(graph_queries.B, "label_flood_components", run)
    graph_queries.compare_methods(spark, "")
    assert len(seen) == 3 and len(seen[0]) == 200 and seen[0] == seen[1] == seen[2]


def with_symbols(i, n):
    """100 words of five letters; n letters, the first of each word and then the second, are pipes."""
    words = [list(f"{i * 100 + k:06d}"[-5:].translate(str.maketrans("0123456789", "abcdefghij"))) for k in range(100)]
    for k in range(n):
        words[k % 100][k // 100] = "|"
    return " ".join(map("".join, words))
