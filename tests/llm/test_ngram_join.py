"""The n-gram Jaccard join against all pairs, and the bitmap filter's bound."""

import collections
import random

import pytest

from tests.llm.test_operators import DATA, ODD, SCHEMA, WORD
from tidegraph.llm import ngram_join

LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def families():
    """Texts that are edited step by step, so that similarities lie on both sides of the threshold and chains form."""
    rng, rows = random.Random(5), []
    for f in range(12):
        text = [f"f{f}w{rng.randrange(400)}" for _ in range(rng.choice([12, 40, 90, 250]))]
        for _ in range(14):
            for _ in range(rng.choice([0, 1, 1, 2, 4])):
                text = [*text]
                text[rng.randrange(len(text))] = f"e{rng.randrange(30)}"
            rows.append((len(rows) + 1, " ".join(text), "en", "a", "x", "y", 3))
    return rows


def shingles(text, k):
    w = WORD.findall((text or "").translate(LOWER))
    return {tuple(w[i : i + k]) for i in range(max(1, len(w) - k + 1))} if w else set()


def by_all_pairs(rows, k, percent):
    sets = [shingles(t, k) for _, t in rows]
    root = list(range(len(rows)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i, a in enumerate(sets):
        for j in range(i):
            b = sets[j]
            if a and b and 100 * min(len(a), len(b)) >= percent * max(len(a), len(b)) and 100 * len(a & b) >= percent * len(a | b):
                root[find(i)] = find(j)
    least = {}
    for i, (d, _) in enumerate(rows):
        if d is not None:
            least[find(i)] = min(least.get(find(i), d), d)
    return collections.Counter((d, len(sets[i]), least.get(find(i))) for i, (d, _) in enumerate(rows)), len({find(i) for i in range(len(rows))})


@pytest.mark.parametrize("name", ["real", "odd", "families"])
@pytest.mark.parametrize(("k", "percent"), [(4, 85), (5, 80)])
def test_components_equal_all_pairs(spark, name, k, percent):
    made = {"odd": [(*r, "x", "y", 3) for r in ODD], "families": families()}
    df = spark.createDataFrame(made[name], SCHEMA) if name in made else spark.read.parquet(f"{DATA}/documents.parquet")
    rows = [(r["doc_id"], r["text"]) for r in df.select("doc_id", "text").collect()]
    want, components = by_all_pairs(rows, k, percent)
    got = ngram_join.similar_groups(df, k=k, percent=percent, block_bytes=30_000).collect()
    assert collections.Counter((r["doc_id"], r["n_shingles"], r["component_id"]) for r in got) == want
    assert sum(r["first"] for r in got) == components


def test_empty_table(spark):
    assert ngram_join.similar_groups(spark.createDataFrame([], SCHEMA)).count() == 0


@pytest.mark.parametrize(("flipped", "passes"), [(14, True), (15, False)])
def test_bitmap_filter_at_its_bound(spark, flipped, passes):
    """Sets of 93 and 93 need 86 shared shingles at 85 percent, so 14 may differ."""
    bits = [(1 << flipped) - 1, *[0] * (ngram_join.WORDS - 1)]
    df = spark.createDataFrame([(bits, [0] * ngram_join.WORDS, 93, 93)], "x array<long>, y array<long>, nx long, ny long")
    assert df.select(ngram_join._differ_little("x", "y", "nx", "ny", 85).alias("p")).first()["p"] is passes
