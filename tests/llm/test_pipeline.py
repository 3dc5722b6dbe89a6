"""The pipeline, and op1's estimates, against plain versions over all rows."""

import collections
import hashlib
import math
import re

import numpy as np
import pytest

from tests.llm.test_ngram_join import by_all_pairs
from tests.llm.test_operators import DATA, words
from tidegraph.llm import pareto_mix, robust_quality
from tidegraph.llm.queries import MODEL

H, STEPS, FLOOR, REJECT, LEAST = 0.75, 5, 0.06, 1e-7, 40


def statistics(text):
    w = words(text)
    lines = [x for x in (text or "").split("\n") if words(x)]
    grams = collections.Counter(tuple(w[j : j + 5]) for j in range(len(w) - 4))
    again = {k for j in range(len(w) - 4) if grams[tuple(w[j : j + 5])] > 1 for k in range(j, j + 5)}
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text or "")), len(lines), len(lines) - len(set(lines)), len(again)


def plain_distances(rows):
    """(id, lang, source, text) -> squared distance by id, None where the base rules fail or no group is large enough."""
    stats = {i: statistics(t) for i, _, _, t in rows}
    fit = [r for r in rows if stats[r[0]][0] >= 10 and 100 * stats[r[0]][5] <= 20 * stats[r[0]][0]]
    x = {i: np.array([math.log((c + 1) / (n + 1)), math.sqrt(s / max(c, 1)), math.sqrt(d / max(k, 1)), math.sqrt(a / max(n, 1))]) for i, (n, c, s, k, d, a) in stats.items()}
    sizes = collections.Counter((lang, source) for _, lang, source, _ in fit)
    rest = collections.Counter()
    for (lang, _), n in sizes.items():
        rest[lang] += n if n < LEAST else 0
    group = {r[0]: (r[1], r[2]) if sizes[r[1:3]] >= LEAST else (r[1],) if rest[r[1]] >= LEAST else () for r in fit}
    out = dict.fromkeys(stats)
    for g in set(group.values()):
        ids = [i for i in group if group[i] == g]
        if len(ids) < LEAST:
            continue
        m = np.array([x[i] for i in ids])
        quart = [np.sort(m, axis=0)[math.ceil(p * len(ids)) - 1] for p in (0.25, 0.5, 0.75)]
        centre, inverse = quart[1], np.diag(1 / (((quart[2] - quart[0]) / 1.349) ** 2 + FLOOR**2))
        for step in range(STEPS):
            d2 = np.maximum(np.einsum("ij,jk,ik->i", m - centre, inverse, m - centre), 0)
            bins = np.floor(64 * np.log2(d2 + 2.0**-20))
            near = m[bins <= np.sort(bins)[math.ceil(H * len(ids)) - 1]]
            centre = near.mean(axis=0)
            scale = H / robust_quality.chi2_cdf(robust_quality.chi2_quantile(H, 4), 6) if step == STEPS - 1 else 1.0
            inverse = np.linalg.inv(np.cov(near.T, bias=True) * scale + np.eye(4) * FLOOR**2)
        for i, z in zip(ids, m - centre, strict=True):
            out[i] = max(float(z @ inverse @ z), 0.0)
    return out, set(group)


def rows_of(df):
    return [tuple(r) for r in df.select("doc_id", "lang", "source", "text").collect()]


def test_estimates_equal_a_plain_version(spark):
    df = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    want, fit = plain_distances(rows_of(df))
    got = {r["doc_id"]: r for r in robust_quality.judge(df).collect()}
    limit = robust_quality.chi2_quantile(1 - REJECT, 4)
    assert sum(d is not None for d in want.values()) > 500
    for i, d in want.items():
        assert (got[i]["distance2"] is None) == (d is None)
        assert d is None or got[i]["distance2"] == pytest.approx(d, rel=1e-6, abs=1e-9)
        assert got[i]["kept"] == (i in fit and (d is None or d <= limit))


def plain_cut(rows):
    """(id, text) -> the same by id, without windows of 20 words that start earlier."""
    seen, out = set(), []
    for i, t in sorted(rows):
        w = words(t)
        gone = [False] * len(w)
        for j in range(len(w) - 19):
            key = tuple(w[j : j + 20])
            if key in seen:
                gone[j : j + 20] = [True] * 20
            seen.add(key)
        if not any(gone):
            out.append((i, t))
        elif not all(gone):
            out.append((i, " ".join(x for x, g in zip(w, gone, strict=True) if not g)))
    return out


def plain_copies(rows, seed=17):
    """(id, source, size) -> copies by id: whole copies, then the head of the ranking that comes nearest to the target."""
    size = collections.Counter()
    for _, s, n in rows:
        size[s] += n
    order = sorted(size, key=lambda s: (s is None, s or ""))
    weight = {s: (3, 1, 2)[k % 3] for k, s in enumerate(order)}
    goal, open_, target = 1.5 * sum(size.values()), set(size), {}
    while open_:
        rate = (goal - sum(target.values())) / sum(weight[s] for s in open_)
        over = {s for s in open_ if rate * weight[s] > 2 * size[s]}
        target |= {s: 2 * size[s] if over else rate * weight[s] for s in over or open_}
        open_ -= over or open_
    copies = {}
    for s in size:
        docs = [(i, n, len(f"{n:b}")) for i, source, n in rows if source == s]
        capped: set[int] = set()  # weights at two copies; the rest share what these leave by weight
        while True:
            free = sum(n * w for _, n, w in docs if w not in capped)
            rate = (target[s] - 2 * sum(n for _, n, w in docs if w in capped)) / free if free else 0.0
            over = {w for _, _, w in docs if w not in capped and rate * w > 2}
            if not over:
                break
            capped.add(max(over))
        mean = {w: 0.0 if not size[s] else 2.0 if w in capped or target[s] >= 2 * size[s] else rate * w for _, _, w in docs}
        left, upto, ranked = target[s] - sum(int(mean[w]) * n for _, n, w in docs), 0, []
        for i, n, w in docs:
            copies[i] = int(mean[w])
            f = mean[w] % 1
            u = (int(hashlib.md5(f"{seed}:{i}".encode()).hexdigest()[:13], 16) + 0.5) / 2**52
            if f > 0:
                ranked.append(((u / (1 - u)) / (f / (1 - f)), i, n))
        for _, i, n in sorted(ranked):
            upto += n
            copies[i] += upto <= left or (upto - n / 2 <= left and upto - n < left)
    return copies


def test_pipeline_equals_a_plain_version(spark, tmp_path):
    import sentencepiece

    import corpus_pipeline

    real = spark.read.parquet(f"{DATA}/documents.parquet")
    odd = spark.createDataFrame([(900_001, None, None, None, None), (900_002, "", "en", "a", 0), (900_003, "few words", None, "b", None), (900_004, " ".join(f"w{k % 997}y{k % 89}" for k in range(20_000)), None, None, None)], "doc_id long, text string, lang string, source string, n_chars long")
    docs = real.unionByName(odd.select(*[odd[c].cast(real.schema[c].dataType) for c in real.columns]))
    docs.write.parquet(f"{tmp_path}/documents.parquet")

    rows = rows_of(docs)
    by = {i: (lang, source) for i, lang, source, _ in rows}
    distance, fit = plain_distances(rows)
    limit = robust_quality.chi2_quantile(1 - REJECT, 4)
    kept = sorted((i, t) for i, _, _, t in rows if i in fit and (distance[i] is None or distance[i] <= limit))
    assert 0 < len(kept) < len(rows)
    groups = collections.defaultdict(list)
    for i, _, c in by_all_pairs(kept, 5, 80)[0]:
        groups[c].append(i)
    firsts = {min(g) for g in groups.values()}
    assert len(firsts) < len(kept)
    clean = plain_cut([(i, t) for i, t in kept if i in firsts])
    copies = plain_copies([(i, by[i][1], len(words(t))) for i, t in clean])
    sp = sentencepiece.SentencePieceProcessor(model_file=MODEL)
    want = collections.Counter()
    for i, t in clean:
        want[(i, *by[i], tuple(sp.encode(t)))] += copies[i]
    got = collections.Counter((r["doc_id"], r["lang"], r["source"], tuple(r["ids"])) for r in corpus_pipeline.run(spark, str(tmp_path)).collect())
    assert got == +want


def test_pipeline_of_an_empty_table(spark, tmp_path):
    import corpus_pipeline

    spark.read.parquet(f"{DATA}/documents.parquet").limit(0).write.parquet(f"{tmp_path}/documents.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0


def test_targets_of_an_empty_source(spark):
    df = spark.createDataFrame([(1, None, "a"), (2, "x y", "b")], "doc_id long, text string, source string")
    assert {r["doc_id"]: r["taken"] for r in pareto_mix.mix(df).collect()} == plain_taken([(1, "a", 0), (2, "b", 2)])


def plain_taken(rows):
    copies = plain_copies(rows)
    return {i: copies[i] * n for i, _, n in rows}
