"""What the second review asked for: factors, sampling frequencies, long runs, hot keys, odd rows."""

import collections
import random
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from tests.llm.test_operators import MODEL, words
from tidegraph.functions import keyed
from tidegraph.llm import blocks, pareto_mix, sentence_pieces, substring_dedup, url_rules, warc


def test_packed_keys_round_trip():
    rng = np.random.default_rng(3)
    for n in (0, 1, 2, 300, 20_000):
        for shift in (0, 9, 30, 60):
            keys = np.unique(rng.integers(0, 1 << 63, n, dtype=np.uint64) * np.uint64(2) >> np.uint64(shift))
            assert (blocks.unpack_sorted(blocks.pack_sorted(keys)) == keys).all()
    odd = np.array([0, 1, 127, 128, 1 << 21, (1 << 64) - 1], np.uint64)
    assert (blocks.from_varints(blocks.varints(odd)) == odd).all() and len(blocks.from_varints(b"")) == 0


def test_blocks_follow_bytes(spark):
    rows = [(i, "x" * (4000 if 100 <= i < 140 else 10)) for i in range(400)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    blocked, n = blocks.with_blocks(df, "doc_id", "text", 20_000)
    size = collections.Counter()
    span = collections.defaultdict(list)
    for r in blocked.collect():
        size[r["_block"]] += len(r["text"]) + 16
        span[r["_block"]].append(r["doc_id"])
    assert len(size) <= n and max(size.values()) <= 40_000
    order = [(min(x), max(x)) for _, x in sorted(span.items())]
    assert all(a[1] < b[0] for a, b in zip(order, order[1:], strict=False))


def passage(tag, n):
    return [f"{tag}{k}" for k in range(n)]


def test_a_passage_is_one_factor_wherever_parts_of_it_occur_first(spark):
    long = passage("p", 100)
    docs = [(1, passage("a", 30) + long[:20] + passage("b", 30)), (2, passage("c", 25) + long + passage("d", 25)), (3, passage("e", 40) + long + passage("f", 10)), (4, long[60:] + passage("g", 3))]
    df = spark.createDataFrame([(i, " ".join(w)) for i, w in docs], "doc_id long, text string")
    for size in (None, 400):
        got = {r["doc_id"]: r for r in substring_dedup.mark_repeats(df, factors=True, block_bytes=size).collect()}
        lists = {i: [(f["start"], f["words"]) for f in r["factors"]] for i, r in got.items()}
        assert lists == {1: [], 2: [(25, 20)], 3: [(40, 100)], 4: [(0, 40)]}


@pytest.mark.parametrize("seed", [1, 2])
def test_factors_are_earlier_text_and_cover_every_repeat(spark, seed):
    rng = random.Random(seed)
    pool = [passage(f"s{k}x", rng.randint(5, 60)) for k in range(12)]
    docs = []
    for i in range(60):
        w = []
        for _ in range(rng.randint(0, 6)):
            p = rng.choice(pool)
            a = rng.randrange(len(p))
            w += p[a:] if rng.random() < 0.5 else [f"n{rng.randrange(10**6)}" for _ in range(rng.randint(1, 15))]
        docs.append((i, w))
    df = spark.createDataFrame([(i, " ".join(w)) for i, w in docs], "doc_id long, text string")
    got = {r["doc_id"]: r for r in substring_dedup.mark_repeats(df, factors=True, block_bytes=1500).collect()}
    seen, before, longest = set(), [], 0
    for i, w in docs:
        gone = [False] * len(w)
        for j in range(len(w) - 19):
            if tuple(w[j : j + 20]) in seen:
                gone[j : j + 20] = [True] * 20
            seen.add(tuple(w[j : j + 20]))
        cover = [False] * len(w)
        text = " " + " ".join(w) + " "
        for f in got[i]["factors"]:
            own = w[f["start"] : f["start"] + f["words"]]
            cover[f["start"] : f["start"] + f["words"]] = [True] * f["words"]
            spot = " " + " ".join(own) + " "
            assert len(own) == f["words"] >= 20 and (any(spot in b for b in before) or text.find(spot) < len(" ".join(["", *w[: f["start"]]])))
            longest = max(longest, f["words"])
        assert cover == gone and got[i]["n_removed"] == sum(gone)
        before.append(text)
    assert longest > 25


def test_realised_frequencies_follow_the_inclusion_probabilities(spark):
    """300 sources of one make are 300 draws."""
    sizes = [3, 3, 5, 6, 9, 12, 20, 20, 33, 40, 41, 65, 90, 130, 200, 260, 300, 520]
    rows = [(s * 100 + k, f"s{s:03d}", " ".join(["w"] * n)) for s in range(300) for k, n in enumerate(sizes)]
    df = spark.createDataFrame(rows, "doc_id long, source string, text string").repartition(4)
    got = pareto_mix.mix(df, weights=(1,), share=0.5).collect()
    taken = collections.Counter()
    for r in got:
        taken[r["doc_id"] % 100] += r["copies"]
    rate = 0.5 * sum(sizes) / sum(n * n.bit_length() for n in sizes)
    for k, n in enumerate(sizes):
        assert abs(taken[k] / 300 - rate * n.bit_length()) < 0.1, (n, taken[k] / 300, rate * n.bit_length())
    assert taken[0] / 300 < 0.25 and taken[len(sizes) - 1] / 300 > 0.45


def test_parameters_beyond_the_broadcast_bound_give_the_same_rows(spark):
    rows = spark.createDataFrame([(i, None if i % 3 == 0 else "ab"[i % 2]) for i in range(50)], "i long, k string")
    params = spark.createDataFrame([(None, 1), ("a", 2)], "p string, x long")
    for how in ("inner", "left"):
        small, large = (sorted(map(str, keyed.attach(rows, params, {"k": "p"}, how, most).collect())) for most in (10, 1))
        assert small == large and len(small) == (50 if how == "left" else sum(i % 3 == 0 or i % 2 == 0 for i in range(50)))


def test_hot_keys_are_spread_without_loss(spark):
    many = spark.range(1000).select((F.col("id") % 7 == 0).cast("int").alias("k"), "id")
    few = spark.createDataFrame([(0, "x"), (1, "y"), (1, "z"), (2, "q")], "k int, v string")
    a, b = keyed.spread(many, few, ["k"], limit=100)
    got = a.join(b, ["k", "_salt"])
    assert collections.Counter((r["id"], r["v"]) for r in got.collect()) == collections.Counter((r["id"], r["v"]) for r in many.join(few, "k").collect())
    assert a.select("_salt").distinct().count() == 9
    assert keyed.spread(many, few, ["k"], limit=10**6)[0].select("_salt").distinct().count() == 1


@pytest.mark.parametrize("text", [" " * 1_000_000, "a" + " " * 4097 + "b" + " " * 3, "\n" * 5000 + " x" * 300 + " " * 77])
def test_long_runs_equal_the_library(text):
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=MODEL)
    with open(MODEL, "rb") as f:
        ids, offs = sentence_pieces.PieceModel(f.read()).encode([text])
    assert ids.tolist() == sp.encode(text) and offs.tolist() == [0, len(ids)]


def test_thousands_of_rules(spark):
    rng = random.Random(5)
    rules = [url_rules.host_rule(f"h{k}.example/p{k % 7}/", rng.choice(["block", "allow"])) for k in range(3000)]
    rules += [url_rules.pattern_rule("paged", "block", r"[?&]page=[0-9]+", ("page",))]
    urls = [f"https://www.h{rng.randrange(4000)}.example/p{rng.randrange(7)}/x?page={rng.randrange(9)}" for _ in range(300)] + [None, "", "no scheme", "http://h1.example"]
    df = spark.createDataFrame([(i, u, "x", "y", 1) for i, u in enumerate(urls)], "page_id long, url string, host string, path string, rule int")
    got = {r["page_id"]: r for r in url_rules.judge(df, rules).collect()}
    for i, u in enumerate(urls):
        at = (u or "").find("://")
        normal = u[at + 3 :] if at >= 0 else ""
        hits = [(r.weight, -k, r) for k, r in enumerate(rules) if re.search(r.pattern, normal)]
        best = max(hits)[2] if hits else None
        assert (got[i]["rule"], got[i]["verdict"]) == ((best.name, best.verdict) if best else (None, "allow"))
        assert got[i]["candidates"] <= 3
    assert url_rules.judge(df, []).where("verdict <> 'allow' or rule is not null").isEmpty()


def test_archive_of_odd_rows(spark, tmp_path):
    rows = [(None, "http://a/", "same"), (None, None, "same"), (3, "http://c/", "same"), (3, "http://c/", "same"), (2, "http://b/", None), (5, "http://e/ f", "ünï"), (4, "u", "")]
    df = spark.createDataFrame([(*r, "x", "y", 1) for r in rows], "page_id long, url string, html string, payload_bytes string, _id string, _kind int")
    got = sorted(map(str, warc.archived(df, str(tmp_path / "a")).select("page_id", "payload_bytes", "record_type", "refers_to", "verified").collect()))
    want = [(i, len((h or "").encode()), "revisit" if (h or "") == "" and i == 4 or h == "same" and i is None else "response", {4: 2}.get(i) if (h or "") == "" else 3 if h == "same" and i is None else None, True) for i, _, h in rows]
    assert collections.Counter(got) == collections.Counter(str(spark_row(*w)) for w in want)
    assert warc.archived(df.limit(0), str(tmp_path / "b")).count() == 0


def spark_row(i, n, kind, to, ok):
    from pyspark.sql import Row

    return Row(page_id=i, payload_bytes=n, record_type=kind, refers_to=to, verified=ok)


def test_pipeline_judges_rows_and_not_ids(spark):
    import corpus_pipeline

    rng = random.Random(9)
    text = lambda: " ".join(f"{rng.choice('abcdefg')}{rng.randrange(10**5)}" for _ in range(60))
    one, two, three = text(), text(), text()
    rows = [(None, one, "en", "a", 1, "r", 1), (None, "too short", "en", "a", 1, "r", 1), (None, two, "en", "a", 1, "r", 1), (7, three, "en", "a", 1, "r", 1), (7, "short as well", "en", "a", 1, "r", 1), (8, three + " more", "en", "a", 1, "r", 1), (9, one, None, None, 1, "r", 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, row string, kept int")
    try:
        good = corpus_pipeline.quality(spark, docs.drop("kept"), "")
        assert sorted(r["text"] for r in good.collect()) == sorted([one, two, three, three + " more", one])
        firsts = corpus_pipeline.near_duplicates(spark, good, "")
        assert sorted(map(str, ((r["doc_id"], r["text"]) for r in firsts.collect()))) == sorted(map(str, [(9, one), (None, two), (7, three)]))
        cut = corpus_pipeline.repeated_passages(spark, good, "")
        assert collections.Counter((r["doc_id"], len(words(r["text"]))) for r in cut.collect()) == {(None, 60): 2, (7, 60): 1, (8, 1): 1}
        mixed = corpus_pipeline.source_mix(spark, good, "")
        assert mixed.columns == good.columns and {r["text"] for r in mixed.collect()} <= {r["text"] for r in good.collect()}
    finally:
        assert good.columns == ["doc_id", "text", "lang", "source", "n_chars", "row"]
