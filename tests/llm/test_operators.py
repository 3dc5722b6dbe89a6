"""Each operator against a brute-force version, over a real table and over a table of odd cases."""

import base64
import collections
import hashlib
import math
import re
import zlib

import numpy as np
import pytest

from tidegraph.llm import language_id, lz_fingerprint, ngram_lm, pareto_mix, robust_quality, sentence_pieces, substring_dedup, url_rules, warc
from tidegraph.llm.queries import MODEL, RULES

DATA = "/root/testdata/sf0.001"
WORD = re.compile("[^\x20\x09-\x0d]+")
LONG = " ".join(f"w{i % 97}x{i % 89}" for i in range(30_000))
ODD = [
    (1, None, "en", "a"), (2, "", None, "a"), (3, "   \n\t ", "en", None), (4, "one", "de", "b"), (5, "Ünïcode wörds 日本語 🎉 x", "fr", "b"),
    (6, "same text here again and again", "en", "a"), (7, "same text here again and again", "en", "a"), (7, "same text here again and again", "en", "a"),
    (None, "no id at all", "en", "c"), (8, LONG, "en", "a"), (9, LONG + " tail", "en", "a"), (10, "l1 a\nl2\nl1 a\n\nl1 a\n#$ %", "es", "b"), (11, "a\x0bb\x0cc\x85d\xa0e f ▁g", "en", "b"),
]
SCHEMA = "doc_id long, text string, lang string, source string, `_id` string, n_words string, block int"


@pytest.fixture(scope="module")
def real(spark):
    return spark.read.parquet(f"{DATA}/documents.parquet")


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame([(*r, "x", "y", 3) for r in ODD], SCHEMA)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def rows_of(df):
    return [(r["doc_id"], r["text"]) for r in df.select("doc_id", "text").collect()]


def words(text):
    return WORD.findall(text or "")


@pytest.mark.parametrize("name", ["real", "odd"])
def test_statistics(name, request):
    df = request.getfixturevalue(name)
    got = collections.Counter(tuple(r) for r in robust_quality.judge(df).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed").collect())
    want = collections.Counter()
    for i, text in rows_of(df):
        w = words(text)
        seen, dups = set(), 0
        for line in (text or "").split("\n"):
            if words(line):
                dups += line in seen
                seen.add(line)
        grams = collections.Counter(tuple(w[j : j + 5]) for j in range(len(w) - 4))
        again = {k for j in range(len(w) - 4) if grams[tuple(w[j : j + 5])] > 1 for k in range(j, j + 5)}
        want[(i, len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text or "")), dups, len(again), len(w) < 10 or 100 * len(again) > 20 * len(w))] += 1
    assert got == want


def test_mcd_rejects_planted_outliers_only(spark):
    rng = np.random.default_rng(5)
    make = lambda n: " ".join("".join(rng.choice(list("abcdefgh"), rng.integers(3, 9))) for _ in range(n))
    clean = [(i, make(120), "en", f"s{i % 2}") for i in range(400)]
    junk = [(1000 + i, " ".join("#$%" * 5 for _ in range(60)) + make(20), "en", "s0") for i in range(40)]
    got = {r["doc_id"]: r["kept"] for r in robust_quality.judge(spark.createDataFrame(clean + junk, "doc_id long, text string, lang string, source string")).collect()}
    assert sum(not got[i] for i, *_ in clean) == 0
    assert not any(got[i] for i, *_ in junk)


def test_chi_square_values():
    """Against known values."""
    assert abs(robust_quality.chi2_quantile(0.95, 4) - 9.487729) < 1e-5
    assert abs(robust_quality.chi2_cdf(3.0, 2) - (1 - math.exp(-1.5))) < 1e-12


def test_warc_round_trip(spark, tmp_path):
    pages = spark.read.parquet(f"{DATA}/pages.parquet").select("page_id", "url", "html")
    extra = spark.createDataFrame([(100_001, "http://x/ y", "dup"), (100_002, None, "dup"), (100_003, "u", None), (100_004, "u", ""), (100_005, "u", "é" * 70_000)], pages.schema)
    pages = pages.unionByName(extra)
    want, first = {}, {}
    for r in sorted(pages.collect(), key=lambda r: r["page_id"]):
        data = (r["html"] or "").encode()
        to = first.setdefault(data, r["page_id"])
        want[r["page_id"]] = (len(data), base64.b32encode(hashlib.sha1(data).digest()).decode(), "response" if to == r["page_id"] else "revisit", None if to == r["page_id"] else to, True)
    folder = str(tmp_path / "a")
    got = {r["page_id"]: tuple(r)[1:] for r in warc.archived(pages, folder, roll_bytes=20_000, shard_bytes=100_000).collect()}
    assert got == want
    manifest = spark.read.parquet(f"{folder}/_manifest").collect()
    for m in manifest:
        assert hashlib.sha256(open(m["path"], "rb").read()).hexdigest() == m["sha256"]
    assert len(manifest) > 5
    other = warc.write_archive(pages, str(tmp_path / "b"), roll_bytes=20_000, shard_bytes=100_000).collect()
    assert {(m["shard"], m["part"], m["sha256"]) for m in manifest} == {(m["shard"], m["part"], m["sha256"]) for m in other}
    full = {r["page_id"]: r["payload"] for r in warc.read_archive(spark, folder, payloads=True).collect()}
    assert full["100005"] == "é" * 70_000
    assert not [p for p in (tmp_path / "a").iterdir() if p.name.startswith(".tmp")]


def test_mix_comes_near_targets_and_reruns_agree(real, odd, empty):
    got = pareto_mix.mix(real).collect()
    assert sorted(map(tuple, got)) == sorted(map(tuple, pareto_mix.mix(real).collect()))
    by = collections.defaultdict(list)
    source = {r["doc_id"]: r["source"] for r in real.collect()}
    for r in got:
        assert r["taken"] <= 2 * r["size"]
        by[source[r["doc_id"]]].append(r)
    total = sum(r["size"] for r in got)
    assert abs(sum(rows[0]["target"] for rows in by.values()) - 1.5 * total) < 1e-6 * total
    for rows in by.values():
        assert abs(sum(r["taken"] for r in rows) - rows[0]["target"]) <= max(r["size"] for r in rows)
    assert pareto_mix.mix(odd).count() == len(ODD)
    assert pareto_mix.mix(empty).count() == 0


def test_targets_reshare_what_capped_sources_leave(spark):
    df = spark.createDataFrame([(s, n) for s, n in [("a", 10), ("b", 1000), ("c", 90), ("d", 0), (None, 400)]], "_source string, size long")
    got = {r["_source"]: r["target"] for r in pareto_mix.source_targets(df).collect()}
    size = {"a": 10, "b": 1000, "c": 90, "d": 0, None: 400}
    w = {"a": 3, "b": 1, "c": 2, "d": 3, None: 1}
    goal, open_, want = 1.5 * sum(size.values()), set(size), {}
    while True:
        rate = (goal - sum(want.values())) / sum(w[s] for s in open_)
        over = {s for s in open_ if rate * w[s] > 2 * size[s]}
        if not over:
            break
        want |= {s: 2 * size[s] for s in over}
        open_ -= over
    want |= {s: rate * w[s] for s in open_}
    assert all(abs(got[s] - want[s]) < 1e-9 for s in size)


def test_url_rules(spark):
    urls = [None, "", "no scheme.net/", "http://a.NET/", "http://a.net", "http://net/", "http://xnet/", "https://de.example.net/en/1?x", "https://example.net/en", "http://Example.com/de/a#b?c", "http://a.org/fr/", "http://a.org/fr?utm_source=1", "http://b.org/x?page=2&ref=z", "ftp://x.org/fr/\nq", "http://a.com/?q=http://b.net/"]
    df = spark.createDataFrame([(i, u) for i, u in enumerate(urls)], "page_id long, url string")
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in url_rules.judge(df, RULES).collect()}
    rules = [("net", "/", "net/", "block"), ("example.net", "/en/", "example.net/en/", "allow"), ("example.com", "/de/", "example.com/de/", "block"), ("org", "/fr/", "org/fr/", "allow")]
    for i, u in enumerate(urls):
        u = u or ""
        host = path = tail = ""
        if "://" in u:
            rest = u.split("://", 1)[1]
            host = re.split("[/?#]", rest)[0]
            tail = rest[len(host) :]
            path = re.split("[?#]", tail)[0]
            host = re.sub("[A-Z]", lambda m: m[0].lower(), host)
        fit = [r for r in rules if (host == r[0] or host.endswith("." + r[0])) and path.startswith(r[1])]
        best = max(fit, key=lambda r: len(r[2]), default=None)
        if best:
            want = (host, path, best[2], best[3])
        elif re.search(r"[?&]page=[0-9]+&ref=", tail):
            want = (host, path, "paged referrals", "block")
        elif "?utm_source=" in tail or "&utm_source=" in tail:
            want = (host, path, "campaign links", "block")
        else:
            want = (host, path, None, "allow")
        assert got[i] == want, u
    assert url_rules.judge(df, []).where("rule is null and verdict = 'allow'").count() == len(urls)
    assert url_rules.judge(df.limit(0), RULES).count() == 0


@pytest.mark.parametrize("name", ["real", "odd"])
def test_fingerprints(name, request):
    df = request.getfixturevalue(name)
    got = lz_fingerprint.fingerprints(df, block_bytes=40_000).collect()
    rows = sorted(((-(1 << 63) if i is None else i, t or "", i) for i, t in rows_of(df)), key=lambda r: (-r[0], r[1]))
    want = collections.Counter()
    for k, (_, t, i) in enumerate(rows):
        half, after = len(t) // 2, rows[(k + 1) % len(rows)][1]
        edited = t[: len(t) - half] + after[:half]
        a, b, c = map(lz_fingerprint.fingerprint, (t, edited, after))
        want[(i, len(t), hashlib.sha256(edited.encode()).hexdigest(), lz_fingerprint.as_text(a), lz_fingerprint.as_text(b), lz_fingerprint.likeness(a, b), lz_fingerprint.likeness(a, c))] += 1
    assert collections.Counter(map(tuple, got)) == want


def test_phrases_are_the_lempel_ziv_parse():
    data = b"abababababcabcabcaaaa"
    ends: list[int] = []
    lz_fingerprint.phrase_ends(data, {}, 0, ends, 0)
    seen, start, want = set(), 0, []
    for e in range(1, len(data) + 1):
        if data[start:e] not in seen:
            seen.add(data[start:e])
            want.append(e)
            start = e
    assert ends == want


@pytest.mark.parametrize("order", [1, 2, 3])
@pytest.mark.parametrize("name", ["real", "odd"])
def test_backoff_scores(name, order, request):
    df = request.getfixturevalue(name)
    texts = [words(t) for _, t in rows_of(df)]
    counts = collections.Counter(tuple(w[j : j + n]) for w in texts for n in range(1, order + 1) for j in range(len(w) - n + 1))
    total = sum(map(len, texts))
    want = collections.Counter()
    for (i, _), w in zip(rows_of(df), texts, strict=True):
        s = 0.0
        for j in range(len(w)):
            factor = 1.0
            for n in range(min(order, j + 1), 0, -1):
                g = tuple(w[j - n + 1 : j + 1])
                if n == 1:
                    s += math.log10(factor * counts[g] / total)
                elif counts[g] >= 2:
                    s += math.log10(factor * counts[g] / counts[g[:-1]])
                    break
                factor *= 0.4
        want[(i, len(w), f"{s / len(w):.8f}" if w else "none")] += 1
    got = ngram_lm.backoff_scores(df, order=order, block_bytes=50_000).collect()
    assert collections.Counter((r["doc_id"], r["n_words"], "none" if r["score"] is None else f"{r['score']:.8f}") for r in got) == want


@pytest.mark.parametrize("name", ["real", "odd"])
def test_sentence_pieces(name, request):
    import sentencepiece

    df = request.getfixturevalue(name)
    sp = sentencepiece.SentencePieceProcessor(model_file=MODEL)
    want = collections.Counter((i, tuple(sp.encode(t or ""))) for i, t in rows_of(df))
    tokens = sentence_pieces.encode(df.select("doc_id", "text"), MODEL)
    got = tokens.collect()
    assert collections.Counter((r["doc_id"], tuple(r["ids"])) for r in got) == want
    back = sentence_pieces.decode(tokens, MODEL).collect()
    assert collections.Counter(map(tuple, back)) == collections.Counter((i, (t or "").replace("▁", " ")) for i, t in rows_of(df))


def test_sentence_pieces_with_a_rich_alphabet(spark):
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=MODEL)
    texts = [" ".join(chr(c) + chr(c + 1) + "ing" for c in range(a, a + 400)) for a in (0x100, 0x400, 0x4E00, 0xAC00)] + ["    two  spaces   and\ttabs" * 3]
    got = sentence_pieces.encode(spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string").coalesce(1), MODEL).collect()
    assert {r["doc_id"]: list(r["ids"]) for r in got} == {i: sp.encode(t) for i, t in enumerate(texts)}


def test_language_held_out_accuracy(spark, real, odd, empty):
    df = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = {r["doc_id"]: r for r in language_id.identify(df).collect()}
    truth = {r["doc_id"]: r["lang"] for r in df.select("doc_id", "lang").collect()}
    held = [i for i in truth if zlib.crc32(str(i).encode()) % 5 == 0]
    assert {i for i, r in got.items() if r["held_out"]} == set(held)
    assert sum(got[i]["lang_pred"] == truth[i] for i in held) / len(held) > 0.97
    odd_rows = language_id.identify(odd).collect()
    assert {r["doc_id"]: r["lang_pred"] for r in odd_rows if r["doc_id"] in (1, 2, 3)} == {1: "und", 2: "und", 3: "und"}
    assert all(0 <= r["score"] <= 1 for r in odd_rows) and len(odd_rows) == len(ODD)
    assert language_id.identify(empty).count() == 0


def test_naive_bayes_equals_a_plain_version(real):
    rows = real.limit(60).collect()
    df = real.sparkSession.createDataFrame(rows, real.schema)
    langs, priors, table = language_id.train(df, orders=(1, 2), bits=10)
    counts = {x: np.zeros(1 << 10) for x in langs}

    def buckets(text):
        chars, offs = language_id._code_points(__import__("pyarrow").array([text]))
        return [b[ok] for b, ok in language_id._buckets(chars, offs, (1, 2), 10)]

    for r in rows:
        for b in buckets(r["text"]):
            counts[r["lang"]] += np.bincount(b, minlength=1 << 10)
    for i, x in enumerate(langs):
        assert np.allclose(table[i], np.log((counts[x] + 0.5) / (counts[x] + 0.5).sum()))
    got = {r["doc_id"]: r["lang_pred"] for r in language_id.predict(df, (langs, priors, table), keep=("doc_id",), orders=(1, 2), bits=10).collect()}
    for r in rows:
        s = [priors[i] + sum(table[i][b].sum() for b in buckets(r["text"])) for i in range(len(langs))]
        assert got[r["doc_id"]] == langs[int(np.argmax(s))]


@pytest.mark.parametrize("name", ["real", "odd"])
def test_substring_dedup(name, request):
    df = request.getfixturevalue(name)
    rows = sorted(rows_of(df), key=lambda r: (r[0] is not None, r[0] or 0, r[1] is not None, r[1] or ""))
    seen, want = set(), collections.Counter()
    for i, t in rows:
        w = words(t)
        gone = [False] * len(w)
        for j in range(len(w) - 19):
            key = tuple(w[j : j + 20])
            if key in seen:
                gone[j : j + 20] = [True] * 20
            seen.add(key)
        want[(i, len(w), sum(gone), " ".join(x for x, g in zip(w, gone, strict=True) if not g))] += 1
    for size in (None, 30_000):
        got = substring_dedup.mark_repeats(df, block_bytes=size).collect()
        assert collections.Counter(map(tuple, got)) == want
    spans = substring_dedup.mark_repeats(df, factors=True, block_bytes=30_000).collect()
    for r in spans:
        covered = {k for f in r["factors"] for k in range(f["start"], f["start"] + f["words"])}
        assert len(covered) == r["n_removed"] and all(f["words"] >= 20 for f in r["factors"])


def test_empty_tables(empty):
    for df in (robust_quality.judge(empty), lz_fingerprint.fingerprints(empty), ngram_lm.backoff_scores(empty), sentence_pieces.encode(empty.select("doc_id", "text"), MODEL), substring_dedup.mark_repeats(empty)):
        assert df.count() == 0
