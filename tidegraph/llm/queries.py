"""The registered queries of this subpackage: each operator over its whole table, with production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tidegraph.llm import language_id, lz_fingerprint, ngram_join, ngram_lm, pareto_mix, robust_quality, sentence_pieces, substring_dedup, url_rules, warc

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
HOST_RULES = (("net/", "block"), ("example.net/en/", "allow"), ("example.com/de/", "block"), ("org/fr/", "allow"))
RULES = [
    *(url_rules.host_rule(n, v) for n, v in HOST_RULES),
    url_rules.pattern_rule("campaign links", "block", r"[?&]utm_source=", ("utm", "source")),
    url_rules.pattern_rule("paged referrals", "block", r"[?&]page=[0-9]+&ref=", ("page", "ref")),
]


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/pages.parquet")


def op1_robust_quality(spark, sf_dir):
    return robust_quality.judge(documents(spark, sf_dir), reject=1e-4)


def op2_warc_shards(spark, sf_dir):
    return warc.archived(pages(spark, sf_dir))


def op3_pareto_mix(spark, sf_dir):
    return pareto_mix.mix(documents(spark, sf_dir)).drop("copies")


def op4_url_rules(spark, sf_dir):
    """rule names the given rules only; a page that only a pattern judges has its verdict, but null there."""
    given = F.col("rule").isin([n for n, _ in HOST_RULES])
    return url_rules.judge(pages(spark, sf_dir), RULES).drop("candidates").withColumn("rule", F.when(given, F.col("rule")))


def op5_ngram_jaccard(spark, sf_dir):
    return ngram_join.similar_groups(documents(spark, sf_dir), k=4, percent=85).drop("first")


def op6_lz_fingerprint(spark, sf_dir):
    return lz_fingerprint.fingerprints(documents(spark, sf_dir))


def op7_backoff_scores(spark, sf_dir):
    """The sums are rounded, as their last digits depend on the order of addition."""
    scored = ngram_lm.backoff_scores(documents(spark, sf_dir))
    return scored.select("doc_id", "n_words", "n_backoff", *[F.round(c, 6).alias(c) for c in ("log10_sum", "score")])


def op8_sentence_pieces(spark, sf_dir):
    return sentence_pieces.encode(documents(spark, sf_dir), MODEL)


def op9_language_id(spark, sf_dir):
    return language_id.identify(documents(spark, sf_dir))


def op10_substring_dedup(spark, sf_dir):
    marked = substring_dedup.mark_repeats(documents(spark, sf_dir))
    return marked.select("doc_id", "n_words", "n_removed", F.sha2(F.col("kept_text"), 256).alias("kept_sha256"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = {k: v for k, v in globals().items() if k.startswith("op") and k[2].isdigit()}
    return dict(sorted(found.items(), key=lambda x: int(x[0][2:].split("_")[0])))


W = r"[^\x20\x09-\x0D]+"

_OP3 = rf"""
WITH d AS (SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '{W}')), 0) AS BIGINT) AS size FROM documents),
src AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source),
num AS (SELECT *, (row_number() OVER (ORDER BY source ASC NULLS LAST) - 1) % 3 AS k FROM src),
wts AS (SELECT source, source_size, CASE k WHEN 0 THEN 3 WHEN 1 THEN 1 ELSE 2 END AS w, source_size * 2 AS cap FROM num),
step AS (SELECT *, (1.5::DOUBLE * CAST(sum(source_size) OVER () AS DOUBLE) - CAST(coalesce(sum(cap) OVER (ORDER BY cap / w, source ASC NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS DOUBLE))
  / CAST(sum(w) OVER (ORDER BY cap / w, source ASC NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS DOUBLE) AS rate FROM wts),
lev AS (SELECT max(rate) AS lev FROM step WHERE rate <= cap / w),
tgt AS (SELECT source, source_size, least(CAST(cap AS DOUBLE), coalesce((SELECT lev FROM lev), 'infinity'::DOUBLE) * w) AS target FROM step),
cls AS (SELECT source, length(bin(size)) AS w, CAST(sum(size) AS BIGINT) AS words FROM d GROUP BY ALL),
lift AS (SELECT c.source, w, words, source_size, target, (target - CAST(coalesce(sum(words) OVER (PARTITION BY c.source ORDER BY w DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) * 2 AS DOUBLE))
  / CAST(nullif(sum(words * w) OVER (PARTITION BY c.source ORDER BY w DESC ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING), 0) AS DOUBLE) AS rate FROM cls c JOIN tgt t ON c.source IS NOT DISTINCT FROM t.source),
fit AS (SELECT *, (SELECT arg_max(l.rate, l.w) FROM lift l WHERE l.source IS NOT DISTINCT FROM lift.source AND l.rate * l.w <= 2) AS lev FROM lift),
cop AS (SELECT *, CASE WHEN source_size = 0 THEN 0.0::DOUBLE WHEN target >= source_size * 2 THEN 2.0::DOUBLE ELSE least(2.0::DOUBLE, coalesce(lev, 'infinity'::DOUBLE) * w) END AS pi FROM fit),
lef AS (SELECT *, target - CAST(sum(floor(pi) * words) OVER (PARTITION BY source) AS DOUBLE) AS rest FROM cop),
p AS (SELECT d.doc_id, d.size, t.source_size, t.target, d.source, t.pi, t.rest,
  (CAST(('0x' || substr(md5('17:' || CAST(doc_id AS VARCHAR)), 1, 13)) AS BIGINT) + 0.5::DOUBLE) / 4503599627370496.0::DOUBLE AS u
  FROM d JOIN lef t ON d.source IS NOT DISTINCT FROM t.source AND length(bin(d.size)) = t.w),
f AS (SELECT *, floor(pi) AS whole, pi - floor(pi) AS f FROM p),
q AS (SELECT *, CASE WHEN f > 0 THEN (u / (1 - u)) / (f / (1 - f)) END AS q FROM f),
c AS (SELECT *, sum(size) OVER (PARTITION BY source ORDER BY q, doc_id, size ROWS UNBOUNDED PRECEDING) AS upto FROM q)
SELECT doc_id, size, source_size, target, CAST((whole + CASE WHEN f > 0 AND (upto <= rest OR (upto - size / 2 <= rest AND upto - size < rest)) THEN 1 ELSE 0 END) * size AS BIGINT) AS taken FROM c
"""

_OP4 = r"""
WITH u AS (SELECT page_id, CASE WHEN instr(coalesce(url, ''), '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
h AS (SELECT page_id, rest, regexp_extract(rest, '^([^/?#]*)', 1) AS raw FROM u),
p AS (SELECT page_id, translate(raw, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(substr(rest, length(raw) + 1), '(?s)^([^?#]*)', 1) AS path, substr(rest, length(raw) + 1) AS tail FROM h),
r(name, verdict, rhost, rpath) AS (VALUES ('net/', 'block', 'net', '/'), ('example.net/en/', 'allow', 'example.net', '/en/'), ('example.com/de/', 'block', 'example.com', '/de/'), ('org/fr/', 'allow', 'org', '/fr/')),
m AS (SELECT p.page_id, p.host, p.path, p.tail, r.name, r.verdict, row_number() OVER (PARTITION BY p.page_id ORDER BY length(r.name) DESC NULLS LAST) AS k
  FROM p LEFT JOIN r ON (p.host = r.rhost OR ends_with(p.host, '.' || r.rhost)) AND starts_with(p.path, r.rpath))
SELECT page_id, host, path,
  coalesce(name, CASE WHEN regexp_matches(tail, '[?&]page=[0-9]+&ref=') THEN 'paged referrals' WHEN regexp_matches(tail, '[?&]utm_source=') THEN 'campaign links' END) AS rule,
  coalesce(verdict, CASE WHEN regexp_matches(tail, '[?&]page=[0-9]+&ref=') OR regexp_matches(tail, '[?&]utm_source=') THEN 'block' ELSE 'allow' END) AS verdict
FROM m WHERE k = 1
"""


WORDS = rf"t AS (SELECT doc_id, text, coalesce(regexp_extract_all(text, '{W}'), []) AS w FROM documents)"

_OP5 = rf"""
WITH RECURSIVE t AS (SELECT doc_id, coalesce(regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '{W}'), []) AS w FROM documents),
sh AS MATERIALIZED (SELECT DISTINCT doc_id, g FROM (
  SELECT doc_id, unnest(list_transform(range(1, len(w) - 2), lambda i: array_to_string(w[i:i + 3], ' '))) AS g FROM t WHERE len(w) >= 4
  UNION ALL SELECT doc_id, array_to_string(w, ' ') FROM t WHERE len(w) BETWEEN 1 AND 3)),
n AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM sh GROUP BY doc_id),
arcs AS MATERIALIZED (SELECT a.doc_id AS src, b.doc_id AS dst FROM sh a JOIN sh b ON a.g = b.g AND a.doc_id <> b.doc_id JOIN n x ON x.doc_id = a.doc_id JOIN n y ON y.doc_id = b.doc_id
  WHERE 100 * least(x.n, y.n) >= 85 * greatest(x.n, y.n) GROUP BY 1, 2, x.n, y.n HAVING 100 * count(*) >= 85 * (x.n + y.n - count(*))),
cc(id, comp) USING KEY (id) AS (SELECT DISTINCT src, src FROM arcs UNION
  (SELECT a.dst, min(c.comp) FROM cc c JOIN arcs a ON a.src = c.id JOIN recurring.cc r ON r.id = a.dst WHERE c.comp < r.comp GROUP BY a.dst))
SELECT t.doc_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_shingles, coalesce(cc.comp, t.doc_id) AS component_id FROM t LEFT JOIN n USING (doc_id) LEFT JOIN cc ON cc.id = t.doc_id
"""

_OP7 = rf"""
WITH {WORDS},
p AS MATERIALIZED (SELECT doc_id, i, w[i] AS w1, CASE WHEN i > 1 THEN w[i - 1] || ' ' || w[i] END AS w2, CASE WHEN i > 1 THEN w[i - 1] END AS w0 FROM (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS i FROM t)),
c1 AS (SELECT w1, count(*) AS c FROM p GROUP BY w1), c2 AS (SELECT w2, count(*) AS c FROM p WHERE w2 IS NOT NULL GROUP BY w2),
s AS (SELECT p.doc_id, i, coalesce(c2.c >= 2, false) AS hit, CASE WHEN c2.c >= 2 THEN log10(c2.c / c0.c) ELSE log10(c1.c / (SELECT count(*) FROM p)) + CASE WHEN i > 1 THEN log10(0.4::DOUBLE) ELSE 0 END END AS v
  FROM p JOIN c1 ON c1.w1 = p.w1 LEFT JOIN c2 ON c2.w2 = p.w2 LEFT JOIN c1 c0 ON c0.w1 = p.w0),
d AS (SELECT doc_id, count(*) FILTER (NOT hit AND i > 1) AS b, sum(v) AS v, count(*) AS n FROM s GROUP BY doc_id)
SELECT t.doc_id, CAST(len(t.w) AS BIGINT) AS n_words, CAST(coalesce(b, 0) AS BIGINT) AS n_backoff, round(coalesce(v, 0.0::DOUBLE), 6) AS log10_sum, round(v / n, 6) AS score FROM t LEFT JOIN d USING (doc_id)
"""

_OP10 = rf"""
WITH {WORDS},
win AS (SELECT doc_id, i, array_to_string(w[i:i + 19], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 18)) AS i FROM t WHERE len(w) >= 20)),
again AS (SELECT doc_id, i FROM (SELECT doc_id, i, row_number() OVER (PARTITION BY g ORDER BY doc_id, i) AS r FROM win) WHERE r > 1),
gone AS (SELECT DISTINCT doc_id, unnest(range(i, i + 20)) AS j FROM again),
kept AS (SELECT t.doc_id, j, x FROM (SELECT doc_id, unnest(range(1, len(w) + 1)) AS j, unnest(w) AS x FROM t) t ANTI JOIN gone USING (doc_id, j)),
txt AS (SELECT doc_id, string_agg(x, ' ' ORDER BY j) AS s, count(*) AS k FROM kept GROUP BY doc_id)
SELECT t.doc_id, CAST(len(t.w) AS BIGINT) AS n_words, CAST(len(t.w) - coalesce(k, 0) AS BIGINT) AS n_removed, sha256(coalesce(s, '')) AS kept_sha256 FROM t LEFT JOIN txt USING (doc_id)
"""


def oracle_sql() -> dict[str, str]:
    return {"op3_pareto_mix": _OP3, "op4_url_rules": _OP4, "op5_ngram_jaccard": _OP5, "op7_backoff_scores": _OP7, "op10_substring_dedup": _OP10}
