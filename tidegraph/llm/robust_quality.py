"""Quality rules from robust multivariate outliers: minimum covariance determinant by language and source.

Each text becomes a vector of transformed statistics. Per (lang, source) the h rows whose covariance
has the least determinant are sought by concentration steps: from a coordinate-wise robust start,
the h nearest rows give the next centre and scatter, until the steps end. Rows whose squared
Mahalanobis distance to the final estimate, scaled for consistency at the normal law, passes a chi-square quantile
are rejected. All steps are aggregates over all rows: the h-th distance is read off a
histogram by group (64 bins to each doubling of the distance; rows of the last bin all count as
near), so no group is ever gathered. The parameters of groups (sources x languages) are broadcast after a count, or joined over
salts beyond it; rows stay where they were read, so a hot source costs its share only.

Cases: null text has no words; null lang or source is a value like any other. Groups under `min_group` fitted rows
are pooled by language, then over all; a pool still smaller rejects nothing. Rows that fail the base
rules never enter a fit. A scatter without spread is held up by `floor` on each axis. Repeated rows are judged
alike. Empty tables give an empty result. Extra columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tidegraph.functions.session import cut, stored
from tidegraph.functions.keyed import attach
from tidegraph.llm.textpack import carried, covered, edges_of, mix, per_doc, pieces, prefix_hash, span_hash, windows, words_of

SYMBOLS = np.zeros(256, np.int64)
SYMBOLS[list(b"#*$%&|<>")] = 1
STATS = "n_words long, word_chars long, n_symbols long, n_lines long, n_dup_lines long, n_repeat_words long"
FEATURES = ("x0", "x1", "x2", "x3")
P = len(FEATURES)
PIECE = 500_000  # bytes of text measured at a time: a dozen arrays of eight times as many bytes are alive at once


def _within(keys: np.ndarray, doc: np.ndarray) -> np.ndarray:
    return mix(keys ^ mix(doc.astype(np.uint64)))


def measure(batches: Iterator[pa.RecordBatch], with_text: bool = False) -> Iterator[pa.RecordBatch]:
    for part in pieces(batches, "_text", PIECE):
        w = words_of(part.column("_text"))
        new_line = w.data == 10
        words = w.counts
        in_word = np.zeros(len(w.data) + 1, np.int64)
        np.add.at(in_word, w.starts, 1)
        np.add.at(in_word, w.ends, -1)
        in_word = np.cumsum(in_word[:-1]) > 0
        ls, le = edges_of(~new_line, w.offs)  # empty lines hold no word and never count as repeats
        has = np.searchsorted(w.starts, le) > np.searchsorted(w.starts, ls)
        doc = np.searchsorted(w.offs, ls, side="right") - 1
        line = _within(span_hash(prefix_hash(w.data), ls, le), doc)[has]
        _, at = np.unique(line, return_index=True)
        dup = np.ones(len(line), bool)
        dup[at] = False
        h, start = windows(w, 5)
        _, inverse, n = np.unique(_within(h, w.doc[start]), return_inverse=True, return_counts=True)
        again = covered(len(w.hashes), start[n[inverse] > 1], 5) if len(h) else np.zeros(len(w.hashes), bool)
        count = lambda d: np.bincount(d, minlength=part.num_rows).astype(np.int64)
        found = [words, per_doc((in_word & ((w.data & 0xC0) != 0x80)).astype(np.int64), w.offs), per_doc(SYMBOLS[w.data], w.offs), count(doc[has]), count(doc[has][dup]), per_doc(again, w.woff)]
        names = [c for c in part.schema.names if with_text or c != "_text"]
        cols = [part.column(c) for c in names]
        yield pa.RecordBatch.from_arrays([*cols, *[pa.array(x, pa.int64()) for x in found]], names=[*names, *[x.split()[0] for x in STATS.split(", ")]])


def text_statistics(docs: DataFrame, text_col: str = "text", keep: dict[str, str] | None = None, carry: tuple[str, ...] = ()) -> DataFrame:
    """keep: column -> its name in the result, beside the statistics. carry: further columns, named _k0, _k1 ...; the text stays _text."""
    keep = keep or {}
    picked = docs.select(*[F.col(f"`{c}`").alias(n) for c, n in keep.items()], *[F.col(f"`{c}`").alias(n) for c, n in zip(carry, carried(carry, text_col), strict=True) if n != "_text"], F.col(text_col).alias("_text"))
    with_text = text_col in carry
    schema = T.StructType([*[f for f in picked.schema if with_text or f.name != "_text"], *T._parse_datatype_string(STATS)])
    return picked.mapInArrow(lambda batches: measure(batches, with_text), schema)


def chi2_cdf(x: float, k: int) -> float:
    """Regularised lower incomplete gamma by its series."""
    a, z = k / 2, x / 2
    term = total = math.exp(-z + a * math.log(z) - math.lgamma(a + 1)) if z > 0 else 0.0
    n = 0
    while term > 1e-17 * max(total, 1e-300) and n < 10_000:
        n += 1
        term *= z / (a + n)
        total += term
    return min(1.0, total)


def chi2_quantile(p: float, k: int) -> float:
    lo, hi = 0.0, 1000.0
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if chi2_cdf(mid, k) < p else (lo, mid)
    return hi


def features() -> list:
    share = lambda a, b: F.sqrt(F.col(a) / F.greatest(F.col(b), F.lit(1)))
    return [F.log((F.col("word_chars") + 1.0) / (F.col("n_words") + 1.0)), share("n_symbols", "word_chars"), share("n_dup_lines", "n_lines"), share("n_repeat_words", "n_words")]


def _distance():
    m = [F.col("m")[i] for i in range(P)]
    z = [F.col(x) - m[i] for i, x in enumerate(FEATURES)]
    terms = [F.col("inv")[i * P + j] * z[i] * z[j] * (1.0 if i == j else 2.0) for i in range(P) for j in range(i, P)]
    total = terms[0]
    for t in terms[1:]:
        total = total + t
    return F.greatest(total, F.lit(0.0))


def _estimates(floor: float, scale: float):
    def run(frames):
        for pdf in frames:
            ms, invs = [], []
            for row in pdf.itertuples(index=False):
                n = max(row.n, 1)
                m = np.array(row.s1, float) / n
                c = np.zeros((P, P))
                c[np.triu_indices(P)] = np.array(row.s2, float) / n
                c = c + np.triu(c, 1).T - np.outer(m, m)
                ms.append(m.tolist())
                invs.append(np.linalg.inv(c * scale + np.eye(P) * floor**2).ravel().tolist())
            pdf["m"], pdf["inv"] = ms, invs
            yield pdf[["g", "m", "inv"]]

    return run


def judge(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", source_col: str = "source", h: float = 0.75, steps: int = 5, floor: float = 0.06, reject: float = 1e-7, min_group: int = 40, min_words: int = 10, repeat_percent: int = 20, keep: tuple[str, ...] = ()) -> DataFrame:
    """One row a document: id, keep columns, the statistics, base_failed, distance2 (null: base rules failed or no fit), kept.

    Only statistics are stored. With keep columns, documents are read and measured a second time beside the final estimates, so no text is written or shuffled.
    """
    named = {id_col: "_id", lang_col: "_lang", source_col: "_source"}

    def measured(carry: tuple[str, ...]) -> DataFrame:
        base_failed = (F.col("n_words") < min_words) | (100 * F.col("n_repeat_words") > repeat_percent * F.col("n_words"))
        return text_statistics(docs, text_col, named, carry).select("*", base_failed.alias("base_failed"), *[x.alias(n) for n, x in zip(FEATURES, features(), strict=True)])

    stats = stored(measured(()), "quality-stats")
    fit = ~F.col("base_failed")
    sizes = stats.where(fit).groupBy("_lang", "_source").agg(F.count("*").alias("n_ls"))
    big = F.col("n_ls") >= min_group
    sizes = sizes.withColumn("n_l", F.sum(F.when(~big, F.col("n_ls"))).over(Window.partitionBy("_lang")))
    g = F.when(big, F.to_json(F.struct(F.lit(2).alias("level"), "_lang", "_source"))).when(F.col("n_l") >= min_group, F.to_json(F.struct(F.lit(1).alias("level"), "_lang"))).otherwise(F.lit("{}"))
    sizes = cut(sizes.select(F.col("_lang").alias("l"), F.col("_source").alias("s"), g.alias("g"), "n_ls"))
    enough = sizes.groupBy("g").agg(F.sum("n_ls").alias("n_g")).where(F.col("n_g") >= min_group)
    sizes = cut(sizes.join(enough, "g"))
    rows = attach(stats.where(fit), sizes, {"_lang": "l", "_source": "s"}).select("g", "n_g", *FEATURES)

    quarters = rows.groupBy("g").agg(*[F.percentile_approx(x, F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75)), F.lit(2000)).alias(f"q{i}") for i, x in enumerate(FEATURES)])
    spread = lambda i: F.pow((F.col(f"q{i}")[2] - F.col(f"q{i}")[0]) / 1.349, 2) + floor**2
    params = cut(quarters.select("g", F.array(*[F.col(f"q{i}")[1] for i in range(P)]).alias("m"), F.array(*[1.0 / spread(i) if i == j else F.lit(0.0) for i in range(P) for j in range(P)]).alias("inv")))
    level = F.floor(64 * F.log2(F.col("d2") + 2.0**-20)).cast("int")
    cross = [(i, j) for i in range(P) for j in range(i, P)]
    cutoff2 = chi2_quantile(h, P)
    consistent = h / chi2_cdf(cutoff2, P + 2)
    for step in range(steps):
        near = attach(rows, params.withColumnRenamed("g", "_g"), {"g": "_g"}).withColumn("d2", _distance()).withColumn("bin", level)
        bins = near.groupBy("g", "n_g", "bin").agg(F.count("*").alias("c"))
        upto = bins.withColumn("cum", F.sum("c").over(Window.partitionBy("g").orderBy("bin"))).where(F.col("cum") >= F.ceil(h * F.col("n_g"))).groupBy("g").agg(F.min("bin").alias("last"))
        sums = attach(near, cut(upto.withColumnRenamed("g", "_g")), {"g": "_g"}).where("bin <= last").groupBy("g").agg(F.count("*").alias("n"), F.array(*[F.sum(x) for x in FEATURES]).alias("s1"), F.array(*[F.sum(F.col(FEATURES[i]) * F.col(FEATURES[j])) for i, j in cross]).alias("s2"))
        params = cut(sums.mapInPandas(_estimates(floor, consistent if step == steps - 1 else 1.0), "g string, m array<double>, inv array<double>"))
    known = cut(sizes.join(params, "g").select("l", "s", "m", "inv"))
    out = attach(measured(keep) if keep else stats, known, {"_lang": "l", "_source": "s"}, "left")
    d2 = F.when(fit, _distance())
    ok = fit & (F.coalesce(d2, F.lit(0.0)) <= F.lit(chi2_quantile(1 - reject, P)))
    return out.select(F.col("_id").alias(id_col), *[F.col(n).alias(c) for n, c in zip(carried(keep, text_col), keep, strict=True)], "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", ok.alias("kept"), d2.alias("distance2"))
