"""Language identification: multinomial naive Bayes over hashed character n-grams.

n-grams of code points (A-Z folded) hash into 2^bits buckets. Training sums bucket counts by language in
each task and adds them up by (language, bucket), with map-side halves, so no task sees more of a language than some of its buckets; it
covers every labelled row the caller passes. The smoothed log-probability matrix (languages x buckets, at most
`most_languages` x 2^bits x 8 bytes) is broadcast. A document's score for a language is the log prior plus the sum of
the matrix over its n-grams, gathered batch-wise in numpy; the posterior of the best one is the score.

Cases: null text, text without a letter, or no training rows: `und` with score 0. Ties go to the
first language by code point. A text shorter than n has only its shorter n-grams. Repeated rows train
once each and are predicted alike. Empty tables give an empty result. Extra columns are ignored.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tidegraph.llm.textpack import U, mix, per_doc, pieces, text_bytes

ORDERS = (1, 2, 3, 4)
BITS = 16


@lru_cache(1)
def _letters() -> np.ndarray:
    return np.array([chr(i).isalpha() for i in range(0x110000)])


def _code_points(column) -> tuple[np.ndarray, np.ndarray]:
    data, offs = text_bytes(column)
    chars = np.frombuffer(data.tobytes().decode("utf-8", "surrogatepass").encode("utf-32-le", "surrogatepass"), np.uint32)
    lead = np.zeros(len(data) + 1, np.int64)
    np.cumsum((data & 0xC0) != 0x80, out=lead[1:])
    return chars, lead[offs]


def _buckets(chars: np.ndarray, offs: np.ndarray, orders, bits: int):
    """For each order: bucket of the n-gram at each place, and whether the n-gram stays inside its document."""
    c = np.where((chars >= 65) & (chars <= 90), chars + 32, chars).astype(np.uint64)
    left = np.repeat(offs[1:], np.diff(offs)) - np.arange(len(c))
    h = np.zeros(len(c), np.uint64)
    for n in range(1, max(orders) + 1):
        h = h * U(0x9E3779B97F4A7C15)
        h[: len(c) - n + 1] += c[n - 1 :]
        if n in orders:
            yield (mix(h + U(n)) >> U(64 - bits)).astype(np.int64), left >= n


def train(docs: DataFrame, text_col: str = "text", lang_col: str = "lang", orders=ORDERS, bits: int = BITS, smoothing: float = 0.5, most_languages: int = 512):
    """(languages, log priors, log-probability matrix)."""
    rows = docs.where(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(lang_col).cast("string").alias("lang"), F.col(text_col).alias("_text"))

    def counted(batches):
        total: dict[str, list] = {}
        for part in pieces(batches, "_text"):
            chars, offs = _code_points(part.column("_text"))
            langs = np.array(part.column("lang").to_pylist(), object)
            by_char = np.repeat(np.arange(len(langs)), np.diff(offs))
            grams = list(_buckets(chars, offs, orders, bits))
            for lang in sorted(set(langs)):
                own = langs == lang
                mask = own[by_char]
                n = sum(np.bincount(b[mask & ok], minlength=1 << bits) for b, ok in grams)
                have = total.setdefault(lang, [0, np.zeros(1 << bits, np.int64)])
                have[0] += int(own.sum())
                have[1] += n
        for lang, (n, counts) in total.items():  # bucket -1 counts documents
            own = np.flatnonzero(counts)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * (len(own) + 1), pa.string()), pa.array(np.append(-1, own), pa.int32()), pa.array(np.append(n, counts[own]), pa.int64())], names=["lang", "bucket", "n"])

    def packed(table: pa.Table) -> pa.Table:  # at most 2^bits + 1 rows
        at, n = table["bucket"].to_numpy(), table["n"].to_numpy()
        counts = np.zeros(1 << bits, np.int64)
        counts[at[at >= 0]] = n[at >= 0]
        return pa.table({"lang": table["lang"][:1], "docs": pa.array(n[at < 0], pa.int64()), "counts": pa.array([counts.tobytes()], pa.binary())})

    added = rows.mapInArrow(counted, "lang string, bucket int, n long").groupBy("lang", "bucket").agg(F.sum("n").alias("n"))
    found = added.groupBy("lang").applyInArrow(packed, "lang string, docs long, counts binary").limit(most_languages + 1).collect()
    if len(found) > most_languages:
        raise ValueError(f"more than {most_languages} languages in the labels")
    found = sorted(found, key=lambda r: r["lang"].encode())
    if not found:
        return [], np.zeros(0), np.zeros((0, 1 << bits))
    counts = np.stack([np.frombuffer(r["counts"], np.int64) for r in found]).astype(np.float64) + smoothing
    priors = np.log(np.array([r["docs"] for r in found], np.float64) / sum(r["docs"] for r in found))
    return [r["lang"] for r in found], priors, np.log(counts / counts.sum(axis=1, keepdims=True))


def predict(docs: DataFrame, model, text_col: str = "text", keep: tuple[str, ...] = (), orders=ORDERS, bits: int = BITS) -> DataFrame:
    """keep columns, lang_pred, score."""
    if {"lang_pred", "score"} & {*keep}:
        raise ValueError("keep columns clash with results: lang_pred, score")
    shared = docs.sparkSession.sparkContext.broadcast(model)
    picked = docs.select(*[F.col(f"`{c}`").alias(f"_k{i}") for i, c in enumerate(keep)], F.col(text_col).alias("_text"))
    fields = [f"{f.name} {f.dataType.simpleString()}" for f in picked.schema if f.name != "_text"]

    def judged(batches):
        langs, priors, table = shared.value
        names = np.array([*langs, "und"], object)
        for part in pieces(batches, "_text"):
            chars, offs = _code_points(part.column("_text"))
            n = part.num_rows
            letters = per_doc(_letters()[chars].astype(np.int64), offs)
            best, score = np.full(n, len(langs)), np.zeros(n)
            if langs:
                total = np.repeat(priors[:, None], n, axis=1)
                for b, ok in _buckets(chars, offs, orders, bits):
                    for i in range(len(langs)):
                        total[i] += per_doc(np.where(ok, table[i][b], 0.0), offs)
                top = total.max(axis=0)
                best = np.where(letters > 0, total.argmax(axis=0), len(langs))
                score = np.where(letters > 0, 1 / np.exp(total - top).sum(axis=0), 0.0)
            yield pa.RecordBatch.from_arrays([*part.columns[: len(keep)], pa.array(names[best], pa.string()), pa.array(np.clip(score, 0, 1))], names=[*part.schema.names[: len(keep)], "lang_pred", "score"])

    out = picked.mapInArrow(judged, ", ".join([*fields, "lang_pred string, score double"]))
    return out.select(*[F.col(f"_k{i}").alias(c) for i, c in enumerate(keep)], "lang_pred", "score")


def identify(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", folds: int = 5) -> DataFrame:
    """Trains outside the fold crc32(id as text) mod folds = 0 and predicts every row: id, held_out, lang_pred, score."""
    fold = F.crc32(F.col(id_col).cast("string").cast("binary")) % folds
    model = train(docs.where(fold != 0), text_col, lang_col)
    rows = docs.select(F.col(id_col).alias("_id"), F.coalesce(fold == 0, F.lit(False)).alias("_h"), F.col(text_col).alias("_t"))
    return predict(rows, model, "_t", ("_id", "_h")).select(F.col("_id").alias(id_col), F.col("_h").alias("held_out"), "lang_pred", "score")
