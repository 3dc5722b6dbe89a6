"""Stupid-backoff language-model scores from relational n-gram counts over the whole corpus.

n-gram counts live in tables partitioned by hash range. Each block of documents explodes its texts
into n-grams, sends its distinct ones with their counts to the tables (so counts cover every document),
receives the corpus counts back by the same join, and sums the scores per document. The first n-1
words of a document use the shorter contexts they have. An n-gram seen fewer than `min_count` times
is not in the table: the score backs off to the shorter one, times `backoff` for each step down;
the unigram score is count / words of the corpus.

Cases: null or wordless text: n_words 0, score null. Equal texts score alike. An empty table
gives an empty result. Only the named columns are read. n-grams are told apart by 64-bit hashes.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tidegraph.functions.session import cut
from tidegraph.llm.blocks import exchange, sums, totals_of, with_blocks
from tidegraph.llm.textpack import per_doc, windows, words_of


def _grams(table: pa.Table, order: int):
    w = words_of(table["_text"])
    return w, {n: (w.hashes, np.arange(len(w.hashes))) if n == 1 else windows(w, n) for n in range(1, order + 1)}


def backoff_scores(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", order: int = 2, min_count: int = 2, backoff: float = 0.4, block_bytes: int | None = None) -> DataFrame:
    """One row a document: id, n_words, n_backoff (words scored below the full order they could have), log10_sum, score (mean log10)."""
    picked = docs.select(F.col(id_col).alias("_id"), F.col(text_col).alias("_text"))
    blocked, blocks = with_blocks(picked, "_id", "_text", block_bytes)
    id_type = picked.schema["_id"].dataType.simpleString()

    def ask(table: pa.Table) -> dict:
        out = {}
        for n, (h, _) in _grams(table, order)[1].items():
            keys, counts = np.unique(h, return_counts=True)
            out[n] = keys, counts.astype(np.uint32)
        return out

    def finish(table: pa.Table, said: dict) -> pa.Table:
        w, grams = _grams(table, order)
        n_words = len(w.hashes)
        counts = {}
        for n, (h, at) in grams.items():  # corpus count of the n-gram that starts at each word
            _, inverse = np.unique(h, return_inverse=True)
            counts[n] = np.zeros(n_words, np.float64)
            counts[n][at] = totals_of(said.get(n, {}))[inverse] if len(h) else 0
        place = np.arange(n_words) - np.repeat(w.woff[:-1], w.counts)
        score, steps, open_ = np.zeros(n_words), np.zeros(n_words, np.int64), np.ones(n_words, bool)
        for n in range(order, 1, -1):
            can = open_ & (place >= n - 1)
            i = np.flatnonzero(can)
            full, context = counts[n][i - n + 1], counts[n - 1][i - n + 1]
            hit = full >= min_count
            score[i[hit]] = np.log10(full[hit] / context[hit])
            open_[i[hit]] = False
            steps[i[~hit]] += 1
        score[open_] = np.log10(counts[1][open_]) if open_.any() else 0
        score += np.log10(backoff) * steps
        cols = [table["_id"], pa.array(w.counts, pa.int64()), pa.array(per_doc(steps > 0, w.woff), pa.int64()), pa.array(per_doc(open_, w.woff), pa.int64()), pa.array(per_doc(score, w.woff), pa.float64())]
        return pa.Table.from_arrays(cols, names=["_id", "n_words", "n_backoff", "n_unigram", "s"])

    sums_ = cut(exchange(blocked, ask, sums, finish, f"_id {id_type}, n_words long, n_backoff long, n_unigram long, s double", max(1, blocks // 2)))
    words = sums_.agg(F.coalesce(F.sum("n_words"), F.lit(0)).cast("double")).first()[0]
    total = F.col("s") - F.col("n_unigram") * F.lit(float(np.log10(max(words, 1.0))))
    return sums_.select(F.col("_id").alias(id_col), "n_words", "n_backoff", total.alias("log10_sum"), F.when(F.col("n_words") > 0, total / F.col("n_words")).alias("score"))
