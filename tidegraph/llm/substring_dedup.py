"""Substring deduplication by relative Lempel-Ziv parsing against all earlier reference blocks.

Every block of documents is a reference block, indexed by the hashes of its k-word windows in a hash-partitioned
index. The index answers each window with the addresses of its first and of its nearest earlier occurrence, in
whatever block. A document is then factored greedily from left to right: at a word whose window occurs earlier, both candidates are
extended, window by window, along consecutive addresses of their reference, and the longer one becomes the factor
(k words at least); the parse goes on behind it. A word whose window is new is a literal.

Factors are the duplicate spans. What they leave open are windows that straddle a factor's end: the k - 1 starts before each
end are looked up, and the last one that occurs earlier becomes a factor of its own, of k words. So the removed words are
exactly those that a window with an earlier occurrence covers, whichever candidates the factors were extended along. Extension
goes along the two listed occurrences only: a longer match with a third one shows as two factors.

Cases: null or wordless text has no words and nothing to remove. Ties: rows with the same id are
ordered by text, null ids come first, and equal rows count as one before the other. A document
shorter than k words is kept whole. Empty tables give an empty result. Only the named columns are
read; `keep` columns pass through unchanged under their own names.
Windows are compared by 64-bit hashes (expected false matches: windows^2 / 2^65).
"""

from __future__ import annotations

from itertools import compress

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tidegraph.llm.blocks import ADDRESS, earlier, earlier_of, exchange, ordered, with_blocks
from tidegraph.llm.textpack import carried, windows, words_of

FACTOR = "array<struct<start:int,words:int,block:long,word:long>>"


def reaches(first: np.ndarray, near: np.ndarray, linked: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """How many windows in a row, from each on, lie at consecutive addresses of its first (its nearest) candidate.

    first, near: addresses by window, -1 for none; linked: whether the next window starts one word further in the same document.
    Chains of windows are jumped along in doubling steps.
    """
    n = len(first)
    place = np.concatenate([first, near])
    to = np.full(2 * n + 1, 2 * n)
    for c in (0, 1):
        want = place[c * n : (c + 1) * n] + 1
        go = np.flatnonzero((want[:-1] > 0) & linked[:-1])
        hit_near, hit_first = near[go + 1] == want[go], first[go + 1] == want[go]
        to[c * n + go[hit_near]] = n + go[hit_near] + 1
        to[c * n + go[hit_first]] = go[hit_first] + 1
    length = np.append((place >= 0).astype(np.int64), 0)
    while (to[:-1] < 2 * n).any():
        length, to = length + np.where(to < 2 * n, length[to], 0), to[to]
    return length[:n], length[n : 2 * n]


def factored(first: np.ndarray, near: np.ndarray, at: np.ndarray, doc: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Greedy factors: first word, words, address. at: the word at which each window starts, ascending; doc: its document."""
    linked = np.append((np.diff(at) == 1) & (np.diff(doc) == 0), False)[: len(at)]
    a, b = reaches(first, near, linked)
    best, where = np.where(b > a, b, a), np.where(b > a, near, first)
    open_ = np.flatnonzero(first >= 0)
    starts, lengths, ends = at[open_], best[open_], at[open_] + best[open_] + k - 1
    after = np.searchsorted(starts, ends)  # the next candidate start behind each factor
    picked, i = [], 0
    after_list = after.tolist()
    while i < len(after_list):
        picked.append(i)
        i = after_list[i]
    picked = np.array(picked, np.int64)
    return starts[picked], lengths[picked] + k - 1, where[open_][picked]


def with_borders(start: np.ndarray, size: np.ndarray, where: np.ndarray, first: np.ndarray, at: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The factors, and for each one's end the last repeated window that straddles it, as one more factor of k words.

    All repeated windows across one end share the words beside it, so the last of them covers what the others do behind the end.
    """
    open_ = np.flatnonzero(first >= 0)
    ends = start + size
    last = np.searchsorted(at[open_], ends) - 1
    across = open_[last[at[open_][last] > ends - k]] if len(open_) else open_
    start, size, where = np.append(start, at[across]), np.append(size, np.full(len(across), k)), np.append(where, first[across])
    by = np.argsort(start, kind="stable")
    return start[by], size[by], where[by]


def mark_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = 20, keep: tuple[str, ...] = (), factors: bool = False, block_bytes: int | None = None) -> DataFrame:
    """One row a document: id, keep columns, n_words, n_removed, kept_text (kept words, one space between).

    With factors: also the factors of the parse in order (first word, words; the reference's block, and in it the word). Where
    blocks begin changes a reference's address, not the factors.
    """
    clash = {"n_words", "n_removed", "kept_text", "factors"} & {id_col, *keep}
    if clash:
        raise ValueError(f"keep columns clash with results: {sorted(clash)}")
    picked = docs.select(F.col(id_col).alias("_id"), F.col(text_col).alias("_text"), *[F.col(f"`{c}`").alias(x) for c, x in zip(keep, carried(keep, text_col), strict=True) if x != "_text"])
    blocked, n = with_blocks(picked, "_id", "_text", block_bytes)
    parts = max(1, n // 2)
    schema = T.StructType([f for f in picked.schema if f.name != "_text" or text_col in keep] + [T.StructField("n_words", T.LongType()), T.StructField("n_removed", T.LongType()), T.StructField("kept_text", T.StringType())])
    if factors:
        schema = schema.add(T.StructField("factors", T._parse_datatype_string(FACTOR)))

    def ask(table: pa.Table) -> dict:
        h, at = windows(words_of(ordered(table)["_text"]), k)
        keys, first = np.unique(h, return_index=True)
        return {0: (keys, at[first])}

    def finish(table: pa.Table, said: dict) -> pa.Table:
        if not table.num_rows:
            return pa.Table.from_batches([], out_schema)
        block = table["_block"][0].as_py()
        table = ordered(table)
        w = words_of(table["_text"])
        h, at = windows(w, k)
        first, near = candidates(h, at, said, block)
        start, size, where = factored(first, near, at, w.doc[at], k)
        start, size, where = with_borders(start, size, where, first, at, k)
        n = len(w.hashes)
        gone = np.cumsum(np.bincount(start, minlength=n + 1) - np.bincount(start + size, minlength=n + 1))[:-1] > 0
        kept, raw, data = [], w.counts, w.data.tobytes()
        taken = np.add.reduceat(np.append(gone, 0), np.minimum(w.woff[:-1], len(gone))) * (raw > 0)
        for d in range(len(raw)):
            words = data[w.offs[d] : w.offs[d + 1]].split()
            if taken[d]:
                words = compress(words, ~gone[w.woff[d] : w.woff[d + 1]])
            kept.append(b" ".join(words).decode())
        cols = {c: table[c] for c in out_schema.names if c in table.column_names}
        cols |= {"n_words": pa.array(raw, pa.int64()), "n_removed": pa.array(taken, pa.int64()), "kept_text": pa.array(kept, pa.string())}
        if factors:
            cols["factors"] = listed(w, start, size, where)
        return pa.table([cols[f.name].cast(f.type) if f.name != "factors" else cols[f.name] for f in out_schema], schema=out_schema)

    def candidates(h: np.ndarray, at: np.ndarray, said: dict, block: int) -> tuple[np.ndarray, np.ndarray]:
        """Addresses of the first and the nearest earlier occurrence of each window; -1 where there is none."""
        if not len(h):
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        keys, own, inverse = np.unique(h, return_index=True, return_inverse=True)
        first, near = (x[inverse] for x in earlier_of(said.get(0, {}), keys, parts))
        order = np.argsort(inverse, kind="stable")
        same = inverse[order][1:] == inverse[order][:-1]
        again, before = order[1:][same], order[:-1][same]  # windows that the block itself has further left, and the last such place
        here = (block << ADDRESS) + at
        near[again] = here[before]
        alone = again[first[again] < 0]
        first[alone] = here[own[inverse[alone]]]
        return first, near

    def listed(w, start, size, where):
        doc = w.doc[start] if len(start) else start
        offs = np.searchsorted(doc, np.arange(len(w.counts) + 1)).astype(np.int32)
        items = pa.StructArray.from_arrays([pa.array(start - w.woff[doc], pa.int32()), pa.array(size, pa.int32()), pa.array(where >> ADDRESS), pa.array(where & ((1 << ADDRESS) - 1))], fields=list(out_schema.field("factors").type.value_type))
        return pa.ListArray.from_arrays(pa.array(offs), items, type=out_schema.field("factors").type)

    from pyspark.sql.pandas.types import to_arrow_schema

    out_schema = to_arrow_schema(schema)
    out = exchange(blocked, ask, earlier, finish, schema, parts)
    named = [F.col("_id").alias(id_col), *[F.col(x).alias(c) for x, c in zip(carried(keep, text_col), keep, strict=True)]]
    return out.select(*named, "n_words", "n_removed", "kept_text", *(["factors"] if factors else []))
