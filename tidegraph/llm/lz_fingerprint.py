"""Lempel-Ziv phrase fingerprints and their likeness.

A text's UTF-8 bytes are parsed into dictionary phrases: each phrase is the shortest piece not met
before. The set of phrases is hashed, and the k smallest hashes are the fingerprint (a minimum-hash
signature of the phrase set). The likeness of two fingerprints estimates the Jaccard index of the
phrase sets from the k smallest hashes of their union, which follows how well one text's dictionary
compresses the other.

To pair each text with its successor by descending id, rows are dealt into id ranges, streamed in order
within each, and every range gets one more row: the first text of the range that follows
(after the last range: of the first). One text shuffle, bounded memory, no global window over rows.

Cases: ids are integers, or cast to them (others count as null); null text is empty; an empty text has an empty fingerprint, two of them are alike (1), one of
them is unlike any other text (0). Rows with the same id follow each other by text; a null id comes last. A
one-row table is its own successor. Empty tables give an empty result. Extra columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
from array import array
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tidegraph.functions.session import cut
from tidegraph.llm.blocks import with_blocks
from tidegraph.llm.textpack import pieces, prefix_hash, span_hash
from tidegraph.operators.primitives import global_index

K = 64
PIECE = 500_000  # bytes of texts whose rows are made together
CHUNK = 250_000  # bytes of texts hashed in one pass
MOST_BLOCKS = 500_000  # id ranges whose tops are broadcast


def phrases(data: bytes, trie: dict[int, int], node: int) -> tuple[int, array]:
    """Parses data; trie maps (node + byte) to the node below. Returns the open node, and for each phrase the bytes of data after its end."""
    rest = iter(data)
    left, get, after = rest.__length_hint__, trie.get, array("q")
    add, fresh = after.append, (len(trie) + 1) << 8
    for c in rest:
        key = node + c
        node = get(key)
        if node is None:
            trie[key] = fresh
            fresh += 256
            add(left())
            node = 0
    return node, after


def phrase_ends(data: bytes, trie: dict[int, int], node: int, ends: list[int], at: int) -> int:
    """Parses data from byte `at` on, and adds where phrases end. Returns the open node."""
    node, after = phrases(data[at:] if at else data, trie, node)
    ends.extend(len(data) - x for x in after)
    return node


def signature(data: bytes, ends: list[int], k: int = K) -> np.ndarray:
    if not ends:
        return np.zeros(0, np.uint32)
    e = np.array(ends)
    s = np.append(0, e[:-1])
    return np.unique((span_hash(prefix_hash(np.frombuffer(data, np.uint8)), s, e) >> np.uint64(32)).astype(np.uint32))[:k]


def likeness(a: np.ndarray, b: np.ndarray, k: int = K) -> float:
    if not len(a) and not len(b):
        return 1.0
    both = np.unique(np.concatenate([a, b]))[:k]
    return float((np.isin(both, a) & np.isin(both, b)).sum() / len(both))


def as_text(sig: np.ndarray) -> str:
    return base64.b64encode(sig.astype(">u4").tobytes()).decode()


class Parsed:
    """A text, and the parse of its first half, from which an edited form goes on.

    A parse is data and its phrases, as parts: (bytes up to the end of the part, bytes from each phrase's end to there).
    """

    def __init__(self, text: str):
        self.half = len(text) // 2
        self.chars = len(text)
        self.head = text[: len(text) - self.half].encode()
        self.trie: dict[int, int] = {}
        self.node, after = phrases(self.head, self.trie, 0)
        self.part = (len(self.head), after)

    def gone_on(self, tail: bytes, trie: dict[int, int]) -> tuple[bytes, list[tuple[int, array]]]:
        data = self.head + tail
        return data, [self.part, (len(data), phrases(tail, trie, self.node)[1])]

    def whole(self, text: str) -> tuple[bytes, list[tuple[int, array]]]:
        """The parse of the text itself."""
        return self.gone_on(text[len(text) - self.half :].encode(), self.trie.copy())

    def edited(self, after: str) -> tuple[bytes, list[tuple[int, array]]]:
        """The parse of the text with its last half replaced by the head of `after`; once only, as it writes to the dictionary."""
        return self.gone_on(after[: self.half].encode(), self.trie)


class Signatures:
    """Signatures of many texts, one after another: that of text i is values[offs[i] : offs[i + 1]]."""

    def __init__(self, values: np.ndarray, counts: np.ndarray):
        self.values, self.offs = values, np.append(0, np.cumsum(counts))

    def __getitem__(self, i: int) -> np.ndarray:
        return self.values[self.offs[i] : self.offs[i + 1]]

    def keyed(self, which: np.ndarray) -> np.ndarray:
        """The hashes of the texts `which`, below the place in `which`."""
        counts = self.offs[which + 1] - self.offs[which]
        ends = np.cumsum(counts)
        at = np.arange(ends[-1]) + np.repeat(self.offs[which] - ends + counts, counts)
        return np.repeat(np.arange(len(which), dtype=np.uint64) << np.uint64(32), counts) | self.values[at]


def signatures(parses: list[tuple[bytes, list[tuple[int, array]]]], first: list[np.ndarray], k: int = K) -> Signatures:
    """The given first signatures, and those of the parses, about CHUNK bytes of text (one text at least) in a numpy pass."""
    values, counts = [np.zeros(0, np.uint32), *first], [np.array([len(x) for x in first], np.int64)]
    a = 0
    while a < len(parses):
        b, size = a + 1, len(parses[a][0])
        while b < len(parses) and size + len(parses[b][0]) <= CHUNK:
            size += len(parses[b][0])
            b += 1
        data = np.frombuffer(b"".join([d for d, _ in parses[a:b]]), np.uint8)
        begin = np.append(0, np.cumsum([len(d) for d, _ in parses[a:b]]))
        found = np.array([sum(len(x) for _, x in parts) for _, parts in parses[a:b]])
        parts = [(off + upto, x) for off, (_, own) in zip(begin[:-1].tolist(), parses[a:b], strict=True) for upto, x in own]
        e = np.repeat([upto for upto, _ in parts], [len(x) for _, x in parts]) - np.concatenate([np.asarray(x) for _, x in parts])
        s = np.append(0, e[:-1])[: len(e)]
        firsts = np.cumsum(found) - found
        s[firsts[found > 0]] = begin[:-1][found > 0]
        doc = np.repeat(np.arange(b - a, dtype=np.uint64), found)
        key = np.sort((doc << np.uint64(32)) | (span_hash(prefix_hash(data), s, e) >> np.uint64(32)))
        key = key[np.append(True, key[1:] != key[:-1])[: len(key)]]
        least = in_group(key, b - a) < k
        values.append(key[least].astype(np.uint32))
        counts.append(np.bincount((key[least] >> np.uint64(32)).astype(np.int64), minlength=b - a))
        a = b
    return Signatures(np.concatenate(values), np.concatenate(counts))


def in_group(key: np.ndarray, groups: int) -> np.ndarray:
    """Each sorted key's place among those with the same upper half, a number below `groups`."""
    group = (key >> np.uint64(32)).astype(np.int64)
    return np.arange(len(key)) - np.searchsorted(group, np.arange(groups))[group]


def likenesses(sigs: Signatures, one: np.ndarray, other: np.ndarray, k: int = K) -> np.ndarray:
    """likeness of the signatures one[i] and other[i], for all i."""
    n = len(one)
    if not n:
        return np.zeros(0)
    key = np.sort(np.concatenate([sigs.keyed(one), sigs.keyed(other)]))
    new = np.append(True, key[1:] != key[:-1])[: len(key)]
    shared = ~np.append(new[1:], True)[: len(key)][new]
    key = key[new]
    least = in_group(key, n) < k
    pair = (key[least] >> np.uint64(32)).astype(np.int64)
    total = np.bincount(pair, minlength=n)
    return np.where(total == 0, 1.0, np.bincount(pair[shared[least]], minlength=n) / np.maximum(total, 1))


def fingerprint(text: str | None) -> np.ndarray:
    data = (text or "").encode()
    ends: list[int] = []
    phrase_ends(data, {}, 0, ends, 0)
    return signature(data, ends)


OUT = "n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def compared(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The operator's rows from the ordered stream of its ranges. A text is parsed alone; hashes and likenesses are taken for many rows at once."""
    wait = None  # the row whose successor is not yet known: id, parse, place of its signature, and between pieces the signature itself
    for batch in pieces(batches, "_text", PIECE):
        parses, first, rows = [], [], []  # a row: id, characters, SHA-256, and the places of three signatures: its own, the edited text's, the next text's
        if wait is not None:
            first.append(wait[3])
            wait = (*wait[:2], 0)
        for own, i, text in zip(batch.column("_own").to_pylist(), batch.column("_id").to_pylist(), batch.column("_text").to_pylist(), strict=True):
            now, place = Parsed(text), len(first) + len(parses)
            parses.append(now.whole(text))
            if wait is not None:
                of, row, at = wait
                edited = row.edited(text)
                parses.append(edited)
                rows.append((of, row.chars, hashlib.sha256(edited[0]).hexdigest(), at, place + 1, place))
            wait = (i, now, place) if own else None
        sigs = signatures(parses, first)
        if wait is not None:
            wait = (*wait, sigs[wait[2]].copy())
        of, chars, sha, at, edit, nxt = map(list, zip(*rows, strict=True)) if rows else ([] for _ in range(6))
        at, edit, nxt = (np.array(x, np.int64) for x in (at, edit, nxt))
        text = [pa.array([as_text(sigs[x]) for x in which], pa.string()) for which in (at, edit)]
        near = [pa.array(likenesses(sigs, at, which), pa.float64()) for which in (edit, nxt)]
        yield pa.RecordBatch.from_arrays([pa.array(of, batch.schema.field("_id").type), pa.array(chars, pa.int64()), pa.array(sha, pa.string()), *text, *near], names=["_id", *[x.split()[0] for x in OUT.split(", ")]])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", block_bytes: int | None = None) -> DataFrame:
    """One row a document: id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next."""
    lowest = -(1 << 63)
    rows = docs.select(F.col(id_col).alias("_id"), F.coalesce(F.col(id_col).cast("long"), F.lit(lowest)).alias("_key"), F.coalesce(F.col(text_col), F.lit("")).alias("_text"))
    rows, blocks = with_blocks(rows, "_key", "_text", block_bytes)
    tops = rows.groupBy(F.col("_block").alias("b")).agg(F.max("_key").alias("top"))
    if blocks <= MOST_BLOCKS:  # a row a range, 16 bytes each: few enough for one window and a broadcast
        up = Window.orderBy("b")
        tops = F.broadcast(tops.select("b", "top", F.coalesce(F.lead("b").over(up), F.first("b").over(up)).alias("to")))
    else:
        at = cut(global_index(tops, "b", "i"))
        following = at.select((F.col("i") - 1).alias("i"), F.col("b").alias("to"))
        tops = at.join(following, "i", "left").crossJoin(F.broadcast(at.agg(F.min("b").alias("least")))).select("b", "top", F.coalesce("to", "least").alias("to"))
    heads = rows.join(tops, (F.col("_block") == F.col("b")) & (F.col("_key") == F.col("top"))).groupBy("to").agg(F.min("_text").alias("_text"))
    id_type = rows.schema["_id"].dataType
    stream = rows.select("_block", F.lit(1).alias("_own"), "_key", "_id", "_text").unionByName(heads.select(F.col("to").alias("_block"), F.lit(0).alias("_own"), F.lit(lowest).alias("_key"), F.lit(None).cast(id_type).alias("_id"), "_text"))
    stream = stream.repartition("_block").sortWithinPartitions("_block", F.desc("_own"), F.desc("_key"), "_text")
    return stream.mapInArrow(compared, f"_id {id_type.simpleString()}, {OUT}").withColumnRenamed("_id", id_col)
