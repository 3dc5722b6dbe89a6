"""Blocks of documents, and the packed exchange of their hashed keys.

Documents are dealt into blocks of consecutive ids with about the same bytes. Each block sends its
distinct keys, sorted, to the key range (part) that owns them: one binary cell a block and part, in which keys
are packed without loss (gaps as variable bytes, low bytes as they are), so a
key costs about six bytes and not a row. A part sees each key at most once from a block, however many
documents repeat it, which is why a key that a third of all documents hold is no hot group. The part
answers every block in the order of its keys, and the block, read again beside its answers, goes on
with global knowledge. Results do not depend on where blocks end.
"""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

U = np.uint64
RANGES = 4096
REQUEST = "part long, block long, kind int, keys binary, extra binary"
REPLY = "block long, kind int, part long, answer binary"
ADDRESS = 32  # an address is a block's number, and below these bits a word's place in the block


def range_of(key: Column, bounds: list[int]) -> Column:
    """How many of the sorted bounds are at most key, in two steps of about sqrt(len(bounds)) comparisons each."""
    if not bounds:
        return F.lit(0)
    step = math.isqrt(len(bounds) - 1) + 1
    longs = lambda xs: f"array({','.join(f'{x}L' if x > -(1 << 63) else 'long(-9223372036854775808)' for x in xs)})"  # noqa: E731  (one literal to parse, not thousands of calls)
    upto = lambda xs: F.size(F.filter(xs, lambda b: b <= key))
    heads = upto(F.expr(longs(bounds[::step])))
    inner = F.expr(f"array({','.join(longs(bounds[i : i + step]) for i in range(0, len(bounds), step))})")
    return F.when(heads == 0, F.lit(0)).otherwise((heads - 1) * step + upto(F.get(inner, heads - 1)))


def with_blocks(docs: DataFrame, id_col: str, text_col: str, block_bytes: int | None = None) -> tuple[DataFrame, int]:
    """Adds _block, ascending with id_col (null first); returns the blocks' number too.

    One aggregate finds the bytes and quantiles of the ids, eight to a block (4,096 ranges at most); a second one weighs the ranges,
    and neighbours are joined while they fit block_bytes, so a stretch of long texts has more blocks than one of short
    texts. Past 4,096 blocks the heavy ranges are split evenly by id. The bounds become literals of the plan.
    """
    key = F.col(id_col).cast("long")
    size = F.coalesce(F.octet_length(F.col(text_col)), F.lit(0)) + 16
    total = docs.agg(F.sum(size)).first()[0] or 0
    if block_bytes is None:  # more than a few thousand blocks only when each is large
        block_bytes = int(min(64e6, max(2e6, total / 4000)))
    n = max(1, math.ceil(total / block_bytes))
    cuts = min(RANGES, 8 * n)
    shares = F.expr(f"array({','.join(f'{i / cuts!r}D' for i in range(1, cuts))})")
    row = docs.agg(F.percentile_approx(key, shares, F.lit(20000)).alias("q"), F.min(key).alias("lo"), F.max(key).alias("hi")).first() if n > 1 else None
    if row is None or row["q"] is None:
        return docs.withColumn("_block", F.lit(0).cast("long")), 1
    bounds = sorted({*row["q"]} - {row["lo"]})
    weights = {r["r"]: r["b"] for r in docs.groupBy(F.coalesce(range_of(key, bounds), F.lit(0)).alias("r")).agg(F.sum(size).alias("b")).collect()}  # a row a range: 4,096 at most
    edges, held = [], weights.get(0, 0)
    for i in range(1, len(bounds) + 1):
        w = weights.get(i, 0)
        if held and held + w > block_bytes:
            edges.append(bounds[i - 1])
            held = 0
        held += w
    fine = math.ceil(max(weights.values()) / block_bytes / 2) if n > RANGES else 1
    block = range_of(key, edges).cast("long")
    if fine > 1:
        firsts, lasts = [row["lo"], *edges], [*edges, row["hi"] + 1]
        lo, hi = (F.element_at(F.array(*[F.lit(e).cast("long") for e in part]), (block + 1).cast("int")) for part in (firsts, lasts))
        block = block * fine + F.least(F.lit(fine - 1), F.floor((key - lo) * fine / F.greatest(hi - lo, F.lit(1))))
    return docs.withColumn("_block", F.when(key.isNull(), 0).otherwise(block).cast("long")), max(1, (len(edges) + 1) * fine)


def ordered(table: pa.Table) -> pa.Table:
    """A block's rows by id and text, null ids first: one order at each reading, but for rows that agree on both."""
    return table.take(pc.sort_indices(table, [("_id", "ascending"), ("_text", "ascending")], null_placement="at_start"))


def part_edges(keys: np.ndarray, parts: int) -> np.ndarray:
    """Where each part's keys begin among sorted keys; parts split the hash range evenly."""
    firsts = np.array([(i << 64) // parts for i in range(parts)], dtype=np.uint64)
    return np.append(np.searchsorted(keys, firsts), len(keys))


def short_keys(parts: int) -> np.uint64:
    """The bits of a hash that a short key keeps: its part's (a power of two of them) and 40 more. Keys that agree on them count as one."""
    return U((1 << 64) - (1 << max(0, 24 - (parts.bit_length() - 1))))


def varints(values: np.ndarray) -> bytes:
    """Unsigned integers of seven bits a byte, low ones first; the high bit says that more follow."""
    v = values.astype(np.uint64)
    size = np.ones(len(v), np.int64)
    for k in range(1, 10):
        size += v >= U(1) << U(7 * k)
    ends = np.cumsum(size)
    out = np.zeros(int(ends[-1]) if len(ends) else 0, np.uint8)
    at = ends - size
    for k in range(int(size.max()) if len(size) else 0):
        own = np.flatnonzero(size > k)
        out[at[own] + k] = ((v[own] >> U(7 * k)) & U(127)).astype(np.uint8) | ((size[own] > k + 1) * 128).astype(np.uint8)
    return out.tobytes()


def from_varints(raw: bytes | np.ndarray) -> np.ndarray:
    b = np.frombuffer(raw, np.uint8)
    ends = np.flatnonzero(b < 128)
    starts = np.append(0, ends[:-1] + 1)[: len(ends)]
    out = np.zeros(len(ends), np.uint64)
    size = ends - starts + 1
    for k in range(int(size.max()) if len(size) else 0):
        own = np.flatnonzero(size > k)
        out[own] |= (b[starts[own] + k] & 127).astype(np.uint64) << U(7 * k)
    return out


def pack_sorted(keys: np.ndarray) -> bytes:
    """Sorted distinct keys without loss: their number, how many low bytes are kept as they are, the gaps of what is above, the low bytes."""
    n = len(keys)
    if not n:
        return b""
    spread = (int(keys[-1]) - int(keys[0])) // n
    low = min(7, max(0, (spread.bit_length() - 1) // 8))
    top = keys >> U(8 * low)
    gaps = np.diff(top, prepend=U(0))
    return np.uint32(n).tobytes() + bytes([low]) + varints(gaps) + np.ascontiguousarray(keys).view(np.uint8).reshape(-1, 8)[:, :low].tobytes()


def unpack_sorted(raw: bytes) -> np.ndarray:
    if not raw:
        return np.zeros(0, np.uint64)
    n, low = int(np.frombuffer(raw, np.uint32, 1)[0]), raw[4]
    b = np.frombuffer(raw, np.uint8)
    mid = len(raw) - n * low
    out = np.zeros((n, 8), np.uint8)
    out[:, :low] = b[mid:].reshape(n, low)
    return out.view(np.uint64).ravel() | (np.cumsum(from_varints(b[5:mid]), dtype=np.uint64) << U(8 * low))


def requests(block: int, sets: dict[int, tuple[np.ndarray, np.ndarray | None]], parts: int, short: bool = False) -> pa.Table:
    """sets: kind -> (sorted distinct keys, numbers aligned with them or None). short: only the bits of short_keys(parts) are sent."""
    rows = {"part": [], "block": [], "kind": [], "keys": [], "extra": []}
    shift = U(max(0, 24 - (parts.bit_length() - 1))) if short else U(0)
    for kind, (keys, extra) in sets.items():
        cuts = part_edges(keys, parts)
        for p in np.flatnonzero(np.diff(cuts)):
            a, b = cuts[p], cuts[p + 1]
            rows["part"].append(int(p))
            rows["block"].append(block)
            rows["kind"].append(kind)
            rows["keys"].append(pack_sorted(keys[a:b] >> shift))
            rows["extra"].append(b"" if extra is None else varints(extra[a:b]))
    return pa.table({k: pa.array(v, t) for (k, v), t in zip(rows.items(), (pa.int64(), pa.int64(), pa.int32(), pa.binary(), pa.binary()), strict=True)})


def _combined(table: pa.Table, answer: Callable) -> pa.Table:
    block, kind = table["block"].to_numpy(), table["kind"].to_numpy()
    out = {"block": [], "kind": [], "part": [], "answer": []}
    part = table["part"][0].as_py()
    keys, extra = table["keys"], table["extra"]
    for k in np.unique(kind):
        rows = np.flatnonzero(kind == k)
        rows = rows[np.argsort(block[rows], kind="stable")]
        own = [unpack_sorted(keys[int(r)].as_py()) for r in rows]
        sizes = np.array([len(x) for x in own])
        _, inverse = np.unique(np.concatenate(own), return_inverse=True)
        ends = np.cumsum(sizes)
        given = np.concatenate([from_varints(extra[int(r)].as_py()) for r in rows])
        for i, said in enumerate(answer(block[rows], np.repeat(np.arange(len(rows)), sizes), inverse, given, ends - sizes, ends)):
            if said is not None:
                out["block"].append(int(block[rows[i]]))
                out["kind"].append(int(k))
                out["part"].append(part)
                out["answer"].append(said)
    return pa.table({k: pa.array(v, t) for (k, v), t in zip(out.items(), (pa.int64(), pa.int32(), pa.int64(), pa.binary()), strict=True)})


def sums(blocks, owner, inverse, given, starts, ends):
    """Answer with each key's total over all blocks."""
    totals = np.bincount(inverse, weights=given).astype(np.uint64)
    for a, b in zip(starts, ends, strict=True):
        yield varints(totals[inverse[a:b]])


def earlier(blocks, owner, inverse, given, starts, ends):
    """given: each key's place in its block. Answer with the keys that an earlier block has: their indices, and the
    addresses of the first and of the nearest earlier place."""
    order = np.argsort(inverse, kind="stable")  # by key, and by block within it
    key = inverse[order]
    new = np.append(True, key[1:] != key[:-1])[: len(key)]
    address = (blocks[owner].astype(np.uint64) << U(ADDRESS)) | given
    first, near = np.zeros(len(key), np.uint64), np.zeros(len(key), np.uint64)
    first[order] = address[order][np.maximum.accumulate(np.where(new, np.arange(len(key)), 0))]
    near[order[1:]] = address[order[:-1]]
    later = np.ones(len(key), bool)
    later[order[new]] = False
    for a, b in zip(starts, ends, strict=True):
        at = np.flatnonzero(later[a:b])
        yield np.uint32(len(at)).tobytes() + first[a + at].tobytes() + near[a + at].tobytes() + varints(np.diff(at, prepend=0)) if len(at) else None


def exchange(blocked: DataFrame, ask: Callable[[pa.Table], dict], answer: Callable, finish: Callable, schema: str, parts: int, short: bool = False) -> DataFrame:
    """ask(block's rows) -> kind -> keys; answer: sums or earlier; finish(rows, replies) -> pa.Table of schema.

    finish gets replies as kind -> part -> bytes. short: the caller has masked its keys by short_keys(parts), parts being a power of two.
    """

    def asked(table: pa.Table) -> pa.Table:
        return requests(table["_block"][0].as_py(), ask(table), parts, short)

    def replied(table: pa.Table) -> pa.Table:
        return _combined(table, answer)

    def finished(rows: pa.Table, replies: pa.Table) -> pa.Table:
        said: dict[int, dict[int, bytes]] = {}
        for k, p, a in zip(replies["kind"].to_pylist(), replies["part"].to_pylist(), replies["answer"].to_pylist(), strict=True):
            said.setdefault(k, {})[p] = a
        return finish(rows, said)

    wanted = blocked.groupBy("_block").applyInArrow(asked, REQUEST)
    replies = wanted.groupBy("part").applyInArrow(replied, REPLY)
    return blocked.groupBy("_block").cogroup(replies.groupBy("block")).applyInArrow(finished, schema)


def totals_of(said: dict[int, bytes]) -> np.ndarray:
    """The answers of sums, in the order of the block's sorted keys."""
    return np.concatenate([from_varints(said[p]) for p in sorted(said)]) if said else np.zeros(0, np.uint64)


def earlier_of(said: dict[int, bytes], keys: np.ndarray, parts: int) -> tuple[np.ndarray, np.ndarray]:
    """Addresses of the first and of the nearest earlier place of each key, where an earlier block has it; else -1."""
    first, near = np.full(len(keys), -1, np.int64), np.full(len(keys), -1, np.int64)
    cuts = part_edges(keys, parts)
    for p, a in said.items():
        n = int(np.frombuffer(a, np.uint32, 1)[0])
        at = cuts[p] + np.cumsum(from_varints(a[4 + 16 * n :])).astype(np.int64)
        first[at], near[at] = np.frombuffer(a, np.int64, n, 4), np.frombuffer(a, np.int64, n, 4 + 8 * n)
    return first, near
