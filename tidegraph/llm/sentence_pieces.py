"""SentencePiece encoding by suffix-array matching, and decoding.

A batch's texts are normalised (spaces become U+2581, one is put in front) and cut into chunks that no piece
can span; distinct chunks are joined into one text, whose suffixes, cut at the longest piece's length, are sorted.
A binary search finds every piece's range of suffixes, that is all its occurrences. These edges,
sorted by where they end, are relaxed from left to right: for each place the last token of the
best segmentation up to there is kept.

Which segmentation is best depends on the model. For a unigram model it is the path of highest score. The public model
at hand is byte-pair merges, whose result is the only path in which each two neighbours would
not have been merged across their border before either was complete; so an edge is
accepted if its token can follow the token that the path up to its start ends with. Where several pieces
share a merge score (runs of blanks), that test has no order to go by, and such a chunk is merged directly, by a heap of its
neighbours (a run of n blanks costs n log n).

Cases: null and empty texts have no tokens. Characters without a piece become their bytes' pieces. Repeated texts cost
a look-up. Very long words are chunks like others; memory follows the slice (about 500 KB of text) and the longest text, and
what a slice leaves free goes back to the system.
Decoding undoes encoding except that U+2581 itself decodes as a blank, as the model says.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import lru_cache
from heapq import heapify, heappop, heappush

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tidegraph.llm.textpack import mix, pieces, prefix_hash, release, span_hash

MARK = "▁"
UNKNOWN = -1
CACHE = 1_200_000  # chunks a worker remembers, about 22 bytes each
PIECE = 500_000  # bytes of text encoded at a time
RELEASE = 4_000_000  # bytes of text after which free memory is given back
PAIR_BITS = 21  # pairs of tokens a worker remembers, 9 bytes each


class PieceModel:
    def __init__(self, serialized: bytes):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_proto=serialized)
        n = sp.get_piece_size()
        self.text = [sp.id_to_piece(i) for i in range(n)]
        plain = [i for i in range(n) if not (sp.is_byte(i) or sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i))]
        self.ids = {self.text[i]: i for i in plain}
        self.unknown = sp.unk_id()
        self.byte_id = {int(self.text[i][3:5], 16): i for i in range(n) if sp.is_byte(i)}
        self.byte_of = {i: b for b, i in self.byte_id.items()}
        self.longest = max(map(len, self.ids))
        scores = {i: sp.get_score(i) for i in plain}
        many = {}
        for i in plain:
            if len(self.text[i]) > 1:
                many.setdefault(scores[i], []).append(i)
        self.time = {i: 0 for i in plain}  # when a merge makes the piece; single characters are there from the start
        for at, s in enumerate(sorted(many, reverse=True), 1):
            for i in many[s]:
                self.time[i] = at
        self.tied = [self.text[i] for own in many.values() if len(own) > 1 for i in own]
        inner = {c for p in self.ids if len(p) > 1 for c in p}
        if any(MARK in p.lstrip(MARK) for p in self.ids):
            raise ValueError("pieces that go on past a word's start are not supported")
        self.ambiguous = re.compile("|".join(map(re.escape, sorted(self.tied, key=len)))) if self.tied else None
        self.parts: dict[int, tuple[int, int]] = {}
        dead = []
        for i in plain:
            if len(self.text[i]) > 1:
                made = self.merge(self.text[i], last_merge=True)
                if made is None:
                    dead.append(i)
                else:
                    self.parts[i] = made
        dead += [self.ids[t] for t in self.tied]
        gone = set(dead)
        self.usable = np.array(sorted((i for i in plain if i not in gone), key=lambda i: self.text[i]))
        self.keys = _keys([self.text[i] for i in self.usable], self.longest)
        self.lengths = np.array([len(self.text[i]) for i in self.usable])
        self.spelled = np.full((len(self.usable), max(16, self.longest)), 0x110001)  # code points; the filler is none
        for row, i in zip(self.spelled, self.usable, strict=True):
            row[: len(self.text[i])] = [*map(ord, self.text[i])]
        self.pairs, self.may = np.full(1 << PAIR_BITS, -1), np.zeros(1 << PAIR_BITS, bool)  # pairs of tokens by hash, and whether the second may follow
        self.forget()
        raw = [bytes([self.byte_of[i]]) if i in self.byte_of else t.replace(MARK, " ").encode() for i, t in enumerate(self.text)]
        self.raw_size = np.array([len(x) for x in raw])
        self.raw_at = np.cumsum(self.raw_size) - self.raw_size
        self.raw = np.frombuffer(b"".join(raw), np.uint8)
        self.apart = np.zeros(256, bool)
        self.apart[[c for c in range(128) if chr(c) not in inner and c != 32]] = True

    def forget(self) -> None:
        """Empties the store of encoded chunks: hashes in order, and each one's slice of ids."""
        self.known, self.at, self.size = np.zeros(0, np.uint64), np.zeros(0, np.uint32), np.zeros(0, np.uint32)
        self.store = np.zeros(0, np.uint16 if len(self.text) <= 1 << 16 else np.int32)

    def merge(self, text: str, last_merge: bool = False):
        """Merges neighbours, best score first and leftmost of equals. With last_merge: the two pieces of the merge that makes the whole text, or None if it is not made."""
        part, final = [*text], None
        n = len(part)
        after, before = [*range(1, n + 1)], [*range(-1, n - 1)]
        heap: list[tuple[int, int, str]] = []
        for at in range(n - 1):
            i = self.ids.get(part[at] + part[at + 1])
            if i is not None:
                heap.append((self.time[i], at, part[at] + part[at + 1]))
        heapify(heap)
        while heap:
            _, at, made = heappop(heap)
            right = after[at] if part[at] is not None else n
            if right >= n or part[at] + part[right] != made:  # one of the two has been merged otherwise
                continue
            final = part[at], part[right]
            part[at], part[right] = made, None
            after[at] = after[right]
            if after[at] < n:
                before[after[at]] = at
            for left, own in ((before[at], at), (at, after[at])):
                if left >= 0 and own < n:
                    i = self.ids.get(part[left] + part[own])
                    if i is not None:
                        heappush(heap, (self.time[i], left, part[left] + part[own]))
        part = [x for x in part if x is not None]
        if last_merge:
            return tuple(self.ids[x] for x in final) if len(part) == 1 and all(x in self.ids for x in final) else None
        return [self.ids.get(x, UNKNOWN) for x in part], part

    def may_follow(self, a: int, b: int) -> bool:
        """Whether merging leaves a|b apart: undo merges on either side, latest first, and see whether
        the pieces that met at the border at some time would have joined before the next merge took place."""
        left, right, ids, time, text = a, b, self.ids, self.time, self.text
        before = len(time) + 1
        while True:
            joined = ids.get(text[left] + text[right])
            if joined is not None and time[joined] < before:
                return False
            if time[left] == 0 and time[right] == 0:
                return True
            if time[left] > time[right]:
                before = time[left]
                left = self.parts[left][1]
            else:  # a merge of the same score further left comes first
                before = time[right] + 1
                right = self.parts[right][0]

    def all_follow(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """may_follow for arrays, through a table with a place for each hash; a pair that lost its place is worked out again."""
        pair = a * len(self.text) + b
        at = (mix(pair.astype(np.uint64)) >> np.uint64(64 - PAIR_BITS)).astype(np.int64)
        out = (a == UNKNOWN) | self.may[at]
        open_ = np.flatnonzero((self.pairs[at] != pair) & (a != UNKNOWN))
        if len(open_):
            new, first, inverse = np.unique(pair[open_], return_index=True, return_inverse=True)
            said = np.array([self.may_follow(*divmod(p, len(self.text))) for p in new.tolist()], bool)
            self.pairs[at[open_[first]]], self.may[at[open_[first]]] = new, said
            out[open_] = said[inverse]
        return out

    def learn(self, chunks: list[str]) -> list[list[int]]:
        """ids of distinct chunks."""
        out: list[list[int] | None] = [None] * len(chunks)
        rest = list(range(len(chunks)))
        if self.ambiguous is not None:
            direct = [i for i in rest if self.ambiguous.search(chunks[i])]
            for i in direct:
                out[i] = self.ids_of(*self.merge(chunks[i]))
            rest = [i for i in rest if out[i] is None]
        if rest:
            for i, ids in zip(rest, self.relaxed([chunks[i] for i in rest]), strict=True):
                out[i] = ids
        return out

    def occurrences(self, chunks: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Every place in the joined chunks where a usable piece stands: the piece's index and the place.

        A suffix, cut at its chunk's end and the longest piece, is two integers of a byte a character where at most
        254 characters occur, and a byte string otherwise.
        """
        joined = _codes("".join(chunks))
        alphabet = np.unique(joined)
        if len(alphabet) > 254 or self.longest > 16:
            suffixes = _suffix_keys(chunks, self.longest)
            order = np.argsort(suffixes)
            ranked = suffixes[order]
            lo = np.searchsorted(ranked, self.keys, "left")
            hi = np.searchsorted(ranked, _after(self.keys, self.lengths), "left")
            return _expand(np.arange(len(self.usable)), lo, hi, order)
        n, sizes = len(joined), np.array([len(c) for c in chunks])
        code = np.append(np.searchsorted(alphabet, joined) + 1, np.zeros(16, np.int64)).astype(np.uint64)
        left = np.repeat(np.cumsum(sizes), sizes) - np.arange(n)
        head, tail = np.zeros(n, np.uint64), np.zeros(n, np.uint64)
        for k in range(16):
            c = np.where(left > k, code[k : n + k], np.uint64(0)) << np.uint64(56 - 8 * (k % 8))
            if k < 8:
                head |= c
            else:
                tail |= c
        order = np.lexsort((tail, head))
        head, tail = head[order], tail[order]
        spell = np.append(alphabet, 0x110000)
        at = np.searchsorted(alphabet, self.spelled)
        ok = ((spell[at] == self.spelled) | (self.spelled == 0x110001)).all(axis=1)
        which = np.flatnonzero(ok)
        code = np.where(self.spelled[which] == 0x110001, 0, at[which] + 1).astype(np.uint64)
        shift = np.arange(56, -1, -8).astype(np.uint64)
        first, second = (code[:, :8] << shift).sum(axis=1, dtype=np.uint64), (code[:, 8:] << shift).sum(axis=1, dtype=np.uint64)
        size = self.lengths[which]
        step = np.uint64(1) << (np.uint64(64) - 8 * np.minimum(size, 8).astype(np.uint64))
        lo, hi = np.searchsorted(head, first, "left"), np.searchsorted(head, first + (step - np.uint64(1)), "right")
        for i in np.flatnonzero((size > 8) & (hi > lo)).tolist():
            a, b = lo[i], hi[i]
            above = int(second[i]) + (1 << (128 - 8 * int(size[i]))) - 1
            lo[i], hi[i] = a + np.searchsorted(tail[a:b], second[i], "left"), a + np.searchsorted(tail[a:b], np.uint64(above), "right")
        return _expand(which, lo, hi, order)

    def relaxed(self, chunks: list[str]) -> list[list[int]]:
        sizes = np.array([len(c) for c in chunks])
        firsts = np.cumsum(sizes) - sizes
        token, start = self.occurrences(chunks)
        end = start + self.lengths[token]
        token = self.usable[token]
        n = int(sizes.sum())
        depth = np.arange(1, n + 1) - np.repeat(firsts, sizes)  # of a place: characters of its chunk up to it
        by = np.argsort(depth[end - 1], kind="stable")
        token, start, end = token[by], start[by], end[by]
        cuts = np.searchsorted(depth[end - 1], np.arange(1, int(sizes.max()) + 2))
        last, back = np.full(n + 1, UNKNOWN), np.arange(-1, n)  # the default: a character without a piece
        begins = np.zeros(n + 1, bool)
        begins[firsts] = True  # a chunk's start shares its place with the end of the one before
        for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):  # all chunks at once, a place further each time
            if a == b:
                continue
            s, t = start[a:b], token[a:b]
            ok = begins[s]
            inner = np.flatnonzero(~ok)
            ok[inner] = self.all_follow(last[s[inner]], t[inner])
            e = end[a:b][ok]
            last[e], back[e] = t[ok], s[ok]
        who, at = np.arange(len(chunks)), firsts + sizes
        path: list[tuple] = []
        while len(who):
            path.append((who, at, last[at]))
            at = back[at]
            go = at > firsts[who]
            who, at = who[go], at[go]
        who, at, ids = (np.concatenate(x) for x in zip(*path, strict=True))
        by = np.argsort(at)
        who, at, ids = who[by], at[by], ids[by]
        ends = np.searchsorted(who, np.arange(len(chunks) + 1)).tolist()
        odd = {*who[ids == UNKNOWN].tolist()}
        flat = ids.tolist()
        out = [flat[a:b] for a, b in zip(ends[:-1], ends[1:], strict=True)]
        for i in odd:  # the only tokens longer than a character are known ones
            part, p = [], 0
            for t in out[i]:
                q = p + (1 if t == UNKNOWN else len(self.text[t]))
                part.append(chunks[i][p:q])
                p = q
            out[i] = self.ids_of(out[i], part)
        return out

    def ids_of(self, ids: list[int], part: list[str]) -> list[int]:
        if UNKNOWN not in ids:
            return ids
        out: list[int] = []
        for i, p in zip(ids, part, strict=True):
            if i != UNKNOWN:
                out.append(i)
            elif self.byte_id:
                out.extend(self.byte_id[b] for b in p.encode())
            elif not out or out[-1] != self.unknown:
                out.append(self.unknown)
        return out

    def encode(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """All ids, and each text's offsets into them."""
        own = [(" " + t).replace(MARK, " ").encode() if t else b"" for t in texts]
        offs = np.zeros(len(own) + 1, np.int64)
        np.cumsum([len(x) for x in own], out=offs[1:])
        joined = b"".join(own)
        data = np.frombuffer(joined, np.uint8)
        if not len(data):
            return np.zeros(0, np.int32), np.zeros(len(own) + 1, np.int64)
        space, apart = data == 32, self.apart[data]
        first = apart | space
        first[1:] &= ~(space[1:] & space[:-1])
        first[1:] |= apart[:-1]
        first[offs[:-1][offs[:-1] < len(data)]] = True
        starts = np.flatnonzero(first)
        ends = np.append(starts[1:], len(data))
        keys, at, inverse = np.unique(span_hash(prefix_hash(data), starts, ends), return_index=True, return_inverse=True)
        if len(self.known) > CACHE:
            self.forget()
        place = np.searchsorted(self.known, keys)
        new = np.ones(len(keys), bool)
        inside = place < len(self.known)
        new[inside] = self.known[place[inside]] != keys[inside]
        if new.any():
            said = self.learn([joined[a:b].decode().replace(" ", MARK) for a, b in zip(starts[at[new]].tolist(), ends[at[new]].tolist(), strict=True)])
            sizes = np.array([len(x) for x in said])
            spot = len(self.store) + np.cumsum(sizes) - sizes
            self.store = np.concatenate([self.store, np.array([i for x in said for i in x], self.store.dtype)])
            by = place[new]
            self.known, self.at, self.size = np.insert(self.known, by, keys[new]), np.insert(self.at, by, spot), np.insert(self.size, by, sizes)
            place = np.searchsorted(self.known, keys)
        size = self.size[place][inverse].astype(np.int64)
        upto = np.cumsum(size)
        ids = self.store[np.arange(upto[-1]) - np.repeat(upto - size, size) + np.repeat(self.at[place][inverse].astype(np.int64), size)].astype(np.int32)
        return ids, np.append(0, upto)[np.searchsorted(starts, offs)]

    def decode(self, ids: np.ndarray, offs: np.ndarray) -> tuple[bytes, np.ndarray]:
        """The bytes of all texts without their leading blank, and each text's offsets into them."""
        size = self.raw_size[ids]
        upto = np.cumsum(size)
        total = int(upto[-1]) if len(upto) else 0
        data = self.raw[np.arange(total) - np.repeat(upto - size, size) + np.repeat(self.raw_at[ids], size)]
        at = np.append(0, upto)[offs]
        firsts = at[:-1][(np.diff(at) > 0)]
        lead = firsts[data[firsts] == 32]
        keep = np.ones(total, bool)
        keep[lead] = False
        return data[keep].tobytes(), at - np.searchsorted(lead, at)


def _pack(codes: np.ndarray) -> np.ndarray:
    """Three bytes a character, none of them zero, so that byte strings compare like the characters and padding sorts first."""
    c = codes.astype(np.uint32)
    out = np.empty((*c.shape, 3), np.uint8)
    out[..., 0], out[..., 1], out[..., 2] = c // 16384 + 1, c // 128 % 128 + 1, c % 128 + 1
    return out


def _codes(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)


def _suffix_keys(chunks: list[str], longest: int) -> np.ndarray:
    """For each character of the joined chunks, the packed suffix of its chunk, up to `longest` characters."""
    sizes = np.array([len(c) for c in chunks])
    packed = np.concatenate([_pack(_codes("".join(chunks))), np.zeros((longest, 3), np.uint8)])
    n = int(sizes.sum())
    left = np.repeat(np.cumsum(sizes), sizes) - np.arange(n)
    out = np.zeros((n, longest, 3), np.uint8)
    for k in range(longest):
        out[:, k] = packed[k : n + k] * (left > k)[:, None]
    return out.reshape(n, -1).view(f"S{3 * longest}").ravel()


def _keys(texts: list[str], longest: int) -> np.ndarray:
    out = np.zeros((len(texts), longest, 3), np.uint8)
    for i, t in enumerate(texts):
        out[i, : len(t)] = _pack(_codes(t))
    return out.reshape(len(texts), -1).view(f"S{3 * longest}").ravel()


def _expand(which: np.ndarray, lo: np.ndarray, hi: np.ndarray, order: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    counts = np.maximum(hi - lo, 0)
    run = np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)
    return np.repeat(which, counts), order[run + np.repeat(lo, counts)]


def _after(keys: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """The least key after all that begin with a piece: its last byte (129 at most) plus one."""
    raw = keys.view(np.uint8).reshape(len(keys), -1).copy()
    raw[np.arange(len(keys)), 3 * lengths - 1] += 1
    return raw.view(keys.dtype).ravel()


@lru_cache(2)
def _model(serialized: bytes) -> PieceModel:
    return PieceModel(serialized)


def encoded(batches: Iterator[pa.RecordBatch], model: PieceModel, kept: int, check: bool) -> Iterator[pa.RecordBatch]:
    """The first `kept` columns of batches that have a column _text, n_tokens, ids and, with check, round_trip; in slices, after which free memory is given back."""
    names, done = ["n_tokens", "ids", *(["round_trip"] if check else [])], 0
    for part in pieces(batches, "_text", PIECE):
        texts = part.column("_text").to_pylist()
        ids, offs = model.encode(texts)
        cols = [*part.columns[:kept], pa.array(np.diff(offs), pa.int64()), pa.ListArray.from_arrays(pa.array(offs.astype(np.int32)), pa.array(ids))]
        if check:
            data, at = model.decode(ids, offs)
            cols.append(pa.array([data[a:b] == (t or "").encode() for a, b, t in zip(at[:-1].tolist(), at[1:].tolist(), texts, strict=True)], pa.bool_()))
            del data, at
        yield pa.RecordBatch.from_arrays(cols, names=[*part.schema.names[:kept], *names])
        done += sum(len(t or "") for t in texts)
        del part, texts, ids, offs, cols
        if done > RELEASE:
            release()
            done = 0
    release()


def encode(docs: DataFrame, model_path: str, text_col: str = "text", keep: tuple[str, ...] = ("doc_id",), check: bool = True) -> DataFrame:
    """keep columns, n_tokens, ids and, with check, round_trip (ids decode to the text).

    The model file (under 1 MB) is read on the driver and travels with the plan.
    """
    names = ["n_tokens", "ids", *(["round_trip"] if check else [])]
    if {*names} & {*keep}:
        raise ValueError("keep columns clash with results: n_tokens, ids, round_trip")
    with open(model_path, "rb") as f:
        shared = docs.sparkSession.sparkContext.broadcast(f.read())
    picked = docs.select(*[F.col(f"`{c}`").alias(f"_k{i}") for i, c in enumerate(keep)], F.col(text_col).alias("_text"))
    fields = [f"{f.name} {f.dataType.simpleString()}" for f in picked.schema if f.name != "_text"]

    def run(batches):
        release()  # an operator that used this worker before may have left memory free
        yield from encoded(batches, _model(shared.value), len(keep), check)

    out = picked.mapInArrow(run, ", ".join([*fields, "n_tokens long", "ids array<int>", *(["round_trip boolean"] if check else [])]))
    return out.select(*[F.col(f"_k{i}").alias(c) for i, c in enumerate(keep)], *names)


def decode(tokens: DataFrame, model_path: str, ids_col: str = "ids", keep: tuple[str, ...] = ("doc_id",), name: str = "text") -> DataFrame:
    """keep columns and the decoded text; null ids decode to null."""
    with open(model_path, "rb") as f:
        shared = tokens.sparkSession.sparkContext.broadcast(f.read())
    picked = tokens.select(*[F.col(f"`{c}`").alias(f"_k{i}") for i, c in enumerate(keep)], F.col(ids_col).alias("_ids"))
    fields = [f"{f.name} {f.dataType.simpleString()}" for f in picked.schema if f.name != "_ids"]

    def run(batches):
        model = _model(shared.value)
        for b in batches:
            lists = b.column("_ids").to_pylist()
            offs = np.zeros(len(lists) + 1, np.int64)
            np.cumsum([len(x or ()) for x in lists], out=offs[1:])
            data, at = model.decode(np.array([i for x in lists for i in x or ()], np.int64), offs)
            texts = [None if x is None else data[p:q].decode("utf-8", "replace") for x, p, q in zip(lists, at[:-1].tolist(), at[1:].tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([*b.columns[: len(keep)], pa.array(texts, pa.string())], names=[*b.schema.names[: len(keep)], "_text"])

    out = picked.mapInArrow(run, ", ".join([*fields, "_text string"]))
    return out.select(*[F.col(f"_k{i}").alias(c) for i, c in enumerate(keep)], F.col("_text").alias(name))
