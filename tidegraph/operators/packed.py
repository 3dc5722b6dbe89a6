"""One iteration of levels over packed neighbour lists: a graph is dealt to parts by vertex, a part is one row of arrays.

A superstep is one exchange: each part reads its lists and what others sent to its vertices, computes in numpy, and sends arrays on. A vertex's
whole list is in one part (`levels.step` keeps graphs with a wider one by rows). Same arcs, vertices, moves and counts as the steps by rows.
"""

from __future__ import annotations

import math
import pickle
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tidegraph.functions.session import cut, dropped, stored

ROW = "p int, kind int, body binary, n array<long>"
SCHEMA = pa.schema([("p", pa.int32()), ("kind", pa.int32()), ("body", pa.binary()), ("n", pa.list_(pa.int64()))])
STATE, ARCS, VERTS, LISTS, LINKS, ROWS, NOTES, LIFTED, JOINED, DONE = range(10)
ARCS_A_PART = 2_000_000  # arcs a part may grow to
MOST_PARTS = 1_000
WEDGES = 1_000_000  # candidates sorted at a time, within a vertex
LEVELS = 40
GROWN, WEDGE, ROOM, SLOTS = LEVELS + 6, LEVELS + 7, LEVELS + 8, LEVELS + 9  # counters: arcs, candidates, room of the next step
M64 = (1 << 64) - 1
P1, P2, P3, P4, P5 = 0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5


def _u(x: int) -> np.uint64:
    return np.uint64(x & M64)


def _rot(x: np.ndarray, r: int) -> np.ndarray:
    return (x << _u(r)) | (x >> _u(64 - r))


def _xx(body: np.ndarray | bytes, seed: np.ndarray) -> np.ndarray:
    """XXH64 as in Spark's xxhash64: of a column of longs, or of one short text under many seeds."""
    if isinstance(body, bytes):
        h, words, rest = seed + _u(P5 + len(body)), [_u(int.from_bytes(body[i : i + 8], "little")) for i in range(0, len(body) - 7, 8)], body[len(body) // 8 * 8 :]
    else:
        h, words, rest = seed + _u(P5 + 8), [body.astype(np.uint64)], b""
    for w in words:
        h = _rot(h ^ (_rot(w * _u(P2), 31) * _u(P1)), 27) * _u(P1) + _u(P4)
    if len(rest) >= 4:
        h, rest = _rot(h ^ (_u(int.from_bytes(rest[:4], "little")) * _u(P1)), 23) * _u(P2) + _u(P3), rest[4:]
    for b in rest:
        h = _rot(h ^ (_u(b) * _u(P5)), 11) * _u(P1)
    h = (h ^ (h >> _u(33))) * _u(P2)
    h = (h ^ (h >> _u(29))) * _u(P3)
    return h ^ (h >> _u(32))


def coins(ids: np.ndarray, *salt) -> np.ndarray:
    """coins.coin01 of kind xx."""
    with np.errstate(over="ignore"):
        h = _xx(ids, np.full(len(ids), 42, np.uint64))
        for s in salt:
            h = _xx(str(s).encode(), h)
    return (h & _u((1 << 52) - 1)).astype(np.float64) / float(1 << 52)


def part_of(ids: np.ndarray, parts: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        return ((ids.astype(np.uint64) * _u(P1)) >> _u(33)).astype(np.int64) % parts


def ranges(start: np.ndarray, count: np.ndarray) -> np.ndarray:
    """start[0], start[0] + 1, ... count[0] of them, then those of start[1] ..."""
    total = int(count.sum())
    return np.arange(total) + np.repeat(start - (np.cumsum(count) - count), count)


def spread_of(*ids: np.ndarray) -> tuple[int, int]:
    """Least id and width of the span of ids, where pairs of a row number and an id may be one long; width 0 for none."""
    some = [x for x in ids if len(x)]
    return (low := min(int(x.min()) for x in some), max(int(x.max()) for x in some) - low + 1) if some else (0, 0)


def routed(kind: int, to: np.ndarray, parts: int, **cols: np.ndarray) -> Iterator[tuple[int, int, dict]]:
    at = part_of(to, parts).astype(np.int16)  # short keys are sorted by digits
    order = np.argsort(at, kind="stable")
    ends = np.searchsorted(at[order], np.arange(parts + 1))
    for p in np.flatnonzero(np.diff(ends)):
        mine = order[ends[p] : ends[p + 1]]
        yield int(p), kind, {"to": to[mine]} | {k: v[mine] for k, v in cols.items()}


class Part:
    """vid sorted; flag: 2 level + active; deg; dst sorted by vertex; df: flags of dst."""

    def __init__(self, p: int, parts: int, body: dict, sent: dict[int, list[dict]], known: dict):
        self.p, self.parts, self.known, self.sent = p, parts, known, sent
        self.__dict__.update(body)
        self.out: list[tuple[int, int, dict]] = []
        self.n: dict[int, int] = {}

    @property
    def body(self) -> dict:
        hidden = {"p", "parts", "known", "sent", "out", "n"}
        return {k: v for k, v in self.__dict__.items() if k not in hidden}

    def get(self, kind: int, *names: str) -> list[np.ndarray]:
        rows = self.sent.get(kind, [])
        return [np.concatenate([r[k] for r in rows]) if rows else np.zeros(0, np.int64) for k in names]

    def send(self, kind: int, to: np.ndarray, **cols: np.ndarray) -> None:
        if len(to):
            self.out.extend(routed(kind, to, self.parts, **cols))

    def count(self, slot: int, k) -> None:
        self.n[slot] = self.n.get(slot, 0) + int(k)

    @property
    def si(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.vid)), self.deg)

    @property
    def lev(self) -> np.ndarray:
        return self.flag >> 1

    def where(self, ids: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.vid, ids)

    def arcs(self, si: np.ndarray, dst: np.ndarray, df: np.ndarray) -> None:
        low, width = spread_of(dst)
        if 0 < (len(self.vid) + 1) * width < 1 << 54:  # one sort of longs
            key = ((si.astype(np.int64) * width + (dst - low)) << 8) | df
            key.sort()
            df, key = (key & 255).astype(np.uint8), key >> 8
            si = key // width
            dst = key - si * width + low
        else:
            order = np.lexsort((dst, si))
            si, dst, df = si[order], dst[order], df[order]
        new = np.ones(len(si), bool)
        new[1:] = (si[1:] != si[:-1]) | (dst[1:] != dst[:-1])
        self.dst, self.df, self.deg = dst[new], df[new].astype(np.uint8), np.bincount(si[new], minlength=len(self.vid)).astype(np.int32)

    def more(self, si: np.ndarray, dst: np.ndarray, df: np.ndarray) -> None:
        if len(si):
            self.arcs(np.concatenate([self.si, si]), np.concatenate([self.dst, dst]), np.concatenate([self.df, df.astype(np.uint8)]))

    def place(self, x: np.ndarray, old: np.ndarray) -> np.ndarray:
        """Where the arcs (x, old) are."""
        low, width = spread_of(self.dst)
        if (len(self.vid) + 1) * width < 1 << 62:
            return np.searchsorted(self.si * width + (self.dst - low), self.where(x) * width + (old - low))
        ids, di = np.unique(self.dst, return_inverse=True)
        return np.searchsorted(self.si * len(ids) + di, self.where(x) * len(ids) + np.searchsorted(ids, old))

    def kept(self, keep: np.ndarray) -> None:
        arcs = keep[self.si]
        self.vid, self.flag, self.deg, self.dst, self.df = self.vid[keep], self.flag[keep], self.deg[keep], self.dst[arcs], self.df[arcs]

    def moves(self, who: np.ndarray, new: np.ndarray, flag: np.ndarray) -> None:
        self.who, self.new, self.newflag = who, new, flag

    def same(self) -> np.ndarray:
        return (self.df >> 1) == self.lev[self.si]

    def direct(self) -> np.ndarray:
        k = np.bincount(self.si[self.same() & ((self.df & 1) == 1)], minlength=len(self.vid))
        full = k >= self.known["cap"][self.lev] if self.known["at_least"] else k > self.known["beta"][self.lev]
        return full & ((self.flag & 1) == 1)


# ---- supersteps -------------------------------------------------------------------------------
def assemble(t: Part) -> None:
    vid, flag = t.get(VERTS, "to", "flag")
    order = np.argsort(vid)
    t.vid, t.flag = vid[order], flag[order].astype(np.uint8)
    src, dst, df = t.get(ARCS, "to", "dst", "df")
    t.arcs(t.where(src), dst, df)
    outlook(t)


def outlook(t: Part) -> None:
    """What the next step may add."""
    lev, si = t.lev, t.si
    cap = t.known["cap"][lev]
    k = np.bincount(si[t.same()], minlength=len(t.vid))
    t.count(GROWN, len(t.dst))
    t.count(WEDGE, (k * np.minimum(k, cap + 1)).sum())
    t.count(ROOM, np.maximum(cap - t.deg, 0)[(t.flag & 1) == 1].clip(max=1 << 32).sum())


def push(t: Part) -> None:
    """Each vertex's list, cut at capacity + 1, to its active neighbours of its level: once for each part that has some."""
    same, si = t.same(), t.si
    cap = t.known["cap"][t.lev]
    at = np.flatnonzero(same)
    k = np.bincount(si[at], minlength=len(t.vid))
    first = np.cumsum(k) - k
    own = np.arange(len(at)) - first[si[at]] <= cap[si[at]]
    lu, la = t.dst[at[own]], (t.df[at[own]] & 1).astype(np.uint8)
    k = np.bincount(si[at[own]], minlength=len(t.vid))
    first = np.cumsum(k) - k
    at = at[(t.df[at] & 1) == 1]
    v, w, p = t.dst[at], si[at], part_of(t.dst[at], t.parts).astype(np.int16)
    order = np.argsort(p, kind="stable")
    ends = np.searchsorted(p[order], np.arange(t.parts + 1))
    for q in np.flatnonzero(np.diff(ends)):
        mine = order[ends[q] : ends[q + 1]]
        new = np.diff(w[mine], prepend=-1) != 0
        ws, wi = w[mine][new], np.cumsum(new) - 1
        e = ranges(first[ws], k[ws])
        t.out.append((int(q), LISTS, {"v": v[mine], "wi": wi.astype(np.int32), "k": k[ws], "u": lu[e], "a": la[e]}))


def pick(t: Part) -> None:
    """The least candidates of each active vertex, as many as it has room for."""
    lev = t.lev
    room = t.known["cap"][lev] - np.bincount(t.si[(t.df >> 1) >= lev[t.si]], minlength=len(t.vid))
    room[(t.flag & 1) == 0] = 0
    rows = t.sent.get(LISTS, [])
    v, k, u, a = t.get(LISTS, "v", "k", "u", "a")
    base = np.cumsum([0] + [len(r["k"]) for r in rows])
    li = np.concatenate([r["wi"] + b for r, b in zip(rows, base, strict=False)]) if rows else np.zeros(0, np.int64)
    vi = t.where(v)
    use = room[vi] > 0
    vi, li = vi[use], li[use]
    order = np.argsort(vi, kind="stable")
    vi, li = vi[order], li[order]
    first = np.cumsum(k) - k
    low, width = spread_of(u)
    ids = None
    if width >= 1 << 40:
        ids = np.unique(u)
        low, width, u = 0, len(ids), np.searchsorted(ids, u)
    ua = ((u - low) << 1) | a  # place in the span and whether active
    ptr = np.cumsum(t.deg) - t.deg
    heads = np.flatnonzero(np.diff(vi, prepend=-1)) if len(vi) else np.zeros(0, np.int64)
    ends = np.append(heads[1:], len(vi)) if len(heads) else heads
    load = np.add.reduceat(k[li], heads) if len(heads) else heads
    batch = (np.cumsum(load) - load) // WEDGES
    found = []
    for b in np.unique(batch):
        some = np.flatnonzero(batch == b)
        lo, hi = heads[some[0]], ends[some[-1]]
        vs, kk = vi[heads[some]], k[li[lo:hi]]
        rank = np.repeat(np.arange(len(vs)), ends[some] - heads[some])
        keys = np.repeat(rank * (2 * width), kk)
        keys += ua[ranges(first[li[lo:hi]], kk)]
        own = np.concatenate([t.dst[ranges(ptr[vs], t.deg[vs])], t.vid[vs]])
        of = np.concatenate([np.repeat(np.arange(len(vs)), t.deg[vs]), np.arange(len(vs))])
        if ids is None:
            there = (own >= low) & (own < low + width)
            own = own - low
        else:
            at = np.minimum(np.searchsorted(ids, own), width - 1)
            there, own = ids[at] == own, at
        keys = np.concatenate([keys * 2 + 1, (of[there] * (2 * width) + own[there] * 2) * 2])  # arcs and the vertex itself come first
        keys.sort()
        new = np.ones(len(keys), bool)
        new[1:] = (keys[1:] >> 2) != (keys[:-1] >> 2)
        keys = keys[new]
        keys = keys[(keys & 1) == 1] >> 1
        of = keys // (2 * width)
        start = np.searchsorted(of, np.arange(len(vs)))
        fits = np.arange(len(keys)) - start[of] < room[vs[of]]
        keys, of = keys[fits], of[fits]
        found.append((vs[of], (keys - of * (2 * width)) >> 1, keys & 1))
    ni, nu, na = (np.concatenate([f[i] for f in found]) if found else np.zeros(0, np.int64) for i in (0, 1, 2))
    nu = nu + low if ids is None else ids[nu]
    t.xi, t.xu, t.xf = ni.astype(np.int32), nu, (lev[ni].astype(np.int64) * 2 + na).astype(np.uint8)
    order = np.argsort(nu, kind="stable")
    t.send(LINKS, nu[order], v=t.vid[ni][order], f=(lev[ni] * 2 + 1).astype(np.uint8)[order])


def merge_links(t: Part) -> None:
    u, v, f = t.get(LINKS, "to", "v", "f")
    t.more(np.concatenate([t.xi, t.where(u)]), np.concatenate([t.xu, v]), np.concatenate([t.xf, f]))
    del t.xi, t.xu, t.xf
    t.count(0, len(t.dst))
    si, dl = t.si, t.df >> 1
    up = np.flatnonzero(dl > t.lev[si])
    up = up[np.lexsort((t.dst[up], -dl[up].astype(np.int64), si[up]))]
    best = up[np.flatnonzero(np.diff(si[up], prepend=-1))] if len(up) else up
    t.moves(si[best], t.dst[best], t.df[best])
    t.count(1, len(best))
    t.count(2, t.direct().sum())


def tell(t: Part) -> None:
    """A vertex that moves, or stays with a new flag, tells its neighbours."""
    ptr = np.cumsum(t.deg) - t.deg
    k = t.deg[t.who]
    e = ranges(ptr[t.who], k)
    t.send(NOTES, t.dst[e], old=np.repeat(t.vid[t.who], k), new=np.repeat(t.new, k), f=np.repeat(t.newflag, k))


def heard(t: Part) -> None:
    x, old, new, f = t.get(NOTES, "to", "old", "new", "f")
    if len(x):
        at = t.place(x, old)
        t.dst, t.df = t.dst.copy(), t.df.copy()
        t.dst[at], t.df[at] = new, f


def hand_over(t: Part) -> None:
    """Renames both ends: neighbours by what was heard; the list of a vertex that moved goes to its new vertex."""
    heard(t)
    to = t.vid.copy()
    to[t.who] = t.new
    si = t.si
    loop, gone = t.dst == to[si], (to != t.vid)[si]
    go = gone & ~loop
    t.send(ROWS, to[si[go]], dst=t.dst[go], df=t.df[go])
    stay = ~gone & ~loop
    t.arcs(si[stay], t.dst[stay], t.df[stay])


def take_over(t: Part) -> None:
    to, dst, df = t.get(ROWS, "to", "dst", "df")
    t.more(t.where(to), dst, df)


def lifted(t: Part) -> None:
    """A vertex that moves and is moved to stays as an inactive one and says so."""
    take_over(t)
    t.out.append((t.p, LIFTED, {"old": t.vid[t.who], "new": t.new}))
    t.flag = t.flag.copy()
    t.flag[t.who] &= 254
    chain = t.who[t.deg[t.who] > 0]
    t.moves(chain, t.vid[chain], t.flag[chain])
    tell(t)


def settle(t: Part) -> None:
    heard(t)
    t.moves(*[np.zeros(0, np.int64)] * 3)
    t.count(2, t.direct().sum())


def beside(t: Part, who: np.ndarray, kind: int, value: np.ndarray) -> None:
    """value of each of who to its neighbours of its level."""
    e = np.flatnonzero(who[t.si] & t.same())
    t.send(kind, t.dst[e], x=value[t.si[e]])


def spread_saturated(t: Part) -> None:
    t.full = t.direct()
    beside(t, t.full, NOTES, t.vid)


def draw(t: Part) -> None:
    (x,) = t.get(NOTES, "to")
    t.full = t.full.copy()
    t.full[t.where(x)] = True
    t.full &= (t.flag & 1) == 1
    at = np.flatnonzero(t.full)
    t.lead = np.zeros(len(t.vid), bool)
    t.lead[at] = coins(t.vid[at], t.known["seed"], t.known["iteration"], "leader") < t.known["rate"][t.lev[at]]
    beside(t, t.lead, NOTES, t.vid)


NONE = np.iinfo(np.int64).max


def least(t: Part) -> np.ndarray:
    x, value = t.get(NOTES, "to", "x")
    out = np.full(len(t.vid), NONE, np.int64)
    np.minimum.at(out, t.where(x), value)
    return out


def pass_on(t: Part) -> None:
    t.one = least(t)
    beside(t, t.one != NONE, NOTES, t.one)


def join_leaders(t: Part) -> None:
    two = least(t)
    to = np.where(t.one != NONE, t.one, two)
    joins = t.full & ~t.lead & (to != NONE) & (to != t.vid)
    t.count(3, t.full.sum())
    t.count(4, joins.sum())
    t.count(5, (joins & (t.one == NONE)).sum())
    for level, k in enumerate(np.bincount(t.lev[t.lead])):
        t.count(6 + level, k)
    who = np.flatnonzero(joins | t.lead)
    t.moves(who, np.where(joins, to, t.vid)[who], ((t.lev[who].astype(np.int64) + 1) * 2 + 1).astype(np.uint8))
    del t.full, t.lead, t.one
    tell(t)


def joined(t: Part) -> None:
    take_over(t)
    gone = t.new != t.vid[t.who]
    t.out.append((t.p, JOINED, {"old": t.vid[t.who[gone]], "new": t.new[gone]}))
    t.flag = t.flag.copy()
    t.flag[t.who[~gone]] = t.newflag[~gone]
    keep = np.ones(len(t.vid), bool)
    keep[t.who[gone]] = False
    t.kept(keep)


def close(t: Part) -> None:
    """Inactive vertices without arcs go; what the next step may grow to is counted."""
    t.kept(((t.flag & 1) == 1) | (t.deg > 0))
    for k in ("who", "new", "newflag"):
        t.__dict__.pop(k, None)
    outlook(t)


def closed_lists(t: Part) -> None:
    """Each vertex's closed neighbourhood to the least id in it."""
    si = t.si
    ptr = np.cumsum(t.deg) - t.deg
    some = np.flatnonzero(t.deg)
    t.mu = t.vid.copy()
    t.mu[some] = np.minimum(t.vid[some], t.dst[ptr[some]])
    deg = t.deg[some].astype(np.int64)
    before = np.add.reduceat(np.append((t.dst < t.vid[si]).astype(np.int64), 0), np.append(ptr[some], len(t.dst)))[: len(some)]  # neighbours below the vertex
    x = np.insert(t.dst, ptr[some] + before, t.vid[some])
    t.send(ROWS, np.repeat(t.mu[some], deg + 1), v=np.repeat(t.vid[some], deg + 1), x=x)


def same_lists(t: Part) -> None:
    """A group is a finished clique if the closed neighbourhood of each member of that of its least id is the same set."""
    m, v, x = t.get(ROWS, "to", "v", "x")
    if not len(m):
        return
    mi = t.where(m)
    heads = np.flatnonzero(np.append(True, v[1:] != v[:-1]))  # a member's list, in order and in one piece
    size, of = np.diff(np.append(heads, len(mi))), mi[heads]
    members = np.bincount(of, minlength=len(t.vid))
    right = (size == members[of]) & (size == t.deg[of] + 1)
    ptr = np.cumsum(t.deg) - t.deg
    good = np.zeros(len(t.vid), np.int64)
    k = np.where(right, size, 0)
    rank = ranges(np.zeros(len(k), np.int64), k)
    owner = np.repeat(of, k)
    want = np.where(rank == 0, t.vid[owner], t.dst[ptr[owner] + np.maximum(rank - 1, 0)])  # the least id, then its neighbours in order
    equal = np.add.reduceat(np.append((x[ranges(heads, k)] == want).astype(np.int64), 0), np.minimum(np.cumsum(k) - k, k.sum()))
    np.add.at(good, of, right & (equal == size))
    done = (good == members) & (members > 0)
    told = np.flatnonzero(done[of])
    t.send(NOTES, v[heads[told]], x=t.vid[of[told]])


def leave(t: Part) -> None:
    x, mu = t.get(NOTES, "to", "x")
    keep = np.ones(len(t.vid), bool)
    keep[t.where(x)] = False
    t.out.append((t.p, DONE, {"old": x, "new": mu}))
    t.count(0, len(x))
    t.kept(keep)
    del t.mu
    outlook(t)


# ---- plans ------------------------------------------------------------------------------------
KEEP = (LIFTED, JOINED, DONE)


def _row(p: int, kind: int, body: dict | None, n: list[int] | None) -> pa.RecordBatch:
    return pa.record_batch([[p], [kind], [None if body is None else pickle.dumps(body, protocol=5)], [n]], schema=SCHEMA)


def superstep(rows: DataFrame, parts: int, known: dict, *works: Callable[[Part], None]) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        states, sent = {}, {}
        for b in batches:
            for i, (p, kind, body) in enumerate(zip(*(b.column(c) for c in ("p", "kind", "body")), strict=True)):
                p, kind = p.as_py(), kind.as_py()
                if kind in KEEP or not body.is_valid:  # moves and counters go through
                    yield pa.RecordBatch.from_arrays([c.slice(i, 1) for c in b.columns], schema=b.schema)
                    continue
                read = pickle.loads(body.as_buffer())
                if kind == STATE:
                    states[p] = read
                else:
                    sent.setdefault(p, {}).setdefault(kind, []).append(read)
        for p in sorted({*states, *sent}):
            t = Part(p, parts, states.pop(p, {}), sent.pop(p, {}), known)
            for work in works:
                work(t)
            yield _row(p, STATE, t.body, None)
            for q, kind, body in t.out:
                yield _row(q, kind, body, None)
            if t.n:
                yield _row(p, STATE, None, [t.n.get(i, 0) for i in range(SLOTS)])

    return rows.repartitionById(parts, F.col("p")).mapInArrow(run, ROW)


def counts(rows: DataFrame) -> list[int]:
    got = rows.where("n is not null").select(F.posexplode("n").alias("i", "k")).groupBy("i").agg(F.sum("k").alias("k")).collect()
    found = {r["i"]: r["k"] for r in got}
    return [found.get(i, 0) for i in range(SLOTS)]


def deal(arcs: DataFrame, verts: DataFrame, parts: int) -> DataFrame:
    def rows_of(kind: int, cols: Callable[[pa.RecordBatch], dict]):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                c = cols(b)
                for p, k, body in routed(kind, c.pop("to"), parts, **c):
                    yield _row(p, k, body, None)

        return run

    num = lambda b, c: b.column(c).to_numpy(zero_copy_only=False)
    a = arcs.select("src", "dst", (F.col("dl") * 2 + F.col("da").cast("int")).alias("f")).mapInArrow(rows_of(ARCS, lambda b: {"to": num(b, "src"), "dst": num(b, "dst"), "df": num(b, "f").astype(np.uint8)}), ROW)
    v = verts.select("vid", (F.col("level") * 2 + F.col("active").cast("int")).alias("f")).mapInArrow(rows_of(VERTS, lambda b: {"to": num(b, "vid"), "flag": num(b, "f").astype(np.uint8)}), ROW)
    return a.unionByName(v)


def unpacked(rows: DataFrame, kind: int, schema: str, cols: Callable[[dict], dict]) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for body in b.column("body"):
                found = {k: np.ascontiguousarray(v) for k, v in cols(pickle.loads(body.as_buffer())).items()}
                size = len(next(iter(found.values())))
                for at in range(0, size, 500_000):
                    yield pa.RecordBatch.from_pydict({k: v[at : at + 500_000] for k, v in found.items()})

    return rows.where((F.col("kind") == kind) & F.col("body").isNotNull()).select("body").mapInArrow(run, schema)


def _ends(s: dict) -> dict:
    f = np.repeat(s["flag"], s["deg"])
    return {"src": np.repeat(s["vid"], s["deg"]), "dst": s["dst"], "sl": (f >> 1).astype(np.int32), "sa": (f & 1).astype(bool), "dl": (s["df"] >> 1).astype(np.int32), "da": (s["df"] & 1).astype(bool)}


def leveled_of(rows: DataFrame) -> DataFrame:
    return unpacked(rows, STATE, "src long, dst long, sl int, sa boolean, dl int, da boolean", _ends)


def verts_of(rows: DataFrame) -> DataFrame:
    return unpacked(rows, STATE, "vid long, level int, active boolean", lambda s: {"vid": s["vid"], "level": (s["flag"] >> 1).astype(np.int32), "active": (s["flag"] & 1).astype(bool)})


def pairs_of(rows: DataFrame, kind: int, names: tuple[str, str] = ("old", "new")) -> DataFrame:
    return cut(unpacked(rows, kind, f"{names[0]} long, {names[1]} long", lambda s: {names[0]: s["old"], names[1]: s["new"]}))


def parts_for(rows: DataFrame, n: list[int]) -> int:
    most = n[GROWN] + 2 * min(n[WEDGE], n[ROOM])
    return max(1, int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), min(MOST_PARTS, math.ceil(most / ARCS_A_PART)))


@dataclass(frozen=True)
class Packed:
    rows: DataFrame
    parts: int
    n: list[int]


def packed_of(arcs: DataFrame, verts: DataFrame, parts: int, known: dict) -> Packed:
    rows = stored(superstep(deal(arcs, verts, parts), parts, known, assemble), "packed")
    return Packed(rows, parts, counts(rows))


def fitted(graph: Packed, known: dict) -> Packed:
    """Dealt anew where a step may outgrow its parts."""
    parts = parts_for(graph.rows, graph.n)
    if graph.parts / 4 <= parts <= graph.parts * 2:
        return graph
    return packed_of(leveled_of(graph.rows), verts_of(graph.rows), parts, known)


def no_counts(rows: DataFrame) -> DataFrame:
    return rows.where("n is null")


def plain(rows: DataFrame) -> DataFrame:
    return no_counts(rows).where(F.col("kind") == STATE)


def iterate(given: Packed, known: dict) -> tuple[Packed, list[DataFrame], dict]:
    """(graph after link, lift and contract, moves, counters)."""
    graph = fitted(given, known)
    go = lambda r, *works: superstep(r, graph.parts, known, *works)
    now = stored(go(go(go(plain(graph.rows), push), pick), merge_links), "packed")
    if graph is not given:
        dropped(graph.rows)
    n = counts(now)
    linked, up, direct, log = n[0] // 2, n[1], n[2], []
    seen = {"saturated": 0, "leaders": 0, "unled": 0, "contracted": 0, "two_hop": 0, "promoted": {}}
    if up:
        later = stored(go(go(go(go(no_counts(now), tell), hand_over), lifted), settle), "packed")
        dropped(now)
        now, direct = later, counts(later)[2]
    if direct:
        later = stored(go(go(go(go(go(go(go(no_counts(now), spread_saturated), draw), pass_on), join_leaders), hand_over), joined), close), "packed")
    else:
        later = stored(go(no_counts(now), close), "packed")
    dropped(now)
    n = counts(later)
    if up:
        log.append(pairs_of(later, LIFTED))
    if direct:
        leaders = {i: n[6 + i] for i in range(LEVELS) if n[6 + i]}
        seen = {"saturated": n[3], "leaders": sum(leaders.values()), "unled": n[3] - n[4] - sum(leaders.values()), "contracted": n[4], "two_hop": n[5], "promoted": leaders}
        if n[4]:
            log.append(pairs_of(later, JOINED))
    return Packed(later, graph.parts, n), log, seen | {"linked": linked, "lifted": up, "edges": n[GROWN] // 2}


def retired(graph: Packed, known: dict) -> tuple[Packed, DataFrame | None]:
    """(graph without finished cliques, their (vid, mu))."""
    go = lambda r, *works: superstep(r, graph.parts, known, *works)
    rows = stored(go(go(go(plain(graph.rows), closed_lists), same_lists), leave), "packed")
    n = counts(rows)
    if not n[0]:
        dropped(rows)
        return graph, None
    return Packed(rows, graph.parts, n), pairs_of(rows, DONE, ("vid", "mu"))


def among(graph: Packed, ids: list[int]) -> DataFrame:
    """(src, dst): arcs with both ends in ids."""
    few = np.unique(np.array(ids, np.int64))

    def of(s: dict) -> dict:
        mine = np.flatnonzero(np.isin(s["vid"], few))
        ptr = np.cumsum(s["deg"]) - s["deg"]
        src, dst = np.repeat(s["vid"][mine], s["deg"][mine]), s["dst"][ranges(ptr[mine], s["deg"][mine])]
        near = np.isin(dst, few)
        return {"src": src[near], "dst": dst[near]}

    return unpacked(graph.rows, STATE, "src long, dst long", of)


def degrees_of(graph: Packed) -> DataFrame:
    return unpacked(graph.rows, STATE, "vid long, level int, active boolean, deg long", lambda s: {"vid": s["vid"], "level": (s["flag"] >> 1).astype(np.int32), "active": (s["flag"] & 1).astype(bool), "deg": s["deg"].astype(np.int64)})
