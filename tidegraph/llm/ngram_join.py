"""n-gram Jaccard join by grouped prefixes, and the components of its links.

A document is its set of distinct k-word shingles. Shingles have one global order, rare ones first, by their
document frequency over all documents. Two sets with Jaccard >= t share a shingle of their
prefixes, the first n - ceil(t n) + 1 of each. A prefix shingle that one document alone has finds
nothing and is not indexed, so documents with no near copy cost nothing beyond the counting.

Documents with equal sets are one class. Classes with the same prefix and size are one group; groups, not
documents, stand in the index and pass the size and position filters, and group pairs are expanded to
members that are verified on whole sets.

Only components are asked for, so a group of near copies is not expanded into all pairs. First, stars:
in each index list and band of sizes the others are held against one pivot (the one with the fewest
shingles of its own), and in each group its members
against the first. What these links join needs no more checks. Then, exactly the rest: in every
list that still has several components, the members outside its largest one are held against all
of other components. Here a bitmap of parities bounds the overlap as well: sets that differ in more bits than a linked
pair may differ in shingles are no link. Every pair that passes the filters is so either verified or already connected.

Cases: A-Z count as lower case. With fewer than k words the whole sequence is the one shingle; without words
or text the set is empty and links with nothing. Repeated rows are one class; null ids take part, and
their component is the least id that is not null (null if none). Empty tables give an empty result. Extra columns are
ignored. Shingles are told apart by 64-bit hashes, sets by 128 bits.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tidegraph.functions.session import cut, stored
from tidegraph.llm.blocks import exchange, ordered, short_keys, sums, totals_of, with_blocks
from tidegraph.functions.keyed import spread
from tidegraph.llm.textpack import U, by_doc, carried, mix, per_doc, shingle_sets, words_of
from tidegraph.operators.baselines import hook_contract_components
from tidegraph.operators.primitives import all_of

LOCAL = 20_000
PLACE = 28  # bits of a row number below its block's number
WORDS = 8  # 64-bit words of a set's parity bitmap


def _sets(docs: DataFrame, id_col: str, text_col: str, k: int, percent: int, fold: bool, block_bytes: int | None, keep: tuple[str, ...] = ()) -> tuple[DataFrame, DataFrame]:
    """The documents in blocks, with keep columns (named by `carried`), and their sets, one row a document: rid (its block and its place there), id, n, sig1, sig2, gid, tokens and places (indexed prefix), shingles (where tokens are)."""
    picked = docs.select(F.col(id_col).alias("_id"), F.col(text_col).alias("_text"), *[F.col(f"`{c}`").alias(x) for c, x in zip(keep, carried(keep, text_col), strict=True) if x != "_text"])
    blocked, blocks = with_blocks(picked, "_id", "_text", block_bytes)
    parts = 1 << (max(1, blocks // 2) - 1).bit_length()
    mask = short_keys(parts)  # keys taken for one another make frequencies larger, never smaller: only the index grows
    schema = T._parse_datatype_string("rid long, n long, a long, sig1 long, sig2 long, gid long, tokens array<long>, places array<int>, shingles array<long>, bits array<long>")
    schema = T.StructType([schema[0], picked.schema["_id"], *schema[1:]])

    def ask(table: pa.Table) -> dict:
        _, h = shingle_sets(words_of(table["_text"], fold), k)
        keys, counts = np.unique(h & mask, return_counts=True)
        return {0: (keys, counts.astype(np.uint32))}

    def finish(table: pa.Table, said: dict) -> pa.Table:
        rows = table.num_rows
        table = ordered(table)
        doc, h = shingle_sets(words_of(table["_text"], fold), k)
        _, inverse = np.unique(h & mask, return_inverse=True)
        df = totals_of(said.get(0, {}))[inverse] if len(h) else np.zeros(0, np.uint64)
        offs = np.searchsorted(doc, np.arange(rows + 1))
        n = np.diff(offs)
        add = lambda x: np.array([int(v) for v in np.add.reduceat(np.append(x, U(0)), offs[:-1])], np.uint64) * (n > 0)
        order = by_doc(np.argsort(np.minimum(df, 65535).astype(np.uint16), kind="stable"), doc)
        rare, times = h[order], df[order]
        place = np.arange(len(h)) - np.repeat(offs[:-1], n)
        common = per_doc((times >= 2).astype(np.int64), offs)  # the most shingles it can share
        inside = place < np.repeat(n + (-percent * n) // 100 + 1, n)
        gid = add(np.where(inside, mix(rare), U(0))) + mix(n.astype(np.uint64))
        index = inside & (times >= 2)
        found = np.append(0, np.cumsum(per_doc(index.astype(np.int64), offs)))
        full = np.repeat(np.diff(found) > 0, n)
        kept = np.append(0, np.cumsum(np.where(np.diff(found) > 0, n, 0)))
        bits = np.zeros(rows * WORDS, U)  # parity bitmap: each shingle flips one bit, so shared ones cancel out
        at = mix(h ^ U(0x5BD1E9955BD1E995))
        np.bitwise_xor.at(bits, doc * WORDS + (at >> U(6)).astype(np.int64) % WORDS, U(1) << (at & U(63)))
        lists = lambda at, values: pa.ListArray.from_arrays(pa.array(at.astype(np.int32)), values)
        signed = lambda x: pa.array(x.astype(np.uint64).view(np.int64))
        block = table["_block"][0].as_py() if rows else 0
        cols = [pa.array((block << PLACE) + np.arange(rows)), table["_id"], pa.array(n), pa.array(common), signed(add(mix(h))), signed(add(mix(h ^ U(0xA5A5A5A5A5A5A5A5)))), signed(gid)]
        cols += [lists(found, signed(rare[index])), lists(found, pa.array((place - np.repeat(n - common, n))[index].astype(np.int32))), lists(kept, signed(h[full]))]
        has = np.diff(found) > 0
        cols.append(lists(np.append(0, np.cumsum(has)) * WORDS, signed(bits[np.repeat(has, WORDS)])))
        return pa.Table.from_arrays(cols, names=["rid", "_id", "n", "a", "sig1", "sig2", "gid", "tokens", "places", "shingles", "bits"])

    return blocked, exchange(blocked, ask, sums, finish, schema, parts, True)


def _beside(blocked: DataFrame, verdicts: DataFrame) -> DataFrame:
    """The documents in blocks with their verdicts, of which every rid has one."""
    added = verdicts.schema.fieldNames()[2:]
    schema = T.StructType([*[f for f in blocked.schema if f.name != "_block"], *[verdicts.schema[c] for c in added]])

    def put(rows: pa.Table, said: pa.Table) -> pa.Table:
        rows, said = ordered(rows).drop_columns("_block"), said.sort_by("place")
        for c in added:
            rows = rows.append_column(c, said[c])
        return rows

    return blocked.groupBy("_block").cogroup(verdicts.groupBy("block")).applyInArrow(put, schema)


def _needed(a: Column, b: Column, percent: int) -> Column:
    """Least intersection of sets of sizes a and b."""
    return F.ceil(percent * (a + b) / (100 + percent) - 1e-9)


def _may_link(x: str, y: str, percent: int) -> Column:
    """Size and position filters for prefix entries under two aliases: n, a (shingles that other documents have too), place among these."""
    nx, ny, ax, ay, px, py = (F.col(f"{s}.{c}") for c in ("n", "a", "place") for s in (x, y))
    most = F.least(px, py) + 1 + F.least(ax - px - 1, ay - py - 1)
    return (100 * F.least(nx, ny) >= percent * F.greatest(nx, ny)) & (most >= _needed(nx, ny, percent))


def _differ_little(x: str, y: str, nx: str, ny: str, percent: int) -> Column:
    """Lossless bitmap filter: bits that differ are at most the shingles that differ. Null bitmaps pass."""
    differ = sum((F.bit_count(F.col(x)[i].bitwiseXOR(F.col(y)[i])) for i in range(WORDS)), F.lit(0))
    return F.coalesce(differ <= F.col(nx) + F.col(ny) - 2 * _needed(F.col(nx), F.col(ny), percent), F.lit(True))


def _verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """(u, v) of those pairs whose whole sets are similar."""
    whole = sets.select("rid", "n", "shingles")
    left = whole.select(F.col("rid").alias("u"), F.col("n").alias("nu"), F.col("shingles").alias("su"))
    right = whole.select(F.col("rid").alias("v"), F.col("n").alias("nv"), F.col("shingles").alias("sv"))
    # a pivot has a pair with every member of its cluster: such pairs are dealt over salts, and its set goes to each salt once
    pairs, left = spread(cut(pairs), left, ["u"])
    pairs, right = spread(pairs.withColumnRenamed("_salt", "_salt_u"), right, ["v"])
    joined = pairs.join(left.withColumnRenamed("_salt", "_salt_u"), ["u", "_salt_u"]).join(right, ["v", "_salt"])
    joined = joined.withColumn("i", F.size(F.array_intersect("su", "sv"))).where(100 * F.col("i") >= percent * (F.col("nu") + F.col("nv") - F.col("i")))
    return cut(joined.select("u", "v"))


def similar_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = 5, percent: int = 80, fold: bool = True, block_bytes: int | None = None, keep: tuple[str, ...] = ()) -> DataFrame:
    """One row a document: id, keep columns, n_shingles, component_id (least id reachable by links), first (one row a component)."""
    if {"n_shingles", "component_id", "first"} & {id_col, *keep}:
        raise ValueError("columns clash with results: n_shingles, component_id, first")
    blocked, sets = _sets(docs, id_col, text_col, k, percent, fold, block_bytes, keep)
    sets = stored(sets, "shingle-sets")
    some = sets.where("n > 0").select("rid", "_id", "n", "sig1", "sig2")
    classes = cut(some.groupBy("sig1", "sig2").agg(F.min("rid").alias("rep"), F.count("*").alias("copies")))
    spare = some.join(classes.where("copies > 1").select("sig1", "sig2", "rep"), ["sig1", "sig2"]).where("rid <> rep").select("rid")
    indexed = sets.where(F.size("tokens") > 0)
    members = cut(indexed.select("rid", "gid", "n", "bits").join(spare, "rid", "left_anti"))  # one a class
    entries = indexed.select("rid", "gid", "n", "a", F.posexplode("tokens").alias("_i", "token"), "places").select("rid", "gid", "n", "a", "token", F.col("places")[F.col("_i")].alias("place"))
    entries = stored(entries.join(spare, "rid", "left_anti"), "prefix-entries")

    groups = entries.groupBy("token", "gid", "n", "a", "place").agg(F.min("rid").alias("lead"))
    band = F.floor(F.ln(F.col("n")) / F.lit(0.1))
    lists = cut(groups.withColumn("band", band))
    pivots = lists.groupBy("token", "band").agg(F.min(F.struct((F.col("n") - F.col("a")).alias("own"), F.xxhash64("gid").alias("h"), "gid", "n", "a", "place", "lead")).alias("p"), F.count("*").alias("c")).where("c > 1").select("token", "band", "p.gid", "p.n", "p.a", "p.place", "p.lead")
    dealt, pivots = spread(lists, pivots, ["token", "band"])
    star = dealt.alias("x").join(pivots.alias("y"), ["token", "band", "_salt"]).where((F.col("x.lead") != F.col("y.lead")) & _may_link("x", "y", percent))
    star = star.select(F.least("x.lead", "y.lead").alias("u"), F.greatest("x.lead", "y.lead").alias("v"))
    leads = members.groupBy("gid").agg(F.min("rid").alias("u"))
    inner = members.select("rid", "gid").join(leads, "gid").where("rid <> u").select("u", F.col("rid").alias("v"))
    first = _verified(star.unionByName(inner).distinct(), sets, percent)

    near = hook_contract_components(first, local_arcs=LOCAL).labels.select(F.col("vertex").alias("rid"), F.col("component").alias("comp"))
    placed = cut(entries.join(near, "rid", "left").groupBy("token", "gid", "n", "a", "place", F.coalesce("comp", "rid").alias("comp")).agg(F.lit(1).alias("_one")).drop("_one"))
    shares = placed.groupBy("token", "comp").agg(F.count("*").alias("c"))
    main = shares.groupBy("token").agg(F.max_by("comp", F.struct("c", "comp")).alias("main"), F.count("*").alias("comps")).where("comps > 1").select("token", "main")
    inside = cut(members.join(near, "rid", "left").select("gid", "rid", "n", "bits", F.coalesce("comp", "rid").alias("comp")))
    # a group's members in one component mostly are one set; where they are several, the group passes without a bitmap
    maps = inside.groupBy("gid", "comp").agg(F.when(F.count("*") == 1, F.any_value("bits")).alias("bits"))
    mixed = cut(placed.join(main, "token").join(maps, ["gid", "comp"]))
    minor = mixed.where("comp <> main")
    dealt, minor = spread(mixed, minor, ["token"])
    rest = minor.alias("x").join(dealt.alias("y"), ["token", "_salt"]).where((F.col("x.comp") != F.col("y.comp")) & _may_link("x", "y", percent) & _differ_little("x.bits", "y.bits", "x.n", "y.n", percent))
    rest = rest.select(*[F.col(f"{a}.{c}").alias(f"{c}_{a}") for a in "xy" for c in ("gid", "comp")]).distinct()
    for a, name in (("x", "p"), ("y", "q")):
        rest = rest.join(inside.select(F.col("gid").alias(f"gid_{a}"), F.col("comp").alias(f"comp_{a}"), F.col("rid").alias(name), F.col("n").alias(f"n_{name}"), F.col("bits").alias(f"bits_{name}")), [f"gid_{a}", f"comp_{a}"])
    rest = rest.where(_differ_little("bits_p", "bits_q", "n_p", "n_q", percent))
    second = _verified(rest.select(F.least("p", "q").alias("u"), F.greatest("p", "q").alias("v")).distinct(), sets, percent)

    labels = hook_contract_components(all_of([first, second]), local_arcs=LOCAL).labels
    named = sets.select("rid", "_id", "n", "sig1", "sig2").join(classes.select(F.col("sig1").alias("_s1"), F.col("sig2").alias("_s2"), "rep"), (F.col("n") > 0) & (F.col("sig1") == F.col("_s1")) & (F.col("sig2") == F.col("_s2")), "left")
    named = named.join(labels, F.col("rep") == F.col("vertex"), "left").select("rid", "_id", "n", F.coalesce("component", "rep", "rid").alias("comp"))
    named = cut(named)
    least = named.groupBy("comp").agg(F.min("_id").alias("component_id"), F.min(F.when(F.col("_id").isNotNull(), F.struct("_id", "rid")))["rid"].alias("r1"), F.min("rid").alias("r2"))
    named, least = spread(named, least, ["comp"])
    out = named.join(least, ["comp", "_salt"]).withColumn("first", F.col("rid") == F.coalesce("r1", "r2"))
    if keep:
        place = F.col("rid").bitwiseAND((1 << PLACE) - 1).alias("place")
        out = _beside(blocked, out.select(F.shiftright("rid", PLACE).alias("block"), place, "n", "component_id", "first"))
    return out.select(F.col("_id").alias(id_col), *[F.col(x).alias(c) for x, c in zip(carried(keep, text_col), keep, strict=True)], F.col("n").alias("n_shingles"), "component_id", "first")
