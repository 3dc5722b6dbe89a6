"""Mixing sources to target weights by Pareto order sampling. DataFrame functions only.

A source's target is dealt over its documents by a document weight: the binary digits of its word count, so that
longer texts are likelier to be taken. A document's expected copies are min(most, rate x weight), with the rate at which the source's expected words are
its target. The whole part are certain copies; the fraction f, which differs between documents, is sampled: documents are ranked
by random odds over inclusion odds, (u / (1 - u)) / (f / (1 - f)), and the sample is the ranking's head whose words come nearest
to what the certain copies leave of the target. The sample's size is thus fixed in words, with an error under half a document, and
a document is in it with a probability near its f. u comes from the md5 of seed and id, so reruns agree.

The rates need one aggregate by (source, weight), at most 64 weights a source. The head is found without gathering a
source: ranks fall into bins, sums by (source, bin) give the bin in
which the target is met, and only that bin's documents are ranked one by one. The parameters of sources are broadcast
after a count, or joined over salts beyond it, so a hot source costs its share of a scan and 1 / bins of its rows in a window.

Cases: null text has size 0 and takes 0; null source is a source of its own, last. Repeated rows share u
and are taken or left side by side. Zero-size sources have target 0. An empty table gives an empty result.
Extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tidegraph.functions.session import cut, stored
from tidegraph.functions.keyed import attach

WORD = r"[^\x20\x09-\x0D]+"
BINS = 16384


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def uniform(id_: Column, seed: int) -> Column:
    """In (0, 1), from 52 bits of an md5."""
    digest = F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(id_.cast("string"), F.lit("null"))))
    return (F.conv(F.substring(digest, 1, 13), 16, 10).cast("double") + 0.5) / float(1 << 52)


def source_targets(sized: DataFrame, weights: tuple[int, ...] = (3, 1, 2), share: float = 1.5, most: int = 2) -> DataFrame:
    """One row a source: _source, source_size, target. Targets are min(cap, rate x weight) with the rate that
    spends the whole share: what capped sources leave goes to the others by weight."""
    sources = sized.groupBy("_source").agg(F.sum("size").alias("source_size"))
    at = F.row_number().over(Window.orderBy(F.col("_source").asc_nulls_last())) - 1
    weight = F.element_at(F.array(*[F.lit(w) for w in weights]), (at % len(weights) + 1).cast("int")).cast("long")
    ranked = sources.withColumn("w", weight).withColumn("cap", F.col("source_size") * most)
    # sources by the rate at which they hit their cap; the open ones are a suffix of this order
    by = Window.orderBy(F.col("cap") / F.col("w"), F.col("_source").asc_nulls_last())
    rest, before = by.rowsBetween(0, Window.unboundedFollowing), by.rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.partitionBy()
    total = F.sum("source_size").over(everything).cast("double")
    rate = (F.lit(float(share)) * total - F.coalesce(F.sum("cap").over(before), F.lit(0)).cast("double")) / F.sum("w").over(rest).cast("double")
    fits = ranked.withColumn("rate", rate).withColumn("fits", F.col("rate") <= F.col("cap") / F.col("w"))
    level = F.max(F.when(F.col("fits"), F.col("rate"))).over(everything)  # rates fall from the first fitting source on
    return fits.select("_source", "source_size", F.least(F.col("cap").cast("double"), F.coalesce(level, F.lit(float("inf"))) * F.col("w")).alias("target"))


def digits(size: Column) -> Column:
    """Binary digits of a size: the document weight."""
    return F.length(F.bin(size)).cast("long")


def expected_copies(classes: DataFrame, targets: DataFrame, most: int) -> DataFrame:
    """One row a source and weight: whole copies, the fraction f, and `left`, the words the source's sample shall have.

    classes: _source, w, words. From the highest weight down, documents at the cap are a prefix; the rate is that of the first
    weight which it does not lift above the cap.
    """
    c = attach(classes, targets, {"_source": "_s"})
    by = Window.partitionBy("_source").orderBy(F.desc("w"))
    before, rest = by.rowsBetween(Window.unboundedPreceding, -1), by.rowsBetween(0, Window.unboundedFollowing)
    rate = (F.col("target") - (F.coalesce(F.sum("words").over(before), F.lit(0)) * most).cast("double")) / F.nullif(F.sum(F.col("words") * F.col("w")).over(rest), F.lit(0)).cast("double")  # no words below: no rate
    c = c.withColumn("rate", rate)
    every = Window.partitionBy("_source")
    level = F.max(F.when(F.col("rate") * F.col("w") <= most, F.struct("w", "rate"))).over(every)["rate"]
    copies = F.when(F.col("target") >= F.col("source_size") * most, F.lit(float(most))).otherwise(F.least(F.lit(float(most)), F.coalesce(level, F.lit(float("inf"))) * F.col("w")))
    c = c.withColumn("copies", F.when(F.col("source_size") > 0, copies).otherwise(F.lit(0.0))).withColumn("whole", F.floor("copies"))
    c = c.withColumn("f", F.col("copies") - F.col("whole")).withColumn("left", F.col("target") - F.sum(F.col("whole") * F.col("words")).over(every).cast("double"))
    return c.select(F.col("_source").alias("_s"), F.col("w").alias("_w"), "source_size", "target", "whole", "f", "left")


def mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: tuple[int, ...] = (3, 1, 2), share: float = 1.5, most: int = 2, seed: int = 17, keep: tuple[str, ...] = ()) -> DataFrame:
    """One row a document: id, keep columns, size, source_size, target, copies, taken (copies x size)."""
    results = ["size", "source_size", "target", "copies", "taken"]
    if {*results} & {id_col, *keep}:
        raise ValueError(f"columns clash with results: {results}")
    carried = [F.col(f"`{c}`").alias(f"_k{i}") for i, c in enumerate(keep)]
    sized = stored(docs.select(F.col(id_col).alias("_id"), F.col(source_col).alias("_source"), word_count(F.col(text_col)).alias("size"), *carried).withColumn("w", digits(F.col("size"))), "mix-sizes")
    targets = cut(source_targets(sized, weights, share, most).withColumnRenamed("_source", "_s"))
    classes = cut(sized.groupBy("_source", "w").agg(F.sum("size").alias("words")))
    params = cut(expected_copies(classes, targets, most))
    rows = attach(sized, params, {"_source": "_s", "w": "_w"})
    u = uniform(F.col("_id"), seed)
    rows = rows.withColumn("q", F.when(F.col("f") > 0, (u / (1 - u)) / (F.col("f") / (1 - F.col("f")))))
    rows = rows.withColumn("bin", F.floor(F.col("q") / (1 + F.col("q")) * BINS).cast("int"))
    bins = rows.where("f > 0").groupBy("_source", "bin", "left").agg(F.sum("size").alias("c"))
    bins = bins.withColumn("upto", F.sum("c").over(Window.partitionBy("_source").orderBy("bin")))
    # the bin in which each source's sample ends, and the words of the bins before it; beyond all bins: no row
    ends = cut(bins.where(F.col("upto") > F.col("left")).groupBy("_source").agg(F.min(F.struct("bin", (F.col("upto") - F.col("c")).alias("before"))).alias("e")).select(F.col("_source").alias("_s"), F.col("e.bin").alias("last"), "e.before"))
    rows = attach(rows, ends, {"_source": "_s"}, "left")
    edge = (F.col("f") > 0) & F.col("last").isNotNull() & (F.col("bin") == F.col("last"))
    plain = rows.where(~F.coalesce(edge, F.lit(False))).withColumn("extra", F.when((F.col("f") > 0) & (F.col("last").isNull() | (F.col("bin") < F.col("last"))), 1).otherwise(0))
    order = Window.partitionBy("_source").orderBy("q", "_id", "size")
    upto = F.col("before") + F.sum("size").over(order.rowsBetween(Window.unboundedPreceding, 0))
    near = rows.where(edge).withColumn("upto", upto)
    near = near.withColumn("extra", F.when((F.col("upto") <= F.col("left")) | (F.col("upto") - F.col("size") / 2 <= F.col("left")) & (F.col("upto") - F.col("size") < F.col("left")), 1).otherwise(0)).drop("upto")
    out = plain.unionByName(near)
    copies = (F.col("whole") + F.col("extra")).cast("long")
    return out.select(F.col("_id").alias(id_col), *[F.col(f"_k{i}").alias(c) for i, c in enumerate(keep)], "size", "source_size", "target", copies.alias("copies"), (copies * F.col("size")).alias("taken"))
