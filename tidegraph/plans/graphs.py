"""Graphs on the given tables: edges(u, v) for every workload."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tidegraph.functions.ids import tag


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def edges_from(df: DataFrame, a: str, b: str, kind_a: str, kind_b: str) -> DataFrame:
    return df.select(tag(F.col(a), kind_a).alias("u"), tag(F.col(b), kind_b).alias("v")).distinct()


def geo_forest(spark, d):
    parts = [("nation", "n_nationkey", "n_regionkey", "nation", "region"), ("customer", "c_custkey", "c_nationkey", "customer", "nation"), ("supplier", "s_suppkey", "s_nationkey", "supplier", "nation")]
    frames = [edges_from(table(spark, d, t), a, b, ka, kb) for t, a, b, ka, kb in parts]
    return frames[0].unionByName(frames[1]).unionByName(frames[2])


def part_supplier(spark, d):
    return edges_from(table(spark, d, "lineitem"), "l_partkey", "l_suppkey", "part", "supplier")


def customer_supplier(spark, d):
    j = table(spark, d, "orders").join(table(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))
    return edges_from(j, "o_custkey", "l_suppkey", "customer", "supplier")


def order_part(spark, d, q=None):
    li = table(spark, d, "lineitem")
    return edges_from(li if q is None else li.where(F.col("l_quantity") <= q), "l_orderkey", "l_partkey", "order", "part")


def user_paths(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = table(spark, d, "events").select("event_id", F.lead("event_id").over(w).alias("nxt")).where("nxt is not null")
    return e.select(tag(F.col("event_id"), "event").alias("u"), tag(F.col("nxt"), "event").alias("v"))


def event_ring(spark, d, rings=1):
    """Events in rank order closed to one ring, or to two over the halves."""
    from tidegraph.operators.primitives import global_index

    e = table(spark, d, "events").select("event_id")
    n = e.count()
    size = n // rings
    r = global_index(e, "event_id", "i").where(F.col("i") < size * rings)
    nxt = (F.floor(F.col("i") / size) * size + (F.col("i") + 1) % size).cast("long")
    return r.select(F.col("i").alias("u"), nxt.alias("v"))


def user_user(spark, d):
    """Users of consecutive events, in the table's total order; a key is carried so that no task holds all rows."""
    from tidegraph.operators.primitives import global_index

    e = global_index(table(spark, d, "events").select("user_id", "ts", "event_id"), ["ts", "event_id"], "i")
    a, b = e.select("i", F.col("user_id").alias("x")), e.select((F.col("i") - 1).alias("i"), F.col("user_id").alias("y"))
    return a.join(b, "i").where("x <> y").select(F.least("x", "y").cast("long").alias("u"), F.greatest("x", "y").cast("long").alias("v")).distinct()


def conversation_turns(spark, d):
    c = table(spark, d, "conversations").select("conv_id", "turn").distinct()
    nxt = c.select("conv_id", (F.col("turn") - 1).alias("turn"))
    return c.join(nxt, ["conv_id", "turn"]).select((F.col("conv_id") * 1000 + F.col("turn")).cast("long").alias("u"), (F.col("conv_id") * 1000 + F.col("turn") + 1).cast("long").alias("v"))


def document_copies(spark, d):
    docs = table(spark, d, "documents").select("doc_id", F.md5("text").alias("h")).where("h is not null")
    least = docs.groupBy("h").agg(F.min("doc_id").alias("u"))
    return docs.join(least, "h").where("doc_id <> u").select(F.col("u").cast("long").alias("u"), F.col("doc_id").cast("long").alias("v"))


def document_lines(spark, d):
    """Documents and their lines of 20 characters or more, lines numbered by the first 13 hex digits of their md5."""
    line = F.explode(F.split("text", "\n"))
    e = table(spark, d, "documents").select("doc_id", line.alias("line")).where(F.length("line") >= 20)
    h = F.conv(F.substring(F.md5("line"), 1, 13), 16, 10).cast("long")
    return e.select((F.col("doc_id").cast("long") * 8).alias("u"), (h * 8 + 7).alias("v")).distinct()


def page_links(spark, d):
    """Hosts and the paths their pages link to, as strings."""
    host = F.regexp_extract("url", r"^[a-z]+://([^/?#]+)", 1)
    href = F.explode(F.regexp_extract_all("html", F.lit(r"href=\"(/[^\"]*)\""), 1))
    return table(spark, d, "pages").select(host.alias("u"), href.alias("v")).distinct()


def user_cliques(spark, d):
    u = table(spark, d, "events").select("user_id").distinct().withColumn("k", F.col("user_id") % 10)
    return u.alias("a").join(u.alias("b"), "k").where("a.user_id < b.user_id").select(F.col("a.user_id").cast("long").alias("u"), F.col("b.user_id").cast("long").alias("v"))


def caterpillar(spark, d):
    pend = table(spark, d, "events").select("event_id", F.explode(F.sequence(F.lit(0), (F.col("event_id") % 5).cast("int"))).alias("k")).where("k > 0")
    return user_paths(spark, d).unionByName(pend.select(tag(F.col("event_id"), "event").alias("u"), ((F.col("event_id") * 5 + F.col("k")) * 8 + 7).cast("long").alias("v")))


def circulant(spark, n, b):
    return spark.range(n).select(F.col("id").alias("u"), F.explode(F.sequence(F.lit(1), F.lit(b // 2))).alias("s")).select("u", ((F.col("u") + F.col("s")) % n).alias("v"))


def _similarities(e: DataFrame, block_rows: int, pick, schema: str) -> DataFrame:
    """Blocks of vectors against blocks of vectors, each pair of blocks one task's matrix product; pick thins its result there."""
    import numpy as np
    import pyarrow as pa

    vec = next(f.name for f in e.schema if f.dataType.simpleString().startswith("array"))
    n = max(1, -(-e.count() // block_rows))
    rows = e.select(F.col(e.columns[0]).cast("long").alias("i"), F.col(vec).cast("array<double>").alias("x"), F.pmod(F.xxhash64(e.columns[0]), F.lit(n)).alias("b"))
    others = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long")))
    left = rows.withColumn("c", others)
    right = rows.select(F.col("i").alias("j"), F.col("x").alias("y"), F.col("b").alias("c2")).withColumn("b2", others)  # names of its own: a cogroup of one frame with itself mixes up its columns

    def run(a: pa.Table, b: pa.Table) -> pa.Table:
        if not a.num_rows or not b.num_rows:
            return pa.table({"i": pa.array([], pa.int64()), "j": pa.array([], pa.int64()), "s": pa.array([], pa.float64())})
        i, j = a["i"].to_numpy(), b["j"].to_numpy()
        x, y = np.array(a["x"].to_pylist(), float), np.array(b["y"].to_pylist(), float)
        s = np.round(x @ y.T, 6)
        s[i[:, None] == j[None, :]] = -np.inf
        p, q = pick(s, j)
        return pa.table({"i": pa.array(i[p], pa.int64()), "j": pa.array(j[q], pa.int64()), "s": pa.array(s[p, q], pa.float64())})

    return left.groupBy("b", "c").cogroup(right.groupBy("b2", "c2")).applyInArrow(run, schema)


def _undirected(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.least("i", "j").alias("u"), F.greatest("i", "j").alias("v")).distinct()


def embedding_neighbors(spark, d, k=1, block_rows=2000):
    """Each vector's k nearest by cosine (unit vectors): exact, by blocks; a pair of blocks sends k candidates a vector on."""
    import numpy as np

    def pick(s, j):
        order = np.lexsort((np.broadcast_to(j, s.shape), -s), axis=1)[:, :k]
        p, q = np.repeat(np.arange(len(s)), order.shape[1]), order.ravel()
        ok = np.isfinite(s[p, q])
        return p[ok], q[ok]

    near = _similarities(table(spark, d, "embeddings"), block_rows, pick, "i long, j long, s double")
    top = near.withColumn("r", F.row_number().over(Window.partitionBy("i").orderBy(F.desc("s"), "j"))).where(F.col("r") <= k)
    return _undirected(top)


def similarity_edges(spark, d, tau=0.35, block_rows=2000):
    """Pairs of vectors with a cosine of tau or more: exact, by blocks; only such pairs leave a task."""
    return _undirected(_similarities(table(spark, d, "embeddings"), block_rows, lambda s, j: (s >= tau).nonzero(), "i long, j long, s double"))


def json_key_edges(spark, d):
    """Events and the key k of their props."""
    k = F.get_json_object("props", "$.k").cast("long")
    e = table(spark, d, "events").select(tag(F.col("event_id"), "event").alias("u"), (k * 8 + 7).alias("v"))
    return e.where("v is not null")


def global_path(spark, d):
    """All events in one row, by time: the largest diameter there can be. Ids are positions."""
    from tidegraph.operators.primitives import global_index

    e = global_index(table(spark, d, "events").select("ts", "event_id"), ["ts", "event_id"], "i")
    return e.where("i > 0").select((F.col("i") - 1).alias("u"), F.col("i").alias("v"))


def path_family(spark, lengths):
    """Disjoint paths of these lengths (in edges): vertices of the k-th are k * 2^32 and up."""
    rows = spark.createDataFrame([(k << 32, n) for k, n in enumerate(lengths)], "base long, n long")
    return rows.select("base", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - 1)).alias("i")).select((F.col("base") + F.col("i")).alias("u"), (F.col("base") + F.col("i") + 1).alias("v"))


def edges_asof(spark, d, until: str):
    """Consecutive events of users as known at a time."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = table(spark, d, "events").where(F.col("ts") <= F.lit(until).cast("timestamp")).select("event_id", F.lead("event_id").over(w).alias("nxt")).where("nxt is not null")
    return e.select(tag(F.col("event_id"), "event").alias("u"), tag(F.col("nxt"), "event").alias("v"))


def cooccurrence(spark, d, seconds=60):
    """Users with events at most `seconds` apart: a range join over time buckets."""
    e = table(spark, d, "events").select("user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    w = seconds * 1_000_000
    a = e.select(F.col("user_id").alias("x"), F.col("t").alias("tx"), F.explode(F.array(F.floor(F.col("t") / w), F.floor(F.col("t") / w) + 1)).alias("k"))
    b = e.select(F.col("user_id").alias("y"), F.col("t").alias("ty"), F.floor(F.col("t") / w).alias("k"))
    j = a.join(b, "k").where((F.col("ty") >= F.col("tx")) & (F.col("ty") - F.col("tx") <= w) & (F.col("x") != F.col("y")))
    return j.select(F.least("x", "y").cast("long").alias("u"), F.greatest("x", "y").cast("long").alias("v")).distinct()


def cooccurrence_chain(spark, d, seconds=60):
    """Edges with the components and vertices of cooccurrence, one an event at most: two users of it are joined by the chain of events between
    theirs, whose gaps are no longer; next neighbours in it are of one user or linked here."""
    from tidegraph.operators.primitives import global_index

    e = table(spark, d, "events").select("user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"), "event_id").where("user_id is not null and t is not null")
    e = global_index(e, ["t", "event_id"], "i")
    a, b = e.select("i", F.col("user_id").alias("x"), F.col("t").alias("tx")), e.select((F.col("i") - 1).alias("i"), F.col("user_id").alias("y"), F.col("t").alias("ty"))
    j = a.join(b, "i").where((F.col("ty") - F.col("tx") <= seconds * 1_000_000) & (F.col("x") != F.col("y")))
    return j.select(F.least("x", "y").cast("long").alias("u"), F.greatest("x", "y").cast("long").alias("v")).distinct()
