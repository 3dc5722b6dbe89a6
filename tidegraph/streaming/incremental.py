"""Incremental components over a stream of edges, and edges from consecutive events.

Each micro-batch renames its edges by the labels so far, finds components of that small graph, and writes the next version of
the labels under its batch id; a replayed batch starts from the same version before it and overwrites its own, so replays change nothing. Labels only merge.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tidegraph.functions.session import cut
from tidegraph.operators.baselines import hook_contract_components

LABELS = "vertex long, component long"
LOCAL = 20_000  # arcs of a batch's remainder that one task finishes


class IncrementalComponents:
    """Labels are a versioned table, one version a batch. A batch is joined with the version before it, the graph of the labels
    it touches is solved, and the next version is written: work beyond one pass over the labels follows the batch, not the stream.
    """

    def __init__(self, spark: SparkSession, folder: str, keep: int = 2):
        self.spark, self.folder, self.keep = spark, folder.rstrip("/"), keep

    def _versions(self) -> list[int]:
        hadoop = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path
        at = hadoop(f"{self.folder}/labels")
        fs = at.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())
        if not fs.exists(at):
            return []
        names = [(x.getPath(), x.getPath().getName()) for x in fs.listStatus(at)]
        return sorted(int(n.split("-")[1]) for p, n in names if n.startswith("batch-") and fs.exists(hadoop(p, "_SUCCESS")))

    def labels(self, before: int = 1 << 62) -> DataFrame:
        """vertex, component as of the last batch below `before`."""
        known = [v for v in self._versions() if v < before]
        if not known:
            return self.spark.createDataFrame([], LABELS)
        return self.spark.read.schema(LABELS).parquet(f"{self.folder}/labels/batch-{known[-1]}")

    def add(self, edges: DataFrame, batch: int) -> None:
        known = self.labels(batch)
        x, y = (known.select(F.col("vertex").alias(c), F.col("component").alias(f"_{c}")) for c in "uv")
        new = cut(edges.select(F.col("u").cast("long"), F.col("v").cast("long")).join(x, "u", "left").join(y, "v", "left"))
        links = new.select(F.coalesce("_u", "u").alias("u"), F.coalesce("_v", "v").alias("v"))
        merged = hook_contract_components(links, local_arcs=LOCAL).labels.select(F.col("vertex").alias("old"), F.col("component").alias("new"))
        fresh = new.where("_u is null").select(F.col("u").alias("vertex")).unionByName(new.where("_v is null").select(F.col("v").alias("vertex"))).where("vertex is not null").distinct()
        all_ = known.unionByName(fresh.select("vertex", F.col("vertex").alias("component")))
        after = all_.join(merged, F.col("component") == F.col("old"), "left").select("vertex", F.coalesce("new", "component").alias("component"))
        after.write.mode("overwrite").parquet(f"{self.folder}/labels/batch-{batch}")
        self._forget(batch)

    def _forget(self, batch: int) -> None:
        """Older versions than the last `keep` go; a batch may be delivered again, the ones before it not."""
        sc = self.spark.sparkContext
        for v in [x for x in self._versions() if x < batch][: -self.keep]:
            at = sc._jvm.org.apache.hadoop.fs.Path(f"{self.folder}/labels/batch-{v}")
            at.getFileSystem(sc._jsc.hadoopConfiguration()).delete(at, True)

    def start(self, stream: DataFrame, checkpoint: str):
        return stream.writeStream.foreachBatch(lambda df, batch: self.add(df, batch)).option("checkpointLocation", checkpoint)


def windowed_edges(events: DataFrame, length: str = "1 hour", late: str = "2 hours", slide: str | None = None) -> DataFrame:
    """A star of each window's users: (start, u = the window's own vertex, v = user), by tumbling or sliding windows.

    The window itself is the hub, so no window's users are gathered; what comes later than `late` is dropped. Output mode append.
    """
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    seen = events.withWatermark("ts", late).groupBy(w.alias("w"), "user_id").agg(F.count("*").alias("events"))
    hub = -F.expr("timestampdiff(MICROSECOND, TIMESTAMP_NTZ '1970-01-01 00:00:00', cast(w.start AS timestamp_ntz))") - 1  # below all ids
    return seen.select(F.col("w.start").alias("start"), hub.alias("u"), F.col("user_id").cast("long").alias("v"), "events")


def session_edges(events: DataFrame, gap: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    """Sessions of users by a gap in time: (user_id, start, end, events)."""
    s = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("events"))
    return s.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "events")


def labelled_events(events: DataFrame, labels: DataFrame) -> DataFrame:
    """Stream-static join: events with their user's component (null if unknown)."""
    return events.join(labels.select(F.col("vertex").alias("user_id"), "component"), "user_id", "left")


def meeting_edges(a: DataFrame, b: DataFrame, key: str, within: str = "1 minute", late: str = "5 minutes") -> DataFrame:
    """Stream-stream join: users of two streams with the same key at most `within` apart; state is bounded by the watermarks."""
    x = a.select(F.col("user_id").alias("u"), F.col("ts").alias("_tx"), F.col(key).alias("_kx")).withWatermark("_tx", late)
    y = b.select(F.col("user_id").alias("v"), F.col("ts").alias("_ty"), F.col(key).alias("_ky")).withWatermark("_ty", late)
    near = F.expr(f"_kx = _ky and _ty >= _tx and _ty <= _tx + interval {within}")
    return x.join(y, near).where("u <> v").select("u", "v")


def consecutive_edges(events: DataFrame) -> DataFrame:
    """Stateful: (u, v) of each user's consecutive events; the state is the user's last event."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def run(key, frames, state):
        last = state.get[0] if state.exists else None
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])["event_id"].tolist()
        chain = ([last] if last is not None else []) + rows
        state.update((chain[-1],))
        yield pd.DataFrame({"u": chain[:-1], "v": chain[1:]}, dtype="int64")

    return events.groupBy("user_id").applyInPandasWithState(run, "u long, v long", "last long", "append", GroupStateTimeout.NoTimeout)
