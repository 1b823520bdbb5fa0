"""Streams: components kept up to date batch by batch, and session components by watermark."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from starfold.functions.keyed import Forest
from starfold.operators.incremental import merge_edges


class ComponentStream:
    """Applies an edge stream to versioned label snapshots. A batch that is replayed finds its snapshot written and stops."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")
        self.empty = spark.createDataFrame([], "vertex long, component long")

    def _snapshots(self) -> list[int]:
        sc = self.spark.sparkContext
        root = sc._jvm.org.apache.hadoop.fs.Path(self.path)
        fs = root.getFileSystem(sc._jsc.hadoopConfiguration())
        if not fs.exists(root):
            return []
        names = [s.getPath() for s in fs.listStatus(root)]
        return sorted(int(p.getName()[6:]) for p in names if p.getName().startswith("epoch=") and fs.exists(sc._jvm.org.apache.hadoop.fs.Path(p, "_SUCCESS")))

    def labels(self) -> DataFrame:
        found = self._snapshots()
        return self.spark.read.parquet(f"{self.path}/epoch={found[-1]}") if found else self.empty

    def apply(self, batch: DataFrame, epoch: int) -> None:
        found = self._snapshots()
        if epoch in found:
            return
        merge_edges(self.labels(), batch.select("a", "b")).write.mode("overwrite").parquet(f"{self.path}/epoch={epoch}")

    def start(self, edges: DataFrame, checkpoint: str) -> StreamingQuery:
        return edges.writeStream.foreachBatch(self.apply).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def session_components(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """Sessions of each user as components: least event, start and size. Works on a stream and on a table."""
    rows = events.withWatermark("ts", late) if events.isStreaming else events
    return rows.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.min("event_id").alias("component"), F.count("*").alias("n")).select("user_id", "component", "n")


def keyed_components(edges: DataFrame, idle_ms: int | None = None) -> DataFrame:
    """Components of an edge stream (key, a, b) within each key, kept as state: every batch gives (key, vertex, component) of the labels it made or changed.

    The state of a key holds its vertices, so it is for keys of bounded size (a user, a session); ``idle_ms`` drops a
    key after that much processing time without a row. Rows with a null end link nothing. A component is named by its
    least vertex, so labels only fall and the last row of a vertex is its label. With ``idle_ms`` Spark starts a batch
    even without rows, so such a query never ends under the availableNow trigger: give it an interval.
    """

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        old = dict(zip(*state.get, strict=True)) if state.exists else {}
        forest = Forest(old)
        for batch in batches:
            ends = batch[["a", "b"]].dropna().astype("int64")
            for a, b in zip(ends["a"].tolist(), ends["b"].tolist(), strict=True):
                forest.link(a, b)
        new = forest.labels()
        state.update((list(new), list(new.values())))
        if idle_ms is not None:
            state.setTimeoutDuration(idle_ms)
        moved = [(v, c) for v, c in new.items() if old.get(v) != c]
        yield pd.DataFrame({"key": [key[0]] * len(moved), "vertex": [v for v, _ in moved], "component": [c for _, c in moved]}, dtype="int64")

    rows = edges.select(*[F.col(c).cast("long").alias(c) for c in ("key", "a", "b")]).where("key is not null")
    timeout = GroupStateTimeout.NoTimeout if idle_ms is None else GroupStateTimeout.ProcessingTimeTimeout
    return rows.groupBy("key").applyInPandasWithState(step, "key long, vertex long, component long", "vertices array<long>, components array<long>", "update", timeout)
