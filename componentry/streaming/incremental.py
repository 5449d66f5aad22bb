"""Components and windows over streams of edges or events."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from componentry.functions.graphs import Graph, normalize_edges
from componentry.operators.components import min_owner
from componentry.plans.storage import cut, drop_path, release, shared_dir


class ComponentStore:
    """Labels kept over micro-batches: a batch's edges are joined to the labels, and only the quotient is solved.

    Each batch writes a generation of labels below ``path``, named by the batch, and then removes the ones before. A store
    opened on the same path, after a restart from the stream's checkpoint, goes on from the last whole generation; a batch
    that is given again (same number) changes nothing. Without a path the store lasts as long as the session.
    """

    def __init__(self, spark: SparkSession, path: str | None = None):
        self.spark = spark
        self.path = path or f"{shared_dir(spark)}/componentry/store-{uuid.uuid4().hex}"
        self.batch = max(self._generations(), default=-1)
        self.labels: DataFrame | None = spark.read.parquet(self._place(self.batch)) if self.batch >= 0 else None

    def _place(self, batch: int) -> str:
        return f"{self.path}/batch={batch:012d}"

    def _generations(self) -> list[int]:
        """Batches whose labels were written whole."""
        jvm = self.spark._jvm
        root = jvm.org.apache.hadoop.fs.Path(self.path)
        fs = root.getFileSystem(self.spark._jsc.hadoopConfiguration())
        if not fs.exists(root):
            return []
        names = [f.getPath().getName() for f in fs.listStatus(root)]
        return [int(n[6:]) for n in names if n.startswith("batch=") and fs.exists(jvm.org.apache.hadoop.fs.Path(f"{self.path}/{n}/_SUCCESS"))]

    def add(self, edges: DataFrame, batch: int) -> None:
        if batch <= self.batch:
            return
        edges = cut(normalize_edges(edges), "batch")
        ids = edges.select(F.explode(F.array("src", "dst")).alias("id")).distinct()
        old = self.labels if self.labels is not None else ids.limit(0).select("id", F.col("id").alias("component"))
        known = ids.join(old, "id", "left").select("id", F.coalesce("component", "id").alias("component"))
        known = cut(known, "known")
        a, b = known.select(F.col("id").alias("src"), F.col("component").alias("ca")), known.select(F.col("id").alias("dst"), F.col("component").alias("cb"))
        quotient = cut(normalize_edges(edges.join(a, "src").join(b, "dst").select(F.col("ca").alias("src"), F.col("cb").alias("dst"))), "quotient")
        moved = min_owner(Graph(quotient), stats=False).components.select(F.col("id").alias("component"), F.col("component").alias("to"))
        fresh = known.join(old.select("id"), "id", "left_anti")
        labels = old.unionByName(fresh).join(moved, "component", "left").select("id", F.coalesce("to", "component").alias("component"))
        labels.write.mode("overwrite").parquet(self._place(batch))
        release(edges, known, quotient)
        for before in self._generations():
            if before < batch:
                drop_path(self.spark, self._place(before))
        self.labels, self.batch = self.spark.read.parquet(self._place(batch)), batch


def components(stream: DataFrame, store: ComponentStore):
    """A writer that keeps ``store`` up to date with a stream of (src, dst); call ``start`` on it."""
    return stream.writeStream.foreachBatch(store.add)


def window_edges(events: DataFrame, ts: str, width: str, src: str, dst: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """(window start, src, dst, n): edges of each tumbling or sliding window; what is later than the watermark is dropped."""
    w = F.window(ts, width, slide) if slide else F.window(ts, width)
    marked = events.withWatermark(ts, late) if events.isStreaming else events
    return marked.groupBy(w.alias("w"), src, dst).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), F.col(src).alias("src"), F.col(dst).alias("dst"), "n")


def session_counts(events: DataFrame, ts: str, part: str, gap: str, late: str = "1 hour") -> DataFrame:
    """(part, start, end, n): sessions, runs of events with no gap of ``gap``."""
    marked = events.withWatermark(ts, late) if events.isStreaming else events
    return marked.groupBy(F.session_window(ts, gap).alias("w"), part).agg(F.count(F.lit(1)).alias("n")).select(part, F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def windowed_graph(edges: DataFrame) -> DataFrame:
    """(start, id, component) of the components inside each window of (start, src, dst): one run for all windows.

    Ids become (window, id) pairs, so no component spans two windows and none is solved alone.
    """
    pair = lambda c: F.struct("start", F.col(c).alias("id"))
    g = Graph(normalize_edges(edges.select(pair("src").alias("src"), pair("dst").alias("dst"))))
    return min_owner(g).components.select("id.start", F.col("id.id").alias("id"), F.col("component.id").alias("component"))


_OPEN = T.StructType([T.StructField("last_id", T.LongType()), T.StructField("last_at", T.DoubleType()), T.StructField("n", T.LongType())])
_LINK = T.StructType([T.StructField("part", T.LongType()), T.StructField("src", T.LongType()), T.StructField("dst", T.LongType())])


def open_chain(stream: DataFrame, id_col: str, part: str, ts: str, max_gap: float) -> DataFrame:
    """Edges between consecutive events of a part within ``max_gap`` seconds; the open end of each chain is kept as state."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        last, at, n = state.get if state.exists else (None, 0.0, 0)
        rows = pd.concat(list(frames)).sort_values(["at", "id"], kind="stable")
        out = []
        for i, t in zip(rows["id"], rows["at"], strict=True):
            if last is not None and t - at <= max_gap:
                out.append((int(key[0]), int(last), int(i)))
            last, at, n = int(i), float(t), n + 1
        state.update((last, at, n))
        yield pd.DataFrame(out, columns=_LINK.names)

    rows = stream.select(F.col(part).cast("long").alias("part"), F.col(id_col).cast("long").alias("id"), (F.unix_micros(F.col(ts).cast("timestamp")) / 1e6).alias("at"))
    return rows.groupBy("part").applyInPandasWithState(step, _LINK, _OPEN, "append", GroupStateTimeout.NoTimeout)


def distinct_edges(stream: DataFrame, ts: str, late: str = "1 hour") -> DataFrame:
    """Each edge once within the watermark."""
    return stream.withWatermark(ts, late).dropDuplicatesWithinWatermark(["src", "dst"])


def drain(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a stream over what there is now and return its output as a frame (an in-memory sink: for results of a bounded size)."""
    query = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    return stream.sparkSession.table(name)
