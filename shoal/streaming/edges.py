"""Structured Streaming around the methods: windowed activity, incremental graphs and labels."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from shoal.core.graph import Graph
from shoal.core.storage import Scratch, shared_folder
from shoal.operators.propagation import propagate_labels


def _timed(events: DataFrame) -> DataFrame:
    """Watermarks need a timestamp with time zone."""
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def stream_activity(events: DataFrame, window: str = "1 hour", slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    """(start, event_type, user_id, n) per window: the small per-window state that edges are paired from."""
    span = F.window("ts", window, slide) if slide else F.window("ts", window)
    return _timed(events).withWatermark("ts", late).groupBy(span.alias("win"), "event_type", "user_id").agg(F.count("*").alias("n")).select(F.col("win.start").alias("start"), "event_type", "user_id", "n")


def stream_sessions(events: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    """(user_id, start, stop, n) of each user's sessions."""
    return _timed(events).withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("s"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("s.start").alias("start"), F.col("s.end").alias("stop"), "n")


def read_stream(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    reader = spark.readStream.schema(spark.read.parquet(path).schema).option("maxFilesPerTrigger", files_per_batch)
    place = spark._jvm.org.apache.hadoop.fs.Path(path)
    if place.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(place).isDirectory():
        return reader.parquet(path)
    folder, _, name = path.rpartition("/")  # file streams watch folders
    return reader.option("pathGlobFilter", name).parquet(folder)


def user_state(events: DataFrame) -> DataFrame:
    """(user_id, n, last_event, last_type) of each user that a micro-batch touches: events so far, and the newest by time, then id.

    The state is one small row a user, whatever the order of the events; `latest` keeps the last row of each."""

    def update(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, *newest = state.get if state.exists else (0, None, None, None)
        for rows in frames:
            n += len(rows)
            top = rows.sort_values(["us", "event_id"]).iloc[-1]
            if newest[0] is None or (top["us"], top["event_id"]) > (newest[0], newest[1]):
                newest = [int(top["us"]), int(top["event_id"]), top["event_type"]]
        state.update((n, *newest))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "last_event": [newest[1]], "last_type": [newest[2]]})

    rows = _timed(events).select("user_id", "event_id", "event_type", F.unix_micros("ts").alias("us")).where("us IS NOT NULL AND event_id IS NOT NULL")
    held = "n long, us long, last_event long, last_type string"
    return rows.groupBy("user_id").applyInPandasWithState(update, "user_id long, n long, last_event long, last_type string", held, "append", GroupStateTimeout.NoTimeout)


def latest(states: DataFrame) -> DataFrame:
    """The last state of each user; the count of events only grows."""
    return states.groupBy("user_id").agg(F.max(F.struct("n", "last_event", "last_type")).alias("s")).select("user_id", "s.n", "s.last_event", "s.last_type")


def late_rows(query: StreamingQuery) -> int:
    """Rows that came too late for a query's state, over the micro-batches whose progress Spark still holds. Aggregates count them after their partial sums."""
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])


def drain(stream: DataFrame, name: str, log: dict[str, int] | None = None) -> DataFrame:
    """Runs a stream over all there is and returns what it wrote (append mode into the shared folder); puts late_rows into `log`."""
    folder = shared_folder(stream.sparkSession, name)
    query = stream.writeStream.format("parquet").outputMode("append").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    if log is not None:
        log["late_rows"] = late_rows(query)
    return stream.sparkSession.read.schema(stream.schema).parquet(f"{folder}/out")


class IncrementalCommunities:
    """Keeps a graph and its communities as tables while micro-batches of edges come in: new and changed edges'
    ends wake, everyone else sleeps, and a few rounds of label propagation follow."""

    def __init__(self, spark: SparkSession, max_rounds: int = 10) -> None:
        self.spark, self.max_rounds, self.scratch = spark, max_rounds, Scratch(spark, "incremental")
        self.graph: Graph | None = None
        self.labels: DataFrame | None = None

    def add(self, edges: DataFrame, batch_id: int = 0) -> DataFrame:
        fresh = Graph.of(edges)
        whole = fresh if self.graph is None else Graph.of(self.graph.edges.union(fresh.edges), self.graph.nodes.union(fresh.nodes))
        old = self.graph, self.labels
        self.graph = Graph(self.scratch.write(whole.edges), self.scratch.write(whole.nodes))
        start = self.graph.nodes.select("id", F.col("id").alias("comm")) if self.labels is None else self.graph.nodes.join(self.labels, "id", "left").select("id", F.coalesce("comm", "id").alias("comm"))
        touched = self.scratch.write(fresh.nodes)
        found = propagate_labels(self.graph, start=self.scratch.write(start), active=touched, max_rounds=self.max_rounds)
        self.labels = self.scratch.write(found)
        if old[0] is not None:
            self.scratch.drop(old[0].edges, old[0].nodes, old[1])
        return self.labels

    def follow(self, stream: DataFrame):
        """A started query that feeds each micro-batch (u, v, w) in."""
        return stream.writeStream.foreachBatch(lambda df, i: self.add(df, i)).option("checkpointLocation", shared_folder(self.spark, "follow")).trigger(availableNow=True).start()
