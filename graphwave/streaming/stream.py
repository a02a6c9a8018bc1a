"""Edge streams: windowed counts, chains, duplicates, late data, and upkeep of a directory by micro-batches.

Every streaming operator has a batch twin with the same columns; a run over all of a finite input with availableNow must return the
twin's rows.
"""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.directory import needs_counts
from ..operators.layout import GraphLayout, build
from ..operators.traverse import bfs
from ..plans.lineage import delete, shared_dir
from ..sources.graphs import Tuples

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def stream_events(spark: SparkSession, sf_dir: str, files_per_trigger: int = 1) -> DataFrame:
    """The events table as a stream, with `at` as event time."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(f"{sf_dir}/events.parquet*")  # a file or a folder of files
    return raw.withColumn("at", F.col("ts").cast("timestamp"))


def batch_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.schema(EVENTS).parquet(f"{sf_dir}/events.parquet").withColumn("at", F.col("ts").cast("timestamp"))


def tumbling(events: DataFrame, width: str = "1 hour") -> DataFrame:
    """(user_id, start, n): events of a user in each window."""
    rows = events.withWatermark("at", "1 hour") if events.isStreaming else events
    out = rows.groupBy("user_id", F.window("at", width).alias("w")).agg(F.count("*").alias("n"))
    return out.select("user_id", F.unix_seconds(F.col("w.start")).alias("start"), "n")


def sliding(events: DataFrame, width: str = "2 hours", step: str = "1 hour") -> DataFrame:
    """(start, users): how many users are active in each sliding window, by an exact set of (user, window) pairs."""
    rows = events.withWatermark("at", "1 hour") if events.isStreaming else events
    pairs = rows.groupBy(F.window("at", width, step).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return pairs.select(F.unix_seconds(F.col("w.start")).alias("start"), "user_id", "n")


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    """(user_id, start, n): sessions of a user, ended by a gap."""
    rows = events.withWatermark("at", "1 hour") if events.isStreaming else events
    out = rows.groupBy("user_id", F.session_window("at", gap).alias("w")).agg(F.count("*").alias("n"))
    return out.select("user_id", F.unix_seconds(F.col("w.start")).alias("start"), "n")


def distinct_edges(events: DataFrame, within: str | None = None) -> DataFrame:
    """(u, v) of user and key once each. A stream keeps the pairs it has seen as state; within: only duplicates so close in event time
    are dropped, and the state stays bounded."""
    edges = events.select("at", F.col("user_id").alias("u"), F.get_json_object("props", "$.k").cast("long").alias("v"))
    if events.isStreaming and within is not None:
        return edges.withWatermark("at", within).dropDuplicatesWithinWatermark(["u", "v"]).select("u", "v")
    return edges.select("u", "v").dropDuplicates(["u", "v"])


def chain_edges(events: DataFrame) -> DataFrame:
    """(u, v) from each event to the next of its user; the last event of a user is kept as state between micro-batches. Events must
    arrive in order of time within a user."""

    def step(key, frames, state: GroupState):
        rows = pd.concat(list(frames))[["at", "event_id"]].sort_values(["at", "event_id"])
        ids = rows["event_id"].tolist()
        if state.exists:
            ids = [state.get[0], *ids]
        state.update((int(ids[-1]),))
        yield pd.DataFrame({"u": ids[:-1], "v": ids[1:]})

    return events.select("user_id", "at", "event_id").groupBy("user_id").applyInPandasWithState(step, "u long, v long", "last long", "append", GroupStateTimeout.NoTimeout)


def enriched(events: DataFrame, users: DataFrame) -> DataFrame:
    """(event_id, vid): a stream meets the static dictionary of vertices."""
    return events.join(users, "user_id").select("event_id", "vid")


def co_activity(events: DataFrame, seconds: int = 600) -> DataFrame:
    """(a, b): events of one user at most `seconds` apart, a before b, as a join of the stream with itself bounded by watermarks."""
    mark = (lambda x: x.withWatermark(x.columns[1], "1 hour")) if events.isStreaming else (lambda x: x)
    left = mark(events.select(F.col("event_id").alias("a"), F.col("at").alias("ta"), F.col("user_id").alias("ua")))
    right = mark(events.select(F.col("event_id").alias("b"), F.col("at").alias("tb"), F.col("user_id").alias("ub")))
    on = (F.col("ua") == F.col("ub")) & (F.col("tb") > F.col("ta")) & (F.col("tb") <= F.col("ta") + F.expr(f"interval {seconds} seconds"))
    return left.join(right, on).select("a", "b")


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream over all that is there and returns what it wrote, as a written table."""
    spark = stream.sparkSession
    folder = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    if mode == "append":
        query = stream.writeStream.format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    else:
        def write(batch: DataFrame, batch_id: int) -> None:  # the last complete result replaces the others
            batch.write.mode("overwrite").parquet(f"{folder}/out")

        query = stream.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{folder}/out")


def late_rows(stream: DataFrame) -> tuple[DataFrame, int]:
    """What a stateful stream wrote, and how many rows came too late for its watermark."""
    spark = stream.sparkSession
    folder = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    query = stream.writeStream.format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    late = sum(op.numRowsDroppedByWatermark for p in query.recentProgress for op in p.stateOperators)
    return spark.read.schema(stream.schema).parquet(f"{folder}/out"), late


class Written:
    """Tables of micro-batches under one folder, told by batch id. A batch that is repeated replaces its own table, so nothing is taken
    twice, and a restarted driver finds all that was written whole."""

    def __init__(self, spark: SparkSession, folder: str, schema: str):
        self.spark, self.folder, self.schema = spark, folder, schema

    def write(self, rows: DataFrame, batch_id: int) -> None:
        rows.write.mode("overwrite").parquet(f"{self.folder}/batch={batch_id}")

    def ids(self) -> list[int]:
        """Batches whose writing was completed."""
        jvm = self.spark._jvm
        root = jvm.org.apache.hadoop.fs.Path(self.folder)
        files = root.getFileSystem(self.spark._jsc.hadoopConfiguration())
        if not files.exists(root):
            return []
        found = [x.getPath() for x in files.listStatus(root)]
        return sorted(int(x.getName().split("=")[1]) for x in found if files.exists(jvm.org.apache.hadoop.fs.Path(x, "_SUCCESS")))

    def read(self, ids: list[int]) -> DataFrame:
        if not ids:
            return self.spark.createDataFrame([], self.schema)
        return self.spark.read.schema(self.schema).parquet(*[f"{self.folder}/batch={i}" for i in ids])

    def drop(self, ids: list[int]) -> None:
        for i in ids:
            delete(self.spark, f"{self.folder}/batch={i}")


class DirectoryKeeper:
    """A directory that follows an edge stream. A micro-batch writes only what it changes; every FOLD batches the changes are folded into
    one table. All state is in the folder, so a keeper that is made anew over it goes on where the last one ended."""

    FOLD = 16

    def __init__(self, g: GraphLayout, folder: str | None = None):
        self.graph, self.folder = g, folder or f"{shared_dir(g.spark)}/keeper-{uuid.uuid4().hex}"
        schema = "needer_block long, owner_block long, slot long, edges long"
        self.changes, self.base = Written(g.spark, f"{self.folder}/changes", schema), Written(g.spark, f"{self.folder}/base", schema)

    def counts(self, before: int | None = None) -> DataFrame:
        """(needer_block, owner_block, slot, edges) of all batches, or of those before one."""
        old = lambda ids: [i for i in ids if before is None or i < before]
        base = old(self.base.ids())[-1:]
        late = [i for i in old(self.changes.ids()) if not base or i > base[0]]
        rows = self.base.read(base).unionByName(self.changes.read(late))
        return rows.groupBy("needer_block", "owner_block", "slot").agg(F.sum("edges").alias("edges")).where("edges > 0")

    def apply(self, batch: DataFrame, batch_id: int) -> None:
        both = batch.select(F.col("u").alias("src"), F.col("v").alias("dst")).unionByName(batch.select(F.col("v").alias("src"), F.col("u").alias("dst")))
        self.changes.write(needs_counts(self.graph, both), batch_id)
        if batch_id % self.FOLD == self.FOLD - 1:
            self.base.write(self.counts(batch_id + 1), batch_id)
            self.changes.drop([i for i in self.changes.ids() if i < batch_id])  # this batch may be repeated
            self.base.drop([i for i in self.base.ids() if i < batch_id - self.FOLD])

    def follow(self, edges: DataFrame) -> DataFrame:
        query = edges.writeStream.foreachBatch(self.apply).option("checkpointLocation", f"{self.folder}/state").trigger(availableNow=True).start()
        query.awaitTermination()
        return self.counts().select("needer_block", "owner_block", "slot")


class SearchKeeper:
    """Searches again after each micro-batch, over all edges written so far, and writes each search's tree by batch id."""

    def __init__(self, n: int, p: int, source: int, spark: SparkSession, folder: str | None = None, method: str = "relational"):
        self.n, self.p, self.source, self.method = n, p, source, method
        self.folder = folder or f"{shared_dir(spark)}/searches-{uuid.uuid4().hex}"
        self.edges, self.trees = Written(spark, f"{self.folder}/edges", "u long, v long"), Written(spark, f"{self.folder}/trees", "vid long, level long, parent long")

    def apply(self, batch: DataFrame, batch_id: int) -> None:
        self.edges.write(batch.select("u", "v"), batch_id)
        g = build(Tuples(self.edges.read([i for i in self.edges.ids() if i <= batch_id]), self.n, self.source), self.p)
        self.trees.write(bfs(g, method=self.method).tree, batch_id)
        g.release()

    def follow(self, edges: DataFrame) -> DataFrame:
        """(vid, level, parent) of the search after the last batch."""
        query = edges.writeStream.foreachBatch(self.apply).option("checkpointLocation", f"{self.folder}/state").trigger(availableNow=True).start()
        query.awaitTermination()
        return self.trees.read(self.trees.ids()[-1:])
