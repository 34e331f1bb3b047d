"""Windowed graphs over a stream of events, and counts that are kept up to date with it."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from huecount.functions.coloring import Coloring
from huecount.operators.graph import DataGraph, simple_edges
from huecount.operators.solve import count_colorful
from huecount.plans.query import QueryGraph
from huecount.session import fresh_dir, remove

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
LATE = "1 hour"


def event_stream(spark: SparkSession, sf_dir: str, files_per_trigger: int = 8) -> DataFrame:
    """Events as a file stream, with a time zone on their timestamps."""
    reader = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger)
    path = spark._jvm.org.apache.hadoop.fs.Path(f"{sf_dir}/events.parquet")
    whole = path.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(path)
    if whole.isDirectory():
        rows = reader.parquet(f"{sf_dir}/events.parquet")
    else:  # the folder may hold other tables: only the events file is taken
        rows = reader.option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def window_column(kind: str):
    if kind == "tumbling":
        return F.window("ts", "1 day")
    if kind == "sliding":
        return F.window("ts", "1 day", "12 hours")
    if kind == "session":
        return F.session_window("ts", "30 minutes")
    raise ValueError(f"no window {kind!r}")


def windowed_edges(events: DataFrame, kind: str) -> DataFrame:
    """win_start, win_end, user_id, event_type, n: the edges of each window's user-type graph. Works on batches
    and, with a watermark, on streams."""
    e = events.withWatermark("ts", LATE) if events.isStreaming else events
    w = window_column(kind)
    grouped = e.groupBy(w.alias("w"), "user_id", "event_type").agg(F.count("*").alias("n"))
    return grouped.select(F.col("w.start").alias("win_start"), F.col("w.end").alias("win_end"), "user_id", "event_type", "n")


def deduplicated(events: DataFrame) -> DataFrame:
    return events.withWatermark("ts", LATE).dropDuplicatesWithinWatermark(["event_id"])


class _Sink:
    """What a stream gives, in the shared folder, never on the driver. A batch overwrites the folder of its own number, so a repeated
    batch changes nothing; in complete mode the last batch is the whole result, and those before it go."""

    def __init__(self, stream: DataFrame, mode: str):
        self.stream, self.mode, self.last = stream, mode, None
        self.folder = fresh_dir(stream.sparkSession, "sink")

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{self.folder}/rows/sink_batch={batch_id}")
        if self.mode == "complete" and self.last not in (None, batch_id):
            remove(self.stream.sparkSession, f"{self.folder}/rows/sink_batch={self.last}")
        self.last = batch_id

    def drive(self) -> StreamingQuery:
        query = self.stream.writeStream.foreachBatch(self).outputMode(self.mode).option("checkpointLocation", f"{self.folder}/log").trigger(availableNow=True).start()
        query.awaitTermination()
        return query

    def rows(self) -> DataFrame:
        spark, schema = self.stream.sparkSession, self.stream.schema
        if self.last is None:
            return spark.createDataFrame([], schema)
        return spark.read.schema(schema).parquet(f"{self.folder}/rows").select(*schema.names)


def run_to_table(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Drive a finite stream to its end and return what it has given."""
    sink = _Sink(stream, mode)
    sink.drive()
    return sink.rows()


def run_to_parquet(stream: DataFrame, path: str, checkpoint: str) -> None:
    """Append to Parquet exactly once: the sink's log and the checkpoint agree on batches."""
    query = stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start()
    query.awaitTermination()


def run_and_count_late(stream: DataFrame, mode: str = "append") -> tuple[DataFrame, int]:
    """Drive a finite stream to its end; return what the sink holds, and how many rows came too late for a
    watermark (of rows that are summed in groups, as many as a batch makes of them)."""
    sink = _Sink(stream, mode)
    query = sink.drive()
    late = sum(o["numRowsDroppedByWatermark"] for p in query.recentProgress for o in p["stateOperators"])
    return sink.rows(), late


def by_nation(events: DataFrame, customers: DataFrame) -> DataFrame:
    """win_start, win_end, nation, n: events of each day by their user's nation. Repeated events go, each event meets the
    static table of customers, and windows are counted: two steps with state in a row, hence append mode on a stream,
    which gives a window when the watermark has passed it."""
    once = deduplicated(events) if events.isStreaming else events.dropDuplicates(["event_id"])
    met = once.join(customers.select(F.col("c_custkey").alias("user_id"), F.col("c_nationkey").alias("nation")), "user_id")
    grouped = met.groupBy(F.window("ts", "1 day").alias("w"), "nation").agg(F.count("*").alias("n"))
    return grouped.select(F.col("w.start").alias("win_start"), F.col("w.end").alias("win_end"), "nation", "n")


def active_pairs(events: DataFrame, minutes: int = 10) -> DataFrame:
    """Stream-stream interval join: users active within some minutes of each other. Slots of that length are a second join key: an
    event meets those of its own slot and of the next one only, not all of its type."""
    slot = lambda ts: F.floor(F.unix_micros(ts) / (minutes * 60_000_000))
    a = events.select(F.col("ts").alias("ts_a"), F.col("user_id").alias("src"), F.col("event_type")).withWatermark("ts_a", LATE)
    b = events.select(F.col("ts").alias("ts_b"), F.col("user_id").alias("dst"), F.col("event_type").alias("type_b")).withWatermark("ts_b", LATE)
    a = a.withColumn("slot", F.explode(F.array(slot("ts_a"), slot("ts_a") + 1)))
    b = b.withColumn("slot_b", slot("ts_b"))
    near = F.expr(f"slot = slot_b AND ts_b > ts_a AND ts_b <= ts_a + interval {minutes} minutes AND event_type = type_b AND src <> dst")
    return a.join(b, near).select("ts_a", "ts_b", "src", "dst")


class WindowedWedges:
    """Wedges of every day's user-type graph, updated batch by batch. A batch's edges overwrite the folder of
    its own number, so a repeated batch changes nothing; counts are read from all batches."""

    def __init__(self, spark: SparkSession, folder: str | None = None):
        self.spark = spark
        self.folder = folder or fresh_dir(spark, "wedges")

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        edges = batch.select(F.to_date("ts").alias("day"), "user_id", "event_type").distinct()
        edges.write.mode("overwrite").parquet(f"{self.folder}/batch={batch_id}")

    def drive(self, events: DataFrame) -> DataFrame:
        events.writeStream.foreachBatch(self).option("checkpointLocation", f"{self.folder}-log").trigger(availableNow=True).start().awaitTermination()
        return self.counts()

    def counts(self) -> DataFrame:
        edges = self.spark.read.parquet(self.folder).select("day", "user_id", "event_type").distinct()
        pairs = lambda by: edges.groupBy("day", by).count().select("day", (F.col("count") * (F.col("count") - 1) / 2).alias("w"))
        return pairs("user_id").union(pairs("event_type")).groupBy("day").agg(F.sum("w").cast("long").alias("wedges"))


class FourCycles:
    """Exact four-cycles of every day's user-type graph, kept up to date. A batch adds, for each day and pair of types, the
    users that come to have both: pairs of its new edges with each other and with older edges of the same
    user. Both are written under the batch's number, so a repeated batch changes nothing."""

    def __init__(self, spark: SparkSession, folder: str | None = None):
        self.spark = spark
        self.folder = folder or fresh_dir(spark, "four-cycles")

    def _older(self, what: str, schema: str, batch_id: int) -> DataFrame:
        return self.spark.read.schema(f"{schema}, batch long").option("basePath", f"{self.folder}/{what}").parquet(f"{self.folder}/{what}").where(F.col("batch") < batch_id).drop("batch")

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        schema, path = "day date, user_id long, event_type string", f"{self.folder}/edges/batch={batch_id}"
        edges = batch.select(F.to_date("ts").alias("day"), "user_id", "event_type").where("user_id is not null and event_type is not null").distinct()
        if batch_id > 0:
            edges = edges.join(self._older("edges", schema, batch_id), ["day", "user_id", "event_type"], "left_anti")
        edges.write.mode("overwrite").parquet(path)
        new = self.spark.read.schema(schema).parquet(path)
        either = new.withColumn("new", F.lit(1))
        if batch_id > 0:
            either = either.union(self._older("edges", schema, batch_id).withColumn("new", F.lit(0)))
        a = either.select("day", "user_id", F.col("event_type").alias("a"), F.col("new").alias("new_a"))
        b = either.select("day", "user_id", F.col("event_type").alias("b"), F.col("new").alias("new_b"))
        pairs = a.join(b, ["day", "user_id"]).where("a < b and new_a + new_b > 0")
        pairs.groupBy("day", "a", "b").agg(F.count("*").alias("users")).write.mode("overwrite").parquet(f"{self.folder}/common/batch={batch_id}")

    def drive(self, events: DataFrame) -> DataFrame:
        events.writeStream.foreachBatch(self).option("checkpointLocation", f"{self.folder}/log").trigger(availableNow=True).start().awaitTermination()
        return self.counts()

    def counts(self) -> DataFrame:
        """day, cnt."""
        common = self._older("common", "day date, a string, b string, users long", 1 << 62).groupBy("day", "a", "b").agg(F.sum("users").alias("c"))
        return common.groupBy("day").agg(F.sum(F.col("c") * (F.col("c") - 1) / 2).cast("long").alias("cnt"))


class WindowedMotifs:
    """Colourful counts of a query in every day's user-type graph. A batch adds its edges under its own number, and
    the days it touches are counted anew into folders of their own: rows are keyed by (day, trial), and a repeated batch
    changes nothing."""

    def __init__(self, spark: SparkSession, query: QueryGraph, trials: int = 3, folder: str | None = None):
        self.spark, self.query, self.trials = spark, query, trials
        self.folder = folder or fresh_dir(spark, "motifs")

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        pairs = batch.where("event_type is not null").select(F.to_date("ts").alias("day"), (F.col("user_id") * 2).alias("src"), (F.pmod(F.xxhash64("event_type"), F.lit(1 << 38)) * 2 + 1).alias("dst"))
        pairs.where("src is not null").distinct().write.mode("overwrite").parquet(f"{self.folder}/edges/batch={batch_id}")
        every = self.spark.read.schema("day date, src long, dst long, batch long").parquet(f"{self.folder}/edges").where(F.col("batch") <= batch_id)
        days = [r[0] for r in batch.select(F.to_date("ts").alias("day")).distinct().collect()]  # the days of one batch
        for day in days:
            g = DataGraph(str(day), simple_edges(every.where(F.col("day") == day).select("src", "dst")), bipartite=True)
            count_colorful(g, self.query, Coloring(self.query.k, trials=self.trials)).write.mode("overwrite").parquet(f"{self.folder}/counts/day={day}")

    def drive(self, events: DataFrame) -> DataFrame:
        events.writeStream.foreachBatch(self).option("checkpointLocation", f"{self.folder}/log").trigger(availableNow=True).start().awaitTermination()
        return self.counts()

    def counts(self) -> DataFrame:
        """day, trial, cnt."""
        return self.spark.read.schema("trial int, cnt long, day date").parquet(f"{self.folder}/counts").select("day", "trial", "cnt")


def stateful_degrees(events: DataFrame, idle_ms: int | None = None) -> DataFrame:
    """user_id, degree, seen: how many event types each user has met so far. idle_ms: forget a user after so
    long without events; a stream with such timers runs on until it is stopped."""

    def update(key, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        types, seen = state.get if state.exists else ("", 0)
        known = set(filter(None, types.split(",")))
        for b in batches:
            known.update(b["event_type"].dropna())
            seen += len(b)
        state.update((",".join(sorted(known)), seen))
        if idle_ms is not None:
            state.setTimeoutDuration(idle_ms)
        yield pd.DataFrame({"user_id": [key[0]], "degree": [len(known)], "seen": [seen]})

    return events.groupBy("user_id").applyInPandasWithState(update, "user_id long, degree long, seen long", "types string, seen long", "update", "NoTimeout" if idle_ms is None else "ProcessingTimeTimeout")
