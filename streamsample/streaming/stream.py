"""Structured Streaming: one threshold for all partitions between micro-batches, or a reservoir for each shard in the state store."""

from __future__ import annotations


from collections.abc import Callable, Iterator
from contextlib import contextmanager

import pandas as pd
from pyspark.sql import Column, DataFrame, Observation, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..model import SamplerSpec
from ..operators.reservoir import DecentralSampler, storage
from ..plans.batches import keyed


def table_stream(spark: SparkSession, sf_dir: str, table: str, files: int = 1) -> DataFrame:
    """A table's file, or folder of files, as a stream."""
    schema = spark.read.parquet(f"{sf_dir}/{table}.parquet").schema
    reader = spark.readStream.schema(schema).option("maxFilesPerTrigger", files).option("pathGlobFilter", f"{table}.parquet").option("recursiveFileLookup", "false")
    return reader.parquet(sf_dir)


def drain(stream: DataFrame, each: Callable[[DataFrame, int], None], checkpoint: str | None = None) -> None:
    """Hand every available micro-batch to ``each``, then stop."""
    checkpoint = checkpoint or storage(stream.sparkSession)
    query = stream.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()


class StreamSampler:
    """The decentralised sampler behind ``foreachBatch``. A micro-batch that comes again, with its number, changes nothing.

    ``path``: where state and runs lie; with the same path, and the stream's checkpoint in it, a query that was stopped or lost goes on where it ended.
    """

    def __init__(self, spark: SparkSession, spec: SamplerSpec, path: str | None = None):
        self.inner = DecentralSampler(spark, spec, path)

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        self.inner.process(batch, batch_id)

    def run(self, stream: DataFrame, checkpoint: str | None = None) -> DataFrame:
        drain(stream, self, checkpoint or f"{self.inner.path}/checkpoint")
        return self.inner.sample()


class WindowStore:
    """Per open window, the k smallest keys so far, kept as files that each micro-batch replaces; closed windows are written once.

    The watermark is the latest event time seen less the lateness, as it was before the micro-batch. Rows of windows that it has passed are dropped and counted.
    """

    def __init__(self, spark: SparkSession, spec: SamplerSpec, length: str, lateness: str):
        self.spark, self.spec, self.length, self.lateness = spark, spec, length, lateness
        self.schema = "window_start timestamp, window_end timestamp, item_id string, w double, key double"
        self.base, self.open, self.closed, self.done = storage(spark), None, [], -1
        self.latest, self.late = None, 0

    def _read(self, *paths: str) -> DataFrame:
        return self.spark.read.schema(self.schema).parquet(*paths) if paths else self.spark.createDataFrame([], self.schema)

    def held(self) -> DataFrame:
        """All windows, closed and open."""
        return self._read(*self.closed, *([self.open] if self.open else []))

    def _passed(self) -> Column:
        if self.latest is None:
            return F.lit(False)
        return F.col("window_end") <= F.lit(self.latest) - F.expr(f"INTERVAL {self.lateness}")

    def add(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id <= self.done:
            return
        span = F.window("ts", self.length)
        seen = Observation()
        rows = keyed(batch, self.spec, "ts").withColumn("window_start", span.getField("start")).withColumn("window_end", span.getField("end"))
        rows = rows.observe(seen, F.max("ts").alias("latest"), F.count_if(self._passed()).alias("late")).where(~self._passed())
        place = F.row_number().over(Window.partitionBy("window_start").orderBy("key", "item_id"))
        # the batch's side comes first: the plan runs in its session, where the observation listens
        now = rows.select("window_start", "window_end", "item_id", "w", "key").unionByName(self._read(*([self.open] if self.open else [])))
        path = f"{self.base}/v{batch_id}"
        now.withColumn("place", place).where(F.col("place") <= self.spec.k).drop("place").write.mode("overwrite").parquet(f"{path}/all")
        got = seen.get
        self.late += got["late"] or 0
        if got["latest"] is not None and (self.latest is None or got["latest"] > self.latest):
            self.latest = got["latest"]
        everything, self.open, self.done = self._read(f"{path}/all"), f"{path}/all", batch_id
        gone = everything.where(self._passed())
        if not gone.isEmpty():
            gone.write.mode("overwrite").parquet(f"{path}/closed")
            everything.where(~self._passed()).write.mode("overwrite").parquet(f"{path}/open")
            self.closed, self.open = [*self.closed, f"{path}/closed"], f"{path}/open"


def stream_window_sample(stream: DataFrame, spec: SamplerSpec, length: str, lateness: str = "1 day") -> DataFrame:
    """A sample of each tumbling window of event time; rows of windows that ended more than ``lateness`` before the latest event of earlier micro-batches are left out."""
    return stream_windows(stream, spec, length, lateness).held()


def stream_windows(stream: DataFrame, spec: SamplerSpec, length: str, lateness: str = "1 day") -> WindowStore:
    """The same, with the count of late rows and the closed windows."""
    store = WindowStore(stream.sparkSession, spec, length, lateness)
    drain(stream.withColumn("ts", F.col("ts").cast("timestamp")), store.add)
    return store


def to_memory(frame: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """What a streaming frame gives until it has read all there is, as a table in memory: for tests and small results."""
    query = frame.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", storage(frame.sparkSession)).trigger(availableNow=True).start()
    query.awaitTermination()
    return frame.sparkSession.table(name)


@contextmanager
def state_on_disk(spark: SparkSession) -> Iterator[None]:
    """Streams started within keep their state in RocksDB: on the disks of the executors, in bounded memory outside the heap."""
    head = "spark.sql.streaming.stateStore."
    new = {
        f"{head}providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider",
        f"{head}rocksdb.boundedMemoryUsage": "true",
        f"{head}rocksdb.maxMemoryUsageMB": "200",
    }
    old = {name: spark.conf.get(name, None) for name in new}
    for name, value in new.items():
        spark.conf.set(name, value)
    try:
        yield
    finally:
        for name, value in old.items():
            spark.conf.unset(name) if value is None else spark.conf.set(name, value)


def to_files(frame: DataFrame) -> DataFrame:
    """What a streaming frame appends until it has read all there is, as files: for results and state of any size."""
    spark, out = frame.sparkSession, storage(frame.sparkSession)
    with state_on_disk(spark):
        frame.writeStream.format("parquet").option("path", out).option("checkpointLocation", storage(spark)).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(frame.schema).parquet(out)


def event_time(stream: DataFrame, lateness: str) -> DataFrame:
    return stream.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", lateness)


def stream_sessions(stream: DataFrame, spec: SamplerSpec, user: str, gap: str = "30 minutes", lateness: str = "1 day") -> DataFrame:
    """A streaming frame (user, session_start, session_end, n, least): each session's k smallest (key, item). A session's keys lie in one state row, so sessions must be short."""
    rows = keyed(event_time(stream, lateness), spec, user, "ts")
    found = rows.groupBy(user, F.session_window("ts", gap).alias("session")).agg(F.count(F.lit(1)).alias("n"), F.sort_array(F.collect_list(F.struct("key", "item_id"))).alias("least"))
    return found.select(user, F.col("session.start").alias("session_start"), F.col("session.end").alias("session_end"), "n", F.slice("least", 1, spec.k).alias("least"))


class SessionStore:
    """All sessions so far, each with its k smallest keys, kept as files that each micro-batch replaces: whatever comes late still joins, or bridges, the sessions it belongs to.

    A session is k rows at most (user, session_start, session_end, n, key, item_id); the first has its count, the others 0. It ends where the gap passes without an event.
    """

    def __init__(self, spark: SparkSession, spec: SamplerSpec, user: str, gap: str = "30 minutes"):
        self.spark, self.spec, self.user, self.gap = spark, spec, user, gap
        self.base, self.rows, self.done = storage(spark), None, -1

    def add(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id <= self.done:
            return
        start, user = F.col("ts").cast("timestamp"), F.col(self.user)
        now = keyed(batch, self.spec, self.user, "ts").select(
            self.user, start.alias("session_start"), (start + F.expr(f"INTERVAL {self.gap}")).alias("session_end"), F.lit(1).cast("long").alias("n"), "key", "item_id"
        )
        if self.rows is not None:
            now = now.unionByName(self.spark.read.schema(now.schema).parquet(self.rows))
        by_time = Window.partitionBy(user).orderBy("session_start", "session_end")
        before = F.max("session_end").over(by_time.rowsBetween(Window.unboundedPreceding, -1))
        fresh = F.coalesce((F.col("session_start") >= before).cast("int"), F.lit(1))
        numbered = now.withColumn("fresh", fresh).withColumn("session", F.sum("fresh").over(by_time.rowsBetween(Window.unboundedPreceding, 0)))
        one = Window.partitionBy(user, "session")
        place = F.row_number().over(one.orderBy("key", "item_id"))
        merged = numbered.select(
            self.user, F.min("session_start").over(one).alias("session_start"), F.max("session_end").over(one).alias("session_end"), F.sum("n").over(one).alias("total"), "key", "item_id", place.alias("place")
        )
        path = f"{self.base}/v{batch_id}"
        kept = merged.where(F.col("place") <= self.spec.k).withColumn("n", F.when(F.col("place") == 1, F.col("total")).otherwise(0))
        kept.select(now.columns).write.mode("overwrite").parquet(path)
        self.rows, self.done, self.schema = path, batch_id, now.schema

    def held(self) -> DataFrame:
        """(user, session_start, session_end, n, least)."""
        rows = self.spark.read.schema(self.schema).parquet(self.rows)
        least = F.sort_array(F.collect_list(F.struct("key", "item_id")))
        return rows.groupBy(self.user, "session_start", "session_end").agg(F.sum("n").alias("n"), least.alias("least"))


def without_repeats(stream: DataFrame, cols: list[str], lateness: str) -> DataFrame:
    """Rows of an at-least-once source once each, within the watermark."""
    return event_time(stream, lateness).dropDuplicatesWithinWatermark(cols)


def session_sample(df: DataFrame, spec: SamplerSpec, user: str, gap_minutes: int) -> DataFrame:
    """A sample of each session: (user, session_no, item_id, w, key, draw_no). A session ends where a user is silent for longer than the gap."""
    rows = keyed(df.withColumn("ts", F.col("ts").cast("timestamp")), spec, user, "ts")
    by_time = Window.partitionBy(user).orderBy("ts", "item_id")
    second = F.rint(F.unix_micros("ts") / 1e6)  # times count to the nearest second
    quiet = second - F.lag(second).over(by_time)
    numbered = rows.withColumn("fresh", F.coalesce((quiet > gap_minutes * 60).cast("int"), F.lit(1))).withColumn("session_no", F.sum("fresh").over(by_time))
    place = F.row_number().over(Window.partitionBy(user, "session_no").orderBy("key", "item_id"))
    return numbered.withColumn("draw_no", place).where(F.col("draw_no") <= spec.k).select(user, "session_no", "item_id", "w", "key", "draw_no")


class ShardReservoir(StatefulProcessor):
    """A shard's k smallest keys and its own threshold, in the state store. The union of the shards holds the k smallest of all."""

    def __init__(self, k: int):
        self.k = k

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.run = handle.getListState("run", "item_id string, w double, key double")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        held = pd.DataFrame(list(self.run.get()), columns=["item_id", "w", "key"])
        limit = held["key"].max() if len(held) >= self.k else float("inf")
        new = [r.loc[r["key"] <= limit, ["item_id", "w", "key"]] for r in rows]
        every = pd.concat([x for x in (held, *new) if len(x)] or [held], ignore_index=True).sort_values(["key", "item_id"]).head(self.k)
        self.run.put(list(every.itertuples(index=False, name=None)))
        yield every.assign(shard=key[0])[["shard", "item_id", "w", "key"]]

    def close(self) -> None:
        pass


def stream_shard_sample(stream: DataFrame, spec: SamplerSpec, shards: int = 4) -> DataFrame:
    """The sample of a stream whose shards each keep a reservoir in state; merged when read. The store must be one with list state."""
    spark = stream.sparkSession
    out, check = storage(spark), storage(spark)
    name, old = "spark.sql.streaming.stateStore.providerClass", spark.conf.get("spark.sql.streaming.stateStore.providerClass")
    spark.conf.set(name, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        sharded = keyed(stream, spec).withColumn("shard", F.pmod(F.xxhash64("item_id"), F.lit(shards)).cast("int"))
        kept = sharded.groupBy("shard").transformWithStateInPandas(ShardReservoir(spec.k), "shard int, item_id string, w double, key double", "Update", "None")

        def keep(batch: DataFrame, batch_id: int) -> None:
            batch.withColumn("batch_id", F.lit(batch_id)).write.mode("overwrite").parquet(f"{out}/batch={batch_id}")

        kept.writeStream.foreachBatch(keep).outputMode("update").option("checkpointLocation", check).trigger(availableNow=True).start().awaitTermination()
    finally:
        spark.conf.set(name, old)
    rows = spark.read.schema("shard int, item_id string, w double, key double, batch_id int").parquet(f"{out}/batch=*")
    newest = rows.groupBy("shard").agg(F.max("batch_id").alias("batch_id"))
    return rows.join(newest, ["shard", "batch_id"]).orderBy("key", "item_id").limit(spec.k)


