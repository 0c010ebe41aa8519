"""Streams around filters: look-ups on a stream, running in-degrees, a feed of updates, late rows, last values, keys to come."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from contextlib import contextmanager
from dataclasses import replace

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from keyloom.operators.lookup import Filter, lookup
from keyloom.operators.mutable import update_values
from keyloom.plans import store
from keyloom.plans.scratch import folders, is_folder, remove_at_exit


def events_stream(spark: SparkSession, path: str, schema=None, per_trigger: int | None = None) -> DataFrame:
    """A Parquet folder or file as a stream; ``ts`` as a timestamp, as watermarks refuse those without a zone."""
    reader = spark.readStream.schema(schema or spark.read.parquet(path).schema)
    if per_trigger:
        reader = reader.option("maxFilesPerTrigger", per_trigger)
    folder, _, name = path.rpartition("/")
    rows = reader.parquet(path) if is_folder(spark, path) else reader.option("pathGlobFilter", name).parquet(folder)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def enrich(stream: DataFrame, filter: Filter, key, out: str = "value") -> DataFrame:
    """Stateless: each row of the stream with its key's value. The filter is broadcast, which a look-up refuses above its limit."""
    return lookup(stream, filter, key, out, strategy="broadcast")


def indegree(stream: DataFrame, key: str, window: str = "1 day", slide: str | None = None, watermark: str = "2 days", session_gap: str | None = None, distinct_within: list[str] | None = None) -> DataFrame:
    """(window_start, key, n): counts over tumbling, sliding or session windows of event time."""
    rows = stream.withWatermark("ts", watermark)
    if distinct_within:
        rows = rows.dropDuplicatesWithinWatermark(distinct_within)
    w = F.session_window("ts", session_gap) if session_gap else F.window("ts", window, slide) if slide else F.window("ts", window)
    return rows.groupBy(w.alias("w"), key).agg(F.count("*").alias("n")).select(F.col("w.start").alias("window_start"), key, "n")


def sliding(panes: DataFrame, key: str, window: str, slide: str) -> DataFrame:
    """(window_start, key, n) over sliding windows, out of the whole counts over tumbling windows of ``slide``: a stream then holds a count for each of those, not for each window that one is in.

    The counts are dealt by key and go to their windows there.
    """
    whole, part = (pd.Timedelta(x) // pd.Timedelta("1 us") for x in (window, slide))
    if whole % part:
        raise ValueError(f"{window} is no multiple of {slide}")
    at = F.unix_micros("window_start")
    rows = panes.repartition(key).select(F.explode(F.sequence(at - F.lit(whole - part), at, F.lit(part))).alias("at"), key, "n")
    return rows.groupBy("at", key).agg(F.sum("n").alias("n")).select(F.timestamp_micros("at").alias("window_start"), key, "n")


def interval_join(left: DataFrame, right: DataFrame, key: str, bound: str = "1 hour", watermark: str = "2 hours") -> DataFrame:
    """Pairs of one key whose times are at most ``bound`` apart. The right side's columns get the prefix r_."""
    a = left.withWatermark("ts", watermark)
    b = right.select(*[F.col(c).alias(f"r_{c}") for c in right.columns]).withWatermark("r_ts", watermark)
    near = F.expr(f"{key} = r_{key} AND r_ts >= ts - interval {bound} AND r_ts <= ts + interval {bound}")
    return a.join(b, near)


_STORE = "spark.sql.streaming.stateStore"
#: A stream's state is kept in files beside a memory of a bounded size, not as objects in the heap, which all windows together fill.
STATE = {
    f"{_STORE}.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider",
    f"{_STORE}.rocksdb.boundedMemoryUsage": "true",
    f"{_STORE}.rocksdb.maxMemoryUsageMB": "256",
    f"{_STORE}.rocksdb.trackTotalNumberOfRows": "false",
}


@contextmanager
def state_in_files(spark: SparkSession) -> Iterator[None]:
    """Streams that start meanwhile keep their state as STATE says."""
    before = {c: spark.conf.get(c, None) for c in STATE}
    for c, x in STATE.items():
        spark.conf.set(c, x)
    try:
        yield
    finally:
        for c, x in before.items():
            spark.conf.unset(c) if x is None else spark.conf.set(c, x)


def run_once(stream: DataFrame, name: str, checkpoint: str, mode: str = "complete") -> DataFrame:
    """Runs what is there now into Parquet beside the checkpoint and gives that: of ``complete`` the last micro-batch, of other modes all.

    Executors write the rows, none pass through the driver; state is kept in files. A micro-batch that comes again overwrites its own folder.
    """
    spark, out = stream.sparkSession, f"{checkpoint.rstrip('/')}-rows"
    remove_at_exit(spark, out)
    put = lambda batch, nth: batch.write.mode("overwrite").parquet(f"{out}/batch={nth}")
    with state_in_files(spark):
        stream.writeStream.foreachBatch(put).queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    batches = sorted(folders(spark, out), key=lambda b: int(b.partition("=")[2]))
    if not batches:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(*(f"{out}/{b}" for b in (batches[-1:] if mode == "complete" else batches)))


class UpdateFeed:
    """Micro-batches of (key, value, order) applied to a mutable filter. A batch that comes again changes nothing: the filter carries the number of the last one.

    With ``path`` each state is saved there, filter and edges, before the batch counts as done; ``resume`` goes on from the last complete one.
    """

    def __init__(self, filter: Filter, graph: DataFrame, key, value: str = "value", order: str | None = None, mode: str = "recompute", path: str | None = None):
        self.filter, self.graph, self.key, self.value, self.order, self.mode, self.path = filter, graph, key, value, order, mode, path

    @property
    def last_batch(self) -> int:
        return self.filter.batch

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id <= self.filter.batch:
            return
        changed, graph, _ = update_values(self.filter, self.graph, batch, self.key, self.value, mode=self.mode, order=self.order)
        changed = replace(changed, batch=batch_id)
        if self.path:
            where = f"{self.path}/batch={batch_id}"
            graph.write.mode("overwrite").parquet(f"{where}/edges")
            store.save(changed, where)  # its manifest, written last, makes the state complete
            spark = graph.sparkSession
            changed, graph = store.load(spark, where), spark.read.parquet(f"{where}/edges")
        self.filter, self.graph = changed, graph

    @classmethod
    def resume(cls, spark: SparkSession, path: str, key, value: str = "value", order: str | None = None, mode: str = "recompute") -> UpdateFeed:
        """The feed after the last batch that was saved whole."""
        states = sorted((r["batch"] for r in spark.read.parquet(f"{path}/batch=*/manifest").select("batch").distinct().collect()), reverse=True)  # a number for each saved batch
        where = f"{path}/batch={states[0]}"
        return cls(store.load(spark, where), spark.read.parquet(f"{where}/edges"), key, value, order, mode, path)


def apply_updates(stream: DataFrame, feed: Callable[[DataFrame, int], None], checkpoint: str) -> None:
    stream.writeStream.foreachBatch(feed).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def latest_value(stream: DataFrame, key: str, value: str, ts: str = "ts") -> DataFrame:
    """(key, value, ts): the last value of each key so far, in state; output mode update."""
    from pyspark.sql.streaming import StatefulProcessor

    kind = dict(stream.dtypes)

    class Last(StatefulProcessor):
        def init(self, handle):
            self.state = handle.getValueState("last", f"v {kind[value]}, t timestamp")

        def handleInputRows(self, k, rows: Iterator[pd.DataFrame], timers):
            best = self.state.get() if self.state.exists() else None
            for part in rows:
                at = part[ts].idxmax()
                if best is None or part[ts][at] >= best[1]:
                    best = (part[value][at], part[ts][at])
            self.state.update(best)
            yield pd.DataFrame({key: [k[0]], value: [best[0]], ts: [best[1]]})

        def close(self):
            pass

    rows = stream.select(key, value, ts)
    return rows.groupBy(key).transformWithStateInPandas(Last(), f"{key} {kind[key]}, {value} {kind[value]}, {ts} timestamp", "Update", "None")


def late_report(progress: list[dict]) -> int:
    """Rows that watermarks dropped, from a query's ``recentProgress``."""
    return sum(s.get("numRowsDroppedByWatermark", 0) for p in progress for s in p.get("stateOperators", ()))


def pending_keys(stream: DataFrame, membership: Filter, key) -> DataFrame:
    """Rows whose key the set surely doesn't have yet: they wait for the next build."""
    return lookup(stream, membership, key, "_m", strategy="broadcast").where("_m is null").drop("_m")
