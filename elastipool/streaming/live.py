"""The live service on Structured Streaming: rates, latencies, sessions, and the elastic queue as a stateful processor or as waves of micro-batches.

:class:`QueueProcessor` replays the virtual clock of the batch kernel up to the watermark: arrivals are kept in state until then, timers are only wake-ups. So its results
equal the batch run on the same tasks. :func:`waves` is the other driver: each micro-batch serves as many tasks as the pool has slots and moves the pool by the rule.
"""

from __future__ import annotations

import heapq
import json
import uuid
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from elastipool.functions.control import step
from elastipool.model import NEVER, RunConfig
from elastipool.operators.workload import global_sequence
from elastipool.session import materialise, scratch_root, ship

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def events(spark: SparkSession, path: str, per_trigger: int = 1, schema: str = EVENTS) -> DataFrame:
    """The event table as a file stream; its time column becomes a timestamp for watermarks."""
    s = spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(path)
    return s.withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(stream: DataFrame, width: str = "1 hour", late: str = "1 hour") -> DataFrame:
    w = stream.withWatermark("ts", late).groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n"))
    return w.select(F.unix_seconds("window.start").alias("start"), "event_type", "n")


def sliding(stream: DataFrame, width: str = "2 hours", slide: str = "1 hour", late: str = "1 hour") -> DataFrame:
    w = stream.withWatermark("ts", late).groupBy(F.window("ts", width, slide)).agg(F.count("*").alias("n"), F.sum(F.floor("value")).cast("long").alias("value"))
    return w.select(F.unix_seconds("window.start").alias("start"), "n", "value")


def sessions(stream: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    w = stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
    return w.select("user_id", F.unix_seconds("session_window.start").alias("start"), "n")


def deduplicated(stream: DataFrame, late: str = "1 hour", key: str = "event_id") -> DataFrame:
    """One event of each key. State ends with the watermark, so a copy behind it is dropped as late; first copies have to come less than ``late`` out of order."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark([key]).select("event_id", "event_type")


@dataclass(frozen=True)
class Drained:
    """What a stream has written: its rows, and how many rows came too late."""

    rows: DataFrame
    late: int
    batches: int


def drain(df: DataFrame, mode: str = "append", folder: str | None = None) -> DataFrame:
    """Run a stream over what is there now and give what it wrote; see :func:`drained`."""
    return drained(df, mode, folder).rows


def drained(df: DataFrame, mode: str = "append", folder: str | None = None) -> Drained:
    """Run a stream over what is there now into Parquet, a folder for each micro-batch, and read that back: all batches in append mode, the last one in complete
    mode. A batch that is run again replaces its own folder, so results are there once. With a ``folder`` of an earlier run the stream goes on from its checkpoint."""
    spark = df.sparkSession
    folder = folder or f"{scratch_root(spark)}/drained-{uuid.uuid4().hex}"
    schema = df.schema

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/rows/batch={number}")

    q = df.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()
    late = sum(int(s["numRowsDroppedByWatermark"]) for p in q.recentProgress for s in p["stateOperators"])
    place = spark._jvm.org.apache.hadoop.fs.Path(f"{folder}/rows")
    files = place.getFileSystem(spark._jsc.hadoopConfiguration())
    numbers = sorted(int(f.getPath().getName().split("=")[1]) for f in files.listStatus(place)) if files.exists(place) else []
    if not numbers:
        return Drained(spark.createDataFrame([], schema), late, 0)
    of = numbers if mode == "append" else numbers[-1:]
    return Drained(spark.read.schema(schema).parquet(*[f"{folder}/rows/batch={k}" for k in of]), late, len(numbers))


def until_stopped(query, stop: Callable[[], bool], wait_s: float = 1.0) -> None:
    """Let a live query run until ``stop`` says so: it waits a bounded time, looks again, and never spins. What is under way is finished first."""
    while query.isActive and not stop():
        query.awaitTermination(wait_s)
    if query.isActive:
        query.processAllAvailable()
        query.stop()


class Clock:
    """State of one queue, advanced to any time; the same order of events as the batch kernel."""

    def __init__(self, cfg: RunConfig, saved: str | None = None):
        self.cfg = cfg
        if saved:
            self.__dict__ |= json.loads(saved)
            self.running = [tuple(x) for x in self.running]
            self.queue = [tuple(x) for x in self.queue]
            self.waiting = [tuple(x) for x in self.waiting]
        else:
            self.idle, self.running, self.queue, self.waiting = list(range(1, cfg.n_init + 1)), [], [], []
            self.n, self.next_id, self.t_last, self.done, self.j = cfg.n_init, cfg.n_init + 1, NEVER, 0, 1

    def saved(self) -> str:
        return json.dumps({k: v for k, v in self.__dict__.items() if k != "cfg"})

    def add(self, enq: int, seq: int, prio: int, svc: int, task: int) -> None:
        heapq.heappush(self.waiting, (enq, seq, prio, svc, task))

    def advance(self, until: int) -> list[tuple]:
        """Rows (task, seq, prio, enq, svc, start, finish, worker) of tasks started by events at or before ``until``."""
        out, far = [], float("inf")
        while True:
            finish = self.running[0][0] if self.running else far
            arrive = self.waiting[0][0] if self.waiting else far
            poll = self.j * self.cfg.poll_ms if self.cfg.autoscale else far
            # polls after all work is done and before the next arrival leave no trace but scale-in: they are replayed too
            t = min(finish, arrive, poll)
            if t > until or (finish == far and arrive == far):
                return out
            if finish == t:
                heapq.heappush(self.idle, heapq.heappop(self.running)[1])
                self.done += 1
            elif arrive == t:
                enq, seq, prio, svc, task = heapq.heappop(self.waiting)
                heapq.heappush(self.queue, (prio, seq, svc, enq, task))
            else:
                d = step(len(self.queue), len(self.running), self.n, t, self.t_last, self.cfg)
                for _ in range(d):
                    heapq.heappush(self.idle, self.next_id)
                    self.next_id += 1
                if d < 0:
                    self.idle = sorted(self.idle)[:d]
                self.n, self.t_last, self.j = self.n + d, t if d else self.t_last, self.j + 1
            while self.idle and self.queue:
                prio, seq, svc, enq, task = heapq.heappop(self.queue)
                w = heapq.heappop(self.idle)
                out.append((task, seq, prio, enq, svc, t, t + svc, w))
                heapq.heappush(self.running, (t + svc, w))


LIVE = "shard int, task_id long, seq long, prio int, enq_ms long, svc_ms long, start_ms long, finish_ms long, worker_id int"


def live_queue(tasks: DataFrame, cfg: RunConfig, late: str = "1 second") -> DataFrame:
    """Tasks (shard, task_id, seq, prio, enq_ms, svc_ms, ts) of a stream through the elastic queue; ``ts`` carries the watermark and is enq_ms as a timestamp.

    Each call replays the clock up to the watermark, which stays ``late`` behind the latest task; tasks behind it are dropped and counted (see :func:`drained`). A
    last row with seq < 0 (a sentinel far ahead) closes the stream.
    """

    def run(key, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        clock = Clock(cfg, state.get[0] if state.exists else None)
        for pdf in parts:
            for r in pdf.itertuples(index=False):
                if r.seq >= 0:
                    clock.add(int(r.enq_ms), int(r.seq), int(r.prio), int(r.svc_ms), int(r.task_id))
        mark = state.getCurrentWatermarkMs()
        rows = clock.advance(mark) if mark > 0 else []
        state.update((clock.saved(),))
        if clock.waiting or clock.running or clock.queue:
            state.setTimeoutTimestamp(max(mark, 0) + 1)
        yield pd.DataFrame([(int(key[0]), a, b, c, d, e, f, g, h) for a, b, c, d, e, f, g, h in rows], columns=[x.split()[0] for x in LIVE.split(", ")])

    return tasks.withWatermark("ts", late).groupBy("shard").applyInPandasWithState(run, LIVE, "clock string", "append", "EventTimeTimeout")


ROCKSDB = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def live_queue_timers(tasks: DataFrame, cfg: RunConfig, late: str = "1 second") -> DataFrame:
    """The same as :func:`live_queue` with state and timers of its own: a stateful processor over RocksDB, so state may outgrow memory. A timer at the next event
    wakes a queue that gets no more rows. Ships the package; the state store's provider is a runtime setting, set here."""
    from pyspark.sql.streaming import StatefulProcessor

    spark = tasks.sparkSession
    ship(spark)
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", ROCKSDB)
    names = [x.split()[0] for x in LIVE.split(", ")]

    class Processor(StatefulProcessor):
        def init(self, handle):
            self.handle = handle
            self.clock = handle.getValueState("clock", "saved string")

        def _advanced(self, key, rows, mark):
            clock = Clock(cfg, self.clock.get()[0] if self.clock.exists() else None)
            for pdf in rows:
                for r in pdf.itertuples(index=False):
                    if r.seq >= 0:
                        clock.add(int(r.enq_ms), int(r.seq), int(r.prio), int(r.svc_ms), int(r.task_id))
            done = clock.advance(mark) if mark > 0 else []
            self.clock.update((clock.saved(),))
            if clock.waiting or clock.running or clock.queue:
                self.handle.registerTimer(max(mark, 0) + 1)
            yield pd.DataFrame([(int(key[0]), *x) for x in done], columns=names)

        def handleInputRows(self, key, rows, timerValues):
            yield from self._advanced(key, rows, timerValues.getCurrentWatermarkInMs())

        def handleExpiredTimer(self, key, timerValues, expiredTimerInfo):
            yield from self._advanced(key, [], timerValues.getCurrentWatermarkInMs())

        def close(self):
            pass

    return tasks.withWatermark("ts", late).groupBy("shard").transformWithStateInPandas(Processor(), LIVE, "Append", "EventTime")


def waves(tasks: DataFrame, cfg: RunConfig, classify, sink: str, slots: int = 8) -> list[tuple[int, int, int]]:
    """Serve a table of pending tasks in waves, as micro-batches do: each takes the first n * slots by (prio, seq) on n partitions, writes them under its number, and moves the pool by the rule.

    Tasks are numbered in that order once, so a wave is a range of numbers: nothing is counted or joined again. A wave that is run again writes the same rows to the
    same place. Returns (wave, n, left); one row a wave reaches the driver.
    """
    order = global_sequence(tasks.withColumnRenamed("seq", "task_seq"), "prio", "task_seq")
    placed = materialise(order.withColumnRenamed("seq", "place").withColumnRenamed("task_seq", "seq"), "placed")
    left, at = placed.count(), 0
    log, n, t_last, wave = [], cfg.n_init, NEVER, 0
    while True:
        log.append((wave, n, left))
        if not left:
            return log
        took = min(left, n * slots)
        take = placed.where(F.col("place").between(at, at + took - 1)).drop("place")
        classify(take.repartition(n)).write.mode("overwrite").parquet(f"{sink}/wave={wave}")
        t = wave * cfg.poll_ms
        d = step(left - took, min(n, left), n, t, t_last, cfg)
        left, at = left - took, at + took
        n, t_last, wave = n + d, t if d else t_last, wave + 1
