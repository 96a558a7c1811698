"""The elastic queue as a discrete-event run over narrow task rows: tasks stream through it in order of arrival, one (run, shard) after another.

A controller is sequential by nature, so runs and shards are what Spark spreads; text never comes here. A run holds the tasks that wait, packed, and nothing else of its
shard. Rows of two kinds leave: results (one a task) and polls (one a control instant), which are told apart by ``kind``; write the frame once before reading both.
"""

from __future__ import annotations

import heapq
import struct
from collections.abc import Iterable, Iterator
from itertools import groupby
from operator import itemgetter

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from elastipool.functions.control import step
from elastipool.model import NEVER, RunConfig
from elastipool.session import ship

RESULT = "run_id string, shard int, task_id long, seq long, prio int, enq_ms long, svc_ms long, start_ms long, finish_ms long, worker_id int"
POLL = "j int, t_ms long, q long, busy int, n_before int, delta int, n_after int, done long, t_last_ms long"
SCHEMA = f"kind string, {RESULT}, {POLL}"
_TYPES = {"string": pa.string(), "int": pa.int32(), "long": pa.int64()}
_ARROW = pa.schema([(name, _TYPES[kind]) for name, kind in (x.split() for x in SCHEMA.split(", "))])
_TASK = ("run_id", "shard", "enq_ms", "seq", "prio", "svc_ms", "task_id")
#: Rows of a batch that leaves.
_BATCH = 10_000

#: A waiting task (prio, seq, svc, enq, task) as bytes that sort as the numbers do: a fifth of the memory of a tuple.
_WAITING, _SIGN = struct.Struct(">5Q"), 1 << 63
_LAST = (1 << 63) - 1


def served(tasks: Iterable[tuple[int, int, int, int, int]], cfg) -> Iterator[tuple]:
    """tasks (enq, seq, prio, svc, task) in order of (enq, seq) -> in order of time, ("result", task, seq, prio, enq, svc, start, finish, worker) and
    ("poll", j, t, q, busy, n, delta, n_after, done, t_last). A task without priority comes last."""
    idle = list(range(1, cfg.n_init + 1))
    running: list[tuple[int, int]] = []  # (finish, worker)
    leaving: set[int] = set()  # busy workers that go after their task and no longer count
    waking: list[tuple[int, int]] = []  # (ready, worker) of workers that are still starting
    queue: list[bytes] = []
    n, next_id, t_last, came, done, j, last, seen = cfg.n_init, cfg.n_init + 1, NEVER, 0, 0, 1, 0, None
    tasks = iter(tasks)
    coming = next(tasks, None)
    far = float("inf")
    while True:
        ended = coming is None and done == came
        poll = j * cfg.poll_ms if cfg.poll_ms and cfg.autoscale else far
        if ended and (poll == far or (seen is not None and seen >= last + cfg.tail_ms) or came == 0):
            return
        arrive = coming[0] if coming is not None else far
        finish = running[0][0] if running else far
        wake = waking[0][0] if waking else far
        t = min(arrive, finish, wake, poll)
        if finish == t:
            worker = heapq.heappop(running)[1]
            if worker in leaving:
                leaving.remove(worker)
            else:
                heapq.heappush(idle, worker)
            done, last = done + 1, t
        elif wake == t:
            heapq.heappush(idle, heapq.heappop(waking)[1])
        elif arrive == t:
            enq, seq, prio, svc, task = coming
            heapq.heappush(queue, _WAITING.pack((_LAST if prio is None else prio) + _SIGN, seq + _SIGN, svc + _SIGN, enq + _SIGN, task + _SIGN))
            came, coming = came + 1, next(tasks, None)
        else:
            q, busy = len(queue), len(running) - len(leaving)
            d = step(q, busy, n, t, t_last, cfg)
            after = n + d
            for _ in range(d):
                heapq.heappush(waking, (t + cfg.spinup_ms, next_id)) if cfg.spinup_ms else heapq.heappush(idle, next_id)
                next_id += 1
            for _ in range(-d):
                pool = idle or [w for _, w in waking]
                if not pool:
                    leaving.add(max(w for _, w in running if w not in leaving))
                    continue
                gone = max(pool)
                idle = [w for w in idle if w != gone]
                waking = [x for x in waking if x[1] != gone]
                heapq.heapify(idle)
                heapq.heapify(waking)
            if d:
                t_last = t
            yield "poll", j, t, q, busy, n, d, after, done, t_last
            n, j, seen = after, j + 1, t
        while idle and queue:
            prio, seq, svc, enq, task = (x - _SIGN for x in _WAITING.unpack(heapq.heappop(queue)))
            w = heapq.heappop(idle)
            yield "result", task, seq, None if prio == _LAST else prio, enq, svc, t, t + svc, w
            heapq.heappush(running, (t + svc, w))


def run_queue(tasks: list[tuple[int, int, int, int]], cfg) -> tuple[dict[int, tuple[int, int, int]], list[tuple]]:
    """tasks (seq, prio, enq, svc) in order of arrival -> {seq: (start, finish, worker)}, polls as (j, t, q, busy, n, delta, n_after, done, t_last)."""
    out: dict[int, tuple[int, int, int]] = {}
    polls: list[tuple] = []
    for kind, *row in served(((enq, seq, prio, svc, 0) for seq, prio, enq, svc in tasks), cfg):
        if kind == "poll":
            polls.append(tuple(row))
        else:
            out[row[1]] = tuple(row[5:])
    return out, polls


def _batch(kind: str, run: str, shard: int, rows: list[tuple]) -> pa.RecordBatch:
    """Rows of one kind and (run, shard); the other kind's columns are null."""
    names = [x.split()[0] for x in (POLL if kind == "poll" else RESULT).split(", ")]
    got = dict(zip(names if kind == "poll" else names[2:], zip(*rows))) | {c: [v] * len(rows) for c, v in (("kind", kind), ("run_id", run), ("shard", shard))}
    return pa.RecordBatch.from_arrays([pa.array(got[f.name], f.type) if f.name in got else pa.nulls(len(rows), f.type) for f in _ARROW], schema=_ARROW)


def _run(configs: dict[str, RunConfig]):
    """A map over task rows sorted by (run, shard, arrival, sequence)."""

    def rows(batches):
        for b in batches:
            yield from zip(*(c.to_pylist() for c in b.columns))

    def run(batches):
        for (name, shard), group in groupby(rows(batches), key=itemgetter(0, 1)):
            held: dict[str, list[tuple]] = {"result": [], "poll": []}
            for kind, *row in served((r[2:] for r in group), configs[name]):
                held[kind].append(row)
                if len(held[kind]) == _BATCH:
                    yield _batch(kind, name, shard, held[kind])
                    held[kind] = []
            yield from (_batch(kind, name, shard, some) for kind, some in held.items() if some)

    return run


def config_frame(spark: SparkSession, configs: list[RunConfig]) -> DataFrame:
    """One row a configuration; it is small by construction and is broadcast."""
    rows = [c.as_row() for c in configs]
    df = spark.createDataFrame(pd.DataFrame(rows))
    for k, v in rows[0].items():
        df = df.withColumn(k, F.col(k).cast("boolean" if isinstance(v, bool) else "string" if isinstance(v, str) else "long"))
    return df.select("run_id", *[F.col(c).alias(f"cfg_{c}") for c in df.columns if c not in ("run_id", "lat_window")])


def simulate(tasks: DataFrame, configs: list[RunConfig]) -> DataFrame:
    """Every task under every configuration, tagged by kind. ``tasks``: shard, task_id, seq, prio, enq_ms, svc_ms. Arrivals may be out of sequence order (random or
    re-timed ones): they are served by time, then sequence."""
    ship(tasks.sparkSession)
    runs = F.explode(F.array(*(F.lit(c.run_id) for c in configs)))
    t = tasks.select(runs.alias("run_id"), *_TASK[1:])
    return t.repartition("run_id", "shard").sortWithinPartitions("run_id", "shard", "enq_ms", "seq").mapInArrow(_run({c.run_id: c for c in configs}), SCHEMA)


def results(sim: DataFrame) -> DataFrame:
    """Task rows with waits and sojourns."""
    r = sim.where("kind = 'result'").select(*[x.split()[0] for x in RESULT.split(", ")])
    return r.withColumn("wait_ms", F.col("start_ms") - F.col("enq_ms")).withColumn("sojourn_ms", F.col("finish_ms") - F.col("enq_ms"))


def polls(sim: DataFrame) -> DataFrame:
    p = sim.where("kind = 'poll'").select("run_id", "shard", *[x.split()[0] for x in POLL.split(", ")])
    return p.withColumn("util_pm", F.floor(F.col("busy") * 1000 / F.col("n_before")).cast("int"))


def scale_events(sim: DataFrame) -> DataFrame:
    return polls(sim).where("delta <> 0").select("run_id", "shard", "j", "t_ms", "q", "busy", "n_before", "delta", "n_after")
