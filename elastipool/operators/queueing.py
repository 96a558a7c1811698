"""Queue order, closed forms and folds that need no Python: one server, equal service, first-in-first-out pools, fluid model, control replay, depth."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from elastipool.functions import control
from elastipool.model import NEVER, RunConfig


#: The fold's result grows by copying, so its cost is quadratic: longer shards go to the kernel.
FOLD_ROWS = 5000


def order(tasks: DataFrame) -> DataFrame:
    """Dispatch position when all tasks are present: (priority, sequence) inside a shard."""
    return tasks.withColumn("pos", F.row_number().over(Window.partitionBy("run_id", "shard").orderBy("prio", "seq")))


def sequential(tasks: DataFrame) -> DataFrame:
    """One server, first in first out: finish = running service + running maximum of (arrival - service before it)."""
    w = Window.partitionBy("run_id", "shard").orderBy("seq").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    t = tasks.withColumn("c", F.sum("svc_ms").over(w)).withColumn("lag", F.col("enq_ms") - (F.col("c") - F.col("svc_ms")))
    t = t.withColumn("finish_ms", F.col("c") + F.max("lag").over(w)).withColumn("start_ms", F.col("finish_ms") - F.col("svc_ms"))
    return _timed(t.withColumn("worker_id", F.lit(1)).drop("c", "lag"))


def fifo_equal(tasks: DataFrame, workers: int, svc_ms: int) -> DataFrame:
    """A pool of equal service times: task i goes to worker i mod w, so each residue is a single server."""
    t = tasks.withColumn("svc_ms", F.lit(svc_ms).cast("long")).withColumn("residue", (F.col("seq") % workers).cast("int"))
    w = Window.partitionBy("run_id", "shard", "residue").orderBy("seq").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    t = t.withColumn("c", F.sum("svc_ms").over(w)).withColumn("finish_ms", F.col("c") + F.max(F.col("enq_ms") - F.col("c") + F.col("svc_ms")).over(w))
    return _timed(t.withColumn("start_ms", F.col("finish_ms") - F.col("svc_ms")).withColumn("worker_id", F.col("residue") + 1).drop("c", "residue"))


def fifo_fold(tasks: DataFrame, workers: int) -> DataFrame:
    """A pool under first in first out as a fold over a shard's arrivals: the worker free first takes the next task. One array a shard of at most ``FOLD_ROWS`` tasks."""
    rows = F.array_sort(F.collect_list(F.struct("seq", "task_id", "prio", "enq_ms", "svc_ms")))
    start = F.struct(F.array_repeat(F.lit(0).cast("long"), workers).alias("free"), F.array().cast("array<struct<seq:bigint,task_id:bigint,prio:int,enq_ms:bigint,svc_ms:bigint,start_ms:bigint,worker_id:int>>").alias("out"))

    def take(acc, x):
        k = F.array_position(acc["free"], F.array_min(acc["free"])).cast("int")
        at = F.greatest(x["enq_ms"], F.array_min(acc["free"]))
        free = F.transform(acc["free"], lambda f, i: F.when(i == k - 1, at + x["svc_ms"]).otherwise(f))
        row = F.struct(x["seq"].alias("seq"), x["task_id"].alias("task_id"), x["prio"].alias("prio"), x["enq_ms"].alias("enq_ms"), x["svc_ms"].alias("svc_ms"), at.alias("start_ms"), k.alias("worker_id"))
        return F.struct(free.alias("free"), F.concat(acc["out"], F.array(row)).alias("out"))

    folded = tasks.groupBy("run_id", "shard").agg(F.aggregate(rows, start, take)["out"].alias("o"))
    t = folded.select("run_id", "shard", F.inline("o")).withColumn("finish_ms", F.col("start_ms") + F.col("svc_ms"))
    return _timed(t)


def _timed(t: DataFrame) -> DataFrame:
    return t.withColumn("wait_ms", F.col("start_ms") - F.col("enq_ms")).withColumn("sojourn_ms", F.col("finish_ms") - F.col("enq_ms"))


def choose(cfg: RunConfig, constant_service: bool, fifo: bool, rows_per_shard: int) -> str:
    """Which plan serves a configuration without the kernel, if any."""
    if cfg.autoscale or not fifo:
        return "kernel"
    if cfg.n_init == 1:
        return "sequential"
    if constant_service:
        return "fifo_equal"
    return "fifo_fold" if rows_per_shard <= FOLD_ROWS else "kernel"


def depth_changes(results: DataFrame) -> DataFrame:
    """(run_id, t_ms, q): the depth after all changes of a millisecond, by a running sum over +1 at arrival and -1 at start."""
    ch = results.select("run_id", F.col("enq_ms").alias("t_ms"), F.lit(1).alias("d")).union(results.select("run_id", "start_ms", F.lit(-1)))
    ch = ch.groupBy("run_id", "t_ms").agg(F.sum("d").alias("d"))
    return ch.withColumn("q", F.sum("d").over(Window.partitionBy("run_id").orderBy("t_ms"))).select("run_id", "t_ms", "q")


def as_of(grid: DataFrame, steps: DataFrame, value: str, default: int = 0) -> DataFrame:
    """The latest value of a step function at each grid time: a union and one running last, instead of a range join."""
    u = grid.select("run_id", "t_ms", F.lit(1).alias("g"), F.lit(None).cast("long").alias("v"), *[c for c in grid.columns if c not in ("run_id", "t_ms")])
    s = steps.select("run_id", "t_ms", F.lit(0).alias("g"), F.col(value).cast("long").alias("v"), *[F.lit(None).cast(grid.schema[c].dataType).alias(c) for c in grid.columns if c not in ("run_id", "t_ms")])
    w = Window.partitionBy("run_id").orderBy("t_ms", "g").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return s.unionByName(u).withColumn(value, F.coalesce(F.last("v", ignorenulls=True).over(w), F.lit(default)).cast("long")).where("g = 1").drop("g", "v")


def marks(results: DataFrame, n: int) -> DataFrame:
    """(run_id, mark, t_ms): right edges of n equal parts of each run."""
    r = results.groupBy("run_id").agg(F.max("finish_ms").alias("r"))
    return r.select("run_id", F.explode(F.sequence(F.lit(1), F.lit(n))).alias("mark"), "r").select("run_id", "mark", F.floor(F.col("mark") * F.col("r") / n).cast("long").alias("t_ms"))


def fluid(rates: DataFrame, cfg: RunConfig, per_worker: int, elastic: bool) -> DataFrame:
    """Bucket by bucket: served = min(queue + arrivals, n * per_worker); the rule sees the queue left and the share of capacity used."""
    rows = F.array_sort(F.collect_list(F.struct("b", "a")))
    start = F.struct(F.lit(0).cast("long").alias("q"), F.lit(cfg.n_init).cast("long").alias("n"), F.lit(NEVER).cast("long").alias("last"), F.array().cast("array<struct<b:bigint,a:bigint,served:bigint,q:bigint,n:bigint,delta:bigint>>").alias("out"))

    def take(acc, x):
        served = F.least(acc["q"] + x["a"], acc["n"] * per_worker)
        q = acc["q"] + x["a"] - served
        pm = F.floor(served * 1000 / (acc["n"] * per_worker)).cast("long")
        d = F.lit(0)
        if elastic:
            cool = (x["b"] - acc["last"]) >= cfg.cooldown_ms
            d = F.when(cool & ((q > cfg.queue_hi) | (pm > cfg.util_hi_pm)), F.least(F.lit(cfg.step), F.lit(cfg.n_max) - acc["n"])).when(cool & (q == 0) & (pm < cfg.util_lo_pm), -F.least(F.lit(cfg.step_down), acc["n"] - cfg.n_min)).otherwise(0)
        d = d.cast("long")
        row = F.struct(x["b"].alias("b"), x["a"].alias("a"), served.alias("served"), q.alias("q"), acc["n"].alias("n"), d.alias("delta"))
        return F.struct(q.alias("q"), (acc["n"] + d).alias("n"), F.when(d != 0, x["b"]).otherwise(acc["last"]).alias("last"), F.concat(acc["out"], F.array(row)).alias("out"))

    return rates.groupBy("run_id").agg(F.aggregate(rows, start, take)["out"].alias("o")).select("run_id", F.inline("o"))


def replay(series: DataFrame, cfg: RunConfig) -> DataFrame:
    """The rule over a recorded (t_ms, q, busy_pm) series, open loop, as a fold; the array holds one run's polls."""
    rows = F.array_sort(F.collect_list(F.struct("t_ms", "q", "busy")))
    start = F.struct(F.lit(cfg.n_init).cast("int").alias("n"), F.lit(NEVER).cast("long").alias("last"), F.array().cast("array<struct<t_ms:bigint,q:bigint,busy:int,n_before:int,delta:int,n_after:int>>").alias("out"))

    def take(acc, x):
        busy = F.least(x["busy"], acc["n"]).cast("int")
        d = control.delta(x["q"], busy, acc["n"], x["t_ms"], acc["last"], cfg)
        row = F.struct(x["t_ms"].alias("t_ms"), x["q"].alias("q"), busy.alias("busy"), acc["n"].alias("n_before"), d.alias("delta"), (acc["n"] + d).cast("int").alias("n_after"))
        return F.struct((acc["n"] + d).cast("int").alias("n"), F.when(d != 0, x["t_ms"]).otherwise(acc["last"]).alias("last"), F.concat(acc["out"], F.array(row)).alias("out"))

    return series.groupBy("run_id").agg(F.aggregate(rows, start, take)["out"].alias("o")).select("run_id", F.inline("o"))
