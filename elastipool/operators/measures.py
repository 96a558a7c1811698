"""Accuracy, latency, queue, pool, cost and efficiency measures of finished runs; each is keyed by run_id.

Quotients are rounded to 6 places and are quotients of integers, so other engines can repeat them.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from elastipool.model import N_MARKS
from elastipool.operators.queueing import as_of, depth_changes, marks


def _ratio(a: Column, b: Column, scale: int = 1) -> Column:
    return F.round(a * float(scale) / b, 6)


def accuracy(pred: DataFrame) -> DataFrame:
    """pred: run_id, y, y_hat. Failed rows carry an error label, so they count as wrong."""
    hit = F.sum(F.when(F.col("y") == F.col("y_hat"), 1).otherwise(0)).cast("long")
    return pred.groupBy("run_id").agg(F.count("*").alias("n"), hit.alias("correct")).withColumn("accuracy", _ratio(F.col("correct"), F.col("n")))


def per_class(pred: DataFrame) -> DataFrame:
    hit = F.sum(F.when(F.col("y") == F.col("y_hat"), 1).otherwise(0)).cast("long")
    return pred.groupBy("run_id", "y").agg(F.count("*").alias("n"), hit.alias("correct")).withColumn("accuracy", _ratio(F.col("correct"), F.col("n")))


def recall(pred: DataFrame, positive: str) -> DataFrame:
    return per_class(pred).where(F.col("y") == positive).select("run_id", F.col("accuracy").alias("recall"), "n", "correct")


def confusion(pred: DataFrame) -> DataFrame:
    return pred.groupBy("run_id", "y", "y_hat").agg(F.count("*").alias("n"))


def precision_f1(pred: DataFrame) -> DataFrame:
    """Per class: precision, recall and F1; 0 where a class is never predicted."""
    c = confusion(pred)
    tp = c.where("y = y_hat").select("run_id", "y", F.col("n").alias("tp"))
    said = c.groupBy("run_id", F.col("y_hat").alias("y")).agg(F.sum("n").alias("said"))
    real = c.groupBy("run_id", "y").agg(F.sum("n").alias("is"))
    j = real.join(said, ["run_id", "y"], "left").join(tp, ["run_id", "y"], "left")
    tp_, said_ = F.coalesce("tp", F.lit(0)), F.coalesce("said", F.lit(0))
    return j.select("run_id", "y", F.when(said_ > 0, _ratio(tp_, said_)).otherwise(0.0).alias("precision"), _ratio(tp_, F.col("is")).alias("recall"), _ratio(tp_ * 2, said_ + F.col("is")).alias("f1"))


def invariance(a: DataFrame, b: DataFrame) -> DataFrame:
    """Number of tasks whose prediction differs between two policies of one classifier; it must be 0."""
    j = a.select("task_id", F.col("y_hat").alias("a")).join(b.select("task_id", F.col("y_hat").alias("b")), "task_id", "full")
    return j.agg(F.sum(F.when(F.col("a").eqNullSafe(F.col("b")), 0).otherwise(1)).cast("long").alias("differing"), F.count("*").alias("tasks"))


def runtime(results: DataFrame) -> DataFrame:
    return results.groupBy("run_id").agg(F.count("*").alias("n"), (F.max("finish_ms") - F.min("enq_ms")).alias("runtime_ms"))


def latency(results: DataFrame) -> DataFrame:
    """Service, wait and sojourn: means, median and 95th percentile by linear interpolation, maximum."""
    p = lambda c, q: F.round(F.percentile(c, F.lit(q)), 6)
    return results.groupBy("run_id").agg(
        F.count("*").alias("n"), _ratio(F.sum("svc_ms"), F.count("*")).alias("svc_mean"), p("svc_ms", 0.95).alias("svc_p95"), _ratio(F.sum("wait_ms"), F.count("*")).alias("wait_mean"), p("wait_ms", 0.95).alias("wait_p95"),
        _ratio(F.sum("sojourn_ms"), F.count("*")).alias("sojourn_mean"), p("sojourn_ms", 0.5).alias("sojourn_p50"), p("sojourn_ms", 0.95).alias("sojourn_p95"), F.max("sojourn_ms").alias("sojourn_max"),
    )


def mark_of(results: DataFrame, n: int = N_MARKS) -> DataFrame:
    """``mark`` of each completion: mark m covers ((m - 1) R / n, m R / n] of a run of length R."""
    r = results.groupBy("run_id").agg(F.max("finish_ms").alias("r"))
    m = F.greatest(F.ceil(F.col("finish_ms") * n / F.col("r")), F.lit(1)).cast("int")
    return results.join(F.broadcast(r), "run_id").withColumn("mark", m).drop("r")


def latency_trace(results: DataFrame, n: int = N_MARKS) -> DataFrame:
    return mark_of(results, n).groupBy("run_id", "mark").agg(F.count("*").alias("n"), _ratio(F.sum("sojourn_ms"), F.count("*")).alias("sojourn_mean"))


def throughput_trace(results: DataFrame, n: int = N_MARKS) -> DataFrame:
    """Completions a minute at each mark, marks without completions included."""
    grid = marks(results, n).select("run_id", "mark")
    r = results.groupBy("run_id").agg(F.max("finish_ms").alias("r"))
    c = mark_of(results, n).groupBy("run_id", "mark").agg(F.count("*").alias("done"))
    j = grid.join(c, ["run_id", "mark"], "left").join(F.broadcast(r), "run_id")
    done = F.coalesce("done", F.lit(0))
    return j.select("run_id", "mark", done.cast("long").alias("done"), _ratio(done * 60_000 * n, F.col("r")).alias("per_minute"))


def queue_trace(results: DataFrame, n: int = N_MARKS) -> DataFrame:
    return as_of(marks(results, n), depth_changes(results), "q").select("run_id", "mark", "t_ms", "q")


def worker_trace(results: DataFrame, polls: DataFrame, n: int = N_MARKS, n_fixed: DataFrame | None = None) -> DataFrame:
    """Pool size at each mark: the last poll's, the first poll's n_before ahead of it; pools without polls are of fixed size (run_id, n)."""
    first = polls.where("j = 1").select("run_id", F.lit(-1).cast("long").alias("t_ms"), F.col("n_before").cast("long").alias("n"))
    steps = first.union(polls.select("run_id", "t_ms", F.col("n_after").cast("long")))
    if n_fixed is not None:
        steps = steps.union(n_fixed.select("run_id", F.lit(-1).cast("long"), F.col("n").cast("long")))
    return as_of(marks(results, n), steps, "n").select("run_id", "mark", "t_ms", "n")


def busy_changes(results: DataFrame) -> DataFrame:
    """(run_id, t_ms, busy): workers that serve after all changes of a millisecond."""
    ch = results.select("run_id", F.col("start_ms").alias("t_ms"), F.lit(1).alias("d")).union(results.select("run_id", "finish_ms", F.lit(-1)))
    ch = ch.groupBy("run_id", "t_ms").agg(F.sum("d").alias("d"))
    return ch.withColumn("busy", F.sum("d").over(Window.partitionBy("run_id").orderBy("t_ms"))).select("run_id", "t_ms", "busy")


def utilisation_trace(results: DataFrame, polls: DataFrame, n_fixed: DataFrame | None = None, n: int = N_MARKS) -> DataFrame:
    """Busy share of the pool at each mark, per mille."""
    busy = as_of(marks(results, n), busy_changes(results), "busy")
    j = busy.join(worker_trace(results, polls, n, n_fixed).select("run_id", "mark", F.col("n").alias("pool")), ["run_id", "mark"])
    return j.select("run_id", "mark", "t_ms", "busy", F.floor(F.col("busy") * 1000 / F.col("pool")).cast("long").alias("util_pm"))


def outcome_counts(grid: DataFrame, outcomes: DataFrame) -> DataFrame:
    """Completed and failed tasks up to each time of ``grid`` (run_id, t_ms, ...), from outcomes (run_id, finish_ms, ok)."""
    ch = outcomes.groupBy("run_id", F.col("finish_ms").alias("t_ms")).agg(F.count("*").alias("c"), F.sum(F.when(F.col("ok"), 0).otherwise(1)).alias("f"))
    w = Window.partitionBy("run_id").orderBy("t_ms")
    steps = ch.select("run_id", "t_ms", F.sum("c").over(w).alias("done"), F.sum("f").over(w).alias("failed"))
    return as_of(as_of(grid, steps, "done"), steps, "failed")


def fault_score(outcomes: DataFrame, faulty: Column) -> DataFrame:
    """Of the rows that were not made to fail, the share that completed without an error, by run; failures come from the outcomes."""
    fine = F.sum(F.when(faulty, 0).otherwise(1)).cast("long")
    kept = F.sum(F.when(~faulty & F.col("ok") & F.col("finish_ms").isNotNull(), 1).otherwise(0)).cast("long")
    return outcomes.groupBy("run_id").agg(fine.alias("fine"), kept.alias("unharmed"), F.sum(F.when(F.col("ok"), 0).otherwise(1)).cast("long").alias("failed"))


def class_line(pred: DataFrame) -> DataFrame:
    """(run_id, per_class): accuracy of each class, as one text a run."""
    c = per_class(pred).select("run_id", F.concat_ws("=", "y", F.format_number("accuracy", 4)).alias("v"))
    return c.groupBy("run_id").agg(F.array_join(F.array_sort(F.collect_list("v")), " ").alias("per_class"))

def queue_summary(results: DataFrame) -> DataFrame:
    """Peak depth, its mean over the run, and the time from the last arrival until the queue is empty for good."""
    d = depth_changes(results)
    nxt = F.lead("t_ms").over(Window.partitionBy("run_id").orderBy("t_ms"))
    area = d.withColumn("dt", F.coalesce(nxt - F.col("t_ms"), F.lit(0))).groupBy("run_id").agg(F.max("q").alias("peak"), F.sum(F.col("q") * F.col("dt")).alias("area"))
    ends = results.groupBy("run_id").agg((F.max("start_ms") - F.max("enq_ms")).alias("drain_ms"), (F.max("finish_ms") - F.min("enq_ms")).alias("runtime_ms"))
    return area.join(ends, "run_id").select("run_id", "peak", F.greatest("drain_ms", F.lit(0)).alias("drain_ms"), _ratio(F.col("area"), F.col("runtime_ms")).alias("mean_depth"))


def seconds(results: DataFrame, polls: DataFrame, n_fixed: DataFrame | None = None) -> DataFrame:
    """Worker, busy and idle milliseconds from 0 to the last completion; pools without polls are of fixed size (run_id, n)."""
    end = results.groupBy("run_id").agg(F.max("finish_ms").alias("end"), F.sum("svc_ms").alias("busy_ms"))
    first = polls.where("j = 1").select("run_id", F.lit(0).cast("long").alias("t_ms"), F.col("n_before").alias("n"))
    steps = first.union(polls.where("delta <> 0").select("run_id", "t_ms", "n_after"))
    if n_fixed is not None:
        steps = steps.union(n_fixed.select("run_id", F.lit(0).cast("long"), "n"))
    j = steps.join(F.broadcast(end), "run_id").where("t_ms < end")
    nxt = F.coalesce(F.lead("t_ms").over(Window.partitionBy("run_id").orderBy("t_ms")), F.col("end"))
    w = j.withColumn("w", F.col("n") * (nxt - F.col("t_ms"))).groupBy("run_id").agg(F.sum("w").alias("worker_ms"))
    return w.join(end, "run_id").select("run_id", "worker_ms", "busy_ms", (F.col("worker_ms") - F.col("busy_ms")).alias("idle_ms"), _ratio(F.col("busy_ms"), F.col("worker_ms")).alias("utilisation"))


def oscillations(events: DataFrame, within_ms: int) -> DataFrame:
    """Scale events, the sum of their sizes, and changes of direction within a time."""
    w = Window.partitionBy("run_id").orderBy("t_ms")
    turn = (F.signum("delta") != F.signum(F.lag("delta").over(w))) & (F.col("t_ms") - F.lag("t_ms").over(w) <= within_ms)
    return events.withColumn("turn", turn).groupBy("run_id").agg(F.count("*").alias("events"), F.sum(F.abs("delta")).cast("long").alias("moved"), F.sum(F.when(F.col("turn"), 1).otherwise(0)).cast("long").alias("turns"))


def reaction(results: DataFrame, events: DataFrame, n_max: int) -> DataFrame:
    """From the first arrival to the first scale-out, and to the full pool."""
    first = results.groupBy("run_id").agg(F.min("enq_ms").alias("t0"))
    e = events.groupBy("run_id").agg(F.min(F.when(F.col("delta") > 0, F.col("t_ms"))).alias("out"), F.min(F.when(F.col("n_after") == n_max, F.col("t_ms"))).alias("full"))
    return first.join(e, "run_id", "left").select("run_id", (F.col("out") - F.col("t0")).alias("first_out_ms"), (F.col("full") - F.col("t0")).alias("full_ms"))


def priority_wait(results: DataFrame) -> DataFrame:
    return results.groupBy("run_id", "prio").agg(F.count("*").alias("n"), _ratio(F.sum("wait_ms"), F.count("*")).alias("wait_mean"), F.max("wait_ms").alias("wait_max"))


def inversions(results: DataFrame, slice_ms: int = 60_000) -> DataFrame:
    """Tasks that started while one of a better priority had waited since before them in another shard: counted by start order. The best task that starts later is
    the better of the best in the rest of the same time slice and the best of all later slices, so no task holds a run: rows are windowed slice by slice, and only
    one row a slice is windowed over a run."""
    r = results.withColumn("slice", F.floor(F.col("start_ms") / slice_ms)).withColumn("own", F.struct("prio", "enq_ms"))
    # from the end backwards, since a frame that reaches to the end is summed up anew for every row
    rest = Window.partitionBy("run_id", "slice").orderBy(F.desc("start_ms"), F.desc("shard"), F.desc("seq")).rowsBetween(Window.unboundedPreceding, -1)
    after = Window.partitionBy("run_id").orderBy(F.desc("slice")).rowsBetween(Window.unboundedPreceding, -1)
    slices = r.groupBy("run_id", "slice").agg(F.min("own").alias("least")).select("run_id", "slice", F.min("least").over(after).alias("beyond"))
    best = F.least(F.col("within"), F.col("beyond"))
    late = r.withColumn("within", F.min("own").over(rest)).join(slices, ["run_id", "slice"]).withColumn("best", best)
    hit = (F.col("best.prio") < F.col("prio")) & (F.col("best.enq_ms") <= F.col("start_ms"))
    return late.groupBy("run_id").agg(F.sum(F.when(hit, 1).otherwise(0)).cast("long").alias("inversions"), F.count("*").alias("n"))


def report(results: DataFrame, pred: DataFrame, work: DataFrame) -> DataFrame:
    """One row a run: accuracy, runtime, latency, throughput, cost, and accuracy points a minute."""
    j = accuracy(pred).drop("n").join(runtime(results), "run_id").join(latency(results).select("run_id", "wait_mean", "sojourn_mean", "sojourn_p95"), "run_id").join(work.select("run_id", "worker_ms", "utilisation"), "run_id")
    return j.withColumn("per_minute", _ratio(F.col("n") * 60_000, F.col("runtime_ms"))).withColumn("efficiency", _ratio(F.col("correct") * 100 * 60_000, F.col("n") * F.col("runtime_ms")))


def six_scores(reports: DataFrame, faults: DataFrame, burst: DataFrame) -> DataFrame:
    """Scores from 0 to 100 in a comparison set: throughput and cost against the best, latency against the least p95, utilisation, rows unharmed by faults, and how
    far the burst was kept up with."""
    all_ = Window.partitionBy(F.lit(1))
    r = reports.withColumn("cost", F.col("correct") / F.col("worker_ms"))
    r = r.withColumn("throughput", F.round(100 * F.col("per_minute") / F.max("per_minute").over(all_), 4)).withColumn("latency", F.round(100 * F.min("sojourn_p95").over(all_) / F.col("sojourn_p95"), 4)).withColumn("cost_score", F.round(100 * F.col("cost") / F.max("cost").over(all_), 4))
    j = r.join(faults, "run_id").join(burst, "run_id")
    return j.select("run_id", "throughput", "latency", F.round(100 * F.col("utilisation"), 4).alias("resource"), F.round(100.0 * F.col("unharmed") / F.col("fine"), 4).alias("fault"), F.round(100 * F.least(F.lit(1.0), F.col("served") / F.col("arrived")), 4).alias("scalability"), "cost_score")


def burst_kept(results: DataFrame, burst_ms: int) -> DataFrame:
    """Arrivals and completions inside the burst."""
    return results.groupBy("run_id").agg(F.sum(F.when(F.col("enq_ms") < burst_ms, 1).otherwise(0)).cast("long").alias("arrived"), F.sum(F.when(F.col("finish_ms") < burst_ms, 1).otherwise(0)).cast("long").alias("served"))
