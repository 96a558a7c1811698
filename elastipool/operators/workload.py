"""Stages 2 and 3: priorities, sequence numbers and arrival times of tasks.

Sequence numbers of small samples come from one window over at most N rows. :func:`global_sequence` numbers any table without a single task: range partitions,
counts per partition (broadcast: one row a partition), local numbers.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from elastipool.model import EVENT_PRIORITY, ROLES, SEED, ArrivalSpec
from elastipool.operators.sampling import key
from elastipool.session import materialise


def priority(kind: str) -> Column:
    """'source', 'label' (this leaks the label), 'event', 'role', 'order' or 'const'."""
    if kind == "source":
        return (F.regexp_extract("source", "([0-9]+)", 1).cast("int") % 3 + 1).cast("int")
    if kind == "label":
        return (F.ascii("y") % 3 + 1).cast("int")
    if kind == "event":
        out = F.lit(9)
        for name, p in EVENT_PRIORITY.items():
            out = F.when(F.col("event_type") == name, p).otherwise(out)
        return out.cast("int")
    if kind == "role":
        return F.when(F.col("role") == "user", 1).otherwise(2).cast("int")
    if kind == "order":
        return F.substring("o_orderpriority", 1, 1).cast("int")
    return F.lit(1).cast("int")


def burst_size(n: Column, spec: ArrivalSpec) -> Column:
    """Number of tasks in the burst: its share of the area under the rate curve, rounded."""
    b, s = spec.burst_pm * spec.ratio_tenths, (1000 - spec.burst_pm) * 10
    return _div(n * b + (b + s) // 2, F.lit(b + s))


def _div(a: Column, b: Column) -> Column:
    """Floor division of non-negative integers."""
    return F.floor((a - a % b) / b).cast("long")


def arrival(seq: Column, n: Column, spec: ArrivalSpec) -> Column:
    """Enqueue time of the 0-based ``seq`` of n tasks: evenly inside the burst and evenly after it."""
    nb, tb = burst_size(n, spec), spec.window_ms * spec.burst_pm // 1000
    seq = seq.cast("long")
    return F.when(seq < nb, _div(seq * tb, nb)).otherwise(tb + _div((seq - nb) * (spec.window_ms - tb), F.greatest(n - nb, F.lit(1)))).cast("long")


def service(role: str) -> Column:
    base, us = ROLES[role]
    return F.greatest(F.lit(base) + _div(F.col("n_chars") * us, F.lit(1000)), F.lit(1)).cast("long")


def tasks(sample: DataFrame, role: str = "zs_fast", prio: str = "source", spec: ArrivalSpec = ArrivalSpec(), seed: int = SEED, run_id: str = "elastic") -> DataFrame:
    """Tasks of an evaluation sample (at most N rows): the same sequence for every configuration."""
    seq = (F.row_number().over(Window.orderBy(key(seed), "doc_id")) - 1).cast("long")
    n = F.count("*").over(Window.partitionBy(F.lit(1)))
    t = sample.withColumn("seq", seq).withColumn("n_all", n)
    return t.select(F.lit(run_id).alias("run_id"), F.lit(0).alias("shard"), F.col("doc_id").alias("task_id"), "seq", priority(prio).alias("prio"), arrival(F.col("seq"), F.col("n_all"), spec).alias("enq_ms"), service(role).alias("svc_ms"), "y", "n_chars")


def global_sequence(df: DataFrame, *order: str, partitions: int | None = None) -> DataFrame:
    """``seq`` (0-based) over the whole table in the given order, as two narrow passes over range partitions."""
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    # the partition number must be the same for both readers below, so it is written with the rows
    parts = materialise(df.repartitionByRange(n, *order).withColumn("p", F.spark_partition_id()), "sequence")
    local = parts.withColumn("l", F.row_number().over(Window.partitionBy("p").orderBy(*order)))
    sizes = parts.groupBy("p").agg(F.count("*").alias("c"))
    offset = sizes.withColumn("before", F.sum("c").over(Window.orderBy("p").rowsBetween(Window.unboundedPreceding, Window.currentRow)) - F.col("c")).select("p", "before")
    return local.join(F.broadcast(offset), "p").withColumn("seq", (F.col("l") + F.col("before") - 1).cast("long")).drop("p", "l", "before")


def numbered(df: DataFrame, *order: str) -> DataFrame:
    """``seq`` in the given order and ``n_all``, the number of rows."""
    return global_sequence(df, *order).crossJoin(F.broadcast(df.agg(F.count("*").alias("n_all"))))


def warp(df: DataFrame, spec: ArrivalSpec, *order: str) -> DataFrame:
    """The real order of events, re-timed to the two-phase curve."""
    return numbered(df, *order).withColumn("enq_ms", arrival(F.col("seq"), F.col("n_all"), spec)).drop("n_all")


def poisson(tasks_: DataFrame, spec: ArrivalSpec, seed: int = SEED) -> DataFrame:
    """Random gaps of the same mean rates from hash uniforms; times are running sums inside a shard."""
    u = (F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.col("task_id").cast("string"))), 1, 8), 16, 10).cast("long") + 1) / 4294967297.0
    gap = F.lead("enq_ms", 1).over(Window.partitionBy("shard").orderBy("seq")) - F.col("enq_ms")
    w = Window.partitionBy("shard").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)
    return tasks_.withColumn("gap", F.round(-F.log(u) * F.coalesce(gap, F.lit(0))).cast("long")).withColumn("enq_ms", F.coalesce(F.sum("gap").over(w), F.lit(0)).cast("long")).drop("gap")


def rate_profile(df: DataFrame, ts: str, unit: str) -> DataFrame:
    """Arrivals a bucket."""
    return df.groupBy(F.date_trunc(unit, F.col(ts)).alias("bucket")).agg(F.count("*").alias("arrivals"))


def rate_estimate(df: DataFrame, at_ms: str, width_ms: int) -> DataFrame:
    """Burst share and ratio of an arrival series, one row: buckets at or above the middle between the least and the greatest rate are the burst. ``fits`` is whether
    they lie in the ranges of the two-phase curve (a share of 35 to 40 %, a ratio of 4 to 7)."""
    b = df.groupBy(F.expr(f"{at_ms} div {width_ms}").alias("b")).agg(F.count("*").alias("a"))
    ends = b.agg((F.min("a") + F.max("a")).alias("twice"))
    high = (F.col("a") * 2 >= F.col("twice")).cast("int")
    r = b.crossJoin(F.broadcast(ends)).withColumn("high", high).agg(
        F.count("*").alias("buckets"), F.sum("high").alias("burst"), F.sum(F.col("a") * F.col("high")).alias("burst_n"), F.sum(F.col("a") * (1 - F.col("high"))).alias("steady_n"),
    )
    beta = F.round(F.col("burst") / F.col("buckets"), 4)
    ratio = F.round((F.col("burst_n") * (F.col("buckets") - F.col("burst"))) / (F.col("burst") * F.col("steady_n")), 4)
    return r.select("buckets", "burst", beta.alias("beta"), ratio.alias("ratio"), (beta.between(0.35, 0.4) & ratio.between(4, 7)).alias("fits"))


def static_sizes(tasks_: DataFrame, spec: ArrivalSpec) -> DataFrame:
    """Pools without elasticity, one row: as many workers as the average load needs, and as many as the burst needs."""
    burst = spec.window_ms * spec.burst_pm // 1000
    s = tasks_.agg(F.sum("svc_ms").alias("all"), F.sum(F.when(F.col("enq_ms") < burst, F.col("svc_ms")).otherwise(0)).alias("high"))
    size = lambda c, t: F.greatest(_div(F.col(c) + (t - 1), F.lit(t)), F.lit(1)).cast("int")
    return s.select(size("all", spec.window_ms).alias("average"), size("high", burst).alias("peak"))
