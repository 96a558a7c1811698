"""Streams over several triggers: equal to the batch run, once after a restart, late rows counted, stopped on demand."""

import time

from pyspark.sql import functions as F

from elastipool.model import FIGURE
from elastipool.operators.kernel import run_queue
from elastipool.plans.streams import in_turn, sent_twice
from elastipool.sources import generator
from elastipool.streaming import live

TASKS = [(0, 100 + k, k, 1 + k % 3, k * 700, 4000 + 900 * (k % 5)) for k in range(60)]
SCHEMA = "shard int, task_id long, seq long, prio int, enq_ms long, svc_ms long"


def frames(spark, groups):
    return [spark.createDataFrame(g, SCHEMA).withColumn("ts", F.timestamp_millis(F.col("enq_ms") + 1)) for g in groups]


def ends():
    return [[(0, -1 - k, -1 - k, 0, 9_000_000 + 10_000 * k, 0)] for k in range(3)]


def want():
    out, _ = run_queue([(s, p, e, v) for _, _, s, p, e, v in TASKS], FIGURE)
    return {100 + s: x for s, x in out.items()}


def source(spark, path):
    schema = spark.read.parquet(f"{path}/part=000").schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{path}/part=*")


def test_stateful_queue_over_triggers_equals_the_batch_run(spark):
    path = in_turn(spark, frames(spark, [TASKS[:20], TASKS[20:35], TASKS[35:], *ends()]), "t")
    got = live.drained(live.live_queue(source(spark, path), FIGURE))
    assert got.batches >= 6 and got.late == 0
    assert {r.task_id: (r.start_ms, r.finish_ms, r.worker_id) for r in got.rows.collect()} == want()


def test_restart_goes_on_from_the_checkpoint(spark):
    first = in_turn(spark, frames(spark, [TASKS[:20], TASKS[20:35]]), "r")
    folder = f"{first}-out"
    one = live.drained(live.live_queue(source(spark, first), FIGURE), folder=folder)
    assert 0 < one.rows.count() < 60
    for k, f in enumerate(frames(spark, [TASKS[35:], *ends()])):
        f.coalesce(1).write.parquet(f"{first}/part={2 + k:03d}")
    two = live.drained(live.live_queue(source(spark, first), FIGURE), folder=folder)
    assert {r.task_id: (r.start_ms, r.finish_ms, r.worker_id) for r in two.rows.collect()} == want() and two.rows.count() == 60


def test_late_tasks_are_dropped_and_counted(spark):
    late = [(0, 999, 999, 1, 10, 100)]
    path = in_turn(spark, frames(spark, [TASKS, *ends()[:2], late, ends()[2]]), "l")
    got = live.drained(live.live_queue(source(spark, path), FIGURE))
    assert got.late == 1 and {r.task_id for r in got.rows.collect()} == set(want())


def test_empty_stream(spark, tmp_path):
    spark.createDataFrame([], "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string").write.parquet(str(tmp_path / "e"))
    got = live.drained(live.tumbling(live.events(spark, str(tmp_path / "e"))), "complete")
    assert got.rows.collect() == [] and got.rows.columns == ["start", "event_type", "n"]


def test_live_query_stops_when_told(spark, tmp_path):
    rate = spark.readStream.format(generator.register(spark)).option("n", 300).option("per_batch", 10).load()
    seen = []
    q = rate.writeStream.foreachBatch(lambda b, k: seen.append(b.count())).option("checkpointLocation", str(tmp_path / "c")).start()
    began = time.time()
    live.until_stopped(q, lambda: sum(seen) >= 50 or time.time() - began > 60, 0.2)
    assert not q.isActive and sum(seen) >= 50


def test_waves_serve_each_task_once(spark, tmp_path):
    t = spark.createDataFrame([(k, 1 + k % 3, k) for k in range(100)], "task_id long, prio int, seq long")
    log = live.waves(t, FIGURE, lambda w: w.select("task_id", "prio", "seq"), str(tmp_path / "w"))
    rows = spark.read.parquet(str(tmp_path / "w")).collect()
    assert sorted(r.task_id for r in rows) == list(range(100)) and log[-1][2] == 0
    order = [r.task_id for r in sorted(rows, key=lambda r: (r.wave, r.prio, r.seq))]
    assert order == [k for _, _, k in sorted((1 + k % 3, k, k) for k in range(100))]


def test_dedup_over_many_triggers_loses_no_event(spark):
    """Events far apart in time, out of order in the table, some without a time or of one id: each comes out once, whatever the number of triggers."""
    rows = [(k % 90, None if k % 30 == 0 else (k * 37 % 100) * 7200, f"t{k}") for k in range(100)]
    e = spark.createDataFrame(rows, "event_id long, at long, event_type string").select(
        "event_id", F.timestamp_seconds("at").cast("timestamp_ntz").alias("ts"), F.lit(1).cast("long").alias("user_id"), "event_type", F.lit(1.0).alias("value"), F.lit("").alias("props")
    )
    stream = live.events(spark, f"{sent_twice(spark, e.repartition(5), 10)}/part=*", schema=f"{live.EVENTS}, sent long")
    got = live.drained(live.deduplicated(stream, key="sent"))
    assert got.batches >= 11
    assert sorted((r.event_id, r.event_type) for r in got.rows.collect()) == sorted((k, t) for k, _, t in rows)


def test_dedup_query_does_not_depend_on_the_number_of_files(spark, sf, tmp_path):
    from elastipool.plans.catalog import CATALOG

    spark.read.parquet(f"{sf}/events.parquet").repartition(80, "event_id").write.parquet(str(tmp_path / "events.parquet"))
    spark.conf.set("spark.sql.files.openCostInBytes", 1 << 30)  # a task for each file
    try:
        got = CATALOG["stream_dedup"][0](spark, str(tmp_path)).count()
    finally:
        spark.conf.unset("spark.sql.files.openCostInBytes")
    assert got == spark.read.parquet(f"{sf}/events.parquet").count()
