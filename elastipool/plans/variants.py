"""Variants around the methods: starting and draining workers, recursive replay, the approximate sample, audits, estimated rates, sized pools, stored experience, request traffic, sources and sinks."""

from __future__ import annotations

import uuid

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from elastipool.model import FIGURE, NEVER, SEED, ArrivalSpec
from elastipool.operators import classify, kernel, measures, queueing, sampling, workload
from elastipool.plans import oracle as O
from elastipool.plans import runs
from elastipool.plans.catalog import EXPERIENCE, POL, RES, add, experience, query, sim, train, _train_sql
from elastipool.session import materialise, scratch_root
from elastipool.sources import ingest

t = ingest.table

# ---- pools whose workers take time to start, or leave after their task ------------------------------------------------------------------------------------
SPINUP = FIGURE.but(run_id="spinup", spinup_ms=4_000)
#: A large pool and a high lower threshold, so that workers are told to go while they serve.
DRAIN = FIGURE.but(run_id="drain", n_init=12, n_max=16, util_lo_pm=700, util_hi_pm=950, cooldown_ms=2_000, step_down=4, retire="drain")
for _n, _c in (("spinup", SPINUP), ("drain", DRAIN), ("drain_idle", DRAIN.but(run_id="drain_idle", retire="idle"))):
    add(f"elastic_{_n}_results", lambda s, d, c=_c: kernel.results(sim(s, d, c)), O.elastic(_c, f"SELECT {RES} FROM res"))
    add(f"elastic_{_n}_polls", lambda s, d, c=_c: kernel.polls(sim(s, d, c)), O.elastic(_c, f"SELECT {POL} FROM pol"))

# ---- recursive replay ---------------------------------------------------------------------------------------------------------------------------------------
_DAYS = "dy AS (SELECT CAST(epoch(date_trunc('day', ts)) AS BIGINT) // 86400 AS h, count(*) AS a FROM events GROUP BY 1), ab AS (SELECT row_number() OVER (ORDER BY h) - 1 AS b, a FROM dy)"


def _recursion(cfg, b: str, long: str, int_: str) -> str:
    """One recursive query for both engines: the rule over a recorded series sg(b, t_ms, q, busy)."""
    rule = f"""CASE WHEN t2 - last < {cfg.cooldown_ms} THEN 0 WHEN q2 > {cfg.queue_hi} OR busy2 * 1000 > n * {cfg.util_hi_pm} THEN least({cfg.step}, {cfg.n_max} - n)
      WHEN q2 = 0 AND busy2 * 1000 < n * {cfg.util_lo_pm} THEN -least({cfg.step_down}, n - {cfg.n_min}, n - busy2) ELSE 0 END"""
    zero = f"CAST(0 AS {long})"
    return f"""f AS (SELECT CAST(-1 AS {long}) AS b, {zero} AS t_ms, {zero} AS q, {zero} AS busy, {zero} AS n0, {zero} AS delta, CAST({cfg.n_init} AS {long}) AS n, CAST({NEVER} AS {long}) AS last
      UNION ALL SELECT b2, t2, q2, busy2, n, d, n + d, CASE WHEN d <> 0 THEN t2 ELSE last END FROM (SELECT *, CAST({rule} AS {long}) AS d
        FROM (SELECT f.n, f.last, sg.b AS b2, sg.t_ms AS t2, sg.q AS q2, least(sg.busy, f.n) AS busy2 FROM f JOIN sg ON sg.b = f.b + 1)))
    SELECT b, t_ms, q, busy, n0 AS n_before, delta, n AS n_after FROM f WHERE b >= 0"""


@query("replay_recursive", f"WITH RECURSIVE {_DAYS}, sg AS (SELECT b, b * 1000 AS t_ms, greatest(a - 300, 0) AS q, a // 100 AS busy FROM ab), {_recursion(FIGURE, 'b', 'BIGINT', 'INTEGER')}")
def _(s, d):
    """The rule over daily counts as a recursive query inside the engine: one round a day, so for short series only; longer ones go through the fold."""
    days = t(s, d, "events").groupBy(F.floor(F.unix_seconds(F.col("ts").cast("timestamp")) / 86_400).alias("h")).agg(F.count("*").alias("a"))
    series = days.select((F.row_number().over(Window.orderBy("h")) - 1).cast("long").alias("b"), "a")
    series = series.select("b", (F.col("b") * 1000).alias("t_ms"), F.greatest(F.col("a") - 300, F.lit(0)).cast("long").alias("q"), F.expr("a div 100").cast("long").alias("busy"))
    materialise(series, "series").createOrReplaceTempView("replay_series")
    return s.sql(f"WITH RECURSIVE sg AS (SELECT * FROM replay_series), {_recursion(FIGURE, 'b', 'BIGINT', 'INT')}")


# ---- samples and audits -------------------------------------------------------------------------------------------------------------------------------------
for _t in ("lang", "quality"):
    add(f"sample_approximate_{_t}", lambda s, d, k=_t: sampling.approximate(ingest.labelled(s, d, k)), f"WITH {O.src(_t)}, {O.reps()}, {O.samp()} SELECT * FROM samp")
    add(
        f"leak_normalised_{_t}", lambda s, d, k=_t: sampling.leakage_normalised(*train(s, d, k), t(s, d, "documents")),
        f"WITH {O.src(_t)}, {O.reps()}, {O.samp()}, {_train_sql(_t)}, nd AS (SELECT doc_id, regexp_replace(lower(text), '[^\\p{{L}}]+', ' ', 'g') AS norm FROM documents) "
        "SELECT count(*) AS shared_normalised FROM nd WHERE doc_id IN (SELECT doc_id FROM train) AND norm IN (SELECT norm FROM nd WHERE doc_id IN (SELECT doc_id FROM samp))",
    )

# ---- rates, sized pools ----------------------------------------------------------------------------------------------------------------------------------
_WARPED = f"wp AS (SELECT event_id, {O.arrival('seq', 'n')} AS enq_ms FROM (SELECT *, row_number() OVER (ORDER BY ts, event_id) - 1 AS seq, count(*) OVER () AS n FROM events))"


def warped(s: SparkSession, d: str) -> DataFrame:
    return workload.warp(t(s, d, "events").select("event_id", "ts"), ArrivalSpec(), "ts", "event_id")


add("rate_estimate_warped", lambda s, d: workload.rate_estimate(warped(s, d), "enq_ms", 1800), f"""WITH {_WARPED}, b AS (SELECT enq_ms // 1800 AS b, count(*) AS a FROM wp GROUP BY 1),
  h AS (SELECT a, CASE WHEN a * 2 >= (SELECT min(a) + max(a) FROM b) THEN 1 ELSE 0 END AS high FROM b),
  r AS (SELECT count(*) AS buckets, CAST(sum(high) AS BIGINT) AS burst, sum(a * high) AS bn, sum(a * (1 - high)) AS sn FROM h),
  e AS (SELECT buckets, burst, round(burst / buckets, 4) AS beta, round(bn * (buckets - burst) / (burst * sn), 4) AS ratio FROM r)
  SELECT *, beta BETWEEN 0.35 AND 0.4 AND ratio BETWEEN 4 AND 7 AS fits FROM e""")

#: Tasks that one worker serves in a bucket of one second, in the fluid model of the warped events.
PER_WORKER, BUCKET_MS = 10, 1000
_SECONDS = f"""{_WARPED}, ab AS (SELECT g.b, coalesce(a, 0) AS a FROM (SELECT unnest(range({ArrivalSpec().window_ms // BUCKET_MS})) AS b) g LEFT JOIN (SELECT enq_ms // {BUCKET_MS} AS b, count(*) AS a FROM wp GROUP BY 1) x ON x.b = g.b)"""


def per_second(s: SparkSession, d: str) -> DataFrame:
    c = warped(s, d).groupBy(F.expr(f"enq_ms div {BUCKET_MS}").alias("b")).agg(F.count("*").alias("a"))
    grid = s.range(ArrivalSpec().window_ms // BUCKET_MS).withColumnRenamed("id", "b")
    return grid.join(c, "b", "left").select(F.lit("events").alias("run_id"), "b", F.coalesce("a", F.lit(0)).cast("long").alias("a"))


def provision(s: SparkSession, d: str) -> DataFrame:
    """Re-timed events against static pools for average and peak load: unserved and unused capacity, the largest queue, and the share of seconds in which capacity
    and arrivals differ by a tenth at most. The average pool falls behind in the burst, the peak pool stands idle after it."""
    rates = materialise(per_second(s, d), "rates")
    spec = ArrivalSpec()
    burst = spec.window_ms * spec.burst_pm // 1000 // BUCKET_MS
    n = rates.agg(F.sum("a").alias("all"), F.sum(F.when(F.col("b") < burst, F.col("a")).otherwise(0)).alias("high")).first()
    out = None
    for name, need, secs in (("average", n["all"], spec.window_ms // BUCKET_MS), ("peak", n["high"], burst)):
        pool = max(1, -(-need // (secs * PER_WORKER)))
        f = queueing.fluid(rates, FIGURE.but(run_id=name, n_init=pool, n_min=pool, n_max=pool), PER_WORKER, False)
        gap = F.col("a") - F.col("n") * PER_WORKER
        one = f.agg(
            F.max("n").alias("n"), F.sum(F.greatest(gap, F.lit(0))).alias("under"), F.sum(F.greatest(-gap, F.lit(0))).alias("over"), F.max("q").alias("peak_queue"),
            F.round(F.sum(F.when(F.abs(gap) * 10 <= F.col("a"), 1).otherwise(0)) / F.count("*"), 6).alias("within"),
        )
        one = one.select(F.lit(name).alias("pool"), "*")
        out = one if out is None else out.unionByName(one)
    return out


_BURST_B = ArrivalSpec().window_ms * ArrivalSpec().burst_pm // 1000 // BUCKET_MS
_WINDOW_B = ArrivalSpec().window_ms // BUCKET_MS
_QUEUE = "CAST(c - least(min(c) OVER (PARTITION BY pool ORDER BY b ROWS UNBOUNDED PRECEDING), 0) AS BIGINT)"  # a queue is its net input less the lowest point of it so far
add("provision_warped", provision, f"""WITH {_SECONDS}, z AS (SELECT 'average' AS pool, greatest((sum(a) + {_WINDOW_B * PER_WORKER - 1}) // {_WINDOW_B * PER_WORKER}, 1) AS n FROM ab
  UNION ALL SELECT 'peak', greatest((sum(a) FILTER (b < {_BURST_B}) + {_BURST_B * PER_WORKER - 1}) // {_BURST_B * PER_WORKER}, 1) FROM ab),
  x AS (SELECT pool, CAST(n AS BIGINT) AS n, b, a, CAST(a - n * {PER_WORKER} AS BIGINT) AS gap, sum(a - n * {PER_WORKER}) OVER (PARTITION BY pool ORDER BY b) AS c FROM ab, z), y AS (SELECT *, {_QUEUE} AS q FROM x)
  SELECT pool, max(n) AS n, CAST(sum(greatest(gap, 0)) AS BIGINT) AS under, CAST(sum(greatest(-gap, 0)) AS BIGINT) AS over, max(q) AS peak_queue,
    round(sum(CASE WHEN abs(gap) * 10 <= a THEN 1 ELSE 0 END) / count(*), 6) AS within FROM y GROUP BY 1""")

# ---- stored experience -------------------------------------------------------------------------------------------------------------------------------------


def store(rows: DataFrame, path: str) -> None:
    """Append experience, one folder a run; a run that is written again replaces its own rows."""
    rows.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("run_id").parquet(path)


def advise(rows: DataFrame) -> DataFrame:
    """Mean next queue by coarse state and action, over all runs that are stored. It is read only; the rule never sees it."""
    e = rows.where("q_next IS NOT NULL")
    return e.groupBy(F.floor(F.col("q") / 10).alias("qb"), "n", F.floor(F.col("util_pm") / 250).cast("int").alias("ub"), "action").agg(
        F.countDistinct("run_id").alias("runs"), F.count("*").alias("seen"), F.round(F.sum("q_next") / F.count("q_next"), 6).alias("q_next"), F.sum(F.when(F.col("q_next") < F.col("q"), 1).otherwise(0)).alias("fell"),
    )


_GRID = runs.sweep_grid(True)


@query(
    "experience_sweep",
    O.several(
        [(c, "zs_fast") for c in _GRID],
        (
            f", {EXPERIENCE} SELECT q // 10 AS qb, n, util_pm // 250 AS ub, action, count(DISTINCT run_id) AS runs, count(*) AS seen, round(CAST(sum(q_next) AS DOUBLE) / "
            "count(q_next), 6) AS q_next, CAST(sum(CASE WHEN q_next < q THEN 1 ELSE 0 END) AS BIGINT) AS fell FROM ex WHERE q_next IS NOT NULL GROUP BY 1, 2, 3, 4"
        ),
    ),
)
def _(s, d):
    """Experience of the runs of the sweep, stored in two appends, of which the second writes a run again, and read back for advice."""
    path = f"{scratch_root(s)}/experience-{uuid.uuid4().hex}"
    x = materialise(kernel.simulate(runs.tasks(s, d), _GRID), "sweep")
    rows = experience(x)
    schema = rows.schema
    half = [c.run_id for c in _GRID[:13]]
    store(rows.where(F.col("run_id").isin(half)), path)
    store(rows.where(~F.col("run_id").isin(half[:-1])), path)
    return advise(s.read.schema(schema).parquet(path))


# ---- request traffic -----------------------------------------------------------------------------------------------------------------------------------------
_STRIP = r"trim(regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), '[ \t\r\n]+', ' ', 'g'))".replace("\\t", "\t").replace("\\r", "\r").replace("\\n", "\n")
add(
    "requests_pages",
    lambda s, d: ingest.pages(s, d).select("doc_id", classify.zs_fast("lang").alias("y_hat")),
    f"SELECT doc_id, {O.label('zs_fast', 'lang')} AS y_hat FROM (SELECT doc_id, {O.TOK} AS tok FROM (SELECT page_id AS doc_id, {_STRIP} AS text FROM pages))",
)


@query(
    "tasks_conversations",
    (
        f"SELECT task_id, CAST(seq AS BIGINT) AS seq, prio, {O.arrival('seq', 'n')} AS enq_ms FROM (SELECT conv_id * 100 + turn AS task_id, CAST(CASE WHEN role = 'user' THEN 1 "
        "ELSE 2 END AS INTEGER) AS prio, row_number() OVER (ORDER BY conv_id, turn) - 1 AS seq, count(*) OVER () AS n FROM conversations)"
    ),
)
def _(s, d):
    """Turns of conversations as tasks, users before assistants."""
    c = t(s, d, "conversations").select("conv_id", "turn", (F.col("conv_id") * 100 + F.col("turn")).alias("task_id"), workload.priority("role").alias("prio"))
    return workload.warp(c, ArrivalSpec(), "conv_id", "turn").select("task_id", "seq", "prio", "enq_ms")


# ---- a model called on batches -----------------------------------------------------------------------------------------------------------------------------
def _length_model():
    """Stands for a model that is loaded once a worker: a batch of (characters, digits) to a class of 0, 1 or 2."""

    def predict(x: np.ndarray) -> np.ndarray:
        x = x.astype(np.int64)
        return np.where(x[:, 1] * 20 > x[:, 0], 2, np.where(x[:, 0] > 1000, 1, 0)).astype(np.int32)

    return predict


_CLASS = "CASE WHEN (length(text) - length(regexp_replace(text, '[0-9]', '', 'g'))) * 20 > length(text) THEN 2 WHEN length(text) > 1000 THEN 1 ELSE 0 END"


@query("external_batch", f"SELECT doc_id, CAST({_CLASS} AS INTEGER) AS y_hat FROM documents WHERE text IS NOT NULL")
def _(s, d):
    features = F.array(F.length("text").cast("double"), (F.length("text") - F.length(F.regexp_replace("text", "[0-9]", ""))).cast("double"))
    return classify.external_batch(t(s, d, "documents").where("text IS NOT NULL"), _length_model, features, 2)


# ---- sources and sinks ------------------------------------------------------------------------------------------------------------------------------------
@query("op_json_lines_roundtrip", "SELECT conv_id, turn, role, md5(text) AS h FROM conversations")
def _(s, d):
    """Conversations written as JSON lines and read back with the fixed schema."""
    c = t(s, d, "conversations").select("conv_id", "turn", "role", "text")
    path = f"{scratch_root(s)}/jsonl-{uuid.uuid4().hex}"
    c.write.json(path)
    return ingest.json_lines(s, path, c.schema).select("conv_id", "turn", "role", F.md5("text").alias("h"))


add(
    "op_variant_props",
    lambda s, d: t(s, d, "events").select(F.variant_get(F.parse_json("props"), "$.k", "bigint").alias("k"), "event_type").groupBy("k", "event_type").agg(F.count("*").alias("n")),
    "SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, event_type, count(*) AS n FROM events GROUP BY 1, 2",
)


@query("op_partitioned_append", O.several([(c, "zs_fast") for c in _GRID[:4]], "SELECT run_id, count(*) AS n, CAST(sum(sojourn_ms) AS BIGINT) AS sojourn_ms FROM res GROUP BY 1"))
def _(s, d):
    """Results appended run by run to one partitioned table; a run written twice is there once."""
    path = f"{scratch_root(s)}/results-{uuid.uuid4().hex}"
    r = materialise(kernel.results(kernel.simulate(runs.tasks(s, d), _GRID[:4])), "runs")
    for k in (0, 1, 2, 3, 2):
        store(r.where(F.col("run_id") == _GRID[k].run_id), path)
    return s.read.schema(r.schema).parquet(path).groupBy("run_id").agg(F.count("*").alias("n"), F.sum("sojourn_ms").alias("sojourn_ms"))
