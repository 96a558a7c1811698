"""Query catalogue: name -> (DataFrame query, SQL of an independent check or None)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from elastipool.functions import control
from elastipool.model import FIGURE, N_MARKS, NEVER, PEAK, SEED, SEQUENTIAL, STATIC2, TEXT, ArrivalSpec, RunConfig
from elastipool.operators import classify, kernel, measures, queueing, sampling, workload
from elastipool.plans import oracle as O
from elastipool.plans import runs
from elastipool.session import materialise
from elastipool.sources import ingest

Query = Callable[[SparkSession, str], DataFrame]
CATALOG: dict[str, tuple[Query, str | None]] = {}
RES = "run_id, shard, task_id, seq, prio, enq_ms, svc_ms, start_ms, finish_ms, worker_id, wait_ms, sojourn_ms"
POL = "run_id, shard, j, t_ms, q, busy, n_before, delta, n_after, done, t_last_ms, util_pm"
MINUTE_FLUID = FIGURE.but(run_id="events", n_init=2, queue_hi=5, cooldown_ms=3, n_max=8)


def query(name: str, sql: str | None = None):
    def put(f: Query) -> Query:
        CATALOG[name] = (f, sql)
        return f

    return put


def add(name: str, f: Query, sql: str | None = None) -> None:
    CATALOG[name] = (f, sql)


def sim(spark: SparkSession, sf: str, cfg: RunConfig, task: str = "lang", role: str = "zs_fast", prio: str = "source") -> DataFrame:
    return materialise(kernel.simulate(runs.tasks(spark, sf, task, role, prio), [cfg]), "sim")


# ---- ingest ----------------------------------------------------------------------------------------------------------------------------------------
for _t in ("lang", "quality", "toxic"):
    add(
        f"ingest_{_t}",
        lambda s, d, t=_t: ingest.labelled(s, d, t).select("doc_id", F.md5("text").alias("text_md5"), "y", "n_chars"),
        f"WITH {O.src(_t)} SELECT doc_id, md5(text) AS text_md5, y, n_chars FROM src",
    )
    add(
        f"class_profile_{_t}",
        lambda s, d, t=_t: ingest.labelled(s, d, t).groupBy("y").agg(F.count("*").alias("n"), F.countDistinct(F.md5("text")).alias("texts"), F.sum("n_chars").alias("chars")),
        f"WITH {O.src(_t)} SELECT y, count(*) AS n, count(DISTINCT md5(text)) AS texts, CAST(sum(n_chars) AS BIGINT) AS chars FROM src GROUP BY y",
    )
add("ingest_requests_conv", lambda s, d: ingest.conversations(s, d), "SELECT conv_id * 100 + turn AS doc_id, text FROM conversations WHERE role = 'user'")
add(
    "ingest_pages_text",
    lambda s, d: ingest.pages(s, d).select("doc_id", F.md5("text").alias("text_md5")),
    r"SELECT page_id AS doc_id, md5(trim(regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), '[ \t\r\n]+', ' ', 'g'))) AS text_md5 FROM pages",
)
add(
    "text_stats_by_lang_source",
    lambda s, d: ingest.table(s, d, "documents").cube("lang", "source").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"), F.max("n_chars").alias("longest")),
    "SELECT lang, source, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars, max(n_chars) AS longest FROM documents GROUP BY CUBE (lang, source)",
)
add(
    "dup_groups",
    lambda s, d: ingest.table(s, d, "documents").groupBy(F.md5("text").alias("text_md5")).agg(F.count("*").alias("n"), F.min("doc_id").alias("first")).where("n > 1"),
    "SELECT md5(text) AS text_md5, count(*) AS n, min(doc_id) AS first FROM documents GROUP BY 1 HAVING count(*) > 1",
)

# ---- sampling --------------------------------------------------------------------------------------------------------------------------------------
for _t in ("lang", "quality", "toxic"):
    add(f"sample_balanced_{_t}", lambda s, d, t=_t: runs.sample(s, d, t), f"WITH {O.src(_t)}, {O.reps()}, {O.samp()} SELECT * FROM samp")
    add(f"sample_proportional_{_t}", lambda s, d, t=_t: runs.sample(s, d, t, balanced=False), f"WITH {O.src(_t)}, {O.reps()}, {O.prop()} SELECT * FROM samp")


def _train_sql(t: str) -> str:
    return f"train AS (SELECT *, CAST(row_number() OVER (ORDER BY md5('18:' || doc_id), doc_id) AS INTEGER) AS r FROM reps WHERE text_md5 NOT IN (SELECT text_md5 FROM samp) ORDER BY r LIMIT 4000)"


def train(s: SparkSession, d: str, t: str) -> tuple[DataFrame, DataFrame]:
    rows = materialise(runs.sample(s, d, t), "sample")
    return sampling.train_split(ingest.labelled(s, d, t), rows), rows


for _t in ("lang", "quality"):
    add(f"train_split_{_t}", lambda s, d, t=_t: train(s, d, t)[0], f"WITH {O.src(_t)}, {O.reps()}, {O.samp()}, {_train_sql(_t)} SELECT doc_id, y, n_chars, source, text_md5, r FROM train")
    add(
        f"leakage_{_t}",
        lambda s, d, t=_t: sampling.leakage(*train(s, d, t)),
        (
            f"WITH {O.src(_t)}, {O.reps()}, {O.samp()}, {_train_sql(_t)} SELECT (SELECT count(*) FROM train WHERE doc_id IN (SELECT doc_id FROM samp)) AS shared_ids, (SELECT count(*) "
            "FROM train WHERE text_md5 IN (SELECT text_md5 FROM samp)) AS shared_texts"
        ),
    )


@query("leak_benchmark", "SELECT d.doc_id, b.item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)")
def _(s, d):
    """Benchmark texts inside documents: the items are few (their number is checked) and are broadcast; documents stay where they are."""
    items = ingest.table(s, d, "benchmark")
    if items.count() > 10_000:
        raise ValueError("too many items for a nested-loop join; use the containment search")
    docs = ingest.table(s, d, "documents").select("doc_id", F.col("text").alias("doc_text"))
    return docs.join(F.broadcast(items), F.col("doc_text").contains(F.col("text"))).select("doc_id", "item_id")


@query(
    "sample_intersection",
    (
        f"WITH {O.src('quality')}, {O.reps()}, {O.samp()}, b AS (SELECT doc_id FROM samp), p AS (WITH {O.prop()} SELECT doc_id FROM samp) SELECT doc_id FROM b INTERSECT "
        "SELECT doc_id FROM p"
    ),
)
def _(s, d):
    return runs.sample(s, d, "quality").select("doc_id").intersect(runs.sample(s, d, "quality", balanced=False).select("doc_id"))


# ---- tasks and arrivals ------------------------------------------------------------------------------------------------------------------------------
TASK = "shard, task_id, seq, prio, enq_ms, svc_ms, y, n_chars"
for _t, _p in (("lang", "source"), ("quality", "source"), ("lang", "label"), ("lang", "const")):
    add(f"tasks_{_t}" + ("" if _p == "source" else f"_{_p}"), lambda s, d, t=_t, p=_p: runs.tasks(s, d, t, prio=p).drop("run_id"), f"WITH {O.base(_t, prio=_p)} SELECT {TASK} FROM tk")


_SHAPES = [(r, b) for r in (40, 48, 50, 60, 70) for b in (350, 380, 400)]


@query(
    "arrivals_grid",
    "WITH s AS (SELECT s_suppkey, row_number() OVER (ORDER BY s_acctbal NULLS FIRST, s_name NULLS FIRST, s_suppkey NULLS FIRST) - 1 AS seq, count(*) OVER () AS n FROM supplier) "
    + " UNION ALL ".join(f"SELECT {r} AS ratio, {b} AS burst, s_suppkey, seq, {O.arrival('seq', 'n', ArrivalSpec(burst_pm=b, ratio_tenths=r))} AS enq_ms FROM s" for r, b in _SHAPES),
)
def _(s, d):
    """Suppliers arrive in the order of their balances, names and keys, on each shape of the curve."""
    t = workload.numbered(ingest.table(s, d, "supplier").select("s_acctbal", "s_name", "s_suppkey"), "s_acctbal", "s_name", "s_suppkey")
    at = [F.struct(F.lit(r).alias("ratio"), F.lit(b).alias("burst"), workload.arrival(F.col("seq"), F.col("n_all"), ArrivalSpec(burst_pm=b, ratio_tenths=r)).alias("enq_ms")) for r, b in _SHAPES]
    return t.select("s_suppkey", "seq", F.explode(F.array(*at)).alias("at")).select("at.ratio", "at.burst", "s_suppkey", "seq", "at.enq_ms")


add(
    "events_rate_hourly",
    lambda s, d: workload.rate_profile(ingest.table(s, d, "events"), "ts", "hour").select(F.unix_seconds(F.col("bucket").cast("timestamp")).alias("bucket"), "arrivals"),
    "SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) AS bucket, count(*) AS arrivals FROM events GROUP BY 1",
)
add(
    "events_warp",
    lambda s, d: workload.warp(ingest.table(s, d, "events").select("event_id", "ts", "event_type"), ArrivalSpec(), "ts", "event_id").select("event_id", "seq", workload.priority("event").alias("prio"), "enq_ms"),
    (
        f"SELECT event_id, seq, {O.EVENT_PRIO} AS prio, {O.arrival('seq', 'n')} AS enq_ms FROM (SELECT *, row_number() OVER (ORDER BY ts, event_id) - 1 AS seq, count(*) OVER () AS "
        "n FROM events)"
    ),
)
_U = f"(CAST('0x' || substr(md5('{SEED}:' || task_id), 1, 8) AS BIGINT) + 1) / 4294967297.0"
add(
    "arrivals_poisson",
    lambda s, d: workload.poisson(runs.tasks(s, d).drop("run_id"), ArrivalSpec()),
    (
        f"WITH {O.base()}, g AS (SELECT *, CAST(round(-ln({_U}) * coalesce(lead(enq_ms) OVER (ORDER BY seq) - enq_ms, 0)) AS BIGINT) AS gap FROM tk) "
        "SELECT shard, task_id, seq, prio, CAST(coalesce(sum(gap) OVER (ORDER BY seq ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS enq_ms, svc_ms, y, "
        "n_chars FROM g"
    ),
)

# ---- queue: closed forms, folds ----------------------------------------------------------------------------------------------------------------------
add(
    "order_all_present",
    lambda s, d: queueing.order(runs.tasks(s, d)).select("task_id", "seq", "prio", "pos"),
    f"WITH {O.base()} SELECT task_id, seq, prio, CAST(row_number() OVER (ORDER BY prio, seq) AS INTEGER) AS pos FROM tk",
)
add(
    "sequential_lindley",
    lambda s, d: queueing.sequential(runs.tasks(s, d)).select("task_id", "seq", "start_ms", "finish_ms", "wait_ms"),
    O.elastic(SEQUENTIAL, "SELECT task_id, seq, start_ms, finish_ms, wait_ms FROM res", prio="const"),
)
add(
    "fifo_two_fold",
    lambda s, d: queueing.fifo_fold(runs.tasks(s, d), 2).select("task_id", "seq", "start_ms", "finish_ms", "wait_ms"),
    O.elastic(STATIC2, "SELECT task_id, seq, start_ms, finish_ms, wait_ms FROM res", prio="const"),
)
add(
    "fifo_equal_residue",
    lambda s, d: queueing.fifo_equal(runs.tasks(s, d), 4, 13_700).select("task_id", "seq", "start_ms", "finish_ms", "wait_ms"),
    (
        f"WITH RECURSIVE {O.base(prio='const')}, t2 AS (SELECT * REPLACE (CAST(13700 AS BIGINT) AS svc_ms) FROM tk), {O.sim(STATIC2.but(n_init=4), '', 't2')} "
        "SELECT task_id, seq, start_ms, finish_ms, wait_ms FROM res"
    ),
)
for _n, _c in (("two", STATIC2), ("max", PEAK)):
    add(f"priority_static_{_n}", lambda s, d, c=_c: kernel.results(sim(s, d, c)), O.elastic(_c, f"SELECT {RES} FROM res"))
add("static_sizes", lambda s, d: workload.static_sizes(runs.tasks(s, d), ArrivalSpec()), f"WITH {O.base()}, {O.sizes()} SELECT * FROM size")
add(
    "depth_at_marks",
    lambda s, d: measures.queue_trace(kernel.results(sim(s, d, FIGURE))),
    O.elastic(
        FIGURE,
        (
            "SELECT run_id, m AS mark, t_ms, (SELECT count(*) FROM res WHERE enq_ms <= t_ms) - (SELECT count(*) FROM res WHERE start_ms <= t_ms) AS q "
            f"FROM (SELECT run_id, CAST(m AS INTEGER) AS m, m * r // {N_MARKS} AS t_ms FROM (SELECT run_id, max(finish_ms) AS r FROM res "
            f"GROUP BY 1), (SELECT unnest(range(1, {N_MARKS + 1})) AS m))"
        ),
    ),
)


@query("busy_at_polls", O.elastic(FIGURE, "SELECT run_id, j, t_ms, busy AS seen, (SELECT count(*) FROM res WHERE start_ms <= p.t_ms AND finish_ms > p.t_ms) AS busy FROM pol p"))
def _(s, d):
    """Busy workers at each poll from task intervals: +1 and -1 events and one running sum; compared with what the controller saw."""
    x = sim(s, d, FIGURE)
    r = kernel.results(x)
    ch = r.select("run_id", F.col("start_ms").alias("t_ms"), F.lit(1).alias("d")).union(r.select("run_id", "finish_ms", F.lit(-1))).groupBy("run_id", "t_ms").agg(F.sum("d").alias("d"))
    steps = ch.withColumn("busy", F.sum("d").over(Window.partitionBy("run_id").orderBy("t_ms")))
    grid = kernel.polls(x).select("run_id", "t_ms", "j", F.col("busy").alias("seen"))
    return queueing.as_of(grid, steps, "busy").select("run_id", "j", "t_ms", "seen", "busy")


def hourly(s: SparkSession, d: str) -> DataFrame:
    """(run_id, b, a): hours numbered from the first, hours without events included."""
    r = workload.rate_profile(ingest.table(s, d, "events"), "ts", "hour").select((F.unix_seconds(F.col("bucket").cast("timestamp")) / 3600).cast("long").alias("h"), "arrivals")
    lo = r.agg(F.min("h").alias("lo"), F.max("h").alias("hi"))
    grid = lo.select(F.explode(F.sequence("lo", "hi")).alias("h"), "lo")
    return grid.join(r, "h", "left").select(F.lit("events").alias("run_id"), (F.col("h") - F.col("lo")).alias("b"), F.coalesce("arrivals", F.lit(0)).cast("long").alias("a"))


_HOURS = (
    "hr AS (SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) // 3600 AS h, count(*) AS a FROM events GROUP BY 1), ab AS (SELECT g.h - (SELECT min(h) "
    "FROM hr) AS b, coalesce(a, 0) AS a FROM (SELECT unnest(range((SELECT min(h) FROM hr), (SELECT max(h) FROM hr) + 1)) AS h) g LEFT JOIN hr USING (h))"
)


def _fluid_sql(cfg: RunConfig, k: int, elastic: bool) -> str:
    d = f"CASE WHEN {str(elastic).lower()} AND b2 - last >= {cfg.cooldown_ms} AND (q2 > {cfg.queue_hi} OR (served * 1000) // (n * {k}) > {cfg.util_hi_pm}) THEN least({cfg.step}, {cfg.n_max} - n) WHEN {str(elastic).lower()} AND b2 - last >= {cfg.cooldown_ms} AND q2 = 0 AND (served * 1000) // (n * {k}) < {cfg.util_lo_pm} THEN -least({cfg.step_down}, n - {cfg.n_min}) ELSE 0 END"
    return f"""WITH RECURSIVE {_HOURS}, f AS (
      SELECT CAST(-1 AS BIGINT) AS b, CAST(0 AS BIGINT) AS a, CAST(0 AS BIGINT) AS served, CAST(0 AS BIGINT) AS q, CAST({cfg.n_init} AS BIGINT) AS n0, CAST({cfg.n_init} AS BIGINT) AS n, CAST(0 AS BIGINT) AS delta, CAST({NEVER} AS BIGINT) AS last
      UNION ALL SELECT b2, a2, served, q2, n, n + d, d, CASE WHEN d <> 0 THEN b2 ELSE last END FROM (SELECT *, CAST({d} AS BIGINT) AS d FROM (SELECT *, q + a2 - served AS q2 FROM (SELECT f.q, f.n, f.last, ab.b AS b2, ab.a AS a2, least(f.q + ab.a, f.n * {k}) AS served FROM f JOIN ab ON ab.b = f.b + 1))))
    SELECT 'events' AS run_id, b, a, served, q, n0 AS n, delta FROM f WHERE b >= 0"""


for _n, _e in (("static", False), ("elastic", True)):
    add(f"fluid_events_{_n}", lambda s, d, e=_e: queueing.fluid(hourly(s, d), MINUTE_FLUID, 4, e), _fluid_sql(MINUTE_FLUID, 4, _e))
add(
    "capacity_gap",
    lambda s, d: queueing.fluid(hourly(s, d), MINUTE_FLUID, 4, True).select("run_id", "b", (F.col("a") - F.col("n") * 4).alias("gap"), F.greatest(F.col("a") - F.col("n") * 4, F.lit(0)).alias("under"), F.greatest(F.col("n") * 4 - F.col("a"), F.lit(0)).alias("over")),
    f"SELECT run_id, b, a - n * 4 AS gap, greatest(a - n * 4, 0) AS under, greatest(n * 4 - a, 0) AS over FROM ({_fluid_sql(MINUTE_FLUID, 4, True)})",
)

# ---- control ------------------------------------------------------------------------------------------------------------------------------------------
_GRID = (
    "SELECT *, count(*) AS readings FROM (SELECT CAST(greatest(floor(l_quantity) - 40, 0) AS INTEGER) AS q, CAST(2 + l_linenumber % 7 AS INTEGER) AS n, CAST(l_partkey % 9 AS INTEGER) "
    "AS busy, CAST(4999 + l_suppkey % 3 AS INTEGER) AS el FROM lineitem) WHERE busy <= n GROUP BY q, n, busy, el"
)


def grid(s: SparkSession, d: str) -> DataFrame:
    """Every line item as a reading of a pool: its quantity over 40 as the queue, its keys as workers, busy ones, and time since the last change around the cooldown. One
    row for each state that occurs, with its readings."""
    num = lambda name, c: c.cast("int").alias(name)
    r = ingest.table(s, d, "lineitem").select(
        num("q", F.greatest(F.floor("l_quantity") - 40, F.lit(0))), num("n", 2 + F.col("l_linenumber") % 7), num("busy", F.col("l_partkey") % 9), num("el", 4999 + F.col("l_suppkey") % 3)
    )
    return r.where("busy <= n").groupBy("q", "n", "busy", "el").agg(F.count("*").alias("readings"))


_RULE = (
    f"CASE WHEN el < {FIGURE.cooldown_ms} THEN 0 WHEN q > {FIGURE.queue_hi} OR busy * 1000 > n * {FIGURE.util_hi_pm} THEN least({FIGURE.step}, {FIGURE.n_max} - n) "
    f"WHEN q = 0 AND busy * 1000 < n * {FIGURE.util_lo_pm} THEN -least({FIGURE.step_down}, n - {FIGURE.n_min}, n - busy) ELSE 0 END"
)
add(
    "rule_truth_table",
    lambda s, d: grid(s, d).select("*", control.delta(F.col("q"), F.col("busy"), F.col("n"), F.col("el"), 0, FIGURE).alias("delta")),
    f"SELECT q, n, busy, el, readings, CAST({_RULE} AS INTEGER) AS delta FROM ({_GRID})",
)
add(
    "rule_bounds",
    lambda s, d: grid(s, d).select("*", control.clip(F.col("n") + control.delta(F.col("q"), F.col("busy"), F.col("n"), F.col("el"), 0, FIGURE), FIGURE).alias("n_after"), control.c_up(F.col("q"), F.col("busy"), F.col("n"), FIGURE).alias("up"), control.c_down(F.col("q"), F.col("busy"), F.col("n"), FIGURE).alias("down")),
    (
        f"SELECT q, n, busy, el, readings, CAST(least(greatest(n + {_RULE}, {FIGURE.n_min}), {FIGURE.n_max}) AS INTEGER) AS n_after, q > {FIGURE.queue_hi} OR busy * "
        f"1000 > n * {FIGURE.util_hi_pm} AS up, q = 0 AND busy * 1000 < n * {FIGURE.util_lo_pm} AS down FROM ({_GRID})"
    ),
)


@query("op_sql_function_rule", f"SELECT q, n, busy, el, readings, CAST({_RULE} AS INTEGER) AS delta FROM ({_GRID})")
def _(s, d):
    control.register_sql(s, FIGURE)
    return grid(s, d).selectExpr("*", "scale_delta(q, busy, n, el) AS delta")


def recorded(s: SparkSession, d: str) -> DataFrame:
    """Hourly series of the events as a recorded signal: queue = arrivals over 12, busy workers = arrivals // 5, one poll a second."""
    return hourly(s, d).select("run_id", (F.col("b") * 1000).alias("t_ms"), F.greatest(F.col("a") - 12, F.lit(0)).cast("long").alias("q"), F.floor(F.col("a") / 5).cast("int").alias("busy"))


def _replay_sql(c: RunConfig) -> str:
    over = " OR ".join(["q2 > %d" % c.queue_hi] * c.use_queue + ["busy2 * 1000 > n * %d" % c.util_hi_pm] * c.use_util)
    d = f"CASE WHEN t2 - last < {c.cooldown_ms} THEN 0 WHEN {over} THEN least({c.step}, {c.n_max} - n) WHEN q2 = 0 AND busy2 * 1000 < n * {c.util_lo_pm} THEN -least({c.step_down}, n - {c.n_min}, n - busy2) ELSE 0 END"
    return f"""WITH RECURSIVE {_HOURS}, sg AS (SELECT b, b * 1000 AS t_ms, greatest(a - 12, 0) AS q, a // 5 AS busy FROM ab), f AS (
      SELECT CAST(-1 AS BIGINT) AS b, CAST(0 AS BIGINT) AS t_ms, CAST(0 AS BIGINT) AS q, CAST(0 AS BIGINT) AS busy, CAST(0 AS BIGINT) AS n0, CAST(0 AS BIGINT) AS delta, CAST({c.n_init} AS BIGINT) AS n, CAST({NEVER} AS BIGINT) AS last
      UNION ALL SELECT b2, t2, q2, busy2, n, d, n + d, CASE WHEN d <> 0 THEN t2 ELSE last END FROM (SELECT *, CAST({d} AS BIGINT) AS d FROM (SELECT f.n, f.last, sg.b AS b2, sg.t_ms AS t2, sg.q AS q2, least(sg.busy, f.n) AS busy2 FROM f JOIN sg ON sg.b = f.b + 1)))
    SELECT 'events' AS run_id, t_ms, q, CAST(busy AS INTEGER) AS busy, CAST(n0 AS INTEGER) AS n_before, CAST(delta AS INTEGER) AS delta, CAST(n AS INTEGER) AS n_after FROM f WHERE b >= 0"""


for _n, _c in (("events", FIGURE), ("no_cooldown", FIGURE.but(cooldown_ms=0)), ("queue_only", FIGURE.but(use_util=False)), ("util_only", FIGURE.but(use_queue=False)), ("step_one", FIGURE.but(step=1, step_down=1))):
    add(f"replay_{_n}", lambda s, d, c=_c: queueing.replay(recorded(s, d), c), _replay_sql(_c))

# ---- flagship -------------------------------------------------------------------------------------------------------------------------------------------
for _n, _c in (("elastic", FIGURE), ("elastic_text", TEXT), ("elastic_cpu_signal", FIGURE.but(use_queue=False, cpu_share_pm=300)), ("elastic_no_cooldown", FIGURE.but(cooldown_ms=0)), ("elastic_util_only", FIGURE.but(use_queue=False)), ("elastic_step_one", FIGURE.but(step=1, step_down=1)), ("elastic_step_four", FIGURE.but(step=4, step_down=4)), ("elastic_queue_only", FIGURE.but(use_util=False))):
    add(f"{_n}_results", lambda s, d, c=_c: kernel.results(sim(s, d, c)), O.elastic(_c, f"SELECT {RES} FROM res"))
    add(f"{_n}_polls", lambda s, d, c=_c: kernel.polls(sim(s, d, c)), O.elastic(_c, f"SELECT {POL} FROM pol"))
add("elastic_scale_events", lambda s, d: kernel.scale_events(sim(s, d, FIGURE)), O.elastic(FIGURE, "SELECT run_id, shard, j, t_ms, q, busy, n_before, delta, n_after FROM pol WHERE delta <> 0"))
add("elastic_fifo_results", lambda s, d: kernel.results(sim(s, d, FIGURE, prio="const")), O.elastic(FIGURE, f"SELECT {RES} FROM res", prio="const"))
add("elastic_quality_results", lambda s, d: kernel.results(sim(s, d, FIGURE, "quality")), O.elastic(FIGURE, f"SELECT {RES} FROM res", task="quality"))
add("elastic_heavy_results", lambda s, d: kernel.results(sim(s, d, FIGURE, role="zs_heavy")), O.elastic(FIGURE, f"SELECT {RES} FROM res", role="zs_heavy"))


def l95(values) -> F.Column:
    """95th percentile of a sorted array by linear interpolation; null for an empty one."""
    at = (F.size(values) - 1) * 0.95
    lo = F.floor(at).cast("int")
    low, high = F.get(values, lo), F.get(values, F.least(lo + 1, F.size(values) - 1))
    return F.when(F.size(values) > 0, F.round(low + (high - low) * (at - lo), 4))


def snapshots(x: DataFrame, window: int = FIGURE.lat_window, time_ms: int | None = None) -> DataFrame:
    """Polls with the 95th percentile of recent service times: of the last ``window`` completions, or of those within ``time_ms``. Polls and completions are one
    ordered series, and a frame holds no more than the window's completions: nothing is joined to all of a run."""
    done = kernel.results(x).select("run_id", "shard", F.col("finish_ms").alias("t_ms"), F.lit(0).alias("g"), "worker_id", "svc_ms")
    own = Window.partitionBy("run_id", "shard")
    cols = ("run_id", "shard", "j", "t_ms", "q", "n_before", "util_pm", "l95_ms", "done")
    p = kernel.polls(x).withColumn("g", F.lit(1))
    if time_ms:
        u = p.unionByName(done, allowMissingColumns=True)
        recent = F.array_sort(F.collect_list("svc_ms").over(own.orderBy("t_ms").rangeBetween(-(time_ms - 1), 0)))
        return u.withColumn("l95_ms", l95(recent)).where("g = 1").select(*cols)
    order = ("t_ms", "g", "worker_id", "svc_ms")
    last = F.array_sort(F.collect_list("svc_ms").over(own.orderBy(*order).rowsBetween(-(window - 1), 0)))
    u = p.unionByName(done.withColumn("v", l95(last)), allowMissingColumns=True)
    return u.withColumn("l95_ms", F.last("v", ignorenulls=True).over(own.orderBy(*order))).where("g = 1").select(*cols)


_L95 = "SELECT p.run_id, p.shard, p.j, p.t_ms, p.q, p.n_before, p.util_pm, (SELECT round(quantile_cont(svc_ms, 0.95), 4) FROM ({}) w) AS l95_ms, p.done FROM pol p"
add(
    "elastic_snapshots",
    lambda s, d: snapshots(sim(s, d, FIGURE), 20),
    O.elastic(
        FIGURE,
        _L95.format("SELECT svc_ms FROM res WHERE finish_ms <= p.t_ms ORDER BY finish_ms DESC, worker_id DESC, svc_ms DESC LIMIT 20").replace("(SELECT round", "(SELECT round"),
    ),
)
add(
    "elastic_snapshots_time",
    lambda s, d: snapshots(sim(s, d, FIGURE), time_ms=30_000),
    O.elastic(FIGURE, _L95.format("SELECT svc_ms FROM res WHERE finish_ms <= p.t_ms AND finish_ms > p.t_ms - 30000")),
)
add(
    "elastic_status_log",
    lambda s, d: kernel.polls(sim(s, d, FIGURE)).select("j", F.concat(F.lit("t="), "t_ms", F.lit(" q="), "q", F.lit(" n="), "n_before", F.lit(" busy="), "busy", F.lit(" util="), "util_pm", F.when(F.col("delta") > 0, F.concat(F.lit(" scale=+"), "delta")).when(F.col("delta") < 0, F.concat(F.lit(" scale="), "delta")).otherwise("")).alias("line")),
    O.elastic(
        FIGURE,
        (
            "SELECT j, 't=' || t_ms || ' q=' || q || ' n=' || n_before || ' busy=' || busy || ' util=' || util_pm || CASE WHEN delta > 0 THEN ' scale=+' || delta "
            "WHEN delta < 0 THEN ' scale=' || delta ELSE '' END AS line FROM pol"
        ),
    ),
)
_NEXT = "lead({}) OVER (PARTITION BY run_id ORDER BY j)"
_L20 = (
    "(SELECT round(quantile_cont(svc_ms, 0.95), 4) FROM (SELECT svc_ms FROM res WHERE res.run_id = p.run_id AND finish_ms <= p.t_ms "
    "ORDER BY finish_ms DESC, worker_id DESC, svc_ms DESC LIMIT 20) w)"
)
EXPERIENCE = (
    f"l20 AS (SELECT p.*, {_L20} AS l95_ms FROM pol p), ex AS (SELECT run_id, t_ms, q, n_before AS n, util_pm, l95_ms, delta AS action, {_NEXT.format('q')} AS q_next, "
    f"{_NEXT.format('n_before')} AS n_next, {_NEXT.format('util_pm')} AS util_next, {_NEXT.format('l95_ms')} AS l95_next FROM l20)"
)
add("elastic_experience", lambda s, d: experience(sim(s, d, FIGURE)), O.elastic(FIGURE, f", {EXPERIENCE} SELECT * FROM ex"))
add(
    "elastic_verify",
    lambda s, d: kernel.scale_events(sim(s, d, FIGURE)).groupBy("run_id").agg(F.max(F.when(F.col("delta") > 0, 1).otherwise(0)).alias("scaled_out"), F.max(F.when(F.col("delta") < 0, 1).otherwise(0)).alias("scaled_in")),
    O.elastic(
        FIGURE,
        "SELECT run_id, max(CASE WHEN delta > 0 THEN 1 ELSE 0 END) AS scaled_out, max(CASE WHEN delta < 0 THEN 1 ELSE 0 END) AS scaled_in FROM pol WHERE delta <> 0 GROUP BY 1",
    ),
)


def experience(x: DataFrame, window: int = 20) -> DataFrame:
    """State, action and the next poll's state, with the latency that each poll saw."""
    w = Window.partitionBy("run_id", "shard").orderBy("j")
    p = kernel.polls(x).join(snapshots(x, window).select("run_id", "shard", "j", "l95_ms"), ["run_id", "shard", "j"])
    return p.select(
        "run_id", "t_ms", "q", F.col("n_before").alias("n"), "util_pm", "l95_ms", F.col("delta").alias("action"), F.lead("q").over(w).alias("q_next"), F.lead("n_before").over(w).alias("n_next"),
        F.lead("util_pm").over(w).alias("util_next"), F.lead("l95_ms").over(w).alias("l95_next"),
    )


@query(
    "experience_advise",
    O.elastic(FIGURE, f", e AS (SELECT q // 10 AS qb, n_before AS n, util_pm // 250 AS ub, delta AS action, {_NEXT.format('q')} AS q_next FROM pol) SELECT qb, n, ub, action, count(*) AS seen, round(CAST(sum(q_next) AS DOUBLE) / count(q_next), 6) AS q_next FROM e WHERE q_next IS NOT NULL GROUP BY 1, 2, 3, 4").replace(") , e AS", "), e AS"),
)
def _(s, d):
    """Advice from stored experience: mean next queue by coarse state and action. It is read only; the rule never sees it."""
    e = experience(sim(s, d, FIGURE)).where("q_next IS NOT NULL")
    return e.groupBy(F.floor(F.col("q") / 10).alias("qb"), "n", F.floor(F.col("util_pm") / 250).cast("int").alias("ub"), "action").agg(F.count("*").alias("seen"), F.round(F.sum("q_next") / F.count("q_next"), 6).alias("q_next"))


# ---- classifiers ----------------------------------------------------------------------------------------------------------------------------------------
def _pred(name: str, task: str, role: str, expr: str) -> None:
    add(name, lambda s, d: ingest.labelled(s, d, task).select("doc_id", "y", runs.label_of(role, task).alias("y_hat")), f"WITH {O.src(task)} SELECT doc_id, y, {expr} AS y_hat FROM (SELECT *, {O.TOK} AS tok FROM src)")


_SHAPE = r"CASE WHEN length(regexp_replace(text, '[^\p{L}]', '', 'g')) * 1000 < length(text) * 735 OR len(list_distinct(tok)) * 1000 < len(tok) * 450 THEN 'junk' ELSE 'clean' END"
for _t in ("lang", "toxic", "quality"):
    for _r in ("zs_fast", "zs_heavy", "zs_weak", "hash"):
        _pred(f"zs_shape_{_t}" if (_r, _t) == ("zs_heavy", "quality") else f"{_r}_label_{_t}" if _r == "hash" else f"{_r}_{_t}", _t, _r, O.label(_r, _t))


def nb_tables(task: str) -> str:
    """Naive Bayes over the training split, ending in nbp(task_id, y, y_hat); after src, reps and samp."""
    tok = O.TOK
    return f"""{_train_sql(task)},
    tt AS (SELECT t.y, unnest({tok}) AS token FROM train t JOIN documents d USING (doc_id)), c0 AS (SELECT token, y, count(*) AS c FROM tt GROUP BY 1, 2),
    voc AS (SELECT token FROM c0 GROUP BY 1 HAVING sum(c) >= 2), c AS (SELECT * FROM c0 WHERE token IN (SELECT token FROM voc)),
    cl AS (SELECT p.y, ln(p.n / (SELECT count(*) FROM train)) AS prior, -ln(coalesce(k.total, 0) + CASE WHEN k.total IS NULL THEN 1 ELSE (SELECT count(*) FROM voc) END) AS other FROM (SELECT y, count(*) AS n FROM train GROUP BY 1) p LEFT JOIN (SELECT y, sum(c) AS total FROM c GROUP BY 1) k USING (y)),
    et AS (SELECT doc_id, token, count(*) AS k FROM (SELECT s.doc_id, unnest({tok}) AS token FROM samp s JOIN documents d USING (doc_id)) WHERE token IN (SELECT token FROM voc) GROUP BY 1, 2),
    ln_ AS (SELECT doc_id, sum(k) AS len FROM et GROUP BY 1), sc AS (SELECT doc_id, y, sum(k * ln(c + 1)) AS s FROM et JOIN c USING (token) GROUP BY 1, 2),
    gr AS (SELECT s.doc_id, s.y AS y0, cl.y, round(cl.prior + coalesce(len, 0) * cl.other + coalesce(sc.s, 0), 6) AS s FROM samp s CROSS JOIN cl LEFT JOIN ln_ USING (doc_id) LEFT JOIN sc ON sc.doc_id = s.doc_id AND sc.y = cl.y),
    nbp AS (SELECT doc_id AS task_id, y0 AS y, y AS y_hat FROM (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY s DESC, y) AS r FROM gr) WHERE r = 1)"""


def nb_sql(task: str) -> str:
    return f"WITH {O.src(task)}, {O.reps()}, {O.samp()}, {nb_tables(task)} SELECT * FROM nbp"


def roles_sql(task: str, roles) -> str:
    """pr_<role>(doc_id, y, y_hat) for each role, after src, reps and samp."""
    parts = [f"st AS (SELECT s.doc_id, s.y, d.text, {O.TOK} AS tok FROM samp s JOIN documents d USING (doc_id))"]
    if {"supervised", "majority"} & set(roles):
        parts.append(nb_tables(task))
    for r in sorted(set(roles)):
        if r == "supervised":
            parts.append("pr_supervised AS (SELECT task_id AS doc_id, y, y_hat FROM nbp)")
        elif r == "majority":
            parts.append("pr_majority AS (SELECT doc_id, y, (SELECT y FROM train GROUP BY y ORDER BY count(*) DESC, y LIMIT 1) AS y_hat FROM st)")
        else:
            parts.append(f"pr_{r} AS (SELECT doc_id, y, {O.label(r, task)} AS y_hat FROM st)")
    return ", ".join(parts)


for _t in ("lang", "quality"):
    add(f"nb_{_t}", lambda s, d, t=_t: runs.predictions(s, d, t, "supervised", materialise(runs.sample(s, d, t), "sample")), nb_sql(_t))
add(
    "majority_quality",
    lambda s, d: classify.majority(train(s, d, "quality")[0]),
    f"WITH {O.src('quality')}, {O.reps()}, {O.samp()}, {_train_sql('quality')} SELECT y AS y_hat FROM train GROUP BY y ORDER BY count(*) DESC, y LIMIT 1",
)
_C6 = (
    "e AS (SELECT vec_id, label, [CAST(floor(CAST(x AS DOUBLE) * 1000) AS BIGINT) FOR x IN embedding] AS v "
    "FROM embeddings), c AS (SELECT label, i, CAST(floor(CAST(sum(v[i]) AS DOUBLE) / count(*)) AS BIGINT) AS c FROM e, (SELECT unnest(range(1, 65)) AS i) "
    "GROUP BY 1, 2), m AS (SELECT label AS y_hat, list(c ORDER BY i) AS m FROM c GROUP BY 1), dd AS (SELECT vec_id, y_hat, CAST(list_sum([(v[i] - m[i]) * (v[i] - m[i]) FOR i "
    "IN range(1, 65)]) AS BIGINT) AS d FROM e, m)"
)
add(
    "centroid_embeddings",
    lambda s, d: classify.nearest_centroid(ingest.table(s, d, "embeddings"), classify.centroids(ingest.table(s, d, "embeddings"))),
    f"WITH {_C6} SELECT vec_id, y_hat, d FROM (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY d, y_hat) AS r FROM dd) WHERE r = 1",
)
_BAD = "substr(md5(CAST(doc_id AS VARCHAR)), 1, 1) = '0'"
add(
    "faulty_results",
    lambda s, d: classify.with_faults(ingest.labelled(s, d, "lang").select("doc_id", "y", classify.zs_fast("lang").alias("y_hat"))),
    f"WITH {O.src('lang')} SELECT doc_id, y, CASE WHEN {_BAD} THEN '__error__' ELSE {O.zs('lang')} END AS y_hat, NOT {_BAD} AS ok FROM (SELECT *, {O.TOK} AS tok FROM src)",
)


def _lexicon_or_fail():
    def f(text: str) -> str:
        if not text or text[0] == "T":
            raise ValueError("refused")
        return "en" if " the " in text else "other"

    return f


add(
    "guarded_external",
    lambda s, d: classify.guarded(ingest.table(s, d, "documents"), _lexicon_or_fail),
    (
        "SELECT doc_id, CASE WHEN text = '' OR text[1] = 'T' THEN '__error__' WHEN contains(text, ' the ') THEN 'en' "
        "ELSE 'other' END AS y_hat, NOT (text = '' OR text[1] = 'T') AS ok, CASE WHEN text = '' OR text[1] = 'T' THEN 'ValueError' END AS err FROM documents"
    ),
)

# ---- measures over the five configurations -----------------------------------------------------------------------------------------------------------------
MATRIX = [("zs_fast", O.zs("lang")), ("zs_weak", O.zs("lang", weak=True))]
_P = "pred AS (" + " UNION ALL ".join(f"SELECT '{r}' AS run_id, doc_id AS task_id, y, {e} AS y_hat FROM st" for r, e in MATRIX) + ")"
_PRED = f"WITH {O.src('lang')}, {O.reps()}, {O.samp()}, st AS (SELECT s.doc_id, s.y, {O.TOK} AS tok FROM samp s JOIN documents d USING (doc_id)), {_P} "
_PQ = (
    f"WITH {O.src('quality')}, {O.reps()}, {O.samp()}, st AS (SELECT s.doc_id, s.y, text, {O.TOK} AS tok FROM samp s "
    f"JOIN documents d USING (doc_id)), pred AS (SELECT 'zs_weak' AS run_id, doc_id AS task_id, y, {O.zs('quality', weak=True)} AS y_hat FROM st UNION ALL "
    f"SELECT 'zs_heavy', doc_id, y, {_SHAPE} FROM st) "
)


def matrix(s: SparkSession, d: str, task: str = "lang", roles: tuple[str, ...] = ("zs_fast", "zs_weak")) -> DataFrame:
    rows = runs.sample(s, d, task)
    out = None
    for r in roles:
        p = runs.predictions(s, d, task, r, rows).withColumn("run_id", F.lit(r))
        out = p if out is None else out.unionByName(p)
    return out


_HIT = "CAST(sum(CASE WHEN y = y_hat THEN 1 ELSE 0 END) AS BIGINT)"
add("accuracy_matrix", lambda s, d: measures.accuracy(matrix(s, d)), _PRED + f"SELECT run_id, count(*) AS n, {_HIT} AS correct, round({_HIT} / count(*), 6) AS accuracy FROM pred GROUP BY 1")
add("per_class_accuracy", lambda s, d: measures.per_class(matrix(s, d)), _PRED + f"SELECT run_id, y, count(*) AS n, {_HIT} AS correct, round({_HIT} / count(*), 6) AS accuracy FROM pred GROUP BY 1, 2")
add("confusion", lambda s, d: measures.confusion(matrix(s, d)), _PRED + "SELECT run_id, y, y_hat, count(*) AS n FROM pred GROUP BY 1, 2, 3")
add(
    "op_pivot_confusion",
    lambda s, d: measures.confusion(matrix(s, d)).groupBy("run_id", "y").pivot("y_hat", ["de", "en", "es", "fr"]).agg(F.sum("n")).na.fill(0),
    _PRED + "SELECT run_id, y, " + ", ".join(f"count(*) FILTER (y_hat = '{v}') AS {v}" for v in ("de", "en", "es", "fr")) + " FROM pred GROUP BY 1, 2",
)
add(
    "precision_f1",
    lambda s, d: measures.precision_f1(matrix(s, d, "quality", ("zs_weak", "zs_heavy"))),
    _PQ + ", k AS (SELECT run_id, y, count(*) AS i, CAST(sum(CASE WHEN y = y_hat THEN 1 ELSE 0 END) AS BIGINT) AS tp FROM pred GROUP BY 1, 2), s AS (SELECT run_id, y_hat AS y, count(*) AS said FROM pred GROUP BY 1, 2) SELECT run_id, y, CASE WHEN coalesce(said, 0) > 0 THEN round(tp / said, 6) ELSE 0 END AS precision, round(tp / i, 6) AS recall, round(2 * tp / (coalesce(said, 0) + i), 6) AS f1 FROM k LEFT JOIN s USING (run_id, y)",
)
add(
    "recall_positive",
    lambda s, d: measures.recall(matrix(s, d, "quality", ("zs_weak", "zs_heavy")), "junk"),
    _PQ + f"SELECT run_id, round({_HIT} / count(*), 6) AS recall, count(*) AS n, {_HIT} AS correct FROM pred WHERE y = 'junk' GROUP BY 1",
)

ALL_POLICIES = (*runs.FIVE, "B6", "B7", "Bmax", "B8")


def policies_sql(names: tuple[str, ...], select: str, task: str = "lang") -> str:
    """Runs of named policies; the sized ones take their number of workers from the tasks."""
    sized = [n for n in names if n in runs.SIZED]
    cfgs = [(O.sized(runs.POLICIES[n][0], runs.SIZED[n]) if n in sized else runs.POLICIES[n][0], runs.POLICIES[n][1]) for n in names]
    return O.several(cfgs, select, task, more=O.sizes(tasks_="tk_zs_fast_source") if sized else "")


def _m(name: str, f, select: str, policies: tuple[str, ...] = ALL_POLICIES) -> None:
    add(name, lambda s, d: f(kernel.results(runs.compare(s, d, "lang", policies))), policies_sql(policies, select))


_m(
    "latency_summary",
    measures.latency,
    (
        "SELECT run_id, count(*) AS n, round(sum(svc_ms) / count(*), 6) AS svc_mean, round(quantile_cont(svc_ms, 0.95), 6) AS svc_p95, round(sum(wait_ms) / count(*), 6) AS "
        "wait_mean, round(quantile_cont(wait_ms, 0.95), 6) AS wait_p95, round(sum(sojourn_ms) / count(*), 6) AS sojourn_mean, round(quantile_cont(sojourn_ms, 0.5), 6) AS "
        "sojourn_p50, round(quantile_cont(sojourn_ms, 0.95), 6) AS sojourn_p95, max(sojourn_ms) AS sojourn_max FROM res GROUP BY 1"
    ),
)
MARKED = (
    f"e AS (SELECT run_id, max(finish_ms) AS r FROM res GROUP BY 1), mk AS (SELECT res.*, greatest(CAST(ceil(CAST(finish_ms * {N_MARKS} AS DOUBLE) / r) AS INTEGER), 1) AS mark "
    "FROM res JOIN e USING (run_id))"
)
EDGES = f"g AS (SELECT run_id, CAST(m AS INTEGER) AS mark, m * r // {N_MARKS} AS t_ms FROM (SELECT run_id, max(finish_ms) AS r FROM res GROUP BY 1), (SELECT unnest(range(1, {N_MARKS + 1})) AS m))"
_DEP = (
    ", ch AS (SELECT run_id, t, sum(d) AS d FROM (SELECT run_id, enq_ms AS t, 1 AS d FROM res UNION ALL SELECT run_id, start_ms, -1 FROM res) "
    "GROUP BY 1, 2), dq AS (SELECT run_id, t, sum(d) OVER (PARTITION BY run_id ORDER BY t) AS q, lead(t) OVER (PARTITION BY run_id ORDER BY t) - t AS dt FROM ch)"
)
_m(
    "queue_summary",
    measures.queue_summary,
    _DEP + " SELECT run_id, CAST(peak AS BIGINT) AS peak, drain_ms, round(area / runtime, 6) AS mean_depth FROM (SELECT run_id, max(q) AS peak, sum(q * coalesce(dt, 0)) AS area FROM dq GROUP BY 1) JOIN (SELECT run_id, greatest(max(start_ms) - max(enq_ms), 0) AS drain_ms, max(finish_ms) - min(enq_ms) AS runtime FROM res GROUP BY 1) USING (run_id)",
)
_m("priority_wait", measures.priority_wait, "SELECT run_id, prio, count(*) AS n, round(sum(wait_ms) / count(*), 6) AS wait_mean, max(wait_ms) AS wait_max FROM res GROUP BY 1, 2")
add(
    "oscillations",
    lambda s, d: measures.oscillations(kernel.scale_events(sim(s, d, FIGURE.but(cooldown_ms=0))), 10_000),
    O.elastic(
        FIGURE.but(cooldown_ms=0),
        (
            ", e AS (SELECT run_id, delta, t_ms, lag(delta) OVER (ORDER BY t_ms) AS pd, lag(t_ms) OVER (ORDER BY t_ms) AS pt FROM pol WHERE delta <> 0) "
            "SELECT run_id, count(*) AS events, CAST(sum(abs(delta)) AS BIGINT) AS moved, CAST(sum(CASE WHEN sign(delta) <> sign(pd) AND t_ms - pt <= 10000 THEN 1 "
            "ELSE 0 END) AS BIGINT) AS turns FROM e GROUP BY 1"
        ),
    ),
)
add(
    "reaction_time",
    lambda s, d: (lambda x: measures.reaction(kernel.results(x), kernel.scale_events(x), 8))(sim(s, d, FIGURE)),
    O.elastic(
        FIGURE,
        (
            "SELECT run_id, (SELECT min(t_ms) FROM pol WHERE delta > 0) - min(enq_ms) AS first_out_ms, (SELECT min(t_ms) FROM pol "
            "WHERE n_after = 8 AND delta <> 0) - min(enq_ms) AS full_ms FROM res GROUP BY 1"
        ),
    ),
)


# ---- sweeps and shards ------------------------------------------------------------------------------------------------------------------------------------------
def sweep(s: SparkSession, d: str, small: bool) -> DataFrame:
    x = kernel.simulate(runs.tasks(s, d), runs.sweep_grid(small))
    return kernel.results(x).groupBy("run_id").agg(F.max("finish_ms").alias("makespan_ms"), F.sum("wait_ms").alias("wait_ms"), F.max("worker_id").alias("workers"))


_SMALL = runs.sweep_grid(True)
add(
    "sweep_bounds",
    lambda s, d: sweep(s, d, True),
    O.several([(c, "zs_fast") for c in _SMALL], "SELECT run_id, max(finish_ms) AS makespan_ms, CAST(sum(wait_ms) AS BIGINT) AS wait_ms, max(worker_id) AS workers FROM res GROUP BY 1"),
)
add("sweep_thresholds", lambda s, d: sweep(s, d, False))


@query("sweep_pareto")
def _(s, d):
    """Configurations that no other beats in both mean wait and worker time."""
    x = materialise(kernel.simulate(runs.tasks(s, d), runs.sweep_grid(False)), "sweep")
    r = kernel.results(x)
    w = measures.seconds(r, kernel.polls(x)).select("run_id", "worker_ms").join(r.groupBy("run_id").agg(F.sum("wait_ms").alias("wait_ms")), "run_id")
    w = materialise(w, "pareto")
    o = w.select(F.col("wait_ms").alias("w2"), F.col("worker_ms").alias("c2"))
    return w.join(F.broadcast(o), (F.col("w2") <= F.col("wait_ms")) & (F.col("c2") <= F.col("worker_ms")) & ((F.col("w2") < F.col("wait_ms")) | (F.col("c2") < F.col("worker_ms"))), "left_anti")


_OT = f"""ot AS (SELECT c_nationkey AS shard, row_number() OVER (PARTITION BY c_nationkey ORDER BY o_orderdate, l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus) - 1 AS seq, count(*) OVER (PARTITION BY c_nationkey) AS n_all, CAST(substr(o_orderpriority, 1, 1) AS INTEGER) AS prio, CAST(floor(l_quantity) AS BIGINT) * 200 AS svc_ms FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey),
  tk AS (SELECT shard, seq, prio, {O.arrival('seq', 'n_all', ArrivalSpec(window_ms=3_600_000))} AS enq_ms, svc_ms FROM ot)"""
add(
    "shards_orders_tasks",
    lambda s, d: runs.order_tasks(s, d).groupBy("shard", "prio").agg(F.count("*").alias("n"), F.sum("enq_ms").alias("enq_ms"), F.sum("svc_ms").alias("svc_ms")),
    f"WITH {_OT} SELECT shard, prio, count(*) AS n, CAST(sum(enq_ms) AS BIGINT) AS enq_ms, CAST(sum(svc_ms) AS BIGINT) AS svc_ms FROM tk GROUP BY 1, 2",
)
add(
    "shards_orders_sequential",
    lambda s, d: queueing.sequential(runs.order_tasks(s, d)).groupBy("shard").agg(F.max("finish_ms").alias("makespan_ms"), F.sum("wait_ms").alias("wait_ms")),
    (
        f"WITH {_OT}, c AS (SELECT *, sum(svc_ms) OVER (PARTITION BY shard ORDER BY seq) AS c FROM tk), f AS (SELECT *, c + max(enq_ms - c + svc_ms) OVER (PARTITION BY shard "
        "ORDER BY seq) AS fin FROM c) SELECT shard, CAST(max(fin) AS BIGINT) AS makespan_ms, CAST(sum(fin - svc_ms - enq_ms) AS BIGINT) AS wait_ms FROM f GROUP BY 1"
    ),
)
ORDERS = FIGURE.but(run_id="orders", n_max=16)
add(
    "shards_orders_elastic",
    lambda s, d: kernel.results(kernel.simulate(runs.order_tasks(s, d), [ORDERS])).groupBy("shard").agg(F.count("*").alias("n"), F.max("finish_ms").alias("makespan_ms"), F.sum("wait_ms").alias("wait_ms")),
)
_STARTS = ("run_id", "shard", "seq", "prio", "enq_ms", "start_ms")
add("shard_inversions", lambda s, d: measures.inversions(materialise(kernel.results(kernel.simulate(runs.order_tasks(s, d), [ORDERS])).select(*_STARTS), "starts")))
