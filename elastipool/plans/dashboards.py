"""The five configurations on the four-language and the skewed binary data: task-level results, report, traces, accuracy by class, scores, faults, invariance.

Each configuration keeps its own classifier. Every run's tasks are classified for that run alone, so a report never borrows another run's predictions.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from elastipool.model import N_MARKS, POSITIVE, ArrivalSpec
from elastipool.operators import classify, kernel, measures
from elastipool.plans import oracle as O
from elastipool.plans import runs
from elastipool.plans.catalog import EDGES, MARKED, add, policies_sql, roles_sql
from elastipool.session import materialise

TASKS = ("lang", "quality")
ROLE = {p: runs.POLICIES[p][1] for p in runs.POLICIES}
BURST_MS = ArrivalSpec().window_ms * ArrivalSpec().burst_pm // 1000


def configs(names: tuple[str, ...] = runs.FIVE):
    return [runs.POLICIES[n][0] for n in names]


def run_five(s: SparkSession, d: str, task: str, faults: bool = False) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """(results, polls, fixed pools, task-level outcomes) of the five configurations."""
    x = runs.compare(s, d, task)
    res = kernel.results(x)
    out = materialise(runs.outcomes(s, d, task, res, {n: ROLE[n] for n in runs.FIVE}, faults), "outcomes")
    return res, kernel.polls(x), runs.fixed(s, configs()), out


def report(s: SparkSession, d: str, task: str) -> tuple[DataFrame, DataFrame]:
    """(report, outcomes): one row a configuration."""
    res, polls, fixed, out = run_five(s, d, task)
    return measures.report(res, out, measures.seconds(res, polls, fixed)).join(measures.class_line(out), "run_id"), out


# ---- SQL of the same -----------------------------------------------------------------------------------------------------------------------------------
_TASKS_SQL = "oc AS (" + " UNION ALL ".join(
    f"SELECT r.run_id, r.task_id, r.seq, r.prio, p.y, p.y_hat, p.y = p.y_hat AS correct, true AS ok, r.worker_id, r.enq_ms, r.start_ms, r.finish_ms, r.svc_ms, r.wait_ms, r.sojourn_ms "
    f"FROM res r JOIN pr_{ROLE[n]} p ON p.doc_id = r.task_id WHERE r.run_id = '{n}'" for n in runs.FIVE
) + ")"
_INIT = ", ".join(f"('{c.run_id}', 0, {c.n_init})" for c in configs())
_WORK_SQL = f"""ev AS (SELECT run_id, t_ms, n_after AS n FROM pol WHERE delta <> 0 UNION ALL SELECT * FROM (VALUES {_INIT}) v(run_id, t_ms, n)),
  en AS (SELECT run_id, max(finish_ms) AS e, sum(svc_ms) AS busy FROM res GROUP BY 1),
  sp AS (SELECT ev.run_id, n * (coalesce(lead(t_ms) OVER (PARTITION BY ev.run_id ORDER BY t_ms), e) - t_ms) AS w FROM ev JOIN en USING (run_id) WHERE t_ms < e),
  ws AS (SELECT run_id, CAST(sum(w) AS BIGINT) AS worker_ms, CAST(any_value(busy) AS BIGINT) AS busy_ms FROM sp JOIN en USING (run_id) GROUP BY 1)"""
_HIT = "CAST(sum(CASE WHEN y = y_hat THEN 1 ELSE 0 END) AS BIGINT)"
_REPORT_SQL = f"""ac AS (SELECT run_id, {_HIT} AS correct, round({_HIT} / count(*), 6) AS accuracy FROM oc GROUP BY 1),
  rt AS (SELECT run_id, count(*) AS n, max(finish_ms) - min(enq_ms) AS runtime_ms, round(sum(wait_ms) / count(*), 6) AS wait_mean,
    round(sum(sojourn_ms) / count(*), 6) AS sojourn_mean, round(quantile_cont(sojourn_ms, 0.95), 6) AS sojourn_p95 FROM res GROUP BY 1),
  pc AS (SELECT run_id, string_agg(y || '=' || printf('%.4f', a), ' ' ORDER BY y) AS per_class FROM (SELECT run_id, y, round({_HIT} / count(*), 6) AS a FROM oc GROUP BY 1, 2) GROUP BY 1),
  rep AS (SELECT run_id, correct, accuracy, n, runtime_ms, wait_mean, sojourn_mean, sojourn_p95, worker_ms, round(busy_ms / worker_ms, 6) AS utilisation,
    round(n * 60000 / runtime_ms, 6) AS per_minute, round(correct * 6000000 / (n * runtime_ms), 6) AS efficiency, per_class
    FROM ac JOIN rt USING (run_id) JOIN ws USING (run_id) JOIN pc USING (run_id))"""


def sql(task: str, select: str) -> str:
    """``select`` over res, pol and oc (task-level outcomes) of the five configurations."""
    return policies_sql(runs.FIVE, f", {roles_sql(task, [ROLE[n] for n in runs.FIVE])}, {_TASKS_SQL} {select}", task)


_BAD = "substr(md5(CAST(task_id AS VARCHAR)), 1, 1) = '0'"
_POOL = f"coalesce((SELECT arg_max(n_after, j) FROM pol p WHERE p.run_id = g.run_id AND p.t_ms <= g.t_ms), (SELECT n FROM (VALUES {_INIT}) v(run_id, t, n) WHERE v.run_id = g.run_id))"
_BUSY = "(SELECT count(*) FROM res x WHERE x.run_id = g.run_id AND start_ms <= g.t_ms AND finish_ms > g.t_ms)"
for _t in TASKS:
    add(f"five_{_t}_tasks", lambda s, d, t=_t: run_five(s, d, t)[3], sql(_t, "SELECT * FROM oc"))
    add(f"five_{_t}_report", lambda s, d, t=_t: report(s, d, t)[0], sql(_t, f", {_WORK_SQL}, {_REPORT_SQL} SELECT * FROM rep"))
    add(
        f"five_{_t}_classes",
        lambda s, d, t=_t: measures.per_class(run_five(s, d, t)[3]),
        sql(_t, f"SELECT run_id, y, count(*) AS n, {_HIT} AS correct, round({_HIT} / count(*), 6) AS accuracy FROM oc GROUP BY 1, 2"),
    )
    add(f"five_{_t}_confusion", lambda s, d, t=_t: measures.confusion(run_five(s, d, t)[3]), sql(_t, "SELECT run_id, y, y_hat, count(*) AS n FROM oc GROUP BY 1, 2, 3"))
    add(
        f"five_{_t}_workers", lambda s, d, t=_t: (lambda r: measures.worker_trace(r[0], r[1], n_fixed=r[2]))(run_five(s, d, t)),
        policies_sql(runs.FIVE, f", {EDGES} SELECT run_id, mark, t_ms, CAST({_POOL} AS BIGINT) AS n FROM g", _t),
    )
    add(
        f"five_{_t}_queue", lambda s, d, t=_t: measures.queue_trace(kernel.results(runs.compare(s, d, t))),
        policies_sql(runs.FIVE, f", {EDGES} SELECT run_id, mark, t_ms, (SELECT count(*) FROM res x WHERE x.run_id = g.run_id AND enq_ms <= t_ms) - (SELECT count(*) FROM res x WHERE x.run_id = g.run_id AND start_ms <= t_ms) AS q FROM g", _t),
    )
    add(
        f"five_{_t}_latency", lambda s, d, t=_t: measures.latency_trace(kernel.results(runs.compare(s, d, t))),
        policies_sql(runs.FIVE, f", {MARKED} SELECT run_id, mark, count(*) AS n, round(sum(sojourn_ms) / count(*), 6) AS sojourn_mean FROM mk GROUP BY 1, 2", _t),
    )
    add(
        f"five_{_t}_throughput", lambda s, d, t=_t: measures.throughput_trace(kernel.results(runs.compare(s, d, t))),
        policies_sql(runs.FIVE, f""", {MARKED}, gm AS (SELECT run_id, r, CAST(m AS INTEGER) AS mark FROM e, (SELECT unnest(range(1, {N_MARKS + 1})) AS m)),
          c AS (SELECT run_id, mark, count(*) AS done FROM mk GROUP BY 1, 2)
          SELECT run_id, mark, coalesce(done, 0) AS done, round(coalesce(done, 0) * {60_000 * N_MARKS} / r, 6) AS per_minute FROM gm LEFT JOIN c USING (run_id, mark)""", _t),
    )
    add(
        f"five_{_t}_utilisation", lambda s, d, t=_t: (lambda r: measures.utilisation_trace(r[0], r[1], r[2]))(run_five(s, d, t)),
        policies_sql(runs.FIVE, f", {EDGES} SELECT run_id, mark, t_ms, {_BUSY} AS busy, CAST(({_BUSY} * 1000) // {_POOL} AS BIGINT) AS util_pm FROM g", _t),
    )
    add(
        f"five_{_t}_seconds", lambda s, d, t=_t: (lambda r: measures.seconds(r[0], r[1], r[2]))(run_five(s, d, t)),
        policies_sql(runs.FIVE, f", {_WORK_SQL} SELECT run_id, worker_ms, busy_ms, worker_ms - busy_ms AS idle_ms, round(busy_ms / worker_ms, 6) AS utilisation FROM ws", _t),
    )
    add(
        f"five_{_t}_efficiency", lambda s, d, t=_t: report(s, d, t)[0].select("run_id", "accuracy", "runtime_ms", "efficiency"),
        sql(_t, f", {_WORK_SQL}, {_REPORT_SQL} SELECT run_id, accuracy, runtime_ms, efficiency FROM rep"),
    )


def relative(rep: DataFrame, base: str = "B3") -> DataFrame:
    """Speed-up and share of worker time against the static pool."""
    b = rep.where(F.col("run_id") == base).select(F.col("runtime_ms").alias("rb"), F.col("worker_ms").alias("wb"))
    return rep.crossJoin(F.broadcast(b)).select("run_id", F.round(F.col("rb") / F.col("runtime_ms"), 6).alias("speed_up"), F.round(F.col("worker_ms") / F.col("wb"), 6).alias("cost_ratio"))


def scores(s: SparkSession, d: str, task: str) -> DataFrame:
    """Six scores of each configuration. Reports come from a run without faults; the fault score from a second one in which chosen rows raise."""
    rep, out = report(s, d, task)
    faulty = classify.faulty("task_id")
    hurt = run_five(s, d, task, faults=True)[3]
    return measures.six_scores(rep, measures.fault_score(hurt, faulty), measures.burst_kept(out, BURST_MS))


_SCORES_SQL = f""", {_WORK_SQL}, {_REPORT_SQL},
  bu AS (SELECT run_id, count(*) FILTER (enq_ms < {BURST_MS}) AS arrived, count(*) FILTER (finish_ms < {BURST_MS}) AS served FROM res GROUP BY 1),
  hu AS (SELECT run_id, {_BAD} AS bad, CASE WHEN {_BAD} THEN NULL ELSE y_hat END AS y_hat, finish_ms FROM oc),
  fa AS (SELECT run_id, count(*) FILTER (NOT bad) AS fine, count(*) FILTER (NOT bad AND y_hat IS NOT NULL AND finish_ms IS NOT NULL) AS unharmed FROM hu GROUP BY 1)
  SELECT run_id, round(100 * per_minute / max(per_minute) OVER (), 4) AS throughput, round(100 * min(sojourn_p95) OVER () / sojourn_p95, 4) AS latency, round(100 * utilisation, 4) AS resource,
    round(100.0 * unharmed / fine, 4) AS fault, round(100 * least(1.0, served / arrived), 4) AS scalability,
    round(100 * (correct / worker_ms) / max(correct / worker_ms) OVER (), 4) AS cost_score FROM rep JOIN bu USING (run_id) JOIN fa USING (run_id)"""
for _t in TASKS:
    add(f"five_{_t}_scores", lambda s, d, t=_t: scores(s, d, t), sql(_t, _SCORES_SQL))
    add(
        f"five_{_t}_relative",
        lambda s, d, t=_t: relative(report(s, d, t)[0]),
        sql(
            _t,
            (
                f", {_WORK_SQL}, {_REPORT_SQL} SELECT a.run_id, round(b.runtime_ms / a.runtime_ms, 6) AS speed_up, round(a.worker_ms / b.worker_ms, 6) AS cost_ratio FROM rep a, rep b "
                "WHERE b.run_id = 'B3'"
            ),
        ),
    )

# ---- faults ----------------------------------------------------------------------------------------------------------------------------------------------
_FAULTY_SQL = f"fo AS (SELECT run_id, task_id, finish_ms, NOT ({_BAD}) AS ok, CASE WHEN {_BAD} THEN '{classify.ERROR}' ELSE y_hat END AS y_hat, NOT ({_BAD}) AND y = y_hat AS correct FROM oc)"


def fault_trace(s: SparkSession, d: str, task: str) -> DataFrame:
    """Completed and failed tasks of each configuration at the marks of its run."""
    out = run_five(s, d, task, faults=True)[3]
    return measures.outcome_counts(measures.marks(out, N_MARKS), out)


add("fault_tasks", lambda s, d: run_five(s, d, "lang", faults=True)[3].select("run_id", "task_id", "finish_ms", "ok", "y_hat", "correct"), sql("lang", f", {_FAULTY_SQL} SELECT * FROM fo"))
add(
    "fault_trace",
    lambda s, d: fault_trace(s, d, "lang"),
    sql(
        "lang",
        (
            f", {_FAULTY_SQL}, {EDGES} SELECT g.*, (SELECT count(*) FROM fo x WHERE x.run_id = g.run_id AND finish_ms <= t_ms) AS done, (SELECT count(*) FROM fo x "
            "WHERE x.run_id = g.run_id AND finish_ms <= t_ms AND NOT ok) AS failed FROM g"
        ),
    ),
)
add(
    "fault_score",
    lambda s, d: measures.fault_score(run_five(s, d, "lang", faults=True)[3], classify.faulty("task_id")),
    sql(
        "lang",
        (
            f", {_FAULTY_SQL} SELECT run_id, count(*) FILTER (NOT ({_BAD})) AS fine, count(*) FILTER (NOT ({_BAD}) AND ok AND finish_ms IS NOT NULL) AS unharmed, count(*) FILTER (NOT "
            "ok) AS failed FROM fo GROUP BY 1"
        ),
    ),
)


# ---- one classifier under several policies, several classifiers under one policy -----------------------------------------------------------------------
SWAP = [(p, r) for p in ("B1", "B3") for r in runs.ALL_ROLES]


def swap_runs(s: SparkSession, d: str, task: str = "lang") -> DataFrame:
    """Task-level outcomes of every role under the elastic and the static policy."""
    cfgs = [(runs.POLICIES[p][0].but(run_id=f"{p}-{r}"), r) for p, r in SWAP]
    res = kernel.results(runs.compare(s, d, task, runs=cfgs))
    return materialise(runs.outcomes(s, d, task, res, {f"{p}-{r}": r for p, r in SWAP}), "swap")


def swap_sql(select: str, task: str = "lang") -> str:
    cfgs = [(runs.POLICIES[p][0].but(run_id=f"{p}-{r}"), r) for p, r in SWAP]
    oc = " UNION ALL ".join(f"SELECT r.run_id, r.task_id, r.enq_ms, r.finish_ms, p.y, p.y_hat FROM res r JOIN pr_{x} p ON p.doc_id = r.task_id WHERE r.run_id = '{n}-{x}'" for n, x in SWAP)
    return O.several(cfgs, f", {roles_sql(task, runs.ALL_ROLES)}, oc AS ({oc}) {select}", task)


def swap_matrix(out: DataFrame) -> DataFrame:
    return measures.accuracy(out).join(measures.runtime(out).drop("n"), "run_id")


def swap_invariance(out: DataFrame) -> DataFrame:
    """For each role the tasks whose label differs between the two policies, each policy's labels having been made in its own run."""
    part = lambda p: out.where(F.col("run_id").startswith(f"{p}-")).select(F.substring("run_id", 4, 20).alias("role"), "task_id", F.col("y_hat").alias(p))
    j = part("B1").join(part("B3"), ["role", "task_id"], "full")
    return j.groupBy("role").agg(F.count("*").alias("tasks"), F.sum(F.when(F.col("B1").eqNullSafe(F.col("B3")), 0).otherwise(1)).alias("differing"))


for _t in TASKS:
    add(
        f"swap_matrix_{_t}",
        lambda s, d, t=_t: swap_matrix(swap_runs(s, d, t)),
        swap_sql(f"SELECT run_id, count(*) AS n, {_HIT} AS correct, round({_HIT} / count(*), 6) AS accuracy, max(finish_ms) - min(enq_ms) AS runtime_ms FROM oc GROUP BY 1", _t),
    )
add(
    "prediction_invariance",
    lambda s, d: swap_invariance(swap_runs(s, d)),
    swap_sql(
        (
            "SELECT substr(coalesce(a.run_id, b.run_id), 4) AS role, count(*) AS tasks, CAST(sum(CASE WHEN a.y_hat IS NOT DISTINCT FROM b.y_hat THEN 0 "
            "ELSE 1 END) AS BIGINT) AS differing FROM (SELECT * FROM oc WHERE run_id LIKE 'B1-%') a FULL JOIN (SELECT * FROM oc "
            "WHERE run_id LIKE 'B3-%') b ON substr(a.run_id, 4) = substr(b.run_id, 4) AND a.task_id = b.task_id GROUP BY 1"
        ),
    ),
)


# ---- the masked collapse -----------------------------------------------------------------------------------------------------------------------------------
def collapse(s: SparkSession, d: str, task: str = "quality") -> DataFrame:
    """Accuracy and recall of the watched class, for classifiers without evidence, on a sample with the data's class shares and on a balanced one."""
    out = None
    for name, even in (("proportional", False), ("balanced", True)):
        rows = materialise(runs.sample(s, d, task, even), "sample")
        for role in ("zs_weak", "supervised"):
            p = runs.predictions(s, d, task, role, rows).withColumn("run_id", F.lit(f"{name}-{role}"))
            one = measures.accuracy(p).join(measures.recall(p, POSITIVE[task]).select("run_id", "recall"), "run_id")
            out = one if out is None else out.unionByName(one)
    return out


def _collapse_sql(task: str = "quality") -> str:
    parts = []
    for name, rows in (("proportional", O.prop()), ("balanced", O.samp())):
        for role in ("zs_weak", "supervised"):
            parts.append(f"SELECT * FROM (WITH {O.src(task)}, {O.reps()}, {rows}, {roles_sql(task, [role])} SELECT '{name}-{role}' AS run_id, count(*) AS n, {_HIT} AS correct, round({_HIT} / count(*), 6) AS accuracy, round(sum(CASE WHEN y = y_hat AND y = '{POSITIVE[task]}' THEN 1 ELSE 0 END) / count(*) FILTER (y = '{POSITIVE[task]}'), 6) AS recall FROM pr_{role})")
    return " UNION ALL ".join(parts)


add("collapse_quality", collapse, _collapse_sql())
