"""Policies, roles and workloads put together: one sample, one sequence, any policy with any classifier."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from elastipool.model import FIGURE, PEAK, SEQUENTIAL, STATIC2, ArrivalSpec, RunConfig
from elastipool.operators import classify, kernel, queueing, sampling, workload
from elastipool.session import materialise
from elastipool.sources import ingest

#: Baselines: policy and role of each. B6 and B7 are static pools of the size that average and peak load need, computed from the tasks; the elastic pools'
#: bound as a static pool is Bmax.
POLICIES: dict[str, tuple[RunConfig, str]] = {
    "B1": (FIGURE.but(run_id="B1"), "zs_fast"),
    "B2": (FIGURE.but(run_id="B2"), "zs_heavy"),
    "B3": (STATIC2.but(run_id="B3"), "zs_fast"),
    "B4": (SEQUENTIAL.but(run_id="B4"), "zs_weak"),
    "B5": (SEQUENTIAL.but(run_id="B5"), "supervised"),
    "B6": (STATIC2.but(run_id="B6"), "zs_fast"),
    "B7": (STATIC2.but(run_id="B7"), "zs_fast"),
    "Bmax": (PEAK.but(run_id="Bmax"), "zs_fast"),
    "B8": (FIGURE.but(run_id="B8", use_queue=False, cpu_share_pm=300), "zs_fast"),
}
SIZED = {"B6": "average", "B7": "peak"}
FIVE = ("B1", "B2", "B3", "B4", "B5")
#: Roles that any policy may run with.
ALL_ROLES = ("zs_fast", "zs_heavy", "zs_weak", "supervised", "majority", "hash")


def order_of(cfg: RunConfig, prio: str = "source") -> str:
    """A sequential pass has no queue, so no priorities: it takes tasks as they come."""
    return "const" if cfg.n_init == 1 and not cfg.autoscale else prio


def policy(name: str, sizes: dict[str, int] | None = None) -> tuple[RunConfig, str]:
    cfg, role = POLICIES[name]
    if name in SIZED:
        n = sizes[SIZED[name]]
        cfg = cfg.but(n_init=n, n_min=n, n_max=n)
    return cfg, role


def sizes_of(spark: SparkSession, sf_dir: str, task: str, spec: ArrivalSpec = ArrivalSpec()) -> dict[str, int]:
    return workload.static_sizes(tasks(spark, sf_dir, task, spec=spec), spec).first().asDict()


@dataclass(frozen=True)
class RunSpec:
    task: str = "lang"
    policy: str = "B1"
    prio: str = "source"
    spec: ArrivalSpec = ArrivalSpec()
    balanced: bool = True


@dataclass(frozen=True)
class RunOutput:
    results: DataFrame
    polls: DataFrame
    scale_events: DataFrame
    predictions: DataFrame


def sample(spark: SparkSession, sf_dir: str, task: str, balanced: bool = True) -> DataFrame:
    df = ingest.labelled(spark, sf_dir, task)
    return sampling.balanced(df) if balanced else sampling.proportional(df)


def tasks(spark: SparkSession, sf_dir: str, task: str = "lang", role: str = "zs_fast", prio: str = "source", spec: ArrivalSpec = ArrivalSpec(), balanced: bool = True) -> DataFrame:
    return workload.tasks(sample(spark, sf_dir, task, balanced), role, prio, spec)


def label_of(role: str, task: str) -> Column:
    """The label a Column role gives to ``text`` (or, for the hash, to ``doc_id``)."""
    if role == "hash":
        return classify.hash_label(task)
    return {"zs_fast": classify.zs_fast, "zs_heavy": classify.zs_heavy, "zs_weak": classify.zs_weak}[role](task)


def predictions(spark: SparkSession, sf_dir: str, task: str, role: str, eval_rows: DataFrame) -> DataFrame:
    """(task_id, y, y_hat) on an evaluation sample: text is read here and nowhere else."""
    docs = ingest.table(spark, sf_dir, "documents").select("doc_id", "text")
    rows = docs.join(F.broadcast(eval_rows.select("doc_id", "y")), "doc_id")
    if role not in ("supervised", "majority"):
        return rows.select(F.col("doc_id").alias("task_id"), "y", label_of(role, task).alias("y_hat"))
    split = sampling.train_split(ingest.labelled(spark, sf_dir, task), eval_rows).select("doc_id", "y")
    if role == "majority":
        return eval_rows.select(F.col("doc_id").alias("task_id"), "y").crossJoin(F.broadcast(classify.majority(split)))
    return classify.nb_predict(rows, classify.nb_fit(split.join(docs, "doc_id"))).join(rows.select("doc_id", "y"), "doc_id").select(F.col("doc_id").alias("task_id"), "y", "y_hat")


def outcomes(spark: SparkSession, sf_dir: str, task: str, results: DataFrame, roles: dict[str, str], faults: bool = False) -> DataFrame:
    """The task-level table: each run's own tasks are classified by the run's role, so nothing is shared between policies. With ``faults`` chosen rows raise inside
    the classifier; the guard turns that into an error label for the row, and the rest of its batch goes on."""
    rows = materialise(sample(spark, sf_dir, task), "sample")
    out = None
    for run, role in roles.items():
        mine = results.where(F.col("run_id") == run)
        own = rows.join(mine.select(F.col("task_id").alias("doc_id")), "doc_id", "left_semi")
        p = predictions(spark, sf_dir, task, role, own)
        p = classify.with_faults(p.withColumnRenamed("task_id", "doc_id")).withColumnRenamed("doc_id", "task_id") if faults else p.withColumn("ok", F.col("y_hat").isNotNull())
        j = mine.join(p, "task_id").withColumn("correct", F.col("ok") & F.col("y").eqNullSafe(F.col("y_hat")))
        out = j if out is None else out.unionByName(j)
    return out.select("run_id", "task_id", "seq", "prio", "y", "y_hat", "correct", "ok", "worker_id", "enq_ms", "start_ms", "finish_ms", "svc_ms", "wait_ms", "sojourn_ms")


def execute(spark: SparkSession, sf_dir: str, run: RunSpec) -> RunOutput:
    """One policy with its classifier: the queue run is written once and split by kind."""
    cfg, role = policy(run.policy, sizes_of(spark, sf_dir, run.task, run.spec) if run.policy in SIZED else None)
    rows = sample(spark, sf_dir, run.task, run.balanced)
    t = workload.tasks(rows, role, run.prio, run.spec)
    if cfg.autoscale or cfg.n_init > 1:
        sim = materialise(kernel.simulate(t, [cfg]), f"run-{cfg.run_id}")
        res, polls = kernel.results(sim), kernel.polls(sim)
    else:
        # one server, first come first served: a window, no kernel
        res = queueing.sequential(t.withColumn("run_id", F.lit(cfg.run_id))).select(*[x.split()[0] for x in kernel.RESULT.split(", ")], "wait_ms", "sojourn_ms")
        polls = spark.createDataFrame([], kernel.polls(_empty(spark)).schema)
    pred = predictions(spark, sf_dir, run.task, role, rows).withColumn("run_id", F.lit(cfg.run_id))
    return RunOutput(res, polls, polls.where("delta <> 0"), pred)


def _empty(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([], kernel.SCHEMA)


def compare(spark: SparkSession, sf_dir: str, task: str = "lang", policies: tuple[str, ...] = FIVE, prio: str = "source", runs: list[tuple[RunConfig, str]] | None = None) -> DataFrame:
    """Tagged rows of several policies (or of any configurations with roles) over one sample; runs of one role and order share a task table."""
    rows = materialise(sample(spark, sf_dir, task), "sample")
    if runs is None:
        sizes = sizes_of(spark, sf_dir, task) if set(policies) & set(SIZED) else None
        runs = [policy(p, sizes) for p in policies]
    by: dict[tuple[str, str], list[RunConfig]] = {}
    for cfg, role in runs:
        by.setdefault((role, order_of(cfg, prio)), []).append(cfg)
    out = None
    for (role, order), cfgs in by.items():
        s = kernel.simulate(workload.tasks(rows, role, order), cfgs)
        out = s if out is None else out.unionByName(s)
    return materialise(out, "compare")


def fixed(spark: SparkSession, cfgs: list[RunConfig]) -> DataFrame:
    """(run_id, n) of the pools that never change."""
    return spark.createDataFrame([(c.run_id, c.n_init) for c in cfgs if not c.autoscale], "run_id string, n int")


def sweep_grid(small: bool) -> list[RunConfig]:
    """The threshold grid: 864 configurations, or 24 of them."""
    if small:
        return [FIGURE.but(run_id=f"m{m}-q{q}-t{t}-s{s}", n_init=2, n_max=m, queue_hi=q, cooldown_ms=t, step=s, step_down=s) for m in (4, 6, 8) for q in (5, 20) for t in (0, 5000) for s in (1, 2)]
    return [
        FIGURE.but(run_id=f"n{a}-m{m}-q{q}-p{p}-t{t}-s{s}", n_init=a, n_min=a, n_max=m, queue_hi=q, poll_ms=p, cooldown_ms=t, step=s, step_down=s)
        for a in (1, 2) for m in (4, 6, 8) for q in (2, 5, 10, 20) for p in (500, 1000, 2000) for t in (0, 3000, 5000, 10_000) for s in (1, 2, 4)
    ]


def order_tasks(spark: SparkSession, sf_dir: str, spec: ArrivalSpec = ArrivalSpec(window_ms=3_600_000)) -> DataFrame:
    """Every line item as a task of its customer's nation: shards are nations, and each shard numbers its own tasks."""
    li, o, c = (ingest.table(spark, sf_dir, t) for t in ("lineitem", "orders", "customer"))
    j = li.join(o.select("o_orderkey", "o_custkey", "o_orderdate", "o_orderpriority"), F.col("l_orderkey") == F.col("o_orderkey")).join(c.select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    from pyspark.sql import Window

    ties = ["o_orderdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus"]
    w = Window.partitionBy("c_nationkey")
    j = j.withColumn("seq", (F.row_number().over(w.orderBy(*ties)) - 1).cast("long")).withColumn("n_all", F.count("*").over(w))
    return j.select(
        F.lit("orders").alias("run_id"), F.col("c_nationkey").cast("int").alias("shard"), F.col("seq").alias("task_id"), "seq", workload.priority("order").alias("prio"),
        workload.arrival(F.col("seq"), F.col("n_all"), spec).alias("enq_ms"), (F.floor("l_quantity") * 200).cast("long").alias("svc_ms"),
    )
