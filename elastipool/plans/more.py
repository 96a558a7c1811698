"""Queries of single operators around the methods, further classifiers, and extensions of the controller."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from elastipool.model import FIGURE, LEXICON, N_MARKS, SEQUENTIAL, STATIC2, ArrivalSpec
from elastipool.operators import classify, extensions, kernel, measures, queueing, sampling
from elastipool.plans import oracle as O
from elastipool.plans import runs
from elastipool.plans.catalog import RES, add, policies_sql, query, sim
from elastipool.session import materialise, scratch_root, ship
from elastipool.sources import ingest

t = ingest.table

# ---- joins ----------------------------------------------------------------------------------------------------------------------------------------------
add(
    "op_semi_eval_members",
    lambda s, d: t(s, d, "documents").join(runs.sample(s, d, "lang").select("doc_id"), "doc_id", "left_semi").select("doc_id", "lang"),
    f"WITH {O.src('lang')}, {O.reps()}, {O.samp()} SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM samp)",
)
add(
    "op_anti_unlabelled",
    lambda s, d: t(s, d, "documents").join(t(s, d, "labels").select("doc_id"), "doc_id", "left_anti").select("doc_id", "lang"),
    "SELECT doc_id, lang FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)",
)
add(
    "op_cross_config_tasks",
    lambda s, d: runs.tasks(s, d).select("task_id", "svc_ms").crossJoin(F.broadcast(kernel.config_frame(s, runs.sweep_grid(True)).select("run_id", "cfg_n_max"))).groupBy("run_id").agg(F.count("*").alias("n"), F.sum(F.col("svc_ms") / 1).cast("long").alias("svc_ms"), F.max("cfg_n_max").alias("n_max")),
    (
        f"WITH {O.base()}, c AS (SELECT * FROM (VALUES {', '.join(f'({c.run_id!r}, {c.n_max})' for c in runs.sweep_grid(True))}) v(run_id, n_max)) "
        "SELECT run_id, count(*) AS n, CAST(sum(svc_ms) AS BIGINT) AS svc_ms, CAST(max(n_max) AS BIGINT) AS n_max FROM tk, c GROUP BY 1"
    ),
)


@query(
    "op_broadcast_phrases",
    "SELECT y, count(*) AS docs FROM (SELECT DISTINCT d.doc_id, p.y FROM (SELECT doc_id, unnest(" + O.TOK + ") AS w FROM documents) d JOIN (VALUES " + ", ".join(f"('{y}', '{w}')" for y, ws in LEXICON["lang"].items() for w in ws) + ") p(y, w) USING (w)) GROUP BY 1",
)
def _(s, d):
    """Documents with at least one phrase of a label: the label space is a fixed list and is broadcast."""
    p = s.createDataFrame([(y, w) for y, ws in LEXICON["lang"].items() for w in ws], "y string, w string")
    tok = t(s, d, "documents").select("doc_id", F.explode(F.array_distinct(classify.tokens(F.col("text")))).alias("w"))
    return tok.join(F.broadcast(p), "w").select("doc_id", "y").distinct().groupBy("y").agg(F.count("*").alias("docs"))


@query(
    "op_full_outer_marks",
    O.elastic(
        FIGURE,
        (
            f", mk AS (SELECT greatest(CAST(ceil(CAST(finish_ms * {N_MARKS} AS DOUBLE) / (SELECT max(finish_ms) FROM res)) AS INTEGER), 1) AS mark "
            f"FROM res), g AS (SELECT CAST(m AS INTEGER) AS mark FROM (SELECT unnest(range(1, {N_MARKS + 6})) AS m)) SELECT coalesce(g.mark, k.mark) AS mark, coalesce(n, 0) AS n "
            "FROM g FULL JOIN (SELECT mark, count(*) AS n FROM mk GROUP BY 1) k ON g.mark = k.mark"
        ),
    ),
)
def _(s, d):
    grid = s.range(1, N_MARKS + 6).select(F.col("id").cast("int").alias("mark"))
    c = measures.mark_of(kernel.results(sim(s, d, FIGURE))).groupBy("mark").agg(F.count("*").alias("n"))
    return grid.join(c, "mark", "full").select("mark", F.coalesce("n", F.lit(0)).alias("n"))


add(
    "op_asof_pool_size",
    lambda s, d: (lambda x: queueing.as_of(kernel.results(x).select("run_id", F.col("start_ms").alias("t_ms"), "task_id"), kernel.polls(x).select("run_id", "t_ms", F.col("n_after").cast("long").alias("n")), "n", 4))(sim(s, d, FIGURE)).select("task_id", "t_ms", "n"),
    O.elastic(FIGURE, "SELECT task_id, start_ms AS t_ms, coalesce((SELECT CAST(arg_max(n_after, j) AS BIGINT) FROM pol WHERE t_ms <= start_ms), 4) AS n FROM res"),
)

# ---- aggregation ------------------------------------------------------------------------------------------------------------------------------------------
_GS = "GROUP BY GROUPING SETS ((event_type, h), (event_type), ())"


@query("op_grouping_sets_events", f"SELECT event_type, h, count(*) AS n, CAST(sum(floor(value)) AS BIGINT) AS value FROM (SELECT event_type, CAST(hour(ts) AS INTEGER) AS h, value FROM events) {_GS}")
def _(s, d):
    e = t(s, d, "events").select("event_type", F.hour("ts").alias("h"), "value")
    return e.groupingSets([["event_type", "h"], ["event_type"], []], "event_type", "h").agg(F.count("*").alias("n"), F.sum(F.floor("value")).cast("long").alias("value"))


add(
    "op_rollup_region_nation",
    lambda s, d: t(s, d, "customer").join(F.broadcast(t(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(t(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).rollup("r_name", "n_name").agg(F.count("*").alias("n")),
    "SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)",
)
add(
    "op_unpivot_latency",
    lambda s, d: measures.latency(kernel.results(sim(s, d, FIGURE))).unpivot("run_id", ["svc_mean", "wait_mean", "sojourn_mean"], "measure", "ms"),
    O.elastic(
        FIGURE,
        (
            "SELECT run_id, 'svc_mean' AS measure, round(sum(svc_ms) / count(*), 6) AS ms FROM res GROUP BY 1 UNION ALL SELECT run_id, 'wait_mean', round(sum(wait_ms) / count(*), 6) "
            "FROM res GROUP BY 1 UNION ALL SELECT run_id, 'sojourn_mean', round(sum(sojourn_ms) / count(*), 6) FROM res GROUP BY 1"
        ),
    ),
)
add(
    "op_percentile_exact",
    lambda s, d: t(s, d, "events").groupBy("event_type").agg(F.round(F.percentile("value", F.lit(0.5)), 6).alias("p50"), F.round(F.percentile("value", F.lit(0.95)), 6).alias("p95")),
    "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS p50, round(quantile_cont(value, 0.95), 6) AS p95 FROM events GROUP BY 1",
)
add("op_approx_percentile", lambda s, d: t(s, d, "events").groupBy("event_type").agg(F.percentile_approx("value", 0.95, 10_000).alias("p95")))
_RANK = "(SELECT count(*) FROM events e WHERE e.event_type = g.event_type AND e.value {} p95)"


@query("op_approx_percentile_error", "SELECT event_type, count(*) AS n, true AS close FROM events GROUP BY 1")
def _(s, d):
    """Whether the sketch's value has a rank within a hundredth of the one asked for."""
    e = t(s, d, "events").select("event_type", "value")
    p = e.groupBy("event_type").agg(F.percentile_approx("value", 0.95, 10_000).alias("p95"))
    r = e.join(F.broadcast(p), "event_type").groupBy("event_type").agg(F.count("*").alias("n"), F.sum((F.col("value") < F.col("p95")).cast("int")).alias("below"), F.sum((F.col("value") <= F.col("p95")).cast("int")).alias("upto"))
    return r.select("event_type", "n", ((F.col("below") <= F.col("n") * 0.96) & (F.col("upto") >= F.col("n") * 0.94)).alias("close"))


add(
    "op_count_distinct_users",
    lambda s, d: t(s, d, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users")),
    "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1",
)
add("op_approx_distinct_users", lambda s, d: t(s, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users")))
# the sketch's own number has no SQL; whether it lies within three of its standard errors has
add(
    "op_approx_distinct_error",
    lambda s, d: t(s, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("a"), F.countDistinct("user_id").alias("users")).select("event_type", "users", (F.abs(F.col("a") - F.col("users")) <= F.col("users") * 0.06 + 1).alias("close")),
    "SELECT event_type, count(DISTINCT user_id) AS users, true AS close FROM events GROUP BY 1",
)


@query("op_grouped_udaf_p95", "SELECT event_type, list_sort(list(value))[CAST(ceil(0.95 * count(*)) AS INTEGER)] AS p95 FROM events GROUP BY 1")
def _(s, d):
    """95th percentile by nearest rank, as a grouped Arrow function: one group's values in a task, so for bounded groups only."""

    @F.pandas_udf("double")
    def p95(v: pd.Series) -> float:
        return float(v.sort_values().iloc[-(-95 * len(v) // 100) - 1])

    return t(s, d, "events").groupBy("event_type").agg(p95("value").alias("p95"))


# ---- windows, top-k, set operations --------------------------------------------------------------------------------------------------------------------
def _e():
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


add(
    "op_ntile_marks",
    lambda s, d: t(s, d, "events").where("user_id < 50").select("event_id", "user_id", F.ntile(4).over(_e()).alias("quarter")),
    "SELECT event_id, user_id, CAST(ntile(4) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS INTEGER) AS quarter FROM events WHERE user_id < 50",
)
add(
    "op_lag_gaps",
    lambda s, d: t(s, d, "events").select("event_id", (F.unix_micros(F.col("ts").cast("timestamp")) - F.lag(F.unix_micros(F.col("ts").cast("timestamp"))).over(_e())).alias("gap_us")),
    "SELECT event_id, epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS gap_us FROM events",
)
def _by_finish():
    return Window.partitionBy("run_id").orderBy("finish_ms", "seq")


add(
    "op_rows_frame_latency",
    lambda s, d: kernel.results(sim(s, d, FIGURE)).select("task_id", F.sum("sojourn_ms").over(_by_finish().rowsBetween(-19, 0)).alias("last20"), F.max("sojourn_ms").over(_by_finish().rowsBetween(-19, 0)).alias("worst20")),
    O.elastic(
        FIGURE,
        (
            "SELECT task_id, CAST(sum(sojourn_ms) OVER w AS BIGINT) AS last20, max(sojourn_ms) OVER w AS worst20 FROM res WINDOW w AS (PARTITION BY run_id "
            "ORDER BY finish_ms, seq ROWS BETWEEN 19 PRECEDING AND CURRENT ROW)"
        ),
    ),
)
add(
    "op_range_frame_latency",
    lambda s, d: kernel.results(sim(s, d, FIGURE)).select("task_id", F.count("*").over(Window.partitionBy("run_id").orderBy("finish_ms").rangeBetween(-29_999, 0)).alias("done30s")),
    O.elastic(FIGURE, "SELECT task_id, count(*) OVER (PARTITION BY run_id ORDER BY finish_ms RANGE BETWEEN 29999 PRECEDING AND CURRENT ROW) AS done30s FROM res"),
)
add(
    "op_topk_slowest",
    lambda s, d: kernel.results(sim(s, d, FIGURE)).orderBy(F.desc("sojourn_ms"), "task_id").limit(10).select("task_id", "sojourn_ms"),
    O.elastic(FIGURE, "SELECT task_id, sojourn_ms FROM res ORDER BY sojourn_ms DESC, task_id LIMIT 10"),
)
add(
    "op_topk_per_class",
    lambda s, d: t(s, d, "documents").withColumn("r", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n_chars"), "doc_id"))).where("r <= 3").select("lang", "r", "doc_id", "n_chars"),
    "SELECT lang, CAST(r AS INTEGER) AS r, doc_id, n_chars FROM (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id) AS r FROM documents) WHERE r <= 3",
)
_TWO = [(STATIC2, "zs_fast"), (FIGURE, "zs_fast")]
add(
    "op_union_runs",
    lambda s, d: kernel.results(kernel.simulate(runs.tasks(s, d), [STATIC2])).unionByName(kernel.results(kernel.simulate(runs.tasks(s, d), [FIGURE]))).groupBy("run_id").agg(F.count("*").alias("n"), F.max("finish_ms").alias("end_ms")),
    O.several(_TWO, "SELECT run_id, count(*) AS n, max(finish_ms) AS end_ms FROM res GROUP BY 1"),
)
add(
    "op_except_predictions",
    lambda s, d: ingest.labelled(s, d, "lang").select("doc_id", classify.zs_fast("lang").alias("y_hat")).exceptAll(ingest.labelled(s, d, "lang").select("doc_id", classify.zs_weak("lang").alias("y_hat"))),
    (
        f"WITH {O.src('lang')} SELECT doc_id, {O.zs('lang')} AS y_hat FROM (SELECT *, {O.TOK} AS tok FROM src) EXCEPT ALL SELECT doc_id, {O.zs('lang', weak=True)} "
        f"FROM (SELECT *, {O.TOK} AS tok FROM src)"
    ),
)
add(
    "op_intersect_samples",
    lambda s, d: runs.tasks(s, d).select("task_id").intersect(runs.tasks(s, d, role="zs_heavy").select("task_id")),
    f"WITH {O.src('lang')}, {O.reps()}, {O.samp()} SELECT doc_id AS task_id FROM samp",
)

# ---- strings, dates, arrays, maps, JSON ------------------------------------------------------------------------------------------------------------------
add(
    "op_strings_normalise",
    lambda s, d: t(s, d, "conversations").select("conv_id", "turn", F.upper(F.substring("role", 1, 4)).alias("role"), F.length(F.trim("text")).alias("n"), F.md5(F.concat_ws("|", "role", F.regexp_replace("text", "[0-9]+", "#"))).alias("h")),
    (
        "SELECT conv_id, turn, upper(substr(role, 1, 4)) AS role, CAST(length(trim(text)) AS INTEGER) AS n, md5(concat_ws('|', role, regexp_replace(text, '[0-9]+', '#', 'g'))) AS "
        "h FROM conversations"
    ),
)
add(
    "op_dates_bucket",
    lambda s, d: t(s, d, "orders").groupBy(F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q"), F.dayofweek("o_orderdate").alias("dow")).agg(F.count("*").alias("n"), F.datediff(F.max("o_orderdate"), F.min("o_orderdate")).alias("span")),
    (
        "SELECT CAST(year(o_orderdate) AS INTEGER) AS y, CAST(quarter(o_orderdate) AS INTEGER) AS q, CAST(dayofweek(o_orderdate) + 1 AS INTEGER) AS dow, count(*) AS n, "
        "CAST(date_diff('day', min(o_orderdate), max(o_orderdate)) AS INTEGER) AS span FROM orders GROUP BY 1, 2, 3"
    ),
)
add(
    "op_array_hof",
    lambda s, d: t(s, d, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.array_position(F.transform("embedding", lambda x: F.floor(x.cast("double") * 1000)), F.array_max(F.transform("embedding", lambda x: F.floor(x.cast("double") * 1000)))).cast("int").alias("at")),
    (
        "SELECT vec_id, CAST(len([x FOR x IN embedding IF x > 0]) AS INTEGER) AS positive, CAST(list_position(v, list_max(v)) AS INTEGER) AS at "
        "FROM (SELECT vec_id, embedding, [floor(CAST(x AS DOUBLE) * 1000) FOR x IN embedding] AS v FROM embeddings)"
    ),
)


@query(
    "op_map_scores",
    f"WITH {O.src('lang')}, {O.reps()}, {O.samp()}, st AS (SELECT s.y, {O.TOK} AS tok FROM samp s JOIN documents d USING (doc_id)), p AS (SELECT y, {O.zs('lang')} AS y_hat FROM st) SELECT 'zs_fast' AS run_id, " + ", ".join(f"CAST(sum(CASE WHEN y = '{y}' AND y_hat = y THEN 1 ELSE 0 END) AS BIGINT) AS {y}" for y in ("de", "en", "es", "fr")) + " FROM p",
)
def _(s, d):
    """Correct predictions by class as one map column, read back by key."""
    p = measures.per_class(runs.predictions(s, d, "lang", "zs_fast", runs.sample(s, d, "lang")).withColumn("run_id", F.lit("zs_fast")))
    m = p.groupBy("run_id").agg(F.map_from_entries(F.collect_list(F.struct("y", "correct"))).alias("m"))
    return m.select("run_id", *[F.coalesce(F.element_at("m", y), F.lit(0)).alias(y) for y in ("de", "en", "es", "fr")])


add(
    "op_json_props",
    lambda s, d: t(s, d, "events").select(F.get_json_object("props", "$.k").cast("long").alias("k"), "event_type").groupBy("k", "event_type").agg(F.count("*").alias("n")),
    "SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, event_type, count(*) AS n FROM events GROUP BY 1, 2",
)


@query("op_json_report_roundtrip", O.elastic(FIGURE, "SELECT run_id, count(*) AS n, max(finish_ms) AS end_ms FROM res GROUP BY 1"))
def _(s, d):
    rep = kernel.results(sim(s, d, FIGURE)).groupBy("run_id").agg(F.count("*").alias("n"), F.max("finish_ms").alias("end_ms"))
    text = rep.select(F.to_json(F.struct("*")).alias("j"))
    return text.select(F.from_json("j", rep.schema).alias("r")).select("r.*")


@query("op_tsv_roundtrip", "SELECT lang AS y, md5(regexp_replace(text, '[\\t\\r\\n]+', ' ', 'g')) AS h FROM documents".replace("\\t", "\t").replace("\\r", "\r").replace("\\n", "\n"))
def _(s, d):
    """Documents written as label, tab, text and read back; quotes are literal, and nulls have a mark of their own."""
    path = f"{scratch_root(s)}/tsv-{uuid.uuid4().hex}"
    mark = lambda c: F.coalesce(c, F.lit(ingest.TSV_NULL))
    t(s, d, "documents").select(F.concat(mark(F.col("lang")), F.lit("\t"), mark(F.regexp_replace("text", "[\\t\\r\\n]+", " "))).alias("value")).write.text(path)
    return ingest.tsv(s, path).where("bad IS NULL").select("y", F.md5("text").alias("h"))


class _SimulatePool:
    """UDTF body: rows of one shard in, dispatches out."""

    def __init__(self):
        self.rows = []

    def eval(self, row):
        self.rows.append((row["seq"], row["prio"], row["enq_ms"], row["svc_ms"], row["task_id"]))

    def terminate(self):
        from elastipool.operators.kernel import run_queue

        out, _ = run_queue([r[:4] for r in sorted(self.rows, key=lambda r: (r[2], r[0]))], FIGURE)
        for seq, _, _, _, task in self.rows:
            yield (task, seq, *out[seq])


@query("op_udtf_simulate_pool", O.elastic(FIGURE, "SELECT task_id, seq, start_ms, finish_ms, worker_id FROM res"))
def _(s, d):
    """The elastic run for SQL users: a table function over a partitioned table."""
    ship(s)
    s.udtf.register("simulate_pool", F.udtf(_SimulatePool, returnType="task_id long, seq long, start_ms long, finish_ms long, worker_id int"))
    runs.tasks(s, d).select("shard", "task_id", "seq", "prio", "enq_ms", "svc_ms").createOrReplaceTempView("pool_tasks")
    return s.sql("SELECT * FROM simulate_pool(TABLE(pool_tasks) PARTITION BY shard ORDER BY seq)")


# ---- further classifiers -----------------------------------------------------------------------------------------------------------------------------------
def _eval_train(s: SparkSession, d: str, task: str) -> tuple[DataFrame, DataFrame]:
    rows = materialise(runs.sample(s, d, task), "sample")
    docs = t(s, d, "documents").select("doc_id", "text")
    train = sampling.train_split(ingest.labelled(s, d, task), rows).select("doc_id", "y").join(docs, "doc_id")
    return rows.select("doc_id", "y").join(docs, "doc_id"), train


add("zs_heavy_ngram", lambda s, d: extensions.profile_predict(*_eval_train(s, d, "lang")))
add("softmax_sgd", lambda s, d: extensions.softmax_predict(*_eval_train(s, d, "quality"), epochs=2, batch=16))
add("mllib_nb", lambda s, d: extensions.mllib_predict(*_eval_train(s, d, "lang")))

# ---- extensions of the controller --------------------------------------------------------------------------------------------------------------------------
AGED = 60_000
_AGED = f"agd AS (SELECT shard, task_id, seq, CAST(prio * {AGED} + enq_ms AS INTEGER) AS prio, enq_ms, svc_ms, y, n_chars FROM tk)"
add(
    "extension_ageing",
    lambda s, d: measures.priority_wait(extensions.aged(runs.tasks(s, d), FIGURE, AGED)),
    (
        f"WITH RECURSIVE {O.base()}, {_AGED}, {O.sim(FIGURE.but(run_id='aged'), '', 'agd')} SELECT r.run_id, k.prio, count(*) AS n, round(sum(wait_ms) / count(*), 6) AS wait_mean, "
        "max(wait_ms) AS wait_max FROM res r JOIN tk k USING (task_id) GROUP BY 1, 2"
    ),
)
add("extension_predictive", lambda s, d: extensions.predictive(runs.tasks(s, d), FIGURE))
_HITS = " + ".join(O.words("lang", y) for y in LEXICON["lang"])
_UNSURE = f"un AS (SELECT doc_id FROM (SELECT doc_id, {O.TOK} AS tok FROM documents) WHERE {_HITS} < {extensions.UNSURE})"
_SECOND = "SELECT shard, task_id, seq, prio, finish_ms AS enq_ms, svc_ms * {} AS svc_ms, y, n_chars FROM res_a WHERE task_id IN (SELECT doc_id FROM un)"
_TWO_TIERS = f"WITH RECURSIVE {O.base()}, {O.sim(FIGURE.but(run_id='fast'), '_a')}, {_UNSURE}, tb AS ({_SECOND.format(3)}), {O.sim(STATIC2.but(run_id='heavy'), '_b', 'tb')}"
add(
    "extension_heterogeneous",
    lambda s, d: extensions.heterogeneous(s, d),
    f"{_TWO_TIERS} SELECT run_id, count(*) AS n, max(finish_ms) AS end_ms, CAST(sum(wait_ms) AS BIGINT) AS wait_ms FROM (SELECT * FROM res_a UNION ALL SELECT * FROM res_b) GROUP BY 1",
)
_FAR = _SECOND.replace("finish_ms AS enq_ms", f"finish_ms + {extensions.LINK_MS} AS enq_ms").replace("svc_ms * {}", "greatest((svc_ms * 700) // 1000, 1)")
add(
    "extension_edge_cloud",
    lambda s, d: extensions.edge_cloud(s, d),
    (
        f"WITH RECURSIVE {O.base()}, {O.sim(STATIC2.but(run_id='edge'), '_a')}, {_UNSURE}, tb AS ({_FAR}), {O.sim(FIGURE.but(run_id='cloud'), '_b', 'tb')}, bk AS (SELECT run_id, "
        f"task_id, finish_ms, wait_ms FROM res_a WHERE task_id NOT IN (SELECT doc_id FROM un) UNION ALL SELECT run_id, task_id, finish_ms + {extensions.LINK_MS}, wait_ms "
        "FROM res_b) SELECT run_id, count(*) AS n, max(finish_ms) AS end_ms, CAST(sum(wait_ms) AS BIGINT) AS wait_ms FROM bk GROUP BY 1"
    ),
)


@query(
    "extension_tuned",
    O.several(
        [(c, "zs_fast") for c in runs.sweep_grid(True)],
        "SELECT run_id, CAST(sum(wait_ms) AS BIGINT) AS wait_ms, max(finish_ms) AS makespan_ms FROM res GROUP BY 1 ORDER BY 2, 3, 1 LIMIT 1",
    ),
)
def _(s, d):
    """Thresholds by search: the grid's configuration of least wait."""
    x = kernel.results(kernel.simulate(runs.tasks(s, d), runs.sweep_grid(True)))
    return x.groupBy("run_id").agg(F.sum("wait_ms").alias("wait_ms"), F.max("finish_ms").alias("makespan_ms")).orderBy("wait_ms", "makespan_ms", "run_id").limit(1)


# ---- workloads: all policies with all roles ------------------------------------------------------------------------------------------------------------------
def _policy(name: str, task: str) -> None:
    cfg, role = runs.POLICIES[name]
    prio = "const" if not cfg.autoscale and cfg.n_init == 1 else "source"
    add(f"run_{name}_{task}", lambda s, d: runs.execute(s, d, runs.RunSpec(task=task, policy=name)).results.select(*RES.split(", ")), O.elastic(cfg, f"SELECT {RES} FROM res", task=task, role=role, prio=prio).replace("CAST(1 AS INTEGER) AS prio", f"{O.PRIO['source']} AS prio") if prio == "source" else None)


for _n in ("B1", "B2", "B3", "Bmax", "B8"):
    for _t in ("lang", "quality"):
        _policy(_n, _t)
for _n in runs.SIZED:
    for _t in ("lang", "quality"):
        add(f"run_{_n}_{_t}", lambda s, d, n=_n, k=_t: runs.execute(s, d, runs.RunSpec(task=k, policy=n)).results.select(*RES.split(", ")), policies_sql((_n,), f"SELECT {RES} FROM res", _t))
for _n in ("B4", "B5"):
    for _t in ("lang", "quality"):
        _cfg, _role = runs.POLICIES[_n]
        add(
            f"run_{_n}_{_t}",
            lambda s, d, n=_n, k=_t: runs.execute(s, d, runs.RunSpec(task=k, policy=n)).results.select("run_id", "task_id", "seq", "start_ms", "finish_ms", "wait_ms", "sojourn_ms"),
            O.elastic(SEQUENTIAL.but(run_id=_n), "SELECT run_id, task_id, seq, start_ms, finish_ms, wait_ms, sojourn_ms FROM res", task=_t, role=_role, prio="const"),
        )
for _r in ("zs_fast", "zs_weak"):
    add(
        f"accuracy_{_r}",
        lambda s, d, r=_r: measures.accuracy(runs.predictions(s, d, "lang", r, runs.sample(s, d, "lang")).withColumn("run_id", F.lit(r))),
        (
            f"WITH {O.src('lang')}, {O.reps()}, {O.samp()}, st AS (SELECT s.y, {O.TOK} AS tok FROM samp s "
            f"JOIN documents d USING (doc_id)), p AS (SELECT y, {O.zs('lang', weak=_r == 'zs_weak')} AS y_hat FROM st) SELECT '{_r}' AS run_id, count(*) AS n, CAST(sum(CASE "
            "WHEN y = y_hat THEN 1 ELSE 0 END) AS BIGINT) AS correct, round(CAST(sum(CASE WHEN y = y_hat THEN 1 ELSE 0 END) AS BIGINT) / count(*), 6) AS accuracy FROM p"
        ),
    )
_CONV = f"SELECT conv_id * 100 + turn AS doc_id, {O.zs('lang')} AS y_hat FROM (SELECT *, {O.TOK} AS tok FROM conversations WHERE role = 'user')"
add("requests_conversations", lambda s, d: ingest.conversations(s, d).select("doc_id", classify.zs_fast("lang").alias("y_hat")), _CONV)
for _b in (350, 400):
    for _q in (40, 70):
        _s = ArrivalSpec(burst_pm=_b, ratio_tenths=_q)
        add(
            f"burst_{_b}_{_q}",
            lambda s, d, k=_s: measures.queue_summary(kernel.results(kernel.simulate(runs.tasks(s, d, spec=k), [FIGURE]))).select("run_id", "peak"),
            (
                f"WITH RECURSIVE {O.base(spec=_s)}, {O.sim(FIGURE)}, ch AS (SELECT t, sum(d) AS d FROM (SELECT enq_ms AS t, 1 AS d FROM res UNION ALL SELECT start_ms, -1 FROM res) "
                "GROUP BY 1) SELECT 'elastic' AS run_id, CAST(max(q) AS BIGINT) AS peak FROM (SELECT sum(d) OVER (ORDER BY t) AS q FROM ch)"
            ),
        )

