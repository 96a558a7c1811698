"""Further classifiers (profiles, softmax by stochastic gradient descent, MLlib) and controller extensions (ageing, prediction, two-tier pools)."""

from __future__ import annotations

import heapq

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from elastipool.model import NEVER, RunConfig
from elastipool.operators import classify, kernel
from elastipool.operators.kernel import RESULT, run_queue
from elastipool.session import ship


def trigrams(text) -> F.Column:
    """Character trigrams of the lower-cased text."""
    chars = F.split(F.lower(text), "")
    return F.transform(F.array(chars), lambda c: F.zip_with(F.zip_with(c, F.slice(c, F.lit(2), F.size(c)), lambda x, y: F.concat(x, y)), F.slice(c, F.lit(3), F.size(c)), lambda x, y: F.concat(x, y)))[0]


def profile_predict(docs: DataFrame, train: DataFrame, most: int = 400) -> DataFrame:
    """Nearest character-trigram profile by cosine; a profile holds the ``most`` commonest trigrams of a class."""
    from pyspark.sql import Window

    c = train.select("y", F.explode(trigrams(F.col("text"))).alias("g")).groupBy("y", "g").agg(F.count("*").alias("c"))
    c = c.withColumn("r", F.row_number().over(Window.partitionBy("y").orderBy(F.desc("c"), "g"))).where(F.col("r") <= most)
    norm = c.groupBy("y").agg(F.sqrt(F.sum(F.col("c") * F.col("c"))).alias("norm"))
    prof = c.join(norm, "y").select("y", "g", (F.col("c") / F.col("norm")).alias("w"))
    mine = docs.select("doc_id", F.explode(trigrams(F.col("text"))).alias("g")).groupBy("doc_id", "g").agg(F.count("*").alias("k"))
    score = mine.join(F.broadcast(prof), "g").groupBy("doc_id", "y").agg(F.round(F.sum(F.col("k") * F.col("w")), 6).alias("s"))
    best = score.groupBy("doc_id").agg(F.max_by("y", F.struct("s", "y")).alias("y_hat"))
    return docs.select("doc_id", "y").join(best, "doc_id", "left")


def softmax_predict(docs: DataFrame, train: DataFrame, epochs: int = 2, batch: int = 16, buckets: int = 4096, seed: int = 5) -> DataFrame:
    """Mini-batch softmax regression on hashed tokens; the training split is bounded (4,000 rows), so one task trains and the weights are broadcast."""
    ship(docs.sparkSession)
    h = lambda df, *c: df.select(*c, F.transform(classify.tokens(F.col("text")), lambda w: F.pmod(F.xxhash64(w), F.lit(buckets)).cast("int")).alias("f"))
    rows = h(train, "doc_id", "y").orderBy("doc_id").toPandas()
    labels = sorted(rows["y"].unique())
    rng, w, b = np.random.default_rng(seed), np.zeros((buckets, len(labels))), np.zeros(len(labels))
    y = rows["y"].map({v: k for k, v in enumerate(labels)}).to_numpy()
    feats = [np.asarray(f, int) for f in rows["f"]]

    def probs(f):
        z = w[f].sum(0) / max(1, len(f)) ** 0.5 + b
        e = np.exp(z - z.max())
        return e / e.sum()

    for _ in range(epochs):
        order = rng.permutation(len(feats))
        for k in range(0, len(order), batch):
            part = order[k : k + batch]
            grads = [(i, probs(feats[i])) for i in part]
            for i, p in grads:
                p[y[i]] -= 1
                np.add.at(w, feats[i], -0.5 * p / max(1, len(feats[i])) ** 0.5 / len(part) * 4)
                b -= 0.1 * p / len(part)
    shared = docs.sparkSession.sparkContext.broadcast((w, b, labels))

    @F.pandas_udf("string")
    def predict(f: pd.Series) -> pd.Series:
        w, b, labels = shared.value
        return f.map(lambda v: labels[int(np.argmax(w[np.asarray(v, int)].sum(0) / max(1, len(v)) ** 0.5 + b))])

    return h(docs, "doc_id", "y").select("doc_id", "y", predict("f").alias("y_hat"))


def mllib_predict(docs: DataFrame, train: DataFrame) -> DataFrame:
    """Naive Bayes of the machine-learning library on hashed token counts."""
    from pyspark.ml import Pipeline
    from pyspark.ml.classification import NaiveBayes
    from pyspark.ml.feature import HashingTF, IndexToString, StringIndexer

    ix = StringIndexer(inputCol="y", outputCol="label", stringOrderType="alphabetAsc").fit(train)
    tok = lambda df: df.withColumn("words", classify.tokens(F.col("text")))
    m = Pipeline(stages=[HashingTF(inputCol="words", outputCol="features", numFeatures=1 << 14), NaiveBayes()]).fit(ix.transform(tok(train)))
    out = m.transform(tok(docs).drop("label"))
    return IndexToString(inputCol="prediction", outputCol="y_hat", labels=ix.labels).transform(out).select("doc_id", "y", "y_hat")


def _one_run(tasks: DataFrame, run_id: str, serve) -> DataFrame:
    """``serve(rows (seq, prio, enq, svc)) -> {seq: (start, finish, worker)}`` for each shard."""
    ship(tasks.sparkSession)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["enq_ms", "seq"])
        out = serve(list(zip(pdf.seq.tolist(), pdf.prio.tolist(), pdf.enq_ms.tolist(), pdf.svc_ms.tolist())))
        res = pdf.assign(run_id=run_id)
        res["start_ms"], res["finish_ms"], res["worker_id"] = ([out[s][k] for s in res.seq] for k in range(3))
        return res[[x.split()[0] for x in RESULT.split(", ")]]

    r = tasks.select("shard", "task_id", "seq", "prio", "enq_ms", "svc_ms").groupBy("shard").applyInPandas(run, RESULT)
    return r.withColumn("wait_ms", F.col("start_ms") - F.col("enq_ms")).withColumn("sojourn_ms", F.col("finish_ms") - F.col("enq_ms"))


def aged(tasks: DataFrame, cfg: RunConfig, aging_ms: int) -> DataFrame:
    """Priorities that improve by one class for each ``aging_ms`` waited. With a fixed rate the order of two waiting tasks never changes, so a static key
    (priority * aging_ms + arrival) is exact and the kernel needs no re-sorting."""

    def serve(rows):
        keyed = [(s, p * aging_ms + e, e, v) for s, p, e, v in rows]
        return run_queue(keyed, cfg)[0]

    return _one_run(tasks, "aged", serve)


def predictive(tasks: DataFrame, cfg: RunConfig, alpha_pm: int = 300) -> DataFrame:
    """Pool sized by a forecast: arrivals of each poll interval are smoothed, the target is the rate times mean service, moved within bounds, step and cooldown. Returns one row: makespan, wait, peak pool."""

    def serve(rows):
        return _predicted(rows, cfg, alpha_pm)

    r = _one_run(tasks, "predictive", serve)
    return r.groupBy("run_id").agg(F.max("finish_ms").alias("makespan_ms"), F.sum("wait_ms").alias("wait_ms"), F.max("worker_id").alias("workers"))


def _predicted(rows, cfg, alpha_pm):
    idle, running, queue, out = list(range(1, cfg.n_init + 1)), [], [], {}
    n, nid, last, at, rate = cfg.n_init, cfg.n_init + 1, NEVER, 0, 0
    mean = sum(r[3] for r in rows) // max(1, len(rows))
    t = 0
    while len(out) < len(rows):
        before = at
        edge = t + cfg.poll_ms
        while True:
            nxt = min([rows[at][2]] if at < len(rows) else [edge], default=edge)
            fin = running[0][0] if running else edge
            now = min(nxt, fin, edge)
            if now >= edge:
                break
            if fin == now:
                heapq.heappush(idle, heapq.heappop(running)[1])
            else:
                heapq.heappush(queue, (rows[at][1], rows[at][0], rows[at][3]))
                at += 1
            while idle and queue:
                _, s, v = heapq.heappop(queue)
                w = heapq.heappop(idle)
                out[s] = (now, now + v, w)
                heapq.heappush(running, (now + v, w))
        t = edge
        rate = ((1000 - alpha_pm) * rate + alpha_pm * 1000 * (at - before)) // 1000  # thousandths of a task a poll
        want = -(-(rate * mean) // (1000 * cfg.poll_ms)) + (1 if queue else 0)
        want = min(max(want, cfg.n_min), cfg.n_max)
        d = max(-cfg.step_down, min(cfg.step, want - n))
        d = -min(-d, len(idle)) if d < 0 else d
        if d and t - last >= cfg.cooldown_ms:
            for _ in range(d):
                heapq.heappush(idle, nid)
                nid += 1
            if d < 0:
                idle = sorted(idle)[:d]
            n, last = n + d, t
        while idle and queue:
            _, s, v = heapq.heappop(queue)
            w = heapq.heappop(idle)
            out[s] = (t, t + v, w)
            heapq.heappush(running, (t + v, w))
    return out


#: Rows with fewer lexicon hits than this are unsure; delay of the way between two places, in ms.
UNSURE, LINK_MS = 20, 250


def _unsure(spark: SparkSession, sf_dir: str, tasks: DataFrame) -> DataFrame:
    """Tasks without evidence: fewer lexicon hits of any label than ``UNSURE``."""
    from elastipool.model import LEXICON
    from elastipool.sources import ingest

    docs = ingest.table(spark, sf_dir, "documents").select(F.col("doc_id").alias("task_id"), "text")
    hits = classify.let(classify.tokens(F.col("text")), lambda tok: sum((classify.count_of(tok, ws) for ws in LEXICON["lang"].values()), F.lit(0)))
    return tasks.select("task_id").join(docs, "task_id").where(hits < UNSURE).select("task_id")


def _totals(df: DataFrame) -> DataFrame:
    return df.groupBy("run_id").agg(F.count("*").alias("n"), F.max("finish_ms").alias("end_ms"), F.sum("wait_ms").alias("wait_ms"))


def heterogeneous(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two tiers: a fast pool takes all rows; those without evidence go on to a heavy pool. One row a tier."""
    from elastipool.model import FIGURE, STATIC2
    from elastipool.plans import runs

    t = runs.tasks(spark, sf_dir)
    fast = kernel.results(kernel.simulate(t, [FIGURE.but(run_id="fast")]))
    second = fast.join(_unsure(spark, sf_dir, t), "task_id").select("shard", "task_id", "seq", "prio", F.col("finish_ms").alias("enq_ms"), (F.col("svc_ms") * 3).alias("svc_ms"))
    return _totals(fast.unionByName(kernel.results(kernel.simulate(second, [STATIC2.but(run_id="heavy")]))))


def edge_cloud(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Placement: a small fixed pool at the edge takes every row; unsure ones travel to an elastic pool in the cloud, which serves faster, and back. One row a place, each
    task counted where it ends, at the time its answer is at the edge."""
    from elastipool.model import FIGURE, STATIC2
    from elastipool.plans import runs

    t = runs.tasks(spark, sf_dir)
    edge = kernel.results(kernel.simulate(t, [STATIC2.but(run_id="edge")]))
    far = _unsure(spark, sf_dir, t)
    second = edge.join(far, "task_id").select("shard", "task_id", "seq", "prio", (F.col("finish_ms") + LINK_MS).alias("enq_ms"), F.greatest(F.expr("svc_ms * 700 div 1000"), F.lit(1)).alias("svc_ms"))
    cloud = kernel.results(kernel.simulate(second, [FIGURE.but(run_id="cloud")])).withColumn("finish_ms", F.col("finish_ms") + LINK_MS)
    return _totals(edge.join(far, "task_id", "left_anti").select("run_id", "finish_ms", "wait_ms").unionByName(cloud.select("run_id", "finish_ms", "wait_ms")))
