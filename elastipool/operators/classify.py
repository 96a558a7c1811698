"""Pluggable classifiers: text in, label out, map-only where the model allows it. None of them sees the queue.

Roles stand in for language models that are not here: a lexicon that votes by words (fast), the lexicon with letter groups of every word, or both shape
rules (heavy), a scorer that only knows label names (weak), and multinomial naive Bayes trained on the split (supervised). Their accuracy is theirs.
A text is split into words once, whatever the number of labels.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from elastipool.model import DEFAULT, DIFFERENT_PM, HINTS, LETTERS_PM, LEXICON, WORD_WEIGHT
from elastipool.session import ship

ERROR = "__error__"
TOKEN = r"[^\p{L}]+"


def let(value: Column, f: Callable[[Column], Column]) -> Column:
    """``f(value)`` with the value computed once, however often f uses it."""
    return F.transform(F.array(value), f)[0]


def tokens(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), TOKEN), lambda t: t != "")


def votes(text: Column, words: tuple[str, ...]) -> Column:
    return count_of(tokens(text), words)


def count_of(tok: Column, words: tuple[str, ...]) -> Column:
    return F.size(F.filter(tok, lambda t: t.isin(*words))) if words else F.lit(0)


def argmax(scores: list[tuple[str, Column]], default: str) -> Column:
    """Label of the highest score; ties to the earlier label, the default without any score."""
    rows = F.array(*[F.struct(s.alias("s"), F.lit(-k).alias("o"), F.lit(y).alias("y")) for k, (y, s) in enumerate(scores)])
    return let(F.array_max(rows), lambda b: F.when(b["s"] > 0, b["y"]).otherwise(default))


def zs_fast(task: str, text: Column | None = None) -> Column:
    """Words of the lexicon; for quality, which has no words of its own, one shape rule."""
    text = F.col("text") if text is None else text
    if task == "quality":
        return F.when(few_letters(text), "junk").otherwise("clean")
    return let(tokens(text), lambda tok: argmax([(y, count_of(tok, w)) for y, w in LEXICON[task].items()], DEFAULT[task]))


def zs_weak(task: str, text: Column | None = None) -> Column:
    """Label names only."""
    text = F.col("text") if text is None else text
    return let(tokens(text), lambda tok: argmax([(y, count_of(tok, (y,))) for y in LEXICON[task]], DEFAULT[task]))


def few_letters(text: Column) -> Column:
    return F.length(F.regexp_replace(text, r"[^\p{L}]", "")) * 1000 < F.length(text) * LETTERS_PM


def shape_junk(text: Column | None = None) -> Column:
    """'junk' by shape: few letters, or few different words."""
    text = F.col("text") if text is None else text
    same = let(tokens(text), lambda t: F.size(F.array_distinct(t)) * 1000 < F.size(t) * DIFFERENT_PM)
    return F.when(few_letters(text) | same, "junk").otherwise("clean")


def hint_pattern(hints: tuple[str, ...]) -> str:
    return "|".join(hints)


def zs_heavy(task: str, text: Column | None = None) -> Column:
    """More evidence, and none of it from labels: both shape rules for quality; else words of the lexicon, weighted, and all words that hold a letter group of the label."""
    text = F.col("text") if text is None else text
    if task == "quality":
        return shape_junk(text)

    def score(tok, y):
        hints = HINTS[task][y]
        more = F.size(F.filter(tok, lambda t: t.rlike(hint_pattern(hints)))) if hints else F.lit(0)
        return count_of(tok, LEXICON[task][y]) * WORD_WEIGHT + more

    return let(tokens(text), lambda tok: argmax([(y, score(tok, y)) for y in LEXICON[task]], DEFAULT[task]))


def hash_label(task: str, id_col: str = "doc_id") -> Column:
    """A label drawn by hash of the id: the floor that any classifier must beat."""
    labels = list(LEXICON[task])
    n = F.conv(F.substring(F.md5(F.col(id_col).cast("string")), 1, 4), 16, 10).cast("int") % len(labels)
    return F.element_at(F.array(*map(F.lit, labels)), n + 1)


def majority(train: DataFrame) -> DataFrame:
    """One row: the most frequent label, ties to the lesser."""
    return train.groupBy("y").agg(F.count("*").alias("c")).orderBy(F.desc("c"), "y").limit(1).select(F.col("y").alias("y_hat"))


def nb_fit(train: DataFrame, least: int = 2) -> tuple[DataFrame, DataFrame]:
    """Multinomial naive Bayes with add-one smoothing: (token, y, logp) and (y, prior, other). Tokens seen once are left out, as any vocabulary at scale must be bounded."""
    tok = train.select("y", F.explode(tokens(F.col("text"))).alias("token"))
    c = tok.groupBy("token", "y").agg(F.count("*").alias("c"))
    vocab = c.groupBy("token").agg(F.sum("c").alias("all")).where(F.col("all") >= least).select("token")
    c = c.join(vocab, "token")
    size = vocab.agg(F.count("*").alias("v"))
    per = c.groupBy("y").agg(F.sum("c").alias("total")).crossJoin(F.broadcast(size))
    prior = train.groupBy("y").agg(F.count("*").alias("n")).crossJoin(F.broadcast(train.agg(F.count("*").alias("n_all"))))
    classes = prior.join(per, "y", "left").select("y", F.log(F.col("n") / F.col("n_all")).alias("prior"), (-F.log(F.coalesce("total", F.lit(0)) + F.coalesce("v", F.lit(1)))).alias("other"))
    return c.select("token", "y", F.log(F.col("c") + 1).alias("gain")), classes


def nb_predict(docs: DataFrame, model: tuple[DataFrame, DataFrame]) -> DataFrame:
    """(doc_id, y_hat). A known token adds log(c + 1) to its classes and the class's denominator to all."""
    gains, classes = model
    known = gains.select("token").distinct()
    tok = docs.select("doc_id", F.explode(tokens(F.col("text"))).alias("token")).groupBy("doc_id", "token").agg(F.count("*").alias("k"))
    tok = tok.join(known, "token")
    length = tok.groupBy("doc_id").agg(F.sum("k").alias("len"))
    score = tok.join(gains, "token").groupBy("doc_id", "y").agg(F.sum(F.col("k") * F.col("gain")).alias("s"))
    grid = docs.select("doc_id").crossJoin(F.broadcast(classes)).join(length, "doc_id", "left").join(score, ["doc_id", "y"], "left")
    grid = grid.withColumn("s", F.round(F.col("prior") + F.coalesce("len", F.lit(0)) * F.col("other") + F.coalesce("s", F.lit(0.0)), 6))
    best = F.row_number().over(Window.partitionBy("doc_id").orderBy(F.desc("s"), "y"))
    return grid.withColumn("r", best).where("r = 1").select("doc_id", F.col("y").alias("y_hat"))


def centroids(vectors: DataFrame) -> DataFrame:
    """Integer class means of vectors scaled by 1,000: (label, dim, c)."""
    e = vectors.select("label", F.posexplode(F.transform("embedding", lambda x: F.floor(x.cast("double") * 1000).cast("long"))).alias("dim", "x"))
    return e.groupBy("label", "dim").agg(F.floor(F.sum("x") / F.count("*")).cast("long").alias("c"))


def nearest_centroid(vectors: DataFrame, model: DataFrame) -> DataFrame:
    """(vec_id, y_hat): least squared distance; the model is (labels x dims) rows and is broadcast as one array a label."""
    m = model.groupBy("label").agg(F.array_sort(F.collect_list(F.struct("dim", "c"))).alias("m")).select(F.col("label").alias("y_hat"), F.col("m.c").alias("m"))
    v = vectors.select("vec_id", F.transform("embedding", lambda x: F.floor(x.cast("double") * 1000).cast("long")).alias("v"))
    d = F.aggregate(F.zip_with("v", "m", lambda a, b: (a - b) * (a - b)), F.lit(0).cast("long"), lambda a, x: a + x)
    best = v.crossJoin(F.broadcast(m)).groupBy("vec_id").agg(F.min(F.struct(d.alias("d"), F.col("y_hat"))).alias("b"))
    return best.select("vec_id", F.col("b.y_hat").alias("y_hat"), F.col("b.d").alias("d"))


def guarded(docs: DataFrame, make: Callable[[], Callable[[str], str]], id_col: str = "doc_id") -> DataFrame:
    """(doc_id, y_hat, ok, err) of any Python callable, made once in each worker; an exception fails its own row only."""
    ship(docs.sparkSession)

    def run(parts):
        f = make()
        for pdf in parts:
            out = []
            for i, t in zip(pdf[id_col], pdf["text"]):
                try:
                    out.append((i, f(t), True, None))
                except Exception as e:  # noqa: BLE001  a classifier's error is a result
                    out.append((i, ERROR, False, type(e).__name__))
            yield pd.DataFrame(out, columns=["doc_id", "y_hat", "ok", "err"])

    return docs.select(id_col, "text").mapInPandas(run, "doc_id long, y_hat string, ok boolean, err string")


def external_batch(docs: DataFrame, make: Callable[[], Callable[[np.ndarray], np.ndarray]], features: Column, width: int, batch: int = 512) -> DataFrame:
    """(doc_id, y_hat int) of a model over feature vectors, loaded once a worker and called on whole batches."""
    from pyspark.ml.functions import predict_batch_udf
    from pyspark.sql.types import IntegerType

    ship(docs.sparkSession)
    f = predict_batch_udf(make, return_type=IntegerType(), batch_size=batch, input_tensor_shapes=[[width]])
    return docs.select("doc_id", f(features).alias("y_hat"))


def faulty(id_col: str = "doc_id", digit: str = "0") -> Column:
    """Rows chosen to fail: those whose digest starts with a hexadecimal digit (one in 16)."""
    return F.substring(F.md5(F.col(id_col).cast("string")), 1, 1) == digit


def with_faults(pred: DataFrame, digit: str = "0") -> DataFrame:
    bad = faulty("doc_id", digit)
    return pred.withColumn("ok", ~bad).withColumn("y_hat", F.when(bad, ERROR).otherwise(F.col("y_hat")))
