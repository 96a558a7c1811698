"""Stage 1: deterministic stratified samples and a disjoint training split.

Ranks use md5(seed:doc_id), which any engine can repeat. A literal bound on the rank lets Spark cut each class to its first rows before the shuffle,
so no task holds a class. Equal texts count once (lowest id), so no text can be in both splits.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from elastipool.model import N_EVAL, N_TRAIN, SEED


def key(seed: int = SEED, id_col: str = "doc_id") -> Column:
    return F.md5(F.concat(F.lit(f"{seed}:"), F.col(id_col).cast("string")))


def distinct_texts(df: DataFrame) -> DataFrame:
    """The row of lowest doc_id of each text; 16-byte digests are shuffled, not texts."""
    low = df.groupBy(F.md5("text").alias("text_md5")).agg(F.min_by(F.struct("doc_id", "y", "n_chars", "source"), "doc_id").alias("r"))
    return low.select("text_md5", "r.doc_id", "r.y", "r.n_chars", "r.source")


def class_sizes(reps: DataFrame, n: int = N_EVAL) -> DataFrame:
    """(classes, per_class): one row; half of the smallest class stays for training."""
    c = reps.groupBy("y").agg(F.count("*").alias("c"))
    return c.agg(F.count("*").alias("classes"), F.min("c").alias("least")).select("classes", F.least(F.expr(f"{n} div classes"), F.expr("least div 2")).alias("per_class"))


def balanced(df: DataFrame, n: int = N_EVAL, seed: int = SEED) -> DataFrame:
    """The same number of rows of each class."""
    reps = distinct_texts(df)
    rank = F.row_number().over(Window.partitionBy("y").orderBy(key(seed), "doc_id"))
    top = reps.withColumn("r", rank).where(F.col("r") <= n)
    return top.crossJoin(F.broadcast(class_sizes(reps, n))).where("r <= per_class").select("doc_id", "y", "n_chars", "source", "text_md5", "r")


def proportional(df: DataFrame, n: int = N_EVAL, seed: int = SEED) -> DataFrame:
    """Class shares of the data, rounded by largest remainder; quotas are one row a class and broadcast."""
    reps = distinct_texts(df)
    c = reps.groupBy("y").agg(F.count("*").alias("c"))
    total = c.agg(F.sum("c").alias("total"))
    q = c.crossJoin(F.broadcast(total)).withColumn("size", F.least(F.lit(n), F.expr("total div 2")))
    q = q.withColumn("base", F.expr("(c * size) div total")).withColumn("rest", F.expr("(c * size) % total"))
    whole = Window.partitionBy("size")
    q = q.withColumn("extra", F.col("size") - F.sum("base").over(whole)).withColumn("o", F.row_number().over(whole.orderBy(F.desc("rest"), "y")))
    q = q.select("y", (F.col("base") + F.when(F.col("o") <= F.col("extra"), 1).otherwise(0)).alias("quota"))
    rank = F.row_number().over(Window.partitionBy("y").orderBy(key(seed), "doc_id"))
    top = reps.withColumn("r", rank).where(F.col("r") <= n)
    return top.join(F.broadcast(q), "y").where("r <= quota").select("doc_id", "y", "n_chars", "source", "text_md5", "r")


def approximate(df: DataFrame, n: int = N_EVAL, seed: int = SEED, margin: float = 1.2) -> DataFrame:
    """The balanced sample by a first map-only cut: of each class only rows whose key lies in the least ``margin * n / size`` of its range go on to be ranked.
    Where that leaves a class short, its rows are ranked in full, so the sample is always the balanced one. Sizes are one row a class."""
    sizes = distinct_texts(df).groupBy("y").agg(F.count("*").alias("c"))
    least = {r.y: int(min(1.0, margin * n / r.c + 8 / r.c) * (1 << 32)) for r in sizes.collect()}
    if not least:
        return balanced(df, n, seed)
    limit = F.create_map(*[F.lit(x) for p in least.items() for x in p])
    at = F.conv(F.substring(key(seed), 1, 8), 16, 10).cast("long")
    kept = df.where(at <= F.element_at(limit, F.col("y"))).select(F.md5("text").alias("text_md5"), "doc_id", "y", "n_chars", "source")
    # a kept row stands for its text only if it is the text's first row; the digests looked up are few, by the cut
    first = df.select(F.md5("text").alias("text_md5"), "doc_id").join(kept.select("text_md5").distinct(), "text_md5", "left_semi").groupBy("text_md5").agg(F.min("doc_id").alias("doc_id"))
    reps = kept.join(first, ["text_md5", "doc_id"], "left_semi")
    per_class = class_sizes(distinct_texts(df), n)
    enough = reps.groupBy("y").agg(F.count("*").alias("c")).agg(F.min("c").alias("c"), F.count("*").alias("k")).crossJoin(per_class).first()
    if enough is None or enough.k < len(least) or enough.c < enough.per_class:
        return balanced(df, n, seed)
    rank = F.row_number().over(Window.partitionBy("y").orderBy(key(seed), "doc_id"))
    return reps.withColumn("r", rank).where(F.col("r") <= enough.per_class).select("doc_id", "y", "n_chars", "source", "text_md5", "r")


def normalised(text: Column) -> Column:
    """Digest of a text without case, punctuation and spacing."""
    return F.md5(F.regexp_replace(F.lower(text), r"[^\p{L}]+", " "))


def leakage_normalised(train: DataFrame, sample: DataFrame, docs: DataFrame) -> DataFrame:
    """Training rows whose normalised text is also that of a sample row. Digests are joined, texts stay where they are."""
    d = docs.select("doc_id", normalised(F.col("text")).alias("norm"))
    seen = d.join(sample.select("doc_id"), "doc_id", "left_semi").select("norm")
    return d.join(train.select("doc_id"), "doc_id", "left_semi").join(seen, "norm", "left_semi").agg(F.count("*").alias("shared_normalised"))


def train_split(df: DataFrame, sample: DataFrame, n: int = N_TRAIN, seed: int = SEED) -> DataFrame:
    """At most ``n`` rows whose texts are not in the sample."""
    left = distinct_texts(df).join(sample.select("text_md5"), "text_md5", "left_anti")
    rank = F.row_number().over(Window.orderBy(key(seed + 1), "doc_id"))
    return left.orderBy(key(seed + 1), "doc_id").limit(n).withColumn("r", rank).select("doc_id", "y", "n_chars", "source", "text_md5", "r")


def leakage(train: DataFrame, sample: DataFrame) -> DataFrame:
    """Shared ids and shared texts of two splits; both are 0 for :func:`train_split`."""
    ids = train.join(sample.select("doc_id"), "doc_id", "left_semi").agg(F.count("*").alias("shared_ids"))
    texts = train.join(sample.select("text_md5"), "text_md5", "left_semi").agg(F.count("*").alias("shared_texts"))
    return ids.crossJoin(texts)
