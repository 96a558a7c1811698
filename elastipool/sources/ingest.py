"""Stage 0: labelled documents and request traffic, read with only the columns a caller needs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def labelled(spark: SparkSession, sf_dir: str, task: str) -> DataFrame:
    """(doc_id, text, y, n_chars, source) of a classification task; the label table is joined only where the label comes from it."""
    docs = table(spark, sf_dir, "documents")
    if task == "lang":
        return docs.select("doc_id", "text", F.col("lang").alias("y"), "n_chars", "source").where(F.col("y").isNotNull())
    labels = table(spark, sf_dir, "labels")
    y = F.when(F.col("quality") == 0, "junk").otherwise("clean") if task == "quality" else F.when(F.col("toxic") == 1, "toxic").otherwise("ok")
    return docs.select("doc_id", "text", "n_chars", "source").join(labels.select("doc_id", y.alias("y")), "doc_id").select("doc_id", "text", "y", "n_chars", "source")


def conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User turns as requests."""
    c = table(spark, sf_dir, "conversations").where("role = 'user'")
    return c.select((F.col("conv_id") * 100 + F.col("turn")).cast("long").alias("doc_id"), "text")


def pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages as requests: markup out, white space squeezed."""
    t = F.regexp_replace(F.col("html"), "<[^>]*>", " ")
    return table(spark, sf_dir, "pages").select(F.col("page_id").alias("doc_id"), F.trim(F.regexp_replace(t, "[ \\t\\r\\n]+", " ")).alias("text"))


#: How a null field is written.
TSV_NULL = "\\N"


def tsv(spark: SparkSession, path: str) -> DataFrame:
    """(y, text, bad) of a label-tab-text file. All characters are literal, quotes too; a row without its tab, or with an empty label, is kept in ``bad``."""
    v = F.col("value")
    tab = F.instr(v, "\t")
    fine = tab > 1
    field = lambda c: F.when(fine & (c != TSV_NULL), c)
    return spark.read.text(path).select(field(F.substring_index(v, "\t", 1)).alias("y"), field(v.substr(tab + 1, F.length(v))).alias("text"), F.when(~fine, v).alias("bad"))


def json_lines(spark: SparkSession, path: str, schema: T.StructType) -> DataFrame:
    return spark.read.schema(schema).json(path)
