"""A corpus pipeline of the training-data operators: each stage reads what the one before it kept, from a written table.

Toxic documents go; of each group of near copies the smallest id stays; documents that hold a benchmark item go; personal data is replaced;
what is left is encoded. Rows that the filtering stages keep, keep all their columns, whatever these are called; the last stage returns counts and digests instead.

Null and empty texts are no reason to go: they are scored like any text without known features, belong to no group, hold no item and no entity, and encode to no ids. Rows
without an id are judged by their text and never taken for copies by id. Repeated rows are judged alike. An empty table stays empty through all stages.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from elastipool.llm import bpe, decontam, pii, setjoin, toxicity
from elastipool.llm.common import discard, materialise, table


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Without the documents predicted to be toxic. Both models are fitted on this stage's input and its labels; without labels nothing goes. Every row is
    judged where it lies, by its own text."""
    lm, model = toxicity.models(docs, table(spark, sf_dir, "labels", "doc_id", "toxic"))
    return toxicity.without_toxic(docs, lm, model)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component of near copies: that of the smallest id. A document that is given in several equal rows stays in all of them; of texts that
    share an id with a copy's, all go with it; rows without an id stay."""
    comp = materialise(setjoin.components_of(docs), "pipeline-classes")
    gone = comp.where("doc_id <> component_id").select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Without documents that hold three quarters of a benchmark item's shingles; without a benchmark nothing goes."""
    return decontam.without_contaminated(docs, table(spark, sf_dir, "benchmark"))


def replace_pii(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data replaced in the texts; n_chars follows the new text. No row goes."""
    out = pii.redacted(docs)
    return out.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in out.columns else out


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Counts and digests of the ids of every text that is left, and of the bytes they decode to; one row for each row, without its other columns."""
    import public_tokenizers

    return bpe.digests(docs, bpe.read_ranks(public_tokenizers.path(bpe.RANKS)), public_tokenizers.PATTERN)


STAGES = [
    ("toxicity", drop_toxic),
    ("near_copies", drop_near_copies),
    ("decontamination", drop_contaminated),
    ("pii", replace_pii),
    ("bpe", encode),
]

#: Learned scores and tokenizer merges have no SQL form: the stages are tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            out = materialise(out, f"pipeline-{name}")
            discard(docs)
        docs = out
    return docs
