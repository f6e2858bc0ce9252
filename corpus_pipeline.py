"""A corpus pipeline of five stages, each by one operator of walkfold.llm, over all that the stage before it kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from walkfold.llm import decontaminate, jaccard_join, mixing, quality, secrets
from walkfold.llm.common import scratch, table

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go. Null and empty texts are scored like any other; repeated rows share their fate; all
    columns are carried, whatever they are called; an empty table stays empty."""
    return quality.keep_good(docs, table(spark, sf_dir, "labels"))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of documents that share 0.8 of their five-word shingles, the first one stays: by doc_id, null ids last, ties by text hash.
    Texts without words link with nothing and all stay; rows repeated whole stay once; all columns are carried."""
    return jaccard_join.keep_one(docs, k=5, percent=80)


def drop_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a window of a benchmark item go. Null texts have no words and stay; an empty benchmark removes nothing; all columns
    are carried, whatever they are called."""
    return decontaminate.drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets are replaced in place; the documents stay. Null texts stay null; a null source is an empty path; repeated rows are treated alike."""
    return secrets.redact(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents that the mix takes, one row for each time: epoch counts from 0, words says how many of its words are taken then.
    Documents without words are never taken; null sources are one source; documents with one id share what is left at the cut."""
    taken = mixing.mix(docs).where("taken > 0")
    epochs = F.sequence(F.lit(0), F.ceil(F.col("taken") / F.col("size")).cast("int") - 1)
    rows = taken.withColumn("epoch", F.explode(epochs))
    return rows.select(*COLUMNS, "epoch", F.least(F.col("size"), F.col("taken") - F.col("epoch") * F.col("size")).alias("words"))


STAGES = [
    ("quality classifier", keep_quality),
    ("n-gram Jaccard join", drop_near_copies),
    ("benchmark decontamination", drop_benchmark),
    ("secret scans", redact_secrets),
    ("mixing to target weights", mix_sources),
]

#: The classifier, the forest and the joins have no SQL form; the tests hold each stage against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages applied to ``documents``, each one's result written and read again."""
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        path = scratch(spark, "stage")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return STAGES[-1][1](spark, docs, sf_dir)
