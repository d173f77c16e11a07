"""A training corpus from ``documents`` in five stages.

Each stage takes (spark, docs, sf_dir), works on all that the one before it kept, and returns a
DataFrame; ``run`` writes each to Parquet in the shared scratch folder and reads it back. All but the
last return the columns of ``documents``; the last adds the mixture's columns.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from factlake.llm import decontam, mixing, neardup, pii, toxicity
from factlake.llm.common import materialize, table

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
BROADCAST = 1_000_000


def _documents(docs: DataFrame) -> DataFrame:
    return docs.select(*(c for c in COLUMNS if c in docs.columns))


def _without(docs: DataFrame, gone: DataFrame) -> DataFrame:
    """Rows whose doc_id is not among ``gone``; ids of a checked size are broadcast."""
    gone = materialize(gone.select("doc_id").distinct(), "pipeline-gone")
    return _documents(docs).join(F.broadcast(gone) if gone.count() <= BROADCAST else gone, "doc_id", "left_anti").select(*(c for c in COLUMNS if c in docs.columns))


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects documents that the toxicity model, fitted on this stage's labelled rows, calls toxic."""
    model = toxicity.fit(docs, docs, table(spark, sf_dir, "labels"))
    return _without(docs, toxicity.score(docs, model).filter("predicted = 1"))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document with the smallest id of every group of near duplicates, and all that have none."""
    return _without(docs, neardup.near_duplicates(docs, size=5, percent=80).filter("NOT kept"))


def drop_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects documents that hold a benchmark item."""
    return _without(docs, decontam.find(docs, table(spark, sf_dir, "benchmark")))


def mask_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every span of personal data becomes its kind in angle brackets; n_chars follows."""
    return pii.mask(_documents(docs))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Adds tokens, domain, posterior, rate and copies; no document's rate is under one, so all stay."""
    rates = mixing.mix(docs, table(spark, sf_dir, "labels"), least=1.0, passes=30)
    few = rates.drop("source").dropDuplicates(["doc_id"])
    return _documents(docs).join(few, "doc_id", "left")


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", drop_benchmark),
    ("pii", mask_personal_data),
    ("mixing", mix_sources),
]

ORACLE_SQL = None  # the stages learn models and join by similarity; tests compare with brute force


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = materialize(stage(spark, docs, sf_dir), f"stage-{name}")
    return docs
