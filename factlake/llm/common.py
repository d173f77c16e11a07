"""Helpers that the corpus operators share: table access, scratch tables, text batches."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from factlake.functions.texts import text_chunks
from factlake.sources.scratch import materialize

__all__ = ["materialize", "residue", "table", "text_chunks"]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def residue(column: str, modulus: int):
    """crc32 of the id written as text, modulo ``modulus``: a split that does not depend on the engine."""
    return F.crc32(F.col(column).cast("string")) % modulus
