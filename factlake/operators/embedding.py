"""An offline stand-in for a sentence encoder: hashed n-grams projected to a unit vector."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from factlake.operators.retrieval import terms


def hashed(df: DataFrame, key: str, text: str, dim: int = 64) -> DataFrame:
    """key and vec: each word and word pair adds its damped count, with a hashed sign, at a hashed place; unit length.

    Texts without a word have no row. One shuffle by key; nothing but built-in functions.
    """
    t = terms(df, key, text)
    place, sign = F.pmod(F.xxhash64("term"), F.lit(dim)), F.when(F.pmod(F.xxhash64(F.lit(1), F.col("term")), F.lit(2)) == 0, 1.0).otherwise(-1.0)
    cells = t.select(key, place.cast("int").alias("at"), (sign * F.log1p(F.col("tf").cast("double"))).alias("x")).groupBy(key, "at").agg(F.sum("x").alias("x"))
    rows = cells.groupBy(key).agg(F.map_from_entries(F.collect_list(F.struct("at", "x"))).alias("m"), F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("norm"))
    full = F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), lambda i: (F.coalesce(F.try_element_at("m", i), F.lit(0.0)) / F.greatest("norm", F.lit(1e-12))).cast("float"))
    return rows.select(key, full.alias("vec"))
