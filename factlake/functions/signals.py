"""Scoring signals as column expressions; all compile into one stage."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from factlake.params import Params, Weights

P = Params()


def age_days(anchor: Column, at: Column, mode: str = "whole") -> Column:
    """Days from ``anchor`` to ``at``, not under zero; whole days or with their fraction."""
    gap = at - anchor
    days = F.extract(F.lit("DAY"), gap).cast("double")
    if mode == "fractional":
        days = days + (F.extract(F.lit("HOUR"), gap) * 3600 + F.extract(F.lit("MINUTE"), gap) * 60 + F.extract(F.lit("SECOND"), gap)).cast("double") / 86400.0
    return F.greatest(F.lit(0.0), days)


def recency(age: Column, half_life: Column | float = P.half_life) -> Column:
    return F.pow(F.lit(2.0), -age / (half_life if isinstance(half_life, Column) else F.lit(float(half_life))))


def _libm_pow2(x: pd.Series) -> pd.Series:
    """2 to the power of x by the C library, once for each distinct x; the JVM's power differs in the last bit for one in eleven."""
    of, at = np.unique(x.to_numpy(np.float64), return_inverse=True)
    return pd.Series(np.array([math.pow(2.0, v) for v in of])[at])


def recency_libm(age: Column, half_life: Column | float = P.half_life) -> Column:
    """``recency`` as SQL engines in C compute it, to the last bit."""
    return F.pandas_udf(_libm_pow2, "double")(-age / (half_life if isinstance(half_life, Column) else F.lit(float(half_life))))


def in_window(valid_from: Column, valid_to: Column, at: Column, window: str = P.window) -> Column:
    """Whether ``at`` lies in the validity interval; a null side is open."""
    before_end = at <= valid_to if window == "closed" else at < valid_to
    return F.coalesce(at >= valid_from, F.lit(True)) & F.coalesce(before_end, F.lit(True))


def temporal(born: Column, valid_from: Column, valid_to: Column, at: Column, p: Params = P, half_life: Column | None = None) -> Column:
    score = recency(age_days(born, at, p.age_mode), F.coalesce(half_life, F.lit(p.half_life)) if half_life is not None else p.half_life)
    if p.floor_in_window:
        score = F.greatest(score, F.lit(p.outside))
    return F.when(in_window(valid_from, valid_to, at, p.window), score).otherwise(F.lit(p.outside))


def floor_crossing(half_life: Column, outside: float = P.outside) -> Column:
    """The age in days at which a valid unit scores no more than an invalid one."""
    return half_life * F.log2(F.lit(1.0 / outside))


def decayed(base: Column, age: Column, half_life: Column | float = P.half_life) -> Column:
    return base * recency(age, half_life)


def after_feedback(value: Column, pos: Column, neg: Column, p: Params = P) -> Column:
    return F.least(F.lit(1.0), F.greatest(F.lit(p.least), value + p.up * pos - p.down * neg))


def after_access(value: Column, n: Column, p: Params = P) -> Column:
    return F.least(F.lit(1.0), value + p.access * F.log1p(n.cast("double")))


def trust(base: Column, born: Column, at: Column, pos: Column, neg: Column, access: Column, p: Params = P, half_life: Column | None = None) -> Column:
    """Live trust: decay, then feedback, then access."""
    h = F.coalesce(half_life, F.lit(p.half_life)) if half_life is not None else p.half_life
    age = age_days(born, at, p.age_mode)
    return after_access(after_feedback(base * recency_libm(age, h) if p.libm else decayed(base, age, h), pos, neg, p), access, p)


def trust_beta(base: Column, born: Column, at: Column, pos: Column, neg: Column, p: Params = P) -> Column:
    """Posterior mean of a Beta prior centred on the decayed base."""
    c = decayed(base, age_days(born, at, p.age_mode), p.half_life)
    return (p.kappa * c + pos) / (p.kappa + pos + neg)


def bonus(degree: Column, p: Params = P) -> Column:
    return F.least(F.lit(p.bonus_cap), p.bonus * F.log1p(degree.cast("double")))


def final(sim: Column, tmp: Column, tru: Column, rel: Column, w: Weights) -> Column:
    """Weighted sum; a signal of weight zero is left out of the plan."""
    parts = [c * float(x) for c, x in zip((sim, tmp, tru, rel), w.as_tuple(), strict=True) if x]
    total = parts[0]
    for part in parts[1:]:
        total = total + part
    return total


def upper_bound(sim: Column, w: Weights, p: Params = P) -> Column:
    """The most that a candidate can score, from its similarity alone."""
    return sim * float(w.sim) + (w.tmp + w.tru + p.bonus_cap * w.rel)


def cosine(a: Column, b: Column) -> Column:
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda u, v: u.cast("double") * v.cast("double")), F.lit(0.0), lambda s, v: s + v)
    return dot(a, b) / F.nullif(F.sqrt(dot(a, a)) * F.sqrt(dot(b, b)), F.lit(0.0))


def arbiter(generated: Column, retrieved: Column, tau: float = 0.35) -> Column:
    """What to do when a generator's confidence and retrieval trust part by more than ``tau``."""
    gap = F.abs(generated - retrieved)
    return F.when(gap <= tau, "answer").when(generated > retrieved, "clarify").otherwise("abstain")


def trajectory(spark: SparkSession, base: float | DataFrame, days: list[int], p: Params = P) -> DataFrame:
    """day and trust of a unit of that base, or the mean trust of units (prior_trust), that many days after they were born."""
    rows = spark.createDataFrame([(int(d),) for d in days], "day int")
    if isinstance(base, DataFrame):
        aged = base.select("prior_trust").crossJoin(F.broadcast(rows))
        return aged.groupBy("day").agg(F.avg(decayed(F.col("prior_trust"), F.col("day").cast("double"), p.half_life)).alias("trust"))
    return rows.select("day", decayed(F.lit(base), F.col("day").cast("double"), p.half_life).alias("trust"))


def register_sql(spark: SparkSession, p: Params = P) -> None:
    """The signals as temporary SQL functions, which the optimiser inlines."""
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION unit_recency(age DOUBLE) RETURNS DOUBLE RETURN pow(2.0D, -age / {p.half_life}D)")
    spark.sql(
        f"""CREATE OR REPLACE TEMPORARY FUNCTION unit_trust(base DOUBLE, age DOUBLE, pos BIGINT, neg BIGINT, n BIGINT) RETURNS DOUBLE RETURN
        least(1.0D, least(1.0D, greatest({p.least}D, base * pow(2.0D, -age / {p.half_life}D) + {p.up}D * pos - {p.down}D * neg)) + {p.access}D * log1p(n))"""
    )
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION unit_bonus(degree BIGINT) RETURNS DOUBLE RETURN least({p.bonus_cap}D, {p.bonus}D * log1p(degree))")
