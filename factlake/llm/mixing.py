"""Mixing to target weights with soft memberships. DataFrame functions only.

Domains are the classes of the labels table (quality and toxic together). A naive Bayes classifier,
fitted on at most ``max_rows`` labelled documents drawn by hash, gives every document a posterior over
the domains, from counts of words, symbols, lines and of class-bound words. Rates r >= ``least`` are
then fitted so that the expected tokens of every domain, sum of r * tokens * posterior, meet the
targets: projected gradient on the least-squares gap, measured in the metric of the domains' token
overlap, in which a step length of one is exact wherever no bound holds. A pass adds up one number
per domain; a document's rate follows from its own posterior and the passes' multipliers, so no state
is kept between passes.

Default targets are the domains' expected token shares to the power ``temper``, scaled so that no
domain shrinks. ``copies`` realises a rate: its whole part, and one more with the chance of the rest,
decided by a hash of the id. Passes end when the gaps of all domains together are under ``tolerance`` of
the targets; every row tells its domain's target and what was reached.

Cases: without labelled rows all is one domain at its present weight; null and empty texts have no
tokens and posterior equal to the prior; a domain named in the targets that no label has is ignored;
repeated labels of a document count once, the largest; repeated rows are mixed each on its own;
extra columns are ignored.
"""

from __future__ import annotations

from functools import reduce
from math import log

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialize

BASE = ("length", "letters", "symbols", "digits", "variety", "lines")


def _domain() -> Column:
    return F.concat(F.lit("quality="), F.coalesce(F.col("quality").cast("string"), F.lit("?")), F.lit(",toxic="), F.coalesce(F.col("toxic").cast("string"), F.lit("?")))


def _words(docs: DataFrame) -> DataFrame:
    """With text coalesced and its words."""
    rows = docs.withColumn("text", F.coalesce(F.col("text").cast("string"), F.lit("")))
    return rows.withColumn("words", F.array_remove(F.split(F.lower("text"), r"[^\p{L}0-9]+"), ""))


def training_rows(labels: DataFrame, max_rows: int) -> DataFrame:
    known = labels.filter("doc_id IS NOT NULL AND (quality IS NOT NULL OR toxic IS NOT NULL)").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("quality").alias("quality"), F.max("toxic").alias("toxic"))
    return known.select("doc_id", _domain().alias("domain")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_rows)


def lexicon(docs: DataFrame, known: DataFrame, each: int = 60, support: int = 5) -> list[list[str]]:
    """For each domain, its most bound words, in the domains' order; at most ``each`` a domain."""
    held = _words(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(known), "doc_id"))
    n = held.groupBy("domain").count().collect()
    total = {r["domain"]: r["count"] for r in n}
    words = held.select("domain", F.explode(F.array_distinct("words")).alias("word")).groupBy("word", "domain").agg(F.count("*").alias("n"))
    words = words.groupBy("word").agg(F.sum("n").alias("all"), *(F.sum(F.when(F.col("domain") == d, F.col("n")).otherwise(0)).alias(f"n{i}") for i, d in enumerate(sorted(total)))).filter(F.col("all") >= support)
    out = []
    rows = sum(total.values())
    words = materialize(words, "mixing-words")
    for i, d in enumerate(sorted(total)):
        odds = F.log((F.col(f"n{i}") + 0.5) / (total[d] + 1.0)) - F.log((F.col("all") - F.col(f"n{i}") + 0.5) / (rows - total[d] + 1.0))
        gain = F.col(f"n{i}") * odds
        out.append([r["word"] for r in words.filter((F.col(f"n{i}") >= support) & (odds > log(3))).orderBy(gain.desc(), "word").select("word").limit(each).collect()])
    return out


def features(docs: DataFrame, lexica: list[list[str]]) -> DataFrame:
    """doc_id, source, tokens and one number per feature, of every document row."""
    source = F.col("source").cast("string") if "source" in docs.columns else F.lit(None).cast("string")
    rows = _words(docs.select(F.col("doc_id").cast("long").alias("doc_id"), source.alias("source"), "text"))
    bound = sorted({w for ws in lexica for w in ws})
    empty = F.array().cast("array<string>")
    rows = rows.withColumn("kinds", F.array_distinct("words"))
    rows = rows.withColumn("hits", F.array_intersect("kinds", F.array(*map(F.lit, bound))) if bound else empty)
    rows = rows.withColumn("tokens", F.size("words").cast("long")).withColumn("chars", F.length("text"))
    n, c = F.greatest(F.col("tokens"), F.lit(1)), F.greatest(F.col("chars"), F.lit(1))
    numbers = [
        F.log1p(F.col("tokens").cast("double")).alias("length"),
        (F.col("chars") / n).alias("letters"),
        ((F.col("chars") - F.length(F.regexp_replace("text", r"[^\p{L}0-9\s]+", ""))) / c).alias("symbols"),
        ((F.col("chars") - F.length(F.regexp_replace("text", "[0-9]+", ""))) / c).alias("digits"),
        (F.size("kinds") / F.sqrt(n.cast("double"))).alias("variety"),
        ((F.size(F.split("text", "\n")) - 1) / n).alias("lines"),
    ]
    hits = [F.log1p((F.size(F.array_intersect("hits", F.array(*map(F.lit, ws)))) if ws else F.lit(0)).cast("double")).alias(f"hits{i}") for i, ws in enumerate(lexica)]
    return rows.select("doc_id", "source", "tokens", *numbers, *hits)


def posteriors(rows: DataFrame, known: DataFrame, names: list[str]) -> tuple[list[str], Column]:
    """Domains and the posterior array as a column of ``rows``, by naive Bayes with normal features."""
    seen = rows.join(F.broadcast(known), "doc_id")
    stats = seen.groupBy("domain").agg(F.count("*").alias("n"), *(F.avg(f).alias(f"m_{f}") for f in names), *(F.var_pop(f).alias(f"v_{f}") for f in names)).orderBy("domain").collect()
    if not stats:
        return ["all"], F.array(F.lit(1.0))
    total = sum(r["n"] for r in stats)
    spread = {f: max(1e-6, sum(r["n"] * (r[f"v_{f}"] + r[f"m_{f}"] ** 2) for r in stats) / total - (sum(r["n"] * r[f"m_{f}"] for r in stats) / total) ** 2) for f in names}
    logs = []
    for r in stats:
        terms = [F.lit(log(r["n"] / total))]
        for f in names:
            v = (r["n"] * r[f"v_{f}"] + 20 * 0.05 * spread[f]) / (r["n"] + 20) + 0.01 * spread[f]
            gap = F.col(f) - F.lit(r[f"m_{f}"])
            terms.append(-(gap * gap) / F.lit(2 * v) - F.lit(0.5 * log(v)))
        # a text without tokens tells nothing
        logs.append(F.when(F.col("tokens") > 0, reduce(lambda a, b: a + b, terms)).otherwise(terms[0]))
    top = F.greatest(*logs) if len(logs) > 1 else logs[0]
    weights = F.transform(F.array(*logs), lambda x: F.exp(x - top))
    return [r["domain"] for r in stats], F.transform(weights, lambda x: x / F.aggregate(weights, F.lit(0.0), lambda a, b: a + b))


def _rate(history: list[list[float]], least: float) -> Column:
    if not history:
        return F.lit(max(1.0, least))
    steps = F.array(*(F.array(*map(F.lit, h)) for h in history))
    move = lambda r, m: F.greatest(F.lit(float(least)), r - F.aggregate(F.zip_with("p", m, lambda a, b: a * b), F.lit(0.0), lambda a, b: a + b))
    return F.aggregate(steps, F.lit(max(1.0, float(least))), move)


def fit_rates(rows: DataFrame, domains: list[str], targets: dict[str, float] | None, temper: float, budget: float | None, least: float, passes: int, tolerance: float) -> tuple[list[list[float]], np.ndarray, np.ndarray]:
    """Multipliers of each pass, the target tokens and the tokens reached, by domain; rows have tokens and p."""
    d = range(len(domains))
    first = rows.agg(*(F.sum(F.col("tokens") * F.col("p")[i]).alias(f"t{i}") for i in d), *(F.sum(F.col("tokens") * F.col("p")[i] * F.col("p")[j]).alias(f"g{i}_{j}") for i in d for j in d)).first()
    now = np.array([first[f"t{i}"] or 0.0 for i in d])
    gram = np.array([[first[f"g{i}_{j}"] or 0.0 for j in d] for i in d])
    gram += np.eye(len(domains)) * max(1e-9, 1e-9 * np.trace(gram))
    share = now / max(now.sum(), 1e-12)
    want = np.array([targets.get(x, 0.0) for x in domains], float) if targets else share**temper * (share > 0)
    want = want / max(want.sum(), 1e-12)
    scale = budget if budget is not None else max((t / w for t, w in zip(now, want, strict=True) if w > 0 and t > 0), default=0.0)
    goal, history = want * scale, []
    reached = now * max(1.0, least)
    for _ in range(passes):
        gap = reached - goal
        if np.abs(gap).sum() <= tolerance * max(goal.sum(), 1e-12):
            break
        history.append((np.linalg.solve(gram, gap)).tolist())
        r = rows.withColumn("r", _rate(history, least)).agg(*(F.sum(F.col("r") * F.col("tokens") * F.col("p")[i]).alias(f"t{i}") for i in d)).first()
        reached = np.array([r[f"t{i}"] or 0.0 for i in d])
    return history, goal, reached


def mix(docs: DataFrame, labels: DataFrame, targets: dict[str, float] | None = None, temper: float = 0.5, budget: float | None = None, least: float = 0.0, max_rows: int = 20_000, passes: int = 60, tolerance: float = 1e-3) -> DataFrame:
    """doc_id, source, tokens, domain, posterior, rate and copies of every row, with its domain's target (goal) and
    expected tokens at the rates (reached)."""
    known = materialize(training_rows(labels, max_rows), "mixing-known")
    lexica = lexicon(docs, known)
    names = [*BASE, *(f"hits{i}" for i in range(len(lexica)))]
    rows = materialize(features(docs, lexica), "mixing-features")
    domains, posterior = posteriors(rows, known, names)
    rows = materialize(rows.select("doc_id", "source", "tokens", posterior.alias("p")), "mixing-posteriors")
    history, goal, reached = fit_rates(rows, domains, targets, temper, budget, least, passes, tolerance)
    best = F.array_max("p")
    chance = F.pmod(F.xxhash64("doc_id"), F.lit(1_000_003)) / F.lit(1_000_003.0)
    rated = rows.withColumn("rate", _rate(history, least))
    copies = (F.floor("rate") + F.when(chance < F.col("rate") - F.floor("rate"), 1).otherwise(0)).cast("long")
    of = lambda values: F.element_at(F.array(*map(F.lit, values)), F.array_position("p", best).cast("int"))
    told = [of([float(x) for x in v]).alias(n) for n, v in (("goal", goal), ("reached", reached))]
    return rated.select("doc_id", "source", "tokens", of(domains).alias("domain"), best.alias("posterior"), "rate", copies.alias("copies"), *told)
