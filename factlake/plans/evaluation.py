"""Measures and experiments over ranked results."""

from __future__ import annotations

from collections.abc import Callable
from math import erf, pi, sqrt

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from factlake.functions import signals as S
from factlake.functions.worlds import inside
from factlake.params import RANKERS, Weights, grid


def judged(ranked: DataFrame, queries: DataFrame, conf: str = "trust") -> DataFrame:
    """Every query with its top answer: right, stale, misled and the confidence in it; no answer is wrong."""
    top = ranked.filter("rank = 1").select("query_id", "unit_id", "status", "is_rumour", F.col(conf).alias("conf"))
    rows = queries.select("query_id", "kind", "truth").join(top, "query_id", "left")
    return _marks(rows)


def _marks(rows: DataFrame) -> DataFrame:
    return rows.withColumns({"right": F.coalesce((F.col("unit_id") == F.col("truth")).cast("double"), F.lit(0.0)), "stale": F.coalesce((F.col("status") == "DEPRECATED").cast("double"), F.lit(0.0)), "misled": F.coalesce(F.col("is_rumour").cast("double"), F.lit(0.0))})


def accuracy(j: DataFrame) -> DataFrame:
    """Accuracy over all and by kind, in one pass."""
    return j.rollup("kind").agg(F.count("*").alias("n"), F.round(F.avg("right"), 6).alias("accuracy")).select(F.coalesce("kind", F.lit("overall")).alias("kind"), "n", "accuracy")


def summary(j: DataFrame, *by: str) -> DataFrame:
    """The measures of the main comparison in one row (for each value of ``by``)."""
    of = lambda k: F.round(F.avg(F.when(F.col("kind") == k, F.col("right"))), 6).alias(k)
    ask = F.col("kind").isin("current", "conflict")
    return j.groupBy(*by).agg(F.count("*").alias("n"), F.round(F.avg("right"), 6).alias("overall"), of("current"), of("time_point"), of("conflict"), F.round(F.avg(F.when(F.col("kind") == "current", F.col("stale"))), 6).alias("stale"), F.round(F.avg(F.when(ask, F.col("misled"))), 6).alias("misled"))


def reliability(j: DataFrame, bins: int = 10, by: tuple[str, ...] = ()) -> DataFrame:
    """By confidence bin: answers, mean confidence, accuracy."""
    b = F.least(F.floor(F.col("conf") * bins), F.lit(bins - 1)).cast("long")
    return j.filter("conf IS NOT NULL").groupBy(*by, b.alias("bin")).agg(F.count("*").alias("n"), F.avg("conf").alias("conf"), F.avg("right").alias("accuracy"))


def ece(j: DataFrame, bins: int = 10) -> DataFrame:
    r = reliability(j, bins)
    return r.agg(F.round(F.sum(F.col("n") * F.abs(F.col("conf") - F.col("accuracy"))) / F.sum("n"), 6).alias("ece"))


def winners(scored: DataFrame, vectors: dict[object, Weights]) -> DataFrame:
    """The candidates that are some weight vector's best, and those vectors' names (won): candidates are sent and sorted once for all."""
    order = Window.partitionBy("query_id").orderBy(F.desc("sim"), F.asc("unit_id"))  # decides between equal scores
    all_ = order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    show, at = ["query_id", "unit_id", "status", "is_rumour", "sim", "trust"], range(len(vectors))
    finals = [F.round(S.final(F.col("sim"), F.col("temporal"), F.col("trust"), F.col("relational"), w), 9).alias(f"_f{i}") for i, w in enumerate(vectors.values())]
    rows = scored.select(*show, *finals)
    rows = rows.select(*show, *(F.col(f"_f{i}").eqNullSafe(F.max(f"_f{i}").over(all_)).alias(f"_m{i}") for i in at), F.row_number().over(order).alias("_n"))
    rows = rows.select(*show, *((F.col("_n") == F.min(F.when(F.col(f"_m{i}"), F.col("_n"))).over(all_)).alias(f"_w{i}") for i in at))
    won = F.array_compact(F.array(*(F.when(F.col(f"_w{i}"), F.lit(n)) for i, n in enumerate(vectors))))
    return rows.select(*show, won.alias("won")).filter(F.size("won") > 0)


def compare(scored: DataFrame, queries: DataFrame, vectors: dict[object, tuple[Weights, str]], name: str) -> DataFrame:
    """The main measures and the calibration error of every weight vector (with its column of confidence), a row each."""
    top = winners(scored, {n: w for n, (w, _) in vectors.items()})
    rows = queries.select("query_id", "kind", "truth").join(top, "query_id", "left")
    # a query without candidates has no answer under any vector
    rows = rows.withColumn(name, F.explode(F.coalesce("won", F.array(*map(F.lit, vectors)))))
    conf = F.coalesce(*(F.when(F.col(name) == n, F.col(c)) for n, (_, c) in vectors.items()))
    return _measures(_marks(rows.withColumn("conf", conf)), name)


def compare_worlds(scored: DataFrame, queries: DataFrame, vectors: dict[str, tuple[Weights, str]], name: str, worlds: int) -> DataFrame:
    """``compare`` in each of several worlds (world: its number).

    Candidates have a similarity for each world (sim_0, ...; null where they are none), queries the worlds in which they
    are asked. Both are sent once, and one grouping finds the winners of all: the same that sorting each would give.
    """
    each = [(i, n) for i in range(worlds) for n in vectors]

    def first(i, n):
        (w, conf), sim = vectors[n], F.col(f"sim_{i}")
        final = F.round(S.final(sim, F.col("temporal"), F.col("trust"), F.col("relational"), w), 9)
        row = F.struct((-final).alias("less"), (-sim).alias("far"), "unit_id", "status", "is_rumour", (sim if conf == "sim" else F.col(conf)).alias("conf"))
        return F.min(F.when(sim.isNotNull(), row)).alias(f"top_{i}_{n}")

    rows = queries.select("query_id", "kind", "truth", "worlds").join(scored.groupBy("query_id").agg(*(first(i, n) for i, n in each)), "query_id", "left")
    asked = F.array_compact(F.array(*(F.when(inside(i), F.struct(F.lit(i).alias("world"), F.lit(n).alias(name), F.col(f"top_{i}_{n}").alias("top"))) for i, n in each)))
    rows = rows.select("kind", "truth", F.explode(asked).alias("e")).select("kind", "truth", "e.world", f"e.{name}", *(f"e.top.{c}" for c in ("unit_id", "status", "is_rumour", "conf")))
    return _measures(_marks(rows), "world", name)


def _measures(j: DataFrame, *name: str, bins: int = 10) -> DataFrame:
    """``summary`` and ``ece`` for each value of ``name``, in one pass over the answers."""
    b = F.when(F.col("conf").isNotNull(), F.least(F.floor(F.col("conf") * bins), F.lit(bins - 1)).cast("long"))
    parts = {"": F.lit(True), **{f"_{k}": F.col("kind") == k for k in ("current", "time_point", "conflict")}, "_asked": F.col("kind").isin("current", "conflict")}
    sums = [F.sum(F.when(on, F.col(c))).alias(f"{c}{k}") for k, on in parts.items() for c in ("right", "stale", "misled")]
    j = j.groupBy(*name, b.alias("bin")).agg(F.count("*").alias("n"), F.avg("conf").alias("conf"), F.avg("right").alias("accuracy"), *(F.count_if(on).alias(f"n{k}") for k, on in parts.items() if k), *sums)
    mean = lambda c, k="": F.round(F.sum(f"{c}{k}") / F.nullif(F.sum(f"n{k}"), F.lit(0)), 6)
    gap, answered = F.when(F.col("bin").isNotNull(), F.col("n") * F.abs(F.col("conf") - F.col("accuracy"))), F.when(F.col("bin").isNotNull(), F.col("n"))
    return j.groupBy(*name).agg(F.sum("n").alias("n"), mean("right").alias("overall"), *(mean("right", f"_{k}").alias(k) for k in ("current", "time_point", "conflict")), mean("stale", "_current").alias("stale"), mean("misled", "_asked").alias("misled"), F.round(F.sum(gap) / F.sum(answered), 6).alias("ece"))


def top_by_weights(scored: DataFrame, weights: DataFrame) -> DataFrame:
    """The winner of each query under each weight row (w_id, w_sim, w_tmp, w_tru, w_rel); the weights are few and broadcast."""
    score = F.col("sim") * F.col("w_sim") + F.col("temporal") * F.col("w_tmp") + F.col("trust") * F.col("w_tru") + F.col("relational") * F.col("w_rel")
    rows = scored.crossJoin(F.broadcast(weights)).withColumn("final", F.round(score, 9))
    w = Window.partitionBy("w_id", "query_id").orderBy(F.desc("final"), F.desc("sim"), F.asc("unit_id"))
    return rows.withColumn("rank", F.row_number().over(w)).filter("rank = 1")


def weight_rows(spark, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame([(i, *map(float, r)) for i, r in enumerate(rows)], "w_id long, w_sim double, w_tmp double, w_tru double, w_rel double")


def ablations(w: Weights = RANKERS["m4"]) -> list[tuple]:
    """The full vector and the four that lack one signal."""
    return [w.as_tuple(), *(w.without(k).as_tuple() for k in ("sim", "tmp", "tru", "rel"))]


def tune(scored: DataFrame, queries: DataFrame, step: float = 0.1, more: tuple = ()) -> DataFrame:
    """Accuracy on the development and test halves of every weight row; the best on development comes first.

    Queries are split by the parity of the number in their id; equal accuracies go to the earlier row. ``more`` vectors come after the grid.
    """
    return tune_rows(scored, queries, [*grid(step), *more])


def tune_rows(scored: DataFrame, queries: DataFrame, rows: list[tuple]) -> DataFrame:
    """The same for any weight rows, numbered in their order."""
    w = weight_rows(scored.sparkSession, rows)
    top = top_by_weights(scored, w).select("w_id", "query_id", (F.col("unit_id") == F.col("truth")).cast("double").alias("right"))
    half = F.when(F.pmod(F.regexp_extract("query_id", "([0-9]+)$", 1).cast("long"), F.lit(2)) == 0, "dev").otherwise("test")
    size = queries.groupBy(half.alias("half")).agg(F.count("*").alias("n"))
    right = top.groupBy("w_id", half.alias("half")).agg(F.sum("right").alias("right"))
    acc = right.join(F.broadcast(size), "half").groupBy("w_id").agg(F.round(F.max(F.when(F.col("half") == "dev", F.col("right") / F.col("n"))), 6).alias("dev"), F.round(F.max(F.when(F.col("half") == "test", F.col("right") / F.col("n"))), 6).alias("test"))
    return w.join(acc, "w_id", "left").fillna(0.0, ["dev", "test"])


def best_weights(tuned: DataFrame) -> DataFrame:
    return tuned.orderBy(F.desc("dev"), "w_id").limit(1)


def tune_sequential(objective, steps: int = 20, start: Weights = RANKERS["m4"], step: float = 0.1) -> tuple[Weights, float]:
    """Coordinate search of weights: moves ``step`` of weight between two signals as long as the objective grows."""
    best, value = start, objective(start)
    for _ in range(steps):
        tried = []
        w = list(best.as_tuple())
        for i in range(4):
            for j in range(4):
                if i != j and w[i] >= step - 1e-9:
                    v = list(w)
                    v[i], v[j] = round(v[i] - step, 6), round(v[j] + step, 6)
                    tried.append(Weights(*v))
        scored = [(objective(t), t) for t in tried]
        top = max(scored, key=lambda x: x[0], default=(value, best))
        if top[0] <= value:
            break
        value, best = top
    return best, value


def tune_bayes(objective: Callable[[list[tuple]], list[float]], trials: int = 24, batch: int = 4, step: float = 0.1, width: float = 0.3) -> tuple[tuple, float, int]:
    """Best weights, their value and the number of vectors tried, by Bayesian search over the grid.

    A Gaussian process over the vectors tried so far gives each grid point a mean and a deviation; the ``batch`` points
    of the largest expected improvement are evaluated next. ``objective`` takes a list of vectors. Starts from the corners.
    """
    points = np.array(grid(step))
    kernel = lambda a, b: np.exp(-((a[:, None] - b[None]) ** 2).sum(-1) / (2 * width**2))
    tried = [int(np.abs(points - w).sum(1).argmin()) for w in (*np.eye(4), np.full(4, 0.25))]
    values = list(objective([tuple(points[i]) for i in tried]))
    while len(tried) < trials:
        y = np.array(values)
        x = points[tried]
        gain = np.linalg.solve(kernel(x, x) + 1e-4 * np.eye(len(x)), np.c_[y - y.mean(), kernel(x, points)])
        mean = y.mean() + kernel(points, x) @ gain[:, 0]
        deviation = np.sqrt(np.maximum(1e-12, 1 - (kernel(points, x) * gain[:, 1:].T).sum(1))) * max(y.std(), 1e-6)
        z = (mean - y.max()) / deviation
        density = np.exp(-z * z / 2) / sqrt(2 * pi)
        expected = deviation * (z * np.vectorize(lambda v: 0.5 * (1 + erf(v / sqrt(2))))(z) + density)
        expected[tried] = -1
        new = np.argsort(-expected, kind="stable")[: min(batch, trials - len(tried))].tolist()
        values += objective([tuple(points[i]) for i in new])
        tried += new
    best = int(np.argmax(values))
    return tuple(float(v) for v in points[tried[best]]), values[best], len(tried)


def ranking_quality(ranked: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """Recall at k, mean reciprocal rank and nDCG of single-truth queries."""
    hit = ranked.join(queries.select("query_id", "truth"), "query_id").filter((F.col("unit_id") == F.col("truth")) & (F.col("rank") <= k)).select("query_id", "rank")
    rows = queries.select("query_id").join(hit, "query_id", "left")
    return rows.agg(F.count("*").alias("n"), F.round(F.avg(F.col("rank").isNotNull().cast("double")), 6).alias("recall"), F.round(F.avg(F.coalesce(1.0 / F.col("rank"), F.lit(0.0))), 6).alias("mrr"), F.round(F.avg(F.coalesce(1.0 / F.log2(F.col("rank") + 1.0), F.lit(0.0))), 6).alias("ndcg"))


def conf_column(name: str) -> str:
    """Similarity stands for confidence where trust takes no part."""
    return "sim" if name == "m1" else "trust"
