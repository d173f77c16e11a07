"""Further variants and workloads."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql import types as T

from factlake.operators import embedding as V
from factlake.operators import maintenance as M
from factlake.operators import retrieval as R
from factlake.params import RANKERS, grid
from factlake.plans import evaluation as E
from factlake.registry import base as B
from factlake.registry.base import query
from factlake.registry.ranking import COUNTS, LOG, main, main_sql, now, orders, policies, policy_table, r6, top, tuned_sql
from factlake.registry.ranking import TOP as TOP_SQL
from factlake.sources import given as G
from factlake.sources import scratch
from factlake.streaming import feedback as X
from factlake.streaming import schedule


@query("eval_main_h30", main_sql(B.orders(30.0)))
def eval_main_h30(spark, d):
    return main(*orders(spark, d, 30.0))


@query("eval_main_exclude_future", main_sql(B.orders(90.0, exclude_future=True)))
def eval_main_exclude_future(spark, d):
    return main(*orders(spark, d, 90.0, exclude_future=True))


@query("rank_m4_k32", B.orders(90.0, 32) + B.ranked(RANKERS["m4"].as_tuple()) + TOP_SQL)
def rank_m4_k32(spark, d):
    return top(R.rank(orders(spark, d, 90.0, 32)[2], RANKERS["m4"]))


HALVES = tuned_sql(B.policies(), (RANKERS["m4"].as_tuple(),))
POINTS = len(grid())


@query("eval_tuning", f"WITH t AS ({HALVES}) SELECT (SELECT test FROM t WHERE w_id < {POINTS} ORDER BY dev DESC, w_id LIMIT 1) AS tuned, max(CASE WHEN w_id = {POINTS} THEN test END) AS default_, max(CASE WHEN w_id = 0 THEN test END) AS plain, count(*) - 1 AS points FROM t")
def eval_tuning(spark, d):
    """Test-half accuracy of the tuned vector, of the default one and of similarity alone, and the size of the grid."""
    _, queries, sc = policies(spark)
    t = E.tune(sc, queries, more=(RANKERS["m4"].as_tuple(),))
    best = E.best_weights(t.filter(F.col("w_id") < POINTS)).select(F.col("test").alias("tuned"))
    of = lambda i: F.max(F.when(F.col("w_id") == i, F.col("test")))
    return best.crossJoin(t.agg(of(POINTS).alias("default_"), of(0).alias("plain"), (F.count("*") - 1).alias("points")))


@query("life_embed", "SELECT doc_id, CAST(64 AS BIGINT) AS dim, CAST(1.0 AS DOUBLE) AS norm FROM documents WHERE len(regexp_extract_all(lower(text), '[\\p{L}0-9]+')) > 0")
def life_embed(spark, d):
    v = V.hashed(G.table(spark, d, "documents").select("doc_id", "text"), "doc_id", "text")
    norm = F.sqrt(F.aggregate("vec", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")))
    return v.select("doc_id", F.size("vec").cast("long").alias("dim"), F.round(norm, 4).alias("norm"))


@query("cand_hashed_passages")
def cand_hashed_passages(spark, d):
    """Benchmark texts as dense queries over hashed vectors of the documents."""
    q = V.hashed(G.table(spark, d, "benchmark").select("item_id", "text"), "item_id", "text").withColumnRenamed("item_id", "query_id")
    u = V.hashed(G.table(spark, d, "documents").select("doc_id", "text"), "doc_id", "text").withColumnRenamed("doc_id", "unit_id")
    return R.candidates_dense(q, u, 8, keep_self=True)


NEWEST = "replaced_by IS NULL AND NOT is_rumour"
JOB = f"WITH {B.policy_units()}, st AS (SELECT CASE WHEN status = 'ACTIVE' AND {B.live_trust()} < 0.15 THEN 'DORMANT' ELSE status END AS status FROM u)"


@query("maint_job", JOB + " SELECT status, count(*) AS n, CAST(11 AS BIGINT) AS edges, CAST(11 AS BIGINT) AS messages, CAST(0 AS BIGINT) AS more, CAST(24 AS BIGINT) AS done FROM st GROUP BY status")
def maint_job(spark, d):
    """Two passes: the second finds the first's edges and queue, so only what was queued since is rippled."""
    u = policy_table(spark)
    none, home = spark.createDataFrame([], "src string, dst string, kind string"), scratch.folder(spark, "job")
    queue = lambda x: u.filter(f"topic % 5 >= {x} AND {NEWEST}").select("unit_id")
    one = schedule.maintenance_job(u, none, queue(4), now(), f"{home}/1", build=G.policy_edges)
    read = lambda at, name: spark.read.parquet(f"{at}/{name}")
    two = schedule.maintenance_job(read(one, "units").select(u.columns), read(one, "edges"), queue(3), now(), f"{home}/2", read(one, "done"))
    n = lambda df, name: df.agg(F.count("*").alias(name))
    out = read(two, "units").groupBy("status").agg(F.count("*").alias("n")).crossJoin(n(read(two, "edges"), "edges"))
    return out.crossJoin(n(read(one, "messages"), "messages")).crossJoin(n(read(two, "messages"), "more")).crossJoin(n(read(two, "done"), "done"))


@query("stream_cycle", JOB + ", hit AS (SELECT CAST(topic + 1 AS BIGINT) AS topic FROM u WHERE topic % 5 = 4 AND topic + 1 < 60 AND replaced_by IS NULL AND NOT is_rumour) SELECT unit_id, round(CASE WHEN replaced_by IS NULL AND NOT is_rumour AND topic IN (SELECT topic FROM hit) THEN greatest(0.01, prior_trust - 0.15) ELSE prior_trust END, 6) AS prior_trust, CAST(2 AS BIGINT) AS passes FROM u")
def stream_cycle(spark, d):
    """Changes that arrive in two files, the second with ids of the first again: each id ripples once, in its own pass."""
    u = policy_table(spark)
    at = X.folder(spark)
    some = lambda rule: u.filter(f"{NEWEST} AND {rule}").select("unit_id").coalesce(1)
    none, home = spark.createDataFrame([], "src string, dst string, kind string"), None
    for rule in ("topic % 10 = 4", "topic % 5 = 4"):
        some(rule).write.mode("append").parquet(f"{at}/changes")
        s = spark.readStream.schema("unit_id string").option("maxFilesPerTrigger", 1).parquet(f"{at}/changes")
        home = schedule.on_changes(spark, s, u, none, now(), home or f"{at}/home", build=G.policy_edges)
    last = schedule.latest(spark, home)
    passes = spark.read.schema("pass long, folder string").parquet(f"{home}/log").agg(F.count("*").alias("passes"))
    return spark.read.parquet(f"{last}/units").select("unit_id", r6(F.col("prior_trust"), "prior_trust")).crossJoin(passes)


@query("stream_unit_counters", f"WITH {LOG} {COUNTS} GROUP BY unit_id")
def stream_unit_counters(spark, d):
    e = X.events(spark, d)
    n = spark.read.parquet(f"{d}/documents.parquet").count()
    unit = F.pmod(F.col("user_id") * 100 + F.get_json_object("props", "$.k").cast("long"), F.lit(n))
    return X.unit_counters(spark, e.select(unit.alias("unit_id"), X.action().alias("action")))


STRIP = "trim(regexp_replace(regexp_replace(regexp_replace(html, '(?s)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '<[^>]*>', ' ', 'g'), '\\s+', ' ', 'g'))"


@query("op_html_text", f"SELECT page_id, md5({STRIP}) AS sha FROM pages")
def op_html_text(spark, d):
    """All visible text by tag stripping; no main-text rules."""
    t = F.regexp_replace(F.regexp_replace("html", r"(?s)<(script|style)[^>]*>.*?</(script|style)>", " "), "<[^>]*>", " ")
    return G.table(spark, d, "pages").select("page_id", F.md5(F.trim(F.regexp_replace(t, r"\s+", " "))).alias("sha"))


@query("op_udf_pandas", "SELECT o_orderkey, round(o_totalprice * 0.3 / 777777.0, 6) AS v FROM orders")
def op_udf_pandas(spark, d):
    @F.pandas_udf(T.DoubleType())
    def scaled(x: pd.Series) -> pd.Series:
        return x * 0.3 / 777777.0

    return G.table(spark, d, "orders").select("o_orderkey", r6(scaled("o_totalprice"), "v"))


@query("op_sample_strat")
def op_sample_strat(spark, d):
    x = G.table(spark, d, "documents").select("doc_id", "lang")
    return x.sampleBy("lang", {"en": 0.1, "fr": 0.5, "de": 0.5, "es": 0.5}, seed=7).groupBy("lang").agg(F.count("*").alias("n"))


@query("maint_contradictions_any_time", "WITH " + B.order_units() + ", p AS (SELECT least(a.unit_id, r.unit_id) AS a, greatest(a.unit_id, r.unit_id) AS b FROM u a JOIN u r ON a.topic = r.topic AND NOT a.is_rumour AND r.is_rumour AND a.value <> r.value) SELECT count(*) AS n, count(DISTINCT a) AS kinds FROM p")
def maint_contradictions_any_time(spark, d):
    return M.value_conflicts(G.order_units(spark, d), overlap=False).agg(F.count("*").alias("n"), F.countDistinct("a").alias("kinds"))
