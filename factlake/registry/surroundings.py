"""The relational surroundings of the methods: scans, joins, aggregates, windows, sets, functions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from factlake.functions import signals as S
from factlake.plans import evaluation as E
from factlake.registry import base as B
from factlake.registry.base import query
from factlake.registry.ranking import J4, LOG, judged4, r6
from factlake.sources import given as G
from factlake.sources import scratch

ORD = "WITH " + B.order_units()
t = G.table


@query("op_scan_pruned", "SELECT o_orderkey, o_totalprice FROM orders WHERE o_orderdate >= TIMESTAMP '1998-01-01' AND o_orderdate < TIMESTAMP '1999-01-01'")
def op_scan_pruned(spark, d):
    return t(spark, d, "orders").filter((F.col("o_orderdate") >= G.at("1998-01-01")) & (F.col("o_orderdate") < G.at("1999-01-01"))).select("o_orderkey", "o_totalprice")


@query("op_filter_valid_at", ORD + " SELECT unit_id FROM u WHERE TIMESTAMP '1999-06-01' >= valid_from AND (valid_to IS NULL OR TIMESTAMP '1999-06-01' <= valid_to)")
def op_filter_valid_at(spark, d):
    return G.order_units(spark, d).filter(S.in_window(F.col("valid_from"), F.col("valid_to"), G.at("1999-06-01"))).select("unit_id")


@query("op_filter_status", ORD + " SELECT status, count(*) AS n FROM u WHERE status IN ('UNCONSOLIDATED', 'ACTIVE', 'DEPRECATED') GROUP BY status")
def op_filter_status(spark, d):
    return G.order_units(spark, d).filter(F.col("status").isin("UNCONSOLIDATED", "ACTIVE", "DEPRECATED")).groupBy("status").agg(F.count("*").alias("n"))


@query("op_case_nullsafe", ORD + " SELECT count(*) AS n FROM u WHERE replaced_by IS NOT DISTINCT FROM replaces")
def op_case_nullsafe(spark, d):
    return G.order_units(spark, d).filter(F.col("replaced_by").eqNullSafe(F.col("replaces"))).agg(F.count("*").alias("n"))


@query("op_join_broadcast", ORD + " SELECT source, round(sum(prior_trust), 6) AS prior FROM u GROUP BY source")
def op_join_broadcast(spark, d):
    return G.order_units(spark, d).groupBy("source").agg(r6(F.sum("prior_trust"), "prior"))


LO = "SELECT o_orderpriority, count(*) AS n, round(sum(l_extendedprice), 2) AS price FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"
for _hint in ("merge", "shuffle_hash"):

    @query(f"op_join_{_hint}", LO)
    def op_join(spark, d, hint=_hint):
        o = t(spark, d, "orders").select("o_orderkey", "o_orderpriority").hint(hint)
        return t(spark, d, "lineitem").select("l_orderkey", "l_extendedprice").join(o, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("price"))


@query("op_join_full_states", ORD + " SELECT coalesce(a.status, 'none') AS a, coalesce(b.status, 'none') AS b, count(*) AS n FROM (SELECT * FROM u WHERE NOT is_rumour) a FULL JOIN (SELECT * FROM u WHERE source <> 'wiki') b ON a.unit_id = b.unit_id GROUP BY 1, 2")
def op_join_full_states(spark, d):
    u = G.order_units(spark, d)
    a = u.filter("NOT is_rumour").select("unit_id", F.col("status").alias("a"))
    b = u.filter("source <> 'wiki'").select("unit_id", F.col("status").alias("b"))
    return a.join(b, "unit_id", "full").groupBy(F.coalesce("a", F.lit("none")).alias("a"), F.coalesce("b", F.lit("none")).alias("b")).agg(F.count("*").alias("n"))


@query("op_join_semi", f"WITH {LOG} SELECT doc_id FROM documents WHERE doc_id IN (SELECT unit_id FROM elog WHERE action = 'correct')")
def op_join_semi(spark, d):
    log = G.document_log(spark, d).filter("action = 'correct'")
    return t(spark, d, "documents").select("doc_id").join(log, F.col("doc_id") == F.col("unit_id"), "left_semi")


@query("op_join_anti", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_orderpriority = '5-LOW')")
def op_join_anti(spark, d):
    low = t(spark, d, "orders").filter("o_orderpriority = '5-LOW'")
    return t(spark, d, "customer").select("c_custkey").join(low, F.col("c_custkey") == F.col("o_custkey"), "left_anti")


@query("op_join_cross", "SELECT w, source, count(*) AS n FROM (SELECT CASE o_orderpriority WHEN '5-LOW' THEN 'chat' ELSE 'other' END AS source FROM orders), (SELECT unnest([0, 1, 2, 3, 4]) AS w) GROUP BY ALL")
def op_join_cross(spark, d):
    o = t(spark, d, "orders").select(F.when(F.col("o_orderpriority") == "5-LOW", "chat").otherwise("other").alias("source"))
    w = E.weight_rows(spark, E.ablations()).select(F.col("w_id").cast("int").alias("w"))
    return o.crossJoin(F.broadcast(w)).groupBy("w", "source").agg(F.count("*").alias("n"))


@query("op_join_interval_time", ORD + ", l AS (SELECT o_custkey, l_shipdate FROM lineitem JOIN orders ON l_orderkey = o_orderkey) SELECT unit_id, count(*) AS n FROM u JOIN l ON topic = o_custkey AND NOT is_rumour AND l_shipdate >= valid_from AND (valid_to IS NULL OR l_shipdate < valid_to) GROUP BY unit_id")
def op_join_interval_time(spark, d):
    l = t(spark, d, "lineitem").select("l_orderkey", "l_shipdate").join(t(spark, d, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    u = G.order_units(spark, d).filter("NOT is_rumour")
    inside = (F.col("topic") == F.col("o_custkey")) & (F.col("l_shipdate") >= F.col("valid_from")) & (F.col("valid_to").isNull() | (F.col("l_shipdate") < F.col("valid_to")))
    return u.join(l, inside).groupBy("unit_id").agg(F.count("*").alias("n"))


@query("op_join_asof", "SELECT c_custkey, coalesce((SELECT max_by(o_orderkey, (o_orderdate, o_orderkey)) FROM orders WHERE o_custkey = c_custkey AND o_orderdate <= TIMESTAMP '1998-06-01'), -1) AS newest FROM customer")
def op_join_asof(spark, d):
    o = t(spark, d, "orders").filter(F.col("o_orderdate") <= G.at("1998-06-01")).groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_orderdate", "o_orderkey")).alias("newest"))
    return t(spark, d, "customer").select("c_custkey").join(o, F.col("c_custkey") == F.col("o_custkey"), "left").select("c_custkey", F.coalesce("newest", F.lit(-1)).alias("newest"))


@query("op_join_nested_loop", "SELECT r_name, x FROM region, (SELECT CAST(unnest([0.5, 1.5, 2.5, 3.5, 4.5]) AS DOUBLE) AS x) WHERE r_regionkey < x")
def op_join_nested_loop(spark, d):
    x = spark.createDataFrame([(0.5,), (1.5,), (2.5,), (3.5,), (4.5,)], "x double")
    return t(spark, d, "region").join(F.broadcast(x), F.col("r_regionkey") < F.col("x")).select("r_name", "x")


@query("op_lateral_topk", "SELECT n_name, c_custkey FROM (SELECT n_name, c_custkey, row_number() OVER (PARTITION BY n_nationkey ORDER BY c_acctbal DESC, c_custkey) AS r FROM customer JOIN nation ON c_nationkey = n_nationkey) WHERE r <= 3")
def op_lateral_topk(spark, d):
    t(spark, d, "nation").createOrReplaceTempView("lat_nation")
    t(spark, d, "customer").createOrReplaceTempView("lat_customer")
    return spark.sql("SELECT n_name, c_custkey FROM lat_nation, LATERAL (SELECT c_custkey FROM lat_customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 3)")


@query("op_agg_hash", ORD + " SELECT topic, count(*) AS n, count(DISTINCT source) AS sources, count(*) FILTER (WHERE is_rumour) AS rumours, bool_and(value > 1000) AS large FROM u GROUP BY topic")
def op_agg_hash(spark, d):
    return G.order_units(spark, d).groupBy("topic").agg(F.count("*").alias("n"), F.countDistinct("source").alias("sources"), F.count_if("is_rumour").alias("rumours"), F.bool_and(F.col("value") > 1000).alias("large"))


@query("op_agg_cube", ORD + " SELECT coalesce(source, '*') AS source, coalesce(status, '*') AS status, count(*) AS n FROM u GROUP BY CUBE (source, status)")
def op_agg_cube(spark, d):
    return G.order_units(spark, d).cube("source", "status").agg(F.count("*").alias("n")).select(F.coalesce("source", F.lit("*")).alias("source"), F.coalesce("status", F.lit("*")).alias("status"), "n")


@query("op_agg_rollup", J4 + ' SELECT coalesce(kind, \'overall\') AS kind, round(avg("right"), 6) AS accuracy FROM j GROUP BY ROLLUP (kind)')
def op_agg_rollup(spark, d):
    return E.accuracy(judged4(spark, d)).drop("n")


@query("op_agg_gsets", "SELECT coalesce(lang, '*') AS lang, coalesce(source, '*') AS source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source))")
def op_agg_gsets(spark, d):
    x = t(spark, d, "documents").select("lang", "source")
    x = x.groupingSets([[x.lang], [x.source]], x.lang, x.source).agg(F.count("*").alias("n"))
    return x.select(F.coalesce("lang", F.lit("*")).alias("lang"), F.coalesce("source", F.lit("*")).alias("source"), "n")


@query("op_agg_pivot", ORD + " SELECT source, count(CASE WHEN status = 'ACTIVE' THEN 1 END) AS active, count(CASE WHEN status = 'DEPRECATED' THEN 1 END) AS deprecated FROM u GROUP BY source")
def op_agg_pivot(spark, d):
    p = G.order_units(spark, d).groupBy("source").pivot("status", ["ACTIVE", "DEPRECATED"]).count().fillna(0)
    return p.select("source", F.col("ACTIVE").alias("active"), F.col("DEPRECATED").alias("deprecated"))


@query("op_agg_maxby", ORD + " SELECT topic, max_by(unit_id, version_no) AS newest FROM u WHERE NOT is_rumour GROUP BY topic")
def op_agg_maxby(spark, d):
    return G.order_units(spark, d).filter("NOT is_rumour").groupBy("topic").agg(F.max_by("unit_id", "version_no").alias("newest"))


@query("op_agg_collect", ORD + " SELECT topic, string_agg(unit_id, '>' ORDER BY version_no) AS line FROM u WHERE NOT is_rumour GROUP BY topic")
def op_agg_collect(spark, d):
    rows = G.order_units(spark, d).filter("NOT is_rumour").groupBy("topic").agg(F.array_sort(F.collect_list(F.struct("version_no", "unit_id"))).alias("v"))
    return rows.select("topic", F.array_join(F.transform("v", lambda x: x["unit_id"]), ">").alias("line"))


@query("op_agg_approx")
def op_agg_approx(spark, d):
    return t(spark, d, "lineitem").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.percentile_approx("l_extendedprice", 0.5).alias("median"))


@query("op_agg_stats", "SELECT round(stddev_samp(o_totalprice), 4) AS spread, round(median(o_totalprice), 4) AS middle, round(corr(o_totalprice, o_custkey), 6) AS corr FROM orders")
def op_agg_stats(spark, d):
    return t(spark, d, "orders").agg(F.round(F.stddev_samp("o_totalprice"), 4).alias("spread"), F.round(F.median("o_totalprice"), 4).alias("middle"), r6(F.corr("o_totalprice", F.col("o_custkey").cast("double")), "corr"))


WIN = "WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)"


def by_customer():
    return Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")


@query("op_win_rank", f"SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER d AS rk, dense_rank() OVER d AS dr, ntile(4) OVER w AS nt, round(percent_rank() OVER w, 6) AS pr FROM orders {WIN}, d AS (PARTITION BY o_custkey ORDER BY o_orderdate)")
def op_win_rank(spark, d):
    w, day = by_customer(), Window.partitionBy("o_custkey").orderBy("o_orderdate")
    big = lambda c, n: c.cast("long").alias(n)
    return t(spark, d, "orders").select("o_orderkey", big(F.row_number().over(w), "rn"), big(F.rank().over(day), "rk"), big(F.dense_rank().over(day), "dr"), big(F.ntile(4).over(w), "nt"), r6(F.percent_rank().over(w), "pr"))


@query("op_win_leadlag", f"SELECT o_orderkey, coalesce(lag(o_orderkey) OVER w, -1) AS before, coalesce(lead(o_orderkey) OVER w, -1) AS after FROM orders {WIN}")
def op_win_leadlag(spark, d):
    w = by_customer()
    return t(spark, d, "orders").select("o_orderkey", F.coalesce(F.lag("o_orderkey").over(w), F.lit(-1)).alias("before"), F.coalesce(F.lead("o_orderkey").over(w), F.lit(-1)).alias("after"))


@query("op_win_running", f"WITH {LOG} SELECT event_id, count(CASE WHEN action = 'access' THEN 1 END) OVER (PARTITION BY unit_id ORDER BY event_id) AS seen FROM elog")
def op_win_running(spark, d):
    w = Window.partitionBy("unit_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, 0)
    return G.document_log(spark, d).select("event_id", F.count(F.when(F.col("action") == "access", 1)).over(w).alias("seen"))


@query("op_win_moving", f"SELECT o_orderkey, round(avg(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS 4 PRECEDING), 4) AS five, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate RANGE INTERVAL 365 DAY PRECEDING) AS year FROM orders")
def op_win_moving(spark, d):
    days_ = F.datediff("o_orderdate", F.lit("1990-01-01"))
    year = Window.partitionBy("o_custkey").orderBy("day").rangeBetween(-365, 0)
    return t(spark, d, "orders").withColumn("day", days_).select("o_orderkey", F.round(F.avg("o_totalprice").over(by_customer().rowsBetween(-4, 0)), 4).alias("five"), F.count("*").over(year).alias("year"))


@query("op_win_firstlast", ORD + " SELECT unit_id, first_value(unit_id) OVER w AS first, last_value(CASE WHEN is_rumour THEN NULL ELSE unit_id END IGNORE NULLS) OVER w AS last FROM u WINDOW w AS (PARTITION BY topic ORDER BY born_at, unit_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)")
def op_win_firstlast(spark, d):
    w = Window.partitionBy("topic").orderBy("born_at", "unit_id").rowsBetween(Window.unboundedPreceding, 0)
    return G.order_units(spark, d).select("unit_id", F.first("unit_id").over(w).alias("first"), F.last(F.when(~F.col("is_rumour"), F.col("unit_id")), ignorenulls=True).over(w).alias("last"))


@query("op_win_sessionize", "SELECT user_id, count(*) AS events, CAST(sum(new) AS BIGINT) AS sessions FROM (SELECT user_id, CASE WHEN lag(ts) OVER w IS NULL OR ts - lag(ts) OVER w > INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) GROUP BY user_id")
def op_win_sessionize(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    new = F.when(F.lag("ts").over(w).isNull() | (F.col("ts") - F.lag("ts").over(w) > F.make_dt_interval(mins=F.lit(30))), 1).otherwise(0)
    return t(spark, d, "events").select("user_id", new.alias("new")).groupBy("user_id").agg(F.count("*").alias("events"), F.sum("new").alias("sessions"))


@query("op_topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
def op_topk_global(spark, d):
    return t(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10)


@query("op_limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 10 OFFSET 20")
def op_limit_offset(spark, d):
    return t(spark, d, "orders").select("o_orderkey").orderBy("o_orderkey").offset(20).limit(10)


@query("op_set_union", "SELECT l_partkey AS k FROM lineitem UNION SELECT p_partkey FROM part")
def op_set_union(spark, d):
    return t(spark, d, "lineitem").select(F.col("l_partkey").alias("k")).union(t(spark, d, "part").select("p_partkey")).distinct()


@query("op_set_intersect", "SELECT l_suppkey AS k FROM lineitem INTERSECT SELECT s_suppkey FROM supplier WHERE s_acctbal > 0")
def op_set_intersect(spark, d):
    return t(spark, d, "lineitem").select(F.col("l_suppkey").alias("k")).intersect(t(spark, d, "supplier").filter("s_acctbal > 0").select("s_suppkey"))


@query("op_set_except_all", "SELECT k, count(*) AS n FROM (SELECT l_linenumber AS k FROM lineitem EXCEPT ALL SELECT CAST(unnest([1, 1, 2]) AS INTEGER)) GROUP BY k")
def op_set_except_all(spark, d):
    few = spark.createDataFrame([(1,), (1,), (2,)], "k int")
    return t(spark, d, "lineitem").select(F.col("l_linenumber").alias("k")).exceptAll(few).groupBy("k").agg(F.count("*").alias("n"))


@query("op_str_tokens", "SELECT doc_id, CAST(len(regexp_extract_all(lower(text), '[\\p{L}0-9]+')) AS BIGINT) AS n, md5(regexp_replace(text, '\\s+', ' ', 'g')) AS folded, sha256(text) AS sha FROM documents")
def op_str_tokens(spark, d):
    return t(spark, d, "documents").select("doc_id", F.size(F.regexp_extract_all(F.lower("text"), F.lit(r"([\p{L}0-9]+)"), F.lit(1))).cast("long").alias("n"), F.md5(F.regexp_replace("text", r"\s+", " ")).alias("folded"), F.sha2("text", 256).alias("sha"))


@query("op_str_distance", "SELECT a.p_partkey AS a, b.p_partkey AS b, levenshtein(a.p_name, b.p_name) AS n FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_size = b.p_size AND a.p_partkey < b.p_partkey")
def op_str_distance(spark, d):
    p = t(spark, d, "part").select("p_partkey", "p_name", "p_brand", "p_size")
    a, b = p.select(*(F.col(c).alias(f"a_{c}") for c in p.columns)), p.select(*(F.col(c).alias(f"b_{c}") for c in p.columns))
    same = (F.col("a_p_brand") == F.col("b_p_brand")) & (F.col("a_p_size") == F.col("b_p_size")) & (F.col("a_p_partkey") < F.col("b_p_partkey"))
    return a.join(b, same).select(F.col("a_p_partkey").alias("a"), F.col("b_p_partkey").alias("b"), F.levenshtein("a_p_name", "b_p_name").cast("long").alias("n"))


@query("op_date_calendar", "SELECT CAST(date_trunc('month', o_orderdate) AS TIMESTAMP) AS month, count(*) AS n, max(CAST(last_day(o_orderdate) AS DATE)) AS last FROM orders GROUP BY 1")
def op_date_calendar(spark, d):
    o = t(spark, d, "orders").select(F.make_timestamp_ntz(F.year("o_orderdate"), F.month("o_orderdate"), F.lit(1), F.lit(0), F.lit(0), F.lit(0)).alias("month"), F.last_day("o_orderdate").alias("last"))
    return o.groupBy("month").agg(F.count("*").alias("n"), F.max("last").alias("last"))


@query("op_math_decay", "SELECT o_orderkey, round(ln(1.0 + o_totalprice), 6) AS logged, round(least(1.0, greatest(0.01, o_totalprice / 77777.0)), 6) AS clipped, o_orderkey % 7 AS bucket FROM orders")
def op_math_decay(spark, d):
    return t(spark, d, "orders").select("o_orderkey", r6(F.log1p("o_totalprice"), "logged"), r6(F.least(F.lit(1.0), F.greatest(F.lit(0.01), F.col("o_totalprice") / 77777.0)), "clipped"), F.pmod("o_orderkey", F.lit(7)).alias("bucket"))


@query("op_arr_cosine", "SELECT a.vec_id, round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 6) AS sim, round(list_cosine_similarity(CAST(a.embedding[1:16] AS DOUBLE[]), CAST(b.embedding[1:16] AS DOUBLE[])), 6) AS coarse FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def op_arr_cosine(spark, d):
    e = t(spark, d, "embeddings").select("vec_id", "embedding")
    n = e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("next"))
    return e.join(n, "vec_id").select("vec_id", r6(S.cosine(F.col("embedding"), F.col("next")), "sim"), r6(S.cosine(F.slice("embedding", 1, 16), F.slice("next", 1, 16)), "coarse"))


@query("op_map_terms", "SELECT p_partkey, CAST(len(list_distinct(string_split(p_name, ' '))) AS BIGINT) AS kinds, string_split(p_name, ' ')[1] AS first FROM part")
def op_map_terms(spark, d):
    w = F.split("p_name", " ")
    counts = F.map_from_entries(F.transform(F.array_distinct(w), lambda x: F.struct(x, F.lit(1))))
    return t(spark, d, "part").select("p_partkey", F.size(F.map_keys(counts)).cast("long").alias("kinds"), F.element_at(w, 1).alias("first"))


@query("op_struct_nested", ORD + " SELECT unit_id, round(prior_trust, 6) AS base, degree FROM u")
def op_struct_nested(spark, d):
    s = G.order_units(spark, d).select("unit_id", F.struct(F.round("prior_trust", 6).alias("base"), "degree").alias("signals"))
    return s.select("unit_id", "signals.*")


@query("op_json_props", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS a, CAST(json_extract_string(props, '$.k') AS BIGINT) AS b, CAST(json_extract_string(props, '$.k') AS BIGINT) AS c FROM events")
def op_json_props(spark, d):
    v = F.variant_get(F.parse_json("props"), "$.k", "bigint")
    return t(spark, d, "events").select("event_id", F.from_json("props", "k long")["k"].alias("a"), F.get_json_object("props", "$.k").cast("long").alias("b"), v.alias("c"))


@query("op_recursive_chain", "SELECT o_custkey, count(*) AS depth FROM orders WHERE o_custkey <= 20 GROUP BY o_custkey")
def op_recursive_chain(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    t(spark, d, "orders").filter("o_custkey <= 20").select("o_custkey", F.row_number().over(w).alias("n")).createOrReplaceTempView("chain_rows")
    return spark.sql("WITH RECURSIVE c(o_custkey, n) AS (SELECT o_custkey, n FROM chain_rows WHERE n = 1 UNION ALL SELECT r.o_custkey, r.n FROM chain_rows r JOIN c ON r.o_custkey = c.o_custkey AND r.n = c.n + 1) SELECT o_custkey, CAST(max(n) AS BIGINT) AS depth FROM c GROUP BY o_custkey")


@query("op_udf_arrow", "SELECT o_orderkey, round(least(1.0, greatest(0.01, o_totalprice / 777777.0 * 0.3)), 6) AS v FROM orders")
def op_udf_arrow(spark, d):
    import pyarrow.compute as pc

    @F.arrow_udf(T.DoubleType())
    def half(x):
        return pc.min_element_wise(1.0, pc.max_element_wise(0.01, pc.multiply(pc.divide(x, 777777.0), 0.3)))

    return t(spark, d, "orders").select("o_orderkey", r6(half("o_totalprice"), "v"))


@query("op_udaf_ece", J4 + " " + B.ECE)
def op_udaf_ece(spark, d):
    @F.pandas_udf("double")
    def gap(conf: pd.Series, right: pd.Series) -> float:
        bins = (conf * 10).astype(int).clip(upper=9)
        g = pd.DataFrame({"b": bins, "c": conf, "r": right}).groupby("b").agg(n=("c", "size"), c=("c", "mean"), r=("r", "mean"))
        return float((g.n * (g.c - g.r).abs()).sum() / g.n.sum())

    return judged4(spark, d).filter("conf IS NOT NULL").agg(r6(gap("conf", "right"), "ece"))


@query("op_udtf_chunks", "SELECT doc_id, CAST(greatest(1, ceil(length(text) / 1000.0)) AS BIGINT) AS n FROM documents")
def op_udtf_chunks(spark, d):
    @F.udtf(returnType="at int, body string")
    class Chunks:
        def eval(self, text: str):
            for i in range(0, max(1, len(text)), 1000):
                yield i, text[i : i + 1000]

    spark.udtf.register("text_chunks", Chunks)
    t(spark, d, "documents").createOrReplaceTempView("udtf_documents")
    return spark.sql("SELECT doc_id, count(*) AS n FROM udtf_documents, LATERAL text_chunks(text) GROUP BY doc_id")


@query("op_sample_hash", "SELECT CASE WHEN (o_orderkey * 37) % 100 < 30 THEN 'dev' ELSE 'test' END AS half, count(*) AS n FROM orders GROUP BY 1")
def op_sample_hash(spark, d):
    return t(spark, d, "orders").groupBy(F.when(F.pmod(F.col("o_orderkey") * 37, F.lit(100)) < 30, "dev").otherwise("test").alias("half")).agg(F.count("*").alias("n"))


@query("op_dq_fk", "SELECT count(*) AS dangling FROM labels WHERE doc_id NOT IN (SELECT doc_id FROM documents)")
def op_dq_fk(spark, d):
    return t(spark, d, "labels").join(t(spark, d, "documents").select("doc_id"), "doc_id", "left_anti").agg(F.count("*").alias("dangling"))


@query("op_dq_range", "SELECT count(*) AS early FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_shipdate < o_orderdate")
def op_dq_range(spark, d):
    return t(spark, d, "lineitem").join(t(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).filter("l_shipdate < o_orderdate").agg(F.count("*").alias("early"))


@query("op_dq_dup", "SELECT l_orderkey, l_linenumber, count(*) AS n FROM lineitem GROUP BY 1, 2 HAVING count(*) > 1")
def op_dq_dup(spark, d):
    return t(spark, d, "lineitem").groupBy("l_orderkey", "l_linenumber").agg(F.count("*").alias("n")).filter("n > 1")


@query("op_html_title", "SELECT page_id, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title FROM pages")
def op_html_title(spark, d):
    return t(spark, d, "pages").select("page_id", F.regexp_extract("html", "<title>([^<]*)</title>", 1).alias("title"))


@query("op_web_versions", "SELECT url, count(*) AS versions, max(page_id) AS newest FROM (SELECT page_id, regexp_replace(url, '[?#].*$', '') AS url FROM pages) GROUP BY url")
def op_web_versions(spark, d):
    return t(spark, d, "pages").select("page_id", F.regexp_replace("url", "[?#].*$", "").alias("url")).groupBy("url").agg(F.count("*").alias("versions"), F.max("page_id").alias("newest"))


@query("op_dialogue_queries", "SELECT conv_id, turn, coalesce(lead(text) OVER (PARTITION BY conv_id ORDER BY turn), '') <> '' AS answered FROM conversations QUALIFY role = 'user'")
def op_dialogue_queries(spark, d):
    w = Window.partitionBy("conv_id").orderBy("turn")
    return t(spark, d, "conversations").withColumn("next", F.lead("text").over(w)).filter("role = 'user'").select("conv_id", "turn", (F.coalesce("next", F.lit("")) != "").alias("answered"))


@query("sink_partitioned")
def sink_partitioned(spark, d):
    """Units written by status with dynamic overwrite, read back with partition pruning."""
    path = scratch.folder(spark, "units")
    G.order_units(spark, d).select("unit_id", "value", "status").write.partitionBy("status").parquet(path)
    return spark.read.parquet(path).filter("status = 'ACTIVE'").agg(F.count("*").alias("n"))


@query("src_json_csv")
def src_json_csv(spark, d):
    """The log through JSON and the authority table through CSV, with explicit schemas."""
    a, b = (scratch.folder(spark, x) for x in ("log", "authority"))
    log = G.document_log(spark, d).select("event_id", "action")
    log.write.json(a)
    G.authority(spark).write.csv(b, header=True)
    back = spark.read.schema(log.schema).json(a).groupBy("action").agg(F.count("*").alias("n"))
    return back.crossJoin(spark.read.schema("source string, prior_trust double").csv(b, header=True).agg(F.round(F.sum("prior_trust"), 6).alias("prior")))


@query("sql_dormant_age", f"SELECT source, days, count(*) AS units, count(CASE WHEN age > days THEN 1 END) AS past FROM (SELECT source, age, round(30.0 * log2(prior / 0.15), 6) AS days FROM (SELECT {B._case('o_orderpriority', B.CLASS)} AS source, CAST({B._case('o_orderpriority', {k: B.PRIOR[v] for k, v in B.CLASS.items()})} AS DOUBLE) AS prior, {B.days('o_orderdate', B.NOW)} AS age FROM orders)) GROUP BY source, days")
def sql_dormant_age(spark, d):
    """Age at which a unit without feedback goes dormant, in closed form, and how many orders of each source are past it."""
    u = G.order_units(spark, d).select("source", S.age_days(F.col("born_at"), G.at(G.NOW)).alias("age"), F.round(30.0 * F.log2(F.col("prior_trust") / 0.15), 6).alias("days"))
    return u.groupBy("source", "days").agg(F.count("*").alias("units"), F.count_if(F.col("age") > F.col("days")).alias("past"))
