"""Workloads over the given tables whose measures depend on the data: time, feedback, calibration, eligibility, tuning."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from factlake.functions import signals as S
from factlake.operators import lifecycle as L
from factlake.operators import maintenance as M
from factlake.operators import retrieval as R
from factlake.params import RANKERS, Params, Weights
from factlake.plans import evaluation as E
from factlake.registry import base as B
from factlake.registry.base import query
from factlake.registry.ranking import LOG, TOP, now, order_corpus, policies, policy_table, r6, top
from factlake.registry.upkeep import DEMOTED, SEEDS, SHOW, aged, ripple_sql, seeds, shown
from factlake.registry.upkeep import ORD as ORDERS
from factlake.registry.upkeep import E_TREE
from factlake.sources import given as G
from factlake.sources.scratch import kept

YEAR = Params(half_life=365.0)
PRIORS = ", ".join(str(B.PRIOR[c]) for c in ("official_db", "policy", "tech_doc", "wiki", "chat"))
DOC_UNITS = f"du AS (SELECT doc_id AS unit_id, text, TIMESTAMP '2024-01-31' - to_days(CAST((doc_id * 37) % 421 AS INTEGER)) AS born_at, [{PRIORS}][CAST(CAST(regexp_extract(source, '([0-9]+)$', 1) AS BIGINT) % 5 AS INTEGER) + 1] AS prior FROM documents)"


def doc_units(spark, d):
    return G.with_authority(G.document_units(spark, d)).withColumnRenamed("doc_id", "unit_id")


def trust_sql(at: str, pos: str = "pos_n", neg: str = "neg_n", n: str = "access_n") -> str:
    return f"least(1.0, least(1.0, greatest(0.01, prior * pow(2.0, -{B.days('born_at', at)} / 365.0) + 0.03 * {pos} - 0.08 * {neg})) + 0.01 * ln(1.0 + {n}))"


# ---- trust at an instant, over time, and against labels

ASOF = "TIMESTAMP '2024-01-15'"
COUNTED = "c AS (SELECT unit_id, count(CASE WHEN action = 'access' THEN 1 END) AS access_n, count(CASE WHEN action = 'accept' THEN 1 END) AS pos_n, count(CASE WHEN action = 'correct' THEN 1 END) AS neg_n FROM elog WHERE ts <= {} GROUP BY unit_id)"
WITH_COUNTS = "x AS (SELECT du.*, coalesce(access_n, 0) AS access_n, coalesce(pos_n, 0) AS pos_n, coalesce(neg_n, 0) AS neg_n FROM du LEFT JOIN c USING (unit_id))"


def trust_of(units, at):
    return S.trust(F.col("prior_trust"), F.col("born_at"), at, F.col("pos_n"), F.col("neg_n"), F.col("access_n"), YEAR)


@query("sig_asof_trust", f"WITH {LOG}, {DOC_UNITS}, {COUNTED.format(ASOF)}, {WITH_COUNTS} SELECT unit_id, round({trust_sql(ASOF)}, 6) AS trust FROM x")
def sig_asof_trust(spark, d):
    """Every document's trust at an instant: its prior decayed to then, with the feedback that had come by then."""
    at = G.at("2024-01-15")
    u = L.apply_feedback(doc_units(spark, d), G.document_log(spark, d), until=at)
    return u.select("unit_id", r6(trust_of(u, at), "trust"))


@query("eval_calibration_labels", f"WITH {LOG}, {DOC_UNITS}, {COUNTED.format('TIMESTAMP ' + chr(39) + '2024-01-31' + chr(39))}, {WITH_COUNTS}, t AS (SELECT {trust_sql('TIMESTAMP ' + chr(39) + '2024-01-31' + chr(39))} AS trust, CAST(quality AS DOUBLE) AS good FROM x JOIN labels ON doc_id = unit_id WHERE quality IS NOT NULL) SELECT CAST(least(floor(trust * 10), 9) AS BIGINT) AS bin, count(*) AS n, round(avg(trust), 6) AS trust, round(avg(good), 6) AS good FROM t GROUP BY 1")
def eval_calibration_labels(spark, d):
    """Live trust of labelled documents in ten bins against the share of good ones."""
    at = G.at(G.DOCS_NOW)
    u = L.apply_feedback(doc_units(spark, d), G.document_log(spark, d), until=at)
    good = G.table(spark, d, "labels").filter("quality IS NOT NULL").select(F.col("doc_id").alias("unit_id"), F.col("quality").cast("double").alias("right"))
    bins = E.reliability(u.join(good, "unit_id").select(trust_of(u, at).alias("conf"), "right"))
    return bins.select("bin", "n", r6(F.col("conf"), "trust"), r6(F.col("accuracy"), "good"))


CURVE = f"""WITH {LOG}, {DOC_UNITS}, days AS (SELECT unnest(range(1, 31)) AS day), seen AS (SELECT DISTINCT unit_id FROM elog),
    daily AS (SELECT unit_id, CAST(date_part('day', ts) AS BIGINT) AS day, count(CASE WHEN action = 'access' THEN 1 END) AS a, count(CASE WHEN action = 'accept' THEN 1 END) AS p, count(CASE WHEN action = 'correct' THEN 1 END) AS m FROM elog GROUP BY ALL),
    x AS (SELECT du.*, day, coalesce(sum(a) OVER w, 0) AS access_n, coalesce(sum(p) OVER w, 0) AS pos_n, coalesce(sum(m) OVER w, 0) AS neg_n FROM seen JOIN du USING (unit_id) CROSS JOIN days LEFT JOIN daily USING (unit_id, day) WINDOW w AS (PARTITION BY unit_id ORDER BY day)),
    t AS (SELECT day, {trust_sql("(TIMESTAMP '2024-01-01' + to_days(CAST(day - 1 AS INTEGER)))")} AS trust FROM x)"""


@query("life_trust_curve", CURVE + " SELECT CAST(day AS BIGINT) AS day, count(*) AS units, round(avg(trust), 6) AS trust FROM t GROUP BY day")
def life_trust_curve(spark, d):
    """Mean trust, day by day, of the documents that readers touched: decay against what feedback has come so far."""
    log = G.document_log(spark, d)
    n = lambda a: F.count_if(F.col("action") == a)
    daily = log.groupBy("unit_id", F.dayofmonth("ts").alias("day")).agg(n("access").alias("a"), n("accept").alias("p"), n("correct").alias("m"))
    grid = log.select("unit_id").distinct().join(doc_units(spark, d).select("unit_id", "prior_trust", "born_at"), "unit_id").withColumn("day", F.explode(F.sequence(F.lit(1), F.lit(30))))
    w = Window.partitionBy("unit_id").orderBy("day")
    sums = {k: F.coalesce(F.sum(c).over(w), F.lit(0)) for k, c in (("access_n", "a"), ("pos_n", "p"), ("neg_n", "m"))}
    rows = grid.join(daily, ["unit_id", "day"], "left").withColumns(sums)
    at = G.at("2024-01-01") + F.make_dt_interval(days=F.col("day") - 1)
    return rows.groupBy(F.col("day").cast("long").alias("day")).agg(F.count("*").alias("units"), r6(F.avg(trust_of(rows, at)), "trust"))


# ---- which units may answer

@query("rank_all_units", B.policies().replace("cand AS (SELECT query_id, unit_id, sim, first_rank FROM asked JOIN near USING (text))", "cand AS (SELECT query_id, b.unit_id, coalesce(sim, 0.0) AS sim FROM asked CROSS JOIN bodies b LEFT JOIN sims s ON s.text = asked.text AND s.unit_id = b.unit_id)") + B.ranked(RANKERS["m4"].as_tuple()) + TOP)
def rank_all_units(spark, d):
    """No first stage: every unit is scored for every query; the units are few and broadcast."""
    units, queries, _ = policies(spark)
    asked = G.policy_asked(queries)
    sims = R.candidates_all(asked, R.index(units), 10**6).select("query_id", "unit_id", "sim")
    every = asked.select("query_id").crossJoin(F.broadcast(units.select("unit_id"))).join(sims, ["query_id", "unit_id"], "left").fillna(0.0, ["sim"])
    return top(R.rank(R.with_signals(every, units, queries, Params()), RANKERS["m4"]))


@query("rank_eligible", B.policies().replace("FROM sims) WHERE first_rank", "FROM sims WHERE unit_id IN (SELECT unit_id FROM u WHERE status = 'ACTIVE')) WHERE first_rank") + B.ranked(RANKERS["m4"].as_tuple(), 3) + TOP)
def rank_eligible(spark, d):
    """Only ACTIVE units enter the first stage, so the eight places are theirs; weights are those of the whole corpus."""
    units, queries, _ = policies(spark)
    index = R.index(units).only(units.filter("status = 'ACTIVE'").select("unit_id"))
    near = R.candidates_all(G.policy_asked(queries), index, 8)
    return top(R.rank(R.with_signals(near, units, queries, Params(), eligible=("ACTIVE",)), RANKERS["m4"], 3))


@query("rank_dense_self", "WITH n AS (SELECT a.vec_id AS query_id, a.label AS want, b.label AS got, round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 9) AS sim, b.vec_id AS unit_id FROM embeddings a JOIN embeddings b ON a.vec_id % 10 = 0 AND a.vec_id <> b.vec_id), r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY sim DESC, unit_id) AS k FROM n) SELECT count(*) AS n, round(avg(CASE WHEN want = got THEN 1.0 ELSE 0.0 END), 6) AS agree, round(avg(CASE WHEN k = 1 THEN CASE WHEN want = got THEN 1.0 ELSE 0.0 END END), 6) AS first FROM r WHERE k <= 8")
def rank_dense_self(spark, d):
    """Dense candidates against the vectors' labels: the share of the eight nearest, and of the nearest, with the query's label."""
    e = G.table(spark, d, "embeddings").select(F.col("vec_id").alias("unit_id"), F.col("embedding").alias("vec"), "label")
    q = e.filter("unit_id % 10 = 0").select(F.col("unit_id").alias("query_id"), "vec", F.col("label").alias("want"))
    rows = R.candidates_dense(q, e, 8).join(q.select("query_id", "want"), "query_id").join(e.select("unit_id", "label"), "unit_id")
    same = (F.col("want") == F.col("label")).cast("double")
    return rows.agg(F.count("*").alias("n"), r6(F.avg(same), "agree"), r6(F.avg(F.when(F.col("first_rank") == 1, same)), "first"))


@query("tune_bayes")
def tune_bayes(spark, d):
    """Weights found by Bayesian search on the development half, with the accuracy that they reach and the vectors tried."""
    _, queries, sc = policies(spark)
    right = lambda ws: [r["dev"] for r in E.tune_rows(sc, queries, ws).orderBy("w_id").collect()]
    w, value, tried = E.tune_bayes(right)
    return spark.createDataFrame([(*w, float(value), tried)], "w_sim double, w_tmp double, w_tru double, w_rel double, dev double, tried long")


# ---- chunks, audit, kernels, edges

@query("life_chunk_words", "WITH w AS (SELECT doc_id, string_split(text, ' ') AS w FROM documents), k AS (SELECT doc_id, w, unnest(range(CAST(greatest(1, ceil((len(w) - 20) / 80.0)) AS BIGINT))) AS k FROM w) SELECT doc_id, CAST(k AS BIGINT) AS chunk_no, CAST(length(array_to_string(w[1:k * 80], ' ')) + CASE WHEN k > 0 THEN 1 ELSE 0 END AS BIGINT) AS span_start, md5(array_to_string(w[k * 80 + 1:k * 80 + 100], ' ')) AS sha FROM k")
def life_chunk_words(spark, d):
    """Chunks of 100 words, each beginning with the last 20 of the one before."""
    return L.chunk(G.table(spark, d, "documents"), 100, "words", overlap=20).select("doc_id", "chunk_no", "span_start", F.md5("body").alias("sha"))


@query("life_chunk_overlap", "SELECT doc_id, CAST(k AS BIGINT) AS chunk_no, CAST(k * 800 AS BIGINT) AS span_start, CAST(least(k * 800 + 1000, length(text)) AS BIGINT) AS span_end, md5(substr(text, k * 800 + 1, 1000)) AS sha FROM (SELECT doc_id, text, unnest(range(CAST(greatest(1, ceil((length(text) - 200) / 800.0)) AS BIGINT))) AS k FROM documents)")
def life_chunk_overlap(spark, d):
    return L.chunk(G.table(spark, d, "documents"), overlap=200).select("doc_id", "chunk_no", "span_start", "span_end", F.md5("body").alias("sha"))


@query("life_explain", ORDERS + f", {DEMOTED} SELECT 'edge' AS source, 'replaces' AS what, CASE WHEN unit_id = 'O:1' THEN replaces ELSE unit_id END AS other FROM u WHERE (unit_id = 'O:1' AND replaces IS NOT NULL) OR replaces = 'O:1' UNION ALL SELECT 'status', status || ' to ' || new_status, 'trust' FROM dem WHERE unit_id = 'O:1' AND status <> new_status UNION ALL SELECT 'feedback', CASE l_returnflag WHEN 'A' THEN 'accept' WHEN 'R' THEN 'correct' ELSE 'access' END, CAST(count(*) AS VARCHAR) FROM lineitem WHERE l_orderkey = 1 GROUP BY ALL")
def life_explain(spark, d):
    """All that can have changed one order's answer: status changes of a pass, edges, and feedback by its lines."""
    u = G.order_units(spark, d)
    flag = F.when(F.col("l_returnflag") == "A", "accept").when(F.col("l_returnflag") == "R", "correct").otherwise("access")
    log = G.table(spark, d, "lineitem").select(F.concat(F.lit("O:"), F.col("l_orderkey").cast("string")).alias("unit_id"), flag.alias("action"))
    return L.explain("O:1", L.audit(u, aged(spark, d), "trust"), L.lineage_edges(u), log)


@query("maint_ripple_constant", ripple_sql(E_TREE, SEEDS, 3, "0.15") + SHOW)
def maint_ripple_constant(spark, d):
    return shown(M.ripple(seeds(spark, "R:0", "N:3"), G.dependency_tree(spark, d), 3, M.constant))


@query("maint_ripple_table", ripple_sql(E_TREE, SEEDS, 3, "[0.2, 0.1, 0.02][CAST(hop AS INTEGER) + 1]") + SHOW)
def maint_ripple_table(spark, d):
    return shown(M.ripple(seeds(spark, "R:0", "N:3"), G.dependency_tree(spark, d), 3, M.by_table([0.2, 0.1, 0.02])))


@query("op_explode_edges", "SELECT 'C:' || c_custkey AS src, 'N:' || c_nationkey AS dst FROM customer")
def op_explode_edges(spark, d):
    """Edge rows again from the list view."""
    ids = G.table(spark, d, "customer").select(F.concat(F.lit("C:"), F.col("c_custkey").cast("string")).alias("unit_id"))
    return M.from_lists(M.as_lists(ids, G.dependency_tree(spark, d))).filter("src LIKE 'C:%'").select("src", "dst")


PAIRED = "FROM orders a WHERE "


@query("op_subq_scalar", f"SELECT o_orderkey {PAIRED} o_totalprice > (SELECT avg(o_totalprice) FROM orders b WHERE b.o_custkey = a.o_custkey)")
def op_subq_scalar(spark, d):
    G.table(spark, d, "orders").createOrReplaceTempView("subq_orders")
    return spark.sql("SELECT o_orderkey FROM subq_orders a WHERE o_totalprice > (SELECT avg(o_totalprice) FROM subq_orders b WHERE b.o_custkey = a.o_custkey)")


@query("op_subq_exists", f"SELECT o_orderkey {PAIRED} NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_returnflag = 'R')")
def op_subq_exists(spark, d):
    G.table(spark, d, "orders").createOrReplaceTempView("subq_orders")
    G.table(spark, d, "lineitem").createOrReplaceTempView("subq_lines")
    return spark.sql("SELECT o_orderkey FROM subq_orders WHERE NOT EXISTS (SELECT 1 FROM subq_lines WHERE l_orderkey = o_orderkey AND l_returnflag = 'R')")


@query("op_subq_in", f"SELECT o_orderkey {PAIRED} o_custkey IN (SELECT c_custkey FROM customer WHERE c_mktsegment = 'BUILDING')")
def op_subq_in(spark, d):
    G.table(spark, d, "orders").createOrReplaceTempView("subq_orders")
    G.table(spark, d, "customer").createOrReplaceTempView("subq_customers")
    return spark.sql("SELECT o_orderkey FROM subq_orders WHERE o_custkey IN (SELECT c_custkey FROM subq_customers WHERE c_mktsegment = 'BUILDING')")


# ---- web pages and dialogues as units

PLAIN = "trim(regexp_replace(regexp_replace(regexp_replace(html, '(?s)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '<[^>]*>', ' ', 'g'), '\\s+', ' ', 'g'))"


@query("web_encode", f"WITH p AS (SELECT page_id, regexp_replace(url, '[?#].*$', '') AS url, {PLAIN} AS text FROM pages), c AS (SELECT page_id, url, text, unnest(range(CAST(greatest(1, ceil(length(text) / 1000.0)) AS BIGINT))) AS k FROM p), v AS (SELECT *, row_number() OVER (PARTITION BY url, k ORDER BY page_id DESC) AS back FROM c) SELECT CASE WHEN back = 1 THEN 'UNCONSOLIDATED' ELSE 'DEPRECATED' END AS status, count(*) AS n, count(DISTINCT url) AS urls FROM v GROUP BY 1")
def web_encode(spark, d):
    """Pages as versions of their canonical URL: chunked, encoded chunk by chunk, older crawls superseded."""
    t = F.regexp_replace(F.regexp_replace("html", r"(?s)<(script|style)[^>]*>.*?</(script|style)>", " "), "<[^>]*>", " ")
    pages = G.table(spark, d, "pages").select("page_id", F.regexp_replace("url", "[?#].*$", "").alias("url"), F.trim(F.regexp_replace(t, r"\s+", " ")).alias("text"))
    chunks = L.chunk(pages.select(F.struct("url", "page_id").alias("doc_id"), "text"))
    arrivals = chunks.select(F.col("doc_id.url").alias("doc_id"), "chunk_no", F.col("doc_id.page_id").alias("version_no"), F.concat_ws(":", F.col("doc_id.page_id").cast("string"), F.col("chunk_no").cast("string")).alias("unit_id"))
    return L.encode(arrivals).groupBy("status").agg(F.count("*").alias("n"), F.countDistinct("doc_id").alias("urls"))


@query("dialogue_feedback", "WITH t AS (SELECT *, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS after, lead(text) OVER (PARTITION BY conv_id ORDER BY turn) AS reply FROM conversations), a AS (SELECT conv_id || ':' || turn AS unit_id, CASE WHEN after IS NULL THEN 'access' WHEN contains(lower(coalesce(reply, '')), 'not') THEN 'correct' ELSE 'accept' END AS action FROM t WHERE role = 'assistant') SELECT action, count(*) AS n FROM a GROUP BY action")
def dialogue_feedback(spark, d):
    """Answers of dialogues as a log: one that the user goes on from is accepted, one that is answered with a 'not' is corrected, a last one only read."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    t = G.table(spark, d, "conversations").withColumn("after", F.lead("role").over(w)).withColumn("reply", F.lead("text").over(w)).filter("role = 'assistant'")
    action = F.when(F.col("after").isNull(), "access").when(F.contains(F.lower(F.coalesce("reply", F.lit(""))), F.lit("not")), "correct").otherwise("accept")
    return t.select(F.concat_ws(":", F.col("conv_id").cast("string"), F.col("turn").cast("string")).alias("unit_id"), action.alias("action")).groupBy("action").agg(F.count("*").alias("n"))
