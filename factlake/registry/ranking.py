"""Signals, corpora, candidates, rankers, measures and experiments."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Window
from pyspark.sql import functions as F

from factlake.functions import signals as S
from factlake.operators import lifecycle as L
from factlake.operators import maintenance as M
from factlake.operators import retrieval as R
from factlake.params import PRESETS, RANKERS, Params, Weights, grid
from factlake.plans import evaluation as E
from factlake.registry import base as B
from factlake.registry.base import query
from factlake.sources import given as G
from factlake.sources.scratch import fitted, kept, later, stamp

r6 = lambda c, name: F.round(c, 6).alias(name)


def now():
    return G.at(G.NOW)


def several(rate):
    """How many worlds an order corpus has: as many as there are rates, none if there is one."""
    return len(rate) if isinstance(rate, tuple) else 0


def order_table(spark, d, rate=None):
    """units, and a key for what is kept of them in this session."""
    key = f"orders {rate} {stamp(spark, d, 'orders', 'customer', 'nation')}"
    return kept(spark, f"{key} units", lambda: G.order_units(fitted(spark, d, "orders"), d, rate, text=True), "unit_id"), key


def order_corpus(spark, d, rate=None):
    """units, queries with their texts, and the key."""
    units, key = order_table(spark, d, rate)

    def build():
        own = fitted(spark, d, "orders")
        return G.order_queries(order_table(own, d, rate)[0], worlds=several(rate)).join(G.topic_text(own, d).withColumnRenamed("topic_text", "text"), "topic")

    return units, kept(spark, f"{key} queries", build), key


def order_candidates(spark, d, k=8, rate=None):
    """The k nearest units of every query; the index (made beside the queries) and the result are kept for the session."""
    key = order_table(spark, d, rate)[1]

    def build():
        own = fitted(spark, d, "orders")
        queries = later(own, lambda: order_corpus(own, d, rate)[1])
        held = R.index(order_table(own, d, rate)[0], hold=lambda name, df, on: kept(own, f"{key} {name}", lambda: df, on), worlds=several(rate))
        return R.candidates(queries.result(), held, k)

    return kept(spark, f"{key} first {k}", build, "unit_id")


def orders(spark, d, half_life=30.0, k=8, rate=None, exclude_future=False, floor_in_window=False, dormant="exclude"):
    """units, queries and candidates with signals of the order corpus; of several rates as so many worlds."""
    near = order_candidates(spark, d, k, rate)
    units, queries, _ = order_corpus(spark, d, rate)
    p = Params(half_life=half_life, floor_in_window=floor_in_window)
    return units, queries, R.with_signals(near, units, queries, p, exclude_future, dormant)


def policy_table(spark, rate=0.3, seed=7, topics=60):
    """The generated corpus, kept for the session."""
    return kept(spark, f"policies {rate} {seed} {topics} units", lambda: G.policy_units(spark, topics=topics, rate=rate, seed=seed).coalesce(1))


def policies(spark, half_life=30.0, k=8, rate=0.3, seed=7, topics=60):
    """units, queries and candidates with signals of the generated corpus."""
    key = f"policies {rate} {seed} {topics}"
    units = policy_table(spark, rate, seed, topics)
    queries = kept(spark, f"{key} queries", lambda: G.order_queries(units).coalesce(1))
    near = kept(spark, f"{key} first {k}", lambda: R.candidates_all(G.policy_asked(queries), R.index(units), k).coalesce(1))
    return units, queries, R.with_signals(near, units, queries, Params(half_life=half_life))


def supplier_policy_table(spark, d):
    """The corpus of the suppliers' policies, kept for the session, and its key."""
    key = f"supplier policies {stamp(spark, d, 'supplier')}"
    return kept(spark, f"{key} units", lambda: G.policy_units(spark, given=G.supplier_topics(spark, d)), "unit_id"), key


def supplier_policies(spark, d, half_life=30.0, k=8):
    """units, queries and candidates with signals of the suppliers' policies."""
    units, key = supplier_policy_table(spark, d)
    queries = kept(spark, f"{key} queries", lambda: G.order_queries(units))

    def build():
        held = R.index(units, hold=lambda name, df, on: kept(spark, f"{key} {name}", lambda: df, on))
        return R.candidates(G.policy_asked(queries), held, k)

    return units, queries, R.with_signals(kept(spark, f"{key} first {k}", build, "unit_id"), units, queries, Params(half_life=half_life))


# ---- signals

AGED = f"SELECT 'O:' || o_orderkey AS unit_id, {B.days('o_orderdate', B.NOW)} AS age, {B._case('o_orderpriority', {k: B.PRIOR[v] for k, v in B.CLASS.items()})} AS base, count(l_orderkey) AS n, count(CASE WHEN l_returnflag = 'A' THEN 1 END) AS pos, count(CASE WHEN l_returnflag = 'R' THEN 1 END) AS neg FROM orders LEFT JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL"


def used_orders(spark, d):
    """Orders with line counts as accesses and return flags as feedback."""
    l = G.table(spark, d, "lineitem").groupBy(F.concat(F.lit("O:"), F.col("l_orderkey").cast("string")).alias("unit_id")).agg(F.count("*").alias("access_n"), F.count_if(F.col("l_returnflag") == "A").alias("pos_n"), F.count_if(F.col("l_returnflag") == "R").alias("neg_n"))
    return G.order_units(spark, d).join(l, "unit_id", "left").fillna(0, ["access_n", "pos_n", "neg_n"])


@query("sig_age", f"SELECT 'O:' || o_orderkey AS unit_id, {B.days('o_orderdate', B.NOW)} AS whole, round(greatest(0.0, (epoch_us({B.NOW}) - epoch_us(o_orderdate)) / 86400000000.0), 6) AS exact FROM orders")
def sig_age(spark, d):
    return G.order_units(spark, d).select("unit_id", S.age_days(F.col("born_at"), now()).alias("whole"), r6(S.age_days(F.col("born_at"), now(), "fractional"), "exact"))


TEMPORAL = "WITH " + B.order_units() + f", a AS (SELECT *, {B.days('born_at', chr(34) + 'at' + chr(34))} AS age FROM (SELECT *, TIMESTAMP '1999-06-01' AS \"at\" FROM u)) SELECT unit_id, "


@query("sig_temporal", TEMPORAL + 'round(CASE WHEN "at" >= valid_from AND (valid_to IS NULL OR "at" <= valid_to) THEN pow(2.0, -age / 30.0) ELSE 0.05 END, 6) AS temporal FROM a')
def sig_temporal(spark, d):
    return G.order_units(spark, d).select("unit_id", r6(S.temporal(F.col("born_at"), F.col("valid_from"), F.col("valid_to"), G.at("1999-06-01")), "temporal"))


@query("sig_temporal_variants", TEMPORAL + 'round(CASE WHEN "at" >= valid_from AND (valid_to IS NULL OR "at" < valid_to) THEN pow(2.0, -age / 90.0) ELSE 0.05 END, 6) AS half_open, round(CASE WHEN "at" >= valid_from AND (valid_to IS NULL OR "at" <= valid_to) THEN greatest(0.05, pow(2.0, -age / 90.0)) ELSE 0.05 END, 6) AS floored, round(pow(2.0, -age / 90.0), 6) AS recency FROM a')
def sig_temporal_variants(spark, d):
    p, at = Params(half_life=90.0), G.at("1999-06-01")
    t = lambda q: S.temporal(F.col("born_at"), F.col("valid_from"), F.col("valid_to"), at, q)
    return G.order_units(spark, d).select("unit_id", r6(t(p.but(window="half_open")), "half_open"), r6(t(p.but(floor_in_window=True)), "floored"), r6(S.recency(S.age_days(F.col("born_at"), at), 90.0), "recency"))


@query("floor_crossover", f"SELECT h AS half_life, round(h * log2(20.0), 6) AS days, count(*) AS units, count(CASE WHEN age > round(h * log2(20.0), 6) THEN 1 END) AS crossed FROM (SELECT {B.days('o_orderdate', B.NOW)} AS age FROM orders), (SELECT CAST(unnest([15.0, 30.0, 60.0, 90.0]) AS DOUBLE) AS h) GROUP BY h")
def floor_crossover(spark, d):
    """By half-life: the age at which a valid order scores no more than an invalid one, and how many orders are past it."""
    h = spark.createDataFrame([(15.0,), (30.0,), (60.0,), (90.0,)], "half_life double").withColumn("days", F.round(S.floor_crossing(F.col("half_life")), 6))
    age = G.table(spark, d, "orders").select(S.age_days(F.col("o_orderdate"), now()).alias("age"))
    return age.crossJoin(F.broadcast(h)).groupBy("half_life", "days").agg(F.count("*").alias("units"), F.count_if(F.col("age") > F.col("days")).alias("crossed"))


@query("sig_trust", f"SELECT unit_id, round(least(1.0, least(1.0, greatest(0.01, base * pow(2.0, -age / 365.0) + 0.03 * pos - 0.08 * neg)) + 0.01 * ln(1.0 + n)), 6) AS trust FROM ({AGED})")
def sig_trust(spark, d):
    return used_orders(spark, d).select("unit_id", r6(S.trust(F.col("prior_trust"), F.col("born_at"), now(), F.col("pos_n"), F.col("neg_n"), F.col("access_n"), Params(half_life=365.0)), "trust"))


@query("sig_trust_steps", f"SELECT unit_id, round(base * pow(2.0, -age / 365.0), 6) AS decayed, round(least(1.0, greatest(0.01, base * pow(2.0, -age / 365.0) + 0.03 * pos - 0.08 * neg)), 6) AS corrected, round(least(1.0, base + 0.01 * ln(1.0 + n)), 6) AS accessed FROM ({AGED})")
def sig_trust_steps(spark, d):
    dec = S.decayed(F.col("prior_trust"), S.age_days(F.col("born_at"), now()), 365.0)
    return used_orders(spark, d).select("unit_id", r6(dec, "decayed"), r6(S.after_feedback(dec, F.col("pos_n"), F.col("neg_n")), "corrected"), r6(S.after_access(F.col("prior_trust"), F.col("access_n")), "accessed"))


@query("sig_trust_bayes", f"SELECT unit_id, round((10.0 * base * pow(2.0, -age / 365.0) + pos) / (10.0 + pos + neg), 6) AS trust FROM ({AGED})")
def sig_trust_bayes(spark, d):
    return used_orders(spark, d).select("unit_id", r6(S.trust_beta(F.col("prior_trust"), F.col("born_at"), now(), F.col("pos_n"), F.col("neg_n"), Params(half_life=365.0)), "trust"))


@query("sig_half_life", f"SELECT unit_id, round(greatest(0.01, base * pow(2.0, -age / coalesce(CASE WHEN base >= 0.9 THEN 900.0 END, 365.0))), 6) AS trust FROM ({AGED})")
def sig_half_life(spark, d):
    own = F.when(F.col("prior_trust") >= 0.9, 900.0)
    zero = F.lit(0)
    return G.order_units(spark, d).select("unit_id", r6(S.trust(F.col("prior_trust"), F.col("born_at"), now(), zero, zero, zero, Params(half_life=365.0), own), "trust"))


@query("sig_trajectory", f"SELECT day, round(avg(prior * pow(2.0, -day / 30.0)), 6) AS trust FROM (SELECT {B._case('o_orderpriority', {k: B.PRIOR[v] for k, v in B.CLASS.items()})} AS prior FROM orders), (SELECT CAST(unnest([0, 30, 60, 75, 76, 90, 180]) AS INTEGER) AS day) GROUP BY day")
def sig_trajectory(spark, d):
    """Mean trust of all orders by days since they were born."""
    return S.trajectory(spark, G.order_units(spark, d), [0, 30, 60, 75, 76, 90, 180]).select("day", r6(F.col("trust"), "trust"))


LOG = "elog AS (SELECT event_id, (user_id * 100 + CAST(json_extract_string(props, '$.k') AS BIGINT)) % (SELECT count(*) FROM documents) AS unit_id, ts, CASE WHEN event_type IN ('view', 'click') THEN 'access' WHEN event_type = 'purchase' THEN 'accept' WHEN event_type = 'error' THEN 'correct' ELSE 'validate' END AS action, user_id AS actor, CAST(date_trunc('day', ts) AS DATE) AS day FROM events)"
COUNTS = "SELECT unit_id, count(CASE WHEN action = 'access' THEN 1 END) AS access_n, count(CASE WHEN action = 'accept' THEN 1 END) AS pos_n, count(CASE WHEN action = 'correct' THEN 1 END) AS neg_n FROM elog"


TREE = "tree AS (SELECT 'N:' || n_nationkey AS src, 'R:' || n_regionkey AS dst FROM nation UNION ALL SELECT 'C:' || c_custkey, 'N:' || c_nationkey FROM customer UNION ALL SELECT 'S:' || s_suppkey, 'N:' || s_nationkey FROM supplier UNION ALL SELECT 'O:' || o_orderkey, 'C:' || o_custkey FROM orders)"


@query("sig_relational", f"WITH {TREE}, deg AS (SELECT unit_id, count(*) AS degree FROM (SELECT src AS unit_id FROM tree UNION ALL SELECT dst FROM tree) GROUP BY unit_id) SELECT unit_id, degree, round(least(0.3, 0.1 * ln(1.0 + degree)), 6) AS bonus FROM deg")
def sig_relational(spark, d):
    deg = M.degree(G.dependency_tree(spark, d).withColumn("kind", F.lit("depends_on")))
    return deg.select("unit_id", "degree", r6(S.bonus(F.col("degree")), "bonus"))


@query("sig_final", B.orders(90.0) + f" SELECT query_id, unit_id, sim, round(temporal, 6) AS temporal, round(trust, 6) AS trust, round(relational, 6) AS relational, {B.score((0.35, 0.25, 0.25, 0.15))} AS final FROM sc")
def sig_final(spark, d):
    _, _, sc = orders(spark, d, 90.0)
    f = S.final(*(F.col(c) for c in ("sim", "temporal", "trust", "relational")), RANKERS["m4"])
    return sc.select("query_id", "unit_id", "sim", *(r6(F.col(c), c) for c in ("temporal", "trust", "relational")), F.round(f, 9).alias("final"))


@query("sig_bound", B.orders(90.0) + " SELECT query_id, unit_id, round(sim * 0.35 + 0.545, 9) AS bound FROM sc")
def sig_bound(spark, d):
    return orders(spark, d, 90.0)[2].select("query_id", "unit_id", F.round(S.upper_bound(F.col("sim"), RANKERS["m4"], Params()), 9).alias("bound"))


@query("sig_authority", f"SELECT source, count(*) AS n, round(avg(prior), 6) AS prior FROM (SELECT source, coalesce({B._case('source', B.PRIOR)}, 0.5) AS prior FROM (SELECT {B._case('o_orderpriority', B.CLASS)} AS source FROM orders)) GROUP BY source")
def sig_authority(spark, d):
    return G.order_units(spark, d).groupBy("source").agg(F.count("*").alias("n"), r6(F.avg("prior_trust"), "prior"))


# ---- corpora and queries

UNIT_COLS = "unit_id, topic, coalesce(version_no, 0) AS version_no, born_at, valid_to, value, source, is_rumour, prior_trust, replaces, replaced_by, status, degree"


SHOWN = ["unit_id", "topic", "version_no", "born_at", "valid_to", "value", "source", "is_rumour", "prior_trust", "replaces", "replaced_by", "status", "degree"]


@query("corpus_orders", "WITH " + B.order_units() + f" SELECT {UNIT_COLS} FROM u")
def corpus_orders(spark, d):
    return G.order_units(spark, d).fillna(0, ["version_no"]).select(*SHOWN)


@query("corpus_policy", "WITH " + B.policy_units(given=B.SUPPLIERS) + f" SELECT {UNIT_COLS}, body FROM u")
def corpus_policy(spark, d):
    return supplier_policy_table(spark, d)[0].fillna(0, ["version_no"]).select(*SHOWN, "body")


for _kind in ("current", "time_point", "conflict"):

    @query(f"queries_{_kind}", "WITH " + B.order_units() + B.QUERY_SET + f" SELECT query_id, topic, ref_time, truth FROM queries WHERE kind = '{_kind}'")
    def queries_of(spark, d, kind=_kind):
        return G.order_queries(G.order_units(spark, d), (kind,) if kind == "current" else ("current", kind)).filter(F.col("kind") == kind).select("query_id", "topic", "ref_time", "truth")


# ---- candidates

@query("cand_tfidf", B.orders(k=8).split(",\n    sc AS")[0] + " SELECT query_id, unit_id, sim, first_rank FROM cand")
def cand_tfidf(spark, d):
    return order_candidates(spark, d).select("query_id", "unit_id", "sim", "first_rank")


def vectors(spark, d, queries: bool = False):
    e = G.table(spark, d, "embeddings").select(F.col("vec_id").alias("query_id" if queries else "unit_id"), F.col("embedding").alias("vec"))
    return e.filter("query_id % 10 = 0") if queries else e


DENSE = "SELECT query_id, unit_id, sim, row_number() OVER (PARTITION BY query_id ORDER BY sim DESC, unit_id) AS first_rank FROM (SELECT a.vec_id AS query_id, b.vec_id AS unit_id, round(list_cosine_similarity(CAST(a.embedding{0} AS DOUBLE[]), CAST(b.embedding{0} AS DOUBLE[])), 9) AS sim FROM embeddings a JOIN embeddings b ON a.vec_id % 10 = 0 AND a.vec_id <> b.vec_id)"


@query("cand_dense", f"SELECT query_id, unit_id, sim, first_rank FROM ({DENSE.format('')}) WHERE first_rank <= 8")
def cand_dense(spark, d):
    return R.candidates_dense(vectors(spark, d, True), vectors(spark, d), 8).select("query_id", "unit_id", "sim", "first_rank")


@query("cand_nested", f"WITH wide AS (SELECT query_id, unit_id FROM ({DENSE.format('[1:16]')}) WHERE first_rank <= 64), fin AS (SELECT query_id, unit_id, round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 9) AS sim FROM wide JOIN embeddings a ON a.vec_id = query_id JOIN embeddings b ON b.vec_id = unit_id) SELECT query_id, unit_id, sim, first_rank FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY sim DESC, unit_id) AS first_rank FROM fin) WHERE first_rank <= 8")
def cand_nested(spark, d):
    return R.candidates_nested(vectors(spark, d, True), vectors(spark, d), 8).select("query_id", "unit_id", "sim", "first_rank")


@query("cand_lsh_recall")
def cand_lsh_recall(spark, d):
    q, u = vectors(spark, d, True), vectors(spark, d)
    exact = R.candidates_dense(q, u, 8).select("query_id", "unit_id")
    near = R.candidates_lsh(q, u, 8).select("query_id", "unit_id", F.lit(1).alias("hit"))
    return exact.join(near, ["query_id", "unit_id"], "left").agg(F.count("*").alias("n"), r6(F.avg(F.coalesce("hit", F.lit(0)).cast("double")), "recall"))


# ---- rankers

TOP = " SELECT query_id, unit_id, rank, final FROM top"


def top(rows):
    return rows.select("query_id", "unit_id", "rank", "final")


for _name, _w in RANKERS.items():

    @query(f"rank_{_name}", B.orders(90.0) + B.ranked(_w.as_tuple()) + TOP)
    def rank_of(spark, d, w=_w):
        return top(R.rank(orders(spark, d, 90.0)[2], w))

    _given = B.SUPPLIERS if _name in ("m3", "m4") else ""  # these two rank the policies of all suppliers

    @query(f"rank_{_name}_policy", B.policies(given=_given) + B.ranked(_w.as_tuple()) + TOP)
    def rank_policy(spark, d, w=_w, given=_given):
        return top(R.rank((supplier_policies(spark, d) if given else policies(spark))[2], w))


for _name, _w in PRESETS.items():

    @query(f"rank_preset_{_name}", B.orders(90.0) + B.ranked(_w.as_tuple()) + TOP)
    def rank_preset(spark, d, w=_w):
        return top(R.rank(orders(spark, d, 90.0)[2], w))


M4 = RANKERS["m4"]


@query("rank_topk", B.orders(90.0) + B.ranked(M4.as_tuple(), 3) + TOP)
def rank_topk(spark, d):
    return top(R.rank(orders(spark, d, 90.0)[2], M4, 3))


@query("rank_pruned", B.orders(90.0) + B.ranked(M4.as_tuple()) + TOP)
def rank_pruned(spark, d):
    return top(R.rank(R.prune_by_bound(orders(spark, d, 90.0)[2], M4, Params(half_life=90.0)), M4))


@query("rank_exclude_future", B.orders(90.0, exclude_future=True) + B.ranked(RANKERS["m3"].as_tuple()) + TOP)
def rank_exclude_future(spark, d):
    return top(R.rank(orders(spark, d, 90.0, exclude_future=True)[2], RANKERS["m3"]))


@query("rank_floor_in_window", B.orders(30.0, floor_in_window=True) + B.ranked(M4.as_tuple()) + TOP)
def rank_floor_in_window(spark, d):
    return top(R.rank(orders(spark, d, 30.0, floor_in_window=True)[2], M4))


@query("rank_hard_filter", B.orders(90.0) + ", top AS (SELECT * FROM (SELECT *, sim AS final, CAST(row_number() OVER (PARTITION BY query_id ORDER BY sim DESC, unit_id) AS BIGINT) AS rank FROM sc WHERE ref_time >= valid_from AND (valid_to IS NULL OR ref_time <= valid_to)) WHERE rank = 1)" + TOP)
def rank_hard_filter(spark, d):
    return top(R.hard_filter(orders(spark, d, 90.0)[2], Params(half_life=90.0)))


DORMANT = "CASE WHEN status = 'ACTIVE' AND least(1.0, greatest(0.01, prior_trust * pow(2.0, -{} / 365.0))) < 0.15 THEN 'DORMANT' ELSE status END".format(B.days("born_at", B.NOW))


def with_dormant(spark, d, dormant, demote=None):
    units = L.step_trust(G.order_units(spark, d, text=True), now(), Params(half_life=365.0)).drop("trust")
    queries = G.order_queries(units, ("current",))
    cands = queries.select("query_id", "topic").join(units.select("topic", "unit_id"), "topic").select("query_id", "unit_id", F.lit(1.0).alias("sim"))
    return top(R.rank(R.with_signals(cands, units, queries, Params(half_life=90.0), dormant=dormant), M4, demote=demote))


def dormant_sql(where: str = "", factor: str = "") -> str:
    s = f"WITH {B.order_units()}{B.QUERY_SET}, cand AS (SELECT query_id, unit_id, CAST(1.0 AS DOUBLE) AS sim FROM queries JOIN u USING (topic) WHERE kind = 'current'){B.scored(90.0)}"
    inner = f"SELECT *, {B.score(M4.as_tuple())} AS plain, {DORMANT} AS now_status FROM sc"
    final = f"round(({B.score(M4.as_tuple())[6:-4]}) * (CASE WHEN now_status = 'DORMANT' THEN {factor} ELSE 1.0 END), 9)" if factor else "plain"
    return s + f", top AS (SELECT * FROM (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY final DESC, sim DESC, unit_id) AS BIGINT) AS rank FROM (SELECT *, {final} AS final FROM ({inner}) {where})) WHERE rank = 1)" + TOP


@query("rank_dormant_exclude", dormant_sql("WHERE now_status <> 'DORMANT'"))
def rank_dormant_exclude(spark, d):
    return with_dormant(spark, d, "exclude")


@query("rank_dormant_demote", dormant_sql(factor="0.5"))
def rank_dormant_demote(spark, d):
    return with_dormant(spark, d, "demote", 0.5)


@query("rank_dormant_include", dormant_sql())
def rank_dormant_include(spark, d):
    return with_dormant(spark, d, "include")


@query("rank_status", B.orders(90.0) + f", top AS (SELECT * FROM (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY final DESC, sim DESC, unit_id) AS BIGINT) AS rank FROM (SELECT *, {B.score(M4.as_tuple())} AS final FROM sc WHERE status = 'ACTIVE')) WHERE rank = 1)" + TOP)
def rank_status(spark, d):
    units, queries, sc = orders(spark, d, 90.0)
    return top(R.rank(sc.filter(F.col("status").isin("ACTIVE")), M4))


@query("rank_external", "SELECT query_id, unit_id, first_rank FROM (SELECT l_orderkey AS query_id, l_partkey AS unit_id, row_number() OVER (PARTITION BY l_orderkey ORDER BY max(l_discount) DESC, l_partkey) AS first_rank FROM lineitem GROUP BY 1, 2)")
def rank_external(spark, d):
    ext = G.table(spark, d, "lineitem").groupBy(F.col("l_orderkey").alias("query_id"), F.col("l_partkey").alias("unit_id")).agg(F.max("l_discount").alias("sim"))
    return R.from_external(ext).select("query_id", "unit_id", "first_rank")


@query("rank_arbiter", B.orders(90.0) + B.ranked(M4.as_tuple()) + " SELECT query_id, CASE WHEN abs(sim - trust) <= 0.35 THEN 'answer' WHEN sim > trust THEN 'clarify' ELSE 'abstain' END AS verdict FROM top")
def rank_arbiter(spark, d):
    return R.rank(orders(spark, d, 90.0)[2], M4).select("query_id", S.arbiter(F.col("sim"), F.col("trust")).alias("verdict"))


# ---- measures and experiments

def ablation_sql(pre: str) -> str:
    rows = ", ".join(f"({i}, {', '.join(repr(float(x)) for x in w)})" for i, w in enumerate(E.ablations()))
    score = "round(sim * w_sim + temporal * w_tmp + trust * w_tru + relational * w_rel, 9)"
    ece = B.ECE.replace("SELECT round(", "SELECT w_id, round(", 1).replace("(SELECT least(", "(SELECT w_id, least(").replace("GROUP BY 1)", "GROUP BY ALL) GROUP BY w_id")
    return pre + f", w(w_id, w_sim, w_tmp, w_tru, w_rel) AS (SELECT CAST(w_id AS BIGINT), CAST(a AS DOUBLE), CAST(b AS DOUBLE), CAST(c AS DOUBLE), CAST(e AS DOUBLE) FROM (VALUES {rows}) t(w_id, a, b, c, e)), top AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY w_id, query_id ORDER BY final DESC, sim DESC, unit_id) AS rank FROM (SELECT *, {score} AS final FROM sc, w)) WHERE rank = 1), j AS (SELECT w.w_id, q.kind, t.trust AS conf, CASE WHEN t.unit_id = q.truth THEN 1.0 ELSE 0.0 END AS \"right\", CASE WHEN t.status = 'DEPRECATED' THEN 1.0 ELSE 0.0 END AS stale, CASE WHEN t.is_rumour THEN 1.0 ELSE 0.0 END AS misled FROM queries q CROSS JOIN w LEFT JOIN top t ON t.query_id = q.query_id AND t.w_id = w.w_id), m AS ({B.summary('j', 'w_id')}), e AS ({ece}) SELECT m.*, e.ece, round(m.overall - f.overall, 6) AS d_overall, round(m.stale - f.stale, 6) AS d_stale, round(e.ece - fe.ece, 6) AS d_ece FROM m JOIN e USING (w_id), (SELECT * FROM m WHERE w_id = 0) f, (SELECT * FROM e WHERE w_id = 0) fe"


def ablation(units, queries, sc):
    """Each weight vector's measures, and how they differ from the full vector's."""
    m = E.compare(sc, queries, {i: (Weights(*w), "trust") for i, w in enumerate(E.ablations())}, "w_id").withColumn("w_id", F.col("w_id").cast("long"))
    full = lambda c: F.max(F.when(F.col("w_id") == 0, F.col(c))).over(Window.partitionBy(F.lit(0)))
    return m.select(*m.columns, *(F.round(F.col(c) - full(c), 6).alias(f"d_{c}") for c in ("overall", "stale", "ece")))


@query("eval_ablation", ablation_sql(B.orders(90.0)))
def eval_ablation(spark, d):
    return ablation(*orders(spark, d, 90.0))


@query("eval_ablation_policy", ablation_sql(B.policies()))
def eval_ablation_policy(spark, d):
    return ablation(*policies(spark))


def main_sql(pre: str) -> str:
    parts, select = pre, []
    for n, w in RANKERS.items():
        parts += B.ranked(w.as_tuple(), name=f"top_{n}") + B.judged(E.conf_column(n), f"top_{n}", f"j_{n}")
        select.append(f"SELECT '{n}' AS ranker, s.*, e.ece FROM ({B.summary(f'j_{n}')}) s, ({B.ECE.replace('FROM j ', f'FROM j_{n} ')}) e")
    return parts + " " + " UNION ALL ".join(select)


def main(units, queries, sc):
    return E.compare(sc, queries, {n: (w, E.conf_column(n)) for n, w in RANKERS.items()}, "ranker")


@query("eval_main", main_sql(B.orders(90.0)))
def eval_main(spark, d):
    return main(*orders(spark, d, 90.0))


@query("eval_main_policy", main_sql(B.policies()))
def eval_main_policy(spark, d):
    return main(*policies(spark))


J4 = B.orders(90.0) + B.ranked(M4.as_tuple()) + B.judged()


def judged4(spark, d):
    units, queries, sc = orders(spark, d, 90.0)
    return E.judged(R.rank(sc, M4), queries)


@query("eval_accuracy", J4 + ' SELECT coalesce(kind, \'overall\') AS kind, count(*) AS n, round(avg("right"), 6) AS accuracy FROM j GROUP BY ROLLUP (kind)')
def eval_accuracy(spark, d):
    return E.accuracy(judged4(spark, d))


@query("eval_stale", J4 + " SELECT round(avg(stale), 6) AS stale FROM j WHERE kind = 'current'")
def eval_stale(spark, d):
    return judged4(spark, d).filter("kind = 'current'").agg(r6(F.avg("stale"), "stale"))


@query("eval_misled", J4 + " SELECT kind, round(avg(misled), 6) AS misled FROM j GROUP BY kind")
def eval_misled(spark, d):
    return judged4(spark, d).groupBy("kind").agg(r6(F.avg("misled"), "misled"))


@query("eval_ece", J4 + " " + B.ECE)
def eval_ece(spark, d):
    return E.ece(judged4(spark, d))


@query("eval_reliability", J4 + ' SELECT CAST(least(floor(conf * 10), 9) AS BIGINT) AS bin, count(*) AS n, round(avg(conf), 6) AS conf, round(avg("right"), 6) AS accuracy FROM j WHERE conf IS NOT NULL GROUP BY 1')
def eval_reliability(spark, d):
    return E.reliability(judged4(spark, d)).select("bin", "n", r6(F.col("conf"), "conf"), r6(F.col("accuracy"), "accuracy"))


def tuned_sql(pre: str, more: tuple = ()) -> str:
    rows = ", ".join(f"({i}, {', '.join(repr(float(x)) for x in w)})" for i, w in enumerate([*grid(), *more]))
    half = "CASE WHEN CAST(regexp_extract(query_id, '([0-9]+)$', 1) AS BIGINT) % 2 = 0 THEN 'dev' ELSE 'test' END"
    return pre + f", w(w_id, w_sim, w_tmp, w_tru, w_rel) AS (SELECT CAST(w_id AS BIGINT), CAST(a AS DOUBLE), CAST(b AS DOUBLE), CAST(c AS DOUBLE), CAST(e AS DOUBLE) FROM (VALUES {rows}) t(w_id, a, b, c, e)), win AS (SELECT w_id, query_id, unit_id = truth AS x FROM (SELECT w_id, query_id, unit_id, truth, row_number() OVER (PARTITION BY w_id, query_id ORDER BY final DESC, sim DESC, unit_id) AS r FROM (SELECT w_id, query_id, unit_id, truth, sim, round(sim * w_sim + temporal * w_tmp + trust * w_tru + relational * w_rel, 9) AS final FROM sc, w)) WHERE r = 1), size AS (SELECT {half} AS half, count(*) AS n FROM queries GROUP BY 1), acc AS (SELECT w_id, {half} AS half, sum(CASE WHEN x THEN 1.0 ELSE 0.0 END) AS good FROM win GROUP BY ALL), both_ AS (SELECT w_id, round(max(CASE WHEN half = 'dev' THEN good / n END), 6) AS dev, round(max(CASE WHEN half = 'test' THEN good / n END), 6) AS test FROM acc JOIN size USING (half) GROUP BY w_id) SELECT w_id, w_sim, w_tmp, w_tru, w_rel, coalesce(dev, 0.0) AS dev, coalesce(test, 0.0) AS test FROM w LEFT JOIN both_ USING (w_id)"


TUNED = tuned_sql(B.policies())


@query("rank_grid", TUNED)
def rank_grid(spark, d):
    _, queries, sc = policies(spark)
    return E.tune(sc, queries)


@query("tune_split", f"SELECT * FROM ({TUNED}) ORDER BY dev DESC, w_id LIMIT 1")
def tune_split(spark, d):
    _, queries, sc = policies(spark)
    return E.best_weights(E.tune(sc, queries))


RATES = (0.0, 0.15, 0.3, 0.5, 0.75)


def sweep_sql(world) -> str:
    out = []
    for rate in RATES:
        s = world(rate) + B.ranked(RANKERS["m1"].as_tuple(), name="t1") + B.judged("sim", "t1", "j1") + B.ranked(M4.as_tuple(), name="t4") + B.judged("trust", "t4", "j4")
        out.append(f"SELECT * FROM ({s} SELECT CAST({rate} AS DOUBLE) AS rate, a.overall AS plain, b.overall AS ours, a.stale AS plain_stale, b.stale AS ours_stale, round(100 * (b.overall - a.overall), 4) AS gap FROM ({B.summary('j1')}) a, ({B.summary('j4')}) b)")
    return " UNION ALL ".join(out)


@query("eval_sweep", sweep_sql(lambda rate: B.policies(rate=rate)))
def eval_sweep(spark, d):
    return sweep({rate: policies(spark, rate=rate) for rate in RATES})


def sweep(worlds):
    """Plain similarity against four signals on each world (its rate, and units, queries and candidates)."""
    out = [E.compare(sc, queries, SWEPT, "ranker").agg(*against()).select(F.lit(rate).alias("rate"), "*", gap()) for rate, (_, queries, sc) in worlds.items()]
    return reduce(lambda a, b: a.unionAll(b), out)


SWEPT = {n: (RANKERS[n], E.conf_column(n)) for n in ("m1", "m4")}


def against():
    of = lambda n, c: F.max(F.when(F.col("ranker") == n, F.col(c)))
    return of("m1", "overall").alias("plain"), of("m4", "overall").alias("ours"), of("m1", "stale").alias("plain_stale"), of("m4", "stale").alias("ours_stale")


def gap():
    return F.round(100 * (F.col("ours") - F.col("plain")), 4).alias("gap")


@query("eval_sweep_orders", sweep_sql(lambda rate: B.orders(90.0, rate=rate)))
def eval_sweep_orders(spark, d):
    """All rates are worlds of one corpus: units, index and candidates are made once, with every rate's own weights and lists."""
    _, queries, sc = orders(spark, d, 90.0, rate=RATES)
    found = E.compare_worlds(sc, queries, SWEPT, "ranker", len(RATES)).groupBy("world").agg(*against())
    rates = spark.createDataFrame(list(enumerate(RATES)), "world int, rate double")
    return rates.join(found, "world", "left").select("rate", "plain", "ours", "plain_stale", "ours_stale", gap())


SEEDS = tuple(range(7, 12))


def seeds_sql() -> str:
    out = []
    for seed in SEEDS:
        for n in ("m1", "m2", "m3", "m4"):
            out.append(f"SELECT * FROM ({B.policies(seed=seed)}{B.ranked(RANKERS[n].as_tuple())}{B.judged(E.conf_column(n))} SELECT '{n}' AS ranker, s.*, e.ece FROM ({B.summary()}) s, ({B.ECE}) e)")
    return f"SELECT ranker, count(*) AS seeds, round(avg(overall), 6) AS overall, round(stddev_samp(overall), 6) AS spread, round(avg(stale), 6) AS stale, round(avg(ece), 6) AS ece FROM ({' UNION ALL '.join(out)}) GROUP BY ranker"


@query("eval_seeds", seeds_sql())
def eval_seeds(spark, d):
    """Mean and deviation of each ranker over five generated corpora."""
    out = []
    for seed in SEEDS:
        _, queries, sc = policies(spark, seed=seed)
        out.append(E.compare(sc, queries, {n: (RANKERS[n], E.conf_column(n)) for n in ("m1", "m2", "m3", "m4")}, "ranker"))
    rows = reduce(lambda a, b: a.unionByName(b), out)
    return rows.groupBy("ranker").agg(F.count("*").alias("seeds"), r6(F.avg("overall"), "overall"), r6(F.stddev_samp("overall"), "spread"), r6(F.avg("stale"), "stale"), r6(F.avg("ece"), "ece"))


@query("eval_ranking", B.orders(90.0) + B.ranked(M4.as_tuple(), 5) + ', hit AS (SELECT query_id, rank FROM top WHERE unit_id = truth), k AS (SELECT q.query_id, rank FROM queries q LEFT JOIN hit USING (query_id)) SELECT count(*) AS n, round(avg(CASE WHEN rank IS NULL THEN 0.0 ELSE 1.0 END), 6) AS recall, round(avg(coalesce(1.0 / rank, 0.0)), 6) AS mrr, round(avg(coalesce(1.0 / log2(rank + 1.0), 0.0)), 6) AS ndcg FROM k')
def eval_ranking(spark, d):
    _, queries, sc = orders(spark, d, 90.0)
    return E.ranking_quality(R.rank(sc, M4, 5).select("query_id", "unit_id", "rank"), queries, 5)


@query("eval_candidate_recall", "SELECT * FROM (" + B.orders(90.0, 8) + " SELECT CAST(8 AS BIGINT) AS k, count(*) AS found, (SELECT count(*) FROM queries) AS n FROM sc WHERE unit_id = truth) UNION ALL SELECT * FROM (" + B.orders(90.0, 32) + " SELECT CAST(32 AS BIGINT) AS k, count(*) AS found, (SELECT count(*) FROM queries) AS n FROM sc WHERE unit_id = truth)")
def eval_candidate_recall(spark, d):
    out = []
    for k in (8, 32):
        _, queries, sc = orders(spark, d, 90.0, k)
        n = queries.agg(F.count("*").alias("n"))
        out.append(sc.filter("unit_id = truth").agg(F.count("*").alias("found")).crossJoin(n).select(F.lit(k).cast("long").alias("k"), "found", "n"))
    return out[0].unionAll(out[1])


@query("bench_passages", "SELECT item_id, doc_id FROM benchmark b JOIN documents d ON contains(d.text, b.text)")
def bench_passages(spark, d):
    """Documents that hold a benchmark text verbatim: candidates by the text's rarest words, then the exact test."""
    docs, items = G.table(spark, d, "documents").select("doc_id", "text"), G.table(spark, d, "benchmark").withColumnRenamed("text", "item")
    tok = lambda c: F.array_distinct(F.regexp_extract_all(F.lower(c), F.lit(R.TOKEN), F.lit(1)))
    words = docs.select("doc_id", F.explode(tok("text")).alias("w"))
    wanted = items.select("item_id", F.explode(F.slice(F.array_sort(tok("item"), lambda a, b: F.length(b) - F.length(a)), 1, 1)).alias("w"))
    pairs = words.join(F.broadcast(wanted), "w").select("doc_id", "item_id").distinct()
    return pairs.join(F.broadcast(items), "item_id").join(docs, "doc_id").filter(F.contains("text", F.col("item"))).select("item_id", "doc_id")
