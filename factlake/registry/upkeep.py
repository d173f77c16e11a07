"""Lifecycle, maintenance, localised updates and context."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from factlake.functions import signals as S
from factlake.operators import context as C
from factlake.operators import lifecycle as L
from factlake.operators import maintenance as M
from factlake.operators import retrieval as R
from factlake.operators import updates as U
from factlake.params import RANKERS, Params
from factlake.registry import base as B
from factlake.registry.base import query
from factlake.registry.ranking import COUNTS, LOG, TREE, now, orders, policies, policy_table, r6
from factlake.sources import given as G

P365 = Params(half_life=365.0)
TRUST = f"least(1.0, greatest(0.01, prior_trust * pow(2.0, -{B.days('born_at', B.NOW)} / 365.0)))"
ORD = "WITH " + B.order_units()


def aged(spark, d):
    return L.step_trust(G.order_units(spark, d), now(), P365)


# ---- lifecycle

@query("life_chunk", "SELECT doc_id, CAST(k AS BIGINT) AS chunk_no, CAST(k * 1000 AS BIGINT) AS span_start, CAST(least((k + 1) * 1000, length(text)) AS BIGINT) AS span_end, md5(substr(text, k * 1000 + 1, 1000)) AS sha FROM (SELECT doc_id, text, unnest(range(CAST(greatest(1, ceil(length(text) / 1000.0)) AS BIGINT))) AS k FROM documents)")
def life_chunk(spark, d):
    return L.chunk(G.table(spark, d, "documents")).select("doc_id", "chunk_no", "span_start", "span_end", F.md5("body").alias("sha"))


@query("life_chunk_lines", "SELECT doc_id, CAST(i - 1 AS BIGINT) AS chunk_no, md5(parts[i]) AS sha FROM (SELECT doc_id, string_split(text, chr(10)) AS parts, unnest(range(1, len(string_split(text, chr(10))) + 1)) AS i FROM documents)")
def life_chunk_lines(spark, d):
    return L.chunk(G.table(spark, d, "documents"), mode="lines").select("doc_id", "chunk_no", F.md5("body").alias("sha"))


ARRIVE = "arr AS (SELECT 'L:' || l_orderkey || ':' || l_partkey || ':' || l_linenumber AS unit_id, l_partkey AS doc_id, CAST(l_linenumber AS BIGINT) AS chunk_no, row_number() OVER (PARTITION BY l_partkey, l_linenumber ORDER BY l_shipdate, l_orderkey) AS version_no FROM (SELECT l_orderkey, l_partkey, l_linenumber, min(l_shipdate) AS l_shipdate FROM lineitem GROUP BY ALL))"


def arrivals(spark, d):
    l = G.table(spark, d, "lineitem").groupBy("l_orderkey", "l_partkey", "l_linenumber").agg(F.min("l_shipdate").alias("day"))
    w = Window.partitionBy("l_partkey", "l_linenumber").orderBy("day", "l_orderkey")
    name = F.concat_ws(":", F.lit("L"), *(F.col(c).cast("string") for c in ("l_orderkey", "l_partkey", "l_linenumber")))
    return l.select(name.alias("unit_id"), F.col("l_partkey").alias("doc_id"), F.col("l_linenumber").cast("long").alias("chunk_no"), F.row_number().over(w).cast("long").alias("version_no"))


ENC = "SELECT unit_id, CASE WHEN b = 1 THEN 'UNCONSOLIDATED' WHEN b > 2 AND {0} THEN 'ARCHIVED' ELSE 'DEPRECATED' END AS status, replaces, replaced_by FROM (SELECT unit_id, row_number() OVER (PARTITION BY doc_id, chunk_no ORDER BY version_no DESC) AS b, lag(unit_id) OVER w AS replaces, lead(unit_id) OVER w AS replaced_by FROM arr WINDOW w AS (PARTITION BY doc_id, chunk_no ORDER BY version_no))"


@query("life_encode", f"WITH {ARRIVE} {ENC.format('FALSE')}")
def life_encode(spark, d):
    return L.encode(arrivals(spark, d)).select("unit_id", "status", "replaces", "replaced_by")


@query("life_archive_on_encode", f"WITH {ARRIVE} {ENC.format('TRUE')}")
def life_archive_on_encode(spark, d):
    return L.encode(arrivals(spark, d), archive=True).select("unit_id", "status", "replaces", "replaced_by")


@query("life_lineage", ORD + " SELECT unit_id AS src, replaces AS dst, 'replaces' AS kind FROM u WHERE replaces IS NOT NULL")
def life_lineage(spark, d):
    return L.lineage_edges(G.order_units(spark, d))


@query("life_chain", ORD + " SELECT topic, unit_id, version_no - 1 AS depth, first_value(unit_id) OVER (PARTITION BY topic ORDER BY version_no) AS root FROM u WHERE NOT is_rumour")
def life_chain(spark, d):
    return L.chain(G.order_units(spark, d))


MOVED = "moved AS (SELECT 'C:' || c_custkey AS old, 'C:' || c_custkey || ':2' AS new FROM customer WHERE c_custkey % 7 = 0)"


@query("life_transfer", f"WITH {TREE}, {MOVED} SELECT DISTINCT coalesce(a.new, src) AS src, coalesce(b.new, dst) AS dst, 'depends_on' AS kind FROM tree LEFT JOIN moved a ON a.old = src LEFT JOIN moved b ON b.old = dst")
def life_transfer(spark, d):
    c = G.table(spark, d, "customer").filter("c_custkey % 7 = 0").select(F.concat(F.lit("C:"), F.col("c_custkey").cast("string")).alias("old"))
    return L.transfer_edges(G.dependency_tree(spark, d).withColumn("kind", F.lit("depends_on")), c.withColumn("new", F.concat("old", F.lit(":2"))))


@query("life_reinforce", f"WITH {LOG}, c AS ({COUNTS} GROUP BY unit_id) SELECT doc_id, coalesce(access_n, 0) AS access_n, coalesce(pos_n, 0) AS pos_n, coalesce(neg_n, 0) AS neg_n FROM documents LEFT JOIN c ON doc_id = unit_id")
def life_reinforce(spark, d):
    return L.apply_feedback(G.table(spark, d, "documents").select("doc_id"), G.document_log(spark, d), "doc_id").select("doc_id", "access_n", "pos_n", "neg_n")


@query("life_log_retrieval", B.orders(90.0) + B.ranked(RANKERS["m4"].as_tuple()) + " SELECT unit_id, ref_time AS ts, 'access' AS action, query_id AS actor FROM top")
def life_log_retrieval(spark, d):
    return L.log_retrieval(R.rank(orders(spark, d, 90.0)[2], RANKERS["m4"]))


DEMOTED = f"dem AS (SELECT *, {TRUST} AS trust, CASE WHEN status = 'ACTIVE' AND {TRUST} < 0.15 THEN 'DORMANT' ELSE status END AS new_status FROM u)"


@query("life_demote", ORD + f", {DEMOTED} SELECT unit_id, new_status AS status FROM dem")
def life_demote(spark, d):
    return aged(spark, d).select("unit_id", "status")


@query("life_wake", ORD + f", {DEMOTED} SELECT unit_id, CASE WHEN new_status = 'DORMANT' AND {TRUST.replace('365.0', '3650.0')} >= 0.15 THEN 'ACTIVE' ELSE new_status END AS status FROM dem")
def life_wake(spark, d):
    return L.step_trust(aged(spark, d).drop("trust"), now(), Params(half_life=3650.0), wake=True).select("unit_id", "status")


@query("life_promote", f"WITH {ARRIVE}, e AS ({ENC.format('FALSE')}) SELECT CASE WHEN status = 'UNCONSOLIDATED' THEN 'ACTIVE' ELSE status END AS status, count(*) AS n FROM e GROUP BY 1")
def life_promote(spark, d):
    return L.promote(L.encode(arrivals(spark, d))).groupBy("status").agg(F.count("*").alias("n"))


@query("life_archive", ORD + " SELECT unit_id, CASE WHEN status = 'DEPRECATED' AND valid_to < TIMESTAMP '1998-01-01' THEN 'ARCHIVED' ELSE status END AS status FROM u")
def life_archive(spark, d):
    return L.archive(G.order_units(spark, d), G.at("1998-01-01")).select("unit_id", "status")


@query("life_audit", ORD + f", {DEMOTED} SELECT unit_id, status AS old_status, new_status, 'trust' AS cause FROM dem WHERE status <> new_status")
def life_audit(spark, d):
    return L.audit(G.order_units(spark, d), aged(spark, d), "trust")


@query("life_illegal", ORD + ", ch AS (SELECT unit_id, status AS old_status, CASE WHEN is_rumour THEN 'ARCHIVED' ELSE 'ACTIVE' END AS new_status FROM u) SELECT old_status, new_status, count(*) AS n FROM ch WHERE old_status <> new_status AND NOT ((old_status = 'DEPRECATED' AND new_status = 'ARCHIVED')) GROUP BY ALL")
def life_illegal(spark, d):
    u = G.order_units(spark, d)
    after = u.withColumn("status", F.when(F.col("is_rumour"), "ARCHIVED").otherwise("ACTIVE"))
    return L.illegal(L.audit(u, after, "test")).groupBy("old_status", "new_status").agg(F.count("*").alias("n"))


@query("life_asof_version", ORD + B.QUERY_SET + " SELECT query_id, max_by(unit_id, valid_from) AS unit_id FROM queries q JOIN u ON q.topic = u.topic AND NOT is_rumour AND valid_from <= ref_time AND (valid_to IS NULL OR ref_time < valid_to) WHERE kind = 'time_point' GROUP BY query_id")
def life_asof_version(spark, d):
    u = G.order_units(spark, d)
    return L.as_of(u, G.order_queries(u).filter("kind = 'time_point'"))


# ---- maintenance

@query("maint_refresh", ORD + f" SELECT unit_id, round({TRUST}, 6) AS trust FROM u")
def maint_refresh(spark, d):
    return aged(spark, d).select("unit_id", r6(F.col("trust"), "trust"))


PAIRS = "pairs AS (SELECT least(a.unit_id, r.unit_id) AS a, greatest(a.unit_id, r.unit_id) AS b FROM u a JOIN u r ON a.topic = r.topic AND NOT a.is_rumour AND r.is_rumour AND a.value <> r.value AND (a.valid_to IS NULL OR r.born_at <= a.valid_to))"


@query("maint_contradictions_value", ORD + f", {PAIRS} SELECT a, b FROM pairs")
def maint_contradictions_value(spark, d):
    return M.value_conflicts(G.order_units(spark, d))


@query("maint_marked", ORD + f", {PAIRS}, tr AS (SELECT unit_id, {TRUST} AS trust FROM u), bo AS (SELECT a AS unit_id, b AS other FROM pairs UNION ALL SELECT b, a FROM pairs) SELECT bo.unit_id, count(*) AS conflicts, bool_or(x.trust < y.trust) AS loses FROM bo JOIN tr x ON x.unit_id = bo.unit_id JOIN tr y ON y.unit_id = other GROUP BY bo.unit_id")
def maint_marked(spark, d):
    u = G.order_units(spark, d)
    return M.marked(L.step_trust(u, now(), P365.but(libm=True)), M.value_conflicts(u))


SHINGLES = "w AS (SELECT doc_id, list_filter(regexp_split_to_array(lower(text), '\\s+'), lambda x: x <> '') AS w FROM documents), sh AS (SELECT doc_id, list_distinct(list_transform(range(1, len(w) - 2), lambda i: md5(w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] || ' ' || w[i + 3]))) AS s FROM w WHERE len(w) >= 4), ex AS (SELECT doc_id, unnest(s) AS g FROM sh), held AS (SELECT g, count(*) AS df FROM ex GROUP BY g), pre AS (SELECT doc_id, g FROM (SELECT doc_id, g, df, row_number() OVER (PARTITION BY doc_id ORDER BY df, g) AS r, count(*) OVER (PARTITION BY doc_id) AS n FROM ex JOIN held USING (g)) WHERE df > 1 AND r <= n - ceil(0.499999 * n) + 1), pr AS (SELECT DISTINCT a.doc_id AS dst, b.doc_id AS src FROM pre a JOIN pre b ON a.g = b.g AND a.doc_id < b.doc_id), jac AS (SELECT src, dst, round(len(list_intersect(x.s, y.s)) / CAST(len(x.s) + len(y.s) - len(list_intersect(x.s, y.s)) AS DOUBLE), 6) AS jaccard FROM pr JOIN sh x ON x.doc_id = src JOIN sh y ON y.doc_id = dst)"


@query("maint_edges_semantic", f"WITH {SHINGLES} SELECT src, dst, jaccard FROM jac WHERE jaccard >= 0.5")
def maint_edges_semantic(spark, d):
    return M.semantic_edges(G.table(spark, d, "documents"))


@query("maint_contradictions_text", f"WITH {SHINGLES} SELECT dst AS a, src AS b FROM jac WHERE jaccard >= 0.5 AND jaccard <= 0.95")
def maint_contradictions_text(spark, d):
    return M.semantic_edges(G.table(spark, d, "documents"), most=0.95).select(F.col("dst").alias("a"), F.col("src").alias("b"))


@query("maint_families", f"WITH RECURSIVE {SHINGLES}, e AS (SELECT src AS a, dst AS b FROM jac WHERE jaccard >= 0.5 UNION ALL SELECT dst, src FROM jac WHERE jaccard >= 0.5), reach AS (SELECT a, b FROM e UNION SELECT r.a, e.b FROM reach r JOIN e ON r.b = e.a) SELECT a AS doc_id, least(a, min(b)) AS family FROM reach GROUP BY a")
def maint_families(spark, d):
    return M.semantic_families(G.table(spark, d, "documents"))


@query("maint_edges_structural", "SELECT doc_id || ':' || k AS src, doc_id || ':0' AS dst, 'depends_on' AS kind FROM (SELECT doc_id, unnest(range(1, CAST(greatest(1, ceil(length(text) / 1000.0)) AS BIGINT))) AS k FROM documents)")
def maint_edges_structural(spark, d):
    return M.structural_edges(L.chunk(G.table(spark, d, "documents")))


@query("maint_edges_apply", f"WITH {TREE} SELECT src, dst, 'depends_on' AS kind FROM tree UNION SELECT 'C:' || c_custkey, 'R:0', 'depends_on' FROM customer WHERE c_custkey <= 20")
def maint_edges_apply(spark, d):
    new = G.table(spark, d, "customer").filter("c_custkey <= 20").select(F.concat(F.lit("C:"), F.col("c_custkey").cast("string")).alias("src"), F.lit("R:0").alias("dst"), F.lit("depends_on").alias("kind"))
    tree = G.dependency_tree(spark, d).withColumn("kind", F.lit("depends_on"))
    return M.apply_edges(tree, tree.unionAll(new))


@query("maint_edge_lists", f"WITH {TREE}, ids AS (SELECT 'C:' || c_custkey AS unit_id FROM customer) SELECT unit_id, coalesce((SELECT string_agg(DISTINCT dst, ',' ORDER BY dst) FROM tree WHERE src = unit_id), '') AS depends_on, coalesce((SELECT string_agg(DISTINCT src, ',' ORDER BY src) FROM tree WHERE dst = unit_id), '') AS depended_by FROM ids")
def maint_edge_lists(spark, d):
    ids = G.table(spark, d, "customer").select(F.concat(F.lit("C:"), F.col("c_custkey").cast("string")).alias("unit_id"))
    return M.as_lists(ids, G.dependency_tree(spark, d)).select("unit_id", F.array_join("depends_on", ",").alias("depends_on"), F.array_join("depended_by", ",").alias("depended_by"))


def ripple_sql(edges: str, seeds: str, hops: int = 2, kernel: str = "0.15 / (hop + 1)", hit_seed: bool = True) -> str:
    steps = ["h0 AS (SELECT DISTINCT s.unit_id AS seed, e.src AS unit_id FROM seeds s JOIN e ON e.dst = s.unit_id)"]
    for h in range(1, hops):
        seen = " UNION ".join(f"SELECT seed, unit_id FROM h{i}" for i in range(h))
        steps.append(f"h{h} AS (SELECT DISTINCT p.seed, e.src AS unit_id FROM h{h - 1} p JOIN e ON e.dst = p.unit_id EXCEPT ({seen}))")
    alls = " UNION ALL ".join(f"SELECT seed, unit_id, CAST({h} AS BIGINT) AS hop FROM h{h}" for h in range(hops))
    keep = "" if hit_seed else "WHERE seed <> unit_id"
    return f"WITH {edges}, seeds AS ({seeds}), {', '.join(steps)}, msg AS (SELECT seed, unit_id, hop, {kernel} AS penalty FROM ({alls}) {keep})"


E_TREE = TREE + ", e AS (SELECT DISTINCT src, dst FROM tree)"
E_PART = "e AS (SELECT DISTINCT 'P:' || a.l_partkey AS src, 'P:' || b.l_partkey AS dst FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey <> b.l_partkey)"
SEEDS = "SELECT 'R:0' AS unit_id UNION ALL SELECT 'N:3'"
PSEEDS = "SELECT 'P:' || p_partkey AS unit_id FROM part WHERE p_partkey <= 5"
SHOW = " SELECT seed, unit_id, hop, round(penalty, 6) AS penalty FROM msg"


def shown(m):
    return m.select("seed", "unit_id", "hop", r6(F.col("penalty"), "penalty"))


def seeds(spark, *ids):
    return spark.createDataFrame([(i,) for i in ids], "unit_id string")


def part_seeds(spark, d):
    return G.table(spark, d, "part").filter("p_partkey <= 5").select(F.concat(F.lit("P:"), F.col("p_partkey").cast("string")).alias("unit_id"))


@query("maint_ripple", ripple_sql(E_TREE, SEEDS) + SHOW)
def maint_ripple(spark, d):
    return shown(M.ripple(seeds(spark, "R:0", "N:3"), G.dependency_tree(spark, d)))


@query("maint_ripple_depth3", ripple_sql(E_TREE, SEEDS, 3) + SHOW)
def maint_ripple_depth3(spark, d):
    return shown(M.ripple(seeds(spark, "R:0", "N:3"), G.dependency_tree(spark, d), 3))


@query("maint_ripple_dense", ripple_sql(E_PART, PSEEDS) + SHOW)
def maint_ripple_dense(spark, d):
    return shown(M.ripple(part_seeds(spark, d), G.part_graph(spark, d)))


@query("maint_ripple_no_seed", ripple_sql(E_PART, PSEEDS, hit_seed=False) + SHOW)
def maint_ripple_no_seed(spark, d):
    return shown(M.ripple(part_seeds(spark, d), G.part_graph(spark, d), hit_seed=False))


@query("maint_ripple_exponential", ripple_sql(E_TREE, SEEDS, 3, "0.15 * pow(0.5, hop)") + SHOW)
def maint_ripple_exponential(spark, d):
    return shown(M.ripple(seeds(spark, "R:0", "N:3"), G.dependency_tree(spark, d), 3, M.exponential))


CAPPED = E_PART.replace("e AS", "e0 AS") + ", e AS (SELECT src, dst FROM (SELECT *, row_number() OVER (PARTITION BY dst ORDER BY src) AS n FROM e0) WHERE n <= 10)"


@query("maint_ripple_capped", ripple_sql(CAPPED, PSEEDS) + SHOW)
def maint_ripple_capped(spark, d):
    return shown(M.ripple(part_seeds(spark, d), G.part_graph(spark, d), fan_out=10))


ALL_PARTS = ", units AS (SELECT 'P:' || p_partkey AS unit_id, 0.5 AS prior FROM part)"


def part_units(spark, d):
    return G.table(spark, d, "part").select(F.concat(F.lit("P:"), F.col("p_partkey").cast("string")).alias("unit_id"), F.lit(0.5).alias("prior_trust"))


def applied(u):
    return u.select("unit_id", r6(F.col("prior_trust"), "prior_trust"), F.coalesce(F.array_join("flags", ","), F.lit("")).alias("flags"))


@query("maint_ripple_apply", ripple_sql(E_PART, PSEEDS) + ALL_PARTS + " SELECT u.unit_id, round(CASE WHEN count(seed) = 0 THEN any_value(prior) ELSE greatest(0.01, any_value(prior) - sum(penalty)) END, 6) AS prior_trust, coalesce(string_agg(DISTINCT seed, ',' ORDER BY seed), '') AS flags FROM units u LEFT JOIN msg m ON u.unit_id = m.unit_id GROUP BY u.unit_id")
def maint_ripple_apply(spark, d):
    return applied(M.apply_ripple(part_units(spark, d), M.ripple(part_seeds(spark, d), G.part_graph(spark, d))))


@query("maint_ripple_unfloored", ripple_sql(E_PART, PSEEDS) + ALL_PARTS + " SELECT u.unit_id, round(any_value(prior) - coalesce(sum(penalty), 0.0), 6) AS prior_trust FROM units u LEFT JOIN msg m ON u.unit_id = m.unit_id GROUP BY u.unit_id")
def maint_ripple_unfloored(spark, d):
    return applied(M.apply_ripple(part_units(spark, d), M.ripple(part_seeds(spark, d), G.part_graph(spark, d)), Params(ripple_floor=None))).drop("flags")


@query("maint_ripple_relative", ripple_sql(E_PART, PSEEDS) + ALL_PARTS + " SELECT u.unit_id, round(CASE WHEN count(seed) = 0 THEN any_value(prior) ELSE greatest(0.01, any_value(prior) * exp(sum(ln(1.0 - penalty)))) END, 6) AS prior_trust FROM units u LEFT JOIN msg m ON u.unit_id = m.unit_id GROUP BY u.unit_id")
def maint_ripple_relative(spark, d):
    return applied(M.apply_ripple(part_units(spark, d), M.ripple(part_seeds(spark, d), G.part_graph(spark, d)), relative=True)).drop("flags")


@query("maint_ripple_stats", ripple_sql(E_PART, PSEEDS) + ", per AS (SELECT seed, count(*) AS messages, count(CASE WHEN hop = 0 THEN 1 END) AS first_hop FROM msg GROUP BY seed) SELECT count(*) AS seeds, CAST(sum(messages) AS BIGINT) AS messages, max(messages) AS most, max(first_hop) AS widest, round(avg(messages), 6) AS mean FROM per")
def maint_ripple_stats(spark, d):
    return M.ripple_stats(M.ripple(part_seeds(spark, d), G.part_graph(spark, d))).withColumn("mean", F.round("mean", 6))


CYCLE = f"WITH {B.policy_units()}, ed AS (SELECT a.unit_id AS src, b.unit_id AS dst FROM u a JOIN u b ON b.topic = a.topic - 1 AND a.topic % 5 = 0 AND a.topic > 0 AND a.replaced_by IS NULL AND NOT a.is_rumour AND b.replaced_by IS NULL AND NOT b.is_rumour), seeds AS (SELECT unit_id FROM u WHERE replaced_by IS NULL AND NOT is_rumour AND topic % 5 = 4), h0 AS (SELECT DISTINCT s.unit_id AS seed, ed.src AS unit_id FROM seeds s JOIN ed ON ed.dst = s.unit_id), h1 AS (SELECT DISTINCT h.seed, ed.src AS unit_id FROM h0 h JOIN ed ON ed.dst = h.unit_id EXCEPT SELECT * FROM h0), msg AS (SELECT unit_id, sum(p) AS hit FROM (SELECT unit_id, 0.15 AS p FROM h0 UNION ALL SELECT unit_id, 0.075 FROM h1) GROUP BY unit_id), tr AS (SELECT * EXCLUDE (degree), {B.live_trust()} AS trust FROM u), dg AS (SELECT unit_id, count(*) AS degree FROM (SELECT src AS unit_id FROM ed UNION ALL SELECT dst FROM ed) GROUP BY unit_id), {PAIRS}, bo AS (SELECT a AS unit_id FROM pairs UNION ALL SELECT b FROM pairs), cf AS (SELECT unit_id, count(*) AS conflicts FROM bo GROUP BY unit_id) SELECT tr.unit_id, CASE WHEN status = 'ACTIVE' AND trust < 0.15 THEN 'DORMANT' ELSE status END AS status, round(trust, 6) AS trust, round(CASE WHEN hit IS NULL THEN prior_trust ELSE greatest(0.01, prior_trust - hit) END, 6) AS prior_trust, coalesce(conflicts, 0) AS conflicts, coalesce(degree, 0) AS degree FROM tr LEFT JOIN msg ON msg.unit_id = tr.unit_id LEFT JOIN cf ON cf.unit_id = tr.unit_id LEFT JOIN dg ON dg.unit_id = tr.unit_id"


@query("maint_cycle", CYCLE)
def maint_cycle(spark, d):
    """One pass that starts without edges and builds them: ripples and degrees follow from what it built."""
    u = policy_table(spark)
    changed = u.filter("replaced_by IS NULL AND NOT is_rumour AND topic % 5 = 4").select("unit_id")
    none = spark.createDataFrame([], "src string, dst string, kind string")
    out, _, _ = M.run_cycle(u, none, changed, now(), build=G.policy_edges)
    return out.select("unit_id", "status", r6(F.col("trust"), "trust"), r6(F.col("prior_trust"), "prior_trust"), "conflicts", "degree")


@query("maint_pending", f"WITH {LOG} SELECT unit_id, count(*) AS n FROM elog WHERE action = 'correct' AND unit_id NOT IN (SELECT unit_id FROM elog WHERE action = 'validate') GROUP BY unit_id")
def maint_pending(spark, d):
    """Corrected documents that nobody has validated: the queue less what is done."""
    log = G.document_log(spark, d)
    return M.pending(log.filter("action = 'correct'").select("unit_id"), log.filter("action = 'validate'").select("unit_id").distinct()).groupBy("unit_id").agg(F.count("*").alias("n"))


@query("maint_guard_weighted", f"WITH {LOG}, c AS (SELECT actor, (count(CASE WHEN action = 'accept' THEN 1 END) + 5.0) / (count(CASE WHEN action IN ('accept', 'correct') THEN 1 END) + 10.0) AS w FROM elog GROUP BY actor), v AS (SELECT *, row_number() OVER (PARTITION BY actor, unit_id, day ORDER BY event_id) AS n FROM elog WHERE action IN ('accept', 'correct')), g AS (SELECT unit_id, action, actor FROM v WHERE n <= 1 UNION ALL SELECT unit_id, action, actor FROM elog WHERE action NOT IN ('accept', 'correct')) SELECT unit_id, count(CASE WHEN action = 'access' THEN 1 END) AS access_n, round(sum(CASE WHEN action = 'accept' THEN w ELSE 0.0 END), 6) AS pos_n, round(sum(CASE WHEN action = 'correct' THEN w ELSE 0.0 END), 6) AS neg_n FROM g JOIN c USING (actor) GROUP BY unit_id")
def maint_guard_weighted(spark, d):
    """Capped votes, each worth its actor's reliability."""
    log = G.document_log(spark, d)
    c = M.weighted_counters(M.guard_feedback(log, 1, M.author_reliability(log)))
    return c.select("unit_id", "access_n", r6(F.col("pos_n"), "pos_n"), r6(F.col("neg_n"), "neg_n"))


@query("maint_author_prior", f"WITH {LOG}, c AS (SELECT actor, count(CASE WHEN action = 'accept' THEN 1 END) AS accepted, count(CASE WHEN action = 'correct' THEN 1 END) AS corrected FROM elog GROUP BY actor) SELECT actor, accepted, corrected, round((accepted + 5.0) / (accepted + corrected + 10.0), 6) AS reliability FROM c")
def maint_author_prior(spark, d):
    return M.author_reliability(G.document_log(spark, d)).withColumn("reliability", F.round("reliability", 6))


@query("maint_guard", f"WITH {LOG}, v AS (SELECT *, row_number() OVER (PARTITION BY actor, unit_id, day ORDER BY event_id) AS n FROM elog WHERE action IN ('accept', 'correct')) SELECT event_id, action FROM v WHERE n <= 1 UNION ALL SELECT event_id, action FROM elog WHERE action NOT IN ('accept', 'correct')")
def maint_guard(spark, d):
    return M.guard_feedback(G.document_log(spark, d), 1).select("event_id", "action")


@query("maint_anomalies", f"WITH {LOG}, n AS (SELECT actor, count(*) AS events FROM elog GROUP BY actor), s AS (SELECT avg(events) AS m, stddev_samp(events) AS sd FROM n) SELECT actor, events, round((events - m) / sd, 6) AS z FROM n, s WHERE (events - m) / sd > 2.0")
def maint_anomalies(spark, d):
    return M.anomalies(G.document_log(spark, d)).withColumn("z", F.round("z", 6))


@query("maint_cold_share", f"WITH {LOG} SELECT count(*) AS units, count(*) - count(c.unit_id) AS cold FROM documents LEFT JOIN (SELECT DISTINCT unit_id FROM elog) c ON doc_id = c.unit_id")
def maint_cold_share(spark, d):
    seen = G.document_log(spark, d).select("unit_id").distinct()
    rows = G.table(spark, d, "documents").select("doc_id").join(seen, F.col("doc_id") == F.col("unit_id"), "left")
    return rows.agg(F.count("*").alias("units"), F.count_if(F.col("unit_id").isNull()).alias("cold"))


# ---- localised updates

EDIT = "ed AS (SELECT doc_id, text AS old, array_to_string(list_concat(w[1:m], ['revised'], w[m + 2:]), ' ') AS new, array_to_string(w[1:m], ' ') || ' ' AS head, w[m + 1] AS mid, ' ' || array_to_string(w[m + 2:], ' ') AS tail FROM (SELECT doc_id, text, string_split(text, ' ') AS w, CAST(floor(len(string_split(text, ' ')) / 2) AS BIGINT) AS m FROM documents) WHERE len(w) >= 3)"


def _same(x: str, y: str) -> str:
    """Length of the common beginning of two strings, of at most 300 characters."""
    return f"coalesce(list_min(list_filter(range(1, least(length({x}), length({y}), 300) + 1), lambda i: substr({x}, i, 1) <> substr({y}, i, 1))) - 1, least(length({x}), length({y}), 300))"


TRIM = EDIT + f", pre AS (SELECT *, least(length(head) + {_same('substr(mid || tail, 1, 300)', "substr('revised' || tail, 1, 300)")}, length(old), length(new)) AS s FROM ed WHERE old <> new), suf AS (SELECT *, least(length(tail) + {_same('reverse(right(head || mid, 300))', "reverse(right(head || 'revised', 300))")}, length(old) - s, length(new) - s) AS e FROM pre)"


def edits(spark, d):
    return U.middle_word_edit(G.table(spark, d, "documents"))


@query("upd_edit", f"WITH {EDIT} SELECT doc_id, md5(new) AS sha FROM ed")
def upd_edit(spark, d):
    return edits(spark, d).select("doc_id", F.md5("new").alias("sha"))


@query("upd_diff_trim", f"WITH {TRIM} SELECT doc_id, CAST(s AS BIGINT) AS old_start, CAST(length(old) - e AS BIGINT) AS old_end, CAST(length(new) - e AS BIGINT) AS new_end, CAST(length(new) - length(old) AS BIGINT) AS delta FROM suf")
def upd_diff_trim(spark, d):
    return U.diff_trim(edits(spark, d)).select("doc_id", "old_start", "old_end", "new_end", "delta")


@query("upd_diff_tokens", f"WITH {EDIT} SELECT count(*) AS edited, CAST(sum(length(new) - length(old)) AS BIGINT) AS delta FROM ed WHERE old <> new")
def upd_diff_tokens(spark, d):
    """Edited documents and the growth of their texts, from all hunks by words."""
    h = U.diff_tokens(edits(spark, d))
    return h.agg(F.countDistinct("doc_id").alias("edited"), F.sum("delta").alias("delta"))


CH = "(SELECT doc_id, md5(substr(text, k * 1000 + 1, 1000)) AS sha FROM (SELECT doc_id, {0} AS text, unnest(range(CAST(greatest(1, ceil(length({0}) / 1000.0)) AS BIGINT))) AS k FROM ed))"


@query("upd_diff_hash", f"WITH {EDIT}, o AS (SELECT DISTINCT * FROM {CH.format('old')}), n AS (SELECT DISTINCT * FROM {CH.format('new')}) SELECT coalesce(o.doc_id, n.doc_id) AS doc_id, CASE WHEN o.sha IS NULL THEN 'added' WHEN n.sha IS NULL THEN 'removed' ELSE 'kept' END AS state, count(*) AS n FROM o FULL JOIN n ON o.doc_id = n.doc_id AND o.sha = n.sha GROUP BY ALL")
def upd_diff_hash(spark, d):
    e = edits(spark, d)
    return U.diff_hash(L.chunk(e.select("doc_id", F.col("old").alias("text"))), L.chunk(e.select("doc_id", F.col("new").alias("text"))))


def spliced(spark, d):
    e = edits(spark, d)
    chunks = L.chunk(e.select("doc_id", F.col("old").alias("text")))
    hunks = U.diff_trim(e)
    return e, chunks, hunks


HIT = f"WITH {TRIM}, ch AS (SELECT doc_id, k AS chunk_no, k * 1000 AS a, least((k + 1) * 1000, length(old)) AS b, s, length(old) - e AS t, e, new, length(new) - length(old) AS delta FROM (SELECT *, unnest(range(CAST(greatest(1, ceil(length(old) / 1000.0)) AS BIGINT))) AS k FROM suf)), hit AS (SELECT doc_id, chunk_no FROM ch WHERE CASE WHEN s = t THEN (a < s AND s <= b) OR (s = 0 AND chunk_no = 0) ELSE a < t AND b > s END)"
SPLICED = HIT + ", st AS (SELECT *, CASE WHEN s < a AND t > a THEN length(new) - e WHEN t <= a AND NOT (s = t AND s = a AND a = 0) THEN a + delta ELSE a END AS f FROM ch), sp AS (SELECT doc_id, chunk_no, f AS span_start, coalesce(lead(f) OVER (PARTITION BY doc_id ORDER BY chunk_no), length(new)) AS span_end, new FROM st)"


@query("upd_affected", f"{HIT} SELECT doc_id, chunk_no FROM hit")
def upd_affected(spark, d):
    _, chunks, hunks = spliced(spark, d)
    return U.affected(chunks, hunks).select("doc_id", "chunk_no")


@query("upd_affected_strict", f"{HIT.replace('(a < s AND s <= b) OR (s = 0 AND chunk_no = 0)', 'a < t AND b > s')} SELECT doc_id, chunk_no FROM hit")
def upd_affected_strict(spark, d):
    _, chunks, hunks = spliced(spark, d)
    return U.affected(chunks, hunks, "strict").select("doc_id", "chunk_no")


@query("upd_splice", f"{SPLICED} SELECT sp.doc_id, sp.chunk_no, CAST(span_start AS BIGINT) AS span_start, CAST(span_end AS BIGINT) AS span_end, hit.doc_id IS NOT NULL AS replaced, md5(substr(new, span_start + 1, span_end - span_start)) AS sha FROM sp LEFT JOIN hit ON hit.doc_id = sp.doc_id AND hit.chunk_no = sp.chunk_no")
def upd_splice(spark, d):
    e, chunks, hunks = spliced(spark, d)
    return U.splice(chunks, hunks, e.join(hunks.select("doc_id").distinct(), "doc_id", "left_semi")).select("doc_id", "chunk_no", "span_start", "span_end", "replaced", F.md5("body").alias("sha"))


@query("upd_rebase", f"{SPLICED} SELECT doc_id, chunk_no, CAST(span_start AS BIGINT) AS span_start FROM sp")
def upd_rebase(spark, d):
    e, chunks, hunks = spliced(spark, d)
    return U.splice(chunks, hunks, e.join(hunks.select("doc_id").distinct(), "doc_id", "left_semi")).select("doc_id", "chunk_no", "span_start")


@query("upd_rebuild_check", f"WITH {EDIT} SELECT doc_id, md5(new) AS sha FROM ed")
def upd_rebuild_check(spark, d):
    e, chunks, hunks = spliced(spark, d)
    return U.rebuild(U.splice(chunks, hunks, e)).select("doc_id", F.md5("text").alias("sha"))


def edited_state(spark, d):
    """Chunks of all documents as units with edges to their first chunk, and what an edit of every text makes of them."""
    e, chunks, hunks = spliced(spark, d)
    none = F.lit(None).cast("string")
    name = F.concat_ws(":", F.col("doc_id").cast("string"), F.col("chunk_no").cast("string"), F.lit("v1"))
    units = chunks.select(name.alias("unit_id"), "doc_id", "chunk_no", F.lit(1).alias("version_no"), "span_start", "span_end", "body", F.lit("ACTIVE").alias("status"), G.at("2024-01-01").alias("born_at"), none.alias("replaces"), none.alias("replaced_by"))
    first = F.concat(F.col("doc_id").cast("string"), F.lit(":0:v1"))
    edges = units.filter("chunk_no > 0").select(F.col("unit_id").alias("src"), first.alias("dst"), F.lit("depends_on").alias("kind"))
    return U.apply_update(units, edges, hunks, e, G.at("2024-02-01"))


@query("upd_state", f"{SPLICED}, base AS (SELECT doc_id, k AS chunk_no, md5(substr(old, k * 1000 + 1, 1000)) AS sha, k * 1000 AS a FROM (SELECT *, unnest(range(CAST(greatest(1, ceil(length(old) / 1000.0)) AS BIGINT))) AS k FROM ed)), x AS (SELECT base.*, hit.doc_id IS NOT NULL AS r, md5(substr(new, span_start + 1, span_end - span_start)) AS new_sha, span_start FROM base LEFT JOIN sp USING (doc_id, chunk_no) LEFT JOIN hit USING (doc_id, chunk_no)) SELECT doc_id || ':' || chunk_no || ':v1' AS unit_id, CASE WHEN r THEN 'DEPRECATED' ELSE 'ACTIVE' END AS status, CAST(CASE WHEN r OR span_start IS NULL THEN a ELSE span_start END AS BIGINT) AS span_start, CASE WHEN r OR new_sha IS NULL THEN sha ELSE new_sha END AS sha, CASE WHEN r THEN doc_id || ':' || chunk_no || ':v2' END AS replaced_by FROM x UNION ALL SELECT doc_id || ':' || chunk_no || ':v2', 'UNCONSOLIDATED', CAST(span_start AS BIGINT), new_sha, NULL FROM x WHERE r")
def upd_state(spark, d):
    """All units after an edit of every document: what is replaced, what moves, what stays."""
    return edited_state(spark, d)[0].select("unit_id", "status", "span_start", F.md5("body").alias("sha"), "replaced_by")


V2 = "doc_id || ':' || {0} || CASE WHEN {1} THEN ':v2' ELSE ':v1' END"


@query("upd_state_edges", f"{HIT}, base AS (SELECT doc_id, unnest(range(CAST(greatest(1, ceil(length(old) / 1000.0)) AS BIGINT))) AS chunk_no FROM ed), x AS (SELECT base.*, hit.doc_id IS NOT NULL AS r, max(CASE WHEN chunk_no = 0 AND hit.doc_id IS NOT NULL THEN 1 ELSE 0 END) OVER (PARTITION BY base.doc_id) = 1 AS r0 FROM base LEFT JOIN hit USING (doc_id, chunk_no)) SELECT {V2.format('chunk_no', 'r')} AS src, {V2.format('0', 'r0')} AS dst, 'depends_on' AS kind FROM x WHERE chunk_no > 0 UNION ALL SELECT doc_id || ':' || chunk_no || ':v2', doc_id || ':' || chunk_no || ':v1', 'replaces' FROM x WHERE r")
def upd_state_edges(spark, d):
    """Edges after the edit: those of replaced units lead to their successors, and lineage is added."""
    return edited_state(spark, d)[1]


@query("upd_enqueue", f"{HIT}, base AS (SELECT doc_id, unnest(range(CAST(greatest(1, ceil(length(old) / 1000.0)) AS BIGINT))) AS chunk_no FROM ed), q AS (SELECT doc_id || ':' || chunk_no || ':v2' AS unit_id, doc_id, chunk_no FROM hit), x AS (SELECT base.*, hit.doc_id IS NOT NULL AS r FROM base LEFT JOIN hit USING (doc_id, chunk_no)) SELECT q.unit_id AS seed, {V2.format('x.chunk_no', 'x.r').replace('doc_id ||', 'x.doc_id ||')} AS unit_id, CAST(0 AS BIGINT) AS hop FROM q JOIN x ON x.doc_id = q.doc_id AND q.chunk_no = 0 AND x.chunk_no > 0")
def upd_enqueue(spark, d):
    """The ripple that the queue of an edit sets off, along the transferred edges."""
    _, edges, queue = edited_state(spark, d)
    return M.ripple(queue, edges.filter("kind = 'depends_on'")).select("seed", "unit_id", "hop")


def topic_documents(spark):
    """Every topic's units as the lines of one document, with the middle word of the newest version's line edited."""
    u = policy_table(spark)
    word = F.split("body", " ")
    mid = F.floor(F.size(word) / 2).cast("int")
    edited = F.concat_ws(" ", F.slice(word, F.lit(1), mid), F.array(F.lit("revised")), F.slice(word, mid + 2, F.size(word)))
    lines = u.select("topic", "unit_id", "body", F.when(F.col("replaced_by").isNull() & ~F.col("is_rumour"), edited).otherwise(F.col("body")).alias("new"))
    both = lines.groupBy(F.col("topic").alias("doc_id")).agg(F.array_sort(F.collect_list(F.struct("unit_id", "body", "new"))).alias("l"))
    text = lambda c: F.array_join(F.transform("l", lambda x: x[c]), "\n")
    return u, both.select("doc_id", text("body").alias("old"), text("new").alias("new"), F.transform("l", lambda x: x["unit_id"]).alias("ids"))


def touched_lines(spark):
    """Lines of the topics' documents, and those that the edit's hunks meet with the unit that each stands for."""
    u, docs = topic_documents(spark)
    chunks = L.chunk(docs.select("doc_id", F.col("old").alias("text")), mode="lines")
    hit = U.affected(chunks, U.diff_tokens(docs)).join(docs.select("doc_id", "ids"), "doc_id")
    return u, chunks, docs, hit.select("doc_id", F.element_at("ids", (F.col("chunk_no") + 1).cast("int")).alias("unit_id"))


# the same by SQL: lines with their places, the edited word's place, and which lines it meets
TOUCH = f"""WITH {B.policy_units()}, ln AS (SELECT topic, unit_id, body, replaced_by IS NULL AND NOT is_rumour AS newest, string_split(body, ' ') AS w, CAST(floor(len(string_split(body, ' ')) / 2) AS BIGINT) AS m,
    sum(length(body) + 1) OVER (PARTITION BY topic ORDER BY unit_id) - length(body) - 1 AS a FROM u),
    cut AS (SELECT topic, a + length(array_to_string(w[1:m], ' ')) + 1 AS s, a + length(array_to_string(w[1:m + 1], ' ')) AS t FROM ln WHERE newest),
    meet AS (SELECT ln.topic, unit_id FROM ln JOIN cut ON cut.topic = ln.topic AND a < t AND a + length(body) > s)"""


@query("upd_cost_policy", f"{TOUCH} SELECT topic, (SELECT count(*) FROM u x WHERE x.topic = c.topic) AS plain, (SELECT count(*) FROM meet y WHERE y.topic = c.topic) AS ours FROM cut c")
def upd_cost_policy(spark, d):
    _, chunks, docs, hit = touched_lines(spark)
    return U.update_cost(chunks, docs, hit).select(F.col("doc_id").alias("topic"), "plain", "ours")


@query("eval_update_cost", f"{TOUCH}, tc AS (SELECT c.topic, (SELECT count(*) FROM u x WHERE x.topic = c.topic) AS plain, (SELECT count(*) FROM meet y WHERE y.topic = c.topic) AS ours FROM cut c), m AS (SELECT count(*) AS messages FROM meet JOIN u USING (unit_id) WHERE u.topic % 5 = 4 AND u.topic + 1 < 60 AND u.replaced_by IS NULL AND NOT u.is_rumour) SELECT count(*) AS edits, round(avg(plain), 6) AS plain, round(avg(ours), 6) AS ours, round(1 - avg(ours) / avg(plain), 6) AS saving, round(any_value(messages) / CAST(count(*) AS DOUBLE), 6) AS messages FROM tc, m")
def eval_update_cost(spark, d):
    """Plain re-embeds every line of a topic's document; ours those that the diff of a single-word edit meets; ripples start from them."""
    u, chunks, docs, hit = touched_lines(spark)
    cost = U.update_cost(chunks, docs, hit)
    n = M.ripple(hit.select("unit_id"), G.policy_edges(u)).agg(F.count("*").alias("n"))
    out = cost.agg(F.count("*").alias("edits"), F.avg("plain").alias("p"), F.avg("ours").alias("o")).crossJoin(n)
    return out.select("edits", r6(F.col("p"), "plain"), r6(F.col("o"), "ours"), r6(1 - F.col("o") / F.col("p"), "saving"), r6(F.col("n") / F.col("edits"), "messages"))


@query("upd_full_reembed", "SELECT doc_id, CAST(greatest(1, ceil(length(text) / 1000.0)) AS BIGINT) AS plain FROM documents WHERE len(string_split(text, ' ')) >= 3")
def upd_full_reembed(spark, d):
    e, chunks, hunks = spliced(spark, d)
    return U.update_cost(chunks, e, U.affected(chunks, hunks)).select("doc_id", "plain")


# ---- context

TOP3 = B.orders(90.0) + B.ranked(RANKERS["m4"].as_tuple(), 3)


def top3(spark, d):
    units, _, sc = orders(spark, d, 90.0)
    return units, R.rank(sc, RANKERS["m4"], 3)


# disputes only among the units of a result list: a rumour against a version of its topic
DISPUTE = TOP3 + ", cu AS (SELECT DISTINCT unit_id FROM top), cx AS (SELECT u.* FROM u JOIN cu USING (unit_id)), pairs AS (SELECT least(a.unit_id, r.unit_id) AS a, greatest(a.unit_id, r.unit_id) AS b FROM cx a JOIN cx r ON a.topic = r.topic AND NOT a.is_rumour AND r.is_rumour AND a.value <> r.value AND (a.valid_to IS NULL OR r.born_at <= a.valid_to)), bo AS (SELECT a AS unit_id, b AS other FROM pairs UNION ALL SELECT b, a FROM pairs), cf AS (SELECT t.query_id, t.unit_id, other AS \"with\" FROM top t JOIN bo ON bo.unit_id = t.unit_id JOIN top s ON s.query_id = t.query_id AND s.unit_id = other)"


def disputes(spark, d):
    """The three best units of each query, and their disputes: only units that some list holds are paired."""
    units, t = top3(spark, d)
    t = t.join(units.select("unit_id", "body"), "unit_id") if "body" not in t.columns else t
    held = units.join(t.select("unit_id").distinct(), "unit_id", "left_semi")
    return t, C.conflicts(t, M.value_conflicts(held))


@query("ctx_conflicts", DISPUTE + " SELECT * FROM cf")
def ctx_conflicts(spark, d):
    return disputes(spark, d)[1]


GUIDE = C.GUIDANCE.replace("'", "''")


@query("ctx_assemble", DISPUTE + f""", ag AS (SELECT query_id, unit_id, string_agg(DISTINCT "with", ', ' ORDER BY "with") AS against FROM cf GROUP BY ALL),
    ln AS (SELECT t.query_id, t.rank, t.rank || ' ' || t.unit_id || ' [' || source || ', v' || coalesce(CAST(version_no AS VARCHAR), '-') || ', ' || strftime(born_at, '%Y-%m-%d') || '] ' || status || ' ' || CAST({B.days('born_at', 'ref_time')} AS BIGINT) || ' days old'
        || chr(10) || '  score ' || printf('%.3f', round(final, 3)) || ' similar ' || printf('%.3f', round(sim, 3)) || ' timely ' || printf('%.3f', round(temporal, 3)) || ' trusted ' || printf('%.3f', round(trust, 3)) || ' linked ' || printf('%.3f', round(relational, 3))
        || chr(10) || '  edges ' || degree || ' read 0 accepted 0 corrected 0' || coalesce(' disputed by ' || against, '') || chr(10) || '  ' || body AS line
        FROM top t JOIN bodies USING (unit_id) LEFT JOIN ag ON ag.query_id = t.query_id AND ag.unit_id = t.unit_id)
    SELECT query_id, '{GUIDE}' || chr(10) || string_agg(line, chr(10) ORDER BY rank) AS context FROM ln GROUP BY query_id""")
def ctx_assemble(spark, d):
    return C.assemble(*disputes(spark, d))


@query("ctx_lines", TOP3 + " SELECT query_id, count(*) AS units, string_agg(unit_id, ',' ORDER BY rank) AS ids FROM top GROUP BY query_id")
def ctx_lines(spark, d):
    _, t = top3(spark, d)
    ids = F.regexp_extract_all("context", F.lit(r"(?m)^[0-9]+ (\S+) \["), F.lit(1))
    return C.assemble(t).select("query_id", F.size(ids).cast("long").alias("units"), F.array_join(ids, ",").alias("ids"))


@query("ctx_citation", ORD + " SELECT unit_id, '[' || source || ', clerk ' || topic % 9 || ', v' || coalesce(CAST(version_no AS VARCHAR), '-') || ', ' || strftime(born_at, '%Y-%m-%d') || ']' AS citation FROM u")
def ctx_citation(spark, d):
    author = F.concat(F.lit("clerk "), F.pmod("topic", F.lit(9)).cast("string"))
    return G.order_units(spark, d).withColumn("author", author).select("unit_id", C.citation().alias("citation"))


F3 = lambda c: f"printf('%.3f', round({c}, 3))"


@query("ctx_json", TOP3 + f" SELECT query_id, '{{\"units\":[' || string_agg('{{\"rank\":' || rank || ',\"unit_id\":\"' || unit_id || '\",\"final\":\"' || {F3('final')} || '\",\"sim\":\"' || {F3('sim')} || '\",\"temporal\":\"' || {F3('temporal')} || '\",\"trust\":\"' || {F3('trust')} || '\",\"relational\":\"' || {F3('relational')} || '\"}}', ',' ORDER BY rank) || ']}}' AS context FROM top GROUP BY query_id")
def ctx_json(spark, d):
    return C.assemble_json(top3(spark, d)[1])


@query("ctx_budget", TOP3 + ", r AS (SELECT query_id, unit_id, CAST(sum(length(unit_id)) OVER (PARTITION BY query_id ORDER BY rank) AS BIGINT) AS used FROM top) SELECT * FROM r WHERE used <= 12")
def ctx_budget(spark, d):
    return C.budget(top3(spark, d)[1], 12, F.length("unit_id")).select("query_id", "unit_id", "used")


@query("sql_signals", f"SELECT 'O:' || o_orderkey AS unit_id, round(least(1.0, least(1.0, greatest(0.01, 0.5 * pow(2.0, -{B.days('o_orderdate', B.NOW)} / 30.0))) + 0.01 * ln(4.0)), 6) AS trust, round(least(0.3, 0.1 * ln(3.0)), 6) AS bonus FROM orders")
def sql_signals(spark, d):
    S.register_sql(spark)
    G.order_units(spark, d).select("unit_id", S.age_days(F.col("born_at"), now()).alias("age")).createOrReplaceTempView("aged_units")
    return spark.sql("SELECT unit_id, round(unit_trust(0.5D, age, 0L, 0L, 3L), 6) AS trust, round(unit_bonus(2L), 6) AS bonus FROM aged_units")


@query("eval_policy_counts", f"WITH {B.policy_units()}{B.QUERY_SET} SELECT (SELECT count(*) FROM u) AS units, (SELECT count(*) FROM queries) AS queries, (SELECT count(*) FROM u WHERE is_rumour) AS rumours")
def eval_policy_counts(spark, d):
    u, q, _ = policies(spark)
    n = lambda df, name: df.agg(F.count("*").alias(name))
    return n(u, "units").crossJoin(n(q, "queries")).crossJoin(n(u.filter("is_rumour"), "rumours"))
