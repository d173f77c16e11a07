"""Queries against their DuckDB SQL on the smallest tables, and properties of plans and experiments."""

import math

import duckdb
import pytest

import __spark_entry__ as entry
from factlake.registry import base
from factlake.registry import queries as registered  # noqa: F401

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SAMPLE = [
    "sig_temporal", "sig_trust", "sig_relational", "corpus_orders", "corpus_policy", "queries_time_point", "queries_conflict", "cand_tfidf", "cand_nested", "rank_m2", "rank_m4_policy", "rank_hard_filter",
    "eval_accuracy", "eval_ece", "tune_split", "life_encode", "life_transfer", "life_asof_version", "maint_ripple", "maint_ripple_capped", "maint_ripple_apply", "maint_cycle", "maint_guard",
    "maint_job", "maint_pending", "maint_guard_weighted", "maint_families", "stream_cycle", "stream_unit_counters", "stream_ingest",
    "maint_edges_semantic", "upd_affected", "upd_diff_trim", "upd_rebuild_check", "upd_splice", "upd_state", "upd_state_edges", "upd_enqueue", "upd_cost_policy", "eval_update_cost",
    "eval_ablation_policy", "eval_tuning", "eval_policy_counts", "eval_main_policy", "eval_sweep", "ctx_assemble", "ctx_json", "ctx_conflicts", "op_win_rank", "op_join_asof", "op_agg_gsets", "op_udtf_chunks", "stream_late", "stream_sliding",
]


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


def plain(v):
    if v is None or isinstance(v, float) and math.isnan(v):
        return "-"
    return f"{v:.5f}" if isinstance(v, float) or type(v).__name__ == "Decimal" else str(v)


@pytest.mark.parametrize("name", SAMPLE)
def test_same_as_sql(spark, sf, duck, name):
    got = base.QUERIES[name](spark, sf)
    cur = duck.execute(base.ORACLES[name])
    cols = [c[0] for c in cur.description]
    assert sorted(cols) == sorted(got.columns)
    want = sorted(tuple(plain(v) for v in r) for r in cur.fetchall())
    assert sorted(tuple(plain(r[c]) for c in cols) for r in got.collect()) == want


@pytest.mark.parametrize("name", ["corpus_policy", "floor_crossover", "rank_m3_policy", "rank_m4_policy", "sig_trajectory", "sql_dormant_age"])
def test_reads_a_given_table(spark, sf, duck, name):
    """Same as SQL, and another result on other tables."""
    rows = lambda where: sorted(tuple(plain(v) for v in r) for r in base.QUERIES[name](spark, where).select(*cols).collect())
    cur = duck.execute(base.ORACLES[name])
    cols = [c[0] for c in cur.description]
    got = rows(sf)
    assert got == sorted(tuple(plain(v) for v in r) for r in cur.fetchall())
    assert got != rows(sf.replace("0.001", "0.01"))


def test_trusts_that_differ_in_the_last_bit(spark, duck, tmp_path):
    """A wiki order a half-life older than a rumour has the same trust but for rounding: who loses is decided as in SQL."""
    con = duckdb.connect()
    con.execute(f"""COPY (SELECT a * 2 + x AS o_orderkey, a AS o_custkey, TIMESTAMP '2001-08-02' - to_days(CAST(a + 365 * x AS INTEGER)) AS o_orderdate, CAST(100 + x AS DOUBLE) AS o_totalprice,
        CASE WHEN x = 1 THEN '4-NOT SPECIFIED' ELSE '5-LOW' END AS o_orderpriority FROM range(1500) t(a), range(2) s(x)) TO '{tmp_path}/orders.parquet'""")
    con.execute(f"CREATE VIEW orders AS SELECT * FROM '{tmp_path}/orders.parquet'")
    want = sorted(con.execute(base.ORACLES["maint_marked"]).fetchall())
    got = sorted((r["unit_id"], r["conflicts"], r["loses"]) for r in base.QUERIES["maint_marked"](spark, str(tmp_path)).collect())
    assert len(got) == 3000 and got == want


def test_entry(spark):
    assert entry.entry(spark).count() > 0


def test_pruning_keeps_winners(spark, sf):
    a, b = (sorted(map(tuple, base.QUERIES[n](spark, sf).collect())) for n in ("rank_m4", "rank_pruned"))
    assert a == b


def test_policy_experiment_shape(spark, sf):
    """The generated corpus has the stated size, and the methods stand in the published order on it."""
    n = base.QUERIES["eval_policy_counts"](spark, sf).first()
    assert (n["units"], n["queries"], n["rumours"]) == (258, 138, 18)
    m = {r["ranker"]: r for r in base.QUERIES["eval_main_policy"](spark, sf).collect()}
    assert m["m2"]["overall"] > m["m4"]["overall"] > m["m3"]["overall"] > m["m1"]["overall"]
    assert m["m4"]["overall"] > 1.6 * m["m1"]["overall"] and m["m4"]["stale"] < m["m1"]["stale"]
    assert m["m1"]["time_point"] < 0.2 and m["m2"]["time_point"] > 0.5 and m["m4"]["conflict"] >= 0.6 and m["m2"]["conflict"] >= 0.6
    assert m["m3"]["ece"] > m["m1"]["ece"] > m["m4"]["ece"]
    a = {r["w_id"]: r for r in base.QUERIES["eval_ablation_policy"](spark, sf).collect()}
    assert a[1]["overall"] < a[2]["overall"] < a[0]["overall"] < a[3]["overall"] and abs(a[4]["d_overall"]) < 0.03
    t = base.QUERIES["eval_tuning"](spark, sf).first()
    assert t["tuned"] >= t["default_"] > t["plain"]
    assert all(r["ours"] > r["plain"] for r in base.QUERIES["eval_sweep"](spark, sf).collect())
    cost = base.QUERIES["eval_update_cost"](spark, sf).first()
    assert cost["ours"] == 1.0 and cost["plain"] == pytest.approx(4.3) and 0.7 < cost["saving"] < 0.8


def test_split_candidates_are_those_of_all_postings(spark):
    """Texts of rare and common terms, hot terms, equal texts, texts without any known term: the same lists as by every posting."""
    import random

    from factlake.operators import retrieval as R

    rnd = random.Random(3)
    word = lambda: rnd.choice("red blue green hot cold".split()) if rnd.random() < 0.6 else f"w{rnd.randint(0, 200)}"
    units = spark.createDataFrame([(f"u{i}", " ".join(word() for _ in range(rnd.randint(1, 6)))) for i in range(1500)], "unit_id string, body string")
    asked = [" ".join(word() for _ in range(rnd.randint(1, 5))) for _ in range(150)] + ["red blue", "red blue", "unknown", "", "hot"]
    queries = spark.createDataFrame(list(enumerate(asked)), "query_id long, text string")
    index = R.index(units)
    rows = lambda df: sorted((r["query_id"], r["first_rank"], r["unit_id"], round(r["sim"], 8)) for r in df.collect())
    want = rows(R.candidates_all(queries, index, 8))
    assert rows(R.candidates(queries, index, 8)) == want
    for rare, deep in ((5, 0), (5, 200), (10**6, 64)):
        was = R.RARE, R.DEEP
        R.RARE, R.DEEP = rare, deep
        try:
            assert rows(R.candidates(queries, R.index(units), 8)) == want
        finally:
            R.RARE, R.DEEP = was


def test_terms_of_middling_frequency_are_common(spark):
    """A term of one unit in fifteen brings in no units for a single text; sets of common terms are settled by the units of their rarest, or by all postings."""
    from factlake.operators import retrieval as R

    units = spark.createDataFrame([(f"u{i}", f"acct{i // 5} seg{i % 3} nation{i % 15} v{i}" + " pad" * (i % 4)) for i in range(1500)], "unit_id string, body string")
    index = R.index(units)
    assert {r["term"] for r in index.lexicon.filter("common").collect()} >= {"seg0", "nation0", "seg0 nation0"}
    asked = [f"acct{i} seg{i % 3} nation{i % 15}" for i in range(20)] + ["seg1 nation2", "seg0 nation0", "seg0", "nation3", "pad seg2 nation1"]
    queries = spark.createDataFrame(list(enumerate(asked)), "query_id long, text string")
    rows = lambda df: sorted((r["query_id"], r["first_rank"], r["unit_id"], round(r["sim"], 8)) for r in df.collect())
    assert rows(R.candidates(queries, index, 8)) == rows(R.candidates_all(queries, index, 8))


def test_stored_index_sends_no_rows_of_hot_terms(spark):
    """Terms of very many units are counted in place; counts, and lists deeper than a text's own rare units, are those of all postings."""
    from factlake.operators import retrieval as R

    units = spark.createDataFrame([(f"u{i}", f"acct{i // 70} seg{i % 3} nation{i % 15} v{i % 7}" + " pad" * (i % 4)) for i in range(600)] + [("none", None), ("empty", "")], "unit_id string, body string")
    count = lambda rows: sorted((r["unit_id"], r["term"], r["tf"]) for r in rows.collect())
    explode = "unit_id, inline(bag)"
    assert count(R.bags(units, "unit_id", "body").selectExpr(*explode.split(", "))) == count(R.terms(units, "unit_id", "body"))
    was, R.HOT = R.HOT, 40
    try:
        index = R.index(units, hold=lambda name, df, on: R.materialize(df, name))
    finally:
        R.HOT = was
    hot = {r["term"] for r in index.hot.collect()}
    assert {"seg0", "seg1", "seg2", "pad"} <= hot and not hot & {r["term"] for r in index.sent.collect()}
    plain = lambda i: {(r["term"], r["df"], r["common"]) for r in i.lexicon.collect()}
    assert plain(index) == plain(R.index(units))
    queries = spark.createDataFrame(list(enumerate([f"acct{i} seg{i % 3} nation{i % 15}" for i in range(6)] + ["seg1 nation2", "v3 pad"])), "query_id long, text string")
    rows = lambda df: sorted((r["query_id"], r["first_rank"], r["unit_id"], round(r["sim"], 8)) for r in df.collect())
    assert rows(R.candidates(queries, index, 8)) == rows(R.candidates_all(queries, index, 8))


def test_order_corpus_is_sent_once_for_all_its_queries(spark, sf):
    """One exchange of the units makes every kind of query, and the sources' trust starts no Python workers."""
    from factlake.sources import given as G

    units = G.order_units(spark, sf)
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    assert "Scan ExistingRDD" not in plan(units)
    stored = _stored(units)
    queries = G.order_queries(stored)
    assert plan(queries).count("Exchange hashpartitioning") == 1
    kinds = {r["kind"]: r["n"] for r in queries.groupBy("kind").count().withColumnRenamed("count", "n").collect()}
    assert set(kinds) == {"current", "time_point", "conflict"} and queries.count() == queries.select("query_id").distinct().count()
    assert sorted(map(tuple, G.order_queries(stored, ("current",)).collect())) == sorted(map(tuple, queries.filter("kind = 'current'").collect()))


def _stored(df):
    from factlake.sources.scratch import materialize

    return materialize(df, "test-units")


def test_forward_table_is_stored_beside_what_needs_no_forward_table(spark):
    """Texts are looked up while the forward table is still being stored; its failure is not lost."""
    import threading

    from factlake.operators import retrieval as R

    units = spark.createDataFrame([(f"u{i}", f"acct{i // 5} seg{i % 3} v{i}") for i in range(300)], "unit_id string, body string")
    go = threading.Event()

    def hold(name, df, on):
        if name == "forward":
            assert go.wait(300)
        return R.materialize(df, name)

    index = R.index(units, hold=hold)
    assert not index.made.done() and {r["term"] for r in index.lexicon.filter("common").collect()} >= {"seg0", "seg1", "seg2"}
    go.set()
    assert index.forward.count() == 300

    def broken(name, df, on):
        if name == "forward":
            raise ValueError("no room")
        return R.materialize(df, name)

    with pytest.raises(ValueError, match="no room"):
        R.index(units, hold=broken).forward


@pytest.mark.parametrize("scale", ["0.001", "0.01"])
def test_lsh_recall(spark, scale):
    assert base.QUERIES["cand_lsh_recall"](spark, f"/root/testdata/sf{scale}").first()["recall"] >= 0.9


def test_bayesian_search_needs_few_trials():
    from factlake.plans import evaluation as E

    goal = (0.5, 0.2, 0.0, 0.3)
    w, value, tried = E.tune_bayes(lambda ws: [-sum((a - b) ** 2 for a, b in zip(x, goal, strict=True)) for x in ws])
    assert value >= -0.021 and tried == 24, w


def test_the_rest_does_not_need_the_corpus_operators(tmp_path):
    """Without the folders of the corpus operators everything else imports and registers its queries."""
    import shutil
    import subprocess
    import sys
    from pathlib import Path

    root = Path(entry.__file__).parent
    shutil.copytree(root / "factlake", tmp_path / "factlake", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(root / "__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; assert len(e.queries()) > 200 and 'pipeline' not in e.queries(); import factlake.streaming.schedule, factlake.operators.maintenance"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, env={"PATH": "/usr/bin:/bin", "PYTHONPATH": str(tmp_path)}, check=True, timeout=120)


def test_tables_that_are_kept_have_as_many_parts_as_their_size_needs(spark, sf):
    """The order corpus is built in few buckets although the session has many shuffle partitions, whose number stays; both read the same rows."""
    from factlake.registry import ranking
    from factlake.sources import scratch

    other = spark.newSession()
    other.conf.set("spark.sql.shuffle.partitions", "150")
    key = str(scratch.fitted(other, sf, "orders").conf.get("spark.sql.shuffle.partitions"))
    assert int(key) == max(1, spark.sparkContext.defaultParallelism) and other.conf.get("spark.sql.shuffle.partitions") == "150"
    assert scratch.fitted(other, "/root/testdata/sf0.1", "orders", "lineitem").conf.get("spark.sql.shuffle.partitions") == "16"
    units = ranking.order_table(other, sf, 0.6)[0]
    assert len({f.rsplit("/", 1)[1] for f in units.inputFiles()}) <= 8
    assert units.sparkSession.conf.get("spark.sql.shuffle.partitions") == "150"
    assert sorted(r[0] for r in units.select("unit_id").collect()) == sorted(r[0] for r in ranking.order_table(spark, sf, 0.6)[0].select("unit_id").collect())


def test_winners_of_all_vectors_by_one_exchange(spark):
    """Ties go to similarity, then id; a missing score is the worst; queries without candidates have no answer; one exchange of the candidates."""
    from factlake.operators import retrieval as R
    from factlake.params import RANKERS
    from factlake.plans import evaluation as E

    rows = [(q, f"u{i}", "ACTIVE" if i % 2 else "DEPRECATED", i % 3 == 0, round(0.9 - i // 2 * 0.1, 1), None if (q, i) == ("q3", 1) else round(0.1 * (i * q_ % 4), 1), round(0.2 * (i % 3), 1), 0.1) for q_, q in enumerate(("q0", "q1", "q2", "q3")) for i in range(6)]
    scored = _stored(spark.createDataFrame(rows, "query_id string, unit_id string, status string, is_rumour boolean, sim double, temporal double, trust double, relational double"))
    queries = spark.createDataFrame([(f"q{i}", "current" if i % 2 else "conflict", f"u{i}") for i in range(6)], "query_id string, kind string, truth string")
    vectors = {n: (w, E.conf_column(n)) for n, w in RANKERS.items()}
    for r in E.winners(scored, {n: w for n, (w, _) in vectors.items()}).collect():
        for n in r["won"]:
            assert R.rank(scored, RANKERS[n]).filter(f"query_id = '{r['query_id']}'").first()["unit_id"] == r["unit_id"], (r, n)
    got = {r["ranker"]: r.asDict() for r in E.compare(scored, queries, vectors, "ranker").collect()}
    for n, (w, conf) in vectors.items():
        j = E.judged(R.rank(scored, w), queries, conf)
        want = E.summary(j).first().asDict() | E.ece(j).first().asDict()
        assert {k: got[n][k] for k in want} == pytest.approx(want), n
    plan = E.winners(scored, {n: w for n, (w, _) in vectors.items()})._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1 and "Aggregate" not in plan


def test_sweep_of_rates_makes_one_index(spark, sf, duck, monkeypatch):
    """All rates share units, index and candidates, each with its own weights; the rows are those of SQL."""
    from factlake.operators import retrieval as R

    made, real = [], R.index
    monkeypatch.setattr(R, "index", lambda *a, **k: made.append(a) or real(*a, **k))
    got = base.QUERIES["eval_sweep_orders"](spark, sf)
    cur = duck.execute(base.ORACLES["eval_sweep_orders"])
    cols = [c[0] for c in cur.description]
    want = sorted(tuple(plain(v) for v in r) for r in cur.fetchall())
    assert sorted(tuple(plain(r[c]) for c in cols) for r in got.collect()) == want
    assert len(made) <= 1


@pytest.mark.parametrize("rare, hot, unroll", [(64, 20000, 8), (5, 20, 8), (5, 20000, 2), (10**6, 20000, 8)])
def test_candidates_of_worlds_are_those_of_each_world(spark, monkeypatch, rare, hot, unroll):
    """Units in some of three worlds; terms and texts that a world doesn't know; the same lists as by every posting of that world."""
    import random

    from factlake.operators import retrieval as R

    for name, value in (("RARE", rare), ("HOT", hot), ("UNROLL", unroll), ("DEEP", 4)):
        monkeypatch.setattr(R, name, value)
    rnd = random.Random(5)
    word = lambda: rnd.choice("red blue green hot cold".split()) if rnd.random() < 0.6 else f"w{rnd.randint(0, 120)}"
    rows = [(f"u{i}", " ".join(word() for _ in range(rnd.randint(1, 5))), rnd.choice([7, 7, 7, 6, 4, 1])) for i in range(900)]
    rows += [(f"only{i}", "odd couple", 4) for i in range(80)] + [("empty", "", 7), ("none", None, 2)]
    units = _stored(spark.createDataFrame(rows, "unit_id string, body string, worlds int"))
    asked = [" ".join(word() for _ in range(rnd.randint(1, 4))) for _ in range(80)] + ["red blue", "red blue", "odd couple", "odd red", "unknown", "", "hot"]
    queries = spark.createDataFrame(list(enumerate(asked)), "query_id long, text string")
    index = R.index(units, hold=lambda name, df, on: R.materialize(df, name), worlds=3)
    got = R.candidates(queries, index, 8).collect()
    for i in range(3):
        own = units.filter(f"worlds & {1 << i} <> 0")
        want = sorted((r["query_id"], r["first_rank"], r["unit_id"], round(r["sim"], 8)) for r in R.candidates_all(queries, R.index(own), 8).collect())
        assert sorted((r["query_id"], r[f"first_rank_{i}"], r["unit_id"], round(r[f"sim_{i}"], 8)) for r in got if r[f"sim_{i}"] is not None) == want
