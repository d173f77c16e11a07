"""Worked examples and invariants of the formulas."""

import pytest
from pyspark.sql import functions as F

from factlake.functions import signals as S
from factlake.operators import lifecycle as L
from factlake.operators import maintenance as M
from factlake.operators import updates as U
from factlake.params import RANKERS, Params, Weights, grid
from factlake.plans import evaluation as E


def value(spark, col):
    return spark.range(1).select(col.alias("v")).first()["v"]


def test_decay_trajectory(spark):
    rows = {r["day"]: r["trust"] for r in S.trajectory(spark, 0.85, [30, 60, 75, 76, 90, 180]).collect()}
    assert rows[30] == pytest.approx(0.425) and rows[60] == pytest.approx(0.2125) and rows[90] == pytest.approx(0.10625) and rows[180] == pytest.approx(0.01328, abs=1e-5)
    assert rows[75] > 0.15 > rows[76]


def test_clip_and_access(spark):
    one = lambda v, p, n: value(spark, S.after_feedback(F.lit(v), F.lit(p), F.lit(n)))
    assert one(0.5, 0, 20) == 0.01 and one(0.5, 40, 0) == 1.0
    assert [round(value(spark, S.after_access(F.lit(0.5), F.lit(n))), 5) for n in (0, 5, 10**6)] == [0.5, 0.51792, 0.63816]


def test_bonus(spark):
    got = [round(value(spark, S.bonus(F.lit(n))), 5) for n in (0, 1, 2, 19, 20)]
    assert got == [0.0, 0.06931, 0.10986, 0.29957, 0.3]


def test_mix(spark):
    f = lambda *x: value(spark, S.final(*map(F.lit, x), RANKERS["m4"]))
    assert f(0.5, 0.891, 0.267, 0.0) == pytest.approx(0.4645, abs=1e-4)
    # the block's printed score leaves the relational term out
    assert f(0.625, 1.0, 0.90, 0.069) == pytest.approx(0.7041, abs=1e-3)
    assert f(1.0, 1.0, 1.0, 0.3) == pytest.approx(0.895)


@pytest.mark.parametrize(("at", "inside"), [("2020-01-01", False), ("2020-02-01", True), ("2020-02-15", True), ("2020-03-01", True), ("2020-03-02", False)])
def test_window_is_closed(spark, at, inside):
    ts = lambda x: F.lit(x).cast("timestamp_ntz")
    got = value(spark, S.temporal(ts("2020-02-01"), ts("2020-02-01"), ts("2020-03-01"), ts(at)))
    assert (got != 0.05) == inside
    assert value(spark, S.in_window(F.lit(None).cast("timestamp_ntz"), F.lit(None).cast("timestamp_ntz"), ts(at)))


def test_floor_crossing(spark):
    assert value(spark, S.floor_crossing(F.lit(30.0))) == pytest.approx(129.66, abs=0.01)


def test_weights():
    assert len(grid()) == 286 and all(abs(sum(w) - 1) < 1e-9 for w in grid())
    assert [round(x, 4) for x in RANKERS["m4"].without("tru").as_tuple()] == [0.4667, 0.3333, 0.0, 0.2]
    with pytest.raises(ValueError):
        Weights(0.5, 0.6)


def edges(spark, *pairs):
    return spark.createDataFrame(list(pairs), "src string, dst string")


def hits(spark, graph, *seeds, **how):
    m = M.ripple(spark.createDataFrame([(s,) for s in seeds], "unit_id string"), edges(spark, *graph), **how)
    return {(r["seed"], r["unit_id"]): r["penalty"] for r in m.collect()}


def test_ripple_chain_diamond_cycle(spark):
    assert hits(spark, [("B", "A"), ("C", "B"), ("D", "C")], "A") == {("A", "B"): pytest.approx(0.15), ("A", "C"): pytest.approx(0.075)}
    assert hits(spark, [("B", "A"), ("C", "A"), ("D", "B"), ("D", "C")], "A")["A", "D"] == pytest.approx(0.075)
    assert hits(spark, [("B", "A"), ("A", "B")], "A") == {("A", "B"): pytest.approx(0.15), ("A", "A"): pytest.approx(0.075)}
    assert hits(spark, [("B", "A"), ("A", "B")], "A", hit_seed=False) == {("A", "B"): pytest.approx(0.15)}


def test_ripple_sums_over_seeds_with_floor(spark):
    units = spark.createDataFrame([("A", 0.5), ("B", 0.5), ("C", 0.5), ("D", 0.2)], "unit_id string, prior_trust double")
    m = M.ripple(spark.createDataFrame([("A",), ("B",)], "unit_id string"), edges(spark, ("C", "A"), ("C", "B"), ("C", "A"), ("D", "A"), ("D", "B")))
    got = {r["unit_id"]: r["prior_trust"] for r in M.apply_ripple(units, m).collect()}
    assert got["C"] == pytest.approx(0.2) and got["D"] == pytest.approx(0.01) and got["A"] == 0.5


def test_ripple_equals_queue(spark, sf):
    """Breadth-first with a queue, seed by seed, on the part graph."""
    from collections import deque

    from factlake.sources import given as G

    e = [(r["src"], r["dst"]) for r in G.part_graph(spark, sf).collect()]
    dependents = {}
    for s, t in e:
        dependents.setdefault(t, set()).add(s)
    seeds = sorted({t for _, t in e})[:3]
    want = {}
    for seed in seeds:
        queue, seen = deque([(seed, 0)]), set()
        while queue:
            x, d = queue.popleft()
            for y in sorted(dependents.get(x, ())):
                if y not in seen and d < 2:
                    seen.add(y)
                    want[seed, y] = 0.15 / (d + 1)
                    queue.append((y, d + 1))
    got = M.ripple(spark.createDataFrame([(s,) for s in seeds], "unit_id string"), G.part_graph(spark, sf))
    assert {(r["seed"], r["unit_id"]): r["penalty"] for r in got.collect()} == pytest.approx(want)


def test_version_trio(spark):
    rows = spark.createDataFrame([(f"v{i}", 1, 0, i) for i in (1, 2, 3)], "unit_id string, doc_id int, chunk_no int, version_no int")
    got = {r["unit_id"]: (r["status"], r["replaces"], r["replaced_by"]) for r in L.encode(rows).collect()}
    assert got == {"v1": ("DEPRECATED", None, "v2"), "v2": ("DEPRECATED", "v1", "v3"), "v3": ("UNCONSOLIDATED", "v2", None)}


@pytest.mark.parametrize(
    ("hunk", "owner", "strict"),
    [((12, 14), [1], [1]), ((8, 12), [0, 1], [0, 1]), ((10, 10), [0], []), ((30, 30), [2], []), ((0, 0), [0], []), ((10, 20), [1], [1])],
)
def test_affected(spark, hunk, owner, strict):
    chunks = spark.createDataFrame([(1, i, 10 * i, 10 * i + 10) for i in range(3)], "doc_id int, chunk_no int, span_start int, span_end int")
    hunks = spark.createDataFrame([(1, *hunk)], "doc_id int, old_start int, old_end int")
    assert sorted(r["chunk_no"] for r in U.affected(chunks, hunks).collect()) == owner
    assert sorted(r["chunk_no"] for r in U.affected(chunks, hunks, "strict").collect()) == strict


@pytest.mark.parametrize("new", ["abcdefghijklmnopqrstuvwxyz", "Xabcdefghijklmnopqrstuvwxyz", "abcdefghijklmnopqrstuvwxyzX", "abcdefghijXklmnopqrstuvwxyz", "abcuvwxyz", "", "aXXcdefghijklmnopqrstYYYuvwxyz", "éèabcdefghijklmnopqrstuvwxyz"])
def test_splice_rebuilds(spark, new):
    docs = spark.createDataFrame([(1, "abcdefghijklmnopqrstuvwxyz", new)], "doc_id long, old string, new string")
    chunks = L.chunk(docs.select("doc_id", F.col("old").alias("text")), 10)
    for diff in (U.diff_trim, U.diff_tokens):
        assert U.rebuild(U.splice(chunks, diff(docs), docs)).first()["text"] == new


def test_ece(spark):
    j = spark.createDataFrame([(0.95, 1.0), (0.95, 0.0), (0.15, 0.0), (0.15, 0.0)], "conf double, right double")
    assert E.ece(j).first()["ece"] == pytest.approx(0.30)


def test_cost(spark):
    units = spark.createDataFrame([(1,)] * 5, "doc_id int")
    one = spark.createDataFrame([(1,)], "doc_id int")
    r = U.update_cost(units, one, one).first()
    assert (r["plain"], r["ours"]) == (5, 1)


def test_trust_bounds(spark):
    p = Params()
    rows = spark.range(2000).select((F.rand(1)).alias("b"), (F.rand(2) * 400).alias("age"), (F.rand(3) * 50).cast("int").alias("p"), (F.rand(4) * 50).cast("int").alias("n"), (F.rand(5) * 1e6).cast("long").alias("a"))
    t = S.after_access(S.after_feedback(S.decayed(F.col("b"), F.col("age")), F.col("p"), F.col("n")), F.col("a"), p)
    r = rows.agg(F.min(t).alias("lo"), F.max(t).alias("hi")).first()
    assert r["lo"] >= 0.01 and r["hi"] <= 1.0


def test_sequential_tuning():
    best, score = E.tune_sequential(lambda w: -abs(w.sim - 0.6) - abs(w.tmp - 0.2) - w.tru)
    assert best.sim == pytest.approx(0.6, abs=0.051) and best.tru == pytest.approx(0.0, abs=0.051) and score > -0.2
