"""First-stage candidates and rankers."""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import Future
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from factlake.functions import signals as S
from factlake.functions.worlds import inside, worlds_of
from factlake.params import Params, Weights
from factlake.sources.scratch import later, materialize

TOKEN = r"([\p{L}0-9]+)"
RARE, DEEP, QUERY_BLOCK = 64, 16, 1024
SLOTS, HOT, UNROLL, FEW, STEPS = 65536, 20000, 8, 1000, 1024


def _words(df: DataFrame, key: str, text: str, *more: str) -> DataFrame:
    """key, w: words, and pairs of neighbouring words."""
    w = df.select(key, *more, F.regexp_extract_all(F.lower(text), F.lit(TOKEN), F.lit(1)).alias("w"))
    pairs = F.when(F.size("w") > 1, F.expr("transform(sequence(1, size(w) - 1), i -> concat(w[i - 1], ' ', w[i]))")).otherwise(F.array().cast("array<string>"))
    return w.select(key, *more, F.concat("w", pairs).alias("w"))


def terms(df: DataFrame, key: str, text: str) -> DataFrame:
    """key, term, tf: words and pairs of neighbouring words."""
    return _words(df, key, text).select(key, F.explode("w").alias("term")).groupBy(key, "term").agg(F.count("*").alias("tf"))


def bags(df: DataFrame, key: str, text: str, *more: str) -> DataFrame:
    """key, bag: the same terms as an array of (term, tf) in every row, without moving rows; keys are unique. ``more`` columns stay.

    Only texts that repeat a term are sorted (s) to count it.
    """
    entry = lambda term, tf: F.struct(term.alias("term"), tf.cast("long").alias("tf"))
    w = _words(df, key, text, *more).select(key, *more, "w", F.array_distinct("w").alias("once"))
    w = w.select(key, *more, "w", F.when(F.size("w") > F.size("once"), F.sort_array("w")).alias("s"))
    first = F.filter(F.sequence(F.lit(0), F.size("s") - 1), lambda i: ~F.get("s", i).eqNullSafe(F.get("s", i - 1)))
    w = w.select(key, *more, "w", "s", F.when(F.col("s").isNotNull(), first).alias("p"))
    counted = F.transform("p", lambda i, j: entry(F.get("s", i), F.coalesce(F.get("p", j + 1), F.size("s")) - i))
    single = F.transform(F.coalesce("w", F.array().cast("array<string>")), lambda x: entry(x, F.lit(1)))
    return w.select(key, *more, F.when(F.col("s").isNotNull(), counted).otherwise(single).alias("bag"))


@dataclass
class Index:
    """made (the forward table, or its making in the background): unit_id, norm, terms: term to tf; sent (term, unit_id, df, head: one row a term; at least the terms of up to RARE units), hot (term, df: all other terms, if any) and total (n: the number of units). A term's weight in a unit is tf * idf / norm.

    With ``worlds``, every unit says which of them it is in (worlds: a bit for each), and norm, df and n have a column for each (norm_0, ...); df and n are those of all units.
    """

    made: DataFrame | Future
    sent: DataFrame
    hot: DataFrame | None
    total: DataFrame
    worlds: int = 0

    @property
    def forward(self) -> DataFrame:
        return self.made.result() if isinstance(self.made, Future) else self.made

    def look_up(self, df: DataFrame | None = None) -> DataFrame:
        """Rows of terms that the index knows (all its terms, if none are given), with df, idf and whether they are common."""
        on = lambda t: t if df is None else df.join(t, "term")
        ends = worlds_of(self.worlds)
        rows = on(self.sent.filter("head").select("term", *dict.fromkeys(["df", *(f"df{s}" for s in ends)])))
        if self.hot is not None:
            rows = rows.unionByName(on(F.broadcast(self.hot)))
        return rows.crossJoin(F.broadcast(self.total)).withColumns({**{f"idf{s}": _idf(s) for s in ends}, "common": F.col("df") > RARE}).drop(*self.total.columns)

    @property
    def lexicon(self) -> DataFrame:
        """term, df, idf and common."""
        return self.look_up()

    @property
    def postings(self) -> DataFrame:
        """term, tf, unit_id and its norm, of all terms."""
        return self.forward.select("unit_id", F.col("norm").alias("unorm"), F.explode("terms").alias("term", "tf"))

    def only(self, units: DataFrame) -> Index:
        """The index of some units (unit_id), with the weights that terms have in all."""
        return Index(self.forward.join(units.select("unit_id"), "unit_id", "left_semi"), self.sent, self.hot, self.total, self.worlds)


def _idf(s: str = "") -> Column:
    """Of a world's columns; a term that no unit of the world has weighs nothing there."""
    idf = F.log((1.0 + F.col(f"n{s}")) / (1.0 + F.col(f"df{s}"))) + 1.0
    return F.when(F.col(f"df{s}") > 0, idf).otherwise(0.0) if s else idf


def index(units: DataFrame, text: str = "body", hold: Callable[[str, DataFrame, str | None], DataFrame] | None = None, worlds: int = 0) -> Index:
    """Tf-idf weights over the units' norms, of every term; ``hold`` (name, table, column to join on) stores the tables of a large index.

    There, the few terms of very many units (at most HOT terms) are counted where their rows lie and broadcast;
    only the others' rows are sent to their term to be counted. Which terms may be so frequent is seen by counting
    hash values first, so nothing is estimated. Terms in more than RARE units are marked common. The forward
    table is stored in the background, as texts can be looked up without it. ``worlds``: so many worlds of units
    (worlds: a bit for each that a unit is in) get their own weights from one pass over all units.
    """
    ends, more = worlds_of(worlds), ["worlds"][: bool(worlds)]
    own = ends if worlds else []
    n = units.agg(F.count("*").alias("n"), *(F.count_if(inside(s)).alias(f"n{s}") for s in own))
    bag, hot = bags(units, "unit_id", text, *more), None
    if hold:
        bag = hold("bags", bag, "unit_id")
    each = cold = bag.select("unit_id", *more, F.explode("bag").alias("e")).select("unit_id", *more, "e.term", "e.tf")
    if hold:
        slot = F.pmod(F.xxhash64("term"), F.lit(SLOTS)).alias("slot")
        slots = each.groupBy(slot).agg(F.count("*").alias("c")).withColumn("most", F.greatest(F.lit(float(RARE)), F.sum("c").over(Window.partitionBy(F.lit(0))) / HOT))
        slots = slots.filter("c > most").select("slot", "most")
        many = each.select("term", *more, slot).join(F.broadcast(slots), "slot").groupBy("term").agg(F.count("*").alias("df"), *(F.count_if(inside(s)).alias(f"df{s}") for s in own), F.first("most").alias("most"))
        hot = hold("hot", many.filter("df > most").drop("most"), None)
        cold = each.join(F.broadcast(hot), "term", "left_anti")
    cold = cold.repartition("term").withColumn("h", F.xxhash64("term"))
    w = Window.partitionBy("h", "term")  # a number sorts faster than terms that begin alike
    cold = cold.select("term", "unit_id", "tf", F.count("*").over(w).alias("df"), *(F.count_if(inside(s)).over(w).alias(f"df{s}") for s in own), (F.row_number().over(w.orderBy("term")) == 1).alias("head"))
    cold = hold("postings", cold, "term") if hold else cold
    x = lambda df: df.crossJoin(F.broadcast(n)).select("unit_id", *((F.col("tf") * _idf(s)).alias(f"x{s}") for s in ends))
    norms = (x(cold).unionByName(x(each.join(F.broadcast(hot), "term"))) if hold else x(cold)).groupBy("unit_id").agg(*map(_norm, ends))
    forward = bag.join(norms, "unit_id").select("unit_id", *more, *(f"norm{s}" for s in ends), F.map_from_entries("bag").alias("terms"))
    return Index(later(units.sparkSession, lambda: hold("forward", forward, "unit_id")) if hold else forward, cold, hot, n, worlds)


def _asked(queries: DataFrame, text: str) -> tuple[DataFrame, DataFrame]:
    """(query_id, tid), and tid and bag of every distinct text."""
    q = queries.select("query_id", F.col(text).alias("text"), F.md5(F.coalesce(F.col(text), F.lit(""))).alias("tid"))
    each = q.select("tid", "text").repartition(4 * queries.sparkSession.sparkContext.defaultParallelism, "tid").distinct()
    return q.select("query_id", "tid"), bags(each, "tid", "text")


def _known(asked: DataFrame, index: Index) -> DataFrame:
    """tid, term, x, idf, df, common of the texts' terms that the index knows; x and idf in each of its worlds."""
    t, ends = index.look_up(asked.select("tid", F.explode("bag").alias("e")).select("tid", "e.*")), worlds_of(index.worlds)
    return t.select("tid", "term", *((F.col("tf") * F.col(f"idf{s}")).alias(f"x{s}") for s in ends), *(f"idf{s}" for s in ends), "df", "common")


def _norm(s: str = "") -> Column:
    """Null in a world that knows none of the terms."""
    norm = F.sqrt(F.sum(F.col(f"x{s}") * F.col(f"x{s}")))
    return (F.nullif(norm, F.lit(0.0)) if s else norm).alias(f"norm{s}")


def candidates_all(queries: DataFrame, index: Index, k: int = 8, text: str = "text") -> DataFrame:
    """query_id, unit_id, sim and first_rank of the k most similar units, by every posting of every term."""
    ids, asked = _asked(queries, text)
    t = _known(asked, index)
    each = t.join(t.groupBy("tid").agg(_norm()), "tid").join(index.postings, "term")
    sim = each.groupBy("tid", "unit_id").agg(F.round(F.sum(F.col("x") / F.col("norm") * (F.col("tf") * F.col("idf") / F.col("unorm"))), 9).alias("sim"))
    return ids.join(best(sim, [F.desc("sim"), F.asc("unit_id")], k, "first_rank", "tid"), "tid").drop("tid")


def _total(c: str | Column, f: Callable[[Column], Column], most: int | None = None) -> Column:
    """The sum of f over an array; written out, which is compiled, if no array has over ``most`` (at most UNROLL) entries."""
    if most is None or most > UNROLL:
        return F.aggregate(c, F.lit(0.0), lambda s, e: s + f(e))
    return reduce(lambda s, i: s + F.coalesce(f(F.get(c, F.lit(i))), F.lit(0.0)), range(most), F.lit(0.0))


def _weight(e: Column) -> Column:
    """Of a text's term in the unit of the same row."""
    return F.coalesce(F.col("terms")[e["term"]], F.lit(0)) * e["idf"] / F.col("unorm")


def candidates(queries: DataFrame, index: Index, k: int = 8, text: str = "text") -> DataFrame:
    """The same result without the postings of common terms for every text.

    Equal texts are asked once. A text's rare terms bring in units, which are scored in full from the
    forward table. A unit without any of them scores by the common terms alone, at most the length of their
    part of the text's vector, as a unit's vector has length 1; a text whose k-th best beats that bound is
    done. Else, as texts with the same common terms order such units alike, one list of the best units for
    each set of common terms serves all its texts. 2 k entries are deep enough: at most k of them are among
    the text's own best, and an entry that rare terms brought in without its being among them is no better
    by its common terms, nor is what follows it. DEEP more stand for sums that differ by rounding.

    With an index of several worlds, every world's k best, in one row for a unit that is among those of any:
    sim_0, first_rank_0 and so on, null where it is not among that world's.
    """
    ends = worlds_of(index.worlds)
    each = lambda f: [f(s) for s in ends]
    ids, asked = _asked(queries, text)
    t = _known(materialize(asked, "asked-bags"), index)
    asked = t.repartition("tid").groupBy("tid").agg(*each(_norm), F.sort_array(F.collect_list(F.struct(*[c for c in t.columns if c != "tid"]))).alias("t"))
    common = F.filter("t", lambda e: e["common"])
    gid = F.when(F.size(common) > 0, F.md5(F.to_json(F.transform(common, lambda e: F.struct(e["term"], *each(lambda s: e[f"x{s}"]))))))
    bound = lambda s: F.sqrt(_total(common, lambda e: e[f"x{s}"] * e[f"x{s}"])).alias(f"bound{s}")
    asked = materialize(asked.select("tid", *each(lambda s: f"norm{s}"), "t", gid.alias("gid"), *each(bound)), "asked", narrow=True)
    longest = asked.agg(F.max(F.size("t"))).first()[0] or 0
    forward = index.forward.withColumnsRenamed({f"norm{s}": f"unorm{s}" for s in ends})
    none = F.array().cast(f"array<struct<less:double,unit_id:{forward.schema['unit_id'].dataType.simpleString()}>>")
    own = asked.select("tid", F.explode(F.filter("t", lambda e: ~e["common"])["term"]).alias("term"))
    pairs = own.join(index.sent.select("term", "unit_id"), "term").select("tid", "unit_id").repartition("unit_id").distinct()
    pairs = _similar(pairs.join(forward, "unit_id"), asked, ends, longest)
    best_ = lambda s: F.slice(F.sort_array(F.collect_list(F.when(F.col(f"less{s}").isNotNull(), F.struct(F.col(f"less{s}").alias("less"), "unit_id")))), 1, k).alias(f"near{s}")
    near = pairs.repartition("tid").groupBy("tid").agg(*each(best_))
    kth = lambda s: -F.get(f"near{s}", F.lit(k - 1))["less"]
    enough = lambda s: F.col("gid").isNull() | F.coalesce(kth(s) > F.round(F.col(f"bound{s}") / F.col(f"norm{s}"), 9) + 1e-9, F.lit(False))
    near = asked.join(near, "tid", "left").select("tid", *each(lambda s: f"norm{s}"), "t", "gid", *each(lambda s: F.coalesce(f"near{s}", none).alias(f"near{s}")), *each(lambda s: enough(s).alias(f"enough{s}")))
    near = materialize(near, "rare-candidates", narrow=True)
    sets = near.filter(~reduce(Column.__and__, each(lambda s: F.col(f"enough{s}")))).groupBy("gid").agg(F.first(common).alias("t"), *each(lambda s: F.bool_or(~F.col(f"enough{s}")).alias(f"open{s}")))
    of = lambda s: F.transform("t", lambda e: F.struct(e["term"], e[f"x{s}"].alias("x"), e[f"idf{s}"].alias("idf"), e["df"]))
    sets = sets.select("gid", F.explode(F.array_compact(F.array(*each(lambda s: F.when(F.col(f"open{s}"), F.struct(F.lit(ends.index(s)).alias("world"), of(s).alias("t"))))))).alias("e")).select("gid", "e.*")
    lists = _group_lists(sets, forward, 2 * k + DEEP, longest, ends)
    lists = lists.groupBy("gid").agg(*each(lambda s: F.first(F.when(F.col("world") == ends.index(s), F.col("list")), True).alias(f"list{s}")))
    found = near.withColumn("gid", F.when(~reduce(Column.__and__, each(lambda s: F.col(f"enough{s}"))), F.col("gid"))).join(lists, "gid", "left")
    less = lambda e, s: F.struct((-F.round(e["dot"] / F.col(f"norm{s}"), 9)).alias("less"), e["unit_id"].alias("unit_id"))
    listed = lambda s: F.transform(F.filter(F.when(~F.col(f"enough{s}"), F.col(f"list{s}")), lambda e: ~F.array_contains(F.col(f"near{s}.unit_id"), e["unit_id"])), lambda e: less(e, s))
    found = found.select("tid", *each(lambda s: F.slice(F.sort_array(F.concat(f"near{s}", F.coalesce(listed(s), none))), 1, k).alias(f"near{s}")))
    if not index.worlds:
        found = ids.join(found, "tid").select("query_id", F.posexplode("near").alias("at", "e"))
        return found.select("query_id", "e.unit_id", (-F.col("e.less")).alias("sim"), (F.col("at") + 1).cast("long").alias("first_rank"))
    found = found.withColumn("unit_id", F.explode(F.array_distinct(F.concat(*each(lambda s: F.col(f"near{s}.unit_id"))))))
    found = found.select("tid", "unit_id", *each(lambda s: F.col(f"near{s}.less").alias(f"less{s}")), *each(lambda s: F.nullif(F.array_position(F.col(f"near{s}.unit_id"), F.col("unit_id")), F.lit(0)).alias(f"first_rank{s}")))
    found = found.select("tid", "unit_id", *each(lambda s: (-F.get(f"less{s}", (F.col(f"first_rank{s}") - 1).cast("int"))).alias(f"sim{s}")), *each(lambda s: f"first_rank{s}"))
    return ids.join(found, "tid").drop("tid")


def _similar(pairs: DataFrame, asked: DataFrame, ends: list[str], longest: int) -> DataFrame:
    """tid, unit_id and less: the similarity (in each world that the unit is in), times -1, of pairs that carry their unit's row."""
    if ends == [""]:
        sim = F.round(_total("t", lambda e: e["x"] / F.col("norm") * _weight(e), longest), 9)
        return pairs.join(asked.select("tid", "norm", "t"), "tid").select("tid", "unit_id", (-sim).alias("less"))
    z = lambda s: F.transform("t", lambda e: e[f"x{s}"] / F.col(f"norm{s}") * e[f"idf{s}"]).alias(f"z{s}")
    rows = _products(pairs.join(asked.select("tid", F.col("t.term").alias("words"), *map(z, ends)), "tid"), ends, longest, "tid", "unit_id")
    return rows.select("tid", "unit_id", *((-F.round(f"dot{s}", 9)).alias(f"less{s}") for s in ends))


def _products(rows: DataFrame, ends: list[str], longest: int, *keep: str) -> DataFrame:
    """``keep`` and dot_0, ...: in each world that the unit of a row is in, the product of its weights (terms, unorm_0, ...) with a vector over words (z_0, ...), if there is one.

    The unit's counts of the words (m) are looked up once for all worlds; an array written out would be put in place of every use.
    """
    few = longest <= UNROLL
    m = F.transform("words", lambda term: F.coalesce(F.col("terms")[term], F.lit(0)))
    dot = lambda s: reduce(lambda a, i: a + F.coalesce(F.get(f"z{s}", F.lit(i)) * F.get("m", F.lit(i)), F.lit(0.0)), range(longest), F.lit(0.0)) if few else _total(F.arrays_zip(f"z{s}", "m"), lambda e: e[f"z{s}"] * e["m"])
    rows = rows.select(*keep, "worlds", *(f"z{s}" for s in ends), *(f"unorm{s}" for s in ends), m.alias("m"))
    return rows.select(*keep, *(F.when(inside(s) & F.col(f"z{s}").isNotNull(), dot(s) / F.col(f"unorm{s}")).alias(f"dot{s}") for s in ends))


def _kept_terms(wanted: DataFrame) -> Column:
    """A unit's terms without those that are not in ``wanted`` (term), if these are few enough to be written into the plan; else all."""
    few = [r[0] for r in wanted.select("term").distinct().limit(FEW + 1).collect()]
    return F.col("terms") if len(few) > FEW else F.map_filter("terms", lambda term, _: term.isin(few))


def _group_lists(groups: DataFrame, forward: DataFrame, most: int, longest: int, ends: list[str]) -> DataFrame:
    """gid, world, list: the ``most`` best units (unit_id, dot) of a world for each set (at most ``longest``) of terms (gid, world, t), exactly.

    Units that hold a set's rarest term are scored in full. If the last of these lists beats what the other
    terms' largest weights could add up to, no unit without the rarest term has a place; else the set goes
    by all its postings.
    """
    order = [F.desc(F.round("dot", 10)), F.asc("unit_id")]
    rarest = F.array_min(F.transform("t", lambda e: F.struct(e["df"], e["term"])))["term"]
    groups = materialize(groups.select("gid", "world", "t", rarest.alias("term"), F.monotonically_increasing_id().alias("g")), "groups", narrow=True)
    listed = lambda df: df.groupBy("g").agg(F.collect_list(F.struct("unit_id", "dot")).alias("list")).join(groups.select("g", "gid", "world"), "g").select("gid", "world", "list")
    about = [c for c in forward.columns if c != "terms"]
    holding = lambda wanted: forward.select(*about, "terms", F.explode(F.map_keys(_kept_terms(wanted))).alias("term"))
    met = lambda units, sets, on: _in_world(units.join(sets, on), ends)
    if ends == [""]:
        scored = holding(groups).join(groups, "term").select("g", "unit_id", _total("t", lambda e: e["x"] * _weight(e), longest).alias("dot"))
    else:
        scored = _scored_in_worlds(holding(groups), groups, ends, most)
    heads = materialize(best(scored, order, most, "nth", "g"), "group-heads", narrow=True)  # numbers sort faster than the sets' hashes
    last = heads.groupBy("g").agg(F.when(F.count("*") >= most, F.min(F.round("dot", 10))).alias("last"))
    others = groups.select("g", "world", F.explode(F.filter("t", lambda e: e["term"] != F.col("term"))).alias("e")).select("g", "world", "e.term", "e.x", "e.idf")
    tops = met(forward.select(*about, F.explode(_kept_terms(others)).alias("term", "tf")), others.select("world", "term", "idf").distinct(), "term").groupBy("world", "term").agg(F.max(F.col("tf") * F.col("idf") / F.col("unorm")).alias("top"))
    rest = others.join(tops, ["world", "term"]).groupBy("g").agg(F.sum(F.col("x") * F.col("top")).alias("rest"))
    settled = (F.size("t") == 1) | F.coalesce(F.col("last") > F.round("rest", 10) + 1e-9, F.lit(False))
    left = materialize(groups.join(last, "g", "left").join(rest, "g", "left").filter(~settled).select("g", "world", "t"), "groups-left", narrow=True)
    if not left.limit(1).count():
        return listed(heads)
    by = left.select("g", "world", F.explode("t").alias("e")).select("g", "world", "e.term", "e.x", "e.idf")
    by = met(holding(by).select(*about, "term", F.col("terms")[F.col("term")].alias("tf")), by, "term")
    full = best(by.groupBy("g", "unit_id").agg(F.sum(F.col("x") * (F.col("tf") * F.col("idf") / F.col("unorm"))).alias("dot")), order, most, "nth", "g")
    return listed(heads.join(left.select("g"), "g", "left_anti").unionByName(full))


def _scored_in_worlds(units: DataFrame, groups: DataFrame, ends: list[str], most: int) -> DataFrame:
    """g, unit_id, dot of units with their sets' rarest terms, but for those that are surely not among a set's ``most`` best.

    A set has as many rows as worlds have units, too many to be sorted for so short lists. So units that hold all terms
    of a set are counted by steps of dot first; where ``most`` of them reach a step, rows of any unit below it are left
    out, with room for dots that are equal when rounded.
    """
    of = lambda i, c: F.when(F.col("world") == i, c)
    wide = groups.groupBy("gid", "term").agg(
        F.first(F.col("t.term")).alias("words"), *(F.first(of(i, F.transform("t", lambda e: e["x"] * e["idf"])), True).alias(f"z{s}") for i, s in enumerate(ends)), *(F.max(of(i, F.col("g"))).alias(f"g{s}") for i, s in enumerate(ends)),
    )
    longest = groups.agg(F.max(F.size("t"))).first()[0] or 0

    def dots(met):
        rows = _products(met, ends, longest, "unit_id", *(f"g{s}" for s in ends))
        rows = rows.select("unit_id", F.explode(F.array(*(F.struct(F.col(f"g{s}").alias("g"), F.col(f"dot{s}").alias("dot")) for s in ends))).alias("e"))
        return rows.select("e.g", "unit_id", "e.dot").filter("dot IS NOT NULL")

    met = units.join(wide, "term")
    step = F.floor(F.col("dot") * STEPS)
    counts = dots(met.filter(F.size(F.array_except("words", F.map_keys("terms"))) == 0)).groupBy("g", step.alias("step")).agg(F.count("*").alias("c"))
    above = Window.partitionBy("g").orderBy(F.desc("step")).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    full = counts.select("g", "step", (F.sum("c").over(above) >= most).alias("full"))
    least = materialize(full.filter("full").groupBy("g").agg(F.max("step").alias("least")), "group-least", narrow=True)
    return dots(met).join(least, "g", "left").filter(F.col("least").isNull() | (F.col("dot") >= F.col("least") / float(STEPS) - 1e-9)).select("g", "unit_id", "dot")


def _in_world(rows: DataFrame, ends: list[str]) -> DataFrame:
    """Rows whose unit is in their ``world``, with the unit's norm there (unorm)."""
    if ends == [""]:
        return rows
    return rows.withColumn("unorm", F.coalesce(*(F.when((F.col("world") == i) & inside(i), F.col(f"unorm{s}")) for i, s in enumerate(ends)))).filter("unorm IS NOT NULL")


def best(df: DataFrame, order: list[Column], k: int, name: str = "rank", by: str = "query_id") -> DataFrame:
    w = Window.partitionBy(by).orderBy(*order)
    return df.withColumn(name, F.row_number().over(w).cast("long")).filter(F.col(name) <= k)


def candidates_dense(queries: DataFrame, units: DataFrame, k: int = 8, dims: int | None = None, keep_self: bool = False) -> DataFrame:
    """Exact cosine neighbours; ``dims`` compares prefixes of the vectors only.

    Queries are packed into blocks of QUERY_BLOCK and dealt to every group of units; a task holds one
    block and one batch of units and sends its k best a query, so neither side has a bound.
    """
    spark = units.sparkSession
    groups = max(1, 2 * spark.sparkContext.defaultParallelism)

    def matrix(batch):
        v = np.array([x[:dims] for x in batch.column(1).to_pylist()], np.float64)
        return batch.column(0).to_numpy(), v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-300)

    def pack(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, QUERY_BLOCK):
                ids, v = matrix(batch.slice(at, QUERY_BLOCK))
                yield pa.RecordBatch.from_arrays([pa.array([ids.astype(np.int64).tobytes()]), pa.array([v.tobytes()])], ["ids", "v"])

    def run(batches):
        for b in batches:
            for ids, q, uid, u in zip(*(c.to_pylist() for c in b.columns), strict=True):
                ids, uid = np.frombuffer(ids, np.int64), np.frombuffer(uid, np.int64)
                sim = np.round(np.frombuffer(q).reshape(len(ids), -1) @ np.frombuffer(u).reshape(len(uid), -1).T, 9)
                if not keep_self:
                    sim[ids[:, None] == uid[None, :]] = -np.inf
                order = np.lexsort((np.broadcast_to(uid, sim.shape), -sim), axis=1)[:, :k]
                i = np.repeat(np.arange(len(ids)), order.shape[1])
                s = sim[i, order.ravel()]
                ok = np.isfinite(s)
                yield pa.RecordBatch.from_arrays([pa.array(ids[i][ok]), pa.array(uid[order.ravel()][ok]), pa.array(s[ok])], ["query_id", "unit_id", "sim"])

    packed = "ids binary, v binary"
    blocks = queries.select(F.col("query_id").cast("long"), "vec").coalesce(groups).mapInArrow(pack, packed).toDF("ids", "q")
    shards = units.select(F.col("unit_id").cast("long"), "vec").mapInArrow(pack, packed).toDF("uid", "u").withColumn("g", F.pmod(F.xxhash64("uid"), F.lit(groups)))
    dealt = blocks.withColumn("g", F.explode(F.sequence(F.lit(0), F.lit(groups - 1)).cast("array<long>")))
    near = shards.join(dealt.hint("merge"), "g").select("ids", "q", "uid", "u").mapInArrow(run, "query_id long, unit_id long, sim double")
    return best(near, [F.desc("sim"), F.asc("unit_id")], k, "first_rank")


def candidates_nested(queries: DataFrame, units: DataFrame, k: int = 8, dims: int = 16, wide: int = 64) -> DataFrame:
    """Coarse to fine: ``wide`` neighbours on vector prefixes, ranked again on whole vectors."""
    coarse = candidates_dense(queries, units, wide, dims).select("query_id", "unit_id")
    full = coarse.join(queries.select("query_id", F.col("vec").alias("qv")), "query_id").join(units.select("unit_id", F.col("vec").alias("uv")), "unit_id")
    return best(full.select("query_id", "unit_id", F.round(S.cosine(F.col("qv"), F.col("uv")), 9).alias("sim")), [F.desc("sim"), F.asc("unit_id")], k, "first_rank")


def candidates_lsh(queries: DataFrame, units: DataFrame, k: int = 8, bands: int = 28, bits: int = 4, seed: int = 5, dim: int = 64) -> DataFrame:
    """Approximate neighbours: sign bits of random projections in bands, equal bands joined, survivors exact."""
    planes = np.random.default_rng(seed).standard_normal((bands, bits, dim)).round(6)

    def keys(df, key):
        sign = lambda p: F.when(F.aggregate(F.zip_with("vec", F.array(*(F.lit(float(x)) for x in p)), lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v) >= 0, 1).otherwise(0)
        codes = [sum((sign(planes[b, i]) * (1 << i) for i in range(bits)), F.lit(b << bits)) for b in range(bands)]
        return df.select(key, F.explode(F.array(*codes)).alias("band"))

    pairs = keys(queries, "query_id").join(keys(units, "unit_id"), "band").filter("query_id <> unit_id").select("query_id", "unit_id").distinct()
    full = pairs.join(queries.select("query_id", F.col("vec").alias("qv")), "query_id").join(units.select("unit_id", F.col("vec").alias("uv")), "unit_id")
    return best(full.select("query_id", "unit_id", F.round(S.cosine(F.col("qv"), F.col("uv")), 9).alias("sim")), [F.desc("sim"), F.asc("unit_id")], k, "first_rank")


def from_external(scored: DataFrame) -> DataFrame:
    """Candidates of any other retriever: its (query_id, unit_id, sim)."""
    return best(scored.select("query_id", "unit_id", F.col("sim").cast("double").alias("sim")), [F.desc("sim"), F.asc("unit_id")], 2**31 - 1, "first_rank")


def with_signals(cands: DataFrame, units: DataFrame, queries: DataFrame, p: Params, exclude_future: bool = False, dormant: str = "exclude", eligible: tuple[str, ...] | None = None) -> DataFrame:
    """Candidates with the query's time, the unit's metadata and all four signals."""
    meta = units if eligible is None else units.filter(F.col("status").isin(*eligible))
    rows = cands.join(meta, "unit_id").join(queries.select("query_id", "kind", "ref_time", "truth"), "query_id")
    if exclude_future:
        rows = rows.filter("born_at <= ref_time")
    if dormant == "exclude":
        rows = rows.filter("status <> 'DORMANT'")
    col = lambda c: F.col(c) if c in units.columns else F.lit(0)
    at = F.col("ref_time")
    return rows.withColumns(
        {
            "temporal": S.temporal(F.col("born_at"), F.col("valid_from"), F.col("valid_to"), at, p),
            "trust": S.trust(F.col("prior_trust"), F.col("born_at"), at, col("pos_n"), col("neg_n"), col("access_n"), p),
            "relational": S.bonus(col("degree"), p),
        }
    )


def rank(scored: DataFrame, w: Weights, k: int = 1, demote: float | None = None) -> DataFrame:
    """The k best candidates a query by final score; ties by similarity, then id. ``demote`` multiplies dormant units' scores."""
    score = S.final(F.col("sim"), F.col("temporal"), F.col("trust"), F.col("relational"), w)
    if demote is not None:
        score = score * F.when(F.col("status") == "DORMANT", demote).otherwise(1.0)
    return best(scored.withColumn("final", F.round(score, 9)), [F.desc("final"), F.desc("sim"), F.asc("unit_id")], k)


def prune_by_bound(scored: DataFrame, w: Weights, p: Params) -> DataFrame:
    """Candidates whose upper bound reaches the best score that similarity alone guarantees; never drops a winner."""
    least = Window.partitionBy("query_id")
    low = F.max(F.col("sim") * float(w.sim)).over(least)
    bound = scored.withColumn("low", F.round(low, 9)).filter(F.round(S.upper_bound(F.col("sim"), w, p), 9) >= F.col("low"))
    return bound.drop("low") if w.sim else scored


def hard_filter(scored: DataFrame, p: Params, k: int = 1) -> DataFrame:
    """Validity as a filter rather than a signal: the most similar of the valid units."""
    ok = S.in_window(F.col("valid_from"), F.col("valid_to"), F.col("ref_time"), p.window)
    return best(scored.filter(ok).withColumn("final", F.col("sim")), [F.desc("final"), F.asc("unit_id")], k)
