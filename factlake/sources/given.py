"""Readers of the given tables, and the corpora of units made from them."""

from __future__ import annotations

from math import gcd

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from factlake.functions.worlds import inside, worlds_of
from factlake.params import AUTHORITY

# The order priority that stands for each class of source
CLASS_OF = {"1-URGENT": "official_db", "2-HIGH": "policy", "3-MEDIUM": "tech_doc", "4-NOT SPECIFIED": "wiki", "5-LOW": "chat"}
NOW = "2001-08-02"
DOCS_NOW = "2024-01-31"
MODULUS = 2**31 - 1


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def at(day: str) -> Column:
    return F.lit(day).cast("timestamp_ntz")


def event_time(df: DataFrame, column: str = "ts") -> DataFrame:
    """Streams need zoned timestamps for watermarks; the files hold local ones."""
    return df.withColumn(column, F.col(column).cast("timestamp"))


def authority(spark: SparkSession) -> DataFrame:
    rows = ", ".join(f"('{source}', {prior}D)" for source, prior in AUTHORITY.items())
    return spark.sql(f"SELECT * FROM VALUES {rows} AS t(source, prior_trust)")


def with_authority(units: DataFrame, default: float = 0.5) -> DataFrame:
    """prior_trust by source, from the five-row table; ``default`` for unknown sources."""
    prior = F.broadcast(authority(units.sparkSession))
    return units.join(prior, "source", "left").withColumn("prior_trust", F.coalesce("prior_trust", F.lit(default)))


def order_units(spark: SparkSession, sf_dir: str, rate: float | tuple[float, ...] | None = None, text: bool = False) -> DataFrame:
    """Orders as versions of their customer's fact; low-priority orders are rumours outside the lineage.

    ``rate`` keeps that share of the rumours, by a hash of the key. Several rates are as many worlds: a unit of any of
    them is there once, and says in which (worlds: a bit for each). Rumours are outside the lineage, so nothing else
    about a unit differs between worlds.
    """
    o = table(spark, sf_dir, "orders")
    source = F.coalesce(*(F.when(F.col("o_orderpriority") == k, F.lit(v)) for k, v in CLASS_OF.items()))
    u = o.select("o_orderkey", F.col("o_custkey").alias("topic"), F.col("o_orderdate").alias("born_at"), F.col("o_totalprice").alias("value"), source.alias("source")).withColumn("is_rumour", F.col("source") == "chat")
    kept_at = lambda r: ~F.col("is_rumour") | (F.pmod(F.col("o_orderkey") * 37, F.lit(100)) < r * 100)
    more = ["worlds"][: isinstance(rate, tuple)]
    if more:
        u = u.withColumn("worlds", sum((F.when(kept_at(r), 1 << i).otherwise(0) for i, r in enumerate(rate)), F.lit(0))).filter("worlds <> 0")
    elif rate is not None:
        u = u.filter(kept_at(rate))
    u = u.repartition("topic")  # serves the windows and the join with the text
    w = Window.partitionBy("topic", "is_rumour").orderBy("born_at", "o_orderkey")
    real = ~F.col("is_rumour")
    name = lambda c: F.concat(F.lit("O:"), c.cast("string"))
    u = u.select(
        name(F.col("o_orderkey")).alias("unit_id"), "topic", F.when(real, F.row_number().over(w).cast("long")).alias("version_no"), "born_at", F.col("born_at").alias("valid_from"),
        F.when(real, F.lead("born_at").over(w)).alias("valid_to"), "value", "source", "is_rumour",
        F.when(real, name(F.lag("o_orderkey").over(w))).alias("replaces"), F.when(real, name(F.lead("o_orderkey").over(w))).alias("replaced_by"), *more,
    )
    u = with_authority(u).withColumn("status", F.when(F.col("replaced_by").isNull(), "ACTIVE").otherwise("DEPRECATED"))
    u = u.withColumn("degree", F.col("replaces").isNotNull().cast("long") + F.col("replaced_by").isNotNull().cast("long"))
    if text:
        u = u.join(topic_text(spark, sf_dir), "topic").withColumn("body", F.concat_ws(" ", "topic_text", F.regexp_replace("source", "_", ""), F.concat(F.lit("v"), F.floor("value").cast("string")))).drop("topic_text")
    return u


def topic_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    c, n = table(spark, sf_dir, "customer"), table(spark, sf_dir, "nation")
    words = F.concat_ws(" ", F.concat(F.lit("acct"), F.col("c_custkey").cast("string")), F.lower("c_mktsegment"), F.lower(F.regexp_replace("n_name", " ", "")))
    return c.join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).select(F.col("c_custkey").alias("topic"), words.alias("topic_text"))


def order_queries(units: DataFrame, kinds: tuple[str, ...] = ("current", "time_point", "conflict"), worlds: int = 0) -> DataFrame:
    """query_id, kind, topic, ref_time and truth (a unit_id); units are sent and sorted once for all kinds.

    Of units in several worlds, with those in which a query is asked (worlds: a bit for each).
    """
    ends, more = worlds_of(worlds), ["worlds"][: bool(worlds)]
    real, now = ~F.col("is_rumour"), at(NOW)
    wide = real & F.coalesce(F.col("valid_to") > F.col("valid_from"), F.lit(True))
    w = Window.partitionBy("topic").orderBy("version_no")
    all_ = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    u = units.select("topic", "unit_id", "version_no", "born_at", "valid_from", "valid_to", "is_rumour", *more, wide.alias("wide")).select(
        "topic", "unit_id", "valid_from", "valid_to", "wide", *more, (real & (F.col("version_no") == F.max(F.when(real, F.col("version_no"))).over(all_))).alias("last"),
        F.max(F.when(real, F.col("born_at"))).over(all_).alias("newest"), *(F.max(F.when(F.col("is_rumour") & inside(s), F.col("born_at"))).over(all_).alias(f"said{s}") for s in ends),
        F.count_if("wide").over(all_).alias("n"), F.count_if("wide").over(w.rowsBetween(Window.unboundedPreceding, Window.currentRow)).alias("r"),
    )
    half = F.floor(F.extract(F.lit("DAY"), F.coalesce("valid_to", now) - F.col("valid_from")) / 2).cast("int")
    mid = F.col("wide") & (F.col("r") == F.ceil(F.col("n") / 2))
    later = lambda s: F.col(f"said{s}") > F.col("newest")
    where = sum((F.when(later(s), 1 << i).otherwise(0) for i, s in enumerate(ends)), F.lit(0))
    ask = {"current": (F.col("last"), now, "worlds"), "time_point": (mid, F.col("valid_from") + F.make_dt_interval(days=half), "worlds"), "conflict": (F.col("last") & (where != 0), now, where)}
    worlds_in = lambda k: [(F.col(x) if isinstance(x, str) else x).alias("worlds") for x in ask[k][2:]][: bool(worlds)]
    asked = F.array(*(F.when(ask[k][0], F.struct(F.lit(k).alias("kind"), ask[k][1].alias("ref_time"), *worlds_in(k))) for k in kinds))
    q = u.filter(F.col("last") | mid).select("topic", F.col("unit_id").alias("truth"), F.explode(F.array_compact(asked)).alias("e"))
    q = q.select("e.kind", "topic", "e.ref_time", "truth", *(f"e.{c}" for c in more))
    return q.withColumn("query_id", F.concat_ws(":", F.substring("kind", 1, 3), F.col("topic").cast("string")))


def document_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as feedback on documents: unit_id, ts, action, actor, day."""
    n = table(spark, sf_dir, "documents").agg(F.count("*").alias("n"))
    e = table(spark, sf_dir, "events")
    action = F.when(F.col("event_type").isin("view", "click"), "access").when(F.col("event_type") == "purchase", "accept").when(F.col("event_type") == "error", "correct").otherwise("validate")
    k = F.get_json_object("props", "$.k").cast("long")
    return e.crossJoin(F.broadcast(n)).select("event_id", F.pmod(F.col("user_id") * 100 + k, F.col("n")).alias("unit_id"), "ts", action.alias("action"), F.col("user_id").alias("actor"), F.date_trunc("day", F.col("ts")).cast("date").alias("day"))


def document_units(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents as units, with a birth day and a prior from fixed rules."""
    d = table(spark, sf_dir, "documents").select("doc_id", "text", "source", "n_chars")
    index = F.pmod(F.regexp_extract("source", "([0-9]+)$", 1).cast("int"), F.lit(5))
    names = list(AUTHORITY)
    born = at(DOCS_NOW) - F.make_dt_interval(days=F.pmod(F.col("doc_id") * 37, F.lit(421)).cast("int"))
    return d.select("doc_id", "text", "n_chars", born.alias("born_at"), F.element_at(F.array(*map(F.lit, names)), (index + 1)).alias("source"))


def with_random(df: DataFrame, seed: int, salts: dict[str, Column | int]) -> DataFrame:
    """A column in [0, 1) for each salt, from integer arithmetic on ``topic`` that any SQL engine repeats; never over 63 bits.

    Step by step, so that no step's expression is written out twice.
    """
    p = F.lit(MODULUS).cast("long")
    col = lambda s: s if isinstance(s, Column) else F.lit(s)
    x, y, z = ({n: F.col(f"_{k}_{n}") for n in salts} for k in "xyz")
    df = df.withColumns({f"_x_{n}": F.pmod(F.lit(seed * 7919 + 1).cast("long") + F.col("topic").cast("long") * 104729 + col(s).cast("long") * 1299709, p) for n, s in salts.items()})
    df = df.withColumns({f"_y_{n}": F.pmod(x[n] * x[n] + 48271 * x[n], p) for n in salts})
    df = df.withColumns({f"_z_{n}": F.pmod(16807 * y[n], p) for n in salts})
    df = df.withColumns({n: F.pmod(z[n] * z[n] + y[n], p) / F.lit(float(MODULUS)) for n in salts})
    return df.drop(*(f"_{k}_{n}" for k in "xyz" for n in salts))


def rumour_topics(topic: Column, topics: int, rate: float, seed: int) -> Column:
    """Whether a topic has a rumour: exactly the share ``rate`` of them, by a step that visits each topic once."""
    step = next(k for k in range(37, 37 + topics + 1) if gcd(k, topics) == 1)
    return F.pmod(topic * step + seed * 11, F.lit(topics)) < round(rate * topics)


def policy_units(spark: SparkSession, topics: int = 60, versions: int = 4, rate: float = 0.3, seed: int = 7, now: str = NOW, given: DataFrame | None = None) -> DataFrame:
    """Generated policies in several versions, rumours beside some; the layout of ``order_units`` with counts of feedback.

    Versions follow each other after 40 to 90 days; in six of ten topics the newest is 12 to 71 days old, in the others
    the oldest is 240 to 420. Rumours are 1 to 10 days old, so newer than any version. Three newest versions in ten and
    one rumour in five say that they are current, as queries ask. Feedback is drawn once: a static prior.
    ``given`` (topic) are topics of a table in place of the numbers below ``topics``; rumours then fall on the same share of them.
    """
    ids = spark.range(topics).select(F.col("id").alias("topic")) if given is None else given.select("topic")
    t = ids
    t = with_random(t, seed, {f"r{k}": k for k in (40, 41, 50, 51, 52, 70, 71, 85, 98, *range(2, versions + 1))})
    r = lambda salt: F.col(f"r{salt}")
    n = lambda salt, most: F.floor(r(salt) * most).cast("long")
    gap = {k: 40 + n(k, 51) for k in range(2, versions + 1)}
    newest = F.when(r(52) < 0.6, 12 + n(51, 60)).otherwise(F.greatest(F.lit(12), 240 + n(50, 181) - sum(gap.values(), F.lit(0))))
    age = sum((F.when(F.col("v") < k, g).otherwise(0) for k, g in gap.items()), newest)
    real = t.withColumn("v", F.explode(F.sequence(F.lit(1), F.lit(versions)))).withColumn("age", age.cast("int"))
    real = with_random(real, seed, {f"by{k}": F.col("v") + k for k in (60, 80, 90, 100)})
    base, step = 100 + F.floor(r(41) * 900), 5 + F.floor(r(40) * 20)
    source = F.element_at(F.array(*map(F.lit, list(AUTHORITY)[:4])), (F.floor(F.col("by60") * 4) + 1).cast("int"))
    mark = lambda sure: F.when(sure, " current").otherwise("")
    by_v = lambda salt, most: F.floor(F.col(f"by{salt}") * most).cast("long")
    real = real.select(
        "topic", F.col("v").cast("long").alias("version_no"), (at(now) - F.make_dt_interval(days="age")).alias("born_at"), (base + (F.col("v") - 1) * step).cast("double").alias("value"), source.alias("source"), F.lit(False).alias("is_rumour"),
        by_v(80, 14).alias("pos_n"), by_v(90, 3).alias("neg_n"), by_v(100, 30).alias("access_n"), mark((F.col("v") == versions) & (r(70) < 0.3)).alias("mark"),
    )
    said = t.filter(rumour_topics(F.col("topic"), topics, rate, seed)).select("topic", F.lit(None).cast("long"), (at(now) - F.make_dt_interval(days=(1 + F.floor(r(98) * 10)).cast("int"))), (base + 500).cast("double"), F.lit("chat"), F.lit(True), n(85, 3), F.lit(0).cast("long"), F.lit(0).cast("long"), mark(r(71) < 0.2))
    u = real.unionAll(said)
    w = Window.partitionBy("topic", "is_rumour").orderBy("born_at", "version_no")
    name = lambda c: F.concat(F.lit("P:"), F.col("topic").cast("string"), F.lit(":"), c.cast("string"))
    keep = ~F.col("is_rumour")
    u = u.select(
        F.when(keep, name(F.col("version_no"))).otherwise(F.concat(F.lit("P:"), F.col("topic").cast("string"), F.lit(":r"))).alias("unit_id"), "topic", "version_no", "born_at", F.col("born_at").alias("valid_from"),
        F.when(keep, F.lead("born_at").over(w)).alias("valid_to"), "value", "source", "is_rumour",
        F.when(keep, name(F.lag("version_no").over(w))).alias("replaces"), F.when(keep, name(F.lead("version_no").over(w))).alias("replaced_by"), "pos_n", "neg_n", "access_n", "mark",
    )
    u = with_authority(u).withColumn("status", F.when(F.col("replaced_by").isNull(), "ACTIVE").otherwise("DEPRECATED"))
    # the topic before and the topic after, where there are such
    there = lambda step, name: ids.select((F.col("topic") + step).alias("topic"), F.lit(True).alias(name))
    u = u.join(there(1, "follows"), "topic", "left").join(there(-1, "precedes"), "topic", "left")
    dep = (F.pmod("topic", F.lit(5)) == 0) & F.col("follows").isNotNull()
    last = F.col("replaced_by").isNull() & keep
    degree = F.when(last & dep, 1).otherwise(0) + F.when(last & (F.pmod(F.col("topic") + 1, F.lit(5)) == 0) & F.col("precedes").isNotNull(), 1).otherwise(0)
    value = F.concat(F.lit(" value"), F.floor("value").cast("string"))
    heard = F.concat(F.lit("heard policy topic"), F.col("topic").cast("string"), F.col("mark"), F.lit(" goes to"), value, F.lit(" soon chat"))
    body = F.when(keep, F.concat(policy_noun(), F.lit(" limit"), F.col("mark"), value)).otherwise(heard)
    return u.withColumn("degree", degree.cast("long")).withColumn("body", body).drop("mark", "follows", "precedes")


def supplier_topics(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A topic for every supplier's policies."""
    return table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("topic"))


def policy_noun() -> Column:
    topic = F.col("topic").cast("string")
    return F.concat(F.lit("policy topic"), topic, F.lit(" clause"), F.pmod("topic", F.lit(20)).cast("string"), F.lit(" area"), topic)


def policy_asked(queries: DataFrame) -> DataFrame:
    """Queries with their text: all kinds ask for the current limit."""
    return queries.withColumn("text", F.concat(policy_noun(), F.lit(" current limit")))


def policy_edges(units: DataFrame) -> DataFrame:
    """Every fifth topic's newest version depends on that of the topic before."""
    last = units.filter("NOT is_rumour AND replaced_by IS NULL").select("topic", "unit_id")
    return last.filter("topic > 0 AND topic % 5 = 0").select(F.col("unit_id").alias("src"), (F.col("topic") - 1).alias("topic")).join(last.withColumnRenamed("unit_id", "dst"), "topic").select("src", "dst", F.lit("depends_on").alias("kind"))


def dependency_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """src depends on dst: nations on regions, customers and suppliers on nations, orders on customers."""
    one = lambda t, a, x, b, y: table(spark, sf_dir, t).select(F.concat(F.lit(a), F.col(x).cast("string")).alias("src"), F.concat(F.lit(b), F.col(y).cast("string")).alias("dst"))
    return one("nation", "N:", "n_nationkey", "R:", "n_regionkey").unionAll(one("customer", "C:", "c_custkey", "N:", "c_nationkey")).unionAll(one("supplier", "S:", "s_suppkey", "N:", "s_nationkey")).unionAll(one("orders", "O:", "o_orderkey", "C:", "o_custkey"))


def part_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts ordered together: the smaller key depends on the larger and the other way round."""
    l = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    r = l.withColumnRenamed("l_partkey", "other")
    return l.join(r, "l_orderkey").filter("l_partkey <> other").select(F.concat(F.lit("P:"), F.col("l_partkey").cast("string")).alias("src"), F.concat(F.lit("P:"), F.col("other").cast("string")).alias("dst")).distinct()
