"""Context blocks for a generator: each retrieved unit with what speaks for and against it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from factlake.functions import signals as S


# What a generator is told before the units
GUIDANCE = "\n".join([
    "Units are listed by their score: similarity, validity at the time asked for, live trust and links.",
    "Trust falls with age and follows the source's authority and the feedback of readers.",
    "Where units dispute each other, rely on the one with more trust.",
    "Name the source, version and date of what is used.",
])


def citation() -> Column:
    """[source, author, version, date]; unknown parts are left out."""
    col = lambda c: F.col(c)
    version = F.concat(F.lit("v"), F.coalesce(col("version_no").cast("string"), F.lit("-")))
    return F.concat(F.lit("["), F.concat_ws(", ", "source", "author", version, F.date_format("born_at", "yyyy-MM-dd")), F.lit("]"))


def conflicts(ranked: DataFrame, pairs: DataFrame) -> DataFrame:
    """Units of one result list that contradict each other: query_id, unit_id, with."""
    both = pairs.select(F.col("a").alias("unit_id"), F.col("b").alias("with")).unionAll(pairs.select("b", "a"))
    r = ranked.select("query_id", F.col("unit_id").alias("with"))
    return ranked.select("query_id", "unit_id").join(both, "unit_id").join(r, ["query_id", "with"]).select("query_id", "unit_id", "with")


def _with_defaults(rows: DataFrame) -> DataFrame:
    """Columns that a caller's units may lack: author, counts and the number of edges."""
    zero = {c: F.lit(0).cast("long") for c in ("access_n", "pos_n", "neg_n", "degree") if c not in rows.columns}
    more = {} if "author" in rows.columns else {"author": F.lit(None).cast("string")}
    return rows.withColumns(zero | more) if zero or more else rows


def line() -> Column:
    """A unit as three lines: who says it, when and how good it is; what is known of its use; disputes and its text."""
    f = lambda c: F.format_string("%.3f", F.round(c, 3))
    n = lambda c: F.col(c).cast("string")
    head = F.concat_ws(" ", n("rank"), "unit_id", citation(), "status", F.concat(F.floor("age").cast("string"), F.lit(" days old")))
    scores = F.concat(F.lit("  score "), f("final"), F.lit(" similar "), f("sim"), F.lit(" timely "), f("temporal"), F.lit(" trusted "), f("trust"), F.lit(" linked "), f("relational"))
    use = F.concat(F.lit("  edges "), n("degree"), F.lit(" read "), n("access_n"), F.lit(" accepted "), n("pos_n"), F.lit(" corrected "), n("neg_n"), F.when(F.col("conflicts") > 0, F.concat(F.lit(" disputed by "), F.array_join("against", ", "))).otherwise(""))
    return F.concat_ws("\n", head, scores, use, F.concat(F.lit("  "), F.col("body")))


def assemble(ranked: DataFrame, flags: DataFrame | None = None, header: str = GUIDANCE) -> DataFrame:
    """query_id and its context: the header, then every unit in order of rank with all that speaks for and against it.

    ``ranked`` has unit columns, signals and ref_time; ``flags`` (query_id, unit_id, with) are disputes.
    """
    rows = _with_defaults(ranked).withColumn("age", S.age_days(F.col("born_at"), F.col("ref_time")))
    if flags is None:
        rows = rows.withColumns({"conflicts": F.lit(0), "against": F.array().cast("array<string>")})
    else:
        n = flags.groupBy("query_id", "unit_id").agg(F.count("*").alias("conflicts"), F.array_sort(F.collect_set("with")).alias("against"))
        rows = rows.join(n, ["query_id", "unit_id"], "left").fillna(0, ["conflicts"])
    block = rows.groupBy("query_id").agg(F.array_sort(F.collect_list(F.struct("rank", line().alias("line")))).alias("b"))
    return block.select("query_id", F.concat_ws("\n", F.lit(header), F.array_join(F.transform("b", lambda x: x["line"]), "\n")).alias("context"))


def assemble_json(ranked: DataFrame) -> DataFrame:
    block = ranked.groupBy("query_id").agg(F.array_sort(F.collect_list(F.struct("rank", "unit_id", *(F.format_string("%.3f", F.round(c, 3)).alias(c) for c in ("final", "sim", "temporal", "trust", "relational"))))).alias("units"))
    return block.select("query_id", F.to_json(F.struct("units")).alias("context"))


def budget(rows: DataFrame, most: int, size: Column) -> DataFrame:
    """The first units of each query whose sizes together stay within ``most``."""
    w = Window.partitionBy("query_id").orderBy("rank").rowsBetween(Window.unboundedPreceding, 0)
    return rows.withColumn("used", F.sum(size).over(w).cast("long")).filter(F.col("used") <= most)
