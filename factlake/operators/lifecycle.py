"""Life of a unit: encode, supersede, reinforce, demote, promote, archive, audit."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from factlake.functions import signals as S
from factlake.params import Params

# Status changes that may happen
LEGAL = [
    ("UNCONSOLIDATED", "ACTIVE"), ("UNCONSOLIDATED", "DEPRECATED"), ("ACTIVE", "DORMANT"), ("DORMANT", "ACTIVE"),
    ("ACTIVE", "DEPRECATED"), ("DORMANT", "DEPRECATED"), ("DEPRECATED", "ARCHIVED"),
]


def chunk(docs: DataFrame, size: int = 1000, mode: str = "chars", overlap: int = 0) -> DataFrame:
    """doc_id, chunk_no, span_start, span_end, body: half-open character ranges that cover the text.

    ``size`` and ``overlap`` count characters, or words (pieces between single blanks) in mode "words"; a chunk
    begins ``overlap`` before the end of the one before it. Mode "lines" makes every line a chunk.
    """
    if not 0 <= overlap < size:
        raise ValueError("overlap must be less than size")
    step = size - overlap
    if mode in ("chars", "words"):
        docs = docs.select("doc_id", "text", *([F.split("text", " ").alias("w")] if mode == "words" else []))
        length = F.size("w") if mode == "words" else F.length("text")
        n = F.greatest(F.ceil((length - overlap) / step), F.lit(1)).cast("int")
        rows = docs.select("*", F.explode(F.sequence(F.lit(0), n - 1)).alias("chunk_no"))
        at = F.col("chunk_no") * step
        if mode == "words":
            body = F.array_join(F.slice("w", at + 1, F.lit(size)), " ")
            start = F.length(F.array_join(F.slice("w", F.lit(1), at), " ")) + F.when(at > 0, 1).otherwise(0)
        else:
            body, start = F.substring("text", at + 1, F.lit(size)), at
        return rows.select("doc_id", F.col("chunk_no").cast("long").alias("chunk_no"), start.cast("long").alias("span_start"), (start + F.length(body)).cast("long").alias("span_end"), body.alias("body"))
    if mode == "lines":
        rows = docs.select("doc_id", F.posexplode(F.split("text", "\n")).alias("chunk_no", "body"))
        w = Window.partitionBy("doc_id").orderBy("chunk_no")
        end = F.sum(F.length("body") + 1).over(w) - 1
        return rows.select("doc_id", F.col("chunk_no").cast("long").alias("chunk_no"), (end - F.length("body")).cast("long").alias("span_start"), end.cast("long").alias("span_end"), "body")
    raise ValueError(f"unknown mode {mode}")


def encode(arrivals: DataFrame, archive: bool = False) -> DataFrame:
    """Versions of (doc_id, chunk_no) in order of version_no: the newest UNCONSOLIDATED, the ones before DEPRECATED
    (with ``archive``, all but the last of these ARCHIVED), with lineage both ways."""
    w = Window.partitionBy("doc_id", "chunk_no").orderBy("version_no")
    back = F.row_number().over(w.orderBy(F.desc("version_no")))
    status = F.when(back == 1, "UNCONSOLIDATED").when((back > 2) & F.lit(archive), "ARCHIVED").otherwise("DEPRECATED")
    return arrivals.withColumns({"status": status, "replaces": F.lag("unit_id").over(w), "replaced_by": F.lead("unit_id").over(w)})


def lineage_edges(units: DataFrame) -> DataFrame:
    return units.filter("replaces IS NOT NULL").select(F.col("unit_id").alias("src"), F.col("replaces").alias("dst"), F.lit("replaces").alias("kind"))


def transfer_edges(edges: DataFrame, moved: DataFrame) -> DataFrame:
    """Edges with both ends led to successors: ``moved`` has old and new."""
    a, b = moved.toDF("src", "new_src"), moved.toDF("dst", "new_dst")
    out = edges.join(a, "src", "left").join(b, "dst", "left")
    return out.select(F.coalesce("new_src", "src").alias("src"), F.coalesce("new_dst", "dst").alias("dst"), "kind").filter("src <> dst").distinct()


def counters(log: DataFrame, until=None) -> DataFrame:
    """access_n, pos_n, neg_n of each unit; ``until`` counts only what came by then."""
    rows = log if until is None else log.filter(F.col("ts") <= until)
    n = lambda a: F.count_if(F.col("action") == a)
    return rows.groupBy("unit_id").agg(n("access").alias("access_n"), n("accept").alias("pos_n"), n("correct").alias("neg_n"), F.max(F.when(F.col("action") == "validate", F.col("ts"))).alias("validated_at"))


def apply_feedback(units: DataFrame, log: DataFrame, key: str = "unit_id", until=None) -> DataFrame:
    c = counters(log, until).withColumnRenamed("unit_id", key)
    out = units.join(c, key, "left")
    return out.fillna(0, ["access_n", "pos_n", "neg_n"])


def log_retrieval(ranked: DataFrame) -> DataFrame:
    """What was returned, as accesses to append to the log."""
    return ranked.select("unit_id", F.col("ref_time").alias("ts"), F.lit("access").alias("action"), F.col("query_id").alias("actor"))


def step_trust(units: DataFrame, at, p: Params, wake: bool = False) -> DataFrame:
    """Live trust; ACTIVE units under the threshold go DORMANT (with ``wake``, the others return)."""
    zero = lambda c: F.col(c) if c in units.columns else F.lit(0)
    t = S.trust(F.col("prior_trust"), F.col("born_at"), at, zero("pos_n"), zero("neg_n"), zero("access_n"), p)
    out = units.withColumn("trust", t)
    status = F.when((F.col("status") == "ACTIVE") & (F.col("trust") < p.dormant_below), "DORMANT")
    if wake:
        status = status.when((F.col("status") == "DORMANT") & (F.col("trust") >= p.dormant_below), "ACTIVE")
    return out.withColumn("status", status.otherwise(F.col("status")))


def promote(units: DataFrame) -> DataFrame:
    return units.withColumn("status", F.when(F.col("status") == "UNCONSOLIDATED", "ACTIVE").otherwise(F.col("status")))


def archive(units: DataFrame, before) -> DataFrame:
    """DEPRECATED units whose validity ended before ``before`` are ARCHIVED; nothing is deleted."""
    gone = (F.col("status") == "DEPRECATED") & (F.col("valid_to") < before)
    return units.withColumn("status", F.when(gone, "ARCHIVED").otherwise(F.col("status")))


def audit(before: DataFrame, after: DataFrame, cause: str) -> DataFrame:
    """unit_id, old_status, new_status, cause of what changed."""
    a, b = before.select("unit_id", F.col("status").alias("old_status")), after.select("unit_id", F.col("status").alias("new_status"))
    return a.join(b, "unit_id").filter(~F.col("old_status").eqNullSafe(F.col("new_status"))).withColumn("cause", F.lit(cause))


def illegal(changes: DataFrame) -> DataFrame:
    legal = changes.sparkSession.createDataFrame(LEGAL, "old_status string, new_status string")
    return changes.join(F.broadcast(legal), ["old_status", "new_status"], "left_anti")


def chain(units: DataFrame) -> DataFrame:
    """Each version with its depth in its line and the oldest version of it."""
    w = Window.partitionBy("topic").orderBy("version_no")
    return units.filter("version_no IS NOT NULL").select("topic", "unit_id", (F.row_number().over(w) - 1).cast("long").alias("depth"), F.first("unit_id").over(w).alias("root"))


def as_of(units: DataFrame, queries: DataFrame) -> DataFrame:
    """The version valid at each query's time, by key and half-open interval."""
    q = queries.select("query_id", "topic", "ref_time")
    hit = q.join(units.filter("NOT is_rumour").select("topic", "unit_id", "valid_from", "valid_to"), "topic").filter("valid_from <= ref_time AND (valid_to IS NULL OR ref_time < valid_to)")
    return hit.groupBy("query_id").agg(F.max_by("unit_id", F.struct("valid_from", "unit_id")).alias("unit_id"))


def explain(unit_id: str, changes: DataFrame, edges: DataFrame, log: DataFrame) -> DataFrame:
    """All that can have changed a unit's answer: status changes, edges and feedback, as (source, what, other)."""
    a = changes.filter(F.col("unit_id") == unit_id).select(F.lit("status").alias("source"), F.concat_ws(" to ", "old_status", "new_status").alias("what"), F.col("cause").alias("other"))
    e = edges.filter((F.col("src") == unit_id) | (F.col("dst") == unit_id)).select(F.lit("edge"), "kind", F.when(F.col("src") == unit_id, F.col("dst")).otherwise(F.col("src")))
    f = log.filter(F.col("unit_id") == unit_id).groupBy("action").count().select(F.lit("feedback"), "action", F.col("count").cast("string"))
    return a.unionAll(e).unionAll(f)
