"""Personal data: base patterns, and more found by contexts bootstrapped from them. DataFrame functions only.

Base spans are the leftmost matches of four kinds (email, ip, card, phone); matches that fail their
check are dropped. Places are found without any loop over characters: the lengths of the pieces
between matches and of the matches themselves are summed in order.

Bootstrapping: seeds are the base spans and long tokens that mix letters and digits (kind secret).
Candidates are tokens with a digit, neighbouring groups of digits as one, and what follows a label
(``key=``, ``key:``, ``key = ``), with digits or without, where no base span touches it. What stands
before an instance is its pattern: the key that touches it, the label before it, or else the two
words before it. Patterns and instances form a graph: a pattern's confidence is the score that its
distinct instances have on average (one failing instance added), an instance's score that of its best
confident pattern; seeds keep 1, and what stands behind a label but can't be an identifier keeps 0.
A pattern needs ``support`` instances that are seeds or were accepted before; instances accepted in one
round support further patterns in the next, until the scores settle or after ``rounds`` rounds.
A two-word pattern must also foretell identifiers: it is counted over all texts and at least
``specific`` of its places must be followed by one. Secrets and candidates behind the remaining
patterns are spans of the kind that most of the pattern's seeds have.

Cases: null texts count as empty; documents without any span get empty strings and zeros; repeated
rows are treated each on its own; equal starts are ordered by kind as listed, found ones after base
ones; very long texts and runs cost linear time; only doc_id and text are read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize

KINDS = ("email", "ip", "card", "phone")
SEEDS = (*KINDS, "secret")

# The base patterns. Possessive and anchored forms match the same places in linear time.
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
GROUP = r"\(?[0-9][0-9()./-]*+"
CANDIDATE = rf"(?<!\S){GROUP}(?:\x20{GROUP}(?!\S))++|(?<!\S)[^\s0-9]*+[0-9]\S*+|(?<!\S)[^\s=:]++[=:][^\s/]\S*+|(?<=[=:]\x20)[^\s=:]++(?!\S)"
SECRET = r"^(?=(?:[^0-9]*[0-9]){4})(?=(?:[^A-Za-z]*[A-Za-z]){4})[A-Za-z0-9_+/=-]{20,}$"
TWO_WORDS = r"(?<!\S)(?:\S++\s++)?\S++\s*+$"
PART = r"0*(?:[0-9]{1,2}|1[0-9]{2}|2[0-4][0-9]|25[0-5])"
NEAR, FEW = 64, 20_000


def _tags(text: Column) -> dict[str, Column]:
    """128 bits of a text, by which its spans find their way back to it."""
    return {"tag": F.xxhash64(text), "tag2": F.xxhash64(F.lit(1), text)}


def _valid(kind: Column, value: Column) -> Column:
    digits = F.regexp_replace(value, "[^0-9]", "")
    n = F.length(digits)
    return (
        F.when(kind == "email", True)
        .when(kind == "ip", value.rlike(rf"^{PART}(?:\.{PART}){{3}}$"))
        .when(kind == "card", n.between(12, 19) & F.call_function("luhn_check", digits))
        .when(kind == "phone", n.between(9, 15))
        .otherwise(F.length(F.regexp_replace(value, r"[^\p{L}0-9]", "")) >= 6)
    )


def _matches(text: Column, kind: str, pattern: str, hint: Column) -> Column:
    """Matches of one kind in order: the piece before each (its length and end) and the match."""
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    pieces = F.split(text, pattern, -1)
    # the last NEAR characters hold two words as a rule; where they don't, the piece is searched as a whole
    last = lambda p: F.when((F.length(p) <= NEAR) | F.substring(p, -NEAR, NEAR).rlike(r"\s\S+\s+\S+\s*$"), F.substring(p, -NEAR, NEAR)).otherwise(F.regexp_extract(p, TWO_WORDS, 0))
    rows = F.transform(
        F.arrays_zip(found.alias("m"), F.slice(pieces, F.lit(1), F.size(found)).alias("p")),
        lambda x: F.struct(F.lit(kind).alias("kind"), F.length(x["p"]).cast("long").alias("gap"), last(x["p"]).alias("tail"), x["m"].alias("value")),
    )
    return F.when(hint, rows).otherwise(F.array().cast("array<struct<kind:string,gap:bigint,tail:string,value:string>>"))


def _pattern(before: Column) -> Column:
    """The key that touches an instance, the label before it, or the two words before it; digits count alike, quotes and brackets not at all."""
    before = F.regexp_replace(before, "[\"'`(\\[{<]+$", "")
    words = F.trim(F.regexp_extract(before, TWO_WORDS, 0))
    label = F.regexp_extract(words, r"\S*[\p{L}0-9]\S*[=:]$", 0)
    found = F.when(~before.rlike(r"\s$"), F.regexp_extract(before, r"\S+$", 0)).when(label != "", label).otherwise(words)
    return F.regexp_replace(F.translate(F.lower(found), "123456789", "000000000"), r"\s+", " ")


def occurrences(docs: DataFrame) -> DataFrame:
    """A row per base span, secret, candidate and other token behind a label: row, doc_id, two hashes of the text, kind (null: a document without any), start, end, value, pattern."""
    rows = docs.select(F.monotonically_increasing_id().alias("row"), F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).withColumns(_tags(F.col("text")))
    digit = F.col("text").rlike("[0-9]")
    hints = {"email": F.contains("text", F.lit("@")), "ip": digit, "card": digit, "phone": F.contains("text", F.lit("+"))}
    found = F.concat(*(_matches(F.col("text"), k, PATTERNS[k], hints[k]) for k in KINDS), _matches(F.col("text"), "candidate", CANDIDATE, F.col("text").rlike("[0-9=:]")))
    # `at` is counted over all kinds, so a document's order within a kind is the order of its matches
    each = rows.select("row", "doc_id", "tag", "tag2", F.posexplode_outer(found).alias("at", "x")).select("row", "doc_id", "tag", "tag2", "at", "x.*").repartition("row")
    before = Window.partitionBy("row", "kind").orderBy("at").rowsBetween(Window.unboundedPreceding, 0)
    size = F.length("value")
    each = each.withColumn("end", F.sum(F.col("gap") + size).over(before)).withColumn("start", F.col("end") - size)
    lead = F.regexp_extract("value", r"^(?:[^\s]*[=:])?[^\p{L}0-9]*", 0)
    core = F.regexp_extract(F.expr("substring(value, length(lead) + 1)"), r"^.*[\p{L}0-9]", 0)
    each = each.withColumn("lead", F.when(F.col("kind") == "candidate", lead).otherwise("")).withColumn("value", F.when(F.col("kind") == "candidate", core).otherwise(F.col("value")))
    each = each.withColumn("start", F.col("start") + F.length("lead")).withColumn("end", F.col("start") + F.length("value"))
    each = each.withColumn("ok", F.coalesce(_valid(F.col("kind"), F.col("value")), F.lit(False)))
    each = each.withColumn("pattern", _pattern(F.concat("tail", "lead")))
    # candidates that a base span touches are no candidates
    base = F.col("ok") & (F.col("kind") != "candidate")
    order = Window.partitionBy("row").orderBy("start", "end", "at")
    upto = F.max(F.when(base, F.col("end"))).over(order.rowsBetween(Window.unboundedPreceding, 0))
    after = F.min(F.when(base, F.col("start"))).over(order.rowsBetween(0, Window.unboundedFollowing))
    free = ~(F.coalesce(upto > F.col("start"), F.lit(False)) | F.coalesce(after < F.col("end"), F.lit(False)))
    each = each.withColumn("free", free)
    named = F.when(F.col("kind") != "candidate", F.when(F.col("ok"), F.col("kind")))
    named = F.coalesce(named, F.when((F.col("kind") == "candidate") & F.col("free"), F.when(~F.col("ok"), F.when(F.col("pattern").rlike("[=:]$"), F.lit("other"))).when(F.col("value").rlike(SECRET), F.lit("secret")).otherwise(F.lit("candidate"))))
    each = each.select("row", "doc_id", "tag", "tag2", named.alias("kind"), "start", "end", "value", "pattern")
    return materialize(each.withColumn("last", F.row_number().over(Window.partitionBy("row").orderBy(F.col("kind").asc_nulls_last(), "start", "end"))).filter("kind IS NOT NULL OR last = 1").drop("last"), "pii-occurrences")


def confident(occ: DataFrame, texts: DataFrame, rounds: int, support: int, confidence: float, specific: float) -> DataFrame:
    """pattern and kind of the patterns to trust."""
    seed = F.col("kind").isin(*SEEDS)
    flags = [F.max((F.col("kind") == k).cast("int")).alias(k) for k in (*SEEDS, "other")]
    edges = occ.filter((F.col("kind").isNotNull()) & (F.length("pattern") >= 3)).groupBy("pattern", "value").agg(F.max(seed.cast("double")).alias("seed"), *flags)
    edges = materialize(edges, "pii-edges")
    score, known = edges.withColumn("score", F.col("seed")), -1.0
    for _ in range(rounds):
        patterns = score.groupBy("pattern").agg((F.sum("score") / (F.count("*") + 1)).alias("confidence"), F.sum((F.col("score") >= confidence).cast("int")).alias("accepted"), F.sum("seed").alias("seeds"), *(F.sum(k).alias(k) for k in SEEDS))
        patterns = patterns.filter((F.col("accepted") >= support) & (F.col("confidence") >= confidence))
        best = edges.select("pattern", "value").join(patterns.select("pattern", "confidence"), "pattern").groupBy("value").agg(F.max("confidence").alias("confidence"))
        accepted = F.when(F.col("other") == 1, F.lit(0.0)).otherwise(F.coalesce("confidence", F.lit(0.0)))
        score = materialize(edges.join(best, "value", "left").select(*edges.columns, F.greatest("seed", accepted).alias("score")), "pii-scores")
        total = score.agg(F.sum("score")).first()[0] or 0.0
        if abs(total - known) <= 1e-4 * total:
            break
        known = total
    # a pattern without seeds of its own takes the kind of its instances' other patterns
    most = lambda: F.greatest(*SEEDS)
    kindless = patterns.filter("seeds = 0").select("pattern")
    lends = edges.select("pattern", "value").join(patterns.select("pattern", *SEEDS), "pattern").groupBy("value").agg(*(F.sum(k).alias(k) for k in SEEDS))
    lent = edges.select("pattern", "value").join(kindless, "pattern").join(lends, "value")
    lent = lent.groupBy("pattern").agg(*(F.sum(k).alias(k) for k in SEEDS)) if kindless.limit(1).count() else None
    kind = F.coalesce(*(F.when((F.col(k) == most()) & (F.col(k) > 0), F.lit(k)) for k in SEEDS))
    # only patterns that have something left to find go on
    useful = edges.filter("email + ip + card + phone = 0 AND other = 0").select("pattern").distinct()
    patterns = patterns.select("pattern", *SEEDS)
    if lent is not None:
        patterns = patterns.join(kindless, "pattern", "left_anti").unionByName(lent)
    patterns = materialize(patterns.join(useful, "pattern", "left_semi").select("pattern", kind.alias("kind")), "pii-patterns")
    wide = patterns.filter(F.contains("pattern", F.lit(" ")))
    n = wide.count()
    if not n:
        return patterns
    norm = F.translate(F.lower(F.coalesce(F.col("text").cast("string"), F.lit(""))), "123456789", "000000000")
    w = texts.select(F.split(norm, r"\s+").alias("w"))
    pairs = w.select(F.explode(F.expr("transform(sequence(1, greatest(size(w) - 1, 1)), i -> concat_ws(' ', try_element_at(w, i), try_element_at(w, i + 1)))")).alias("pattern"))
    if n <= FEW:  # a checked size: the patterns are looked up while rows stream by
        held = pairs.filter(F.col("pattern").isin([r["pattern"] for r in wide.collect()]))
    else:
        held = pairs.join(wide.select("pattern"), "pattern")
    held = held.groupBy("pattern").agg(F.count("*").alias("places"))
    used = occ.filter("kind IS NOT NULL AND kind <> 'other'").join(F.broadcast(wide.select("pattern")) if n <= FEW else wide.select("pattern"), "pattern", "left_semi").groupBy("pattern").agg(F.count("*").alias("used"))
    fit = held.join(used, "pattern").filter(F.col("used") >= specific * F.col("places")).select("pattern")
    return materialize(patterns.filter(~F.contains("pattern", F.lit(" "))).unionByName(wide.join(fit, "pattern", "left_semi")), "pii-specific")


def spans(docs: DataFrame, rounds: int = 8, support: int = 3, confidence: float = 0.6, specific: float = 0.5) -> DataFrame:
    """row, doc_id, the text's hashes, and arrays of (start, rank of kind, kind, end): base spans and all spans of every document row."""
    occ = occurrences(docs)
    patterns = confident(occ, docs.select("text"), rounds, support, confidence, specific)
    few = patterns.limit(FEW + 1).count() <= FEW
    trusted = patterns.withColumnRenamed("kind", "as_kind")
    named = occ.join(F.broadcast(trusted) if few else trusted, "pattern", "left")
    order = F.coalesce(*(F.when(F.col("kind") == k, F.lit(i)) for i, k in enumerate(KINDS)), F.lit(len(KINDS)))
    is_base = F.col("kind").isin(*KINDS)
    span = F.struct("start", order.alias("nth"), F.when(is_base, F.col("kind")).otherwise(F.col("as_kind")).alias("kind"), "end")
    base = F.when(is_base, span)
    found = F.when(is_base | (F.col("kind").isin("secret", "candidate") & F.col("as_kind").isNotNull()), span)
    return named.groupBy("row", "doc_id", "tag", "tag2").agg(F.array_sort(F.collect_list(base)).alias("base"), F.array_sort(F.collect_list(found)).alias("spans"))


def digest(found: DataFrame) -> DataFrame:
    """doc_id, counts by kind, the hash of the base spans and all spans as text."""
    line = lambda c: F.array_join(F.transform(c, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))), ",")
    count = lambda k: F.size(F.filter("base", lambda x: x["kind"] == k)).cast("long").alias(f"n_{k}")
    counts = [count(k) for k in KINDS]
    return found.select("doc_id", *counts, F.sha2(line("base").cast("binary"), 256).alias("base_sha256"), line("spans").alias("spans"))


def mask(docs: DataFrame, **how) -> DataFrame:
    """``docs`` with every span of personal data in ``text`` replaced by its kind in angle brackets, overlapping
    spans by that of the first, and ``n_chars`` (if there) brought up to date. Spans depend on the text
    alone, so they are joined by a 128-bit hash of it, and only to texts that have some."""
    texts = docs.select(F.lit(None).cast("long").alias("doc_id"), "text")
    few = materialize(spans(texts, **how).filter(F.size("spans") > 0).select("tag", "tag2", "spans").dropDuplicates(["tag", "tag2"]), "pii-masks")
    # spans that overlap the one before them fall to it
    ends = F.transform("spans", lambda x, i: F.when(i == 0, 0).otherwise(F.array_max(F.transform(F.slice("spans", F.lit(1), F.greatest(i, F.lit(1))), lambda y: y["end"]))).cast("long"))
    own = few.select("tag", "tag2", F.filter(F.transform(F.arrays_zip("spans", ends.alias("before")), lambda z: F.struct(z["spans"]["start"].alias("start"), F.greatest(z["spans"]["end"], z["before"]).alias("end"), z["spans"]["kind"].alias("kind"), z["before"].alias("before"))), lambda x: x["start"] >= x["before"]).alias("own"), F.array_max(F.transform("spans", lambda x: x["end"])).alias("stop"))
    own = own.select("tag", "tag2", "own", "stop")
    rows = docs.withColumns({f"_{k}": v for k, v in _tags(F.coalesce(F.col("text").cast("string"), F.lit(""))).items()})
    own = own.withColumnsRenamed({"tag": "_tag", "tag2": "_tag2", "own": "_own", "stop": "_stop"})
    rows = rows.join(F.broadcast(own) if few.count() <= FEW * 10 else own, ["_tag", "_tag2"], "left")
    piece = lambda x: F.concat(F.substr(F.col("text"), (x["before"] + 1).cast("int"), (x["start"] - x["before"]).cast("int")), F.lit("<"), x["kind"], F.lit(">"))
    text = F.when(F.col("_own").isNull(), F.col("text")).otherwise(F.concat(F.array_join(F.transform("_own", piece), ""), F.substr(F.col("text"), (F.col("_stop") + 1).cast("int"))))
    rows = rows.withColumn("text", text)
    if "n_chars" in docs.columns:
        rows = rows.withColumn("n_chars", F.coalesce(F.length("text").cast("long"), F.col("n_chars")) if dict(docs.dtypes)["n_chars"] == "bigint" else F.col("n_chars"))
    return rows.select(*docs.columns)
