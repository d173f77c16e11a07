"""Localised updates: what an edit touches, and what has to be embedded again."""

from __future__ import annotations

import difflib
import re

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from factlake.operators import lifecycle as L
from factlake.sources.scratch import materialize

HUNK = "doc_id long, old_start long, old_end long, new_start long, new_end long, delta long"


def _hunk_batch(rows):
    cols = list(zip(*rows, strict=True)) if rows else [()] * 6
    return pa.RecordBatch.from_arrays([pa.array(list(c), pa.int64()) for c in cols], ["doc_id", "old_start", "old_end", "new_start", "new_end", "delta"])


def diff_trim(pairs: DataFrame) -> DataFrame:
    """One hunk a document (doc_id, old, new): what is left between the common beginning and the common end."""

    def common(a: str, b: str) -> int:
        lo, hi = 0, min(len(a), len(b))
        while lo < hi:
            mid = (lo + hi + 1) // 2
            lo, hi = (mid, hi) if a[:mid] == b[:mid] else (lo, mid - 1)
        return lo

    def run(batches):
        for b in batches:
            rows = []
            for d, old, new in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                old, new = old or "", new or ""
                if old == new:
                    continue
                s = common(old, new)
                e = min(common(old[::-1], new[::-1]), len(old) - s, len(new) - s)
                rows.append((d, s, len(old) - e, s, len(new) - e, len(new) - len(old)))
            yield _hunk_batch(rows)

    return pairs.select("doc_id", "old", "new").mapInArrow(run, HUNK)


def diff_tokens(pairs: DataFrame) -> DataFrame:
    """All hunks of a document by its words and the space between them."""
    token = re.compile(r"\s+|[^\s]+")

    def run(batches):
        for b in batches:
            rows = []
            for d, old, new in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                x, y = token.findall(old or ""), token.findall(new or "")
                at_x, at_y = [0], [0]
                for t in x:
                    at_x.append(at_x[-1] + len(t))
                for t in y:
                    at_y.append(at_y[-1] + len(t))
                for op, a1, a2, b1, b2 in difflib.SequenceMatcher(None, x, y, autojunk=False).get_opcodes():
                    if op != "equal":
                        rows.append((d, at_x[a1], at_x[a2], at_y[b1], at_y[b2], (at_y[b2] - at_y[b1]) - (at_x[a2] - at_x[a1])))
            yield _hunk_batch(rows)

    return pairs.select("doc_id", "old", "new").mapInArrow(run, HUNK)


def diff_hash(old: DataFrame, new: DataFrame) -> DataFrame:
    """doc_id, state, n: chunks kept, added and removed, by their hashes alone."""
    key = lambda df: df.select("doc_id", F.sha2("body", 256).alias("sha")).distinct()
    a, b = key(old).withColumn("in_old", F.lit(True)), key(new).withColumn("in_new", F.lit(True))
    state = F.when(F.col("in_old").isNull(), "added").when(F.col("in_new").isNull(), "removed").otherwise("kept")
    return a.join(b, ["doc_id", "sha"], "full").groupBy("doc_id", state.alias("state")).agg(F.count("*").alias("n"))


def affected(chunks: DataFrame, hunks: DataFrame, overlap: str = "owner") -> DataFrame:
    """Distinct chunks that a hunk meets. An insertion at a border belongs to the chunk that ends there ("owner") or to none ("strict")."""
    h = hunks.select(F.col("doc_id").alias("d"), "old_start", "old_end")
    meets = (F.col("span_start") < F.col("old_end")) & (F.col("span_end") > F.col("old_start"))
    if overlap == "owner":
        insert = F.col("old_start") == F.col("old_end")
        own = ((F.col("span_start") < F.col("old_start")) & (F.col("old_start") <= F.col("span_end"))) | ((F.col("old_start") == 0) & (F.col("chunk_no") == 0))
        meets = F.when(insert, own).otherwise(meets)
    return chunks.join(h, (F.col("doc_id") == F.col("d")) & meets, "left_semi")


def splice(chunks: DataFrame, hunks: DataFrame, new_texts: DataFrame, overlap: str = "owner") -> DataFrame:
    """Chunks of the new texts: doc_id, chunk_no, span_start, span_end, body, replaced.

    Untouched chunks move by the hunks before them; a touched one takes the new text between its moved
    start and the moved start of the chunk after it, so the chunks still make up the whole text.
    """
    hit = affected(chunks, hunks, overlap).select("doc_id", "chunk_no", F.lit(True).alias("replaced"))
    # a chunk's start moves by the hunks that end at or before it; inside a hunk, to the end of the new text
    h = hunks.select("doc_id", "old_start", "old_end", "new_end", "delta")
    insert = (F.col("old_start") == F.col("old_end")) & (F.col("old_start") == F.col("span_start"))
    before = (F.col("old_end") <= F.col("span_start")) & ~(insert & (F.col("span_start") == 0))
    inside = (F.col("old_start") < F.col("span_start")) & (F.col("old_end") > F.col("span_start"))
    starts = chunks.join(h, "doc_id", "left").groupBy("doc_id", "chunk_no", "span_start").agg(F.coalesce(F.sum(F.when(before, F.col("delta"))), F.lit(0)).alias("shift"), F.max(F.when(inside, F.col("new_end"))).alias("jump"))
    starts = starts.select("doc_id", "chunk_no", F.coalesce("jump", F.col("span_start") + F.col("shift")).alias("from"))
    new = new_texts.select("doc_id", "new")
    rows = starts.join(hit, ["doc_id", "chunk_no"], "left").join(new, "doc_id")
    w = Window.partitionBy("doc_id").orderBy("chunk_no")
    end = F.coalesce(F.lead("from").over(w), F.length("new").cast("long"))
    return rows.select("doc_id", "chunk_no", F.col("from").alias("span_start"), end.alias("span_end"), "new", F.coalesce("replaced", F.lit(False)).alias("replaced")).select(
        "doc_id", "chunk_no", "span_start", "span_end", F.substr("new", (F.col("span_start") + 1).cast("int"), (F.col("span_end") - F.col("span_start")).cast("int")).alias("body"), "replaced"
    )


def apply_update(units: DataFrame, edges: DataFrame, hunks: DataFrame, new_texts: DataFrame, at, overlap: str = "owner") -> tuple[DataFrame, DataFrame, DataFrame]:
    """An edit as a change of state: units (UNIT columns below), edges and the queue of units to ripple from.

    Units have unit_id, doc_id, chunk_no, version_no, span_start, span_end, body, status, born_at, replaces and
    replaced_by; the live ones of an edited document are its chunks. A touched chunk is deprecated and replaced by an
    UNCONSOLIDATED one with the text of its new span, lineage both ways and the edges of the old one; the others only
    move. Units of other documents and older versions stay as they are.
    """
    live = units.filter("replaced_by IS NULL")
    edited = live.join(hunks.select("doc_id").distinct(), "doc_id", "left_semi")
    moved = materialize(splice(edited, hunks, new_texts, overlap), "update-spans")
    joined = edited.drop("span_start", "span_end", "body").join(moved, ["doc_id", "chunk_no"])
    name = F.concat_ws(":", F.col("doc_id").cast("string"), F.col("chunk_no").cast("string"), F.concat(F.lit("v"), (F.col("version_no") + 1).cast("string")))
    cols = units.columns
    stay = joined.filter("NOT replaced").select(*cols)
    heirs = joined.filter("replaced").select(F.col("unit_id").alias("old"), name.alias("new"), *(c for c in cols if c != "unit_id"))
    fresh = heirs.withColumns({"unit_id": F.col("new"), "version_no": F.col("version_no") + 1, "status": F.lit("UNCONSOLIDATED"), "born_at": at, "replaces": F.col("old"), "replaced_by": F.lit(None).cast("string")}).select(*cols)
    gone = units.join(heirs.select(F.col("old").alias("unit_id"), "new"), "unit_id").withColumns({"status": F.lit("DEPRECATED"), "replaced_by": F.col("new")}).select(*cols)
    rest = units.join(joined.select("unit_id"), "unit_id", "left_anti").select(*cols)
    pairs = heirs.select("old", "new")
    lineage = pairs.select(F.col("new").alias("src"), F.col("old").alias("dst"), F.lit("replaces").alias("kind"))
    kept = edges.filter("kind = 'replaces'").select("src", "dst", "kind")
    return rest.unionAll(stay).unionAll(gone).unionAll(fresh), L.transfer_edges(edges.filter("kind <> 'replaces'"), pairs).unionAll(kept).unionAll(lineage), pairs.select(F.col("new").alias("unit_id"))


def rebuild(chunks: DataFrame) -> DataFrame:
    """doc_id and text, from the chunks in their order."""
    rows = chunks.groupBy("doc_id").agg(F.array_sort(F.collect_list(F.struct("chunk_no", "body"))).alias("c"))
    return rows.select("doc_id", F.array_join(F.transform("c", lambda x: x["body"]), "").alias("text"))


def middle_word_edit(docs: DataFrame, word: str = "revised") -> DataFrame:
    """doc_id, old, new: the middle word of every text of at least three words replaced."""
    n = F.size(F.split("text", " "))
    mid = F.floor(n / 2).cast("int")
    w = F.split("text", " ")
    new = F.concat_ws(" ", F.slice(w, F.lit(1), mid), F.array(F.lit(word)), F.slice(w, mid + 2, F.greatest(n - mid - 1, F.lit(0))))
    return docs.filter(n >= 3).select("doc_id", F.col("text").alias("old"), new.alias("new"))


def update_cost(units: DataFrame, edits: DataFrame, touched: DataFrame) -> DataFrame:
    """doc_id, plain (all units of the document) and ours (those touched) for every edit."""
    plain = units.groupBy("doc_id").agg(F.count("*").alias("plain"))
    ours = touched.groupBy("doc_id").agg(F.count("*").alias("ours"))
    return edits.select("doc_id").join(plain, "doc_id").join(ours, "doc_id", "left").select("doc_id", "plain", F.coalesce("ours", F.lit(0)).alias("ours"))
