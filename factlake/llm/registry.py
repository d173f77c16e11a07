"""The queries over the training-data tables, and their SQL where SQL can express them."""

from __future__ import annotations

from pyspark.sql import functions as F

from . import decontam, exactdup, language, licenses, mixing, neardup, pages, pii, toxicity, vectors
from .common import residue, table


def op9_language(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    langs, lookup = language.fit(docs.filter(residue("doc_id", 4) != 2))
    return language.predict(docs, langs, lookup).select("doc_id", (residue("doc_id", 4) == 2).alias("held_out"), "lang_pred", "score")


def op10_license_scan(spark, sf_dir):
    return licenses.scan(table(spark, sf_dir, "documents")).drop("lines")


def op1_exact_topk(spark, sf_dir):
    vectors_ = vectors.quantize(table(spark, sf_dir, "embeddings").select("vec_id", "embedding"))
    return vectors.top_k(vectors_, vectors_.filter("vec_id % 50 = 0"), k=5)


def op2_decontamination(spark, sf_dir):
    return decontam.find(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op4_pii(spark, sf_dir):
    return pii.digest(pii.spans(table(spark, sf_dir, "documents").select("doc_id", "text")))


def op5_suffix_dedup(spark, sf_dir):
    return exactdup.deduplicate(table(spark, sf_dir, "documents")).drop("kept")


def op6_mixing(spark, sf_dir):
    return mixing.mix(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op7_near_duplicates(spark, sf_dir):
    return neardup.near_duplicates(table(spark, sf_dir, "documents"), size=4, percent=80)


def op8_main_text(spark, sf_dir):
    return pages.extract(table(spark, sf_dir, "pages"))


def op3_toxicity(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    labels = table(spark, sf_dir, "labels").select("doc_id", "toxic").filter(residue("doc_id", 5) != 0)
    model = toxicity.fit(docs, docs, labels)
    return toxicity.score(docs, model).select("doc_id", (residue("doc_id", 5) == 0).alias("held_out"), "score", "predicted")


QUERIES = {
    "op1_exact_topk": op1_exact_topk,
    "op2_decontamination": op2_decontamination,
    "op3_toxicity": op3_toxicity,
    "op4_pii": op4_pii,
    "op5_suffix_dedup": op5_suffix_dedup,
    "op6_mixing": op6_mixing,
    "op7_near_duplicates": op7_near_duplicates,
    "op8_main_text": op8_main_text,
    "op9_language": op9_language,
    "op10_license_scan": op10_license_scan,
}

ORACLES: dict[str, str] = {
    "op1_exact_topk": """
        WITH v AS (SELECT CAST(vec_id AS BIGINT) AS vec_id, list_transform(embedding, lambda x: floor(CAST(x AS DOUBLE) * 256)) AS q FROM embeddings
                   WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
             s AS (SELECT a.vec_id AS query_id, b.vec_id AS vec_id, CAST(list_inner_product(a.q, b.q) AS BIGINT) AS score
                   FROM v a JOIN v b ON a.vec_id % 50 = 0 AND a.vec_id <> b.vec_id),
             r AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM s)
        SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5""",
}
