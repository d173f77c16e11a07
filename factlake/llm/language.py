"""Language identification with hyperdimensional profiles.

Every letter slot has a random vector of +1/-1. An n-gram's vector binds (multiplies) its letters'
vectors, each rotated by its place; a text's vector bundles (adds) those of its n-grams; a language's
prototype bundles those of its training texts. A text gets the language whose prototype has the
largest cosine with its vector.

Both sides of a cosine are sums over n-grams, so the product of a text with a prototype is the sum of
one table entry per n-gram (n-gram vector times prototype). The table has SLOTS**3 entries a language,
is computed once, and is all that workers need. Random vectors are nearly orthogonal, so a text's
squared length is taken as the dimension times its squared n-gram counts.

Cases: null texts and texts without a letter give ``und`` with score 0; ties go to the alphabetically
first language; without any training row every text is ``und``. Texts of any length are read whole.
Other columns are ignored, so clashing names do no harm.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import text_chunks

SLOTS, PLANE, SLICE = 64, 0x110000, 1_000_000
GRAMS = SLOTS**3
MAX_LANGUAGES = 200  # bounds the table sent to workers: 1 MB a language
_slots: list[np.ndarray] = []


def letter_slots() -> np.ndarray:
    """Slot of each code point: 0 for no letter, 1-26 for a-z, a hashed slot for any other letter."""
    if not _slots:
        t = np.zeros(PLANE + 1, np.uint8)
        for c in range(PLANE):
            if chr(c).isalpha():
                t[c] = c - 96 if 97 <= c <= 122 else 27 + (c * 2654435761 >> 7) % (SLOTS - 27)
        _slots.append(t)
    return _slots[0]


def grams(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Codes of the letter trigrams around each letter (runs of non-letters count as one gap) and the letters' places."""
    cp = np.frombuffer(f" {text} ".lower().encode("utf-32-le", "surrogatepass"), "<u4")
    s = letter_slots()[np.minimum(cp, PLANE)]
    keep = np.flatnonzero((s[1:] != 0) | (s[:-1] != 0)) + 1
    keep = keep if s[0] == 0 else np.concatenate(([0], keep))
    s = s[keep].astype(np.int64)
    s, at = np.concatenate(([0], s, [0])), np.concatenate(([0], keep, [0]))
    mid = np.flatnonzero(s[1:-1]) + 1
    return (s[mid - 1] * SLOTS + s[mid]) * SLOTS + s[mid + 1], at[mid]


def long_counts(text: str) -> np.ndarray:
    """Dense counts of a text of any length, slice by slice; slices are cut at the letter before them and after them."""
    text, total = text.lower(), np.zeros(GRAMS, np.int64)
    for i in range(0, len(text), SLICE):
        lo = max(0, i - 64)
        codes, at = grams(text[lo : i + SLICE + 64])
        own = (at >= i - lo + 1) & (at < i - lo + 1 + min(SLICE, len(text) - i))
        total += np.bincount(codes[own], minlength=GRAMS)
    return total


def chunk_counts(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text number, code, count) rows of all texts, ordered by text."""
    rows, codes = [], []
    short = [t if len(t) <= SLICE else "" for t in texts]
    ends = np.cumsum([len(t.lower()) + 2 for t in short])
    code, at = grams("  ".join(short))
    key = np.searchsorted(ends, at - 1, side="right").astype(np.int64) * GRAMS + code
    key, n = np.unique(key, return_counts=True)
    rows.append(key // GRAMS), codes.append(key % GRAMS)
    counts = [n]
    for i, t in enumerate(texts):
        if len(t) > SLICE:
            c = long_counts(t)
            hit = np.flatnonzero(c)
            rows.append(np.full(len(hit), i)), codes.append(hit), counts.append(c[hit])
    rows, codes, counts = np.concatenate(rows), np.concatenate(codes), np.concatenate(counts)
    order = np.argsort(rows, kind="stable") if len(counts) and len(texts) > 1 else slice(None)
    return rows[order], codes[order], counts[order]


def corpus_counts(docs: DataFrame) -> DataFrame:
    """(lang, code, n) over all rows: each task sums its own first."""

    def run(batches):
        sums: dict[str, np.ndarray] = {}
        for batch, texts in text_chunks(batches):
            langs = np.array(batch.column(1).to_pylist(), object)
            rows, codes, n = chunk_counts(texts)
            for lang in set(langs):
                own = langs[rows] == lang
                total = sums.setdefault(lang, np.zeros(GRAMS, np.int64))
                total += np.bincount(codes[own], n[own], minlength=GRAMS).astype(np.int64)
        for lang, total in sums.items():
            hit = np.flatnonzero(total)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(hit), pa.string()), pa.array(hit, pa.int64()), pa.array(total[hit], pa.int64())], ["lang", "code", "n"])

    rows = docs.filter(F.col("text").isNotNull() & F.col("lang").isNotNull()).select("text", "lang").mapInArrow(run, "lang string, code long, n long")
    return rows.groupBy("lang", "code").agg(F.sum("n").alias("n"))


def prototype_table(counts: np.ndarray, dim: int, seed: int) -> np.ndarray:
    """Product of each n-gram's vector with each language's unit prototype, over sqrt(dim)."""
    letters = np.random.default_rng(seed).choice(np.array([-1, 1], np.float32), (SLOTS, dim))
    first, second = np.roll(letters, 2, 1), np.roll(letters, 1, 1)

    def block(a):  # vectors of all n-grams that begin with slot a
        return (first[a] * second[:, None, :] * letters[None, :, :]).reshape(SLOTS * SLOTS, dim)

    by_first = counts.reshape(len(counts), SLOTS, SLOTS * SLOTS)
    used = [a for a in range(SLOTS) if by_first[:, a].any()]
    proto = sum(by_first[:, a].astype(np.float64) @ block(a) for a in used)
    proto /= np.maximum(np.linalg.norm(proto, axis=1, keepdims=True), 1e-12)
    return np.concatenate([block(a) @ proto.T.astype(np.float32) for a in range(SLOTS)]) / np.float32(np.sqrt(dim))


def fit(docs: DataFrame, dim: int = 1024, seed: int = 11) -> tuple[list[str], np.ndarray]:
    """Languages and their table from all rows that have text and lang."""
    rows = corpus_counts(docs).toArrow()  # at most GRAMS rows a language
    langs = sorted(set(rows.column("lang").to_pylist()))
    if len(langs) > MAX_LANGUAGES:
        raise ValueError(f"{len(langs)} languages; the table that workers get is bounded at {MAX_LANGUAGES}")
    counts = np.zeros((len(langs), GRAMS), np.float32)
    which = {x: i for i, x in enumerate(langs)}
    counts[[which[x] for x in rows.column("lang").to_pylist()], rows.column("code").to_numpy()] = rows.column("n").to_numpy()
    return langs, prototype_table(counts, dim, seed) if langs else np.zeros((GRAMS, 0), np.float32)


def predict(docs: DataFrame, langs: list[str], lookup: np.ndarray) -> DataFrame:
    """doc_id, lang_pred and score of every row of ``docs`` (doc_id, text)."""
    shared = docs.sparkSession.sparkContext.broadcast(lookup)

    def run(batches):
        t = shared.value
        for batch, texts in text_chunks(batches):
            rows, codes, n = chunk_counts(texts)
            cos = np.zeros((len(texts), max(1, len(langs))))
            size = np.bincount(rows, n.astype(float) ** 2, minlength=len(texts))
            for k in range(len(langs)):
                cos[:, k] = np.bincount(rows, n * t[codes, k].astype(float), minlength=len(texts))
            cos /= np.sqrt(np.maximum(size, 1))[:, None]
            best = cos.argmax(1)
            known = (size > 0) & bool(langs)
            pred = [langs[b] if ok else "und" for b, ok in zip(best, known, strict=True)]
            score = np.where(known, np.clip(cos[np.arange(len(texts)), best], 0, 1), 0.0)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(pred, pa.string()), pa.array(score, pa.float64())], ["doc_id", "lang_pred", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, lang_pred string, score double")
