"""Benchmark decontamination: every training passage is a query against a BM25 index of test items.

Texts are cut into windows of 2L words every L words (L: words of the longest item), so an item that a
text holds lies whole in some window. An item's threshold is the least BM25 score that a window can
have which still holds ``coverage`` of the item's five-word shingles: its score against itself less
its heaviest words, one per shingle that may be missing. No item above the threshold is lost.

Retrieval is block-max WAND in batch form. Words common among the items are set aside as long as an
item's share of them stays under half its threshold; the rest decide. Items stand in blocks with a
maximum per word; a block whose maxima over a window's deciding words cannot reach the threshold is
skipped, the others are scored in full. What is above its threshold is verified: ``coverage`` of the
item's shingles, ``question`` of the words of its question part and ``answer`` of the words of its
answer (its last sentence, or last quarter) near the shared shingles.

The index is sent to workers; items are taken in shards of at most SHARD_CHARS characters, one pass
over the texts each, so its size is bounded however large the benchmark.

Cases: null and empty texts and items match nothing; items of fewer than five words are one shingle;
repeated items are reported each under its id, repeated documents too; ties between windows go to the
first; other columns are ignored.
"""

from __future__ import annotations

import re
from collections import Counter
from math import ceil, log

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import text_chunks

WORD = re.compile(r"[^\W_]+")
SENTENCE = re.compile(r"[.?!]\s+(?=\S*\w)")
K1, B, SHINGLE, BLOCK, SHARD_CHARS, SHARE = 1.2, 0.75, 5, 16, 20_000_000, 0.5
SCHEMA = "doc_id long, item_id long, score double, coverage double, question double, answer double, first_word long, last_word long"


def words(text: str | None) -> list[str]:
    return WORD.findall((text or "").lower())


def split_item(text: str) -> tuple[list[str], list[str]]:
    """Question and answer words of an item."""
    cut = [m.end() for m in SENTENCE.finditer(text)]
    q, a = words(text[: cut[-1]] if cut else ""), words(text[cut[-1] :] if cut else "")
    if not q or not a:
        w = words(text)
        n = max(1, len(w) // 4)
        q, a = w[:-n] or w, w[-n:]
    return q, a


def shingles(w: list[str]) -> list[tuple]:
    return list(zip(*(w[i:] for i in range(SHINGLE)), strict=False)) if len(w) >= SHINGLE else [tuple(w)] if w else []


def build(items: list[tuple[int, str]], coverage: float) -> dict | None:
    """The index as plain arrays and lists."""
    kept = [(i, *split_item(t)) for i, t in items if words(t)]
    if not kept:
        return None
    ids, texts = [k[0] for k in kept], [k[1] + k[2] if k[1] != k[2] else k[1] for k in kept]
    n, length = len(kept), max(map(len, texts))
    mean = sum(map(len, texts)) / n
    df = Counter(t for w in texts for t in set(w))
    idf = {t: log(1 + (n - d + 0.5) / (d + 0.5)) for t, d in df.items()}
    post: dict[str, list[tuple[int, float]]] = {}
    theta = []
    for i, w in enumerate(texts):
        tf, norm = Counter(w), K1 * (1 - B + B * len(w) / mean)
        score = {t: idf[t] * c * (K1 + 1) / (c + norm) for t, c in tf.items()}
        k = len(shingles(w))
        lost = k - max(1, ceil(round(coverage * k, 9)))
        theta.append(max(1e-9, sum(score.values()) - sum(sorted(score.values())[::-1][:lost])))
        for t, s in score.items():
            post.setdefault(t, []).append((i, s / theta[-1]))
    aside, common = np.zeros(n), set()
    for t in sorted(df, key=lambda t: (-df[t], t)):
        at, u = np.array([p[0] for p in post[t]]), np.array([p[1] for p in post[t]])
        if (aside[at] + u <= SHARE).all():
            aside[at] += u
            common.add(t)
    order = sorted(df, key=lambda t: (t in common, t))
    deciding, blocks = len(df) - len(common), -(-n // BLOCK)
    iptr, iidx, ival, bptr, bidx, bval = [0], [], [], [0], [], []
    for t in order:
        most: dict[int, float] = {}
        for i, u in post[t]:
            iidx.append(i), ival.append(u)
            most[i // BLOCK] = max(most.get(i // BLOCK, 0), u)
        iptr.append(len(iidx))
        if len(bptr) <= deciding:
            bidx += most
            bval += most.values()
            bptr.append(len(bidx))
    need = np.array([1 - aside[b * BLOCK : (b + 1) * BLOCK].max() for b in range(blocks)]) - 1e-9
    arrays = {k: np.array(v, float if k.endswith("val") else np.int64) for k, v in {"iptr": iptr, "iidx": iidx, "ival": ival, "bptr": bptr, "bidx": bidx, "bval": bval}.items()}
    return arrays | {"ids": ids, "question": [k[1] for k in kept], "answer": [k[2] for k in kept], "texts": texts, "theta": np.array(theta), "need": need, "length": length, "deciding": deciding, "vocabulary": {t: i for i, t in enumerate(order)}}


def _spread(ptr: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each row, the indices of its postings: (which row, index)."""
    n = ptr[rows + 1] - ptr[rows]
    which = np.repeat(np.arange(len(rows)), n)
    return which, np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + ptr[rows][which]


def windows_above(x: dict, docs: list[list[str]]):
    """(document number, first word, last word, item number, normalised score) of every window above an item's threshold."""
    get, length, terms = x["vocabulary"].get, x["length"], len(x["vocabulary"])
    sizes = np.array([len(w) for w in docs], np.int64)
    ids = np.fromiter((get(w, terms) for d in docs for w in d), np.int64, int(sizes.sum()))
    start = np.cumsum(sizes) - sizes
    count = np.maximum(1, -(-sizes // length) - 1)
    base = np.cumsum(count) - count
    hit = np.flatnonzero(ids < x["deciding"])
    doc = np.searchsorted(start, hit, side="right") - 1
    own = (hit - start[doc]) // length
    win, term = [], []
    for step in (0, 1):
        j = own - step
        ok = (j >= 0) & (j < count[doc])
        win.append(base[doc[ok]] + j[ok]), term.append(ids[hit[ok]])
    key = np.unique(np.concatenate(win) * terms + np.concatenate(term))
    win, term = key // terms, key % terms
    which, at = _spread(x["bptr"], term)
    blocks = len(x["need"])
    cell, back = np.unique(win[which] * blocks + x["bidx"][at], return_inverse=True)
    bound = np.bincount(back, x["bval"][at], minlength=len(cell))
    cell = cell[bound >= x["need"][cell % blocks]]
    for w in np.unique(cell // blocks):
        d = int(np.searchsorted(base, w, side="right") - 1)
        lo = int((w - base[d]) * length)
        hi = int(min(sizes[d], lo + 2 * length))
        t = np.unique(ids[start[d] + lo : start[d] + hi])
        _, at = _spread(x["iptr"], t[t < terms])
        score = np.bincount(x["iidx"][at], x["ival"][at], minlength=len(x["ids"]))
        alive = np.isin(np.arange(len(score)) // BLOCK, cell[cell // blocks == w] % blocks)
        for i in np.flatnonzero((score >= 1 - 1e-9) & alive):
            yield d, lo, hi, int(i), float(score[i])


def verify(window: list[str], item: list[str], question: list[str], answer: list[str]) -> tuple[float, float, float, int, int]:
    """Coverage of the item's shingles, question and answer overlap, and where the shared shingles lie."""
    where: dict[tuple, int] = {}
    for p, s in enumerate(shingles(window) if len(item) >= SHINGLE else zip(*(window[i:] for i in range(len(item))), strict=False)):
        where.setdefault(s, p)
    found = [where[s] for s in shingles(item) if s in where]
    if not found:
        return 0.0, 0.0, 0.0, 0, 0
    lo, hi = min(found), max(found) + min(SHINGLE, len(item))
    near = set(window[max(0, lo - SHINGLE) : hi + SHINGLE])
    share = lambda w: len(near & set(w)) / len(set(w))
    return len(found) / len(shingles(item)), share(question), share(answer), lo, hi


def find(docs: DataFrame, items: DataFrame, coverage: float = 0.8, question: float = 0.8, answer: float = 0.5) -> DataFrame:
    """One row per document and item that it holds: the best window's figures and its words' places."""
    spark = docs.sparkSession
    items = items.filter("item_id IS NOT NULL AND text IS NOT NULL").select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text"))
    shards = -(-(items.agg(F.sum(F.length("text"))).first()[0] or 0) // SHARD_CHARS)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    out = spark.createDataFrame([], SCHEMA)
    for k in range(shards):
        part = items.filter(F.pmod(F.xxhash64("item_id"), F.lit(shards)) == k)
        index = build([(r["item_id"], r["text"]) for r in part.orderBy("item_id", "text").collect()], coverage)
        if index:
            out = out.unionAll(_scan(texts, index, coverage, question, answer)) if k else _scan(texts, index, coverage, question, answer)
    return out


def _scan(texts: DataFrame, index: dict, coverage: float, question: float, answer: float) -> DataFrame:
    shared = texts.sparkSession.sparkContext.broadcast(index)

    def run(batches):
        x = shared.value
        for batch, chunk in text_chunks(batches):
            docs = [words(t) for t in chunk]
            ids = batch.column(0).to_pylist()
            best: dict[tuple[int, int], tuple] = {}
            for d, lo, hi, i, score in windows_above(x, docs):
                c, q, a, s, e = verify(docs[d][lo:hi], x["texts"][i], x["question"][i], x["answer"][i])
                if c >= coverage - 1e-9 and q >= question - 1e-9 and a >= answer - 1e-9 and c > best.get((d, i), (0,))[0]:
                    best[d, i] = (c, q, a, lo + s, lo + e - 1, score * x["theta"][i])
            rows = [(ids[d], x["ids"][i], v[5], v[0], v[1], v[2], v[3], v[4]) for (d, i), v in sorted(best.items())]
            cols = list(zip(*rows, strict=True)) or [()] * 8
            names = ["doc_id", "item_id", "score", "coverage", "question", "answer", "first_word", "last_word"]
            types = [pa.int64()] * 2 + [pa.float64()] * 4 + [pa.int64()] * 2
            yield pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(cols, types, strict=True)], names)

    return texts.mapInArrow(run, SCHEMA)
