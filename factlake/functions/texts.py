"""Texts in bounded slices, and word shingles as 64-bit numbers."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame

GOLD = np.uint64(0x9E3779B97F4A7C15)


class WordCodes(dict):
    """Word (bytes) -> 64-bit hash; forgets all words when it has grown to ``most``."""

    def __init__(self, most: int = 300_000):
        self.most = most

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.most:
            self.clear()
        h = self[word] = xxhash.xxh64_intdigest(word)
        return h


def ascii_words(text: str | None) -> list[bytes]:
    """A-Z lower-cased, cut at ASCII white space."""
    return (text or "").encode("utf-8", "surrogatepass").lower().split()


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


def shingle_set(words: list[bytes], size: int, codes: WordCodes) -> np.ndarray:
    """Sorted distinct hashes of the runs of ``size`` words; all words as one run if there are fewer; empty without words."""
    if not words:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(codes.__getitem__, words), np.uint64, len(words))
    k = min(size, len(words))
    total = np.zeros(len(words) - k + 1, np.uint64)
    for i in range(k):
        total = (total + h[i : len(h) - k + 1 + i]) * GOLD
    return np.unique(mix(total + np.uint64(k)))


def overlap(a: np.ndarray, b: np.ndarray) -> int:
    """Size of the intersection of two sorted distinct arrays."""
    if len(a) > len(b):
        a, b = b, a
    if not len(a):
        return 0
    at = np.searchsorted(b, a)
    at[at == len(b)] = len(b) - 1
    return int((b[at] == a).sum())


def similar(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    """Whether 100 * |a & b| >= percent * |a | b|."""
    if 100 * min(len(a), len(b)) < percent * max(len(a), len(b)):
        return False
    both = overlap(a, b)
    return 100 * both >= percent * (len(a) + len(b) - both)


def text_chunks(batches: Iterator[pa.RecordBatch], text_at: str = "text", most: int = 1_000_000) -> Iterator[tuple[pa.RecordBatch, list]]:
    """Slices of Arrow batches of about ``most`` characters each, with their texts (null as ''): bounds a worker's memory."""
    for batch in batches:
        texts = batch.column(batch.schema.get_field_index(text_at)).to_pylist()
        start = size = 0
        for i, text in enumerate(texts):
            size += len(text or "")
            if size >= most:
                yield batch.slice(start, i + 1 - start), [t or "" for t in texts[start : i + 1]]
                start, size = i + 1, 0
        if start < len(texts):
            yield batch.slice(start), [t or "" for t in texts[start:]]


def bucket_counts(sets: DataFrame, buckets: int, segments: int = 64) -> np.ndarray:
    """How many shingles of all ``members`` (packed sets) fall into each bucket of their low bits.

    A task sends its counts as ``segments`` packed rows, whatever it holds, and segments are added up apart.
    """
    size = buckets // segments

    def count(batches):
        total = np.zeros(buckets, np.int64)
        for batch in batches:
            for m in batch.column(0):
                total += np.bincount((np.frombuffer(m.as_buffer(), np.uint64) & np.uint64(buckets - 1)).astype(np.int64), minlength=buckets)
        yield pa.RecordBatch.from_arrays([pa.array(range(segments), pa.int32()), pa.array([total[i * size : (i + 1) * size].tobytes() for i in range(segments)], pa.binary())], ["segment", "counts"])

    def add(t: pa.Table) -> pa.Table:
        total = sum((np.frombuffer(c.as_py(), np.int64) for c in t.column("counts")), np.zeros(size, np.int64))
        return pa.table({"segment": t.column("segment").slice(0, 1), "counts": pa.array([total.tobytes()], pa.binary())})

    rows = sets.select("members").coalesce(4 * sets.sparkSession.sparkContext.defaultParallelism).mapInArrow(count, "segment int, counts binary")
    rows = rows.groupBy("segment").applyInArrow(add, "segment int, counts binary").toArrow().to_pydict()  # ``segments`` rows
    out = np.zeros(buckets, np.int64)
    for i, c in zip(rows["segment"], rows["counts"], strict=True):
        out[i * size : (i + 1) * size] = np.frombuffer(c, np.int64)
    return out
