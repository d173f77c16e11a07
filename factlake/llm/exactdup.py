"""Removal of repeated 100-byte strings, exactly, over a whole corpus.

A byte goes if some WIDTH-byte window over it also starts earlier: in a smaller doc_id, or earlier in
the same document. Nothing is decided on a sample.

1. Copies of whole texts are found by their 128-bit hash; only the first goes on.
2. Every window has an anchor (``anchors``); runs of windows with one anchor are compared by the hash of
   all bytes under the run. Within a group of equal anchors, equal runs form classes; all members but
   the earliest lose all their windows. Tasks merge their own classes before anything is sent, so a run
   that a third of all documents hold is sent once a task.
3. Where a group has several classes, only those that could share a window go on: a common window holds
   34 bytes left of the anchor, or 34 to its right, so one of two half-context hashes must repeat.
4. For these, the bytes under the classes' windows become a text with one symbol for every LONG-byte
   string, a stretch for each class and half-context; strings that occur once part it. Its suffix array
   is built by linear grouping (``suffixes``). Neighbours in its order whose common prefix has NEED
   symbols begin with the same WIDTH bytes, so the intervals of the array with at least that common
   prefix are the repeats; of each interval all starts but the earliest are removed. Groups of many
   classes are dealt out by what their windows begin with.

Strings are compared by 64-bit hashes, runs by 48 more bits beside their anchor's 64. Packed arrays
are sent rather than rows.

Cases: null texts are empty; texts under WIDTH bytes keep every byte; rows that share a doc_id are one
document as regards order (neither is earlier), each keeping its own text; overlapping repeats count;
texts of any length are taken whole, in slices that overlap; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .anchors import GRAM, SLICE, WIDTH, Sums, runs, spread
from .common import materialize, text_chunks
from .suffixes import suffix_array

HALF = (WIDTH - GRAM) // 2
LONG = 96  # bytes of a symbol
NEED = WIDTH - LONG + 1  # symbols of a window
PART_BYTES, FLUSH, GROUP, BROADCAST = 8_000_000, 300_000, 4096, 1_000_000
AT_ONCE = 100_000  # symbols of whole groups whose suffix array is built at a time
RUN = np.dtype([("h", "<u8"), ("ctx", "<u4"), ("ctx2", "<u2"), ("left", "<u2"), ("right", "<u2"), ("doc", "<i8"), ("tag", "<i8"), ("at", "<i4"), ("slice", "<i4"), ("first", "u1"), ("last", "u1")])
ASK = np.dtype([("h", "<u8"), ("slice", "<i4"), ("lo", "<i4"), ("hi", "<i4"), ("salts", "<i4")])
SYMBOL = np.dtype([("h", "<u8"), ("w", "<u8"), ("doc", "<i8"), ("tag", "<i8"), ("at", "<i8"), ("start", "u1")])
COVER = np.dtype([("lo", "<i8"), ("hi", "<i8")])
FOUND = "part int, doc_id long, tag long, kind int, data binary"
STEP = SLICE - WIDTH + 1


def _text(docs: DataFrame) -> DataFrame:
    t = F.coalesce(F.col("text").cast("string"), F.lit(""))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), t.alias("text"), F.xxhash64(t).alias("tag"))


def _utf8(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8)


def text_runs(data: np.ndarray, doc: int, tag: int) -> Iterator[np.ndarray]:
    """The runs of a text, slice by slice."""
    for k, lo in enumerate(range(0, max(0, len(data) - WIDTH + 1), STEP)):
        part = data[lo : lo + SLICE]
        sums, at, first, last = runs(part)
        out = np.zeros(len(at), RUN)
        out["h"] = spread(sums.hash(at, at + GRAM))  # anchors have small hashes: spread them anew
        ctx = sums.hash(first, last + WIDTH) ^ ((at - first).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
        out["ctx"], out["ctx2"] = ctx & np.uint64(0xFFFFFFFF), (ctx >> np.uint64(32)) & np.uint64(0xFFFF)
        # windows that begin HALF or more before the anchor hold its left half-context, the others its right one
        out["left"] = np.where(at - first >= HALF, sums.hash(np.maximum(at - HALF, 0), at + GRAM) >> np.uint64(48), 0)
        out["right"] = np.where(at - last < HALF, sums.hash(at, np.minimum(at + GRAM + HALF, len(part))) >> np.uint64(48), 0)
        out["doc"], out["tag"], out["at"], out["slice"], out["first"], out["last"] = doc, tag, at, k, at - first, at - last
        yield out


def _spans(rows: np.ndarray) -> np.ndarray:
    out = np.zeros(len(rows), COVER)
    at = rows["at"].astype(np.int64) + rows["slice"].astype(np.int64) * STEP
    out["lo"], out["hi"] = at - rows["first"], at - rows["last"]
    return out


def _changes(*columns: np.ndarray) -> np.ndarray:
    """Where a sorted table's key changes: first row of each key."""
    n = len(columns[0])
    new = np.ones(n, bool)
    if n:
        new[1:] = np.logical_or.reduce([c[1:] != c[:-1] for c in columns])
    return np.flatnonzero(new)


def _classes(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted by class and place: which rows are their class's first, and which lie strictly after it."""
    order = np.lexsort((rows["at"], rows["slice"], rows["doc"], rows["ctx2"], rows["ctx"], rows["h"]))
    rows = rows[order]
    start = _changes(rows["h"], rows["ctx"], rows["ctx2"])
    lead = np.repeat(start, np.diff(np.append(start, len(rows))))
    later = (rows["doc"] != rows["doc"][lead]) | (rows["at"] != rows["at"][lead]) | (rows["slice"] != rows["slice"][lead])
    return rows, later


def _by_doc(doc: np.ndarray, tag: np.ndarray, data: np.ndarray, kind: int) -> Iterator[tuple]:
    if len(data):
        order = np.lexsort((tag, doc))
        doc, tag, data = doc[order], tag[order], data[order]
        start = _changes(doc, tag)
        for a, b in zip(start, np.append(start[1:], len(doc)), strict=True):
            yield 0, int(doc[a]), int(tag[a]), kind, data[a:b].tobytes()


def _merged(spans: np.ndarray) -> np.ndarray:
    """Window ranges, those that touch as one."""
    spans = np.sort(spans, order=("lo", "hi"))
    if not len(spans):
        return spans
    reach = np.maximum.accumulate(spans["hi"])
    start = np.flatnonzero(np.concatenate(([True], spans["lo"][1:] > reach[:-1] + 1)))
    out = np.zeros(len(start), COVER)
    out["lo"], out["hi"] = spans["lo"][start], reach[np.append(start[1:], len(spans)) - 1]
    return out


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    part, doc, tag, kind, data = zip(*rows, strict=True) if rows else ((),) * 5
    return pa.RecordBatch.from_arrays([pa.array(part, pa.int32()), pa.array(doc, pa.int64()), pa.array(tag, pa.int64()), pa.array(kind, pa.int32()), pa.array(data, pa.binary())], ["part", "doc_id", "tag", "kind", "data"])


def _dealt(rows: np.ndarray, key: np.ndarray, parts: int, kind: int) -> Iterator[tuple]:
    """Packed rows by part of the key's upper bits; rows must be sorted by key."""
    part = ((key >> np.uint64(32)) * np.uint64(parts)) >> np.uint64(32)
    start = _changes(part)
    for a, b in zip(start, np.append(start[1:], len(rows)), strict=True):
        yield int(part[a]), 0, 0, kind, rows[a:b].tobytes()


def _send_runs(texts: DataFrame, parts: int) -> DataFrame:
    """Packed runs by part (kind 0), and what a task already knows to be covered (kind 1)."""

    def flush(held):
        rows, later = _classes(np.concatenate(held))
        yield _batch([(int(d) % parts, d, t, k, x) for _, d, t, k, x in _by_doc(rows["doc"][later], rows["tag"][later], _spans(rows[later]), 1)])
        rows = rows[~later]
        yield _batch(list(_dealt(rows, rows["h"], parts, 0)))

    def run(batches):
        held, n = [], 0
        for batch, chunk in text_chunks(batches):
            for doc, tag, t in zip(batch.column(0).to_pylist(), batch.column(2).to_pylist(), chunk, strict=True):
                for r in text_runs(_utf8(t), doc, tag):
                    held.append(r)
                    n += len(r)
                    if n >= FLUSH:
                        yield from flush(held)
                        held, n = [], 0
        if held:
            yield from flush(held)

    return texts.select("doc_id", "text", "tag").mapInArrow(run, FOUND)


def _part_by_part(batches, dtype, kind: int, solve):
    """Rows of other kinds as they are; packed rows of ``kind`` gathered by part (they come sorted) and solved."""
    part, held = None, []
    for batch in batches:
        if not batch.num_rows:
            continue
        kinds = batch.column(3).to_numpy()
        if (kinds != kind).any():
            yield batch.filter(pa.array(kinds != kind))
        for p, k, data in zip(batch.column(0).to_pylist(), kinds, batch.column(4), strict=True):
            if k == kind:
                if p != part and held:
                    yield _batch(list(solve(np.concatenate(held))))
                    held = []
                part = p
                held.append(np.frombuffer(data.as_buffer(), dtype).copy())
    if held:
        yield _batch(list(solve(np.concatenate(held))))


def _solve_runs(rows: np.ndarray) -> Iterator[tuple]:
    """Covered window ranges of classes' later members (kind 1); classes to look into (kind 2)."""
    rows, later = _classes(rows)
    yield from _by_doc(rows["doc"][later], rows["tag"][later], _spans(rows[later]), 1)
    rows = rows[~later]
    rows = rows[_changes(rows["h"], rows["ctx"], rows["ctx2"], rows["doc"], rows["tag"], rows["slice"], rows["at"])]

    for side, has, lo, hi in (
        ("left", rows["first"] >= HALF, rows["at"] - rows["first"], rows["at"] - np.maximum(rows["last"], HALF)),
        ("right", rows["last"] < HALF, rows["at"] - np.minimum(rows["first"], HALF - 1), rows["at"] - rows["last"]),
    ):
        own, lo, hi = rows[has], lo[has], hi[has]
        key = spread(own["h"] ^ spread(own[side].astype(np.uint64) + np.uint64(1 if side == "left" else 1 << 20)))
        _, back, n = np.unique(key, return_inverse=True, return_counts=True)
        busy = n[back] > 1
        ask = np.zeros(int(busy.sum()), ASK)
        ask["h"], ask["slice"], ask["lo"], ask["hi"], ask["salts"] = key[busy], own["slice"][busy], lo[busy], hi[busy], 1 + n[back][busy] // GROUP
        yield from _by_doc(own["doc"][busy], own["tag"][busy], ask, 2)


def _places(lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Every place of the ranges lo..hi: (which range, place)."""
    size = hi.astype(np.int64) - lo + 1
    which = np.repeat(np.arange(len(lo)), size)
    return which, lo[which].astype(np.int64) + np.arange(len(which)) - np.repeat(np.cumsum(size) - size, size)


def _send_windows(asked: DataFrame, parts: int) -> DataFrame:
    """The symbols of the windows asked for, packed by part of group and salt (kind 3)."""

    def flush(held):
        rows = np.concatenate(held)
        rows = rows[np.argsort(rows["h"], kind="stable")]
        yield _batch(list(_dealt(rows, rows["h"], parts, 3)))

    def run(batches):
        held, n = [], 0
        for batch, chunk in text_chunks(batches):
            for doc, tag, asks, t in zip(batch.column(0).to_pylist(), batch.column(2).to_pylist(), batch.column(3).to_pylist(), chunk, strict=True):
                ask = np.concatenate([np.frombuffer(a, ASK) for a in asks])
                data = _utf8(t)
                for k in np.unique(ask["slice"]):
                    part = data[int(k) * STEP : int(k) * STEP + SLICE]
                    sums, own = Sums(part), ask[ask["slice"] == k]
                    # windows lo..hi begin with the symbols lo..hi and need NEED - 1 more behind them
                    whole = own["salts"] == 1
                    which, at = _places(own["lo"], own["hi"] + np.where(whole, NEED - 1, 0))
                    start = at <= own["hi"][which]
                    salt = sums.hash(at, at + LONG) % own["salts"][which].astype(np.uint64)
                    if not whole.all():  # the windows of groups that are dealt out go each with its own symbols
                        alone = ~whole[which]
                        more = np.flatnonzero(alone)
                        each, step = np.repeat(more, NEED - 1), np.tile(np.arange(1, NEED), len(more))
                        which, at = np.concatenate((which, which[each])), np.concatenate((at, at[each] + step))
                        start, salt = np.concatenate((start, np.zeros(len(each), bool))), np.concatenate((salt, salt[each]))
                    out = np.zeros(len(at), SYMBOL)
                    out["w"] = sums.hash(at, at + LONG)
                    out["h"] = own["h"][which] + salt * np.uint64(0x9E3779B97F4A7C15)
                    out["doc"], out["tag"], out["at"], out["start"] = doc, tag, at + int(k) * STEP, start
                    held.append(out)
                    n += len(out)
                    if n >= FLUSH:
                        yield from flush(held)
                        held, n = [], 0
        if held:
            yield from flush(held)

    return asked.select("doc_id", "text", "tag", "asks").mapInArrow(run, FOUND)


def repeated_starts(text: np.ndarray, need: int) -> tuple[np.ndarray, np.ndarray]:
    """Suffixes in the array's order that share ``need`` symbols with a neighbour, none of them 0, and the number of their interval."""
    sa = np.array(suffix_array(text.tolist()), np.int64)
    padded = np.append(text, np.zeros(need, text.dtype))
    alike = np.zeros(len(sa), bool)  # whether a suffix shares them with the one before
    near = np.arange(1, len(sa))
    for j in range(need):
        a, b = padded[sa[near] + j], padded[sa[near - 1] + j]
        near = near[(a == b) & (a > 0)]
    alike[near] = True
    held = alike.copy()
    held[:-1] |= alike[1:]
    return sa[held], np.cumsum(~alike)[held]


def _solve_windows(rows: np.ndarray) -> Iterator[tuple]:
    """Windows that also start earlier, by intervals of the suffix array of the groups' symbols (kind 1)."""
    rows = rows[np.argsort(rows["h"], kind="stable")]
    cut = np.append(_changes(rows["h"]), len(rows))
    lo = 0
    for hi in cut[1:].tolist():
        if hi - lo >= AT_ONCE or hi == len(rows):
            yield from _solve_groups(rows[lo:hi])
            lo = hi


def _solve_groups(rows: np.ndarray) -> Iterator[tuple]:
    """The same of the symbols of whole groups."""
    order = np.lexsort((rows["at"], rows["doc"], rows["tag"], rows["h"]))
    rows = rows[order]
    # one row a place: it is a start if any window asked for starts there
    first = _changes(rows["h"], rows["tag"], rows["doc"], rows["at"])
    start = np.maximum.reduceat(rows["start"], first) > 0 if len(rows) else np.zeros(0, bool)
    rows = rows[first]
    _, symbol, n = np.unique(rows["w"] ^ (rows["h"] * np.uint64(0xD6E8FEB86659FD93)), return_inverse=True, return_counts=True)
    keep = n[symbol] > 1
    rows, symbol, start = rows[keep], symbol[keep] + 1, start[keep]
    if not len(rows):
        return
    # stretches of neighbouring places, set apart by the least symbol
    broken = np.flatnonzero((rows["h"][1:] != rows["h"][:-1]) | (rows["doc"][1:] != rows["doc"][:-1]) | (rows["tag"][1:] != rows["tag"][:-1]) | (rows["at"][1:] != rows["at"][:-1] + 1)) + 1
    where = np.insert(np.arange(len(rows)), broken, -1)
    at, group = repeated_starts(np.insert(symbol, broken, 0), NEED)
    own = where[at]
    at, group = own[start[own]], group[start[own]]
    rows = rows[at]
    # of an interval, the earliest start stays
    rank = np.lexsort((rows["at"], rows["doc"], group))
    begin = _changes(group[rank])
    lead = np.zeros(len(rows), np.int64)
    lead[rank] = np.repeat(rank[begin], np.diff(np.append(begin, len(rows))))
    later = (rows["doc"] != rows["doc"][lead]) | (rows["at"] != rows["at"][lead])
    out = np.zeros(int(later.sum()), COVER)
    out["lo"] = out["hi"] = rows["at"][later]
    doc, tag = rows["doc"][later], rows["tag"][later]
    for p, d, t, k, x in _by_doc(doc, tag, out, 1):
        yield p, d, t, k, _merged(np.frombuffer(x, COVER)).tobytes()


def _solved(sent: DataFrame, parts: int, dtype, kind: int, solve) -> DataFrame:
    """Each part in one piece; a task takes one or more parts, one after the other."""
    return sent.repartition(parts, "part").sortWithinPartitions("part").mapInArrow(lambda batches: _part_by_part(batches, dtype, kind, solve), FOUND)


def _only(docs: DataFrame, ids: DataFrame, how: str) -> DataFrame:
    """Semi or anti join on doc_id; ids of a checked size are broadcast."""
    return docs.join(F.broadcast(ids) if ids.count() <= BROADCAST else ids, "doc_id", how)


def covered(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Ids and tags of copies of whole texts, and (doc_id, tag, spans): ranges of windows that also start earlier."""
    texts = _text(docs)
    narrow = materialize(texts.select("doc_id", "tag", F.md5("text").alias("md5"), F.octet_length("text").cast("long").alias("n")).filter(F.col("n") >= WIDTH), "exactdup-hashes")
    # written first, so that the join below reads both sides from a shuffle and a hot hash can be split
    many = materialize(narrow.groupBy("md5").agg(F.min("doc_id").alias("first"), F.count("*").alias("k")).filter("k > 1"), "exactdup-many", narrow=True)
    copies = materialize(narrow.join(many, "md5").filter("doc_id > first").select("doc_id", "tag").distinct(), "exactdup-copies")
    total = narrow.agg(F.sum("n")).first()[0] or 0
    parts = max(12, -(-total // PART_BYTES))
    own = _only(texts, copies.select("doc_id").distinct(), "left_anti") if not _shared_ids(narrow) else texts.join(copies, ["doc_id", "tag"], "left_anti")
    found = materialize(_solved(_send_runs(own, parts), parts, RUN, 0, _solve_runs), "exactdup-runs")
    asks = materialize(found.filter("kind = 2").groupBy("doc_id", "tag").agg(F.collect_list("data").alias("asks")), "exactdup-asks")
    asked = _only(texts, asks.select("doc_id").distinct(), "left_semi").join(asks, ["doc_id", "tag"])
    more = _solved(_send_windows(asked, parts), parts, SYMBOL, 3, _solve_windows)
    spans = found.filter("kind = 1").select("doc_id", "tag", "data").unionAll(more.select("doc_id", "tag", "data"))
    return copies, materialize(spans.groupBy("doc_id", "tag").agg(F.collect_list("data").alias("spans")), "exactdup-spans")


def _shared_ids(narrow: DataFrame) -> bool:
    """Whether rows with different texts share a doc_id."""
    return bool(narrow.groupBy("doc_id").agg(F.min("tag").alias("a"), F.max("tag").alias("b")).filter("a <> b").limit(1).count())


def kept_bytes(data: bytes, spans: np.ndarray) -> tuple[bytes, int, int]:
    """The bytes that stay, how many go, and in how many runs."""
    spans = np.sort(spans, order=("lo", "hi"))
    lo, end = spans["lo"], np.maximum.accumulate(spans["hi"] + WIDTH)
    start = np.flatnonzero(np.concatenate(([True], lo[1:] > end[:-1])))
    a, b = lo[start], end[np.append(start[1:], len(spans)) - 1]
    pieces, at = [], 0
    for x, y in zip(a.tolist(), b.tolist(), strict=True):
        pieces.append(data[at:x])
        at = y
    pieces.append(data[at:])
    return b"".join(pieces), int((b - a).sum()), len(a)


def deduplicate(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 and kept (the remaining bytes) of every row."""
    copies, spans = covered(docs)
    texts = _text(docs)
    touched = materialize(copies.select("doc_id").unionAll(spans.select("doc_id")).distinct(), "exactdup-touched")
    n = F.octet_length("text").cast("long")
    plain = _only(texts, touched, "left_anti").select("doc_id", n.alias("n_bytes"), F.lit(0).cast("long").alias("n_removed"), F.lit(0).cast("long").alias("n_spans"), F.sha2(F.col("text").cast("binary"), 256).alias("kept_sha256"), F.col("text").cast("binary").alias("kept"))

    def run(batches):
        for batch, chunk in text_chunks(batches):
            rows = []
            for doc, copy, spans, t in zip(batch.column(0).to_pylist(), batch.column(2).to_pylist(), batch.column(3).to_pylist(), chunk, strict=True):
                data = t.encode("utf-8", "surrogatepass")
                if copy and len(data) >= WIDTH:
                    kept, gone, k = b"", len(data), 1
                elif spans:
                    kept, gone, k = kept_bytes(data, np.concatenate([np.frombuffer(s, COVER) for s in spans]))
                else:
                    kept, gone, k = data, 0, 0
                rows.append((doc, len(data), gone, k, hashlib.sha256(kept).hexdigest(), kept))
            cols = zip(*rows, strict=True)
            types = [pa.int64()] * 4 + [pa.string(), pa.binary()]
            yield pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(cols, types, strict=True)], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])

    cut = _only(texts, touched, "left_semi").join(copies.withColumn("copy", F.lit(True)), ["doc_id", "tag"], "left").join(spans, ["doc_id", "tag"], "left")
    cut = cut.select("doc_id", "text", F.coalesce("copy", F.lit(False)).alias("copy"), "spans").mapInArrow(run, plain.schema)
    return plain.unionAll(cut)
