"""Exact top-k inner products by a three-phase uniform threshold.

A score is the sum of the partial scores of PARTS blocks of components, each block a list of its own.
Phase 1 gathers from every list of every shard the KEEP best entries of each query and what the best
entry left behind has, resolves these few in full and takes the k-th best total as a cutoff that is
safe: the answer's totals are no less. Phase 2 holds the cutoff against the lists: an entry below
cutoff/PARTS in all lists cannot reach the cutoff, so a shard whose lists left nothing of at least
that behind has given all that counts; only the others are read again, and only for the queries that
need it. Phase 3 takes the collected entries' totals and keeps those that reach the cutoff. The result
is exact, ties included.

Vectors are packed into shards and queries into blocks of bounded size; every (shard, block) pair is
scored once as integer matrix products. Queries are not broadcast: blocks are dealt to row groups, as
many as the cluster's cores or the shards ask for, and joined with the shards by group.

Cases: null vectors and vectors with a null or non-finite component take no part; vectors of unequal
length are compared over the shorter one's components; repeated vec_ids are separate candidates except
that no row of the query's own id is; empty tables give an empty result; with fewer than k candidates
all are returned; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize

PARTS, SHARD, BLOCK, KEEP = 2, 4096, 1024, 16
LEAST = -(2**63)


def quantize(df: DataFrame, scale: float = 256.0, vec: str = "embedding") -> DataFrame:
    """vec_id and integer components floor(scale * x); unusable vectors are left out."""
    x = F.col(vec).cast("array<double>")
    good = F.col(vec).isNotNull() & (F.size(x) > 0) & ~F.exists(x, lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == float("inf")))
    return df.filter(F.coalesce(good, F.lit(False))).select(F.col("vec_id").cast("long").alias("vec_id"), F.transform(x, lambda v: F.floor(v * F.lit(scale)).cast("long")).alias("q"))


def pack(df: DataFrame, rows: int) -> DataFrame:
    """Rows of up to ``rows`` vectors: their ids, their components as int64 bytes, and the padded length."""

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, rows):
                part = batch.slice(at, rows)
                vs = part.column(1)
                sizes = np.diff(vs.offsets.to_numpy())
                flat = vs.flatten().to_numpy(zero_copy_only=False)
                dim = int(sizes.max())
                m = np.zeros((len(sizes), dim), np.int64)
                m[np.arange(dim)[None, :] < sizes[:, None]] = flat
                yield pa.RecordBatch.from_arrays([pa.array([part.column(0).to_numpy().tobytes()]), pa.array([m.tobytes()]), pa.array([dim], pa.int32())], ["ids", "m", "dim"])

    return df.select("vec_id", "q").mapInArrow(run, "ids binary, m binary, dim int")


def _matrix(ids: bytes, m: bytes, dim: int) -> tuple[np.ndarray, np.ndarray]:
    a = np.frombuffer(ids, np.int64)
    return a, np.frombuffer(m, np.int64).reshape(len(a), dim)


def _product(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Exact integer product: in floats where they hold every sum exactly, else in integers."""
    top = float(np.abs(a).max(initial=0)) * float(np.abs(b).max(initial=0)) * a.shape[1]
    if top < 2**53:
        return (a.astype(np.float64) @ b.T.astype(np.float64)).astype(np.int64)
    return a @ b.T


def _partials(q: np.ndarray, v: np.ndarray) -> list[np.ndarray]:
    dim = min(q.shape[1], v.shape[1])
    cuts = np.linspace(0, dim, PARTS + 1).astype(int)
    return [_product(q[:, a:b], v[:, a:b]) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]


def _own_lists(q, qi, v, vi) -> list[np.ndarray]:
    """Partial scores by list; a query's own row has the least integer."""
    own = qi[:, None] == vi[None, :]
    return [np.where(own, LEAST, p) for p in _partials(q, v)]


def _resolved(parts, rows, cols):
    """Rows, columns and totals of the cells that are no query's own, best first within a row."""
    keep = parts[0][rows, cols] != LEAST
    rows, cols = rows[keep], cols[keep]
    score = sum(p[rows, cols] for p in parts)
    order = np.lexsort((cols, -score, rows))
    return rows[order], cols[order], score[order]


def _gathered(qi, q, vi, v, k: int, keep: int):
    """Phase 1: of each query the kept entries' ids and totals, the k best totals, and the best partial score left behind."""
    parts = _own_lists(q, qi, v, vi)
    n, take = len(vi), min(max(k, keep), len(vi))
    top = [np.argpartition(p, n - take, axis=1)[:, n - take :] for p in parts]
    floor = np.full(len(qi), LEAST)
    if take < n:
        for p, t in zip(parts, top, strict=True):
            rest = p.copy()
            np.put_along_axis(rest, t, LEAST, axis=1)
            floor = np.maximum(floor, rest.max(axis=1))
    key = np.unique(np.repeat(np.arange(len(qi)), take * len(parts)) * n + np.concatenate(top, axis=1).ravel())
    rows, cols, score = _resolved(parts, key // n, key % n)
    cut = np.searchsorted(rows, np.arange(len(qi) + 1))
    return [(vi[cols[a:b]], score[a:b], score[a : min(b, a + k)], int(f)) for a, b, f in zip(cut[:-1], cut[1:], floor, strict=True)]


def _read_again(qi, q, vi, v, cuts: dict[int, int], k: int):
    """Phases 2 and 3 for the queries named: entries of at least cutoff/PARTS in some list whose totals reach the cutoff."""
    some = np.flatnonzero(np.isin(qi, list(cuts)))
    cut = np.array([cuts[int(i)] for i in qi[some]], np.int64)
    parts = _own_lists(q[some], qi[some], v, vi)
    share = -((-cut) // PARTS)  # the least integer of at least cutoff / PARTS
    hits = np.logical_or.reduce([p >= share[:, None] for p in parts])
    rows, cols, score = _resolved(parts, *np.nonzero(hits))
    keep = score >= cut[rows]
    return qi[some][rows[keep]], vi[cols[keep]], score[keep]


def _grouped(shards: DataFrame, blocks: DataFrame, groups: int) -> DataFrame:
    """Every (shard, block) pair once; shards stay where their group is, blocks go to every group."""
    dealt = blocks.withColumn("g", F.explode(F.sequence(F.lit(0), F.lit(groups - 1)).cast("array<long>")))
    return shards.withColumn("g", F.pmod(F.col("shard"), F.lit(groups))).join(dealt.hint("merge"), "g")


def _lists(pairs: DataFrame, k: int, keep: int) -> DataFrame:
    schema = "shard long, block long, query_id long, ids array<long>, scores array<long>, best array<long>, floor long"

    def run(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                shard, block, *cells = (batch.column(c)[i].as_py() for c in range(batch.num_columns))
                (qi, q), (vi, v) = _matrix(*cells[:3]), _matrix(*cells[3:])
                ids, scores, best, floor = zip(*_gathered(qi, q, vi, v, k, keep), strict=True)
                long = pa.list_(pa.int64())
                cols = [pa.array([shard] * len(qi), pa.int64()), pa.array([block] * len(qi), pa.int64()), pa.array(qi, pa.int64()), pa.array(ids, long), pa.array(scores, long), pa.array(best, long), pa.array(floor, pa.int64())]
                yield pa.RecordBatch.from_arrays(cols, ["shard", "block", "query_id", "ids", "scores", "best", "floor"])

    return pairs.select("shard", "block", "qids", "qm", "qdim", "ids", "m", "dim").mapInArrow(run, schema)


def _again(todo: DataFrame, k: int) -> DataFrame:
    def run(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                *cells, asks = (batch.column(c)[i].as_py() for c in range(batch.num_columns))
                (qi, q), (vi, v) = _matrix(*cells[:3]), _matrix(*cells[3:])
                a, b, c = _read_again(qi, q, vi, v, {x["query_id"]: x["cut"] for x in asks}, k)
                yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(c, pa.int64())], ["query_id", "vec_id", "score"])

    return todo.select("qids", "qm", "qdim", "ids", "m", "dim", "asks").mapInArrow(run, "query_id long, vec_id long, score long")


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 5, keep: int = KEEP) -> DataFrame:
    """query_id, rank, vec_id, score of the k best candidates of each query; inputs as ``quantize`` gives them."""
    cores = queries.sparkSession.sparkContext.defaultParallelism
    shards = materialize(pack(vectors, SHARD).withColumn("shard", F.monotonically_increasing_id()), "vector-shards")
    blocks = pack(queries.coalesce(max(1, cores)), BLOCK).select(F.monotonically_increasing_id().alias("block"), F.col("ids").alias("qids"), F.col("m").alias("qm"), F.col("dim").alias("qdim"))
    blocks = materialize(blocks, "query-blocks")
    groups = max(1, min(shards.count(), max(64, 4 * cores)))
    lists = materialize(_lists(_grouped(shards, blocks, groups), k, keep), "vector-lists")
    # the k-th best total of what was gathered; without k of them, everything was
    nth = Window.partitionBy("query_id").orderBy(F.desc("total"))
    best = lists.select("query_id", F.explode("best").alias("total")).withColumn("r", F.row_number().over(nth)).filter(F.col("r") <= k)
    cutoff = best.groupBy("query_id").agg(F.when(F.count("*") >= k, F.min("total")).otherwise(F.lit(LEAST)).alias("cut"))
    held = lists.join(cutoff, "query_id")
    enough = (F.col("floor") == LEAST) | F.expr(f"floor < CASE WHEN cut > 0 THEN (cut + {PARTS - 1}) div {PARTS} ELSE cut div {PARTS} END")
    kept = held.filter(enough).select("query_id", "cut", F.explode(F.arrays_zip("ids", "scores")).alias("e")).select("query_id", "cut", F.col("e.ids").alias("vec_id"), F.col("e.scores").alias("score")).filter("score >= cut").drop("cut")
    todo = held.filter(~enough).groupBy("shard", "block").agg(F.collect_list(F.struct("query_id", "cut")).alias("asks"))
    todo = materialize(todo, "vector-again")
    found = kept
    if todo.limit(1).count():
        found = kept.unionAll(_again(todo.join(blocks, "block").join(shards, "shard"), k))
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
