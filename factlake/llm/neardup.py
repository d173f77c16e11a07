"""Near duplicates by tensored MinHash: pairs that meet in a table, verified on full sets.

A document is the set of its word shingles; two are linked if 100 * |a & b| >= percent * |a | b|.

1. One pass over the texts hashes the shingles and takes 2 * 2 * GROUPS minhashes: two collections of
   GROUPS keys of two minhashes each. GROUPS**2 table keys, one for each pair of a first and a second
   key, come from that many fewer hashes; a pair at similarity 0.8 shares none of them with a chance
   of 2 * 0.36**GROUPS, 2e-7, and is then not found.
2. Equal sets are one class, by a 128-bit hash; only its smallest doc_id goes on.
3. Keys that occur once are dropped before pairs of keys are formed, so only documents with some
   partner in both collections get table keys.
4. Every table has a leader, the member whose keys are the most common; each member is verified against
   its leaders on full sets. Verified links give components.
5. Tables whose other members lie in several components are still open: members outside the table's
   largest component are verified against all members of other components, so every pair that meets
   in a table is either verified or connected already. No other pair is ever looked at.
6. An open table that would form over OPEN pairs is hot. The members of hot tables are compared by an
   exact prefix filter instead: shingles are put in one global order, rare first; a linked pair
   shares a shingle of both prefixes at places that leave room for the overlap. Within a shingle's
   group again only members outside its largest component are compared, and only across components.

Cases: without words a document is in no class and linked with nothing; with fewer words than a
shingle has, all words are one shingle; rows that share a doc_id are one document; null texts are
empty; any length is taken whole; the component's id is its smallest doc_id.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from factlake.functions.texts import WordCodes, ascii_words, bucket_counts, overlap, shingle_set

from .common import materialize, text_chunks

GROUPS, BUCKETS, BROADCAST, OPEN = 16, 1 << 16, 1_000_000, 1024


def _hashes(seed: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(seed)
    n = 4 * GROUPS
    return rng.integers(0, 2**63, n, dtype=np.uint64) * np.uint64(2) + np.uint64(1), rng.integers(0, 2**63, n, dtype=np.uint64)


def signatures(docs: DataFrame, size: int, seed: int) -> DataFrame:
    """doc_id, n_shingles, set_hash and the 2 * GROUPS keys of every row."""
    a, b = _hashes(seed)

    def minhash(s: np.ndarray) -> np.ndarray:
        low = np.full(len(a), np.iinfo(np.uint64).max, np.uint64)
        for at in range(0, len(s), 8192):
            low = np.minimum(low, (s[None, at : at + 8192] * a[:, None] + b[:, None]).min(1))
        return low

    def run(batches):
        codes = WordCodes()
        place = np.arange(2 * GROUPS, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        for batch, texts in text_chunks(batches):
            sizes, hashes, keys = [], [], []
            for t in texts:
                s = shingle_set(ascii_words(t), size, codes)
                sizes.append(len(s))
                if len(s):
                    m = minhash(s)
                    hashes.append(xxhash.xxh3_128_digest(s.tobytes()))
                    keys.append(((m[0::2] ^ place) * np.uint64(0xD6E8FEB86659FD93) + m[1::2]).view(np.int64))
                else:
                    hashes.append(None)
                    keys.append(np.empty(0, np.int64))
            flat, ends = np.concatenate(keys), np.cumsum([0, *map(len, keys)])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sizes, pa.int64()), pa.array(hashes, pa.binary()), pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(flat))], ["doc_id", "n_shingles", "set_hash", "keys"])

    return _narrow(docs).mapInArrow(run, "doc_id long, n_shingles long, set_hash binary, keys array<long>")


def _narrow(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))


def _sets(docs: DataFrame, ids: DataFrame, n: int, size: int) -> DataFrame:
    """rep and its full set, for the ids asked for; so few ids may be broadcast, more are joined by shuffle."""

    def run(batches):
        codes = WordCodes()
        for batch, texts in text_chunks(batches):
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([shingle_set(ascii_words(t), size, codes).tobytes() for t in texts], pa.binary())], ["rep", "members"])

    ids = ids.select(F.col("rep").alias("doc_id"))
    return _narrow(docs).join(F.broadcast(ids) if n <= BROADCAST else ids, "doc_id", "left_semi").mapInArrow(run, "rep long, members binary")


def _links(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (x, y) that are similar enough on full sets."""

    def run(batches):
        for batch in batches:
            x, y = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            keep = []
            for i, (p, q) in enumerate(zip(batch.column(2), batch.column(3), strict=True)):
                a, b = np.frombuffer(p.as_buffer(), np.uint64), np.frombuffer(q.as_buffer(), np.uint64)
                if 100 * min(len(a), len(b)) >= percent * max(len(a), len(b)):
                    both = overlap(a, b)
                    if 100 * both >= percent * (len(a) + len(b) - both):
                        keep.append(i)
            yield pa.RecordBatch.from_arrays([pa.array(x[keep]), pa.array(y[keep])], ["x", "y"])

    left, right = sets.select(F.col("rep").alias("x"), F.col("members").alias("mx")), sets.select(F.col("rep").alias("y"), F.col("members").alias("my"))
    return pairs.join(left, "x").join(right, "y").select("x", "y", "mx", "my").mapInArrow(run, "x long, y long")


def components(edges: DataFrame, name: str = "components") -> DataFrame:
    """node and label (the smallest node that it reaches) of every node in the edges (x, y)."""
    both = materialize(edges.select("x", "y").unionAll(edges.select(F.col("y").alias("x"), F.col("x").alias("y"))).filter("x <> y").distinct(), f"{name}-edges", narrow=True)
    labels = materialize(both.groupBy("x").agg(F.least(F.min("y"), F.first("x")).alias("label")).withColumnRenamed("x", "node"), f"{name}-labels", narrow=True)
    while True:
        seen = both.join(labels.select(F.col("node").alias("y"), "label"), "y").groupBy(F.col("x").alias("node")).agg(F.min("label").alias("near"))
        low = labels.join(seen, "node").select("node", "label", F.least("label", "near").alias("low"))
        low = materialize(low, f"{name}-low", narrow=True)
        jump = low.select(F.col("node").alias("low"), F.col("low").alias("far"))
        new = materialize(low.join(jump, "low", "left").select("node", F.least("low", F.coalesce("far", "low")).alias("label"), (F.least("low", F.coalesce("far", "low")) < F.col("label")).alias("moved")), f"{name}-labels", narrow=True)
        labels = new.select("node", "label")
        if not new.filter("moved").limit(1).count():
            return labels


def _tables(classes: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Representatives with partners in both collections, and (t, n, x, y): members x of table t beside its leader y."""
    keys = classes.select("rep", "n_shingles", F.posexplode("keys").alias("at", "key"))
    busy = keys.groupBy("key").agg(F.count("*").alias("n")).filter("n > 1").select("key", F.col("n"))
    held = keys.join(busy, "key")
    side = lambda first: F.collect_list(F.when((F.col("at") < GROUPS) == first, F.col("key")))
    contested = held.groupBy("rep").agg(F.first("n_shingles").alias("size"), side(True).alias("a"), side(False).alias("b"), F.sum(F.log2("n")).alias("common")).filter((F.size("a") > 0) & (F.size("b") > 0))
    rank = F.least(F.floor(F.col("common") * 64), F.lit(2**18)).cast("long") * F.lit(2**44) + F.xxhash64("rep").bitwiseAND(F.lit(2**44 - 1))
    contested = materialize(contested.select("rep", "size", "a", "b", rank.alias("rank")), "neardup-contested", narrow=True)
    held = contested.select("rep", "rank", "b", F.explode("a").alias("ka")).select("rep", "rank", "ka", F.explode("b").alias("kb")).select("rep", "rank", F.xxhash64("ka", "kb").alias("t"))
    lead = held.groupBy("t").agg(F.max("rank").alias("lead"), F.count("*").alias("n")).filter("n > 1")
    members = held.join(lead, "t").filter("lead <> rank").select("t", "n", F.col("rep").alias("x"), "lead")
    return contested, members.join(contested.select(F.col("rank").alias("lead"), F.col("rep").alias("y")), "lead").select("t", "n", "x", "y")


def _open_members(members: DataFrame, contested: DataFrame, labels: DataFrame) -> DataFrame:
    """t, rep, size, comp, main and hot of the members (without leaders) of tables that several components share."""
    named = contested.select(F.col("rep").alias("x"), "size").join(labels.select(F.col("node").alias("x"), "label"), "x", "left")
    named = named.select("x", "size", F.coalesce("label", "x").alias("comp"))
    rows = members.filter("n > 2").select("t", "x").join(named, "x")
    some = rows.groupBy("t").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).filter("lo < hi").select("t")
    rows = materialize(rows.join(materialize(some, "neardup-open"), "t"), "neardup-open-members", narrow=True)
    sizes = rows.groupBy("t", "comp").agg(F.count("*").alias("k"))
    main = sizes.groupBy("t").agg(F.max_by("comp", "k").alias("main"), F.sum("k").alias("all"), F.max("k").alias("most"))
    main = materialize(main.select("t", "main", ((F.col("all") - F.col("most")) * F.col("all") > OPEN).alias("hot")), "neardup-main", narrow=True)
    return rows.join(main, "t").select("t", F.col("x").alias("rep"), "size", "comp", "main", "hot")


def _pairs_in_tables(rows: DataFrame, percent: int) -> DataFrame:
    """Pairs across components that meet in an open table which is not hot, and whose sizes allow a link."""
    cols = ["rep", "comp", "size"]
    x = rows.filter("NOT hot AND comp <> main").select("t", *(F.col(c).alias(f"{c}_x") for c in cols))
    y = rows.filter("NOT hot").select("t", *(F.col(c).alias(f"{c}_y") for c in cols))
    fits = (F.col("comp_x") != F.col("comp_y")) & (100 * F.least("size_x", "size_y") >= percent * F.greatest("size_x", "size_y"))
    return x.join(y, "t").filter(fits).select(F.least("rep_x", "rep_y").alias("x"), F.greatest("rep_x", "rep_y").alias("y")).distinct()


def _prefixes(sets: DataFrame, percent: int) -> DataFrame:
    """token, rep, size, pos: each set's shingles that can be its first shared one, in the global order."""

    often = bucket_counts(sets, BUCKETS)
    shared = sets.sparkSession.sparkContext.broadcast(often)

    def run(batches):
        often = shared.value
        for batch in batches:
            for rep, m in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                s = np.frombuffer(m.as_buffer(), np.uint64)
                n = len(s)
                k = n - -(-percent * n // 100) + 1
                order = np.lexsort((s, often[(s & np.uint64(BUCKETS - 1)).astype(np.int64)]))[:k]
                yield pa.RecordBatch.from_arrays([pa.array(s[order].view(np.int64)), pa.array(np.full(len(order), rep, np.int64)), pa.array(np.full(len(order), n, np.int64)), pa.array(np.arange(len(order)), pa.int64())], ["token", "rep", "size", "pos"])

    return sets.select("rep", "members").mapInArrow(run, "token long, rep long, size long, pos long")


def _open_pairs(prefixes: DataFrame, labels: DataFrame, percent: int) -> DataFrame:
    """Pairs across components that the prefix, size and place filters leave."""
    rows = prefixes.join(labels.select(F.col("node").alias("rep"), "label"), "rep", "left").withColumn("comp", F.coalesce("label", "rep")).drop("label")
    rows = materialize(rows, "neardup-prefixes")
    sizes = rows.groupBy("token", "comp").agg(F.count("*").alias("n"))
    main = sizes.groupBy("token").agg(F.max_by("comp", F.col("n") * 2.0).alias("main"), F.count("*").alias("comps")).filter("comps > 1").select("token", "main")
    open_ = rows.join(main, "token")
    cols = ["rep", "comp", "size", "pos"]
    x = open_.filter("comp <> main").select("token", *(F.col(c).alias(f"{c}_x") for c in cols))
    y = open_.select("token", *(F.col(c).alias(f"{c}_y") for c in cols))
    need = F.expr(f"(({percent} * (size_x + size_y)) + {99 + percent}) div {100 + percent}")
    fits = (F.col("comp_x") != F.col("comp_y")) & (F.col("pos_x") + need <= F.col("size_x")) & (F.col("pos_y") + need <= F.col("size_y"))
    return x.join(y, "token").filter(fits).select(F.least("rep_x", "rep_y").alias("x"), F.greatest("rep_x", "rep_y").alias("y")).distinct()


def near_duplicates(docs: DataFrame, size: int = 5, percent: int = 80, seed: int = 3) -> DataFrame:
    """doc_id, n_shingles, component_id and kept of every row."""
    sig = materialize(signatures(docs, size, seed), "neardup-signatures")
    classes = materialize(sig.filter("n_shingles > 0").groupBy("set_hash").agg(F.min("doc_id").alias("rep"), F.first("keys").alias("keys"), F.first("n_shingles").alias("n_shingles")), "neardup-classes", narrow=True)
    contested, members = _tables(classes)
    members = materialize(members, "neardup-tables", narrow=True)
    sets = materialize(_sets(docs, contested.select("rep").distinct(), contested.count(), size), "neardup-sets")
    links = materialize(_links(members.select("x", "y").distinct(), sets, percent), "neardup-links", narrow=True)
    labels = components(links)
    still = materialize(_open_members(members, contested, labels), "neardup-still", narrow=True)
    more = _pairs_in_tables(still, percent)
    hot = materialize(still.filter("hot").select("rep").distinct(), "neardup-hot", narrow=True)
    if hot.limit(1).count():
        more = more.unionAll(_open_pairs(_prefixes(sets.join(hot, "rep", "left_semi"), percent), labels, percent)).distinct()
    more = materialize(_links(more, sets, percent), "neardup-more", narrow=True)
    if more.limit(1).count():
        labels = components(links.unionAll(more))
    named = classes.select("set_hash", "rep").join(labels.select(F.col("node").alias("rep"), "label"), "rep", "left").select("set_hash", F.coalesce("label", "rep").alias("label"))
    out = sig.select("doc_id", "n_shingles", "set_hash").join(materialize(named, "neardup-named", narrow=True), "set_hash", "left")
    comp = F.coalesce("label", "doc_id")
    return out.select("doc_id", "n_shingles", comp.alias("component_id"), (F.col("doc_id") == comp).alias("kept"))
