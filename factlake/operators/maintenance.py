"""The background pass: contradictions, dependency edges, ripples of changes, guards."""

from __future__ import annotations

from collections.abc import Callable
from math import ceil

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from factlake.functions.texts import WordCodes, overlap, shingle_set, text_chunks
from factlake.operators import lifecycle as L
from factlake.params import Params
from factlake.sources.scratch import materialize

P = Params()
BUCKETS, BROADCAST, BLOCK = 1 << 16, 1_000_000, 1 << 25
SEGMENTS, SLOTS, SENT = 256, 1 << 30, 1 << 23


def harmonic(hop: Column, strength: float = P.ripple) -> Column:
    return F.lit(strength) / (hop + 1)


def exponential(hop: Column, strength: float = P.ripple) -> Column:
    return F.lit(strength) * F.pow(F.lit(0.5), hop)


def constant(hop: Column, strength: float = P.ripple) -> Column:
    return F.lit(strength) + hop * 0.0


def by_table(strengths: list[float]) -> Callable[[Column], Column]:
    """A kernel that reads a hop's strength from a table; none beyond its end."""
    return lambda hop: F.coalesce(F.try_element_at(F.array(*map(F.lit, strengths)), (hop + 1).cast("int")), F.lit(0.0))


def capped(edges: DataFrame, fan_out: int) -> DataFrame:
    """At most ``fan_out`` dependents of each unit, the first by id: a guard against hubs."""
    w = Window.partitionBy("dst").orderBy("src")
    return edges.withColumn("n", F.row_number().over(w)).filter(F.col("n") <= fan_out).drop("n")


def ripple(seeds: DataFrame, edges: DataFrame, hops: int = P.hops, kernel: Callable[[Column], Column] = harmonic, hit_seed: bool = True, fan_out: int | None = None) -> DataFrame:
    """seed, unit_id, hop, penalty: dependents within ``hops`` steps, each at its least distance from each seed.

    Unrolled joins along reverse dependency; a seed may be hit through a cycle. Duplicate edges count once.
    """
    e = edges.select("src", "dst").distinct()
    if fan_out:
        e = capped(e, fan_out)
    front = seeds.select(F.col("unit_id").alias("seed"), F.col("unit_id").alias("at"))
    seen = None
    for hop in range(hops):
        step = front.join(e, F.col("at") == F.col("dst")).select("seed", F.col("src").alias("at")).distinct()
        if seen is not None:
            step = step.join(seen.select("seed", F.col("unit_id").alias("at")), ["seed", "at"], "left_anti")
        found = step.select("seed", F.col("at").alias("unit_id"), F.lit(hop).cast("long").alias("hop"))
        seen = found if seen is None else seen.unionAll(found)
        front = step
    out = seen if hit_seed else seen.filter("seed <> unit_id")
    return out.withColumn("penalty", kernel(F.col("hop")))


def apply_ripple(units: DataFrame, messages: DataFrame, p: Params = P, relative: bool = False) -> DataFrame:
    """prior_trust less all penalties, floored; the seeds stay as flags. ``relative`` multiplies by (1 - penalty) instead."""
    total = F.exp(F.sum(F.log1p(-F.col("penalty")))) if relative else F.sum("penalty")
    m = messages.groupBy("unit_id").agg(total.alias("hit"), F.array_sort(F.collect_set("seed")).alias("flags"))
    out = units.join(m, "unit_id", "left")
    base = F.col("prior_trust") * F.coalesce("hit", F.lit(1.0)) if relative else F.col("prior_trust") - F.coalesce("hit", F.lit(0.0))
    base = F.when(F.col("hit").isNull(), F.col("prior_trust")).otherwise(base if p.ripple_floor is None else F.greatest(F.lit(p.ripple_floor), base))
    return out.withColumn("prior_trust", base).drop("hit")


def ripple_stats(messages: DataFrame) -> DataFrame:
    """Messages a seed, and the widest step: the monitor against runaways."""
    per = messages.groupBy("seed").agg(F.count("*").alias("messages"), F.count_if(F.col("hop") == 0).alias("first_hop"))
    return per.agg(F.count("*").alias("seeds"), F.sum("messages").alias("messages"), F.max("messages").alias("most"), F.max("first_hop").alias("widest"), F.avg("messages").alias("mean"))


def value_conflicts(units: DataFrame, overlap: bool = True) -> DataFrame:
    """Pairs a < b of one topic with different values, neither archived, not of one lineage; a rumour against versions.

    Only rumours stand outside the lineage, so one side is a rumour and groups are not squared.
    """
    live = units.filter("status <> 'ARCHIVED'").select("topic", "unit_id", "value", "is_rumour", "version_no", "born_at", "valid_to")
    r = live.filter("is_rumour").select("topic", F.col("unit_id").alias("r"), F.col("value").alias("rv"), F.col("born_at").alias("said"))
    pairs = live.filter("NOT is_rumour").join(r, "topic").filter("value <> rv")
    if overlap:
        pairs = pairs.filter("valid_to IS NULL OR said <= valid_to")
    return pairs.select(F.least("unit_id", "r").alias("a"), F.greatest("unit_id", "r").alias("b"))


def marked(units: DataFrame, pairs: DataFrame) -> DataFrame:
    """Each unit's conflicts, both ways, and whether it has the lower trust in one."""
    both = pairs.select(F.col("a").alias("unit_id"), F.col("b").alias("other")).unionAll(pairs.select("b", "a"))
    t = units.select(F.col("unit_id").alias("other"), F.col("trust").alias("other_trust"))
    return both.join(units.select("unit_id", "trust"), "unit_id").join(t, "other").groupBy("unit_id").agg(F.count("*").alias("conflicts"), F.bool_or(F.col("trust") < F.col("other_trust")).alias("loses"))


def _each(batches, size: int):
    """(doc_id, its sorted distinct word shingles) of every text with ``size`` words or more, a list for each slice of a batch."""
    codes = WordCodes()
    for batch, texts in text_chunks(batches):
        words = ((i, t.encode("utf-8", "surrogatepass").split()) for i, t in zip(batch.column(0).to_pylist(), texts, strict=True))
        yield [(i, shingle_set(w, size, codes)) for i, w in words if len(w) >= size]


def _mapped(docs: DataFrame, run: Callable, schema: str) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.lower("text").alias("text")).mapInArrow(run, schema)


def _set_hashes(docs: DataFrame, size: int) -> DataFrame:
    """doc_id, n and set_hash of every set of shingles; the sets themselves are not kept but made again where they are needed."""

    def run(batches):
        for rows in _each(batches, size):
            hashes = [xxhash.xxh3_128_digest(s.tobytes()) for _, s in rows]
            yield pa.RecordBatch.from_arrays([pa.array([i for i, _ in rows], pa.int64()), pa.array([len(s) for _, s in rows], pa.int64()), pa.array(hashes, pa.binary())], ["doc_id", "n", "set_hash"])

    return _mapped(docs, run, "doc_id long, n long, set_hash binary")


def _sets(docs: DataFrame, size: int) -> DataFrame:
    """doc_id and members: the packed set."""

    def run(batches):
        for rows in _each(batches, size):
            yield pa.RecordBatch.from_arrays([pa.array([i for i, _ in rows], pa.int64()), pa.array([s.tobytes() for _, s in rows], pa.binary())], ["doc_id", "members"])

    return _mapped(docs, run, "doc_id long, members binary")


def _sketch(docs: DataFrame, size: int, slots: int) -> tuple[np.ndarray, np.ndarray]:
    """A bit for each of ``slots`` low values of a shingle, set if several sets hold such a shingle (a clear bit: at most one does), and how often the set ones of each of BUCKETS ranges occur.

    A task sends the sorted slots of its sets as differences, in segments that are added up apart.
    """
    width, ranges = slots // SEGMENTS, BUCKETS // SEGMENTS

    def send(found):
        x = np.sort(np.concatenate(found))
        ends = np.searchsorted(x, np.arange(1, SEGMENTS + 1, dtype=np.int64) * width)
        out = []
        for g, (i, j) in enumerate(zip(np.r_[0, ends[:-1]], ends, strict=True)):
            step = np.diff(x[i:j].astype(np.int64) - g * width, prepend=0)
            out.append(step.astype(np.uint32 if len(step) and step.max() > 65535 else np.uint16))
        return pa.RecordBatch.from_arrays([pa.array(range(SEGMENTS), pa.int32()), pa.array([x.itemsize for x in out], pa.int32()), pa.array([x.tobytes() for x in out], pa.binary())], ["segment", "bytes", "steps"])

    def run(batches):
        found, n = [], 0
        for rows in _each(batches, size):
            found += [(s & np.uint64(slots - 1)).astype(np.uint32) for _, s in rows]
            n += sum(len(s) for _, s in rows)
            if n > SENT:
                yield send(found)
                found, n = [], 0
        if found:
            yield send(found)

    def add(t: pa.Table) -> pa.Table:
        total = np.zeros(width, np.int32)
        for b, x in zip(t.column("bytes").to_pylist(), t.column("steps"), strict=True):
            at, n = np.unique(np.cumsum(np.frombuffer(x.as_buffer(), np.uint32 if b == 4 else np.uint16), dtype=np.int64), return_counts=True)
            total[at] += n.astype(np.int32)
        total[total < 2] = 0
        often = total.reshape(ranges, -1).sum(axis=1, dtype=np.int64)
        return pa.table({"segment": t.column("segment").slice(0, 1), "bits": pa.array([np.packbits(total > 0, bitorder="little").tobytes()], pa.binary()), "often": pa.array([often.tobytes()], pa.binary())})

    rows = _mapped(docs, run, "segment int, bytes int, steps binary").groupBy("segment").applyInArrow(add, "segment int, bits binary, often binary").toArrow()
    bits, often = np.zeros((SEGMENTS, width // 8), np.uint8), np.zeros((SEGMENTS, ranges), np.int64)
    for g, x, n in zip(rows.column("segment").to_pylist(), rows.column("bits"), rows.column("often"), strict=True):
        bits[g], often[g] = np.frombuffer(x.as_buffer(), np.uint8), np.frombuffer(n.as_buffer(), np.int64)
    return bits.ravel(), often.ravel()


def _prefixes(docs: DataFrame, size: int, low: float, total: int) -> DataFrame:
    """token, rep, size, pos, index: the shingles of each set, rare ones first, one of which a partner must share.

    A partner of no more shingles shares one of its own first (``index``) with these. Shingles that the sketch
    shows to be in one set only come first of all and take up their places, but can't be shared and are not sent.
    """
    slots = min(SLOTS, max(1 << 20, 1 << (3 * total).bit_length()))
    shared = docs.sparkSession.sparkContext.broadcast(_sketch(docs, size, slots))
    names = ["token", "rep", "size", "pos", "index"]

    def run(batches):
        bits, often = shared.value
        for rows in _each(batches, size):
            out = []
            for rep, s in rows:
                n = len(s)
                k, first = n - ceil(low * n) + 1, n - ceil(2 * low / (1 + low) * n) + 1
                slot = (s & np.uint64(slots - 1)).astype(np.int64)
                held = (bits[slot >> 3] >> (slot & 7).astype(np.uint8)) & 1 > 0
                alone = n - int(held.sum())
                if alone >= k:
                    continue
                s, slot = s[held], slot[held]
                order = np.lexsort((s, often[slot // (slots // BUCKETS)]))[: k - alone]
                at = np.arange(alone, alone + len(order), dtype=np.int32)
                out.append((s[order].view(np.int64), np.full(len(order), rep, np.int64), np.full(len(order), n, np.int32), at, at < first))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*out, strict=True)], names)

    return _mapped(docs, run, "token long, rep long, size int, pos int, index boolean")


def _only(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """The rows of ``docs`` whose doc_id is among ``ids``, which are counted."""
    return docs.join(F.broadcast(ids) if ids.count() <= BROADCAST else ids, "doc_id", "left_semi")


def _shared_counts(pairs: DataFrame, docs: DataFrame, sizes: DataFrame, size: int) -> DataFrame:
    """x, y, both, total: sizes of the intersection and the sum of every pair of sets; ``sizes`` has doc_id and n.

    Sets are dealt to blocks and sent once to each pair of blocks that needs them, not once a pair.
    """
    reps = materialize(pairs.select(F.col("x").alias("doc_id")).unionAll(pairs.select("y")).distinct(), "edges-reps", narrow=True)
    held = _only(sizes, reps).agg(F.sum("n")).first()[0] or 0
    k = max(3, ceil(8 * held / BLOCK))
    block = lambda c: F.pmod(F.xxhash64(c), F.lit(k))
    pairs = pairs.withColumns({"bx": block("x"), "by": block("y")})
    ends = F.explode(F.array("x", "y")).alias("doc_id")
    need = materialize(pairs.select(F.col("bx").alias("cx"), F.col("by").alias("cy"), ends).distinct().groupBy("doc_id").agg(F.collect_list(F.struct("cx", "cy")).alias("to")), "edges-need", narrow=True)
    few = need.count() * 2 * k <= BROADCAST
    held = _sets(_only(docs, reps), size).join(F.broadcast(need) if few else need, "doc_id").select("doc_id", "members", F.explode("to").alias("to")).select("doc_id", "members", "to.*")

    def run(p, s):
        of = {i: np.frombuffer(m.as_buffer(), np.uint64) for i, m in zip(s.column("doc_id").to_pylist(), s.column("members"), strict=True)}
        x, y = p.column("x").to_pylist(), p.column("y").to_pylist()
        both = [overlap(of[i], of[j]) for i, j in zip(x, y, strict=True)]
        return pa.table({"x": pa.array(x, pa.int64()), "y": pa.array(y, pa.int64()), "both": pa.array(both, pa.int64()), "total": pa.array([len(of[i]) + len(of[j]) for i, j in zip(x, y, strict=True)], pa.int64())})

    return pairs.groupBy("bx", "by").cogroup(held.groupBy("cx", "cy")).applyInArrow(run, "x long, y long, both long, total long")


def similar_classes(docs: DataFrame, tau: float = 0.5, size: int = 4) -> tuple[DataFrame, DataFrame]:
    """(doc_id, rep, n): texts of equal shingle sets (of n shingles) have the smallest doc_id among them as ``rep``; and (x, y, jaccard): reps x < y with Jaccard of at least ``tau``.

    Every such pair has a shingle among the first of both sets in one global order, so none is lost,
    however many texts hold a shingle. Texts are read four times, and only what may be shared is stored.
    """
    low = tau - 6e-7  # of what is rounded to six places
    sig = materialize(_set_hashes(docs, size), "edges-hashes")
    classes = sig.groupBy("set_hash").agg(F.min("doc_id").alias("rep"))
    members = materialize(sig.join(classes, "set_hash").select("doc_id", "rep", "n").distinct(), "edges-members", narrow=True)
    sizes = members.filter("doc_id = rep")
    own = _only(docs, sizes.select("doc_id"))
    total = sizes.agg(F.sum("n")).first()[0] or 0
    rows = _prefixes(own, size, low, total).withColumn("df", F.count("*").over(Window.partitionBy("token")))
    rows = materialize(rows.filter("df > 1").drop("df"), "edges-prefixes")
    x, y = (rows.select("token", *(F.col(c).alias(f"{c}_{k}") for c in ("rep", "size", "pos", "index"))) for k in "xy")
    need = F.ceil(F.lit(low / (1 + low)) * (F.col("size_x") + F.col("size_y")))
    left = F.least(F.col("size_x") - F.col("pos_x"), F.col("size_y") - F.col("pos_y"))
    fits = (F.col("rep_x") != F.col("rep_y")) & (F.col("size_y") <= F.col("size_x")) & (F.col("size_y") >= F.lit(low) * F.col("size_x")) & (left >= need)
    pairs = x.join(y.filter("index_y"), "token").filter(fits).select(F.least("rep_x", "rep_y").alias("x"), F.greatest("rep_x", "rep_y").alias("y")).distinct()
    pairs = materialize(pairs, "edges-pairs", narrow=True)
    jaccard = F.round(F.col("both") / (F.col("total") - F.col("both")), 6)
    links = _shared_counts(pairs, docs, sizes, size).select("x", "y", jaccard.alias("jaccard")).filter(F.col("jaccard") >= tau)
    return members, materialize(links, "edges-links", narrow=True)


def semantic_edges(docs: DataFrame, tau: float = 0.5, most: float = 1.0) -> DataFrame:
    """src depends on dst (the smaller id): Jaccard of word shingles of at least ``tau`` and at most ``most``; copies count like others."""
    members, links = similar_classes(docs, tau)
    links = links.filter(F.col("jaccard") <= most)
    a, b = (members.select(F.col("rep").alias(r), F.col("doc_id").alias(d)) for r, d in (("x", "p"), ("y", "q")))
    out = links.join(a, "x").join(b, "y").select(F.greatest("p", "q").alias("src"), F.least("p", "q").alias("dst"), "jaccard")
    if most < 1:
        return out
    same = a.join(b.withColumnRenamed("y", "x"), "x").filter("p < q")
    return out.unionAll(same.select(F.col("q").alias("src"), F.col("p").alias("dst"), F.lit(1.0).alias("jaccard")))


def semantic_families(docs: DataFrame, tau: float = 0.5) -> DataFrame:
    """doc_id and family, the smallest id that it reaches over links, of every text that has a partner; copies are not paired."""
    members, links = similar_classes(docs, tau)
    near = materialize(links.select("x", "y").unionAll(links.select("y", "x")), "family-links", narrow=True)
    label = materialize(near.select("x").distinct().select(F.col("x").alias("rep"), F.col("x").alias("family")), "family-labels", narrow=True)
    while True:  # the least label of the neighbours, then that label's own label: a logarithm of rounds on paths
        seen = near.join(label.select(F.col("rep").alias("y"), "family"), "y").groupBy(F.col("x").alias("rep")).agg(F.min("family").alias("low"))
        low = label.join(seen, "rep").select("rep", "family", F.least("family", "low").alias("low"))
        far = low.select(F.col("rep").alias("low"), F.col("low").alias("far"))
        new = materialize(low.join(far, "low").select("rep", F.col("far").alias("family"), (F.col("far") < F.col("family")).alias("moved")), "family-labels", narrow=True)
        label = new.select("rep", "family")
        if not new.filter("moved").limit(1).count():
            break
    copies = members.groupBy("rep").agg(F.count("*").alias("n")).filter("n > 1").select("rep")
    named = label.unionAll(copies.join(label, "rep", "left_anti").select("rep", F.col("rep").alias("family")))
    return members.join(named, "rep").select("doc_id", "family")


def structural_edges(chunks: DataFrame) -> DataFrame:
    """Every later chunk of a document depends on its first."""
    name = lambda c: F.concat_ws(":", F.col("doc_id").cast("string"), c)
    return chunks.filter("chunk_no > 0").select(name(F.col("chunk_no").cast("string")).alias("src"), name(F.lit("0")).alias("dst"), F.lit("depends_on").alias("kind"))


def apply_edges(edges: DataFrame, new: DataFrame) -> DataFrame:
    return edges.select("src", "dst", "kind").unionAll(new.select("src", "dst", "kind")).filter("src <> dst").distinct()


def degree(edges: DataFrame, kinds: tuple[str, ...] = ("depends_on",)) -> DataFrame:
    """unit_id and how many edges of these kinds touch it."""
    e = edges.filter(F.col("kind").isin(*kinds)).select("src", "dst", "kind").distinct()
    return e.select(F.col("src").alias("unit_id")).unionAll(e.select("dst")).groupBy("unit_id").agg(F.count("*").alias("degree"))


def as_lists(units: DataFrame, edges: DataFrame) -> DataFrame:
    """The list view: depends_on and depended_by of every unit, empty where there are none."""
    out = edges.groupBy(F.col("src").alias("unit_id")).agg(F.array_sort(F.collect_set("dst")).alias("depends_on"))
    inn = edges.groupBy(F.col("dst").alias("unit_id")).agg(F.array_sort(F.collect_set("src")).alias("depended_by"))
    empty = F.array().cast("array<string>")
    return units.select("unit_id").join(out, "unit_id", "left").join(inn, "unit_id", "left").select("unit_id", F.coalesce("depends_on", empty).alias("depends_on"), F.coalesce("depended_by", empty).alias("depended_by"))


def from_lists(lists: DataFrame, kind: str = "depends_on") -> DataFrame:
    """Edge rows of the list view, each edge once however many lists hold it."""
    out = lists.select(F.col("unit_id").alias("src"), F.explode("depends_on").alias("dst"))
    inn = lists.select(F.explode("depended_by").alias("src"), F.col("unit_id").alias("dst")).select("src", "dst")
    return out.unionAll(inn).distinct().withColumn("kind", F.lit(kind))


def author_reliability(log: DataFrame, kappa: float = 10.0, prior: float = 0.5) -> DataFrame:
    """Share of accepted among each actor's accepted and corrected, shrunk to ``prior``."""
    good, bad = F.count_if(F.col("action") == "accept"), F.count_if(F.col("action") == "correct")
    return log.groupBy("actor").agg(good.alias("accepted"), bad.alias("corrected")).withColumn("reliability", (F.col("accepted") + kappa * prior) / (F.col("accepted") + F.col("corrected") + kappa))


def guard_feedback(log: DataFrame, cap: int = 3, weights: DataFrame | None = None) -> DataFrame:
    """At most ``cap`` accepts and corrections by an actor on a unit in a day; the rest of the log passes.

    ``weights`` (actor, reliability) adds a column ``weight``: what a vote counts, 1 for actors without one.
    """
    vote = F.col("action").isin("accept", "correct")
    w = Window.partitionBy("actor", "unit_id", "day").orderBy("event_id")
    votes = log.filter(vote).withColumn("n", F.row_number().over(w)).filter(F.col("n") <= cap).drop("n")
    out = log.filter(~vote).unionByName(votes)
    if weights is None:
        return out
    return out.join(weights.select("actor", "reliability"), "actor", "left").withColumn("weight", F.coalesce("reliability", F.lit(1.0))).drop("reliability")


def weighted_counters(log: DataFrame) -> DataFrame:
    """access_n, pos_n and neg_n of each unit, votes by their weight."""
    n = lambda a: F.sum(F.when(F.col("action") == a, F.col("weight")).otherwise(0.0))
    return log.groupBy("unit_id").agg(F.count_if(F.col("action") == "access").alias("access_n"), n("accept").alias("pos_n"), n("correct").alias("neg_n"))


def anomalies(log: DataFrame, z: float = 2.0) -> DataFrame:
    """Actors whose number of events lies more than ``z`` deviations over the mean."""
    n = log.groupBy("actor").agg(F.count("*").alias("events"))
    s = n.agg(F.avg("events").alias("m"), F.stddev_samp("events").alias("sd"))
    return n.crossJoin(F.broadcast(s)).withColumn("z", (F.col("events") - F.col("m")) / F.col("sd")).filter(F.col("z") > z).select("actor", "events", "z")


def run_cycle(units: DataFrame, edges: DataFrame, changes: DataFrame, at, p: Params = P, pairs: DataFrame | None = None, build: Callable[[DataFrame], DataFrame] | None = None, recompute_after: bool = False) -> tuple[DataFrame, DataFrame, DataFrame]:
    """One pass in its printed order: trust and demotion, contradictions, edges, ripples, promotion.

    ``build`` finds edges (src, dst, kind) among the units; they join those that there are before the ripple runs.
    Returns units (with trust, conflicts, flags and the degree that follows from the edges), edges and the ripple's messages.
    """
    u = L.step_trust(units, at, p)
    pairs = value_conflicts(u) if pairs is None else pairs
    u = u.join(marked(u, pairs).select("unit_id", "conflicts"), "unit_id", "left").fillna(0, ["conflicts"])
    e = apply_edges(edges, build(u)) if build else edges
    messages = ripple(changes, e.filter("kind = 'depends_on'"), p.hops)
    u = L.promote(apply_ripple(u, messages, p))
    u = u.drop("degree").join(degree(e), "unit_id", "left").fillna(0, ["degree"])
    return (L.step_trust(u, at, p) if recompute_after else u), e, messages


def pending(changes: DataFrame, done: DataFrame) -> DataFrame:
    """Queued changes that no cycle has processed."""
    return changes.join(done.select("unit_id"), "unit_id", "left_anti")
