"""License scan: exact containment join of license templates with the lines of a text.

Words are lower-cased (A-Z) runs of letters, digits and non-ASCII characters. A template matches a
line if the line holds at least ``threshold`` of the template's distinct words. All such pairs are
found: words are ordered by their count in the whole corpus, rarest first; a line that meets the
threshold must hold one of the first |T| - need + 1 words of template T (prefix filter) and have at least
``need`` distinct words of templates (length filter). The words of both sides are met in that one
order, so at the n-th common word the places on both sides bound what can still come; a template goes
as soon as that cannot make ``need`` (positional filter). What remains is counted in full. Blocks that run over line ends are windows of
|T| / threshold consecutive words of the text. Every template met gives a label, except one whose words in the text
all belong to a template met to a higher share there. Templates are the bounded side: at
most MAX_TEMPLATES, sent to every worker; the corpus is read twice and never shuffled.

Base phrases are looked for as consecutive words anywhere in the text, across lines.

Cases: null and empty texts have no words, no labels and score 0; extra columns are ignored; repeated
rows are scanned each on its own; lines of any length are taken whole.
"""

from __future__ import annotations

from bisect import bisect_left, bisect_right
from collections import Counter
from itertools import groupby
from math import ceil

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import text_chunks

# Phrases and the labels they stand for
PHRASES = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}

# Usual one-line notices and headers of public licenses
TEMPLATES = {
    "agpl": "licensed under the gnu affero general public license version 3",
    "apache-2.0": "licensed under the apache license version 2.0",
    "apache-2.0-terms": "you may not use this file except in compliance with the license",
    "bsd": "redistribution and use in source and binary forms with or without modification are permitted",
    "cc-by-nc": "licensed under cc by nc 4.0",
    "cc-by-sa": "licensed under creative commons attribution sharealike 4.0 international",
    "cc0": "no copyright reserved dedicated to the public domain under cc0 1.0 universal",
    "gpl-3.0": "this work is licensed under the gnu general public license version 3",
    "lgpl": "licensed under the gnu lesser general public license version 2.1",
    "mit": "released under the mit license",
    "mit-grant": "permission is hereby granted free of charge to any person obtaining a copy of this software",
    "mpl-2.0": "this source code form is subject to the terms of the mozilla public license v 2.0",
    "reserved": "all rights reserved",
}
MAX_TEMPLATES, THRESHOLD = 10_000, 0.8

_BREAKS = bytes(c if chr(c).isascii() and (48 <= c <= 57 or 97 <= c <= 122) or c >= 128 else 32 for c in range(256))
_LINE = bytes(10 if c == 10 else b for c, b in enumerate(_BREAKS))


def words(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").lower().translate(_BREAKS).split()


def phrase_starts(ws: list[bytes], phrases: list[list[bytes]]) -> list[list[int]]:
    """Word indices at which each phrase stands; places may overlap."""
    held = set(ws)
    out = []
    for p in phrases:
        at = []
        if held.issuperset(p):
            i = -1
            try:
                while True:
                    i = ws.index(p[0], i + 1)
                    if ws[i : i + len(p)] == p:
                        at.append(i)
            except ValueError:
                pass
        out.append(at)
    return out


def word_counts(docs: DataFrame, vocabulary: set[bytes]) -> dict[bytes, int]:
    """Corpus counts of the templates' words, over every text; the result is as small as the templates."""

    def run(batches):
        c: Counter = Counter()
        for _, texts in text_chunks(batches):
            for t in texts:
                ws = words(t)
                if not vocabulary.isdisjoint(ws):
                    c.update(w for w in ws if w in vocabulary)
        yield pa.RecordBatch.from_arrays([pa.array(list(c), pa.binary()), pa.array(list(c.values()), pa.int64())], ["word", "n"])

    rows = docs.select("text").mapInArrow(run, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n")).collect()
    return {bytes(r["word"]): r["n"] for r in rows}


class Templates:
    """Templates with words in global order, and an inverted index over their prefixes."""

    def __init__(self, templates: dict[str, str], counts: dict[bytes, int], threshold: float):
        if len(templates) > MAX_TEMPLATES:
            raise ValueError(f"{len(templates)} templates; at most {MAX_TEMPLATES} are sent to workers")
        self.names, self.sets, self.need, self.index = [], [], [], {}
        self.spans = []
        for name, text in sorted(templates.items()):
            ordered = sorted(set(words(text)), key=lambda w: (counts.get(w, 0), w))
            if not ordered:
                continue
            need = max(1, ceil(round(threshold * len(ordered), 9)))
            k = len(self.names)
            self.names.append(name), self.sets.append(set(ordered)), self.need.append(need)
            self.spans.append(ceil(round(len(words(text)) / threshold, 9)))
            for i, w in enumerate(ordered[: len(ordered) - need + 1]):
                self.index.setdefault(w, []).append((k, i))
        self.keys = set(self.index)
        self.rank = {w: i for i, w in enumerate(sorted(set().union(*self.sets), key=lambda w: (counts.get(w, 0), w)))}

    def candidates(self, line: set[bytes], positional: bool = True) -> list[int]:
        """Numbers of the templates that the prefix, length and positional filters leave."""
        block = sorted(line & self.rank.keys(), key=self.rank.__getitem__)
        n, common = len(block), {}
        for j, w in enumerate(block):
            for k, i in self.index.get(w, ()):
                if n < self.need[k]:
                    continue
                both = common.get(k, 0) + 1
                fits = both + min(len(self.sets[k]) - i, n - j) - 1 >= self.need[k]
                if both > 0 and (fits or not positional):
                    common[k] = both
                else:
                    common[k] = -1  # stays out, whatever comes
        return [k for k, both in common.items() if both > 0]

    def matches(self, line: list[bytes]) -> dict[str, float]:
        """Template name -> containment, for all templates that the line's words hold enough of."""
        held, out = set(line), {}
        for k in self.candidates(held):
            both = len(self.sets[k] & held)
            if both >= self.need[k]:
                out[self.names[k]] = both / len(self.sets[k])
        return out

    def blocks(self, name: str, ws: list[bytes], line_of: list[int]) -> list[tuple[float, list[int]]]:
        """Containment and word indices of every line and every run of windows that holds enough of a template."""
        k = bisect_left(self.names, name)
        t, need, span = self.sets[k], self.need[k], self.spans[k]
        at = [i for i, w in enumerate(ws) if w in t]
        out = []
        for _, g in groupby(at, key=line_of.__getitem__):
            places = list(g)
            both = len({ws[i] for i in places})
            if both >= need:
                out.append((both / len(t), places))
        start, inside, run, best = 0, Counter(), [], 0
        for i in at:
            inside[ws[i]] += 1
            while i - at[start] >= span:
                w = ws[at[start]]
                inside[w] -= 1
                if not inside[w]:
                    del inside[w]
                start += 1
            if len(inside) >= need:
                new = at[start : bisect_left(at, i) + 1]
                if run and new[0] > run[-1]:
                    out.append((best / len(t), run))
                    run, best = [], 0
                run += new[bisect_right(new, run[-1]) :] if run else new
                best = max(best, len(inside))
        return [*out, (best / len(t), run)] if run else out


def unexplained(found: list[tuple[str, float, list[int]]]) -> list[tuple[str, float, list[int]]]:
    """Without the matches whose words all belong to a stronger match."""
    sets = [set(x[2]) for x in found]
    return [x for x, a in zip(found, sets, strict=True) if not any(y[1] > x[1] and a <= b for y, b in zip(found, sets, strict=True))]


def scan(docs: DataFrame, templates: dict[str, str] | None = None, threshold: float = THRESHOLD, phrases: dict[str, str] | None = None) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, and the matched lines' numbers."""
    templates, phrases = TEMPLATES if templates is None else templates, PHRASES if phrases is None else phrases
    counts = word_counts(docs, {w for t in templates.values() for w in words(t)})
    index = Templates(templates, counts, threshold)
    wanted = [words(p) for p in phrases]
    names = list(phrases.values())

    def one(text: str):
        raw = text.encode("utf-8", "surrogatepass").lower()
        ws = raw.translate(_BREAKS).split()
        base, at = set(), []
        for name, starts in zip(names, phrase_starts(ws, wanted), strict=True):
            if starts:
                base.add(name)
                at += starts
        found: dict[str, float] = {}
        lines: set[int] = set()
        met = index.matches(ws) if not index.keys.isdisjoint(ws) else {}
        if met:
            line_of = [i for i, line in enumerate(raw.translate(_LINE).split(b"\n")) for _ in line.split()]
            for name, share, at_words in unexplained([(name, *x) for name in met for x in index.blocks(name, ws, line_of)]):
                found[name] = max(found.get(name, 0), share)
                lines.update(line_of[i] for i in at_words)
        score = 1.0 if base else max(found.values(), default=0.0)
        return (len(ws), len(at), min(at, default=None), max(at, default=None), ",".join(sorted(base)), ",".join(sorted(base | set(found))), score, sorted(lines))

    schema = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, lines array<int>"
    types = [pa.int64()] * 4 + [pa.string()] * 2 + [pa.float64(), pa.list_(pa.int32())]
    cols = ["doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", "lines"]

    def run(batches):
        for batch, texts in text_chunks(batches):
            found = list(zip(*map(one, texts), strict=True)) or [[]] * len(types)
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(v, t) for v, t in zip(found, types, strict=True))], cols)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, schema)
