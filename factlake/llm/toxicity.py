"""Toxicity of texts that may be disguised: a noisy-channel decoder in front of a learned word list.

What differs from plain words spans a character lattice: tokens with digits or symbols among letters,
with separators inside or with letters repeated three times or more, and runs of single signs spelled
out with spaces or separators between them. Each written sign may stand for some letters, a repeated
letter for none, and a separator for nothing or for the end of a word, so words are cut within the
lattice, not before it. Viterbi search (k best) finds the likeliest texts under a letter trigram model
counted over the whole corpus; they take the place of what is written, and the restored text is
scored. A plain word has a single path and needs no search.

A word may also be cut in two or more plain pieces. Joining pieces can change a score only where the
joined letters begin with a listed feature that crosses the cut; there, and nowhere else, the pieces
go through the lattice, and count as joined if a best reading joins them.

The word list is learned from labelled rows: features are words and their beginnings. Features are
taken greedily, each time the one that explains the most toxic rows not yet explained less a penalty
for clean rows that hold it, so words that merely go along with others get no weight of their own.
A text's score is a noisy-or over the features it holds, above the rate of toxic rows without any.

``fit`` reads at most ``max_rows`` labelled rows, drawn by hash; the letter model reads every text.

Cases: null and empty texts score the rate without features; rows without a label are scored like any
other; null labels are not learned from; without toxic rows to learn from every score is 0; repeated
rows score alike; texts and tokens are read whole, in time linear in their length; columns other than
those named are ignored.
"""

from __future__ import annotations

import re
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize, text_chunks
from .language import GRAMS, PLANE, SLOTS, grams, letter_slots

# Letters that a written sign often stands for
LEET = {
    "0": "o", "1": "il", "2": "z", "3": "e", "4": "a", "5": "s", "6": "gb", "7": "t", "8": "b", "9": "g",
    "@": "a", "$": "s", "!": "il", "|": "li", "+": "t", "(": "c", "€": "e", "¡": "i", "£": "l", "#": "h",
}
SEPARATORS = " \t\n\r._-*~'`^/\\,:;"
_SIGN, _SEP = rf"(?:[^\W_]|[{re.escape(''.join(c for c in LEET if not c.isalnum()))}])", rf"[{re.escape(SEPARATORS)}]"
SPELLED = re.compile(rf"(?<![^\W_]){_SIGN}(?:{_SEP}+{_SIGN}(?![^\W_])){{2,}}")
CUT = re.compile(rf"{_SEP}+")
WORDS = re.compile(r"[^\W\d_]+")
TRIPLE = re.compile(r"([^\W\d_])\1\1")
REPEATS = re.compile(r"(.)\1{2,}", re.S)
PREFIXES, MEMO = (4, 5, 6), 200_000
# costs (minus log probability) of the channel: another sign, nothing, the letter itself; of a separator: the end of a word, one wider than others read as nothing, one between pieces of plain words read as nothing
SWAP, SKIP, LETTER, GAP, WIDE, PIECE = 1.2, 0.4, 0.05, 0.7, 2.0, 3.0


@dataclass
class Model:
    log3: np.ndarray  # minus log probability of a letter slot after two others
    chance: dict[str, float] = field(default_factory=dict)  # of being toxic, by feature
    base: float = 0.0


def letter_model(docs: DataFrame) -> np.ndarray:
    """Trigram costs from letter counts over every text; what reaches the driver has at most SLOTS**3 rows."""

    def run(batches):
        total = np.zeros(GRAMS, np.int64)
        for _, texts in text_chunks(batches):
            total += np.bincount(grams("  ".join(texts))[0], minlength=GRAMS)
        hit = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(hit, pa.int64()), pa.array(total[hit], pa.int64())], ["code", "n"])

    rows = docs.select("text").mapInArrow(run, "code long, n long").groupBy("code").agg(F.sum("n").alias("n")).toArrow()
    c3 = np.zeros(GRAMS)
    c3[rows.column("code").to_numpy()] = rows.column("n").to_numpy()
    c3 = c3.reshape(SLOTS, SLOTS, SLOTS)
    after = c3.sum(0)  # (middle, next), next may be the gap
    first = c3[0].sum(1)  # first letters of words
    p1 = (after.sum(0) + 0.5) / (after.sum() + 0.5 * SLOTS)
    p2 = (after + 5 * p1) / (after.sum(1, keepdims=True) + 5)
    p3 = (c3 + 2 * p2[None]) / (c3.sum(2, keepdims=True) + 2)
    p3[0, 0] = (first + 0.5 * p1) / (first.sum() + 0.5)
    return -np.log(p3).astype(np.float32)


def decode(written: str, log3: np.ndarray, best: int = 3, join: float | None = None) -> list[str]:
    """The ``best`` likeliest readings, likeliest first; words in them are parted by one space.

    ``join`` is the cost of reading a separator as nothing; by default it depends on its width.
    """
    slots = letter_slots()
    signs = REPEATS.sub(r"\1\1", written)
    widths = [len(m) for m in CUT.findall(signs)]
    narrow = min(widths, default=1)
    # state (letter before, last letter) -> ways (cost, hash of the output, output as a linked list), best first
    states: dict = {(0, 0): [(0.0, 0, None)]}
    at, last = 0, ""
    while at < len(signs):
        ch = signs[at]
        cut = CUT.match(signs, at) if ch in SEPARATORS else None
        new: dict = {}
        if cut:
            wide = cut.end() - at > narrow
            skip = join if join is not None else WIDE if wide else SKIP
            gap = 0.1 if wide or join is not None else GAP
            for (a, b), ways in states.items():
                new.setdefault((a, b), []).extend((cost + skip, h, out) for cost, h, out in ways)
                if b:
                    end = gap + float(log3[a, b, 0])
                    new.setdefault((0, 0), []).extend((cost + end, hash((h, " ")), (out, " ")) for cost, h, out in ways)
            at = cut.end()
        else:
            if ch.isalpha():
                emits, skip = ((ch, LETTER),), SKIP if ch == last else None
            elif ch in LEET:
                emits, skip = tuple((x, SWAP) for x in LEET[ch]), (SKIP if ch == last else 4.0)
            else:
                emits, skip = (), 2.0
            for (a, b), ways in states.items():
                if skip is not None:
                    new.setdefault((a, b), []).extend((cost + skip, h, out) for cost, h, out in ways)
                for x, c in emits:
                    s = int(slots[min(ord(x), PLANE)])
                    step = c + float(log3[a, b, s])
                    new.setdefault((b, s), []).extend((cost + step, hash((h, x)), (out, x)) for cost, h, out in ways)
            at += 1
        states, last = {k: _distinct(ways, best) for k, ways in new.items()}, ch
    ends = _distinct([(cost + (float(log3[a, b, 0]) if b else 0.0), h, out) for (a, b), ways in states.items() for cost, h, out in ways], best)
    return list(dict.fromkeys(x for x in map(_output, ends) if x))


def _distinct(ways: list[tuple], best: int) -> list[tuple]:
    """The cheapest ways with different outputs."""
    if len(ways) == 1:
        return ways
    kept: dict = {}
    for w in sorted(ways, key=lambda w: w[0]):
        if w[1] not in kept:
            kept[w[1]] = w
            if len(kept) == best:
                break
    return list(kept.values())


def _output(way: tuple) -> str:
    out, link = [], way[2]
    while link:
        link, x = link
        out.append(x)
    return "".join(out[::-1]).strip()


def readings(token: str, log3: np.ndarray) -> list[str]:
    """Readings of a token that differs from plain words; none for a plain word."""
    core = token.strip(".,;:?\"'()[]{}<>*%&#=~`^_-/\\")
    if core.endswith("!") or core.startswith("!"):
        core = core.rstrip("!")
    if not core or (core.isalpha() and not TRIPLE.search(core)):
        return []
    signs = sum(c in LEET for c in core)
    if not any(c.isalpha() for c in core) or (signs == 0 and not TRIPLE.search(core) and not any(c in SEPARATORS for c in core)):
        return []
    return decode(core, log3)


def word_features(word: str) -> set[str]:
    return {f"{word} ", *(word[:n] for n in PREFIXES if len(word) >= n)}


def token_features(token: str, log3: np.ndarray) -> frozenset[str]:
    """Features of a token or a spelled-out run as restored: of its readings, or else of its words as written."""
    if token.isalpha() and len(token) < 4:
        return frozenset((f"{token} ",))
    out: set[str] = set()
    for w in {w for r in readings(token, log3) for w in WORDS.findall(r)} or set(WORDS.findall(token)):
        out |= word_features(w)
    return frozenset(out)


def tokens(text: str) -> set[str]:
    """Distinct lower-case tokens, and runs of single signs."""
    low = text.lower()
    return {*low.split(), *(m for m in SPELLED.findall(low) if any(c.isalpha() for c in m))}


def text_features(text: str, log3: np.ndarray, memo: dict) -> set[str]:
    out: set[str] = set()
    for t in tokens(text):
        f = memo.get(t)
        if f is None:
            if len(memo) >= MEMO:
                memo.clear()
            f = memo[t] = token_features(t, log3)
        out |= f
    return out


class Pieces:
    """Words cut in plain pieces, looked for only where joining them makes a listed feature."""

    def __init__(self, features, log3: np.ndarray):
        self.features, self.log3 = features, log3
        self.longest = max(map(len, features), default=0)
        self.starts = {f.strip()[:n] for f in features for n in range(1, len(f.strip()))}
        self.memo: dict[str, frozenset] = {}

    def found(self, text: str) -> set[str]:
        if not self.starts:
            return set()
        ws = [w.strip(".,;:!?\"'()[]") for w in text.lower().split()]
        out: set[str] = set()
        for i in [i for i, w in enumerate(ws) if w in self.starts]:
            joined = ws[i]
            for j in range(i + 1, len(ws)):
                if not ws[j].isalpha():
                    break
                before, joined = len(joined), joined + ws[j]
                crossing = {f for f in word_features(joined) if f in self.features and len(f.strip()) > before}
                if crossing:
                    out |= crossing & self._read(" ".join(ws[i : j + 1]), joined)
                if joined not in self.starts:
                    break
        return out

    def _read(self, written: str, joined: str) -> frozenset:
        if written not in self.memo:
            if len(self.memo) >= MEMO:
                self.memo.clear()
            held = joined in decode(written, self.log3, join=PIECE)
            self.memo[written] = frozenset(word_features(joined)) if held else frozenset()
        return self.memo[written]


def _sample(docs: DataFrame, labels: DataFrame, max_rows: int) -> DataFrame:
    """At most ``max_rows`` labelled rows with text, the smallest by a hash of the id, each id once; so few ids may be broadcast."""
    known = labels.filter(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    known = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_rows)
    texts = docs.filter(F.col("text").isNotNull()).select("doc_id", "text")
    return materialize(texts.join(F.broadcast(known), "doc_id").select("doc_id", "text", "toxic"), "toxicity-sample")


def _toxic_rows(sample: DataFrame, log3) -> list[list[str]]:
    """Features of each toxic row of the sample, those of at least two rows in a task or rare ones alike."""

    def run(batches):
        memo: dict = {}
        for batch, texts in text_chunks(batches):
            yield pa.RecordBatch.from_arrays([pa.array([sorted(text_features(t, log3, memo)) for t in texts], pa.list_(pa.string()))], ["f"])

    return [r.as_py() for r in sample.filter("toxic = 1").select("text").mapInArrow(run, "f array<string>").toArrow().column("f")]


def _clean_counts(sample: DataFrame, log3, wanted: set[str]) -> tuple[Counter, int]:
    shared = sample.sparkSession.sparkContext.broadcast(wanted)

    def run(batches):
        memo: dict = {}
        want, c, n = shared.value, Counter(), 0
        for _, texts in text_chunks(batches):
            for t in texts:
                c.update(text_features(t, log3, memo) & want)
                n += 1
        yield pa.RecordBatch.from_arrays([pa.array([*c, ""], pa.string()), pa.array([*c.values(), n], pa.int64())], ["f", "n"])

    rows = sample.filter("toxic = 0").select("text").mapInArrow(run, "f string, n long").groupBy("f").agg(F.sum("n").alias("n")).toArrow().to_pydict()
    c = Counter(dict(zip(rows["f"], rows["n"], strict=True)))
    return c, c.pop("", 0)


def choose(rows: list[list[str]], clean: Counter, n_clean: int, support: int = 3, penalty: float = 4.0) -> tuple[dict[str, float], float]:
    """Greedy cover of the toxic rows: chance of each chosen feature, and the rate without any."""
    holders: dict[str, list[int]] = {}
    for i, fs in enumerate(rows):
        for f in fs:
            holders.setdefault(f, []).append(i)
    full = {f: len(h) for f, h in holders.items()}
    left = {f: n for f, n in full.items() if n >= support and clean[f] * 9 <= n}
    open_, chance = set(range(len(rows))), {}
    while left:
        f = max(left, key=lambda f: (left[f] - penalty * clean[f], -clean[f], len(f), f))
        if left[f] < support or left[f] <= penalty * clean[f]:
            break
        chance[f] = (full[f] + 0.5) / (full[f] + clean[f] + 1)
        for i in set(holders[f]) & open_:
            open_.discard(i)
            for g in rows[i]:
                if g in left:
                    left[g] -= 1
        left = {g: n for g, n in left.items() if n >= support and g != f}
    rest = n_clean - max((clean[f] for f in chance), default=0)
    return chance, len(open_) / max(1, len(open_) + rest)


def fit(docs: DataFrame, labelled: DataFrame, labels: DataFrame, max_rows: int = 20_000) -> Model:
    """Letter model from ``docs``, word list from the rows of ``labelled`` that ``labels`` marks."""
    model = Model(letter_model(docs))
    sample = _sample(labelled, labels, max_rows)
    rows = _toxic_rows(sample, model.log3)
    often = Counter(f for r in rows for f in r)
    rows = [[f for f in r if often[f] >= 3] for r in rows]
    clean, n_clean = _clean_counts(sample, model.log3, {f for r in rows for f in r})
    if rows:
        model.chance, model.base = choose(rows, clean, n_clean)
    return model


def score(docs: DataFrame, model: Model, id_col: str = "doc_id") -> DataFrame:
    """id, score in 0..1 and predicted of every row."""
    shared = docs.sparkSession.sparkContext.broadcast((model.log3, model.chance, model.base))

    def run(batches):
        log3, chance, base = shared.value
        memo: dict = {}
        pieces = Pieces(chance, log3)

        def chances(token):
            return {f: chance[f] for f in token_features(token, log3) if f in chance}

        for batch, texts in text_chunks(batches):
            out = []
            for t in texts:
                held: dict[str, float] = {}
                for x in tokens(t):
                    f = memo.get(x)
                    if f is None:
                        if len(memo) >= MEMO:
                            memo.clear()
                        f = memo[x] = chances(x)
                    if f:
                        held |= f
                for g in pieces.found(t):
                    held[g] = chance[g]
                keep = 1 - base
                for p in held.values():
                    keep *= 1 - p
                out.append(min(1.0, max(0.0, 1 - keep)))
            s = np.array(out, float)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(s), pa.array((s >= 0.5).astype(np.int32))], [id_col, "score", "predicted"])

    return docs.select(F.col(id_col).cast("long").alias(id_col), "text").mapInArrow(run, f"{id_col} long, score double, predicted int")
