"""Main text of web pages: block parsing, and differencing against the page with the nearest URL.

A page is read as blocks of text; each block knows the elements that hold it. All pages of two or
more on a host are paired, within their host, with a page next to them in the order of URL paths (the
one whose path is closer in edits), and the blocks of both are aligned by a longest common subsequence.
Shared blocks are evidence of a template, which is added up over the host:

- a container (the innermost elements with their class and id) of which ``SURE`` of all blocks, on
  ``PAGES`` pages or more, are shared is template: all its blocks go, also those of a page that differ;
- a line that is shared on ``SURE`` of the host's pages is template wherever it stands;
- on a page without an article or main element, every shared block goes.

Two pages that share all their blocks are copies of one text rather than two texts in one template:
such a pair is no evidence and loses nothing by it. A shared block of an article that neither its
container nor its host speak against stays, as articles quote each other.

Differencing can't see what differs from page to page and yet is no text: menus, adverts, footers and
readers' comments of one page alone. These go by element, class, id or role, and where a page has an
article or main element, only its blocks stay.

Pairing never gathers a host: pages are sorted by range of (host, path), neighbours are taken within
a range, and the one page that a host may have alone in a range gets its neighbour from the ends of
the ranges before and after. Only ids, paths and hashes of blocks are sent.

Cases: null or empty html gives the empty text; a null URL counts as the empty path of an empty host;
repeated pages are paired like any others; unclosed and misnested elements are closed at the next
fitting end; a comment or script without an end runs to the end of the page; extra columns are
ignored; the time for a page is linear in its length, the alignment's is n * m / 64 word steps.
"""

from __future__ import annotations

import re
from collections import Counter
from functools import lru_cache
from html import unescape

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize, text_chunks

TAG = re.compile(r"<(?:!--(?P<c>.*?)(?:-->|\Z)|(?P<end>/?)(?P<name>[a-zA-Z][a-zA-Z0-9:-]*)(?P<attrs>(?:[^<>\"']|\"[^\"]*\"|'[^']*')*)(?:>|(?=<)|\Z)|[!?][^>]*(?:>|\Z))", re.S)
ATTR = re.compile(r"(class|id|role|hidden|aria-hidden)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.I)
NAME = re.compile(r"[A-Z]?[a-z]+|[A-Z]+|\d+")
SPACE = re.compile(r"\s+")

# Elements by their part in a page
RAW = {"script", "style", "title", "textarea", "noscript", "template", "iframe", "xmp", "noframes"}
BLOCKS = set("address article aside blockquote body center caption dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol option p pre search section select summary table tbody td tfoot th thead tr ul".split())
AWAY = {"nav", "footer", "aside", "form", "head", "menu", "dialog", "select", "button", "search", "svg", "object", "canvas", "audio", "video"}
IMPLIED = {"p", "li", "dt", "dd", "tr", "td", "th", "option", "h1", "h2", "h3", "h4", "h5", "h6"}
ROOTS = {"article", "main"}
COMMENTS = set("comment comments disqus discussion replies reply respond".split())
NOISE = COMMENTS | set(
    "ad ads adsense advert adverts advertisement advertising sponsor sponsored sponsors promo promotion banner cookie cookies consent gdpr notice notices alert newsletter subscribe subscription signup popup modal overlay sidebar sidenav nav navbar navigation menu breadcrumb breadcrumbs footer masthead topbar toolbar pagination pager related recommended recommendations share sharing social widget widgets copyright login search complementary contentinfo".split()
)
VOID = set("area base br col embed hr img input link meta param source track wbr".split())
SURE, PAGES = 0.6, 3
CELLS = 1 << 26  # bits of an alignment held at once


def _noise(name: str, attrs: str, inside: bool) -> str:
    """'' to keep an element, else why it goes."""
    if name in ROOTS | {"html", "body"}:
        found = {w.lower() for k, *v in ATTR.findall(attrs) if k.lower() in ("class", "id") for w in NAME.findall("".join(v))}
        return "comments" if name == "article" and found & COMMENTS else ""
    if name in AWAY or name == "header" and not inside:
        return "element"
    if not attrs:
        return ""
    for k, *v in ATTR.findall(attrs):
        value, k = "".join(v), k.lower()
        if k == "hidden" or k == "aria-hidden" and value == "true":
            return "hidden"
        found = {w.lower() for w in NAME.findall(value)}
        if found & COMMENTS:
            return "comments"
        if found & NOISE:
            return "name"
    return "name" if name not in ("div", "section") and 'class="header"' in attrs else ""


def marked_blocks(html: str | None) -> list[tuple[str, str, bool, bool]]:
    """(text, container, whether a rule speaks against it, whether it stands in an article or main element) in page order."""
    html = html or ""
    # element, class and id, why its text goes, whether it stands in a root; the last two hold for all below it
    stack: list[tuple[str, str, str, bool]] = []
    names: Counter = Counter()
    out: list[tuple[str, str, bool, bool]] = []
    part: list[str] = []

    def close():
        if part:
            text = SPACE.sub(" ", unescape("".join(part))).strip()
            part.clear()
            if text:
                why, root = stack[-1][2:] if stack else ("", False)
                out.append((text, ">".join(x for _, x, _, _ in stack[-3:]), bool(why), root))

    def pop() -> str:
        name = stack.pop()[0]
        names[name] -= 1
        return name

    at, size = 0, len(html)
    while at < size:
        m = TAG.search(html, at)
        if m is None:
            part.append(html[at:])
            break
        part.append(html[at : m.start()])
        at = max(m.end(), m.start() + 1)
        name = (m["name"] or "").lower()
        if not name:
            continue
        if not m["end"] and name in RAW:
            end = _end_of(name).search(html, at)
            at = end.end() if end else size
            continue
        if name in BLOCKS or name in AWAY:
            close()
        if m["end"]:
            if names[name]:
                close()
                while pop() != name:
                    pass
        elif name == "br":
            part.append(" ")
        elif name not in VOID:
            if name in BLOCKS:
                while stack and stack[-1][0] in IMPLIED and _implies_end(stack[-1][0], name):
                    pop()
            _, _, above, inside = stack[-1] if stack else ("", "", "", False)
            why = _noise(name, m["attrs"], inside)
            if name in ROOTS and above != "comments" and not why:
                above = ""  # what was left open before a root doesn't hold it
            if name in BLOCKS or name in AWAY or why:
                if why and not above:
                    close()
                mark = " ".join("".join(v) for k, *v in ATTR.findall(m["attrs"]) if k.lower() in ("class", "id")) if m["attrs"] else ""
                stack.append((name, f"{name}.{mark}" if mark else name, above or why, inside or name in ROOTS and not (above or why)))
                names[name] += 1
    close()
    return out


def _implies_end(open_name: str, name: str) -> bool:
    """Whether a start tag ends the open paragraph, item, cell or heading before it."""
    if open_name in ("li", "td", "th", "dd"):
        return name in IMPLIED and name != "p"
    return name in IMPLIED | {"div", "ul", "ol", "table", "section", "article", "main", "footer", "nav", "aside", "header"}


@lru_cache
def _end_of(name: str) -> re.Pattern:
    return re.compile(rf"</{name}\s*>?", re.I)


def blocks(html: str | None) -> tuple[list[str], bool]:
    """The blocks that rules keep, in page order, and whether they are those of article or main elements."""
    out = [(t, root) for t, _, against, root in marked_blocks(html) if not against]
    inside = [t for t, root in out if root]
    return (inside, True) if inside else ([t for t, _ in out], False)


def _steps(a: list, b: list, keep: bool = False):
    """Bit rows of the alignment of b's prefixes with growing a: a zero bit is a place where the subsequence grows."""
    where: dict = {}
    for j, x in enumerate(b):
        where[x] = where.get(x, 0) | 1 << j
    full = (1 << len(b)) - 1
    v, rows = full, []
    for x in a:
        u = v & where.get(x, 0)
        v = ((v + u) | (v - u)) & full
        if keep:
            rows.append(v)
    return rows if keep else v


def _lengths(v: int, n: int) -> list[int]:
    """Length of the subsequence with each prefix of b."""
    bits = np.unpackbits(np.frombuffer(v.to_bytes(n // 8 + 1, "little"), np.uint8), bitorder="little")[:n]
    return [0, *np.cumsum(1 - bits.astype(np.int64)).tolist()]


def shared_lines(a: list, b: list) -> set[int]:
    """Indices of ``a`` in one longest common subsequence with ``b``; bit-parallel, halved where it would hold too much."""
    out: set[int] = set()
    todo = [(0, len(a), 0, len(b))]
    while todo:
        lo, hi, left, right = todo.pop()
        while lo < hi and left < right and a[lo] == b[left]:
            out.add(lo)
            lo, left = lo + 1, left + 1
        while lo < hi and left < right and a[hi - 1] == b[right - 1]:
            hi, right = hi - 1, right - 1
            out.add(hi)
        if lo == hi or left == right:
            continue
        if hi - lo == 1:
            if a[lo] in b[left:right]:
                out.add(lo)
        elif (hi - lo) * (right - left) <= CELLS:
            rows = _steps(a[lo:hi], b[left:right], True)
            i, j = hi - lo - 1, right - left - 1
            while i >= 0 and j >= 0:  # a zero bit that the row before lacks was made by this line
                if rows[i] >> j & 1:
                    j -= 1
                elif i and not rows[i - 1] >> j & 1:
                    i -= 1
                else:
                    out.add(lo + i)
                    i, j = i - 1, j - 1
        else:
            mid, n = (lo + hi) // 2, right - left
            ahead = _lengths(_steps(a[lo:mid], b[left:right]), n)
            back = _lengths(_steps(a[mid:hi][::-1], b[left:right][::-1]), n)
            cut = max(range(n + 1), key=lambda k: ahead[k] + back[n - k])
            todo += [(lo, mid, left, left + cut), (mid, hi, left + cut, right)]
    return out


def parsed(pages: DataFrame) -> DataFrame:
    """page_id, url, lines and, for each line, its hash, its container's hash, and 1 for a rule against it plus 2 for a root."""

    def run(batches):
        for batch, texts in text_chunks(batches, "html", 4_000_000):
            found = [marked_blocks(t) for t in texts]
            h = lambda x: xxhash.xxh64_intdigest(x.encode("utf-8", "surrogatepass")) - (1 << 63)
            cols = [pa.array([[x[0] for x in f] for f in found], pa.list_(pa.string())), pa.array([[h(x[0]) for x in f] for f in found], pa.list_(pa.int64()))]
            cols += [pa.array([[h(x[1]) for x in f] for f in found], pa.list_(pa.int64())), pa.array([[x[2] + 2 * x[3] for x in f] for f in found], pa.list_(pa.int32()))]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *cols], ["page_id", "url", "lines", "hashes", "boxes", "marks"])

    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return rows.mapInArrow(run, "page_id long, url string, lines array<string>, hashes array<long>, boxes array<long>, marks array<int>")


def _host() -> Column:
    return F.lower(F.regexp_extract(F.coalesce("url", F.lit("")), r"^[A-Za-z][A-Za-z0-9+.-]*://([^/?#]*)", 1))


def partners(pages: DataFrame) -> DataFrame:
    """row, host and partner: for each row of (row, url) the nearer one of the rows beside it in the order of its host's paths."""
    path = F.regexp_replace(F.regexp_replace(F.coalesce("url", F.lit("")), r"^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*", ""), r"[?#].*$", "")
    rows = pages.select("row", _host().alias("host"), path.alias("path"))
    ranges = int(pages.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = materialize(rows.repartitionByRange(ranges, "host", "path", "row").withColumn("part", F.spark_partition_id()), "page-order")
    beside = Window.partitionBy("host", "part").orderBy("path", "row")
    near = lambda step: F.struct(step("row").over(beside).alias("row"), step("path").over(beside).alias("path"))
    rows = rows.withColumn("a", near(F.lag)).withColumn("b", near(F.lead))
    # a host's only row in a range looks at the ranges beside it: one row for every host and range
    ends = rows.groupBy("host", "part").agg(F.min(F.struct("path", "row")).alias("first"), F.max(F.struct("path", "row")).alias("last"), F.count("*").alias("k"))
    over = Window.partitionBy("host").orderBy("part")
    single = ends.withColumn("alone", F.coalesce(F.lag("last").over(over), F.lead("first").over(over))).filter("k = 1 AND alone IS NOT NULL").select(F.col("first.row").alias("row"), F.col("alone.row").alias("alone"))
    gap = lambda c: F.when(F.col(f"{c}.row").isNotNull(), F.coalesce(F.nullif(F.levenshtein(F.col("path"), F.col(f"{c}.path"), 64), F.lit(-1)), F.lit(65)))
    inner = F.when(F.coalesce(gap("a"), F.lit(99)) <= F.coalesce(gap("b"), F.lit(99)), F.col("a.row")).otherwise(F.col("b.row"))
    return rows.select("row", "host", inner.alias("inner")).join(single, "row", "left").select("row", "host", F.coalesce("inner", "alone").alias("partner"))


def differences(rows: DataFrame) -> DataFrame:
    """Of every page with a partner that is no copy: row, host, the indices of the shared lines, their hashes, and of each container the lines and shared lines."""
    schema = "row long, host string, shared array<int>, lines array<long>, boxes array<struct<key: long, n: long, k: long>>"
    vote = pa.list_(pa.struct([("key", pa.int64()), ("n", pa.int64()), ("k", pa.int64())]))

    def run(batches):
        for batch in batches:
            out = []
            for row, host, a, boxes, b in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                shared = shared_lines(a, b)
                if len(shared) < len(a):
                    n, k = Counter(boxes), Counter(boxes[i] for i in shared)
                    out.append((row, host, sorted(shared), sorted({a[i] for i in shared}), [{"key": x, "n": c, "k": k[x]} for x, c in n.items()]))
            cols = list(zip(*out, strict=True)) or [()] * 5
            types = [pa.int64(), pa.string(), pa.list_(pa.int32()), pa.list_(pa.int64()), vote]
            yield pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(cols, types, strict=True)], ["row", "host", "shared", "lines", "boxes"])

    pairs = partners(rows).filter("partner IS NOT NULL")
    both = pairs.join(rows.select("row", "hashes", "boxes"), "row").join(rows.select(F.col("row").alias("partner"), F.col("hashes").alias("other")), "partner")
    return both.select("row", "host", "hashes", "boxes", "other").mapInArrow(run, schema)


def templates(found: DataFrame) -> DataFrame:
    """host and the hashes of its template containers and lines, from all its pages' differences."""
    boxes = found.select("host", F.explode("boxes").alias("b")).groupBy("host", "b.key").agg(F.sum("b.n").alias("n"), F.sum("b.k").alias("k"), F.count("*").alias("pages"))
    lines = found.select("host", F.explode("lines").alias("key")).groupBy("host", "key").agg(F.count("*").alias("k")).filter(F.col("k") >= PAGES)
    lines = lines.join(found.groupBy("host").agg(F.count("*").alias("n")), "host").select("host", "key", "n", "k", F.col("n").alias("pages"))
    sure = boxes.unionByName(lines).filter((F.col("pages") >= PAGES) & (F.col("k") >= SURE * F.col("n")))
    return sure.groupBy("host").agg(F.collect_set("key").alias("template"))


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text and n_chars of every page."""
    rows = materialize(parsed(pages).withColumn("row", F.monotonically_increasing_id()), "page-lines")
    found = materialize(differences(rows), "page-differences", narrow=True)
    known = materialize(templates(found), "page-templates", narrow=True)
    # what is told of a page: a host's templates also speak against pages that are copies of their neighbours
    held = F.array_intersect("template", F.array_union("hashes", "boxes"))  # of a host's templates, what the page has
    told = rows.select("row", _host().alias("host"), "hashes", "boxes").join(known, "host").select("row", held.alias("template")).filter(F.size("template") > 0)
    told = told.join(found.filter(F.size("shared") > 0).select("row", "shared"), "row", "full") if known.limit(1).count() else found.filter(F.size("shared") > 0).select("row", F.lit(None).cast("array<long>").alias("template"), "shared")
    kept = rows.join(materialize(told, "page-told", narrow=True), "row", "left")
    rooted = F.exists("marks", lambda m: m == 2)
    against = lambda z: F.array_contains("template", z["hashes"]) | F.array_contains("template", z["boxes"])
    stays = lambda z, i: (z["marks"] % 2 == 0) & ~F.coalesce(against(z), F.lit(False)) & F.when(rooted, z["marks"] == 2).otherwise(~F.coalesce(F.array_contains("shared", i), F.lit(False)))
    text = F.array_join(F.transform(F.filter(F.arrays_zip("lines", "hashes", "boxes", "marks"), stays), lambda z: z["lines"]), "\n")
    return kept.select("page_id", "url", F.coalesce(text, F.lit("")).alias("text")).withColumn("n_chars", F.length("text").cast("long"))
