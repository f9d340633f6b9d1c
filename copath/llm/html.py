"""Main text of web pages by a maximum-scoring subsequence.

A page is a sequence of runs of words and of the tags between them. Words score positive, words of links less, tags negative,
all by how often labelled pages have them inside and outside of their content. One linear scan finds the contiguous
region with the greatest sum, which then grows to the whole elements that it lies in.

Labelled pages are those that mark their content themselves, by exactly one outermost article or main element; marks aren't among the
features that are learnt. Elements are judged by the words of their class, id and role: log odds of the words of text
under them, inside against outside of content, over all labelled pages, on top of a few common names as pseudo-counts. An
element with clearly negative odds is left out, unless it holds a marked element or next to nothing would be left without it. Elements that HTML itself sets
apart (menus, footers, asides, forms, scripts, ...) and hidden ones are always left out. Where a page marks its content, words beside
it score negative.

Null and empty pages, and pages without words, have empty text. Unclosed elements reach to the end of their parent, stray end tags are
ignored, an unclosed comment, script or style hides the rest. A quote without its partner is text of its tag, which ends at the next bracket.
Repeated pages are extracted one by one. Without labelled pages the default weights count.
"""

from __future__ import annotations

import html as entities
import re
from collections import defaultdict
from math import log

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Fixed values of HTML: elements that hold raw text, that are empty, that stand inside a line, that end by each other, and that are no content by themselves.
RAW = frozenset("script style textarea title xmp iframe noembed noframes".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i img ins kbd mark q s samp small span strike strong sub sup time tt u var wbr".split())
CLOSES = {"p": ("p",), "li": ("li",), "td": ("td", "th"), "th": ("td", "th"), "tr": ("td", "th", "tr"), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "option": ("option",)}
APART = frozenset("nav footer aside form menu dialog button label fieldset select datalist template noscript svg math object canvas audio video".split())
CONTENT = frozenset("article main".split())
#: Blocks of text, as against elements that hold blocks.
TEXT_BLOCKS = frozenset("p h1 h2 h3 h4 h5 h6 li td th dt dd pre blockquote figcaption caption summary address".split())
#: Names that are common for what isn't content and for what is; each counts like ``PRIOR`` words on its side.
BESIDE_NAMES = "ad ads adv advert adverts advertisement advertising banner sponsor sponsored promo promotion sidebar menu nav navbar navigation breadcrumb breadcrumbs footer masthead cookie cookies consent gdpr notice notices alert popup modal newsletter subscribe signup social share sharing related recommended comment comments disqus replies login widget pagination copyright"
CONTENT_NAMES = "article content entry post story main body text"
PRIOR = 50.0
#: Log odds from which an element counts as beside the content.
BESIDE = -1.0
HIDDEN = re.compile(r"""(?:^|\s)hidden(?:\s|=|$)|aria-hidden\s*=\s*["']?true|display\s*:\s*none""", re.I)
NAMES = re.compile(r"""(?:^|\s)(?:class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.I)
NAME = re.compile(r"[a-z0-9]+")
#: A value in quotes may hold brackets, but no tag: no ">" before a "<".
_QUOTED = r"""[^Q<>]*+(?:<[^Q<>]*+)*+(?:>[^Q<>]*+)*+"""
TAG = re.compile(
    r"""<(?:!--.*?(?:-->|\Z)|(/?)([a-zA-Z][^\s/>]*+)((?:[^<>"'=]++|=\s*+(?:"%s"|'%s'|[^\s"'<>]*+)|["'])*+)>|[!?/][^>]*+>)""" % (_QUOTED.replace("Q", '"'), _QUOTED.replace("Q", "'")),
    re.S,
)
ENDS = {name: re.compile(rf"</{name}(?=[\s/>])", re.I) for name in RAW}
DEFAULT = {"words": 1.0, "link words": 0.2, "tag": -0.3}


class Page:
    """Elements (parent, name, names of class, id and role) and runs of text (text, element, whether a block ends before it, tags before it, in a link)."""

    def __init__(self, page: str):
        self.parent, self.name, self.names, self.apart, self.marked = [-1], ["html"], [()], [False], [False]
        self.runs: list[tuple[str, int, bool, list[str], bool]] = []
        self.tags: list[tuple[str, int]] = []
        opened: dict[str, int] = defaultdict(int)
        at, now, broken, link, before = 0, 0, False, False, []
        while True:
            m = TAG.search(page, at)
            stop = m.start() if m else len(page)
            if stop > at:
                self.runs.append((page[at:stop], now, broken, before, link))
                broken, before = False, []
            if m is None:
                break
            at = m.end()
            if m[2] is None:
                continue
            name = m[2].lower()
            self.tags.append((name, now))
            before.append(name)
            if name not in INLINE:
                broken, link = True, False
            if m[1]:
                if name == "a":
                    link = False
                elif opened[name]:
                    while self.name[now] != name:
                        opened[self.name[now]] -= 1
                        now = self.parent[now]
                    opened[name] -= 1
                    now = self.parent[now]
                continue
            if name == "a":
                link = True
            if name in RAW:
                end = ENDS[name].search(page, at)
                at = end.start() if end else len(page)
                continue
            if name in VOID or name in INLINE and not m[3].strip() or m[3].endswith("/"):
                continue
            if name in INLINE and not HIDDEN.search(m[3]):
                continue
            for other in CLOSES.get(name, ()):
                if self.name[now] == other:
                    opened[other] -= 1
                    now = self.parent[now]
            named = " ".join(x or y or z for x, y, z in NAMES.findall(m[3])).lower() if m[3] else ""
            content = name in CONTENT
            inside = self.marked[now] or content
            self.parent.append(now)
            self.name.append(name)
            self.names.append(tuple(dict.fromkeys(NAME.findall(named)[:12])) if named and name not in ("html", "body") and not content else ())
            self.apart.append(self.apart[now] or name in APART or name == "header" and not inside or bool(m[3]) and name not in ("html", "body") and bool(HIDDEN.search(m[3])))
            self.marked.append(inside)
            now = len(self.parent) - 1
            opened[name] += 1

    def label(self) -> int | None:
        """The only outermost article or main element that isn't set apart."""
        found = [i for i in range(1, len(self.name)) if self.marked[i] and not self.marked[self.parent[i]] and not self.apart[i]]
        return found[0] if len(found) == 1 else None

    def under(self, i: int) -> list[bool]:
        """Whether each element is element ``i`` or inside it."""
        out = [False] * len(self.parent)
        out[i] = True
        for k in range(i + 1, len(out)):
            out[k] = out[self.parent[k]]
        return out

    def beside(self, words: list[int], weights: dict[str, float]) -> list[bool]:
        """Whether each element is left out. words: of each run."""
        n = len(self.parent)
        suspect = [min((weights.get(f".{x}", 0.0) for x in self.names[i]), default=0.0) <= BESIDE for i in range(n)]
        out = list(self.apart)
        if not any(suspect):
            return out
        held, marks = [0] * n, list(self.marked)
        for (_, i, *_), k in zip(self.runs, words):
            if not self.apart[i]:
                held[i] += k
        for i in range(n - 1, 0, -1):
            held[self.parent[i]] += held[i]
            marks[self.parent[i]] |= marks[i]
        # What holds a marked element from outside is no junk; nor is what holds nearly everything.
        junk = [s and not (marks[i] and not self.marked[i]) for i, s in enumerate(suspect)]
        while True:
            out = [False] * n
            lost, largest = 0, None
            for i in range(1, n):
                p = self.parent[i]
                out[i] = out[p] or junk[i]
                if junk[i] and not out[p]:
                    lost += held[i]
                    if largest is None or held[i] > held[largest]:
                        largest = i
            if largest is None or held[0] - lost >= 0.1 * held[0]:
                return [a or b for a, b in zip(out, self.apart)]
            junk[largest] = False


def best_segment(scores: list[float]) -> tuple[int, int]:
    """Begin and end of the contiguous part with the greatest sum, the first and shortest of equal ones; (0, 0) if none is positive."""
    best, span, total, begin = 0.0, (0, 0), 0.0, 0
    for i, x in enumerate(scores):
        if total <= 0:
            total, begin = 0.0, i
        total += x
        if total > best:
            best, span = total, (begin, i + 1)
    return span


def extract(page: str | None, weights: dict[str, float] = DEFAULT) -> str:
    """Text of the best region of a page."""
    p = Page(page or "")
    words = [len(r[0].split()) for r in p.runs]
    out = p.beside(words, weights)
    marks = any(p.marked[i] and not out[i] for i in range(len(out)))
    live = [k for k, r in enumerate(p.runs) if not out[r[1]]]
    scores, cost, tag = [], 0.0, weights["tag"]
    for k in live:
        text, i, _, before, link = p.runs[k]
        cost = sum(weights.get(f"<{t}", tag) for t in before)
        value = weights["words"]
        if marks and not p.marked[i]:
            value = -value
        elif link and not marks:
            value = weights["link words"]
        scores += [cost, value * words[k]]
    lo, hi = best_segment(scores)
    if lo == hi:
        return ""
    first, last = live[lo // 2], live[(hi - 1) // 2]
    if marks:
        # Whole marked elements, as far as the region touches them.
        def top(i: int) -> int:
            while p.marked[p.parent[i]]:
                i = p.parent[i]
            return i

        touched = {top(p.runs[k][1]) for k in live if first <= k <= last and p.marked[p.runs[k][1]]}
        chosen = [k for k in live if p.marked[p.runs[k][1]] and top(p.runs[k][1]) in touched]
    else:
        # Whole blocks beside each other in the element that holds the region's ends.
        def holder(k: int) -> int:
            i = p.runs[k][1]
            while i and p.name[i] in TEXT_BLOCKS:
                i = p.parent[i]
            return i

        place = {k: j for j, k in enumerate(live)}
        a, b = place[first], place[last]
        plain = lambda k: not words[k] or not p.runs[k][4] or p.name[p.runs[k][1]] in ("p", "li", "td")
        while a and holder(live[a - 1]) == holder(first) and plain(live[a - 1]):
            a -= 1
        while b + 1 < len(live) and holder(live[b + 1]) == holder(last) and plain(live[b + 1]):
            b += 1
        chosen = live[a : b + 1]
    # Text without a block's edge between is one run; character references end with their piece.
    parts, previous = [], -1
    for k in chosen:
        if any(p.runs[j][2] for j in range(previous + 1, k + 1)):
            parts.append(" ")
        previous = k
        parts.append(entities.unescape(p.runs[k][0]))
    return " ".join("".join(parts).split())


def count_features(page: str, count: dict) -> None:
    """Adds a labelled page's words and tags, inside and outside of its content, by feature."""
    p = Page(page)
    own = p.label()
    if own is None:
        return
    inside = p.under(own)
    above = set()
    i = p.parent[own]
    while i >= 0:
        above.add(i)
        i = p.parent[i]
    for text, at, _, _, link in p.runs:
        n = len(text.split())
        if n:
            side, i, seen = inside[at], at, set()
            count["link words" if link else "words", side] += n
            # Elements around the content say nothing about it.
            while i > 0 and i not in above:
                seen.update(p.names[i])
                i = p.parent[i]
            for x in seen:
                count[f".{x}", side] += n
    for name, i in p.tags:
        if name not in CONTENT:
            count[f"<{name}", inside[i]] += 1


def weights_of(count: dict[tuple[str, bool], float]) -> dict[str, float]:
    """Scores from counts of (feature, inside); names and tags that no labelled page has keep their prior."""
    out = dict(DEFAULT)
    odds = lambda f, more=0.0, less=0.0: log((count.get((f, True), 0) + more + 1) / (count.get((f, False), 0) + less + 1))
    for f in ("words", "link words"):
        if count.get((f, True), 0) + count.get((f, False), 0) >= 100:
            out[f] = max(0.5, min(3.0, odds(f))) if f == "words" else max(-1.0, min(out["words"], odds(f)))
    prior = {**dict.fromkeys(BESIDE_NAMES.split(), (0.0, PRIOR)), **dict.fromkeys(CONTENT_NAMES.split(), (PRIOR, 0.0))}
    for f in {f for f, _ in count} | {f".{x}" for x in prior}:
        if f[0] == ".":
            out[f] = odds(f, *prior.get(f[1:], (0.0, 0.0)))
        elif f[0] == "<":
            out[f] = min(-0.05, max(-3.0, odds(f)))
    return out


DEFAULT |= {f: x for f, x in weights_of({}).items() if f not in DEFAULT}


def weights_from(pages: DataFrame, html_col: str = "html", most_features: int = 100_000) -> dict[str, float]:
    """Scores from all labelled pages. Of the names and tags, the ``most_features`` most frequent ones are kept; that bounds the model."""

    def one(batches):
        for b in batches:
            count: dict[tuple[str, bool], int] = defaultdict(int)
            for page in b.column("html").to_pylist():
                count_features(page, count)
            yield pa.RecordBatch.from_arrays([pa.array([k for k, _ in count], pa.string()), pa.array([i for _, i in count], pa.bool_()), pa.array(list(count.values()), pa.int64())], ["feature", "inside", "n"])

    marked = pages.select(F.col(f"`{html_col}`").alias("html")).where(F.lower("html").rlike("<(article|main)[ >]"))
    sums = marked.mapInArrow(one, "feature string, inside boolean, n long").groupBy("feature").agg(F.sum(F.when(F.col("inside"), F.col("n")).otherwise(0)).alias("yes"), F.sum(F.when(F.col("inside"), 0).otherwise(F.col("n"))).alias("no"))
    count: dict[tuple[str, bool], int] = {}
    for r in sums.orderBy(F.desc(F.col("yes") + F.col("no")), "feature").limit(most_features).collect():
        count[r.feature, True], count[r.feature, False] = r.yes, r.no
    return weights_of(count)


def main_text(pages: DataFrame, html_col: str = "html", out_col: str = "text", weights: dict[str, float] | None = None) -> DataFrame:
    """The rows with their pages' main text in place of the HTML; other columns stay (one named like ``out_col`` is replaced)."""
    known = pages.sparkSession.sparkContext.broadcast(weights or weights_from(pages, html_col))
    rest = [c for c in pages.columns if c not in (html_col, out_col)]
    packed = pages.select(F.struct(*[F.col(f"`{c}`") for c in rest]).alias("row") if rest else F.lit(None).cast("string").alias("row"), F.col(f"`{html_col}`").alias("html"))

    def one(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column("row"), pa.array([extract(p, known.value) for p in b.column("html").to_pylist()], pa.string())], ["row", "text"])

    out = packed.mapInArrow(one, f"row {packed.schema['row'].dataType.simpleString()}, text string")
    return out.select(*[F.col(f"row.`{c}`").alias(c) for c in rest], F.col("text").alias(out_col))


def report(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars of every page."""
    return main_text(pages.select("page_id", "url", "html")).withColumn("n_chars", F.length("text").cast("long"))
