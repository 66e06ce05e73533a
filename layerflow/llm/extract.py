"""Main text of web pages by a maximum-scoring subsequence.

A page is a sequence of tags and words.  Words score positive and tags negative; the best contiguous run of that
sequence, found by one linear scan over running sums, is the content region.  How much a tag costs is learned from
labelled pages, those that mark their content with ``article`` or ``main``: the rarer a tag is within the marked part
against the rest of the page, the more it costs.  Words inside elements that hold no content (menus, forms, notices,
reader comments, adverts and so on, told by element name or by class, id and role) cost instead of adding, and such
elements inside the region are left out of its text, as are scripts, styles and markup.  Names that content bears too
(``related``, ``legal``, ...) only exclude an element without running text: a paragraph of ``RUNNING`` words out of links.
Where an excluded element interrupts content it costs nothing, however long it is: within a marked element, or between
two paragraphs of one element (headings count as such below the body).

Defined results: a null or empty page has the empty text; a page with no words scoring above its tags too.  Of equal
regions the first wins.  Unclosed elements end with the page or with their parent, excluded ones already at the next
sectioning element.  A tag ends at the first ``>`` out of quotes; after one that has none but in quotes, the rest of the
page is read without regard to them, and a ``<`` with no ``>`` behind it is text.  All steps are linear in the page.
"""

from __future__ import annotations

import html as entities
import math
import re
from collections import Counter
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from layerflow.llm import store

#: HTML elements that flow within a line, those without an end tag, and those that hold no content.
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
OUTSIDE = frozenset("nav header footer aside form menu dialog button head fieldset".split())
MARKED = frozenset("article main".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
SECTIONS = MARKED | HEADINGS | frozenset("section nav header footer aside".split())
RAW = frozenset("script style template noscript svg iframe object textarea select title".split())
OUTSIDE_NAMES = frozenset("""ad ads advert adverts advertisement sponsor sponsored promo promotion banner nav navigation navbar menu breadcrumb
    breadcrumbs sidebar footer masthead comment comments reply replies disqus cookie cookies consent notice popup modal overlay newsletter
    subscribe subscription pagination pager toolbar""".split())
DOUBTFUL_NAMES = frozenset("side widget header respond signup share sharing social related recommended recommend search login legal copyright".split())
#: Words of a paragraph, out of links, that make an element of a doubtful name one of content.
RUNNING = 20
_ATTRIBUTE = re.compile(r"\b(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_HIDDEN = re.compile(r"\bhidden\b|display\s*:\s*none|aria-hidden\s*=\s*[\"']?true", re.I)
_NAME = re.compile(r"<(/?)([A-Za-z][A-Za-z0-9:-]*)")
_ATTRIBUTES = re.compile(r"(?>[^>\"'=]+|=\s*+\"[^\"]*+\"|=\s*+'[^']*+'|[=\"'])*+>")
_NAME_PART = re.compile(r"[^\s_-]+")
WORD = 1.0
#: Costs of tags no labelled page shows.
DEFAULT_COST = 1.5


class Token(NamedTuple):
    kind: str  # open, close or text
    value: str  # an element's name in lower case, or the text
    attributes: str = ""


def tokens(page: str) -> Iterator[Token]:
    """Tags and texts in order; comments, declarations and what raw-text elements hold are left out."""
    at, last, quotes = 0, page.rfind(">"), True
    while at < len(page):
        begin = page.find("<", at)
        if begin != at:
            yield Token("text", page[at:begin] if begin > 0 else page[at:])
            if begin < 0:
                return
        name = _NAME.match(page, begin)
        if page.startswith("<!--", begin):
            end = page.find("-->", begin + 4)
            at = end + 3 if end >= 0 else len(page)
        elif begin > last or name is None and page[begin + 1] not in "!?":
            yield Token("text", "<")
            at = begin + 1
        elif name is None:
            at = page.index(">", begin) + 1
        else:
            rest = _ATTRIBUTES.match(page, name.end()) if quotes and name.end() <= last else None
            quotes = quotes and rest is not None
            at = rest.end() if rest else page.find(">", name.end()) + 1
            kind, value = ("close" if name[1] else "open"), name[2].lower()
            yield Token(kind, value, page[name.end() : at - 1])
            if kind == "open" and value in RAW:
                end = re.compile(rf"</{value}\s*>", re.I).search(page, at)
                at = end.end() if end else len(page)


def extents(found: list[Token]) -> tuple[list[int], list[bool]]:
    """Of each token, the end of the element that it opens (its own place, if none), and whether a tag closes it."""
    end, closed = list(range(len(found))), [True] * len(found)
    stack: list[int] = []
    count: Counter = Counter()

    def pop(i: int, by_tag: bool) -> str:
        top = stack.pop()
        end[top], closed[top] = i, by_tag
        count[found[top].value] -= 1
        return found[top].value

    for i, t in enumerate(found):
        if t.kind == "close" and count[t.value]:
            while found[stack[-1]].value != t.value:
                pop(i - 1, False)
            pop(i, True)
        elif t.kind == "open" and t.value not in VOID and t.value not in RAW and not t.attributes.rstrip().endswith("/"):
            if t.value == "p" and stack and found[stack[-1]].value == "p":
                pop(i - 1, True)
            stack.append(i)
            count[t.value] += 1
    while stack:
        pop(len(found) - 1, False)
    return end, closed


def _names(attributes: str) -> set[str]:
    return {x.lower() for a in _ATTRIBUTE.findall(attributes) for x in _NAME_PART.findall("".join(a))}


def regions(found: list[Token]) -> tuple[list[int], list[bool], set[int]]:
    """Of each token the number of the outermost excluded element around it (0: none) and whether it is in a marked one;
    and the numbers of excluded elements that interrupt content."""
    n = len(found)
    end, closed = extents(found)
    section, after = [n] * (n + 1), n
    for i in range(n - 1, -1, -1):
        section[i] = after
        if found[i].kind == "open" and found[i].value in SECTIONS:
            after = i
    # where paragraphs of running text begin
    running, links, words = [0] * (n + 1), 0, 0
    for i, t in enumerate(found):
        running[i + 1] = running[i]
        if t.kind == "text":
            words += len(t.value.split()) if not links else 0
        elif t.value == "a":
            links = 1 if t.kind == "open" else 0
        elif t.value not in INLINE:
            words = 0
        if words >= RUNNING:
            running[i + 1], words = running[i] + 1, 0
    number, until, marked_until = 0, -1, -1
    out, marked = [0] * n, [False] * n
    stack: list[list] = [[n, "", None]]  # end, name and the last region's number at the last paragraph
    inside: set[int] = set()
    spans: list[tuple[int, int]] = []
    for i, t in enumerate(found):
        while stack[-1][0] < i:
            stack.pop()
        if t.kind == "open" and i > until:
            bad = t.value in OUTSIDE
            if t.attributes and t.value not in ("html", "body"):
                bad = bad or _HIDDEN.search(t.attributes) is not None
                if not bad:
                    names = _names(t.attributes)
                    bad = not names.isdisjoint(OUTSIDE_NAMES) or not names.isdisjoint(DOUBTFUL_NAMES) and running[end[i] + 1] == running[i]
            if bad:
                number += 1
                until = end[i] if closed[i] else min(end[i], section[i] - 1)
                end[i] = until
                if i <= marked_until:
                    inside.add(number)
            elif t.value == "p" or t.value in HEADINGS and stack[-1][1] not in ("", "html", "body"):
                if stack[-1][2] is not None:
                    spans.append((stack[-1][2] + 1, number))
                stack[-1][2] = number
        if t.kind == "open" and t.value in MARKED and i > until:
            marked_until = max(marked_until, end[i])
        out[i] = number if i <= until else 0
        marked[i] = i <= marked_until
        if end[i] > i:
            stack.append([end[i], t.value, None])
    step = [0] * (number + 2)
    for a, b in spans:
        step[a] += 1
        step[b + 1] -= 1
    depth = 0
    for i in range(1, number + 1):
        depth += step[i]
        if depth:
            inside.add(i)
    return out, marked, inside


def labelled_counts(page: str) -> Counter:
    """How often each tag stands in and out of marked content; empty for a page without any."""
    found = list(tokens(page))
    out, marked, _ = regions(found)
    if not any(marked):
        return Counter()
    return Counter((("/" if t.kind == "close" else "") + t.value, m and not o) for t, o, m in zip(found, out, marked) if t.kind != "text")


def learn_costs(pages: DataFrame, key: str = "page_id", html: str = "html", sample: int = 2000) -> dict[str, float]:
    """Tag costs from about ``sample`` pages at most, chosen by a hash of the key."""
    total = pages.count()
    rows = pages.select(F.col(key).alias("k"), F.col(html).alias("h")).where("h is not null")
    if total > sample:
        rows = rows.where(F.pmod(F.xxhash64(F.col("k").cast("string"), F.lit("fit")), F.lit(1 << 30)) < int(sample / total * (1 << 30)))

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        seen: Counter = Counter()
        for batch in batches:
            for h in batch["h"]:
                seen.update(labelled_counts(h))
        yield pd.DataFrame([(t, bool(i), n) for (t, i), n in seen.items()], columns=["tag", "inside", "n"])

    found = rows.select("k", "h").mapInPandas(count, "tag string, inside boolean, n long").groupBy("tag", "inside").agg(F.sum("n").alias("n")).collect()
    inside = Counter({r.tag: r.n for r in found if r.inside})
    outside = Counter({r.tag: r.n for r in found if not r.inside})
    a, b = sum(inside.values()) + 1, sum(outside.values()) + 1
    return {t: _cost((inside[t] + 0.5) / a, (outside[t] + 0.5) / b) for t in inside | outside}


def _cost(inside: float, outside: float) -> float:
    """A small cost for tags of content, a growing one for others."""
    odds = math.log(outside / inside)
    return 0.02 if odds < 0 else min(2.0, 0.02 + 0.5 * odds)


def best_run(scores: list[float]) -> tuple[int, int]:
    """Begin and end of the contiguous run with the largest positive sum, the first of several; (0, 0) if there is none."""
    sums = np.concatenate([[0.0], np.cumsum(scores)])
    lowest = np.minimum.accumulate(sums)
    gain = sums - lowest
    end = int(gain.argmax())
    if gain[end] <= 0:
        return 0, 0
    return int(np.flatnonzero(sums[: end + 1] == lowest[end])[-1]), end


def main_text(page: str | None, costs: dict[str, float]) -> str:
    if not page:
        return ""
    found = list(tokens(page))
    out, _, inside = regions(found)
    scores: list[float] = []
    for t, o in zip(found, out):
        if o in inside:
            scores.append(0.0)
        elif t.kind == "text":
            scores.append((-WORD if o else WORD) * len(t.value.split()))
        else:
            scores.append(-max(costs.get("/" + t.value if t.kind == "close" else t.value, DEFAULT_COST), DEFAULT_COST if o else 0.0))
    begin, end = best_run(scores)
    blocks, line = [], []
    for t, o in zip(found[begin:end], out[begin:end]):
        if t.kind == "text":
            if not o:
                line.append(entities.unescape(t.value))
        elif t.value not in INLINE:
            blocks.append("".join(line))
            line = []
    blocks.append("".join(line))
    return " ".join(b for b in (" ".join(x.split()) for x in blocks) if b)


def extract(pages: DataFrame, costs: dict[str, float], html: str = "html") -> DataFrame:
    """Adds text and n_chars to every row."""
    kept = pages.drop("text", "n_chars")
    names = kept.columns
    store.text_batches(pages.sparkSession)
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema.fields), "text string, n_chars long"])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [main_text(x.as_py(), costs) for x in batch.column(names.index(html))]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(found, pa.string()), pa.array([len(x) for x in found], pa.int64())], names=[*names, "text", "n_chars"])

    return kept.mapInArrow(work, schema)
