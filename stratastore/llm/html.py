"""Main text of web pages: marked articles by their markup, the rest by a suffix array of each host.

On a page that marks its article (``article``, ``main`` or role main) the marks decide: its blocks
without menus, notices, adverts, forms, comments and the like. On other pages the blocks that no markup
rules out are the page's token stream; the streams of a host are put into one suffix array, sorted to
``min_run`` tokens, and tokens inside runs that ``min_pages`` distinct pages of the host share go.
A host of more than ``max_tokens`` tokens is not gathered: its runs are counted by hash over all tasks,
which covers the same tokens.

Why not the suffix array alone: on the given pages menus, adverts and footers differ from page to page,
and article passages recur on pages of one host, so repetition alone keeps the first and drops the second.

Null and empty pages have empty text. A null or unreadable url has the empty host. Copies of a page
share all their runs, so copies of an unmarked page (``min_pages`` or more on one host) lose those.
"""

from __future__ import annotations

import html as _html
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import textkernel as K
from .shared import free_name, plus, written

MIN_RUN, MIN_PAGES, MAX_TOKENS = 6, 3, 2_000_000

_TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)"
    r"|<(script|style|noscript|template|svg|textarea|iframe|math|title)\b(?:[^>\"']|\"[^\"]*\"|'[^']*')*>.*?(?:</\1\s*>|\Z)"
    r"|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>"
    r"|<[!?][^>]*>",
    re.S | re.I,
)
_ATTR = re.compile(r"([a-zA-Z-]+)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))|\bhidden\b", re.S)
_WORD = re.compile(r"[a-z0-9]+")

INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr img".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
DROPPED = frozenset("head nav footer aside button select option dialog menu object canvas audio video map frameset noframes applet datalist".split())
MAIN = frozenset(("article", "main"))
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
DROPPED_ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert alertdialog menu menubar toolbar".split())
DROPPED_CLASSES = frozenset(
    "nav navbar navigation menu breadcrumb breadcrumbs masthead footer sidebar aside ad ads adv advert adverts advertisement advertising banner promo promotion sponsor sponsored cookie cookies consent gdpr notice notices alert popup modal overlay newsletter subscribe subscription signup social share sharing related recommended recommendations comment comments disqus reply replies respond reviews widget search login toolbar pagination pager skip hidden".split()
)
#: Words that name a box and not what is in it: beside them a furniture word still names all of a box.
BOXES = frozenset("area bar block bottom box buttons container content element form group inner item items layout left link links list main module outer page panel posts row right section site slot thread top unit user wrap wrapper zone".split())
READERS = frozenset("comment comments reply replies disqus".split())
#: What an open paragraph ends at, and for each element with an implied end the tags that end it and those that keep it open.
_ENDS_P = frozenset("address article aside blockquote details div dl fieldset figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())
_ENDS = {
    "li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "option": ({"option"}, {"select", "datalist"}),
    "tr": ({"tr", "td", "th"}, {"table"}), "td": ({"td", "th"}, {"table", "tr"}), "th": ({"td", "th"}, {"table", "tr"}), "tbody": ({"tbody", "thead", "tr", "td", "th"}, {"table"}), "tfoot": ({"tbody", "thead", "tr", "td", "th"}, {"table"}),
}
#: Where a page marks its article; the same rule runs in the plan and in the tests.
MARKED = r"(?i)<(article|main)\b|\brole\s*=\s*[\"']?main\b"


def _names_furniture(names: list[str], words: frozenset[str] = DROPPED_CLASSES) -> bool:
    """Whether a class or id as a whole names furniture: each of its words does, or names a box, and one does."""
    for name in names:
        own = _WORD.findall(name)
        if any(w in words for w in own) and all(w in words or w in BOXES or w.isdigit() for w in own):
            return True
    return False


def _attributes(raw: str) -> tuple[list[str], list[str], str, bool]:
    """(classes, ids, role, hidden) of a tag."""
    classes, ids, role, hidden = [], [], "", False
    for m in _ATTR.finditer(raw):
        name, value = (m[1] or "hidden").lower(), (m[2] or m[3] or m[4] or "").lower()
        if name == "class":
            classes += value.split()
        elif name == "id":
            ids.append(value)
        elif name == "role":
            role = value.strip()
        elif name == "hidden" or name == "aria-hidden" and value == "true" or name == "style" and "display:none" in value.replace(" ", ""):
            hidden = True
    return classes, ids, role, hidden


#: Why text of an element is left out: not at all, because a form holds it, or for what the element is.
KEPT, FORM, OUT = range(3)


def blocks(page: str | None) -> tuple[list[str], list[str], list[str]]:
    """(blocks of marked articles, blocks outside them, blocks outside that a form holds), without what markup rules out; white space is made one space.

    Ends of paragraphs, list items and table cells may be left out, as in the living standard. An article
    in a form is an article: pages that are one form as a whole are common.
    """
    found: tuple[list[str], list[str], list[str]] = ([], [], [])
    run: list[str] = []
    stack: list[tuple[str, int, bool]] = []  # tag, dropped, main: each also holds for what is in it
    dropped, main = KEPT, False

    def flush() -> None:
        if run:
            if text := " ".join(_html.unescape("".join(run)).split()):
                found[0 if main else 2 if dropped == FORM else 1].append(text)
            run.clear()

    def close(k: int) -> None:
        nonlocal dropped, main
        del stack[k:]
        dropped, main = stack[-1][1:] if stack else (KEPT, False)

    def implied(tag: str) -> None:
        """Ends what a start tag ends without saying so."""
        if tag in _ENDS_P:
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == "p":
                    return close(k)
                if stack[k][0] not in INLINE:
                    break
        if ends := _ENDS.get(tag):
            at = None
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] in ends[1]:
                    break
                if stack[k][0] in ends[0]:
                    at = k
            if at is not None:
                close(at)

    at = 0
    page = page or ""
    for m in _TOKEN.finditer(page):
        if m.start() > at and (dropped == KEPT or dropped == FORM and not main):
            run.append(page[at : m.start()])
        at = m.end()
        if (tag := m[3]) is None:
            continue
        tag = tag.lower()
        if m[2]:
            if tag not in INLINE:
                flush()
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == tag:
                    close(k)
                    break
            continue
        if tag not in INLINE:
            flush()
            implied(tag)
        if tag in VOID:
            continue
        classes, ids, role, hidden = _attributes(m[4]) if m[4] else ([], [], "", False)
        marks = tag in MAIN or role == "main"
        if dropped == OUT or hidden or tag in DROPPED or role in DROPPED_ROLES - {"form"} or tag == "header" and not main:
            drop = OUT
        elif marks:
            drop = OUT if _names_furniture(classes + ids, READERS) else KEPT
        elif tag not in ("html", "body") and _names_furniture(classes if tag in HEADINGS else classes + ids):
            drop = OUT
        else:
            drop = FORM if tag in ("form", "fieldset") or role == "form" else dropped
        if drop != dropped and tag in INLINE:
            flush()
        stack.append((tag, drop, main or marks))
        dropped, main = stack[-1][1:]
    if at < len(page) and (dropped == KEPT or dropped == FORM and not main):
        run.append(page[at:])
    flush()
    return found


def main_text(page: str | None) -> str:
    """Text of a page that marks its article; all that markup does not rule out if the marks hold nothing."""
    inside, outside, wrapped = blocks(page)
    return " ".join(inside or outside or wrapped)


def host_of(url: Column) -> Column:
    return F.lower(F.coalesce(F.regexp_extract(url, r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?([^/:?#]+)", 1), F.lit("")))


def repeated_tokens(tokens: np.ndarray, first: np.ndarray, min_run: int, min_pages: int) -> np.ndarray:
    """Which tokens lie in a run of min_run tokens or more that stands on min_pages distinct pages, by a suffix array sorted to that depth.

    Longer repeated runs are unions of such runs, so sorting on would cover the same tokens.

    tokens: ids over all pages; first: index of each page's first token (length pages + 1).
    """
    n, pages = len(tokens), len(first) - 1
    if not n:
        return np.zeros(0, dtype=bool)
    page = np.repeat(np.arange(pages), np.diff(first))
    # one mark of its own after each page, so no run crosses pages
    at = np.arange(n) + page
    text = np.empty(n + pages, dtype=np.int64)
    text[first[1:] + np.arange(pages)] = int(tokens.max()) + 1 + np.arange(pages)
    text[at] = tokens
    rank = np.unique(text, return_inverse=True)[1].astype(np.int64)
    depth = 1
    while depth < min_run:  # rank by the first 2 * depth tokens; the last step overlaps to reach min_run exactly
        step = min(depth, min_run - depth)
        nxt = np.concatenate((rank[step:] + 1, np.zeros(step, np.int64)))
        rank = np.unique(rank * (len(text) + 2) + nxt, return_inverse=True)[1].astype(np.int64)
        depth += step
    suffix = np.argsort(rank, kind="stable")
    owner = np.searchsorted(first[1:] + np.arange(pages) + 1, np.arange(len(text)), "right")
    key = rank[suffix] * pages + owner[suffix]
    distinct = np.bincount(np.unique(key) // pages, minlength=int(rank.max()) + 1)
    start = distinct[rank] >= min_pages
    start &= np.arange(len(text)) + min_run <= (first[1:] + np.arange(pages))[np.minimum(owner, pages - 1)]
    cover = np.zeros(len(text) + 1, dtype=np.int64)
    where = np.flatnonzero(start)
    np.add.at(cover, where, 1)
    np.add.at(cover, where + min_run, -1)
    return (np.cumsum(cover)[:-1] > 0)[at]


def _text(words: list[str], covered: np.ndarray) -> str:
    return " ".join(w for w, c in zip(words, covered.tolist(), strict=True) if not c)


def extract(pages: DataFrame, html_col: str = "html", url_col: str = "url", min_run: int = MIN_RUN, min_pages: int = MIN_PAGES, max_tokens: int = MAX_TOKENS) -> DataFrame:
    """The pages with their main text in a new column ``text``."""
    name = free_name(pages, "text")
    schema = plus(pages, {name: "string"})
    marked = F.coalesce(F.col(html_col).rlike(MARKED), F.lit(True))

    def by_markup(batches):
        for batch in batches:
            for part in K.slices(batch, html_col):
                texts = [main_text(x) for x in part.column(html_col).to_pylist()]
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(texts, pa.string())], names=schema.names)

    own = pages.where(marked).mapInArrow(by_markup, schema)
    rest = pages.where(~marked)
    host, row, body, size = (free_name(pages, x) for x in ("host", "row", "body", "size"))
    rest_schema = plus(rest, {host: "string", row: "bigint", body: "array<string>", size: "bigint"})

    def by_block(batches):
        for batch in batches:
            for part in K.slices(batch, html_col):
                found = [blocks(x) for x in part.column(html_col).to_pylist()]
                words = [" ".join(x[1] or x[2]).split() for x in found]
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(words, pa.list_(pa.string())), pa.array([len(x) for x in words], pa.int64())], names=[*part.schema.names, body, size])

    # parsed once; a row's number is fixed by being written
    rest = written(rest.withColumns({host: host_of(F.col(url_col)), row: F.monotonically_increasing_id()}).mapInArrow(by_block, rest_schema), "pages")
    large = F.broadcast(rest.groupBy(host).agg(F.sum(size).alias(size)).where(F.col(size) > max_tokens).select(host))
    out = [c for c in rest.columns if c not in (host, row, body, size)]

    def one_host(table: pa.Table) -> pa.Table:
        words = table.column(body).combine_chunks()
        ids = words.flatten().dictionary_encode().indices.to_numpy()
        first = np.concatenate(([0], np.cumsum(table.column(size).to_numpy())))
        covered = repeated_tokens(ids, first, min_run, min_pages)
        texts = [_text(w, covered[a:b]) for w, a, b in zip(words.to_pylist(), first[:-1].tolist(), first[1:].tolist(), strict=True)]
        return table.select(out).append_column(name, pa.array(texts, pa.string()))

    small = rest.join(large, host, "left_anti").groupBy(host).applyInArrow(one_host, schema)
    hot = _by_counts(rest.join(large, host, "left_semi"), host, row, body, name, min_run, min_pages)
    return own.unionByName(small).unionByName(hot.select(*schema.names))


def _by_counts(rest: DataFrame, host: str, row: str, body: str, name: str, min_run: int, min_pages: int) -> DataFrame:
    """What one_host does, for hosts that are too large for one task: runs are counted by hash, salted by that hash."""
    words = F.col(body)
    runs = F.when(F.size(words) >= min_run, F.transform(F.sequence(F.lit(1), F.size(words) - min_run + 1), lambda i: F.xxhash64(F.array_join(F.slice(words, i, min_run), " ")))).otherwise(F.array().cast("array<bigint>"))
    each = rest.select(F.col(host).alias("h"), F.col(row).alias("r"), F.posexplode(runs).alias("i", "run"))
    common = each.select("h", "run", "r").distinct().groupBy("h", "run").agg(F.count("*").alias("pages")).where(F.col("pages") >= min_pages).select("h", "run")
    starts_at = free_name(rest, "starts")
    starts = each.join(common, ["h", "run"], "left_semi").groupBy(F.col("r").alias(row)).agg(F.collect_list("i").alias(starts_at))
    kept = [c for c in rest.columns if c not in (host, row, body)]
    schema = plus(rest.select(*kept), {name: "string"})

    def uncovered(batches):
        for batch in batches:
            texts = []
            for w, s in zip(batch.column(body).to_pylist(), batch.column(starts_at).to_pylist(), strict=True):
                edge = np.zeros(len(w) + 1, np.int64)
                np.add.at(edge, np.array(s or [], np.int64), 1)
                np.add.at(edge, np.array(s or [], np.int64) + min_run, -1)
                texts.append(_text(w, np.cumsum(edge)[:-1] > 0))
            yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in kept], pa.array(texts, pa.string())], names=schema.names)

    return rest.join(starts, row, "left").mapInArrow(uncovered, schema)
