"""Main-text extraction from web pages by line-block distribution.

Markup is stripped into lines, one for each block of the page. A line's weight is the length of its text, or nothing
where it is boilerplate: within menus, forms, notices, adverts, comments and the like, or made of links. Sums of
weights over a sliding window of lines show where the text surges and where it dives, on every page; the lines between
such points are kept, with adjoining unmarked ones before them and those of the same parent. Marked article and main
parts then change the weights: if a single one weighs no less than all that was kept outside such parts, lines in them,
and a heading directly before one, weigh as much as a surge and all others nothing, and the window runs again. Markup is
read in one pass, in time linear in the page whatever is left open in it.
"""

from __future__ import annotations

import html
import re
from collections import Counter
from collections.abc import Iterable, Iterator
from itertools import accumulate
from typing import NamedTuple

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import prepare_workers

# Element and class names.
BLOCKS = frozenset("address article aside blockquote body br caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html li main menu nav ol option p pre section summary table tbody td tfoot th thead title tr ul".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template iframe object svg math textarea title canvas audio video select button".split())
SKIP = frozenset("nav footer aside form dialog menu head".split())
MAIN = frozenset("article main".split())
NAMES = frozenset(
    "ad ads adbox adslot advert adverts advertisement advertising aside banner bottombar breadcrumb breadcrumbs byline-share comment comments commentlist commenting consent cookie cookies copyright disclaimer discussion disqus dropdown footer footnav gdpr hidden"
    " legal login masthead menu menubar modal nav navbar navigation newsletter notice notification outbrain overlay pager pagination paywall popup promo promoted promotion recommended registration related replies reply respond search share sharing shoutbox"
    " sidebar sidenav signin signup skip skyscraper social sponsor sponsored sponsors subscribe subscription tagcloud taboola teaser teasers toc toolbar topbar tracking trending warning widget widgets".split()
)
PLAIN = frozenset(
    "also area articles bar block body bottom box btn button buttons card cards center col column container content cta data desktop entry follow form global group header heading holder icon icons id inline inner item items js latest"
    " left like line link links list main message meta mini mobile module more news next our outer page pages panel placeholder popular post posts primary read region results right row secondary section sections see site small"
    " sticky stories story strip sub tab tabs text this title tool tools top us user users wrap wrapper you".split()
)
CERTAIN = frozenset(
    "ad ads adbox adslot advert adverts advertisement advertisements advertising breadcrumb breadcrumbs comment comments commentlist commenting consent cookie cookies disqus gdpr menubar navbar newsletter outbrain pagination paywall popup"
    " promo promoted shoutbox sidebar sidenav skyscraper sponsor sponsored sponsors tagcloud taboola".split()
)
HOLDS = frozenset("with without has no".split())
CONTAINERS = frozenset("article body center dd div li main section td".split())
PAGE_HEADS = frozenset("header head masthead topbar".split())
ROLES = frozenset("navigation banner contentinfo complementary search dialog alert form menu".split())
OPEN = re.compile(r"<(?:!--|[!?]|/?[a-zA-Z])")
NAME = re.compile(r"[^\s/>]+")
STEP = re.compile(r"[>=]")
OWNER = re.compile(r"\W*(?:copyright\W+(?:\(c\)\W*)?\d{4}|(?:copyright\s*)?(?:©|\(c\)\s*\d{4}))", re.I)
ATTR = re.compile(r"""(class|id|role|hidden|style|aria-hidden)(?:\s*=\s*("[^"]*"|'[^']*'|[^\s"'>]+))?""", re.I)
WORD = re.compile(r"[A-Z]?[a-z]+|[A-Z]+")


def _marked(name: str, attrs: str, inside: bool) -> tuple[bool, bool]:
    """Whether an element is boilerplate by its attributes, and whether by its class or id; ``inside`` the article, page headers aren't.

    A class such as with-sidebar tells what an element holds, not what it is.
    """
    named = False
    for key, value in ATTR.findall(attrs):
        key, value = key.lower(), value.strip("\"'")
        if key == "hidden" and not value.lower().startswith("until") or key == "aria-hidden" and value.lower() == "true":
            return True, False
        if key == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value, re.I):
            return True, False
        if key == "role" and value.lower() in ROLES and not (inside and value.lower() == "banner"):
            return True, False
        if key in ("class", "id") and name not in ("html", "body", "main"):
            for one in value.split():
                words = [w.lower() for w in WORD.findall(one)]
                named = named or not HOLDS.intersection(words) and _names_boilerplate(words, inside)
    return False, named


def _names_boilerplate(words: list[str], inside: bool) -> bool:
    """Whether a class or id of these words names boilerplate.

    Words such as sidebar do in any company. Others, such as legal, search or notice, do among words that say nothing of
    the matter (search-results, but not search-results-study); outside of the article also as the last word.
    """
    if CERTAIN.intersection(words):
        return True
    heads = NAMES if inside else NAMES | PAGE_HEADS
    return bool(heads.intersection(words)) and (all(w in heads or w in PLAIN for w in words) or not inside and words[-1] in heads)


class Element(NamedTuple):
    name: str
    parent: int
    hard: bool  # boilerplate by its kind or attributes
    soft: bool  # boilerplate by its class or id, or a form: not so if it holds the article
    main: int  # the outermost article or main part that it is or is in, -1 outside


class Line(NamedTuple):
    text: str
    linked: int  # characters in links
    at: int  # the innermost element


class Markup:
    """The tags of a page in order, in one pass: what a search didn't find once, it isn't sent for again."""

    def __init__(self, page: str):
        self.page = page
        self.lost: set[str] = set()  # what doesn't occur any more
        self.closers: dict[str, re.Pattern] = {}
        self.quotes = True  # whether a > in a quoted value doesn't end a tag: no longer once a tag ran to the end of the page

    def find(self, what: str, at: int) -> int:
        k = -1 if what in self.lost else self.page.find(what, at)
        if k < 0:
            self.lost.add(what)
        return k

    def tag_end(self, at: int) -> int:
        """The place of the > that ends the tag whose name ends before ``at``, or -1."""
        start = at
        while self.quotes:
            m = STEP.search(self.page, at)
            if not m:
                self.quotes = False
                break
            at = m.end()
            if m[0] == ">":
                return m.start()
            while at < len(self.page) and self.page[at].isspace():
                at += 1
            if self.page[at : at + 1] in ('"', "'"):
                k = self.find(self.page[at], at + 1)
                at = k + 1 if k >= 0 else at + 1
        return self.find(">", start)

    def close(self, name: str, at: int) -> int:
        """Where the next end tag of ``name`` ends, or -1."""
        m = None if "/" + name in self.lost else self.closers.setdefault(name, re.compile(rf"</{re.escape(name)}\s*+>", re.I)).search(self.page, at)
        if not m:
            self.lost.add("/" + name)
        return m.end() if m else -1


def parse(page: str) -> tuple[list[Line], list[Element]]:
    """Each block with text, in page order, and the elements, parents before children; the first stands for the page."""
    out: list[Line] = []
    elements = [Element("", -1, False, False, -1)]
    marked = [False]  # by element: boilerplate, or in it
    stack: list[int] = [0]
    open_names: Counter[str] = Counter()
    skips: list[int] = []  # places in the stack of elements that are boilerplate by their kind
    text: list[str] = []
    markup = Markup(page)
    linked = at = link_depth = 0

    def flush() -> None:
        nonlocal linked
        if text:
            joined = " ".join(html.unescape("".join(text)).split())
            if joined:
                out.append(Line(joined, linked, stack[-1]))
            text.clear()
        linked = 0

    def take(piece: str) -> None:
        nonlocal linked
        if piece:
            text.append(piece)
            if link_depth:
                linked += len(" ".join(html.unescape(piece).split()))

    def cut(k: int) -> None:
        open_names.subtract(elements[i].name for i in stack[k:])
        del stack[k:]
        while skips and skips[-1] >= k:
            skips.pop()

    while True:
        m = OPEN.search(page, at)
        if not m:
            take(page[at:])
            break
        take(page[at : m.start()])
        if m[0] == "<!--":
            k = markup.find("-->", m.end())
            at = k + 3 if k >= 0 else len(page)
            continue
        if m[0] in ("<!", "<?"):
            k = markup.find(">", m.end())
        else:
            word = NAME.match(page, m.end() - 1)
            k = markup.tag_end(word.end())
        if k < 0:  # not a tag
            take(m[0])
            at = m.end()
            continue
        at = k + 1
        if m[0] in ("<!", "<?"):
            continue
        name, attrs, ends = word[0].lower(), page[word.end() : k], m[0][1] == "/"
        if name in RAW and not ends:
            if name in BLOCKS:
                flush()
            if not attrs.endswith("/"):
                end = markup.close(name, at)
                at = end if end >= 0 else (len(page) if name in ("script", "style") else at)
            continue
        if name in BLOCKS:
            flush()
        if name == "a":
            link_depth = 0 if ends else 1
        if ends:
            if open_names[name]:
                k = len(stack) - 1
                while elements[stack[k]].name != name:
                    k -= 1
                cut(k)
        elif name not in VOID and not attrs.endswith("/"):
            if name in MAIN and marked[stack[-1]] and skips:  # an article doesn't sit in a menu: what is left open there has ended
                cut(skips[0])
            if name == "p":
                while elements[stack[-1]].name in ("p", "b", "i", "em", "strong", "span", "u", "font"):
                    cut(len(stack) - 1)
            up, new = stack[-1], len(elements)
            inside = elements[up].main >= 0
            hard, soft = _marked(name, attrs, inside)
            hard = hard or name in SKIP and name != "form" or name == "header" and not inside
            soft = soft or name == "form"
            is_main = name in MAIN or bool(re.search(r"role\s*=\s*[\"']?main\b", attrs, re.I))
            elements.append(Element(name, up, hard, soft and not hard, elements[up].main if inside else new if is_main else -1))
            marked.append(marked[up] or hard or soft)
            if name in SKIP and (hard or soft):
                skips.append(len(stack))
            stack.append(new)
            open_names[name] += 1
    flush()
    return out, elements


def _boilerplate(found: list[Line], elements: list[Element], weight: list[int], window: int, surge: int) -> list[bool]:
    """By element, whether it is boilerplate or in it.

    An element that is only named like boilerplate isn't if it holds the page's main part; or if it weighs no less than
    all unmarked text, and has the page's only articles or a main heading; or, where the unmarked text has no surge, if it is the
    heaviest such element of several blocks.
    """
    n = len(elements)
    own, blocks, mains, articles, heads = ([0] * n for _ in range(5))
    inner, outer = [False] * n, [-1] * n  # in or at a hard element; the outermost soft one
    for i, e in enumerate(elements):
        up = e.parent
        inner[i] = e.hard or up >= 0 and inner[up]
        outer[i] = outer[up] if up >= 0 and outer[up] >= 0 else i if e.soft else -1
        free = not inner[i] and not e.soft
        mains[i], articles[i], heads[i] = int(free and e.main == i and e.name != "article"), int(free and e.name == "article"), int(free and e.name == "h1")
    bare = [0] * len(found)
    for k, (x, w) in enumerate(zip(found, weight, strict=True)):
        if not inner[x.at]:
            own[x.at] += w
            blocks[x.at] += w > 0
            bare[k] = w if outer[x.at] < 0 else 0
    for i in range(n - 1, 0, -1):
        for t in (own, blocks, mains, articles, heads):
            t[elements[i].parent] += t[i]
    rest = sum(bare)
    total = [0, *accumulate(bare)]
    flat = all(b - a < surge for a, b in zip(total, total[window:] + total[-1:] * window, strict=False))
    several = [i for i, e in enumerate(elements) if e.soft and not inner[i] and outer[i] == i and blocks[i] >= window]
    heaviest = max(several, key=own.__getitem__, default=-1)
    bad = [False] * n
    for i, e in enumerate(elements):
        holds = mains[i] or own[i] >= rest and (heads[i] or articles[i] and articles[i] == articles[0] and not heads[0]) or flat and i == heaviest and not (mains[0] or heads[0])
        bad[i] = e.hard or e.soft and not holds or e.parent >= 0 and bad[e.parent]
    return bad


def regions(weight: list[int], window: int, least: float) -> list[bool]:
    """Which lines lie between a surge point, where a window from a line on weighs ``least``, and the dive point after it.

    Lines without weight don't, nor do those behind the dive point, where a whole window weighs nothing. Lines with
    weight that run up to a surge point do.
    """
    n = len(weight)
    total = [0, *accumulate(weight)]
    keep = [False] * n
    i = 0
    while i < n:
        if weight[i] and total[min(n, i + window)] - total[i] >= least:
            j = i - 1
            while j >= 0 and weight[j] and not keep[j]:  # a heading or byline before it
                keep[j] = True
                j -= 1
            j = i
            while j < n and total[j + 1] > total[max(i, j - window + 1)]:
                keep[j] = bool(weight[j])
                j += 1
            i = j
        i += 1
    return keep


def main_text(page: str, window: int = 3, surge: int = 60, links: float = 0.6) -> str:
    """The article's text: blocks joined by one space; empty if the page has none."""
    found, elements = parse(page)
    if not found:
        return ""
    weight = [0 if x.linked > links * len(x.text) else len(x.text) for x in found]
    bad = _boilerplate(found, elements, weight, window, surge)
    for k, x in enumerate(found):  # an owner's line outside of the article
        if bad[x.at] or elements[x.at].main < 0 and len(x.text) < 200 and OWNER.match(x.text):
            weight[k] = 0
    total = [0, *accumulate(weight)]
    top = max(b - a for a, b in zip(total, total[window:] + total[-1:] * window, strict=False))
    least = min(surge, top / 2)  # a page of short blocks surges by its own measure
    keep = regions(weight, window, least)
    blocks, holders = _holders(elements)
    kept = {holders[x.at] for x, k in zip(found, keep, strict=True) if k}
    keep = [k or w > 0 and holders[x.at] in kept for x, k, w in zip(found, keep, weight, strict=True)]  # short blocks beyond an advert
    mass: dict[int, int] = {}
    for x, k, w in zip(found, keep, weight, strict=True):
        part = elements[x.at].main
        mass[part] = mass.get(part, 0) + (w if k else 0)
    if max((w for part, w in mass.items() if part >= 0), default=0) >= max(1, mass.get(-1, 0)):
        inside = [elements[x.at].main >= 0 for x in found]
        marks = [m and not bad[x.at] for m, x in zip(inside, found, strict=True)]
        for i in range(1, len(found)):  # a heading, and what stands between it and the part
            if marks[i] and not inside[i - 1]:
                j = i - 1
                while j >= 0 and weight[j] and not inside[j]:
                    if elements[blocks[found[j].at]].name in ("h1", "h2", "h3"):
                        marks[j:i] = [True] * (i - j)
                    j -= 1
        keep = regions([max(surge, len(x.text)) if m else 0 for x, m in zip(found, marks, strict=True)], window, surge)
    return " ".join(x.text for x, k in zip(found, keep, strict=True) if k)


def _holders(elements: list[Element]) -> tuple[list[int], list[int]]:
    """By element, the block that it is or is in, and the element that holds that block, paragraphs, lists and the like not counted."""
    blocks, near, holders = [0] * len(elements), [0] * len(elements), [0] * len(elements)
    for i, e in enumerate(elements):
        up = max(e.parent, 0)
        blocks[i] = i if e.name in BLOCKS else blocks[up]
        near[i] = i if e.name in CONTAINERS else near[up]
        at = blocks[i]
        holders[i] = near[elements[at].parent if at and elements[at].name != "body" else at]
    return blocks, holders


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", window: int = 3, surge: int = 60) -> DataFrame:
    """One row per row of ``pages``: (id_col, url_col, text, n_chars). Null and empty pages give an empty text and 0.

    Ids and urls pass through, null or repeated; whole pages are read, whatever their length; other columns are not.
    """
    prepare_workers(pages.sparkSession)

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [main_text(h or "", window, surge) for h in b.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64())], names=[id_col, url_col, "text", "n_chars"])

    kind = lambda c: pages.schema[c].dataType.simpleString()
    return pages.select(F.col(id_col), F.col(url_col), F.col(html_col).cast("string").alias("strata_html")).mapInArrow(work, f"`{id_col}` {kind(id_col)}, `{url_col}` {kind(url_col)}, text string, n_chars long")
