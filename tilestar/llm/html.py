"""Main text of web pages: flat text blocks, classified by a decision tree.

A page is read once by a tolerant tokeniser into flat blocks, the stretches of text between block-level tags. A block's features are its words and link density,
those of its neighbours, and where it stands (main element, menus and the like, telling class names, headings, lists). A decision tree grown on the blocks of the small labelled pages
beside this module (a block that begins with the mark is main text) says which blocks are main text. Texts of scripts, styles, comments and the head never become blocks.

Character references are decoded, white space inside a block becomes one space, blocks are trimmed, empty ones dropped, and the rest joined in
page order by a line feed. Nothing else is dropped or capped.

Defined results: null html counts as empty and gives an empty text; broken markup is read as far as it makes sense (a "<" that starts no tag, or whose tag never ends, is text, but for a tag's name that ends the page; an
unclosed quote is an ordinary character; an open comment or script ends with the page), in time proportional to its length; repeated rows are extracted alike; extra columns
are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import html as entities
import re
from collections import Counter
from collections.abc import Iterator
from pathlib import Path
from typing import NamedTuple

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

NAME = re.compile(r"[A-Za-z][\w:.-]*")
STOP = re.compile("[>\"']")
NAMES = re.compile(r"""(?<![^\s"'/])(class|id|role|aria-label)\s*=\s*("[^"]*"|'[^']*'|[^\s>]+)""", re.IGNORECASE)
WORDS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+")
_set = lambda text: frozenset(text.split())
#: Element names by kind, and words in class names and ids that tell what a part of a page is.
RAW = _set("script style textarea title xmp")
HIDDEN = _set("template noscript iframe object svg math head select option canvas audio video datalist")
BLOCK = _set(
    "address article aside blockquote body button caption center col colgroup dd details dialog dir div dl dt fieldset figcaption figure footer form frameset h1 h2 h3 h4 h5 h6"
    " header hgroup hr html legend li main menu nav ol optgroup p pre search section summary table tbody td tfoot th thead tr ul label input"
)
ASIDE = _set("nav footer aside form menu dialog button fieldset search label")
MAIN = _set("article main")
HEADS = _set("h1 h2 h3 h4 h5 h6")
ITEMS = _set("li dt dd td th")
VOID = _set("hr col input br img meta link wbr area base embed source track")
#: elements that a new one of the same kind closes
SIBLINGS = _set("p li td th tr dt dd option")
IN_HEAD = _set("meta link title style script base noscript template")
TELLING = _set(
    "ad ads advert adverts advertisement advertising adbox banner sponsor sponsored promo promotion cookie cookies consent gdpr notice notices alert popup modal overlay sidebar side widget"
    " nav navbar navigation menu breadcrumb breadcrumbs crumbs footer foot masthead topbar toolbar share sharing social"
    " newsletter subscribe subscription signup login signin register search form copyright legal disclaimer pagination pager tags skip complementary contentinfo toc"
)
#: of these, an article inside is one too
REMARKS = _set("comment comments discussion disqus reply replies respond reviews related recommended recommendations teaser teasers")
HEADER = _set("header")
#: a class name that begins so tells of the page's layout, not of the element
ABOUT_LAYOUT = _set("with no has without is layout page js not")

MARK = "\u00a7"
FEATURES = (
    "words", "links", "words_before", "links_before", "words_after", "links_after", "in_main", "in_aside", "telling", "heading", "in_header", "item", "paragraph",
)
DEPTH = 9


class Place(NamedTuple):
    """An open element, with what it passes on to the blocks inside it."""

    name: str = ""
    main: int = 0
    aside: int = 0
    telling: int = 0
    heading: int = 0
    header: int = 0
    item: int = 0
    paragraph: int = 0
    remark: int = 0
    hidden: int = 0


def grow(rows: list[tuple[int, ...]], depth: int = DEPTH) -> object:
    """Decision tree by Gini impurity: (feature, bound, tree at or below the bound, tree above), or the share of ones."""
    ones = sum(r[-1] for r in rows)
    if depth == 0 or ones in (0, len(rows)):
        return ones / len(rows)
    best = None
    for k in range(len(rows[0]) - 1):
        values = sorted({r[k] for r in rows})
        for low, high in zip(values, values[1:], strict=False):
            bound = (low + high) / 2
            sides = [[r for r in rows if (r[k] > bound) is above] for above in (False, True)]
            cost = sum(len(s) * (p := sum(r[-1] for r in s) / len(s)) * (1 - p) for s in sides)
            if best is None or cost < best[0] - 1e-12:
                best = (cost, k, bound, sides)
    if best is None:
        return ones / len(rows)
    return (best[1], best[2], grow(best[3][0], depth - 1), grow(best[3][1], depth - 1))


def leaf(tree: object, row: tuple[int, ...]) -> float:
    while isinstance(tree, tuple):
        tree = tree[3] if row[tree[0]] > tree[1] else tree[2]
    return tree


def _told(attributes: str) -> tuple[int, int, int]:
    """Whether class names, id and role tell of something beside the main text, of remarks, of a header."""
    telling = remark = header = 0
    if "=" in attributes:
        for _, value in NAMES.findall(attributes):
            for name in value.strip("\"'").split():
                words = [w.lower() for w in WORDS.findall(name)]
                if not words or words[0] in ABOUT_LAYOUT and len(words) > 1 and words[0] != "page":
                    continue
                telling |= any(w in TELLING for w in words)
                remark |= any(w in REMARKS for w in words)
                header |= any(w in HEADER for w in words)
    return int(telling), int(remark), int(header)


class Tags:
    """Where the tags of a page end. Every search either moves on or is never made again, so a page is read in time proportional to its length."""

    def __init__(self, page: str) -> None:
        self.page, self.loose, self.over, self.unpaired = page, False, False, set()

    def end(self, at: int) -> int:
        """Place of the ">" that ends the tag whose name ends at `at`; -1 if there is none. A ">" in a quoted value ends nothing."""
        page, start = self.page, at
        if self.over:
            return -1
        while not self.loose:
            m = STOP.search(page, at)
            if not m:
                self.loose = True  # only quoted ones, if any: from here on quotes are ordinary characters
                break
            at = m.start()
            if page[at] == ">":
                return at
            before = at - 1
            while before >= start and page[before].isspace() and at - before < 8:
                before -= 1
            if page[before] == "=" and page[at] not in self.unpaired:
                close = page.find(page[at], at + 1)
                if close < 0:
                    self.unpaired.add(page[at])
                else:
                    at = close
            at += 1
        found = page.find(">", start)
        self.over = found < 0
        return found


def blocks(page: str | None) -> list[tuple[str, int, int, Place]]:
    """(text, words, words in links, place) of each flat block, in page order."""
    page = page or ""
    out, parts, linked = [], [], []
    stack, count = [Place()], Counter()
    links, at, end, tags, text_from, solid = 0, 0, len(page), Tags(page), 0, len(page.rstrip())

    def close() -> None:
        if parts:
            words = entities.unescape("".join(parts)).split() if not stack[-1].hidden else []
            if words:
                in_links = len(entities.unescape("".join(linked)).split()) if linked else 0
                out.append((" ".join(words), len(words), min(in_links, len(words)), stack[-1]))
            parts.clear()
            linked.clear()

    def text(until: int) -> None:
        if until > text_from:
            parts.append(page[text_from:until])
            if links:
                linked.append(page[text_from:until])

    def drop(name: str) -> None:
        """Closes the last open `name` and what is open inside it."""
        if count[name]:
            while True:
                gone = stack.pop().name
                count[gone] -= 1
                if gone == name:
                    return

    while True:
        at = page.find("<", at)
        if at < 0:
            break
        nxt = page[at + 1 : at + 2]
        if nxt == "!" or nxt == "?":
            text(at)
            if page.startswith("<!--", at):
                stop = page.find("-->", at + 4)
                at = stop + 3 if stop >= 0 else end
            else:
                stop = page.find(">", at) if not tags.over else -1
                at = stop + 1 if stop >= 0 else end
            text_from = at
            continue
        closing = nxt == "/"
        m = NAME.match(page, at + 1 + closing)
        stop = tags.end(m.end()) if m else -1
        if stop < 0:
            if m and m.end() >= solid:  # the page breaks off within a tag's name
                text(at)
                text_from = end
                break
            at += 1
            continue
        text(at)
        name, attributes = m[0].lower(), page[m.end() : stop]
        at = text_from = stop + 1
        if closing:
            if name == "a":
                links = 0
                linked.append(" ") if linked else None
            elif name in BLOCK or name in HIDDEN:
                close()
                links = 0
                drop(name)
            continue
        if name in RAW and not attributes.endswith("/"):
            close()
            m = re.compile(rf"</{name}(?=[\s/>])", re.IGNORECASE).search(page, at)
            stop = page.find(">", m.end()) if m else -1
            at = text_from = stop + 1 if stop >= 0 else end
        elif name == "a":
            links = 1
        elif name == "br":
            parts.append(" ")
        elif name in BLOCK or name in HIDDEN:
            close()
            links = 0
            if name in VOID or name in HIDDEN and attributes.endswith("/"):
                continue
            if count["head"] and name not in IN_HEAD:
                drop("head")
            if stack[-1].name == name and name in SIBLINGS or stack[-1].name == "p":
                count[stack.pop().name] -= 1  # its end tag was left out
            up = stack[-1]
            telling, remark, header = _told(attributes) if name not in ("body", "html") else (0, 0, 0)
            remark = int(up.remark or remark)
            inherited = up.telling and (name not in MAIN or up.remark)
            stack.append(
                Place(
                    name,
                    int(up.main or name in MAIN),
                    int(up.aside or name in ASIDE),
                    int(inherited or telling or remark),
                    int(name in HEADS),
                    int(up.header or name == "header" or header),
                    int(name in ITEMS),
                    int(name in ("p", "blockquote", "pre")),
                    remark,
                    int(up.hidden or name in HIDDEN),
                )
            )
            count[name] += 1
    text(end)
    close()
    return out


def features(found: list[tuple[str, int, int, Place]]) -> Iterator[tuple[int, ...]]:
    """One row of FEATURES for each block."""
    share = [100 * linked // n for _, n, linked, _ in found]
    for k, (_, n, _, place) in enumerate(found):
        before = (found[k - 1][1], share[k - 1]) if k else (0, 0)
        after = (found[k + 1][1], share[k + 1]) if k + 1 < len(found) else (0, 0)
        yield (n, share[k], *before, *after, *place[1:8])


def labelled(pages: list[str]) -> list[tuple[int, ...]]:
    """Rows of FEATURES and a label, from pages in which a block of main text begins with the mark."""
    rows = []
    for page in pages:
        marked = [b[0].startswith(MARK) for b in blocks(page)]
        plain = blocks(page.replace(MARK, ""))
        rows += [(*f, int(m)) for f, m in zip(features(plain), marked, strict=True)]
    return rows


LABELLED = labelled([path.read_text() for path in sorted((Path(__file__).parent / "labelled_pages").glob("*.html"))])
TREE = grow(LABELLED)


def extract(page: str | None, tree: object = TREE) -> str:
    """Main text of a page."""
    found = blocks(page)
    return "\n".join(b[0] for b, row in zip(found, features(found), strict=True) if leaf(tree, row) >= 0.5)


def op10_html(df: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [extract(x.as_py()) for x in b.column(2)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    rows = df.select(F.col("page_id").cast("bigint").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return rows.mapInArrow(run, "page_id bigint, url string, text string, n_chars bigint")
