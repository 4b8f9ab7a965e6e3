"""Main text of web pages: flat text blocks, features of neighbours, a decision tree.

A page is cut at block-level tags into flat blocks.  Each block has its word count and link density, those of the
block before and of the block after it, one mark (an element around it says menu, notice, advert and so on: by its
class or id words, or, stronger, by its tag or role) and its zone (inside an article or main element, outside of it,
or on a page without one).  A CART tree (Gini, numpy) trained on the labelled pages of ``labelled_pages`` gives each
block's class.  They are written by a rule: eleven layouts, with and without article elements and class words, whose
block lengths come from a seeded generator; training takes a moment on the driver.  Character references are decoded, white space
inside a block becomes one space, and the blocks of class text are joined by line ends.

Tags are read as the HTML standard reads them: a quote opens a value after an equals sign only, values have any
length, and an unclosed quote leaves the tag to end at its first ``>``.  Reading is linear in the page.

One pass, no shuffle; memory is that of one page and its blocks.  Edge cases: null and empty pages give the empty text; unclosed tags, comments
and scripts end at the page's end; an unclosed container ends where an article or main element opens; very long pages, texts and
attributes are read whole; blocks with equal figures get equal verdicts (a value equal to a split's limit goes to its low side);
repeated rows give repeated results; an empty table gives none; other columns are ignored, whatever their names.
"""

from __future__ import annotations

import html as references
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from tilemine.llm.common import table

_NAME = re.compile(r"(/?)([A-Za-z][^\s/>]*+)")
#: White space and slashes, then the tag's end or one attribute with its value.
_ATTRIBUTE = re.compile(r"""[\s/]*+(?:(>)|([^\s/>][^\s/>=]*+)(?:\s*+=\s*+("[^"]*+"|'[^']*+'|(?!["'])[^\s>]++)?+)?+)""")
#: Element names of the HTML standard.
_INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_RAW = frozenset("script style textarea noscript template iframe svg math object select title xmp noembed noframes canvas audio video".split())
_UNPUSHED = frozenset("p li dt dd tr td th option thead tbody tfoot html".split())
_BOILER_TAGS = frozenset("nav aside footer header form menu dialog button fieldset head".split())
_BOILER_ROLES = frozenset("navigation banner contentinfo complementary search form dialog alertdialog alert menu menubar note".split())
_TEXT_TAGS = frozenset("p h1 h2 h3 h4 h5 h6 li dt dd td th blockquote pre figure figcaption".split())
_HINTED = frozenset("span small strong em b i".split())
#: Words of class and id attributes that name parts other than the article, on any element.
_BOILER_NAMES = frozenset(
    "ad ads advert adverts advertisement advertising adbox banner promo promotion sponsor sponsored sponsors cookie cookies consent gdpr notification popup modal overlay newsletter subscribe subscription "
    "sidebar nav navbar navigation breadcrumb breadcrumbs masthead topbar toolbar footer comments disqus login signin signup pagination pager copyright disclaimer widget widgets tagcloud".split()
)
#: Words that do so on containers only; a paragraph or heading may bear them for other reasons.
_CONTAINER_NAMES = frozenset("notice notices side menu menus header foot comment reply replies respond share sharing social related recommended recommendations more register search legal form tags teaser skip".split())
_CONTENT_NAMES = frozenset("article content post entry story main body text".split())
_READ = frozenset("class id role hidden aria-hidden style".split())


@dataclass
class Block:
    text: str
    words: int
    link_words: int
    mark: int  # 0: none, 1: class or id words, 2: tag, role or hidden
    article: bool


def _tag(page: str, at: int) -> tuple[int, dict[str, str]]:
    """The end of the tag whose name ends at ``at``, and its attributes of _READ."""
    found: dict[str, str] = {}
    while m := _ATTRIBUTE.match(page, at):
        at = m.end()
        if m[1]:
            return at, found
        key = m[2].lower()
        if key in _READ:
            found.setdefault(key, (m[3] or "").strip("\"'").lower())
    return len(page), found


def _mark(name: str, attributes: dict[str, str], in_article: bool) -> int:
    """What an element says of the blocks in it; an article's own header holds its title."""
    if name in _BOILER_TAGS and not (name == "header" and in_article):
        return 2
    if not attributes or name in ("body", "html", "article", "main"):
        return 0
    if attributes.get("role") in _BOILER_ROLES or "hidden" in attributes or attributes.get("aria-hidden") == "true" or re.search(r"display\s*:\s*none", attributes.get("style", "")):
        return 2
    for one in f"{attributes.get('class', '')} {attributes.get('id', '')}".split():
        parts = [x for x in re.split(r"[^a-z]+", one) if x]
        if parts and not (len(parts) > 1 and parts[-1] in _CONTENT_NAMES):
            if any(x in _BOILER_NAMES or x in _CONTAINER_NAMES and name not in _TEXT_TAGS for x in (parts[0], parts[-1])):
                return 1
    return 0


def blocks(page: str) -> list[Block]:
    """The page's flat text blocks in order."""
    out: list[Block] = []
    parts: list[tuple[str, bool]] = []
    stack: list[tuple[str, int]] = []
    marked = [0, 0, 0]
    article = link = at = begin = 0

    def close() -> None:
        if parts:
            text = " ".join("".join(t for t, _ in parts).split())
            if text:
                linked = sum(len(t.split()) for t, is_link in parts if is_link)
                out.append(Block(text, len(text.split()), linked, 2 if marked[2] else 1 if marked[1] else 0, article > 0))
            parts.clear()

    def read(stop: int) -> None:
        if stop > begin:
            parts.append((references.unescape(page[begin:stop]), link > 0))

    while (at := page.find("<", at)) >= 0:
        opened = at
        m = _NAME.match(page, at + 1)
        if m is None:
            if page.startswith("<!--", at):
                end = page.find("-->", at + 2)
                at = len(page) if end < 0 else end + 3
            elif page[at + 1 : at + 2] in ("!", "?", "/"):
                end = page.find(">", at)
                at = len(page) if end < 0 else end + 1
            else:  # a literal sign
                at += 1
                continue
            read(opened)
            begin = at
            continue
        read(opened)
        closing, name = m[1] == "/", m[2].lower()
        at, attributes = (m.end() + 1, {}) if page.startswith(">", m.end()) else _tag(page, m.end())
        begin = at
        if name == "a":
            link = 0 if closing else 1
            continue
        if name in _RAW:
            if not closing and page[at - 2] != "/":
                if name not in _INLINE:
                    close()
                end = re.compile(rf"</{name}\b[^>]*>?", re.I).search(page, at)
                at = begin = end.end() if end else len(page)
            continue
        if name == "br":
            parts.append((" ", False))
            continue
        mark = 0 if closing else _mark(name, attributes, article > 0)
        if name in _INLINE and not (mark and name in _HINTED) and not any(s[0] == name for s in stack[-3:]):
            continue
        close()
        link = 0
        if name in _VOID or name in _UNPUSHED and not mark and not any(s[0] == name for s in stack):
            continue
        if closing:
            depth = next((i for i in range(len(stack) - 1, -1, -1) if stack[i][0] == name), None)
            if depth is not None:
                for gone, was in stack[depth:]:
                    marked[was] -= 1
                    article -= gone in ("article", "main")
                del stack[depth:]
        else:
            if name in ("body", "main") or name == "article" and not article and any(s[0] in _BOILER_TAGS for s in stack):
                stack.clear()
                marked, article = [0, 0, 0], 0
            if name in _UNPUSHED and stack and stack[-1][0] == name:
                marked[stack.pop()[1]] -= 1
            stack.append((name, mark))
            marked[mark] += 1
            article += name in ("article", "main")
    read(len(page))
    close()
    return out


def features(found: list[Block]) -> np.ndarray:
    """Rows of: words, link density; the same of the block before and after; the mark; the zone (0 outside of the page's
    article, 1 on a page that has none, 2 inside)."""
    n = len(found)
    own = np.array([[b.words, b.link_words / max(b.words, 1)] for b in found], float).reshape(n, 2)
    before, after = np.zeros_like(own), np.zeros_like(own)
    before[1:], after[:-1] = own[:-1], own[1:]
    elsewhere = 0 if any(b.article for b in found) else 1
    flags = np.array([[b.mark, 2 if b.article else elsewhere] for b in found], float).reshape(n, 2)
    return np.concatenate([own, before, after, flags], axis=1)


class Tree:
    """A binary CART tree: Gini gain, midpoints between neighbouring values, the first best split."""

    def __init__(self, x: np.ndarray, y: np.ndarray, depth: int = 12, least: int = 8):
        self.verdict = bool(y.mean() >= 0.5)
        self.split: tuple[int, float] | None = None
        if depth and 0 < y.sum() < len(y):
            best = (1e-9, 0, 0.0)
            total = 2 * y.sum() * (len(y) - y.sum()) / len(y)
            for f in range(x.shape[1]):
                order = np.argsort(x[:, f], kind="stable")
                v, k = x[order, f], np.cumsum(y[order])
                i = np.flatnonzero(v[1:] != v[:-1]) + 1
                i = i[(i >= least) & (i <= len(y) - least)]
                if len(i):
                    low, high, rest = k[i - 1], k[-1] - k[i - 1], len(y) - i
                    gain = total - 2 * low * (i - low) / i - 2 * high * (rest - high) / rest
                    j = int(gain.argmax())
                    if gain[j] > best[0] + 1e-9:
                        best = (gain[j], f, (v[i[j] - 1] + v[i[j]]) / 2)
            if best[0] > 1e-9:
                self.split = best[1:]
                low = x[:, best[1]] <= best[2]
                self.low, self.high = Tree(x[low], y[low], depth - 1, least), Tree(x[~low], y[~low], depth - 1, least)

    def predict(self, x: np.ndarray) -> np.ndarray:
        if self.split is None:
            return np.full(len(x), self.verdict)
        low = x[:, self.split[0]] <= self.split[1]
        out = np.empty(len(x), bool)
        out[low], out[~low] = self.low.predict(x[low]), self.high.predict(x[~low])
        return out

    def used(self) -> set[int]:
        """Features that some split asks for."""
        return set() if self.split is None else {self.split[0]} | self.low.used() | self.high.used()


def _w(n: int) -> str:
    return " ".join(["word"] * int(n))


class Layout:
    """Writes one labelled page: markup, and a character for each block, 1 for main text."""

    def __init__(self, seed: int):
        self.random, self.html, self.labels = np.random.default_rng(seed), [], []

    def some(self, low: int, high: int) -> int:
        return int(self.random.integers(low, high + 1))

    def put(self, html: str, label: str) -> None:
        self.html.append(html)
        self.labels.append(label)

    def links(self, low: int, high: int, each: int = 3, open_: str = "<ul>", shut: str = "</ul>", tag: str = "li") -> None:
        n = self.some(low, high)
        self.put(open_ + "".join(f'<{tag}><a href="/{i}">{_w(self.some(1, each))}</a></{tag}>' for i in range(n)) + shut, "0" * n)

    def text(self, low: int, high: int, tag: str = "p", label: str = "1") -> None:
        n = self.some(low, high)
        linked = n // 8 if n > 12 and self.random.random() < 0.3 else 0
        link = f" <a href=x>{_w(linked)}</a>" if linked else ""
        self.put(f"<{tag}>{_w(n - linked)}{link}</{tag.split()[0]}>", label)

    def prose(self, low: int, high: int, tag: str = "p") -> None:
        """Paragraphs of all lengths, single words among them, now and then one that is a link."""
        for _ in range(self.some(low, high)):
            kind = self.random.random()
            if kind < 0.2:
                self.text(1, 6, tag)
            elif kind < 0.3:
                if self.random.random() < 0.5:
                    self.text(1, 3, tag)
                self.text(10, 90, tag)
                self.put(f"<{tag}><a href=y>{_w(self.some(2, 9))}</a></{tag}>", "1")
                self.text(20, 60, tag)
            else:
                self.text(10, 160, tag)

    def page(self) -> tuple[str, str]:
        return "".join(self.html), "".join(self.labels)


def _news(p: Layout) -> None:
    p.links(3, 9, 2, "<header><nav><ul>", "</ul></nav></header>")
    p.put("<article>", "")
    p.text(3, 12, "h1")
    p.prose(3, 12)
    p.put("</article>", "")
    p.text(8, 60, "aside", "0")
    p.text(2, 40, "footer", "0")


def _news_with_related(p: Layout) -> None:
    """Links to other stories stand inside the article, unmarked, in a row."""
    p.links(3, 7, 2, "<nav><ul>", "</ul></nav>")
    p.put("<article>", "")
    p.text(3, 9, "h1")
    p.prose(2, 5)
    p.text(25, 60)
    p.links(3, 6, 9)
    p.put("</article>", "")
    p.text(3, 9, "footer", "0")


def _plain(p: Layout) -> None:
    """No article element, no class words: only lengths and links tell."""
    p.links(4, 9, 2)
    p.text(3, 10, "h1")
    p.text(30, 90)
    for _ in range(p.some(1, 4)):
        p.text(1, 6)
        p.text(30, 150)
    p.links(3, 7, 4)
    p.text(2, 6, "div", "0")


def _plain_short(p: Layout) -> None:
    """As _plain, with paragraphs of medium length and a line below the links."""
    p.links(3, 5, 2)
    for _ in range(p.some(2, 6)):
        p.text(12, 40)
    p.links(2, 5, 3)
    p.text(3, 9, "div", "0")


def _adverts(p: Layout) -> None:
    """Class words on containers; adverts and notices as long as paragraphs."""
    p.text(5, 50, 'div class="notice"', "0")
    p.put("<article>", "")
    p.text(1, 8, "h2")
    for _ in range(p.some(2, 5)):
        p.text(1, 90)
        if p.random.random() < 0.5:
            p.text(4, 60, 'div class="ad"', "0")
    p.text(2, 70)
    p.put("</article>", "")
    p.put("<section id=comments>", "")
    for _ in range(p.some(1, 4)):
        p.text(4, 60, "p", "0")
    p.put("</section>", "")


def _marked(p: Layout) -> None:
    """Class words without an article element."""
    p.links(3, 6, 2, '<div class="menu"><ul>', "</ul></div>")
    p.text(20, 60, 'div class="sidebar"', "0")
    for _ in range(p.some(2, 5)):
        p.text(15, 90)
        if p.random.random() < 0.4:
            p.text(5, 55, 'div class="promo"', "0")
    p.text(20, 80)
    p.text(4, 40, "form", "0")
    p.text(3, 40, "footer", "0")


def _main(p: Layout) -> None:
    """A main element with short entries; lines of any length outside of it."""
    p.text(2, 30, "div", "0")
    p.put("<main>", "")
    p.text(1, 5, "h1")
    for _ in range(p.some(2, 7)):
        p.text(1, 9, "li")
    p.prose(1, 3)
    p.put("</main>", "")
    p.text(2, 60, "div", "0")
    p.links(1, 4, 5, "<div>", "</div>", "p")


def _bare(p: Layout) -> None:
    """An article with nothing around it, or short lines; single words between and at the end."""
    if p.random.random() < 0.4:
        p.text(1, 4, "header", "0")
    p.put("<article>", "")
    p.text(1, 14, "h1")
    p.text(1, 14)
    p.prose(1, 9)
    p.text(1, 3)
    p.text(60, 400)
    if p.random.random() < 0.5:
        p.text(1, 2)
    else:
        p.text(20, 60)
        p.put(f"<p><a href=y>{_w(p.some(3, 9))}</a></p>", "1")
        p.text(20, 60)
    p.put("</article>", "")
    if p.random.random() < 0.4:
        p.put(f"<footer>{_w(p.some(1, 9))}</footer>", "0")


def _short_story(p: Layout) -> None:
    """An article of a heading and a few words between much longer other parts."""
    p.links(3, 7, 2, "<nav><ul>", "</ul></nav>")
    p.text(10, 80, 'div class="ad"', "0")
    p.put("<article>", "")
    p.text(1, 12, "h1")
    for _ in range(p.some(1, 3)):
        p.text(1, 25)
    p.put("</article>", "")
    if p.random.random() < 0.5:
        p.text(1, 90, "div", "0")


def _teasers(p: Layout) -> None:
    """No article element; below the text other stories, each a link and some words of it."""
    p.links(4, 9, 2)
    p.text(3, 10, "h1")
    for _ in range(p.some(2, 6)):
        p.text(15, 150)
    for _ in range(p.some(3, 6)):
        p.put(f"<h3><a href=z>{_w(p.some(3, 9))}</a></h3>", "0")
        p.text(10, 40, "p", "0")
    p.put(f"<h3><a href=z>{_w(p.some(3, 9))}</a></h3>", "0")
    p.text(2, 9, "div", "0")


def _hub(p: Layout) -> None:
    """Link lists with short headings and nothing to read."""
    for _ in range(p.some(2, 4)):
        p.text(1, 4, "h2", "0")
        p.links(3, 7, 8)
    p.text(2, 6, "div", "0")


LAYOUTS = (_news, _news_with_related, _plain, _plain_short, _adverts, _marked, _main, _bare, _short_story, _teasers, _hub)


def labelled_pages(each: int = 60, seed: int = 1) -> list[tuple[str, str]]:
    """The labelled table: ``each`` pages of every layout."""
    out = []
    for i in range(each):
        for j, layout in enumerate(LAYOUTS):
            page = Layout(seed * 10_000 + i * len(LAYOUTS) + j)
            layout(page)
            out.append(page.page())
    return out


def rows(labelled: list[tuple[str, str]]) -> tuple[np.ndarray, np.ndarray]:
    """Features and classes of labelled pages."""
    x, y = [], []
    for page, labels in labelled:
        found = blocks(page)
        if len(found) != len(labels):
            raise ValueError(f"{len(found)} blocks, {len(labels)} labels: {page[:80]}")
        x.append(features(found))
        y += [int(c) for c in labels]
    return np.concatenate(x), np.array(y)


def train(labelled: list[tuple[str, str]] | None = None, depth: int = 12) -> Tree:
    return Tree(*rows(labelled_pages() if labelled is None else labelled), depth)


def main_text(page: str, tree: Tree) -> str:
    found = blocks(page)
    return "\n".join(b.text for b, yes in zip(found, tree.predict(features(found))) if yes) if found else ""


def extract(pages: DataFrame, page: str = "page_id", url: str = "url", html: str = "html", labelled: list[tuple[str, str]] | None = None) -> DataFrame:
    """(page_id, url, text, n_chars) per row of ``pages``."""
    schema = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("text", pa.string()), ("n_chars", pa.int64())])
    tree = train(labelled)  # a few dozen numbers, sent with the function

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start in range(0, batch.num_rows, 256):
                part = batch.slice(start, 256)
                texts = [main_text(x or "", tree) for x in part.column(2).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1).cast(pa.string()), pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64())], schema=schema)

    return pages.select(F.col(page).cast("long").alias("page_id"), F.col(url).cast("string").alias("url"), F.col(html).cast("string").alias("html")).mapInArrow(run, "page_id long, url string, text string, n_chars long")


def op4_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(table(spark, sf_dir, "pages"))
