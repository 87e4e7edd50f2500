"""Main text of web pages by tag-path ratios.

Each piece of text has a path of tags from the root. Over all pieces of one
path its text length, punctuation and linked text are summed and divided by
their number; the ratios are smoothed along the page and multiplied into one
score. Elements and names that mark menus, adverts, comments and their like
(``MARGINS``, ``MARKED``), and places outside a page's article element, divide
the score by ``PENALTY`` each, so that such text is content only where the page
has nothing better. The logarithm of a piece's score over the page's threshold
speaks for or against it. Elements take the labels content or not that agree
best with their pieces, where each change of label between an element and one
inside it costs ``CHANGE``; so a heading stays with the paragraphs around it,
and a menu or an advert inside an article goes.

Pages are read in time linear in their length, whatever they hold.
"""

from __future__ import annotations

import html
import re
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treesketch.llm.storage import only, small_batches

# Fixed values of HTML: elements without content, with raw content, that make blocks, that end an open paragraph.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript iframe xmp noembed noframes template".split())
BLOCKS = frozenset(
    "address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form frameset "
    "h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol optgroup option p pre section select summary table tbody tfoot thead tr ul".split()
)
CLOSES_P = BLOCKS - {"html", "head", "body", "option", "optgroup", "caption", "tbody", "tfoot", "thead", "tr", "legend"}
SIBLINGS = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",), "p": ("p",)}
SCOPES = frozenset("html body table ul ol dl td th article section main aside nav header footer form div blockquote figure select".split())
#: Elements whose text is never read, and those that mark what surrounds an article.
NEVER = frozenset("head button select input menu svg canvas object audio video map script style textarea title noscript iframe template xmp noembed noframes".split())
MARGINS = frozenset("nav footer aside form fieldset dialog label".split())
#: Words in class, id or role that mark what surrounds an article.
MARKED = frozenset(
    "ad ads adv advert adverts advertisement advertising sponsor sponsored promo promoted banner nav navbar navigation menu menubar breadcrumb breadcrumbs sidebar side aside widget widgets "
    "footer foot masthead topbar toolbar cookie cookies consent gdpr notice notices alert disclaimer newsletter subscribe subscription signup login share sharing social related recommended recommendation "
    "recommendations comment comments commentlist disqus reply replies respond discussion popup modal overlay pagination pager search form complementary contentinfo hidden".split()
)
LISTS = frozenset("ul ol dl table select menu dir".split())
#: A start tag after its "<": name and attributes; no quantifier gives back what it took, so a tag costs its length.
_START = r"""([a-zA-Z][^\s/>]*+)((?:[^=>]++|=\s*+"[^"]*+"|=\s*+'[^']*+'|=(?!\s*+["']))*+)>"""
_ATTRIBUTE = r"""([^\s=>/"']++)(?:\s*+=\s*+(?:"([^"]*+)"|'([^']*+)'|([^\s>]*+)))?"""
_PUNCTUATION = r"[.,;:!?…。、，；：！？]"
#: Pieces on either side that a ratio is smoothed over.
SMOOTH_RADIUS = 1
#: Characters and punctuation marks of a piece from which on a path's ratio counts in full.
FULL_LENGTH, FULL_MARKS = 300, 6
#: What each mark divides a score by, and the share of the page's highest score that makes content.
PENALTY = 1000
THRESHOLD = 0.01
#: Bound of a piece's vote, below which one against unmarked text is none, and the cost of a change of label, also where a marked element begins.
VOTE, DOUBT = 4.0, 1.0
CHANGE, CHANGE_AT_MARK = 2.0, 0.0
#: Marked text alone is an article only if it has punctuation or pieces of so many characters.
LONG = 80


@lru_cache(maxsize=10_000)
def _tokens_of_names(attributes: str) -> tuple[frozenset, bool]:
    """Words of class, id and role, and whether the element is hidden."""
    words, hidden = set(), False
    for found in re.finditer(_ATTRIBUTE, attributes):
        name = found[1].lower()
        value = found[2] or found[3] or found[4] or ""
        if name in ("class", "id", "role"):
            words.update(re.split(r"[^a-z0-9]+", re.sub(r"([a-z])([A-Z])", r"\1 \2", value).lower()))
        hidden |= name == "hidden" or (name == "aria-hidden" and value.lower() == "true") or (name == "style" and "display:none" in re.sub(r"\s+", "", value.lower()))
    return frozenset(words), hidden


def is_marked(tag: str, attributes: str, inside_article: bool) -> bool:
    """Whether an element's name or attributes say that it surrounds an article."""
    if tag in MARGINS or (tag == "header" and not inside_article):
        return True
    if not attributes or tag in ("html", "body", "article", "main"):
        return False
    words, hidden = _tokens_of_names(attributes) if len(attributes) < 1000 else _tokens_of_names.__wrapped__(attributes)
    return hidden or not MARKED.isdisjoint(words)


class Tags:
    """A page's text and tags in order, in linear time: ``next`` gives (text before, tag, attributes, closes) until the tag is None."""

    def __init__(self, page: str):
        self.page, self.at = page, 0
        self._last = page.rfind(">")
        self._quoted = True  # whether a ">" in quotes can be told from a tag's end
        self._start = re.compile(_START).match

    def skip_raw(self, tag: str) -> None:
        """Go behind the end tag of an element without markup in it; an open one ends the page."""
        found = re.compile(f"</{tag}(?=[\\s/>])", re.I).search(self.page, self.at)
        self.at = len(self.page) if found is None else self._behind(found.end())

    def _behind(self, at: int) -> int:
        end = self.page.find(">", at)
        return len(self.page) if end < 0 else end + 1

    def next(self) -> tuple[str, str | None, str, bool]:
        page, begin = self.page, self.at
        at = page.find("<", begin)
        while at >= 0:
            after = page[at + 1 : at + 2]
            if after.isascii() and after.isalpha() or after in ("/", "!", "?") and after:
                break
            at = page.find("<", at + 1)
        if at < 0:
            self.at = len(page)
            return page[begin:], None, "", False
        text = page[begin:at]
        if page.startswith("<!--", at):
            end = page.find("-->", at + 4)
            self.at = len(page) if end < 0 else end + 3
            return text, "", "", False
        if page.startswith("<![CDATA[", at):
            end = page.find("]]>", at)
            self.at = len(page) if end < 0 else end + 3
            return text + html.escape(page[at + 9 : end if end >= 0 else None]), "", "", False
        if at > self._last:  # a tag that the page ends in
            self.at = len(page)
            return text, None, "", False
        if after in "!?":
            self.at = self._behind(at)
            return text, "", "", False
        if after == "/":
            self.at = self._behind(at)
            name = re.match(r"[a-zA-Z][^\s/>]*+", page[at + 2 : self.at])
            return text, name[0].lower() if name else "", "", True
        found = self._start(page, at + 1) if self._quoted else None
        if found:
            self.at = found.end()
            return text, found[1].lower(), found[2], False
        self._quoted = False  # a quote stays open; from here on the next ">" ends a tag
        self.at = self._behind(at)
        name = re.match(r"[a-zA-Z][^\s/>]*+", page[at + 1 : self.at])
        return text, name[0].lower(), page[at + 1 + name.end() : self.at - 1], False


class Page:
    """A page as elements, pieces of text and blocks.

    Element 0 is the root; ``parent``, ``path`` (a number for each path of tags),
    ``marks``, ``inside`` (an article) and ``change`` (the cost of a label unlike
    the parent's) are lists by element. A piece is the
    text of one block in one element: ``element``, ``text``, ``linked`` (characters
    in links). A block is a list of (piece, raw text) in order.
    """

    def __init__(self, page: str):
        self.parent, self.path, self.marks, self.inside, self.change = [-1], [0], [0], [False], [0.0]
        self.element: list[int] = []
        self.text: list[str] = []
        self.linked: list[int] = []
        self.blocks: list[list[tuple[int, str]]] = []
        self._paths: dict[tuple[int, str], int] = {}
        self._read(page)

    def _add(self, above: int, tag: str, marked: bool) -> int:
        self.parent.append(above)
        self.path.append(self._paths.setdefault((self.path[above], tag), len(self._paths) + 1))
        self.marks.append(self.marks[above] + marked)
        self.change.append(CHANGE_AT_MARK if marked else CHANGE)
        self.inside.append(self.inside[above] or tag in ("article", "main"))
        return len(self.parent) - 1

    def _block(self, held: list[tuple[int, str, bool]]) -> None:
        parts: dict[int, list[tuple[str, bool]]] = {}
        for element, text, linked in held:
            parts.setdefault(element, []).append((text, linked))
        pieces: dict[int, int] = {}
        for element, texts in parts.items():
            text = " ".join(html.unescape("".join(t for t, _ in texts)).split())
            if text:
                pieces[element] = len(self.text)
                self.element.append(element), self.text.append(text)
                self.linked.append(sum(len(" ".join(t.split())) for t, linked in texts if linked))
        block = [(pieces[element], text) for element, text, _ in held if element in pieces]
        if block:
            self.blocks.append(block)

    def _read(self, page: str) -> None:
        tags = Tags(page)
        stack: list[tuple[str, int, bool, bool]] = [("", 0, False, False)]  # tag, element, whether its text is never read, whether it is linked
        held: list[tuple[int, str, bool]] = []
        open_: Counter = Counter()

        def flush() -> None:
            if held:
                self._block(held)
                held.clear()

        def say(text: str) -> None:
            if text and not stack[-1][2]:
                held.append((stack[-1][1], text, stack[-1][3]))

        def pop_to(index: int) -> None:
            while len(stack) > index:
                tag, _, dead, _ = stack.pop()
                open_[tag] -= 1
                if tag in BLOCKS and not dead:
                    flush()

        def close(names: tuple[str, ...], scopes: frozenset) -> None:
            if any(open_[n] for n in names):
                for i in range(len(stack) - 1, 0, -1):
                    if stack[i][0] in names:
                        return pop_to(i)
                    if stack[i][0] in scopes:
                        return None
            return None

        while True:
            text, tag, attributes, closes = tags.next()
            say(text)
            if tag is None:
                break
            if not tag:
                continue
            if closes:
                if tag in ("td", "th", "br"):
                    say(" ")
                if open_[tag] > 0:
                    i = len(stack) - 1
                    while stack[i][0] != tag:
                        i -= 1
                    pop_to(i)
                continue
            if tag in RAW:
                tags.skip_raw(tag)
                continue
            if tag in CLOSES_P:
                close(("p",), SCOPES - {"div"} if tag != "p" else SCOPES)
            if tag in SIBLINGS and tag != "p":
                close(SIBLINGS[tag], LISTS)
            if tag == "a":
                close(("a",), SCOPES)
            if tag in BLOCKS:
                flush()
            if tag in ("br", "td", "th"):
                say(" ")
            if tag in VOID:
                continue
            _, above, dead, linked = stack[-1]
            marked = not dead and is_marked(tag, attributes, self.inside[above])
            element = above
            if not dead and (marked or tag in BLOCKS):
                element = self._add(above, tag, marked)
            if tag not in BLOCKS and (marked or tag in NEVER):
                say(" ")
            if not attributes.rstrip().endswith("/") or tag in BLOCKS:
                stack.append((tag, element, dead or tag in NEVER, linked or (tag == "a" and "href" in attributes.lower())))
                open_[tag] += 1
        pop_to(1)
        flush()


class PageReader:
    def __init__(self):
        self._marks = re.compile(_PUNCTUATION).findall

    def ratios(self, page: Page) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Characters, punctuation marks and the share of linked characters of each piece's path, for each piece of it."""
        path = np.array([page.path[e] for e in page.element])
        sums = {}
        for name, values in (("chars", [len(t) for t in page.text]), ("marks", [len(self._marks(t)) for t in page.text]), ("linked", page.linked)):
            sums[name] = np.bincount(path, values)[path]
        n = np.bincount(path)[path]
        return sums["chars"] / n, sums["marks"] / n, np.minimum(1.0, sums["linked"] / sums["chars"])

    def scores(self, page: Page) -> np.ndarray:
        """The fused score of each piece: smoothed length times smoothed punctuation, less links and marks."""
        chars, marks, linked = self.ratios(page)
        level = self.levels(page)
        fused = self._smooth(np.minimum(chars, FULL_LENGTH), level) * (1 + self._smooth(np.minimum(marks, FULL_MARKS), level)) * (1 - linked) ** 2
        return fused / float(PENALTY) ** np.minimum(level, 4)

    @staticmethod
    def levels(page: Page) -> np.ndarray:
        """Marks of each piece: those of its element, and one if it is outside the page's article element."""
        level = np.array([page.marks[e] for e in page.element])
        inside = np.array([page.inside[e] for e in page.element])
        return level + ~inside if (inside & (level == 0)).any() else level

    @staticmethod
    def _smooth(x: np.ndarray, level: np.ndarray) -> np.ndarray:
        """Weighted means over neighbours along the page with as many marks."""
        total, weight = x.astype(np.float64), np.ones(len(x))
        for o in range(1, min(SMOOTH_RADIUS, len(x) - 1) + 1):
            same = (level[o:] == level[:-o]) * np.exp(-0.5 * o * o)
            total[o:] += same * x[:-o]
            total[:-o] += same * x[o:]
            weight[o:] += same
            weight[:-o] += same
        return total / weight

    def votes(self, scores: np.ndarray, level: np.ndarray) -> np.ndarray:
        """For each piece the bounded logarithm of its score over the page's threshold; a weak one against unmarked text is none."""
        limit = THRESHOLD * scores.max()
        if limit <= 0:
            return np.full(len(scores), -VOTE)
        votes = np.clip(np.log(np.maximum(scores, 1e-300) / limit), -VOTE, VOTE)
        return np.where((votes < 0) & (votes > -DOUBT) & (level == 0), 0.0, votes)

    @staticmethod
    def labels(parent: list[int], change: list[float], element: list[int], votes: list[float]) -> list[bool]:
        """Whether each piece is content, by the labels of elements and pieces with the greatest sum of votes less the changes.

        An element unlike its parent costs its ``change``, a piece unlike its
        element ``CHANGE``. Elements are numbered from the root on, an element
        above those inside it.
        """
        gain = [[0.0, 0.0] for _ in parent]
        for e, v in zip(element, votes):
            gain[e][0] += max(0.0, v - CHANGE)
            gain[e][1] += max(v, -CHANGE)
        for e in range(len(parent) - 1, 0, -1):
            out, in_ = gain[e]
            above = gain[parent[e]]
            above[0] += max(out, in_ - change[e])
            above[1] += max(in_, out - change[e])
        label = [gain[0][1] > gain[0][0]]
        for e in range(1, len(parent)):
            out, in_ = gain[e]
            label.append(in_ >= out - change[e] if label[parent[e]] else in_ - change[e] > out)
        return [v >= -CHANGE if label[e] else v > CHANGE for e, v in zip(element, votes)]

    def text(self, source: str | None) -> str:
        """The article's blocks, one to a line; empty for a page without text."""
        page = Page(source or "")
        if not page.text:
            return ""
        kept = self.labels(page.parent, page.change, page.element, self.votes(self.scores(page), self.levels(page)).tolist())
        chosen = [i for i, k in enumerate(kept) if k]
        if all(page.marks[page.element[i]] for i in chosen):
            pieces = [page.text[i] for i in chosen]
            if not any(self._marks(t) for t in pieces) and sum(map(len, pieces)) < LONG * len(pieces):
                return ""
        lines = []
        for block in page.blocks:
            line = " ".join(html.unescape("".join(t if kept[i] else " " for i, t in block)).split())
            if line:
                lines.append(line)
        return "\n".join(lines)


def extract_main_text(pages: DataFrame) -> DataFrame:
    """``page_id, url, text`` for each row of ``pages(page_id, url, html)``; a null or empty page gives an empty text."""
    small_batches(pages.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        reader = PageReader()
        for batch in batches:
            texts = [reader.text(page.as_py()) for page in batch.column(2)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string())], names=["page_id", "url", "text"])

    return only(pages, "page_id", "url", "html").select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html")).mapInArrow(run, "page_id long, url string, text string")
