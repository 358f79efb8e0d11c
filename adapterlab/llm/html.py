"""Main-text extraction by tag-path ratios.

Text length and punctuation are summed for each root-to-leaf tag path of a page; both ratios are smoothed along
the page and fused with a weight of the path's names (none for page furniture), and paths above a threshold hold the
content. The smallest element around all of that content and the sentences beside it, or the article that the page
names, is the article: its short blocks (headings, one-line paragraphs) count as well, if their path has a score.

Pages are scanned once, and no step looks back: markup that is cut off, never closed or nested without end costs time in
proportion to its length.
"""

from __future__ import annotations

import html as entities
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from adapterlab.llm.common import texts, with_small_batches

# Element kinds of HTML and words that name page furniture in classes, ids and roles.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style template noscript iframe textarea title svg math object canvas audio video select option button".split())
BLOCKS = frozenset(
    "address article aside blockquote body br caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 "
    "head header hr html legend li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split()
)
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
FURNITURE_TAGS = frozenset("head nav header footer aside form menu dialog fieldset".split()) | RAW
FURNITURE = frozenset(
    "ad ads adv advert adverts advertisement advertising banner sponsor sponsored promo promotion sidebar sidebars side menu menus nav navbar navigation "
    "breadcrumb breadcrumbs footer header masthead topbar cookie cookies consent gdpr notice notices alert popup modal overlay newsletter subscribe "
    "subscription signup login share sharing social comment comments disqus replies respond related recommended widget widgets pagination pager "
    "copyright search searchbox contentinfo complementary form toolbar".split()
)
CLOSED_BY = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
SCOPES = frozenset("ul ol dl table html body".split())
PUNCTUATION = re.compile(r"[.,;:!?…。，；：！？、¿¡]")
END_MARKS = frozenset(".!?…。！？")
TAG = re.compile(r"<(/?)([A-Za-z][^\s/>]*+)")
ATTRIBUTE = re.compile(r"""[\s/]*+(?:([^\s/>=][^\s/>=]*+|=)(?:\s*+=\s*+(?:"([^"]*+)"|'([^']*+)'|([^\s>]*+)))?)?""")
WORD = re.compile(r"[A-Z]?[a-z]+|[A-Z]+(?![a-z])")
SMOOTH = np.array([0.06, 0.24, 0.4, 0.24, 0.06])
THRESHOLD = 0.25  # of the best path's score
SHARE = 0.9  # of the content, in an article that the page names
SENTENCE_WORDS = 5
PHRASING = frozenset("p b i em strong span a font u".split()) | HEADINGS
SKIPPED = RAW - frozenset("select option button object canvas audio video svg math noscript template".split())


@dataclass
class Element:
    tag: str
    parent: int  # place in the page's list of elements, -1 for none
    depth: int
    path: int  # number of its root-to-element tag path
    furniture: bool  # it or an element around it
    linked: bool  # the same for links
    spoken: bool  # the same for headings and paragraphs


@dataclass
class Leaf:
    text: str
    element: int
    block: int


@dataclass
class Page:
    leaves: list[Leaf] = field(default_factory=list)
    elements: list[Element] = field(default_factory=list)
    paths: dict[tuple[int, str], int] = field(default_factory=dict)

    def sums(self, values: dict[int, float]) -> list[float]:
        """For each element what it and the elements inside it have; they follow it in the list."""
        total = [0.0] * len(self.elements)
        for k, v in values.items():
            total[k] += v
        for k in range(len(total) - 1, -1, -1):
            if self.elements[k].parent >= 0:
                total[self.elements[k].parent] += total[k]
        return total


def _attributes(page: str, at: int) -> tuple[dict[str, str], int, bool]:
    """Attributes of the tag whose name ends at `at`, where the tag ends, and whether it closes itself.

    A quote that is never closed counts as any other character.
    """
    found: dict[str, str] = {}
    closed = False
    while at < len(page) and page[at] != ">":
        m = ATTRIBUTE.match(page, at)
        if m[1]:
            found.setdefault(m[1].lower(), m[2] or m[3] or m[4] or "")
            closed = bool(m[4]) and m[4].endswith("/")
        else:
            closed = m[0].endswith("/")
        at = m.end()
    return found, min(at + 1, len(page)), closed


def _is_furniture(tag: str, attributes: dict[str, str]) -> tuple[bool, str]:
    """Whether tag, names or a hidden state say so, and the element's step in a tag path."""
    if not attributes:
        return tag in FURNITURE_TAGS, tag
    words = {w.lower() for name in ("class", "id", "role") if name in attributes for w in WORD.findall(attributes[name])}
    label = f"{tag}.{'.'.join(sorted(attributes['class'].lower().split()))}" if attributes.get("class") else tag
    named = bool(words & FURNITURE) and tag not in ("html", "body", "main", "article")
    if tag == "article" and words & {"comment", "comments", "related", "ad", "ads", "advert", "promo", "sponsored", "reply", "teaser"}:
        named = True
    hidden = "hidden" in attributes or attributes.get("aria-hidden", "").strip().lower() == "true"
    hidden |= "display:none" in "".join(attributes.get("style", "").lower().split())
    return tag in FURNITURE_TAGS or named or hidden, label


class _Open:
    """The open elements; the depth of the last one of a tag or kind is known without looking through them."""

    def __init__(self, elements: list[Element]):
        self.elements, self.stack = elements, []
        self.by_tag: dict[str, list[int]] = {}
        self.kinds: dict[str, list[int]] = {"": [], "block": [], "not p": [], "scope": []}

    def _places(self, tag: str) -> Iterator[list[int]]:
        yield self.by_tag.setdefault(tag, [])
        if tag in BLOCKS:
            yield self.kinds["block"]
            if tag != "p":
                yield self.kinds["not p"]
        if tag in SCOPES:
            yield self.kinds["scope"]

    def push(self, k: int) -> None:
        for places in self._places(self.elements[k].tag):
            places.append(len(self.stack))
        self.stack.append(k)

    def close(self, tags: set[str], stop: str) -> None:
        """Closes the last open element of `tags` with all inside it, unless one of kind `stop` is inside it."""
        at = max((p[-1] for t in tags if (p := self.by_tag.get(t))), default=-1)
        barrier = self.kinds[stop][-1] if self.kinds[stop] else -1
        if at < 0 or barrier > at:
            return
        while len(self.stack) > at:
            for places in self._places(self.elements[self.stack.pop()].tag):
                places.pop()


def parse(html: str) -> Page:
    page = Page()
    elements, leaves = page.elements, page.leaves
    open_ = _Open(elements)
    block, at, n = 0, 0, len(html)
    lower = ""

    def text(raw: str) -> None:
        if raw and not raw.isspace():
            leaves.append(Leaf(entities.unescape(raw), open_.stack[-1] if open_.stack else -1, block))
        elif raw and leaves and leaves[-1].block == block:
            leaves[-1].text += " "

    begin = 0  # of text not yet taken
    while (at := html.find("<", at)) >= 0:
        if html.startswith("<!--", at):
            text(html[begin:at])
            end = html.find("-->", at + 4)
            begin = at = end + 3 if end >= 0 else n
            continue
        if html.startswith(("<!", "<?"), at):
            text(html[begin:at])
            end = html.find(">", at)
            begin = at = end + 1 if end >= 0 else n
            continue
        if (m := TAG.match(html, at)) is None:
            at += 1  # a bare sign is text
            continue
        text(html[begin:at])
        tag = m[2].lower()
        attributes, begin, closed = _attributes(html, m.end())
        at = begin
        if tag in BLOCKS:
            block += 1
        if m[1]:
            open_.close({tag}, "" if tag in BLOCKS else "block")
            continue
        if tag in VOID:
            continue
        if tag in BLOCKS:
            open_.close({"p"}, "not p")
        if tag in CLOSED_BY:
            open_.close(CLOSED_BY[tag], "scope")
        if tag in SKIPPED:
            lower = lower or html.lower()
            lower = lower if len(lower) == n else "".join(c if len(c) == 1 else " " for c in map(str.lower, html))  # some letters grow
            end = lower.find(f"</{tag}", at)
            end = html.find(">", end) if end >= 0 else -1
            begin = at = end + 1 if end >= 0 else n
            continue
        furniture, label = _is_furniture(tag, attributes)
        parent = open_.stack[-1] if open_.stack else -1
        around = elements[parent] if parent >= 0 else Element("", -1, 0, -1, False, False, False)
        path = page.paths.setdefault((around.path, label), len(page.paths))
        said = tag == "p" or tag in HEADINGS
        elements.append(Element(tag, parent, around.depth + 1, path, furniture or around.furniture, tag == "a" or around.linked, said or around.spoken))
        if not closed:
            open_.push(len(elements) - 1)
    text(html[begin:])
    return page


def path_scores(page: Page) -> dict[int, float]:
    """Score of each tag path with text: its ratios of text and of punctuation to its leaves, smoothed along the page and
    fused; links add nothing, and a path inside page furniture weighs nothing."""
    elements, leaves = page.elements, page.leaves
    paths = [elements[x.element].path if x.element >= 0 else -1 for x in leaves]
    linked = [x.element >= 0 and elements[x.element].linked for x in leaves]
    weight = [0.0 if x.element >= 0 and elements[x.element].furniture else 1.0 for x in leaves]
    chars, stops, count = Counter(), Counter(), Counter()
    for x, p, link in zip(leaves, paths, linked):
        count[p] += 1
        if not link:
            chars[p] += len(x.text.strip())
            stops[p] += len(PUNCTUATION.findall(x.text))
    w = np.array(weight)
    ratio = np.array([chars[p] / count[p] for p in paths]) * w
    marks = np.array([stops[p] / count[p] for p in paths]) * w
    pad = len(SMOOTH) // 2
    smooth = lambda v: np.convolve(np.pad(v, pad, mode="edge"), SMOOTH, mode="valid")
    fused = np.sqrt(smooth(ratio) * ratio) * (1 + np.sqrt(smooth(marks) * marks))
    total: Counter[int] = Counter()
    for p, v in zip(paths, fused.tolist()):
        total[p] += v
    return {p: total[p] / count[p] for p in total}


def content_paths(scores: dict[int, float]) -> set[int]:
    """Paths whose score reaches the threshold."""
    least = THRESHOLD * max(scores.values(), default=0.0)
    return {p for p, v in scores.items() if v > 0 and v >= least}


def _has_sentence(text: str) -> bool:
    """An end mark after five words or more."""
    return any((bare := w.rstrip("\"')]}»”’*_"))[-1:] in END_MARKS and bare for w in text.split()[SENTENCE_WORDS - 1 :])


def main_text(html: str | None) -> str:
    """The article of a page; empty if there is none."""
    page = parse(html or "")
    elements, leaves = page.elements, page.leaves
    if not leaves:
        return ""
    scores = path_scores(page)
    chosen = content_paths(scores)
    path = lambda x: elements[x.element].path if x.element >= 0 else -1
    linked = lambda x: x.element >= 0 and elements[x.element].linked
    furniture = lambda x: x.element >= 0 and elements[x.element].furniture
    content = [x for x in leaves if path(x) in chosen]
    # Unlinked sentences beside the content, though on paths below the threshold, belong to the article.
    beside = [x for x in leaves if path(x) not in chosen and scores[path(x)] > 0 and not linked(x) and _has_sentence(x.text)]
    held, mass = Counter(x.element for x in content + beside), Counter()
    for x in content:
        mass[x.element] += len(x.text)
    whole = sum(mass.values())
    loose = held.pop(-1, 0)  # text outside all elements
    mass.pop(-1, 0)
    inside, weight = page.sums(held), page.sums(mass)
    around = [k for k, e in enumerate(elements) if not loose and inside[k] == sum(held.values()) and e.tag not in PHRASING]
    article = max(around, key=lambda k: elements[k].depth, default=-1)
    named = [k for k, e in enumerate(elements) if e.tag in ("article", "main") and weight[k] >= SHARE * whole]
    if named:  # the page says itself where the article is
        article = max(named, key=lambda k: elements[k].depth)
    within = [article < 0] * len(elements)
    for k, e in enumerate(elements):
        within[k] = article < 0 or k == article or (e.parent >= 0 and within[e.parent])
    # Blocks of nothing but links are menus, unless they are headings, paragraphs or amid the content.
    mixed = {x.block for x in leaves if not linked(x) and x.text.strip() and not furniture(x)}
    spots = [i for i, x in enumerate(leaves) if path(x) in chosen]
    blocks: dict[int, list[str]] = {}
    for i, x in enumerate(leaves):
        e = elements[x.element] if x.element >= 0 else None
        if path(x) not in chosen:
            if furniture(x) or not (within[x.element] if e else article < 0):
                continue
            if not (x.block in mixed or (e and e.spoken) or (spots and spots[0] < i < spots[-1])):
                continue
        blocks.setdefault(x.block, []).append(x.text)
    return " ".join(t for t in (" ".join("".join(b).split()) for b in blocks.values()) if t)


def extract_main_text(pages: DataFrame) -> DataFrame:
    """(page_id, url, text, n_chars) per row of `pages`; null html is an empty page with an empty text.

    Other columns are not read, repeated rows stay.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [main_text(t) for t in texts(batch.column("html"))]
            arrays = [batch.column("page_id"), batch.column("url"), pa.array(found, pa.string()), pa.array(map(len, found), pa.int64())]
            yield pa.RecordBatch.from_arrays(arrays, names=["page_id", "url", "text", "n_chars"])

    rows = with_small_batches(pages).select(F.col("page_id").cast("long"), F.col("url").cast("string"), "html")
    return rows.mapInArrow(run, "page_id long, url string, text string, n_chars long")
