"""Main text of web pages by scoring the element tree.

Paragraph-like elements earn points for their length and their commas and pass
them to their ancestors, less the further up; a container's points are
discounted by the share of its text that lies in links. The best container is
kept, with those siblings that score alike.

Elements are left out for what they are (nav, footer, ...), for their role, or
for a word of a class or id. Such words are a rule of thumb, so they give way:
a name that tells what an element has or not ("has-sidebar", "share-enabled",
"main-with-ads") does not count, words that also name parts of an article do
not count on paragraphs, and where nothing is left, they are not applied. A
form that wraps an article or paragraphs is no form but a container.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Element names of HTML by their role here.
RAW = frozenset("script style noscript template iframe noembed noframes xmp".split())
RAW_TEXT = frozenset("textarea title".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
DROPPED = frozenset("head nav header footer aside form script style noscript template iframe noembed noframes xmp textarea title svg math canvas object audio video button select input dialog menu fieldset datalist map".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr img".split())
PARAGRAPHS = frozenset("p pre blockquote td dd li div section article main figcaption".split())
ENDS_PARAGRAPH = frozenset("address article aside blockquote details div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
PARAGRAPHS_ALONE = frozenset("p pre blockquote li td dd figcaption".split())
CLOSES = {"li": ("li", "ul ol menu".split()), "dt": ("dt dd", ["dl"]), "dd": ("dt dd", ["dl"]), "tr": ("tr td th", ["table"]), "td": ("td th", "tr table".split()), "th": ("td th", "tr table".split()), "option": ("option", ["select"])}
UNLIKELY_ROLES = frozenset("navigation banner contentinfo complementary search dialog alert alertdialog menu menubar form status".split())
#: Words in class or id that mostly stand at what is no article text.
UNLIKELY = frozenset(
    "ad ads adv advert adverts advertisement advertising sponsor sponsored promo promotion banner cookie cookies consent gdpr notice notices alert popup modal overlay newsletter subscribe subscription signup login"
    " comment comments commentlist respond reply replies disqus discussion sidebar aside menu nav navbar navigation breadcrumb breadcrumbs pagination pager share sharing social related recommended footer masthead"
    " toolbar widget widgets tags copyright legal disclaimer skip".split()
)

#: Words by which a class or id tells what an element has, not what it is.
QUALIFIERS = frozenset("has have with without no not non is show hide enabled disabled enable disable on off open".split())
#: Words that also name parts of an article, where they stand at a paragraph or heading.
FINE_IN_TEXT = frozenset("legal copyright disclaimer discussion reply replies respond skip alert notice notices tags status related".split())
#: Characters in paragraphs that make a form a container, and in a text that is taken without regard to words.
WRAPPED, LEAST_TEXT = 140, 140
#: A short block beside the container that is a sentence belongs to it from this length on.
LEAD = 15
_SENTENCE = re.compile(r"[.!?…。！？][\"'”’»)\]]*\s*$")

_TOKEN = re.compile(r"<!--.*?(?:-->|$)|<![^>]*>?|<\?[^>]*>?|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']++|\"[^\"]*\"|'[^']*'|[\"'])*+)(?:>|$)", re.S)
_ATTRIBUTE = re.compile(r"(?:^|[\s\"'/])(class|id|role|hidden|aria-hidden|style)\b(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.I)
_WORD = re.compile(r"[a-z]+")
_CAMEL = re.compile(r"(?<=[a-z])(?=[A-Z])")


class Element:
    __slots__ = ("by_word", "children", "dropped", "links", "parent", "points", "size", "tag")

    def __init__(self, tag: str, parent: Element | None, dropped: bool = False, by_word: bool = False):
        self.tag, self.parent, self.dropped, self.by_word, self.children = tag, parent, dropped, by_word, []
        self.points = self.size = self.links = 0.0


def _named_unlikely(tag: str, names: str) -> bool:
    """Whether a class or id says that an element is no article text."""
    for name in names.split():
        words = _WORD.findall(_CAMEL.sub(" ", name).lower())
        found = UNLIKELY.intersection(words)
        if found and QUALIFIERS.isdisjoint(words) and not ((tag in PARAGRAPHS_ALONE or tag in HEADINGS) and found <= FINE_IN_TEXT):
            return True
    return False


def _unlikely(tag: str, attributes: str) -> int:
    """1: hidden or by its role, 2: by a word of its class or id."""
    worded = 0
    for name, a, b, c in _ATTRIBUTE.findall(attributes):
        name, value = name.lower(), a or b or c
        if name == "hidden" or name == "aria-hidden" and value.lower() == "true":
            return 1
        if name == "style":
            if "display:none" in value.replace(" ", "").lower():
                return 1
        elif name == "role":
            if value.lower() in UNLIKELY_ROLES:
                return 1
        elif name in ("class", "id") and _named_unlikely(tag, value):
            worded = 2
    return worded


def parse(html: str) -> Element:
    """Element tree of a page, however broken: open elements end where HTML lets them, the rest at the end."""
    root = Element("html", None)
    forms: list[Element] = []
    at, here, end = root, 0, len(html)
    while here < end:
        m = _TOKEN.search(html, here)
        if m is None:
            at.children.append(html[here:])
            break
        if m.start() > here:
            at.children.append(html[here : m.start()])
        here = m.end()
        if not (tag := (m[2] or "").lower()):
            continue
        if m[1]:
            node = at
            while node is not None and node.tag != tag:
                # an inline end tag does not reach out of the block that it stands in
                node = None if tag in INLINE and node.tag not in INLINE else node.parent
            if node is not None and node.parent is not None:
                at = node.parent
            elif tag == "p" and node is None:
                at.children.append(Element("p", at))
            continue
        if tag in ("html", "body"):
            if tag == "body" and at.tag == "head":
                at = at.parent
            continue
        if at.tag == "head" and tag not in ("title", "meta", "link", "base", "script", "style", "noscript", "template"):
            at = at.parent
        if tag in ENDS_PARAGRAPH:
            node = at
            while node is not None and (node.tag in INLINE or node.tag in HEADINGS and tag in HEADINGS):
                node = node.parent
            if node is not None and node.tag == "p":
                at = node.parent
            elif node is not None and tag in HEADINGS and at.tag in HEADINGS:
                at = at.parent
        elif tag in CLOSES:
            ended, within = CLOSES[tag]
            ended, node = ended.split(), at
            found = None
            while node is not None and node.tag not in within and node.tag not in ("html",):
                if node.tag in ended:
                    found = node
                node = node.parent
            if found is not None:
                at = found.parent
        why = 1 if tag in DROPPED else _unlikely(tag, m[3]) if m[3] else 0
        node = Element(tag, at, why > 0, why == 2)
        at.children.append(node)
        if tag == "form":
            forms.append(node)
        if tag in VOID or m[3].endswith("/") and tag not in ENDS_PARAGRAPH and tag not in INLINE:
            continue
        if tag in RAW or tag in RAW_TEXT:
            close = re.compile(rf"</{re.escape(tag)}(?=[\s/>])[^>]*>?", re.I).search(html, here)
            here = close.end() if close else end
            continue
        at = node
    for form in reversed(forms):  # inner ones first
        form.dropped = not _wraps(form)
    return root


def _wraps(form: Element) -> bool:
    """Whether a form holds an article or main element, or paragraphs of some length."""
    size, todo = 0, [(form, False)]
    while todo:
        node, inside = todo.pop()
        for c in node.children:
            if type(c) is str:
                size += len(c.strip()) if inside else 0
            elif not c.dropped:
                if c.tag in ("article", "main") or size >= WRAPPED:
                    return True
                todo.append((c, inside and c.tag != "label" or c.tag == "p"))
    return size >= WRAPPED


def _order(root: Element) -> list[Element]:
    """Kept elements, parents first, without recursion: pages may nest deeply."""
    found, todo = [], [root]
    while todo:
        node = todo.pop()
        if not node.dropped:
            found.append(node)
            todo += [c for c in reversed(node.children) if type(c) is Element]
    return found


def score(root: Element) -> Element:
    """Sets sizes and points; returns the best container."""
    order = _order(root)
    commas: dict[Element, int] = {}
    for node in order:
        node.points = 0.0
    for node in reversed(order):  # children before parents
        size, links, marks, own = 0.0, 0.0, 0, 0.0
        for c in node.children:
            if type(c) is str:
                n = len(c.strip())
                size, own = size + n, own + n
                marks += c.count(",") + c.count("،") + c.count("，") + c.count("、")
            elif not c.dropped:
                size, links, marks = size + c.size, links + (c.size if c.tag == "a" else c.links), marks + commas[c]
                if c.tag in INLINE:
                    own += c.size
        node.size, node.links, commas[node] = size, links, marks
        if node.tag in PARAGRAPHS and own > 0:
            points = (1 + marks + min(node.size / 100, 3)) * (1 - node.links / node.size)
            up, part = (node if node.tag in ("div", "section", "article", "main", "td") else node.parent), 1.0
            while up is not None and part > 0.05:
                up.points += points * part
                up, part = up.parent, part / 2 if part == 1.0 else part * 2 / 3
    best, most = root, -1.0
    for node in order:
        rated = node.points * (1 - node.links / node.size) if node.size else 0.0
        if node.tag not in INLINE and node.tag not in ("p", "li", "ul", "ol", "tr") and rated > most:
            best, most = node, rated
    # an article or main element above that holds little else is the container itself
    up = best.parent
    while up is not None:
        if up.tag in ("article", "main") and up.points >= most / 3:
            best = up
        up = up.parent
    return best


def _blocks(node: Element, out: list[list[str]]) -> None:
    """Adds the text of ``node``, in page order, as blocks of parts.

    Lists of links stay, as references do; what is navigation, aside or related
    by its element, role, class or id was dropped in ``parse``.
    """
    todo: list = [node]
    while todo:
        c = todo.pop()
        if type(c) is str:
            out[-1].append(c)
        elif c is None:
            out.append([])
        elif not c.dropped:
            if c.tag == "br":
                out[-1].append(" ")
            inline = c.tag in INLINE
            if not inline:
                out.append([])
                todo.append(None)
            todo += reversed(c.children)


def _joined(out: list[list[str]]) -> str:
    return " ".join(filter(None, (" ".join(unescape("".join(b)).split()) for b in out)))


def _text_of(node: Element) -> str:
    out: list[list[str]] = [[]]
    _blocks(node, out)
    return _joined(out)


def _is_lead(c: Element, density: float) -> bool:
    """A short block of one or more sentences without links, as leads and intermediate remarks are."""
    return c.tag in ("div", "section", "p", "blockquote") and c.size >= LEAD and density == 0 and bool(_SENTENCE.search(_text_of(c)))


def _main_text(root: Element) -> str:
    best = score(root)
    kept = [best]
    if best.parent is not None:
        least = max(1.0, 0.2 * best.points)
        kept = []
        for c in best.parent.children:
            if type(c) is Element and not c.dropped:
                density = c.links / c.size if c.size else 1.0
                if c is best or c.points * (1 - density) >= least or c.tag in HEADINGS and c.size or c.tag == "p" and c.size >= 80 and density < 0.25 or _is_lead(c, density):
                    kept.append(c)
    out: list[list[str]] = [[]]
    for c in kept:
        _blocks(c, out)
        out.append([])
    return _joined(out)


def extract(html: str | None) -> str:
    """The article's text, white space inside a block made one space, blocks joined by one space; empty if none.

    If nothing is left, elements that went by a word of their class or id come
    back, and the text is taken if it has some length.
    """
    if not html:
        return ""
    root = parse(html)
    text = _main_text(root)
    if not text:
        todo, back = [root], False
        while todo:
            node = todo.pop()
            back |= node.by_word
            node.dropped = node.dropped and not node.by_word
            todo += [c for c in node.children if type(c) is Element]
        again = _main_text(root) if back else ""
        text = again if len(again) >= LEAST_TEXT else ""
    return text


def extract_pages(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars of every page, from its whole html.

    Null or empty html gives an empty text; a null page_id or url stays null;
    repeated rows are extracted each; other columns take no part. Rows are
    independent: no shuffle.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [extract(h.as_py()) for h in batch.column(2)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    slim = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return slim.mapInArrow(run, "page_id long, url string, text string, n_chars long")
