"""Main text of web pages by composite text density.

The page becomes a tree of elements.  Parts that never hold an article (scripts, navigation, footers, forms,
and elements whose class, id or role names them as such) are cut off.  Every other element has a density: its
characters outside links for each tag in it, lowered by its share of link text.  An element's density sum is
that of its children and of its own text; the subtree with the largest sum is the main text, widened to its
article or main element.  Inside it, elements whose density is below the least on the path from the body to
it and whose text is mostly links are left out.  Articles beside it at or above that density with
few links are kept as well; on a page without an article element so are all such parts beside the path, and
headings, which are short but belong to what follows them.

Defined results: null html is empty; a page without text gives an empty string.  Unclosed, misnested and
unknown tags are tolerated.  Repeated rows are each returned.  Empty table: empty result.
"""

from __future__ import annotations

import re
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame

from skipsketch.llm.common import arrow_map, values

VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: Elements whose content is no text.
RAW = frozenset("script style template noscript iframe svg textarea title object audio video canvas".split())
SKIPPED = RAW | frozenset("head nav header footer aside form button select dialog menu".split())
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd mark q s samp small span strike strong sub sup time tt u var wbr label math mi mo mn mrow mfrac msup msub mtext".split())
#: Start tags that close an open paragraph.
CLOSES_P = frozenset("address article aside blockquote center details div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())
SAME = {"li": ("ul", "ol", "menu"), "dt": ("dl",), "dd": ("dl",), "tr": ("table",), "td": ("tr", "table"), "th": ("tr", "table"), "option": ("select",)}
#: Elements at which the search for an open paragraph ends, and those of lists and tables.
STOPS = frozenset("article main body div section td li table blockquote".split())
LISTS = frozenset(SAME) | frozenset(x for stop in SAME.values() for x in stop)
#: Words in class, id or role that name parts other than the article.
BOILERPLATE = frozenset("""ad ads advert advertisement adverts advertising banner breadcrumb breadcrumbs comment comments consent cookie
    cookies disqus footer header masthead menu nav navbar navigation newsletter notice notices pager pagination popup promo related
    share sharing sidebar skip social sponsor sponsored subscribe toolbar widget complementary contentinfo""".split())
#: Words that such names are put together with; a name with any other word (related-work, notice-period) says nothing.
NEUTRAL = frozenset("""area articles bar block bottom box buttons container content count form global group header inner item items left
    link links list main message outer page panel post posts primary reader right row secondary section site slot stories the thread title
    to top unit user users wrap wrapper""".split())
#: Elements of text itself: what they are called does not make them another part.
TEXTUAL = frozenset("html body article main h1 h2 h3 h4 h5 h6".split())
#: Elements of which an id may be the anchor of a part of the article; only class and role name these.
ANCHORED = frozenset("section p li dl dt dd table tr td th blockquote pre figure".split()) | INLINE

_token = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>", re.S)
_attribute = re.compile(r"""(?:^|\s)(class|id|role|hidden|aria-hidden)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>"']+)))?""", re.I)
_part = re.compile(r"[^A-Za-z0-9]+|(?<=[a-z])(?=[A-Z])")
_space = re.compile(r"[ \t\n\r\f\v\xa0  -     　]+")


class Node:
    __slots__ = ("tag", "parent", "items", "skip", "chars", "linked", "tags", "sum", "own", "block", "listed")

    def __init__(self, tag: str, parent: Node | None, skip: bool):
        self.tag, self.parent, self.items, self.skip = tag, parent, [], skip
        # the nearest of itself and what holds it that matters to start tags that close others
        self.block = self if tag == "p" or tag in STOPS or parent is None else parent.block
        self.listed = self if tag in LISTS or parent is None else parent.listed
        self.chars = self.linked = self.tags = self.own = 0
        self.sum = 0.0


def _names_other(name: str) -> bool:
    """Whether a class or id names a part other than the article: by boilerplate words and neutral ones only."""
    found = [x.lower() for x in _part.split(name) if x and not x.isdigit()]
    return any(x in BOILERPLATE for x in found) and all(x in BOILERPLATE or x in NEUTRAL for x in found)


def _skipped(tag: str, attributes: str) -> bool:
    if tag in SKIPPED:
        return True
    if not attributes:
        return False
    for name, *value in _attribute.findall(attributes):
        name = name.lower()
        if name == "hidden" or name == "aria-hidden" and "true" in value:
            return tag not in ("html", "body")
        if tag in TEXTUAL or name == "aria-hidden" or name == "id" and tag in ANCHORED:
            continue
        if any(map(_names_other, "".join(value).split())):
            return True
    return False


def parse(html: str) -> Node:
    """The tree; an item of a node is a text or a node."""
    root = at = Node("#", None, False)
    opened: dict[str, int] = {}  # elements that are open, by tag
    pos, n = 0, len(html)
    while pos < n:
        m = _token.search(html, pos)
        if m is None:
            at.items.append(html[pos:])
            break
        if m.start() > pos:
            at.items.append(html[pos : m.start()])
        pos = m.end()
        tag = m.group(2)
        if tag is None:
            if m.group().startswith("<![CDATA["):
                at.items.append(m.group()[9:].removesuffix("]]>").replace("&", "&amp;"))
            continue
        tag = tag.lower()
        if m.group(1):
            if opened.get(tag):  # each step up closes an element for good
                while at.tag != tag:
                    opened[at.tag] -= 1
                    at = at.parent
                opened[tag] -= 1
                at = at.parent
            continue
        if tag in CLOSES_P or tag in SAME:
            goal = tag if tag in SAME else "p"
            up = at.block if goal == "p" else at.listed
            while goal != "p" and opened.get(goal) and up.parent is not None and up.tag not in SAME[tag] and up.tag != goal:
                up = up.parent.listed
            if up.parent is not None and up.tag == goal and opened.get(goal):
                while at is not up.parent:
                    opened[at.tag] -= 1
                    at = at.parent
        node = Node(tag, at, _skipped(tag, m.group(3)))
        at.items.append(node)
        if tag in RAW:
            end = re.compile(rf"</{re.escape(tag)}\b[^>]*>|\Z", re.I).search(html, pos)
            pos = end.end()
        elif tag not in VOID and not m.group(3).rstrip().endswith("/"):
            at = node
            opened[tag] = opened.get(tag, 0) + 1
    return root


def density(node: Node) -> float:
    """Characters outside links for each tag, lowered by the share of link text."""
    if not node.chars:
        return 0.0
    plain = node.chars - node.linked
    return plain / max(1, node.tags) * (plain / node.chars)


def measure(root: Node) -> list[Node]:
    """Fill in the counts bottom-up; the nodes in page order."""
    order, stack = [], [root]
    while stack:
        node = stack.pop()
        order.append(node)
        stack += [x for x in reversed(node.items) if isinstance(x, Node) and not x.skip]
    for node in reversed(order):
        node.own = sum(len(_space.sub("", x)) for x in node.items if isinstance(x, str))
        node.chars += node.own
        if node.tag == "a":
            node.linked = node.chars
        node.sum += node.own
        if node.parent is not None:
            up = node.parent
            up.chars += node.chars
            up.linked += node.linked
            up.tags += node.tags + 1
            up.sum += density(node)
    return order


def chosen(root: Node) -> tuple[list[Node], float]:
    """The subtrees that hold the main text, in page order, and the least density on the path to the best."""
    order = measure(root)
    best = max(order, key=lambda x: x.sum)
    path = [best]
    while path[-1].parent is not None:
        path.append(path[-1].parent)
    wide = next((x for x in reversed(path) if x.tag in ("article", "main")), None)
    top = wide or best
    least = min((density(x) for x in path if x.tag != "#"), default=0.0)
    while top.tag in INLINE or top.tag in ("p", "h1", "h2", "h3", "h4", "h5", "h6", "li"):  # a block alone is no subtree
        top = top.parent
    keep = [top]
    # parts beside the path, up to the body, that are as dense as it is and no links; headings belong to what follows
    node = top
    while node.parent is not None and wide is None:
        node = node.parent
        beside = [x for x in node.items if isinstance(x, Node) and not x.skip and x not in path and x is not top and x.tag not in INLINE]
        keep += [x for x in beside if 2 * x.linked < x.chars and (x.tag in HEADINGS or density(x) >= least > 0)]
    if wide is not None:
        keep += [x for x in order if x.tag == wide.tag and x is not top and density(x) >= least > 0 and 2 * x.linked < x.chars]
    place = {id(x): i for i, x in enumerate(order)}
    own = {id(x) for x in keep}
    return sorted((x for x in keep if not _under(x, own)), key=lambda x: place[id(x)]), least


HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())


def _under(node: Node, kept: set[int]) -> bool:
    """Whether something that holds the node is kept."""
    while (node := node.parent) is not None:
        if id(node) in kept:
            return True
    return False


def blocks(node: Node, least: float) -> list[str]:
    """The texts of the blocks, in page order."""
    out: list[str] = []
    held: list[str] = []

    def close() -> None:
        if held:
            text = _space.sub(" ", unescape("".join(held))).strip(" ")
            held.clear()
            if text:
                out.append(text)

    stack: list = [node]
    while stack:
        x = stack.pop()
        if x is None:
            close()
        elif isinstance(x, str):
            held.append(x)
        elif x.skip or (x is not node and x.tag not in INLINE and 2 * x.linked > x.chars and density(x) < least and x.tag in ("ul", "ol", "div", "section", "table", "dl")):
            continue
        elif x.tag == "br":
            held.append(" ")
        elif x.tag in INLINE:
            stack += reversed(x.items)
        else:
            close()
            stack.append(None)
            stack += reversed(x.items)
    close()
    return out


def main_text(html: str | None) -> str:
    if not html:
        return ""
    keep, least = chosen(parse(html))
    return "\n".join(x for node in keep for x in blocks(node, least))


def extracted(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars: a row for each page."""

    def each(batch: pa.RecordBatch) -> pa.RecordBatch:
        texts = [main_text(x) for x in values(batch.column(2))]
        return pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(x) for x in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    kind = pages.schema["page_id"].dataType.simpleString()
    return arrow_map(pages.select("page_id", "url", "html"), each, f"page_id {kind}, url string, text string, n_chars long")


def oracle() -> str:
    """The same in SQL for the pages of the given tables, whose article is marked as such."""
    article = "regexp_replace(regexp_replace(regexp_extract(html, '(?s)<article>(.*)</article>', 1), '<br>', ' ', 'g'), '</?b>', '', 'g')"
    parts = f"string_split_regex({article}, '</?(?:p|h1)>')"
    decoded = "replace(replace(replace(replace(replace(x, '&lt;', '<'), '&gt;', '>'), '&quot;', '\"'), '&#x27;', ''''), '&amp;', '&')"
    text = f"array_to_string(list_filter(list_transform({parts}, lambda x: trim(regexp_replace({decoded}, '\\s+', ' ', 'g'))), lambda x: x <> ''), chr(10))"
    return f"SELECT page_id, url, coalesce({text}, '') AS text, length(coalesce({text}, ''))::BIGINT AS n_chars FROM pages"
