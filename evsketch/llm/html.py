"""Main text of web pages by composite text density.

A tolerant tag scanner builds a node tree. Each node has text characters, tags, link characters
and link tags of its subtree; its density is characters per tag, damped by the logarithm of the
share of link text in it against the body's. The densities of a node's children are summed; the
threshold is the least density on the path from the body to the node of the largest sum, and the
subtree with the largest sum at or above it is the content. Inside it, boilerplate elements
(navigation, forms, adverts, reader comments and the like) are left out, and the remaining blocks
are written in page order.

A class, id or role that is a marked word drops its element; one that only has such a part does where
the element is less dense than the page; html and body, main and article never go by their names.

Defined cases: null, empty or text-free html gives an empty text; markup that never closes ends
with the page; a page without tags is one block; repeated rows give equal rows; other columns are
not read.
"""

from __future__ import annotations

import math
import re
from dataclasses import dataclass, field
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame

from evsketch.llm.common import arrow_map, empty_safe

# Element names by role.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template textarea title iframe xmp noembed noframes".split())
DROPPED = frozenset(
    "script style noscript template textarea title iframe xmp noembed noframes head nav header footer aside form button select option label svg math canvas object audio video map menu dialog fieldset datalist input embed".split()
)
BLOCK = frozenset(
    "address article aside blockquote body br button caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol option p pre search section summary table tbody td tfoot th thead tr ul".split()
)
#: Words in a class, id or role that mark an element as not part of the article.
MARKS = frozenset(
    "ad ads adv advert adverts advertisement advertising banner sponsor sponsored promo promoted cookie cookies consent gdpr notice notices popup modal overlay newsletter subscribe subscription nav navbar navigation menu breadcrumb breadcrumbs sidebar side rail widget widgets related recommended recommendations share sharing social comment comments commentlist disqus respond reply replies reader-comments footer header masthead topbar toolbar pagination pager login signup search complementary contentinfo alert disclaimer copyright legal".split()
)
#: Elements that a start tag of the same group closes.
CLOSES = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
SCOPE = frozenset("ul ol dl table select body html div article section main td th".split())
NOT_IN_P = BLOCK - frozenset(["br", "button", "option", "caption", "legend"])

_TAG = re.compile(r"<(?:!--.*?(?:-->|\Z)|!\[CDATA\[(.*?)\]\]>|[!?][^>]*(?:>|\Z)|/([A-Za-z][^\s/>]*)[^>]*(?:>|\Z)|([A-Za-z][^\s/>]*)((?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+[^>]*)(?:>|\Z))", re.S)
_ATTR = re.compile(r"""(class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>"']+))""", re.I)
_HIDDEN = re.compile(r"""(?:\shidden(?=[\s=/>]|$)|aria-hidden\s*=\s*["']?true|display\s*:\s*none)""", re.I)
_WORD = re.compile(r"[a-z0-9]+(?:-[a-z]+)?")
_PART = re.compile(r"[A-Za-z][a-z0-9]*|[0-9]+")


@dataclass(slots=True)
class Node:
    tag: str
    drop: bool = False
    link: bool = False
    parent: Node | None = None
    doubt: bool = False  # a part of a class name is marked; density decides
    parts: list = field(default_factory=list)  # str or Node, in page order
    chars: int = 0
    tags: int = 0
    link_chars: int = 0
    link_tags: int = 0
    density: float = 0.0
    total: float = 0.0


def _marked(attrs: str) -> tuple[bool, bool, bool]:
    """Whether a whole class, id or role, or only a part of one, names what is not the article; whether it is hidden."""
    if not attrs or "=" not in attrs and "hidden" not in attrs:
        return False, False, False
    whole = part = False
    for m in _ATTR.finditer(attrs):
        for name in (m[2] or m[3] or m[4] or "").split():
            whole = whole or name.lower() in MARKS
            part = part or any(p.lower() in MARKS for p in _PART.findall(name))
    return whole, part, bool(_HIDDEN.search(attrs))


def parse(html: str) -> Node:
    """The page's tree; unclosed elements end where HTML's rules close them."""
    root = Node("html")
    here, at, size = root, 0, len(html)
    while at < size:
        m = _TAG.search(html, at)
        if not m:
            here.parts.append(html[at:])
            break
        if m.start() > at:
            here.parts.append(html[at : m.start()])
        at = m.end()
        if m[1]:
            here.parts.append(m[1])
        elif m[2]:
            name, node = m[2].lower(), here
            while node is not root and node.tag != name:
                node = node.parent
            if node is not root:
                here = node.parent
        elif m[3]:
            name, attrs = m[3].lower(), m[4] or ""
            if name in ("html", "body"):
                if name == "body":
                    while here is not root:
                        here = here.parent
                continue
            if name in NOT_IN_P:
                node = here
                while node is not root and node.tag not in NOT_IN_P:
                    node = node.parent
                if node.tag == "p":
                    here = node.parent
            if name in CLOSES:
                node = here
                while node is not root and node.tag not in CLOSES[name] and node.tag not in SCOPE:
                    node = node.parent
                if node.tag in CLOSES[name]:
                    here = node.parent
            whole, part, hidden = _marked(attrs)
            named = name not in ("main", "article")  # these are the article whatever their class
            node = Node(name, name in DROPPED or hidden or whole and named, name == "a", here, part and named)
            here.parts.append(node)
            if name in VOID or attrs.endswith("/"):
                continue
            if name in RAW:
                end = re.compile(rf"</{re.escape(name)}(?=[\s/>])[^>]*>|\Z", re.I).search(html, at)
                at = end.end()
                continue
            here = node
    return root


def _postorder(root: Node) -> list[Node]:
    order, stack = [], [root]
    while stack:
        node = stack.pop()
        order.append(node)
        stack.extend(x for x in node.parts if isinstance(x, Node) and not x.drop)
    return order[::-1]


def weigh(root: Node) -> list[Node]:
    """Composite density and the sum of children's densities for all kept nodes, children first."""
    order = _postorder(root)
    for n in order:
        n.chars = n.tags = n.link_chars = n.link_tags = 0
        for x in n.parts:
            if isinstance(x, str):
                n.chars += len(x.strip())
            elif not x.drop:
                n.chars += x.chars
                n.tags += x.tags + 1
                n.link_chars += x.link_chars
                n.link_tags += x.link_tags + x.link
        if n.link:
            n.link_chars = n.chars
    body = root.link_chars / max(1, root.chars)
    for n in order:
        if not n.chars:
            n.density = 0.0
            continue
        plain = n.chars / max(1, n.tags)
        other = max(1, n.chars - n.link_chars)
        base = math.log(n.chars / other * n.link_chars + body * n.chars + math.e)
        scale = (n.chars / max(1, n.link_chars)) * (max(1, n.tags) / max(1, n.link_tags))
        n.density = plain * max(0.0, math.log(max(1.0, scale)) / math.log(max(math.e, base)))
        if not n.link_chars:
            n.density = plain * max(1.0, math.log(max(math.e, scale)) / math.log(max(math.e, base)))
    for n in order:
        n.total = sum(x.density for x in n.parts if isinstance(x, Node) and not x.drop)
    return order


def main_node(root: Node) -> Node:
    """The subtree of the largest density sum under the body-path threshold."""
    order = weigh(root)
    doubtful = [n for n in order if n.doubt and n.density < root.density]
    if doubtful:
        for n in doubtful:
            n.drop = True
        order = weigh(root)
    best = max(order, key=lambda n: n.total)
    if best.total <= 0:
        return root
    floor, node = best.density, best
    while node is not None:
        floor = min(floor, node.density) if node.density else floor
        node = node.parent
    chosen = max((n for n in order if n.density >= floor), key=lambda n: n.total, default=best)
    # A semantic container around the choice is the article itself, with its headings.
    node = chosen
    while node is not None:
        if node.tag in ("article", "main"):
            return node
        node = node.parent
    inside = [n for n in order if n.tag == "article" and _under(n, chosen)]
    if len(inside) == 1:
        return inside[0]
    return chosen if chosen.tag not in ("p", "b", "span", "em", "strong", "i", "a") or chosen.parent is None else _container(chosen)


def _under(node: Node | None, top: Node) -> bool:
    while node is not None:
        if node is top:
            return True
        node = node.parent
    return False


def _container(node: Node) -> Node:
    while node.parent is not None and node.tag not in ("div", "section", "td", "html", "body"):
        node = node.parent
    return node


def blocks(top: Node) -> list[str]:
    """The kept text under ``top``, one string per block, references decoded, white space folded."""
    out: list[str] = []
    run: list[str] = []

    def close() -> None:
        text = " ".join(unescape("".join(run)).split())
        if text:
            out.append(text)
        run.clear()

    stack: list = [iter(top.parts)]
    ends: list[bool] = [False]
    while stack:
        for x in stack[-1]:
            if isinstance(x, str):
                run.append(x)
            elif not x.drop:
                block = x.tag in BLOCK
                if block:
                    close()
                stack.append(iter(x.parts))
                ends.append(block)
                break
        else:
            stack.pop()
            if ends.pop():
                close()
    close()
    return out


def main_text(html: str | None) -> str:
    return " ".join(blocks(main_node(parse(html)))) if html else ""


def extract(pages: DataFrame, key: str = "page_id", url: str = "url", html: str = "html") -> DataFrame:
    """One row per page: key, url, its main text and the text's code points."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        texts = [main_text(h) for h in empty_safe(batch.column(html)).to_pylist()]
        return pa.RecordBatch.from_arrays([batch.column(key), batch.column(url), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())], [key, url, "text", "n_chars"])

    kind = {c: pages.schema[c].dataType.simpleString() for c in (key, url)}
    return arrow_map(pages.select(key, url, html), run, f"`{key}` {kind[key]}, `{url}` {kind[url]}, text string, n_chars long")
