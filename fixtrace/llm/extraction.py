"""Main-text extraction by tree scoring.

A tolerant tokenizer builds a block tree (implied end tags, raw-text elements, unclosed inline markup).  Boiler-
plate subtrees go by element, role, class or id.  Each remaining text block passes points for length and commas
to its ancestors, halved at each step, in one pass from the leaves up; a container's points are discounted by the share of its text inside
links.  The best container is kept together with siblings that score near it.

Defined results: null, empty and text-free pages give an empty text; a page without any element is one block;
repeated rows give repeated results; very long, deep or malformed pages are handled whole, in time in proportion to
their length (times a logarithm where quotes are never closed).  Only ``page_id``, ``url`` and ``html``
are read.  One Arrow pass, no shuffle.
"""

from __future__ import annotations

import bisect
import html as entities
import re

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from fixtrace.llm.common import by_batch, table

#: A start or end tag whose quoted values are closed; what does not match is cut by ``_Tags``.
_TAG = re.compile(r"<(/?)([A-Za-z][^\s/>]*+)((?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+)>")
_HEAD = re.compile(r"<(/?)([A-Za-z][^\s/>]*+)")
_ATTRIBUTE = re.compile(r"""([^\s=/"']++)(?:\s*+=\s*+("[^"]*+"?|'[^']*+'?|[^\s"'>]++))?|.""", re.S)
_RAW = {"script", "style", "textarea", "title", "xmp", "iframe", "noembed", "noframes"}
_VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "source", "track", "wbr", "param"}
_BLOCK = {
    "html", "body", "address", "article", "aside", "blockquote", "center", "dd", "details", "dialog", "dir", "div", "dl", "dt", "fieldset",
    "figcaption", "figure", "footer", "form", "h1", "h2", "h3", "h4", "h5", "h6", "header", "hgroup", "hr", "li", "main", "menu", "nav",
    "ol", "p", "pre", "section", "summary", "table", "tbody", "thead", "tfoot", "tr", "td", "th", "caption", "ul", "option",
}
_GONE = {
    "head", "script", "style", "noscript", "template", "nav", "footer", "aside", "form", "button", "select", "textarea", "iframe", "svg",
    "canvas", "object", "embed", "audio", "video", "menu", "dialog", "title", "noembed", "noframes", "map", "input", "math", "label", "fieldset",
}
#: An open element of the value is ended by a start tag of the key, unless a boundary of the third part lies between.
_ENDS = {"li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr", "td", "th"}, {"table"}), "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "option": ({"option"}, {"select"})}
_ROLES = {"navigation", "banner", "contentinfo", "complementary", "search", "form", "dialog", "alert", "alertdialog", "menu", "menubar", "toolbar"}
_BAD = re.compile(
    r"(?:^|[\s_-])(?:ads?|adverts?|advert\w*|adslot|adbox|banner|promo\w*|sponsor\w*|sidebar|sidenav|side|menu|nav|navbar|navigation|breadcrumbs?"
    r"|footer|masthead|cookies?|consent|gdpr|notices?|alert|popup|modal|overlay|newsletter|subscribe|subscription|signup|login|share|sharing|social"
    r"|related|recommend\w*|comments?|commentlist|respond|reply|replies|disqus|pagination|pager|widgets?|toolbar|skip|topbar|header)(?:$|[\s_-])",
    re.I,
)
_TITLED = re.compile(r"(?:article|entry|post|story|content)[\w-]*[\s_-]header", re.I)
#: Names such as "has-sidebar" tell of the page around, not of the element.
_SAYS_OF_PAGE = re.compile(r"(?<!\S)(?:has|with|no|without)[-_]\S+", re.I)
_KEPT = {"html", "body", "article", "main"}


class Node:
    """An element; ``owner`` is the nearest block element, itself included."""

    __slots__ = ("tag", "parent", "owner", "children", "gone", "depth", "own", "held", "score", "scored", "chars", "linked", "first", "kept", "menu")

    def __init__(self, tag: str, parent: Node | None, gone: bool):
        self.tag, self.parent, self.gone = tag, parent, gone
        self.owner: Node = self if parent is None or tag in _BLOCK else parent.owner
        self.depth = 0 if parent is None else parent.depth + 1
        self.children: list[Node | str] = []
        self.own = self.held = self.score = 0.0
        self.chars = self.linked = 0
        self.first = -1
        self.scored = self.kept = self.menu = False


class _Tags:
    """Ends of tags on a page where some quoted value is never closed, each quote followed once for all tags.

    A tag ends at the first ``>`` outside quotes, or, where its quotes are never closed, at the first ``>``.
    """

    def __init__(self, page: str):
        self.at = {c: [m.start() for m in re.finditer(c, page)] for c in (">", '"', "'")}
        self.special = sorted(x for found in self.at.values() for x in found)
        self.page = page
        self.ends: dict[int, int] = {}

    def _after(self, found: list[int], start: int) -> int:
        k = bisect.bisect_left(found, start)
        return found[k] if k < len(found) else -1

    def end(self, start: int) -> int:
        """Position of the ``>`` that ends a tag whose attributes begin at ``start``; -1 without any."""
        path, here, out = [], start, None
        while out is None:
            stop = self._after(self.special, here)
            if stop < 0 or self.page[stop] == ">":
                out = stop
            elif stop in self.ends:
                out = self.ends[stop]
            else:
                path.append(stop)
                close = self._after(self.at[self.page[stop]], stop + 1)
                if close < 0:
                    out = -1
                here = close + 1
        for x in path:
            self.ends[x] = out
        return out if out >= 0 else self._after(self.at[">"], start)


def _unwanted(tag: str, raw: str, inside: bool) -> bool:
    if tag in _GONE or tag == "header" and not inside:
        return True
    if not raw or raw.isspace():
        return False
    found: dict[str, str] = {}
    for m in _ATTRIBUTE.finditer(raw):
        if m[1]:
            found.setdefault(m[1].lower(), (m[2] or "").strip("\"'"))
    if "hidden" in found or found.get("aria-hidden", "").lower() == "true" or re.search(r"display\s*+:\s*+none", found.get("style", ""), re.I):
        return True
    if tag in _KEPT:
        return False
    if found.get("role", "").lower() in _ROLES:
        return True
    named = _SAYS_OF_PAGE.sub(" ", f"{found.get('class', '')} {found.get('id', '')}")
    return bool(_BAD.search(named)) and not _TITLED.search(named)


def parse(page: str) -> list[Node]:
    """The elements of a page, parents first; texts are decoded, subtrees of boilerplate are marked ``gone``.

    Each character is looked at a bounded number of times, and an open element is found by its tag, not by climbing.
    """
    root = at = Node("#root", None, False)
    nodes = [root]
    open_tags: dict[str, list[Node]] = {}
    tables: _Tags | None = None
    here = search = 0

    def close(node: Node) -> None:
        nonlocal at
        while at is not node.parent:
            open_tags[at.tag].pop()
            at = at.parent

    def opened(tags, stop) -> Node | None:
        """The innermost open element of ``tags``, unless one of ``stop`` is open further in."""
        found = max((open_tags[t][-1] for t in tags if open_tags.get(t)), key=lambda n: n.depth, default=None)
        if found and any(open_tags[t][-1].depth > found.depth for t in stop if open_tags.get(t)):
            return None
        return found

    def write(text: str) -> None:
        if text and not at.gone:
            at.children.append(entities.unescape(text) if "&" in text else text)

    while (start := page.find("<", search)) >= 0:
        follows = page[start + 1 : start + 2]
        if follows in ("!", "?") and follows:
            write(page[here:start])
            mark = "-->" if page.startswith("<!--", start) else ">"
            end = page.find(mark, start + (4 if mark == "-->" else 1))
            here = search = end + len(mark) if end >= 0 else len(page)
            continue
        m = _TAG.match(page, start) if tables is None else None
        if m:
            closing, name, raw, after = m[1], m[2], m[3], m.end()
        else:
            letter = page[start + 2 : start + 3] if follows == "/" else follows
            if not ("a" <= letter <= "z" or "A" <= letter <= "Z"):
                search = start + 1
                continue
            tables = tables or _Tags(page)
            end = tables.end(start + 1)
            if end < 0:
                break  # no tag ends any more: the rest is text
            head = _HEAD.match(page, start, end)
            closing, name, raw, after = head[1], head[2], page[head.end() : end], end + 1
        write(page[here:start])
        here = search = after
        tag = name.lower()
        if closing:
            if node := opened((tag,), ("table",) if tag in ("p", "li") else ()):
                close(node)
            continue
        if tag == "br":
            if not at.gone:
                at.children.append(" ")
            continue
        if tag in _BLOCK and (node := opened(("p",), ("table", "td", "th", "button"))):
            close(node)
        if tag in _ENDS:
            for _ in range(2):
                if node := opened(*_ENDS[tag]):
                    close(node)
        child = Node(tag, at, at.gone or _unwanted(tag, raw, bool(open_tags.get("article") or open_tags.get("main"))))
        nodes.append(child)
        if tag in _VOID:
            if tag == "hr" and not at.gone:
                at.children.append(child)
            continue
        if tag in _RAW:
            end = re.compile(rf"</{re.escape(tag)}(?=[\s/>])[^>]*+>", re.I).search(page, here)
            here = search = end.end() if end else len(page)
            continue
        at.children.append(child)
        if not raw.endswith("/") or tag in _BLOCK:
            at = child
            open_tags.setdefault(tag, []).append(child)
    write(page[here:])
    return nodes


def _blocks(root: Node):
    """(container, text, link characters) of each text block in page order; iterative, as trees may be deep."""
    buffer: list[str] = []
    linked = 0
    owner = root
    stack: list[tuple[Node, int, bool]] = [(root, 0, False)]

    def flush():
        nonlocal linked
        text = " ".join("".join(buffer).split())
        out = (owner, text, min(linked, len(text)))
        buffer.clear()
        linked = 0
        return out if text else None

    while stack:
        node, k, link = stack.pop()
        block = node.owner is node
        if k == 0 and block:
            if out := flush():
                yield out
            owner = node
        while k < len(node.children):
            child = node.children[k]
            k += 1
            if isinstance(child, str):
                buffer.append(child)
                if link:
                    linked += len(child.strip())
            elif not child.gone:
                stack.append((node, k, link))
                stack.append((child, 0, link or child.tag == "a"))
                break
        else:
            if block:
                if out := flush():
                    yield out
                owner = node.parent.owner if node.parent else root


#: Blocks of these elements pass their points on whole; they are no containers themselves.
_LEAVES = {"p", "h1", "h2", "h3", "h4", "h5", "h6", "li", "pre", "dd", "dt"}


def score(nodes: list[Node], blocks: list[tuple[Node, str, int]]) -> Node:
    """Score every container and return the best; of equal ones the first in page order, then the innermost."""
    for k, (owner, text, linked) in enumerate(blocks):
        owner.own += (1 + text.count(",") + min(len(text) / 100, 3)) * (1 - linked / len(text))
        owner.chars += len(text)
        owner.linked += linked
        owner.first = k if owner.first < 0 else owner.first
    best = nodes[0]
    for node in reversed(nodes):  # children before parents: each passes half of what it holds on
        if node.first < 0:
            continue
        leaf = node.tag in _LEAVES
        node.held += 0.0 if leaf else node.own
        node.scored = node.scored or not leaf
        if up := node.parent:
            up.held += node.held / 2 + (node.own if leaf else 0.0)
            up.chars += node.chars
            up.linked += node.linked
            up.first = node.first if up.first < 0 else min(up.first, node.first)
            up.scored = True
        if node.scored:
            bonus = {"article": 25.0, "main": 15.0}.get(node.tag, 0.0)
            node.score = (node.held + bonus) * (1 - node.linked / max(node.chars, 1))
    return max((n for n in nodes if n.scored), key=lambda n: (n.score, -n.first, n.depth), default=best)


def main_text(page: str | None) -> str:
    """The article of a page: its blocks joined by line feeds."""
    if not page:
        return ""
    nodes = parse(page)
    blocks = list(_blocks(nodes[0]))
    if not blocks:
        return ""
    best = score(nodes, blocks)
    keep = {best}
    if best.parent is not None:
        for x in best.parent.children:
            if isinstance(x, Node) and x is not best and not x.gone and x.chars:
                density = x.linked / x.chars
                if x.scored and x.score >= max(10.0, 0.2 * best.score) or x.tag == "p" and x.chars > 80 and density < 0.25 or x.tag == "h1" and density < 0.25:
                    keep.add(x)
    for node in nodes:  # parents before children: what is kept, and below that the lists that hold links only
        if node in keep:
            node.kept = True
        elif up := node.parent:
            links = node.tag in ("ul", "ol", "dl") and node.chars > 0 and node.linked > 0.8 * node.chars and len(node.children) >= 3
            node.kept, node.menu = up.kept, up.menu or links
    return "\n".join(text for owner, text, _ in blocks if owner.kept and not owner.menu)


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text and n_chars for each page."""

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        texts = [main_text(x.as_py()) for x in batch.column(2)]
        return pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(x) for x in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    return pages.select("page_id", "url", "html").mapInArrow(by_batch(kernel), "page_id bigint, url string, text string, n_chars bigint")


def op3_tree_scoring_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(table(spark, sf_dir, "pages"))
