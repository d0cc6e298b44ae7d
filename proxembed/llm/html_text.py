"""Main text of web pages by tree scoring.

A page becomes a tree of elements with text blocks. Boilerplate subtrees (menus, forms, scripts, adverts, notices,
comments, by element name and by the words of a container's class, id, role and label) and hidden ones are cut off; a section
of an article that only its id or label speaks against stays if it is prose. Each paragraph passes points for its
length and its commas to its parent and half of them to the grandparent; a container's points are discounted by the
share of its text that lies in links. The best container is kept, with siblings that score near it or hold plain prose.

Defined cases: null and empty html give the empty text; markup that is cut short is read as far as it goes, and an
unfinished tag at the end is dropped; a line break is white space inside its block; repeated rows are extracted alike;
extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import html
import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from proxembed.llm.common import spread, table

TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)"
    r"|<(?P<raw>script|style|noscript|template|textarea|title|iframe|svg|math|xmp)\b[^>]*>.*?(?:</(?P=raw)\s*>|\Z)"
    r"|<(?P<close>/?)(?P<name>[a-zA-Z][^\s/>]*)(?P<attributes>(?:\"[^\"]*\"|'[^']*'|[^'\">])*+)>"
    r"|<(?P<close2>/?)(?P<name2>[a-zA-Z][^\s/>]*)[^>]*>"
    r"|</?[a-zA-Z][^>]*\Z",
    re.S | re.I,
)
ATTRIBUTE = re.compile(r"([^\s\"'>/=]+)(?:\s*=\s*(\"[^\"]*\"|'[^']*'|[^\s\"'>]+))?")
NO_DISPLAY = re.compile(r"(?:^|;)\s*display\s*:\s*none\b", re.I)
# Element names by role.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCK = frozenset("address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol option p pre section summary table tbody td tfoot th thead tr ul".split())
CUT = frozenset("nav footer aside form header menu dialog button select option input label fieldset head object embed canvas audio video".split())
SCOPE = frozenset("article section div main body td th table aside nav footer header form blockquote li ul ol dl dd figure".split())
UNLIKELY = re.compile(
    r"(?:^|[\s_-])(?:ads?|advert\w*|sponsor\w*|promo\w*|banner|cookies?|consent|gdpr|notice|alert|comments?|disqus|respond|reply|replies|sidebar|side-?bar|menu|nav|navbar|navigation|breadcrumbs?|footer|header|masthead|share|sharing|social|related|recommend\w*|popup|modal|overlay|newsletter|subscribe|signup|login|search|pagination|pager|widget|toolbar|skip|print|complementary|contentinfo|advertisement|dialog)(?:$|[\s_-])",
    re.I,
)
LIKELY = re.compile(r"(?:^|[\s_-])(?:article|body|content|entry|main|page|post|story|text|blog)(?:$|[\s_-])", re.I)
# Only these are boilerplate by their words.
CONTAINERS = frozenset("div section aside nav header footer form ul ol dl table figure center details".split())
PARAGRAPHS = frozenset("p pre td blockquote li dd h1 h2 h3 h4 h5 h6".split())


class _Node:
    __slots__ = ("name", "parent", "bias", "score", "text", "linked", "order", "doubt")

    def __init__(self, name: str, parent: _Node | None, bias: float, order: int):
        self.name, self.parent, self.bias, self.order = name, parent, bias, order
        self.score, self.text, self.linked, self.doubt = 0.0, 0, 0, False


def _clean(parts: list[str]) -> str:
    text = "".join(parts)
    return " ".join((html.unescape(text) if "&" in text else text).split())


def _attributes(source: str) -> dict[str, str]:
    """Values by name in small letters; of repeated names the first holds, a bare one is empty."""
    out: dict[str, str] = {}
    for name, value in ATTRIBUTE.findall(source):
        if value[:1] in ("'", '"'):
            value = value[1:-1]
        out.setdefault(name.lower(), html.unescape(value) if "&" in value else value)
    return out


def _hidden(a: dict[str, str]) -> bool:
    return "hidden" in a or a.get("aria-hidden", "").strip().lower() == "true" or NO_DISPLAY.search(a.get("style", "")) is not None


def _read(source: str) -> tuple[list[_Node], list[tuple[_Node, str, int]]]:
    """Elements kept, and (element, text, linked characters) of each block in page order."""
    root = _Node("html", None, 0.0, 0)
    stack, nodes, blocks = [root], [root], []
    parts: list[str] = []
    linked, link_depth, cut_depth = 0, 0, 0
    owner = root

    def flush() -> None:
        nonlocal parts, linked
        if parts:
            text = _clean(parts)
            if text:
                blocks.append((owner, text, min(linked, len(text))))
            parts, linked = [], 0

    def words(s: str) -> None:
        nonlocal linked, owner
        if s and not cut_depth:
            if not parts:
                owner = next(n for n in reversed(stack) if n.name in BLOCK)
            parts.append(s)
            if link_depth:
                linked += len(s)

    def leave(to: int) -> None:
        """Close open elements down to stack position `to`."""
        nonlocal cut_depth, link_depth
        while len(stack) > to:
            n = stack.pop()
            if n.bias == -1.0:
                cut_depth -= 1
            if n.name == "a":
                link_depth -= 1

    at = 0
    for m in TOKEN.finditer(source):
        if m.start() > at:
            words(source[at : m.start()])
        at = m.end()
        name = m["name"] or m["name2"]
        if not name:
            if m[0][:9].upper() == "<![CDATA[":
                words(html.escape(m[0][9:].removesuffix("]]>")))
            continue
        name = name.lower()
        if m["close"] or m["close2"]:
            if name in BLOCK:
                flush()
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].name == name:
                    leave(k)
                    break
                if stack[k].name in SCOPE and name not in SCOPE:
                    break
            continue
        if name == "br":
            words(" ")
            continue
        if name in BLOCK:
            flush()
            # A block ends an open paragraph; list items, cells and options end their like.
            for k in range(len(stack) - 1, 0, -1):
                other = stack[k].name
                if other == "p" or other == name and name in ("li", "option", "tr", "td", "th", "dt", "dd"):
                    leave(k)
                    break
                if other in SCOPE:
                    break
        if name in VOID:
            continue
        attributes = _attributes(m["attributes"]) if m["attributes"] else {}
        said = " ".join(attributes[k] for k in ("class", "id", "role", "aria-label") if k in attributes)
        bias, doubt = 0.0, False
        if name not in ("html", "body", "article", "main"):
            inside = any(n.name in ("article", "main") for n in stack)
            unlikely = said and name in CONTAINERS and UNLIKELY.search(said) and not (LIKELY.search(said) and name in ("div", "section"))
            if unlikely and inside and name == "section" and not UNLIKELY.search(" ".join(attributes.get(k, "") for k in ("class", "role"))):
                doubt, unlikely = True, False
            if name in CUT and not (name == "header" and inside) or unlikely or _hidden(attributes):
                bias = -1.0
        elif name in ("article", "main"):
            bias = 25.0
        if said and bias >= 0 and LIKELY.search(said):
            bias += 10.0
        node = _Node(name, stack[-1], bias, len(nodes))
        node.doubt = doubt
        stack.append(node)
        if bias == -1.0:
            flush()
            cut_depth += 1
        elif not cut_depth and name in BLOCK:
            nodes.append(node)
        if name == "a":
            link_depth += 1
    words(source[at:])
    flush()
    return nodes, _sure(blocks) if any(n.doubt for n in nodes) else blocks


def _above(n: _Node | None) -> Iterator[_Node]:
    while n is not None:
        yield n
        n = n.parent


def _sure(blocks: list[tuple[_Node, str, int]]) -> list[tuple[_Node, str, int]]:
    """Without the sections in doubt that aren't prose: short, or a quarter in links."""
    text, links = Counter(), Counter()
    for owner, t, linked in blocks:
        for n in _above(owner):
            if n.doubt:
                text[id(n)] += len(t)
                links[id(n)] += linked
    return [b for b in blocks if not any(n.doubt and (text[id(n)] < 80 or links[id(n)] >= text[id(n)] / 4) for n in _above(b[0]))]


def _container(n: _Node) -> _Node:
    """The nearest element that holds paragraphs rather than is one."""
    while n.parent is not None and (n.name in PARAGRAPHS and n.name not in ("td", "blockquote") or n.name not in BLOCK):
        n = n.parent
    return n


def main_blocks(source: str | None) -> list[str]:
    """The text blocks of the main part, in page order."""
    if not source:
        return []
    nodes, blocks = _read(source)
    candidates: dict[int, _Node] = {}
    for owner, text, linked in blocks:
        up: _Node | None = owner
        while up is not None:
            up.text += len(text)
            up.linked += linked
            up = up.parent
        if len(text) < 25 and owner.name != "p":
            continue
        points = 1 + text.count(",") + min(len(text) / 100, 3.0)
        holder = _container(owner)
        for n, share in ((holder, 1.0), (holder.parent and _container(holder.parent), 0.5)):
            if n is not None:
                n.score += points * share
                candidates[id(n)] = n
    density = lambda n: n.linked / n.text if n.text else 0.0
    value = lambda n: (n.score + n.bias) * (1 - density(n))
    if not candidates:
        for n in nodes:
            if n.text and (n.name in ("article", "main") or n.bias > 0):
                candidates[id(n)] = n
        if not candidates:
            return [t for _, t, linked in blocks if linked < len(t) / 2]
    best = max(candidates.values(), key=lambda n: (value(n), -n.order))
    kept, bar = {id(best)}, max(10.0, 0.2 * value(best))
    if best.parent is not None:
        for n in nodes:
            if n.parent is best.parent and n is not best and n.text:
                if value(n) >= bar or n.name == "p" and density(n) < 0.25 and n.text > 80:
                    kept.add(id(n))

    def inside(n: _Node | None) -> bool:
        while n is not None:
            if id(n) in kept:
                return True
            n = n.parent
        return False

    return [t for owner, t, _ in blocks if inside(owner)]


def extract(source: str | None) -> str:
    """The main blocks, joined by two newlines."""
    return "\n\n".join(main_blocks(source))


def main_text(pages: DataFrame) -> DataFrame:
    """(page_id, url, html) -> (page_id, url, text, n_chars): blocks joined by two newlines."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            text = [extract(x.as_py()) for x in b.column(2)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(text, pa.string()), pa.array([len(t) for t in text], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return spread(rows).mapInArrow(run, "page_id long, url string, text string, n_chars long")


def op5_tree_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return main_text(table(spark, sf_dir, "pages"))
