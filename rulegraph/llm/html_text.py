"""Main text of web pages by tree scoring.

A page is read once into a tree. Every block of text passes points (one, plus its
commas, plus one for each 100 characters up to three) to the elements around it:
all of them to the nearest, half to the next, a third to the one after that. As a
bonus the nearest ``article`` and ``main`` around a block get its whole points too. An
element's sum is discounted by its link density, and the best one is the container,
whatever its tag; an ``article`` or ``main`` in it that has nine tenths of its score is
taken for it, as is one around it that has as much. Siblings that score a fifth of the container, or look like plain
paragraphs or headings, are kept with it. Menus, headers, footers, sidebars, notices,
adverts, forms, reader comments, scripts and styles are known by element, role,
class and id, and never score.

Defined results: null and empty html, and pages without text, give an empty text
of 0 characters. Unclosed and wrongly nested tags are closed as browsers do; a quote
in a tag that nothing closes is an ordinary character; a tag that the page's end
cuts is no text. Several equal scores go to the first element in page order. Every
row of the input gives one row; extra columns are ignored. Time is linear in the
page, however deep or broken it is.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rulegraph.llm.common import chunks

BLOCK_BYTES = 4_000_000

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*+(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*+)((?:[^>=]++|=\s*+\"[^\"]*+\"|=\s*+'[^']*+'|=)*+)(?:>|\Z)", re.S)
_ATTR = re.compile(r"([^\s=/\"'>]++)\s*+(?:=\s*+(?:\"([^\"]*+)\"|'([^']*+)'|([^\s>]++)))?+")
_WORD = re.compile(r"[^a-z0-9]+")

VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript iframe noembed noframes xmp template svg math select".split())
BLOCK = frozenset(
    "address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol optgroup option p pre section summary table tbody td tfoot th thead tr ul".split()
)
NEVER = frozenset("aside button datalist dialog fieldset footer form head header input label menu nav object output".split()) | RAW
ROLES = frozenset("alert alertdialog banner complementary contentinfo dialog form menu menubar navigation search toolbar".split())
#: Words of a class or id that mark what is not part of the article.
MARKS = frozenset(
    "ad ads advert adverts advertisement advertising banner breadcrumb breadcrumbs comment comments consent cookie cookies disqus footer gdpr header masthead menu modal nav navbar navigation newsletter notice notices notification pagination popup promo promotion recommended related replies share sharing sidebar skip social sponsor sponsored subscribe toolbar widget".split()
)
#: Where one of these begins, an open element of those ends, unless one of the last stands between.
ENDS = {"li": (("li",), ("ul", "ol", "menu", "dir")), "dt": (("dt", "dd"), ("dl",)), "dd": (("dt", "dd"), ("dl",)), "tr": (("tr", "td", "th"), ("table",)), "td": (("td", "th"), ("table", "tr")), "th": (("td", "th"), ("table", "tr")), "tbody": (("tr", "td", "th"), ("table",)), "tfoot": (("tr", "td", "th"), ("table",))}
WHOLE = ("article", "main")
#: Elements whose points go to the element around them.
HOLDS = frozenset("p pre li td th h1 h2 h3 h4 h5 h6 dd dt blockquote figcaption".split())


class _Node:
    __slots__ = ("tag", "up", "off", "block", "article", "main", "depth", "points", "chars", "linked", "links", "kept")

    def __init__(self, tag: str, up: _Node | None, off: bool):
        self.tag, self.up, self.off = tag, up, off
        #: the nearest block element, article and main, itself included
        self.block = self if up is None or tag in BLOCK else up.block
        self.article = self if tag == "article" else up and up.article
        self.main = self if tag == "main" else up and up.main
        self.depth = up.depth + 1 if up else 0
        self.points, self.chars, self.linked, self.links, self.kept = 0.0, 0, 0, 0, False


def _excluded(tag: str, attrs: str) -> bool:
    if tag in NEVER:
        return True
    if not attrs or tag in ("html", "body", "article", "main"):
        return False
    for name, a, b, c in _ATTR.findall(attrs):
        name, value = name.lower(), (a or b or c).lower()
        if name == "hidden":
            return True
        if name == "class" or name == "id":
            if MARKS.intersection(_WORD.split(value)):
                return True
        elif name == "role":
            if value.strip() in ROLES:
                return True
        elif name == "aria-hidden":
            if value.strip() == "true":
                return True
        elif name == "style" and "display:none" in value.replace(" ", ""):
            return True
    return False


def blocks_of(html: str) -> tuple[list[_Node], list[tuple[_Node, str, int]]]:
    """Elements, and blocks as (element, text, characters in links), both in page order. Excluded elements give no block."""
    root = _Node("html", None, False)
    stack, nodes, out = [root], [root], []
    #: places on the stack of the open elements of each kind
    where: dict[str, list[int]] = {}
    text: list[str] = []
    in_link = 0
    linked = 0

    def end_block() -> None:
        nonlocal linked
        if text:
            t = " ".join("".join(text).split())
            text.clear()
            if t:
                out.append((stack[-1].block, t, min(linked, len(t))))
        linked = 0

    def put(s: str) -> None:
        nonlocal linked
        if s and not stack[-1].off:
            if "&" in s:
                s = unescape(s)
            text.append(s)
            if in_link:
                linked += len(s)

    def last(tags: tuple[str, ...]) -> int:
        """The highest place of an open element of these kinds, 0 for none."""
        return max((where[t][-1] for t in tags if where.get(t)), default=0)

    def close(k: int) -> None:
        nonlocal in_link
        for node in stack[k:]:
            in_link -= node.tag == "a"
            where[node.tag].pop()
        del stack[k:]

    pos, n = 0, len(html)
    while True:
        m = _TOKEN.search(html, pos)
        if m is None:
            put(html[pos:])
            break
        put(html[pos : m.start()])
        pos = m.end()
        tag = m[2]
        if tag is None:
            continue
        tag = tag.lower()
        if m[1]:
            k = last((tag,))
            if k:
                if any(x.tag in BLOCK for x in stack[k:]):
                    end_block()
                close(k)
            elif tag == "p":
                end_block()
            continue
        attrs = m[3]
        if tag in RAW:
            end = re.compile(rf"</{re.escape(tag)}[\s/>]", re.I).search(html, pos)
            if end is None:
                pos = n
            else:
                gt = html.find(">", end.start())
                pos = n if gt < 0 else gt + 1
            continue
        if tag == "br":
            put(" ")
            continue
        if tag in BLOCK:
            end_block()
            if tag in ENDS:
                ends, scope = ENDS[tag]
                floor = last(scope)
                # the lowest of them above the scope, so that a row ends with its cells
                k = min((p for t in ends if where.get(t) and (p := where[t][-1]) > floor), default=0)
                if k:
                    close(k)
            if tag not in ("td", "th", "tr", "caption") and (k := last(("p",))):
                close(k)
        if tag in VOID or attrs.endswith("/") and tag not in BLOCK:
            continue
        if tag == "html":
            continue
        up = stack[-1]
        node = _Node(tag, up, up.off or _excluded(tag, attrs))
        where.setdefault(tag, []).append(len(stack))
        stack.append(node)
        nodes.append(node)
        if tag == "a":
            in_link += 1
            if not up.off:
                up.links += 1
    end_block()
    return nodes, out


def _score(x: _Node) -> float:
    return x.points * (1 - x.linked / x.chars) if x.chars else 0.0


def _add_up(nodes: list[_Node], blocks: list[tuple[_Node, str, int]]) -> None:
    """Characters, linked ones and links inside each element; elements come after those around them."""
    for x in nodes:
        x.chars = x.linked = 0
    for node, text, linked in blocks:
        node.chars += len(text)
        node.linked += linked
    for x in reversed(nodes[1:]):
        x.up.chars += x.chars
        x.up.linked += x.linked
        x.up.links += x.links


def main_text(html: str | None) -> str:
    """The main text of a page, its blocks joined by newlines."""
    if not html:
        return ""
    nodes, blocks = blocks_of(html)
    if not blocks:
        return ""
    _add_up(nodes, blocks)
    # lists that only link elsewhere are menus, whatever they are called
    for x in nodes:
        x.kept = not (x.up is not None and not x.up.kept or x.tag in ("ul", "ol", "dl") and x.links >= 3 and x.linked > 0.9 * x.chars)
    if not all(b[0].kept for b in blocks):
        blocks = [b for b in blocks if b[0].kept]
        _add_up(nodes, blocks)
    if not blocks:
        return ""
    for node, text, linked in blocks:
        points = (1 + text.count(",") + min(3.0, len(text) / 100)) * (1 - linked / len(text))
        at, level, given = (node.up or node) if node.tag in HOLDS else node, 1, set()
        while at is not None and level <= 3:
            whole = at.tag in WHOLE
            at.points += points if whole else points / level
            if whole:
                given.add(id(at))
            at, level = at.up, level + 1
        for whole in (node.article, node.main):
            if whole is not None and id(whole) not in given:
                whole.points += points
    top = max(nodes, key=_score)
    enough = 0.9 * _score(top)
    around = [x for x in (top.article, top.main) if x is not None and _score(x) >= enough]
    if around:
        top = max(around, key=lambda x: x.depth)
    for x in nodes:
        x.kept = x is top or x.up is not None and x.up.kept
    top = max((x for x in nodes if x is top or x.kept and x.tag in WHOLE and _score(x) >= enough), key=lambda x: x.depth)
    keep = {id(top)}
    if top.up is not None and top.tag != "body":
        least = 0.2 * _score(top)
        for x in nodes:
            if x.up is top.up and x is not top:
                plain = x.chars and x.linked < 0.25 * x.chars and (x.tag in ("p", "pre", "blockquote") and x.chars > 80 or x.tag in ("h1", "h2", "h3") and top.tag not in WHOLE)
                if _score(x) >= least > 0 or plain:
                    keep.add(id(x))
    for x in nodes:
        x.kept = id(x) in keep or x.up is not None and x.up.kept
    return "\n".join(t for node, t, _ in blocks if node.kept)


def extract_main_text(pages: DataFrame, *, html: str = "html", keep: list[str]) -> DataFrame:
    """Columns ``keep`` with ``text`` and ``n_chars`` (code points)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in chunks(batch, 0, BLOCK_BYTES):
                got = [main_text(h) for h in part.column(0).to_pylist()]
                yield pa.RecordBatch.from_arrays([*part.columns[1:], pa.array(got, pa.string()), pa.array([len(t) for t in got], pa.int64())], [*[f"k{i}" for i in range(len(keep))], "text", "n_chars"])

    fields = ", ".join(f"k{i} {pages.schema[c].dataType.simpleString()}" for i, c in enumerate(keep))
    out = pages.select(F.col(html).alias("_html"), *[F.col(c).alias(f"k{i}") for i, c in enumerate(keep)]).mapInArrow(run, f"{fields}, text string, n_chars bigint")
    return out.select(*[F.col(f"k{i}").alias(c) for i, c in enumerate(keep)], "text", "n_chars")
