"""Main-text extraction by tag-path ratios.

Every text node of a page belongs to a root-to-leaf tag path.  Text length and punctuation are aggregated per
path, laid out along the page, smoothed with a Gaussian, fused into one ratio and thresholded; the paths above the
threshold mark where the article is.  The innermost container that holds nearly all of their text is then read as a
whole, so that short paragraphs and headings of the article stay, while navigation, notices, adverts, forms and
comments inside or around it are left out by role.

Defined results: a null or empty page gives an empty text; a page of boilerplate only gives an empty text; unclosed
tags and truncated markup are tolerated; repeated rows give repeated results; an empty table gives an empty table.
"""

from __future__ import annotations

import html as html_lib
import math
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

_TAG = re.compile(r"""<(/?)([a-zA-Z][^\s/>]*)((?:[^>"']|"[^"]*"|'[^']*')*+)>|<(/?)([a-zA-Z][^\s/>]*)([^>]*)>|<!--|<[!?/][^>]*>""")
_ATTR = re.compile(r"""([a-zA-Z_:][-\w:.]*)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""")
_SPACE = re.compile(r"\s+")
_PUNCT = re.compile(r"[.,;:!?¿¡。，、]")
_OPEN_END = re.compile(r"<(?:/?[a-zA-Z!?][^>]*)?\Z")

RAW = frozenset("script style textarea title noscript iframe template svg math object".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
BOXES = frozenset("html body div article main section td table tbody tr center".split())
CLOSERS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
BARRIER = frozenset("ul ol dl table div article section main body html td th blockquote".split())
DROPPED = frozenset("nav footer aside form button select menu dialog head fieldset input".split())
ROLES = frozenset("navigation banner contentinfo complementary search dialog alertdialog alert menu menubar form".split())
MARKS = re.compile(
    r"(?:^|[\s_-])(?:ads?|adverts?|advertisements?|adsense|sponsor(?:ed)?|promo(?:tion)?s?|banners?|cookies?|consent|gdpr|notices?|newsletter|subscribe|side-?bar|menus?|nav|navbar|navigation|breadcrumbs?|footer|masthead|"
    r"comments?|commentlist|disqus|repl(?:y|ies)|share|sharing|social|related|recommended|widgets?|popup|modal|overlay|toolbar|pagination|pager|log-?in|sign-?up|search|skip|toc|disclaimer)(?:$|[\s_-]|\d)",
    re.I,
)
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())


class _Node:
    __slots__ = ("tag", "parent", "off", "path", "kids_text", "score", "heading")

    def __init__(self, tag: str, parent: _Node | None, off: bool, path: str):
        self.tag, self.parent, self.off, self.path = tag, parent, off, path
        self.score = 0.0
        self.heading = False


def _is_off(tag: str, attrs: str, parent: _Node) -> bool:
    if parent.off or tag in DROPPED:
        return True
    if tag == "header":
        up = parent
        while up is not None and up.tag not in ("article", "main"):
            up = up.parent
        if up is None:
            return True
    if attrs and "=" in attrs and tag not in ("html", "body", "article", "main"):
        for m in _ATTR.finditer(attrs):
            key = m[1].lower()
            value = m[2] or m[3] or m[4] or ""
            if (key in ("class", "id") and MARKS.search(value)) or (key == "role" and value.lower() in ROLES) or (key == "aria-hidden" and value.lower() == "true"):
                return True
    return bool(attrs) and re.search(r"(?:^|\s)hidden(?:\s|$)", attrs) is not None


def blocks_of(page: str) -> tuple[list[tuple[_Node, str, int, int]], _Node]:
    """Text nodes in page order as (element, raw text, block number, length inside links), and the root."""
    root = _Node("#root", None, False, "")
    cur, block, out, pos, n, breaks = root, 0, [], 0, len(page), 0
    links = 0

    def text(a: int, b: int) -> None:
        nonlocal breaks
        if a < b:
            piece = page[a:b]
            if not piece.isspace():
                breaks = 0
            if cur.off is False:
                out.append((cur, piece, block, links))

    while pos < n:
        m = _TAG.search(page, pos)
        if m is None:
            end = _OPEN_END.search(page, pos)
            text(pos, end.start() if end else n)
            break
        text(pos, m.start())
        pos = m.end()
        name = m[2] or m[5]
        if name is None:
            if m[0] == "<!--":
                end = page.find("-->", pos)
                pos = n if end < 0 else end + 3
            continue
        tag, attrs = name.lower(), m[3] or m[6] or ""
        if m[1] or m[4]:  # an end tag
            if tag == "a" and links:
                links -= 1
            up = cur
            while up.parent is not None and up.tag != tag:
                up = up.parent
            if up.parent is not None:
                cur = up.parent
            if tag not in INLINE:
                block += 1
            continue
        if tag in RAW and not attrs.endswith("/"):
            end = re.compile(f"</{tag}(?=[\\s/>])", re.I).search(page, pos)
            if end is None:
                break
            close = page.find(">", end.end())
            pos = n if close < 0 else close + 1
            continue
        if tag in VOID:
            if tag == "br":
                breaks += 1
                if breaks > 1:
                    block += 1
                elif not cur.off:
                    out.append((cur, " ", block, links))
            elif tag == "hr":
                block += 1
            continue
        if tag not in INLINE:
            block += 1
            up = cur  # a block closes an open paragraph, a list item its predecessor
            while up.parent is not None and up.tag not in BARRIER:
                if up.tag == "p" or up.tag in CLOSERS.get(tag, ()):
                    cur = up.parent
                up = up.parent
            if tag in CLOSERS and up.tag in CLOSERS[tag]:
                cur = up.parent
        if not attrs.endswith("/"):
            if tag == "a":
                links += 1
            cur = _Node(tag, cur, _is_off(tag, attrs, cur), f"{cur.path}/{tag}")
    return out, root


def path_scores(nodes: list[tuple[str, int, int]], sigma: float = 1.0) -> dict[str, float]:
    """Fused tag-path ratio of each path, from text nodes (path, length, punctuation marks) in page order."""
    total: dict[str, list[float]] = {}
    for path, size, marks in nodes:
        t = total.setdefault(path, [0, 0, 0])
        t[0] += size
        t[1] += marks
        t[2] += 1
    radius = max(1, math.ceil(2 * sigma))
    kernel = [math.exp(-(k * k) / (2 * sigma * sigma)) for k in range(-radius, radius + 1)]
    lengths = [total[p][0] / total[p][2] for p, _, _ in nodes]
    punct = [total[p][1] / total[p][2] for p, _, _ in nodes]
    sums: dict[str, list[float]] = {}
    for i, (path, _, _) in enumerate(nodes):
        norm = size_s = punct_s = 0.0
        for k in range(-radius, radius + 1):
            if 0 <= i + k < len(nodes):
                g = kernel[k + radius]
                norm += g
                size_s += g * lengths[i + k]
                punct_s += g * punct[i + k]
        s = sums.setdefault(path, [0.0, 0])
        s[0] += math.sqrt((size_s / norm) * (1.0 + punct_s / norm))
        s[1] += 1
    return {p: s / c for p, (s, c) in sums.items()}


def main_text(page: str | None, sigma: float = 1.0, strength: float = 0.5, hold: float = 0.75) -> str:
    """The article's text; ``strength`` times the deviation of the path scores is the threshold, ``hold`` the share of the marked text a container must have."""
    if not page:
        return ""
    pieces, root = blocks_of(page)
    shown = [(node, html_lib.unescape(raw) if "&" in raw else raw, block, links) for node, raw, block, links in pieces]
    solid = [(node, t, block, links) for node, t, block, links in shown if not t.isspace()]
    if not solid:
        return ""
    scores = path_scores([(node.path, 0 if links else len(t), len(_PUNCT.findall(t))) for node, t, _, links in solid], sigma)
    mean = sum(scores.values()) / len(scores)
    threshold = min(strength * math.sqrt(sum((s - mean) ** 2 for s in scores.values()) / len(scores)), max(scores.values()))
    kids: dict[_Node, set[_Node]] = {}
    whole = 0.0
    for node, t, _, links in solid:
        if scores[node.path] >= threshold and not links:
            whole += len(t)
            at: _Node | None = node
            while at is not None:
                at.score += len(t)
                if at.parent is not None:
                    kids.setdefault(at.parent, set()).add(at)
                at = at.parent
    for node, t, _, _ in solid:
        at = node
        if any(True for _ in _up_to_heading(at)):
            while at is not None:
                at.heading = True
                at = at.parent
    box = root
    while box.tag not in ("article", "main"):
        best = max((k for k in kids.get(box, ()) if k.tag in BOXES), key=lambda k: k.score, default=None)
        if best is None or best.score < hold * whole or (box.heading and not best.heading):
            break
        box = best
    if box.tag == "main":  # an article inside main, if it has the text
        inner = max((k for k in kids.get(box, ()) if k.tag == "article"), key=lambda k: k.score, default=None)
        box = inner if inner is not None and inner.score >= hold * whole else box
    parts: dict[int, list[str]] = {}
    for node, t, block, _ in shown:
        at = node
        while at is not None and at is not box:
            at = at.parent
        if at is box:
            parts.setdefault(block, []).append(t)
    lines = (_SPACE.sub(" ", "".join(p)).strip() for p in parts.values())
    return "\n".join(x for x in lines if x)


def _up_to_heading(node: _Node | None) -> Iterator[_Node]:
    while node is not None:
        if node.tag in HEADINGS:
            yield node
        node = node.parent


def extract(pages: DataFrame, sigma: float = 1.0, strength: float = 0.5, hold: float = 0.75) -> DataFrame:
    """One row per page: page_id, url, text, n_chars.  Row-wise: no shuffle, bounded by one Arrow batch of pages."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [main_text(h, sigma, strength, hold) for h in b.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64())], ["page_id", "url", "text", "n_chars"])

    return pages.select("page_id", "url", "html").mapInArrow(run, "page_id long, url string, text string, n_chars long")
