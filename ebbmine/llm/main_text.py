"""Main text of raw web pages by tree scoring.

Paragraph-like blocks earn points for their length and commas and pass them to their ancestors;
an ancestor's sum is discounted by its link density; the best container and its good siblings
make the article. One page is one independent unit, so the operator is a map without a shuffle.

What is left out: elements that are clutter by their kind, role or being hidden (inline ones too);
elements whose class or id names clutter as a whole word of that attribute, unless they hold the page's
one heading or most of its text as its one article, or nothing else is left; lists of short links; headers outside
the article. Attributes are read one by one, so no other attribute's value can drop or spill text.

Null or empty html: empty text. Pages without any block: empty text. Repeated rows stay repeated.
Extra columns are ignored. Pages are parsed whole, whatever their length and depth, in linear time.
A quote that never closes ends with its tag; comments and scripts that never close run to the end.
"""

from __future__ import annotations

import html as entities
import re

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import only, tidy

# Fixed values of HTML: elements by their role.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript iframe xmp noembed noframes".split())
BLOCK = frozenset(
    "address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup html li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split()
)
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
CLUTTER = frozenset("nav aside footer button dialog menu head label template svg math object select datalist canvas audio video".split())
FORMS = frozenset("form fieldset".split())
FOREIGN = frozenset("svg math".split())
ROLES = frozenset("navigation banner contentinfo complementary search dialog alertdialog alert form menu menubar".split())
CLOSES = {
    "li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"),
    "thead": ("tr", "td", "th"), "tbody": ("thead", "tbody", "tr", "td", "th"), "tfoot": ("tbody", "tr", "td", "th"), "option": ("option",),
}
SCOPE = {"li": ("ul", "ol", "menu", "dir"), "dt": ("dl",), "dd": ("dl",)}
P_SCOPE = ("table", "td", "th", "button", "article", "section", "main")

# A name of clutter: one of these words, alone or beside words that only say where or what kind of box it is.
_WHERE = r"(?:site|page|post|article|entry|global|top|bottom|left|right|upper|lower|first|last|primary|secondary|main|side|inline|sticky|fixed|floating|user|reader|google|text|js|block|module|section|mobile|desktop|email|mail|gdpr|privacy|eu)"
_CLUTTER = (
    r"(?:ads?|adbox|adslot|adsense|adverts?|advertisements?|advertising|banner|breadcrumbs?|comments?|commentlist|cookies?|cookiebar|consent|disqus|footer|masthead|menu|modal|nav|navbar|navigation|newsletter|notices?|pager|pagination"
    r"|popup|promos?|promotion|related|recommended|recommendations|replies|reply|respond|share|shares|sharing|sharedaddy|sidebars?|skip|skiplink|social|socials|sponsor|sponsored|sponsors|subscribe|subscription|tags|toolbar|topbar|widgets?)"
)
_WHAT = r"(?:area|articles?|bar|banner|block|body|bottom|box|button|buttons|column|container|content|entry|form|group|header|holder|icons?|inner|item|items|label|left|line|links?|list|listing|lists|main|menu|message|meta|module|notice|outer|overlay|pages|panel|placeholder|popup|posts?|region|right|row|section|slot|stories|story|text|thread|title|toggle|top|topics|unit|widget|widgets|wrap|wrapper|\d+)"
CLUTTER_NAME = re.compile(rf"(?:{_WHERE}[-_]+)*{_CLUTTER}(?:[-_]+(?:{_CLUTTER}|{_WHAT}))*", re.I)
HEADER_NAME = re.compile(r"(?:(?:site|page|top|global|main)[-_]?)?header(?:[-_](?:inner|wrap|wrapper|container|content))?", re.I)
CONTENT_NAMES = re.compile(r"article|body|content|entry|main|post|story|text", re.I)
HIDING = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden", re.I)

TAG_NAME = re.compile(r"[A-Za-z][^\s/>]*+")
ATTRIBUTE = re.compile(r"[\s/]*+(?:(=?[^\s/>=]*+)(?:\s*+=\s*+(?:([\"'])|([^\s>]*+)))?)")
SPACES = re.compile(r"\s+")
COMMENT_END = re.compile(r"--!?>")

#: Why an element is no article text: never, by a name (or as a form), as a header outside the article.
PLAIN, SURE, NAMED, HEADER = 0, 1, 2, 3


class _Node:
    __slots__ = ("tag", "parent", "names", "why", "owner", "chars", "link_chars", "links", "texts", "blocks", "score")

    def __init__(self, tag: str, parent: int, names: str, why: int, owner: int):
        self.tag, self.parent, self.names, self.why, self.owner = tag, parent, names, why, owner
        self.chars = self.link_chars = self.links = self.texts = self.blocks = 0
        self.score = 0.0


def _attributes(page: str, at: int, last: dict[str, int]) -> tuple[dict[str, str], bool, int]:
    """(attributes, whether the tag closes itself, where the tag ends); each character is looked at once."""
    got: dict[str, str] = {}
    n = len(page)
    while at < n and page[at] != ">":
        m = ATTRIBUTE.match(page, at)
        name, quote = m[1], m[2]
        at, begin = m.end(), at
        value = m[3] or ""
        if quote:
            end = page.find(quote, at) if at <= last[quote] else page.find(">", at)
            end = n if end < 0 else end
            value = page[at:end]
            at = end + 1 if end < n and page[end] == quote else end
        if name:
            got.setdefault(name.lower(), value)
        elif at == begin:
            at += 1
    return got, at > 0 and page[at - 1] == "/", min(at + 1, n)


def _why(tag: str, got: dict[str, str], names: str, in_code: bool) -> int:
    if tag in CLUTTER or "hidden" in got or got.get("aria-hidden", "").strip().lower() == "true" or HIDING.search(got.get("style", "")):
        return SURE
    if not ROLES.isdisjoint(got.get("role", "").lower().split()):
        return SURE
    if tag in FORMS:
        return NAMED
    if names and tag not in ("body", "html", "main") and not in_code:
        words = names.split()
        if any(CLUTTER_NAME.fullmatch(x) for x in words):
            return NAMED
        if any(HEADER_NAME.fullmatch(x) for x in words):
            return HEADER
    return HEADER if tag == "header" else PLAIN


def _parsed(page: str) -> tuple[list[_Node], list[tuple[int, list[tuple[int, str, bool]]]]]:
    """The tree of elements, parents before children, and the text blocks in page order: (owner, [(element, text, in a link)])."""
    nodes = [_Node("html", -1, "", PLAIN, 0)]
    stack, at, n = [0], 0, len(page)
    open_at: dict[str, list[int]] = {}  # depths of the open elements of a tag
    block_at = [0]  # depths of the open blocks
    last = {q: page.rfind(q) for q in "\"'"}
    blocks: list[tuple[int, list[tuple[int, str, bool]]]] = []
    parts: list[tuple[int, str, bool]] = []
    breaks = 0

    def flush() -> None:
        nonlocal parts, breaks
        breaks = 0
        if parts:
            blocks.append((nodes[stack[-1]].owner, parts))
            parts = []

    def is_open(*tags: str) -> bool:
        return any(open_at.get(t) for t in tags)

    def nearest(tags) -> int:
        return max((open_at[t][-1] for t in tags if open_at.get(t)), default=0)

    def pop_to(depth: int) -> None:
        if block_at and block_at[-1] >= depth:
            flush()
        while len(stack) > depth:
            open_at[nodes[stack.pop()].tag].pop()
        while block_at and block_at[-1] >= depth:
            block_at.pop()

    def close(tags: tuple[str, ...], fence: int) -> None:
        """Closes the nearest open element of these, unless a fence is nearer."""
        depth = nearest(tags)
        if depth > fence:
            pop_to(depth)

    while at < n:
        cut = page.find("<", at)
        if cut < 0:
            cut = n
        if cut > at:
            parts.append((stack[-1], page[at:cut], bool(open_at.get("a"))))
            if breaks and not page[at:cut].isspace():
                breaks = 0
        if cut >= n:
            break
        mark = page[cut + 1 : cut + 2]
        if mark == "!" or mark == "?":
            if page.startswith("<!--", cut):
                if page.startswith((">", "->"), cut + 4):
                    at = page.find(">", cut + 4) + 1
                else:
                    m = COMMENT_END.search(page, cut + 4)
                    at = m.end() if m else n
            else:
                sign = "]]>" if page.startswith("<![CDATA[", cut) else ">"
                end = page.find(sign, cut)
                at = n if end < 0 else end + len(sign)
            continue
        ending = mark == "/"
        m = TAG_NAME.match(page, cut + 1 + ending)
        if m is None:
            if ending:  # "</" and no name: a comment up to the next ">"
                end = page.find(">", cut)
                at = n if end < 0 else end + 1
            else:  # a lone "<" is text
                parts.append((stack[-1], "<", bool(open_at.get("a"))))
                at = cut + 1
            continue
        tag = m[0].lower()
        if m.end() < n and page[m.end()] == ">":
            got, itself, at = {}, False, m.end() + 1
        else:
            got, itself, at = _attributes(page, m.end(), last)
        if ending:
            if tag == "p" and not is_open("p"):
                flush()
            elif tag == "br":
                parts.append((stack[-1], " ", False))
            else:
                close((tag,), 0 if tag in BLOCK else block_at[-1] if block_at else 0)
            continue
        if tag == "br":
            breaks += 1
            parts.append((stack[-1], " ", False))
            if breaks > 1:
                flush()
            continue
        if tag in BLOCK or tag == "hr":
            close(("p",), nearest(P_SCOPE))
        if tag in CLOSES:
            close(CLOSES[tag], nearest(SCOPE.get(tag, ("table",))))
        if tag in HEADINGS and nodes[stack[-1]].tag in HEADINGS:
            pop_to(len(stack) - 1)
        if tag == "a":
            close(("a",), block_at[-1] if block_at else 0)
        if tag in VOID:
            if tag == "hr":
                flush()
            continue
        if tag in RAW:
            end = re.compile(rf"</{tag}(?=[\s/>])[^>]*>|</{tag}\Z", re.I).search(page, at)
            at = end.end() if end else n
            parts.append((stack[-1], " ", False))
            continue
        if itself and (tag in FOREIGN or is_open(*FOREIGN)):
            continue
        names = f"{got.get('class', '')} {got.get('id', '')}" if got else ""
        parent = nodes[stack[-1]]
        why = parent.why if parent.why == SURE else _why(tag, got, names, is_open("pre", "code"))
        if why == HEADER and is_open("article", "main"):
            why = PLAIN
        if tag in BLOCK:
            flush()
            block_at.append(len(stack))
        open_at.setdefault(tag, []).append(len(stack))
        nodes.append(_Node(tag, stack[-1], names, why, len(nodes) if tag in BLOCK else parent.owner))
        stack.append(len(nodes) - 1)
    flush()
    return nodes, blocks


def _shut(nodes: list[_Node], blocks) -> list[int]:
    """Why each element is left out, with what its ancestors say. Names and forms give way to the main element, to the
    page's one heading, and to its one article if half of the page's text is in there."""
    free = [x.why for x in nodes]
    size = [0] * len(nodes)
    for _, parts in blocks:
        for k, text, _ in parts:
            size[k] += len(text)
    for k in range(len(nodes) - 1, 0, -1):
        size[nodes[k].parent] += size[k]
    plain = [k for k, x in enumerate(nodes) if x.why == PLAIN and x.tag in ("h1", "article")]
    once = {t for t in ("h1", "article") if sum(nodes[k].tag == t for k in plain) == 1}
    speaks = {k for k in plain if nodes[k].tag in once and (nodes[k].tag == "h1" or 2 * size[k] >= size[0])}
    holds = [x.why == PLAIN and (x.tag == "main" or k in speaks) for k, x in enumerate(nodes)]
    for k in range(len(nodes) - 1, 0, -1):
        if free[k] == HEADER:
            continue  # a header's heading does not speak for what is around it
        if holds[k] and free[k] == NAMED:
            free[k] = PLAIN
        holds[nodes[k].parent] = holds[nodes[k].parent] or holds[k]
    for k in range(1, len(nodes)):
        above = free[nodes[k].parent]
        free[k] = above if above in (SURE, NAMED) or above == HEADER and free[k] == PLAIN else free[k]
    return free


def _weight(node: _Node) -> float:
    """Prior of a container by its element and its names."""
    prior = {"article": 25, "main": 15, "section": 3, "div": 5, "td": 3, "blockquote": 3, "pre": 3, "body": 0, "html": -5}.get(node.tag, -3)
    return prior + 15 * bool(CONTENT_NAMES.search(node.names))


def _texts(blocks, shut: list[int], allowed: tuple[int, ...]) -> list[tuple[int, str, int]]:
    """(owner, text, link characters) of the blocks, from the elements that are not shut."""
    out = []
    for owner, parts in blocks:
        held = [(entities.unescape(text) if "&" in text else text, link) for k, text, link in parts if shut[k] in allowed]
        text = SPACES.sub(" ", "".join(x for x, _ in held)).strip()
        if text:
            out.append((owner, text, min(len(text), sum(len(x.strip()) for x, link in held if link))))
    return out


def main_text(page: str | None) -> str:
    """The article of one page; blocks joined by an empty line."""
    if not page:
        return ""
    nodes, parts = _parsed(page)
    shut = _shut(nodes, parts)
    allowed: tuple[int, ...] = (PLAIN,)
    blocks = _texts(parts, shut, allowed)
    if not blocks:  # then names alone decide nothing
        allowed = (PLAIN, NAMED, HEADER)
        blocks = _texts(parts, shut, allowed)
    if not blocks:
        return ""
    for k in range(len(nodes)):
        if nodes[k].tag == "a":
            nodes[nodes[k].owner].links += 1
        if k and nodes[k].tag in BLOCK:
            nodes[nodes[nodes[k].parent].owner].blocks += 1
    for owner, text, linked in blocks:
        nodes[owner].texts += 1
        nodes[owner].chars += len(text)
        nodes[owner].link_chars += linked
    for x in reversed(nodes):
        if x.parent >= 0:
            up = nodes[x.parent]
            up.chars += x.chars
            up.link_chars += x.link_chars
            up.links += x.links
    earned: dict[int, float] = {}
    for owner, text, _ in blocks:
        x = nodes[owner]
        if x.tag in HEADINGS:
            points = 0.5
        elif len(text) < 25:
            points = 0.25
        else:
            points = 1 + text.count(",") + text.count("，") + min(len(text) / 100, 3.0)
        # a box of several texts is a container itself; one of a single text is a paragraph, whatever its element
        holds = x.tag in ("article", "section", "main", "body", "html") or x.tag in ("div", "td", "center", "blockquote", "pre") and (x.texts > 1 or x.blocks)
        k, share = (owner if holds else x.parent), 1.0
        for divisor in (1, 2, 3, 4, 5):
            if k < 0:
                break
            k = nodes[k].owner
            earned[k] = earned.get(k, 0.0) + points * share
            k, share = nodes[k].parent, 1.0 / (divisor * 2)

    def kept_share(k: int) -> float:
        return 1 - nodes[k].link_chars / max(1, nodes[k].chars)

    def final(k: int) -> float:
        total = earned[k] + _weight(nodes[k])
        return total * kept_share(k) if total > 0 else total

    best = max(sorted(earned), key=lambda k: (final(k), -k))
    k = best
    while k >= 0:  # an article or main element around the best container bounds it
        if nodes[k].tag in ("article", "main"):
            best = k
            break
        k = nodes[k].parent
    keep = {best}
    around = nodes[best].parent
    bar = max(2.0, 0.2 * earned.get(best, 0.0) * kept_share(best))
    if around >= 0:
        for k, got in earned.items():
            if nodes[k].parent == around and k != best:
                bonus = 0.2 * earned.get(best, 0.0) if nodes[best].names.strip() and nodes[k].names == nodes[best].names else 0.0
                if got * kept_share(k) + bonus >= bar:
                    keep.add(k)
    # from the top down: what lies in a kept element, and in a list of short links
    inside, crowded = [False] * len(nodes), [False] * len(nodes)
    for k, x in enumerate(nodes):
        up = x.parent
        menu = x.tag in ("ul", "ol", "dl", "table", "div", "section") and k not in keep and x.link_chars > 0.5 * x.chars and x.chars < 60 * x.links
        inside[k] = k in keep or up >= 0 and inside[up]
        crowded[k] = k not in keep and (menu or up >= 0 and crowded[up])
    if nodes[best].tag not in ("body", "html") and allowed == (PLAIN,):  # a header within the article's box holds its title, unless it has a menu
        menus = set()
        for k in range(len(nodes) - 1, 0, -1):
            if nodes[k].tag in ("nav", "ul", "form") or k in menus:
                menus.add(nodes[k].parent)
        for k in range(1, len(nodes)):
            if shut[k] == HEADER and inside[k] and (shut[nodes[k].parent] == PLAIN) and k not in menus:
                shut[k] = PLAIN
        blocks = _texts(parts, shut, allowed)
    out = []
    for owner, text, linked in blocks:
        x = nodes[owner]
        beside = x.tag == "p" and x.parent == around and len(text) > 80 and linked < 0.25 * len(text)
        if (inside[owner] or beside) and not crowded[owner]:
            out.append(text)
    return "\n\n".join(out)


def extract_main_text(pages: DataFrame) -> DataFrame:
    """pages(page_id, url, html) -> page_id, url, text, n_chars."""

    def run(batches):
        for batch in batches:
            texts = [main_text(x.as_py()) for x in batch.column("html")]
            yield pa.RecordBatch.from_arrays(
                [batch.column("page_id"), batch.column("url"), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())],
                ["page_id", "url", "text", "n_chars"],
            )

    return only(pages, page_id="bigint", url="string", html="string").mapInArrow(tidy(run), "page_id bigint, url string, text string, n_chars bigint")
