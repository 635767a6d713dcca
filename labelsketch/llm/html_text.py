"""Main text of web pages by consensus host paths.

Every page's containers are scored (text of their blocks, less link text, none from boilerplate), under a generalised path
of tags and classes. The scores are summed per host and path in Spark, the best path of each host wins, and its pages are
extracted again around the winning path; a page that lacks it falls back on its own best container. From there the text
grows to the whole article: outwards through every container that adds mostly text without links.

A container that only its class, id or role, or being a form, marks as boilerplate is none if it holds most of the page's
text without links: a page is not lost by the name of its layout.

Null and empty pages, and pages without text, give an empty text. Blocks of the chosen container are kept whole, whatever
their length. Malformed markup is read leniently. Repeated rows are treated alike, extra columns are ignored, an empty
table gives an empty result. A hot host is only ever a sum of partial sums and one side of a join that Spark can split.
"""

from __future__ import annotations

import html
import re

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common

#: Elements whose content is no text, those that hold no article text, those that end a block, those without content.
RAW = frozenset("script style textarea title noscript template iframe svg math object canvas xmp noembed".split())
SKIP = frozenset("head nav aside footer form menu dialog button select option input label fieldset datalist audio video map".split()) | RAW
BLOCK = frozenset("p div h1 h2 h3 h4 h5 h6 li ul ol dl dt dd article section main body html table thead tbody tfoot tr td th blockquote pre header footer nav aside form figure figcaption address hr center details summary hgroup caption menu dialog fieldset".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
CONTAINER = frozenset("article section main div td body blockquote table tbody tr center".split())
#: Words of a class, id or role that mark boilerplate.
NOISE = frozenset(
    "ad ads adv advert adverts advertisement advertising adsense adbox banner promo promotion sponsor sponsored sponsors nav navbar navigation menu menus submenu sidebar sidebars side rail footer foot header masthead topbar toolbar breadcrumb breadcrumbs cookie cookies consent gdpr notice notices alert notification popup modal overlay newsletter subscribe subscription signup login search share sharing social related recommended recommendations comment comments commentlist disqus reply replies respond discussion reviews pagination pager tags taglist widget widgets legal copyright disclaimer skip complementary contentinfo paywall".split()
)
#: Words that say that what follows is, or is not, beside an element; tags that are never boilerplate by name;
#: tags that are boilerplate only where they do not hold most of the text; tags that show where an article is, and how surely.
BESIDE = frozenset("has no with without".split())
NEVER = frozenset("body html article main".split())
SOFT = frozenset("form fieldset".split())
ANCHOR = {"article": 2, "main": 2, "h1": 1}
#: Share of the text without links beyond which a mark is overruled: where no surer anchor with text is outside it, and else.
MOST, NEARLY_ALL = 0.5, 0.75
#: Closing tags that a new element of a kind implies.
CLOSES = {"li": {"li", "p"}, "dt": {"dt", "dd", "p"}, "dd": {"dt", "dd", "p"}, "tr": {"tr", "td", "th", "p"}, "td": {"td", "th", "p"}, "th": {"td", "th", "p"}, "option": {"option"}}
STOPS = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"tr", "table"}, "th": {"tr", "table"}, "option": {"select"}}

MARKUP = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/<>]*+)((?:[^<>\"']|\"[^\"]*\"|'[^']*')*+)>", re.S)
ATTRIBUTE = re.compile(r"(?<![\w-])(class|id|role|hidden|aria-hidden|style)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.I)
BLANKS = re.compile(r"\s+")
SPLIT = re.compile(r"[^a-z]+")
#: Hosts whose winning paths are broadcast at most (about 100 bytes each); beyond it they are joined by a shuffle.
BROADCAST_HOSTS = 200_000
HOST = r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/:?#]*)"

#: Open elements up to which containers have paths of their own.
DEEPEST = 3000


class Node:
    __slots__ = ("tag", "path", "noise", "link", "score", "box", "rest", "rest_linked", "mark", "anchor", "holds", "in_article")

    def __init__(self, tag: str, path: str, noise: bool, link: bool, box: Node | None):
        self.tag, self.path, self.noise, self.link, self.score = tag, path, noise, link, 0.0
        self.holds = self.in_article = False  # is it a container; is it inside of (or itself) article or main
        self.box = box  # the container around it
        self.rest = self.rest_linked = 0  # characters below it, and those in links, that are not of the chosen containers
        self.mark: Mark | None = None  # the innermost mark that can be overruled; none under one that can't be
        self.anchor = 0  # the surest anchor between the mark and here


class Mark:
    """What a mark that can be overruled holds; the root stands for the text that is not marked."""

    __slots__ = ("at", "in_article", "inside", "worth", "anchor")

    def __init__(self, at: int, in_article: bool):
        self.at, self.in_article, self.worth, self.anchor = at, in_article, 0.0, 0
        self.inside: list[Mark] = []

    def hold(self, size: int, link: bool, anchor: int) -> None:
        self.worth += -size if link else size
        self.anchor = max(self.anchor, anchor)


def named_noise(value: str) -> bool:
    """Is a word of one of the names in the value that of boilerplate, and not behind a word like has or no."""
    for name in value.split():
        for word in SPLIT.split(name):
            if word in BESIDE:
                break
            if word in NOISE:
                return True
    return False


def described(tag: str, attributes: str, inside_article: bool) -> tuple[str, bool, bool]:
    """(step of a generalised path, is it boilerplate, can that be overruled)."""
    step, noise = tag, tag in SKIP or (tag == "header" and not inside_article)
    hard = noise and tag not in SOFT
    if attributes:
        for m in ATTRIBUTE.finditer(attributes):
            name, value = m[1].lower(), (m[2] or m[3] or m[4] or "").lower()
            if name == "class":
                step += "".join(f".{c}" for c in sorted(set(re.sub(r"[0-9]+", "#", value).split())))
            if name in ("class", "id", "role"):
                noise |= tag not in NEVER and named_noise(value)
            elif name == "hidden" or (name == "aria-hidden" and value == "true"):
                hard = True
            elif name == "style":
                hard |= "display:none" in value.replace(" ", "")
    return step, noise or hard, not hard


def overruled(root: Mark) -> set[int]:
    """Where the marks begin that hold most of the page's text without links; none beside an article that is not marked."""
    order = [root]
    for m in order:
        order += m.inside
    sums: dict[int, tuple[float, int]] = {}
    for m in reversed(order):
        below = [sums[x.at] for x in m.inside]
        sums[m.at] = max(m.worth, 0.0) + sum(x for x, _ in below), max([m.anchor, *(x for _, x in below)])
    whole, at, found, outside = sums[root.at][0], root, set(), root.anchor
    while whole and at.inside:
        at = max(at.inside, key=lambda m: sums[m.at][0])
        held, anchor = sums[at.at]
        if outside == 2 > anchor and not at.in_article or held <= whole * (NEARLY_ALL if outside > anchor else MOST):
            break
        found.add(at.at)
        outside = max(outside, at.anchor)
    return found


def blocks(page: str, allowed: frozenset[int] | None = None) -> tuple[list[tuple[str, int, list[Node]]], list[Node]]:
    """(text, characters in links and containers of each block outside boilerplate, in page order; all containers).

    The marks of boilerplate on the elements at ``allowed`` do not count; None: on those that hold most of the text.
    """
    root = Node("html", "html", False, False, None)
    root.box = root
    root.holds = True
    marks = root.mark = Mark(-1, False)
    stack, found, boxes = [root], [], [root]
    parts: list[str] = []
    linked = 0
    at, n = 0, len(page)
    lowered = None

    def flush() -> None:
        nonlocal linked
        if parts:
            text = BLANKS.sub(" ", html.unescape("".join(parts))).strip()
            if text:
                chain, box = [], stack[-1] if stack[-1].holds else stack[-1].box
                while True:
                    chain.append(box)
                    if box is root:
                        break
                    box = box.box
                worth = len(text) - 2.0 * linked
                for share, node in zip((1.0, 0.5, 0.25, 0.1), chain, strict=False):
                    node.score += share * worth
                found.append((text, min(linked, len(text)), chain))
            parts.clear()
        linked = 0

    def leave(k: int) -> None:
        if any(x.tag in BLOCK or x.noise for x in stack[k:]):
            flush()
        del stack[k:]

    while at < n:
        m = MARKUP.search(page, at)
        end = m.start() if m else n
        if end > at and (top := stack[-1]).mark is not None:
            piece = page[at:end]
            if allowed is None and (size := len(piece.strip())):
                top.mark.hold(size, top.link, top.anchor)
            if not top.noise:
                parts.append(piece)
                if top.link:
                    linked += len(piece)
        if not m:
            break
        at = m.end()
        if m[2] is None:
            continue
        tag = m[2].lower()
        if m[1]:
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].tag == tag:
                    leave(k)
                    break
                if tag not in BLOCK and stack[k].tag in BLOCK:
                    break  # an inline end tag closes no block
            else:
                if tag in BLOCK:
                    flush()
            continue
        if tag in BLOCK:
            flush()
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].tag == "p" or (stack[k].tag in CLOSES.get(tag, ())):
                    leave(k)
                    break
                if stack[k].tag in STOPS.get(tag, CONTAINER):
                    break
        elif tag == "br" or tag == "wbr":
            parts.append(" " if tag == "br" else "")
        if tag in VOID or m[3].endswith("/") and tag not in BLOCK and tag not in RAW:
            continue
        if tag in RAW:
            lowered = page.lower() if lowered is None else lowered
            close = lowered.find(f"</{tag}", at)
            if close < 0:
                at = n if tag in ("script", "style", "template", "xmp") else at
                continue
            at = page.find(">", close) + 1 or n
            continue
        top = stack[-1]
        in_article = top.in_article
        step, noise, soft = described(tag, m[3], in_article)
        noise &= not (soft and allowed and at in allowed)
        box = top if top.holds else top.box
        if noise and not top.noise:
            flush()
        holds = tag in CONTAINER and len(stack) <= DEEPEST  # deeper elements keep their marks, their paths end here
        node = Node(tag, f"{box.path}>{step}" if holds else box.path, top.noise or noise, top.link or tag == "a", box)
        node.holds, node.in_article = holds, in_article or tag in ("article", "main")
        if top.mark is not None and (soft or not noise):
            if noise and allowed is None:
                node.mark = Mark(at, in_article)
                top.mark.inside.append(node.mark)
            else:
                node.mark, node.anchor = top.mark, max(top.anchor, ANCHOR.get(tag, 0))
        stack.append(node)
        if holds and not node.noise:
            boxes.append(node)
    flush()
    if allowed is None and marks.inside and (most := overruled(marks)):
        return blocks(page, frozenset(most))
    return found, boxes


def best_paths(page: str | None) -> dict[str, float]:
    """Score of every container path of a page, positive ones."""
    scores: dict[str, float] = {}
    if page:
        for box in blocks(page)[1]:
            if box.score > 0:
                scores[box.path] = scores.get(box.path, 0.0) + box.score
    return scores


def article(found: list[tuple[str, int, list[Node]]], chosen: set[int]) -> list[str]:
    """Texts of the article that the chosen containers are part of.

    An article element is taken whole. Otherwise each container around is taken whole, up to main or the root, unless half
    of what it adds is in links: then only its blocks with less than that are added (of body those outside other
    containers). Further out, too, only blocks outside other containers are added, such as a heading above the article.
    """
    starts = {id(b): b for _, _, chain in found for b in chain if id(b) in chosen}
    for text, linked, chain in found if starts else ():
        if not any(id(b) in chosen for b in chain):
            for b in chain:
                b.rest += len(text)
                b.rest_linked += linked
    taken, thinned, own = set(starts), set(), set()
    for box in starts.values():
        around = [box]
        while around[-1].box is not around[-1]:
            around.append(around[-1].box)
        k = max((i for i, b in enumerate(around) if b.tag == "article"), default=0)
        taken.update(id(b) for b in around[: k + 1])
        closed = any(b.tag == "main" for b in around[: k + 1]) or around[k].tag == "article" and all(b.tag != "main" for b in around)
        for inner, b in zip(around[k:], around[k + 1 :], strict=False):
            if closed:
                own.add(id(b))
            elif 2 * (b.rest_linked - inner.rest_linked) < b.rest - inner.rest or b.rest == inner.rest:
                taken.add(id(b))
                closed = b.tag == "main"
            else:
                (own if b.tag in ("body", "html") else thinned).add(id(b))
                closed = True
    return [t for t, linked, chain in found if any(id(b) in taken for b in chain) or 2 * linked < len(t) and (id(chain[0]) in own or any(id(b) in thinned for b in chain))]


def extract(page: str | None, winner: str | None) -> str:
    """Text of the article around the containers at the winning path; around the page's own best container where it has none."""
    if not page:
        return ""
    found, boxes = blocks(page)
    texts = article(found, {id(b) for b in boxes if b.path == winner})
    if not texts and found:
        texts = article(found, {id(max(boxes, key=lambda b: b.score))})
    return "\n\n".join(texts)


def host(url):
    return F.lower(F.regexp_extract(F.coalesce(url, F.lit("")), HOST, 1))


PATHS = T.ArrayType(T.StructType([T.StructField("path", T.StringType()), T.StructField("score", T.DoubleType())]))


def host_paths(pages: DataFrame) -> DataFrame:
    """host, winner: the container path with the largest summed score of all pages of the host.

    Pages without a host have no consensus; each takes its own best container.
    """

    def make():
        return lambda pages: [[[{"path": p, "score": round(s)} for p, s in best_paths(x).items()] for x in pages]]

    known = pages.select(host(F.col("url")).alias("host"), "html").filter("host <> ''")
    scored = common.map_texts(known, ["host"], ["html"], [T.StructField("paths", PATHS)], make)
    votes = scored.select("host", F.inline("paths")).groupBy("host", "path").agg(F.sum("score").alias("score"))
    return votes.groupBy("host").agg(F.max_by("path", F.struct("score", "path")).alias("winner"))


def main_text(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars of every page.

    The hosts' winning paths are broadcast if there are few enough of them, so that no page is shuffled.
    """
    winners = common.written(host_paths(pages), "hosts")
    if winners.count() <= BROADCAST_HOSTS:
        winners = F.broadcast(winners)
    rows = pages.select("page_id", "url", "html", host(F.col("url")).alias("host")).join(winners, "host", "left")

    def make():
        def work(pages: list[str | None], winners: list[str | None]) -> list:
            texts = [extract(p, w) for p, w in zip(pages, winners, strict=True)]
            return [texts, [len(x) for x in texts]]

        return work

    return common.map_texts(rows, ["page_id", "url"], ["html", "winner"], [T.StructField("text", T.StringType()), T.StructField("n_chars", T.LongType())], make)
