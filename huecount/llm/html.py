"""Main text of web pages, by equivalence classes of template tokens.

Pages of a host come from few templates. A token is a tag with its path (names, classes and ids of the elements
around it), or the text of a block with the box it lies in. Its occurrence vector, how often it occurs in each
page of the host, is kept as a number of pages and an exclusive-or of hashes of (page, count), which partial
aggregation can merge; pages of equal html are one page in it, so that none can cancel another.
Tokens of equal vectors form a class. A class is valid if it holds several tokens, a tag among them, and
occurs in enough pages; valid classes nest by the span of their positions, and those inside the class that the
most pages share, on half of the pages at least, are the template. Its tags bound slots; its texts are its own.

The template chooses the slots of the article: of the boxes (body, divisions, sections, articles) that it has once
a page, the deepest one with most (MAIN_SHARE) of the text that is neither a link nor the template's own. A page's main text
is what lies in that box, without the template's own texts. Hosts with fewer than SUPPORT pages, and pages
without their host's box, use the template of all pages; pages without that box are taken whole. Names decide
between slots that the template cannot tell apart: what lies in an element called menu, header, footer, aside,
form, advert, notice, comments and the like is no article, and of a box with elements marked as article or main only
these count. Text that is common to pages is kept inside marked elements if it is most of what they hold:
then the pages are copies of one article. In a box without marks, blocks of links are dropped.

Inside a block white space becomes one blank, blocks are trimmed, empty ones dropped, the rest joined by
line ends. A line break element is white space. Every step of reading a page takes time in proportion to it.

Defined results: a null or empty html gives an empty text; a null url is the host ''; repeated rows give equal
rows; broken markup is read as far as it goes: a tag ends at the first > outside of quotes, after a quote that
never ends at the first > of all, and without any the rest of the page is dropped; boxes nested more than
MAX_BOXES deep count as part of those around them; long pages are read whole; an empty table gives an empty
result; extra columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from html import unescape

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from huecount.llm.common import cut, cut_texts, made, settle, slices

SUPPORT = 3
#: Pages that text inside marked articles has to share before it can be the template's.
MARKED_SUPPORT = 8
#: Share of the marked text up to which common text is the template's; beyond, pages are copies.
MINOR = 0.2
CLASS_SIZE = 3
MAIN_SHARE = 0.7
MAX_BOXES = 32
ALL_HOSTS = "*"

_ATTR = re.compile(r"""(?<![a-zA-Z-])([a-zA-Z-]++)\s*+=\s*+(?:"([^"]*)"|'([^']*)'|([^\s"'>]++))""")
_NAME = re.compile(r"[a-zA-Z][^\s/>]*+")
_QUOTE_OR_END = re.compile(r"""["'>]""")
_SPACE = re.compile(r"\s+")
_DIGITS = re.compile(r"\d+")
# Fixed lists of elements.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript template iframe svg math object select option button".split())
CLOSED_RAW = frozenset("script style title textarea".split())
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
BOXES = frozenset("html body div article main section center td".split())
DROPPED = frozenset("nav header footer aside form menu dialog fieldset".split())
CONTENT = frozenset(("article", "main"))
_DROPPED_NAMES = re.compile(
    r"(?i)(?:^|[\s_-])(?:ads?|advert\w*|adbox|banner|sponsor\w*|promo\w*|nav\w*|menus?|breadcrumbs?|sidebars?|side|footer\w*|header|masthead|cookies?|consent|gdpr|notices?|alerts?|"
    r"popups?|modal|overlay|newsletter|subscribe|subscription|signup|login|search|share|sharing|social|related|recommend\w*|pagination|pager|toolbar|widgets?|skip|copyright|legal)(?:$|[\s_-])"
)
_COMMENT_NAMES = re.compile(r"(?i)(?:^|[\s_-])(?:comments?|commentlist|replies|reply|responses?|disqus|respond|discussion)(?:$|[\s_-]|-?list|-?area)")
_DROPPED_ROLES = frozenset("navigation banner contentinfo complementary search dialog alert alertdialog menu menubar form".split())


def hashed(text: str, seed: int = 0) -> int:
    """A signed 64-bit hash; the seed is one as well."""
    import xxhash

    return xxhash.xxh3_64_intdigest(text.encode("utf-8", "surrogatepass"), seed & 0xFFFFFFFFFFFFFFFF) - (1 << 63)


ROOT = 0


class Block:
    """Text between two tags that end blocks: its parts, the box it lies in, its region, and the number of tags before it."""

    __slots__ = ("parts", "box", "dropped", "content", "chars", "linked", "place")

    def __init__(self, box: int, dropped: bool, content: bool, place: int):
        self.parts, self.box, self.dropped, self.content, self.chars, self.linked, self.place = [], box, dropped, content, 0, 0, place

    def text(self) -> str:
        return _SPACE.sub(" ", "".join(self.parts)).strip()


class Element:
    """An open element, and what holds for its content: path, number of its box, region, the places in the
    stack of the nearest element that is not inline, of the nearest list and of the nearest list item, and how
    many boxes of a kind it holds so far."""

    __slots__ = ("name", "path", "box", "dropped", "content", "commented", "linked", "solid", "list", "item", "boxes")


class Page:
    """A page as read: blocks in page order, tag tokens, and boxes (path, number of the box around, depth)."""

    def __init__(self, html: str | None):
        self.blocks: list[Block] = []
        self.tags: list[int] = [ROOT]
        self.boxes: list[tuple[int, int, int]] = [(ROOT, -1, 0)]
        self._read(html or "")

    def _read(self, html: str) -> None:
        top = Element()
        top.name, top.path, top.box, top.dropped, top.content, top.commented, top.linked = "", ROOT, 0, False, False, False, False
        top.solid, top.list, top.item, top.boxes = 0, -1, -1, {}
        self.stack, self.open, self.block = [top], {}, None
        at, strict, n = 0, True, len(html)
        while at < n:
            sign = html.find("<", at)
            while 0 <= sign < n - 1 and not (html[sign + 1].isalpha() and html[sign + 1].isascii() or html[sign + 1] in "/!?"):
                sign = html.find("<", sign + 1)
            if sign < 0 or sign == n - 1:
                self._text(html[at:])
                return
            if sign > at:
                self._text(html[at:sign])
            if html.startswith("<!--", sign):
                end = html.find("-->", sign + 4)
                at = end + 3 if end >= 0 else n
                continue
            closing = html[sign + 1] == "/"
            name = _NAME.match(html, sign + 1 + closing)
            if name is None:  # a declaration, or an end tag without a name
                end = html.find(">", sign)
                at = end + 1 if end >= 0 else n
                continue
            end = name.end()
            while strict:
                mark = _QUOTE_OR_END.search(html, end)
                if mark is None or mark[0] == ">":
                    end = mark.start() if mark else -1
                    break
                end = html.find(mark[0], mark.end()) + 1
                if end == 0:
                    strict = False
            if not strict:
                end = html.find(">", name.end())
            if end < 0:
                return
            at = end + 1
            if closing:
                self._close(name[0].lower())
            else:
                raw = self._start(name[0].lower(), html[name.end() : end])
                if raw:
                    shut = re.compile(rf"</{re.escape(raw)}(?=[\s/>])", re.I).search(html, at)
                    stop = html.find(">", shut.end()) if shut else -1
                    at = stop + 1 if stop >= 0 else n

    def _text(self, text: str) -> None:
        top = self.stack[-1]
        dropped = top.dropped or top.commented
        b = self.block
        if b is None or (b.box, b.dropped, b.content) != (top.box, dropped, top.content):
            if not text.strip() and b is None:
                return
            b = self.block = Block(top.box, dropped, top.content, len(self.tags))
            self.blocks.append(b)
        text = unescape(text)
        b.parts.append(text)
        n = len(text.strip())
        b.chars += n
        b.linked += n * top.linked

    def _close(self, name: str) -> None:
        if name not in INLINE:
            self.block = None
        if name == "br":
            self._text(" ")
        if not self.open.get(name):
            return
        while self._pop() != name:
            pass

    def _pop(self) -> str:
        gone = self.stack.pop()
        self.open[gone.name] -= 1
        return gone.name

    def _cut(self, place: int) -> None:
        while len(self.stack) > place:
            self._pop()

    def _start(self, name: str, attributes: str) -> str:
        """Open an element; return its name if its content is no markup."""
        inline = name in INLINE
        if not inline:
            self.block = None
        elif name == "br":
            self._text(" ")
        alone = attributes.rstrip().endswith("/")
        top = self.stack[-1]
        if name in RAW:
            self.tags.append(hashed(name, top.path))
            return name if name in CLOSED_RAW or not alone else ""
        if name == "p" and self.stack[top.solid].name == "p":  # a paragraph ends where the next one starts
            self._cut(top.solid)
        elif name == "li" and top.item > top.list:
            self._cut(top.item)
        top = self.stack[-1]
        found = {k.lower(): a or b or c for k, a, b, c in _ATTR.findall(attributes)} if "=" in attributes else {}
        e = Element()
        e.name, e.path, e.box, e.linked = name, top.path, top.box, top.linked or name == "a"
        e.dropped, e.content, e.commented = top.dropped, top.content, top.commented
        e.solid, e.list, e.item, e.boxes = top.solid, top.list, top.item, top.boxes if inline else {}
        kind = region(name, attributes, found) if attributes or not inline else ""
        if not inline:
            called = _DIGITS.sub("", f"{name}.{found.get('class', '')}#{found.get('id', '')}")
            if name in BOXES and called.endswith(".#"):  # boxes without a name of their own are told apart by their order
                nth = top.boxes[called] = top.boxes.get(called, 0) + 1
                called = f"{called}{nth}"
            e.path = hashed(called, top.path)
            self.tags.append(e.path)
        if name in VOID or alone:
            return ""
        place = len(self.stack)
        if not inline:
            e.solid = place
        if name in ("ul", "ol"):
            e.list = place
        elif name == "li":
            e.item = place
        marked = kind == "content" and not top.commented
        if marked:
            e.content, e.dropped = True, False
        elif kind == "dropped":
            e.dropped = True
        e.commented = top.commented or kind == "comments"
        depth = self.boxes[top.box][2]
        if name in BOXES and (marked or not top.content) and depth < MAX_BOXES:
            e.box = len(self.boxes)
            self.boxes.append((e.path, top.box, depth + 1))
        self.stack.append(e)
        self.open[name] = self.open.get(name, 0) + 1
        return ""


def region(name: str, attributes: str, found: dict[str, str]) -> str:
    """'' for neutral elements, else dropped, comments or content."""
    names = f"{found.get('class', '')} {found.get('id', '')}"
    if names != " " and _COMMENT_NAMES.search(names):
        return "comments"
    if name in CONTENT or found.get("role") in CONTENT:
        return "content"
    if name in DROPPED or found.get("role") in _DROPPED_ROLES or "hidden" in attributes.split():
        return "dropped"
    if name not in ("body", "html") and names != " " and _DROPPED_NAMES.search(names):
        return "dropped"
    if found.get("aria-hidden") == "true" or "display:none" in found.get("style", "").replace(" ", ""):
        return "dropped"
    return ""


def own_token(page: Page, block: Block, text: str) -> int:
    return hashed(text, page.boxes[block.box][0] ^ 1)


def main_text(html: str | None, boxes: tuple[int | None, ...] = (), own: frozenset[int] | set[int] = frozenset()) -> tuple[str, int]:
    """The main text, given paths of boxes to look for, in this order, and the template's own texts; and which
    of the boxes was found, -1 if none."""
    page = Page(html)
    number = {}
    for i, (path, _, _) in enumerate(page.boxes):
        number.setdefault(path, i)
    which = next((k for k, b in enumerate(boxes) if b is not None and b in number), -1)
    inside = [which < 0] * len(page.boxes)
    for i, (path, around, _) in enumerate(page.boxes):
        inside[i] = inside[i] or (around >= 0 and inside[around]) or path == boxes[which]
    kept = [(b, b.text()) for b in page.blocks if inside[b.box] and not b.dropped]
    kept = [(b, t) for b, t in kept if t]
    if any(b.content for b, _ in kept):
        kept = [(b, t) for b, t in kept if b.content]
    else:
        kept = [(b, t) for b, t in kept if 2 * b.linked <= b.chars]
    return "\n".join(t for b, t in kept if not own or own_token(page, b, t) not in own), which


def _with_host(pages: DataFrame) -> DataFrame:
    host = F.lower(F.regexp_extract(F.coalesce("url", F.lit("")), r"^\s*(?:[a-zA-Z][a-zA-Z0-9+.-]*:)?//(?:[^/?#@]*@)?([^/?#:]*)", 1))
    return pages.select(F.col("page_id").cast("string").alias("page_id"), "url", "html", host.alias("host"))


def distinct(pages: DataFrame) -> DataFrame:
    """html, host, copy: pages of equal html once, under the first of their hosts. Only pages that have copies
    are dealt out anew."""
    rows = _with_host(pages).select("html", "host", F.md5(F.coalesce("html", F.lit("")).cast("binary")).alias("copy"))
    copies = rows.groupBy("copy").agg(F.count("*").alias("n"), F.min("host").alias("first_host")).where("n > 1").drop("n")
    copies = cut(copies, "html-copies")
    alone = rows.join(copies, "copy", "left_anti")
    once = rows.join(copies, "copy").where("host = first_host").drop("first_host").dropDuplicates(["copy"])
    return alone.unionByName(once)


TOKEN = "host string, token long, kind int, depth int, box long, chain array<long>, pages long, times long, words long, place long, marked long, vector long"
TAG, TEXT, MARKED = range(3)


def page_tokens(html: str | None) -> dict[int, list]:
    """token -> kind, depth (of boxes, else -1), box, chain (paths of the boxes around a box and its own), times,
    words (of a box all that are no links, of a text its own), place, words of marked elements (of the root only)."""
    page, found = Page(html), {}
    for k, path in enumerate(page.tags):
        found.setdefault(path, [TAG, -1, 0, None, 0, 0, k, 0])[4] += 1
    words = [0] * len(page.boxes)
    for b in page.blocks:
        if not b.dropped and (t := b.text()):
            n = t.count(" ") + 1
            one = found.setdefault(own_token(page, b, t), [MARKED if b.content else TEXT, -1, page.boxes[b.box][0], None, 0, 0, b.place, 0])
            one[4] += 1
            one[5] += n
            found[ROOT][7] += n * b.content
            words[b.box] += n if 2 * b.linked <= b.chars else 0
    for i in range(len(words) - 1, 0, -1):  # a box comes after the one around it
        words[page.boxes[i][1]] += words[i]
    chains = [[ROOT]]
    for path, around, _ in page.boxes[1:]:
        chains.append([*chains[around], path])
    for (path, _, depth), chain, n in zip(page.boxes, chains, words, strict=True):
        one = found[path]
        one[1], one[3] = depth, chain
        one[5] += n
    return found


def occurrence(pages: DataFrame) -> DataFrame:
    """Merged tokens of all hosts, and of all pages as one host, with their number of pages and occurrences and their
    occurrence vectors; those on SUPPORT pages at least."""
    columns = [c.split()[0] for c in TOKEN.split(", ")]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in slices(batches, "html"):
            seen: dict[tuple[str, int], list] = {}
            for html, host, copy in batch[["html", "host", "copy"]].itertuples(index=False):
                for token, (kind, depth, box, chain, times, words, place, marked) in page_tokens(html).items():
                    one = seen.setdefault((host, token), [kind, depth, box, chain, 0, 0, 0, 0, 0, 0])
                    one[4] += 1
                    one[5] += times
                    one[6] += words
                    one[7] += place
                    one[8] += marked
                    one[9] ^= hashed(copy, times)
            yield pd.DataFrame([(h, t, *v) for (h, t), v in seen.items()], columns=columns)

    parts = distinct(pages).select("html", "host", "copy").mapInPandas(run, TOKEN)
    same = [F.max(c).alias(c) for c in ("kind", "depth", "box", "chain")]
    sums = [*[F.sum(c).alias(c) for c in ("pages", "times", "words", "place", "marked")], F.bit_xor("vector").alias("vector")]
    per_host = cut_texts(parts.groupBy("host", "token").agg(*same, *sums), "html-tokens")
    everywhere = per_host.groupBy("token").agg(*same, *sums).select(F.lit(ALL_HOSTS).alias("host"), "*")
    enough = F.col("pages") >= SUPPORT
    return per_host.where(enough).unionByName(everywhere.where(enough))


def template_tokens(tokens: DataFrame) -> DataFrame:
    """Tokens of valid classes that nest in the class that most pages share, with host_pages."""
    classes = (
        tokens.withColumn("at", F.col("place") / F.col("pages"))
        .groupBy("host", "pages", "vector")
        .agg(F.count("*").alias("size"), F.count_if(F.col("kind") == TAG).alias("n_tags"), F.min("at").alias("lo"), F.max("at").alias("hi"))
        .where((F.col("size") >= CLASS_SIZE) & (F.col("n_tags") > 0))
    )
    roots = classes.groupBy("host").agg(F.max(F.struct("pages", (F.col("hi") - F.col("lo")).alias("span"), "lo", "hi")).alias("root"))
    most = tokens.groupBy("host").agg(F.max("pages").alias("host_pages"))  # every page has the root token
    inside = (F.col("lo") >= F.col("root.lo")) & (F.col("hi") <= F.col("root.hi")) & (2 * F.col("pages") >= F.col("host_pages"))
    nested = classes.join(roots, "host").join(most, "host").where(inside).select("host", "pages", "vector", "host_pages")
    return tokens.join(nested, ["host", "pages", "vector"])


def templates(tokens: DataFrame) -> DataFrame:
    """host, box (path of the article's box), own (the template's own texts). Tokens on half of a host's pages are
    at most twice as many as a page has in the mean, so a row does not grow with the number of pages."""
    template = cut(template_tokens(tokens), "html-template")
    marked = tokens.where(F.col("token") == ROOT).select("host", F.col("marked").alias("marked_words"))
    texts = template.where(F.col("kind") != TAG).join(marked, "host", "left")
    common = F.sum(F.when(F.col("kind") == MARKED, F.col("words")))
    share = texts.groupBy("host").agg((common / F.max("marked_words")).alias("share"))
    copies = (F.col("kind") == MARKED) & ((F.col("share") > MINOR) | (F.col("pages") < MARKED_SUPPORT))
    own = cut(texts.join(share, "host").where(~copies).select("host", "token", "box", "words"), "html-own")
    boxes = template.where("depth >= 0").select("host", "token", "depth", "chain", "pages", "times", "words")
    theirs = own.join(boxes.select("host", F.col("token").alias("box"), "chain"), ["host", "box"])
    theirs = theirs.select("host", F.explode("chain").alias("token"), "words").groupBy("host", "token").agg(F.sum("words").alias("own_words"))
    mass = F.col("words") - F.coalesce("own_words", F.lit(0))
    weighed = boxes.join(theirs, ["host", "token"], "left").select("host", "token", "depth", "pages", "times", mass.alias("mass"))
    whole = weighed.where("depth = 0").select("host", F.col("mass").alias("whole"))
    fit = weighed.join(whole, "host").where((F.col("times") == F.col("pages")) & (F.col("mass") >= MAIN_SHARE * F.col("whole")) & (F.col("mass") > 0))
    best = fit.groupBy("host").agg(F.max(F.struct("depth", "mass", "token")).getField("token").alias("box"))
    texts = own.groupBy("host").agg(F.array_sort(F.collect_list("token")).alias("own"))
    return best.join(texts, "host", "full")


def extracted(pages: DataFrame) -> DataFrame:
    """page_id, url, text, decided ('host', 'all' or 'page': whose template chose the box) of every page."""
    since = made()
    template = settle(templates(occurrence(pages)), "html-templates", since)
    common = template.where(F.col("host") == ALL_HOSTS).select("box", "own").first()  # one row, as long as a page
    all_box, all_own = (common[0], frozenset(common[1] or ())) if common else (None, frozenset())
    own = template.where(F.col("host") != ALL_HOSTS).withColumnRenamed("host", "t_host")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in slices(batches, "html"):
            texts, decided = [], []
            for html, known, box, own in zip(batch["html"], batch["t_host"], batch["box"], batch["own"], strict=True):
                if known is None:
                    text, which = main_text(html, (None, all_box), all_own)
                else:
                    text, which = main_text(html, (None if box is None else int(box), all_box), frozenset(() if own is None else own))
                texts.append(text)
                decided.append(("host", "all", "page")[which])
            yield batch[["page_id", "url"]].assign(text=texts, decided=decided)

    joined = _with_host(pages).join(own, F.col("host") == F.col("t_host"), "left")
    joined = joined.select("page_id", "url", "html", "t_host", F.col("box").cast("string").alias("box"), "own")
    return joined.mapInPandas(run, "page_id string, url string, text string, decided string").withColumn("page_id", F.col("page_id").cast("long"))


def op7_html(pages: DataFrame) -> DataFrame:
    return extracted(pages).select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"), "decided")
