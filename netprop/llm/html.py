"""Main text of web pages by equivalence-class template deduction.

Pages of one host are taken to come from one template. A token is an element in its
place (the path of block elements that it stands in, with their classes and ids), or
a run of text in its place. Its occurrence vector says how often it stands in each
page of the host; tokens of equal vectors form an equivalence class. Three passes:

1. Tokens and vectors (:func:`vectors`), and from them the large classes of frequent
   tokens (:func:`candidates`). A class holds an element at least.
2. Validity (:func:`judged`): in every page the tokens of a class must come in one and
   the same order, once a round, and the rounds of two classes may lie in each other's
   gaps, always the same gap, but not overlap. Valid classes so nest into a template.
3. Extraction (:func:`extract_text`): what no valid class holds is slot text. The
   article is the page's one outermost <article> or <main>, taken whole; where it has
   none or several, the slot text of the innermost section of the host's template that
   holds all slot text.

Vectors are never built: each page adds a hash of (page, count) to a sum per token,
which is folded per batch and host before anything travels, so a host with a third of
all pages costs no more than any other. Sums do not depend on the order of pages, and
repeated pages add alike to all of their tokens.
"""

from __future__ import annotations

import html as entities
import re
from urllib.parse import urlsplit

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, functions as F

from netprop.llm import common

#: Share of a host's pages that a class must reach, and different pages that a host needs for a template.
SUPPORT, LEAST_PAGES = 0.5, 4
#: A page whose article would lose more than this share to the template is a copy of others, and keeps its text.
COPY_SHARE = 0.5
#: Hosts up to which their templates are broadcast if they also hold so many tokens at most; beyond, pages are salted and joined.
BROADCAST_HOSTS, BROADCAST_TOKENS, SALTS = 100_000, 1_000_000, 32

# Element names of the markup language by their role.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript template iframe svg noembed noframes".split())
VERBATIM = frozenset(["xmp"])
SECTIONS = frozenset("body div section article main td table center".split())
BLOCKS = SECTIONS | VERBATIM | frozenset("html head p h1 h2 h3 h4 h5 h6 ul ol li dl dt dd pre blockquote figure figcaption address hr tr th thead tbody tfoot caption nav header footer aside form fieldset details summary hgroup menu dialog".split())
CLOSES = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
CLUTTER = frozenset("nav footer aside form button select option label fieldset dialog menu head object audio video canvas".split()) | RAW
ARTICLES, NEVER_CLUTTER = frozenset(["article", "main"]), frozenset(["html", "body", "article", "main"])
# end of fixed values

#: Words for kinds of content that are no article. Inside an <article> or <main> they count only as a whole class, id or role.
KINDS = frozenset(
    "ad ads advert adverts advertisement advertising sponsor sponsored sidebar side-bar menu nav navbar navigation breadcrumb breadcrumbs footer notice notices cookie cookies "
    "cookie-notice cookie-banner ad-banner ad-slot comment comments commentlist comment-list comments-area comment-form disqus respond".split()
)
#: Words that count outside of an article too, also as one part of a hyphenated name.
OUTSIDE = KINDS | frozenset(
    "promo promotion banner pagination pager masthead consent gdpr alert popup modal overlay newsletter subscribe subscription signup login search share sharing social related "
    "recommended reply replies complementary contentinfo toolbar widget widgets skip toc".split()
)
#: First parts that say what a wrapper lacks or holds besides (``no-sidebar``).
QUALIFIERS = frozenset("no has with without not hide".split())

_OPEN = re.compile(r"<(?:(/?)([A-Za-z][^\s/>]*)|!--|!\[CDATA\[|[!?])")
_ATTRIBUTES = re.compile(r"""(?:[^"'>]|"[^"]*"|'[^']*')*+>""")
_NAMED = re.compile(r"""(?:^|\s)(class|id|role)\s*=\s*("[^"]*"|'[^']*'|[^\s"'>]+)""", re.I)
_PARTS = re.compile(r"[\s_]+")
_SPACE = re.compile(r"\s+")
_DIGITS = re.compile(r"[0-9]{3,}")  # numbers of posts in ids
_ENDS = {name: re.compile(rf"</{name}\s*>", re.I) for name in RAW | VERBATIM}
_WRAPPERS = frozenset("html nav footer aside form header ul ol".split())
_FULL = (1 << 64) - 1


def marks_of(attributes: str) -> list[str]:
    """Words of class, id and role, in lower case."""
    return [w for _, v in _NAMED.findall(attributes) for w in _PARTS.split(v.strip("\"'").lower()) if w]


def is_clutter(tag: str, marks: list[str], inside_article: bool) -> bool:
    if tag in CLUTTER or (tag == "header" and not inside_article):
        return True
    if not marks or tag in NEVER_CLUTTER:
        return False
    if inside_article:
        return any(w in KINDS for w in marks)
    for w in marks:
        parts = w.split("-")
        if w in OUTSIDE or (parts[0] not in QUALIFIERS and any(p in OUTSIDE for p in parts)):
            return True
    return False


class Page:
    """A page as places in a tree (numbers; a parent comes before its children), blocks of text and the order of both.

    Tokenizing, closing and summing are linear in the length of the page.
    """

    def __init__(self, page: str):
        self.parent, self.token, self.names, self.clutter, self.inside, self.section, self.depth = [-1], [0], [""], [False], [False], [0], [0]
        self.count = [1]
        self.blocks: list[tuple[int, str, bool]] = []  # place, text, whether all of it is in links
        self.events: list[int] = []  # elements by place, blocks as -1 - number
        self._known: dict[tuple[int, str], int] = {}
        self._read(page)

    def _enter(self, at: int, name: str, attributes: str) -> int:
        label = f"{name}{attributes}"
        place = self._known.get((at, label))
        if place is None:
            marks = marks_of(attributes) if attributes else []
            token = xxhash.xxh64_intdigest(_DIGITS.sub("0", " ".join([name, *marks])), self.token[at])
            place = self._known.get((at, token))  # other attributes, same marks
            if place is None:
                place = len(self.parent)
                inside = self.inside[at] or self.names[at] in ARTICLES
                self.parent.append(at)
                self.token.append(token)
                self.names.append(name)
                self.inside.append(inside)
                self.clutter.append(self.clutter[at] or is_clutter(name, marks, inside))
                self.section.append(place if name in SECTIONS else self.section[at])
                self.depth.append(self.depth[at] + 1)
                self.count.append(0)
                self._known[at, token] = place
            self._known[at, label] = place
        return place

    def _read(self, page: str) -> None:
        stack, at = [0], 0
        open_by_scope: list[dict[str, int]] = [{}]  # open elements since each open section
        text: list[str] = []
        owner, linked, links, plain = 0, 0, False, False
        size, known_open = len(page), {}

        def flush():
            nonlocal linked
            if text:
                raw = "".join(text)
                block = _SPACE.sub(" ", entities.unescape(raw) if "&" in raw else raw).strip()
                if block:
                    self.events.append(-1 - len(self.blocks))
                    self.blocks.append((owner, block, linked * 10 >= 9 * len(raw)))
                text.clear()
                linked = 0

        def add(some: str):
            nonlocal linked, owner
            if some and not self.clutter[stack[-1]]:
                if not text:
                    owner = stack[-1]
                text.append(some)
                if links:
                    linked += len(some)

        def push(place: int, name: str):
            stack.append(place)
            known_open[name] = known_open.get(name, 0) + 1
            if name in SECTIONS:
                open_by_scope.append({})
            open_by_scope[-1][name] = open_by_scope[-1].get(name, 0) + 1

        def cut(k: int):
            while len(stack) > k:
                name = self.names[stack.pop()]
                known_open[name] -= 1
                open_by_scope[-1][name] -= 1
                if name in SECTIONS:
                    open_by_scope.pop()

        while at < size:
            m = _OPEN.search(page, at)
            if m is None:
                break
            add(page[at : m.start()])
            name, e = m[2], m.end()
            if name is None:
                kind = m[0]
                close = "-->" if kind == "<!--" else "]]>" if kind == "<![CDATA[" else ">"
                end = page.find(close, e if kind != "<!--" else e - 2)
                if kind == "<![CDATA[":
                    add(page[e : end if end >= 0 else size])
                elif end < 0 and close == ">":
                    add(page[m.start() :])
                at = size if end < 0 else end + len(close)
                continue
            end = page.find(">", e)
            if end < 0:  # no tag ends any more
                add(page[m.start() :])
                at = size
                break
            attributes = page[e:end]
            if not plain and ('"' in attributes or "'" in attributes):
                whole = _ATTRIBUTES.match(page, e)
                plain = whole is None  # quotes do not pair up to the end of the page: from here on they are no quotes
                if whole:
                    end = whole.end() - 1
                    attributes = page[e:end]
            at, name = end + 1, name.lower()
            block = name in BLOCKS
            if m[1]:  # end tag
                if name == "a":
                    links = False
                if block:
                    flush()
                if not known_open.get(name):
                    continue
                crosses = name in SECTIONS or name in _WRAPPERS
                if crosses or open_by_scope[-1].get(name):  # else a stray end tag, which leaves its section alone
                    k = len(stack) - 1
                    while self.names[stack[k]] != name:
                        k -= 1
                    cut(k)
                continue
            if name == "a":
                links = True
            if name == "br":
                add(" ")
                continue
            if block:
                flush()
                shut = CLOSES.get(name, ())
                for k in range(len(stack) - 1, 0, -1):
                    held = self.names[stack[k]]
                    if held == "p" or held in shut:
                        cut(k)
                        break
                    if held in BLOCKS and held not in ("tr", "tbody"):
                        break
            if name in VOID:
                continue
            parent = stack[-1]
            if not block and name not in CLUTTER and not known_open.get(name):  # inline markup places no text, unless its marks say that it is none
                if not attributes or self.clutter[parent] or not is_clutter(name, marks_of(attributes), self.inside[parent] or self.names[parent] in ARTICLES):
                    continue
            place = self._enter(parent, name, attributes)
            self.count[place] += 1
            self.events.append(place)
            if name in _ENDS:  # its content is no markup
                close = _ENDS[name].search(page, at)
                if name in VERBATIM:
                    push(place, name)
                    add(page[at : close.start() if close else size].replace("&", "&amp;"))
                    flush()
                    cut(len(stack) - 1)
                at = close.end() if close else size
                continue
            if not attributes.endswith("/") or block:
                push(place, name)
        add(page[at:])
        flush()

    def texts(self) -> list[int]:
        """The token of each block."""
        return [xxhash.xxh64_intdigest(t, self.token[p]) for p, t, _ in self.blocks]

    def held(self, counted: list[bool]) -> list[int]:
        """Characters of the counted blocks in each place, those below it included."""
        size = [0] * len(self.parent)
        for (p, t, _), c in zip(self.blocks, counted, strict=True):
            if c:
                size[p] += len(t)
        for p in range(len(size) - 1, 0, -1):
            size[self.parent[p]] += size[p]
        return size

    def within(self, place: int) -> list[bool]:
        found = [False] * len(self.parent)
        for p in range(len(found)):
            found[p] = p == place or (p > 0 and found[self.parent[p]])
        return found


def host_of(url: str | None) -> str:
    try:
        return (urlsplit(url or "").hostname or "").lower()
    except ValueError:
        return ""


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


# ------------------------------------------------------------- tokens and classes

_VECTORS = "host string, token long, is_text boolean, pages long, low long, high long"


def vectors(pages: DataFrame) -> DataFrame:
    """``(host, token, is_text, pages, low, high)``: each token's pages and the sums that stand for its vector.

    The row of token 0 is the host's. A text that in some batch has the vector of no
    element is left out there: a class needs an element, and the sums now differ for good.
    """

    def run(batches):
        for batch in batches:
            found: dict[tuple, list[int]] = {}
            for url, page in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                host, page = host_of(url), page or ""
                key = xxhash.xxh64_intdigest(page)
                held, counts = Page(page), {}
                for token, n in zip(held.token, held.count, strict=True):
                    counts[token, False] = n
                for t in held.texts():
                    counts[t, True] = counts.get((t, True), 0) + 1
                mixed = {n: xxhash.xxh64_intdigest(n.to_bytes(8, "little"), key) for n in set(counts.values())}
                for k, n in counts.items():
                    v, row = mixed[n], found.get((host, *k))
                    if row is None:
                        found[host, *k] = [1, v & 0xFFFFFFFF, v >> 32]
                    else:
                        row[0] += 1
                        row[1] += v & 0xFFFFFFFF
                        row[2] += v >> 32
            elements = {(k[0], *v) for k, v in found.items() if not k[2]}
            rows = [(*k, *v) for k, v in found.items() if not k[2] or (k[0], *v) in elements]
            kinds = (pa.string(), pa.int64(), pa.bool_(), pa.int64(), pa.int64(), pa.int64())
            columns = list(zip(*rows, strict=True)) if rows else [()] * len(kinds)
            columns[1] = [_signed(x) for x in columns[1]]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=["host", "token", "is_text", "pages", "low", "high"])

    return pages.select("url", "html").mapInArrow(run, _VECTORS).groupBy("host", "token", "is_text").agg(*[F.sum(c).alias(c) for c in ("pages", "low", "high")])


def candidates(found: DataFrame, distinct: DataFrame, support: float = SUPPORT, least: int = LEAST_PAGES) -> DataFrame:
    """``(host, token, class)``: large classes of frequent tokens, of hosts ``(host, distinct)`` with enough different pages.

    A class has two tokens or more, one of them an element.
    """
    hosts = found.where("token = 0 and not is_text").select("host", F.col("pages").alias("host_pages"))
    hosts = hosts.join(distinct.where(F.col("distinct") >= least).select("host"), "host")
    often = found.join(hosts, "host").where((F.col("pages") >= support * F.col("host_pages")) & ((F.col("token") != 0) | F.col("is_text")))
    members = often.groupBy("host", F.xxhash64("low", "high").alias("class")).agg(F.collect_list("token").alias("tokens"), F.bool_or(~F.col("is_text")).alias("element"))
    return members.where("element and size(tokens) > 1").select("host", F.explode("tokens").alias("token"), "class")


def packed(members: DataFrame) -> DataFrame:
    """``(host, members)``: a host's tokens and classes in one row. Each stands in half of its pages at least, so they are twice as many as a page's tokens at most."""
    return members.groupBy("host").agg(F.sort_array(F.collect_list(F.struct("token", "class"))).alias("members"))


# ---------------------------------------------------------------------- validity


def walk(page: Page, texts: list[int], classes: dict[int, int], sizes: dict[int, int]) -> dict[int, tuple[int, int, bool]]:
    """For each class that the page holds: a number for the order of its tokens, one for the gap it lies in, and whether it is sound here."""
    order: dict[int, list[int]] = {}
    at: dict[int, int] = {}
    slot: dict[int, int] = {}
    bad: set[int] = set()
    stack: list[int] = []
    for event in page.events:
        token = texts[-1 - event] if event < 0 else page.token[event]
        c = classes.get(token)
        if c is None or c in bad:
            continue
        k, first = at.get(c, 0), order.setdefault(c, [])
        if k == 0:
            while stack and stack[-1] in bad:
                stack.pop()
            gap = xxhash.xxh64_intdigest(f"{stack[-1]}/{at[stack[-1]]}") if stack else 0
            if slot.setdefault(c, gap) != gap:
                bad.add(c)
                continue
            stack.append(c)
        else:
            while stack[-1] != c:  # opened inside this round and not done: they overlap
                bad.add(stack.pop())
        if len(first) < sizes[c]:
            first.append(token)
        elif first[k] != token:
            bad.add(c)
        at[c] = (k + 1) % sizes[c]
        if at[c] == 0 and stack and stack[-1] == c:
            stack.pop()
    bad |= set(stack)
    return {c: (_signed(xxhash.xxh64_intdigest(np.array(first, np.uint64).tobytes())), _signed(slot.get(c, 0)), c not in bad and len(set(first)) == sizes[c]) for c, first in order.items()}


class Template:
    """A host's members as dictionaries."""

    def __init__(self, members: list[dict] | None):
        self.classes = {m["token"] & _FULL: m["class"] for m in members or ()}
        self.sizes: dict[int, int] = {}
        for c in self.classes.values():
            self.sizes[c] = self.sizes.get(c, 0) + 1


def _by_host(hosts: list[str], column, known: dict[str, Template]) -> list[Template]:
    out = []
    for i, h in enumerate(hosts):
        t = known.get(h)
        if t is None:
            t = known[h] = Template(column[i].as_py())
        out.append(t)
    if len(known) > 2000:
        known.clear()
    return out


def judged(pages: DataFrame) -> DataFrame:
    """``(host, class, token, chars, whole)`` of pages ``(host, html, members)``: valid classes, and per section token the slot text it held.

    Rows of token 0 speak of a class: it is valid if it was sound, in one order and in
    one gap, in every page. Other rows speak of sections: ``chars`` of slot text in all
    pages, of a whole of ``whole`` in the pages that hold the section once.
    """

    def run(batches):
        known: dict[str, Template] = {}
        for batch in batches:
            hosts = batch.column(0).to_pylist()
            orders: dict[tuple, list] = {}
            held: dict[tuple, list] = {}
            for host, text, t in zip(hosts, batch.column(1).to_pylist(), _by_host(hosts, batch.column(2), known), strict=True):
                if not t.classes:
                    continue
                page = Page(text or "")
                texts = page.texts()
                for c, (order, gap, sound) in walk(page, texts, t.classes, t.sizes).items():
                    row = orders.setdefault((host, c), [order, order, gap, gap, True])
                    row[:] = min(row[0], order), max(row[1], order), min(row[2], gap), max(row[3], gap), row[4] and sound
                size = page.held(slot_blocks(page, texts, t.classes))
                for p in range(1, len(size)):
                    c = t.classes.get(page.token[p])
                    if c is not None and page.section[p] == p:
                        row = held.setdefault((host, c, page.token[p]), [0, 0, True, page.depth[p]])
                        row[:] = row[0] + size[p], row[1] + size[0], row[2] and page.count[p] == 1, row[3]
            rows = [(h, c, 0, 0, 0, True, 0, *v) for (h, c), v in orders.items()]
            rows += [(h, c, _signed(tok), *v, 0, 0, 0, 0, True) for (h, c, tok), v in held.items()]
            kinds = (pa.string(), *[pa.int64()] * 4, pa.bool_(), *[pa.int64()] * 5, pa.bool_())
            names = "host class token chars whole once depth o1 o2 g1 g2 sound".split()
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names=names)

    schema = "host string, class long, token long, chars long, whole long, once boolean, depth long, o1 long, o2 long, g1 long, g2 long, sound boolean"
    rows = pages.select("host", "html", "members").mapInArrow(run, schema)
    return rows.groupBy("host", "class", "token").agg(
        F.sum("chars").alias("chars"), F.sum("whole").alias("whole"), F.min("once").alias("once"), F.max("depth").alias("depth"),
        ((F.min("o1") == F.max("o2")) & (F.min("g1") == F.max("g2")) & F.min("sound")).alias("valid"),
    )


def slot_blocks(page: Page, texts: list[int], classes: dict[int, int]) -> list[bool]:
    """Which blocks are slot text to judge a place by: no template text, and not all links (a menu)."""
    return [t not in classes and not links for t, (_, _, links) in zip(texts, page.blocks, strict=True)]


def templates(members: DataFrame, verdicts: DataFrame) -> DataFrame:
    """``(host, members, article)``: the valid classes of each host, and the innermost of their sections that held all slot text."""
    valid = members.join(verdicts.where("token = 0 and valid").select("host", "class"), ["host", "class"])
    whole = verdicts.where("token <> 0 and once and chars = whole and whole > 0").select("host", "class", "token", "depth")
    best = whole.join(valid, ["host", "class", "token"]).groupBy("host").agg(F.max_by("token", F.struct("depth", "token")).alias("article"))
    return packed(valid.select("host", "token", "class")).join(best, "host", "left")


# -------------------------------------------------------------------- extraction


def article_of(page: Page, texts: list[int], template: Template, article: int | None) -> tuple[int, bool]:
    """The place of the page's article, and whether its markup names it as one."""
    slots = slot_blocks(page, texts, template.classes)
    size = page.held([True] * len(slots))
    named = [p for p in range(1, len(size)) if page.names[p] in ARTICLES and not page.inside[p] and size[p] and not page.clutter[p]]
    if len(named) == 1 and page.count[named[0]] == 1:
        return named[0], True
    size = page.held(slots)
    whole = [p for p in range(len(size)) if page.count[p] == 1 and page.section[p] == p and size[p] == size[0]]
    if article is not None:
        for p in whole:
            if page.token[p] == article:
                return p, False
    return (whole[-1] if whole and size[0] else 0), False


def extract_text(text: str, template: Template, article: int | None = None) -> str:
    """Slot text of the article. An <article> or <main> is all slot; elsewhere template text goes, unless it were more than COPY_SHARE of what is there."""
    page = Page(text)
    texts = page.texts()
    place, named = article_of(page, texts, template, article)
    inside = page.within(place)
    mine = [(t, b) for t, (p, b, _) in zip(texts, page.blocks, strict=True) if inside[p]]
    slots = [b for t, b in mine if t not in template.classes]
    lost = sum(len(b) for _, b in mine) - sum(map(len, slots))
    return "\n\n".join(slots if not named and lost <= COPY_SHARE * sum(len(b) for _, b in mine) else [b for _, b in mine])


def placed(rows: DataFrame, known: DataFrame, broadcast_hosts: int = BROADCAST_HOSTS) -> DataFrame:
    """Pages ``(page_id, url, html, host)`` with what is known of their host. A host's pages never meet in one task."""
    known = common.checkpointed(known)
    hosts, tokens = known.agg(F.count("*"), F.coalesce(F.sum(F.size("members")), F.lit(0))).first()
    if hosts <= broadcast_hosts and tokens <= BROADCAST_TOKENS:
        return rows.join(F.broadcast(known), "host", "left")  # counted
    spread = known.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    return rows.withColumn("_salt", F.pmod(F.xxhash64("page_id", "url"), F.lit(SALTS)).cast("int")).join(spread, ["host", "_salt"], "left").drop("_salt")


def main_text(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", broadcast_hosts: int = BROADCAST_HOSTS, least: int = LEAST_PAGES) -> DataFrame:
    """``(page_id, url, text, n_chars)``, one row per input row.

    Null or empty html gives an empty text, and so does a page without text. Pages
    without a usable url share the host of no name. A host of fewer than ``least``
    different pages has no template: its pages are judged one by one. Repeated rows
    and ids are kept as they are; other columns are left out.
    """
    rows = pages.select(F.col(id_col).alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html"))

    @F.pandas_udf("string")
    def host(urls):
        return urls.map(host_of)

    hosted = rows.withColumn("host", host(F.coalesce("url", F.lit(""))))
    found = common.checkpointed(vectors(rows))  # one row per token of a host, as folded
    distinct = hosted.select("host", F.xxhash64("html").alias("h")).distinct().groupBy("host").agg(F.count("*").alias("distinct"))
    members = common.checkpointed(candidates(found, distinct, least=least))
    verdicts = common.checkpointed(judged(placed(hosted, packed(members), broadcast_hosts)))
    known = templates(members, verdicts)

    def run(batches):
        cache: dict[str, Template] = {}
        for batch in batches:
            hosts, articles = batch.column(2).to_pylist(), batch.column(5).to_pylist()
            texts = [extract_text(p or "", t, None if a is None else a & _FULL) for p, t, a in zip(batch.column(3).to_pylist(), _by_host(hosts, batch.column(4), cache), articles, strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64())], names=["page_id", "url", "text", "n_chars"])

    joined = placed(hosted, known, broadcast_hosts).select("page_id", "url", "host", "html", "members", "article")
    kind = rows.schema["page_id"].dataType.simpleString()
    return joined.mapInArrow(run, f"page_id {kind}, url string, text string, n_chars long")
