"""Main text of web pages by wrappers: union-free regular expressions over tags, inferred per host.

A page is read as a tree of block elements. Inside an element, neighbouring children of one label fold into
a repeated group (also groups of two or three), inline markup and text fold into a text slot. Aligning
the trees of a host's pages turns what only some have into optional groups, and texts that differ into slots;
the others stay constant. The outcome is one tree per host, and each page is read along it, without what is
constant: under its own main elements if it has some, else whole.
"""

from __future__ import annotations

import functools
import hashlib
import html as entities
import json
import re
import sys
from bisect import bisect_left
from collections import Counter
from collections.abc import Iterator
from contextlib import contextmanager
from urllib.parse import urlsplit

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written

NAME = re.compile(r"[a-zA-Z][^\s/>]*")
COMMENT_END = re.compile(r"--!?>")
UNQUOTED = re.compile(r"[^>\"']*")
BROKEN = re.compile(r"[^<>]*>?")
# Fixed value: elements whose content is no markup.
RAW = {name: re.compile(rf"</{name}\s*>", re.I) for name in "script style noscript iframe textarea title".split()}
MARK = re.compile(r"""\b(class|id|role|itemprop|hidden|aria-hidden)(?:\s*=\s*("[^"]*"|'[^']*'|[^\s"'>]+))?""", re.I)
# Element names of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var".split())
#: Elements inside a text like inline markup, whose end tags close what is open in them; those of HIDDEN show no text.
EMBEDDED = frozenset("math object audio video mi mn mo ms mtext mspace mrow mfrac msqrt mroot mstyle merror mpadded mphantom menclose msub msup msubsup munder mover munderover mmultiscripts mprescripts mtable mtr mtd maction semantics".split())
HIDDEN = frozenset("svg select canvas template annotation annotation-xml".split())
FOREIGN = frozenset("svg math".split())
UNFIT = frozenset("svg math select".split())  # a block inside shows that their end tag is missing
CLOSES_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section summary table ul".split())
SIBLINGS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}, "thead": {"tr", "td", "th"}, "tbody": {"thead", "tbody", "tr", "td", "th"}, "tfoot": {"tbody", "tr", "td", "th"}}
LEFT = frozenset("p svg math select li dt dd tr td th option thead tbody".split())
SCOPES = frozenset("ul ol dl table div article section main aside nav body html form td th menu foreignobject template object".split())
APART = frozenset("nav aside footer header form button dialog menu fieldset input head".split())
#: Words of class, id and role values that mark what is not content, and what is.
NOISE = frozenset("ad ads advert adverts advertisement advertising adsense banner sponsor sponsored promo promotion promoted sidebar side aside menu nav navbar navigation breadcrumb breadcrumbs crumbs footer header masthead cookie cookies consent gdpr notice notices alert popup modal overlay newsletter subscribe subscription signup login share sharing social related recommended comment comments commentlist reply replies respond disqus discussion widget widgets pagination pager toolbar toc search form complementary contentinfo".split())
OTHER = frozenset("ad ads advert adverts advertisement advertising adsense sponsor sponsored promoted related recommended comment comments commentlist reply replies respond disqus discussion widget widgets".split())
BESIDE = frozenset("nav aside footer menu button".split())
LAYOUT_FIRST = frozenset("has no with without is hide show".split())
LAYOUT_LAST = frozenset("layout fixed open opened closed collapsed expanded enabled disabled visible".split())
MAIN = frozenset("main article articlebody".split())
SLOT, TAB, SAME = "#", "\t", "="
#: What is equal on so many different pages, and differs on none that has it, belongs to the template; in a main part it
#: takes MAIN_PAGES.
TEMPLATE_PAGES, MAIN_PAGES = 3, 8
#: Elements may lie so deep in each other. Deeper ones are dissolved into the one they lie in, their texts staying blocks of
#: their own; those whose kind differs from that of the element around them may go twice as deep.
DEPTH = 150


def tokens(page: str) -> Iterator[tuple[str, str, str]]:
    """(kind, name, rest) of a page: "text" with the text as rest, "open" with attributes as rest, "close".

    Time is linear in the page, whatever is left open: a tag whose quote or bracket is never closed ends at the next
    bracket, and where a search for an end failed once it is not taken up again.
    """
    at, end, dead = 0, len(page), set()
    while at < end:
        lt = page.find("<", at)
        if lt < 0:
            yield "text", "", page[at:]
            return
        if lt > at:
            yield "text", "", page[at:lt]
        if page.startswith("<!--", lt):
            m = COMMENT_END.search(page, lt + 4)
            at = m.end() if m else end
            continue
        if page[lt + 1 : lt + 2] in ("!", "?"):
            gt = page.find(">", lt)
            at = gt + 1 if gt >= 0 else end
            continue
        closing = page[lt + 1 : lt + 2] == "/"
        name = NAME.match(page, lt + 1 + closing)
        if name is None:
            if closing:
                at = BROKEN.match(page, lt + 1).end()
            else:
                yield "text", "", "<"
                at = lt + 1
            continue
        gt, quotes = UNQUOTED.match(page, name.end()).end(), []
        while gt < end and page[gt] != ">":
            if gt in dead:
                gt = end
                break
            quotes.append(gt)
            gt = page.find(page[gt], gt + 1)
            gt = UNQUOTED.match(page, gt + 1).end() if gt >= 0 else end
        if gt >= end:
            dead.update(quotes)
            at = BROKEN.match(page, lt + 1).end()
            continue
        tag, at = name[0].lower(), gt + 1
        if closing:
            yield "close", tag, ""
        elif tag in RAW:
            m = RAW[tag].search(page, at)
            at = m.end() if m else end
        else:
            yield "open", tag, page[name.end() : gt]


def described(tag: str, rest: str) -> tuple[str, str]:
    """Label and kind of an element; those of long tags are not remembered."""
    return _described(tag, rest) if len(rest) < 400 else _described.__wrapped__(tag, rest)


@functools.lru_cache(10_000)
def _described(tag: str, rest: str) -> tuple[str, str]:
    """Label and kind of an element. The label has the tag and the first words of its class, id, role and itemprop,
    figures as 0, then hidden marks and the kind, which is told from all words as they are written."""
    marks, flags = [], set()
    if "=" in rest or "hidden" in rest.lower():
        for name, value in MARK.findall(rest):
            name, value = name.lower(), value.strip("\"'")
            if name in ("hidden", "aria-hidden"):
                if name == "hidden" or value.lower() == "true":
                    flags.add("!hidden")
            else:
                marks += [("@" if name in ("role", "itemprop") else ".", w) for w in value.split()]
    kind = kind_of(tag, marks, bool(flags))
    words = {s + re.sub("[0-9]+", "0", w.lower()) for s, w in marks}
    return tag + "".join(sorted(words | flags)[:12]) + (TAB + kind if kind != "plain" else ""), kind


def kind_of(tag: str, marks: list[tuple[str, str]], hidden: bool) -> str:
    """Of an element: hidden; main; apart (form or dialog, which can hold the whole page); other (texts beside the
    main one, such as comments); noise (what else is not content); or plain."""
    if tag in HIDDEN or tag == "head" or hidden:
        return "hidden"
    parts = {p for _, w in marks for p in parts_of(w)}
    if tag in ("article", "main") or any(s == "@" and w.lower() in MAIN for s, w in marks):
        return "other" if parts & {"comment", "comments", "reply"} or tag == "article" and "related" in parts else "main"
    if tag in BESIDE or parts & OTHER:
        return "other"
    if parts & NOISE:
        return "noise"
    return "apart" if tag in ("form", "dialog") else "noise" if tag in APART else "plain"


def parts_of(word: str) -> list[str]:
    """A class or id and its parts; of words such as has-sidebar or header-fixed, which tell how a page is laid out, no parts."""
    parts = [p.lower() for p in re.split(r"[-_:.@!]+|(?<=[a-z0-9])(?=[A-Z])|(?<=[A-Z])(?=[A-Z][a-z])", word)]
    word = word.lower()
    return [word] if len(parts) > 1 and (parts[0] in LAYOUT_FIRST or parts[-1] in LAYOUT_LAST) else [word, *parts]


class Node:
    """home: the element that takes what stands in this one, itself unless it is dissolved."""

    __slots__ = ("tag", "label", "kind", "children", "sign", "home", "depth")

    def __init__(self, tag: str, rest: str = ""):
        self.tag, self.children, self.sign, self.home, self.depth = tag, [], None, self, 0
        self.label, self.kind = described(tag, rest)

    def part(self) -> None:
        """End the text before: a rule stands for the border of a dissolved block."""
        if not (self.children and isinstance(self.children[-1], Node) and self.children[-1].tag == "hr"):
            self.children.append(Node("hr"))


class _Open:
    """The open elements of a page, and how many of each name are open at all, since the last scope and since the last
    element that is no inline markup: what no search can find is not searched for."""

    def __init__(self, root: Node):
        self.stack, self.all = [root], Counter()
        self.scopes, self.blocks = [Counter()], [None]

    def push(self, node: Node) -> None:
        tag = node.tag
        self.stack.append(node)
        if tag in INLINE:
            if self.blocks[-1] is None:
                self.blocks[-1] = Counter()
            self.blocks[-1][tag] += 1
            return
        self.all[tag] += 1
        self.blocks.append(None)
        if tag in LEFT:
            self.scopes[-1][tag] += 1
        if tag in SCOPES:
            self.scopes.append(Counter())

    def cut(self, at: int) -> None:
        while len(self.stack) > at:
            tag = self.stack.pop().tag
            if tag in INLINE:
                self.blocks[-1][tag] -= 1
                continue
            self.all[tag] -= 1
            self.blocks.pop()
            if tag in SCOPES:
                self.scopes.pop()
            if tag in LEFT:
                self.scopes[-1][tag] -= 1

    def leave(self, tags: set[str] | frozenset[str]) -> bool:
        """Close the last element of these names up to the last scope."""
        here = self.scopes[-1]
        if not (tags & SCOPES) and not any(here.get(t) for t in tags):
            return False
        for at in range(len(self.stack) - 1, 0, -1):
            if self.stack[at].tag in tags:
                self.cut(at)
                return True
            if self.stack[at].tag in SCOPES:
                return False
        return False

    def close(self, tag: str) -> None:
        """An end tag; that of inline markup closes nothing beyond the block it stands in."""
        if self.stack[-1].tag == tag and len(self.stack) > 1:
            self.cut(len(self.stack) - 1)
            return
        if not ((self.blocks[-1] or {}) if tag in INLINE else self.all).get(tag):
            return
        for at in range(len(self.stack) - 1, 0, -1):
            if self.stack[at].tag == tag:
                self.cut(at)
                return


def parsed(page: str | None) -> Node:
    """The tree of a page; children are nodes and strings (texts as they stand, a break being white space)."""
    root = Node("html")
    now = _Open(root)
    for what, tag, rest in tokens(page or ""):
        top = now.stack[-1]
        if what == "text":
            top.home.children.append(rest)
            continue
        if what == "close":
            now.close(tag)
            if now.stack[-1] is not top and now.stack[-1].home is top.home:
                top.home.part()
            continue
        if tag in ("html", "body"):
            continue
        if tag in CLOSES_P:
            now.leave({"p"})
            while now.leave(UNFIT):
                pass
        if tag in SIBLINGS:
            now.leave(SIBLINGS[tag])
        home = now.stack[-1].home
        if tag in ("br", "wbr"):
            home.children.append("\n" if tag == "br" else "")
            continue
        node = Node(tag, rest)
        node.depth = home.depth + 1
        if node.depth > 2 * DEPTH or node.depth > DEPTH and (node.kind == home.kind or node.kind == "plain"):
            node.home = home
            if is_block(node):
                home.part()
        else:
            home.children.append(node)
        if tag in VOID or rest.endswith("/") and (tag in INLINE or tag in EMBEDDED or tag in FOREIGN or any(now.all[x] for x in FOREIGN)):
            continue
        now.push(node)
    return root


def is_block(n: Node) -> bool:
    """Inline and embedded elements without marks of noise or main parts are markup inside a text."""
    return n.kind != "plain" or n.tag not in INLINE and n.tag not in EMBEDDED


def flat(n: Node) -> list:
    """Children of an element with inline markup dissolved."""
    out: list = []
    for c in n.children:
        if isinstance(c, str) or is_block(c):
            out.append(c)
        else:
            out.extend(flat(c))
    return out


def digest(text: str) -> str:
    return hashlib.blake2b(" ".join(text.split()).encode("utf-8", "replace"), digest_size=6).hexdigest()


def sign_of(n: Node) -> str:
    """Digest of all that an element shows, its texts and the elements in it."""
    if n.sign is None:
        n.sign = digest("".join(c if isinstance(c, str) else f"\0{c.label}\0{sign_of(c)}\0" for c in flat(n) if isinstance(c, str) or c.tag not in HIDDEN))
    return n.sign


# A wrapper node is [label, children, constant]; a child is [group, many, optional], a group being a list of wrapper
# nodes. A constant is [digest of what the element or text shows, digests of some pages that have it], or null where pages differ.
def wrapper_of(n: Node, page: str | None = None) -> list:
    page = page or sign_of(n)
    items: list = []
    for c in flat(n):
        if isinstance(c, str):
            if items and items[-1][0] == SLOT:
                items[-1][2].append(c)
            elif c.strip():
                items.append([SLOT, [], [c]])
        elif c.tag not in HIDDEN:
            items.append(wrapper_of(c, page))
    for x in items:
        if x[0] == SLOT:
            x[2] = [digest("".join(x[2])), [page]]
    return [n.label, folded([[[x], False, False] for x in items]), [sign_of(n), [page]]]


def met(a: list | None, b: list | None) -> list | None:
    """The constant of two nodes."""
    return [a[0], sorted({*a[1], *b[1]})[:MAIN_PAGES]] if a and b and a[0] == b[0] else None


def _signs(group: list) -> list[str]:
    return [x[0] for x in group]


def folded(children: list) -> list:
    """Repeated neighbours, alone or in groups of up to three, become one group that may repeat."""
    for period in (1, 2, 3):
        out: list = []
        for c in children:
            out.append(c)
            while len(out) >= 2 * period:
                last, before = out[-period:], out[-2 * period : -period]
                if period > 1 and (any(x[1] or x[2] or len(x[0]) > 1 for x in last + before) or len({x[0][0][0] for x in last}) == 1):
                    break
                if [_signs(x[0]) for x in last] != [_signs(x[0]) for x in before]:
                    break
                if period == 1:
                    group = [aligned(p, q) for p, q in zip(before[0][0], last[0][0])]
                    out[-2:] = [[group, True, before[0][2] and last[0][2]]]
                else:
                    out[-2 * period :] = [[[aligned(p[0][0], q[0][0]) for p, q in zip(before, last)], True, False]]
                    break
            if period > 1 and len(out) > period and out[-period - 1][1] and len(out[-period - 1][0]) == period:
                last = out[-period:]
                if all(not x[1] and len(x[0]) == 1 for x in last) and [x[0][0][0] for x in last] == _signs(out[-period - 1][0]):
                    out[-period - 1][0] = [aligned(p, q[0][0]) for p, q in zip(out[-period - 1][0], last)]
                    del out[-period:]
        children = out
    return children


def matching(a: list, b: list) -> list[tuple[int, int]]:
    """Places of a common subsequence of two lists, in order: a longest one, or, between lists so long that a table of
    all their places would be large, one through the items that each has once."""
    low = 0
    while low < min(len(a), len(b)) and a[low] == b[low]:
        low += 1
    high = 0
    while high < min(len(a), len(b)) - low and a[-1 - high] == b[-1 - high]:
        high += 1
    head, tail = [(i, i) for i in range(low)], [(len(a) - i, len(b) - i) for i in range(high, 0, -1)]
    x, y = a[low : len(a) - high], b[low : len(b) - high]
    if not x or not y:
        return head + tail
    if len(x) * len(y) > 40_000:
        once = Counter(y)
        place = {v: j for j, v in enumerate(y)}
        times = Counter(x)
        least: list[int] = []  # a longest rising sequence of places in y
        ends: list[tuple[int, int]] = []
        before: dict[int, int | None] = {}
        for i, v in enumerate(x):
            if once[v] == 1 and times[v] == 1:
                k = bisect_left(least, place[v])
                least[k:] = [place[v]] if k == len(least) else [place[v], *least[k + 1 :]]
                ends[k : k + 1] = [(i, place[v])]
                before[i] = ends[k - 1][0] if k else None
        chain, i = [], ends[-1][0] if ends else None
        while i is not None:
            chain.append((i, place[x[i]]))
            i = before[i]
        middle, i, j = [], 0, 0
        for p, q in [*reversed(chain), (len(x), len(y))]:
            if chain and (p - i) * (q - j) <= 40_000:
                middle += [(i + u, j + v) for u, v in matching(x[i:p], y[j:q])]
            if p < len(x):
                middle.append((p, q))
            i, j = p + 1, q + 1
    else:
        best = [[0] * (len(y) + 1) for _ in range(len(x) + 1)]
        for i in range(len(x) - 1, -1, -1):
            for j in range(len(y) - 1, -1, -1):
                best[i][j] = best[i + 1][j + 1] + 1 if x[i] == y[j] else max(best[i + 1][j], best[i][j + 1])
        middle, i, j = [], 0, 0
        while i < len(x) and j < len(y):
            if x[i] == y[j]:
                middle.append((i, j))
                i, j = i + 1, j + 1
            elif best[i + 1][j] >= best[i][j + 1]:
                i += 1
            else:
                j += 1
    return head + [(i + low, j + low) for i, j in middle] + tail


def aligned(a: list, b: list) -> list:
    """The wrapper of both of two nodes with one label: matching groups meet, the rest becomes optional, and what
    they show stays constant only if it is the same."""
    if a == b:
        return a
    x, y = a[1], b[1]
    pairs = matching([tuple(_signs(c[0])) for c in x], [tuple(_signs(c[0])) for c in y])
    out, i, j = [], 0, 0
    for p, q in [*pairs, (len(x), len(y))]:
        out += [[c[0], c[1], True] for c in x[i:p]] + [[c[0], c[1], True] for c in y[j:q]]
        if p < len(x) and q < len(y):
            out.append([[aligned(u, v) for u, v in zip(x[p][0], y[q][0])], x[p][1] or y[q][1], x[p][2] or y[q][2]])
        i, j = p + 1, q + 1
    return [a[0], folded(out), met(a[2], b[2])]


def expression(w: list) -> str:
    """A wrapper as one line: ( )+ repeats, ( )? is optional, # is a text slot."""
    if w[0] == SLOT:
        return SLOT
    inner = []
    for group, many, optional in w[1]:
        body = " ".join(expression(g) for g in group)
        inner.append(f"({body}){'*' if many and optional else '+' if many else '?'}" if many or optional else body)
    return f"<{w[0].split(TAB)[0]}>{' '.join(inner)}</>"


def content_slots(w: list) -> dict:
    """The wrapper as nested dicts by label, with "#" where there is a text slot; "=" has the digests of what
    is the template's there, of elements in their own dict and of texts in that of "#", with the number of pages
    that were seen to have it."""
    out: dict = {}
    for group, _, _ in w[1]:
        for g in group:
            at = out.setdefault(g[0], {})
            if g[2] and len(g[2][1]) >= TEMPLATE_PAGES:
                at.setdefault(SAME, {})[g[2][0]] = len(g[2][1])
            if g[0] != SLOT:
                _join(at, content_slots(g))
    return out


def _join(a: dict, b: dict) -> None:
    for k, v in b.items():
        if isinstance(v, int):
            a[k] = max(a.get(k, 0), v)
        else:
            _join(a.setdefault(k, {}), v)


def has_main(n: Node, through: frozenset[str]) -> bool:
    """Whether a main element lies below n, in elements of the given kinds alone."""
    return any(not isinstance(c, str) and (c.kind == "main" or c.kind in through and has_main(c, through)) for c in n.children)


# Kinds of elements that are looked through for main elements, the first that finds some.
WAYS = [frozenset(("plain", "apart")), frozenset(("plain", "apart", "noise")), frozenset(("plain", "apart", "noise", "other"))]


def main_text(root: Node, slots: dict) -> str:
    """The texts of a page's content slots, a block each, read along the wrapper.

    Content are the slots under the page's own article or main elements, which may lie in forms or in what its
    name makes noise, or, in a page without, all slots; what the wrapper holds as constant is no slot (in a main
    part it takes more pages to tell). Elements that are navigation, notices, adverts, forms, comments and the like are
    left out. Where that leaves no text, constant texts, forms, and then articles beside the main part are read.
    """
    for through in WAYS[:2]:
        if has_main(root, through):
            text = read_slots(root, slots, through, False, False, MAIN_PAGES) or read_slots(root, slots, through, False, False) or read_slots(root, slots, through, False, True)
            break
    else:
        text = read_slots(root, slots, frozenset(), True, False, TEMPLATE_PAGES) or read_slots(root, slots, frozenset(), True, False) or read_slots(root, slots, frozenset(), True, True)
    return text or (read_slots(root, slots, WAYS[2], False, False) if has_main(root, WAYS[2]) else "")


def read_slots(root: Node, slots: dict, through: frozenset[str], whole: bool, forms: bool, pages: int = 0) -> str:
    """pages: constants of so many pages are left out (0: none)."""
    blocks: list[str] = []

    def read(n: Node, at: dict, inside: bool) -> None:
        run: list[str] = []

        def close() -> None:
            if inside and SLOT in at and (text := " ".join(entities.unescape("".join(run)).split())):
                if not (pages and (same := at[SLOT].get(SAME)) and same.get(digest("".join(run)), 0) >= pages):
                    blocks.append(text)
            run.clear()

        for c in flat(n):
            if isinstance(c, str):
                run.append(c)
                continue
            content = c.kind in ("plain", "main") or forms and c.kind == "apart"
            if not content and (c.tag in INLINE or c.tag in EMBEDDED or c.tag in HIDDEN):
                continue  # inline noise goes and does not part a block
            close()
            if pages and (inside or whole) and (same := at.get(c.label, {}).get(SAME)) and same.get(sign_of(c), 0) >= pages:
                continue
            if c.label in at and (content or c.kind in through and has_main(c, through)):
                read(c, at[c.label], content and (inside or c.kind == "main"))
        close()

    read(root, slots, whole)
    return "\n\n".join(blocks)


def host_of(url: str | None) -> str:
    try:
        return (urlsplit((url or "").strip()).hostname or "").lower()
    except ValueError:
        return ""


@contextmanager
def deep_trees() -> Iterator[None]:
    """Let functions call each other as deep as trees go (DEPTH bounds them)."""
    before = sys.getrecursionlimit()
    sys.setrecursionlimit(max(before, 1000 + 40 * DEPTH))
    try:
        yield
    finally:
        sys.setrecursionlimit(before)


def merged(some: DataFrame, *keys: str) -> DataFrame:
    """One wrapper for each value of the keys (host first): rows stream by in order, one wrapper is held at a time."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        now, whole = None, None
        row = lambda: pd.DataFrame({"host": [now[0]], "wrapper": [json.dumps(whole)]}, dtype=object)
        with deep_trees():
            for b in batches:
                for *key, text in zip(*[b[k] for k in keys], b["wrapper"]):
                    w = json.loads(text)
                    if key == now:
                        whole = aligned(whole, w)
                        continue
                    if now is not None:
                        yield row()
                    now, whole = key, w
            if now is not None:
                yield row()

    return some.repartition(*keys).sortWithinPartitions(*keys, "wrapper").mapInPandas(run, "host string, wrapper string")


def wrappers(pages: DataFrame, parts: int = 32, flush_chars: int = 32 << 20) -> DataFrame:
    """host, wrapper (JSON): from every page. Tasks align what they read and pass it on after so many characters; then parts
    of a host are aligned, then hosts."""

    def infer(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        known: dict[str, list] = {}
        read = 0

        def out() -> pd.DataFrame:
            return pd.DataFrame({"host": list(known), "wrapper": [json.dumps(w) for w in known.values()]}, dtype=object)

        with deep_trees():
            for b in batches:
                for url, page in zip(b["url"], b["html"]):
                    host, w = host_of(url), wrapper_of(parsed(page))
                    known[host] = aligned(known[host], w) if host in known else w
                    read += len(page or "")
                    if read > flush_chars:
                        yield out()
                        known.clear()
                        read = 0
            yield out()

    some = pages.select("url", "html").mapInPandas(infer, "host string, wrapper string").distinct()
    return merged(merged(some.withColumn("part", F.pmod(F.xxhash64("wrapper"), F.lit(parts))), "host", "part"), "host")


def extracted_pages(pages: DataFrame, broadcast_bytes: int = 32 << 20) -> DataFrame:
    """page_id, url, text, n_chars of every page.

    A null or empty page has an empty text. Pages without a readable host share the wrapper of the empty
    host. Repeated rows are read each. Elements of any depth are read. Wrappers go to all tasks if their size, which is
    counted, is within broadcast_bytes, and by a shuffled join else.
    """
    found = written(wrappers(pages), "wrappers")
    size = found.agg(F.sum(F.length("wrapper"))).first()[0] or 0

    def named(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield b.assign(host=[host_of(u) for u in b["url"]])

    kinds = {f.name: f.dataType.simpleString() for f in pages.schema}
    rows = pages.select("page_id", "url", "html")
    if size <= broadcast_bytes:
        sent = pages.sparkSession.sparkContext.broadcast({r["host"]: r["wrapper"] for r in found.toLocalIterator()})
    else:
        sent = None
        rows = rows.mapInPandas(named, f"page_id {kinds['page_id']}, url string, html string, host string").join(found, "host").select("page_id", "url", "html", "wrapper")

    def read(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        slots: dict[str, dict] = {}

        def slots_of(wrapper: str) -> dict:
            if wrapper not in slots:
                if len(slots) > 5000:
                    slots.clear()
                slots[wrapper] = content_slots(json.loads(wrapper))
            return slots[wrapper]

        for b in batches:
            of = b["wrapper"] if sent is None else [sent.value[host_of(u)] for u in b["url"]]
            with deep_trees():
                texts = [main_text(parsed(p), slots_of(w)) for p, w in zip(b["html"], of)]
            yield pd.DataFrame({"page_id": b["page_id"], "url": b["url"], "text": texts, "n_chars": [len(t) for t in texts]})

    return rows.mapInPandas(read, f"page_id {kinds['page_id']}, url string, text string, n_chars long")
