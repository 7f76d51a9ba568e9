"""Main text of web pages by wrapper induction over the pages of a host.

A page is a tree of block elements; consecutive paragraphs, list items, rows or cells with equal labels are one node (an iterator). The
wrapper of a host starts as the tree of one of its pages, and further pages are merged into it: simple tree matching finds the largest
set of order-preserving pairs of nodes with equal labels, and nodes without a partner are inserted beside their aligned neighbours. Then
every page of the host is aligned with the wrapper, which gives each of its nodes the number of a wrapper node, its slot; nodes that
remain alone get a slot from their parent's and their label. Over all pages of the host are counted, by slot, the blocks of text that
recur there and the regions of running text: how many there are, how many of them differ, and how much text they hold. Pages with equal
slots and blocks count once, so exact copies give no support.

A block is template if SUPPORT pages, and a share SHARE of those with its slot, hold it; a box whose own blocks are all template goes.
Of what varies, the region whose slot holds the most text over the host's pages is the page's main region; others are content if their
slot varies from page to page and holds enough text beside the main one: a share VOLUME, or PROSE where the text stands in paragraphs,
or any under a heading. So a page with a short article is judged by where the articles of its host stand. Lists of links are no content,
nor are elements that their tag, role or class names as navigation, advert, form, notice, comments and the like.

Marks of an article (or main part) are confirmed by the regions: where the longest region is in an article, regions outside of articles
are not content, those inside are; where it is not, articles that are teasers are not. A page of which only headings would be left is a
near copy of others, and keeps its template blocks.

Blocks are the texts between the borders of block elements, character references decoded, runs of white space one space, trimmed; a line
break is white space. Defined cases: null or empty html, or none but boilerplate, gives an empty text; a page of an unknown host, or
alone on its host, is judged by its own regions; a tag without an end is text; repeated rows get a row each; other columns are ignored.
"""

from __future__ import annotations

import json
import math
import re
from collections import defaultdict
from html import unescape

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from diversify.llm.base import checkpoint, table

#: Pages that shape the tree of a host's wrapper; all pages are counted.
SHAPES = 8
#: Least pages that hold a template block, their least share of those with its slot, and the least share of different texts of a content slot.
SUPPORT, SHARE, VARIES = 3, 0.5, 0.5
#: Least text of a content slot beside the main one, without and with paragraphs.
VOLUME, PROSE = 0.25, 0.02
#: Share of a region's characters within links from which it is a menu.
LINKS = 0.5
#: Most bytes of wrappers that are broadcast.
BROADCAST = 64_000_000
#: Mark of the slots of nodes without a partner, and shapes after which a matching starts anew, which bounds its memory.
ALONE, FORGET = 1 << 50, 100_000

# Elements by role.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title xmp iframe noembed noframes".split())
NEVER = frozenset(
    "head script style noscript template nav footer aside form button select option textarea input label fieldset iframe object embed svg math "
    "canvas audio video picture map dialog menu title link meta".split()
)
BLOCK = frozenset(
    "html body article section main div p h1 h2 h3 h4 h5 h6 ul ol li dl dt dd table thead tbody tfoot tr td th caption blockquote pre figure "
    "figcaption header footer nav aside form fieldset address hr details summary hgroup center".split()
)
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
#: Elements that are parts of the running text or list around them.
PARTS = HEADINGS | frozenset("p blockquote pre hr li dt dd thead tbody tfoot tr td th caption figcaption summary".split())
RUNNING = frozenset("p h1 h2 h3 h4 h5 h6 blockquote pre table ul ol dl figure address".split())
CLOSED_BY_P = BLOCK - frozenset("html body li dt dd tr td th thead tbody tfoot caption figcaption summary".split())
SIBLINGS = {
    "li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",),
    "thead": ("tr", "td", "th"), "tbody": ("thead", "tr", "td", "th"), "tfoot": ("tbody", "tr", "td", "th"),
}
SCOPES = {
    "li": ("ul", "ol", "menu"), "dt": ("dl",), "dd": ("dl",), "tr": ("table",), "td": ("table",), "th": ("table",), "thead": ("table",),
    "tbody": ("table",), "tfoot": ("table",), "option": ("select",),
}
P_SCOPES = ("table", "button", "td", "th", "caption", "object")
ROLES = frozenset("navigation banner contentinfo complementary search dialog alert alertdialog form menu menubar toolbar".split())
NAMES = frozenset(
    "ad ads adv advert adverts advertisement advertising adsense banner banners sponsor sponsored promo promos promotion sidebar sidebars side "
    "menu menus nav navbar navigation navi breadcrumb breadcrumbs footer foot masthead cookie cookies consent gdpr notice notices alert popup "
    "modal overlay newsletter subscribe subscription signup login share sharing social related recommended recommendations comment comments "
    "commentlist disqus respond reply replies pagination pager widget widgets toolbar skip disclaimer".split()
)

_TAG = re.compile(r"<(/?)([a-zA-Z][^\s/>]*+)")
#: The rest of a tag. Quotes count after an equals sign only, so an apostrophe elsewhere opens nothing.
_REST = re.compile(r"(?:[^>=]++|=\s*+\"[^\"]*+\"|=\s*+'[^']*+'|=)*+>")
_ATTRIBUTE = re.compile(r"(?<![^\s\"'/])([^\s=\"'/>]++)(?:\s*+=\s*+(\"[^\"]*+\"|'[^']*+'|[^\s>]++))?+")
_WORDS = re.compile(r"[a-z]+")
_CLOSE = {tag: re.compile(f"</{tag}", re.I) for tag in RAW}


class Node:
    """A block element: items are its texts (text, characters within links) and block elements in order; box the element of regions around it."""

    __slots__ = ("box", "items", "label", "never", "slot", "tag")

    def __init__(self, tag: str, label: str, never: bool, box: Node | None):
        self.tag, self.label, self.never, self.items, self.slot = tag, label, never, [], 0
        self.box = box if box is not None and tag in PARTS else self


def described(tag: str, attributes: str) -> tuple[str, bool]:
    """(label, whether tag, role, class or style say that it is no content) of an element."""
    label, never = tag, tag in NEVER
    if attributes:
        named = {k.lower(): v.strip("\"'").lower() for k, v in _ATTRIBUTE.findall(attributes)}
        names = set(_WORDS.findall(named.get("class", "") + " " + named.get("id", "")))
        if names and tag != "p" and tag not in HEADINGS:
            label = tag + "." + " ".join(sorted(names))
        if tag not in ("html", "body", "article", "main"):
            unseen = named.get("aria-hidden") == "true" or "display:none" in named.get("style", "").replace(" ", "")
            never = never or bool(names & NAMES) or named.get("role") in ROLES or unseen
        never = never or "hidden" in named
    return label, never


def parse(html: str) -> Node:
    """The block elements of a page, in time linear in its length; end tags that HTML lets be left out are supplied, stray ones ignored."""
    root = Node("#root", "#root", False, None)
    open_: list[tuple[str, bool, bool, bool, bool]] = []  # tag, whether a block, mutes, links, has a node
    places: dict[str, list[int]] = defaultdict(list)  # of the open elements of a tag
    nodes, held = [root], []
    linked = mute = links = 0

    def flush() -> None:
        nonlocal linked
        if text := " ".join("".join(held).split()):
            nodes[-1].items.append((text, linked))
        held.clear()
        linked = 0

    def add(text: str) -> None:
        nonlocal linked
        if text and not mute:
            held.append(unescape(text) if "&" in text else text)
            linked += len(text) if links else 0

    def close(tags: tuple[str, ...], within: tuple[str, ...] = ()) -> None:
        """Closes the last open one of some tags, unless an element of ``within`` stands between."""
        nonlocal mute, links
        at = max((places[t][-1] for t in tags if places[t]), default=-1)
        if at < 0 or any(places[t] and places[t][-1] > at for t in within):
            return
        while len(open_) > at:
            tag, block, mutes, link, own = open_.pop()
            places[tag].pop()
            if block:
                flush()
            mute, links = mute - mutes, links - link
            if own:
                nodes.pop()

    at, last, quoted = 0, html.rfind(">"), True
    while 0 <= (lt := html.find("<", at)) <= last:
        m = _TAG.match(html, lt)
        if m is None:
            if html.startswith("<!--", lt):
                add(html[at:lt])
                end = html.find("-->", lt + 4)
                at = end + 3 if end >= 0 else len(html)
            elif html[lt + 1] in "!?":
                add(html[at:lt])
                at = html.find(">", lt) + 1
            else:
                add(html[at : lt + 1])
                at = lt + 1
            continue
        add(html[at:lt])
        # After a first tag that quotes leave without an end, quotes are not looked at, so no text is read again and again.
        rest = _REST.match(html, m.end()) if quoted else None
        quoted = rest is not None
        at = rest.end() if rest else html.find(">", m.end()) + 1
        tag, attributes = m[2].lower(), html[m.end() : at - 1]
        if m[1]:
            if tag not in VOID:
                close((tag,))
            continue
        if tag in CLOSED_BY_P:
            close(("p",), P_SCOPES)
        if tag in SIBLINGS:
            for _ in range(2):
                close(SIBLINGS[tag], SCOPES[tag])
        if tag in RAW:
            if not attributes.endswith("/"):
                end = _CLOSE[tag].search(html, at)
                at = html.find(">", end.end()) + 1 if end else len(html)
                at = at or len(html)
            continue
        if tag in ("br", "wbr"):
            add(" " if tag == "br" else "")
            continue
        block = tag in BLOCK
        if block:
            flush()
        label, never = described(tag, attributes)
        own = block and not mute and tag not in ("html", "body")
        if own:
            node = Node(tag, label, never, nodes[-1].box if len(nodes) > 1 else None)
            nodes[-1].items.append(node)
        if tag in VOID or attributes.endswith("/"):
            continue
        if own:
            nodes.append(node)
        places[tag].append(len(open_))
        open_.append((tag, block, never, tag == "a", own))
        mute, links = mute + never, links + (tag == "a")
    if at < len(html):
        add(html[at:lt] if lt >= 0 and html.startswith("<!", lt) else html[at:])
    flush()
    return root


def below(node: Node) -> list[Node]:
    return [x for x in node.items if isinstance(x, Node)]


def blocks(node: Node, inside: bool = False, outer: bool = False) -> list[tuple[str, int, Node]]:
    """(text, characters within links, element around it) of the blocks below a node, in page order.

    inside: the node stands in an article; outer: without articles below it.
    """
    out: list[tuple[str, int, Node]] = []
    todo: list[tuple] = [(node, node, inside)]
    while todo:
        x, near, within = todo.pop()
        if not isinstance(x, Node):
            out.append((*x, near))
        elif x is node or not (x.never or x.tag == "header" and not within or outer and x.tag in ("article", "main")):
            within = within or x.tag in ("article", "main")
            todo.extend((p, x, within) for p in reversed(x.items))
    return out


def digest(text: str) -> int:
    return xxhash.xxh64_intdigest(text) & 0xFFFFFFFFFFFF


# Trees for matching are lists [label, children, what they stand for]: elements of a page, or the slot of a wrapper.


def outline(root: Node) -> list:
    """The tree of a page; consecutive parts with equal labels are one node."""
    tree = ["#root", [], [root]]
    todo = [tree]
    while todo:
        group = todo.pop()
        kids = group[1]
        for c in (c for x in group[2] for c in below(x)):
            if kids and c.tag in PARTS and kids[-1][0] == c.label:
                kids[-1][2].append(c)
            else:
                kids.append([c.label, [], [c]])
        todo.extend(kids)
    return tree


def walked(tree: list) -> list[list]:
    """All nodes, parents before their children."""
    out, todo = [], [tree]
    while todo:
        out.append(todo.pop())
        todo.extend(reversed(out[-1][1]))
    return out


class Aligner:
    """Simple tree matching of pages with one tree. Equal subtrees have one shape, and sizes are kept by pairs of shapes, so what recurs is matched once."""

    def __init__(self, tree: list):
        self.tree = tree
        self._forget()

    def _forget(self) -> None:
        self.numbers: dict[tuple, int] = {}
        self.shapes: list[tuple[str, tuple[int, ...], int]] = []  # label, shapes of the children, nodes
        self.sizes: dict[tuple[int, int], int] = {}
        self.own = self.shaped(self.tree)

    def shaped(self, tree: list) -> dict[int, int]:
        """The shape of each node, by its id."""
        of: dict[int, int] = {}
        for x in reversed(walked(tree)):
            kind = x[0], tuple(of[id(c)] for c in x[1])
            if kind not in self.numbers:
                self.numbers[kind] = len(self.shapes)
                self.shapes.append((*kind, 1 + sum(self.shapes[c][2] for c in kind[1])))
            of[id(x)] = self.numbers[kind]
        return of

    def size(self, x: int, y: int) -> int:
        """Number of pairs of the largest matching of two shapes."""
        todo = [(x, y)]
        while todo:
            a, b = todo[-1]
            if (a, b) in self.sizes or self.shapes[a][0] != self.shapes[b][0]:
                self.sizes.setdefault((a, b), 0)
                todo.pop()
            elif a == b:
                self.sizes[todo.pop()] = self.shapes[a][2]
            else:
                left, right = self.shapes[a][1], self.shapes[b][1]
                of = self._by_label(right)
                if need := [(c, e) for c in set(left) for e in of[self.shapes[c][0]] if (c, e) not in self.sizes]:
                    todo.extend(need)
                else:
                    self.sizes[todo.pop()] = 1 + (int(best_row(self._rows(left, right), len(left), len(right))[-1]) if left and right else 0)
        return self.sizes[x, y]

    def _by_label(self, shapes: tuple[int, ...]) -> dict[str, list[int]]:
        out = defaultdict(list)
        for k in set(shapes):
            out[self.shapes[k][0]].append(k)
        return out

    def _rows(self, left: tuple[int, ...], right: tuple[int, ...]):
        """The weights of a left child with each right one; only shapes with equal labels are looked at."""
        kinds, at = np.unique(np.array(right, np.int64), return_inverse=True)
        number, of = {int(k): i for i, k in enumerate(kinds)}, self._by_label(right)

        def row(i: int) -> np.ndarray:
            out = np.zeros(len(kinds), np.int64)
            for k in of[self.shapes[left[i]][0]]:
                out[number[k]] = self.size(left[i], k)
            return out[at]

        return row

    def pairing(self, page: list):
        """(node, its partner in the tree or None) of all nodes of a page, parents first."""
        if len(self.shapes) > FORGET:
            self._forget()
        of = self.shaped(page)
        todo = [(page, self.tree)]
        while todo:
            x, y = todo.pop()
            yield x, y
            partner: dict[int, int] = {}
            if y is not None and x[1] and y[1]:
                left, right = tuple(of[id(c)] for c in x[1]), tuple(self.own[id(c)] for c in y[1])
                partner = {i: i for i in range(len(left))} if left == right else dict(ordered_pairs(self._rows(left, right), len(left), len(right)))
                # What stands in another order than in the tree, if a name tells it.
                free = defaultdict(list)
                for j in set(range(len(right))) - set(partner.values()):
                    free[y[1][j][0]].append(j)
                for i, c in enumerate(x[1]):
                    if i not in partner and "." in c[0] and len(free.get(c[0], ())) == 1:
                        partner[i] = free.pop(c[0])[0]
            todo.extend((c, y[1][partner[i]] if i in partner else None) for i, c in reversed(list(enumerate(x[1]))))


def _next_row(best: np.ndarray, weights: np.ndarray) -> np.ndarray:
    out = np.zeros_like(best)
    np.maximum.accumulate(np.maximum(best[1:], np.where(weights > 0, best[:-1] + weights, 0)), out=out[1:])
    return out


def best_row(rows, m: int, n: int) -> np.ndarray:
    best = np.zeros(n + 1, np.int64)
    for i in range(m):
        best = _next_row(best, rows(i))
    return best


def ordered_pairs(rows, m: int, n: int) -> list[tuple[int, int]]:
    """The heaviest set of pairs (i, j), both increasing, where rows(i) has the weights of i with each j.

    Of the table only every so many rows are kept and those between made again, so memory follows n times the root of m.
    """
    step = math.isqrt(m) + 1
    kept = [np.zeros(n + 1, np.int64)]
    for i in range(m):
        best = _next_row(kept[-1] if i % step == 0 else best, rows(i))
        if (i + 1) % step == 0:
            kept.append(best)
    out, j = [], n
    for first in range((m - 1) // step * step, -1, -step):
        table_ = [kept[first // step]]
        for i in range(first, min(first + step, m)):
            table_.append(_next_row(table_[-1], rows(i)))
        for i in range(len(table_) - 1, 0, -1):
            while j and table_[i][j] == table_[i][j - 1]:
                j -= 1
            if j and table_[i][j] > table_[i - 1][j]:
                j -= 1
                out.append((first + i - 1, j))
    return out[::-1]


def induced(pages: list[list]) -> list:
    """The wrapper's tree of some pages: that of the first one, the others merged into it; slots are numbers in page order."""
    wrapper = ["#root", [], 0]
    for page in pages:
        partner = {id(x): y for x, y in list(Aligner(wrapper).pairing(page)) if y is not None}
        for x in walked(page):  # parents first: what is inserted has a partner when its own children come
            y = partner[id(x)]
            place = {id(e): k for k, e in enumerate(y[1])}
            new: dict[int, list[list]] = defaultdict(list)
            at = -1
            for c in x[1]:
                if id(c) in partner:
                    at = max(at, place[id(partner[id(c)])])
                else:
                    partner[id(c)] = [c[0], [], 0]
                    new[at].append(partner[id(c)])
            if new:
                y[1][:] = [e for k in range(-1, len(y[1])) for e in ([y[1][k]] if k >= 0 else []) + new.get(k, [])]
    for k, x in enumerate(walked(wrapper)):
        x[2] = k
    return wrapper


def align(root: Node, known: Aligner) -> None:
    """Gives every element of a page its slot."""
    above: dict[int, int] = {}
    for x, y in known.pairing(outline(root)):
        slot = y[2] if y is not None else digest(f"{above[id(x)]}/{x[0]}") | ALONE
        for e in x[2]:
            e.slot = slot
        above.update((id(c), slot) for c in x[1])


class Region:
    """Running text of one element: the outermost article or main element around it (or none), its blocks, its slot."""

    __slots__ = ("headed", "mark", "own", "prose", "size", "slot")

    def __init__(self, mark: Node | None, own: list[tuple[str, int, Node]], slot: int):
        self.mark, self.own, self.slot = mark, own, slot
        self.size = sum(len(t) - n for t, n, _ in own)
        self.prose = any(e.tag in PARTS for _, _, e in own)
        self.headed = any(e.tag in HEADINGS and n == 0 for _, n, e in own)


def regions(root: Node) -> list[Region]:
    """The regions with running text that are no lists of links, in page order."""
    out, todo = [], [(root, None, False)]
    while todo:
        x, mark, inside = todo.pop()
        if not isinstance(x, Node):  # text outside any block
            out.append(Region(None, [(*x, root)], root.slot))
            continue
        if x.never or x.tag == "header" and not inside:
            continue
        # A main element that holds articles is only their frame.
        if x.tag == "article" and (mark is None or mark.tag == "main") or x.tag == "main" and mark is None:
            mark = x
        inside = inside or x.tag in ("article", "main")
        free = mark is None or mark.tag == "main"
        if x is not root and any(not isinstance(p, Node) or p.tag in RUNNING and not p.never for p in x.items):
            own = blocks(x, inside, free)
            if own and sum(n for _, n, _ in own) <= LINKS * sum(len(t) for t, _, _ in own):
                out.append(Region(mark, own, x.slot))
            if free:
                todo.extend((a, mark, inside) for a in reversed(marked(x)))
            continue
        todo.extend((p, mark, inside) for p in reversed(x.items) if isinstance(p, Node) or x is root)
    return out


def marked(node: Node) -> list[Node]:
    """The outermost article and main elements below a node that are no boilerplate, in page order."""
    out, todo = [], list(reversed(below(node)))
    while todo:
        x = todo.pop()
        if x.never or x.tag == "header":
            continue
        if x.tag in ("article", "main"):
            out.append(x)
        else:
            todo.extend(reversed(below(x)))
    return out


def confirmed(found: list[Region]) -> list[Region] | None:
    """The regions that are content by the marks of articles; None where no mark is borne out."""
    size: dict[int, int] = defaultdict(int)
    first: dict[int, Region] = {}
    outside = 0
    for r in found:
        n = sum(len(t) for t, _, _ in r.own)
        if r.mark is None:
            outside = max(outside, n)
        elif r.own:
            size[id(r.mark)] += n
            first.setdefault(id(r.mark), r)
    if not size:
        return None
    # A teaser begins with a link to what it is about.
    teasers = {k for k, r in first.items() if r.own[0][1] and r.own[0][1] >= len(r.own[0][0])}
    main = {k for k in size if k not in teasers}
    if main and max(size[k] for k in main) >= outside or not outside:
        chosen = main or set(size)
        return [r for r in found if r.mark is not None and id(r.mark) in chosen]
    return None


def unmarked(found: list[Region]) -> list[Region]:
    """The regions without the articles that are teasers or comments: several ones in one slot, or such as begin with a link."""
    slots = {id(r.mark): r.mark.slot for r in found if r.mark is not None}
    several = {s for s in slots.values() if list(slots.values()).count(s) > 1}
    teasers = {id(r.mark) for r in found if r.mark is not None and r.own and r.own[0][1] and r.own[0][1] >= len(r.own[0][0])}
    return [r for r in found if r.mark is None or r.mark.slot not in several and id(r.mark) not in teasers]


class Wrapper:
    """What is known of a host: the tree, template blocks by slot, and of the slots of regions (mean text, share of different ones, pages)."""

    def __init__(self, tree: str | None = None, known: str | None = None):
        at: list[list] = []
        for k, (up, label) in enumerate(json.loads(tree) if tree else []):
            at.append([label, [], k])
            if up >= 0:
                at[up][1].append(at[k])
        self.aligner = Aligner(at[0]) if at else None
        found = json.loads(known) if known else {"template": {}, "regions": {}}
        self.template = {int(k): frozenset(v) for k, v in found["template"].items()}
        self.regions = {int(k): v for k, v in found["regions"].items()}

    def is_template(self, block: tuple[str, int, Node]) -> bool:
        known = self.template.get(block[2].slot)
        return known is not None and digest(block[0]) in known

    def content(self, found: list[Region]) -> list[Region]:
        """The regions whose slots are content."""
        known = [self.regions.get(r.slot) for r in found]
        volume = [k[0] if k else r.size for k, r in zip(known, found, strict=True)]
        main = max(volume, default=0)
        out = []
        for r, k, v in zip(found, known, volume, strict=True):
            varies = not k or k[2] < SUPPORT or k[1] >= VARIES
            enough = v >= (PROSE if r.prose else VOLUME) * main or r.headed or r.own[0][2].box.tag in PARTS
            if v == main or varies and enough:
                out.append(r)
        return out


NOTHING = Wrapper()


def without_template(found: list[Region], wrapper: Wrapper) -> list[Region]:
    varies = {id(x[2].box) for r in found for x in r.own if x[2].box.tag != "#root" and not wrapper.is_template(x)}
    out = []
    for r in found:
        left = [x for x in r.own if id(x[2].box) in varies or x[2].box.tag == "#root" and not wrapper.is_template(x)]
        if left:
            out.append(Region(r.mark, left, r.slot))
    return out


def main_text(html: str | None, wrapper: Wrapper = NOTHING) -> str:
    root = parse(html or "")
    align(root, wrapper.aligner or Aligner(["#root", [], 0]))
    found = regions(root)
    left = without_template(found, wrapper)
    if all(x[2].tag in HEADINGS for r in left for x in r.own):  # a near copy
        left = found
    chosen = confirmed(left)
    if chosen is None:
        chosen = wrapper.content(unmarked(left))
    return "\n".join(t for r in chosen for t, _, _ in r.own)


def host(url: Column) -> Column:
    return F.coalesce(F.lower(F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]+)", 1)), F.lit(""))


def trees(pages: DataFrame) -> DataFrame:
    """(host, tree): the wrapper's tree of each host, from SHAPES of its pages at most: those with the least hashes of as many buckets."""
    own = pages.select("host", F.xxhash64("html").alias("h"), "html").where("host <> '' AND html IS NOT NULL")
    some = own.groupBy("host", F.pmod("h", F.lit(SHAPES)).alias("b")).agg(F.min(F.struct("h", "html")).alias("p"))
    some = some.groupBy("host").agg(F.array_sort(F.collect_list("p")).alias("p")).select("host", F.col("p.html").alias("html"))

    def made(batches):
        for batch in batches:
            out = []
            for html in batch.column("html").to_pylist():
                all_ = walked(induced([outline(parse(h)) for h in html]))
                up = {id(c): x[2] for x in all_ for c in x[1]}
                out.append(json.dumps([[up.get(id(x), -1), x[0]] for x in all_]))
            yield pa.RecordBatch.from_arrays([batch.column("host"), pa.array(out, pa.string())], ["host", "tree"])

    return some.mapInArrow(made, "host string, tree string")


def _sized(df: DataFrame, column: str) -> DataFrame:
    """``df`` to be broadcast while its column has at most BROADCAST bytes."""
    size = df.agg(F.sum(F.length(column))).first()[0] or 0
    return F.broadcast(df) if size <= BROADCAST else df


def wrappers(pages: DataFrame) -> DataFrame:
    """(host, tree, known): for each host of ``pages`` (host, html) what ``Wrapper`` reads, counted over all its pages."""
    shaped = checkpoint(trees(pages))
    joined = pages.where("html IS NOT NULL").join(_sized(shaped, "tree"), "host").select("host", "html", "tree")

    def counted(batches):
        kind = pa.list_(pa.struct([("slot", pa.int64()), ("digest", pa.int64()), ("size", pa.int64())]))
        for batch in batches:
            read: dict[str, Wrapper] = {}
            whole, parts = [], []
            for h, t in zip(batch.column("html").to_pylist(), batch.column("tree").to_pylist(), strict=True):
                if t not in read:
                    read[t] = Wrapper(t)
                root = parse(h)
                align(root, read[t].aligner)
                found = regions(root)
                held = {(x[2].slot, digest(x[0])) for r in found for x in r.own}
                rows = [{"slot": s} for s in sorted({s for s, _ in held})] + [{"slot": s, "digest": d} for s, d in sorted(held)]
                rows += [{"slot": r.slot, "digest": digest("\n".join(t for t, _, _ in r.own)), "size": r.size} for r in found]
                parts.append(rows)
                whole.append(xxhash.xxh64_intdigest(repr([tuple(x.values()) for x in rows])) - (1 << 63))
            yield pa.RecordBatch.from_arrays([batch.column("host"), pa.array(whole, pa.int64()), pa.array(parts, kind)], ["host", "whole", "parts"])

    seen = joined.mapInArrow(counted, "host string, whole long, parts array<struct<slot:long,digest:long,size:long>>")
    seen = seen.groupBy("host", "whole").agg(F.first("parts").alias("parts")).select("host", F.inline("parts"))
    region = F.col("size").isNotNull()
    texts = seen.groupBy("host", "slot", "digest", region.alias("region")).agg(F.count("*").alias("n"), F.sum("size").alias("size"))
    # A row for each slot: the pages that have it, its frequent blocks (bounded by SUPPORT), and the sums of its regions.
    often = F.when((F.col("n") >= SUPPORT) & F.col("digest").isNotNull() & ~F.col("region"), F.struct("n", "digest"))
    own = texts.groupBy("host", "slot").agg(
        F.max(F.when(F.col("digest").isNull(), F.col("n"))).alias("pages"), F.collect_list(often).alias("often"), F.sum(F.when(F.col("region"), F.col("n"))).alias("n"),
        F.count_if("region").alias("kinds"), F.sum("size").alias("size"),
    )
    common = F.transform(F.filter("often", lambda x: x["n"] >= SHARE * F.col("pages")), lambda x: x["digest"])
    own = own.select("host", "slot", "pages", "n", "kinds", "size", F.array_sort(common).alias("digests"))
    slim = own.where((F.greatest("pages", "n") >= SUPPORT) | (F.col("slot") < ALONE)).select("host", F.struct("slot", "n", "kinds", "size", "digests").alias("slot"))

    def made(batches):
        for batch in batches:
            out = []
            for rows in batch.column("slots").to_pylist():
                rows = sorted(rows, key=lambda r: r["slot"])
                template = {r["slot"]: r["digests"] for r in rows if r["digests"]}
                known = {r["slot"]: [round(r["size"] / r["n"], 3), round(r["kinds"] / r["n"], 6), r["n"]] for r in rows if r["n"]}
                out.append(json.dumps({"template": template, "regions": known}))
            yield pa.RecordBatch.from_arrays([batch.column("host"), pa.array(out, pa.string())], ["host", "known"])

    known = slim.groupBy("host").agg(F.collect_list("slot").alias("slots")).mapInArrow(made, "host string, known string")
    return shaped.join(known, "host", "left")


def extract(pages: DataFrame) -> DataFrame:
    """(page_id, url, text, n_chars) of every page."""
    pages = pages.select("page_id", "url", "html", host(F.col("url")).alias("host"))

    def made(batches):
        for batch in batches:
            read: dict[tuple, Wrapper] = {}
            out = []
            for h, *of in zip(*(batch.column(c).to_pylist() for c in ("html", "tree", "known")), strict=True):
                if tuple(of) not in read:
                    read[tuple(of)] = Wrapper(*of)
                out.append(main_text(h, read[tuple(of)]))
            n = pa.array([len(t) for t in out], pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("url"), pa.array(out, pa.string()), n], ["page_id", "url", "text", "n_chars"])

    # While all wrappers fit in BROADCAST bytes the pages are not shuffled; beyond, a host with very many pages is a skewed key that the join splits.
    known = _sized(checkpoint(wrappers(pages)), "known")
    joined = pages.join(known, "host", "left").select("page_id", "url", "html", "tree", "known")
    return joined.mapInArrow(made, f"page_id {dict(pages.dtypes)['page_id']}, url string, text string, n_chars long")


def pages_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(table(spark, sf_dir, "pages"))


QUERIES = {"op7_wrapper_induction": pages_text}
SQL: dict[str, str] = {}
