"""HTML extraction by wrapper induction.

A page is parsed into a tree of units: a block is one, and so are neighbouring paragraphs, list items and the like that look alike. The pages of a host that share the look of their body are folded into one wrapper, all of them: tasks align page by page with what they have by simple tree matching, and partial wrappers are aligned with each other in the same way. A unit of the wrapper knows on how many pages it was and whether its text was the same on all of them; such constant text is template, what varies is a slot, and so is a unit that only some pages have. A page is then aligned with its wrapper: its text is the slots, in page order, but for elements that are menus, forms, asides and the like.

Where the page marks its article or main part and that holds most of the slots' text, only those count. Class names decide between slots only: a slot whose names all say that it is an advert, a notice, reader comments or the like goes.
"""

from __future__ import annotations

import hashlib
import html
import json
import re
import sys
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import lru_cache
from math import isqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from arealex.llm.common import stored

# HTML element kinds.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = "script style noscript template svg math iframe object canvas textarea title"
BLOCK = frozenset("address article aside blockquote body center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html legend li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
PROSE = frozenset("p h1 h2 h3 h4 h5 h6 li blockquote pre td th dd dt figcaption".split())
CLOSED_BY_BLOCK = frozenset({"p"})
SELF_CLOSING = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
SCOPES = frozenset("article main section div table ul ol dl body td th blockquote aside nav footer header form".split())
#: Elements and name parts of what isn't content.
ASIDE_TAGS = frozenset("nav footer aside form button select menu dialog head script style noscript template svg math iframe object canvas textarea title input label".split())
ASIDE_WORDS = frozenset(
    "ad ads adv advert adverts advertisement banner sponsor sponsored promo cookie cookies consent gdpr notice nav navbar navigation menu breadcrumb breadcrumbs sidebar footer masthead comment comments disqus reply replies related recommended share sharing social newsletter subscribe popup modal widget login signup search pagination pager toolbar skip".split()
)
#: Name parts that say nothing about what an element is.
NEUTRAL_WORDS = frozenset("area bar block box bottom btn button col column container element foot global group head holder id inner item left link links list main outer page panel right row section site small sticky top ul wide wrap wrapper".split())
CONTENT_TAGS = frozenset("article main".split())
#: Pages that a constant text has to be on to be template: text of other blocks, and paragraphs, headings and the like outside an article, as a sentence may well be on several pages.
LEAST_PAGES, LEAST_PAGES_PROSE = 2, 4

_TAG = re.compile(r"<!--.*?(?:-->|\Z)|<(script|style|noscript|template|svg|math|iframe|object|canvas|textarea|title)\b[^>]*>.*?(?:</\1\s*>|\Z)|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:\"[^\"]*\"|'[^']*'|[^'\">])*)>|<[!?/][^>]*>", re.S | re.I)
_NAMED = re.compile(r"\b(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)


@dataclass(slots=True)
class Node:
    tag: str
    names: str = ""
    parts: list = field(default_factory=list)  # nodes and strings, in order


def parse(text: str) -> Node:
    """A tree of elements and texts. Comments, scripts and the like are left out; end tags without a start are ignored; elements that a block ends are closed by it."""
    root = Node("#root")
    stack, open_, at = [root], Counter(), 0

    def cut(k: int) -> None:
        for n in stack[k:]:
            open_[n.tag] -= 1
        del stack[k:]

    def close(tags: frozenset | set) -> None:
        if any(open_[t] > 0 for t in tags):
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].tag in tags:
                    return cut(k)
                if stack[k].tag in SCOPES:
                    return

    for m in _TAG.finditer(text):
        if m.start() > at:
            stack[-1].parts.append(text[at : m.start()])
        at = m.end()
        if m[3] is None:
            continue
        tag = m[3].lower()
        if m[2]:
            if open_[tag] > 0:
                for k in range(len(stack) - 1, 0, -1):
                    if stack[k].tag == tag:
                        cut(k)
                        break
                    if tag not in SCOPES and stack[k].tag in SCOPES and tag != "html":
                        break
            continue
        if tag in BLOCK:
            close(CLOSED_BY_BLOCK)
        if tag in SELF_CLOSING:
            close(SELF_CLOSING[tag])
        named = _NAMED.findall(m[4]) if m[4] else ()
        node = Node(tag, " ".join(a or b or c for a, b, c in named).lower())
        stack[-1].parts.append(node)
        if tag not in VOID and not m[4].rstrip().endswith("/"):
            stack.append(node)
            open_[tag] += 1
    if at < len(text):
        stack[-1].parts.append(text[at:])
    return root


@lru_cache(maxsize=8192)
def _names(text: str) -> tuple[str, ...]:
    return tuple(sorted(set(re.split(r"[^a-z]+", text)) - {""}))


def is_aside(node: Node) -> bool:
    """Whether an element is not content by its kind, or by names that all say so."""
    if node.tag in ASIDE_TAGS:
        return True
    if not node.names or node.tag in CONTENT_TAGS or node.tag in ("body", "html"):
        return False
    names = _names(node.names)
    return any(x in ASIDE_WORDS for x in names) and all(x in ASIDE_WORDS or x in NEUTRAL_WORDS for x in names)


@dataclass(slots=True)
class Unit:
    """A block, or neighbouring prose elements that look alike, on one page or (as part of a wrapper) on several: the hash of their own text if it was the same on all pages, else None; the number of pages; the units of their blocks; a hash and the size of the structure."""

    sig: str
    text: str | None
    pages: int
    kids: list
    nodes: list = field(default_factory=list)
    length: int = 0
    shape: str = ""
    size: int = 1
    seen: list = field(default_factory=list)  # of a root: the eight smallest hashes of whole pages


def _hash(text: str) -> str:
    return hashlib.blake2b(text.encode("utf-8", "surrogatepass"), digest_size=8).hexdigest()


def _shaped(u: Unit) -> None:
    u.size = 1
    for k in u.kids:
        u.size += k.size
    u.shape = _hash(u.sig + "(" + ",".join([k.shape for k in u.kids]) + ")") if u.kids else u.sig


def _signature(node: Node) -> str:
    return f"{node.tag}.{'-'.join(_names(node.names))}" if node.names else node.tag


def _own(node: Node) -> tuple[list[str], list[Node]]:
    """The text of a node outside its blocks, and its blocks; in prose elements all is text."""
    text: list[str] = []
    blocks: list[Node] = []
    prose = node.tag in PROSE
    stack = [iter(node.parts)]
    while stack:
        p = next(stack[-1], None)
        if p is None:
            stack.pop()
        elif isinstance(p, str):
            text.append(p)
        elif p.tag in BLOCK and not prose:
            blocks.append(p)
            text.append(" ")
        else:
            text.append(" " if p.tag in BLOCK or p.tag in VOID else "")
            stack.append(iter(p.parts))
    return text, blocks


def units(root: Node) -> Unit:
    """The tree of units of a page, with structure hashes."""
    top = Unit("#root", None, 1, [], [root])
    order, at = [top], 0
    while at < len(order):
        u = order[at]
        at += 1
        text: list[str] = []
        for n in u.nodes:
            own, blocks = _own(n)
            text += own
            text.append(" ")
            for c in blocks:
                sig = _signature(c)
                if c.tag in PROSE and u.kids and u.kids[-1].sig == sig:
                    u.kids[-1].nodes.append(c)
                else:
                    u.kids.append(Unit(sig, None, 1, [], [c]))
        plain = " ".join(html.unescape("".join(text)).split())
        u.text, u.length = _hash(plain) if plain else "", len(plain)
        order += u.kids
    for u in reversed(order):
        _shaped(u)
    top.seen = [_hash(",".join([u.text for u in order]))]
    return top


#: Tables of up to this many cells are filled in Python, larger ones a row at a time in numpy.
CELLS = 64
#: Weights held for a larger table, and sizes of matchings held in all; what goes is worked out again.
HELD_WEIGHTS, HELD_SIZES = 8_000_000, 1_000_000


def aligned(x: list[Unit], y: list[Unit], memo: dict, paired: bool = True) -> tuple[int, list[tuple[int, int]]]:
    """Simple tree matching of two sibling lists of any length: the size of the largest matching that keeps order and levels, and (if asked) which units it pairs. Equal structures at both ends are paired at once, which no other matching beats."""
    low, m, n = 0, len(x), len(y)
    total = 0
    head: list[tuple[int, int]] = []
    tail: list[tuple[int, int]] = []
    while low < m and low < n and x[low].shape == y[low].shape:
        total += x[low].size
        head.append((low, low))
        low += 1
    while m > low and n > low and x[m - 1].shape == y[n - 1].shape:
        m, n = m - 1, n - 1
        total += x[m].size
        tail.append((m, n))
    p, q = m - low, n - low
    if p and q:
        size, pairs = (_table if p * q <= CELLS else _rows)(x[low:m], y[low:n], memo, paired)
        total += size
        head += [(i + low, j + low) for i, j in pairs]
    return total, head + tail[::-1]


def matched(a: Unit, b: Unit, memo: dict) -> int:
    """The size of the largest matching of two trees, which depends on their structures only."""
    if a.sig != b.sig:
        return 0
    if a.shape == b.shape:
        return a.size
    if not a.kids or not b.kids:
        return 1
    key = (a.shape, b.shape)
    size = memo.get(key)
    if size is None:
        size = 1 + aligned(a.kids, b.kids, memo, False)[0]
        if len(memo) >= HELD_SIZES:
            memo.clear()
        memo[key] = size
    return size


def _table(x: list[Unit], y: list[Unit], memo: dict, paired: bool) -> tuple[int, list[tuple[int, int]]]:
    best = [[0] * (len(y) + 1) for _ in range(len(x) + 1)]
    for i in range(len(x)):
        for j in range(len(y)):
            best[i + 1][j + 1] = max(best[i][j + 1], best[i + 1][j], best[i][j] + matched(x[i], y[j], memo))
    return best[-1][-1], _back(best, len(x), 0, len(y))[0][::-1] if paired else []


def _back(best: list, i: int, least: int, j: int) -> tuple[list[tuple[int, int]], int]:
    """The pairs of rows ``least`` to ``i`` of a table, the last ones first, and the column where that ends; ``best`` begins with row ``least``."""
    pairs = []
    while i > least and j:
        if best[i - least][j] == best[i - 1 - least][j]:
            i -= 1
        elif best[i - least][j] == best[i - least][j - 1]:
            j -= 1
        else:
            i, j = i - 1, j - 1
            pairs.append((i, j))
    return pairs, j


def _rows(x: list[Unit], y: list[Unit], memo: dict, paired: bool) -> tuple[int, list[tuple[int, int]]]:
    """The same table a row at a time. Rows are held at even steps, and those between are made again on the way back, so memory follows the root of a list's length."""
    first: dict[str, int] = {}
    kinds: list[Unit] = []
    for u in y:
        if u.shape not in first:
            first[u.shape] = len(kinds)
            kinds.append(u)
    column = np.array([first[u.shape] for u in y])
    looks: dict[str, list[int]] = {}
    for k, u in enumerate(kinds):
        looks.setdefault(u.sig, []).append(k)
    weights: dict[str, np.ndarray] = {}

    def after(row: np.ndarray, u: Unit) -> np.ndarray:
        if u.sig not in looks:
            return row
        w = weights.get(u.shape)
        if w is None:
            w = np.zeros(len(kinds), np.int32)
            for k in looks[u.sig]:
                w[k] = matched(u, kinds[k], memo)
            if (len(weights) + 1) * len(kinds) > HELD_WEIGHTS:
                weights.clear()
            weights[u.shape] = w
        out = row.copy()
        np.maximum(row[1:], row[:-1] + w[column], out=out[1:])
        return np.maximum.accumulate(out)

    step = isqrt(len(x)) + 1
    row = np.zeros(len(y) + 1, np.int32)
    held = []
    for i, u in enumerate(x):
        if paired and i % step == 0:
            held.append(row)
        row = after(row, u)
    pairs: list[tuple[int, int]] = []
    i, j = len(x), len(y)
    while held and j:
        least = (len(held) - 1) * step
        best = [held.pop()]
        for u in x[least:i]:
            best.append(after(best[-1], u))
        found, j = _back(best, i, least, j)
        pairs += found
        i = least
    return int(row[-1]), pairs[::-1]


def folded(a: Unit, b: Unit) -> Unit:
    """Two wrappers (a page is the wrapper of itself) of the same look as one: units that are paired add up, the others stay as units that some pages have."""
    memo: dict = {}
    stack = [(a, b)]
    changed = []
    while stack:
        p, q = stack.pop()
        p.pages += q.pages
        p.length = max(p.length, q.length)
        p.text = p.text if p.text == q.text else None
        if not p.kids and not q.kids:
            continue
        pairs = aligned(p.kids, q.kids, memo)[1]
        if len(pairs) < len(p.kids) or len(pairs) < len(q.kids):
            changed.append(p)
        kids, at = [], 0
        partner = dict(pairs)
        for i, child in enumerate(p.kids):
            if i in partner:
                kids += q.kids[at : partner[i]]
                at = partner[i] + 1
                stack.append((child, q.kids[partner[i]]))
            kids.append(child)
        p.kids = kids + q.kids[at:]
    a.seen = sorted(set(a.seen) | set(b.seen))[:8]
    if changed:
        _reshaped(a)
    return a


def _preorder(top: Unit) -> list[Unit]:
    out, stack = [], [top]
    while stack:
        u = stack.pop()
        out.append(u)
        stack += u.kids[::-1]
    return out


def _reshaped(top: Unit) -> None:
    for u in reversed(_preorder(top)):
        _shaped(u)


@lru_cache(maxsize=65536)
def _path(above: str, sig: str) -> str:
    return _hash(f"{above}>{sig}")


def paths(root: Node) -> set[str]:
    """The paths (looks from the page's root down, hashed) of a page's units. Units that are aligned have the same path."""
    found, stack = {""}, [(root, "")]
    while stack:
        node, above = stack.pop()
        for c in _own(node)[1]:
            at = _path(above, _signature(c))
            found.add(at)
            stack.append((c, at))
    return found


def shared(top: Unit, common: frozenset[str]) -> Unit:
    """A page's units whose path other pages have, too. The others are aligned with nothing on any page: a wrapper would have each with a single page, as no template, and grow with every page."""
    stack = [(top, "")]
    order = []
    while stack:
        u, above = stack.pop()
        order.append(u)
        at = [_path(above, k.sig) for k in u.kids]
        u.kids = [k for k, p in zip(u.kids, at, strict=True) if p in common]
        stack += [(k, p) for k, p in zip(u.kids, [p for p in at if p in common], strict=True)]
    for u in reversed(order):
        _shaped(u)
    return top


def flat(top: Unit) -> str:
    """A wrapper as text: its units in page order with their depth."""
    rows, stack = [], [(top, 0)]
    while stack:
        u, depth = stack.pop()
        rows.append((depth, u.sig, u.text, u.pages, u.length))
        stack += [(k, depth + 1) for k in u.kids[::-1]]
    return json.dumps([top.seen, rows], separators=(",", ":"))


def unflat(text: str) -> Unit:
    seen, rows = json.loads(text)
    path: list[Unit] = []
    for depth, sig, own, pages, length in rows:
        u = Unit(sig, own, pages, [], [], length)
        del path[depth:]
        if path:
            path[-1].kids.append(u)
        path.append(u)
    top = path[0]
    top.seen = seen
    _reshaped(top)
    return top


def layout_of(root: Node) -> str:
    """The look of the body (and of what is around it) without its blocks."""
    out, at = [], root
    for _ in range(2):
        at = next((c for c in at.parts if isinstance(c, Node) and c.tag in ("html", "body")), None)
        if at is None:
            break
        out.append(_signature(at))
    return ">".join(out)


def induce(pages: list[str]) -> Unit | None:
    """The wrapper of pages of one host that look alike."""
    top = None
    for p in pages:
        u = units(parse(p))
        top = u if top is None else folded(top, u)
    return top


def _template(page: Unit, wrapper: Unit) -> set[int]:
    """Ids of the page's nodes whose own text is template. Where nothing varies, the pages are copies of one, and nothing is."""
    if not any(u.text is None and u.length for u in _preorder(wrapper)):
        return set()
    memo: dict = {}
    mute: set[int] = set()
    stack = [(page, wrapper, False)]
    while stack:
        u, w, inside = stack.pop()
        tag = u.nodes[0].tag
        inside = inside or tag in CONTENT_TAGS
        if w.text and u.text == w.text:
            prose = tag in PROSE
            if w.pages >= LEAST_PAGES if not prose else not inside and w.pages >= LEAST_PAGES_PROSE and len(wrapper.seen) >= LEAST_PAGES_PROSE:
                mute.update([id(n) for n in u.nodes])
        stack += [(u.kids[i], w.kids[j], inside) for i, j in aligned(u.kids, w.kids, memo)[1]]
    return mute


def _frames(root: Node) -> set[int]:
    """Ids of a page's headers without a heading, and of its menus: lists or parts that are links and hardly anything else."""
    found: set[int] = set()
    # Sums of each open element: links, characters in links, characters, headings.
    stack: list[tuple[Node, Iterator, bool, list[int]]] = [(root, iter(root.parts), False, [0, 0, 0, 0])]
    while stack:
        node, parts, linked, sums = stack[-1]
        c = next(parts, None)
        if c is None:
            stack.pop()
            if stack:
                up = stack[-1][3]
                for k in range(4):
                    up[k] += sums[k]
            links, inside, whole, headings = sums
            if node.tag == "header" and not headings:
                found.add(id(node))
            if links >= 3 and 10 * inside >= 8 * whole and node.tag in BLOCK and node.tag not in PROSE and node.tag not in ("body", "html"):
                found.add(id(node))
        elif isinstance(c, str):
            size = len(c.strip())
            sums[2] += size
            sums[1] += size if linked else 0
        else:
            sums[0] += c.tag == "a"
            sums[3] += c.tag in ("h1", "h2")
            stack.append((c, iter(c.parts), linked or c.tag == "a", [0, 0, 0, 0]))
    return found


def blocks(nodes: list[Node], mute: set[int], dropped: set[int] = frozenset()) -> list[str]:
    """Texts of the blocks in ``nodes``, in order: character references decoded, white space made single. Asides and nodes in ``dropped`` are left out, and of nodes in ``mute`` their own text."""
    out: list[str] = []
    line: list[str] = []

    def end() -> None:
        text = " ".join(html.unescape("".join(line)).split())
        line.clear()
        if text:
            out.append(text)

    for top in nodes:
        # Parts, whether the node ends a block, whether its own text is left out, whether it is prose (whose blocks are its own text).
        stack: list[tuple[Iterator, bool, bool, bool]] = [(iter([top]), False, False, False)]
        while stack:
            parts, is_block, silent, prose = stack[-1]
            p = next(parts, None)
            if p is None:
                stack.pop()
                if is_block:
                    end()
            elif isinstance(p, str):
                if not silent:
                    line.append(p)
            elif id(p) in dropped or is_aside(p):
                end() if p.tag in BLOCK else line.append(" ")
            elif p.tag in VOID:
                line.append(" ")
                if p.tag == "hr":
                    end()
            else:
                block = p.tag in BLOCK
                if block:
                    end()
                stack.append((iter(p.parts), block, silent if prose or not block else id(p) in mute, prose or p.tag in PROSE))
        end()
    return out


def _articles(root: Node) -> list[Node]:
    """The article and main elements outside asides, the outermost ones."""
    out, stack = [], [root]
    while stack:
        n = stack.pop()
        if n.tag in CONTENT_TAGS:
            out.append(n)
        elif not is_aside(n):
            stack += [c for c in n.parts[::-1] if isinstance(c, Node)]
    return out


def extract(page: str | None, wrappers: dict[str, Unit]) -> str:
    """The page's text under the wrapper of its layout, if there is one; else all of the page is a slot."""
    if not page:
        return ""
    root = parse(page)
    wrapper = wrappers.get(layout_of(root))
    mute = _template(units(root), wrapper) if wrapper is not None else set()
    marked = _articles(root)
    inside = blocks(marked, mute) if marked else []
    everything = blocks([root], mute, _frames(root))
    # A few teasers may be articles, too; the content has most of the text.
    return "\n\n".join(inside if inside and 2 * sum(map(len, inside)) >= sum(map(len, everything)) else everything)


def host_of(url):
    """The host of a URL column, in lower case; empty without one."""
    return F.lower(F.coalesce(F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1), F.lit("")))


#: A task passes its partial wrappers on when they have so many units together.
HELD_UNITS = 200_000


def _deep() -> None:
    """Trees may be as deep as pages are; only Python frames are stacked."""
    sys.setrecursionlimit(max(sys.getrecursionlimit(), 1_000_000))


#: A task passes its counts of paths on when it has so many.
HELD_PATHS = 500_000


def common_paths(rows: DataFrame) -> DataFrame:
    """host and common (JSON: layout to paths) of hosts with paths that two or more of a layout's pages have, from ``rows`` (host, html)."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _deep()
        held: Counter = Counter()

        def passed() -> pa.RecordBatch:
            keys = list(held)
            n = pa.array([held[k] for k in keys], pa.int64())
            held.clear()
            return pa.RecordBatch.from_arrays([*[pa.array([k[j] for k in keys], pa.string()) for j in range(3)], n], names=["host", "layout", "path", "n"])

        for batch in batches:
            for host, page in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                root = parse(page)
                layout = layout_of(root)
                held.update([(host, layout, p) for p in paths(root)])
                if len(held) >= HELD_PATHS:
                    yield passed()
        yield passed()

    seen = rows.mapInArrow(count, "host string, layout string, path string, n bigint").groupBy("host", "layout", "path").agg(F.sum("n").alias("n")).where("n > 1")
    lists = seen.groupBy("host", "layout").agg(F.array_join(F.sort_array(F.collect_list("path")), " ").alias("paths"))
    return lists.groupBy("host").agg(F.to_json(F.map_from_entries(F.sort_array(F.collect_list(F.struct("layout", "paths"))))).alias("common"))


#: A table with a row for each host is broadcast up to so many hosts and characters in all; beyond that it is joined by a shuffle.
BROADCAST_HOSTS, BROADCAST_CHARS = 20_000, 16_000_000


def _by_host(rows: DataFrame, hosts: DataFrame, column: str) -> DataFrame:
    """``rows`` with the column of their host."""
    n, chars = hosts.agg(F.count("*"), F.coalesce(F.sum(F.length(column)), F.lit(0))).first()
    small = n <= BROADCAST_HOSTS and chars <= BROADCAST_CHARS
    return rows.join(F.broadcast(hosts) if small else hosts.hint("shuffle_hash"), "host", "left")


def wrappers(pages: DataFrame) -> DataFrame:
    """host and wrappers (JSON: layout to wrapper) of hosts that have a layout with two pages or more, from all pages. Paths are counted first, over all of a layout's pages. Tasks fold their pages, so a host costs a row for each task and layout."""
    rows = pages.where("html is not null").select(host_of(F.col("url")).alias("host"), "html")
    rows = _by_host(rows, stored(common_paths(rows)), "common").select("host", "html", "common").where("common is not null")

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _deep()
        held: dict[tuple[str, str], Unit] = {}
        total = 0

        @lru_cache(maxsize=256)
        def loaded(text: str) -> dict[str, frozenset[str]]:
            return {k: frozenset(v.split(" ")) for k, v in json.loads(text).items()}

        def passed() -> pa.RecordBatch:
            nonlocal total
            rows = [(h, k, flat(u)) for (h, k), u in held.items()]
            held.clear()
            total = 0
            cols = list(zip(*rows, strict=True)) or [(), (), ()]
            return pa.RecordBatch.from_arrays([pa.array(c, pa.string()) for c in cols], names=["host", "layout", "wrapper"])

        for batch in batches:
            for host, page, text in zip(*(batch.column(j).to_pylist() for j in range(3)), strict=True):
                root = parse(page)
                key = (host, layout_of(root))
                common = loaded(text).get(key[1])
                if common is None:
                    continue
                u = shared(units(root), common)
                for x in _preorder(u):
                    x.nodes = []
                old = held.get(key)
                before = old.size if old is not None else 0
                held[key] = u if old is None else folded(old, u)
                total += held[key].size - before
                if total >= HELD_UNITS:
                    yield passed()
        yield passed()

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _deep()
        host: str | None = None
        layout: str | None = None
        top: Unit | None = None
        done: dict[str, str] = {}

        def settle() -> None:
            if top is not None and len(top.seen) > 1:
                done[layout] = flat(top)

        def made() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([host] if done else [], pa.string()), pa.array([json.dumps(done)] if done else [], pa.string())], names=["host", "wrappers"])

        for batch in batches:
            for h, k, w in zip(*(batch.column(j).to_pylist() for j in range(3)), strict=True):
                if (h, k) != (host, layout):
                    settle()
                    if h != host:
                        yield made()
                        done = {}
                    host, layout, top = h, k, unflat(w)
                else:
                    top = folded(top, unflat(w))
        settle()
        yield made()

    parts = rows.mapInArrow(fold, "host string, layout string, wrapper string").repartition("host").sortWithinPartitions("host", "layout", "wrapper")
    return parts.mapInArrow(merge, "host string, wrappers string")


def extract_pages(pages: DataFrame) -> DataFrame:
    """page_id, url, text and n_chars of every row of ``pages`` (page_id, url, html).

    A null or empty page has an empty text; a page without a URL shares the wrapper of the others without one. Repeated rows give repeated rows. An empty table gives an empty result. Other columns are ignored.
    """
    w = stored(wrappers(pages))
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html", host_of(F.col("url")).alias("host"))
    joined = _by_host(rows, w, "wrappers").select("page_id", "url", "html", "wrappers")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _deep()

        @lru_cache(maxsize=256)
        def loaded(text: str | None) -> dict[str, Unit]:
            return {k: unflat(v) for k, v in json.loads(text or "{}").items()}

        for batch in batches:
            texts = [extract(p, loaded(k)) for p, k in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return joined.mapInArrow(work, "page_id long, url string, text string, n_chars long")
