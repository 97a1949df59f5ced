"""Main text of web pages by wrapper induction over the pages of a host.

Every page is parsed to a tree of block elements, labelled with name, id and
class (digits left out), whose repeated siblings are folded: its frame. The frame
most pages of a host have is the host's reference, and simple tree matching
aligns every other frame with it. Two things are learned over all pages of the
host. Text that stands in the same node on most pages is template. And the text
that varies (each distinct text of a node counts once, without what is linked)
shows where the content is: from the root down, as long as one child holds more
than half of the varying text, the content lies in that child; a varying heading
directly beside it belongs to it. What aligns with the reference outside this
region is template however much it varies, as menus and adverts do.

A page gives the blocks whose element lies in the region, but for template text,
for subtrees the reference doesn't have there and whose label it has only outside
(broken markup moves a footer into an unclosed article), and for what alignment
can't tell from an article: elements within a region narrower than the page that
their name, id, class or role calls forms, reader comments or the like
(`_PURPOSE`, `_CHROME`). A page without anything aligned with the region gives
all that is no template.

Hosts with fewer than `min_pages` different pages give too little to compare:
there the element names alone decide (the marked article, without elements of
another purpose).

Statistics cover all pages of a host and are combined by partial aggregation;
pages are parsed twice, once to learn and once to read. What returns to the
pages is, per host, the reference, the varying text by node and the template
texts, all bounded by the size of a page: broadcast while their measured size
stays under a bound, so that pages are not shuffled, else joined by host, where
adaptive execution splits hot hosts.

Defined cases: a null or empty page gives an empty text; a null url belongs to
a host of its own name (empty); repeated rows count as pages, but text that only
copies of one page share is never template; broken markup is repaired like a
browser would, as far as blocks go; scripts, styles and the like that are never
closed run to the end of the page, other unclosed elements hold what follows;
depth and length are not limited; an empty table gives an empty result; other
columns are ignored.
"""

from __future__ import annotations

import html
import re
from collections.abc import Iterator
from hashlib import blake2b

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut

SHARE = 0.5
MIN_PAGES = 8
#: Share of the varying text that one child must hold for the content to lie in it.
DOMINANT = 0.5
BROADCAST_BYTES = 32 << 20
#: Parts by which a node's texts meet its alignment where that is too large to broadcast.
SALTS = 16

_TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)|<[!?][^>]*+>?|<(/?)([a-zA-Z][^\s/>]*+)((?:[^>\"']++|\"[^\"]*+\"|'[^']*+'|[\"'])*+)>?", re.S
)
_SPACE = re.compile(r"\s+")
_NAMED = re.compile(r"(?:^|\s)(?:class|id|role|aria-label|itemprop)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_HIDDEN = re.compile(r"(?:^|\s)hidden(?:\s|=|$)|aria-hidden\s*=\s*[\"']?true|display\s*:\s*none", re.I)
_PART = re.compile(r"[A-Z]?[a-z]+|[A-Z]+|\d+")

# Element names and the words in class, id and role that tell an element's purpose.
_BLOCKS = frozenset(
    "address article aside blockquote body caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 "
    "header hgroup hr html legend li main menu nav ol p pre section summary table tbody tfoot thead tr ul".split()
)
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_RAW = frozenset("script style noscript iframe template textarea title svg math object select noembed noframes canvas audio video".split())
_RUNS_ON = frozenset("script style iframe textarea title noembed noframes".split())
_HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
#: Elements that hold a stretch of running text; alike ones in a row are one node of the frame.
_FLOW = frozenset("p li tr dd dt pre blockquote figure figcaption caption h1 h2 h3 h4 h5 h6".split())
_PURPOSE = frozenset("nav aside footer form menu dialog button fieldset label input".split())
_CHROME = frozenset(
    "ad ads adv advert advertisement adverts advertising banner breadcrumb breadcrumbs comment comments cookie cookies consent copyright disqus "
    "footer login masthead menu modal nav navbar navigation newsletter notice notices pagination pager popup promo promoted promotion related reply "
    "replies respond search share sharing sidebar signup social sponsor sponsored subscribe subscription toolbar widget alert gdpr toc "
    "complementary contentinfo discussion responses".split()
)
_READERS = frozenset("comment comments disqus discussion replies reply respond responses".split())
_CLOSES_P = _BLOCKS - {"body", "html", "caption", "tbody", "tfoot", "thead", "tr", "li", "dd", "dt", "legend", "summary"}
_SAME = {"li": {"li"}, "dd": {"dd", "dt"}, "dt": {"dd", "dt"}, "tr": {"tr"}, "option": {"option"}, "tbody": {"tbody", "thead"}, "tfoot": {"tbody", "thead"}}
_HOLDS = {"li": {"ul", "ol", "menu"}, "dd": {"dl"}, "dt": {"dl"}, "tr": {"table"}, "tbody": {"table"}, "tfoot": {"table"}}


class Node:
    __slots__ = ("tag", "label", "chrome", "article", "kids", "parent", "shape", "folds", "place")

    def __init__(self, tag: str, parent: Node | None, label: str = "", chrome: int = 0, article: bool = False):
        self.tag, self.parent, self.label, self.chrome, self.article = tag, parent, label or tag, chrome, article
        self.kids: list[Node] = []
        self.shape, self.folds, self.place = 0, [], 0


class _Small(dict):
    """A cache of bounded size that travels empty."""

    def __reduce__(self) -> tuple:
        return (_Small, ())

    def keep(self, key: object, value: object) -> object:
        if len(self) > 20_000:
            self.clear()
        self[key] = value
        return value


_PURPOSES = _Small()
_MARK = re.compile(r"(?:^|\s)(class|id)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)


def _label(tag: str, attrs: str) -> str:
    """Element name with id and classes, digits and signs left out."""
    marks = ["." + re.sub(r"[^A-Za-z_-]+", "", w) for _, a, b, c in _MARK.findall(attrs) for w in (a or b or c).split()] if attrs else []
    return tag + "".join(m for m in marks if m != ".")


def _purpose(tag: str, attrs: str) -> tuple[int, bool, str]:
    """0 for content, 1 for another purpose unless the article lies inside, 2 for another purpose; whether this is the article; and the label."""
    got = _PURPOSES.get((tag, attrs))
    if got is not None:
        return got
    article, chrome = tag in ("article", "main"), 2 * (tag in _PURPOSE)
    if attrs and tag not in ("html", "body"):
        if _HIDDEN.search(attrs):
            chrome = 2
        for a, b, c in _NAMED.findall(attrs):
            words = {w.lower() for w in _PART.findall(a or b or c)}
            if words & _READERS:
                chrome = 2
            elif words & _CHROME and not article:
                chrome = max(chrome, 1)
            if "main" in words or "articlebody" in (a or b or c).lower():
                article = True
    return _PURPOSES.keep((tag, attrs), (chrome, article, _label(tag, attrs)))


def parse(page: str) -> tuple[Node, list[tuple[Node, str, int]]]:
    """The tree of block elements and the text blocks in page order, each with the element that holds it and its number of linked characters."""
    root = node = Node("html", None)
    stack: list[tuple[str, Node]] = [("html", root)]
    blocks: list[tuple[Node, str, int]] = []
    run: list[str] = []
    links = linked = 0

    def flush() -> None:
        nonlocal linked
        if run:
            text = " ".join(html.unescape("".join(run)).split())
            run.clear()
            if text:
                blocks.append((node, text, min(linked, len(text))))
        linked = 0

    def say(text: str) -> None:
        nonlocal linked
        run.append(text)
        if links:
            linked += len(text)

    def shut(depth: int) -> None:
        nonlocal node, links
        links -= sum(t == "a" for t, _ in stack[depth:])
        if any(n is not node or t in _BLOCKS for t, n in stack[depth:]):
            flush()
        del stack[depth:]
        node = stack[-1][1] if stack else root

    at, n, search = 0, len(page), _TOKEN.search
    while at < n:
        m = search(page, at)
        if m is None:
            say(page[at:])
            break
        if m.start() > at:
            say(page[at:m.start()])
        at = m.end()
        tag = m.group(2)
        if tag is None:
            continue
        tag, attrs = tag.lower(), m.group(3) or ""
        if m.group(1):
            if tag == "p" and not any(t == "p" for t, _ in stack):
                flush()
                continue
            for i in range(len(stack) - 1, 0, -1):
                if stack[i][0] == tag:
                    shut(i)
                    break
                if tag not in _BLOCKS and stack[i][0] in _BLOCKS:
                    break
            continue
        if tag in _RAW:
            if not attrs.rstrip().endswith("/") or tag not in ("svg", "math"):
                low = re.compile(rf"</{tag}\b[^>]*>?", re.I).search(page, at)
                at = low.end() if low else n if tag in _RUNS_ON else at
            run.append(" ")
            continue
        if tag in _VOID:
            if tag == "hr":
                flush()
            elif tag != "wbr":
                run.append(" ")
            continue
        if tag in _CLOSES_P:
            for i in range(len(stack) - 1, 0, -1):
                if stack[i][0] == "p":
                    shut(i)
                    break
                if stack[i][0] in ("table", "td", "th", "button", "object"):
                    break
        if tag in _SAME:
            for i in range(len(stack) - 1, 0, -1):
                if stack[i][0] in _SAME[tag]:
                    shut(i)
                    break
                if stack[i][0] in _HOLDS.get(tag, ()):
                    break
        if tag in ("html", "body", "head"):
            continue
        if attrs.rstrip().endswith("/"):
            run.append(" ") if tag in ("td", "th") else None
            continue
        chrome, article, label = _purpose(tag, attrs)
        if tag in ("td", "th"):
            run.append(" ")
        if tag in _BLOCKS or chrome:
            flush()
            kid = Node(tag, node, label, chrome, article)
            node.kids.append(kid)
            node = kid
        links += tag == "a"
        stack.append((tag, node))
    flush()
    return root, blocks


class _Shapes:
    """Folded trees as numbers: equal trees have equal numbers."""

    def __init__(self) -> None:
        self.known: dict[tuple[str, tuple[int, ...]], int] = {}
        self.label: list[str] = []
        self.kids: list[tuple[int, ...]] = []
        self.size: list[int] = []

    def of(self, label: str, kids: tuple[int, ...]) -> int:
        got = self.known.get((label, kids))
        if got is None:
            got = self.known[label, kids] = len(self.label)
            self.label.append(label), self.kids.append(kids), self.size.append(1 + sum(self.size[k] for k in kids))
        return got

    def text(self, shape: int) -> str:
        out: list[str] = []
        todo: list[int | str] = [shape]
        while todo:
            x = todo.pop()
            if isinstance(x, str):
                out.append(x)
                continue
            out.append(self.label[x])
            if self.kids[x]:
                out.append("(")
                todo.append(")")
                for i, k in reversed(list(enumerate(self.kids[x]))):
                    todo.append(k)
                    if i:
                        todo.append(" ")
        return "".join(out)

    def read(self, text: str) -> int:
        """The shape of a frame given as nested labels."""
        path: list[tuple[str, list[int]]] = [("", [])]
        for label, sign in re.findall(r"([^( )]*)([( )]|$)", text):
            if sign == "(":
                path.append((label, []))
                continue
            if label:
                path[-1][1].append(self.of(label, ()))
            if sign == ")":
                name, kids = path.pop()
                path[-1][1].append(self.of(name, tuple(kids)))
        return path[0][1][0]


def _fold(shapes: _Shapes, kids: list[int]) -> tuple[list[int], list[int]]:
    """Kids without repeats (runs of one to three that come again; of alike containers three stay apart), and each kid's place among them."""
    own: list[int] = []
    place: list[int] = []
    for k in kids:
        place.append(len(own))
        own.append(k)
        for p in (1, 2, 3):
            times = 2 if p > 1 or shapes.label[k].partition(".")[0] in _FLOW else 4
            if len(own) >= p * times and own[-p:] * times == own[-p * times:]:
                del own[-p:]
                i = len(place) - 1
                while i >= 0 and place[i] >= len(own):
                    place[i] -= p
                    i -= 1
                break
    return own, place


def frame(root: Node) -> str:
    """The page's tree with repeats folded, as nested labels. Sets each node's `place`, the preorder number of the frame's node that it folds into."""
    stack, seen, shapes = [root], [], _Shapes()
    while stack:
        x = stack.pop()
        seen.append(x)
        stack.extend(x.kids)
    for x in reversed(seen):
        own, x.folds = _fold(shapes, [k.shape for k in x.kids])
        x.shape = shapes.of(x.label, tuple(own))
    root.place = 0
    for x in seen:
        at = [x.place + 1]
        for k in shapes.kids[x.shape]:
            at.append(at[-1] + shapes.size[k])
        for k, i in zip(x.kids, x.folds, strict=True):
            k.place = at[i]
    return shapes.text(root.shape)


def _best_pairs(weight: np.ndarray, a: list[int], b: list[int]) -> tuple[int, list[tuple[int, int]]]:
    """Largest total weight of pairs in order, and the pairs; `a` and `b` are rows and columns of `weight`. Rows of the table are kept in steps, so memory grows with m^.5 * n."""
    m, n = len(a), len(b)
    b = np.array(b)
    step = max(1, int(m**0.5))

    def rows(first: int, last: int, start: np.ndarray) -> list[np.ndarray]:
        out = [start]
        for i in range(first, last):
            w = weight[a[i], b]
            row = out[-1].copy()
            np.maximum(row[1:], np.where(w > 0, out[-1][:-1] + w, 0), out=row[1:])
            out.append(np.maximum.accumulate(row))
        return out

    kept = [np.zeros(n + 1, np.int64)]
    for i in range(0, m, step):
        kept.append(rows(i, min(m, i + step), kept[-1])[-1])
    pairs, j = [], n
    for part in range(len(kept) - 2, -1, -1):
        first = part * step
        table = rows(first, min(m, first + step), kept[part])
        i = len(table) - 1
        while i and j:
            if table[i][j] == table[i - 1][j]:
                i -= 1
            elif table[i][j] == table[i][j - 1]:
                j -= 1
            else:
                i, j = i - 1, j - 1
                pairs.append((first + i, j))
    return int(kept[-1][n]), pairs[::-1]


def matched(a: str, b: str) -> list[int]:
    """Simple tree matching of two frames: for each node of `a` in preorder the number of its node in `b` or -1, for the largest matching that keeps labels, order and ancestry."""
    shapes = _Shapes()
    x, y = shapes.read(a), shapes.read(b)
    out = [-1] * shapes.size[x]
    if shapes.label[x] != shapes.label[y]:
        return out
    done: dict[tuple[int, int], tuple[int, list[tuple[int, int]]]] = {}
    todo = [(x, y)]
    while todo:
        p, q = pair = todo[-1]
        if pair in done:
            todo.pop()
            continue
        rows, cols = sorted(set(shapes.kids[p])), sorted(set(shapes.kids[q]))
        alike = [(r, c) for r in rows for c in cols if r != c and shapes.label[r] == shapes.label[c]]
        wait = [k for k in alike if k not in done]
        if wait:
            todo.extend(wait)
            continue
        todo.pop()
        at_row, at_col = {r: i for i, r in enumerate(rows)}, {c: i for i, c in enumerate(cols)}
        weight = np.zeros((len(rows), len(cols)), np.int64)
        for r, c in alike:
            weight[at_row[r], at_col[c]] = done[r, c][0]
        for r in set(rows) & set(cols):
            weight[at_row[r], at_col[r]] = shapes.size[r]
        total, pairs = _best_pairs(weight, [at_row[r] for r in shapes.kids[p]], [at_col[c] for c in shapes.kids[q]]) if rows and cols else (0, [])
        done[pair] = 1 + total, pairs
    open_ = [(x, 0, y, 0)]
    while open_:
        p, i, q, j = open_.pop()
        if p == q:
            out[i:i + shapes.size[p]] = range(j, j + shapes.size[p])
            continue
        out[i] = j
        left, right = (np.cumsum([n + 1, *(shapes.size[k] for k in shapes.kids[z])]).tolist() for n, z in ((i, p), (j, q)))
        open_.extend((shapes.kids[p][r], left[r], shapes.kids[q][c], right[c]) for r, c in done[p, q][1])
    return out


def text_hash(text: str) -> int:
    return int.from_bytes(blake2b(text.encode("utf-8", "surrogatepass"), digest_size=8).digest(), "little", signed=True)


class Wrapper:
    """What the pages of a host have taught: the reference, where its content lies, and its template texts."""

    def __init__(self, reference: str, varying: list[tuple[int, int, int]], constants: set[tuple[int, int]], dominant: float = DOMINANT):
        """`varying` has (node, characters, number of texts) of the distinct texts of the reference's nodes."""
        self.reference, self.constants = reference, constants
        self.known: dict[str, list[int]] = {}
        self.labels, self.parents = [], []
        path: list[int] = []
        for label, sign in re.findall(r"([^( )]*)([( )]|$)", reference):
            if label:
                self.labels.append(label), self.parents.append(path[-1] if path else -1)
            if sign == "(":
                path.append(len(self.labels) - 1)
            elif sign == ")":
                path.pop()
        n = len(self.labels)
        self.texts, own = [0] * n, [0] * n
        for node, chars, texts in varying:
            own[node], self.texts[node] = chars, texts
        kids: list[list[int]] = [[] for _ in range(n)]
        self.end = list(range(1, n + 1))
        for i in range(n - 1, 0, -1):
            up = self.parents[i]
            kids[up].append(i)
            own[up] += own[i]
            self.end[up] = max(self.end[up], self.end[i])
        at = 0
        while kids[at]:
            best = max(kids[at], key=lambda k: (own[k], -k))
            if own[best] <= dominant * own[at] or (not kids[best] and self.tag(best) in _FLOW):
                break
            at = best
        while at and any(k != at and self._heads(k, kids) for k in kids[self.parents[at]]):
            at = self.parents[at]
        self.region = at
        self.above = {0}
        while at > 0:
            at = self.parents[at]
            self.above.add(at)
        self.above.discard(self.region)
        inner = set(self.labels[self.region:self.end[self.region]])
        self.outer = {x for i, x in enumerate(self.labels) if not self.inside(i) and i not in self.above} - inner

    def tag(self, node: int) -> str:
        return self.labels[node].partition(".")[0]

    def _heads(self, node: int, kids: list[list[int]]) -> bool:
        """A heading whose text varies, or a header that holds one."""
        if self.tag(node) in _HEADINGS:
            return self.texts[node] > 1
        return self.tag(node) in ("header", "hgroup") and any(self.tag(k) in _HEADINGS and self.texts[k] > 1 for k in kids[node])

    def inside(self, node: int) -> bool:
        return self.region <= node < self.end[self.region]

    def place(self, own: str) -> list[int]:
        got = self.known.get(own)
        if got is None:
            if len(self.known) > 1_000:
                self.known.clear()
            got = self.known[own] = matched(own, self.reference)
        return got

    def read(self, root: Node, blocks: list[tuple[Node, str, int]]) -> str:
        found = self.place(frame(root))
        whole = self.region not in found
        fate: dict[int, tuple[bool, int]] = {}
        kept = []
        for x, text, _ in blocks:
            line, y = [], x
            while y is not None and id(y) not in fate:
                line.append(y)
                y = y.parent
            off, near = fate[id(y)] if y is not None else (False, -1)
            for y in reversed(line):
                at = found[y.place]
                if at >= 0:
                    near = at
                    off = off or not (at in self.above or self.inside(at)) or (at > self.region > 0 and y.chrome > 0)
                else:
                    off = off or (self.region > 0 and y.chrome > 0) or (near in self.above and not whole) or (self.inside(near) and y.label in self.outer)
                fate[id(y)] = off, near
            at = found[x.place]
            if off or (at >= 0 and (at, text_hash(text)) in self.constants) or (at in self.above and not whole):
                continue
            kept.append(text)
        return "\n".join(kept)


def by_names(blocks: list[tuple[Node, str, int]]) -> str:
    """Blocks outside elements of another purpose; inside the article, where one is marked."""
    fate: dict[int, tuple[bool, bool]] = {}
    holds: set[int] = set()
    for x in {id(x): x for x, _, _ in blocks}.values():
        inside = False
        while x is not None:
            if inside:
                if id(x) in holds:
                    break
                holds.add(id(x))
            inside = inside or x.article
            x = x.parent

    def judge(x: Node) -> tuple[bool, bool]:
        """(dropped, inside the article), settled from the root down."""
        line, y = [], x
        while y is not None and id(y) not in fate:
            line.append(y)
            y = y.parent
        off, inside = fate[id(y)] if y is not None else (False, False)
        for y in reversed(line):
            off = off or y.chrome == 2 or (y.chrome == 1 and (inside or id(y) not in holds)) or (y.tag == "header" and not inside)
            inside = inside or y.article
            fate[id(y)] = off, inside
        return off, inside

    judged = [(judge(x), text) for x, text, _ in blocks]
    kept = [(inside, text) for (off, inside), text in judged if not off]
    if any(a for a, _ in kept):
        kept = [k for k in kept if k[0]]
    return "\n".join(t for _, t in kept)


def host_of(url: Column) -> Column:
    return F.lower(F.coalesce(F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1), F.lit("")))


def _small(df: DataFrame, size: Column) -> bool:
    return (df.agg(F.sum(size)).first()[0] or 0) <= BROADCAST_BYTES


SEEN = "host string, fh long, node int, h long, n long, low long, high long, chars long, frame string"


def _observe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Per batch and host: frames (node -2), whole pages (node -1), and the texts of each node of each frame."""
    for batch in batches:
        counts: dict[tuple[str, int, int, int], list] = {}
        for host, page in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            root, blocks = parse(page or "")
            text = frame(root)
            fh, whole = text_hash(text), text_hash("\n".join(t for _, t, _ in blocks))
            found = {(host, fh, -2, 0): (0, text), (host, fh, -1, whole): (0, None)}
            for x, t, linked in blocks:
                found[host, fh, x.place, text_hash(t)] = len(t) - linked, None
            for key, (chars, name) in found.items():
                got = counts.setdefault(key, [0, whole, whole, chars, name])
                got[0], got[1], got[2], got[3] = got[0] + 1, min(got[1], whole), max(got[2], whole), max(got[3], chars)
        cols = list(zip(*((*k, *v) for k, v in counts.items()), strict=True)) or [[]] * 9
        kinds = [pa.string(), pa.int64(), pa.int32(), *[pa.int64()] * 5, pa.string()]
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["host", "fh", "node", "h", "n", "low", "high", "chars", "frame"])


def _align(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """For every node of every frame its node in the host's reference, or that of its nearest ancestor that has one."""
    for batch in batches:
        for host, fh, own, reference in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            found = matched(own, reference)
            parents = Wrapper(own, [], set()).parents
            near = list(found)
            for i, at in enumerate(found):
                if at < 0:
                    near[i] = near[parents[i]] if i else 0
            n = len(found)
            yield pa.RecordBatch.from_arrays(
                [pa.array([host] * n), pa.array([fh] * n), pa.array(range(n), pa.int32()), pa.array(near, pa.int32()), pa.array([at >= 0 for at in found])], ["host", "fh", "node", "ref", "own"],
            )


def induce(pages: DataFrame, share: float = SHARE, min_pages: int = MIN_PAGES) -> DataFrame:
    """(host, reference, varying, constants) from columns host and html of all pages, for hosts with enough of them."""
    seen = cut(
        pages.select("host", "html").mapInArrow(_observe, SEEN).groupBy("host", "fh", "node", "h")
        .agg(F.sum("n").alias("n"), F.min("low").alias("low"), F.max("high").alias("high"), F.max("chars").alias("chars"), F.max("frame").alias("frame"))
    )
    frames = seen.where("node = -2").select("host", "fh", "n", "frame")
    enough = seen.where("node = -1").groupBy("host").agg(F.sum("n").alias("pages"), F.count(F.lit(1)).alias("different")).where(F.col("different") >= min_pages)
    told = F.struct(F.col("frame").contains("(").alias("some"), "n", "frame")
    hosts = cut(frames.groupBy("host").agg(F.max_by("frame", told).alias("reference")).join(enough, "host").select("host", "reference", "pages"))
    known = hosts.select("host", "reference")
    known = F.broadcast(known) if _small(known, F.octet_length("host") + F.octet_length("reference") + 40) else known
    aligned = cut(frames.join(known, "host").select("host", "fh", "frame", "reference").mapInArrow(_align, "host string, fh long, node int, ref int, own boolean"))
    texts = seen.where("node >= 0").select("host", "fh", "node", "h", "n", "low", "high", "chars")
    if _small(aligned, F.octet_length("host") + 64):
        met = texts.join(F.broadcast(aligned), ["host", "fh", "node"])
    else:
        salted = aligned.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        met = texts.withColumn("salt", F.pmod("h", F.lit(SALTS)).cast("int")).join(salted, ["host", "fh", "node", "salt"])
    slots = met.groupBy("host", "ref", "own", "h").agg(F.sum("n").alias("n"), F.min("low").alias("low"), F.max("high").alias("high"), F.max("chars").alias("chars"))
    slots = cut(slots)
    varying = slots.groupBy("host", "ref").agg(F.sum("chars").alias("chars"), F.count(F.lit(1)).alias("texts")).groupBy("host").agg(
        F.collect_list(F.struct("ref", "chars", "texts")).alias("varying")  # one entry for each node of the reference at most
    )
    often = slots.where(F.col("own") & (F.col("n") >= min_pages) & (F.col("low") < F.col("high"))).join(F.broadcast(hosts.select("host", "pages")) if _small(hosts, F.octet_length("host") + 40) else hosts.select("host", "pages"), "host")
    fixed = often.where(F.col("n") >= F.col("pages") * F.lit(share)).groupBy("host").agg(F.collect_set(F.struct("ref", "h")).alias("constants"))
    return hosts.join(varying, "host", "left").join(fixed, "host", "left").select("host", "reference", "varying", "constants")


def extract(pages: DataFrame, id_col: str = "page_id", url: str = "url", page: str = "html", share: float = SHARE, min_pages: int = MIN_PAGES) -> DataFrame:
    """(page_id, url, text, n_chars) for every row."""
    own = pages.select(F.col(id_col).alias("page_id"), F.col(url).alias("url"), F.col(page).alias("html"), host_of(F.col(url)).alias("host"))
    wrappers = cut(induce(own, share, min_pages))

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        learned: dict[str, Wrapper] = {}
        for batch in batches:
            texts = []
            hosts, references = batch.column(3).to_pylist(), batch.column(4).to_pylist()
            for i, page_html in enumerate(batch.column(2).to_pylist()):
                root, blocks = parse(page_html or "")
                if references[i] is None:
                    texts.append(by_names(blocks))
                    continue
                if hosts[i] not in learned:
                    if len(learned) > 1_000:
                        learned.clear()
                    varying, constants = batch.column(5)[i].as_py() or [], batch.column(6)[i].as_py() or []
                    learned[hosts[i]] = Wrapper(references[i], [(v["ref"], v["chars"], v["texts"]) for v in varying], {(c["ref"], c["h"]) for c in constants})
                texts.append(learned[hosts[i]].read(root, blocks))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    kind = own.schema["page_id"].dataType.simpleString()
    size = F.octet_length("host") + F.octet_length("reference") + 40 + 24 * F.greatest(F.size("varying"), F.lit(0)) + 16 * F.greatest(F.size("constants"), F.lit(0))
    wrappers = F.broadcast(wrappers) if _small(wrappers, size) else wrappers
    joined = own.join(wrappers, "host", "left").select("page_id", "url", "html", "host", "reference", "varying", "constants")
    return joined.mapInArrow(read, f"page_id {kind}, url string, text string, n_chars long")
