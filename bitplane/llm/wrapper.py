"""Main text of web pages by wrapper induction.

Every page becomes a tree of collapsed tag runs.  Pages of one host are aligned
with a neighbour by simple tree matching: two nodes match if their labels do,
and children are matched in order for the largest total.  A matched slot votes
constant if its text is the same on both pages and varying if not; what
matches nothing varies.  A host's wrapper follows from its votes: the container
that holds the varying text outside page furniture, and the constant slots inside it
that are template.  Extraction then reads every page through its host's wrapper.

A slot's path is the 63-bit hash of its label and its parent's path, and every walk is a
loop with its own stack, so that trees of any depth cost what their size says.
"""

from __future__ import annotations

import html
import json
import re
import zlib
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import stored

TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^<>\"']|\"[^\"]*\"|'[^']*')*)>|<[!?][^>]*(?:>|\Z)", re.S)
NAMED = re.compile(r"""(class|id|role|hidden|aria-hidden)\s*(?:=\s*("[^"]*"|'[^']*'|[^\s"'>]+))?""", re.I)

#: Element classes of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title template noscript iframe svg select option button".split())
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
FURNITURE = frozenset("head nav footer aside form script style textarea title template noscript iframe svg select option button input dialog menu object canvas".split())
CLOSES_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section table ul".split())
SIBLINGS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}, "thead": {"thead", "tbody", "tfoot"}, "tbody": {"thead", "tbody", "tfoot"}}
FENCES = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"table"}, "th": {"table"}}

ENDS = {tag: re.compile(f"</{tag}", re.I | re.A) for tag in RAW}

#: Words in class, id or role that mark page furniture.
SIGNS = re.compile(
    r"(?:^|[\s_-])(?:ads?|advert\w*|sponsor\w*|promo\w*|banner|nav|navbar|navigation|menu|menubar|breadcrumbs?|sidebar|side-?bar|aside|complementary|footer|foot|contentinfo|masthead|topbar|"
    r"header|comments?|disqus|respond|replies|cookies?|consent|gdpr|notice|notification|alert|popup|modal|overlay|newsletter|subscribe|subscription|signup|login|search|searchbox|share|sharing|social|related|recommend\w*|"
    r"pagination|pager|widget|toolbar|skip-?link|form)(?:$|[\s_-])",
    re.I,
)


def step(path: int, label: str) -> int:
    """The path of a child; 0 is the root's."""
    return xxhash.xxh3_64_intdigest(label.encode("utf-8", "surrogatepass"), path) >> 1


def path_of(*labels: str) -> int:
    path = 0
    for label in labels:
        path = step(path, label)
    return path


class Node:
    __slots__ = ("label", "children", "furniture", "tag", "main")

    def __init__(self, tag: str, label: str, furniture: bool, main: bool):
        self.tag, self.label, self.furniture, self.main, self.children = tag, label, furniture, main, []


def attributes(text: str) -> tuple[str, bool]:
    """Class, id and role in one label part; whether they mark furniture or hide the element."""
    if not text or text.isspace():
        return "", False
    parts, marked = [], False
    for name, value in NAMED.findall(text):
        name, value = name.lower(), value.strip("\"'")
        if name == "hidden" or name == "aria-hidden":
            marked |= name == "hidden" or value == "true"
            continue
        marked |= bool(SIGNS.search(value))
        if name != "id":
            parts.append(".".join(sorted(value.lower().split())))
    return "".join(f".{p}" for p in parts if p), marked


def parse(page: str) -> Node:
    """A tolerant tree: unclosed paragraphs, list items and cells end where HTML says, stray end tags are passed over."""
    root = Node("#root", "#root", False, False)
    stack, at = [root], 0
    open_tags: Counter[str] = Counter()
    n = len(page)

    def cut(k: int) -> None:
        for node in stack[k:]:
            open_tags[node.tag] -= 1
        del stack[k:]

    def close(tags: set[str], fences: set[str]) -> None:
        if not any(open_tags[t] for t in tags):
            return
        for k in range(len(stack) - 1, 0, -1):
            if stack[k].tag in tags:
                return cut(k)
            if stack[k].tag in fences:
                return None

    while at < n:
        m = TOKEN.search(page, at)
        if m is None:
            stack[-1].children.append(page[at:])
            break
        if m.start() > at:
            stack[-1].children.append(page[at : m.start()])
        at = m.end()
        if m[0].startswith("<![CDATA["):
            stack[-1].children.append(html.escape(m[0][9:].removesuffix("]]>"), quote=False))
        if m[2] is None:
            continue
        tag = m[2].lower()
        if m[1]:
            for k in range(len(stack) - 1, 0, -1) if open_tags[tag] else ():
                if stack[k].tag == tag:
                    cut(k)
                    break
                if tag in INLINE and stack[k].tag not in INLINE:
                    break
            continue
        label, marked = attributes(m[3])
        if tag in CLOSES_P:
            close({"p"}, {"table", "td", "th", "div", "article", "section", "main", "li", "blockquote"})
        if tag in SIBLINGS:
            close(SIBLINGS[tag], FENCES.get(tag, set()))
        if tag == "body":
            close({"head"}, set())
        inside = stack[-1].main
        # A header or a title group inside the article is part of it.
        node = Node(tag, tag + label, tag in FURNITURE or tag == "header" and not inside or marked and tag not in ("html", "body", "article", "main"), inside or tag in ("article", "main"))
        stack[-1].children.append(node)
        if tag in VOID or m[3].rstrip().endswith("/") and tag in RAW:
            continue
        if tag in RAW:
            end = ENDS[tag].search(page, at)
            if end is None:
                at = n if tag in ("script", "style") else at
                continue
            stop = page.find(">", end.start())
            at = n if stop < 0 else stop + 1
            continue
        stack.append(node)
        open_tags[tag] += 1
    return root


def squeezed(text: str) -> str:
    return " ".join(html.unescape(text).split())


class Slot:
    """A run of like siblings: label, whether furniture, their own text's digest and length, and their children merged."""

    __slots__ = ("label", "furniture", "digest", "chars", "children")

    def __init__(self, label: str, furniture: bool):
        self.label, self.furniture, self.digest, self.chars, self.children = label, furniture, 0, 0, []


def collapse(nodes: list[Node]) -> list[Slot]:
    """Neighbouring siblings of one label become one slot, so alignment costs by kinds of siblings, not by their number."""
    forest: list[Slot] = []
    todo: list[tuple[list[Node], list[Slot]]] = [(nodes, forest)]
    while todo:
        siblings, out = todo.pop()
        groups: list[list[Node]] = []
        for node in siblings:
            if node.tag in RAW or node.tag in VOID:
                continue
            if out and out[-1].label == node.label:
                groups[-1].append(node)
                continue
            out.append(Slot(node.label, node.furniture))
            groups.append([node])
        for slot, members in zip(out, groups):
            inner: list[Node] = []
            for node in members:
                for child in node.children:
                    if isinstance(child, Node) and child.tag not in INLINE:
                        inner.append(child)
                    else:
                        text = child if isinstance(child, str) else inline_text(child)
                        if text and not text.isspace():
                            slot.digest = zlib.crc32(squeezed(text).encode("utf-8", "surrogatepass"), slot.digest)
                            slot.chars += len(text)
            # Children of all members are ordered by first occurrence, so that runs merge across members.
            first: dict[str, int] = {}
            inner.sort(key=lambda c: first.setdefault(c.label, len(first)))
            todo.append((inner, slot.children))
    return forest


def inline_text(node: Node) -> str:
    out, todo = [], [node]
    while todo:
        x = todo.pop()
        if isinstance(x, str):
            out.append(x)
        elif x.tag == "br":
            out.append(" ")
        elif not x.furniture and x.tag not in RAW:
            todo.extend(reversed(x.children))
    return "".join(out)


def align(a: list[Slot], b: list[Slot]) -> tuple[int, list[tuple[Slot, Slot]]]:
    """Simple tree matching of two forests: the size of the best match and its pairs of nodes.

    Pairs of forests are listed from the roots down and scored from the leaves up.
    """
    forests, inner = [(a, b)], []
    for x, y in forests:  # grows as pairs of equal labels are met
        below: dict[tuple[int, int], int] = {}
        for i, s in enumerate(x):
            for j, t in enumerate(y):
                if s.label == t.label:
                    below[i, j] = len(forests) if s.children and t.children else -1
                    if s.children and t.children:
                        forests.append((s.children, t.children))
        inner.append(below)
    scores, tables = [0] * len(forests), [None] * len(forests)
    for k in range(len(forests) - 1, -1, -1):
        x, y = forests[k]
        n, m = len(x), len(y)
        best = tables[k] = [[0] * (m + 1) for _ in range(n + 1)]
        below = inner[k]
        for i in range(n):
            row, up = best[i + 1], best[i]
            for j in range(m):
                most = up[j + 1] if up[j + 1] >= row[j] else row[j]
                if (at := below.get((i, j))) is not None:
                    most = max(most, up[j] + 1 + (scores[at] if at >= 0 else 0))
                row[j + 1] = most
        scores[k] = best[n][m]
    pairs, todo = [], [0]
    while todo:
        k = todo.pop()
        x, y = forests[k]
        best, below = tables[k], inner[k]
        i, j = len(x), len(y)
        while i and j:
            at = below.get((i - 1, j - 1))
            if at is not None and best[i][j] == best[i - 1][j - 1] + 1 + (scores[at] if at >= 0 else 0):
                pairs.append((x[i - 1], y[j - 1]))
                if at >= 0:
                    todo.append(at)
                i, j = i - 1, j - 1
            elif best[i][j] == best[i - 1][j]:
                i -= 1
            else:
                j -= 1
    return scores[0], pairs


def slots(forest: list[Slot]) -> Iterator[tuple[int, int, int, Slot, bool]]:
    """(path, parent's path, depth, slot, whether it is or lies in furniture) of all slots, parents first."""
    todo = [(s, 0, 1, False) for s in reversed(forest)]
    while todo:
        s, parent, depth, outside = todo.pop()
        path, outside = step(parent, s.label), outside or s.furniture
        yield path, parent, depth, s, outside
        todo.extend((c, path, depth + 1, outside) for c in reversed(s.children))


def packed(forest: list[Slot]) -> list:
    """Slots in pre-order, each with its number of children."""
    out = [len(forest)]
    todo = forest[::-1]
    while todo:
        s = todo.pop()
        out.append([s.label, s.furniture, s.digest, s.chars, len(s.children)])
        todo.extend(reversed(s.children))
    return out


def unpacked(data: list) -> list[Slot]:
    forest: list[Slot] = []
    open_: list[tuple[list[Slot], int]] = [(forest, data[0])]
    for label, furniture, digest, chars, children in data[1:]:
        while len(open_[-1][0]) == open_[-1][1]:
            open_.pop()
        s = Slot(label, furniture)
        s.digest, s.chars = digest, chars
        open_[-1][0].append(s)
        open_.append((s.children, children))
    return forest


#: A slot's place (path, parent's path, depth, label, furniture) and what is counted there.
Place = tuple[int, int, int, str, bool]


def votes(page: list[Slot], other: list[Slot] | None) -> Iterator[tuple[Place, tuple[int, int, int, int]]]:
    """Per slot: votes for constant and for varying, characters of varying and of constant text.

    A slot without text of its own votes neither way, nor does any of a page without another; its text counts as varying.
    """
    same = set() if other is None else {id(x) for x, y in align(page, other)[1] if x.digest == y.digest}
    for path, parent, depth, s, off in slots(page):
        place = (path, parent, depth, s.label, off)
        if not s.chars:
            yield place, (0, 0, 0, 0)
        elif id(s) in same:
            yield place, (1, 0, 0, s.chars)
        else:
            yield place, (0, int(other is not None), s.chars, 0)


def container(rows: list[tuple]) -> int:
    """The path of the outermost article or main around nine tenths of all varying text outside furniture; without one,
    of the deepest element that holds all of it.  ``rows`` holds a place and its four counts flat.
    """
    place: dict[int, tuple[int, int, str]] = {}
    mass: dict[int, int] = {}
    total = 0
    for path, parent, depth, label, off, _, _, chars, _ in rows:
        place[path] = (parent, depth, label)
        if chars and not off:
            mass[path] = mass.get(path, 0) + chars
            total += chars
    for path in sorted(place, key=lambda p: -place[p][1]):
        if path in mass and place[path][0]:
            mass[place[path][0]] = mass.get(place[path][0], 0) + mass[path]

    def deepest(least: float) -> int:
        return max((p for p, c in mass.items() if c >= least), key=lambda p: (place[p][1], p), default=0)

    def tag(path: int) -> str:
        return place[path][2].split(".")[0]

    at, outermost = deepest(0.9 * total), 0
    while at:
        outermost = at if tag(at) in ("article", "main") else outermost
        at = place[at][0]
    best = outermost or deepest(total)
    # A slot of blocks belongs to the element around it.
    while best and tag(best) not in ("article", "main", "section", "div", "body", "td", "html"):
        best = place[best][0]
    return best


def blocks(node: Node, path: int, template: frozenset[int], out: list[str]) -> None:
    """Appends the texts of a container's blocks in page order.  Of a template slot its own text is left out, not the blocks in it."""
    todo: list = [(node, path, False)]
    text: list[str] = []
    below = step if template else lambda at, label: 0

    def flush() -> None:
        joined = squeezed("".join(text))
        text.clear()
        if joined:
            out.append(joined)

    while todo:
        x, at, done = todo.pop()
        if isinstance(x, str):
            text.append(x)
            continue
        block = x.tag not in INLINE
        if done:
            flush()
            continue
        if x is not node and (x.furniture or x.tag in RAW):
            if block:
                flush()
            continue
        if x is not node and at in template:
            flush()
            todo.extend((c, below(at, c.label), False) for c in reversed(x.children) if isinstance(c, Node) and c.tag not in INLINE)
            continue
        if x.tag == "br":
            text.append(" ")
            continue
        if block:
            flush()
            todo.append((x, at, True))
        todo.extend((c, below(at, c.label) if isinstance(c, Node) else at, False) for c in reversed(x.children))
    flush()


def extract(page: str | None, where: int = 0, template: frozenset[int] = frozenset()) -> str:
    """Main text of one page.  Where the wrapper's container is missing, the page's own outermost articles and mains or its body stand in."""
    if not page:
        return ""
    root = parse(page)
    found: list[tuple[Node, int]] = []
    own: list[tuple[Node, int]] = []
    named = {"article": own, "main": own, "body": []}
    todo: list[tuple[Node, int]] = [(root, 0)]
    while todo:
        x, at = todo.pop()
        if where and at == where:
            found.append((x, at))
            continue
        if x.tag in named:
            named[x.tag].append((x, at))
        todo.extend((c, step(at, c.label)) for c in reversed(x.children) if isinstance(c, Node) and not c.furniture)
    if not found:
        found = next((v for v in named.values() if v), [(root, 0)])
        # In page order, so the elements inside one come behind it and are passed over.
        inner: set[int] = set()
        outer = []
        for x, at in found:
            if id(x) not in inner:
                outer.append((x, at))
                inner.update(map(id, _descendants(x)))
        found = outer
    out: list[str] = []
    for x, at in found:
        blocks(x, at, template, out)
    return "\n".join(out)


def _descendants(node: Node) -> Iterator[Node]:
    todo = [c for c in node.children if isinstance(c, Node)]
    while todo:
        x = todo.pop()
        yield x
        todo.extend(c for c in x.children if isinstance(c, Node))


def skeleton_of(page: str | None) -> list[Slot]:
    return collapse([c for c in parse(page or "").children if isinstance(c, Node)])


def host_of(url):
    return F.lower(F.coalesce(F.regexp_extract(url, r"^(?:[a-zA-Z][a-zA-Z0-9+.-]*:)?//(?:[^/?#@]*@)?([^/?#:]*)", 1), F.lit("")))


def induce(pages: DataFrame, salts: int = 64, constant_share: float = 0.8, least_pages: int = 8) -> DataFrame:
    """One row per host: host, container, template (paths of constant slots inside it).

    A host's pages are dealt over ``salts`` streams by a hash of the page id, and each is
    aligned with the one before it in its stream, so a task holds two skeletons at a time however
    large the host.  A stream's first page is aligned with the last of the stream before, the host's first
    with its last: on a host of any size every page votes, unless it is the only one.
    Slots are called template from ``least_pages`` votes on.
    """
    def skeleton(batches: Iterator[pa.RecordBatch]):
        for batch in batches:
            for i in range(0, batch.num_rows, 256):
                part = batch.slice(i, 256)
                rows = [json.dumps(packed(skeleton_of(h)), separators=(",", ":")) for h in part.column(3).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), part.column(2), pa.array(rows, pa.string())], ["host", "salt", "key", "skeleton"])

    names = ["host", "path", "parent", "depth", "label", "furniture", "constant", "varying", "chars", "same_chars"]

    def counted(cast: dict[tuple, list[int]]) -> pa.RecordBatch:
        cols = list(zip(*((host, *place, *counts) for (host, place), counts in cast.items()))) or [()] * 10
        kinds = [pa.string(), pa.int64(), pa.int64(), pa.int32(), pa.string(), pa.bool_(), *[pa.int64()] * 4]
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], names)

    def add(cast: dict[tuple, list[int]], host: str, page: list[Slot], other: list[Slot] | None) -> None:
        for place, counts in votes(page, other):
            now = cast.setdefault((host, place), [0, 0, 0, 0])
            for k, c in enumerate(counts):
                now[k] += c

    def pairwise(batches: Iterator[pa.RecordBatch]):
        before: tuple | None = None
        for batch in batches:
            for i in range(0, batch.num_rows, 256):
                part = batch.slice(i, 256)
                cast: dict[tuple, list[int]] = {}
                for host, salt, text in zip(*(part.column(c).to_pylist() for c in ("host", "salt", "skeleton"))):
                    page = unpacked(json.loads(text))
                    if before is not None and before[:2] == (host, salt):
                        add(cast, host, page, before[2])
                    before = (host, salt, page)
                yield counted(cast)

    def across(batches: Iterator[pa.RecordBatch]):
        for batch in batches:
            for i in range(0, batch.num_rows, 256):
                part = batch.slice(i, 256)
                cast: dict[tuple, list[int]] = {}
                for host, text, before in zip(*(part.column(c).to_pylist() for c in ("host", "first", "before"))):
                    add(cast, host, unpacked(json.loads(text)), None if before is None else unpacked(json.loads(before)))
                yield counted(cast)

    key = F.xxhash64("page_id", "url")
    rows = pages.select(host_of(F.col("url")).alias("host"), F.pmod(key, F.lit(salts)).cast("int").alias("salt"), key.alias("key"), F.col("html"))
    small = stored(rows.mapInArrow(skeleton, "host string, salt int, key long, skeleton string"), "skeletons")
    dealt = small.repartition("host", "salt").sortWithinPartitions("host", "salt", "key", "skeleton")
    # One row a stream, at most ``salts`` a host.
    page = F.struct("key", "skeleton")
    ends = small.groupBy("host", "salt").agg(F.min(page).alias("first"), F.max(page).alias("last"))
    by_host = Window.partitionBy("host").orderBy("salt")
    around = by_host.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    ends = ends.withColumn("before", F.coalesce(F.lag("last").over(by_host), F.last("last").over(around)))
    ends = ends.select("host", F.col("first.skeleton").alias("first"), F.when(F.col("before") != F.col("first"), F.col("before.skeleton")).alias("before"))
    schema = "host string, path long, parent long, depth int, label string, furniture boolean, constant long, varying long, chars long, same_chars long"
    cast = dealt.mapInArrow(pairwise, schema).unionByName(ends.mapInArrow(across, schema))
    cast = cast.groupBy(*names[:6]).agg(*[F.sum(c).alias(c) for c in names[6:]])

    def decide(frame):
        rows = list(frame[names[1:]].itertuples(index=False, name=None))
        where = container(rows)
        # Parents come before their children.
        within, held = {where}, []
        for r in sorted(rows, key=lambda r: r[2]):
            if r[1] in within and r[0] != where:
                within.add(r[0])
                if not r[4]:
                    held.append(r)
        inside = [r[0] for r in held if r[5] + r[6] >= least_pages and r[5] >= constant_share * (r[5] + r[6])]
        constant, varying, chars, same_chars = (sum(r[k] for r in held) for k in (5, 6, 7, 8))
        if constant > varying and same_chars > chars:
            inside = []  # mostly copies of one page: constancy says nothing about the template
        return frame.iloc[:1][["host"]].assign(container=where, template=[sorted(inside)])

    # A group is one host's distinct slots, not its pages.
    return stored(cast.groupBy("host").applyInPandas(decide, "host string, container long, template array<long>"), "wrappers")


#: Hosts up to which the wrappers are broadcast (a path and a few slots each); beyond, they are joined by shuffling.
BROADCAST_HOSTS = 200_000


def main_text(pages: DataFrame, wrappers: DataFrame | None = None) -> DataFrame:
    """page_id, url, text, n_chars of every row.

    Null or empty html gives the empty text; pages may be nested to any depth.  Pages without a usable url share
    one wrapper; a host's lone page is its own sample.  Rows that repeat a page are extracted alike.
    """
    wrappers = induce(pages) if wrappers is None else wrappers
    if wrappers.count() <= BROADCAST_HOSTS:
        wrappers = F.broadcast(wrappers)

    def run(batches: Iterator[pa.RecordBatch]):
        for batch in batches:
            for i in range(0, batch.num_rows, 256):
                part = batch.slice(i, 256)
                texts = [extract(h, w or 0, frozenset(() if t is None else t)) for h, w, t in zip(*(part.column(c).to_pylist() for c in ("html", "container", "template")))]
                yield pa.RecordBatch.from_arrays([part.column("page_id"), part.column("url"), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())], ["page_id", "url", "text", "n_chars"])

    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html", host_of(F.col("url")).alias("host"))
    return rows.join(wrappers, "host", "left").select("page_id", "url", "html", "container", "template").mapInArrow(run, "page_id long, url string, text string, n_chars long")
