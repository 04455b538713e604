"""HTML extraction: wrapper induction.

All different pages of a host take part: its wrapper is counted, not estimated. Pages are aligned as DOM trees by simple tree matching.
Siblings of one label are folded into one repeated node, so a tree has a node per label path, and two trees match in time about in
proportion to their nodes. Pages of one tree (a shape) align alike and are matched once. Shapes are taken in the order of what their trees
share with those of all pages of the host: one that matches a layout's centre well joins the first such layout, another is the centre of a
layout of its own, so a host may have several. Nodes whose text is the same on most different pages of a layout that have the node are
template, nodes whose text varies are slots. The wrapper of a host is the list of template texts by node path.

Induction sees every visible block, whatever its tag and names. The wrapper is then applied to each page of the host: blocks that are
template go. Of what varies, blocks in elements that by tag, role or class hold menus, adverts, forms, comments and the like go too.
Names are whole words of class, id or role; they never count on html, body, main and article, and neither tags nor names
count on an element that holds most of the host's varying text. Names don't count where they would leave a page empty.

``induce`` does this for pages in memory, ``wrappers`` for a table, with the same result. There no task holds a host: pages are told apart
by digests of their texts, shapes and texts are counted by combined sums, and shapes meet the centres in rounds, ``ROUND`` to ``ROUNDS`` shapes of each
host asked for new centres at a time until every shape has its layout. A shape is matched only with centres that share a node it can't do without. Texts are
exchanged as digests of 64 bits; those of the templates are read again from one page each. Every page is then
extracted, whole, in one pass without shuffling the html; wrappers are joined by host.

Defined results: null or empty html, or no content, give empty text. Pages without a host, and hosts with fewer than
``least`` different pages, use the rules on tags, roles and classes alone. Unclosed and misnested tags are repaired
as browsers do for p, li, td and the like. Repeated rows are extracted alike; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import html as entities
import json
import math
import re
from collections import Counter, defaultdict
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import Stored, store, table

VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: Elements whose content is no text of the page.
SILENT = frozenset("script style noscript template head title iframe object svg canvas math audio video".split())
#: Elements that are never part of an article.
ASIDE = frozenset("nav footer aside form button select option textarea input label menu dialog fieldset".split())
INLINE = frozenset(
    "a abbr acronym b bdi bdo big cite code data del dfn em font i img ins kbd mark q s samp small span strike strong sub sup time tt u var wbr br".split()
)
#: Words in class, id or role that name parts outside the article.
NAMED = frozenset(
    "ad ads advert adverts advertisement advertising banner sponsor sponsored promo promotion menu nav navbar navigation breadcrumb"
    " breadcrumbs sidebar aside footer masthead topbar toolbar cookie cookies consent notice notices alert gdpr popup modal"
    " overlay newsletter subscribe signup login share sharing social related recommended trending pagination pager"
    " comment comments respond disqus reply replies widget widgets search complementary contentinfo".split()
)
#: An open element of these ends before one of those; fixed values of the HTML parsing rules.
ENDS = {"p": None, "li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
HEADER = frozenset({"header", "hgroup"})
#: Elements that no name puts outside the article.
WHOLE = frozenset({"html", "body", "main", "article"})
#: End the label of an element that its name or its tag puts outside; parsed pages never hold them in a label.
ASIDE_BY_NAME, ASIDE_BY_TAG = "\0", "\1"
#: Of the elements that are never part of an article, those that stand inside a line.
CONTROLS = frozenset("button select option textarea input label".split())
#: A page belongs to a layout if it matches this share of the smaller tree; a text is template on this share of a node's pages.
SAME_LAYOUT, TEMPLATE = 0.5, 0.6
#: Shapes of a host asked for new centres in the first round and, at most, in a later one: eight times as many each round.
ROUND, ROUNDS = 16, 4096
#: Characters of shapes that meet the centres of a host in one group.
MEET = 1_000_000
#: Labels of a path: of elements nested deeper, the innermost count.
DEPTH = 64

_TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)"
    r"|<(?P<end>/?)(?P<tag>[a-zA-Z][^\s/>]*)(?P<attrs>(?:[^>=]++|=\s*+\"[^\"]*+\"|=\s*+'[^']*+'|=)*+)>",
    re.S,
)
_ATTR = re.compile(r"(class|id|role|hidden|aria-hidden|style)\s*(?:=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.I)
_SPACE = re.compile(r"\s+")


class Node:
    __slots__ = ("aside", "deep", "mark", "tag", "outside", "parts")

    def __init__(self, tag: str, mark: str = "", outside: bool = False, aside: str = ""):
        self.tag, self.mark, self.outside, self.aside = tag, mark, outside, aside
        self.deep = False  # holds a block
        self.parts: list[str | Node] = []


def _marks(attrs: str) -> tuple[str, bool, bool]:
    """A label of the element's class and id, whether it is hidden, and whether a name puts it outside the article."""
    if not attrs or attrs.isspace():
        return "", False, False
    label, outside, named = [], False, False
    for name, a, b, c in _ATTR.findall(attrs):
        value, name = (a or b or c).lower(), name.lower()
        if name == "hidden" or name == "aria-hidden" and value == "true" or name == "style" and "display:none" in value.replace(" ", ""):
            outside = True
        elif name in ("class", "id", "role"):
            if name != "role":
                label.append(re.sub(r"\d+", "#", value))
            named |= not NAMED.isdisjoint(value.split())
    return ".".join(label), outside, named


def parse(page: str) -> Node:
    """A lenient DOM: elements with their label, text kept in ``parts`` between child elements."""
    root = Node("#")
    stack, at, n = [root], 0, len(page)
    unclosed: set[str] = set()
    while at < n:
        m = _TOKEN.search(page, at)
        if not m:
            stack[-1].parts.append(page[at:])
            break
        if m.start() > at:
            stack[-1].parts.append(page[at : m.start()])
        at = m.end()
        tag = m["tag"]
        if not tag:
            continue
        tag = tag.lower()
        if m["end"]:
            for i in range(len(stack) - 1, 0, -1):
                if stack[i].tag == tag:
                    del stack[i:]
                    break
                if stack[i].tag in ("article", "body", "main", "table") and tag in INLINE:
                    break
            continue
        if tag in SILENT:
            if not m["attrs"].endswith("/"):
                close = None if tag in unclosed else re.compile(rf"</{re.escape(tag)}\s*>", re.I).search(page, at)
                if close:
                    at = close.end()
                    continue
                unclosed.add(tag)
                if tag in ("script", "style", "title", "noscript", "template", "iframe"):
                    at = n
            continue
        if tag not in INLINE:
            _close_before(stack, tag)
        label, outside, named = _marks(m["attrs"])
        node = Node(tag, label, outside, ASIDE_BY_TAG if tag in ASIDE else ASIDE_BY_NAME if named and tag not in WHOLE else "")
        if tag not in INLINE:
            for x in reversed(stack):
                if x.deep:
                    break
                x.deep = True
        stack[-1].parts.append(node)
        if tag not in VOID and not m["attrs"].endswith("/"):
            stack.append(node)
    return root


def _close_before(stack: list[Node], tag: str) -> None:
    """Ends what a new block ends: an open paragraph with its inline elements, or an item of the same list."""
    for i in range(len(stack) - 1, 0, -1):
        open_ = stack[i].tag
        if open_ == "p" or tag in (ENDS.get(open_) or ()):
            del stack[i:]
            return
        if open_ not in INLINE:
            return


def _inline_text(node: Node) -> list[str]:
    out: list[str] = []
    work: list[str | Node] = [node]
    while work:
        x = work.pop()
        if isinstance(x, str):
            out.append(x)
        elif x.outside or x.tag == "br":
            out.append(" ")
        else:
            work += reversed(x.parts)
    return out


def blocks(root: Node) -> list[tuple[tuple[str, ...], str]]:
    """(path, text) of each visible block of text in page order; labels tell what lies outside articles by tag or name."""
    out: list[tuple[tuple[str, ...], str]] = []
    held: list[str] = []
    made: dict[int, tuple[str, ...]] = {}

    def written(path: tuple | None) -> tuple[str, ...]:
        """The labels along a path, once for each element."""
        chain, known = [], ()
        while path:
            if id(path) in made:
                known = made[id(path)]
                break
            chain.append(path)
            path = path[0]
        for x in reversed(chain):
            known = made[id(x)] = (*known[-(DEPTH - 1):], x[1])
        return known

    def flush(path: tuple | None) -> None:
        text = _SPACE.sub(" ", entities.unescape("".join(held))).strip()
        held.clear()
        if text:
            out.append((written(path), text))

    # depth first without recursion: pages may be nested deeper than Python's stack
    # a path is (path of the parent, label, whether inside an article)
    kept_alive: list[tuple] = []  # ids of paths stay theirs
    work: list[tuple] = [("open", root, None)]
    while work:
        what, node, path = work.pop()
        if what == "text":
            held.append(node)
        elif what == "flush":
            flush(path)
        else:
            if node.outside or node.tag == "br":
                held.append(" ")
                continue
            inside = bool(path and path[2])
            aside = ASIDE_BY_TAG if node.tag in HEADER and not inside else node.aside
            in_line = node.tag in INLINE or node.tag in CONTROLS
            inline = (in_line and not (aside and node.deep)) or node is root
            label = (f"{node.tag}.{node.mark}" if node.mark else node.tag).replace(ASIDE_BY_NAME, "").replace(ASIDE_BY_TAG, "") + aside
            if inline and aside:  # apart from the text around it, which goes on
                around, held[:] = held[:], _inline_text(node)
                kept_alive.append((path, label, inside))
                flush(kept_alive[-1])
                held[:] = [*around, " "]
                continue
            here = path if inline else (path, label, inside or node.tag in ("article", "main"))
            if not inline:
                kept_alive.append(here)
                flush(path)
                work.append(("flush", None, here))
            for part in reversed(node.parts):
                work.append(("text", part, here) if isinstance(part, str) else ("open", part, here))
    flush(None)
    return out


def _digest(text: str) -> int:
    """64 bits of a text, signed."""
    return int.from_bytes(hashlib.blake2b(text.encode(), digest_size=8).digest(), "little", signed=True)


class Tree:
    """A DOM tree reduced for alignment: blocks only, siblings of one label folded into one repeated node; ``at`` is the place of its path."""

    __slots__ = ("at", "children", "label")

    def __init__(self, label: str):
        self.label, self.at = label, -1
        self.children: dict[str, Tree] = {}


def shape_of(found: list[tuple[tuple[str, ...], str]]) -> str:
    """The different paths of a page's blocks in page order, as text: of each the number of labels shared with the one before, and the rest."""
    coded, before = [], ()
    for path in dict.fromkeys(p for p, _ in found):
        n = 0
        while n < len(path) and n < len(before) and path[n] == before[n]:
            n += 1
        coded.append([n, *path[n:]])
        before = path
    return json.dumps(coded, separators=(",", ":"))


def _items(found: list[tuple[tuple[str, ...], str]]) -> Counter:
    """Characters of each text of a page at each place among its different paths."""
    place = {p: k for k, p in enumerate(dict.fromkeys(p for p, _ in found))}
    out: Counter = Counter()
    for p, t in found:
        out[place[p], t] += len(t)
    return out


class Shape:
    """What pages of one tree share: their paths, the tree and a digest for each of its nodes."""

    __slots__ = ("id", "nodes", "paths", "tree")

    def __init__(self, coded: str):
        self.id, self.tree = _digest(coded), Tree("#")
        self.paths: list[tuple[str, ...]] = []
        self.nodes = {(): 0}
        before: tuple[str, ...] = ()
        for n, *rest in json.loads(coded):
            before = (*before[:n], *rest)
            node, known = self.tree, 0
            for depth, label in enumerate(before, 1):
                if label not in node.children:
                    node.children[label] = Tree(label)
                    self.nodes[before[:depth]] = _digest(f"{known}/{label}")
                node, known = node.children[label], self.nodes[before[:depth]]
            node.at = len(self.paths)
            self.paths.append(before)

    def needed(self) -> list[int]:
        """Nodes of which a match with a tree at least as large holds one: so many, the deepest, that the others are too few for it."""
        return [self.nodes[p] for p in sorted(self.nodes, key=len)[math.ceil(SAME_LAYOUT * len(self.nodes)) - 1 :]]

    def aligned(self, centre: Shape) -> list[int] | None:
        """The places of the paths that match nodes of the centre; None if too few do."""
        size, pairs = match(centre.tree, self.tree)
        if self.id != centre.id and (size <= 1 or size < SAME_LAYOUT * min(len(self.nodes), len(centre.nodes))):
            return None
        return [y.at for _, y in pairs if y.at >= 0]


def _heaviest(order: list[tuple[int, int]]) -> list[int]:
    """Indices of the heaviest subsequence of (place, weight) with rising places."""
    rank = {p: i + 1 for i, p in enumerate(sorted(p for p, _ in order))}
    best = [(0, -1)] * (len(order) + 1)  # a tree of prefix maxima over places: weight, last index
    before = []
    for i, (place, weight) in enumerate(order):
        at, top = rank[place] - 1, (0, -1)
        while at:
            top = max(top, best[at])
            at &= at - 1
        before.append(top[1])
        at, mine = rank[place], (top[0] + weight, i)
        while at < len(best):
            best[at] = max(best[at], mine)
            at += at & -at
    at, top = len(order), (0, -1)
    while at:
        top = max(top, best[at])
        at &= at - 1
    i, out = top[1], []
    while i >= 0:
        out.append(i)
        i = before[i]
    return out[::-1]


def match(a: Tree, b: Tree) -> tuple[int, list[tuple[Tree, Tree]]]:
    """Simple tree matching: size of the largest top-down, order-keeping mapping of equal labels, and the mapping.

    Labels are unique among siblings, so the children that can match are known, and the best order-keeping choice is a
    heaviest rising subsequence. Without recursion: pages are nested as deep as they like.
    """
    if a.label != b.label:
        return 0, []
    pairs: list[tuple[Tree, Tree, list[int]]] = []
    work: list[tuple[Tree, Tree, int]] = [(a, b, -1)]
    while work:
        x, y, parent = work.pop()
        if parent >= 0:
            pairs[parent][2].append(len(pairs))
        pairs.append((x, y, []))
        work += [(c, y.children[label], len(pairs) - 1) for label, c in reversed(x.children.items()) if label in y.children]
    size, chosen = [1] * len(pairs), [[] for _ in pairs]
    for i in range(len(pairs) - 1, -1, -1):
        _, y, below = pairs[i]
        if below:
            place = {label: k for k, label in enumerate(y.children)}
            rise = _heaviest([(place[pairs[j][0].label], size[j]) for j in below])
            chosen[i] = [below[k] for k in rise]
            size[i] += sum(size[j] for j in chosen[i])
    found, walk = [], [0]
    while walk:
        i = walk.pop()
        found.append(pairs[i][:2])
        walk += reversed(chosen[i])
    return size[0], found


def _aside(path: tuple[str, ...], marks: str, kept: Iterable[str]) -> bool:
    return any(x[-1] in marks and "/".join(path[: i + 1]) not in kept for i, x in enumerate(path))


def _unnamed(found: list[tuple[tuple[str, ...], str]], kept: Iterable[str] = ()) -> list[tuple[tuple[str, ...], str]]:
    """The blocks in no element that its tag or name puts outside, but for elements at the paths ``kept``; names don't count if none is left."""
    both = [(p, t) for p, t in found if not _aside(p, ASIDE_BY_NAME + ASIDE_BY_TAG, kept)]
    return both or [(p, t) for p, t in found if not _aside(p, ASIDE_BY_TAG, kept)]


#: Of a page, each node counts for this over the tree's size: whole numbers, so that sums don't depend on their order.
_SHARE = 1_000_000


class Centres:
    """Centres in their order, found by nodes: of the smaller tree, those it can't do without in a match meet any node of the other."""

    def __init__(self, shapes: Iterable[Shape] = ()):
        self.all: list[Shape] = []
        self.by_node: dict[int, list[int]] = defaultdict(list)
        self.by_needed: dict[int, list[int]] = defaultdict(list)
        for x in shapes:
            self.add(x)

    def add(self, x: Shape) -> None:
        for v in x.nodes.values():
            self.by_node[v].append(len(self.all))
        for v in x.needed():
            self.by_needed[v].append(len(self.all))
        self.all.append(x)

    def first(self, x: Shape) -> tuple[Shape, list[int]] | None:
        """The first centre that a shape matches, and the places of the paths that match."""
        near = {k for v in x.needed() for k in self.by_node.get(v, ())}
        near.update(k for v in x.nodes.values() for k in self.by_needed.get(v, ()))
        for k in sorted(near):
            if (places := x.aligned(self.all[k])) is not None:
                return self.all[k], places
        return None


def leaders(shapes: list[Shape]) -> Centres:
    """The centres among shapes in their order: those that match no centre before them."""
    out = Centres()
    for x in shapes:
        if out.first(x) is None:
            out.add(x)
    return out


def _asides(path: tuple[str, ...]) -> list[str]:
    """The paths of the elements around a block that tag or name puts outside."""
    return ["/".join(path[: i + 1]) for i, x in enumerate(path) if x[-1] in ASIDE_BY_NAME + ASIDE_BY_TAG]


def induce(pages: list[str], least: int = 4) -> dict | None:
    """The wrapper of a host from its pages; None if too few differ."""
    different: dict[str, tuple] = {}
    for page in pages:
        if found := blocks(parse(page)):
            coded, key = shape_of(found), "\n".join(t for _, t in found)
            this = (_digest(coded), [k for k, _ in _items(found)], coded, found)
            different[key] = min(different.get(key, this), this, key=lambda x: x[:2])
    if len(different) < least:
        return None
    number = Counter(coded for _, _, coded, _ in different.values())
    shapes = {coded: Shape(coded) for coded in number}
    weight: Counter = Counter()
    for coded, x in shapes.items():
        for node in x.nodes.values():
            weight[node] += number[coded] * _SHARE // len(x.nodes)
    centres = leaders(sorted(shapes.values(), key=lambda x: (-sum(weight[v] for v in x.nodes.values()), x.id)))
    layout: dict[str, tuple[int, list[int]]] = {}
    for coded, x in shapes.items():
        centre, places = centres.first(x)
        layout[coded] = centre.id, places
    of = Counter()
    for coded, n in number.items():
        of[layout[coded][0]] += n
    if max(of.values()) < least:
        return None
    seen, times, chars = Counter(), Counter(), Counter()
    for _, _, coded, found in different.values():
        centre, places = layout[coded]
        if of[centre] >= least:
            held = {shapes[coded].paths[k] for k in places}
            seen.update((centre, p) for p in held)
            times.update({(centre, p, t) for p, t in found if p in held})
            for p, t in found:
                if p in held:
                    chars[centre, p, t] += len(t)
    template: dict[str, set[str]] = {}
    varying, all_ = Counter(), 0
    for (centre, p, t), n in times.items():
        if n >= least and n >= TEMPLATE * seen[centre, p]:
            template.setdefault("/".join(p), set()).add(t)
        else:
            all_ += chars[centre, p, t]
            for x in _asides(p):
                varying[x] += chars[centre, p, t]
    return _wrapper(template, [p for p, n in varying.items() if 2 * n > all_])


def _wrapper(template: dict[str, set[str]], kept: Iterable[str]) -> dict:
    return {"template": {p: sorted(t) for p, t in sorted(template.items())}, "kept": sorted(kept)}


def removed(page: str | None, wrapper: dict | None) -> dict[str, int]:
    """How many of a page's blocks the wrapper removes, how many of the others tags and names remove, and how many stay."""
    found = blocks(parse(page or ""))
    template = wrapper["template"] if wrapper else {}
    left = [(p, t) for p, t in found if t not in template.get("/".join(p), ())]
    stay = len(_unnamed(left, wrapper["kept"] if wrapper else ()))
    return {"template": len(found) - len(left), "aside": len(left) - stay, "kept": stay}


def extract(page: str | None, wrapper: dict | None = None) -> str:
    """The content of a page: its blocks, one a line."""
    if not page:
        return ""
    found = blocks(parse(page))
    if wrapper:
        template = wrapper["template"]
        left = [(p, t) for p, t in found if t not in template.get("/".join(p), ())]
        return "\n".join(t for _, t in _unnamed(left, wrapper["kept"]))
    found = _unnamed(found)
    main = [(p, t) for p, t in found if any(x.split(".")[0] in ("article", "main") for x in p)]
    return "\n".join(t for _, t in (main or found))


_PAGES = "host string, key binary, shape long, coded string, at array<int>, text array<long>, chars array<long>, ref long"


def _different(pages: DataFrame) -> DataFrame:
    """For each different page of a host its shape, its texts as digests with place and characters, and a digest of its html."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows: list[tuple] = []
            for host, page, ref in zip(*(batch.column(c).to_pylist() for c in ("host", "html", "ref")), strict=True):
                if not (found := blocks(parse(page))):
                    continue
                coded = shape_of(found)
                chars = _items(found)
                key = hashlib.blake2b("\n".join(t for _, t in found).encode(), digest_size=16).digest()
                rows.append((host, key, _digest(coded), coded, [k for k, _ in chars], [_digest(t) for _, t in chars], list(chars.values()), ref))
            kinds = [pa.string(), pa.binary(), pa.int64(), pa.string(), pa.list_(pa.int32()), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.int64()]
            columns = zip(*rows, strict=True) if rows else [()] * len(kinds)
            names = ["host", "key", "shape", "coded", "at", "text", "chars", "ref"]
            yield pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(columns, kinds, strict=True)], names)

    rest = F.struct("shape", "at", "text", "ref", "coded", "chars")
    read = pages.where("host is not null and html is not null").select("host", "html", F.xxhash64("html").alias("ref"))
    return read.mapInArrow(run, _PAGES).groupBy("host", "key").agg(F.min(rest).alias("m")).select("host", "m.*")


def _scored(shapes: DataFrame) -> DataFrame:
    """Shapes with what their trees share with those of all pages of the host."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            nodes = [list(Shape(c).nodes.values()) for c in batch.column("coded").to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [batch.column("host"), batch.column("shape"), batch.column("n"), pa.array(nodes, pa.list_(pa.int64()))], ["host", "shape", "n", "nodes"]
            )

    of = shapes.select("host", "shape", "n", "coded").mapInArrow(run, "host string, shape long, n long, nodes array<long>")
    each = of.select("host", "shape", F.expr(f"n * {_SHARE} div size(nodes)").alias("share"), F.explode("nodes").alias("node"))
    weight = each.groupBy("host", "node").agg(F.sum("share").alias("weight"))
    score = each.join(weight, ["host", "node"]).groupBy("host", "shape").agg(F.sum("weight").alias("score"))
    return shapes.join(score, ["host", "shape"])


_LAID = "host string, shape long, n long, coded string, score long, centre long, paths array<string>, asides array<array<string>>"


def _laid_out(shapes: DataFrame) -> list[Stored]:
    """Shapes with the centre of their layout and, where they match it, their paths: a table a round, null centres go on to the next."""

    def lead(group):
        rows = sorted(zip(*(group.column(c).to_pylist() for c in ("score", "shape", "coded")), strict=True), key=lambda x: (-x[0], x[1]))
        coded = {x: c for _, x, c in rows}
        found = [coded[x.id] for x in leaders([Shape(c) for c in coded.values()]).all]
        return pa.table({"host": pa.array([group.column("host")[0].as_py()] * len(found), pa.string()), "place": range(len(found)), "coded": found})

    def meet(group, asked):
        rows = sorted(zip(asked.column("place").to_pylist(), asked.column("coded").to_pylist(), strict=True))
        centres = Centres(Shape(c) for _, c in rows)
        laid: list[tuple] = []
        for coded in group.column("coded").to_pylist():
            x = Shape(coded)
            centre, places = centres.first(x) or (None, ())
            held = set(places)
            paths = ["/".join(p) if k in held else None for k, p in enumerate(x.paths)] if held else []
            laid.append((centre.id if centre else None, paths, [_asides(p) for p in x.paths] if held else []))
        made = zip(*laid, strict=True) if laid else [()] * 3
        kinds = [pa.int64(), pa.list_(pa.string()), pa.list_(pa.list_(pa.string()))]
        columns = {c: group.column(c) for c in ("host", "shape", "n", "coded", "score")}
        return pa.table(columns | {c: pa.array(list(v), k) for c, v, k in zip(("centre", "paths", "asides"), made, kinds, strict=True)})

    out, left, size = [], shapes, ROUND
    best = Window.partitionBy("host").orderBy(F.desc("score"), "shape")
    while True:
        asked = left.select("host", "shape", "coded", "score", F.row_number().over(best).alias("rank")).where(F.col("rank") <= size)
        centres = asked.groupBy("host").applyInArrow(lead, "host string, place long, coded string")
        groups = left.groupBy("host").agg((F.sum(F.length("coded")) / MEET + 1).cast("long").alias("groups"))
        dealt = left.join(groups, "host").withColumn("group", F.expr("pmod(shape, groups)")).drop("groups")
        told = centres.join(groups, "host").withColumn("group", F.explode(F.sequence(F.lit(0).cast("long"), F.col("groups") - 1))).drop("groups")
        met = dealt.groupBy("host", "group").cogroup(told.groupBy("host", "group")).applyInArrow(meet, _LAID)
        out.append(store(met, "wrap-layouts"))
        left, size = out[-1].df.where("centre is null").select("host", "shape", "n", "coded", "score"), min(8 * size, ROUNDS)
        if left.isEmpty():
            return out


def _texts(pages: DataFrame) -> DataFrame:
    """host, digest and text of every block."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [(h, t) for h, page in zip(*(batch.column(c).to_pylist() for c in ("host", "html")), strict=True) for _, t in blocks(parse(page))]
            columns = [pa.array([h for h, _ in rows], pa.string()), pa.array([_digest(t) for _, t in rows], pa.int64()), pa.array([t for _, t in rows], pa.string())]
            yield pa.RecordBatch.from_arrays(columns, ["host", "text", "words"])

    return pages.select("host", "html").mapInArrow(run, "host string, text long, words string").distinct()


def wrappers(pages: DataFrame, least: int = 4) -> DataFrame:
    """host and its wrapper as JSON, for hosts where one can be induced, from all of their pages: stored."""
    different = store(_different(pages), "wrap-pages")
    counted = different.df.groupBy("host", "shape").agg(F.count(F.lit(1)).alias("n"), F.max("coded").alias("coded"))
    enough = different.df.groupBy("host").count().where(F.col("count") >= least).select("host")
    shapes = store(counted.join(enough, "host", "left_semi"), "wrap-shapes")
    scored = store(_scored(shapes.df), "wrap-scores")
    rounds = _laid_out(scored.df)
    laid = rounds[0].df
    for x in rounds[1:]:
        laid = laid.union(x.df)
    laid = laid.where("centre is not null")
    large = laid.groupBy("host", "centre").agg(F.sum("n").alias("of")).where(F.col("of") >= least).select("host", "centre")
    node = F.transform("paths", lambda p: F.when(p.isNotNull(), F.xxhash64("host", "centre", p)))
    laid = laid.join(large, ["host", "centre"], "left_semi").select("host", "shape", "n", "paths", "asides", node.alias("nodes"))
    each = laid.select("host", "n", F.explode(F.arrays_zip("nodes", "paths", "asides")).alias("x")).select("host", "n", "x.*").where("nodes is not null")
    nodes = store(each.groupBy("host", F.col("nodes").alias("node"), F.col("paths").alias("path"), "asides").agg(F.sum("n").alias("seen")), "wrap-nodes")

    places = different.df.join(laid.select("host", "shape", "nodes"), ["host", "shape"])
    places = places.select("ref", F.transform("at", lambda k: F.get("nodes", k)).alias("node"), "text", "chars")
    items = places.select("ref", F.explode(F.arrays_zip("node", "text", "chars")).alias("x"))
    times = items.select("ref", "x.*").where("node is not null").groupBy("node", "text").agg(
        F.count(F.lit(1)).alias("times"), F.sum("chars").alias("chars"), F.min("ref").alias("ref")
    )
    constant = (F.col("times") >= least) & (F.col("times") >= TEMPLATE * F.col("seen"))
    told = times.join(nodes.df.select("node", "seen"), "node").select("node", F.when(constant, F.col("text")).alias("text"), "chars", "ref")
    told = store(told.groupBy("node", "text").agg(F.sum("chars").alias("chars"), F.min("ref").alias("ref")), "wrap-texts")

    found = told.df.where("text is not null").join(nodes.df, "node").select("host", "path", "text", "ref")
    hashed = pages.where("host is not null").select("host", "html", F.xxhash64("html").alias("ref"))
    one = hashed.join(found.select("host", "ref").distinct(), ["host", "ref"], "left_semi").dropDuplicates(["host", "ref"])
    template = found.join(_texts(one), ["host", "text"]).select("host", "path", "words")
    vary = told.df.where("text is null").join(nodes.df, "node").select("host", "asides", "chars")
    all_ = vary.groupBy("host").agg(F.sum("chars").alias("all"))
    outside = vary.select("host", F.explode("asides").alias("path"), "chars").groupBy("host", "path").agg(F.sum("chars").alias("n"))
    kept = outside.join(all_, "host").where(2 * F.col("n") > F.col("all")).select("host", "path", F.lit(None).cast("string").alias("words"))
    hosts = nodes.df.select("host", F.lit(None).cast("string").alias("path"), F.lit(None).cast("string").alias("words")).distinct()

    def run(group):
        template: dict[str, set[str]] = {}
        kept = []
        for path, text in zip(group.column("path").to_pylist(), group.column("words").to_pylist(), strict=True):
            if text is not None:
                template.setdefault(path, set()).add(text)
            elif path is not None:
                kept.append(path)
        return pa.table({"host": group.column("host")[:1], "wrapper": pa.array([json.dumps(_wrapper(template, kept))], pa.string())})

    out = store(hosts.union(template).union(kept).groupBy("host").applyInArrow(run, "host string, wrapper string"), "wrap-found")
    for x in (different, shapes, scored, *rounds, nodes, told):
        x.drop()
    return out.df


def extract_pages(pages: DataFrame, least: int = 4) -> DataFrame:
    """page_id, url, text and n_chars of every page."""
    host = F.lower(F.regexp_extract("url", r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]+)", 1))
    hosted = pages.select("page_id", "url", "html", F.when(host != "", host).alias("host"))
    found = wrappers(hosted, least)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[str, dict] = {}
        for batch in batches:
            texts = []
            for page, w in zip(batch.column("html").to_pylist(), batch.column("wrapper").to_pylist(), strict=True):
                if w is not None and w not in known:
                    if len(known) > 10_000:
                        known.clear()
                    known[w] = json.loads(w)
                texts.append(extract(page, known.get(w) if w is not None else None))
            yield pa.RecordBatch.from_arrays(
                [batch.column("page_id"), batch.column("url"), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())],
                ["page_id", "url", "text", "n_chars"],
            )

    joined = hosted.join(found, "host", "left").select("page_id", "url", "html", "wrapper")
    return joined.mapInArrow(run, "page_id long, url string, text string, n_chars long")


def op5_wrapper_induction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_pages(table(spark, sf_dir, "pages"))
