"""Main text of web pages by wrapper induction over pages of one host.

Each host has a reference page, a typical one of its pages. Every page of the host is parsed to a tree and
aligned with the reference by simple tree matching: two elements match if their names agree, and their
children are matched in order so that the number of matched elements is largest. Over all pages each line
of text of a reference node gathers on how many pages it was matched, how many different texts stood there,
how often the most frequent one, and how much text. A line whose text recurs is template, one whose text
differs from page to page is a slot.

The wrapper of a host has three parts. Its container is found by descending from the body while one element
holds most of the slots' text. Its constants are the lines inside the container that are the same on
nearly all of at least LEAST pages, while others there vary and they are no more than half of the text: they are template
too, and are left out wherever the same element has that very text. And it names those elements whose names sound like boilerplate, but
which hold the page's headline and most of the slots: there the data overrule the names. A page's text
is what stands in the container without the constants. Reader comments, rotating adverts and the like vary as articles
do, so inside the container, and on hosts with too few pages to tell, elements and names decide.

Alignment first takes off equal subtrees at both ends of the child lists, where matching them is best
anyway, so its cost is near linear on pages of one template. It keeps its own stack, so depth does not
matter; lists for which the pairs of one page would exceed CELLS are aligned along the subtrees of a shape
that occurs once in both, in order, and between those by name in order. Only counts per line of the reference
leave a task; a frequent host is spread over tasks as its pages are.

Defined cases: null HTML counts as empty and has empty text; pages that lack the wrapper's container are
read in their first article or main element, else in their body; a null URL's host is empty; unclosed and
misnested elements are closed where their parents end; nodes nested deeper than DEPTH take no part in
the induction but in the text; repeated pages are rows of their own; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import html as entities
import json
import re
from bisect import bisect_left
from collections import Counter, defaultdict
from collections.abc import Callable, Collection, Iterator
from operator import attrgetter

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stored
from .urlfilter import host_of

#: Bytes of reference pages or wrappers up to which they travel to every executor; salts of the join beyond it.
BROADCAST_BYTES, SALTS = 16 << 20, 64
#: Pairs of children that are weighed for one page; levels of nesting that the induction looks at.
CELLS, DEPTH = 250_000, 100
#: Pages that it takes to call a line constant, and the share of them that must agree.
LEAST, AGREE = 5, 0.9

# Element classes of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript template iframe".split())
BLOCK = frozenset("address article aside blockquote body center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html li main nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
CLOSES_P = BLOCK - frozenset("body html td th tr tbody thead tfoot li dd dt summary".split())
CONTAINER = frozenset("body div section main article center table tbody tr td".split())
BOILERPLATE = frozenset("head nav header footer aside form script style noscript template iframe button select input textarea svg canvas object audio video menu dialog title".split())
NAMES = frozenset("ad ads advert advertisement advertising banner sponsor sponsored promo cookie cookies consent gdpr notice popup modal overlay newsletter subscribe signup sidebar side-bar menu nav navbar navigation breadcrumb breadcrumbs header footer masthead comments comment comment-list respond disqus share sharing social related recommended widget toolbar skip pagination pager".split())
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert menu menubar".split())

TOKEN = re.compile(r"<!--.*?(?:-->|$)|<[!?][^>]*>?|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>|<", re.S)
ATTRIBUTE = re.compile(r"""([a-zA-Z_:][-\w:.]*)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'=<>`]+)))?""")


class Node:
    __slots__ = ("tag", "names", "kids", "parts", "shape", "whole", "size")

    def __init__(self, tag: str, attributes: str = ""):
        self.tag, self.kids, self.parts = tag, [], []  # kids: elements; parts: elements and texts in order
        self.names: frozenset[str] = frozenset()
        if attributes.strip():
            got = {m[1].lower(): next((x for x in m.groups()[1:] if x is not None), "") for m in ATTRIBUTE.finditer(attributes)}
            names = set(f"{got.get('class', '')} {got.get('id', '')}".lower().split())
            if got.get("role", "").lower() in ROLES:
                names.add("nav")
            if "hidden" in got or got.get("aria-hidden") == "true" or "display:none" in got.get("style", "").replace(" ", "").lower():
                names.add("popup")
            self.names = frozenset(names)
        self.shape = self.whole = self.size = 0

    def seal(self) -> None:
        """Sizes, shapes, and shapes with texts of all subtrees, children first."""
        order, stack = [], [self]
        while stack:
            node = stack.pop()
            order.append(node)
            stack.extend(node.kids)
        for node in reversed(order):
            node.size = 1 + sum(k.size for k in node.kids)
            node.shape = hash((node.tag, node.names, tuple(k.shape for k in node.kids)))
            node.whole = hash((node.tag, node.names, tuple(p if isinstance(p, str) else p.whole for p in node.parts)))

    @property
    def named(self) -> bool:
        """Whether its names sound like boilerplate."""
        return bool(self.names) and any(n in NAMES or not NAMES.isdisjoint(re.split(r"[-_]", n)) for n in self.names) and self.tag not in ("html", "body", "article", "main")

    @property
    def boilerplate(self) -> bool:
        return self.tag in BOILERPLATE or self.named


def parse(source: str) -> Node:
    """A forgiving parser: implied ends of p, li, table cells and the like; raw text of scripts and styles is skipped."""
    root = Node("html")
    stack, at, n = [root], 0, len(source)
    match = TOKEN.search
    opened: Counter[str] = Counter()  # what is open, so that a search in vain costs nothing

    def leave(k: int) -> None:
        for node in stack[k:]:
            opened[node.tag] -= 1
        del stack[k:]

    while at < n:
        m = match(source, at)
        end = m.start() if m else n
        if end > at:
            stack[-1].parts.append(source[at:end])
        if not m:
            break
        at = m.end()
        if m[2] is None:
            if m[0] == "<":
                stack[-1].parts.append("<")
            continue
        tag = m[2].lower()
        if m[1]:
            for k in range(len(stack) - 1 if opened[tag] else 0, 0, -1):
                if stack[k].tag == tag:
                    leave(k)
                    break
                if stack[k].tag in ("td", "th", "table") and tag not in ("table", "tr", "td", "th", "tbody", "thead", "tfoot", "body", "html"):
                    break
            else:
                if tag == "p":
                    stack[-1].parts.append("\n")
            continue
        if tag == "html":
            continue
        implied = {"p"} if tag in CLOSES_P else set()
        scope = {"li": ({"li"}, {"ul", "ol"}), "dd": ({"dd", "dt"}, {"dl"}), "dt": ({"dd", "dt"}, {"dl"}), "option": ({"option"}, {"select"}), "tr": ({"tr", "td", "th"}, {"table"}), "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "body": ({"head"}, set())}.get(tag)
        if implied and opened["p"]:
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].tag == "p":
                    leave(k)
                    break
                if stack[k].tag in BLOCK:
                    break
        if scope and any(opened[x] for x in scope[0]):
            for k in range(len(stack) - 1, 0, -1):
                if stack[k].tag in scope[0]:
                    leave(k)
                    break
                if stack[k].tag in scope[1]:
                    break
        node = Node(tag, m[3] or "")
        stack[-1].kids.append(node)
        stack[-1].parts.append(node)
        if tag in RAW:
            close = re.compile(rf"</{tag}\b[^>]*>", re.I).search(source, at)
            at = close.end() if close else n
        elif tag not in VOID and not (m[3] or "").endswith("/"):
            stack.append(node)
            opened[tag] += 1
    root.seal()
    return root


def matched(a: Node, b: Node) -> list[tuple[Node, Node]]:
    """Pairs of a largest simple tree matching of two trees with equal roots, in document order of a."""
    aligner = _Aligner()
    out: list[tuple[Node, Node]] = []
    stack = [(a, b)]
    while stack:
        x, y = stack.pop()
        out.append((x, y))
        stack.extend(reversed(_run(aligner.children(x.kids, y.kids))))
    return out


def _run(task: Iterator):
    """Run a generator that yields generators whose results it waits for: recursion with a stack of its own."""
    stack, value = [task], None
    while stack:
        try:
            stack.append(stack[-1].send(value))
            value = None
        except StopIteration as end:
            stack.pop()
            value = end.value
    return value


class _Aligner:
    """Alignments of children, and the sizes of largest matchings they rest on, for one pair of pages."""

    def __init__(self):
        self.memo: dict[tuple[int, int], int] = {}
        self.cells = CELLS

    def weight(self, x: Node, y: Node):
        """Elements in a largest matching of two subtrees."""
        if x.tag != y.tag:
            return 0
        if x.shape == y.shape:
            return x.size
        if not x.kids or not y.kids:
            return 1
        key = (id(x), id(y))
        if key not in self.memo:
            total = 1
            for p, q in (yield self.children(x.kids, y.kids)):
                total += yield self.weight(p, q)
            self.memo[key] = total
        return self.memo[key]

    def children(self, xs: list[Node], ys: list[Node]):
        # a largest matching pairs equal subtrees at the ends; where there is a choice, those with equal texts come first
        head, tail, most = 0, 0, min(len(xs), len(ys))
        for key in ("whole", "shape"):
            same = attrgetter(key)
            while head < most - tail and same(xs[head]) == same(ys[head]):
                head += 1
            while tail < most - head and same(xs[-1 - tail]) == same(ys[-1 - tail]):
                tail += 1
        p, q = xs[head : len(xs) - tail], ys[head : len(ys) - tail]
        middle: list[tuple[Node, Node]] = []
        if p and q:
            if len(p) * len(q) <= self.cells:
                self.cells -= len(p) * len(q)
                middle = yield self.best(p, q)
            else:
                middle = _in_order(p, q)
        return [*zip(xs[:head], ys[:head]), *middle, *(zip(xs[len(xs) - tail :], ys[len(ys) - tail :]) if tail else ())]

    def best(self, p: list[Node], q: list[Node]):
        """The alignment in order with the most matched elements."""
        table = [[0] * (len(q) + 1) for _ in range(len(p) + 1)]
        own = {}
        for i in range(len(p) - 1, -1, -1):
            row, below = table[i], table[i + 1]
            for j in range(len(q) - 1, -1, -1):
                w = 0
                if p[i].tag == q[j].tag:
                    w = own[i, j] = yield self.weight(p[i], q[j])
                row[j] = max(below[j], row[j + 1], below[j + 1] + w)
        out, i, j = [], 0, 0
        while i < len(p) and j < len(q):
            w = own.get((i, j), 0)
            if w and table[i][j] == table[i + 1][j + 1] + w:
                out.append((p[i], q[j]))
                i, j = i + 1, j + 1
            elif table[i][j] == table[i + 1][j]:
                i += 1
            else:
                j += 1
        return out


def _in_order(p: list[Node], q: list[Node]) -> list[tuple[Node, Node]]:
    """An alignment in near linear time: along the longest run in order of shapes that occur once in both, and by name in order between them."""
    once = lambda xs: {s for s, c in Counter(x.shape for x in xs).items() if c == 1}
    both = once(p) & once(q)
    there = {y.shape: j for j, y in enumerate(q) if y.shape in both}
    ends: list[int] = []  # of runs in order: place in q of the last one, the smallest for each length
    at: list[int] = []
    links: list[tuple[int, int, int]] = []  # place in p, place in q, link before
    for i, x in enumerate(p):
        if x.shape in both:
            j = there[x.shape]
            k = bisect_left(ends, j)
            links.append((i, j, at[k - 1] if k else -1))
            ends[k : k + 1], at[k : k + 1] = [j], [len(links) - 1]
    chain, k = [], at[-1] if at else -1
    while k >= 0:
        chain.append(links[k][:2])
        k = links[k][2]
    out, i, j = [], 0, 0
    for to_i, to_j in [*reversed(chain), (len(p), len(q))]:
        while i < to_i and j < to_j:
            if p[i].tag == q[j].tag:
                out.append((p[i], q[j]))
                i, j = i + 1, j + 1
            elif to_i - i > to_j - j:
                i += 1
            else:
                j += 1
        if to_i < len(p):
            out.append((p[to_i], q[to_j]))
        i, j = to_i + 1, to_j + 1
    return out


def step_of(node: Node) -> str:
    return node.tag + "".join("." + x for x in sorted(node.names))


def _paths(root: Node) -> list[tuple[Node, str]]:
    """Nodes in document order down to DEPTH, each with its path: steps joined by '/', with its place among equal steps of its siblings. A node's number is its place here."""
    out, stack = [], [(root, "html", 0)]
    while stack:
        node, path, depth = stack.pop()
        out.append((node, path))
        seen: dict[str, int] = defaultdict(int)
        below = []
        for kid in node.kids if depth < DEPTH else ():
            step = step_of(kid)
            below.append((kid, f"{path}/{step}[{seen[step]}]", depth + 1))
            seen[step] += 1
        stack.extend(reversed(below))
    return out


def _mark(node: Node, text: str) -> int:
    """What a constant is known by: its element and its text."""
    return xxhash.xxh3_64_intdigest(f"{step_of(node)}\n{text}".encode("utf-8", "surrogatepass")) - (1 << 63)


def container(reference: Node, lines: list[tuple[int, int, int, int, int, int, int]]) -> str:
    """The wrapper as JSON: path of the container, marks of constants (drop), elements whose names are overruled (keep).

    lines: (number of the node, number of the line in it, pages matched, different texts, pages with the most frequent text, its mark, characters).
    """
    nodes = _paths(reference)
    slots, vary = [0.0] * len(nodes), [0.0] * len(nodes)
    for number, _, hits, different, _, _, chars in lines:
        share = 1.0 if hits <= 1 else (different - 1) / (hits - 1)
        slots[number] += share * chars / max(hits, 1)
        vary[number] = max(vary[number], share)
    place = {id(node): i for i, (node, _) in enumerate(nodes)}
    order = range(len(nodes) - 1, -1, -1)  # children before their parents
    total, heads = list(slots), [n.tag in ("article", "main", "h1") for n, _ in nodes]
    for i in order:
        for kid in nodes[i][0].kids:
            if id(kid) in place:
                total[i] += total[place[id(kid)]]
                heads[i] |= heads[place[id(kid)]]
    keep = {step_of(n) for i, (n, _) in enumerate(nodes) if n.named and n.tag not in BOILERPLATE and heads[i] and total[i] > 0.5 * total[0]}
    # the same without boilerplate
    live = [True] * len(nodes)
    for i, (node, _) in enumerate(nodes):
        live[i] &= not (node.boilerplate and step_of(node) not in keep)
        for kid in node.kids:
            if id(kid) in place:
                live[place[id(kid)]] &= live[i]
    weight = [w * on for w, on in zip(slots, live)]
    for i in order:
        for kid in nodes[i][0].kids:
            if id(kid) in place:
                weight[i] += weight[place[id(kid)]]
    here = 0
    while nodes[here][0].tag not in ("article", "main"):
        inside = [place[id(k)] for k in nodes[here][0].kids if id(k) in place and k.tag in CONTAINER and live[place[id(k)]]]
        nxt = max(inside, key=lambda i: (weight[i], nodes[i][1]), default=None)
        if nxt is None or weight[nxt] < 0.6 * weight[here]:
            break
        here = nxt
    path = nodes[here][1]
    within = {i for i, (_, p) in enumerate(nodes) if live[i] and (p == path or p.startswith(path + "/"))}
    varies = max((vary[i] for i in within), default=0.0) >= 0.5
    inner = [line for line in lines if line[0] in within]
    fixed = [line for line in inner if varies and line[2] >= LEAST and line[4] >= AGREE * line[2]]
    # pages that agree in most of their text are copies of one article, not articles in one template
    drop = sorted({line[5] for line in fixed}) if 2 * sum(line[6] for line in fixed) <= sum(line[6] for line in inner) else []
    return json.dumps({"path": path, "drop": drop, "keep": sorted(keep)})


def find(root: Node, path: str) -> Node | None:
    node = root
    for step in path.split("/")[1:]:
        name, _, place = step.rpartition("[")
        same = [k for k in node.kids if step_of(k) == name]
        if len(same) <= int(place[:-1]):
            return None
        node = same[int(place[:-1])]
    return node


def first(root: Node, tags: tuple[str, ...]) -> Node | None:
    stack = [root]
    while stack:
        node = stack.pop()
        if node.tag in tags:
            return node
        stack.extend(reversed(node.kids))
    return None


def lines_of(node: Node, skip: Callable[[Node], bool]) -> Iterator[tuple[Node, str]]:
    """Lines of text below a node in page order, with the block element that each stands in: white space folded, references decoded; skipped elements are left out with all below."""
    line: list[str] = []
    owners = [node]
    stack: list = [(node, True)]
    while stack:
        item, opens = stack.pop()
        if isinstance(item, str):
            line.append(item)
            continue
        if opens and item is not node and skip(item):
            continue
        if item.tag == "br":
            line.append("\n")
            continue
        if item.tag in BLOCK or not opens:
            text = " ".join(entities.unescape("".join(line)).split())
            line.clear()
            if text:
                yield owners[-1], text
        if not opens:
            owners.pop()
            continue
        if item.tag in BLOCK:
            owners.append(item)
            stack.append((item, False))
        stack.extend((p, True) for p in reversed(item.parts))
    text = " ".join(entities.unescape("".join(line)).split())
    if text:
        yield owners[-1], text


def blocks(node: Node, drop: Collection[int] = (), keep: Collection[str] = ()) -> list[str]:
    """Texts of the blocks in a container, without boilerplate elements (but those in keep) and without lines whose marks are in drop."""
    found = lines_of(node, lambda x: x.boilerplate and not (x.named and x.tag not in BOILERPLATE and step_of(x) in keep))
    return [text for owner, text in found if not drop or _mark(owner, text) not in drop]


def main_text(source: str | None, wrapper: str | None) -> str:
    root = parse(source or "")
    spec = json.loads(wrapper) if wrapper else {}
    node = find(root, spec["path"]) if spec else None
    if node is None or node.tag in ("html", "body"):
        node = first(root, ("article",)) or first(root, ("main",)) or node or first(root, ("body",)) or root
    return "\n\n".join(blocks(node, frozenset(spec.get("drop", ())), frozenset(spec.get("keep", ()))))


def _by_host(pages: DataFrame, other: DataFrame, value: str) -> DataFrame:
    """Left join on host; other has one row per host, of a size that is measured first."""
    total = other.agg(F.coalesce(F.sum(F.length(value) + F.length("host")), F.lit(0))).first()[0]
    if total <= BROADCAST_BYTES:
        return pages.join(F.broadcast(other), "host", "left")
    salted = pages.withColumn("_salt", F.pmod(F.xxhash64("page_id"), F.lit(SALTS)).cast("int"))
    return salted.join(other.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1)))), ["host", "_salt"], "left").drop("_salt")


COUNTS = "host string, node int, line int, mark long, n long, chars long"


def _counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """host, html, reference to counts of texts per line of the reference's nodes."""
    trees: dict[str, tuple[Node, dict[int, int]]] = {}
    total: dict[tuple[str, int, int, int], list[int]] = {}

    def given() -> pa.RecordBatch:
        rows = [(*k, *v) for k, v in total.items()]
        total.clear()
        columns = list(zip(*rows)) or [[]] * 6
        types = (pa.string(), pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types)], ["host", "node", "line", "mark", "n", "chars"])

    for batch in batches:
        for host, page, reference in zip(*(c.to_pylist() for c in batch.columns)):
            if host not in trees:
                if len(trees) >= 64:
                    trees.clear()
                tree = parse(reference or "")
                trees[host] = (tree, {id(node): i for i, (node, _) in enumerate(_paths(tree))})
            tree, numbers = trees[host]
            root = parse(page or "")
            texts: dict[int, list[tuple[Node, str]]] = {}
            for owner, text in lines_of(root, lambda x: x.tag in RAW or x.tag == "head"):
                texts.setdefault(id(owner), []).append((owner, text))
            for x, y in matched(tree, root):
                number = numbers.get(id(x))
                if number is not None:
                    for k, (owner, text) in enumerate(texts.get(id(y), ())):
                        row = total.setdefault((host, number, k, _mark(owner, text)), [0, 0])
                        row[0] += 1
                        row[1] += len(text)
            if len(total) > 50_000:
                yield given()
    if total:
        yield given()


def wrappers(pages: DataFrame) -> DataFrame:
    """pages(page_id, host, html) to (host, wrapper): path of the container of each host.

    The page that all others are aligned with has the median number of opening tags of its host's pages with any, and
    of such pages the smallest id: neither an empty page, nor a short error page, nor a long one of another kind.
    """
    tagged = pages.select("page_id", "host", "html", F.regexp_count("html", F.lit("<[A-Za-z]")).alias("tags")).where("tags > 0")
    middle = stored(tagged.groupBy("host").agg(F.expr("cast(percentile_disc(0.5) within group (order by tags) as int)").alias("middle")), "middle")
    typical = _by_host(tagged, middle, "host").where("tags = middle")
    references = stored(typical.groupBy("host").agg(F.min_by("html", F.struct("page_id", F.xxhash64("html"))).alias("reference")), "references")
    joined = _by_host(pages, references, "reference").select("host", "html", "reference")
    texts = joined.mapInArrow(_counts, COUNTS).groupBy("host", "node", "line", "mark").agg(F.sum("n").alias("n"), F.sum("chars").alias("chars"))
    lines = texts.groupBy("host", "node", "line").agg(
        F.sum("n").alias("hits"), F.count("*").alias("different"), F.max(F.struct("n", "mark")).alias("top"), F.sum("chars").alias("chars")
    ).select("host", "node", "line", "hits", "different", F.col("top.n").alias("most"), F.col("top.mark").alias("mark"), "chars")

    def induce(table: pa.Table, reference: pa.Table) -> pa.Table:  # a host's rows are the lines of one page
        if not table.num_rows or not reference.num_rows:
            return pa.table({"host": pa.array([], pa.string()), "wrapper": pa.array([], pa.string())})
        rows = list(zip(*(table.column(c).to_pylist() for c in ("node", "line", "hits", "different", "most", "mark", "chars"))))
        wrapper = container(parse(reference.column("reference")[0].as_py() or ""), sorted(rows))
        return pa.table({"host": reference.column("host")[:1], "wrapper": pa.array([wrapper], pa.string())})

    return stored(lines.groupBy("host").cogroup(references.groupBy("host")).applyInArrow(induce, "host string, wrapper string"), "wrappers")


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(page_id, url, text) for every page."""
    used = pages.select(F.col(id_col).alias("page_id"), F.col(url_col).alias("url"), F.col(html_col).cast("string").alias("html")).withColumn("host", host_of(F.col("url")))
    joined = _by_host(used, wrappers(used), "wrapper").select("page_id", "url", "html", "wrapper")

    def texts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            text = [main_text(h, w) for h, w in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist())]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(text, pa.string())], ["page_id", "url", "text"])

    out = joined.mapInArrow(texts, f"page_id {used.schema['page_id'].dataType.simpleString()}, url string, text string")
    return out.select(F.col("page_id").alias(id_col), F.col("url").alias(url_col), "text")
