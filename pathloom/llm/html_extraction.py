"""Main text of web pages by wrapper induction.

Pages of one host and layout (the kinds of sectioning elements, in the order of their first use) form a pool;
hosts with too few pages of a layout share a pool by layout. The page with the smallest key is its pool's
seed, and every other page's tree is aligned with it by simple tree matching: the largest mapping that keeps
tags, ancestors and order. What aligns with a seed node in all pages is one template node. A node whose text is
the same in most pages is constant; other nodes are slots. The wrapper's region is the deepest
template node that holds nearly all of the pool's varying text, links not counted; a page's text is what aligns
with the region, without constant nodes and without parts that are named as something else.

Tags, roles and names are features of a node: they take its text out of account when the region is sought,
unless nearly all text of a pool's pages is in nodes so named. A landmark (article, main) is preferred among
nodes that hold most of the text. A page alone in its pool has a wrapper of its own, from the same features.

Statistics are counts per pool and template node, summed within batches first, so a host with most of the pages is as
many rows as its seed has nodes. Copies of a page count once. Nothing is dropped or capped inside a page.
"""

from __future__ import annotations

import html as html_lib
import re
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import BROADCAST_BYTES, broadcast_if_small, pick, stored, table
from .memory import released

#: Pages of a host and layout from which they form a pool of their own; shares of pages and of text that decide.
LEAST_PAGES, CONSTANT_SHARE, REGION_SHARE, LANDMARK_SHARE = 4, 0.6, 0.9, 0.5
#: Pages of a pool that go to one task at most where pools are dealt by a shuffle.
SPLIT_PAGES = 100_000
#: Elements whose order of first use is a page's layout.
SECTIONING = "body|header|nav|main|article|section|aside|footer|form"
#: Element kinds of HTML, and words of class, id and role that name parts which are not content.
VOID = set("area base br col embed hr img input link meta param source track wbr".split())
BLOCKS = set("address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol optgroup option p pre section summary table tbody td tfoot th thead tr ul".split())
CLOSES_P = BLOCKS - set("td th tr tbody thead tfoot option optgroup html body legend".split())
LEFT_OUT = set("head nav footer aside form script style noscript template button select textarea iframe svg canvas object dialog menu audio video".split())
ROLES = set("navigation banner contentinfo complementary search alert alertdialog dialog menu menubar form".split())
NAMES = set(
    "ad ads advert adverts advertisement advertising banner banners cookie cookies consent gdpr notice notices alert alerts sidebar sidebars menu menus nav navbar navigation breadcrumb breadcrumbs footer masthead topbar comment comments commentlist disqus reply replies respond share sharing social related recommended recommendations newsletter subscribe subscription signup login popup modal overlay promo promotion promotions sponsor sponsored widget widgets toolbar pagination pager search".split()
)
CELL_PARENTS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
LIST_SCOPE = set("ul ol dl table select menu".split())

#: Longest attributes whose features are remembered.
MOST_REMEMBERED = 512

_TOKEN = re.compile(
    r"""<!--.*?(?:-->|\Z)|<(?P<raw>script|style)\b(?:"[^"]*"|'[^']*'|[^>"'])*>.*?(?:</(?P=raw)[^>]*>|\Z)|<(?P<end>/?)(?P<tag>[a-zA-Z][^\s/>]*)(?P<attrs>(?:"[^"]*"|'[^']*'|[^>"'])*)>|<(?P<end2>/?)(?P<tag2>[a-zA-Z][^\s/>]*)(?P<attrs2>[^>]*)>|<[!?/][^>]*(?:>|\Z)|<[a-zA-Z][^>]*\Z""",
    re.DOTALL | re.IGNORECASE,
)
_ATTRIBUTE = re.compile(r"""([^\s"'>/=]+)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""")


class Node:
    """An element. out: its tag, role or an attribute says that it is no content; named: a class or id does."""

    __slots__ = ("tag", "out", "named", "children", "number", "shape")

    def __init__(self, tag: str, out: bool = False, named: bool = False):
        self.tag, self.out, self.named, self.children, self.number, self.shape = tag, out, named, [], -1, 0


@lru_cache(maxsize=1 << 14)
def _features(tag: str, attrs: str, inside: bool) -> tuple[bool, bool]:
    """(out, named) of an element. inside: within an article or main element, where only whole names count."""
    if tag in LEFT_OUT or (tag == "header" and not inside):
        return True, False
    named = False
    for name, a, b, c in _ATTRIBUTE.findall(attrs) if attrs and not attrs.isspace() else ():
        name, value = name.lower(), (a or b or c).lower()
        if name == "role":
            if not ROLES.isdisjoint(value.split()):
                return True, False
        elif name == "hidden" or (name == "aria-hidden" and value.strip() == "true"):
            return True, False
        elif name in ("class", "id") and tag not in ("body", "html", "main"):
            # within content a word of a longer name tells of a topic as often as of a part
            named = named or not NAMES.isdisjoint(value.split() if inside else re.split(r"[^a-z]+", value))
    return False, named


def parse(source: str) -> Node:
    """The page's tree. Children are nodes and strings; unclosed, misnested and cut-off markup is allowed."""
    root = Node("#root")
    stack, within = [root], [False]  # within: is a member of the stack, or one before it, an article or main element
    at = 0
    for m in _TOKEN.finditer(source):
        start, after = m.span()
        if start > at:
            stack[-1].children.append(source[at:start])
        at = after
        _, end, tag, attrs, end2, tag2, attrs2 = m.groups()
        tag = tag or tag2
        if not tag:
            continue
        tag = tag.lower()
        if end or end2:
            for i in range(len(stack) - 1, 0, -1):
                if stack[i].tag == tag:
                    del stack[i:], within[i:]
                    break
                if tag not in BLOCKS and stack[i].tag in BLOCKS and stack[i].tag != "p":
                    break
            continue
        if tag in CLOSES_P:
            for i in range(len(stack) - 1, 0, -1):
                if stack[i].tag == "p":
                    del stack[i:], within[i:]
                    break
                if stack[i].tag in BLOCKS:
                    break
        if tag in CELL_PARENTS:
            for i in range(len(stack) - 1, 0, -1):
                if stack[i].tag in CELL_PARENTS[tag]:
                    del stack[i:], within[i:]
                    break
                if stack[i].tag in LIST_SCOPE:
                    break
        attrs = attrs or attrs2 or ""
        if attrs and attrs.isspace():
            attrs = ""
        inside = bool(attrs or tag == "header") and within[-1]
        # pages of a site repeat their tags with their attributes; long ones (data in a URL, say) are not remembered
        node = Node(tag, *(_features(tag, attrs, inside) if len(attrs) <= MOST_REMEMBERED else _features.__wrapped__(tag, attrs, inside)))
        stack[-1].children.append(node)
        if tag not in VOID and (tag in BLOCKS or not attrs.rstrip().endswith("/")):
            stack.append(node)
            within.append(within[-1] or tag == "article" or tag == "main")
    if at < len(source):
        stack[-1].children.append(source[at:])
    return root


def own_text(node: Node) -> str:
    """A node's own strings, decoded, with white space as single spaces."""
    text = " ".join([c for c in node.children if isinstance(c, str)])
    return " ".join((html_lib.unescape(text) if "&" in text else text).split())


def blocks(node: Node, drop: frozenset | set = frozenset()) -> list[str]:
    """The texts of the blocks below a node, in order, without parts left out and the nodes in drop."""
    out: list[str] = []
    line: list[str] = []

    def flush() -> None:
        text = " ".join(html_lib.unescape("".join(line)).split())
        line.clear()
        if text:
            out.append(text)

    work: list = [node]
    while work:
        x = work.pop()
        if x is None:
            flush()
        elif isinstance(x, str):
            line.append(x)
        elif x.out or x in drop:
            continue
        elif x.tag == "br":
            line.append(" ")
        elif x.tag in BLOCKS:
            flush()
            work.append(None)
            work.extend(reversed(x.children))
        else:
            work.extend(reversed(x.children))
    flush()
    return out


def _elements(node: Node) -> list[Node]:
    return [c for c in node.children if not isinstance(c, str)]


def numbered(root: Node) -> list[Node]:
    """All elements in document order; sets their numbers and, from below, hashes of their shapes."""
    out, below, work = [], [], [root]
    while work:
        x = work.pop()
        x.number = len(out)
        out.append(x)
        elements = _elements(x)
        below.append(elements)
        work.extend(reversed(elements))
    for x, elements in zip(reversed(out), reversed(below), strict=True):
        x.shape = hash((x.tag, tuple([c.shape for c in elements])))
    return out


def _middle(x: list[Node], y: list[Node]) -> tuple[int, int]:
    """How many children have equal shapes at both lists' beginnings, and then at their ends."""
    least = min(len(x), len(y))
    low = 0
    while low < least and x[low].shape == y[low].shape:
        low += 1
    high = 0
    while high < least - low and x[-1 - high].shape == y[-1 - high].shape:
        high += 1
    return low, high


class Matcher:
    """Simple tree matching. A mapping's size depends on two subtrees' shapes only, so sizes are kept by shape."""

    def __init__(self):
        self.size: dict[tuple[int, int], int] = {}
        self.whole: dict[int, int] = {}

    def _weights(self, x: list[Node], y: list[Node]) -> Iterator[np.ndarray]:
        """Sizes of the mappings of each of a list's members with another's, 0 for different tags."""
        shapes = {c.shape: i for i, c in enumerate(y)}
        columns = {s: np.array([d.shape == s for d in y]) for s in shapes}
        rows: dict[int, np.ndarray] = {}
        for c in x:
            if c.shape not in rows:
                rows[c.shape] = row = np.zeros(len(y), np.int32)
                for s, i in shapes.items():
                    if y[i].tag == c.tag:
                        row[columns[s]] = self.size[c.shape, s]
            yield rows[c.shape]

    def _chosen(self, x: list[Node], y: list[Node]) -> tuple[int, list[tuple[Node, Node]]]:
        """The best order-keeping pairs of two lists, and the sum of their sizes.

        A row of the table is a running maximum of what the row above and its own pairs give. Kept of each row
        is one bit a cell for where it is above the row before, and one for where it rises.
        """
        weights = self._weights(x, y)
        above = np.zeros(len(y) + 1, np.int64)
        gains, rises = [], []
        for row in weights:
            here = np.concatenate([[0], np.maximum(above[1:], np.where(row > 0, above[:-1] + row, 0))])
            np.maximum.accumulate(here, out=here)
            gains.append(np.packbits(here[1:] > above[1:]))
            rises.append(np.packbits(here[1:] > here[:-1]))
            above = here
        pairs, j = [], len(y)
        for i in range(len(x) - 1, -1, -1):
            if not j:
                break
            if np.unpackbits(gains[i], count=j)[-1]:  # the row's node is used, where its row rose to this value
                j = int(np.flatnonzero(np.unpackbits(rises[i], count=j))[-1]) + 1
                pairs.append((x[i], y[j - 1]))
                j -= 1
        return int(above[-1]), pairs

    def _measure(self, a: Node, b: Node) -> None:
        """Fill in the sizes that the mapping of two nodes needs, from below."""
        work = [(a, b, False)]
        while work:
            p, q, ready = work.pop()
            if (p.shape, q.shape) in self.size:
                continue
            if p.shape == q.shape:
                self.size[p.shape, q.shape] = self._count(p)
                continue
            x, y = _elements(p), _elements(q)
            low, high = _middle(x, y)
            outer = sum(self._count(c) for c in [*x[:low], *x[len(x) - high :]])
            x, y = x[low : len(x) - high], y[low : len(y) - high]
            if ready:
                self.size[p.shape, q.shape] = 1 + outer + (self._chosen(x, y)[0] if x and y else 0)
                continue
            work.append((p, q, True))
            kinds = {c.shape: c for c in x}.values(), {d.shape: d for d in y}.values()
            work.extend((c, d, False) for c in kinds[0] for d in kinds[1] if c.tag == d.tag and (c.shape, d.shape) not in self.size)

    def _count(self, node: Node) -> int:
        """Elements of a subtree."""
        if node.shape not in self.whole:
            n, work = 0, [node]
            while work:
                x = work.pop()
                n += 1
                work.extend(_elements(x))
            self.whole[node.shape] = n
        return self.whole[node.shape]

    def pairs(self, a: Node, b: Node, wanted: set[Node] | None = None) -> list[tuple[Node, Node]]:
        """The mapping's pairs; with wanted, only those of these nodes of the first tree (and, unused, some more)."""
        out, walk = [], [(a, b)]
        while walk:
            p, q = walk.pop()
            if wanted is not None and p not in wanted:
                continue
            out.append((p, q))
            x, y = _elements(p), _elements(q)
            if p.shape == q.shape:
                walk.extend(zip(x, y, strict=True))
                continue
            low, high = _middle(x, y)
            walk.extend(zip(x[:low], y[:low], strict=True))
            walk.extend(zip(x[len(x) - high :], y[len(y) - high :], strict=True))
            x, y = x[low : len(x) - high], y[low : len(y) - high]
            tags = [c.tag for c in x]
            if tags == [d.tag for d in y] and len(set(tags)) == len(tags):
                walk.extend(zip(x, y, strict=True))  # each has one partner only, and all fit
            elif x and y:
                for c in {c.shape: c for c in x}.values():
                    for d in {d.shape: d for d in y if d.tag == c.tag}.values():
                        self._measure(c, d)
                walk.extend(self._chosen(x, y)[1])
        return out


def aligned(a: Node, b: Node) -> list[tuple[Node, Node]]:
    """The pairs of a largest top-down mapping of two trees that keeps tags, ancestors and order."""
    return Matcher().pairs(a, b)


@lru_cache(maxsize=256)
def _seed(source: str) -> tuple[Node, list[Node], list[str]]:
    root = parse(source)
    nodes = numbered(root)
    return root, nodes, [own_text(n) for n in nodes]


#: For each template node: pages with it, pages with the seed's text, characters outside links (all, varying, and those in parts that are named).
Stats = dict[int, tuple[int, int, int, int, int]]


def _plain_chars(node: Node, matched: set[Node]) -> tuple[int, int]:
    """Characters below a node that no template node has (children not aligned), links not counted: all, and those in named parts."""
    total = named = 0
    work = [(c, c.named) for c in _elements(node) if c not in matched]
    while work:
        x, inside = work.pop()
        if x.out or x.tag == "a":
            continue
        n = len(own_text(x))
        total += n
        named += n if inside else 0
        work.extend((c, inside or c.named) for c in _elements(x))
    return total, named


def page_stats(top: Node, texts: list[str], page: Node) -> Iterator[tuple[int, tuple[int, int, int, int, int]]]:
    """What one page adds to the statistics of each template node that it has."""
    numbered(page)
    pairs = aligned(top, page)
    matched = {q for _, q in pairs}
    named: dict[int, bool] = {}
    linked: dict[int, bool] = {}
    for p, q in pairs:  # parents come before children
        here = named.get(id(q), False) or q.named
        link = linked.get(id(q), False) or q.tag == "a" or q.out
        for c in _elements(q):
            named[id(c)], linked[id(c)] = here, link
        text = own_text(q)
        same = text == texts[p.number]
        own = 0 if link else len(text)
        extra, inside = (0, 0) if link else _plain_chars(q, matched)
        yield p.number, (1, int(same), own + extra, (0 if same else own) + extra, own + extra if here else inside)


def _counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The statistics of each pool's template nodes over a task's pages."""
    total: dict[tuple[str, int], list[int]] = {}

    def batch_of() -> pa.RecordBatch:
        keys, counts = list(total), list(total.values())
        return pa.RecordBatch.from_arrays(
            [pa.array([k[0] for k in keys], pa.string()), pa.array([k[1] for k in keys], pa.int32()), *(pa.array([c[i] for c in counts], pa.int64()) for i in range(5))], names=["pool", "node", *COUNTS]
        )

    seeds: dict[str, str] = {}
    for batch in batches:
        for i, (pool, source) in enumerate(zip(*(batch.column(c).to_pylist() for c in ("pool", "html")), strict=True)):
            root, _, texts = _seed(_of_pool(seeds, pool, lambda i=i, b=batch: b.column("seed")[i].as_py()))
            if source:
                for number, counts in page_stats(root, texts, parse(source)):
                    sums = total.setdefault((pool, number), [0] * 5)
                    for i, n in enumerate(counts):
                        sums[i] += n
        if len(total) > 200_000:  # hand on what there is; sums are completed after the exchange
            yield batch_of()
            total.clear()
    yield batch_of()


def wrapper(nodes: list[Node], stats: Stats) -> tuple[int, set[int], set[int]]:
    """(region, constant nodes, named nodes that are content all the same), by number of template node."""
    none = (0, 0, 0, 0, 0)
    pages = stats.get(0, none)[0]
    get = lambda n: stats.get(n.number, none)
    several = pages >= 2
    # a pool whose pages hardly differ tells nothing of what is constant: all its text counts
    differs = several and sum(s[3] for s in stats.values()) >= (1 - REGION_SHARE) * sum(s[2] for s in stats.values())
    of = 3 if differs else 2
    whole, named = sum(s[of] for s in stats.values()), sum(s[4] for s in stats.values())
    trusted = several and named >= REGION_SHARE * sum(s[2] for s in stats.values())  # the names are this site's own
    mass = [0 if n.out else max(0, get(n)[of] - (0 if trusted else get(n)[4])) for n in nodes]
    for n in reversed(nodes):
        if not n.out:
            mass[n.number] += sum(mass[c.number] for c in _elements(n) if not c.out and (trusted or not c.named))
    at = nodes[0]
    while mass[0]:
        below = [c for c in _elements(at) if not c.out and (trusted or not c.named) and c.tag in BLOCKS and c.tag != "p"]
        heavy = [c for c in below if mass[c.number] >= REGION_SHARE * mass[0]]
        marks = [c for c in below if c.tag in ("article", "main") and mass[c.number] >= LANDMARK_SHARE * mass[0]]
        if not heavy and not marks:
            break
        at = (heavy or marks)[0]
    constant = {k for k, (n, same, *_) in stats.items() if differs and n >= LEAST_PAGES and same >= CONSTANT_SHARE * n and n >= CONSTANT_SHARE * pages}
    return at.number, constant, {n.number for n in nodes if n.named and trusted} if whole else set()


def alone(root: Node) -> tuple[Node, set[Node]]:
    """The region of a page that has no pool, by its own statistics, and its named parts."""
    nodes = numbered(root)
    texts = [own_text(n) for n in nodes]
    region, _, _ = wrapper(nodes, dict(page_stats(root, texts, root)))
    return nodes[region], {n for n in nodes if n.named}


def main_text(source: str | None, seed: str | None = None, stats: Stats | None = None) -> str:
    """A page's text: what aligns with its pool's region, without constant nodes and parts that are named as something else."""
    if not source:
        return ""
    root = parse(source)
    if seed and stats and stats.get(0, (0,))[0] >= 2:
        top, texts, region, constant, content, wanted = _wrapper(seed, stats)
        page = numbered(root)
        pairs = Matcher().pairs(top, root, wanted)
        of = {q: p.number for p, q in pairs}
        found = next((q for p, q in pairs if p.number == region), None)
        if found is not None:
            drop = {q for p, q in pairs if p.number in constant and texts[p.number] and own_text(q) == texts[p.number] and not _elements(q)}
            named = {q for q in page if q.named and q is not found and not (content and of.get(q, -1) in content)} if not content else set()
            return "\n".join(blocks(found, drop | named))
    region, named = alone(root)
    return "\n".join(blocks(region, named))


#: Pools whose seeds and statistics a task remembers: rows repeat them, and they are decoded once for each pool.
MOST_POOLS = 256


def _of_pool(known: dict, pool: str, decode: Callable):
    """What a task knows of a pool; decoded from a row of it if it is not known, or no longer."""
    if pool not in known:
        if len(known) >= MOST_POOLS:
            known.clear()
        known[pool] = decode()
    return known[pool]


_WRAPPERS: dict[tuple[str, int], tuple] = {}


def _wrapper(seed: str, stats: Stats) -> tuple[Node, list[str], int, set[int], set[int], set[Node]]:
    """A seed's tree and texts, its wrapper, and the seed's nodes that pages are aligned with for it, remembered for the pools that are being read."""
    key = (seed, id(stats))
    if key not in _WRAPPERS:
        if len(_WRAPPERS) >= MOST_POOLS:
            _WRAPPERS.clear()
        top, nodes, texts = _seed(seed)
        region, constant, content = wrapper(nodes, stats)
        # alignment is needed down to the region, to constant nodes with text, and to parts whose names do not count
        wanted, ends = set(), {region, *content, *(k for k in constant if texts[k])}
        for n in reversed(nodes):
            if n.number in ends or any(c in wanted for c in _elements(n)):
                wanted.add(n)
        _WRAPPERS[key] = ((top, texts, region, constant, content, wanted), stats)
    return _WRAPPERS[key][0]


def _extracted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    known: dict[str, tuple[str | None, Stats]] = {}

    def decoded(batch: pa.RecordBatch, i: int) -> tuple[str | None, Stats]:
        stats = batch.column("stats")[i].as_py()
        return batch.column("seed")[i].as_py(), {s["node"]: tuple(s[c] for c in COUNTS) for s in stats or []}

    for batch in batches:
        texts = []
        for i, (pool, source) in enumerate(zip(*(batch.column(c).to_pylist() for c in ("pool", "html")), strict=True)):
            texts.append(main_text(source, *_of_pool(known, pool, lambda i=i, b=batch: decoded(b, i))))
        yield pa.RecordBatch.from_arrays(
            [batch.column("key"), batch.column("url"), pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64())], names=["key", "url", "text", "n_chars"]
        )


def host_of(url: Column) -> Column:
    return F.lower(F.regexp_extract(F.coalesce(url, F.lit("")), r"^[a-zA-Z][a-zA-Z0-9+.\-]*://(?:[^/@?#]*@)?([^/:?#]+)", 1))


def layout_of(html: Column) -> Column:
    """The sectioning elements of a page in the order of their first use."""
    found = F.regexp_extract_all(F.coalesce(html, F.lit("")), F.lit(rf"(?i)<({SECTIONING})[\s/>]"), F.lit(1))
    return F.array_join(F.array_distinct(F.transform(found, F.lower)), " ")


COUNTS = ["pages", "same", "chars", "varying", "in_named"]


def _with_pool(rows: DataFrame, few: DataFrame, row_bytes: str, sizes: DataFrame) -> DataFrame:
    """rows with their pool's columns. few is broadcast while its measured bytes allow it; beyond, pools of many pages are dealt to several tasks."""
    size = few.agg(F.sum(F.expr(row_bytes))).first()[0] or 0
    if size <= BROADCAST_BYTES:
        return rows.join(F.broadcast(few), "pool", "left")
    hot = sizes.filter(F.col("pool_pages") > SPLIT_PAGES).select("pool", F.ceil(F.col("pool_pages") / SPLIT_PAGES).cast("int").alias("splits"))
    hot = broadcast_if_small(hot, 200)  # one row for each SPLIT_PAGES pages at most
    one = F.coalesce("splits", F.lit(1))
    spread = few.join(hot, "pool", "left").withColumn("split", F.explode(F.sequence(F.lit(0), one - 1))).drop("splits")
    dealt = rows.join(hot, "pool", "left").withColumn("split", F.pmod(F.xxhash64("html"), one).cast("int")).drop("splits")
    return dealt.join(spread, ["pool", "split"], "left").drop("split")


def extracted_pages(pages: DataFrame, key: str = "page_id", url: str = "url", html: str = "html") -> DataFrame:
    """key, url, text, n_chars for each row of pages.

    Null and empty pages have an empty text. Pages whose url is null or has no host form one host. Repeated rows
    and null keys are kept; copies of a page count once for their pool. A host with fewer than LEAST_PAGES
    pages of a layout shares a pool with other such hosts' pages of that layout; a page alone there
    is judged by its own statistics. Pages are aligned at any depth, with sibling lists of any length. Extra
    columns are ignored; an empty table gives an empty result.
    """
    rows = pick(pages, key, url, html).toDF("key", "url", "html")
    # html is parsed by the executors only in the two passes below; hosts and layouts stay in the JVM
    rows = rows.withColumn("host", host_of(F.col("url"))).withColumn("layout", layout_of(F.col("html")))
    order = F.struct(F.coalesce(F.col("key").cast("long"), F.lit((1 << 63) - 1)), F.md5("html"))
    full = rows.filter("html <> ''").withColumn("copy", F.md5("html"))
    groups = stored(full.groupBy("host", "layout", "copy").agg(F.min(order).alias("first"), F.count("*").alias("n")), "page-groups")
    many = groups.groupBy("host", "layout").agg(F.count("*").alias("n")).filter(F.col("n") >= LEAST_PAGES).select("host", "layout", F.lit(True).alias("own"))
    many = broadcast_if_small(stored(many, "own-pools"), 200)

    def pooled(df: DataFrame) -> DataFrame:
        own = F.concat_ws("\n", F.lit("host"), "host", "layout")
        return df.join(many, ["host", "layout"], "left").withColumn("pool", F.when(F.col("own"), own).otherwise(F.concat_ws("\n", F.lit("layout"), "layout"))).drop("own")

    members = pooled(groups)
    sizes = stored(members.groupBy("pool").agg(F.count("*").alias("pool_pages"), F.min("first").alias("first")), "pools")
    firsts = sizes.select("pool", F.col("first.col2").alias("copy"))
    placed = pooled(full)
    seeds = placed.join(broadcast_if_small(firsts, 200), ["pool", "copy"], "left_semi").groupBy("pool").agg(F.min_by("html", order).alias("seed"))
    seeds = stored(seeds, "seeds")
    again = stored(groups.filter("n > 1").select("host", "layout", "copy", F.col("first.col1").alias("first_key")), "page-copies")
    once = placed.join(broadcast_if_small(again, 100), ["host", "layout", "copy"], "left")
    once = once.filter(F.col("first_key").isNull() | (F.coalesce(F.col("key").cast("long"), F.lit((1 << 63) - 1)) == F.col("first_key"))).select("pool", "html")
    counted = _with_pool(once, seeds, "200 + length(seed)", sizes).select("pool", "html", "seed").mapInArrow(released(_counted), "pool string, node int, " + ", ".join(f"{c} long" for c in COUNTS))
    sums = counted.groupBy("pool", "node").agg(*(F.sum(c).alias(c) for c in COUNTS))
    stats = sums.groupBy("pool").agg(F.collect_list(F.struct("node", *COUNTS)).alias("stats"))
    wrappers = stored(seeds.join(stats, "pool", "left"), "wrappers")
    found = _with_pool(pooled(rows), wrappers, "200 + length(seed) + 48 * coalesce(size(stats), 0)", sizes)
    kind = rows.schema["key"].dataType.simpleString()
    out = found.select("key", "url", "pool", "html", "seed", "stats").mapInArrow(released(_extracted), f"key {kind}, url string, text string, n_chars long")
    return out.toDF(key, url, "text", "n_chars")


def op6_wrapper_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extracted_pages(table(spark, sf_dir, "pages"))
