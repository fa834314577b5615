"""Main text of web pages by wrapper induction (operator 6).

Each page becomes a tree of its block elements (:func:`parse`). The pages of a host are
aligned with a reference page of that host by simple tree matching (:func:`align`), a
large order-preserving match of equal labels from the root down: siblings at both ends pair
off where labels are equal, and a table over what lies between finds the largest match. The
pages of each layout of a host (:func:`layout`) have a reference of their own besides. A block of
the reference whose text is the same on all pages aligned with it, over at least
:data:`MIN_PAGES` pages that are not copies of each other, is template; slots whose text
varies are content. What is left inside the main element and articles (else the body) and outside
elements that mark themselves as boilerplate is the page's text. A class or id marks an element by
one of its whole tokens, without the words for a container at the token's end: ``share-buttons`` and
``site-footer`` do, ``share-price`` and ``search-results`` do not.

Trees are flat lists in preorder, walked without recursion, and the scanner looks for the
end of a tag at most once past the last one, so that neither deep nesting nor unclosed tags
cost more than a page's length.

Only skeletons travel (labels and hashes of text, some hundred bytes a page), never
markup: they are joined with the reference of their host, votes are combined before the
shuffle, so a host with a third of all pages is no burden. The blocks to drop come back as
a small table that is joined with the pages, by broadcast only if Spark finds its files
small.

Defined results: null html gives an empty text; a null url belongs to the host ''; pages
that repeat an id are judged each by their own html; a host with fewer than MIN_PAGES
different pages has no template; an empty table gives an empty one. Runs of white space
include no-break spaces.
"""

from __future__ import annotations

import marshal
import math
import re
from collections import Counter
from collections.abc import Generator, Iterator
from functools import lru_cache
from html import unescape

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import scratch

#: Different pages of a host on which a constant block counts as template.
MIN_PAGES = 5
#: Most cells of an alignment table that is kept whole; of larger ones some rows are kept and the others computed again.
MAX_CELLS = 40_000
#: Depth to which the elements with children make up a page's layout.
LAYOUT_DEPTH = 3
#: Parts of a host that meet its reference in tasks of their own.
PARTS = 16

# Element names of the public HTML standard.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title iframe noembed noframes xmp".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark nobr q s samp small span strike strong sub sup time tt u var".split())
SKIPPED = frozenset("head nav footer aside form script style noscript template iframe button select option textarea title svg canvas object dialog menu noembed noframes".split())
CLOSES = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
#: Words in class, id or role that mark an element as boilerplate.
MARKS = frozenset("ad ads advert adverts advertisement advertising sponsor sponsored promo sidebar menu nav navbar navigation breadcrumb breadcrumbs footer masthead banner cookie cookies consent notice alert popup modal newsletter subscribe comment comments respond replies disqus share sharing social related widget pagination complementary contentinfo search".split())

#: Words that name a container at the end of a class.
CONTAINERS = frozenset("area bar block box button buttons container content form group inner item items link links list outer panel row section slot thread title top unit wrap wrapper".split())

TAG = re.compile(r"(/?)([a-zA-Z][^\s/>]*)")
PLAIN = re.compile(r"[^>\"']*+")
MARKING = re.compile(r"\b(class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))|\b(hidden)\b", re.I)
PART = re.compile(r"[a-z]+|[^a-z]+")


class Node:
    """A block element: label, children, and what it is in or is itself: boilerplate, the main part."""

    __slots__ = ("label", "tag", "kids", "skip", "off", "main")

    def __init__(self, tag: str, label: str, skip: bool, around: Node | None = None):
        self.tag, self.label, self.skip, self.kids = tag, label, skip, []
        self.off = skip or (around is not None and around.off)
        self.main = tag in ("article", "main") or (around is not None and around.main)


@lru_cache(1 << 14)
def _marked(value: str) -> bool:
    """Whether a class, id or role names boilerplate by one of its tokens."""
    for token in value.split():
        parts = [x for x in PART.findall(token) if x.isalpha()]
        while len(parts) > 1 and parts[-1] in CONTAINERS:
            parts.pop()
        if parts and parts[-1] in MARKS:
            return True
    return False


def _attributes(attrs: str) -> tuple[str, bool]:
    label, skip = "", False
    for name, a, b, c, hidden in MARKING.findall(attrs) if attrs else ():
        value = a or b or c
        if hidden:
            skip = True
        elif name.lower() != "id":
            label += "." + value
        skip = skip or bool(value) and _marked(value.lower())
    return label, skip


def scan(html: str) -> Iterator[tuple[str, str, str, str, int]]:
    """(text before, "/" of an end tag, tag name, attributes, place after it) of each tag; last the
    text that is left with an empty name. Comments and declarations have an empty name too.

    An element whose text is raw is left by sending the place where to go on.
    """
    at, n = 0, len(html)
    start, tag_ends, quoted = 0, html.rfind(">"), True
    while True:
        lt = html.find("<", at)
        if lt < 0:
            break
        if html.startswith("<!--", lt):
            end = html.find("-->", lt + 4)
            after = n if end < 0 else end + 3
            jump = yield html[start:lt], "", "", "", after
        elif lt > tag_ends:
            break  # no tag ends from here on: the rest is text
        elif html.startswith(("<!", "<?"), lt):
            after = html.find(">", lt) + 1
            jump = yield html[start:lt], "", "", "", after
        elif m := TAG.match(html, lt + 1):
            end = m.end()
            while quoted:
                end = PLAIN.match(html, end).end()
                if end < n and html[end] == ">":
                    break
                end = html.find(html[end], end + 1) + 1 if end < n else 0
                if not end:  # a quote stays open up to the page's end: quotes count no longer
                    quoted = False
            if not quoted:
                end = html.find(">", m.end())
            after = end + 1
            jump = yield html[start:lt], m[1], m[2].lower(), html[m.end() : end], after
        else:
            at = lt + 1
            continue
        start = at = after if jump is None else jump
    yield html[start:], "", "", "", n


def parse(html: str) -> tuple[Node, list[tuple[Node, Node, str]]]:
    """The block tree and its text blocks in page order: leaf, element around it, text."""
    root = Node("#", "#", False)
    stack, blocks = [root], []
    opened: Counter = Counter()
    current: list[str] = []

    def flush():
        if current:
            text = " ".join("".join(current).split())
            if text:
                leaf = Node("#text", "#text", False)
                stack[-1].kids.append(leaf)
                blocks.append((leaf, stack[-1], text))
            current.clear()

    def pop(to):
        for x in stack[to:]:
            opened[x.tag] -= 1
        del stack[to:]

    def shut(tag):
        if opened[tag]:
            flush()
            pop(next(i for i in range(len(stack) - 1, 0, -1) if stack[i].tag == tag))

    def push(node):
        stack[-1].kids.append(node)
        stack.append(node)
        opened[node.tag] += 1

    n, tags, skip_to = len(html), scan(html), None
    while True:
        try:
            text, end_tag, tag, attrs, after = tags.send(skip_to)
        except StopIteration:
            break
        skip_to = None
        if text:
            current.append(unescape(text))
        if not tag:
            continue
        if end_tag:
            if tag in ("p", "br"):
                flush()
            shut(tag)
            continue
        if tag in INLINE:
            if not attrs:
                continue
            label, skip = _attributes(attrs)
            if not skip:
                continue
            flush()
            push(Node(tag, tag + label, True, stack[-1]))
            continue
        if tag in VOID:
            if tag in ("br", "hr"):
                flush()
            continue
        if tag in RAW:
            end = re.compile(rf"</{tag}\s*>", re.I).search(html, after)
            skip_to = end.end() if end else n
            if tag != "xmp":
                flush()
                continue
        flush()
        if tag == "body":
            shut("head")
        closes = CLOSES.get(tag, ())
        if opened["p"] or any(opened[x] for x in closes):
            for i in range(len(stack) - 1, 0, -1):
                t = stack[i].tag
                if t == "p" or t in closes:
                    pop(i)
                elif t in ("ul", "ol", "table", "dl", "div", "article", "section", "body"):
                    break
        label, skip = _attributes(attrs) if attrs else ("", False)
        skip = (skip and tag not in ("html", "body", "main")) or tag in SKIPPED or (tag == "header" and not stack[-1].main)
        node = Node(tag, tag + label, skip, stack[-1])
        if attrs.endswith("/") and tag in ("svg", "iframe"):
            stack[-1].kids.append(node)
        else:
            push(node)
    flush()
    return root, blocks


def content(html: str | None) -> tuple[Node, list[tuple[Node, str]]]:
    """The tree and the blocks inside the main element and articles, if any, that no marked element holds."""
    root, blocks = parse(html or "")
    kept = [b for b in blocks if not b[1].off]
    kept = [b for b in kept if b[1].main] or kept
    return root, [(leaf, text) for leaf, _, text in kept]


def skeleton(html: str | None) -> tuple:
    """Labels, subtree sizes, text hashes and numbers among the content blocks (or -1), in preorder."""
    root, blocks = content(html)
    own = {id(leaf): (i, xxhash.xxh64_intdigest(text) >> 1) for i, (leaf, text) in enumerate(blocks)}
    labels, sizes, hashes, numbers = [], [], [], []
    todo: list = [root]
    while todo:
        node = todo.pop()
        if isinstance(node, int):  # all below this place is done
            sizes[node] = len(labels) - node
            continue
        number, h = own.get(id(node), (-1, 0))
        todo.append(len(labels))
        labels.append(node.label)
        sizes.append(1)
        hashes.append(h)
        numbers.append(number)
        todo += [k for k in reversed(node.kids) if not k.skip]
    return tuple(labels), tuple(sizes), tuple(hashes), tuple(numbers)


def _kids(sizes: tuple, i: int) -> list[int]:
    """Places of a node's children."""
    out, at, end = [], i + 1, i + sizes[i]
    while at < end:
        out.append(at)
        at += sizes[at]
    return out


class _Shapes:
    """Trees by their labels alone; equal shapes have one number, so that a pair of shapes is matched once."""

    def __init__(self):
        self.numbers: dict[tuple, int] = {}
        self.all: list[tuple] = []
        self.memo: dict[tuple[int, int], tuple[int, list]] = {}

    def number(self, tree: tuple) -> list[int]:
        """The numbers of the shapes of a tree's nodes."""
        labels, sizes = tree[:2]
        of = [0] * len(labels)
        for i in range(len(labels) - 1, -1, -1):
            shape = (labels[i], tuple(of[k] for k in _kids(sizes, i)))
            if shape not in self.numbers:
                self.numbers[shape] = len(self.all)
                self.all.append(shape)
            of[i] = self.numbers[shape]
        return of

    def match(self, a: int, b: int) -> tuple[int, list]:
        """(matched nodes, places of the matched children) of two shapes with equal labels."""
        if (a, b) in self.memo:
            return self.memo[a, b]
        # Each step asks for the pairs below it; a list of open steps stands for recursion.
        steps, answer = [((a, b), self._solve(a, b))], None
        while steps:
            pair, step = steps[-1]
            try:
                asked = step.send(answer)
            except StopIteration as end:
                answer = self.memo[pair] = end.value
                steps.pop()
                continue
            answer = self.memo.get(asked)
            if answer is None:
                steps.append((asked, self._solve(*asked)))
        return self.memo[a, b]

    def _solve(self, a: int, b: int) -> Generator:
        xs, ys = self.all[a][1], self.all[b][1]
        labels = [self.all[x][0] for x in xs], [self.all[y][0] for y in ys]
        # Siblings with equal labels at both ends pair off, and runs of a single label in order.
        start, end, most = 0, 0, min(len(xs), len(ys))
        while start < most and labels[0][start] == labels[1][start]:
            start += 1
        while end < most - start and labels[0][-1 - end] == labels[1][-1 - end]:
            end += 1
        places = [(i, i) for i in range(start)] + [(len(xs) - k, len(ys) - k) for k in range(1, end + 1)]
        m, n = len(xs) - end - start, len(ys) - end - start
        if m and n:
            if len({*labels[0][start : start + m], *labels[1][start : start + n]}) == 1:
                places += [(start + i, start + i) for i in range(min(m, n))]
            else:
                inner = yield from self._table(xs[start : start + m], ys[start : start + n])
                places += [(start + i, start + j) for i, j in inner]
        total = 1
        for i, j in places:
            total += (yield xs[i], ys[j])[0]
        return total, places

    def _table(self, xs: tuple, ys: tuple) -> Generator:
        """The pairs of the largest order-preserving match of two lists of shapes."""
        m, n = len(xs), len(ys)
        kinds = sorted(set(ys))
        at = {y: k for k, y in enumerate(kinds)}
        column = np.array([at[y] for y in ys])
        #: Nodes that each of xs matches with each of ys, 0 where labels differ.
        gains: dict[int, list] = {}
        for x in dict.fromkeys(xs):
            by_kind = []
            for y in kinds:
                by_kind.append((yield x, y)[0] if self.all[x][0] == self.all[y][0] else 0)
            gains[x] = np.array(by_kind, np.int64)[column] if n >= 64 else [by_kind[k] for k in column]

        def row(x, below):
            g = gains[x]
            if n >= 64:
                top = np.where(g > 0, np.maximum(below[:-1], below[1:] + g), below[:-1])
                return np.append(np.maximum.accumulate(top[::-1])[::-1], 0)
            out = [0] * (n + 1)
            for j in range(n - 1, -1, -1):
                out[j] = max(below[j], out[j + 1], below[j + 1] + g[j] if g[j] else 0)
            return out

        step = 1 if m * n <= MAX_CELLS else math.isqrt(m) + 1
        rows = {m: np.zeros(n + 1, np.int64) if n >= 64 else [0] * (n + 1)}
        below = rows[m]
        for i in range(m - 1, -1, -1):
            below = row(xs[i], below)
            if i % step == 0:
                rows[i] = below
        i = j = 0
        pairs = []
        while i < m and j < n:
            if i + 1 not in rows:
                # The rows up to the next one kept, from it.
                for k in range(min(m, (i // step + 1) * step) - 1, i, -1):
                    rows[k] = row(xs[k], rows[k + 1])
            here, under, g = rows[i][j], rows[i + 1], gains[xs[i]][j]
            if g and here == under[j + 1] + g:
                pairs.append((i, j))
                i, j = i + 1, j + 1
                rows.pop(i - 1)
            elif here == under[j]:
                i += 1
                rows.pop(i - 1)
            else:
                j += 1
        return pairs


def align(a: tuple, b: tuple) -> list[tuple[int, int]]:
    """Places of the leaves that a top-down, order-preserving match of two skeletons pairs."""
    if a[0][0] != b[0][0]:
        return []
    shapes, leaves, todo = _Shapes(), [], [(0, 0)]
    of_a, of_b = shapes.number(a), shapes.number(b)
    while todo:
        x, y = todo.pop()
        if a[1][x] == b[1][y] == 1:
            leaves.append((x, y))
            continue
        xs, ys = _kids(a[1], x), _kids(b[1], y)
        todo += [(xs[i], ys[j]) for i, j in shapes.match(of_a[x], of_b[y])[1]]
    return leaves


def layout(tree: tuple, depth: int = LAYOUT_DEPTH) -> int:
    """A hash of the paths of labels to elements with children, down to a depth."""
    labels, sizes = tree[:2]
    paths: set[tuple] = set()
    todo = [(0, ())]
    while todo:
        i, path = todo.pop()
        if sizes[i] > 1 and len(path) < depth:
            paths.add((*path, labels[i]))
            todo += [(k, (*path, labels[i])) for k in _kids(sizes, i)]
    return xxhash.xxh64_intdigest(repr(sorted(paths))) >> 1


class _References:
    """Reference skeletons by their bytes; few at a time."""

    def __init__(self):
        self.known: dict[bytes, tuple] = {}

    def __call__(self, data: bytes) -> tuple:
        if data not in self.known:
            if len(self.known) >= 4096:
                self.known.clear()
            self.known[data] = marshal.loads(data)
        return self.known[data]


def _skeletons(batches):
    for batch in batches:
        for at in range(0, batch.num_rows, 500):
            part = batch.slice(at, 500)
            trees = [skeleton(x.as_py()) for x in part.column(2)]
            hashes = [xxhash.xxh64_intdigest(repr([h for h, i in zip(t[2], t[3]) if i >= 0])) >> 1 for t in trees]
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array([marshal.dumps(t) for t in trees], pa.binary()), pa.array(hashes, pa.int64()), pa.array([layout(t) for t in trees], pa.int64())], names=["key", "host", "tree", "page", "layout"])


def _votes(batches):
    load = _References()
    for batch in batches:
        rows = []
        for host, tree, page, ref in zip(*(batch.column(i).to_pylist() for i in range(4))):
            t = marshal.loads(tree)
            rows += [(host, x, t[2][y], page) for x, y in align(load(ref), t) if t[3][y] >= 0]
        names = ["host", "node", "text", "page"]
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows) if rows else [[]] * 4, (pa.string(), pa.int32(), pa.int64(), pa.int64()))], names=names)


def _drops(batches):
    load = _References()
    for batch in batches:
        keys, drops = [], []
        for key, tree, ref, nodes in zip(*(batch.column(i).to_pylist() for i in range(4))):
            t, constant = marshal.loads(tree), set(nodes)
            out = [t[3][y] for x, y in align(load(ref), t) if t[3][y] >= 0 and x in constant]
            if out:
                keys.append(key)
                drops.append(sorted(out))
        yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array(drops, pa.list_(pa.int32()))], names=["key", "drops"])


def grouped(trees: DataFrame) -> DataFrame:
    """Each skeleton twice: with all of its host (null layout) and with those of its layout there."""
    return trees.withColumn("layout", F.explode(F.array(F.lit(None).cast("long"), F.col("layout")))).withColumn("host", F.concat_ws("|", F.coalesce(F.col("layout").cast("string"), F.lit("")), "host")).drop("layout")


def _beside(trees: DataFrame, small: DataFrame) -> DataFrame:
    """Join skeletons with one row a host, a large host's over many tasks."""
    dealt = trees.withColumn("part", F.pmod("key", F.lit(PARTS)).cast("int"))
    return dealt.join(small.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(PARTS - 1)))), ["host", "part"])


def induce(trees: DataFrame) -> DataFrame:
    """Template blocks of each host: (host, ref, nodes) from skeletons (key, host, tree, page)."""
    refs = trees.groupBy("host").agg(F.min_by("tree", F.struct("page", "key")).alias("ref"), F.count(F.lit(1)).alias("n")).filter(F.col("n") >= MIN_PAGES).select("host", "ref")
    votes = _beside(trees, refs).select("host", "tree", "page", "ref").mapInArrow(_votes, "host string, node int, text long, page long")
    by_page = votes.groupBy("host", "node", "page").agg(F.min("text").alias("a"), F.max("text").alias("b"))
    tally = by_page.groupBy("host", "node").agg(F.min("a").alias("a"), F.max("b").alias("b"), F.count(F.lit(1)).alias("pages"))
    constant = tally.filter((F.col("a") == F.col("b")) & (F.col("pages") >= MIN_PAGES))
    return constant.groupBy("host").agg(F.sort_array(F.collect_list("node")).alias("nodes")).join(refs, "host").select("host", "ref", "nodes")


def extract(pages: DataFrame, html_col: str = "html", url_col: str = "url", text_col: str = "text") -> DataFrame:
    """Add ``text_col``, the main text of each page."""
    spark = pages.sparkSession
    keep = [c for c in pages.columns if c != text_col]
    host = F.lower(F.regexp_extract(F.coalesce(F.col(url_col), F.lit("")), r"^[A-Za-z][A-Za-z0-9+.-]*://([^/?#]*)", 1))
    keyed = pages.select(*[F.col(f"`{c}`") for c in keep], F.col(f"`{html_col}`").cast("string").alias("__html"), host.alias("__host"))
    keyed = keyed.withColumn("__key", F.xxhash64("__host", "__html"))
    folder = scratch(spark, "skeletons")
    source = keyed.select(F.col("__key").alias("key"), F.col("__host").alias("host"), F.col("__html").alias("html"))
    source.mapInArrow(_skeletons, "key long, host string, tree binary, page long, layout long").write.parquet(f"{folder}/trees")
    trees = spark.read.schema("key long, host string, tree binary, page long, layout long").parquet(f"{folder}/trees")
    induce(grouped(trees)).write.parquet(f"{folder}/wrappers")
    wrappers = spark.read.schema("host string, ref binary, nodes array<int>").parquet(f"{folder}/wrappers")
    drops = _beside(grouped(trees.dropDuplicates(["key"])), wrappers).select("key", "tree", "ref", "nodes").mapInArrow(_drops, "key long, drops array<int>")
    drops = drops.groupBy("key").agg(F.array_distinct(F.flatten(F.collect_list("drops"))).alias("drops"))
    drops.write.parquet(f"{folder}/drops")
    drops = spark.read.schema("key long, drops array<int>").parquet(f"{folder}/drops")

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                part = batch.slice(at, 500)
                texts = []
                for html, drop in zip(part.column(len(keep)), part.column(len(keep) + 1).to_pylist()):
                    blocks, out = content(html.as_py())[1], set(drop or ())
                    texts.append(" ".join(t for i, (_, t) in enumerate(blocks) if i not in out))
                yield pa.RecordBatch.from_arrays([*(part.column(i) for i in range(len(keep))), pa.array(texts, pa.string())], names=[*keep, text_col])

    joined = keyed.join(drops.toDF("__k", "__drops"), F.col("__key") == F.col("__k"), "left")
    schema = pages.select(*[F.col(f"`{c}`") for c in keep]).schema.add(text_col, "string")
    return joined.select(*[F.col(f"`{c}`") for c in keep], "__html", "__drops").mapInArrow(run, schema)
