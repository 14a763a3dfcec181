"""Main text of web pages by site style trees.

The pages of a host are merged into one tree of block elements. A node is a path of labelled
elements; its presentations are the sequences of children that it has, its contents the texts below
it. Nodes whose presentations and contents are spread over many pages carry little information; every node
that two pages share is judged. A branch is cut as far as its nodes are noisy throughout: a block goes if its own
node is noisy, and one that says something else on each page stays wherever it stands. A host with few pages
leans on the tree of all hosts.

What authors mark as no main text (elements such as ``nav``, words in class and id) is a prior: it takes half of the
importance, so that the branch falls below the threshold, unless the tree speaks against it. A mark has no
weight where the marked element holds the main text of the site's pages, and one that only resembles a mark
(``has-sidebar``) has none on nodes of great importance.
"""

from __future__ import annotations

import functools
import html
import re
from collections.abc import Callable, Iterator
from math import log

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stored

#: Branches of less importance than this are cut.
THRESHOLD = 0.6
#: Weight of presentation against content: each kind of presentation takes this factor off the content's weight.
GAMMA = 0.9
#: Pages of a host that count as much as all other hosts together.
LEAN = 50
#: So many judged nodes of all hosts at most are broadcast (8 bytes each); beyond it they are joined to each page's own.
MOST_BROADCAST = 4_000_000
#: An element that holds this share of its pages' main text is not cut for its mark; a vague mark counts below this importance.
HOLDS, VAGUE = 0.5, 0.8
#: "Nearly all" text of a page.
ALL = 0.9
#: Elements that lie deeper than this are taken for the node of the element at this depth.
DEPTH = 100
PRESENTATION, CONTENT, PAGE, MARK = 0, 1, 2, 3

#: Elements that begin a block, that never hold anything, whose content is no markup, that are no main text, of these that show no text, and that are menus.
BLOCKS = frozenset(
    "html body article main section div header footer nav aside form fieldset table tr ul ol dl li dt dd p h1 h2 h3 h4 h5 h6 pre blockquote figure figcaption address details summary center hr dialog menu "
    "button select textarea iframe object video audio canvas svg noscript template head".split()
)
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style title textarea iframe noscript xmp noembed noframes".split())
NEVER = frozenset("nav footer aside form dialog menu button select textarea iframe object video audio canvas svg noscript template head fieldset".split())
UNSEEN = frozenset("button select textarea iframe object video audio canvas svg noscript template head".split())
MENUS = frozenset("nav footer menu".split())
#: Words in class or id by which authors mark what is no main text.
MARKS = frozenset(
    "ad ads adv advert adverts advertisement advertising banner sponsor sponsored promo promotion nav navbar navigation menu breadcrumb breadcrumbs sidebar footer masthead topbar cookie cookies consent gdpr notice notices popup modal "
    "overlay newsletter subscribe signup login social share sharing related recommended comment comments disqus respond reply replies widget toolbar pagination pager search copyright".split()
)
#: Words that leave a mark beside them what it is; with any other word it is a vague one.
BESIDE = frozenset("area article articles bar block body bottom box container content count entry form group holder inner item items left link links list main module outer page panel post posts right section site slot text thread top unit wrap wrapper zone".split())
#: An element of the first kind ends an open one of the second, unless one of the third lies between.
ENDS = {
    "li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr"}, {"table"}),
}

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>|</?[a-zA-Z][^>]*(?:>|\Z)|([^<]+|<)", re.S)
_ATTRIBUTE = re.compile(r"\b(class|id)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)
_NAME = re.compile(r"[a-z]+|[A-Z][a-z]*")


NONE, VAGUELY, CLEARLY = 0, 1, 2


@functools.lru_cache(maxsize=50_000)
def label(tag: str, rest: str) -> tuple[str, int, bool]:
    """The element's label (tag, class and id without digits), whether its author marks it as no main text, and whether as a header."""
    names = [re.sub(r"\d+", "", a or b or c) for _, a, b, c in _ATTRIBUTE.findall(rest)] if rest else []
    found = " ".join(names)
    mark, words = CLEARLY if tag in NEVER else NONE, set()
    for name in found.split() if tag not in ("html", "body") else ():
        own = {w.lower() for w in _NAME.findall(name)}
        words |= own
        if own & MARKS:
            mark = max(mark, CLEARLY if own <= MARKS | BESIDE else VAGUELY)
    header = tag == "header" or "header" in words and not words & {"article", "post", "entry", "content"}
    return f"{tag}.{found}" if found else tag, mark, header


@functools.lru_cache(maxsize=200_000)
def key(text: str, above: int = 0) -> int:
    """The number of a text, or of the node of an element with this label below the node ``above``."""
    return xxhash.xxh64_intdigest(text, seed=above & 0xFFFFFFFFFFFFFFFF) - (1 << 63)


class Page:
    """Blocks of a page in order: (node, text, marked nodes at or above it). Also each element's children, and the marked nodes.

    ``marks`` has, for each marked node, whether its mark is a vague one and the share of the main text that it
    holds. The main text is the longest ``article`` or ``main`` that is not marked itself; where there is none, it is all text,
    of which a clearly marked element must have nearly all to count as holding it.
    """

    def __init__(self, source: str):
        self.blocks: list[tuple[int, str, tuple[int, ...]]] = []
        self.children: list[tuple[int, list[str]]] = []
        self.above: dict[int, int] = {}
        # tag, node, marked nodes, children, characters before it, own mark
        stack: list[tuple[str, int, tuple[int, ...], list[str], int, int]] = [("", 0, (), [], 0, NONE)]
        opened: dict[str, int] = {}
        text: list[str] = []
        main = total = best = 0  # open elements that hold main text (a header inside them belongs to it); characters; the longest main text
        around: tuple[int, ...] = ()
        held: dict[tuple[int, int], int] = {}

        def flush() -> None:
            nonlocal text, total
            if text and (said := " ".join(html.unescape("".join(text)).split())):
                self.blocks.append((stack[-1][1], said, stack[-1][2]))
                total += len(said)
            text = []

        def close(at: int) -> None:
            nonlocal main, best, around
            flush()
            while len(stack) > at:
                tag, node, marks, inner, before, mark = stack.pop()
                self.children.append((node, inner))
                opened[tag] -= 1
                if mark and tag not in UNSEEN:
                    held[node, mark] = held.get((node, mark), 0) + (0 if tag in MENUS else total - before)
                if tag in ("article", "main"):
                    main -= 1
                    if mark != CLEARLY and total - before > best:
                        best, around = total - before, marks

        def end_open(tags: set[str], stops: set[str]) -> None:
            if any(opened.get(tag) for tag in tags):
                for i in range(len(stack) - 1, 0, -1):
                    if stack[i][0] in tags:
                        close(i)
                        break
                    if stack[i][0] in stops:
                        break

        at, size = 0, len(source)
        while at < size:
            m = _TOKEN.match(source, at)
            at = m.end()
            end, tag, rest, said = m.groups()
            if said is not None:
                text.append(said)
                continue
            if tag is None:
                continue
            tag = tag.lower()
            if end:
                if tag in BLOCKS:
                    end_open({tag}, set())
                elif tag in ("td", "th"):
                    text.append(" ")
                continue
            if tag in BLOCKS:
                flush()
                if stack[-1][0] == "p":
                    close(len(stack) - 1)
                if tag in ENDS:
                    end_open(*ENDS[tag])
                elif tag == "body" and stack[-1][0] == "head":
                    close(len(stack) - 1)
                name, mark, header = label(tag, rest)
                if header and not main:
                    mark = CLEARLY
                _, node, marks, inner, _, _ = stack[-1]
                inner.append(name)
                if tag not in VOID and not rest.endswith("/"):
                    if len(stack) <= DEPTH:
                        self.above[below := key(name, node)] = node
                        node = below
                    if mark and node not in marks:
                        marks = (*marks, node)
                    stack.append((tag, node, marks, [], total, mark))
                    opened[tag] = opened.get(tag, 0) + 1
                    main += tag in ("article", "main")
            elif tag in ("br", "td", "th", "img"):
                text.append(" ")
            if tag in RAW:
                stop = re.compile(f"</{tag}(?=[\\s/>])[^>]*>?|\\Z", re.I).search(source, at)
                at = max(stop.end(), at)
                if tag in BLOCKS:
                    close(len(stack) - 1)
        close(1)
        part = lambda chars: chars / max(total, 1)
        self.marks = {node: (mark == VAGUELY, float(node in around) if best else part(chars) if mark == VAGUELY else float(part(chars) >= ALL)) for (node, mark), chars in sorted(held.items())}

    def ancestors(self, node: int) -> list[int]:
        """The node and those above it."""
        out = []
        while node:
            out.append(node)
            node = self.above[node]
        return out


def host_of(url: str | None) -> str:
    found = re.search(r"://([^/?#]*)", url or "")
    return found[1].lower() if found else ""


def tree_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (host, path, kind, feature, n, nlogn) for the merged tree, added up within a batch; of a mark, pages and the shares that it holds."""
    for batch in batches:
        held: dict[tuple[str, int, int, int], list[float]] = {}
        for url, source in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
            host, page = host_of(url), Page(source.as_py() or "")
            own: dict[tuple[int, int, int], int] = {}
            for path, inner in page.children:
                runs = [x for i, x in enumerate(inner) if not i or inner[i - 1] != x]
                for at in ((path, PRESENTATION, key(" ".join(runs))), (path, PAGE, 0)):
                    own[at] = own.get(at, 0) + 1
            for path, said, _ in page.blocks:
                feature = key(said.replace(host, "") if host else said)
                for above in page.ancestors(path):
                    at = (above, CONTENT, feature)
                    own[at] = own.get(at, 0) + 1
            for path, (vague, part) in page.marks.items():
                sums = held.setdefault((host, path, MARK, int(vague)), [0, 0.0])
                sums[0] += 1
                sums[1] += part
            for (path, kind, feature), n in own.items():
                n = 1 if kind == PAGE else n
                sums = held.setdefault((host, path, kind, feature), [0, 0.0])
                sums[0] += n
                sums[1] += n * log(n)
        rows = list(held)
        columns = list(zip(*rows, strict=True)) or [[]] * 4
        yield pa.RecordBatch.from_arrays([
            pa.array(columns[0], pa.string()), pa.array(columns[1], pa.int64()), pa.array(columns[2], pa.int32()), pa.array(columns[3], pa.int64()),
            pa.array([held[r][0] for r in rows], pa.int64()), pa.array([held[r][1] for r in rows], pa.float64()),
        ], ["host", "path", "kind", "feature", "n", "nlogn"])


def importance(features: DataFrame, scope: tuple[str, ...]) -> DataFrame:
    """Composite importance of each node, by ``scope``: entropies are in units of the pages that have the node.

    A feature that one page has alone has no entropy and is worth 1; one that all pages share is worth 0.
    Presentations that differ from page to page make a node important. ``part`` is the mean share of the main text
    that a marked node holds, null for others.
    """
    of = lambda kind, value: F.sum(F.when(F.col("kind") == kind, value))
    entropy = F.log("n") - F.col("nlogn") / F.col("n")
    sums = features.groupBy(*scope, "path").agg(
        of(PAGE, F.col("n")).alias("pages"), of(CONTENT, F.lit(1)).alias("contents"), of(CONTENT, entropy).alias("content_entropy"),
        of(MARK, F.col("nlogn") / F.col("n")).alias("part"), F.max((F.col("kind") == MARK) & (F.col("feature") == 1)).alias("vague"),
        of(PRESENTATION, F.lit(1)).alias("kinds"), of(PRESENTATION, F.col("n")).alias("shown"), of(PRESENTATION, F.col("n") * F.log("n")).alias("shown_log"),
    )
    unit = F.log(F.greatest("pages", F.lit(2)).cast("double"))
    content = F.when(F.col("contents") > 0, 1 - F.least(F.col("content_entropy") / F.col("contents") / unit, F.lit(1.0)))
    look = F.least((F.log("shown") - F.col("shown_log") / F.col("shown")) / unit, F.lit(1.0))
    weight = F.pow(F.lit(GAMMA), F.col("kinds"))
    value = F.when(F.col("pages") < 2, F.lit(1.0)).otherwise(F.coalesce((1 - weight) * look + weight * content, look))
    return sums.select(*scope, "path", "pages", "vague", "part", value.alias("importance"))


def judged_nodes(pages: DataFrame) -> DataFrame:
    """(host, path, void): the nodes to cut, and, with ``void``, marked nodes whose mark does not count.

    A node that one page has alone is worth 1 and is never cut but for its mark.
    """
    rows = pages.select("url", "html").mapInArrow(tree_rows, "host string, path long, kind int, feature long, n long, nlogn double")
    features = stored(rows.groupBy("host", "path", "kind", "feature").agg(F.sum("n").alias("n"), F.sum("nlogn").alias("nlogn")), "tree-features")
    overall = features.groupBy("path", "kind", "feature").agg(F.sum("n").alias("n"), F.sum("nlogn").alias("nlogn"))
    overall = stored(importance(overall, ()), "tree-overall").withColumnRenamed("importance", "all_importance").withColumnRenamed("part", "all_part").drop("pages", "vague")
    own = importance(features, ("host",)).where("pages > 1 OR part IS NOT NULL")
    weight = F.col("pages") / (F.col("pages") + LEAN)
    lean = lambda name: weight * F.col(name) + (1 - weight) * F.col(f"all_{name}")
    both = stored(own, "tree-hosts").join(overall, "path").select("host", "path", "pages", "vague", lean("importance").alias("importance"), lean("part").alias("part"))
    noisy = (F.col("pages") > 1) & (F.col("importance") < THRESHOLD)
    void = (F.col("part") >= HOLDS) | (F.col("vague") & (F.col("importance") >= VAGUE))
    found = both.select("host", "path", F.explode(F.filter(F.array(F.when(noisy, False), F.when(void, True)), lambda x: x.isNotNull())).alias("void"))
    return stored(found, "tree-judged")


def main_text(page: Page, noisy: frozenset[int], void: frozenset[int]) -> str:
    """Blocks left when all branches are cut as far as their nodes are noisy throughout: those with a noisy node or below a mark that counts go."""
    return "\n".join(said for node, said, marks in page.blocks if node not in noisy and void.issuperset(marks))


def extracted(pages: DataFrame) -> DataFrame:
    """page_id, url, text and n_chars of every row of ``pages`` (page_id, url, html; others are ignored).

    A null or empty html has an empty text. Pages without a host share the host of the empty name. Repeated
    rows count as pages each. Broken markup is read as far as it goes; a tag cut off by the page's end is
    dropped. Elements more than ``DEPTH`` deep have the node of the one at that depth.
    """
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    kind = "page_id long, url string, text string, n_chars long"
    found = judged_nodes(rows)
    if found.count() <= MOST_BROADCAST:
        return rows.mapInArrow(_with_broadcast(found), kind)
    same = F.xxhash64(F.coalesce("url", F.lit("")), F.lit("\n"), F.coalesce("html", F.lit("")))
    named = rows.withColumn("page", same)
    nodes = named.select("page", "url", "html").mapInArrow(page_nodes, "page long, host string, path long")
    met = nodes.join(found, ["host", "path"]).groupBy("page").agg(*(F.collect_set(F.when(F.col("void") == kind, F.col("path"))).alias(name) for name, kind in (("noisy", False), ("void", True))))
    return named.join(met, "page", "left").select("page_id", "url", "html", "noisy", "void").mapInArrow(_with_columns, kind)


def nodes_of(page: Page) -> set[int]:
    """Nodes that decide about the page's blocks."""
    return {node for node, _, _ in page.blocks} | page.marks.keys()


def page_nodes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(page, host, path) of the nodes that decide about a page's blocks."""
    for batch in batches:
        out: list[tuple[int, str, int]] = []
        for page, url, source in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
            out += [(page, host_of(url), node) for node in nodes_of(Page(source.as_py() or ""))]
        columns = list(zip(*out, strict=True)) or [[]] * 3
        yield pa.RecordBatch.from_arrays([pa.array(columns[0], pa.int64()), pa.array(columns[1], pa.string()), pa.array(columns[2], pa.int64())], ["page", "host", "path"])


def _texts(batch: pa.RecordBatch, texts: list[str]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])


def _with_columns(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows = zip(batch.column(2), batch.column(3), batch.column(4), strict=True)
        yield _texts(batch, [main_text(Page(source.as_py() or ""), frozenset(noisy.as_py() or ()), frozenset(void.as_py() or ())) for source, noisy, void in rows])


def _with_broadcast(found: DataFrame) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    rows = found.groupBy("host", "void").agg(F.sort_array(F.collect_list("path")).alias("paths")).toArrow()
    keys = zip(rows["host"].to_pylist(), rows["void"].to_pylist(), strict=True)
    lists = {at: paths.values.to_numpy() for at, paths in zip(keys, (x for c in rows["paths"].chunks for x in c), strict=True)}
    shared, none = found.sparkSession.sparkContext.broadcast(lists), np.zeros(0, np.int64)

    def among(nodes: np.ndarray, listed: np.ndarray) -> frozenset[int]:
        if not len(listed):
            return frozenset()
        at = np.minimum(np.searchsorted(listed, nodes), len(listed) - 1)
        return frozenset(nodes[listed[at] == nodes].tolist())

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = []
            for url, source in zip(batch.column(1).to_pylist(), batch.column(2), strict=True):
                page, host = Page(source.as_py() or ""), host_of(url)
                nodes = np.array(list(nodes_of(page)), np.int64)
                texts.append(main_text(page, *(among(nodes, shared.value.get((host, void), none)) for void in (False, True))))
            yield _texts(batch, texts)

    return work
