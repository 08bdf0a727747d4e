"""Main text of pages by a site style tree.

Pages of one host are merged into one tree: an element is known by the path of tags, classes and ids that
leads to it, its presentation by the sequence of its children, its content by the text below it. Over the
host's pages both have an entropy, scaled to 0..1 by the number of pages; an element's importance is the
larger of the two. Branches of low importance, which look and read alike on page after page, are removed
from each page, as are branches that mark themselves as navigation, advert, form and the like.

Any host with two pages has a tree, and every branch is judged, in the article and around it. Pages with the
same article count once, so that copies of an article do not look like a template; within the article one
imagined page of another look stands against each branch, so that a line which two articles share is no
template either, but one of seven is.

First pass: one row per page and element path, with hashes made from the leaves up, so that nesting costs
nothing; Spark counts them by host and path. Second pass: each page with those of its own paths that its host
drops. No row holds more than one page.

Results on odd input: null or empty html has empty text; pages without a host share the empty host; rows
repeat as they come; unclosed, misnested and unknown tags are read as browsers would roughly do; an empty
table gives no rows; further columns are not read.
"""

from __future__ import annotations

import html
import math
import re

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch, ship, slices

#: Below this importance a branch is dropped.
LEAST_IMPORTANCE = 0.2

#: Elements without an end, elements whose content is not markup, elements that begin a block.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript iframe template xmp".split())
BLOCK = frozenset(
    "address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split()
)
#: Elements, roles and names that mark what is not the article.
NOISE_TAGS = frozenset("head nav footer aside form script style noscript iframe template textarea select button svg canvas object menu dialog title xmp".split())
NOISE_ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert alertdialog menu menubar".split())
NOISE_NAMES = frozenset(
    "ad ads advert adverts advertisement adsbygoogle banner breadcrumb breadcrumbs comment comments commentlist consent cookie cookies disqus footer gdpr header masthead menu menubar modal nav navbar navigation newsletter notice pager pagination popup promo promoted related respond share sharing sidebar social sponsor sponsored subscribe toolbar widget".split()
)
MAIN_TAGS = frozenset(("article", "main"))
_BITS = 2**64 - 1

_TAG = re.compile(r"""<!--.*?(?:-->|\Z)|<[!?][^>]*+(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*+)((?:[^>"']++|"[^"]*+"|'[^']*+')*+)(?:>|\Z)""", re.S)
_ATTR = re.compile(r"""([^\s"'>/=]+)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""")
_NAME = re.compile(r"[a-z]+")
_SPACE = re.compile(r"\s+")
#: An open element of the first kind ends where a tag of the second begins.
ENDS = {"p": BLOCK, "li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr"}, "td": {"td", "th", "tr"}, "th": {"td", "th", "tr"}, "option": {"option"}}
_CLOSE = {k: re.compile(rf"</{k}\s*>", re.I) for k in RAW}


class Node:
    __slots__ = ("tag", "label", "kids", "noise", "named", "main")

    def __init__(self, tag: str, attrs: str):
        self.tag, self.kids = tag, []
        label, names, role, hidden = tag, [], "", False
        if attrs:
            for name, a, b, c in _ATTR.findall(attrs):
                value, name = a or b or c, name.lower()
                if name == "role":
                    role = value.lower()
                elif name == "hidden":
                    hidden = True
                elif name in ("class", "id"):
                    label += ("." if name == "class" else "#") + value
                    # A name speaks by its last word: "main-nav" is navigation, "nav-less" is not.
                    names += [words[-1] for words in map(_NAME.findall, value.lower().split()) if words]
        self.label = label
        self.main = tag in MAIN_TAGS or role == "main"
        # A page-wide <header> is noise; one inside an article holds its title.
        self.noise = tag in NOISE_TAGS or hidden or role in NOISE_ROLES
        #: Noise by its names alone.
        self.named = not self.noise and tag not in ("html", "body", *MAIN_TAGS) and not NOISE_NAMES.isdisjoint(names)


def parse(text: str) -> Node:
    root = Node("#root", "")
    stack, at, size = [root], 0, len(text)
    while at < size:
        m = _TAG.search(text, at)
        if m is None:
            stack[-1].kids.append(text[at:])
            break
        if m.start() > at:
            stack[-1].kids.append(text[at : m.start()])
        at = m.end()
        if m[2] is None:
            continue
        tag = m[2].lower()
        if m[1]:
            for i in range(len(stack) - 1, 0, -1):
                if stack[i].tag == tag:
                    del stack[i:]
                    break
                # The end of an inline element does not close the block around it.
                if tag not in BLOCK and stack[i].tag in BLOCK:
                    break
            continue
        for i in range(len(stack) - 1, 0, -1):
            if tag in ENDS.get(stack[i].tag, ()):
                del stack[i:]
                break
            if stack[i].tag in BLOCK:
                break
        node = Node(tag, m[3])
        stack[-1].kids.append(node)
        if tag in RAW:
            end = _CLOSE[tag].search(text, at)
            at = end.end() if end else size
        elif tag not in VOID and not m[3].endswith("/"):
            stack.append(node)
    _judge_names(root)
    return root


def _judge_names(root: Node) -> None:
    """Names make noise of a branch unless it holds the article, or stands in the article and holds its heading."""
    todo, seen = [(root, -1, False)], []
    while todo:
        node, above, inside = todo.pop()
        seen.append([node, above, inside, node.main and not node.noise, node.tag == "h1"])
        todo += [(x, len(seen) - 1, inside or node.main) for x in node.kids if isinstance(x, Node)]
    for node, above, inside, main, title in reversed(seen):
        if node.named and not main and not (inside and title):
            node.noise = True
        if above >= 0 and not node.noise:
            seen[above][3] |= main
            seen[above][4] |= title


def _step(path: int, label: str) -> int:
    """Of the path above and an element, the element's path."""
    return xxhash.xxh3_64_intdigest(label, path & _BITS)


def _hash(parts: list[str]) -> int:
    return xxhash.xxh3_64_intdigest("\x00".join(parts))


def elements(text: str | None) -> tuple[int, list[tuple[int, bool, int, int]]]:
    """Hash of the article (or of all text), and (path, in article, presentation, content) of each path outside noise that may be dropped."""
    todo, seen = [(parse(text or ""), 0, -1, False)], []
    while todo:  # parents first; no recursion, for deep pages
        node, path, above, inside = todo.pop()
        inner, at = inside or node.main, len(seen)
        seen.append((node, path, above, inside, [], {}))
        for x in node.kids:
            if isinstance(x, Node) and not x.noise and not (x.tag == "header" and not inner):
                todo.append((x, _step(path, x.label), at, inner))
    by_path: dict[int, tuple[bool, list[str], list[str]]] = {}
    articles, total = [], 0
    for node, path, above, inside, _, below in reversed(seen):
        # What is not among the children's hashes is noise.
        words = [" ".join(x.split()) if isinstance(x, str) else below.get(id(x), "") for x in node.kids]
        content = f"{_hash(words):x}" if any(words) else ""
        if above >= 0:
            seen[above][5][id(node)] = content
        else:
            total = content
        if node.main and not inside and content:
            articles.append(content)
        if content and (node.tag in BLOCK or node.label != node.tag) and node.tag not in ("html", "body") and not node.main:
            entry = by_path.setdefault(path, (inside, [], []))
            entry[1].append(",".join(x.label for x in node.kids if isinstance(x, Node)))
            entry[2].append(content)
    return _hash(articles or [str(total)]), [(path, inside, _hash(style), _hash(content)) for path, (inside, style, content) in by_path.items()]


def main_text(text: str | None, drop: frozenset = frozenset()) -> str:
    """Blocks of the page in order, one a line, without noise and the paths of ``drop``."""
    root = parse(text or "")
    blocks, line = [], []

    def flush():
        if line:
            block = _SPACE.sub(" ", html.unescape("".join(line))).strip()
            if block:
                blocks.append(block)
            line.clear()

    todo: list = [(root, 0, False)]
    while todo:
        x = todo.pop()
        if x is None:
            flush()
        elif isinstance(x, str):
            line.append(x)
        else:
            node, path, inside = x
            if node.noise or (node.tag == "header" and not inside) or path in drop:
                line.append(" ")
                continue
            if node.tag == "br":
                line.append(" ")
                continue
            block = node.tag in BLOCK
            if block:
                flush()
                todo.append(None)
            inner = inside or node.main
            todo += [k if isinstance(k, str) else (k, _step(path, k.label), inner) for k in reversed(node.kids)]
    flush()
    return "\n".join(blocks)


def _signed(values) -> pa.Array:
    return pa.array(np.array(list(values), np.uint64).view(np.int64))


def _importance(k: str) -> Column:
    """Entropy of the counts of one kind, scaled by that of as many different ones; in the article one more page, unlike all, counts."""
    m, s = F.col("m") + F.col("inside").cast("int"), F.col("s")  # the imagined one adds 1 * log(1)
    return F.when(m > 1, (F.log(m) - s / m) / F.log(m)).otherwise(1.0).alias(k)


def low_paths(seen: DataFrame) -> DataFrame:
    """(host, path) of low importance, of ``seen(host, body, path, inside, style, content)``."""
    once = seen.groupBy("host", "path", "body").agg(F.max("inside").alias("inside"), F.min("style").alias("style"), F.min("content").alias("content"))
    kinds = once.select("host", "path", "inside", F.explode(F.array(F.struct(F.lit("s").alias("k"), F.col("style").alias("v")), F.struct(F.lit("c").alias("k"), F.col("content").alias("v")))).alias("x"))
    counts = kinds.groupBy("host", "path", "x.k", "x.v").agg(F.count("*").alias("n"), F.max("inside").alias("inside"))
    sums = counts.groupBy("host", "path", "k").agg(F.sum("n").alias("m"), F.sum(F.col("n") * F.log("n")).alias("s"), F.max("inside").alias("inside"))
    by_path = sums.select("host", "path", "m", _importance("e")).groupBy("host", "path").agg(F.max("e").alias("e"), F.max("m").alias("m"))
    return by_path.where((F.col("m") > 1) & (F.col("e") < LEAST_IMPORTANCE)).select("host", "path")


def extract(pages: DataFrame, page_id: str = "page_id", url: str = "url", html: str = "html") -> DataFrame:
    """(page_id, url, text, n_chars) of every page."""
    spark = pages.sparkSession
    ship(spark)
    scratch = Scratch(spark, "html")
    host = F.translate(F.regexp_extract(F.coalesce("url", F.lit("")), r"(?s)^.*?://([^/?#]*)", 1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    rows = pages.select(F.col(page_id).alias("page_id"), F.col(url).alias("url"), F.col(html).alias("html"))
    # Pages of equal address and html have equal results, so a hash of both is all that a page needs as its name.
    rows = rows.withColumn("host", host).withColumn("page", F.xxhash64("url", "html"))

    def tree(batches):
        for b in slices(batches):
            out = []
            for name, page, h in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist()):
                article, found = elements(h)
                out += [(name, page, article, *x) for x in found]
            names, ids, body, path, inside, style, content = zip(*out) if out else [()] * 7
            yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array(ids, pa.int64()), _signed(body), _signed(path), pa.array(inside, pa.bool_()), _signed(style), _signed(content)], ["host", "page", "body", "path", "inside", "style", "content"])

    seen = scratch.keep(rows.select("host", "page", "html").mapInArrow(tree, "host string, page long, body long, path long, inside boolean, style long, content long"), "elements")
    low = scratch.keep(low_paths(seen), "low")
    drops = scratch.keep(seen.join(low, ["host", "path"]).groupBy("page").agg(F.collect_set("path").alias("drop")), "drops")
    scratch.drop_all_but(drops)
    joined = rows.join(drops, "page", "left").select("page_id", "url", "html", "drop")

    def work(batches):
        for b in slices(batches):
            texts = [main_text(h, frozenset(x & _BITS for x in d or ())) for h, d in zip(b.column(2).to_pylist(), b.column(3).to_pylist())]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())], ["page_id", "url", "text", "n_chars"])

    kinds = dict(rows.dtypes)
    return joined.mapInArrow(work, f"page_id {kinds['page_id']}, url {kinds['url']}, text string, n_chars long")


def importance(counts: list[int], pages: int) -> float:
    """Entropy of how often each presentation or content occurs, scaled by that of ``pages`` different ones."""
    m = sum(counts)
    return (math.log(m) - sum(n * math.log(n) for n in counts) / m) / math.log(pages) if m and pages > 1 else 1.0
