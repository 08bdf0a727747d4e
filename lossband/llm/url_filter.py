"""Judge URLs by rules for hosts and paths, and pass blocks on to their aliases.

A URL's own longest rule decides. URLs that redirect to one another or name one another as canonical are
one document: connected components over these edges carry a block to every alias without a rule of its own.
An explicit allow of the URL itself always comes first. All of it is DataFrame functions; edges and
components stay distributed.

Results on odd input: a null URL, or one without "://", has empty host and path, no rule, and is allowed
unless an edge says otherwise; null html has no edges; repeated rows are judged alike; an empty table gives
no rows; further columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch, connected_components

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Query parameters that do not change a page.
TRACKING = r"(?i)^(utm_[a-z_]+|fbclid|gclid|ref)="
_PARTS = r"(?s)^.*?://([^/?#]*)([^?#]*)(\??[^#]*)"
_LINK = r"(?is)<link\b[^>]*\brel\s*=\s*[\"']?canonical\b[^>]*>"
_REFRESH = r"(?is)<meta\b[^>]*\bhttp-equiv\s*=\s*[\"']?refresh\b[^>]*>"


def host(url: Column) -> Column:
    return F.translate(F.regexp_extract(F.coalesce(url, F.lit("")), _PARTS, 1), UPPER, LOWER)


def path(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), _PARTS, 2)


def node(url: Column) -> Column:
    """One name for URLs that differ in scheme, fragment and tracking parameters only; null without "://"."""
    query = F.array_join(F.filter(F.split(F.substring(F.regexp_extract(url, _PARTS, 3), 2, 1_000_000), "&"), lambda x: (x != "") & ~x.rlike(TRACKING)), "&")
    return F.when(F.contains(url, F.lit("://")), F.concat(host(url), path(url), F.when(query != "", F.concat(F.lit("?"), query)).otherwise("")))


def own_rule(at: Column, way: Column, rules) -> Column:
    """(n, rule, verdict) of the longest rule that fits, or null; ``rules`` is a short list of (verdict, "host/path")."""
    fits = []
    for verdict, rule in rules:
        top, slash, rest = rule.partition("/")
        hit = ((at == top) | at.endswith(f".{top}")) & way.startswith(slash + rest)
        fits.append(F.when(hit, F.struct(F.lit(len(rule)).alias("n"), F.lit(rule).alias("rule"), F.lit(verdict).alias("verdict"))))
    return F.greatest(*fits, *([F.lit(None).cast("struct<n:int,rule:string,verdict:string>")] * (2 - min(2, len(fits)))))


def _absolute(target: Column, url: Column) -> Column:
    """Of a target that is a full URL, one without scheme, or a path of the host."""
    return F.when(F.contains(target, F.lit("://")), target).when(target.startswith("//"), F.concat(F.lit("http:"), target)).when(target.startswith("/"), F.concat(F.lit("http://"), host(url), target))


def page_edges(pages: DataFrame, url: str = "url", html: str = "html") -> DataFrame:
    """(a, b): nodes of a page and of what its canonical link or its refresh names."""
    text = F.coalesce(F.col(html), F.lit(""))
    href = F.transform(F.regexp_extract_all(text, F.lit(_LINK), F.lit(0)), lambda x: F.regexp_extract(x, r"(?i)\bhref\s*=\s*[\"']?([^\"'\s>]+)", 1))
    goes = F.transform(F.regexp_extract_all(text, F.lit(_REFRESH), F.lit(0)), lambda x: F.regexp_extract(x, r"(?i)\burl\s*=\s*[\"']?([^\"'\s>]+)", 1))
    # Most pages name neither; the cheap test comes first.
    named = F.when(text.rlike("(?i)canonical|http-equiv"), F.filter(F.concat(href, goes), lambda x: x != ""))
    rows = pages.select(F.col(url).alias("url"), F.explode(named).alias("target")).select("url", F.regexp_replace("target", "&amp;", "&").alias("target"))
    return rows.select(node(F.col("url")).alias("a"), node(_absolute(F.col("target"), F.col("url"))).alias("b")).where("a is not null and b is not null and a <> b")


def judge(pages: DataFrame, rules, page_id: str = "page_id", url: str = "url", html: str | None = "html", redirects: DataFrame | None = None) -> DataFrame:
    """(page_id, url, host, path, rule, verdict, component) of every page; ``redirects(source, target)`` adds edges between URLs."""
    scratch = Scratch(pages.sparkSession, "url")
    edges = page_edges(pages, url, html) if html else None
    if redirects is not None:
        more = redirects.select(node(F.col("source")).alias("a"), node(F.col("target")).alias("b")).where("a is not null and b is not null and a <> b")
        edges = more if edges is None else edges.union(more)
    rows = pages.select(F.col(page_id).alias("page_id"), F.col(url).alias("url"), host(F.col(url)).alias("host"), path(F.col(url)).alias("path"), node(F.col(url)).alias("node"))
    rows = rows.withColumn("own", own_rule(F.col("host"), F.col("path"), rules))
    if edges is None:
        return rows.select("page_id", "url", "host", "path", F.col("own.rule").alias("rule"), F.coalesce("own.verdict", F.lit("allow")).alias("verdict"), F.lit(None).cast("string").alias("component"))
    parts = connected_components(scratch, scratch.keep(edges, "edges"))
    # A node's name holds its host and path, so that rules also judge pages that were never fetched.
    named = F.concat(F.lit("x://"), F.col("node"))
    judged = parts.withColumn("block", (own_rule(host(named), path(named), rules)["verdict"] == "block").cast("int"))
    blocked = judged.groupBy("component").agg(F.max("block").alias("blocked"))
    spread = scratch.keep(parts.join(blocked, "component"), "spread")
    out = rows.join(spread, "node", "left")
    verdict = F.coalesce("own.verdict", F.when(F.col("blocked") == 1, "block"), F.lit("allow"))
    return out.select("page_id", "url", "host", "path", F.col("own.rule").alias("rule"), verdict.alias("verdict"), "component")
