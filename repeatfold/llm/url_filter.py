"""URL filter with redirect equivalence.

Rules judge a url by its host (with all subdomains) and path prefix; the longest rule wins, allow before block among equally long
ones. A url without a rule takes the verdict of its aliases: urls joined by redirect or canonical-link edges form components, found by
distributed connected components, and a component with an allowed member is allowed, else one with a blocked member is blocked, else
the default holds.

Edges have three sources: canonical links and meta refreshes of the pages' HTML (every such tag; targets resolved against the page's url, with
entities and dot segments; other schemes than those with ``://`` are no targets), tables of redirects, and the canonical form of each url:
https, no ``www.`` or ``m.`` before the host, no index page, ``.html`` or slash at the end of the path, no tracking parameters, no fragment.

Nodes are the urls themselves, so nothing depends on hashes. Nulls, empty texts and urls without ``://`` have empty host and path, fit no rule
and have no aliases. Repeated rows are judged alike. Columns of the input named like the results are replaced, others never clash; an empty
table gives no rows.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from repeatfold.llm.common import components, cut, fresh

#: A rule list is configuration; it is compiled into the plan. Longer lists are refused rather than broadcast unchecked.
MAX_RULES = 2_000
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_URL = r"(?s)^.*?://([^/?#]*)([^?#]*)"
CANONICAL = r"(?is)<link\b[^>]*\brel\s*=\s*[\"']?canonical\b[^>]*>"
HREF = r"(?is)\bhref\s*=\s*[\"']?([^\"'\s>]+)"
REFRESH = r"(?is)<meta\b[^>]*\bhttp-equiv\s*=\s*[\"']?refresh\b[^>]*>"
TARGET = r"(?is)\burl\s*=\s*[\"']?([^\"'\s>]+)"


def host(url: Column) -> Column:
    return F.coalesce(F.translate(F.regexp_extract(url, _URL, 1), _UPPER, _LOWER), F.lit(""))


def path(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, _URL, 2), F.lit(""))


def rule_of(host_: Column, path_: Column, rules: Sequence[tuple[str, str, str]]) -> Column:
    """Struct (rule, action) of the longest fitting rule among ``(action, host, path)``, or null."""
    if len(rules) > MAX_RULES:
        raise ValueError(f"{len(rules)} rules; at most {MAX_RULES}")
    out = None
    for action, h, p in sorted(rules, key=lambda r: (-len(r[1] + r[2]), r[0] != "allow", r)):
        fits = ((host_ == h) | host_.endswith("." + h)) & path_.startswith(p)
        hit = F.struct(F.lit(h + p).alias("rule"), F.lit(action).alias("action"))
        out = F.when(fits, hit) if out is None else out.when(fits, hit)
    return F.lit(None).cast("struct<rule:string,action:string>") if out is None else out


SCHEME = r"^[A-Za-z][A-Za-z0-9+.\-]*:"
FIRST_LABEL = r"^(?:www|m)\."
PAGE_END = r"(?:/index)?(?:\.html?)?/*$"
TRACKING = r"^(?:utm_[^=]*|ref|gclid|fbclid)(?:=|$)"


def head(url: Column) -> Column:
    """Scheme, ``://`` and host, as they stand."""
    return F.regexp_extract(url, r"(?s)^(.*?://[^/?#]*)", 1)


def without_dots(path_: Column) -> Column:
    """A path from ``/`` on without ``.`` and ``..`` segments."""
    parts = F.slice(F.split(path_, "/"), 2, 1 << 20)
    start = F.array().cast("array<string>")
    kept = F.aggregate(parts, start, lambda a, x: F.when(x == "..", F.slice(a, 1, F.greatest(F.size(a) - 1, F.lit(0)))).when(x == ".", a).otherwise(F.concat(a, F.array(x))))
    ends = F.when(path_.rlike(r"/\.\.?$"), F.concat(kept, F.array(F.lit("")))).otherwise(kept)
    return F.when(path_.contains("/."), F.concat(F.lit("/"), F.array_join(ends, "/"))).otherwise(path_)


def resolved(target: Column, base: Column) -> Column:
    """The url that ``target`` means on a page at ``base``; null for other schemes than those with ``://``."""
    t = F.regexp_replace(target, "&(?:amp|#38|#[xX]26);", "&")
    root, plain = head(base), F.regexp_extract(base, r"(?s)^([^?#]*)", 1)
    folder = F.regexp_extract(base, r"(?s)^(.*?://[^/?#]*(?:/[^?#]*/|/)?)", 1)
    full = (
        F.when(t.rlike(SCHEME + "//"), t)
        .when(t.rlike(SCHEME), F.lit(None))
        .when(t.startswith("//"), F.concat(F.regexp_extract(base, r"(?s)^(.*?:)//", 1), t))
        .when(t.startswith("/"), F.concat(root, t))
        .when(t.startswith("?"), F.concat(plain, t))
        .when(t.startswith("#"), base)
        .otherwise(F.concat(folder, F.when(folder.endswith("/"), F.lit("")).otherwise(F.lit("/")), t))
    )
    rest = lambda u: F.regexp_extract(u, r"(?s)^.*?://[^/?#]*[^?#]*(.*)$", 1)
    return F.concat(head(full), without_dots(F.regexp_extract(full, _URL, 2)), rest(full))


def canonical(url: Column) -> Column:
    """The canonical form of a url; null without ``://``."""
    query = F.regexp_extract(url, r"(?s)^.*?://[^?#]*\?([^#]*)", 1)
    kept = F.array_join(F.filter(F.split(query, "&"), lambda x: (x != "") & ~x.rlike(TRACKING)), "&")
    short = F.concat(F.lit("https://"), F.regexp_replace(host(url), FIRST_LABEL, ""), F.regexp_replace(path(url), PAGE_END, ""))
    return F.when(url.contains("://"), F.concat(short, F.when(kept != "", F.concat(F.lit("?"), kept)).otherwise("")))


def link_edges(pages: DataFrame, url_col: str = "url", html_col: str | None = "html") -> DataFrame:
    """``(from_url, to_url)`` from each page's canonical links and meta refreshes, if it has an ``html_col``, and from its url to the canonical form."""
    url = F.col(url_col)
    own = F.array(canonical(url))
    if html_col is not None:
        html = F.coalesce(html_col, F.lit(""))
        tags = lambda tag, part: F.transform(F.regexp_extract_all(html, F.lit(tag), F.lit(0)), lambda x: F.regexp_extract(x, part, 1))
        targets = F.filter(F.concat(tags(CANONICAL, HREF), tags(REFRESH, TARGET)), lambda t: t != "")
        own = F.concat(own, F.transform(targets, lambda t: resolved(t, url)))
    return pages.where(url.contains("://")).select(url.alias("from_url"), F.explode(own).alias("to_url")).where("to_url is not null")


def node(url: Column) -> Column:
    """A url's node: without its fragment, A-Z of scheme and host lower-cased; null without ``://``."""
    return F.when(head(url) != "", F.concat(F.translate(head(url), _UPPER, _LOWER), F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^#]*)", 1)))


def judge(pages: DataFrame, rules: Sequence[tuple[str, str, str]], edges: DataFrame | None = None, url_col: str = "url", default: str = "allow") -> DataFrame:
    """``pages`` with ``host, path, rule, verdict`` (columns of these names are replaced). ``edges (from_url, to_url)``: redirects and canonical links."""
    hit, at, said_ = fresh(pages, "_hit", "_node", "_said")
    base = pages.withColumns({"host": host(F.col(url_col)), "path": path(F.col(url_col))})
    base = base.withColumn(hit, rule_of(F.col("host"), F.col("path"), rules)).withColumn("rule", F.col(f"{hit}.rule"))
    if edges is None:
        return base.withColumn("verdict", F.coalesce(f"{hit}.action", F.lit(default))).drop(hit)
    said = alias_verdicts(edges, rules).withColumnsRenamed({"node": at, "said": said_})
    out = base.withColumn(at, node(F.col(url_col))).join(said, at, "left")
    return out.withColumn("verdict", F.coalesce(f"{hit}.action", said_, F.lit(default))).drop(hit, said_, at)


def alias_verdicts(edges: DataFrame, rules: Sequence[tuple[str, str, str]]) -> DataFrame:
    """``node, said``: the verdict of the component of each node that an edge joins to another one, null where no member has a rule."""
    found = components(edges.select(node(F.col("from_url")).alias("a"), node(F.col("to_url")).alias("b")))
    action = rule_of(host(F.col("node")), path(F.col("node")), rules)["action"]
    votes = found.select("component", action.alias("action")).where("action is not null").groupBy("component").agg(F.max(F.col("action") == "allow").alias("any_allow"))
    # a written table, so that the join with it has two shuffled sides and a giant component may be split
    said = cut(votes.select("component", F.when(F.col("any_allow"), "allow").otherwise("block").alias("said")))
    return found.join(said, "component").select("node", "said")
