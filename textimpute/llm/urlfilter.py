"""URL filters with redirect equivalence (DataFrame operations only).

A rule is (action, host, path): it fits its host and every subdomain if the url's path starts with the rule's path, and
the longest fitting rule (host and path, in characters; ties: allow) decides. Pages that no rule reaches take the
decision of their aliases: urls joined by canonical links or by refresh redirects found in the html form connected
components. In a component an explicit allow outranks every block; without one a block reaches all aliases; a page with
a rule of its own always keeps that rule's decision. Nothing decided: allow.

Link targets may be relative: they are resolved against the page's url (its scheme, host and folder; `..`, query-only and
fragment-only targets included), and the character references of `&`, quotes and angle brackets are decoded.

Defined edge results: a null url or one without `://` has empty host and path, no rule and no alias; null html has no
links; repeated rows give repeated rows; an empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import hot_join, written
from .components import connected_components

#: Rules of the contract.
RULES = (
    ("allow", "org", "/"),
    ("block", "example.org", "/es/"),
    ("block", "example.org", "/en/1"),
    ("allow", "com", "/fr/"),
    ("block", "com", "/de/"),
)


def host_and_path(url: Column) -> tuple[Column, Column]:
    at = F.locate("://", url)
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))
    rest = F.coalesce(rest, F.lit(""))
    host = F.regexp_extract(rest, r"^([^/?#]*)", 1)
    path = F.regexp_extract(F.regexp_replace(rest, r"^[^/?#]*", ""), r"(?s)^([^?#]*)", 1)
    return F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), path


def longest_rule(host: Column, path: Column, rules=RULES) -> Column:
    """struct(rule, verdict) of the longest fitting rule, or null: one expression, longest rule first."""
    ordered = sorted(rules, key=lambda r: (-len(r[1]) - len(r[2]), r[0] != "allow", r[1:]))
    fits = [
        F.when(((host == h) | host.endswith("." + h)) & path.startswith(p),
               F.struct(F.lit(h + p).alias("rule"), F.lit(action).alias("verdict")))
        for action, h, p in ordered
    ]
    return F.coalesce(*fits)


def without_dots(path: Column) -> Column:
    """The path with its `.` and `..` segments applied; one that ends in such a segment ends in a slash."""
    parts = F.split(path, "/")
    kept = F.aggregate(F.slice(parts, 2, F.greatest(F.size(parts) - 1, F.lit(0))), F.array().cast("array<string>"), lambda done, p: (
        F.when(p == "..", F.slice(done, 1, F.greatest(F.size(done) - 1, F.lit(0)))).when(p == ".", done).otherwise(F.concat(done, F.array(p)))))
    slash = path.rlike(r"/\.\.?$") & (F.size(kept) > 0)
    return F.when(path.contains("/."), F.concat(F.lit("/"), F.array_join(kept, "/"), F.when(slash, F.lit("/")).otherwise(F.lit("")))).otherwise(path)


def normalised(url: Column) -> Column:
    """The key under which urls are aliases: lower-case host, path without dot segments, and query; no scheme, fragment and
    outer blanks."""
    host, path = host_and_path(F.trim(url))
    query = F.regexp_extract(F.trim(url), r"(?s)^[^?#]*(\?[^#]*)", 1)
    return F.when((host != "") & url.isNotNull(), F.concat(host, F.when(path == "", F.lit("/")).otherwise(without_dots(path)), query))


#: Character references that may stand in an attribute, the ampersand last.
REFERENCES = ((r"&(?:quot|#34|#[xX]22);", '"'), (r"&(?:apos|#39|#[xX]27);", "'"), (r"&(?:lt|#60|#[xX]3[cC]);", "<"), (r"&(?:gt|#62|#[xX]3[eE]);", ">"), (r"&(?:amp|#38|#[xX]26);", "&"))


def decoded(value: Column) -> Column:
    for pattern, character in REFERENCES:
        value = F.regexp_replace(value, pattern, character)
    return value


def absolute(url: Column, target: Column) -> Column:
    """The target as seen from the page: with scheme and host. Null for an empty one and for other schemes than those of
    the web (mailto and the like have no host)."""
    bare = F.regexp_extract(F.trim(url), r"(?s)^([^#]*)", 1)
    without_query = F.regexp_extract(bare, r"(?s)^([^?]*)", 1)
    scheme = F.regexp_extract(bare, r"^([^:/?#]+):", 1)
    origin = F.regexp_extract(bare, r"^([^:/?#]+://[^/?#]*)", 1)
    rooted = F.when(without_query == origin, F.concat(origin, F.lit("/"))).otherwise(F.regexp_extract(without_query, r"(?s)^(.*/)", 1))
    return (F.when((target == "") | (origin == ""), None)
            .when(target.rlike(r"^[A-Za-z][A-Za-z0-9+.-]*://"), target)
            .when(target.startswith("//"), F.concat(scheme, F.lit(":"), target))
            .when(target.rlike(r"^[A-Za-z][A-Za-z0-9+.-]*:"), None)
            .when(target.startswith("/"), F.concat(origin, target))
            .when(target.startswith("?"), F.concat(without_query, target))
            .when(target.startswith("#"), bare)
            .otherwise(F.concat(rooted, target)))


def link_targets(url: Column, html: Column) -> Column:
    """Targets of canonical links and refresh redirects in the html, absolute."""
    low = r"(?is)"
    tag = F.regexp_extract_all(html, F.lit(low + r"(<(?:link|meta)\b[^>]*>)"), F.lit(1))
    canonical = F.transform(
        F.filter(tag, lambda t: t.rlike(low + r"^<link\b.*\brel\s*=\s*[\"']?\s*canonical\b")),
        lambda t: F.regexp_extract(t, low + r"\bhref\s*=\s*[\"']?\s*([^\"'\s>]+)", 1))
    refresh = F.transform(
        F.filter(tag, lambda t: t.rlike(low + r"^<meta\b.*\bhttp-equiv\s*=\s*[\"']?\s*refresh\b")),
        lambda t: F.regexp_extract(t, low + r"\burl\s*=\s*[\"']?\s*([^\"'\s>]+)", 1))
    found = F.filter(F.transform(F.concat(canonical, refresh), lambda t: absolute(url, decoded(t))), lambda t: t.isNotNull())
    # most pages have neither: a plain search saves the patterns
    return F.when(F.lower(html).contains("canonical") | F.lower(html).contains("refresh"), found)


def judge(pages: DataFrame, rules=RULES, redirects: DataFrame | None = None) -> DataFrame:
    """pages (page_id, url, html) -> page_id, host, path, rule, verdict, component.

    redirects: optional table (from_url, to_url) of redirects seen while crawling. Urls are grouped to one row each
    before components are formed; only urls with a link take part in the iteration.
    """
    host, path = host_and_path(F.col("url"))
    links = (pages.select(normalised(F.col("url")).alias("u"), F.explode(link_targets(F.col("url"), F.col("html"))).alias("t"))
             .select("u", normalised(F.col("t")).alias("v")))
    if redirects is not None:
        links = links.unionAll(redirects.select(normalised(F.col("from_url")), normalised(F.col("to_url"))))
    components = connected_components(links)
    ruled = pages.select("page_id", normalised(F.col("url")).alias("__key"), host.alias("host"), path.alias("path"))
    ruled = ruled.withColumn("__own", longest_rule(F.col("host"), F.col("path"), rules))
    # a decision reaches aliases from any url of the component, crawled or only linked to
    nodes = written(components.select("node", "component"), "aliases")
    node_host = F.regexp_extract("node", r"^([^/?#]*)", 1)
    node_path = F.regexp_extract(F.regexp_replace("node", r"^[^/?#]*", ""), r"(?s)^([^?#]*)", 1)
    decision = longest_rule(node_host, node_path, rules)["verdict"]
    # 'allow' sorts before 'block'; a very large component is dealt over several tasks
    decided = nodes.select("component", decision.alias("d")).groupBy(F.col("component").alias("c")).agg(F.min("d").alias("shared"), F.count("*").alias("members"))
    n_nodes = nodes.count()
    shared = hot_join(nodes, decided, "component", "c", "members", n_nodes).select("node", "component", "shared")
    if n_nodes:
        weights = ruled.groupBy(F.col("__key").alias("w")).agg(F.count("*").alias("pages"))
        shared = shared.join(weights, F.col("node") == F.col("w"), "left").select("node", "component", "shared", F.coalesce("pages", F.lit(0)).alias("pages"))
        out = hot_join(ruled, shared, "__key", "node", "pages", pages.count(), "left")
    else:
        out = ruled.join(shared, F.col("__key") == F.col("node"), "left")
    return out.select("page_id", "host", "path", F.col("__own")["rule"].alias("rule"),
                      F.coalesce(F.col("__own")["verdict"], F.col("shared"), F.lit("allow")).alias("verdict"), "component")
