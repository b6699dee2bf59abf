"""URL rules with redirect equivalence, in DataFrame operations only.

A page's own rule decides first: the longest rule that fits its host and path.  A page without one takes the decision of
its aliases: pages and link targets tied by canonical links (``<link rel=canonical>``), immediate redirects (``<meta
http-equiv=refresh>``) or equal addresses form connected components; a component with an explicitly allowed address allows,
else one with a blocked address blocks, else the page is allowed.

A null url, or one without ``://``, has empty host and path, no rule and no alias; a null html has no links; repeated
pages are judged one by one; an empty table gives no rows; columns other than id, url and html are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from segcube.llm import shared
from segcube.llm.components import components

# The rules of the query (action, host, path).
RULES = (
    ("block", "net", "/"),
    ("allow", "example.net", "/en/"),
    ("block", "example.com", "/de/"),
    ("allow", "org", "/fr/"),
)


def host_of(url: Column) -> Column:
    return F.translate(F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://([^/?#]*)", 1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def path_of(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://[^/?#]*([^?#]*)", 1)


def _fits(host: Column, path: Column, rule: tuple[str, str, str]) -> Column:
    _, rule_host, rule_path = rule
    return ((host == rule_host) | host.endswith("." + rule_host)) & path.startswith(rule_path)


def rule_of(host: Column, path: Column, rules=RULES) -> Column:
    """The longest fitting rule as ``struct(action, rule)``, or null; a chain of tests, meant for some hundred rules."""
    out = F.lit(None).cast("struct<action:string,rule:string>")
    for rule in sorted(rules, key=lambda r: (len(r[1] + r[2]), r[1] + r[2])):
        out = F.when(_fits(host, path, rule), F.struct(F.lit(rule[0]).alias("action"), F.lit(rule[1] + rule[2]).alias("rule"))).otherwise(out)
    return out


def _without_dots(path: Column) -> Column:
    """A path with its ``.`` and ``..`` segments resolved; it ends in a slash where it ended in such a segment."""
    parts = F.split(F.substring(path, 2, 1 << 30), "/")
    step = lambda done, part: F.when(part == "..", F.slice(done, 1, F.greatest(F.size(done) - 1, F.lit(0)))).when(part == ".", done).otherwise(F.array_append(done, part))
    left = F.aggregate(parts, F.array().cast("array<string>"), step)
    ending = F.when(path.rlike(r"/\.\.?$") & (F.size(left) > 0), "/").otherwise("")
    return F.when(path.rlike(r"/\.\.?(/|$)"), F.concat(F.lit("/"), F.array_join(left, "/"), ending)).otherwise(path)


def address_of(url: Column) -> Column:
    """Scheme, fragment and dot segments do not tell addresses apart; host, path and query do.  Null where there is no host."""
    path = path_of(url)
    query = F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://[^?#]*(\?[^#]*)", 1)
    return F.when(host_of(url) != "", F.concat(host_of(url), F.when(path == "", "/").otherwise(_without_dots(path)), query))


def link_targets(html: Column) -> Column:
    """Canonical and redirect targets of a page, as they stand."""
    tags = F.regexp_extract_all(F.coalesce(html, F.lit("")), F.lit(r"(?is)<(?:link|meta)\s[^>]*>"), F.lit(0))
    canonical = F.transform(F.filter(tags, lambda t: t.rlike(r"(?is)^<link\b.*\brel\s*=\s*[\"']?canonical\b")), lambda t: F.regexp_extract(t, r"(?is)\bhref\s*=\s*[\"']?([^\"'\s>]+)", 1))
    refresh = F.transform(F.filter(tags, lambda t: t.rlike(r"(?is)^<meta\b.*\bhttp-equiv\s*=\s*[\"']?refresh\b")), lambda t: F.regexp_extract(t, r"(?is)\bcontent\s*=\s*[\"']?[^\"'>]*?url\s*=\s*[\"']?([^\"'\s>]+)", 1))
    return F.transform(F.filter(F.concat(canonical, refresh), lambda t: t != ""), lambda t: F.regexp_replace(t, "&amp;", "&"))


def absolute(target: Column, url: Column) -> Column:
    """A link's target seen from the page's url: absolute, host-relative, root-relative or relative to its folder."""
    origin = F.regexp_extract(url, r"(?s)^(.*?://[^/?#]*)", 1)
    folder = F.regexp_extract(url, r"(?s)^(.*?://[^/?#]*/(?:[^?#]*/)?)", 1)
    return (
        F.when(target.contains("://"), target)
        .when(target.startswith("//"), F.concat(F.lit("http:"), target))
        .when(target.startswith("/"), F.concat(origin, target))
        .otherwise(F.concat(F.when(folder != "", folder).otherwise(F.concat(origin, F.lit("/"))), target))
    )


def judge(pages: DataFrame, rules=RULES, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """One row per page: ``page_id, host, path, rule, verdict, reason``."""
    seen = pages.select(F.col(id_col).alias("page_id"), F.col(url_col).alias("url"), F.col(html_col).alias("html"))
    links = seen.filter("url is not null").select(address_of(F.col("url")).alias("a"), F.explode(F.transform(link_targets(F.col("html")), lambda t: address_of(absolute(t, F.col("url"))))).alias("b"))
    edges = shared.materialised(links.filter("a is not null and b is not null and a != b").distinct(), "links")
    judged = seen.select("page_id", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"), address_of(F.col("url")).alias("node")).withColumn("own", rule_of(F.col("host"), F.col("path"), rules))
    if edges.isEmpty():
        judged = judged.withColumn("method", F.lit(None).cast("string"))
    else:
        ties = components(edges)
        address = F.concat(F.lit("http://"), F.col("node"))
        decided = ties.withColumn("action", rule_of(host_of(address), path_of(address), rules)["action"])
        by_component = decided.groupBy("component").agg(F.max(F.when(F.col("action") == "allow", 2).when(F.col("action") == "block", 1).otherwise(0)).alias("strength"))
        aliases = ties.join(by_component.filter("strength > 0"), "component").select("node", F.when(F.col("strength") == 2, "allow").otherwise("block").alias("method"))
        judged = judged.join(aliases, "node", "left")
    return judged.select(
        "page_id", "host", "path", F.col("own.rule").alias("rule"), F.coalesce(F.col("own.action"), F.col("method"), F.lit("allow")).alias("verdict"),
        F.when(F.col("own").isNotNull(), "rule").when(F.col("method").isNotNull(), "alias").otherwise("default").alias("reason"),
    )
