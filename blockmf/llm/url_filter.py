"""URL filter with redirect equivalence, in DataFrame operations only.

A url is judged by its host and path: the longest rule that fits decides. Urls without a rule take the decision
of their aliases: pages are nodes (host + path), canonical links, refresh redirects and given redirect pairs are
edges, and the connected components of that graph spread decisions. Pages whose urls differ only after '?' or '#' are one node
and share their links, since rules look at host and path alone. Precedence for a url without a rule of its
own: an alias that a rule allows makes the component allowed; else an alias that a rule blocks makes it blocked;
else it is allowed.

Edge cases. Null url or one without '://': host and path empty, no rule, no aliases, allowed. Null or empty html:
no links. Repeated pages: one row each. Empty table: empty result. Link targets that are no pages themselves still
carry decisions. Relative targets are resolved against the page; targets that are not http(s) are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from blockmf.llm.common import UPPER
from blockmf.llm.components import connected_components

RULES = (("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/"))

_LINK = r"(?is)<link\b[^>]*\brel\s*=\s*[\"']?canonical\b[^>]*>"
_META = r"(?is)<meta\b[^>]*\bhttp-equiv\s*=\s*[\"']?refresh\b[^>]*>"
_HREF = (r"(?is)\bhref\s*=\s*\"([^\"]*)\"", r"(?is)\bhref\s*=\s*'([^']*)'", r"(?is)\bhref\s*=\s*([^\s\"'>]+)")
_URL = (r"(?is)\burl\s*=\s*[\"']?([^\"'>\s]+)",)


def host_of(url: Column) -> Column:
    at = F.locate("://", url)
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url)))
    return F.coalesce(F.translate(F.regexp_extract(rest, r"^([^/?#]*)", 1), UPPER, UPPER.lower()), F.lit(""))


def path_of(url: Column) -> Column:
    rest = F.when(F.locate("://", url) > 0, F.substring(url, F.locate("://", url) + 3, F.length(url)))
    return F.coalesce(F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1), F.lit(""))


def rule_of(host: Column, path: Column, rules=RULES) -> Column:
    """struct(action, rule) of the longest rule that fits, else null."""
    said = F.lit(None).cast("struct<action:string,rule:string>")
    for action, h, p in sorted(rules, key=lambda r: len(r[1]) + len(r[2])):
        fits = ((host == h) | host.endswith(f".{h}")) & path.startswith(p)
        said = F.when(fits, F.struct(F.lit(action).alias("action"), F.lit(h + p).alias("rule"))).otherwise(said)
    return said


def _first(text: Column, patterns) -> Column:
    return F.coalesce(*[F.nullif(F.regexp_extract(text, p, 1), F.lit("")) for p in patterns])


def _resolve(base: Column, host: Column, path: Column, target: Column) -> Column:
    target = F.trim(target)
    scheme = F.substring_index(base, "://", 1)
    site = F.concat(scheme, F.lit("://"), host)
    folder = F.regexp_extract(path, r"^(.*/)", 1)
    return (
        F.when(target.rlike(r"(?i)^https?://"), target)
        .when(target.startswith("//"), F.concat(scheme, F.lit(":"), target))
        .when(target.startswith("/"), F.concat(site, target))
        .when(target.rlike(r"^[A-Za-z][A-Za-z0-9+.-]*:"), F.lit(None).cast("string"))
        .when(target.rlike(r"^[?#]"), F.concat(site, path))
        .otherwise(F.concat(site, F.when(folder == "", F.lit("/")).otherwise(folder), target))
    )


def alias_edges(pages: DataFrame) -> DataFrame:
    """(src, dst): host + path of a page and of what its canonical link or refresh points at."""
    linked = pages.where(F.col("html").rlike(r"(?i)canonical|http-equiv") & (F.locate("://", F.col("url")) > 0))
    linked = linked.select("url", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"), _first(F.regexp_extract("html", _LINK, 0), _HREF).alias("canon"), _first(F.regexp_extract("html", _META, 0), _URL).alias("moved"))
    to = linked.select(F.concat("host", "path").alias("src"), F.explode(F.array("canon", "moved")).alias("target"), "url", "host", "path").where("target is not null")
    to = to.withColumn("full", _resolve(F.col("url"), F.col("host"), F.col("path"), F.col("target"))).where("full is not null")
    return to.select("src", F.concat(host_of(F.col("full")), path_of(F.col("full"))).alias("dst")).where("src != dst and src != '' and dst != ''")


def judge(pages: DataFrame, rules=RULES, redirects: DataFrame | None = None) -> DataFrame:
    """pages(page_id, url, html) -> page_id, host, path, rule, verdict, component. redirects: optional (src_url, dst_url) pairs."""
    page = pages.select("page_id", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))
    page = page.withColumn("own", rule_of(F.col("host"), F.col("path"), rules)).withColumn("node", F.nullif(F.concat("host", "path"), F.lit("")))
    edges = alias_edges(pages)
    if redirects is not None:
        a, b = F.col("src_url"), F.col("dst_url")
        given = redirects.where((F.locate("://", a) > 0) & (F.locate("://", b) > 0)).select(F.concat(host_of(a), path_of(a)).alias("src"), F.concat(host_of(b), path_of(b)).alias("dst"))
        edges = edges.unionByName(given.where("src != dst"))
    comp = connected_components(edges, "src", "dst")
    if comp.isEmpty():
        judged = page.withColumn("component", F.col("node")).withColumn("spread", F.lit(None).cast("string"))
    else:
        host, path = F.regexp_extract("node", r"^([^/?#]*)", 1), F.regexp_extract("node", r"^[^/?#]*([^?#]*)", 1)
        said = rule_of(host, path, rules)["action"]
        spread = comp.groupBy("component").agg(F.when(F.max(said == "allow"), "allow").when(F.max(said == "block"), "block").alias("spread"))
        labelled = comp.join(spread, "component")
        judged = page.join(labelled, "node", "left").withColumn("component", F.coalesce("component", "node"))
    verdict = F.coalesce(F.col("own.action"), F.col("spread"), F.lit("allow"))
    return judged.select("page_id", "host", "path", F.col("own.rule").alias("rule"), verdict.alias("verdict"), "component")
