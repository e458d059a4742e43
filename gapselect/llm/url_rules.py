"""URL filters with redirect equivalence, with DataFrame functions only.

Host and path rules decide first: a rule fits its host and all subdomains where the path
starts with the rule's path, and the longest fitting rule wins. Pages without a rule of
their own follow their aliases. Redirects (``meta refresh``) and canonical links are edges
between URL keys (host, path and query without tracking parameters); connected components
over them are alias classes. A class that holds an explicitly allowed URL is allowed; else
one that holds a blocked URL is blocked; else the default applies. Link targets that are no
pages take part with the verdict of their own URL.

Defined results: a null URL or one without ``://`` has empty host and path, no rule and no
aliases, and gets the default; null html has no edges; repeated rows are judged each; an
empty table gives no rows; extra columns are not read.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gapselect.llm.common import written
from gapselect.llm.components import connected_components

#: scheme://host path ?query, taken apart at the first "://".
_PARTS = r"(?s)^.*?://([^/?#]*)([^?#]*)(\?[^#]*)?"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Query parameters that only tell where a visitor came from: fixed values.
TRACKING = r"(?i)(utm_[a-z]+|gclid|fbclid|ref|msclkid|mc_cid|mc_eid)"


@dataclass(frozen=True)
class UrlRule:
    verdict: str
    host: str
    path: str = "/"

    @property
    def text(self) -> str:
        return self.host + self.path


#: The rules of the registered query: fixed values.
RULES = (
    UrlRule("allow", "org"),
    UrlRule("block", "example.org", "/es/"),
    UrlRule("block", "example.org", "/en/1"),
    UrlRule("allow", "com", "/fr/"),
    UrlRule("block", "com", "/de/"),
)


def host_of(url: Column) -> Column:
    return F.coalesce(F.translate(F.regexp_extract(url, _PARTS, 1), _UPPER, _LOWER), F.lit(""))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, _PARTS, 2), F.lit(""))


def matched_rule(host: Column, path: Column, rules: tuple[UrlRule, ...]) -> Column:
    """The longest fitting rule as struct(text, verdict), null where none fits. Rules are
    tried from the longest to the shortest, of equal ones the longer host first."""
    out = F.lit(None).cast("struct<text:string,verdict:string>")
    for r in sorted(rules, key=lambda r: (len(r.text), len(r.host), r.text)):
        fits = ((host == r.host) | host.endswith("." + r.host)) & path.startswith(r.path)
        out = F.when(fits, F.struct(F.lit(r.text).alias("text"), F.lit(r.verdict).alias("verdict"))).otherwise(out)
    return out


def url_key(url: Column) -> Column:
    """What two URLs must share to be one page; null for what is no URL."""
    query = F.regexp_extract(url, _PARTS, 3)
    kept = F.filter(F.split(F.substring(query, 2, 1 << 30), "&"), lambda p: (p != "") & ~p.rlike("^" + TRACKING + "(=.*)?$"))
    path = F.when(path_of(url) == "", F.lit("/")).otherwise(path_of(url))
    key = F.concat(host_of(url), path, F.when(F.size(kept) > 0, F.concat(F.lit("?"), F.array_join(F.array_sort(kept), "&"))).otherwise(F.lit("")))
    return F.when(host_of(url) != "", key)


_ATTRIBUTE = r"""\s*=\s*["']?([^"'>\s]+)"""
CANONICAL = r"""(?is)<link\b(?=[^>]*\brel\s*=\s*["']?canonical\b)[^>]*\bhref""" + _ATTRIBUTE
REFRESH = r"""(?is)<meta\b(?=[^>]*\bhttp-equiv\s*=\s*["']?refresh\b)[^>]*\bcontent\s*=\s*["']?[^"'>]*?url\s*=\s*["']?([^"'>\s;]+)"""


def resolved(target: Column, base: Column) -> Column:
    """``target`` as an absolute URL, seen from the page at ``base``."""
    scheme = F.regexp_extract(base, r"(?s)^(.*?)://", 1)
    root = F.regexp_extract(base, r"(?s)^(.*?://[^/?#]*)", 1)
    folder = F.regexp_extract(path_of(base), r"(?s)^(.*/)", 1)
    return (
        F.when(target.contains("://"), target)
        .when(target.startswith("//"), F.concat(scheme, F.lit(":"), target))
        .when(target.startswith("/"), F.concat(root, target))
        .otherwise(F.concat(root, F.when(folder == "", F.lit("/")).otherwise(folder), target))
    )


def alias_edges(pages: DataFrame, url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(u, v, to): keys of the two ends and the URL of the target, one row per different edge."""
    html, url = F.col(html_col), F.col(url_col)
    found = pages.filter(html.rlike(r"(?i)canonical|http-equiv")).select(
        url.alias("url"), F.explode(F.array_union(F.regexp_extract_all(html, F.lit(CANONICAL), F.lit(1)), F.regexp_extract_all(html, F.lit(REFRESH), F.lit(1)))).alias("target")
    )
    to = F.regexp_replace(resolved(F.col("target"), F.col("url")), "&amp;", "&")
    return found.select(url_key(F.col("url")).alias("u"), url_key(to).alias("v"), to.alias("to")).filter("u IS NOT NULL AND v IS NOT NULL AND u <> v").distinct()


def judge_urls(pages: DataFrame, rules: tuple[UrlRule, ...] = RULES, default: str = "allow", id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """id, host, path, rule, verdict, and whether the verdict came over an alias."""
    url = F.col(url_col)
    parts = pages.select(F.col(id_col).alias("id"), url.alias("url"), host_of(url).alias("host"), path_of(url).alias("path"))
    own = parts.withColumn("m", matched_rule(F.col("host"), F.col("path"), rules))
    edges = written(alias_edges(pages, url_col, html_col))
    label = written(connected_components(edges.select("u", "v")))
    ends = own.select(url_key(F.col("url")).alias("node"), F.col("m.verdict").alias("v")).unionByName(
        edges.select(F.col("v").alias("node"), matched_rule(host_of(F.col("to")), path_of(F.col("to")), rules)["verdict"].alias("v"))
    )
    # Of a node's verdicts one is enough; 'allow' comes before 'block'.
    told = ends.filter("v IS NOT NULL").groupBy("node").agg(F.min("v").alias("v"))
    seen = written(told.join(label, "node").groupBy("component").agg(F.min("v").alias("said")))
    classes = written(label.join(seen, "component").select("node", "said"))
    judged = own.withColumn("node", url_key(F.col("url"))).join(classes, "node", "left")
    return judged.select(
        F.col("id").alias(id_col), "host", "path", F.col("m.text").alias("rule"),
        F.coalesce("m.verdict", "said", F.lit(default)).alias("verdict"),
        (F.col("m").isNull() & F.col("said").isNotNull()).alias("by_alias"),
    )
