"""URL filters: host and path rules, carried over redirects and canonical links.

A rule names a host, which stands for all its subdomains, and a prefix of the path; the longest rule that fits decides. Pages without
a rule take the decision of their equivalence class: a URL without its fragment is a node; canonical links, refresh redirects and
given redirects are edges; classes are connected components. With `spellings`, URLs that differ only in scheme, `www.` or `m.`, tracking
parameters, `.html` or a last slash are one node too. An explicit allow anywhere in a class outweighs blocks; a class without any
rule is allowed.

Edge cases: a null url, or one without `://`, has neither host nor path, fits no rule and is a node of its own text; null html has no
links; relative link targets are resolved; links elsewhere than http(s) are ignored; repeated rows share a node; rules of
equal length are taken in the order of their text.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from webtext.llm.graph import components

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_and_path(url: Column) -> tuple[Column, Column]:
    found = F.coalesce(url.contains("://"), F.lit(False))
    rest = F.substr(url, F.instr(url, "://") + 3)
    raw = F.regexp_extract(rest, r"^[^/?#]*", 0)
    path = F.regexp_extract(F.substr(rest, F.length(raw) + 1), r"^[^?#]*", 0)
    return F.when(found, F.translate(raw, _UPPER, _LOWER)).otherwise(""), F.when(found, path).otherwise("")


def canonical(url: Column) -> Column:
    """One spelling for URLs that lead to the same page; the url itself if it has no host."""
    host, path = host_and_path(url)
    query = F.regexp_extract(url, r"^[^?#]*\?([^#]*)", 1)
    kept = F.array_join(F.array_sort(F.filter(F.split(query, "&"), lambda p: (p != "") & ~p.rlike(r"^(utm_[a-z]+|ref|fbclid|gclid)="))), "&")
    clean = F.regexp_replace(F.regexp_replace(path, r"\.html?$", ""), r"/+$", "")
    return F.when(host == "", F.coalesce(url, F.lit(""))).otherwise(F.concat(F.regexp_replace(host, r"^(www|m)\.", ""), clean, F.when(kept != "", F.concat(F.lit("?"), kept)).otherwise("")))


def absolute(target: Column, base: Column) -> Column:
    """target as seen from the page base; null if it is no web address."""
    target = F.replace(F.trim(target), F.lit("&amp;"), F.lit("&"))
    site = F.regexp_extract(base, r"^[^:]+://[^/?#]*", 0)
    folder = F.regexp_replace(F.regexp_replace(base, r"[?#].*$", ""), r"(?<=[^/:])/[^/]*$", "")
    return (
        F.when(target.rlike(r"(?i)^https?://"), target)
        .when(target.startswith("//"), F.concat(F.substring_index(base, "//", 1), target))
        .when(target.startswith("/"), F.concat(site, target))
        .when((target != "") & ~target.rlike(r"^[A-Za-z][A-Za-z0-9+.-]*:"), F.concat(folder, F.lit("/"), target))
    )


def links(pages: DataFrame) -> DataFrame:
    """from_url, to_url of the canonical links and refresh redirects of pages (url, html)."""
    tags = F.regexp_extract_all("html", F.lit(r"(?i)<(?:link|meta)\b[^>]*>"), F.lit(0))
    tag = pages.where(F.col("html").rlike("(?i)canonical|refresh")).select("url", F.explode(tags).alias("tag"))
    href = F.regexp_extract("tag", r"""(?i)\bhref\s*=\s*["']?([^"'\s>]+)""", 1)
    refresh = F.regexp_extract("tag", r"""(?i)\bcontent\s*=\s*["']?[^"'>]*?url\s*=\s*'?([^"'\s>]+)""", 1)
    to = F.when(F.col("tag").rlike(r"""(?i)^<link\b.*\brel\s*=\s*["']?canonical\b"""), href).when(F.col("tag").rlike(r"""(?i)^<meta\b.*\bhttp-equiv\s*=\s*["']?refresh\b"""), refresh)
    return tag.select(F.col("url").alias("from_url"), absolute(to, F.col("url")).alias("to_url")).where("to_url is not null")


Rules = list[tuple[str, str, str]]


def _longest(host: Column, path: Column, rules: Rules) -> tuple[Column, Column]:
    """rule and verdict; rules are (verdict, host, path), at most a few thousand as they become part of the plan."""
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for said, h, p in sorted(rules, key=lambda r: (-len(r[1] + r[2]), r[1] + r[2]), reverse=True):
        fits = ((host == h) | host.endswith(f".{h}")) & path.startswith(p)
        rule, verdict = F.when(fits, F.lit(h + p)).otherwise(rule), F.when(fits, F.lit(said)).otherwise(verdict)
    return rule, verdict


def judge(pages: DataFrame, rules: Rules, redirects: DataFrame | None = None, spellings: bool = False) -> DataFrame:
    """page_id, host, path, rule, verdict of pages (page_id, url, html); redirects (from_url, to_url) are further edges."""
    found = links(pages)
    if redirects is not None:
        found = found.unionByName(redirects.select("from_url", "to_url"))
    plain = lambda url: F.coalesce(F.regexp_replace(url, r"(?s)#.*$", ""), F.lit(""))
    node = lambda url: F.xxhash64(canonical(F.col(url)) if spellings else plain(F.col(url)))
    labels = components(found.select(node("from_url").alias("u"), node("to_url").alias("v")))
    host, path = host_and_path(F.col("url"))
    rule, said = _longest(F.col("host"), F.col("path"), rules)
    own = pages.select("page_id", host.alias("host"), path.alias("path"), node("url").alias("node")).withColumns({"rule": rule, "said": said})
    own = own.join(labels, "node", "left").withColumn("comp", F.coalesce("comp", "node")).drop("node")
    judged = own.where("said is not null").groupBy("comp").agg(F.bool_or(F.col("said") == "allow").alias("allowed"))
    shared = F.when(F.col("allowed"), "allow").when(~F.col("allowed"), "block").otherwise("allow")
    return own.join(judged, "comp", "left").select("page_id", "host", "path", "rule", F.coalesce("said", shared).alias("verdict"))
