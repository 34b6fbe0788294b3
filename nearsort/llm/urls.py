"""URL filter rules, spread over redirect and canonical-link equivalence. DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from .components import components

#: Rules of the page query: (verdict, host, path prefix).
RULES = (("block", "com", "/en/"), ("allow", "example.com", "/en/7"), ("allow", "net", "/de/"), ("block", "example.net", "/de/8"), ("block", "org", "/es/"))
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_of(url: Column) -> Column:
    """After the first :// up to / ? # or the end, A-Z lower-cased; empty for null or without ://."""
    rest = F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1)
    return F.coalesce(F.translate(rest, _UPPER, _LOWER), F.lit(""))


def path_of(url: Column) -> Column:
    """After the host, up to ? # or the end."""
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def best_rule(host: Column, path: Column, rules: tuple[tuple[str, str, str], ...] = RULES) -> tuple[Column, Column]:
    """(rule text, verdict) of the longest rule that fits, else nulls. Equal lengths: allow, then the text that sorts first."""
    ordered = sorted(rules, key=lambda r: (-len(r[1] + r[2]), r[0] != "allow", r[1] + r[2]))
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for kind, h, p in reversed(ordered):
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        rule, verdict = F.when(fits, h + p).otherwise(rule), F.when(fits, kind).otherwise(verdict)
    return rule, verdict


def absolute(target: Column, base: Column) -> Column:
    """A link's target as a url of its own: as it is if it has a scheme, else on the base's scheme, host or folder. &amp; is undone; dots are kept as they are."""
    target = F.regexp_replace(F.trim(target), r"(?i)&amp;|&#38;|&#x26;", "&")
    scheme = F.regexp_extract(base, r"(?s)^(.*?:)//", 1)
    origin = F.regexp_extract(base, r"(?s)^(.*?://[^/?#]*)", 1)
    page = F.regexp_extract(base, r"(?s)^(.*?://[^/?#]*[^?#]*)", 1)
    folder = F.when(page == origin, F.concat(origin, F.lit("/"))).otherwise(F.regexp_replace(page, r"[^/]*$", ""))
    whole = (
        F.when(target.rlike(r"^[A-Za-z][A-Za-z0-9+.-]*:"), target)
        .when(target.startswith("//"), F.concat(scheme, target))
        .when(target.startswith("/"), F.concat(origin, target))
        .when(target.startswith("?"), F.concat(page, target))
        .when(target.startswith("#") | (target == ""), F.lit(None).cast("string"))
        .otherwise(F.concat(folder, target))
    )
    return F.when((origin != "") | target.contains("://"), whole)


def canonical_links(pages: DataFrame, url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(src, dst): targets of canonical links and of refresh redirects named in the html, relative ones as absolute() resolves them."""
    tag = r"(?is)<link\b(?=[^>]*\brel\s*=\s*[\"']?canonical\b)[^>]*\bhref\s*=\s*[\"']?([^\"'\s>]+)"
    refresh = r"(?is)<meta\b(?=[^>]*\bhttp-equiv\s*=\s*[\"']?refresh\b)[^>]*\bcontent\s*=\s*[\"'][^\"'>]*?url\s*=\s*([^\"'\s>]+)"
    html = F.col(html_col)
    found = F.array(*(F.regexp_extract(html, x, 1) for x in (tag, refresh)))
    marked = pages.where(html.contains("anonical") | html.contains("CANONICAL") | F.lower(html).contains("refresh"))
    links = marked.select(F.col(url_col).alias("src"), F.explode(found).alias("dst")).where("src is not null and dst <> ''")
    return links.select("src", absolute(F.col("dst"), F.col("src")).alias("dst")).where(F.col("dst").contains("://"))


def judge(pages: DataFrame, rules: tuple[tuple[str, str, str], ...] = RULES, redirects: DataFrame | None = None, id_col: str = "page_id", url_col: str = "url", html_col: str | None = "html") -> DataFrame:
    """host, path, rule and verdict of every page's url.

    Redirects (columns src, dst) and canonical links join urls into classes of aliases. A url
    that a rule fits has that rule's verdict: an explicit allow is never overruled. Any other is
    blocked if a url of its class is blocked by a rule and none is allowed by one, else allowed.
    Null urls have empty host and path, fit no rule with a host and are in no class; repeated rows
    each give a row. An empty table gives an empty result; further columns are ignored.
    """
    host, path = host_of(F.col("url")), path_of(F.col("url"))
    base = pages.select(F.col(id_col), F.col(url_col).alias("url")).select(F.col(id_col), "url", host.alias("host"), path.alias("path"))
    rule, verdict = best_rule(F.col("host"), F.col("path"), rules)
    base = base.withColumns({"rule": rule, "own": verdict})
    edges = None
    if html_col and html_col in pages.columns:
        edges = canonical_links(pages, url_col, html_col)
    if redirects is not None:
        given = redirects.select(F.col("src").cast("string"), F.col("dst").cast("string"))
        edges = given if edges is None else edges.unionByName(given)
    if edges is None:
        return base.select(id_col, "host", "path", "rule", F.coalesce("own", F.lit("allow")).alias("verdict"))
    roots = components(edges, "src", "dst")
    members = roots.unionByName(roots.select(F.col("root").alias("node"), "root")).distinct()
    own = best_rule(host_of(F.col("node")), path_of(F.col("node")), rules)[1]
    classes = members.withColumn("own", own).groupBy("root").agg(F.max(F.col("own") == "block").alias("blocked"), F.max(F.col("own") == "allow").alias("allowed"))
    spread = classes.where("blocked and not coalesce(allowed, false)").select("root").join(members, "root").select(F.col("node").alias("url"), F.lit("block").alias("alias"))
    columns = (id_col, "host", "path", "rule", F.coalesce("own", "alias", F.lit("allow")).alias("verdict"))
    joined = base.where("url is not null").join(spread, "url", "left").select(*columns)  # null urls would all meet in one task
    return joined.unionByName(base.where("url is null").withColumn("alias", F.lit(None).cast("string")).select(*columns))
