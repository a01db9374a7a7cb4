"""URL rules with redirect equivalence, with DataFrame functions only."""

from __future__ import annotations

import json
from html.entities import html5

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ascii_lower, let, stage, table
from .components import components

#: Fixed by the contract: verdict, host, path.
RULES = [("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/")]

_PARTS = r"^(?s)(.*?)://([^/?#]*)([^?#]*)(\??[^#]*)"
_SCHEME = r"^[A-Za-z][A-Za-z0-9+.\-]*:"
_CANONICAL = r"(?is)<link\b(?=[^>]*\brel\s*=\s*[\"']?canonical\b)[^>]*\bhref\s*=\s*[\"']?\s*([^\"'\s>]+)"
_REFRESH = r"(?is)<meta\b(?=[^>]*\bhttp-equiv\s*=\s*[\"']?refresh\b)[^>]*\burl\s*=\s*[\"']?\s*([^\"'\s>]+)"
_BASE = r"(?is)<base\b[^>]*\bhref\s*=\s*[\"']?\s*([^\"'\s>]+)"
#: Fixed by HTML: the named entities that end in `;`.
_NAMED = json.dumps({k: v for k, v in html5.items() if k.endswith(";")})


def host(url: Column) -> Column:
    """Null or without `://`: empty."""
    return F.coalesce(ascii_lower(F.regexp_extract(url, _PARTS, 2)), F.lit(""))


def path(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, _PARTS, 3), F.lit(""))


def _undotted(p: Column) -> Column:
    """A path without `.` and `..` steps; above the root there is nothing."""
    step = lambda done, x: F.when(x == "..", F.slice(done, 1, F.greatest(F.size(done) - 1, F.lit(1)))).when(x == ".", done).otherwise(F.concat(done, F.array(x)))
    parts = lambda w: F.concat(F.aggregate(F.slice(w, 2, F.size(w)), F.array(F.lit("")), step), F.when(F.element_at(w, -1).isin(".", ".."), F.array(F.lit(""))).otherwise(F.array().cast("array<string>")))
    return F.when(p.contains("/."), F.array_join(let(F.split(p, "/", -1), parts), "/")).otherwise(p)


def resource(url: Column) -> Column:
    """The node of a url: scheme, host, path without dot steps and query; an empty path is `/`, a fragment names the same resource."""
    p = F.when(path(url) == "", "/").otherwise(_undotted(path(url)))
    return F.concat(ascii_lower(F.regexp_extract(url, _PARTS, 1)), F.lit("://"), host(url), p, F.regexp_extract(url, _PARTS, 4))


def decoded(text: Column) -> Column:
    """text with its HTML entities decoded once, named and numbered."""
    named = F.from_json(F.lit(_NAMED), "map<string,string>")

    def one(part: Column) -> Column:
        name = F.regexp_extract(part, r"^(#[xX][0-9A-Fa-f]{1,6};|#[0-9]{1,7};|[A-Za-z0-9]+;)", 1)
        code = F.when(name.rlike("^#[xX]"), F.conv(F.regexp_extract(name, r"([0-9A-Fa-f]+);$", 1), 16, 10)).otherwise(F.regexp_extract(name, r"([0-9]+);$", 1)).try_cast("long")
        sign = F.decode(F.unhex(F.lpad(F.hex(code), 8, "0")), "UTF-32")
        valid = ((code > 0) & (code < 0xD800)) | ((code > 0xDFFF) & (code < 0x110000))
        value = F.when(name.startswith("#"), F.when(valid, sign)).when(name != "", F.element_at(named, name))
        return F.coalesce(F.concat(value, part.substr(F.length(name) + 1, F.length(part))), F.concat(F.lit("&"), part))

    parts = lambda w: F.concat(F.slice(w, 1, 1), F.transform(F.slice(w, 2, F.size(w)), one))
    return F.when(text.contains("&"), F.array_join(let(F.split(text, "&", -1), parts), "")).otherwise(text)


def resolved(to: Column, url: Column) -> Column:
    """A target as read at url; one with another scheme form (`mailto:`) stays as it is."""
    scheme = F.regexp_extract(url, _PARTS, 1)
    site = F.concat(scheme, F.lit("://"), F.regexp_extract(url, _PARTS, 2))
    here, query = path(url), F.regexp_extract(url, _PARTS, 4)
    there, rest = F.regexp_extract(to, r"^([^?#]*)", 1), F.regexp_extract(to, r"(?s)^[^?#]*(.*)$", 1)
    folder = F.when(here == "", "/").otherwise(F.regexp_extract(here, r"(?s)^(.*/)", 1))
    return (
        F.when(to.rlike(_SCHEME), to)
        .when(to.startswith("//"), F.concat(scheme, F.lit(":"), to))
        .when(to.startswith("/"), F.concat(site, _undotted(there), rest))
        .when(to.startswith("?"), F.concat(site, here, to))
        .when((to == "") | to.startswith("#"), F.concat(site, here, query, to))
        .otherwise(F.concat(site, _undotted(F.concat(folder, there)), rest))
    )


def rule_of(h: Column, p: Column, rules=RULES) -> Column:
    """struct(rule, verdict) of the longest rule that fits, else null. Rules are a list in the configuration; their number does not follow the data."""
    out = F.lit(None).cast("struct<rule:string,verdict:string>")
    for verdict, rh, rp in sorted(rules, key=lambda r: len(r[1] + r[2])):
        fits = ((h == rh) | h.endswith(f".{rh}")) & p.startswith(rp)
        out = F.when(fits, F.struct(F.lit(rh + rp).alias("rule"), F.lit(verdict).alias("verdict"))).otherwise(out)
    return out


def alias_edges(pages: DataFrame, redirects: DataFrame | None = None) -> DataFrame:
    """(a, b): canonical links and refresh redirects in the html, and rows (from_url, to_url) of a crawl's redirects.

    Every canonical and refresh target of a page counts; entities are decoded,
    and relative targets are read against the page's `<base>` or url. Empty or
    missing html gives no edge."""
    found = F.concat(F.regexp_extract_all("html", F.lit(_CANONICAL), F.lit(1)), F.regexp_extract_all("html", F.lit(_REFRESH), F.lit(1)))
    links = pages.where(F.col("html").rlike(r"(?i)canonical|refresh") & F.col("url").contains("://")).select("url", F.array(F.regexp_extract("html", _BASE, 1)).alias("base"), F.explode(found).alias("to"))
    # A step a column: an expression put into another would be repeated for each mention of it.
    links = links.select("url", F.explode("base").alias("base"), "to").select("url", decoded(F.col("base")).alias("base"), decoded(F.col("to")).alias("to"))
    links = links.select("url", let(F.col("base"), lambda b: resolved(b, F.col("url"))).alias("base"), "to")
    if redirects is not None:
        links = links.unionByName(redirects.where("to_url is not null").select(F.col("from_url").alias("url"), F.col("from_url").alias("base"), F.col("to_url").alias("to")))
    links = links.select("url", let(F.struct("to", "base"), lambda x: resolved(x["to"], x["base"])).alias("to"))
    return links.where(F.col("to").contains("://") & F.col("url").contains("://")).select(resource(F.col("url")).alias("a"), resource(F.col("to")).alias("b"), "url", "to")


def judge_urls(pages: DataFrame, rules=RULES, redirects: DataFrame | None = None) -> DataFrame:
    """pages with host, path, rule and verdict.

    A rule's own verdict stands, allow as well as block. A url without a rule
    is blocked if a url of its redirect component is, else allowed. Equal urls
    get equal verdicts; a null url has no rule and no alias and is allowed."""
    edges = stage(alias_edges(pages, redirects))
    judged = pages.withColumn("host", host(F.col("url"))).withColumn("path", path(F.col("url")))
    judged = judged.withColumn("_hit", rule_of(F.col("host"), F.col("path"), rules)).withColumn("rule", F.col("_hit.rule"))
    if edges.isEmpty():
        return judged.withColumn("verdict", F.coalesce("_hit.verdict", F.lit("allow"))).drop("_hit")
    nodes = stage(components(edges))
    ends = edges.select(F.col("a").alias("node"), F.col("url").alias("u")).unionByName(edges.select(F.col("b").alias("node"), F.col("to").alias("u"))).distinct()
    bad = ends.where(rule_of(host(F.col("u")), path(F.col("u")), rules)["verdict"] == "block").select("node").distinct()
    blocked = nodes.join(bad, "node").select("component").distinct()
    tainted = nodes.join(blocked, "component").select(F.col("node").alias("_node"), F.lit(True).alias("_bad"))
    out = judged.withColumn("_own", F.when(F.col("_hit").isNull(), resource(F.col("url")))).join(tainted, F.col("_own") == F.col("_node"), "left")
    return out.withColumn("verdict", F.coalesce(F.col("_hit.verdict"), F.when(F.col("_bad"), F.lit("block")), F.lit("allow"))).drop("_hit", "_own", "_node", "_bad")


def op9_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("page_id", "url", "html")
    return judge_urls(pages).select("page_id", "host", "path", "rule", "verdict")


#: The given pages hold no canonical or refresh link, so a url without a rule is allowed here; aliases are tested on fixtures.
ORACLE = r"""
WITH u AS (SELECT page_id, CASE WHEN contains(url, '://') THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS r FROM pages),
p AS (SELECT page_id, translate(regexp_extract(r, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
  regexp_extract(substr(r, length(regexp_extract(r, '^[^/?#]*')) + 1), '^[^?#]*') AS path FROM u),
k(rule, h, q, verdict) AS (VALUES ('net/', 'net', '/', 'block'), ('example.net/en/', 'example.net', '/en/', 'allow'), ('example.com/de/', 'example.com', '/de/', 'block'), ('org/fr/', 'org', '/fr/', 'allow')),
b AS (SELECT p.page_id, arg_max(k.rule, length(k.rule)) AS rule, arg_max(k.verdict, length(k.rule)) AS verdict
  FROM p JOIN k ON (host = h OR ends_with(host, '.' || h)) AND starts_with(path, q) GROUP BY 1)
SELECT p.page_id, p.host, p.path, b.rule, coalesce(b.verdict, 'allow') AS verdict FROM p LEFT JOIN b USING (page_id)
"""
