"""URL filter with redirect equivalence.

Explicit (host, path) rules decide first. Redirects and canonical links make URLs aliases of one another; a block decision spreads
over the whole alias class, found as a connected component, while a URL that a rule allows explicitly stays allowed.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialize, scratch, table
from .components import connected_components

RULES = (("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/"))

CANONICAL = r"""(?is)<link\b(?=[^>]*\brel\s*=\s*["']?canonical\b)[^>]*?\bhref\s*=\s*["']?([^"'\s>]+)"""
REFRESH = r"""(?is)<meta\b(?=[^>]*\bhttp-equiv\s*=\s*["']?refresh\b)[^>]*?\burl\s*=\s*["']?([^"'\s>]+)"""


def host_of(url: Column) -> Column:
    """After the first :// up to / ? # or the end, A-Z lower-cased; empty for null or no ://."""
    rest = F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1)
    return F.coalesce(F.translate(rest, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), F.lit(""))


def path_of(url: Column) -> Column:
    """What follows the host up to ? # or the end; empty for null or no ://."""
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def rule_columns(host: Column, path: Column, rules: Sequence[tuple[str, str, str]] = RULES) -> tuple[Column, Column]:
    """(rule, verdict) of the longest fitting rule, null where none fits. A rule fits its host and subdomains and path prefixes."""
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for kind, h, p in sorted(rules, key=lambda r: (len(r[1] + r[2]), r)):  # later ones are longer and override
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        rule, verdict = F.when(fits, F.lit(h + p)).otherwise(rule), F.when(fits, F.lit(kind)).otherwise(verdict)
    return rule, verdict


def link_edges(pages: DataFrame, url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(u, v) redirect and canonical-link edges that the pages declare: <link rel=canonical> and <meta refresh>, absolute targets."""
    targets = F.array(F.regexp_extract(html_col, CANONICAL, 1), F.regexp_extract(html_col, REFRESH, 1))
    found = pages.where(F.col(html_col).isNotNull() & F.col(url_col).isNotNull()).select(F.col(url_col).alias("u"), F.explode(targets).alias("v"))
    return found.where(F.col("v").contains("://"))


#: What a tag says: all canonical links and refreshes of a page, in any number.
TARGETS = (CANONICAL, REFRESH)


def declared_edges(pages: DataFrame, url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(u, v) of all canonical links and refreshes that the pages declare, with relative targets resolved against the page's URL.

    //host/x takes the scheme, /x the host, ?q the path, other ones the folder of the page; . and .. segments are removed. Fragments
    alone (#x) and targets of other schemes (mailto:x) name no other page; a page without :// resolves absolute targets only.
    """
    targets = F.array_distinct(F.flatten(F.array(*[F.regexp_extract_all(html_col, F.lit(t), 1) for t in TARGETS])))
    found = pages.where(F.col(html_col).isNotNull() & F.col(url_col).isNotNull()).select(F.col(url_col).alias("u"), F.explode(targets).alias("v"))
    return found.withColumn("v", resolved(F.col("u"), F.col("v"))).where("v is not null")


def resolved(base: Column, target: Column) -> Column:
    """The absolute URL of a target on the page base; null if it has none."""
    part = lambda p: F.regexp_extract(base, p, 1)
    scheme, root, page = part(r"(?s)^(.*?:)//"), part(r"(?s)^(.*?://[^/?#]*)"), part(r"(?s)^.*?://[^/?#]*([^?#]*)")
    folder = F.when(page.contains("/"), F.regexp_extract(page, r"(?s)^(.*/)", 1)).otherwise(F.lit("/"))
    cut = F.regexp_extract(target, r"(?s)^([^?#]*)", 1)
    rest = F.substr(target, F.length(cut) + 1)
    path = F.when(cut.startswith("/"), cut).otherwise(F.concat(folder, cut))
    # segments in order; .. takes the one before it away, a last . or .. leaves the folder
    kept = F.aggregate(F.slice(F.split(path, "/"), 2, 1_000_000), F.array().cast("array<string>"), lambda a, x: F.when(x == "..", F.slice(a, 1, F.greatest(F.size(a) - 1, F.lit(0)))).when(x == ".", a).otherwise(F.concat(a, F.array(x))))
    flat = F.concat(F.lit("/"), F.array_join(kept, "/"), F.when(path.rlike(r"/\.\.?$") & (F.size(kept) > 0), F.lit("/")).otherwise(F.lit("")))
    return (F.when(target.rlike(r"^[A-Za-z][A-Za-z0-9+.\-]*://"), target).when(target.rlike(r"^[A-Za-z][A-Za-z0-9+.\-]*:") | target.startswith("#") | (root == "") | (target == ""), F.lit(None))
            .when(target.startswith("//"), F.concat(scheme, target)).when(target.startswith("?"), F.concat(root, page, target)).otherwise(F.concat(root, flat, rest)))


def url_verdicts(pages: DataFrame, edges: DataFrame, rules: Sequence[tuple[str, str, str]] = RULES, id_col: str = "page_id", url_col: str = "url", default: str = "allow") -> DataFrame:
    """Verdict of every page row: page id, host, path, rule, verdict, alias_class (smallest URL of the class, null if it has no alias).

    `edges` (u, v) may name URLs that are not pages; they carry decisions too. A class is blocked if a rule blocks one of its
    URLs; members without a rule take that block, members with an allow rule keep it. Null or malformed URLs have no rule and no
    alias and get `default`. Repeated rows give repeated results; extra columns are ignored; empty tables give empty results.
    """
    seen = pages.select(F.col(id_col).alias(id_col), F.col(url_col).alias("_url"))
    host, path = host_of(F.col("_url")), path_of(F.col("_url"))
    judged = seen.withColumns({"host": host, "path": path})
    rule, verdict = rule_columns(F.col("host"), F.col("path"), rules)
    judged = judged.withColumns({"rule": rule, "_own": verdict})
    with scratch(pages.sparkSession):
        classes = materialize(connected_components(edges))
        r, v = rule_columns(host_of(F.col("node")), path_of(F.col("node")), rules)
        bad = materialize(classes.withColumn("_v", v).where("_v = 'block'").select("component").distinct().withColumn("_blocked", F.lit(True)))
        alias = classes.join(bad, "component", "left").select(F.col("node").alias("_url"), F.col("component").alias("alias_class"), F.coalesce("_blocked", F.lit(False)).alias("_blocked"))
        alias = materialize(alias, lasting=True)
    out = judged.join(alias, "_url", "left")
    final = F.coalesce("_own", F.when(F.col("_blocked"), F.lit("block")), F.lit(default))
    return out.select(id_col, "host", "path", "rule", final.alias("verdict"), "alias_class")


def op8_url_redirect_equivalence(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages")
    return url_verdicts(pages, declared_edges(pages)).select("page_id", "host", "path", "rule", "verdict")


ORACLE = """
WITH RECURSIVE links AS (
  SELECT url AS u, regexp_extract(html, '<link[^>]*rel="?canonical"?[^>]*href="?([^"\\s>]+)', 1) AS v FROM pages WHERE html IS NOT NULL AND url IS NOT NULL
  UNION SELECT url, regexp_extract(html, '<meta[^>]*http-equiv="?refresh"?[^>]*url="?([^"\\s>]+)', 1) FROM pages WHERE html IS NOT NULL AND url IS NOT NULL
), e AS (SELECT u, v FROM links WHERE contains(v, '://') UNION SELECT v, u FROM links WHERE contains(v, '://')),
reach(a, b) AS (SELECT u, v FROM e UNION SELECT r.a, e.v FROM reach r JOIN e ON r.b = e.u),
urls AS (SELECT page_id, url,
  coalesce(lower(regexp_extract(url, '^.*?://([^/?#]*)', 1)), '') AS host,
  coalesce(regexp_extract(url, '^.*?://[^/?#]*([^?#]*)', 1), '') AS path FROM pages),
hit AS (SELECT *, CASE
  WHEN (host = 'example.net' OR ends_with(host, '.example.net')) AND starts_with(path, '/en/') THEN 'example.net/en/'
  WHEN (host = 'example.com' OR ends_with(host, '.example.com')) AND starts_with(path, '/de/') THEN 'example.com/de/'
  WHEN (host = 'org' OR ends_with(host, '.org')) AND starts_with(path, '/fr/') THEN 'org/fr/'
  WHEN (host = 'net' OR ends_with(host, '.net')) AND starts_with(path, '/') THEN 'net/' END AS rule FROM urls),
tainted AS (SELECT DISTINCT r.a FROM reach r JOIN hit h ON h.url = r.b WHERE h.rule IN ('net/', 'example.com/de/'))
SELECT page_id, host, path, rule, CASE WHEN rule IN ('net/', 'example.com/de/') THEN 'block' WHEN rule IS NOT NULL THEN 'allow'
  WHEN url IN (SELECT a FROM tainted) THEN 'block' ELSE 'allow' END AS verdict
FROM hit
"""
