"""URL filter over redirect equivalence, in DataFrame operations only.

Edges join a page's URL to the targets of its canonical link and refresh redirect, and every such URL, page or target,
to the form that its site redirects to (scheme, default subdomain, fragment, tracking parameters, index suffix and
trailing slash aside). Rules decide every URL, crawled or only linked; connected components over all edges carry
decisions to aliases: an explicit allow of any member comes first, then a block.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut, table
from .graph import components

#: (verdict, host, path); a fixed, short list in the query, a small broadcast table in the operator.
QUERY_RULES = [
    ("block", "com", "/en/"),
    ("allow", "example.com", "/en/7"),
    ("allow", "net", "/de/"),
    ("block", "example.net", "/de/8"),
    ("block", "org", "/es/"),
]
#: Rules are driver-side arguments; more than this many are refused instead of broadcast.
MOST_RULES = 100_000


def host_of(url: Column) -> Column:
    host = F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1)
    return F.coalesce(F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), F.lit(""))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def canonical_form(url: Column) -> Column:
    """Where a site's usual redirects lead: no scheme, ``www.`` or ``m.``, fragment, tracking query, ``.html`` or end slash."""
    host = F.regexp_replace(host_of(url), r"^(www|m)\.", "")
    path = F.regexp_replace(F.regexp_replace(path_of(url), r"(/index)?\.html?$", ""), r"/+$", "")
    query = F.regexp_extract(url, r"(?s)^.*?://[^?#]*(\?[^#]*)?", 1)
    query = F.regexp_replace(query, r"[?&](utm_[a-z]+|ref)=[^&]*", "")
    return F.when(host != "", F.concat(F.lit("//"), host, path, F.when(query != "", F.concat(F.lit("?"), F.regexp_replace(query, r"^[?&]", ""))).otherwise("")))


def without_dots(path: Column) -> Column:
    """An absolute path with ``.`` and ``..`` segments resolved; ``..`` at the root stays there."""
    parts = F.split(path, "/")
    none = F.array().cast("array<string>")
    step = lambda kept, p: F.when(p == ".", kept).when(p == "..", F.slice(kept, 1, F.greatest(F.size(kept) - 1, F.lit(1)))).otherwise(F.concat(kept, F.array(p)))
    kept = F.aggregate(parts, none, step)
    end = F.when(F.element_at(parts, -1).isin(".", ".."), F.array(F.lit(""))).otherwise(none)
    return F.when(path.rlike(r"/\.\.?(/|$)"), F.array_join(F.concat(kept, end), "/")).otherwise(path)


def resolved(target: Column, url: Column) -> Column:
    """The absolute URL of a link target in the page at ``url``; null for one without authority (``mailto:x``) or nothing but a fragment."""
    origin = F.regexp_extract(url, r"(?s)^(.*?://[^/?#]*)", 1)
    folder = F.concat(F.regexp_extract(path_of(url), r"(?s)^(.*)/", 1), F.lit("/"))
    path, rest = F.regexp_extract(target, r"(?s)^([^?#]*)", 1), F.regexp_extract(target, r"(?s)^[^?#]*(.*)", 1)
    return (
        F.when(target.rlike(r"^[A-Za-z][A-Za-z0-9+.-]*://"), target)
        .when(target.rlike(r"^([A-Za-z][A-Za-z0-9+.-]*:|#|$)"), F.lit(None))
        .when(target.startswith("//"), F.concat(F.regexp_extract(url, r"(?s)^(.*?:)//", 1), target))
        .when(target.startswith("/"), F.concat(origin, without_dots(path), rest))
        .when(target.startswith("?"), F.concat(origin, path_of(url), target))
        .otherwise(F.concat(origin, without_dots(F.concat(folder, path)), rest))
    )


def link_targets(html: Column, url: Column) -> Column:
    """Absolute targets of canonical links and refresh redirects in the page, relative ones resolved against its URL."""
    tags = F.regexp_extract_all(html, F.lit(r"(?i)(<link\b[^>]*\brel\s*=\s*[\"']?canonical\b[^>]*>|<meta\b[^>]*http-equiv\s*=\s*[\"']?refresh\b[^>]*>)"), 1)
    targets = F.transform(tags, lambda t: F.regexp_extract(t, r"(?i)(?:href|url)\s*=\s*[\"']?\s*([^\"'\s>]+)", 1))
    return F.array_distinct(F.filter(F.transform(targets, lambda t: resolved(t, url)), lambda t: t.isNotNull()))


def match_rules(pages: DataFrame, rules: list[tuple[str, str, str]]) -> DataFrame:
    """Adds the longest fitting rule (text and verdict, else null) to rows with host and path, by joins on host suffixes."""
    if len(rules) > MOST_RULES:
        raise ValueError(f"more than {MOST_RULES} rules")
    spark = pages.sparkSession
    known = F.broadcast(spark.createDataFrame([(h, p, h + p, v) for v, h, p in rules], "rule_host string, rule_path string, rule string, rule_verdict string"))
    labels = F.split("host", r"\.")
    suffixes = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    keyed = pages.select("host", "path").distinct().withColumn("rule_host", F.explode(suffixes))
    fits = keyed.join(known, "rule_host").where(F.col("path").startswith(F.col("rule_path")))
    best = fits.groupBy("host", "path").agg(F.max_by(F.struct("rule", "rule_verdict"), F.struct(F.length("rule"), "rule", F.col("rule_verdict") != "block")).alias("best"))
    return pages.join(best, ["host", "path"], "left").select(*pages.columns, F.col("best.rule").alias("rule"), F.col("best.rule_verdict").alias("rule_verdict"))


def filter_urls(pages: DataFrame, rules: list[tuple[str, str, str]], id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """page_id, host, path, rule, verdict and the component's root for every input row.

    A rule's own verdict stands. A page without a rule is allowed if an alias is explicitly allowed, else blocked if an
    alias is blocked, else allowed; an alias may be a linked URL that is no row of ``pages``. Null URLs and URLs without ``://`` have empty host and path and no aliases.
    """
    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html"))
    own = F.when(F.instr("url", "://") > 0, F.col("url"))
    parts = lambda df: df.select("*", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))
    links = cut(rows.where(own.isNotNull()).select(F.col("url").alias("a"), F.explode(link_targets(F.col("html"), F.col("url"))).alias("b")), "url-links")
    linked = links.select(F.col("b").alias("url")).distinct()
    forms = rows.where(own.isNotNull()).select("url").union(linked).select(F.col("url").alias("a"), canonical_form(F.col("url")).alias("b"))
    told = cut(match_rules(parts(rows.select("page_id", "url")), rules), "url-rules")
    roots = components(links.union(forms), told.where("url is not null").select(F.col("url").alias("node")))
    ruled = told.select("url", "rule_verdict").union(match_rules(parts(linked), rules).select("url", "rule_verdict")).where("rule_verdict is not null")
    decided = ruled.distinct().join(roots, F.col("url") == F.col("node"))
    by_root = decided.groupBy("root").agg(F.max(F.when(F.col("rule_verdict") == "allow", 1).otherwise(0)).alias("allowed"))
    aliases = roots.join(by_root, "root", "left").select("node", "root", "allowed")
    verdict = F.coalesce("rule_verdict", F.when(F.col("allowed") == 0, "block").otherwise("allow"))
    return told.join(aliases, told["url"] == aliases["node"], "left").select("page_id", "host", "path", "rule", verdict.alias("verdict"), "root")


def op4_redirect_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return filter_urls(table(spark, sf_dir, "pages"), QUERY_RULES)
