"""URL block lists whose decisions follow redirects and canonical links."""

from __future__ import annotations

import re
from collections.abc import Sequence
from urllib.parse import urljoin

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StringType

from .common import LOWER, UPPER, components

#: Fixed values: (verdict, host, path), as the query's contract lists them.
RULES = (
    ("block", "com", "/en/"),
    ("allow", "example.com", "/en/7"),
    ("allow", "net", "/de/"),
    ("block", "example.net", "/de/8"),
    ("block", "org", "/es/"),
)
#: A rule list is compiled into one expression up to this length; longer ones become a table, joined by host suffix.
MOST_RULES = 200


def url_parts(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path of a url; both empty for null or without `://`."""
    whole = F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://([^/?#]*)([^?#]*)", 0)
    host = F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://([^/?#]*)([^?#]*)", 1)
    path = F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://([^/?#]*)([^?#]*)", 2)
    return F.when(whole == "", "").otherwise(F.translate(host, UPPER, LOWER)), F.when(whole == "", "").otherwise(path)


def match_rule(host: Column, path: Column, rules: Sequence[tuple[str, str, str]]) -> Column:
    """The longest fitting rule as struct (rule, verdict); null where none fits.

    Length counts the host and path characters; of equally long rules an allow wins, then text order.
    """
    out = F.lit(None).cast("struct<rule:string,verdict:string>")
    for verdict, h, p in sorted(rules, key=lambda r: (len(r[1] + r[2]), r[0] == "allow", r[1] + r[2])):
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        out = F.when(fits, F.struct(F.lit(h + p).alias("rule"), F.lit(verdict).alias("verdict"))).otherwise(out)
    return out


def with_rule(df: DataFrame, rules: Sequence[tuple[str, str, str]]) -> DataFrame:
    """Adds `hit`, the longest fitting rule as struct (rule, verdict), to rows with host and path.

    A long list of rules is a table: every distinct host and path meets the rules of its suffixes, of which the longest
    fitting one is combined before any shuffle.
    """
    if len(rules) <= MOST_RULES:
        return df.withColumn("hit", match_rule(F.col("host"), F.col("path"), rules))
    table = df.sparkSession.createDataFrame([(v, h, p) for v, h, p in rules], "verdict string, h string, p string")
    labels = F.split("host", r"\.")
    suffixes = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda n: F.array_join(F.slice(labels, F.size(labels) - n + 1, n), "."))
    places = df.select("host", "path").distinct()
    met = places.withColumn("h", F.explode(F.array_distinct(suffixes))).join(table, "h").where(F.col("path").startswith(F.col("p")))
    text = F.concat("h", "p")
    best = F.max(F.struct(F.length(text).alias("n"), (F.col("verdict") == "allow").alias("allow"), text.alias("rule"), "verdict"))
    hits = met.groupBy("host", "path").agg(best.alias("best")).select("host", "path", F.struct(F.col("best.rule").alias("rule"), F.col("best.verdict").alias("verdict")).alias("hit"))
    return df.join(hits, ["host", "path"], "left")


@F.udf(StringType())
def _resolved(page: str, base: str, target: str) -> str:
    """An absolute target as it stands, others against the page's url (and its <base>); empty for what has no host."""
    if re.match(r"(?i)[a-z][a-z0-9+.-]*://", target):
        return target
    try:
        scheme, mark, rest = urljoin(urljoin(page, base), target).partition("://")
    except ValueError:
        return ""
    own = page.partition("://")[0]
    return (own if own.lower() == scheme else scheme) + mark + rest if mark and re.fullmatch(r"(?i)[a-z][a-z0-9+.-]*", scheme) else ""


def page_links(pages: DataFrame) -> DataFrame:
    """Alias edges (a, b) that pages state themselves: canonical links and refreshes, relative targets resolved."""
    html = F.coalesce("html", F.lit(""))
    tags = F.concat(
        F.when(F.lower(html).contains("canonical"), F.regexp_extract_all(html, F.lit(r"(?is)<link\b[^>]*\brel\s*=\s*[\"']?canonical\b[^>]*>"), 0)).otherwise(F.array().cast("array<string>")),
        F.when(F.lower(html).contains("http-equiv"), F.regexp_extract_all(html, F.lit(r"(?is)<meta\b[^>]*\bhttp-equiv\s*=\s*[\"']?refresh\b[^>]*>"), 0)).otherwise(F.array().cast("array<string>")),
    )
    base = F.regexp_extract(html, r"(?is)<base\b[^>]*\bhref\s*=\s*[\"']?([^\"'\s>]+)", 1)
    target = F.regexp_extract("tag", r"(?is)(?:\bhref\s*=\s*[\"']?|\burl\s*=\s*[\"']?)\s*([^\"'\s>]+)", 1)
    return (
        pages.where(F.col("url").isNotNull())
        .select(F.col("url").alias("a"), base.alias("base"), F.explode(tags).alias("tag"))
        .select("a", "base", target.alias("target")).where("target <> ''")
        .select("a", _resolved("a", "base", "target").alias("b"))
        .where("b <> ''")
    )


def _node(url: Column) -> Column:
    """A url without its fragment; scheme and host in lower case (A-Z), an empty path as `/`."""
    plain = F.regexp_replace(url, r"(?s)#.*$", "")
    head, rest = (F.regexp_extract(plain, r"(?s)^(.*?://[^/?]*)(.*)$", i) for i in (1, 2))
    return F.when(head == "", plain).otherwise(F.concat(F.translate(head, UPPER, LOWER), F.when(rest == "", "/").otherwise(rest)))


def filter_urls(
    pages: DataFrame, rules: Sequence[tuple[str, str, str]] = RULES, redirects: DataFrame | None = None
) -> DataFrame:
    """Judge every page's url: page_id, host, path, rule, verdict, component.

    A url's own longest rule decides. Without one, the url takes part in its redirect
    class: the connected component over canonical links, refreshes and the given
    `redirects` (src, dst); fragments do not make urls differ. A class with a blocked url
    and no explicitly allowed one is blocked whole; all else is allowed. Targets
    that are not pages count, with the rules that fit them. Null urls and urls
    without `://` fit no rule and are allowed. Rows stay one to one, repeats included.
    """
    links = page_links(pages)
    if redirects is not None:
        links = links.unionByName(redirects.select(F.col("src").alias("a"), F.col("dst").alias("b")))
    classes = components(links.select(_node(F.col("a")).alias("a"), _node(F.col("b")).alias("b")), "aliases")
    host, path = url_parts(F.col("node"))
    judged = with_rule(classes.select("node", "component", host.alias("host"), path.alias("path")), rules).withColumn("hit", F.col("hit.verdict"))
    spread = judged.groupBy("component").agg(
        (F.max(F.col("hit").eqNullSafe("block")) & ~F.max(F.col("hit").eqNullSafe("allow"))).alias("blocked")
    )
    spread = classes.join(spread, "component").select("node", "component", "blocked")
    host, path = url_parts(F.col("url"))
    rows = with_rule(pages.select("page_id", host.alias("host"), path.alias("path"), _node(F.col("url")).alias("node")), rules)
    # Null urls meet nothing and get keys of their own; rows of a common url are spread by adaptive execution, which may split the left side.
    lone = F.concat(F.lit(" "), F.monotonically_increasing_id().cast("string"))
    rows = rows.withColumn("key", F.coalesce("node", lone))
    return rows.join(spread.withColumnRenamed("node", "key"), "key", "left").select(
        "page_id", "host", "path", F.col("hit.rule").alias("rule"),
        F.coalesce("hit.verdict", F.when(F.col("blocked"), "block"), F.lit("allow")).alias("verdict"),
        F.coalesce("component", "node").alias("component"),
    )
