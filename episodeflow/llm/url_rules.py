"""URL rules, and block decisions that reach a page's aliases; DataFrame functions only.

A rule is (verdict, host, path): it fits its host and all subdomains where the url's path starts with the rule's. The
longest rule (host and path together) wins, allow before block among equals. Where no rule fits, the page's aliases
decide: urls joined by canonical links and meta-refresh redirects, in any number of steps, are one class. A class with
an explicitly allowed member is allowed, else one with a blocked member is blocked, else the page is allowed. A url's
node is its host, path and query; scheme and fragment make no other page. Targets that aren't pages themselves count.

Null urls and urls without `://` have an empty host and path, fit no rule, have no aliases and are allowed; pages with
null or empty html have no links; repeated rows are judged one by one; other columns aren't read. Every page of a hot
host or url costs the same: links are reduced to nodes before components, and verdicts join back by node.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialise
from .components import components

#: Verdict, host, path.
RULES = (("allow", "org", "/"), ("block", "example.org", "/es/"), ("block", "example.org", "/en/1"), ("allow", "com", "/fr/"), ("block", "com", "/de/"))
AFTER = r"^.*?://"


def _lower(c: Column) -> Column:
    return F.translate(c, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def split_url(df: DataFrame, url: str = "url") -> DataFrame:
    """Adds host, path and node (null where there is none)."""
    at = F.expr(f"instr({url}, '://')")
    rest = F.when(at > 0, F.expr(f"substring({url}, instr({url}, '://') + 3)")).otherwise(F.lit(""))
    df = df.withColumn("_rest", F.coalesce(rest, F.lit("")))
    plain = F.regexp_extract("_rest", r"^([^?#]*)", 1)
    df = df.withColumn("host", _lower(F.regexp_extract("_rest", r"^([^/?#]*)", 1))).withColumn("_plain", plain)
    df = df.withColumn("path", F.when(F.instr("_plain", "/") > 0, F.expr("substring(_plain, instr(_plain, '/'))")).otherwise(F.lit("")))
    query = F.regexp_extract("_rest", r"^[^#]*?(\?[^#]*)", 1)
    node = F.when(F.col("host") != "", F.concat("host", "path", query))
    return df.withColumn("node", node).drop("_rest", "_plain")


def rule_of(host: Column, path: Column, rules: tuple = RULES) -> tuple[Column, Column]:
    """The winning rule as written, and its verdict; both null where none fits."""
    order = sorted(rules, key=lambda r: (-len(r[1] + r[2]), r[0] != "allow", r[1:]))
    text, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for said, h, p in reversed(order):
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        text, verdict = F.when(fits, F.lit(h + p)).otherwise(text), F.when(fits, F.lit(said)).otherwise(verdict)
    return text, verdict


def links(pages: DataFrame) -> DataFrame:
    """(a, b): nodes joined by a canonical link or a meta refresh, distinct."""
    some = pages.where(F.col("html").rlike("(?i)canonical|http-equiv") & F.col("url").contains("://")).select("url", "html")
    tags = F.filter(F.regexp_extract_all("html", F.lit(r"(?i)<(?:link|meta)\b[^>]*>"), F.lit(0)), lambda t: t.rlike(r"(?i)rel\s*=\s*[\"']?canonical\b|http-equiv\s*=\s*[\"']?refresh\b"))
    href = F.coalesce(F.nullif(F.regexp_extract("tag", r"(?i)href\s*=\s*[\"']?([^\"'\s>]+)", 1), F.lit("")), F.regexp_extract("tag", r"(?i)url\s*=\s*[\"']?([^\"'\s>;]+)", 1))
    at = some.select("url", F.explode(tags).alias("tag")).select("url", F.replace(href, F.lit("&amp;"), F.lit("&")).alias("href")).where("href <> ''")
    at = materialise(at, "page-targets")  # the expressions of both steps in one plan outgrow a compiled method
    own = F.regexp_extract("url", r"^(.*?://[^/?#]*)", 1)
    target = F.when(F.col("href").contains("://"), F.col("href")).when(F.col("href").startswith("//"), F.concat(F.lit("x:"), F.col("href"))).when(F.col("href").startswith("/"), F.concat(own, F.col("href")))
    both = split_url(split_url(at.withColumn("target", target)).select(F.col("node").alias("a"), "target"), "target").select("a", F.col("node").alias("b"))
    return both.where("a is not null and b is not null and a <> b").distinct()


def judge(pages: DataFrame, rules: tuple = RULES) -> DataFrame:
    """(page_id, host, path, rule, verdict) of every page."""
    joined = components(materialise(links(pages), "page-links"))
    parts = split_url(joined.withColumn("_u", F.concat(F.lit("x://"), "node")).select("node", "component", "_u").withColumnRenamed("node", "_n"), "_u")
    said = parts.select("_n", "component", rule_of(F.col("host"), F.col("path"), rules)[1].alias("v"))
    classes = said.groupBy("component").agg(F.max(F.col("v") == "allow").alias("ok"), F.max(F.col("v") == "block").alias("bad"))
    spread = said.join(classes, "component").select("_n", F.when(F.coalesce("ok", F.lit(False)), F.lit("allow")).when(F.coalesce("bad", F.lit(False)), F.lit("block")).alias("_of_class"))
    rows = split_url(pages.select("page_id", "url"))
    rule, verdict = rule_of(F.col("host"), F.col("path"), rules)
    rows = rows.withColumn("rule", rule).withColumn("_own", verdict)
    out = rows.join(spread, rows["node"] == spread["_n"], "left")
    return out.select("page_id", "host", "path", "rule", F.coalesce("_own", "_of_class", F.lit("allow")).alias("verdict"))
