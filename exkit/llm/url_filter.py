"""URL filters: pattern rules indexed by their rarest literal token.

A rule is a regular expression over host and path with the literal tokens that
every match must hold. Of those tokens the one that is rarest among the URLs
becomes the rule's only index entry. A URL's tokens fetch candidate rules from
that index by an equi-join, and only candidates run their expression. Rules
without a whole literal token are indexed under the empty token, which every
URL has. Distinct URLs are judged once. Only DataFrame functions are used.

Defined results: null URLs and URLs without ``://`` have empty host and path and
get the default verdict unless a rule matches the empty target; repeated rows
get equal rows; an empty table gives an empty result; of several fitting list
rules the longest wins, on equal length the greater text; other columns are
ignored.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from exkit.llm.text import LOWER, UPPER, ascii_lower

#: Up to this many rules the index is sent to every executor (about 200 bytes a rule); beyond it, it is joined by a shuffle.
BROADCAST_RULES = 50_000


@dataclass(frozen=True)
class Rule:
    """``listed`` rules name a host and path and win by length; the others (``listed`` False) decide the rest."""

    name: str
    action: str
    pattern: str
    tokens: tuple[str, ...]
    listed: bool = True


def _lower(s: str) -> str:
    return s.translate(str.maketrans(UPPER, LOWER))


def _quote(s: str) -> str:
    return re.sub(r"([^A-Za-z0-9_/])", r"\\\1", s)


def host_rule(host: str, path: str, action: str) -> Rule:
    """Fits the host and all its subdomains where the URL's path starts with ``path``."""
    whole = re.findall(r"[A-Za-z0-9]+", host) + re.findall(r"[A-Za-z0-9]+(?=[^A-Za-z0-9])", path)
    end = "" if path.startswith("/") else "(?=/|$)"
    return Rule(host + path, action, rf"^(?:[^/]*\.)?{_quote(host)}{end}{_quote(path)}", tuple(sorted({_lower(t) for t in whole})))


def pattern_rule(name: str, action: str, pattern: str, tokens: tuple[str, ...] = ()) -> Rule:
    return Rule(name, action, pattern, tuple(_lower(t) for t in tokens), listed=False)


#: Judges what no listed rule covers: advertising and link-farm hosts, trackers, and pages for adults or gambling.
GENERAL_RULES = (
    pattern_rule("ads host", "block", r"^(?:[^/]*[.-])?ads[.-]", ("ads",)),
    pattern_rule("ad server", "block", r"^(?:[^/]*\.)?ad(?:server)?\.", ()),
    pattern_rule("tracker host", "block", r"^(?:[^/]*[.-])?track(?=[.-])", ("track",)),
    pattern_rule("spam host", "block", r"^(?:[^/]*[.-])?spam[.-]", ("spam",)),
    pattern_rule("link farm", "block", r"^[^/]*-farm\.", ("farm",)),
    pattern_rule("casino", "block", r"(?:^|[./_-])casino(?=$|[./_-])", ("casino",)),
    pattern_rule("adult", "block", r"(?:^|[./_-])(?:xxx|porn)(?=$|[./_-])", ()),
)


def url_parts(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path of a URL; both empty without ``://``."""
    shape = r"(?s)^.*?://([^/?#]*)([^?#]*)"
    part = lambda i: F.coalesce(F.regexp_extract(url, shape, i), F.lit(""))
    return ascii_lower(part(1)), part(2)


def _tokens(host: Column, path: Column) -> Column:
    words = F.split(ascii_lower(F.concat(host, F.lit("/"), path)), "[^a-z0-9]+")
    return F.array_distinct(F.concat(words, F.array(F.lit(""))))


def rule_index(urls: DataFrame, rules: list[Rule], spark: SparkSession) -> DataFrame:
    """One row per rule with the token it is found by: its rarest literal token among ``urls`` (host, path)."""
    rows = [(r.name, r.action, r.pattern, r.listed, list(r.tokens) or [""]) for r in rules]
    table = spark.createDataFrame(rows, "name string, action string, pattern string, listed boolean, tokens array<string>")
    spread = table.select("*", F.explode("tokens").alias("token")).drop("tokens")
    wanted = spread.select("token").distinct()
    wanted = F.broadcast(wanted) if len(rules) <= BROADCAST_RULES else wanted
    seen = urls.select(F.explode(_tokens(F.col("host"), F.col("path"))).alias("token")).join(wanted, "token").groupBy("token").agg(F.count(F.lit(1)).alias("n_urls"))
    best = F.min(F.struct(F.coalesce("n_urls", F.lit(0)).alias("n"), "token"))["token"]
    return spread.join(seen, "token", "left").groupBy("name", "action", "pattern", "listed").agg(best.alias("token"))


def judge_urls(pages: DataFrame, rules: list[Rule], default: str = "allow", url_col: str = "url") -> DataFrame:
    """``pages`` columns plus host, path, rule (name of the winning listed rule or null) and verdict, which replace columns of these names."""
    spark = pages.sparkSession
    host, path = url_parts(F.col("url"))
    urls = pages.select(F.col(url_col).alias("url")).distinct().select("url", host.alias("host"), path.alias("path"))
    index = rule_index(urls, rules, spark)
    index = F.broadcast(index) if len(rules) <= BROADCAST_RULES else index.hint("merge")  # a token that most URLs have is split there
    hits = (
        urls.select("url", F.concat("host", "path").alias("target"), F.explode(_tokens(F.col("host"), F.col("path"))).alias("token"))
        .join(index, "token")
        .where(F.rlike("target", F.col("pattern")))
    )
    longest = F.max(F.when(F.col("listed"), F.struct(F.length("name").alias("n"), F.col("name"), F.col("action"))))
    other = F.max(F.when(~F.col("listed"), F.col("action")))
    judged = hits.groupBy("url").agg(longest.alias("best"), other.alias("other")).select(
        F.col("url").alias("judged_url"), F.col("best.name").alias("rule"), F.coalesce("best.action", "other").alias("verdict")
    )
    quoted = ["`" + c.replace("`", "``") + "`" for c in pages.columns if c not in ("host", "path", "rule", "verdict")]
    own = pages.select(F.struct(*map(F.col, quoted)).alias("page"), F.col(url_col).alias("url"))
    return own.join(judged, own["url"].eqNullSafe(judged["judged_url"]), "left").select(
        *[f"page.{c}" for c in quoted], host.alias("host"), path.alias("path"), "rule", F.coalesce("verdict", F.lit(default)).alias("verdict")
    )


#: The listed rules of the query.
QUERY_RULES = [
    host_rule("com", "/", "allow"),
    host_rule("example.com", "/en/", "block"),
    host_rule("www.example.com", "/en/", "allow"),
    host_rule("net", "/es/", "block"),
    host_rule("net", "/fr/", "block"),
]


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url")
    return judge_urls(pages, [*QUERY_RULES, *GENERAL_RULES]).select("page_id", "host", "path", "rule", "verdict")


SQL = r"""
WITH parts AS (
  SELECT page_id,
    translate(coalesce(regexp_extract(url, '(?s)^.*?://([^/?#]*)([^?#]*)', 1), ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
    coalesce(regexp_extract(url, '(?s)^.*?://([^/?#]*)([^?#]*)', 2), '') AS path
  FROM pages),
ruled AS (
  SELECT *, CASE
      WHEN (host = 'www.example.com' OR host LIKE '%.www.example.com') AND path LIKE '/en/%' THEN 'www.example.com/en/'
      WHEN (host = 'example.com' OR host LIKE '%.example.com') AND path LIKE '/en/%' THEN 'example.com/en/'
      WHEN (host = 'net' OR host LIKE '%.net') AND path LIKE '/es/%' THEN 'net/es/'
      WHEN (host = 'net' OR host LIKE '%.net') AND path LIKE '/fr/%' THEN 'net/fr/'
      WHEN (host = 'com' OR host LIKE '%.com') AND path LIKE '/%' THEN 'com/' END AS rule
  FROM parts)
SELECT page_id, host, path, rule, CASE
    WHEN rule IN ('www.example.com/en/', 'com/') THEN 'allow'
    WHEN rule IS NOT NULL THEN 'block'
    WHEN regexp_matches(host || path, '^([^/]*[.-])?ads[.-]') OR regexp_matches(host || path, '^([^/]*\.)?ad(server)?\.')
      OR regexp_matches(host || path, '^([^/]*[.-])?track[.-]') OR regexp_matches(host || path, '^([^/]*[.-])?spam[.-]')
      OR regexp_matches(host || path, '^[^/]*-farm\.') OR regexp_matches(host || path, '(^|[./_-])casino($|[./_-])')
      OR regexp_matches(host || path, '(^|[./_-])(xxx|porn)($|[./_-])') THEN 'block'
    ELSE 'allow' END AS verdict
FROM ruled
"""
