"""URL filter: pattern rules indexed by their rarest literal token.

Every rule is a regular expression over host + path together with literal tokens that any URL it matches must
contain. The rule is filed under the one of its tokens that is rarest among the URLs at hand (counted over all
of them). A URL fetches the rules filed under its own tokens, and only those run their regular expression.

Everything is DataFrame expressions. Up to `inline_limit` rules the index is a literal map inside the plan (no
shuffle at all); larger rule sets are joined on the token, on distinct URLs. Rules are a list on the driver, so the index is
broadcast whatever its length, and no frequent token is a hot key.

Null URL, or one without "://": host and path are empty and no rule fits. Repeated rows are judged alike. Rules of equal
length: the later one by name wins. Very long URLs are judged whole. Other columns of the table are ignored. An empty table
gives an empty result.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class UrlRule:
    """name; verdict; regular expression on host + path; literal tokens; listed: reported as the page's rule."""

    name: str
    verdict: str
    pattern: str
    tokens: tuple[str, ...]
    listed: bool = True


def pieces(text: str) -> list[str]:
    return [x for x in re.split(r"[^A-Za-z0-9]+", text) if x]


def host_rule(verdict: str, rule: str) -> UrlRule:
    """Rule such as example.com/en/: the host with all its subdomains, and paths that start so."""
    host, slash, rest = rule.partition("/")
    path = slash + rest
    whole = path if not path or not path[-1].isalnum() else path[: len(path.rstrip("abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789"))]
    return UrlRule(rule, verdict, "^(?:[^/]*\\.)?" + re.escape(host + path), tuple(dict.fromkeys(pieces(host.lower()) + pieces(whole))))


def word_rule(word: str) -> UrlRule:
    """Blocks hosts that have the word as a whole piece of their name."""
    return UrlRule(f"host:{word}", "block", f"^(?:[^/]*[.-])?{re.escape(word)}[.-]", (word,), listed=False)


#: The rules of the registered query.
LISTED = [("allow", "com/"), ("block", "example.com/en/"), ("allow", "www.example.com/en/"), ("block", "net/es/"), ("block", "net/fr/")]
#: Words that block a host where no listed rule fits.
BLOCKED_WORDS = ["spam", "casino", "porn", "xxx", "warez"]
RULES = [host_rule(v, r) for v, r in LISTED] + [word_rule(w) for w in BLOCKED_WORDS]


def host_path(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path of a URL as columns; empty without "://"."""
    at = F.coalesce(F.locate("://", url), F.lit(0))
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))
    host = F.regexp_extract(rest, r"(?s)^([^/?#]*)", 1)
    path = F.regexp_extract(rest, r"(?s)^[^/?#]*([^?#]*)", 1)
    return F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), path


def rarest(urls: DataFrame, rules: list[UrlRule], inline_limit: int = 2000) -> dict[str, list[UrlRule]]:
    """Index token -> rules. Reads all URLs once; what reaches the driver is one count per token of the rules."""
    words = sorted({t for r in rules for t in r.tokens})
    tokens = urls.select(F.explode("tokens").alias("t"))
    if len(words) <= inline_limit:
        tokens = tokens.where(F.col("t").isin(words))
    else:
        # As long as the rules, which are on the driver anyway.
        tokens = tokens.join(F.broadcast(urls.sparkSession.createDataFrame([(w,) for w in words], "t string")), "t", "left_semi")
    counts = tokens.groupBy("t").count()
    seen = {r["t"]: r["count"] for r in counts.collect()}
    index: dict[str, list[UrlRule]] = {}
    for r in rules:
        index.setdefault(min(r.tokens, key=lambda t: (seen.get(t, 0), t)), []).append(r)
    return index


def judge(pages: DataFrame, rules: list[UrlRule] = RULES, default: str = "allow", inline_limit: int = 2000) -> DataFrame:
    """page_id, host, path, rule, verdict, pattern for each row of pages(page_id, url).

    The longest listed rule that fits decides; without one, the first blocking pattern; else `default`.
    rule: the listed rule or null. pattern: the unlisted rule that decided, or null."""
    host, path = host_path(F.col("url"))
    urls = pages.select("page_id", "url", host.alias("host"), path.alias("path"))
    urls = urls.withColumn("tokens", F.array_distinct(F.filter(F.split(F.concat("host", "path"), "[^A-Za-z0-9]+"), lambda t: t != "")))
    index = rarest(urls, rules, inline_limit)
    entry = "struct<listed:boolean,len:int,name:string,verdict:string,pattern:string>"
    if len(rules) <= inline_limit:
        flat = [(t, [(r.listed, len(r.name), r.name, r.verdict, r.pattern) for r in rs]) for t, rs in sorted(index.items())]
        lit = lambda e: F.struct(F.lit(e[0]).alias("listed"), F.lit(e[1]).alias("len"), F.lit(e[2]).alias("name"), F.lit(e[3]).alias("verdict"), F.lit(e[4]).alias("pattern"))
        empty = F.array().cast(f"array<{entry}>")
        fetch = lambda t: F.coalesce(F.element_at(F.create_map(*[c for k, rs in flat for c in (F.lit(k), F.array(*map(lit, rs)))]), t), empty)
        known = F.array_intersect("tokens", F.array(*[F.lit(k) for k, _ in flat])) if flat else F.array().cast("array<string>")
        candidates = F.flatten(F.transform(known, fetch)) if flat else empty
        hits = urls.withColumn("hits", F.filter(candidates, lambda r: F.rlike(F.concat("host", "path"), r["pattern"])))
    else:
        spark = pages.sparkSession
        rows = [(t, r.listed, len(r.name), r.name, r.verdict, r.pattern) for t, rs in index.items() for r in rs]
        table = spark.createDataFrame(rows, "t string, listed boolean, len int, name string, verdict string, pattern string")
        keys = urls.select("host", "path", "tokens").distinct()
        found = keys.select("host", "path", F.explode("tokens").alias("t")).join(F.broadcast(table), "t").where(F.expr("concat(host, path) rlike pattern"))
        found = found.groupBy("host", "path").agg(F.collect_list(F.struct("listed", "len", "name", "verdict", "pattern")).alias("hits"))
        hits = urls.join(found, ["host", "path"], "left").withColumn("hits", F.coalesce("hits", F.array().cast(f"array<{entry}>")))
    listed = F.array_max(F.filter("hits", lambda r: r["listed"]))
    other = F.array_min(F.filter("hits", lambda r: ~r["listed"]))
    hits = hits.withColumn("best", listed).withColumn("other", other)
    return hits.select(
        "page_id", "host", "path", F.col("best.name").alias("rule"),
        F.coalesce("best.verdict", "other.verdict", F.lit(default)).alias("verdict"),
        F.when(F.col("best").isNull(), F.col("other.name")).alias("pattern"),
    )


def op2_url_filters(spark, sf_dir: str) -> DataFrame:
    return judge(spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url"))


SQL = """
with r(verdict, rule) as (values ('allow', 'com/'), ('block', 'example.com/en/'), ('allow', 'www.example.com/en/'), ('block', 'net/es/'), ('block', 'net/fr/')),
s as (select verdict, rule, split_part(rule, '/', 1) rh, substr(rule, length(split_part(rule, '/', 1)) + 1) rp from r),
rest as (select page_id, url, case when url like '%://%' then substr(url, strpos(url, '://') + 3) else '' end x from pages),
u as (select page_id, url, translate(regexp_extract(x, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') host, regexp_extract(x, '^[^/?#]*([^?#]*)', 1) path from rest),
b as (select u.*, (select struct_pack(rule := s.rule, verdict := s.verdict) from s where (u.host = s.rh or ends_with(u.host, '.' || s.rh)) and starts_with(u.path, s.rp) order by length(s.rule) desc limit 1) best,
  (select min('host:' || w) from (values ('spam'), ('casino'), ('porn'), ('xxx'), ('warez')) t(w) where regexp_matches(u.host, '(^|[.-])' || w || '[.-]')) other from u)
select page_id, host, path, best.rule as rule, coalesce(best.verdict, case when other is not null then 'block' else 'allow' end) as verdict, case when best is null then other end as pattern from b
"""
