"""URL filters: prefix rules on hosts, and pattern rules indexed by their rarest literal token.

A prefix rule names a host and the start of a path; it fits the host and its subdomains, and the longest rule
that fits decides. Urls that no prefix rule fits are judged by pattern rules. Each pattern rule states literal
tokens that every match contains; how many urls hold each of these is counted over the whole table, and the
rule is filed under its rarest one. A url's own tokens fetch the rules filed under them, and only those run
their regular expression. The first of the matching rules decides; without one the url is allowed.

Everything is a native expression; the index is a literal map of at most one entry for each rule.

Defined results: a null url, or one without ``://``, has an empty host and path and no prefix rule; a null url
has no token, so it is allowed; urls of any length are judged whole; repeated rows are judged each; an empty table
gives an empty result; other columns of the input are ignored, whatever their names.
"""

from __future__ import annotations

import json

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

#: (verdict, host, start of the path)
PREFIX_RULES = [
    ("allow", "org", "/"),
    ("block", "example.org", "/es/"),
    ("block", "example.org", "/en/1"),
    ("allow", "com", "/fr/"),
    ("block", "com", "/de/"),
]

_EDGE, _END = "(^|[^a-z0-9])", r"([^a-z0-9]|\z)"


def _rule(verdict: str, *tokens: str, gap: str = "[^a-z0-9]+") -> tuple[str, tuple[str, ...], str]:
    """A rule for tokens that follow one another with a gap between them."""
    return verdict, tokens, _EDGE + gap.join(tokens) + _END


#: In order of priority: (verdict, literal tokens of every match, regular expression over the lower-case url).
PATTERN_RULES = [
    ("allow", ("wiki",), r"://([a-z0-9-]+\.)*wiki[./]"),
    ("allow", ("docs",), r"://docs\.[a-z0-9.-]+/"),
    ("allow", ("edu",), r"://[a-z0-9.-]+\.edu(/|\z)"),
    ("allow", ("gov",), r"://[a-z0-9.-]+\.gov(/|\z)"),
    ("block", ("spam", "farm"), r"://([a-z0-9-]+\.)*spam-farm\."),
    ("block", ("cheap", "pills"), r"://([a-z0-9-]+\.)*cheap-pills\."),
    ("block", ("casino", "win"), r"://([a-z0-9-]+\.)*casino-win\."),
    ("block", ("ads", "track"), r"://([a-z0-9-]+\.)*ads-track\."),
    ("block", ("free", "money"), _EDGE + "free[-_]?[^a-z0-9]money" + _END),
    *(_rule("block", a, b, gap="[-_./]") for a in ("buy", "cheap", "discount", "order") for b in ("viagra", "cialis", "pills", "meds", "replica", "followers")),
    *(_rule("block", a, b, gap="[-_./]") for a in ("online", "best", "live") for b in ("casino", "poker", "slots", "betting", "roulette")),
    *(_rule("block", a, b, gap="[-_./]") for a in ("payday", "instant", "fast") for b in ("loan", "loans", "credit")),
    *(_rule("block", a, b, gap="[-_./]") for a in ("adult", "xxx", "sex") for b in ("cam", "cams", "chat", "video", "videos", "dating")),
    ("block", ("adclick",), _EDGE + "adclick" + _END),
    ("block", ("doubleclick",), r"://([a-z0-9-]+\.)*doubleclick\."),
    ("block", ("banner", "ads"), r"/banner[-_/]ads(/|\z)"),
    ("block", ("wp", "login", "php"), r"/wp-login\.php" + _END),
    ("block", ("cgi", "bin"), r"/cgi-bin/"),
    ("block", ("sessionid",), r"[?&;]sessionid="),
    ("block", ("phpsessid",), r"[?&;]phpsessid="),
    ("block", ("replytocom",), r"[?&]replytocom="),
    *(("block", (x,), rf"\.{x}([?#]|\z)") for x in ("exe", "apk", "dmg", "iso", "zip", "rar", "torrent")),
]


def rest_of(url: str | Column) -> Column:
    """What follows the first ``://``; empty without one."""
    c = F.coalesce(F.col(url) if isinstance(url, str) else url, F.lit(""))
    at = F.instr(c, "://")
    return F.when(at > 0, F.substring(c, at + 3, F.length(c))).otherwise("")


def host_of(url: str | Column) -> Column:
    return F.translate(F.regexp_extract(rest_of(url), r"^[^/?#]*", 0), UPPER, LOWER)


def path_of(url: str | Column) -> Column:
    return F.regexp_extract(rest_of(url), r"^[^/?#]*([^?#]*)", 1)


def tokens_of(url: str | Column) -> Column:
    """Distinct runs of a-z and 0-9 of the lower-case url."""
    return F.array_distinct(F.split(F.translate(F.coalesce(F.col(url) if isinstance(url, str) else url, F.lit("")), UPPER, LOWER), "[^a-z0-9]+"))


def prefix_rule(host: Column, path: Column, rules: list = PREFIX_RULES) -> Column:
    """The longest rule that fits, as a struct of size, rule and verdict; null without one."""
    listed = F.array(*(F.struct(F.lit(len(h + p)).alias("size"), F.lit(h + p).alias("rule"), F.lit(v).alias("verdict"), F.lit(h).alias("h"), F.lit(p).alias("p")) for v, h, p in rules))
    fits = F.filter(listed, lambda r: ((host == r.h) | host.endswith(F.concat(F.lit("."), r.h))) & path.startswith(r.p))
    return F.array_max(fits)


def token_counts(pages: DataFrame, url_column: str, rules: list = PATTERN_RULES) -> dict[str, int]:
    """How many rows hold each literal token of the rules; at most one entry for each such token comes back."""
    wanted = sorted({t for _, tokens, _ in rules for t in tokens})
    held = F.filter(tokens_of(url_column), lambda t: t.isin(wanted))
    rows = pages.select(F.explode(held).alias("token")).groupBy("token").count().collect()
    return dict.fromkeys(wanted, 0) | {r["token"]: r["count"] for r in rows}


def rarest_index(counts: dict[str, int], rules: list = PATTERN_RULES) -> dict[str, list[dict]]:
    """Rules by their rarest literal token."""
    index: dict[str, list[dict]] = {}
    for k, (verdict, tokens, pattern) in enumerate(rules):
        token = min(tokens, key=lambda t: (counts.get(t, 0), t))
        index.setdefault(token, []).append({"priority": k, "verdict": verdict, "pattern": pattern})
    return index


def pattern_verdict(url: str, index: dict[str, list[dict]]) -> Column:
    """The verdict of the first matching pattern rule; null without one."""
    filed = F.from_json(F.lit(json.dumps(index)), "map<string, array<struct<priority: int, verdict: string, pattern: string>>>")
    known = sorted(index)
    fetched = F.flatten(F.transform(F.filter(tokens_of(url), lambda t: t.isin(known)), lambda t: F.try_element_at(filed, t)))
    lowered = F.translate(F.col(url), UPPER, LOWER)
    return F.array_min(F.filter(fetched, lambda r: F.regexp_like(lowered, r.pattern)))["verdict"]


def judge(pages: DataFrame, id_column: str = "page_id", url_column: str = "url", prefix_rules: list = PREFIX_RULES, pattern_rules: list = PATTERN_RULES) -> DataFrame:
    """page_id, host, path, rule and verdict of every row."""
    index = rarest_index(token_counts(pages, url_column, pattern_rules), pattern_rules)
    rows = pages.select(F.col(id_column).alias("page_id"), F.col(url_column).alias("url"))
    rows = rows.select("page_id", "url", host_of("url").alias("host"), path_of("url").alias("path"))
    rows = rows.withColumn("fit", prefix_rule(F.col("host"), F.col("path"), prefix_rules))
    verdict = F.coalesce(F.col("fit.verdict"), pattern_verdict("url", index), F.lit("allow"))
    return rows.select("page_id", "host", "path", F.col("fit.rule").alias("rule"), verdict.alias("verdict"))


def oracle_sql(prefix_rules: list = PREFIX_RULES, pattern_rules: list = PATTERN_RULES) -> str:
    """The same by trying every rule on every url."""
    quote = lambda x: "'" + x.replace("'", "''") + "'"
    prefixes = ", ".join(f"({quote(v)}, {quote(h)}, {quote(p)})" for v, h, p in prefix_rules)
    patterns = ", ".join(f"({k}, {quote(v)}, {quote(p)})" for k, (v, _, p) in enumerate(pattern_rules))
    return f"""
WITH prefixes(verdict, h, p) AS (VALUES {prefixes}),
patterns(priority, verdict, pattern) AS (VALUES {patterns}),
rests AS (
  SELECT page_id, url, CASE WHEN strpos(coalesce(url, ''), '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest
  FROM pages
), parts AS (
  SELECT page_id, translate(url, '{UPPER}', '{LOWER}') AS lowered,
         translate(regexp_extract(rest, '^[^/?#]*', 0), '{UPPER}', '{LOWER}') AS host,
         regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path,
         row_number() OVER () AS k
  FROM rests
), fits AS (
  SELECT k, arg_max(h || p, length(h || p)) AS rule, arg_max(verdict, length(h || p)) AS verdict
  FROM parts JOIN prefixes ON (host = h OR suffix(host, '.' || h)) AND starts_with(path, p) GROUP BY k
), hits AS (
  SELECT k, arg_min(verdict, priority) AS verdict FROM parts JOIN patterns ON regexp_matches(lowered, pattern) GROUP BY k
)
SELECT page_id, host, path, fits.rule AS rule, coalesce(fits.verdict, hits.verdict, 'allow') AS verdict
FROM parts LEFT JOIN fits USING (k) LEFT JOIN hits USING (k)
"""
