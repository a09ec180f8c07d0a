"""URL filters: pattern rules indexed by their rarest literal token, in DataFrame functions only.

A URL's tokens fetch the rules filed under them, and only those run their regular expressions. Up
to ``LITERAL`` rules travel inside the plan as one literal map, so judging is a map over the scan;
more become a table that joins with the tokens of the distinct URLs.
"""

from __future__ import annotations

import json
import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Rules that may be one literal; a map is searched from its start, so the bound is low.
LITERAL = 256
TOKEN_GAP = "[^A-Za-z0-9]+"


@dataclass(frozen=True)
class UrlRule:
    """``pattern`` runs on host and path together; ``tokens`` are lower-case runs of letters and digits that any match holds whole."""

    name: str
    pattern: str
    tokens: tuple[str, ...]
    verdict: str
    base: bool = False


def host_rule(verdict: str, host: str, path: str) -> UrlRule:
    """Fits the host and all subdomains where the URL's path starts with ``path``."""
    whole = path if not path or not path[-1].isalnum() else re.sub(r"[A-Za-z0-9]+$", "", path)
    tokens = tuple(t.lower() for t in re.split(TOKEN_GAP, f"{host}/{whole}") if t)
    return UrlRule(host + path, rf"^([^/]*\.)?{re.escape(host)}{re.escape(path)}", tokens, verdict, True)


# The base rules.
BASE_RULES = (
    host_rule("allow", "com", "/"),
    host_rule("block", "example.com", "/en/"),
    host_rule("allow", "www.example.com", "/en/"),
    host_rule("block", "net", "/es/"),
    host_rule("block", "net", "/fr/"),
)


def parse_rule(line: str) -> UrlRule | None:
    """A rule of a filter list; None for blank lines and for comments, which begin with ``!``.

    ``@@`` in front allows, otherwise the rule blocks. ``||host/path`` starts at a host or one of its
    subdomains; a word of letters and digits alone fits as a whole token; anything else fits where
    it occurs. ``*`` stands for any characters, ``^`` for a separator or the end. Cases don't matter.
    Tokens are those that the text holds whole: bounded on both sides inside the pattern.
    """
    text = line.strip()
    if not text or text.startswith("!"):
        return None
    verdict, body = ("allow", text[2:]) if text.startswith("@@") else ("block", text)
    if re.fullmatch("[A-Za-z0-9]+", body):
        return UrlRule(f"token:{body}", rf"(?i)(^|[^A-Za-z0-9]){body}([^A-Za-z0-9]|$)", (body.lower(),), verdict)
    anchored = body.startswith("||")
    body = body[2:] if anchored else body
    pattern = re.escape(body).replace(r"\*", ".*").replace(r"\^", r"([^A-Za-z0-9_.%-]|$)")
    bounded = ("/" if anchored else "") + body
    tokens = tuple(t.lower() for part in bounded.split("*") for t in re.findall("(?<=[^A-Za-z0-9])[A-Za-z0-9]+(?=[^A-Za-z0-9])", part))
    return UrlRule(text, ("(?i)" + (r"^([^/]*\.)?" if anchored else "") + pattern), tokens, verdict)


def parse_rules(text: str) -> tuple[UrlRule, ...]:
    return tuple(r for r in map(parse_rule, text.splitlines()) if r)


# The method's own rules, for URLs that no base rule fits: tokens that mark adult, gambling, drug-selling, piracy and malware hosts or paths.
METHOD_LIST = """
! adult
adult
porn
xxx
sex
escort
! gambling
casino
betting
bets
poker
lottery
! drugs by mail
viagra
cialis
pills
! copies and cracks
warez
keygen
! malware
phishing
malware
"""
METHOD_RULES = parse_rules(METHOD_LIST)


def host_of(url: Column) -> Column:
    return F.translate(F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://([^/?#]*)", 1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def path_of(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://[^/?#]*([^?#]*)", 1)


def url_tokens(address: Column) -> Column:
    """Distinct tokens, the empty one included."""
    return F.array_distinct(F.concat(F.split(F.lower(address), TOKEN_GAP), F.array(F.lit(""))))


def file_rules(addresses: DataFrame, rules: tuple[UrlRule, ...], address_col: str = "__address") -> dict[str, list[UrlRule]]:
    """Rules by their rarest token; those without one under the empty token, which every URL has. Frequencies are counted over all addresses, for the rules' own tokens."""
    wanted = sorted({t for r in rules for t in r.tokens})
    own = F.filter(url_tokens(F.col(address_col)), lambda t: t.isin(wanted)) if len(wanted) <= 4 * LITERAL else url_tokens(F.col(address_col))
    counts = addresses.select(F.explode(own).alias("token")).groupBy("token").count()
    if len(wanted) > 4 * LITERAL:
        counts = counts.join(addresses.sparkSession.createDataFrame([(t,) for t in wanted], "token string"), "token")
    n = {r["token"]: r["count"] for r in counts.collect()}  # as many rows as the rules have tokens, at most
    out: dict[str, list[UrlRule]] = {}
    for r in rules:
        out.setdefault(min(r.tokens, key=lambda t: (n.get(t, 0), t), default=""), []).append(r)
    return out


_ENTRY = "struct<name:string,pattern:string,verdict:string,base:boolean>"


def _best(found: Column) -> Column:
    """Base rules before the method's; the longest name of those; then the name itself."""
    return F.array_max(F.transform(found, lambda r: F.struct(r["base"].alias("base"), F.length(r["name"]).alias("size"), r["name"].alias("name"), r["verdict"].alias("verdict"))))


def judge_urls(pages: DataFrame, rules: tuple[UrlRule, ...] = BASE_RULES + METHOD_RULES, url_col: str = "url") -> DataFrame:
    """``pages`` with ``host``, ``path``, ``rule`` (a base rule's name or null) and ``verdict``.

    Null URLs and those without ``://`` have an empty host and path; no rule fits them, and the
    method blocks them, since nothing can be fetched there. Other URLs that no rule fits are
    allowed. Every row stays, repeated or not; columns of the four added names are replaced,
    whatever their case, and all others stay as they are.
    """
    keep = [F.col(f"`{c}`") for c in pages.columns if c.lower() not in ("host", "path", "rule", "verdict")]
    url = F.col(f"`{url_col}`").cast("string")
    rows = pages.select(*keep, host_of(url).alias("host"), path_of(url).alias("path")).withColumn("__address", F.concat("host", "path"))
    filed = file_rules(rows.select("__address"), rules) if rules else {}
    if len(rules) <= LITERAL:
        said = {t: [{"name": r.name, "pattern": r.pattern, "verdict": r.verdict, "base": r.base} for r in own] for t, own in sorted(filed.items())}
        index = F.from_json(F.lit(json.dumps(said)), f"map<string,array<{_ENTRY}>>")
        candidates = F.flatten(F.transform(F.filter(url_tokens(F.col("__address")), lambda t: F.map_contains_key(index, t)), lambda t: F.element_at(index, t)))
        rows = rows.withColumn("__best", _best(F.filter(candidates, lambda r: F.rlike(F.col("__address"), r["pattern"]))))
    else:
        data = [(t, r.name, r.pattern, r.verdict, r.base) for t, own in filed.items() for r in own]
        index_rows = pages.sparkSession.createDataFrame(data, "__token string, name string, pattern string, verdict string, base boolean")
        seen = rows.select("__address").distinct().withColumn("__token", F.explode(url_tokens(F.col("__address"))))
        hit = seen.join(index_rows, "__token").where(F.expr("__address rlike pattern"))
        best = hit.groupBy("__address").agg(F.max(F.struct("base", F.length("name").alias("size"), "name", "verdict")).alias("__best"))
        rows = rows.join(best, "__address", "left")
    method = F.when(F.col("__address") == "", F.lit("block")).otherwise(F.lit("allow"))
    return rows.select(*keep, "host", "path", F.when(F.col("__best")["base"], F.col("__best")["name"]).alias("rule"), F.coalesce(F.col("__best")["verdict"], method).alias("verdict"))
