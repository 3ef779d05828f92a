"""Operator 1: URL rules indexed by their rarest literal token.

Every rule becomes a regular expression over ``host || path``.  A rule's *literal tokens* are the runs of
``[a-z0-9]`` in its pattern that are delimited on both sides, so that an address can only fit the rule if it holds
each of them as a whole token.  One pass counts those tokens over all addresses; each rule is filed under its rarest
one.  An address then looks its own tokens up in a hash-bucketed index (a constant of the plan), and only the rules
so fetched run their regular expressions.  The whole judgement is a projection: no shuffle, no join, no Python.

Rules beyond ``PLAN_RULES`` go into further passes over the rows, each with an index of its own, and the best rule of
all passes wins: their number has no limit.

Defined results: a null address, or one without ``://``, has empty host and path, fits no rule and is allowed; an address
of any length is judged whole; of rules that tie in tier and length the smaller label wins; repeated rows are judged
alike; an empty table gives no rows; columns other than the address pass through, but for those called host, path, rule,
pattern, verdict or n_candidates, which the results of those names replace.
"""

from __future__ import annotations

import json
import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from evenpart.llm.columns import fresh
from evenpart.plans.scratch import cut
from evenpart.sources.tables import read_table

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Rules of one pass: they are a constant inside the plan, and this many keep it within a few MB.
PLAN_RULES = 20_000
INDEX_TYPE = "array<array<struct<token:string,regex:string,rule:string,action:string,tier:int,size:int>>>"


@dataclass(frozen=True)
class Rule:
    """``tier`` 2 beats tier 1; within a tier the longer ``label`` wins, then the smaller one."""

    action: str
    label: str
    regex: str
    tokens: tuple[str, ...]
    tier: int


def site_rule(action: str, host: str, path: str) -> Rule:
    """Fits ``host`` and its subdomains where the address's path starts with ``path``."""
    regex = r"(?s)^(?:[^/]*\.)?" + re.escape(host) + (re.escape(path) if path else r"(?:/|$)")
    # a host is delimited by its start, dots and the path; the last run of a path prefix may go on in the address
    runs = re.findall(r"[a-z0-9]+", host.lower()) + re.findall(r"(?<![a-z0-9])[a-z0-9]+(?=[^a-z0-9])", path.lower())
    return Rule(action, host + path, regex, tuple(runs), 2)


def pattern_rule(action: str, pattern: str) -> Rule:
    """Fits where ``pattern`` stands anywhere in ``host || path``; ``*`` stands for any run of characters."""
    regex = "(?s)" + ".*".join(map(re.escape, pattern.split("*")))
    tokens = re.findall(r"(?<=[^a-z0-9*])[a-z0-9]+(?=[^a-z0-9*])", pattern.lower())
    return Rule(action, pattern, regex, tuple(tokens), 1)


#: Fixed values of the contract: (action, host, path).
SITE_RULES = (("allow", "org", "/"), ("block", "example.org", "/es/"), ("block", "example.org", "/en/1"), ("allow", "com", "/fr/"), ("block", "com", "/de/"))
#: The method's own rules, for addresses that no site rule fits.
PATTERN_RULES = (("block", "/ads/"), ("block", ".ads."), ("block", "/casino/*"), ("block", "/wp-login."), ("block", "/cgi-bin/"), ("block", "/tracker/"))


def default_rules() -> list[Rule]:
    return [site_rule(*r) for r in SITE_RULES] + [pattern_rule(*r) for r in PATTERN_RULES]


def split_url(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path."""
    parts = r"(?s)^.*?://([^/?#]*)([^?#]*)"
    text = F.coalesce(url, F.lit(""))
    return F.translate(F.regexp_extract(text, parts, 1), UPPER, LOWER), F.regexp_extract(text, parts, 2)


def url_tokens(target: Column) -> Column:
    return F.array_distinct(F.split(F.lower(target), "[^a-z0-9]+"))


def token_counts(urls: DataFrame, rules: list[Rule], url: str = "url") -> dict[str, int]:
    """How many addresses hold each literal token of a rule: as many rows at most as the rules have tokens."""
    wanted = sorted({t for r in rules for t in r.tokens})
    host, path = split_url(F.col(url))
    held = urls.select(F.explode(F.array_intersect(url_tokens(F.concat(host, path)), F.array(*map(F.lit, wanted)) if wanted else F.array().cast("array<string>"))).alias("token"))
    return {r["token"]: r["n"] for r in held.groupBy("token").agg(F.count("*").alias("n")).collect()}


def build_index(rules: list[Rule], counts: dict[str, int]) -> tuple[list[list[dict]], list[dict]]:
    """Hash buckets of rules by rarest token, and the rules without a delimited token, which always run."""
    filed, always = [], []
    for r in rules:
        row = {"token": min(r.tokens, key=lambda t: (counts.get(t, 0), t)) if r.tokens else "", "regex": r.regex, "rule": r.label, "action": r.action, "tier": r.tier, "size": len(r.label)}
        (filed if r.tokens else always).append(row)
    buckets: list[list[dict]] = [[] for _ in range(max(1, 2 * len(filed)))]
    for row in filed:
        buckets[_bucket(row["token"], len(buckets))].append(row)
    return buckets, always


def _bucket(token: str, n: int) -> int:
    """The same in Python and in Spark: a base-31 value of the first eight characters, by crc32."""
    import zlib

    return zlib.crc32(token.encode()) % n


def _let(value: Column, body) -> Column:
    """``body`` of a value that is evaluated once."""
    return F.transform(F.array(value), body)[0]


def _best(rules: list[Rule], counts: dict[str, int], target: Column) -> Column:
    """(n, top): how many rules the index hands out for ``target``, and the best of those that fit."""
    buckets, always = build_index(rules, counts)
    index = F.from_json(F.lit(json.dumps(buckets)), INDEX_TYPE)
    rest = F.from_json(F.lit(json.dumps([always])), INDEX_TYPE)[0]

    def fetched(t: Column) -> Column:
        hits = F.transform(url_tokens(t), lambda k: F.filter(index[F.pmod(F.crc32(k.cast("binary")), F.lit(len(buckets))).cast("int")], lambda r: r["token"] == k))
        return F.concat(F.flatten(hits), rest)

    def best(t: Column) -> Column:
        fit = F.filter(fetched(t), lambda r: F.call_function("rlike", t, r["regex"]))
        top = F.array_min(F.transform(fit, lambda r: F.struct((-r["tier"]).alias("t"), (-r["size"]).alias("s"), r["rule"].alias("rule"), r["action"].alias("action"))))
        return F.struct(F.size(fetched(t)).alias("n"), top.alias("top"))

    return _let(target, best)


def judge(urls: DataFrame, rules: list[Rule], url: str = "url", plan_rules: int = PLAN_RULES) -> DataFrame:
    """``urls`` with host, path, rule, verdict, pattern (the fitting rule of lower tier) and n_candidates."""
    counts, (top,) = token_counts(urls, rules, url), fresh(urls, "_top")
    host, path = split_url(F.col(url))
    for lo in range(0, max(len(rules), 1), plan_rules):
        here = _best(rules[lo : lo + plan_rules], counts, F.concat(host, path))
        if lo:  # the smaller struct is the better rule, and least() passes over nulls
            here = _let(here, lambda h: F.struct((F.col(top)["n"] + h["n"]).alias("n"), F.least(F.col(top)["top"], h["top"]).alias("top")))
        urls = urls.withColumn(top, here)
        if lo + plan_rules < len(rules):
            urls = cut(urls)
    found = F.col(top)["top"]
    site = found["t"] == -2
    made = {
        "rule": F.when(site, found["rule"]), "pattern": F.when(~site, found["rule"]), "verdict": F.coalesce(found["action"], F.lit("allow")), "n_candidates": F.col(top)["n"],
        "host": host, "path": path,
    }
    return urls.withColumns(made).drop(top)


def op1_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(read_table(spark, sf_dir, "pages", "page_id", "url"), default_rules()).select("page_id", "host", "path", "rule", "verdict", "pattern")


_FITS = " ".join(
    f"WHEN (host = '{h}' OR host LIKE '%.{h}') AND starts_with(path, '{p}') THEN {{}}'{h}{p}'" for _, h, p in sorted(SITE_RULES, key=lambda r: (-len(r[1] + r[2]), r[1]))
)
_ACTIONS = " ".join(f"WHEN '{h}{p}' THEN '{a}'" for a, h, p in SITE_RULES)
_PATTERNS = " ".join(f"WHEN contains(host || path, '{p.replace('*', '')}') THEN '{p}'" for _, p in sorted(PATTERN_RULES, key=lambda r: (-len(r[1]), r[1])))
OP1_SQL = f"""
WITH cut AS (SELECT page_id, CASE WHEN contains(coalesce(url, ''), '://') THEN substr(url, position('://' IN url) + 3) ELSE '' END AS rest FROM pages),
parts AS (SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*'), '{UPPER}', '{LOWER}') AS host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM cut),
ruled AS (SELECT *, CASE {_FITS.replace("{}", "")} END AS rule FROM parts),
pats AS (SELECT *, CASE WHEN rule IS NULL THEN CASE {_PATTERNS} END END AS pattern FROM ruled)
SELECT page_id, host, path, rule, CASE rule {_ACTIONS} ELSE CASE WHEN pattern IS NULL THEN 'allow' ELSE 'block' END END AS verdict, pattern FROM pats
"""
