"""URL filters: pattern rules that are looked up by their rarest literal token.

A rule is a regular expression over ``host + path`` with the whole tokens
(runs of a-z and 0-9 between other characters) that every match must hold. How
often each of the rules' tokens occurs is counted over all URLs; a rule is
filed under the token that occurs least. A URL's tokens then fetch candidate
rules and only those are matched. The set of rules is given by the caller, so
its size doesn't follow the data; above ``MOST_RULES`` the call is refused.

A list rule (host, path, verdict) fits its host and all subdomains where the
path starts with the rule's; the longest that fits decides. Else a pattern rule
that matches blocks, and without any the URL is allowed.

Cases: a null URL or one without ``://`` has an empty host and path and is
allowed; repeated rows give a row each; an empty table gives no rows; other
columns are left out; a null id stays null.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Rules travel to every executor; this bounds what they take.
MOST_RULES = 200_000
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
TOKEN = re.compile("[a-z0-9]+")


@dataclass(frozen=True)
class Rule:
    name: str
    verdict: str
    pattern: str
    tokens: tuple[str, ...]
    #: List rules before patterns, and the longer before the shorter.
    weight: int


def list_rule(host: str, path: str, verdict: str) -> Rule:
    name = host + path
    pattern = r"^(?:[^/]*\.)?" + re.escape(name)
    whole = TOKEN.findall(name) if name.endswith("/") else TOKEN.findall(name)[:-1]
    return Rule(name, verdict, pattern, tuple(t.lower() for t in whole), 1 + len(name))


def word_rule(*tokens: str) -> Rule:
    """Blocks URLs that hold these tokens one after the other, with one separator between."""
    edge = "[^a-z0-9]"
    body = edge.join(map(re.escape, tokens))
    return Rule("", "block", rf"(?i)(?:^|{edge}){body}(?:{edge}|$)", tokens, 0)


#: The list rules of the contract.
LIST_RULES = (
    list_rule("com", "/", "allow"),
    list_rule("example.com", "/en/", "block"),
    list_rule("www.example.com", "/en/", "allow"),
    list_rule("net", "/es/", "block"),
    list_rule("net", "/fr/", "block"),
)
#: Our own pattern rules for what no list rule decides.
WORD_RULES = tuple(
    word_rule(*tokens)
    for tokens in (
        ("casino",), ("casino", "win"), ("spam", "farm"), ("ads", "track"), ("adserver",), ("doubleclick",), ("porn",), ("xxx",), ("viagra",),
        ("free", "money"), ("click", "bait"), ("torrent",), ("warez",), ("phishing",), ("malware",), ("link", "farm"), ("betting",), ("poker",),
    )
)


def host_of(url: Column) -> Column:
    """After the first ``://`` up to ``/``, ``?``, ``#`` or the end, ASCII letters in lower case."""
    return F.translate(F.coalesce(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), F.lit("")), UPPER, LOWER)


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def token_counts(urls: DataFrame, rules: tuple[Rule, ...]) -> dict[str, int]:
    """In how many URLs each token of the rules occurs; other tokens are left out before the shuffle."""
    wanted = sorted({t for r in rules for t in r.tokens})
    if not wanted:
        return {}
    found = F.array_intersect(F.split(F.translate(F.col("target"), UPPER, LOWER), "[^a-z0-9]+"), F.array(*map(F.lit, wanted)))
    rows = urls.select(F.explode(found).alias("token")).groupBy("token").count().collect()
    return {r.token: r["count"] for r in rows}


def index_of(rules: tuple[Rule, ...], counts: dict[str, int]) -> tuple[dict[str, list[int]], list[int]]:
    """Rules by their rarest token, and those that have none and must always be tried."""
    by_token: dict[str, list[int]] = {}
    always: list[int] = []
    for i, rule in enumerate(rules):
        if rule.tokens:
            rarest = min(rule.tokens, key=lambda t: (counts.get(t, 0), -len(t), t))
            by_token.setdefault(rarest, []).append(i)
        else:
            always.append(i)
    return by_token, always


def judge(urls: DataFrame, rules: tuple[Rule, ...]) -> DataFrame:
    """``urls`` has page_id and url; adds host, path, rule, verdict and n_tried (regular expressions run)."""
    if len(rules) > MOST_RULES:
        raise ValueError(f"{len(rules)} rules; at most {MOST_RULES} are sent to the executors")
    split = urls.select("page_id", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))
    counts = token_counts(split.select(F.concat("host", "path").alias("target")), rules)
    by_token, always = index_of(rules, counts)

    @F.pandas_udf("rule string, verdict string, n_tried int")
    def decided(parts: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        compiled: dict[int, re.Pattern] = {}
        lower = str.maketrans(UPPER, LOWER)
        for targets in parts:
            out = []
            for target in targets:
                tried = {i for t in TOKEN.findall(target.translate(lower)) for i in by_token.get(t, ())}
                best = None
                for i in (*tried, *always):
                    if i not in compiled:
                        compiled[i] = re.compile(rules[i].pattern, re.ASCII)
                    if (best is None or rules[i].weight > best.weight) and compiled[i].search(target):
                        best = rules[i]
                out.append(((best.name or None) if best else None, best.verdict if best else "allow", len(tried) + len(always)))
            yield pd.DataFrame(out, columns=["rule", "verdict", "n_tried"])

    return split.withColumn("found", decided(F.concat("host", "path"))).select("page_id", "host", "path", "found.rule", "found.verdict", "found.n_tried")
