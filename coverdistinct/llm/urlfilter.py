"""URL rules in a trie over reversed host labels and then path segments.

A rule ``(host, path)`` fits its host and all subdomains when the url's path starts
with the rule's path; of the fitting rules the longest (host and path together)
wins, and a block before an allow of equal length.  The trie walks the host from
its last label to its first, so a url costs as many steps as it has labels and
segments, whatever the number of rules.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower

#: Characters of rule text that may be broadcast; a larger list is refused (split it by host first).
MAX_RULE_CHARS = 64_000_000


class RuleTrie:
    """Nested dicts: host labels, ``None`` to the path part, then whole segments;
    under ``""`` the unfinished last segments, each a string prefix."""

    def __init__(self, rules: list[tuple[str, str, str]], default: str = "allow"):
        if sum(len(h) + len(p) for _, h, p in rules) > MAX_RULE_CHARS:
            raise ValueError("too many rules for one broadcast")
        self.root: dict = {}
        self.default = default
        for verdict, host, path in rules:
            if verdict not in ("allow", "block") or not path.startswith("/"):
                raise ValueError(f"bad rule {verdict} {host}{path}")
            node = self.root
            for label in reversed(host.lower().split(".")):
                node = node.setdefault(label, {})
            node = node.setdefault(None, {})
            *whole, last = path[1:].split("/")
            for segment in whole:
                node = node.setdefault("/" + segment, {})
            ends = node.setdefault("", {})
            old = ends.get(last)
            if old is None or verdict == "block":
                ends[last] = (len(host) + len(path), verdict == "block", host + path, verdict)

    def match(self, host: str, path: str) -> tuple[str | None, str]:
        best = None
        node = self.root
        if host and path.startswith("/"):
            segments = path[1:].split("/")
            for label in reversed(host.split(".")):
                node = node.get(label)
                if node is None:
                    break
                below = node.get(None)
                for segment in segments:
                    if below is None:
                        break
                    ends = below.get("")
                    if ends:
                        if len(ends) <= len(segment) + 1:
                            hits = [x for end, x in ends.items() if segment.startswith(end)]
                        else:
                            hits = [ends[segment[:n]] for n in range(len(segment) + 1) if segment[:n] in ends]
                        best = max([best, *hits] if best else hits, default=best)
                    below = below.get("/" + segment)
        return (best[2], best[3]) if best else (None, self.default)


#: The production rules: fixed values.
RULES = [
    ("allow", "org", "/"),
    ("block", "example.org", "/es/"),
    ("block", "example.org", "/en/1"),
    ("allow", "com", "/fr/"),
    ("block", "com", "/de/"),
]


def url_parts(df: DataFrame, url: str = "url") -> DataFrame:
    """Adds host and path: JVM string functions, both empty without ``://``."""
    u = F.coalesce(F.col(url), F.lit(""))
    at = F.instr(u, "://")
    rest = F.when(at > 0, F.expr(f"substring(coalesce(`{url}`, ''), instr(coalesce(`{url}`, ''), '://') + 3)")).otherwise("")
    df = df.withColumn("__rest", F.substring_index(F.substring_index(rest, "?", 1), "#", 1))
    host = F.substring_index("__rest", "/", 1)
    return df.withColumn("host", ascii_lower(host)).withColumn("path", F.expr("substring(__rest, length(substring_index(__rest, '/', 1)) + 1)")).drop("__rest")


def judge(df: DataFrame, rules: list[tuple[str, str, str]] = RULES, default: str = "allow", url: str = "url") -> DataFrame:
    """Adds host, path, rule (null if none fits) and verdict to every row.

    Null, empty or schemeless urls have empty host and path and get the default;
    repeated rows are judged alike; very long urls are walked segment by segment.
    The trie is broadcast; its size is checked when it is built."""
    trie = df.sparkSession.sparkContext.broadcast(RuleTrie(rules, default))

    @F.pandas_udf("struct<rule string, verdict string>")
    def walk(parts: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.DataFrame]:
        match = trie.value.match
        for hosts, paths in parts:
            yield pd.DataFrame([match(h, p) for h, p in zip(hosts, paths)], columns=["rule", "verdict"])

    out = url_parts(df.drop("host", "path", "rule", "verdict"), url).withColumn("__v", walk("host", "path"))
    return out.withColumn("rule", F.col("__v.rule")).withColumn("verdict", F.col("__v.verdict")).drop("__v")


def judge_pages(pages: DataFrame) -> DataFrame:
    return judge(pages.select("page_id", "url")).select("page_id", "host", "path", "rule", "verdict")


SQL = r"""
WITH rules(verdict, host, path) AS (VALUES ('allow', 'org', '/'), ('block', 'example.org', '/es/'), ('block', 'example.org', '/en/1'), ('allow', 'com', '/fr/'), ('block', 'com', '/de/')),
u AS (SELECT page_id, CASE WHEN instr(url, '://') > 0 THEN regexp_extract(substr(url, instr(url, '://') + 3), '^[^?#]*') ELSE '' END AS rest FROM pages),
p AS (SELECT page_id, translate(regexp_extract(rest, '^[^/]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, substr(rest, length(regexp_extract(rest, '^[^/]*')) + 1) AS path FROM u),
m AS (SELECT p.page_id, p.host, p.path, r.host || r.path AS rule, r.verdict, row_number() OVER (PARTITION BY p.page_id ORDER BY length(r.host || r.path) DESC NULLS LAST, r.verdict DESC) AS k
  FROM p LEFT JOIN rules r ON (p.host = r.host OR ends_with(p.host, '.' || r.host)) AND starts_with(p.path, r.path))
SELECT page_id, host, path, rule, coalesce(verdict, 'allow') AS verdict FROM m WHERE k = 1
"""
