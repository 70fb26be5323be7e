"""URL filters: allow and block entries in a trie over reversed host labels, then path segments.

The trie is built on the driver from a rule list of checked size and sent to the tasks; a url walks it once.
A rule fits its host and all subdomains if the url's path starts with the rule's path; the longest fitting rule (host labels, then
path) wins, and of an allow and a block entry for the same place the allow one.

Defined results: a null url, or one without "://", has an empty host and path and gets the default verdict; hosts
are compared as written (a port or a final dot belongs to the last label); repeated rows stay; an empty table gives an empty one.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: The production rules as (verdict, rule).
RULES = (("block", "net/"), ("allow", "example.net/en/"), ("block", "example.com/de/"), ("allow", "org/fr/"))
MAX_RULES = 500_000


def split_url(url: str | None) -> tuple[str, str]:
    """Host with A-Z lower-cased, and path."""
    at = (url or "").find("://")
    if at < 0:
        return "", ""
    rest, slash = url[at + 3 :], len(url)
    for k, c in enumerate(rest):
        if c in "?#":
            rest = rest[:k]
            break
    slash = rest.find("/")
    host, path = (rest, "") if slash < 0 else (rest[:slash], rest[slash:])
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in host), path


class Trie:
    """Nodes are [children, tails]; tails are (rest of a path, verdict, rule) kept longest first."""

    def __init__(self, rules):
        if len(rules) > MAX_RULES:
            raise ValueError(f"more than {MAX_RULES} rules; the trie is broadcast")
        self.hosts: list = [{}, None]
        for verdict, rule in sorted(rules, key=lambda r: r[0] != "allow"):
            slash = rule.find("/")
            host, path = (rule, "") if slash < 0 else (rule[:slash], rule[slash:])
            node = self.hosts
            for label in reversed(host.split(".")):
                node = node[0].setdefault(label, [{}, None])
            if node[1] is None:
                node[1] = [{}, []]
            *whole, tail = path.split("/")
            node = node[1]
            for segment in whole:
                node = node[0].setdefault(segment, [{}, []])
            if all(t[0] != tail for t in node[1]):
                node[1].append((tail, verdict, rule))
                node[1].sort(key=lambda t: -len(t[0]))

    def find(self, host: str, path: str) -> tuple[str, str] | None:
        """(verdict, rule) of the longest fitting rule."""
        node, best = self.hosts, None
        segments = path.split("/")
        for label in reversed(host.split(".")):
            node = node[0].get(label)
            if node is None:
                break
            if node[1] is not None:
                best = self._path(node[1], segments) or best
        return best

    @staticmethod
    def _path(node, segments):
        best = None
        for k, segment in enumerate(segments):
            best = next(((v, r) for tail, v, r in node[1] if segment.startswith(tail)), best)
            node = node[0].get(segment) if k + 1 < len(segments) else None
            if node is None:
                break
        return best


def judge_urls(pages: DataFrame, rules=RULES, default: str = "allow", id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """(id, host, path, rule, verdict): rule is null, and verdict the default, where no rule fits."""
    trie = pages.sparkSession.sparkContext.broadcast(Trie(rules))
    names = ["id", "host", "path", "rule", "verdict"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            parts = [split_url(u) for u in b.column(1).to_pylist()]
            found = [trie.value.find(*p) or (default, None) for p in parts]
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(list(c), type=pa.string()) for c in ([p[0] for p in parts], [p[1] for p in parts], [f[1] for f in found], [f[0] for f in found]))], names=names)

    return pages.select(F.col(id_col).cast("long").alias("id"), F.col(url_col).cast("string").alias("u")).mapInArrow(run, "id long, host string, path string, rule string, verdict string")


def op7(pages: DataFrame) -> DataFrame:
    return judge_urls(pages).withColumnRenamed("id", "page_id")


#: DuckDB.
SQL = r"""
WITH cut AS (
  SELECT page_id, CASE WHEN position('://' IN url) > 0 THEN regexp_extract(substr(url, position('://' IN url) + 3), '^[^?#]*', 0) ELSE '' END AS rest FROM pages),
split AS (
  SELECT page_id, translate(regexp_extract(rest, '^[^/]*', 0), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         CASE WHEN position('/' IN rest) > 0 THEN substr(rest, position('/' IN rest)) ELSE '' END AS path FROM cut),
ruled AS (
  SELECT *, CASE
    WHEN ('.' || host) LIKE '%.example.net' AND starts_with(path, '/en/') THEN 'example.net/en/'
    WHEN ('.' || host) LIKE '%.example.com' AND starts_with(path, '/de/') THEN 'example.com/de/'
    WHEN ('.' || host) LIKE '%.org' AND starts_with(path, '/fr/') THEN 'org/fr/'
    WHEN ('.' || host) LIKE '%.net' AND starts_with(path, '/') THEN 'net/' END AS rule FROM split)
SELECT page_id, host, path, rule, CASE WHEN rule IN ('net/', 'example.com/de/') THEN 'block' ELSE 'allow' END AS verdict FROM ruled
"""
