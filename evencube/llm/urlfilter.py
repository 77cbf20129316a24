"""URL filter: a trie over reversed host labels, then path segments, with longest match.

A rule names a host and a path prefix. It fits the host and all its subdomains
when the url's path starts with the rule's path. Of several fitting rules the
one with the most host labels wins, then the one with the longest path; of an
allow and a block with the same host and path, block wins.
"""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, field

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

UPPER, SMALL = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

#: Most characters of rules that are broadcast; more are judged in several tries.
MAX_RULE_CHARS = 64 << 20


@dataclass(frozen=True)
class Rule:
    verdict: str
    host: str
    path: str = ""

    @property
    def name(self) -> str:
        return self.host + self.path

    @property
    def labels(self) -> int:
        return len(self.host.split(".")) if self.host else 0


@dataclass
class _Node:
    labels: dict[str, "_Node"] = field(default_factory=dict)
    paths: "_Path | None" = None


@dataclass
class _Path:
    segments: dict[str, "_Path"] = field(default_factory=dict)
    #: the unfinished last segment of a rule, with the rule; longest first
    heads: list[tuple[str, Rule]] = field(default_factory=list)
    bare: Rule | None = None


def _keep(old: Rule | None, new: Rule) -> Rule:
    return old if old is not None and old.verdict == "block" else new


class HostPathTrie:
    """Host labels from the right, then path segments from the left."""

    def __init__(self, rules: Iterable[Rule]) -> None:
        self.root = _Node()
        for rule in rules:
            self.add(rule)

    def add(self, rule: Rule) -> None:
        node = self.root
        for label in reversed(rule.host.lower().split(".")) if rule.host else ():
            node = node.labels.setdefault(label, _Node())
        at = node.paths = node.paths or _Path()
        if not rule.path:
            at.bare = _keep(at.bare, rule)
            return
        *whole, head = rule.path.split("/")[1:]
        for segment in whole:
            at = at.segments.setdefault(segment, _Path())
        heads = dict(at.heads)
        heads[head] = _keep(heads.get(head), rule)
        at.heads = sorted(heads.items(), key=lambda x: -len(x[0]))

    def match(self, host: str, path: str) -> Rule | None:
        node, fitting = self.root, [self.root]
        for label in reversed(host.split(".")):
            node = node.labels.get(label)
            if node is None:
                break
            fitting.append(node)
        for node in reversed(fitting):
            if node.paths is not None and (found := self._in_path(node.paths, path)) is not None:
                return found
        return None

    @staticmethod
    def _in_path(at: _Path, path: str) -> Rule | None:
        best = at.bare
        for segment in path.split("/")[1:]:
            best = next((rule for head, rule in at.heads if segment.startswith(head)), best)
            at = at.segments.get(segment)
            if at is None:
                break
        return best


def url_host(url: Column) -> Column:
    """Text after the first ``://`` up to ``/``, ``?``, ``#`` or the end, A-Z lower-cased; without ``://`` or null: empty."""
    host = F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1)
    return F.coalesce(F.translate(host, UPPER, SMALL), F.lit(""))


def url_path(url: Column) -> Column:
    """Text after the host up to ``?``, ``#`` or the end; without ``://`` or null: empty."""
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def judge_urls(pages: DataFrame, rules: list[Rule], url: str = "url", default: str = "allow") -> DataFrame:
    """``pages`` with host, path, rule (null without one) and verdict (the rule's, else ``default``).

    Columns of those names are replaced. A null, empty or malformed url gets
    empty host and path, no rule and the default verdict; repeated rows are
    judged alike, an empty table gives an empty result. Rows never move: the
    trie is broadcast, its size is checked first; rules of more than
    ``MAX_RULE_CHARS`` make several tries, of which the longest match wins.
    """
    if default not in ("allow", "block"):
        raise ValueError("default is allow or block")
    tries = [pages.sparkSession.sparkContext.broadcast(HostPathTrie(part)) for part in _blocks(rules)]

    def judge(trie, host: Column, path: Column) -> Column:
        @F.pandas_udf("labels int, chars int, rule string, verdict string")
        def judged(host: pd.Series, path: pd.Series) -> pd.DataFrame:
            match, seen, out = trie.value.match, {}, []
            for key in zip(host, path):
                if key not in seen:
                    rule = match(*key)
                    seen[key] = (-1, -1, None, default) if rule is None else (rule.labels, len(rule.path), rule.name, rule.verdict)
                out.append(seen[key])
            return pd.DataFrame(out, columns=["labels", "chars", "rule", "verdict"])

        return judged(host, path)

    names = [c for c in pages.columns if c.lower() not in ("host", "path", "rule", "verdict")]
    # under names of their own, as pages may have columns of any name
    plain = pages.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("own"), url_host(F.col(url)).alias("host"), url_path(F.col(url)).alias("path"))
    found = plain.select("*", *[judge(trie, F.col("host"), F.col("path")).alias(f"judged{k}") for k, trie in enumerate(tries)])
    # a struct is greater by its labels first, then by its path's length
    best = F.greatest(*[F.col(f"judged{k}") for k in range(len(tries))]) if len(tries) > 1 else F.col("judged0")
    found = found.select("own", "host", "path", best.alias("best"))
    return found.select(*[F.col("own").getField(c).alias(c) for c in names], "host", "path", F.col("best.rule").alias("rule"), F.col("best.verdict").alias("verdict"))


def _blocks(rules: list[Rule]) -> list[list[Rule]]:
    """Rules of ``MAX_RULE_CHARS`` or so each; rules of one host and path stay together."""
    out: list[list[Rule]] = [[]]
    size, last = 0, None
    for rule in sorted(rules, key=lambda r: (r.host.lower(), r.path)):
        if size > MAX_RULE_CHARS and (rule.host.lower(), rule.path) != last:
            out.append([])
            size = 0
        out[-1].append(rule)
        size, last = size + len(rule.name), (rule.host.lower(), rule.path)
    return out
