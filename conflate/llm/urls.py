"""URL filter: a trie over reversed host labels and path segments, sent to every task.

Hosts come after the first ``://`` up to ``/``, ``?``, ``#`` or the end, A-Z lower-cased; paths from there
up to ``?``, ``#`` or the end.  A null URL, an empty one or one without ``://`` has an empty host and path and
gets the default verdict.  A rule fits its host and every subdomain when the path starts with the rule's
path, character by character; among fitting rules the one with most host labels wins, then the longest path,
so a longer allow entry beats a shorter block entry and the other way round.  A later repeat of a rule replaces
the earlier one.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from conflate.llm.common import small_batches

#: Largest rule list that is sent to the tasks; a longer list is refused rather than sent.
MAX_RULES = 5_000_000


@dataclass
class Node:
    labels: dict[str, "Node"] = field(default_factory=dict)
    paths: "PathNode | None" = None


@dataclass
class PathNode:
    """Whole segments lead to children; ``tails`` are last segments, which may be cut short."""

    segments: dict[str, "PathNode"] = field(default_factory=dict)
    tails: dict[str, tuple[str, str]] = field(default_factory=dict)


def split_url(url: str | None) -> tuple[str, str]:
    if not url or (at := url.find("://")) < 0:
        return "", ""
    rest = url[at + 3 :]
    for stop in "?#":
        rest = rest.partition(stop)[0]
    slash = rest.find("/")
    host, path = (rest, "") if slash < 0 else (rest[:slash], rest[slash:])
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in host), path


class HostPathTrie:
    def __init__(self, rules: Iterable[tuple[str, str, str]], default: str = "allow"):
        """rules: (host, path, verdict)."""
        self.root, self.default = Node(), default
        for n, (host, path, verdict) in enumerate(rules):
            if n >= MAX_RULES:
                raise ValueError(f"more than {MAX_RULES} rules: too large to send to every task")
            node = self.root
            for label in reversed(host.lower().split(".")):
                node = node.labels.setdefault(label, Node())
            at = node.paths = node.paths or PathNode()
            *whole, tail = path.split("/")
            for segment in whole:
                at = at.segments.setdefault(segment, PathNode())
            at.tails[tail] = (host.lower() + path, verdict)

    def match(self, host: str, path: str) -> tuple[str | None, str]:
        """The winning rule and its verdict; (None, default) when none fits."""
        chain, node = [], self.root
        for label in reversed(host.split(".")):
            node = node.labels.get(label)
            if node is None:
                break
            if node.paths:
                chain.append(node.paths)
        segments = path.split("/")
        for top in reversed(chain):
            best, at = None, top
            for segment in segments:
                fits = [t for t in at.tails if segment.startswith(t)] if len(at.tails) < 8 else [segment[:k] for k in range(len(segment) + 1) if segment[:k] in at.tails]
                if fits:
                    best = at.tails[max(fits, key=len)]
                at = at.segments.get(segment)
                if at is None:
                    break
            if best:
                return best
        return None, self.default


def judge(pages: DataFrame, rules: Iterable[tuple[str, str, str]], default: str = "allow", key: str = "page_id", url: str = "url") -> DataFrame:
    """(key, host, path, rule, verdict) for every row."""
    small_batches(pages.sparkSession)
    trie = HostPathTrie(rules, default)
    sent = pages.sparkSession.sparkContext.broadcast(trie)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = sent.value
        for b in batches:
            hosts, paths, names, verdicts = [], [], [], []
            for u in b.column(1).to_pylist():
                host, path = split_url(u)
                rule, verdict = t.match(host, path)
                hosts.append(host)
                paths.append(path)
                names.append(rule)
                verdicts.append(verdict)
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(x, pa.string()) for x in (hosts, paths, names, verdicts))], ["key", "host", "path", "rule", "verdict"])

    kind = pages.schema[key].dataType.simpleString()
    rows = pages.select(F.col(key).alias("key"), F.col(url).alias("url")).mapInArrow(run, f"key {kind}, host string, path string, rule string, verdict string")
    return rows.withColumnRenamed("key", key)


def apply(pages: DataFrame, rules: Iterable[tuple[str, str, str]], default: str = "allow", key: str = "page_id", url: str = "url") -> DataFrame:
    """The rows of ``pages`` that aren't blocked, all columns kept."""
    trie = HostPathTrie(rules, default)
    sent = pages.sparkSession.sparkContext.broadcast(trie)

    @F.pandas_udf("boolean")
    def allowed(u):  # noqa: ANN001, ANN202
        return u.map(lambda x: sent.value.match(*split_url(x))[1] != "block")

    return pages.where(allowed(F.col(url)))
