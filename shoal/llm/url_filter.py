"""URL allow and block lists as a trie over reversed host labels, then path segments.

The trie is built once from the rules and broadcast (`MAX_RULES` bounds it); each URL walks it from
its top-level label down. A rule fits its host and every subdomain, and any path that starts with
the rule's path; the longest rule that fits decides. Paths are walked segment by segment; the last
segment of a rule may be only the beginning of the URL's segment.

Defined results: a null URL or one without `://` has empty host and path and takes the default;
equal rules keep the last verdict given; rows are judged one by one, so repeats give repeats.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shoal.llm.storage import arrow_stage

MAX_RULES = 2_000_000
_LOWER = str.maketrans({c: chr(c + 32) for c in range(65, 91)})


def split_url(url: str | None) -> tuple[str, str]:
    """Host (A-Z lower-cased) and path."""
    if url is None or (at := url.find("://")) < 0:
        return "", ""
    rest = url[at + 3 :]
    cut = min((p for p in (rest.find("?"), rest.find("#")) if p >= 0), default=len(rest))
    slash = rest.find("/", 0, cut)
    end = cut if slash < 0 else slash
    return rest[:end].translate(_LOWER), rest[end:cut]


class Node:
    __slots__ = ("labels", "segments", "tails")

    def __init__(self) -> None:
        self.labels: dict[str, Node] = {}
        self.segments: dict[str, Node] = {}
        self.tails: dict[str, tuple[str, str]] = {}  # beginning of a segment -> rule, verdict


class UrlTrie:
    """rules: (verdict, host, path) with path empty or beginning with a slash."""

    def __init__(self, rules: Iterable[tuple[str, str, str]]) -> None:
        self.root, n = Node(), 0
        for verdict, host, path in rules:
            node = self.root
            for label in reversed(host.translate(_LOWER).split(".")):
                node = node.labels.setdefault(label, Node())
            *whole, last = path.split("/")
            for segment in whole:
                node = node.segments.setdefault(segment, Node())
            node.tails[last] = (host.translate(_LOWER) + path, verdict)
            if (n := n + 1) > MAX_RULES:
                raise ValueError(f"more than {MAX_RULES} rules: too many to broadcast; split them by top-level label and filter in turns")

    def _paths(self, node: Node, path: str) -> tuple[str, str] | None:
        found, rest = None, path
        while True:
            segment, slash, after = rest.partition("/")
            if node.tails:
                for size in range(len(segment), -1, -1):
                    if hit := node.tails.get(segment[:size]):
                        found = hit
                        break
                else:
                    hit = None
            if not slash or (node := node.segments.get(segment)) is None:
                return found
            rest = after

    def match(self, host: str, path: str) -> tuple[str, str] | None:
        """(rule, verdict) of the longest rule: host labels first, then path."""
        node, found = self.root, None
        for label in reversed(host.split(".")):
            if (node := node.labels.get(label)) is None:
                break
            if node.tails or node.segments:
                found = self._paths(node, path) or found
        return found


def filter_urls(pages: DataFrame, rules: Iterable[tuple[str, str, str]], default: str = "allow", key: str = "page_id", url: str = "url") -> DataFrame:
    """One row per page: key, host, path, rule (null if none fits), verdict."""
    trie = pages.sparkSession.sparkContext.broadcast(UrlTrie(rules))
    kind = pages.schema[key].dataType.simpleString()

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        match = trie.value.match
        for b in batches:
            parts = [split_url(u) for u in b.column(1).to_pylist()]
            hits = [match(*p) for p in parts]
            columns = [b.column(0), *(pa.array(x, pa.string()) for x in ([p[0] for p in parts], [p[1] for p in parts], [h and h[0] for h in hits], [h[1] if h else default for h in hits]))]
            yield pa.RecordBatch.from_arrays(columns, [key, "host", "path", "rule", "verdict"])

    return arrow_stage(pages, [F.col(key), F.col(url)], judge, f"{key} {kind}, host string, path string, rule string, verdict string")
