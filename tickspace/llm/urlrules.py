"""URL rules over hosts and paths by a sorted sweep of nested intervals.

Reversed host labels, each closed by a dot, are the key: a rule's host and all
its subdomains are exactly the keys that begin with the rule's key, an interval.
Such intervals nest or are disjoint, so one pass over a batch's keys in order,
merged with the rules in order, keeps the rules whose intervals are open on a
stack; the longest rule on it whose path begins the url's path wins.

Rules are a list of the driver's, of at most ``max_rules`` (checked: more are
refused), and all go to the tasks, in blocks of ``block_rules``; each block is
one sweep in the same scan, the longest winner stays.  Pages are
sorted within their batch only: no shuffle, so hot hosts cost nothing extra.

Defined cases: null urls and urls without ``://`` have empty host and path and
match nothing; a rule's length is that of its host and path together, then of
its host; of rules that are equal but for the verdict, block wins; repeated rows
are judged each; rules with null or empty host are ignored, a null path is
empty; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterable

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

_LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def split_url(url: str | None) -> tuple[str, str]:
    """(host, path) of a url."""
    if url is None or "://" not in url:
        return "", ""
    rest = url.split("://", 1)[1]
    end = min((at for c in "?#" if (at := rest.find(c)) >= 0), default=len(rest))
    rest = rest[:end]
    host, slash, path = rest.partition("/")
    return host.translate(_LOWER), slash + path


def reversed_key(host: str) -> str:
    return "".join(f"{label}." for label in reversed(host.split(".")))


class Rules:
    def __init__(self, rules: Iterable[tuple[str, str, str]]):
        """rules: (host, path, verdict)."""
        by_key: dict[str, list] = {}
        for host, path, verdict in rules:
            if host:
                by_key.setdefault(reversed_key(host.translate(_LOWER)), []).append((len(host) + len(path or ""), len(host), path or "", host.translate(_LOWER), verdict))
        self.sorted = sorted((k, sorted(v, key=lambda r: (-r[0], r[4] != "block"))) for k, v in by_key.items())

    def sweep(self, urls: list[tuple[str, str]]) -> list[tuple | None]:
        """The winning rule of each (host, path)."""
        keys = [reversed_key(h) if h else "" for h, _ in urls]
        out: list = [None] * len(urls)
        stack: list = []
        at, rules = 0, self.sorted
        for i in sorted(range(len(urls)), key=keys.__getitem__):
            key = keys[i]
            if not key:
                continue
            while at < len(rules) and rules[at][0] <= key:
                while stack and not rules[at][0].startswith(stack[-1][0]):
                    stack.pop()
                stack.append(rules[at])
                at += 1
            while stack and not key.startswith(stack[-1][0]):
                stack.pop()
            path, best = urls[i][1], None
            for _, group in stack:
                for rule in group:
                    if best is not None and rule[:2] <= best[:2]:
                        break
                    if path.startswith(rule[2]):
                        best = rule
                        break
            out[i] = best
        return out


def _judge(blocks, default: str):
    def run(batches):
        for batch in batches:
            urls = [split_url(u) for u in batch.column(1).to_pylist()]
            best: list = [None] * len(urls)
            for block in blocks:
                best = [b if a is None or (b is not None and b[:2] > a[:2]) else a for a, b in zip(best, block.value.sweep(urls))]
            rule = [None if r is None else r[3] + r[2] for r in best]
            verdict = [default if r is None else r[4] for r in best]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([h for h, _ in urls], pa.string()), pa.array([p for _, p in urls], pa.string()), pa.array(rule, pa.string()), pa.array(verdict, pa.string())], ["page_id", "host", "path", "rule", "verdict"])

    return run


def judge_urls(pages: DataFrame, rules: Iterable[tuple[str, str, str]], default: str = "allow", block_rules: int = 200_000, max_rules: int = 2_000_000, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """page_id, host, path, rule, verdict of every row of ``pages``."""
    sc, blocks, part = pages.sparkSession.sparkContext, [], []
    for n, rule in enumerate(rules):
        if n >= max_rules:
            raise ValueError(f"more than {max_rules} rules")
        part.append(tuple(rule))
        if len(part) == block_rules:
            blocks.append(sc.broadcast(Rules(part)))
            part = []
    if part:
        blocks.append(sc.broadcast(Rules(part)))
    src = pages.select(F.col(id_col).cast("bigint").alias("page_id"), F.col(url_col).alias("url"))
    return src.mapInArrow(_judge(blocks, default), "page_id bigint, host string, path string, rule string, verdict string")
