"""URL rules by a sort-merge range join.

A host's canonical key is its labels reversed, each followed by a byte 0x01 (one that a label holds is written as 0x02
0x02, and 0x02 as 0x02 0x03): every host below a rule's host has a key that begins with the rule's, so a rule is the interval [key, key + 0xFF). Host intervals nest or are disjoint.
URLs sorted by key meet rules sorted by start, and one sweep keeps the stack of the rules whose interval contains
the current key; the innermost rule on it whose path begins the URL's path wins (longer hosts first, then longer
paths; of a rule with both verdicts `block`). One sweep runs over all batches of a partition.

Rules are a table of rules, not of data. Up to `MOST_RULES` they travel to every task, and URLs are sorted within
their own partition: no shuffle and no skew. Beyond that, `judge` takes the same decision by equality on each
host's ancestors, so that nothing large is broadcast.

Defined cases: a null url, or one without "://", has an empty host and path and no rule; the host runs from the
first "://" to "/", "?", "#" or the end, A-Z lower-cased; the path runs on to "?", "#" or the end and may be empty,
in which case no rule fits (a rule's path begins with "/"); a rule's host is lower-cased in A-Z like a URL's; without a
rule the verdict is `default` (allow); repeated urls and ties get equal verdicts, null ids stay null; a URL of any
length is one row; an empty table gives an empty result; other columns aren't read, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

MOST_RULES = 200_000
MARK, ESCAPE = "\x01", "\x02"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_FOLD = str.maketrans(_UPPER, _LOWER)

#: Fixed: the rules of the query (verdict, host, path).
RULES = (
    ("allow", "com", "/"),
    ("block", "example.com", "/en/"),
    ("allow", "www.example.com", "/en/"),
    ("block", "net", "/es/"),
    ("block", "net", "/fr/"),
)


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Both empty for a null url or one without "://"."""
    after = F.regexp_extract(F.coalesce(url, F.lit("")), r"^(?s:.*?)://((?s:.*))$", 1)
    host = F.translate(F.regexp_extract(after, r"^([^/?#]*)", 1), _UPPER, _LOWER)
    return host, F.regexp_extract(after, r"^[^/?#]*([^?#]*)", 1)


def canonical_key(host: Column) -> Column:
    plain = F.replace(F.replace(host, F.lit(ESCAPE), F.lit(ESCAPE + "\x03")), F.lit(MARK), F.lit(ESCAPE * 2))
    return F.concat(F.array_join(F.reverse(F.split(plain, r"\.")), MARK), F.lit(MARK))


def key_of(host: str) -> str:
    return MARK.join(reversed(host.replace(ESCAPE, ESCAPE + "\x03").replace(MARK, ESCAPE * 2).split("."))) + MARK


def folded(host: str) -> str:
    return host.translate(_FOLD)


def ordered_rules(rules) -> list[tuple[str, str, str, str]]:
    """(key, path, verdict, text) of different rules, by key and then from the weakest to the strongest."""
    seen = {(key_of(folded(h)), p, v, folded(h) + p) for v, h, p in rules}
    best: dict[tuple[str, str], tuple[str, str, str, str]] = {}
    for r in sorted(seen, key=lambda r: (r[2] != "block", r[3])):
        best.setdefault(r[:2], r)
    return sorted(best.values(), key=lambda r: (r[0].encode(), len(r[1]), r[1].encode()))


def sweep(urls: Iterable[tuple[str, str]], rules: list[tuple[str, str, str, str]]) -> Iterator[tuple[str, str] | None]:
    """(text, verdict) of the winning rule of each url (key, path), which come in the order of their keys; `rules` as
    ordered."""
    stack: list[tuple[str, list[tuple[str, str, str, str]]]] = []
    at = 0
    for key, path in urls:
        raw = key.encode()
        while stack and not key.startswith(stack[-1][0]):
            stack.pop()
        while at < len(rules) and rules[at][0].encode() <= raw:
            start = rules[at][0]
            group = []
            while at < len(rules) and rules[at][0] == start:
                group.append(rules[at])
                at += 1
            while stack and not start.startswith(stack[-1][0]):
                stack.pop()
            if key.startswith(start):
                stack.append((start, group))
        yield next(((r[3], r[2]) for _, group in reversed(stack) for r in reversed(group) if path.startswith(r[1])), None)


def judge_small(pages: DataFrame, rules, default: str = "allow", id_column: str = "page_id", url_column: str = "url") -> DataFrame:
    table = ordered_rules(rules)
    names = [id_column, "host", "path", "rule", "verdict"]
    host, path = host_and_path(F.col(url_column))
    parts = pages.select(F.col(id_column).cast("long").alias(id_column), host.alias("host"), path.alias("path"))
    parts = parts.withColumn("key", F.when(F.col("host") == "", F.lit("")).otherwise(canonical_key(F.col("host")))).sortWithinPartitions("key", "path")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        read, keys = [], []

        def each() -> Iterator[tuple[str, str]]:
            for b in batches:
                read.append(b)
                keys.append(b.num_rows)
                yield from zip(b[3].to_pylist(), b[2].to_pylist(), strict=True)

        # One sweep over the partition; a batch is given out as soon as its last url has its rule.
        found = []
        for winner in sweep(each(), table):
            found.append(winner)
            while keys and len(found) == keys[0]:
                b = read.pop(0)
                keys.pop(0)
                yield pa.RecordBatch.from_arrays([b[0], b[1], b[2], pa.array([x and x[0] for x in found], pa.string()), pa.array([x[1] if x else default for x in found], pa.string())], names)
                found = []

    return parts.mapInArrow(run, f"{id_column} long, host string, path string, rule string, verdict string")


def judge_large(pages: DataFrame, rules: DataFrame, default: str = "allow", id_column: str = "page_id", url_column: str = "url") -> DataFrame:
    """The same verdicts for a table of rules (verdict, host, path) of any size: each different host and path is
    matched once, by equality of the rule's host with one of the host's ancestors."""
    host, path = host_and_path(F.col(url_column))
    parts = pages.select(F.col(id_column).cast("long").alias(id_column), host.alias("host"), path.alias("path"))
    r = rules.select("verdict", F.translate("host", _UPPER, _LOWER).alias("rule_host"), F.col("path").alias("rule_path")).distinct()
    labels = F.split("host", r"\.")
    ancestors = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    each = parts.select("host", "path").distinct().where("host <> ''").withColumn("rule_host", F.explode(ancestors))
    hit = each.join(r, "rule_host").where(F.col("path").startswith(F.col("rule_path")))
    rank = F.struct(F.size(F.split("rule_host", r"\.")).alias("a"), F.length("rule_path").alias("b"), (F.col("verdict") == "block").alias("c"))
    best = hit.groupBy("host", "path").agg(F.max_by(F.struct(F.concat("rule_host", "rule_path").alias("rule"), "verdict"), rank).alias("w"))
    out = parts.join(best, ["host", "path"], "left")
    return out.select(id_column, "host", "path", F.col("w.rule").alias("rule"), F.coalesce("w.verdict", F.lit(default)).alias("verdict"))


def judge(pages: DataFrame, rules, default: str = "allow", **columns) -> DataFrame:
    """page_id, host, path, rule, verdict of every page. rules: (verdict, host, path) in a list or a DataFrame."""
    if isinstance(rules, DataFrame):
        few = rules.select("verdict", "host", "path").limit(MOST_RULES + 1).collect()
        if len(few) > MOST_RULES:
            return judge_large(pages, rules, default, **columns)
        rules = [tuple(x) for x in few]
    return judge_small(pages, rules, default, **columns)


__all__ = ["RULES", "Window", "canonical_key", "host_and_path", "judge", "judge_large", "judge_small", "ordered_rules", "sweep"]
