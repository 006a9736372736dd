"""URL filters as a sort-merge range join.

A host's labels are reversed and each is ended by a separator that sorts before all others, so a rule's host is
a prefix of exactly the keys of its host and subdomains: an interval of the sorted keys. Pages and rules are dealt
to ranges of (key, salt) whose bounds come from a sample of the pages, a rule to every range that its interval
meets; each range is sorted and swept once, with the nested rules that are active on a stack. The salt splits a
host that holds many pages. Of the active rules whose path the page's path starts with the longest wins.

Cases: a null url or one without :// has an empty host and path and gets the default; repeated urls are judged
each; of rules with equal host and path a block wins; no rules or no pages are allowed.
"""

from __future__ import annotations

from bisect import bisect_left, bisect_right
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from joinpoisson.llm.common import hash_sample

#: Fixed values of the contract.
RULES = (("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow"))
DEFAULT, SAMPLE, RANGES_PER_PARTITION = "allow", 8192, 4
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
COLUMNS = ["range", "key", "kind", "page_id", "host", "path", "action"]
END = "\x00"
LAST = "\U0010ffff"


def host_of(url: Column) -> Column:
    return F.translate(F.coalesce(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), F.lit("")), UPPER, LOWER)


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def host_key(host: str) -> str:
    return END.join(reversed(host.split("."))) + END


def rules_frame(spark: SparkSession, rules=RULES) -> DataFrame:
    return spark.createDataFrame(list(rules), "host string, path string, action string")


def judge(pages: DataFrame, rules: DataFrame, default: str = DEFAULT, sample: int = SAMPLE) -> DataFrame:
    """page_id, host, path, rule, verdict for every row of pages (page_id, url)."""
    spark = pages.sparkSession
    key = F.concat(F.array_join(F.reverse(F.split("host", r"\.")), END), F.lit(END))
    split = pages.select("page_id", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"), F.xxhash64("page_id", "url").alias("salt")).withColumn("key", key)
    drawn = hash_sample(split.select("key", "salt"), sample, "salt", "key").collect()
    seen = sorted((r["key"], r["salt"]) for r in drawn)
    ranges = min(len(seen), RANGES_PER_PARTITION * int(spark.conf.get("spark.sql.shuffle.partitions")))
    bounds = [seen[len(seen) * i // ranges] for i in range(1, ranges)]
    shape = "range int, key string, kind int, page_id long, host string, path string, action string"

    def place_pages(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            keys = b.column("key").to_pylist()
            at = [bisect_right(bounds, x) for x in zip(keys, b.column("salt").to_pylist(), strict=True)]
            n = b.num_rows
            yield pa.RecordBatch.from_arrays([pa.array(at, pa.int32()), b.column("key"), pa.array([1] * n, pa.int32()), b.column("page_id").cast(pa.int64()), b.column("host"), b.column("path"), pa.array([None] * n, pa.string())], names=COLUMNS)

    def place_rules(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        low, high = -(1 << 63), 1 << 63
        for b in batches:
            for rule in b.to_pylist():
                k = host_key(rule["host"])
                at = range(bisect_left(bounds, (k, low)), bisect_left(bounds, (k + LAST, high)) + 1)
                n = len(at)
                yield pa.RecordBatch.from_arrays([pa.array(at, pa.int32()), *[pa.array([x] * n, t) for x, t in ((k, pa.string()), (0, pa.int32()), (None, pa.int64()), (rule["host"], pa.string()), (rule["path"], pa.string()), (rule["action"], pa.string()))]], names=COLUMNS)

    both = split.select("page_id", "host", "path", "key", "salt").mapInArrow(place_pages, shape).unionByName(rules.select("host", "path", "action").mapInArrow(place_rules, shape))
    dealt = both.repartition(int(spark.conf.get("spark.sql.shuffle.partitions")), "range").sortWithinPartitions("range", "key", "kind")
    return dealt.mapInArrow(lambda x: _sweep(x, default), "page_id long, host string, path string, rule string, verdict string")


class _Active:
    """The path rules of one host on the stack."""

    def __init__(self, key: str, host: str):
        self.key, self.host, self.paths, self.lengths = key, host, {}, []

    def add(self, path: str, action: str) -> None:
        if self.paths.get(path) != "block":
            self.paths[path] = action
        self.lengths = sorted({len(p) for p in self.paths}, reverse=True)

    def longest(self, path: str) -> str | None:
        return next((p for n in self.lengths if (p := path[:n]) in self.paths), None)


def _sweep(batches: Iterator[pa.RecordBatch], default: str) -> Iterator[pa.RecordBatch]:
    stack: list[_Active] = []
    within = None
    for b in batches:
        out = []
        for part, key, kind, page, host, path, action in zip(*[c.to_pylist() for c in b.columns], strict=True):
            if part != within:
                stack, within = [], part
            while stack and not key.startswith(stack[-1].key):
                stack.pop()
            if kind == 0:
                if not stack or stack[-1].key != key:
                    stack.append(_Active(key, host))
                stack[-1].add(path, action)
                continue
            best = None
            for a in stack:
                if (p := a.longest(path)) is not None and (best is None or len(a.host) + len(p) >= len(best[0]) + len(best[1])):
                    best = (a.host, p, a.paths[p])
            out.append((page, host, path, best[0] + best[1] if best else None, best[2] if best else default))
        columns = list(zip(*out, strict=True)) if out else [()] * 5
        yield pa.RecordBatch.from_arrays([pa.array(columns[0], pa.int64()), *[pa.array(c, pa.string()) for c in columns[1:]]], names=["page_id", "host", "path", "rule", "verdict"])
