"""URL filter as a sort-merge range join of pages and host rules.

Hosts are written from the top-level label down ("org.example.www."), so that a rule's host and all its
subdomains are one interval of keys. Pages are dealt out by ranges of keys, rules go to every range that
their interval meets, and one sweep over each sorted range keeps a stack of the rules that are open.
"""

from __future__ import annotations

from bisect import bisect_left, bisect_right
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower, drawn

#: Rows that are looked at to place the borders of ranges. Borders only balance the work: any borders give the same result.
BORDER_SAMPLE = 4_000
BEYOND = "\U0010ffff"


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Host: after the first "://" up to "/", "?", "#" or the end, A-Z lower-cased; path: from there up to "?" or "#"."""
    rest = F.when(F.instr(url, "://") > 0, F.expr("substring(url, instr(url, '://') + 3)"))
    host = F.regexp_extract(rest, r"^([^/?#]*)", 1)
    path = F.regexp_extract(rest, r"^[^/?#]*(/[^?#]*)", 1)
    return F.coalesce(ascii_lower(host), F.lit("")), F.coalesce(path, F.lit(""))


def host_key(host: Column) -> Column:
    return F.concat(F.array_join(F.reverse(F.split(host, r"\.")), "."), F.lit("."))


class Sweep:
    """The stack of open rules while keys come in order."""

    def __init__(self) -> None:
        self.stack: list[tuple[str, str, dict[str, tuple[str, str]], list[int]]] = []

    def close(self, key: str) -> None:
        while self.stack and not key.startswith(self.stack[-1][0]):
            self.stack.pop()

    def add(self, key: str, host: str, path: str, verdict: str) -> None:
        self.close(key)
        if not self.stack or self.stack[-1][0] != key:
            self.stack.append((key, host, {}, []))
        _, _, paths, lengths = self.stack[-1]
        if path not in paths or (verdict == "block" and paths[path] != "block"):
            paths[path] = verdict
        if len(path) not in lengths:
            lengths.append(len(path))

    def judge(self, key: str, path: str) -> tuple[str, str] | None:
        """The longest rule (host and path together, then host) that fits, and its verdict."""
        self.close(key)
        best, found = (-1, -1), None
        for _, host, paths, lengths in self.stack:
            for n in lengths:
                if n <= len(path) and (v := paths.get(path[:n])) and (rank := (len(host) + n, len(host))) > best:
                    best, found = rank, (host + path[:n], v)
        return found


def url_filter(pages: DataFrame, rules: DataFrame, default: str = "allow", ranges: int | None = None) -> DataFrame:
    """pages(page_id, url, ...), rules(host, path, verdict) -> page_id, host, path, rule, verdict.

    A rule fits its host and every subdomain if the url's path starts with the rule's; the longest wins; of two equal
    rules "block" wins. One row for each row of pages. Null urls and urls without "://" have an empty host and path,
    which no rule with a host fits. Without a fitting rule, `rule` is null and the verdict `default`.
    Null parts of a rule are empty. Empty tables are fine; extra columns are ignored.
    """
    spark = pages.sparkSession
    n = ranges or max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    host, path = host_and_path(F.col("url"))
    split = pages.select("page_id", F.col("url").alias("url")).select("page_id", host.alias("host"), path.alias("path"))
    keyed = split.select(host_key(F.col("host")).alias("key"), "page_id", "host", "path")
    # A bounded sample, for the borders only: about BORDER_SAMPLE rows pass, and twice as many at most are fetched.
    seen = sorted(r[0] for r in drawn(keyed.select("key"), BORDER_SAMPLE, pages.count()).limit(2 * BORDER_SAMPLE).collect())
    borders = [seen[i * len(seen) // n] for i in range(1, n)] if seen else []

    def places(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rules: a row for each range that they meet."""
        for b in batches:
            out = []
            for r in b.to_pylist():
                first, last = bisect_left(borders, r["key"]), bisect_right(borders, r["key"] + BEYOND)
                out += [r | {"part": k} for k in range(first, last + 1)]
            yield pa.RecordBatch.from_pylist(out, schema=ARROW)

    def ranged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Pages: their range; where a key fills several ranges, its rows are spread over them by their place."""
        at = 0
        for b in batches:
            keys, part = b.column("key").to_pylist(), []
            for k in keys:
                lo, hi = bisect_left(borders, k), bisect_right(borders, k)
                part.append(lo + at % (hi - lo + 1))
                at += 1
            yield pa.RecordBatch.from_arrays([pa.array(part, pa.int64()), *b.columns], schema=ARROW)

    columns = "part long, key string, tag int, page_id long, host string, path string, verdict string"
    fields = [("part", pa.int64()), ("key", pa.string()), ("tag", pa.int32()), ("page_id", pa.int64()), ("host", pa.string()), ("path", pa.string()), ("verdict", pa.string())]
    ARROW = pa.schema(fields)
    text = lambda c: F.coalesce(F.col(c), F.lit(""))
    from_rules = rules.select(text("host").alias("host"), text("path").alias("path"), "verdict").distinct()
    own = F.when(F.col("host") == "", F.lit("")).otherwise(host_key(ascii_lower(F.col("host"))))
    from_rules = from_rules.select(F.lit(0).cast("long").alias("part"), own.alias("key"), F.lit(0).alias("tag"), F.lit(None).cast("long").alias("page_id"), "host", "path", "verdict")
    from_pages = keyed.select("key", F.lit(1).alias("tag"), F.col("page_id").cast("long").alias("page_id"), "host", "path", F.lit(None).cast("string").alias("verdict"))
    both = from_pages.mapInArrow(ranged, columns).unionByName(from_rules.mapInArrow(places, columns))
    dealt = both.repartition(n, "part").sortWithinPartitions("part", "key", "tag")
    result = pa.schema([("page_id", pa.int64()), ("host", pa.string()), ("path", pa.string()), ("rule", pa.string()), ("verdict", pa.string())])

    def swept(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, sweep = None, Sweep()
        for b in batches:
            out = []
            for p, key, tag, page, host, path, verdict in zip(*[c.to_pylist() for c in b.columns], strict=True):
                if p != part:
                    part, sweep = p, Sweep()
                if tag == 0:
                    sweep.add(key, host, path, verdict)
                else:
                    rule, given = sweep.judge(key, path) or (None, default)
                    out.append((page, host, path, rule, given))
            cols = list(zip(*out, strict=True)) or [()] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(cols, result, strict=True)], schema=result)

    return dealt.mapInArrow(swept, "page_id long, host string, path string, rule string, verdict string")
