"""URL filters as a sort-merge range join.

A host is turned into a key of its labels from the right, each closed by a dot, so that a host and all its subdomains are one interval of keys. A sweep
over rules and urls in key order keeps a stack of the rules whose intervals hold the present key; the longest of them whose path fits decides.

Rules of up to LOCAL_RULES rows travel with the tasks, and urls are sorted where they lie: nothing is shuffled. Larger rule tables are dealt out with
the urls by ranges of keys; a key too common for one range has several, and rules go to every range that they reach.

Null url or one without "://": empty host and path, so no rule fits. Equal rules: block wins over allow. Repeated rows are judged alike; an empty table
of urls or of rules is fine; other columns do not matter.
"""

from __future__ import annotations

import bisect
from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

LOCAL_RULES = 100_000
#: Rows of urls of one part, when rules are dealt out; most ranges of keys (a range has several parts where there are more rows than that).
RANGE_ROWS, MAX_RANGES = 200_000, 4096

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_AFTER = chr(0x10FFFF)


def host_of(url: Column) -> Column:
    return F.coalesce(F.translate(F.regexp_extract(_rest(url), "^[^/?#]*", 0), _UPPER, _LOWER), F.lit(""))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(_rest(url), "^[^/?#]*([^?#]*)", 1), F.lit(""))


def _rest(url: Column) -> Column:
    return F.when(F.locate("://", url) > 0, F.substr(url, F.locate("://", url) + F.lit(3)))


def host_key(host: Column) -> Column:
    return F.when(host == "", F.lit("")).otherwise(F.concat(F.array_join(F.reverse(F.split(host, r"\.", -1)), "."), F.lit(".")))


class Sweep:
    """Rules in key order, taken up as keys go by."""

    def __init__(self, rules: list[tuple[str, str, str, str]]) -> None:
        self.rules, self.at, self.stack = sorted(rules), 0, []

    def judge(self, key: str, path: str) -> tuple[str | None, str | None]:
        """rule and verdict for the next key; keys come in ascending order."""
        while self.stack and not key.startswith(self.stack[-1][0]):
            self.stack.pop()
        while self.at < len(self.rules) and self.rules[self.at][0] <= key:
            rule, self.at = self.rules[self.at], self.at + 1
            if key.startswith(rule[0]):
                self.stack.append(rule)
        fits = [(len(host) + len(start), verdict == "block", host + start, verdict) for _, start, host, verdict in self.stack if path.startswith(start)]
        return max(fits)[2:] if fits else (None, None)

    def table(self, keys: list[str], paths: list[str]) -> list[pa.Array]:
        rule, verdict, last, known = [], [], None, {}
        for key, path in zip(keys, paths, strict=True):
            if key != last:
                last, known = key, {}
            if path not in known:
                known[path] = self.judge(key, path)
                if len(known) > 10_000:
                    known = {path: known[path]}
            r, v = known[path]
            rule.append(r)
            verdict.append(v)
        return [pa.array(rule, pa.string()), pa.array(verdict, pa.string())]


def match_rules(urls: DataFrame, rules: DataFrame, id_col: str = "page_id", url_col: str = "url", default: str = "allow", local_rules: int = LOCAL_RULES, range_rows: int = RANGE_ROWS) -> DataFrame:
    """id, host, path, rule (host and path of the longest rule that fits, or null), verdict (that rule's, else default). rules: host, path, verdict."""
    rows = urls.select(F.col(f"`{id_col}`").alias("id"), host_of(F.col(f"`{url_col}`")).alias("host"), path_of(F.col(f"`{url_col}`")).alias("path")).withColumn("key", host_key(F.col("host")))
    keyed = rules.select(host_key(F.col("host")).alias("key"), "path", "host", "verdict")
    few = [tuple(r) for r in keyed.limit(local_rules + 1).collect()]
    kind = dict(rows.dtypes)["id"]
    schema = f"id {kind}, host string, path string, rule string, verdict string"
    if len(few) <= local_rules:

        def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            sweep = Sweep(few)
            for b in batches:
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), *sweep.table(b.column(3).to_pylist(), b.column(2).to_pylist())], ["id", "host", "path", "rule", "verdict"])

        done = rows.sortWithinPartitions("key").mapInArrow(local, schema)
    else:
        done = _by_range(rows, keyed, schema, range_rows)
    return done.select(F.col("id").alias(id_col), "host", "path", "rule", F.coalesce("verdict", F.lit(default)).alias("verdict"))


def _by_range(rows: DataFrame, rules: DataFrame, schema: str, range_rows: int) -> DataFrame:
    wanted = max(1, -(-rows.count() // range_rows))
    n = min(wanted, MAX_RANGES)
    parts = -(-wanted // n)
    # Bounds only spread the load; a sample of some twenty keys for each range is enough, whatever it holds. It is bounded, as the ranges are.
    drawn = rows.select("key", F.xxhash64("key", "path", "id").alias("h")).orderBy("h").limit(20 * n).select("key").collect()
    keys = sorted(r.key for r in drawn)
    bounds = [keys[len(keys) * k // n] for k in range(1, n)] if keys else []

    @F.pandas_udf("int")
    def of_url(key: pd.Series, h: pd.Series) -> pd.Series:
        lo = [bisect.bisect_left(bounds, k) for k in key]
        hi = [bisect.bisect_right(bounds, k) for k in key]
        some = [int(x) % ((b - a + 1) * parts) for a, b, x in zip(lo, hi, h, strict=True)]
        return pd.Series([(a + x // parts) * parts + x % parts for a, x in zip(lo, some, strict=True)], dtype="int32")

    @F.pandas_udf("array<int>")
    def of_rule(key: pd.Series) -> pd.Series:
        return pd.Series([list(range(bisect.bisect_left(bounds, k) * parts, (bisect.bisect_right(bounds, k + _AFTER) + 1) * parts)) for k in key])

    dealt_urls = rows.withColumn("part", of_url("key", F.xxhash64("path", "id")))
    dealt_rules = rules.withColumn("part", F.explode(of_rule("key")))

    def sweep(left: pa.Table, right: pa.Table) -> pa.Table:
        left = left.sort_by("key")
        s = Sweep(list(zip(*(right.column(c).to_pylist() for c in ("key", "path", "host", "verdict")), strict=True)) if right.num_rows else [])
        # Arrow sorts strings by bytes, which is the order of code points
        found = s.table(left.column("key").to_pylist(), left.column("path").to_pylist())
        return pa.table([left.column("id"), left.column("host"), left.column("path"), *found], names=["id", "host", "path", "rule", "verdict"])

    return dealt_urls.groupBy("part").cogroup(dealt_rules.groupBy("part")).applyInArrow(sweep, schema)
