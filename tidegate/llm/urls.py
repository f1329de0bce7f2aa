"""URL rules by a sort-merge range join: canonical keys make prefixes intervals, a sorted sweep keeps a stack of nested rules.

A host's canonical key is its labels reversed, each followed by a dot (`a.b.org` is `org.b.a.`), so that a rule's host and
all its subdomains are the keys of one interval. URLs sorted by (host key, path) are merged with the sorted rule hosts; the
stack holds the rule hosts that are open at the sweep's place, innermost last, each with its sorted path prefixes.

Up to `chunk_rules` rules are sent to all, and every Arrow batch of URLs is a sweep of its own: no shuffle, and a hot host or URL makes no
task larger than its scan split. More rules never pass through the driver: rules and URLs are dealt together into ranges of
(host key, kind, path, salt), so that a hot host is parted too; each range is given the rules of the hosts above its first key,
which were opened in ranges before it, and swept as a stream.

Defined results: host is what stands after the first `://` up to / ? # or the end, A-Z lower-cased; path follows up to
? # or the end; null urls and urls without `://` have both empty and meet no rule with a host. Of the rules that fit, the
longest host and path together wins, then the longer host; equal rules: block before allow; rules with a null are left out. No
rule: `default`. Repeated rows are judged each; an empty table gives no rows; extra columns are left out, whatever their names.
"""

from __future__ import annotations

from bisect import bisect_right

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tidegate.llm.common import ASCII_UPPER, ascii_lower, stored


LOWER = str.maketrans(ASCII_UPPER, ASCII_UPPER.lower())


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Host and path columns of a url column; both empty where there is no `://`."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.lit(2**31 - 1))).otherwise(F.lit(""))
    host = F.regexp_extract(rest, r"^[^/?#]*", 0)
    path = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    return F.coalesce(ascii_lower(host), F.lit("")), F.coalesce(path, F.lit(""))


def host_key(host: str) -> str:
    return "".join(f"{label}." for label in reversed(host.split(".")))


def prepare(rules: list[tuple[str, str, str]]) -> list[tuple[str, int, list[str], list[str]]]:
    """Sorted (host key, host length, sorted paths, verdicts); of equal rules block stays."""
    by: dict[str, dict[str, str]] = {}
    for host, path, verdict in rules:
        paths = by.setdefault(host.translate(LOWER), {})
        if paths.get(path) != "block":
            paths[path] = verdict
    return sorted((host_key(h), len(h), sorted(p), [p[x] for x in sorted(p)]) for h, p in by.items())


def longest_prefix(paths: list[str], path: str) -> int:
    """Index of the longest of the sorted paths that `path` starts with, or -1."""
    end = len(path)
    while end >= 0:
        i = bisect_right(paths, path[:end]) - 1
        if i < 0:
            return -1
        if path.startswith(paths[i]):
            return i
        # nothing between: go back to what the neighbour and the path have in common
        common = 0
        for a, b in zip(paths[i], path[:end], strict=False):
            if a != b:
                break
            common += 1
        end = min(common, end - 1)
    return -1


class Sweep:
    """The rule hosts that are open at a place, each (key, host length, sorted paths, verdicts)."""

    def __init__(self):
        self.stack: list[tuple[str, int, list[str], list[str]]] = []

    def move(self, key: str) -> None:
        """Closes what does not hold this key."""
        while self.stack and not key.startswith(self.stack[-1][0]):
            self.stack.pop()

    def rule(self, key: str, path: str, verdict: str) -> None:
        """The next rule, by (key, path, allow before block)."""
        self.move(key)
        if not self.stack or self.stack[-1][0] != key:
            self.stack.append((key, len(key) - 1, [], []))
        _, _, paths, verdicts = self.stack[-1]
        if paths and paths[-1] == path:
            verdicts[-1] = verdict
        else:
            paths.append(path)
            verdicts.append(verdict)

    def judge(self, key: str, path: str) -> tuple[str | None, str | None]:
        """Rule (as text) and verdict of a url, null where none fits."""
        self.move(key)
        best, got = (-1, -1), (None, None)
        for open_key, length, prefixes, verdicts in self.stack:
            k = longest_prefix(prefixes, path)
            if k >= 0 and (length + len(prefixes[k]), length) > best:
                best = (length + len(prefixes[k]), length)
                got = (".".join(reversed(open_key[:-1].split("."))) + prefixes[k], verdicts[k])
        return got


def sweep(hosts: list[str], paths: list[str], table: list) -> tuple[list, list]:
    """Rule (as text) and verdict of each url, null where none fits."""
    keys = [host_key(h) for h in hosts]
    order = sorted(range(len(keys)), key=lambda i: (keys[i], paths[i]))
    rule, verdict = [None] * len(keys), [None] * len(keys)
    s, nxt, last, got = Sweep(), 0, None, (None, None)
    for i in order:
        here = (keys[i], paths[i])
        if here != last:
            last = here
            while nxt < len(table) and table[nxt][0] <= keys[i]:
                s.move(table[nxt][0])
                s.stack.append(table[nxt])
                nxt += 1
            got = s.judge(*here)
        rule[i], verdict[i] = got
    return rule, verdict


def apply_rules(urls: DataFrame, rules: DataFrame, url_col: str = "url", keep: tuple[str, ...] = ("page_id",), default: str = "allow", chunk_rules: int = 200_000) -> DataFrame:
    """`keep` columns, host, path, rule and verdict of each url. rules: DataFrame (host, path, verdict)."""
    host, path = host_and_path(F.col(url_col))
    said = urls.select(F.struct(*keep).alias("row"), host.alias("host"), path.alias("path"))
    named = rules.where(F.col("host").isNotNull() & F.col("path").isNotNull() & F.col("verdict").isNotNull()).select(ascii_lower(F.col("host")).alias("host"), "path", "verdict").distinct()
    judged = _sent(said, named) if named.limit(chunk_rules + 1).count() <= chunk_rules else _dealt(said, named)
    return judged.select("row.*", "host", "path", "rule", F.coalesce("verdict", F.lit(default)).alias("verdict"))


def _sent(said: DataFrame, named: DataFrame) -> DataFrame:
    """All rules, whose number is bounded, with every batch of URLs."""
    table = said.sparkSession.sparkContext.broadcast(prepare([tuple(r) for r in named.toLocalIterator()]))

    def run(batches):
        for batch in batches:
            rule, verdict = sweep(batch.column("host").to_pylist(), batch.column("path").to_pylist(), table.value)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(rule, pa.string()), pa.array(verdict, pa.string())], names=[*batch.schema.names, "rule", "verdict"])

    none = F.lit(None).cast("string")
    return said.mapInArrow(run, said.withColumns({"rule": none, "verdict": none}).schema)


def key_of(host: Column) -> Column:
    return F.concat(F.array_join(F.reverse(F.split(host, r"\.", -1)), "."), F.lit("."))


def _dealt(said: DataFrame, named: DataFrame) -> DataFrame:
    """Rules and URLs together in ranges of the canonical key."""
    none = F.lit(None).cast("string")
    row = said.schema["row"].dataType
    asked = said.select(key_of(F.col("host")).alias("key"), F.lit(1).alias("kind"), "path", none.alias("verdict"), "host", "row", F.xxhash64("row").alias("salt"))
    given = named.select(key_of(F.col("host")).alias("key"), F.lit(0).alias("kind"), "path", "verdict", "host", F.lit(None).cast(row).alias("row"), F.lit(0).cast("long").alias("salt"))
    parts = int(said.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranges = stored(given.unionByName(asked).repartitionByRange(parts, "key", "kind", "path", "salt").withColumn("part", F.spark_partition_id()), "url-ranges")
    # hosts above a range's first key, itself included, and their rules in ranges before it: a row a label of a key a range
    firsts = ranges.groupBy("part").agg(F.min(F.struct("key", "kind", "path", "salt")).alias("first")).select("part", F.col("first.key").alias("first"))
    labels = F.split("first", r"\.", -1)
    above = F.transform(F.sequence(F.lit(1), F.size(labels) - 1), lambda n: F.concat(F.array_join(F.slice(labels, 1, n), "."), F.lit(".")))
    opened = firsts.select("part", F.explode(above).alias("key")).join(ranges.where("kind = 0").withColumnRenamed("part", "home"), "key").where("home < part")
    whole = ranges.unionByName(opened.drop("home")).repartition("part").sortWithinPartitions("part", "key", "kind", "path", "verdict")

    def run(batches):
        s, part, last, got = Sweep(), None, None, (None, None)
        for batch in batches:
            at, rule, verdict = [], [], []
            columns = (batch.column(n).to_pylist() for n in ("part", "key", "kind", "path", "verdict"))
            for i, (here, key, kind, path, said_) in enumerate(zip(*columns, strict=True)):
                if here != part:
                    s, part, last = Sweep(), here, None
                if not kind:
                    s.rule(key, path, said_)
                    continue
                if (key, path) != last:
                    last, got = (key, path), s.judge(key, path)
                at.append(i)
                rule.append(got[0])
                verdict.append(got[1])
            picked = pa.array(at, pa.int64())
            yield pa.RecordBatch.from_arrays([*(batch.column(n).take(picked) for n in ("row", "host", "path")), pa.array(rule, pa.string()), pa.array(verdict, pa.string())], names=["row", "host", "path", "rule", "verdict"])

    return whole.mapInArrow(run, said.withColumns({"rule": none, "verdict": none}).schema)
