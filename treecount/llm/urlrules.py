"""URL rules by a sort-merge range join: reversed hosts, a sorted sweep, a stack of the rules in force."""

from __future__ import annotations

from bisect import bisect_right

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import LOWER, UPPER, commit, lower_az, ready

#: verdict and rule; a rule is a host, then a path from its first slash.
RULES = [("allow", "org/"), ("block", "example.org/es/"), ("block", "example.org/en/1"), ("allow", "com/fr/"), ("block", "com/de/")]
#: The verdict where no rule fits.
OTHERWISE = "allow"


def parts(url: Column) -> tuple[Column, Column]:
    """Host and path: the host follows the first ``://`` and ends at ``/``, ``?``, ``#``; both are empty without ``://``."""
    before = F.instr(url, "://")
    after = F.when(before > 0, F.substring(url, before + 3, F.length(url))).otherwise(F.lit(""))
    host = F.regexp_extract(after, "^[^/?#]*", 0)
    path = F.regexp_extract(F.substring(after, F.length(host) + 1, F.length(after)), "^[^?#]*", 0)
    return lower_az(host), path


def host_key(host: Column) -> Column:
    """Labels in reverse, each with a dot after it: a host and its subdomains are then one interval of keys. Empty for an empty host."""
    return F.when(host == "", F.lit("")).otherwise(F.concat(F.array_join(F.reverse(F.split(host, "\\.", -1)), "."), F.lit(".")))


def split_rule(rule: str) -> tuple[str, str]:
    """Host, A-Z lower-cased, and path."""
    host, slash, path = rule.partition("/")
    return host.translate(str.maketrans(UPPER, LOWER)), slash + path


class Frame:
    """The rules of one host. Their paths are intervals too: each knows the longest other path that it begins with."""

    def __init__(self, key: str):
        self.key, self.rules = key, {}
        self.paths: list[str] | None = None

    def add(self, path: str, rule: str, verdict: str) -> None:
        """Of rules for the same host and path a block wins, then the first."""
        own = self.rules.get(path)
        if own is None or own[1] != "block" and verdict == "block":
            self.rules[path] = (rule, verdict)
            self.paths = None

    def fit(self, path: str) -> tuple[str, str] | None:
        """The rule whose path is the longest that ``path`` starts with."""
        if self.paths is None:
            self.paths, self.outer, open_ = sorted(self.rules), [], []
            for k, p in enumerate(self.paths):
                while open_ and not p.startswith(self.paths[open_[-1]]):
                    open_.pop()
                self.outer.append(open_[-1] if open_ else -1)
                open_.append(k)
        at = bisect_right(self.paths, path) - 1
        while at >= 0 and not path.startswith(self.paths[at]):
            at = self.outer[at]
        return self.rules[self.paths[at]] if at >= 0 else None


class Sweep:
    """Meets rules and urls in ascending order of host keys, a host's rules first; the stack holds the hosts whose interval the
    current key is in."""

    def __init__(self):
        self.stack: list[Frame] = []

    def move(self, key: str) -> None:
        while self.stack and not key.startswith(self.stack[-1].key):
            self.stack.pop()

    def rule(self, key: str, path: str, rule: str, verdict: str) -> None:
        self.move(key)
        if not self.stack or self.stack[-1].key != key:
            self.stack.append(Frame(key))
        self.stack[-1].add(path, rule, verdict)

    def judge(self, key: str, path: str) -> tuple[str | None, str | None]:
        """The longest rule (host and path) that fits; of equally long ones that of the longer host."""
        self.move(key)
        best = (None, None)
        for frame in reversed(self.stack):
            found = frame.fit(path)
            if found and (best[0] is None or len(found[0]) > len(best[0])):
                best = found
        return best


OUT = "page_id long, host string, path string, rule string, verdict string"


def judge_urls(pages: DataFrame, rules: list[tuple[str, str]] | DataFrame = RULES, otherwise: str = OTHERWISE) -> DataFrame:
    """page_id, host, path, rule and verdict of each row. Repeated rows are judged each; a null url has empty parts and no
    rule; an empty table gives no rows; other columns are not looked at.

    rules: (verdict, rule) pairs, or a DataFrame of those columns of any size; null rules, and rules without a host, fit nothing.
    Rules and urls are dealt to ranges together, by host key and then path, so a host with a large share of all urls is cut
    too. A range begins with the rules still open there: those of the hosts that its first key lies under.
    """
    spark = pages.sparkSession
    host, path = parts(F.col("url"))
    urls = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url")).select("page_id", host.alias("host"), path.alias("path"))
    given = rules if isinstance(rules, DataFrame) else spark.createDataFrame(rules, "verdict string, rule string")
    given = given.where("rule is not null").select("verdict", "rule", lower_az(F.substring_index("rule", "/", 1)).alias("host")).where("host <> ''")
    both = urls.select(host_key(F.col("host")).alias("key"), F.lit(1).alias("kind"), "path", "page_id", "host", F.lit(None).cast("string").alias("rule"), F.lit(None).cast("string").alias("verdict"))
    both = both.union(given.select(host_key(F.col("host")), F.lit(0), F.expr("substring(rule, length(host) + 1)"), F.lit(None).cast("long"), "host", "rule", "verdict"))
    placed = commit(both.repartitionByRange("key", "kind", "path", "page_id").withColumn("part", F.spark_partition_id()), "urls")
    firsts = placed.groupBy("part").agg(F.min("key").alias("first"))
    labels = F.split("first", "\\.", -1)
    above = F.when(F.col("first") != "", F.transform(F.sequence(F.lit(1), F.greatest(F.size(labels) - 1, F.lit(1))), lambda i: F.concat(F.array_join(F.slice(labels, 1, i), "."), F.lit("."))))
    opened = firsts.select(F.col("part").alias("into"), F.explode(above).alias("key")).join(placed.where("kind = 0"), "key").select("key", F.lit(-1).alias("kind"), "path", "page_id", "host", "rule", "verdict", F.col("into").alias("part"))
    ranges = (firsts.agg(F.max("part")).first()[0] or 0) + 1

    def sweep(batches):
        part, s = None, Sweep()
        for batch in batches:
            keep, found, verdicts = [], [], []
            for row, (key, kind, p, rule, verdict, at) in enumerate(zip(*(batch.column(c).to_pylist() for c in (0, 1, 2, 5, 6, 7)), strict=True)):
                if at != part:
                    part, s = at, Sweep()
                if kind < 1:
                    s.rule(key, p, rule, verdict)
                    continue
                rule, verdict = s.judge(key, p)
                keep.append(row)
                found.append(rule)
                verdicts.append(verdict or otherwise)
            some = batch.take(pa.array(keep, pa.int64()))
            yield pa.RecordBatch.from_arrays([some.column(3), some.column(4), some.column(2), pa.array(found, pa.string()), pa.array(verdicts, pa.string())], names=["page_id", "host", "path", "rule", "verdict"])

    return placed.union(opened).repartitionById(ranges, F.col("part")).sortWithinPartitions("part", F.col("kind") >= 0, "key", "kind", "path", "rule").mapInArrow(sweep, OUT)


def op3(spark: SparkSession, pages: DataFrame) -> DataFrame:
    """Every url of ``pages`` (page_id, url) by the fixed rules; see :func:`judge_urls`."""
    ready(spark)
    return judge_urls(pages)


def oracle() -> str:
    values = ", ".join(f"('{v}', '{r}', '{split_rule(r)[0]}', '{split_rule(r)[1]}')" for v, r in RULES)
    return f"""
with rules(verdict, rule, rule_host, rule_path) as (values {values}),
cut as (select page_id, case when strpos(url, '://') > 0 then substr(url, strpos(url, '://') + 3) else '' end as rest from pages),
parted as (select page_id, regexp_extract(rest, '^[^/?#]*') as raw_host, rest from cut),
urls as (select page_id, translate(raw_host, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host,
                regexp_extract(substr(rest, length(raw_host) + 1), '^[^?#]*') as path from parted),
fits as (select u.page_id, u.host, u.path, r.rule, r.verdict,
                row_number() over (partition by u.page_id order by length(r.rule) desc nulls last, length(r.rule_host) desc) as place
         from urls u left join rules r on (u.host = r.rule_host or ends_with(u.host, '.' || r.rule_host)) and starts_with(u.path, r.rule_path))
select page_id, host, path, rule, coalesce(verdict, '{OTHERWISE}') as verdict from fits where place = 1"""
