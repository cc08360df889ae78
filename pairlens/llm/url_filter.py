"""URL rules: host-suffix and path-prefix expressions, joined by short hash prefixes, confirmed by full digests."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Most rules that are broadcast; more are joined by a shuffle.
BROADCAST_RULES = 100_000
#: Hex digits of a digest that the join compares before the whole is confirmed.
PREFIX_DIGITS = 8
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


@dataclass(frozen=True)
class Rule:
    """verdict is allow or block; path is empty or starts with a slash."""

    verdict: str
    host: str
    path: str = ""

    @property
    def text(self) -> str:
        return self.host + self.path


def url_host(url: Column) -> Column:
    """What stands after the first :// up to / ? # or the end, A-Z lower-cased; empty for null or without ://."""
    rest = F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1)
    return F.coalesce(F.translate(rest, UPPER, LOWER), F.lit(""))


def url_path(url: Column) -> Column:
    """What follows the host up to ? # or the end."""
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def suffixes(host: Column) -> Column:
    """The host and each domain above it, longest first."""
    parts = F.split(host, r"\.", -1)
    return F.transform(F.sequence(F.lit(1), F.size(parts)), lambda i: F.concat_ws(".", F.slice(parts, i, F.size(parts))))


def judge(pages: DataFrame, rules: list[Rule], default: str = "allow", url: str = "url", key: str = "page_id") -> DataFrame:
    """key, host, path, rule, verdict for every row; rule is null where none fits and the verdict is then the default.

    A rule fits its host and the hosts below it if the url's path starts with the rule's. The longest rule wins, of
    equally long ones the one that blocks. A null url has an empty host and path. Repeated keys are judged row by row.
    """
    spark = pages.sparkSession
    plain = pages.select(F.col(key).alias("key"), url_host(F.col(url)).alias("host"), url_path(F.col(url)).alias("path"))
    lengths = sorted({len(r.path) for r in rules})
    if not rules:
        none = F.lit(None).cast("string")
        return plain.select(F.col("key").alias(key), "host", "path", none.alias("rule"), F.lit(default).alias("verdict"))
    table = spark.createDataFrame([(r.text, r.verdict) for r in dict.fromkeys(rules)], "rule string, rule_verdict string")
    # a rule that is both allowed and blocked blocks
    table = table.groupBy("rule").agg(F.max("rule_verdict").alias("rule_verdict")).withColumn("digest", F.sha2("rule", 256))
    table = table.select(F.left("digest", F.lit(PREFIX_DIGITS)).alias("short"), F.col("digest").alias("rule_digest"), "rule", "rule_verdict")
    # few hosts and paths repeat a lot: each distinct pair is judged once, as far as a task sees it
    pairs = plain.select("host", "path").distinct()
    heads = F.transform(F.filter(F.array(*map(F.lit, lengths)), lambda n: n <= F.length("path")), lambda n: F.substring(F.col("path"), F.lit(1), n))
    asked = pairs.select("host", "path", F.explode(suffixes(F.col("host"))).alias("suffix"), heads.alias("heads"))
    asked = asked.select("host", "path", F.explode("heads").alias("head"), "suffix").withColumn("digest", F.sha2(F.concat("suffix", "head"), 256))
    asked = asked.withColumn("short", F.left("digest", F.lit(PREFIX_DIGITS)))
    side = F.broadcast(table) if len(rules) <= BROADCAST_RULES else table
    hits = asked.join(side, "short").where((F.col("digest") == F.col("rule_digest")) & (F.concat("suffix", "head") == F.col("rule")))
    best = hits.groupBy("host", "path").agg(F.max(F.struct(F.length("rule").alias("n"), "rule_verdict", "rule")).alias("best"))
    out = plain.join(best, ["host", "path"], "left")
    return out.select(F.col("key").alias(key), "host", "path", F.col("best.rule").alias("rule"), F.coalesce("best.rule_verdict", F.lit(default)).alias("verdict"))
