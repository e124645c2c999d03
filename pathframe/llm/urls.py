"""URL filters: host-suffix and path-prefix expressions, joined to a rule list on short hash prefixes."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ascii_lower

#: (action, host, path): the contract's list.
RULES = (
    ("allow", "com", "/"),
    ("block", "example.com", "/en/"),
    ("allow", "www.example.com", "/en/"),
    ("block", "net", "/es/"),
    ("block", "net", "/fr/"),
)
#: Rules that may be broadcast; a longer list is joined by a shuffle on the hash prefix.
BROADCAST_RULES = 200_000
#: Expressions of a url (host suffixes by path prefixes) that are looked up one after another in its own row; with more
#: kinds of them, or a longer list, they are exploded and put together again by row.
IN_ROW = 24
#: Hex digits of the digest that the equi-join compares before the full digest does.
PREFIX_DIGITS = 8


def host_of(url: Column) -> Column:
    return ascii_lower(F.regexp_extract(_rest(url), "^([^/?#]*)", 1))


def path_of(url: Column) -> Column:
    return F.regexp_extract(_rest(url), "^[^/?#]*([^?#]*)", 1)


def _rest(url: Column) -> Column:
    at = F.locate("://", url)
    return F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise("")


def rule_frame(spark: SparkSession, rules: Sequence[tuple[str, str, str]]) -> DataFrame:
    """Rules with the digest of host + path; of equal host and path, block goes before allow."""
    best: dict[str, str] = {}
    for action, host, path in rules:
        best[host + path] = max(action, best.get(host + path, ""))
    rows = spark.createDataFrame(sorted(best.items()), "rule string, action string")
    digest = F.sha2("rule", 256)
    return rows.select("rule", "action", F.length("rule").alias("rank"), digest.alias("rule_digest"), F.substring(digest, 1, PREFIX_DIGITS).alias("prefix"))


def expressions(host: Column, path: Column, most_labels: int, path_lengths: Sequence[int]) -> Column:
    """Every host suffix of at most most_labels labels with every path prefix of a length that a rule has."""
    labels = F.split(host, "\\.")
    hosts = F.transform(F.sequence(F.lit(1), F.least(F.size(labels), F.lit(most_labels))), lambda n: F.array_join(F.slice(labels, -n, n), "."))
    prefixes = F.filter(F.transform(F.array(*[F.lit(n) for n in path_lengths]), lambda n: F.when(F.length(path) >= n, F.substring(path, F.lit(1), n))), lambda p: p.isNotNull())
    return F.flatten(F.transform(hosts, lambda h: F.transform(prefixes, lambda p: F.concat(h, p))))


def judge_urls(pages: DataFrame, rules: Sequence[tuple[str, str, str]] = RULES, default: str = "allow") -> DataFrame:
    """page_id, host, path, rule, verdict for each row of pages.

    Rows repeated stay repeated. A null url, or one without ://, has an empty host and path, no rule and the default
    verdict; so has any url while rules is empty. A null page_id is kept. Other columns of pages are ignored.
    """
    spark = pages.sparkSession
    own = pages.select("page_id", F.coalesce(host_of(F.col("url")), F.lit("")).alias("host"), F.coalesce(path_of(F.col("url")), F.lit("")).alias("path"))
    if not rules:
        return own.select("page_id", "host", "path", F.lit(None).cast("string").alias("rule"), F.lit(default).alias("verdict"))
    lengths = sorted({len(p) for _, _, p in rules})
    most = max(h.count(".") + 1 for _, h, _ in rules)
    listed = rule_frame(spark, rules)
    if len(rules) <= BROADCAST_RULES and most * len(lengths) <= IN_ROW:
        return _judged(_looked_up(own, listed, most, lengths), default)
    if len(rules) <= BROADCAST_RULES:
        listed = F.broadcast(listed)
    rows = own.withColumn("row", F.monotonically_increasing_id())
    grown = rows.withColumn("expression", F.explode_outer(expressions(F.col("host"), F.col("path"), most, lengths)))
    grown = grown.withColumn("digest", F.sha2("expression", 256))
    met = grown.join(listed, (F.substring("digest", 1, PREFIX_DIGITS) == F.col("prefix")) & (F.col("digest") == F.col("rule_digest")), "left")
    best = met.groupBy("row", "page_id", "host", "path").agg(F.max(F.when(F.col("rule").isNotNull(), F.struct("rank", "action", "rule"))).alias("best"))
    return _judged(best, default)


def _looked_up(own: DataFrame, listed: DataFrame, most: int, lengths: Sequence[int]) -> DataFrame:
    """own with the best rule: an equi-join with the broadcast list for each kind of expression, on the digest's prefix
    and then the whole digest, which is unique in the list, so that a url stays one row and nothing is shuffled."""
    best, names = own, []
    for labels in range(1, most + 1):
        for length in lengths:
            k, name = len(names), f"met_{len(names)}"
            suffix = F.when(F.size(F.split("host", "\\.")) >= labels, F.substring_index("host", ".", -labels))
            expression = F.concat(suffix, F.when(F.length("path") >= length, F.substring("path", 1, length)))
            rules = F.broadcast(listed.select(F.col("prefix").alias(f"prefix_{k}"), F.col("rule_digest").alias(f"digest_{k}"), F.struct("rank", "action", "rule").alias(name)))
            digest = F.sha2(expression, 256)
            best = best.join(rules, (F.substring(digest, 1, PREFIX_DIGITS) == F.col(f"prefix_{k}")) & (digest == F.col(f"digest_{k}")), "left")
            names.append(name)
    return best.select("page_id", "host", "path", (F.greatest(*names) if len(names) > 1 else F.col(names[0])).alias("best"))


def _judged(best: DataFrame, default: str) -> DataFrame:
    return best.select("page_id", "host", "path", F.col("best.rule").alias("rule"), F.coalesce("best.action", F.lit(default)).alias("verdict"))


SQL = """
WITH parts AS (
  SELECT page_id, CASE WHEN contains(url, '://') THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
split AS (
  SELECT page_id, translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM parts)
SELECT page_id, host, path,
  CASE WHEN (host = 'www.example.com' OR ends_with(host, '.www.example.com')) AND starts_with(path, '/en/') THEN 'www.example.com/en/'
       WHEN (host = 'example.com' OR ends_with(host, '.example.com')) AND starts_with(path, '/en/') THEN 'example.com/en/'
       WHEN (host = 'net' OR ends_with(host, '.net')) AND starts_with(path, '/es/') THEN 'net/es/'
       WHEN (host = 'net' OR ends_with(host, '.net')) AND starts_with(path, '/fr/') THEN 'net/fr/'
       WHEN (host = 'com' OR ends_with(host, '.com')) AND starts_with(path, '/') THEN 'com/' END AS rule,
  CASE WHEN (host = 'www.example.com' OR ends_with(host, '.www.example.com')) AND starts_with(path, '/en/') THEN 'allow'
       WHEN (host = 'example.com' OR ends_with(host, '.example.com')) AND starts_with(path, '/en/') THEN 'block'
       WHEN (host = 'net' OR ends_with(host, '.net')) AND (starts_with(path, '/es/') OR starts_with(path, '/fr/')) THEN 'block'
       ELSE 'allow' END AS verdict
FROM split
"""
