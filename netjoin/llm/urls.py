"""URL filtering by host-suffix and path-prefix expressions.

Every URL expands into the expressions a rule could be written as: each suffix of its host at a label boundary with each prefix of
its path whose length some rule has. Expressions meet the rules in an equi-join on a short hash
prefix; the full digest confirms a hit, and the longest rule wins. Only DataFrame expressions run.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from netjoin.llm.common import BROADCAST_ROWS, join_small, materialise

# The rules of the contract, (verdict, host, path).
RULES = (
    ("allow", "com", "/"),
    ("block", "example.com", "/en/"),
    ("allow", "www.example.com", "/en/"),
    ("block", "net", "/es/"),
    ("block", "net", "/fr/"),
)
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Hex digits of the digest that the equi-join uses.
PREFIX_HEX = 8


def host_of(url: Column) -> Column:
    """What follows the first ``://`` up to ``/``, ``?``, ``#`` or the end, A-Z lower-cased; else empty."""
    at = F.locate("://", url)
    rest = F.substring(url, at + 3, F.length(url))
    return F.when(url.isNull() | (at == 0), F.lit("")).otherwise(F.translate(F.regexp_extract(rest, r"(?s)^[^/?#]*", 0), _UPPER, _LOWER))


def path_of(url: Column) -> Column:
    """What follows the host up to ``?``, ``#`` or the end."""
    at = F.locate("://", url)
    rest = F.substring(url, at + 3, F.length(url))
    return F.when(url.isNull() | (at == 0), F.lit("")).otherwise(F.regexp_extract(rest, r"(?s)^[^/?#]*([^?#]*)", 1))


def rule_table(spark: SparkSession, rules: Sequence[tuple[str, str, str]]) -> DataFrame:
    """verdict, host, path, expression, digest, short: an in-line table of SQL literals."""
    quote = lambda s: "'" + s.replace("\\", "\\\\").replace("'", "\\'") + "'"
    rows = ", ".join(f"({', '.join(map(quote, r))})" for r in rules) or "('', '', '')"
    made = spark.sql(f"SELECT * FROM VALUES {rows} AS r(verdict, host, path)")
    return _digested(made if rules else made.limit(0))


def _digested(rules: DataFrame) -> DataFrame:
    full = rules.withColumn("expression", F.concat("host", "path")).withColumn("digest", F.sha2("expression", 256))
    return full.withColumn("short", F.substring("digest", 1, PREFIX_HEX))


def judge_urls(pages: DataFrame, rules: DataFrame, *, default: str = "allow", id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """page_id, host, path, rule, verdict for every row.

    Null urls and urls without ``://`` have an empty host and path, no rule, and the default verdict. A rule's empty path fits every path,
    its empty host no page. Of the rules that fit, the longest expression wins, then the longer host, then ``allow``.
    Rows that repeat are judged each, by content alone, whatever their order; urls may have any length, and other columns of ``pages`` are not read. An empty table gives no rows. ``rules`` comes from ``rule_table`` or has its columns;
    up to BROADCAST_ROWS rules are broadcast, more are shuffled.
    """
    n, lengths, deepest = rules.agg(F.count(F.lit(1)), F.array_sort(F.collect_set(F.length("path"))), F.max(F.size(F.split("host", r"\.", -1)))).first()
    named = pages.select(F.col(id_col).alias("page_id"), F.col(url_col).cast("string").alias("url"))
    parsed = named.select("page_id", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))
    if not n:
        return parsed.select("page_id", "host", "path", F.lit(None).cast("string").alias("rule"), F.lit(default).alias("verdict"))
    # no rule sees more of a path than its own, or more labels of a host: hosts and path fronts are judged once each
    front = F.substring("path", 1, max(lengths))
    seen = parsed.where("host <> ''").select("host", front.alias("front")).distinct()
    labels = F.split("host", r"\.", -1)
    suffixes = F.transform(F.sequence(F.greatest(F.lit(1), F.size("labels") - deepest + 1), F.size("labels")), lambda i: F.array_join(F.slice("labels", i, F.size("labels")), "."))
    prefixes = F.transform(F.filter(F.array(*map(F.lit, lengths)), lambda k: k <= F.length("front")), lambda k: F.substring(F.col("front"), F.lit(1), k))
    wide = seen.withColumn("labels", labels).withColumn("suffixes", suffixes)
    pairs = F.flatten(F.transform("suffixes", lambda s: F.transform(prefixes, lambda p: F.struct(s.alias("host"), p.alias("path")))))
    tried = wide.select("host", "front", F.explode(pairs).alias("e")).select("host", "front", F.col("e.host").alias("host_part"), F.col("e.path").alias("path_part"))
    tried = tried.withColumn("full", F.sha2(F.concat("host_part", "path_part"), 256)).withColumn("short", F.substring("full", 1, PREFIX_HEX))
    small = rules.select("short", "digest", "expression", "verdict", F.col("host").alias("rule_host"), F.col("path").alias("rule_path"))
    hits = tried.join(F.broadcast(small) if n <= BROADCAST_ROWS else small, "short").where("full = digest AND host_part = rule_host AND path_part = rule_path")
    best = hits.groupBy("host", "front").agg(F.max(F.struct(F.length("expression").alias("n"), F.length("rule_host").alias("h"), (F.col("verdict") == "allow").alias("mild"), "expression", "verdict")).alias("best"))
    judged = materialise(best.select("host", "front", F.col("best.expression").alias("rule"), F.col("best.verdict").alias("verdict")), "url-verdicts")
    all_rows = join_small(parsed.withColumn("front", front), judged, ["host", "front"], "left")
    return all_rows.select("page_id", "host", "path", "rule", F.coalesce("verdict", F.lit(default)).alias("verdict"))
