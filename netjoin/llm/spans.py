"""Regex matches with positions as SQL expressions, and labelled examples as in-line tables."""

from __future__ import annotations

import json
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Code points of context kept on either side of a match.
CONTEXT = 32
#: Matches whose positions are summed in one fold; a text with more has several, so the work stays near linear.
BLOCK = 256


def quoted(pattern: str) -> str:
    """A SQL string literal."""
    return "'" + pattern.replace("\\", "\\\\").replace("'", "\\'") + "'"


def matches(text: str, pattern: str) -> Column:
    """array<struct<start, end, value, left, right>> of the leftmost non-overlapping matches; code points, end exclusive.

    The text between matches comes from a split by the same pattern, so positions are running sums of lengths.
    ``left`` and ``right`` are the context up to the neighbouring match. The pattern must not match the empty string.
    """
    p = quoted(pattern)
    found, gaps = f"regexp_extract_all({text}, {p}, 0)", f"split({text}, {p}, -1)"
    step = (f"(s, x) -> named_struct('at', s.at + length(x.g) + length(x.m), 'out', array_append(s.out, named_struct("
            f"'start', s.at + length(x.g), 'end', s.at + length(x.g) + length(x.m), 'value', x.m, 'left', right(x.g, {CONTEXT}), 'right', left(x.n, {CONTEXT}))))")
    empty = "named_struct('at', 0, 'out', cast(array() AS array<struct<start:int,end:int,value:string,left:string,right:string>>))"
    zipped = "zip_with(zip_with(w.m, slice(w.g, 1, size(w.m)), (m, g) -> named_struct('m', m, 'g', g)), slice(w.g, 2, size(w.m)), (a, n) -> named_struct('m', a.m, 'g', a.g, 'n', n))"
    blocks = f"transform(array({zipped}), z -> transform(sequence(0, (size(z) - 1) div {BLOCK}), i -> aggregate(slice(z, i * {BLOCK} + 1, {BLOCK}), {empty}, {step})))[0]"
    shifted = ("flatten(zip_with(b, sequence(0, size(b) - 1), (k, i) -> transform(array(aggregate(slice(b, 1, i), 0, (s, e) -> s + e.at)), o -> "
               "transform(k.out, c -> named_struct('start', c.start + o, 'end', c.end + o, 'value', c.value, 'left', c.left, 'right', c.right)))[0]))")
    one = f"transform(array(named_struct('m', {found}, 'g', {gaps})), w -> transform(array({blocks}), b -> {shifted})[0])[0]"
    none = "cast(array() AS array<struct<start:int,end:int,value:string,left:string,right:string>>)"
    return F.expr(f"CASE WHEN {text} RLIKE {p} THEN {one} ELSE {none} END")


def sampled_rows(rows: DataFrame, n: int) -> DataFrame:
    """At most 2 n rows, by a hash of all columns at a rate of one in count // n: what models are fitted on."""
    every = max(1, rows.count() // n)
    return rows.where(F.pmod(F.xxhash64(*rows.columns), F.lit(every)) == 0).limit(2 * n)


def contexts_of(rows: DataFrame, n: int, *, by_hash: bool = False) -> list[tuple[str, str]]:
    """(left, right) around some word boundary of up to ``n`` of the texts: real prose to put generated examples into. ``by_hash`` draws the first by their hash, the same for the same rows."""
    at = F.floor(F.pmod(F.xxhash64("text", F.lit(3)), F.length("text") + 1)).cast("int")
    cut = rows.where("length(text) > 0").withColumn("at", at).select(F.expr(f"substring(text, greatest(1, at - {CONTEXT} + 1), least(at, {CONTEXT}))").alias("l"), F.expr(f"substring(text, at + 1, {CONTEXT})").alias("r"))
    cut = cut.orderBy(F.xxhash64("l", "r"), "l", "r") if by_hash else cut
    got = sorted((r["l"], r["r"]) for r in cut.limit(n).collect())
    return [(left.rpartition(" ")[0] + " ", " " + right.partition(" ")[2]) for left, right in got] or [("the text before ", " and after it")]


def inline_rows(spark: SparkSession, rows: Sequence[dict], schema: str) -> DataFrame:
    """A small table from one JSON literal: plain SQL, no Python data on the executors."""
    return spark.range(1).select(F.explode(F.from_json(F.lit(json.dumps(list(rows))), f"array<struct<{schema}>>")).alias("r")).select("r.*")
