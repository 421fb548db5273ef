"""Quality rules as a bitmask ledger.

Every rule is evaluated once for a document; its failure becomes a bit, and what it measured is kept beside it. A policy is
a versioned mask: a document passes if none of the policy's bits is set, so policies can be changed or compared without
reading a text again. Ablations (what each rule alone costs) are bit counts over the ledger.

One pass over the texts in Arrow batches measures them; bits, verdicts and ablations are DataFrame expressions over the stored ledger.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from netjoin.llm.common import materialise, slices, text_or_empty

_WORDS = re.compile(r"[^\x20\x09-\x0D]+")
_LETTERS, _CAPITALS = regex.compile(r"\p{L}+"), regex.compile(r"\p{Lu}+")
_SYMBOLS = str.maketrans("", "", "#*$%&|<>")
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_upper", "n_letters")

#: Bit -> (name, SQL condition under which a document fails). Bits are never reused.
RULES: dict[int, tuple[str, str]] = {
    0: ("few_words", "n_words < 50"),
    1: ("repeated_words", "100 * n_repeat_words > 50 * n_words"),
    2: ("symbols", "100 * n_symbols > 20 * n_words"),
    3: ("repeated_lines", "n_lines >= 10 AND 100 * n_dup_lines > 50 * n_lines"),
    4: ("short_words", "word_chars < 2 * n_words"),
    5: ("long_words", "word_chars > 20 * n_words"),
    6: ("shouting", "100 * n_upper > 60 * n_letters"),
    7: ("no_letters", "n_letters < n_words"),
}
#: Version -> bits that reject. ``base`` has the contract's own two rules.
POLICIES: dict[str, int] = {"base": 0b11, "v1": 0b1111_1111, "lenient": 0b0000_0111}


def measure(text: str) -> tuple[int, ...]:
    """MEASURES of one text."""
    words = _WORDS.findall(text)
    n = len(words)
    repeat = 0
    if n >= 3:
        ids: dict[str, int] = {}
        w = np.fromiter((ids.setdefault(x, len(ids)) for x in words), np.int64, n)
        if len(ids) < n - 1:
            size = len(ids)
            pair = w[:-1] * size + w[1:]
            pair = np.unique(pair, return_inverse=True)[1] if size > 2_000_000 else pair
            window = pair[:-1] * size + w[2:]
            order = np.argsort(window, kind="stable")
            same = window[order[1:]] == window[order[:-1]]
            if same.any():
                twice = np.zeros(n, np.int8)
                start = np.zeros(n - 2, bool)
                start[order[1:][same]] = True
                start[order[:-1][same]] = True
                at = np.flatnonzero(start)
                twice[at] = twice[at + 1] = twice[at + 2] = 1
                repeat = int(twice.sum())
    lines = [x for x in text.split("\n") if _WORDS.search(x)] if "\n" in text else [text] * bool(n)
    letters = sum(map(len, _LETTERS.findall(text)))
    upper = sum(map(len, _CAPITALS.findall(text)))
    return n, sum(map(len, words)), len(text) - len(text.translate(_SYMBOLS)), len(lines) - len(set(lines)), repeat, len(lines), upper, letters


def measured(docs: DataFrame, text_col: str, *, carry: bool) -> DataFrame:
    """A struct ``row``, the measures, and ``bits``: one failure bit for each rule. One pass, no join. ``row`` holds all columns of ``docs``, or with ``carry`` off
    all but the text, which then does not come back from the workers."""
    held = [c for c in docs.columns if carry or c != text_col]
    text = [] if carry else [text_or_empty(f"`{text_col}`").alias("text")]
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in held)).alias("row"), *text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            row = batch.column(0)
            found = [measure(t or "") for t in (row.field(held.index(text_col)) if carry else batch.column(1)).to_pylist()]
            columns = list(zip(*found)) if found else [()] * len(MEASURES)
            yield pa.RecordBatch.from_arrays([row, *(pa.array(c, pa.int64()) for c in columns)], names=["row", *MEASURES])

    return rows.mapInArrow(run, f"row {rows.schema['row'].dataType.simpleString()}, " + ", ".join(f"{m} long" for m in MEASURES)).withColumn("bits", failure_bits(RULES))


def ledger(docs: DataFrame, *, path: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, the measures, and ``bits``: one failure bit for each rule, one row for every row, written to ``path`` (or the shared scratch folder) and read back.

    Null and empty texts have no words. Lines count as equal if identical, and only lines with a word count. Texts of any length are measured whole. Rows that repeat
    are measured each, a null id is passed on, and an empty table gives an empty ledger. Other columns of ``docs`` are not read.
    """
    book = measured(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")), "text", carry=False)
    return materialise(book.select("row.doc_id", *MEASURES, "bits"), "quality-ledger", path=path)


def failure_bits(rules: dict[int, tuple[str, str]]) -> Column:
    return F.expr(" | ".join(f"IF({condition}, {1 << bit}L, 0L)" for bit, (_, condition) in sorted(rules.items())))


def passes(policy: str | int) -> Column:
    mask = POLICIES[policy] if isinstance(policy, str) else policy
    return F.expr(f"(bits & {mask}L) = 0")


def verdicts(book: DataFrame, *, policy: str | int = "v1") -> DataFrame:
    """The ledger with base_failed and kept: false where a base rule fails, else the policy's verdict. No text is read."""
    base = passes("base")
    return book.withColumn("base_failed", ~base).withColumn("kept", base & passes(policy))


def ablation(book: DataFrame, policy: str | int = "v1") -> DataFrame:
    """rule, n_failed, n_only for each rule of the policy: documents that fail it, and documents that only this rule rejects. One aggregation over the bits;
    an empty ledger gives zeros."""
    mask = POLICIES[policy] if isinstance(policy, str) else policy
    used = [(b, n) for b, (n, _) in sorted(RULES.items()) if mask >> b & 1]
    sums = [F.expr(f"count_if(bit_get(bits, {b}) = 1)").alias(f"f{b}") for b, _ in used] + [F.expr(f"count_if((bits & {mask}L) = {1 << b}L)").alias(f"o{b}") for b, _ in used]
    rows = ", ".join(f"'{n}', f{b}, o{b}" for b, n in used)
    return book.agg(*sums).selectExpr(f"stack({len(used)}, {rows}) AS (rule, n_failed, n_only)")


def kept_documents(docs: DataFrame, *, policy: str | int = "v1", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that the policy keeps, with all their columns; the cases are those of ``ledger``."""
    return measured(docs, text_col, carry=True).where(passes("base") & passes(policy)).select("row.*")
