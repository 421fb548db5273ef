"""Language identification by compression.

Each language has a raw-content dictionary of zstandard: folded training text up to a byte bound. A text is folded the same way,
cut into pieces that a dictionary can matter for, and compressed with each dictionary; the smallest total names
the language. The margin to the second is the score, and narrow margins are marked as rejected.

The dictionaries are the model: fitted on a bounded sample of labelled rows, drawn over the whole table, and sent
to the workers as a value of at most ``dict_bytes`` for each language.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from netjoin.llm.common import slices

_OTHER = re.compile(r"[\W\d_]+")
#: Characters of a folded text that are compressed at once.
PIECE = 8192


def fold(text: str) -> str:
    """Lower-case letters, everything else one space."""
    return _OTHER.sub(" ", text.lower())


def held_out(id_column: Column) -> Column:
    """The documents that are never learned from: crc32 of the id as text leaves 2 modulo 4. A null id is never learned from either."""
    return F.coalesce(F.crc32(id_column.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def fit_dictionaries(labelled: DataFrame, *, dict_bytes: int = 60_000, per_language: int = 400, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> dict[str, bytes]:
    """Language -> folded sample text, the most frequent language first. Rows without a label, text or id are not learned from, rows that repeat
    are drawn together, an empty table gives no language, and other columns are not read.

    Rows are drawn by a hash of the id at a rate of one in ``n // per_language`` (all rows of a language that has fewer), in expectation fewer than twice
    ``per_language``. Of each an excerpt at a hashed place inside the whole text is learned, of an equal share for each row, ``dict_bytes`` in all, so neither long texts nor common openings fill a dictionary.
    """
    rows = labelled.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"), F.col(lang_col).alias("lang")).where("lang IS NOT NULL AND text IS NOT NULL AND doc_id IS NOT NULL")
    counts = {r["lang"]: r["n"] for r in rows.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}
    if not counts:
        return {}
    rate = F.create_map(*(x for lang, n in counts.items() for x in (F.lit(lang), F.lit(max(1, n // per_language)).cast("long"))))
    share = max(200, 2 * dict_bytes // per_language)
    picked = rows.where(F.pmod(F.xxhash64("doc_id"), F.element_at(rate, F.col("lang"))) == 0)
    place = 1 + F.pmod(F.xxhash64("doc_id", F.lit(2)), F.greatest(F.lit(1), F.length("text") - 4 * share + 1))
    sample = picked.select("lang", F.xxhash64("doc_id", F.lit(1)).alias("k"), F.substring(F.col("text"), place.cast("int"), F.lit(4 * share)).alias("text")).collect()
    out: dict[str, bytes] = {}
    for lang in sorted(counts, key=lambda x: (-counts[x], x)):
        own = sorted((r["k"], r["text"]) for r in sample if r["lang"] == lang)
        each = max(share, dict_bytes // max(1, len(own)))
        out[lang] = b" ".join(fold(t)[:each].encode() for _, t in own)[-dict_bytes:]
    return {lang: d for lang, d in out.items() if len(d) >= 8}


@lru_cache(maxsize=2)
def _compressors(model: tuple[tuple[str, bytes], ...], level: int):
    import zstandard

    made = []
    for lang, content in model:
        d = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        d.precompute_compress(level=level)
        made.append((lang, zstandard.ZstdCompressor(level=level, dict_data=d, write_content_size=False, write_checksum=False, write_dict_id=False)))
    return made


def identify_text(text: str | None, model: tuple[tuple[str, bytes], ...], level: int = 10) -> tuple[str, float]:
    """(language, score); ``und`` with score 0 if the text has no letter or nothing was learned."""
    folded = fold(text or "").strip()
    if not folded or not model:
        return "und", 0.0
    pieces = [folded[i : i + PIECE].encode("utf-8", "replace") for i in range(0, len(folded), PIECE)]
    sizes = sorted((sum(len(c.compress(p)) for p in pieces), order, lang) for order, (lang, c) in enumerate(_compressors(model, level)))
    best, second = sizes[0], sizes[1] if len(sizes) > 1 else sizes[0]
    return best[2], min(1.0, max(0.0, 4.0 * (second[0] - best[0]) / max(1, second[0]))) if len(sizes) > 1 else 1.0


def identify(docs: DataFrame, dictionaries: dict[str, bytes], *, margin: float = 0.04, level: int = 10, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out, lang_pred, score, rejected (margin too narrow to trust) for every row, in one pass without a shuffle.

    Texts that are null, empty or have no letter give ``und`` with score 0, rejected; so does every text where nothing was learned. Texts of any length are compressed whole, in pieces.
    Ties go to the language with more labelled rows. Rows that repeat are predicted each, a null id is passed on, an empty table gives no rows, and other columns are not read.
    """
    model = tuple(dictionaries.items())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            found = [identify_text(t, model, level) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([f[0] for f in found], pa.string()), pa.array([f[1] for f in found], pa.float64())], names=["doc_id", "lang_pred", "score"])

    kind = docs.schema[id_col].dataType.simpleString()
    made = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, f"doc_id {kind}, lang_pred string, score double")
    return made.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score", (F.col("score") < margin).alias("rejected"))


def identify_table(docs: DataFrame, **options) -> DataFrame:
    """Fit on the labelled rows that are not held out, then predict every row."""
    return identify(docs, fit_dictionaries(docs.where(~held_out(F.col("doc_id")))), **options)
