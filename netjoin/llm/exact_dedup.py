"""Exact deduplication by a log-structured merge index of text digests.

Each task is a memtable: it flushes its digests as one sorted Parquet run. Compaction merges the runs of a level into
two: digests of one row, and digests that several rows share, with the row that stays and the group's size. Every merged run has a
Bloom filter, an array of at most FILTER_BITS bits built by bit_or over hashed words. A lookup asks the filter first; what it
rules out is never shuffled. In the query most texts are alone in their group, so only the few that
the filter of shared digests lets through look their group up.

Rows that hit a digest of another row are verified byte by byte: the normalised bytes of all
hits of a digest meet in one min/max aggregation (combined before the shuffle, so
a group of any size sends at most two texts from each task); digests whose bytes differ are
regrouped by the bytes themselves.

Everything runs as DataFrame expressions. Only digests and ids are shuffled, and the texts of hits.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from netjoin.llm.common import BROADCAST_ROWS, SPACE, join_small, materialise, scratch_path, text_or_empty

#: Rank of a row in its group: most code points first, then the smallest id (a null id last).
RANK = "struct(-n_chars AS a, isnull(doc_id) AS b, doc_id AS c)"


def normalised(text: Column) -> Column:
    """The text without the white space that equality ignores."""
    return F.translate(text, SPACE, "")


#: Most bits of a filter: 8 MB. Beyond some 6 million digests a filter lets more through and stays right.
FILTER_BITS = 1 << 26
#: Bits set for each digest.
PROBES = 3


def _spots(digest: Column, bits: int) -> list[Column]:
    return [F.xxhash64(digest, F.lit(i)).bitwiseAND(F.lit(bits - 1)) for i in range(PROBES)]


def build_filter(digests: DataFrame) -> tuple[DataFrame, int]:
    """(one row with the array ``words`` of 64 bits each, number of bits): a Bloom filter of the column ``digest``, some 12 bits a digest."""
    n = digests.count()
    bits = min(FILTER_BITS, 1 << max(6, (12 * n).bit_length()))
    spots = digests.select(F.explode(F.array(*_spots(F.col("digest"), bits))).alias("spot"))
    filled = spots.groupBy(F.shiftright("spot", 6).alias("i")).agg(F.bit_or(F.expr("shiftleft(1L, int(spot & 63))")).alias("word"))
    every = digests.sparkSession.range(bits // 64).select(F.col("id").alias("i")).join(filled, "i", "left")
    words = every.agg(F.array_sort(F.collect_list(F.struct("i", F.coalesce("word", F.lit(0).cast("long")).alias("word")))).alias("w"))
    return words.select(F.expr("transform(w, x -> x.word)").alias("words")), bits


def may_hold(digest: Column, words: Column, bits: int) -> Column:
    """False where the filter rules the digest out."""
    out = F.lit(True)
    for spot in _spots(digest, bits):
        word = F.get(words, F.shiftright(spot, 6).cast("int"))
        out = out & (F.bit_get(word, spot.bitwiseAND(F.lit(63)).cast("int")) == 1)
    return out


class DigestIndex:
    """Levels of sorted digest runs in the shared folder.

    ``flush`` appends a level-0 run of postings (digest, doc_id, n_chars), one file for each memtable (task).
    ``compact`` merges all runs into level 1, keeps the smallest rank and retires the level-0 runs it has merged, so that each row counts once. Level 1
    is two runs, ``single`` and ``shared`` (digest, keep, group_size), each with a filter.
    ``probe`` looks digests of new rows up without changing the index, asking the filters first.
    """

    def __init__(self, spark: SparkSession, path: str | None = None):
        self.spark, self.path = spark, path or scratch_path(spark, "digest-index")
        self.runs: list[str] = []
        self.flushed = self.compacted = 0
        self.merged: str | None = None
        self.filters: dict[str, tuple[str, int]] = {}

    def _write(self, df: DataFrame, name: str, *, sort: str | None = "digest") -> str:
        to = f"{self.path}/{name}"
        (df.sortWithinPartitions(sort) if sort else df).write.mode("overwrite").parquet(to)
        return to

    def flush(self, postings: DataFrame) -> DataFrame:
        """Write a batch as a level-0 run and return it as read back."""
        self.runs.append(self._write(postings, f"l0-{self.flushed:05d}"))
        self.flushed += 1
        return self.spark.read.parquet(self.runs[-1])

    def level(self, part: str | None = None) -> DataFrame:
        """Level 1, or its run ``single`` or ``shared``."""
        rows = self.spark.read.parquet(self.merged)
        return rows.where((F.col("group_size") > 1) if part == "shared" else (F.col("group_size") == 1)) if part else rows

    def compact(self) -> DataFrame:
        """Merge level 0 and level 1 into a new level 1."""
        if self.merged and not self.runs:
            return self.level()
        keep = F.min(F.expr(RANK)).alias("keep")
        fresh = self.spark.read.parquet(*self.runs).groupBy("digest").agg(keep, F.count(F.lit(1)).alias("group_size"))
        if self.merged:
            fresh = self.level().unionByName(fresh).groupBy("digest").agg(F.min("keep").alias("keep"), F.sum("group_size").alias("group_size"))
        self.merged = self._write(fresh, f"l1-{self.compacted:05d}")
        self.compacted += 1
        self.runs.clear()
        self.filters.clear()
        return self.level()

    def passes(self, digest: Column, part: str) -> Column:
        """False where the filter of a level-1 run rules a digest out; the filter is built at the first lookup after a compaction."""
        if part not in self.filters:
            words, bits = build_filter(self.level(part).select("digest"))
            self.filters[part] = self._write(words, f"filter-{self.compacted:05d}-{part}", sort=None), bits
        at, bits = self.filters[part]
        return may_hold(digest, self.spark.read.parquet(at).scalar(), bits)

    def lookup(self, postings: DataFrame, part: str) -> DataFrame:
        """All postings, with keep and group_size where the run holds their digest; only those that pass its filter are joined."""
        marked = postings.withColumn("__asks", self.passes(F.col("digest"), part))
        run = self.level(part)
        asking = marked.where("__asks").join(run.hint("merge"), "digest", "left")
        nothing = [F.lit(None).cast(run.schema[c].dataType).alias(c) for c in ("keep", "group_size")]
        return asking.drop("__asks").unionByName(marked.where("NOT __asks").drop("__asks").select("*", *nothing))

    def probe(self, postings: DataFrame) -> DataFrame:
        """Postings whose digest the compacted index holds, with the row that stays."""
        found = [self.lookup(postings, part).where("keep IS NOT NULL") for part in ("single", "shared")]
        return found[0].unionByName(found[1])


def exact_groups(docs: DataFrame, *, digest=lambda text: F.sha2(text, 256), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256.

    Null text counts as empty, and all empty texts are one group. A null id stays only if its whole group has none.
    Rows that repeat both id and text count in group_size and share one decision; equal lengths are decided by the id. An empty table gives no rows.
    Other columns of ``docs`` are never read. ``digest`` is replaceable so that tests can force collisions.
    """
    rows = docs.select(F.col(id_col).alias("doc_id"), text_or_empty(text_col).alias("text"))
    keyed = rows.withColumn("norm", normalised(F.col("text")))
    index = DigestIndex(docs.sparkSession)
    postings = index.flush(keyed.select("doc_id", F.length("text").cast("long").alias("n_chars"), F.sha2("norm", 256).alias("text_sha256"), digest(F.col("norm")).alias("digest")))
    index.compact()
    grouped = index.lookup(postings, "shared")
    alone = F.col("keep").isNull()
    keep_id = F.when(alone, F.col("doc_id")).otherwise(F.col("keep.c"))
    result = materialise(grouped.select("doc_id", keep_id.alias("keep_id"), F.coalesce("group_size", F.lit(1)).cast("long").alias("group_size"), F.col("doc_id").eqNullSafe(keep_id).alias("kept"), "text_sha256", "digest"), "exact-assigned")

    hits = materialise(result.where("group_size > 1").select(F.col("doc_id").alias("hit")).distinct(), "exact-hits")
    n_hits = hits.count()
    if not n_hits:
        return result.drop("digest")
    # null-safe: a row without an id is verified like any other
    near = F.broadcast(hits) if n_hits <= BROADCAST_ROWS else hits.hint("merge")
    seen = keyed.select("doc_id", "norm").join(near, F.col("doc_id").eqNullSafe(F.col("hit")), "left_semi").select("norm", digest(F.col("norm")).alias("digest"))
    checked = seen.groupBy("digest").agg(F.min("norm").alias("low"), F.max("norm").alias("high"))
    clashes = materialise(checked.where("low <> high").select("digest"), "exact-clashes")
    n_clashes = clashes.count()
    if not n_clashes:
        return result.drop("digest")
    suspects = join_small(keyed.withColumn("digest", digest(F.col("norm"))).withColumn("n_chars", F.length("text").cast("long")), clashes, ["digest"], "left_semi", rows=n_clashes)
    exact = suspects.groupBy("norm").agg(F.min(F.expr(RANK)).alias("keep"), F.count(F.lit(1)).alias("group_size"))
    again = suspects.join(exact.hint("merge"), "norm").select("doc_id", F.col("keep.c").alias("keep_id"), "group_size", F.col("doc_id").eqNullSafe(F.col("keep.c")).alias("kept"), F.sha2("norm", 256).alias("text_sha256"))
    return join_small(result, clashes, ["digest"], "left_anti", rows=n_clashes).drop("digest").unionByName(again)


def drop_exact_copies(docs: DataFrame, **options) -> DataFrame:
    """The rows of ``docs`` that stay, with all their columns; rows of a null id stay."""
    lost = materialise(exact_groups(docs, **options).where("NOT kept AND doc_id IS NOT NULL").select(F.col("doc_id").alias("__lost")).distinct(), "exact-lost")
    n = lost.count()
    if not n:
        return docs
    key = options.get("id_col", "doc_id")
    return docs.join(F.broadcast(lost) if n <= BROADCAST_ROWS else lost.hint("merge"), docs[key] == lost["__lost"], "left_anti")
