"""Near-duplicate detection by b-bit MinHash, with every link confirmed on whole shingle sets.

1. One pass over the texts (Arrow batches) gives each document the size and digest of its shingle set, band keys
   over full minima, and the low bits of all minima packed into longs.
2. Documents with equal sets form a class; only its smallest id goes on, so copies are never paired.
3. In each band bucket all members are compared with one hub, the member that meets most others over all bands: a group of n near
   copies costs n comparisons. Pairs come from an equi-join whose large partitions Spark can split.
4. Pairs whose collision-corrected estimate of the packed bits is far too low are dropped; the rest are confirmed on whole sets.
5. What the hubs leave in several components of one bucket is compared across these components (never within one): by a join in
   small buckets, in blocks of bounded size that emit nothing but links in crowded ones. So no pair
   of a bucket that could join two components is skipped. Components come from star contractions.

A band of ``rows`` minima collides with probability s^rows, so a pair of similarity 0.8 meets in some band with
probability 1 - (1 - 0.8^rows)^bands: the defaults (64 bands of 8) miss fewer than 8 of a million such pairs.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from netjoin.llm.common import BROADCAST_ROWS, join_small, materialise, slices, text_or_empty
from netjoin.operators.components import connected_components

#: Bound of a worker's table of word hashes.
CACHE_WORDS = 150_000
#: What hubs leave open in buckets of at most so many members is paired by a join; larger buckets are compared in blocks.
SMALL_BUCKET = 16
#: Most rows of either side of a block.
BLOCK_ROWS = 1024


class _Hashes(dict):
    """64-bit hash of a word, remembered in a bounded table."""

    def __missing__(self, word: bytes) -> int:
        if len(self) >= CACHE_WORDS:
            self.clear()
        value = self[word] = int.from_bytes(hashlib.blake2b(word, digest_size=8).digest(), "little")
        return value


_HASHES = _Hashes()


def shingle_set(text: str | None, words: int) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the text's shingles of so many words; with fewer words, of the whole sequence; without words, empty."""
    found = (text or "").encode("utf-8", "surrogatepass").lower().split()  # of bytes: A-Z, and the six ASCII white space characters
    if not found:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(_HASHES.__getitem__, found), np.uint64, len(found))
    n = max(1, len(h) - words + 1)
    mixed = np.full(n, len(found) if len(found) < words else words, np.uint64)
    for k in range(min(words, len(h))):
        mixed = (mixed ^ h[k : k + n]) * np.uint64(0x9E3779B97F4A7C15)
        mixed ^= mixed >> np.uint64(29)
    mixed *= np.uint64(0xBF58476D1CE4E5B9)
    return np.unique(mixed ^ (mixed >> np.uint64(32)))


class Sketcher:
    """Minima, band keys and packed low bits of shingle sets."""

    def __init__(self, bands: int, rows: int, bits: int, seed: int = 7):
        self.bands, self.rows, self.bits = bands, rows, bits
        random = np.random.default_rng(seed)
        n = bands * rows
        self.factor = (random.integers(1, 2**31, n, dtype=np.uint32) << np.uint32(1)) | np.uint32(1)
        self.add = random.integers(0, 2**32, n, dtype=np.uint32)
        self.block = np.empty((64, n), np.uint32)
        self.mix = (random.integers(1, 2**62, (bands, rows), dtype=np.uint64) << np.uint64(1)) | np.uint64(1)
        self.salt = random.integers(1, 2**62, bands, dtype=np.uint64)

    def minima(self, shingles: np.ndarray) -> np.ndarray:
        low = np.full(len(self.factor), 0xFFFFFFFF, np.uint32)
        x = (shingles >> np.uint64(16)).astype(np.uint32)
        for i in range(0, len(x), 64):
            part = x[i : i + 64]
            h = self.block[: len(part)]
            np.multiply(part[:, None], self.factor, out=h)
            np.add(h, self.add, out=h)
            np.minimum(low, np.minimum.reduce(h, axis=0), out=low)
        return low

    def keys(self, low: np.ndarray) -> np.ndarray:
        k = ((low.reshape(self.bands, self.rows).astype(np.uint64) + np.uint64(1)) * self.mix).sum(axis=1, dtype=np.uint64) ^ self.salt
        k = (k ^ (k >> np.uint64(31))) * np.uint64(0x94D049BB133111EB)
        return (k ^ (k >> np.uint64(29))).view(np.int64)

    def packed(self, low: np.ndarray) -> np.ndarray:
        """Low bits of the mixed minima: plane by plane, 64 minima to a long.

        Unmixed, the low bits of a minimum would follow from those of its shingle alone (factors are odd), and in small sets
        unequal minima would not agree in 2^-bits of the cases.
        """
        low = (low ^ (low >> np.uint32(16))) * np.uint32(0x85EBCA6B)
        low = (low ^ (low >> np.uint32(13))) * np.uint32(0xC2B2AE35)
        low ^= low >> np.uint32(16)
        planes = [np.packbits(((low >> np.uint32(b)) & np.uint32(1)).astype(np.uint8)) for b in range(self.bits)]
        return np.concatenate(planes).view(np.int64)


def sketches(docs: DataFrame, *, words: int, bands: int, rows: int, bits: int, id_col: str, text_col: str) -> DataFrame:
    """doc_id, n_shingles, set_key, band_keys, low_bits for every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        s, none = Sketcher(bands, rows, bits), np.empty(0, np.int64)
        for part in slices(batches):
            size, digest, keys, packs = [], [], [], []
            for text in part.column(1).to_pylist():
                found = shingle_set(text, words)
                size.append(len(found))
                digest.append(hashlib.blake2b(found.tobytes(), digest_size=16).digest())
                low = s.minima(found) if len(found) else None
                keys.append(s.keys(low) if low is not None else none)
                packs.append(s.packed(low) if low is not None else none)
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(size, pa.int64()), pa.array(digest, pa.binary()), _lists(keys), _lists(packs)], names=["doc_id", "n_shingles", "set_key", "band_keys", "low_bits"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("doc_id"), text_or_empty(text_col).alias("text")).mapInArrow(run, f"doc_id {kind}, n_shingles long, set_key binary, band_keys array<long>, low_bits array<long>")


def _lists(arrays: list[np.ndarray]) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, arrays)]), pa.int32()), pa.array(np.concatenate(arrays) if arrays else np.empty(0, np.int64), pa.int64()))


def shingle_sets(docs: DataFrame, *, words: int, id_col: str, text_col: str) -> DataFrame:
    """doc_id, shingles array<long> (distinct)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches):
            yield pa.RecordBatch.from_arrays([part.column(0), _lists([shingle_set(t, words).view(np.int64) for t in part.column(1).to_pylist()])], names=["doc_id", "shingles"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("doc_id"), text_or_empty(text_col).alias("text")).mapInArrow(run, f"doc_id {kind}, shingles array<long>")


def estimate(left: str, right: str, *, hashes: int, bits: int):
    """Similarity estimated from packed bits: share of equal low bits, corrected for chance collisions 2^-bits."""
    per = (hashes + 63) // 64
    diff = " + ".join("bit_count(" + " | ".join(f"({left}[{b * per + i}] ^ {right}[{b * per + i}])" for b in range(bits)) + ")" for i in range(per))
    chance = 2.0**-bits
    return F.expr(f"((1 - ({diff}) / {float(hashes)}D) - {chance}D) / {1 - chance}D")


def blockwise_links(crowds: DataFrame, sets: DataFrame, *, percent: int, hashes: int, bits: int, slack: float) -> DataFrame:
    """Links (a, b) between different components of crowded buckets, found without emitting a pair that is not one.

    ``crowds`` has main, rep, component: everything that shares a bucket with the component ``main``. Rows outside main
    are compared with all others of the crowd, in blocks of at most BLOCK_ROWS rows a side that are tasks of their own.
    """
    part = crowds.withColumn("stray", F.col("component") != F.col("main"))
    sizes = part.groupBy("main").agg(F.ceil(F.count(F.lit(1)) / float(BLOCK_ROWS)).cast("int").alias("n_all"), F.ceil(F.greatest(F.count_if("stray"), F.lit(1)) / float(BLOCK_ROWS)).cast("int").alias("n_stray"))
    part = join_small(part, materialise(sizes, "crowd-sizes"), ["main"], "inner")
    every = part.withColumn("i", F.pmod(F.xxhash64("rep"), "n_all").cast("int")).withColumn("j", F.explode(F.expr("sequence(0, n_stray - 1)"))).withColumn("asks", F.lit(False))
    asking = part.where("stray").withColumn("j", F.pmod(F.xxhash64("rep", F.lit(1)), "n_stray").cast("int")).withColumn("i", F.explode(F.expr("sequence(0, n_all - 1)"))).withColumn("asks", F.lit(True))
    cols = ["main", "i", "j", "asks", "rep", "component"]
    dealt = every.select(*cols).unionByName(asking.select(*cols)).join(sets.hint("merge"), "rep")
    per = (hashes + 63) // 64
    least = (1 - (percent / 100 - slack)) * (1 - 2.0**-bits) * hashes

    def run(block: pa.Table) -> pa.Table:
        rep, component, asks = (block.column(c).to_numpy(zero_copy_only=False) for c in ("rep", "component", "asks"))
        packs = block.column("low_bits").combine_chunks().flatten().to_numpy().reshape(len(rep), -1)
        held = block.column("shingles").combine_chunks()
        ends = np.cumsum([0, *held.value_lengths().to_numpy()])
        flat = held.flatten().to_numpy()
        other = np.flatnonzero(~asks)
        out_a, out_b = [], []
        for x in np.flatnonzero(asks):
            apart = other[component[other] != component[x]]
            diff = packs[apart] ^ packs[x]
            planes = np.bitwise_or.reduce(diff.reshape(len(apart), bits, per), axis=1)
            apart = apart[np.bitwise_count(planes.view(np.uint64)).sum(axis=1) <= least]  # of signed longs it would count the absolute value's bits
            mine = np.sort(flat[ends[x] : ends[x + 1]])
            size = ends[apart + 1] - ends[apart]
            apart = apart[(100 * np.minimum(size, len(mine)) >= percent * np.maximum(size, len(mine)))]
            for y in apart:
                theirs = flat[ends[y] : ends[y + 1]]
                both = int((mine[np.minimum(np.searchsorted(mine, theirs), len(mine) - 1)] == theirs).sum())
                if 100 * both >= percent * (len(mine) + len(theirs) - both):
                    out_a.append(rep[x])
                    out_b.append(rep[y])
        return pa.table({"a": pa.array(out_a, block.schema.field("rep").type), "b": pa.array(out_b, block.schema.field("rep").type)})

    kind = crowds.schema["rep"].dataType.simpleString()
    return dealt.groupBy("main", "i", "j").applyInArrow(run, f"a {kind}, b {kind}").distinct()


def near_duplicates(docs: DataFrame, *, words: int = 5, percent: int = 80, bands: int = 64, rows: int = 8, bits: int = 2, slack: float = 0.14, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id, kept, n_class (documents with an equal set).

    Two documents are linked if 100 * |intersection| >= percent * |union| of their distinct shingle sets.
    Null and blank texts have an empty set, no links, and stay. A row with a null id has no links, a null component and stays. Rows that
    repeat an id with one text share a class and its decision. An empty table gives no rows; other columns are not read.
    ``slack`` is what a bit estimate may fall below the threshold before a pair is dropped unconfirmed: 6.6 standard
    deviations (0.021) of the estimate at similarity 0.8 with the default 512 minima of two bits, whatever the size of the sets.
    """
    sketch = materialise(sketches(docs, words=words, bands=bands, rows=rows, bits=bits, id_col=id_col, text_col=text_col), "sketches")
    filled = sketch.where("n_shingles > 0 AND doc_id IS NOT NULL")
    classes = materialise(filled.groupBy("set_key").agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("n_class")), "classes")
    several = classes.where("n_class > 1")
    shadowed = sketch.join(several.hint("merge"), "set_key").where("doc_id <> rep").select("doc_id").distinct()
    reps = materialise(filled.join(materialise(shadowed, "shadowed").hint("merge"), "doc_id", "left_anti"), "reps")

    exploded = reps.select(F.col("doc_id").alias("rep"), "n_shingles", F.explode("band_keys").alias("bucket"))
    # aggregates are written before they are joined back: then both sides of a join on a hot key are plain exchanges that AQE can split
    crowded = materialise(exploded.groupBy("bucket").agg(F.count(F.lit(1)).alias("crowd")).where("crowd > 1"), "crowded")
    members = materialise(exploded.join(crowded.hint("merge"), "bucket"), "buckets")
    degree = members.groupBy("rep").agg(F.sum("crowd").alias("meets"))
    members = materialise(members.select("bucket", "rep", "n_shingles").join(degree.hint("merge"), "rep"), "members")
    bits_of = reps.select(F.col("doc_id").alias("rep"), "n_shingles", "low_bits")

    def confirmed(pairs: DataFrame, name: str) -> DataFrame:
        """Pairs (a, b) that hold on the whole sets."""
        least = percent / 100 - slack
        near = (pairs.join(bits_of.select(F.col("rep").alias("b"), F.col("low_bits").alias("bits_b")).hint("merge"), "b")
                .join(bits_of.select(F.col("rep").alias("a"), F.col("low_bits").alias("bits_a")).hint("merge"), "a")
                .where(estimate("bits_a", "bits_b", hashes=bands * rows, bits=bits) >= least).select("a", "b"))
        near = materialise(near, f"{name}-near")
        wanted = materialise(near.select(F.explode(F.array("a", "b")).alias(id_col)).distinct(), f"{name}-wanted")
        sets = materialise(shingle_sets(join_small(docs.select(id_col, text_col), wanted, [id_col], "left_semi"), words=words, id_col=id_col, text_col=text_col).dropDuplicates(["doc_id"]), f"{name}-sets")
        both = (near.join(sets.select(F.col("doc_id").alias("b"), F.col("shingles").alias("set_b")).hint("merge"), "b")
                .join(sets.select(F.col("doc_id").alias("a"), F.col("shingles").alias("set_a")).hint("merge"), "a")
                .select("a", "b", F.size("set_a").alias("na"), F.size("set_b").alias("nb"), F.size(F.array_intersect("set_a", "set_b")).alias("both")))
        return materialise(both.where(f"100L * both >= {percent}L * (na + nb - both)").select("a", "b"), f"{name}-links")

    def sized(a: str, b: str) -> str:
        return f"100L * least({a}, {b}) >= {percent}L * greatest({a}, {b})"

    hubs = members.groupBy("bucket").agg(F.min(F.struct((-F.col("meets")).alias("m"), "rep", "n_shingles")).alias("h")).select("bucket", F.col("h.rep").alias("a"), F.col("h.n_shingles").alias("size_a"))
    hubs = materialise(hubs, "hubs")
    starred = members.join(hubs.hint("merge"), "bucket").where("a <> rep AND " + sized("size_a", "n_shingles")).select("a", F.col("rep").alias("b")).distinct()
    links = confirmed(starred, "hub")
    labels = materialise(connected_components(links), "labels")

    labelled = members.join(labels.select(F.col("id").alias("rep"), "component").hint("merge"), "rep", "left").select("bucket", "rep", "n_shingles", F.coalesce("component", "rep").alias("component"))
    mixed = labelled.groupBy("bucket").agg(F.min("component").alias("low"), F.max("component").alias("high"), F.count(F.lit(1)).alias("crowd")).where("low <> high").select("bucket", "crowd")
    mixed = materialise(mixed, "mixed")
    open_rows = materialise(labelled.join(mixed.hint("merge"), "bucket"), "open")

    few = open_rows.where(F.col("crowd") <= SMALL_BUCKET).withColumn("step", F.floor(F.log("n_shingles") / F.lit(float(np.log(100 / percent)))).cast("int"))
    left = few.select("bucket", F.col("rep").alias("x"), F.col("n_shingles").alias("size_x"), F.col("component").alias("part_x"), F.explode(F.array(F.col("step") - 1, "step", F.col("step") + 1)).alias("step"))
    across = left.join(few.hint("merge"), ["bucket", "step"]).where("x < rep AND part_x <> component AND " + sized("size_x", "n_shingles")).select(F.col("x").alias("a"), F.col("rep").alias("b")).distinct()
    tested = starred.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    rest = materialise(across.join(tested.hint("merge"), ["a", "b"], "left_anti"), "across")
    more = None if rest.isEmpty() else confirmed(rest, "across")

    many = open_rows.where(F.col("crowd") > SMALL_BUCKET)
    if not many.isEmpty():
        main = many.groupBy("bucket", "component").agg(F.count(F.lit(1)).alias("n")).groupBy("bucket").agg(F.max(F.struct("n", "component")).alias("m")).select("bucket", F.col("m.component").alias("main"))
        crowds = materialise(many.join(materialise(main, "mains").hint("merge"), "bucket").select("main", "rep", "component").distinct(), "crowds")
        wanted = materialise(crowds.select(F.col("rep").alias(id_col)).distinct(), "crowd-ids")
        sets = shingle_sets(join_small(docs.select(id_col, text_col), wanted, [id_col], "left_semi"), words=words, id_col=id_col, text_col=text_col).dropDuplicates(["doc_id"])
        full = materialise(sets.join(reps.select("doc_id", "low_bits").hint("merge"), "doc_id").withColumnRenamed("doc_id", "rep"), "crowd-sets")
        found = materialise(blockwise_links(crowds, full, percent=percent, hashes=bands * rows, bits=bits, slack=slack), "crowd-links")
        more = found if more is None else more.unionByName(found)
    if more is not None and not more.isEmpty():
        labels = materialise(connected_components(links.unionByName(more)), "labels")

    parts = classes.join(labels.select(F.col("id").alias("rep"), "component").hint("merge"), "rep", "left").select("set_key", F.coalesce("component", "rep").alias("component"), "n_class")
    linked = sketch.select("doc_id", "n_shingles", "set_key").join(parts.hint("merge"), "set_key", "left")
    alone = F.col("n_shingles") == 0
    component = F.when(alone | F.col("doc_id").isNull(), F.col("doc_id")).otherwise(F.col("component"))
    return linked.select("doc_id", "n_shingles", component.alias("component_id"), component.eqNullSafe(F.col("doc_id")).alias("kept"), F.when(alone | F.col("doc_id").isNull(), F.lit(1)).otherwise(F.col("n_class")).cast("long").alias("n_class"))


def drop_near_copies(docs: DataFrame, **options) -> DataFrame:
    """One document of each group (its smallest id), with all columns of ``docs``; rows of a null id stay."""
    key = options.get("id_col", "doc_id")
    lost = materialise(near_duplicates(docs, **options).where("NOT kept AND doc_id IS NOT NULL").select(F.col("doc_id").alias("__lost")).distinct(), "near-lost")
    n = lost.count()
    return docs.join(F.broadcast(lost) if n <= BROADCAST_ROWS else lost.hint("merge"), docs[key] == lost["__lost"], "left_anti") if n else docs
