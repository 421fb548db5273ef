"""WARC archives: writing through Spark's committed text sink, reading by boundary-chain verification.

Writing: equal payloads of at least ``least_bytes`` are stored once; the others become revisit records. Which page stays is decided on digests
alone, so payloads are not shuffled unless the table of repeated digests outgrows a broadcast.
Archives are plain files of one sort, rotated by record count, committed by Spark and safe against lost executors.

Reading: a file is split at every occurrence of the record magic, in parallel over blocks of files. Each piece is a candidate record and names
its successor: its offset plus header, content length and trailer. Pointer jumping from offset 0 doubles the step
in each round and keeps what is reachable; magic inside a payload starts a candidate that no record leads to, and is rejected.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from netjoin.llm.common import BROADCAST_ROWS, materialise, scratch_path

# Fixed values of the format.
MAGIC = "WARC/1.1\r\n"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
#: Payloads from this many bytes on are stored once.
LEAST_BYTES = 1000
#: Records in one archive file.
FILE_RECORDS = 20_000


def _clean(value: Column) -> Column:
    """A header value on one line; a space after a value that would make a magic with its line end."""
    line = F.regexp_replace(F.replace(F.replace(value, F.lit("\r"), F.lit("%0D")), F.lit("\n"), F.lit("%0A")), "[\\x00]", "%00")
    return F.when(F.endswith(line, F.lit(MAGIC.strip())), F.concat(line, F.lit(" "))).otherwise(line)


def repeated_payloads(pages: DataFrame, *, least_bytes: int) -> DataFrame:
    """digest, n_bytes, response_id for payloads that several rows share: the largest id is the response."""
    keyed = pages.where(F.col("n_bytes") >= least_bytes)
    return keyed.groupBy("digest", "n_bytes").agg(F.max("page_id").alias("response_id"), F.count(F.lit(1)).alias("n")).where("n > 1 AND response_id IS NOT NULL").drop("n")


def write_archives(pages: DataFrame, path: str, *, least_bytes: int = LEAST_BYTES, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> None:
    """Write one record for every row to ``path``.

    A null payload is empty. Rows with a null id and payload are responses of their own. Rows that repeat both the largest id and its payload are all
    responses. An empty table writes no record.
    """
    rows = pages.select(F.col(id_col).cast("string").alias("id_text"), F.col(id_col).alias("page_id"), F.coalesce(F.col(url_col).cast("string"), F.lit("")).alias("url"), F.coalesce(F.col(html_col).cast("string"), F.lit("")).alias("html"))
    rows = rows.withColumn("digest", F.sha1(F.col("html").cast("binary"))).withColumn("n_bytes", F.octet_length("html").cast("long"))
    shared = materialise(repeated_payloads(rows.select("page_id", "digest", "n_bytes"), least_bytes=least_bytes), "warc-repeats")
    rows = rows.join(F.broadcast(shared) if shared.count() <= BROADCAST_ROWS else shared.hint("merge"), ["digest", "n_bytes"], "left")
    again = F.expr("response_id IS NOT NULL AND page_id IS NOT NULL AND page_id <> response_id")
    block = F.when(again, F.lit("")).otherwise(F.col("html"))
    lines = [
        F.concat(F.lit("WARC-Type: "), F.when(again, F.lit("revisit")).otherwise(F.lit("response"))),
        F.concat(F.lit("WARC-Record-ID: <urn:page:"), F.coalesce("id_text", F.lit("")), F.lit(">")),
        F.concat(F.lit("WARC-Target-URI: "), _clean(F.col("url"))),
        F.concat(F.lit("WARC-Payload-Digest: sha1:"), F.col("digest")),
        F.concat(F.lit("WARC-Payload-Length: "), F.col("n_bytes").cast("string")),
        F.when(again, F.concat(F.lit(f"WARC-Profile: {PROFILE}\r\nWARC-Refers-To: <urn:page:"), F.col("response_id").cast("string"), F.lit(">"))),
        F.lit("Content-Type: text/html; charset=utf-8"),
        F.concat(F.lit("Content-Length: "), F.octet_length(block).cast("string")),
    ]
    # the sink ends each value with a line feed: the last byte of the record's trailer
    record = F.concat(F.lit(MAGIC), F.concat_ws("\r\n", *lines), F.lit("\r\n\r\n"), block, F.lit("\r\n\r"))
    rows.select(record.alias("value")).write.mode("overwrite").option("maxRecordsPerFile", FILE_RECORDS).text(path)


_CANDIDATE = "file string, block long, at long, size long, head long, next long, page_id string, kind string, refers string, n_bytes long, digest string, whole boolean"


def _header(piece: bytes) -> tuple[dict[str, str], int]:
    """Header fields (lower-case names) and the header's length with its blank line; 0 if there is none."""
    end = piece.find(b"\r\n\r\n")
    if end < 0:
        return {}, 0
    fields = (line.partition(":") for line in piece[:end].decode("utf-8", "replace").split("\r\n"))
    return {k.strip().lower(): v.strip() for k, sep, v in fields if sep}, end + 4


def _inside(value: str) -> str | None:
    return value[len("<urn:page:") : -1] or None if value.startswith("<urn:page:") and value.endswith(">") else None


def candidates(spark: SparkSession, path: str) -> DataFrame:
    """One row for each piece after a magic: its place inside its block of the file, its successor's, and what its header says."""
    magic = len(MAGIC)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        here, at = None, 0
        for batch in batches:
            out = []
            files, blocks = batch.column(1).to_pylist(), batch.column(2).to_pylist()
            for piece, file, block in zip(batch.column(0), files, blocks):
                if (file, block) != here:
                    here, at = (file, block), 0
                piece = piece.as_py()
                fields, head = _header(piece)
                length = fields.get("content-length", "")
                length = int(length) if length.isdigit() and len(length) < 16 and head else None
                payload = piece[head : head + length] if length is not None else b""
                whole = length is not None and head + length + 4 == len(piece)
                given = fields.get("warc-payload-length", "")
                kind = fields.get("warc-type")
                stored = kind != "revisit"
                n_bytes = length if stored else int(given) if given.isdigit() and len(given) < 16 else None
                digest = hashlib.sha1(payload).hexdigest() if stored and whole else fields.get("warc-payload-digest", "").removeprefix("sha1:")
                out.append((file, block, at, len(piece), head, None if length is None else at + magic + head + length + 4, _inside(fields.get("warc-record-id", "")), kind, _inside(fields.get("warc-refers-to", "")), n_bytes, digest, whole))
                at += len(piece) + magic
            yield pa.RecordBatch.from_pylist([dict(zip(names, row)) for row in out], schema=schema)

    kinds = {"string": pa.string(), "long": pa.int64(), "boolean": pa.bool_()}
    names = [c.split()[0] for c in _CANDIDATE.split(", ")]
    schema = pa.schema([(c.split()[0], kinds[c.split()[1]]) for c in _CANDIDATE.split(", ")])
    return _pieces(spark, path).select(F.col("value").cast("binary").alias("value"), "file", "block").mapInArrow(run, _CANDIDATE)


def _pieces(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.option("lineSep", MAGIC).text(path).select("value", F.col("_metadata.file_path").alias("file"), F.col("_metadata.file_block_start").alias("block"))


def reachable(succ: np.ndarray) -> np.ndarray:
    """Which of the positions 0..n-1 a chain from 0 reaches; succ[i] is the next position or n. Each round doubles the step."""
    n = len(succ)
    jump, seen = np.append(succ, n), np.zeros(n + 1, bool)
    seen[0] = n > 0
    while True:
        more = jump[np.flatnonzero(seen)]
        fresh = more[~seen[more]]
        seen[fresh] = True
        if not len(fresh) and (jump == n).all():
            return seen[:n]
        jump = jump[jump]


def read_archives(spark: SparkSession, path: str) -> DataFrame:
    """page_id (text), payload_bytes, payload_digest, record_type, refers_to (text) of every record that a chain from its file's start reaches.

    A file is one group of its candidates, some dozens of bytes each. A record whose payload holds the magic lies in several pieces; the chain step
    says which, and they are put together again. Files without a record give no rows.
    """
    magic = len(MAGIC)
    found = materialise(candidates(spark, path), "warc-candidates")

    def run(group: pa.Table) -> pa.Table:
        block, at, size, nxt = (group.column(c).to_numpy(zero_copy_only=False) for c in ("block", "at", "size", "next"))
        order = np.lexsort((at, block))
        block, at, size, nxt = block[order], at[order], size[order], np.nan_to_num(nxt[order].astype(float), nan=-1).astype(np.int64)
        ends = at + size + magic
        last = np.append(block[1:] != block[:-1], True)
        totals = ends[last]
        base = np.repeat(np.cumsum(np.append(0, totals[:-1])), np.diff(np.append(-1, np.flatnonzero(last))))
        start = at + base - magic  # of the record; the piece before the first magic has none
        following = np.where(nxt >= 0, nxt + base - magic, -1)
        real = np.flatnonzero(start >= 0)
        place = {int(s): k for k, s in enumerate(start[real])}
        n = len(real)
        succ = np.fromiter((place.get(int(x), n) for x in following[real]), np.int64, n)
        keep = real[reachable(succ)] if n and start[real[0]] == 0 else real[:0]
        # pieces between a kept record and its successor belong to that record
        owner = keep[np.maximum(np.searchsorted(keep, np.arange(len(start)), side="right") - 1, 0)] if len(keep) else np.zeros(0, np.int64)
        whole = np.asarray(group.column("whole").to_pylist(), bool)[order]
        rows = np.flatnonzero((start >= 0) & (start < following[owner]) & ((owner == np.arange(len(start))) | ~whole[owner])) if len(keep) else keep
        return (group.take(pa.array(order[rows])).append_column("start", pa.array(start[owner[rows]] if len(keep) else [], pa.int64()))
                .append_column("offset", pa.array(start[rows], pa.int64())))

    chain = materialise(found.groupBy("file").applyInArrow(run, _CANDIDATE + ", start long, offset long"), "warc-chain")
    kept = chain.where("start = offset")
    records = kept.select("file", "start", "page_id", F.col("n_bytes").alias("payload_bytes"), F.col("digest").alias("payload_digest"), F.col("kind").alias("record_type"), F.col("refers").alias("refers_to"), "whole")
    if kept.where("NOT whole").isEmpty():
        return records.drop("file", "start", "whole")
    mended = _reassemble(spark, path, chain)
    fixed = records.join(mended, ["file", "start"], "left").withColumn("payload_digest", F.when(~F.col("whole") & (F.col("record_type") != "revisit"), F.col("mended")).otherwise(F.col("payload_digest")))
    return fixed.drop("file", "start", "whole", "mended")


def _reassemble(spark: SparkSession, path: str, chain: DataFrame) -> DataFrame:
    """file, start, mended: the digest of payloads that hold the magic, from all pieces between a record's start and its successor."""
    magic = len(MAGIC)
    heads = chain.where("start = offset AND NOT whole").select("file", "start", "head")
    wanted = chain.select("file", "block", "at", "start", "offset").join(heads, ["file", "start"])

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        here, at = None, 0
        for batch in batches:
            spots = []
            for piece, file, block in zip(batch.column(0), batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                if (file, block) != here:
                    here, at = (file, block), 0
                spots.append(at)
                at += len(piece.as_py()) + magic
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), pa.array(spots, pa.int64())], names=["piece", "file", "block", "at"])

    pieces = _pieces(spark, path).select(F.col("value").cast("binary").alias("value"), "file", "block").mapInArrow(cut, "piece binary, file string, block long, at long")
    files = heads.select("file").distinct()
    parts = pieces.join(files, "file", "left_semi").join(wanted, ["file", "block", "at"]).groupBy("file", "start", "head").agg(F.array_sort(F.collect_list(F.struct("offset", "piece"))).alias("parts"))
    whole = F.expr(f"aggregate(slice(parts, 2, size(parts)), parts[0].piece, (s, p) -> concat(s, cast('{MAGIC}' AS binary), p.piece))".replace("\r", "\\r").replace("\n", "\\n"))
    # bytes: the header's length is what the candidate pass has read, and four bytes of trailer follow the payload
    payload = F.expr("substring(whole, int(head) + 1, length(whole) - int(head) - 4)")
    return parts.withColumn("whole", whole).select("file", "start", F.sha1(payload).alias("mended"))


def archive_round_trip(pages: DataFrame, *, path: str | None = None, id_col: str = "page_id", **options) -> DataFrame:
    """Write the rows as archives, read them back: page_id, payload_bytes, payload_digest, record_type, refers_to per row.

    A null payload is empty, a null url an empty header; payloads and urls may hold the magic, line ends and any length. Repeated rows are records each:
    of equal payloads, all rows with the largest id are responses. A null id comes back null and is never revisited. An empty table gives no rows.
    Other columns of ``pages`` are not read.
    """
    spark = pages.sparkSession
    path = path or scratch_path(spark, "archive")
    write_archives(pages, path, id_col=id_col, **options)
    kind = pages.schema[id_col].dataType
    back = read_archives(spark, path)
    return back.select(F.col("page_id").cast(kind).alias("page_id"), "payload_bytes", "payload_digest", "record_type", F.col("refers_to").cast(kind).alias("refers_to"))
