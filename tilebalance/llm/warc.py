"""WARC archives: writing with revisit records, and reading by boundary-chain verification.

Reading: the archive is cut at every occurrence of the version line, whatever it
stands in, by Spark's splittable text reader.  Each piece is a candidate record:
the task that has it emits its offset and, from its Content-Length, the offset
its successor must have.  Pointer jumping from offset 0 over these (offset,
successor) pairs, file by file, keeps the reachable ones; version lines inside
payloads are never reached and are given back to the record they stand in.
"""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import fresh_path, materialise

VERSION, TAIL = "WARC/1.1\r\n", "\r\n\r\n"
LEAST_BYTES, RECORDS_PER_FILE = 100, 50_000
_SEP = len(VERSION)


def revisits(pages: DataFrame, least_bytes: int = LEAST_BYTES) -> DataFrame:
    """pages (page_id, url, payload binary) with digest, n_bytes and refers_to (the smallest page_id with the same payload of at least least_bytes, null for that page itself)."""
    full = pages.withColumns({"digest": F.sha2("payload", 256), "n_bytes": F.octet_length("payload").cast("bigint")})
    first = full.where((F.col("n_bytes") >= least_bytes) & F.col("page_id").isNotNull()).groupBy("digest").agg(F.min("page_id").alias("first"), F.count("*").alias("n")).where("n > 1").select("digest", "first")
    # Payloads that are too small are never looked up: their key is their own.
    keyed = full.withColumn("key", F.when(F.col("n_bytes") >= least_bytes, F.col("digest")).otherwise(F.concat(F.lit("page "), F.coalesce(F.col("page_id").cast("string"), F.col("digest")))))
    joined = keyed.join(first.withColumnRenamed("digest", "key"), "key", "left")
    return joined.select("page_id", "url", "payload", "digest", "n_bytes", F.when(F.col("first") < F.col("page_id"), F.col("first")).alias("refers_to"))


def write(pages: DataFrame, path: str, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", least_bytes: int = LEAST_BYTES, date: str = "1970-01-01T00:00:00Z", compression: str = "gzip", records_per_file: int = RECORDS_PER_FILE) -> None:
    """One record per row.  A revisit record has no body: its headers name the response and hold digest and length of the full payload.

    Control characters in a url are percent-encoded; a null url has no target
    header, a null html is an empty payload, a row with a null id is a response
    with an id made of its digest.  Rows that repeat a page_id with equal
    payload are all responses.
    """
    own = pages.select(F.col(id_col).cast("bigint").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.coalesce(F.col(html_col), F.lit("")).cast("binary").alias("payload"))
    rows = revisits(own, least_bytes)
    name = lambda c: F.concat(F.lit("<urn:page:"), c.cast("string"), F.lit(">"))
    clean = F.regexp_replace(F.regexp_replace("url", "\r", "%0D"), "\n", "%0A")
    again = F.col("refers_to").isNotNull()
    head = F.concat(
        F.lit(VERSION + "WARC-Type: "), F.when(again, "revisit").otherwise("response"), F.lit("\r\nWARC-Record-ID: "), F.coalesce(name(F.col("page_id")), F.concat(F.lit("<urn:sha256:"), "digest", F.lit(">"))),
        F.lit(f"\r\nWARC-Date: {date}\r\n"), F.coalesce(F.concat(F.lit("WARC-Target-URI: "), clean, F.lit("\r\n")), F.lit("")),
        F.coalesce(F.concat(F.lit("WARC-Refers-To: "), name(F.col("refers_to")), F.lit("\r\nWARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest\r\n")), F.lit("")),
        F.lit("WARC-Payload-Digest: sha256:"), F.col("digest"), F.lit("\r\nX-Payload-Length: "), F.col("n_bytes").cast("string"), F.lit("\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: "),
        F.when(again, "0").otherwise(F.col("n_bytes").cast("string")), F.lit(TAIL),
    )
    record = F.concat(head.cast("binary"), F.when(again, F.lit("").cast("binary")).otherwise(F.col("payload")))
    rows.select(record.cast("string").alias("value")).write.option("lineSep", TAIL).option("compression", compression).option("maxRecordsPerFile", records_per_file).text(path)


_HEADER = re.compile(rb"(?im)^([!-9;-~]+):[ \t]*(.*?)\r?$")


def parse_head(piece: bytes) -> tuple[int, dict[str, str]] | None:
    """(bytes of the header with its blank line, fields by lower-case name) of what follows a version line; null unless it has a proper Content-Length."""
    end = piece.find(b"\r\n\r\n")
    if end < 0:
        return None
    fields = {k.decode("latin-1").lower(): v.decode("utf-8", "replace") for k, v in _HEADER.findall(piece[:end])}
    return (end + 4, fields) if fields.get("content-length", "").isdigit() and "warc-type" in fields else None


_CANDIDATE = "file string, block bigint, ord bigint, rel bigint, seg_len bigint, head bigint, length bigint, kind string, record_id string, refers_to string, uri string, claimed_digest string, claimed_length bigint, payload_sha256 string"


def _pieces(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.option("lineSep", VERSION).text(path).select(F.col("_metadata.file_path").alias("file"), F.col("_metadata.file_block_start").alias("block"), F.col("value").cast("binary").alias("piece"))


def candidates(spark: SparkSession, path: str) -> DataFrame:
    """Candidate records: place (file, block of the reader, number and offset in it), what the header says, and the digest of a body that ends within the piece."""

    def run(batches):
        at, number, rel = None, 0, 0
        for batch in batches:
            rows = []
            for file, block, piece in zip(*[c.to_pylist() for c in batch.columns]):
                if (file, block) != at:
                    at, number, rel = (file, block), 0, 0
                row = [file, block, number, rel, len(piece), *[None] * 9]
                if found := parse_head(piece):
                    head, f = found
                    length = int(f["content-length"])
                    row[5:13] = head, length, f["warc-type"], f.get("warc-record-id"), f.get("warc-refers-to"), f.get("warc-target-uri"), f.get("warc-payload-digest"), int(f["x-payload-length"]) if f.get("x-payload-length", "").isdigit() else None
                    if head + length <= len(piece):
                        row[13] = hashlib.sha256(memoryview(piece)[head : head + length]).hexdigest()
                rows.append(row)
                number, rel = number + 1, rel + len(piece) + _SEP
            i, t = pa.int64(), pa.string()
            kinds = [t, i, i, i, i, i, i, t, t, t, t, t, i, t]
            names = [c.split()[0] for c in _CANDIDATE.split(", ")]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows) if rows else [[]] * 14, kinds)], names=names)

    found = _pieces(spark, path).mapInArrow(run, _CANDIDATE)
    return found


def jump(at: np.ndarray, following: np.ndarray) -> np.ndarray:
    """Which offsets are reached from offset 0: the successor of the successor, doubling each round."""
    order = np.argsort(at, kind="stable")
    place = at[order]
    k = np.searchsorted(place, following[order])
    n = len(at)
    if not n:
        return np.zeros(0, bool)
    step = np.where((k < n) & (place[np.minimum(k, n - 1)] == following[order]), k, n)
    step = np.append(step, n)
    reached = np.zeros(n + 1, bool)
    reached[:-1] = place == 0
    for _ in range(n.bit_length() + 1):  # a chain of n records is covered by then, and loops end too
        more = reached.copy()
        more[step[np.flatnonzero(reached)]] = True
        reached, step = more, step[step]
    out = np.zeros(n, bool)
    out[order] = reached[:-1]
    return out


def chain(spark: SparkSession, path: str) -> DataFrame:
    """Reachable records with offset and next_offset (of the uncompressed file), and `whole`: body and tail lie in one piece.  A file's last record may be cut short: `complete` is false then.  A chain that ends before its file does raises ValueError."""
    found = materialise(candidates(spark, path), "candidates")
    sums = found.groupBy("file", "block").agg(F.sum(F.col("seg_len") + _SEP).alias("n"))
    earlier = Window.partitionBy("file").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    size = Window.partitionBy("file")
    bases = sums.select("file", "block", F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("base"), (F.sum("n").over(size) - _SEP).alias("file_bytes"))
    placed = found.join(bases, ["file", "block"]).withColumn("offset", F.col("base") + F.col("rel") - _SEP)
    placed = placed.withColumn("next_offset", F.col("offset") + _SEP + F.col("head") + F.col("length") + len(TAIL))
    pairs = placed.select("file", "offset", F.coalesce("next_offset", F.lit(-1)).alias("next_offset"), "file_bytes")

    def run(key, rows):
        size = int(rows["file_bytes"].iloc[0])
        rows = rows[(rows["offset"] >= 0) & (rows["next_offset"] >= 0)]
        rows = rows[jump(rows["offset"].to_numpy(), rows["next_offset"].to_numpy())]
        if (end := int(rows["next_offset"].max()) if len(rows) else 0) < size:
            raise ValueError(f"{key[0]}: the chain of records ends at byte {end} of {size}")
        return rows[["file", "offset"]]

    reached = pairs.groupBy("file").applyInPandas(run, "file string, offset bigint")
    return placed.join(reached, ["file", "offset"]).select(
        "file", "offset", "next_offset", "block", "ord", "head", "length", "kind", "record_id", "refers_to", "uri", "claimed_digest", "claimed_length", "payload_sha256",
        F.col("payload_sha256").isNotNull().alias("whole"), (F.col("next_offset") <= F.col("file_bytes")).alias("complete"),
    )


def bodies(spark: SparkSession, path: str, records: DataFrame) -> DataFrame:
    """(file, offset, payload) of the given rows of chain(), pieces of one record put together again."""

    def run(batches):
        at, rel = None, 0
        for batch in batches:
            rows = []
            for file, block, piece in zip(*[c.to_pylist() for c in batch.columns]):
                if (file, block) != at:
                    at, rel = (file, block), 0
                rows.append((file, block, rel, piece))
                rel += len(piece) + _SEP
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows) if rows else [[]] * 4, [pa.string(), pa.int64(), pa.int64(), pa.binary()])], names=["file", "block", "rel", "piece"])

    pieces = _pieces(spark, path).mapInArrow(run, "file string, block bigint, rel bigint, piece binary")
    sums = pieces.groupBy("file", "block").agg(F.sum(F.octet_length("piece") + _SEP).alias("n"))
    bases = sums.select("file", "block", F.coalesce(F.sum("n").over(Window.partitionBy("file").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    placed = pieces.join(bases, ["file", "block"]).select("file", (F.col("base") + F.col("rel") - _SEP).alias("at"), "piece")
    wanted = records.select("file", "offset", "next_offset", "head", "length")
    own = placed.join(wanted, (placed.file == wanted.file) & (placed["at"] >= wanted["offset"]) & (placed["at"] < wanted["next_offset"])).select(wanted["file"], "offset", "head", "length", "at", "piece")
    text = F.reduce(F.array_sort(F.collect_list(F.struct("at", "piece"))), F.lit(None).cast("binary"), lambda acc, x: F.when(acc.isNull(), x["piece"]).otherwise(F.concat(acc, F.lit(VERSION).cast("binary"), x["piece"])))
    whole = own.groupBy("file", "offset").agg(F.first("head").alias("head"), F.first("length").alias("length"), text.alias("text"))
    return whole.select("file", "offset", F.expr("substring(text, cast(head as int) + 1, cast(length as int))").alias("payload"))


def read(spark: SparkSession, path: str) -> DataFrame:
    """Every reachable record with its digest and length, those whose payload holds a version line too: file, offset, next_offset, kind, record_id, refers_to, uri, payload_bytes, payload_digest, complete."""
    records = materialise(chain(spark, path), "chain")
    broken = records.where("not whole")
    again = bodies(spark, path, broken).select("file", "offset", F.sha2("payload", 256).alias("again")) if not broken.isEmpty() else None
    out = records.join(again, ["file", "offset"], "left").withColumn("sha", F.coalesce("payload_sha256", "again")) if again is not None else records.withColumn("sha", F.col("payload_sha256"))
    revisit = F.col("kind") == "revisit"
    return out.select(
        "file", "offset", "next_offset", "kind", "record_id", "refers_to", "uri", F.when(revisit, F.col("claimed_length")).otherwise(F.col("length")).alias("payload_bytes"),
        F.when(revisit, F.regexp_replace("claimed_digest", "^sha256:", "")).otherwise(F.col("sha")).alias("payload_digest"), "complete",
    )


def round_trip(pages: DataFrame, **options) -> DataFrame:
    """Write pages to archives in the shared directory and read them back: page_id, payload_bytes, payload_digest, record_type, refers_to, file, offset."""
    path = fresh_path(pages.sparkSession, "warc")
    write(pages, path, **options)
    number = lambda c: F.regexp_extract(c, "^<urn:page:(-?[0-9]+)>$", 1)
    as_id = lambda c: F.when(number(c) != "", number(c).cast("bigint"))
    return read(pages.sparkSession, path).select(as_id(F.col("record_id")).alias("page_id"), "payload_bytes", "payload_digest", F.col("kind").alias("record_type"), as_id(F.col("refers_to")).alias("refers_to"), "file", "offset")
