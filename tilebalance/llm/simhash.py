"""SimHash near-duplicates by multi-index hashing.

The 64-bit fingerprint is cut into segments.  Fingerprints within `radius`
differing bits agree up to radius // segments bits in at least one segment, so
each segment has a table keyed by its value; the values in a fingerprint's small
Hamming ball are looked up in it, and what is fetched is verified by the complete
distance.  Of a pair either side finds the other: a value is looked up only where
at least half of the flipped bits were set, as that holds for one of the two.

Only distinct fingerprints are entered, however many copies there are.  Values
that more than `bucket` of them share would still give many pairs; members and
seekers of such buckets are linked exactly by another index: keys made of the
complete fingerprint that two of them share if and only if they are close
enough, where neighbours in key order connect all members.
"""

from __future__ import annotations

from itertools import combinations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import components, materialise, slices, tidy

SEGMENTS, RADIUS, BUCKET = 2, 2, 256
#: Fingerprints whose copies are settled by broadcast.
HOT = 1024


def fingerprint(text: str | None, words_per_shingle: int = 3, seed: int = 42) -> int:
    """Unsigned fingerprint of one text; zero if it has no words.  A-Z lower-cased, words split at ASCII white space."""
    import numpy as np
    import xxhash

    words = (text or "").encode().lower().split()
    if not words:
        return 0
    k, digest = words_per_shingle, xxhash.xxh64_intdigest
    if len(words) <= k:
        hashes = [digest(b" ".join(words), seed)]
    elif k == 3:
        hashes = [digest(b"%b %b %b" % z, seed) for z in zip(words, words[1:], words[2:])]
    else:
        hashes = [digest(b" ".join(z), seed) for z in zip(*[words[i:] for i in range(k)])]
    octets = np.array(hashes, dtype="<u8").view(np.uint8).reshape(-1, 8)
    counts = np.bincount((octets + np.arange(0, 2048, 256)).ravel(), minlength=2048).reshape(8, 256)
    bits = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1, bitorder="little")
    ones = (counts @ bits.astype(np.int64)).ravel()  # of each bit, the lowest first
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words_per_shingle: int = 3) -> DataFrame:
    """(doc_id, fp): the fingerprint of each whole text as a signed long."""

    def run(batches):
        import numpy as np

        for batch in batches:
            for a, b in slices(batch.column(1)):
                part = batch.slice(a, b - a)
                prints = np.array([fingerprint(t, words_per_shingle) for t in part.column(1).to_pylist()], dtype=np.uint64)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(prints.view(np.int64))], names=["doc_id", "fp"])

    return docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(tidy(run), "doc_id bigint, fp bigint")


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _ball(low: int, width: int, radius: int) -> list[int]:
    """Every mask of at most radius bits among `width` from bit `low` on."""
    return [_signed(sum(1 << (low + b) for b in bits)) for k in range(radius + 1) for bits in combinations(range(width), k)]


def _masks(masks: list[int]):
    return F.array(*[F.lit(m).cast("bigint") for m in masks])


def _value(s: int, segments: int):
    """The bits of segment s, with the segment's number above them."""
    low, high = 64 * s // segments, 64 * (s + 1) // segments
    return F.shiftrightunsigned("fp", low).bitwiseAND(F.lit((1 << (high - low)) - 1).cast("bigint")) + F.lit(s << 32).cast("bigint"), high - low


def _sought(key, width: int, radius: int):
    """The values in the ball of a segment's value, flipped from where at least half of the bits were set."""
    some = F.filter(_masks(_ball(0, width, radius)), lambda m: F.bit_count(key.bitwiseAND(m)) * 2 >= F.bit_count(m))
    return F.transform(some, lambda m: key.bitwiseXOR(m))


def _dense_links(prints: DataFrame, radius: int) -> DataFrame:
    """Links (fp, fp2) that connect all of prints within radius bits, without a pair for each two.

    Even radius: keys are all values within radius / 2 bits, which meet between
    two fingerprints.  Odd radius: one bit is left out first, each in turn.
    """
    ball = _masks(_ball(0, 64, radius // 2))
    if radius % 2:
        keys = F.flatten(F.transform(F.sequence(F.lit(0), F.lit(63)), lambda i: F.transform(ball, lambda m: F.struct(i.alias("bit"), F.col("fp").bitwiseXOR(m).bitwiseAND(F.bitwise_not(F.call_function("shiftleft", F.lit(1).cast("bigint"), i))).alias("key")))))
    else:
        keys = F.transform(ball, lambda m: F.struct(F.lit(-1).alias("bit"), F.col("fp").bitwiseXOR(m).alias("key")))
    under = Window.partitionBy("bit", "key").orderBy("fp")
    return prints.select("fp", F.inline(keys)).distinct().select("fp", F.lag("fp").over(under).alias("fp2")).where("fp2 is not null")


def links(distinct: DataFrame, radius: int = RADIUS, segments: int = SEGMENTS, bucket: int = BUCKET) -> DataFrame:
    """Links (a, b) between rows (fp, rep) of distinct fingerprints that differ in 1 to `radius` bits, enough of them to connect every such pair."""
    if not 0 <= radius <= 4 or not 2 <= segments <= 16:
        raise ValueError("up to 4 differing bits and 2 to 16 segments are supported")
    own = [_value(s, segments) for s in range(segments)]
    seek = [_sought(key, width, radius // segments) for key, width in own]
    table = distinct.select("fp", F.explode(F.array(*[key for key, _ in own])).alias("key"))
    full = materialise(table.groupBy("key").count().where(F.col("count") > bucket).select("key"), "full")
    sought = distinct.select("fp", F.explode(F.flatten(F.array(*seek))).alias("key"))
    entered = table.join(full, "key", "left_anti").select(F.col("fp").alias("fp2"), "key").hint("shuffle_hash")
    close = F.bit_count(F.col("fp").bitwiseXOR(F.col("fp2"))) <= radius
    found = sought.join(entered, "key").where((F.col("fp") != F.col("fp2")) & close).select("fp", "fp2")
    if not full.isEmpty():
        dense = sought.join(full, "key", "left_semi").select("fp").distinct()
        found = found.unionByName(_dense_links(dense, radius).where(close))
    pairs = found.select(F.least("fp", "fp2").alias("fp"), F.greatest("fp", "fp2").alias("fp2")).distinct()
    a, b = distinct.select("fp", F.col("rep").alias("a")), distinct.select(F.col("fp").alias("fp2"), F.col("rep").alias("b"))
    return pairs.join(a, "fp").join(b, "fp2").select("a", "b")


def near_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words_per_shingle: int = 3, radius: int = RADIUS, hot: int = HOT) -> DataFrame:
    """One row per input row: doc_id, fingerprint (16 hex digits), component_id (smallest doc_id reachable over links).

    Texts that are null, empty or without words have fingerprint zero and are
    linked like any other.  Rows with a null id share their fingerprint's
    component (null if it has no other id); repeated rows are repeated in the
    result; ties cannot arise as the smallest id is unique.  Extra columns are
    not read; an empty table gives no rows.  Copies of the `hot` commonest
    fingerprints get their component map-side.
    """
    prints = materialise(fingerprints(docs, id_col, text_col, words_per_shingle), "prints")
    distinct = materialise(prints.groupBy("fp").agg(F.min("doc_id").alias("rep"), F.count("*").alias("n")), "distinct")
    roots = components(links(distinct.where("rep is not null"), radius))
    classes = materialise(distinct.join(roots, distinct.rep == roots.id, "left").select("fp", F.coalesce("root", "rep").alias("component_id"), "n"), "classes")
    common = F.broadcast(materialise(classes.orderBy(F.desc("n"), "fp").limit(hot).drop("n"), "hot"))
    settled, rest = prints.join(common, "fp"), prints.join(common, "fp", "left_anti").join(classes.drop("n"), "fp")
    return settled.unionByName(rest).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
