"""Exact deduplication with a heavy-hitter split, in DataFrame functions alone.

A frequent-items sketch of the Misra-Gries family (Spark's approx_top_k) names
every digest that holds more than about 1/max_items of the rows.  Exact counts
and winners of those few digests are then verified by a partial aggregate and
broadcast (at most `heavy` rows, whatever the input), so rows of hot texts are
settled map-side; all other digests take an ordinary shuffle.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import materialise

#: Digests settled by broadcast, and items the sketch tracks (a power of two).
HEAVY, TRACKED = 1024, 16384


def digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, digest): SHA-256 of the whole text in UTF-8, null as empty."""
    return docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.unhex(F.sha2(F.coalesce(F.col(text_col), F.lit("")).cast("binary"), 256)).alias("digest"))


def frequent(narrow: DataFrame, heavy: int = HEAVY, tracked: int = TRACKED) -> DataFrame:
    """At most `heavy` digests that the sketch holds for more than one row."""
    top = narrow.agg(F.expr(f"approx_top_k(base64(digest), {heavy}, {tracked})").alias("top"))
    return top.select(F.explode("top").alias("t")).where("t.count > 1").select(F.unbase64("t.item").alias("digest"))


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", heavy: int = HEAVY, tracked: int = TRACKED) -> DataFrame:
    """One row per input row: doc_id, keep_id, group_size, kept, text_sha256.

    Of equal texts the row with the largest doc_id stays.  Null and empty texts
    are equal.  Rows that repeat both id and text count each in group_size and
    share their fate; null ids sort below all others (a group of null ids only
    has keep_id null and kept true).  Only the two named columns are read, so
    extra columns of any name do no harm; an empty table gives no rows.
    """
    narrow = materialise(digests(docs, id_col, text_col), "digests")
    # The sketch depends on the order in which blocks are merged, so its list is made once and written: both sides of the split read the same one.
    hot = F.broadcast(materialise(frequent(narrow, heavy, tracked), "frequent"))
    winners = narrow.join(hot, "digest").groupBy("digest").agg(F.max("doc_id").alias("keep_id"), F.count("*").alias("group_size"))
    settled = narrow.join(F.broadcast(winners), "digest")
    same = Window.partitionBy("digest")
    rest = narrow.join(hot, "digest", "left_anti").select("digest", "doc_id", F.max("doc_id").over(same).alias("keep_id"), F.count("*").over(same).alias("group_size"))
    return settled.select(rest.columns).unionByName(rest).select(
        "doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), F.lower(F.hex("digest")).alias("text_sha256")
    )


SQL = """
SELECT doc_id, max(doc_id) OVER same AS keep_id, count(*) OVER same AS group_size,
       doc_id = max(doc_id) OVER same AS kept, h AS text_sha256
FROM (SELECT doc_id, sha256(coalesce(text, '')) AS h FROM documents)
WINDOW same AS (PARTITION BY h)
"""
