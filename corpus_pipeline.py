"""A corpus pipeline of five stages over documents.

Each stage takes (spark, docs, sf_dir) and works on every row that its
predecessor kept; run() writes each result as Parquet and rereads it.  All but
the last return the columns of their input.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tilebalance.llm import decontaminate, exact_dedup, near_copies, pieces, toxicity
from tilebalance.llm.common import bitmap, marked, materialise, shrink, table

TOXIC_FROM = 0.5
LISTED, SLOTS = 64, 29


def digest(docs: DataFrame) -> Column:
    """SHA-256 of a row's text, null as empty: what a verdict on the text goes by, whatever the row's id."""
    return F.sha2(F.coalesce(docs.text.cast("string"), F.lit("")).cast("binary"), 256)


def without(docs: DataFrame, gone: DataFrame) -> DataFrame:
    """docs without the rows whose text's digest _sha (and id _id, if it has one) is listed.

    A bitmap of the listed digests' hashes (LISTED bits each, 2 ** SLOTS at most) lets all other rows pass where they are: only rows
    that it marks, the listed ones and a few more, are shuffled and joined with the list, by their complete digests.
    """
    gone = materialise(gone.distinct(), "gone")
    width = max(12, min(SLOTS, (LISTED * gone.count()).bit_length()))
    slot = lambda sha: F.shiftrightunsigned(F.xxhash64(sha), 64 - width)
    bits = bitmap(gone, slot(F.col("_sha")))
    maybe = marked(docs, slot(digest(docs)), bits, "left_semi")
    same = digest(docs) == gone["_sha"]
    left = maybe.join(gone, same & docs.doc_id.eqNullSafe(gone["_id"]) if "_id" in gone.columns else same, "left_anti")
    return marked(docs, slot(digest(docs)), bits, "left_anti").union(left)


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents scored below TOXIC_FROM; the field is fitted on the labelled rows among them."""
    shrink(spark)
    model = toxicity.train(docs, table(spark, sf_dir, "labels"))
    score = toxicity.score_column(model)
    return docs.where(score(F.col("text").cast("string")) < TOXIC_FROM)


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the row with the largest doc_id."""
    gone = exact_dedup.exact_dedup(docs).where("not kept").select(F.col("doc_id").alias("_id"), F.col("text_sha256").alias("_sha"))
    return without(docs, gone)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, that with the smallest doc_id, of each group of near copies: 5-word shingles, similarity 0.8 or more."""
    shrink(spark)
    return near_copies.first_of_group(docs)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without any benchmark window."""
    shrink(spark)
    found = decontaminate.report(docs.withColumn("_sha", digest(docs)), table(spark, sf_dir, "benchmark"), id_col="_sha", id_type="string")
    return without(docs, found.where("contaminated").select(F.col("doc_id").alias("_sha")))


def encode_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Piece ids of every kept text with the digest of what they decode to: doc_id, n_pieces, ids_crc32, n_chunks, decoded_sha256, ids (packed unsigned 32-bit numbers)."""
    shrink(spark)
    model = public_tokenizers.path("piece_bpe_32k.model")
    return pieces.encode(docs, model, columns=(*pieces.DIGEST, "ids"))


STAGES = [("toxicity", drop_toxic), ("exact dedup", drop_copies), ("simhash near-dedup", drop_near_copies), ("benchmark decontamination", drop_contaminated), ("sentencepiece encoding", encode_pieces)]

#: The first stage's scores are a fitted model's: SQL cannot give them.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = materialise(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return docs
