"""Near copies by SimHash candidates and an exact completion, both verified by Jaccard similarity of word shingles.

First the multi-index of `simhash` gives candidates: fingerprints of 5-word
shingles within a few differing bits, linked if the similarity of their complete
shingle sets is 0.8 or more.  A similarity of 0.8 can lie ten and more bits
apart, which no index of small balls reaches, so a second pass completes them.

Its candidates come from prefix filtering, which misses none: under any one
order of all shingles, two sets of similarity s or more share a shingle among the
first n - ceil(s * n) + 1 of each.  The order puts shingles that a sample found
often last; a poor sample costs time and changes no result.

Large groups of near copies would give a pair for each two members.  Members of a
key are therefore tried first with one hub, the member that has fewest rarer
shingles (the least altered copy of a group, mostly); what is linked by then
needs no more trial, and only members of different components are tried pair by
pair.  Sets that differ in d elements have parity bits (of the numbers of
elements in 512 hashed classes) that differ in d places at most, so the bits
of two texts tell most candidates apart that are no near copies, and none that
are, before sets are sent anywhere.  Exact copies are represented by one row from the start.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import simhash
from .common import by_row, components, forget, materialise, release, slices, tidy

WORDS, SIMILAR = 5, (4, 5)  # 4 / 5 = 0.8, compared in whole numbers
#: Differing bits up to which fingerprints are candidates.
BITS = 3
SAMPLE_DOCS, SAMPLE_OFTEN, OFTEN_LIMIT = 20_000, 3, 200_000
PARITY = 8  # longs of parity bits a text


def shingles(text: str | None, words_per_shingle: int = WORDS, seed: int = 42):
    """Sorted distinct hashes of a text's shingles, split and lower-cased as in simhash; a shorter text is one shingle."""
    import numpy as np
    import xxhash

    words = (text or "").encode().lower().split()
    k, digest = words_per_shingle, xxhash.xxh64_intdigest
    found = [b" ".join(words)] if len(words) <= k else map(b" ".join, zip(*[words[i:] for i in range(k)]))
    return np.unique(np.array([digest(s, seed) for s in found], dtype=np.uint64))


def _least(n, similar):
    """ceil(similar * n)."""
    return -(-n * similar[0] // similar[1])


def sets(rows: DataFrame, words_per_shingle: int = WORDS) -> DataFrame:
    """rows (_row, text) to (_row, set): the distinct hashes."""
    kind = pa.list_(pa.int64())

    def run(batches):
        for batch in batches:
            for a, b in slices(batch.column(1)):
                part = batch.slice(a, b - a)
                own = [shingles(t, words_per_shingle).view("int64") for t in part.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(own, kind)], names=["_row", "set"])

    return rows.select("_row", "text").mapInArrow(tidy(run), "_row bigint, set array<bigint>")


def often(rows: DataFrame, words_per_shingle: int = WORDS):
    """Hashes that a sample of texts holds often, the rarest first."""
    import numpy as np

    def run(batches):
        for batch in batches:
            for t in batch.column(0).to_pylist():
                yield pa.RecordBatch.from_arrays([pa.array(shingles(t, words_per_shingle).view(np.int64))], names=["h"])

    n = rows.count()
    part = rows.where(F.pmod(F.xxhash64("_row"), F.lit(1 << 20)) < (1 << 20) * SAMPLE_DOCS // n) if n > SAMPLE_DOCS else rows
    found = part.select("text").mapInArrow(tidy(run), "h bigint").groupBy("h").agg(F.count("*").alias("n")).where(F.col("n") >= SAMPLE_OFTEN)
    top = found.orderBy(F.desc("n"), "h").limit(OFTEN_LIMIT).select("h").toArrow().column("h").to_numpy()
    return top[::-1].astype(np.int64).view(np.uint64)


def parity(own, bits: int):
    """Whether an odd number of hashes falls on each of `bits` bits (a power of two), as longs.  Halves put together by exclusive or are those of half as many bits."""
    import numpy as np

    return np.packbits(np.bincount((own & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1).view(np.int64)


def prefixes(rows: DataFrame, words_per_shingle: int = WORDS, similar: tuple[int, int] = SIMILAR) -> DataFrame:
    """(_row, n, keys, parity, wide) of each text: its number of shingles, those by which it can be found, the rarest first, and bits, each whether an odd number of its shingles fall on it: 64 * PARITY, and that many or at least n, doubled."""
    import numpy as np

    late = often(rows, words_per_shingle)
    by_hash = np.argsort(late)
    shared = rows.sparkSession.sparkContext.broadcast((late[by_hash], by_hash))
    longs = pa.list_(pa.int64())

    def run(batches):
        known, rank = shared.value
        for batch in batches:
            for a, b in slices(batch.column(1)):
                part = batch.slice(a, b - a)
                keys, sizes, odd, wide = [], [], [], []
                for t in part.column(1).to_pylist():
                    own = shingles(t, words_per_shingle)
                    n = len(own)
                    wide.append(parity(own, max(64 * PARITY, 1 << (n - 1).bit_length())))
                    odd.append(np.bitwise_xor.reduce(wide[-1].reshape(-1, PARITY)))
                    if len(known):
                        k = np.minimum(np.searchsorted(known, own), len(known) - 1)
                        hit = known[k] == own
                        own = np.concatenate([own[~hit], own[hit][np.argsort(rank[k[hit]])]])
                    keys.append(own[: n - _least(n, similar) + 1].view(np.int64))
                    sizes.append(n)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sizes, pa.int32()), pa.array(keys, longs), pa.array(odd, longs), pa.array(wide, longs)], names=["_row", "n", "keys", "parity", "wide"])

    return rows.select("_row", "text").mapInArrow(tidy(run), "_row bigint, n int, keys array<bigint>, parity array<bigint>, wide array<bigint>")


def alike(similar: tuple[int, int], wide: bool = False) -> str:
    """Sizes n, n2 and bits of parity that allow the similarity: sets that differ in d elements have sizes within d and parities within d bits.

    Of wide ones, whose number of bits goes by the size, the longer is folded; sizes that fit make it twice as long at most.
    """
    s, t = similar
    if wide:
        m = "least(size(wide), size(wide2))"
        half = "wide{0}[i] ^ if(size(wide{0}) > {1}, get(wide{0}, i + {1}), 0L)"
        bits = f"aggregate(sequence(0, {m} - 1), 0, (x, i) -> x + bit_count({half.format('', m)} ^ {half.format('2', m)}))"
    else:
        bits = " + ".join(f"bit_count(parity[{i}] ^ parity2[{i}])" for i in range(PARITY))
    return f"least(n, n2) * {t} >= greatest(n, n2) * {s} and ({bits}) * {s + t} <= (n + n2) * {t - s}"


def verified(pairs: DataFrame, rows: DataFrame, words_per_shingle: int = WORDS, similar: tuple[int, int] = SIMILAR) -> DataFrame:
    """Those pairs (a, b) whose similarity is large enough."""
    ids = pairs.select(F.col("a").alias("_row")).union(pairs.select("b")).distinct()
    own = sets(by_row(rows, ids, "left_semi"), words_per_shingle)
    both = pairs.join(own.select(F.col("_row").alias("a"), F.col("set").alias("x")), "a").join(own.select(F.col("_row").alias("b"), F.col("set").alias("y")), "b")
    same = F.size(F.array_intersect("x", "y"))
    return both.where(same * similar[1] >= (F.size("x") + F.size("y") - same) * similar[0]).select("a", "b").repartition("a", "b")  # few links become few files


def _near(found: DataFrame, rows: DataFrame, about: DataFrame, words_per_shingle: int, similar: tuple[int, int]) -> DataFrame:
    """Of candidates (a, b) in any order, repeated or not, the links.  Sizes and wide parities (about: _row, n, wide) rule out most before sets are compared."""
    pairs = found.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    pairs = pairs.join(about.select(F.col("_row").alias("a"), "n", "wide"), "a").join(about.select(F.col("_row").alias("b"), F.col("n").alias("n2"), F.col("wide").alias("wide2")), "b")
    pairs = materialise(pairs.where(alike(similar, True)).select("a", "b"), "pairs")
    out = materialise(verified(pairs, rows, words_per_shingle, similar), "near")
    forget(pairs)
    release(rows.sparkSession)
    return out


def close_prints(rows: DataFrame, words_per_shingle: int = WORDS, bits: int = BITS) -> DataFrame:
    """Candidates (a, b) by fingerprints: of one print each row with the first, and the first ones of prints within `bits`."""
    prints = materialise(simhash.fingerprints(rows, "_row", "text", words_per_shingle), "prints")
    distinct = prints.groupBy("fp").agg(F.min("doc_id").alias("rep"), F.count("*").alias("n"))
    same = prints.join(distinct.where("n > 1"), "fp").where("doc_id <> rep").select(F.col("doc_id").alias("a"), F.col("rep").alias("b"))
    return simhash.links(distinct.select("fp", "rep"), bits).unionByName(same)


def roots(rows: DataFrame, words_per_shingle: int = WORDS, similar: tuple[int, int] = SIMILAR, bits: int = BITS) -> DataFrame:
    """(id, root): components of near copies among rows (_row, text); rows without near copies are missing."""
    spark = rows.sparkSession
    every = materialise(prefixes(rows, words_per_shingle, similar), "prefixes")
    about = every.select("_row", "n", "parity", "wide")
    links = _near(close_prints(rows, words_per_shingle, bits), rows, about, words_per_shingle, similar)
    # One shuffle of all keys: those of a single text are dropped where they are counted.
    keyed = every.select("_row", F.posexplode("keys").alias("pos", "key")).withColumn("_count", F.count("*").over(Window.partitionBy("key")))
    entries = materialise(keyed.where("_count > 1").drop("_count"), "shared")
    release(spark)
    s, t = similar
    #: Sizes and places of one shared key that allow the similarity: the first key that two such sets share does.
    fits = f"least(n, n2) * {t} >= greatest(n, n2) * {s} and least(n - pos, n2 - pos2) * {s + t} >= (n + n2) * {s}"
    ends = [F.min("root").alias("_lo"), F.max("root").alias("_hi")]
    hub = F.min(F.struct("pos", "n", "_row", "root")).alias("hub")

    def apart(entries: DataFrame, links: DataFrame, *more) -> tuple[DataFrame, DataFrame]:
        """Entries with their component, and the keys whose members lie in several."""
        own = entries.join(components(links).withColumnRenamed("id", "_row"), "_row", "left").withColumn("root", F.coalesce("root", "_row"))
        own = materialise(own, "rooted")
        return own, own.groupBy("key").agg(*ends, *more).where("_lo < _hi").drop("_lo", "_hi")

    own, keys = apart(entries.join(about.select("_row", "n"), "_row"), links, hub)
    hubs = keys.select("key", F.col("hub.pos").alias("pos2"), F.col("hub.n").alias("n2"), F.col("hub._row").alias("b"), F.col("hub.root").alias("root2"))
    own = materialise(own.join(hubs, "key"), "tried")
    forget(entries)
    links = links.unionByName(_near(own.where("root <> root2").where(fits).select(F.col("_row").alias("a"), "b"), rows, about, words_per_shingle, similar))
    own, keys = apart(own.where("_row <> b").select("_row", "pos", "key", "n"), links)  # a key's hub has been tried with all others
    own = materialise(own.join(keys, "key", "left_semi").join(about.select("_row", "parity"), "_row"), "left")
    other = own.select("key", F.col("_row").alias("b"), F.col("n").alias("n2"), F.col("pos").alias("pos2"), F.col("root").alias("root2"), F.col("parity").alias("parity2"))
    return components(links.unionByName(_near(own.join(other, "key").where("root < root2").where(fits).where(alike(similar)).select(F.col("_row").alias("a"), "b"), rows, about, words_per_shingle, similar)))


def first_of_group(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of docs without the near copies: of each group the row with the smallest id stays (nulls last; of equal ids the text with the smaller digest).

    Null texts count as empty ones, and all texts without words are copies of
    each other; a text of fewer words than a shingle is one shingle; very long
    texts are compared whole; repeated rows are copies; columns other than the
    two named pass through unread, but for names that begin with an underscore,
    which are reserved; an empty table gives no rows.
    """
    numbered = materialise(docs.withColumn("_row", F.monotonically_increasing_id()), "rows")
    text = F.col(text_col).cast("string")
    digests = materialise(numbered.select("_row", F.col(id_col).alias("_id"), F.sha2(F.coalesce(text, F.lit("")).cast("binary"), 256).alias("_sha")), "digests")
    # Copies are settled by aggregates that combine map-side: the row that stands for a digest is its first by (id, row).
    stands = digests.groupBy("_sha").agg(F.min(F.struct(F.col("_id").isNull().alias("none"), F.col("_id").alias("_id"), F.col("_row").alias("_row"))).alias("first")).select("_sha", "first.none", "first._id", "first._row")
    stands = materialise(stands, "stands")
    rows = numbered.select("_row", text.alias("text"))
    if stands.count() < digests.count():
        rows = by_row(rows, stands, "left_semi")
    grouped = stands.join(roots(rows), F.col("_row") == F.col("id"), "left").withColumn("root", F.coalesce("root", "_row"))
    best = grouped.groupBy("root").agg(F.min(F.struct("none", "_id", "_sha", "_row")).alias("best")).select(F.col("best._row").alias("_row"))
    best = materialise(best, "best")
    return by_row(numbered, best, "left_semi").select(*docs.columns)
