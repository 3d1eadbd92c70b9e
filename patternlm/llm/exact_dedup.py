"""Exact deduplication through an extendible-hash index on shared files (built-in functions only).

1. A scan writes the entry (doc_id, 64-bit hash, SHA-256) of each row to the shared folder; entries are counted by hash, combined map-side.
2. The directory starts as one slot and one bucket. Buckets with more than `capacity` distinct hashes split by the next bit of the hash, and the
   directory doubles whenever a bucket is deeper than it, until no bucket is overfull. Depth grows with the data; slots of one bucket
   share it. The directory is a table that is joined by slot (Spark broadcasts it while it is small).
3. Texts are read again only where a hash was seen twice (a bitmap of those hashes, of bounded size, spares the others; the exact join
   follows) and compared byte by byte: the aggregate's key is the text itself, combined map-side, so a group of copies sends one row
   per map task and a hot group is never gathered. Unequal texts of one hash are links of one chain.
4. The directory gives each text its bucket; owner tasks take ranges of buckets, number the chains and write the index to shared files.
5. Each entry goes from its slot to its bucket and along the chain of its hash to the link with its digest.

Null text counts as empty; equal means identical after lower-casing A-Z; the largest doc_id stays (a null id loses to any other).
Empty input gives an empty result; extra columns are ignored, whatever their names.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from patternlm.llm.common import ascii_lower, column, whole_row
from patternlm.session import cut

CAPACITY = 100_000
BUCKETS_A_TASK = 8
MARGIN = 3  # bits of a directory beyond the depth that evenly spread hashes need
MOST_BITS = 1 << 26  # of the bitmap that spares texts: a broadcast of 2**20 words at most


def entries(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", hash_bits: int = 64) -> DataFrame:
    """doc_id, norm, h (its first hash_bits bits), digest."""
    norm = ascii_lower(F.coalesce(column(text_col), F.lit("")))
    h = F.xxhash64("norm")
    if hash_bits < 64:
        h = F.shiftleft(F.shiftrightunsigned(h, 64 - hash_bits), 64 - hash_bits)
    return docs.select(column(id_col).cast("long").alias("doc_id"), norm.alias("norm")).select("doc_id", "norm", h.alias("h"), F.unhex(F.sha2(F.col("norm").cast("binary"), 256)).alias("digest"))


def first_bits(h: Column, depth: int) -> Column:
    return F.shiftrightunsigned(h, 64 - depth) if depth else F.lit(0).cast("long")


def leaves(hashes: DataFrame, capacity: int, depth: int) -> DataFrame:
    """(depth, prefix, held): the buckets after splitting every overfull one, up to `depth` bits; a deeper split is left to the caller."""
    slots = hashes.groupBy(first_bits(F.col("h"), depth).alias("slot")).agg(F.count("*").alias("n"))
    levels = slots.select("slot", "n", F.explode(F.sequence(F.lit(0), F.lit(depth))).alias("depth"))
    held = cut(levels.groupBy("depth", F.expr(f"shiftright(slot, {depth} - depth)").alias("prefix")).agg(F.sum("n").alias("held")), "dedup-levels")
    split = held.where(F.col("held") > capacity).select((F.col("depth") + 1).alias("depth"), F.col("prefix").alias("above"))
    below = held.where((F.col("held") <= capacity) | (F.col("depth") == depth)).withColumn("above", F.shiftright("prefix", 1))
    return below.where("depth = 0").drop("above").unionByName(below.where("depth > 0").join(split, ["depth", "above"], "left_semi").drop("above"))


def directory(hashes: DataFrame, capacity: int) -> tuple[DataFrame, int]:
    """The directory (slot, bucket) over distinct hashes (h), and its depth in bits. bucket is 1 followed by the bucket's bits."""
    n = hashes.count()
    depth = min(62, max(0, math.ceil(math.log2(max(n, 1) / capacity))) + MARGIN) if n > capacity else 0
    while True:
        found = cut(leaves(hashes, capacity, depth), "dedup-leaves")
        if depth >= 62 or found.where(F.col("held") > capacity).isEmpty():
            break
        depth = min(62, depth + MARGIN)  # hashes that agree in their first bits
    span = F.expr(f"shiftleft(1L, {depth} - depth)")
    slots = F.sequence(F.col("prefix") * span, (F.col("prefix") + 1) * span - 1)
    return cut(found.select(F.expr("shiftleft(1L, depth) + prefix").alias("bucket"), F.explode(slots).alias("slot")), "dedup-directory"), depth


def repeated_texts(texts: DataFrame, twice: DataFrame) -> DataFrame:
    """The distinct texts whose hash is in `twice` (h): (h, digest, keep_id, group_size). Only texts that a bitmap of those hashes lets pass are shuffled."""
    n = twice.count()
    if not n:
        return twice.select("h", F.lit(None).cast("binary").alias("digest"), F.lit(None).cast("long").alias("keep_id"), F.lit(0).cast("long").alias("group_size")).limit(0)
    bits = min(MOST_BITS, max(1 << 16, 1 << (8 * n).bit_length()))
    word, bit = F.expr(f"pmod(h, {bits}) div 64").alias("word"), F.expr(f"shiftleft(1L, cast(pmod(h, {bits}) % 64 as int))")
    marks = twice.groupBy(word).agg(F.bit_or(bit).alias("bits"))
    some = texts.select("doc_id", "norm", "h", word).join(F.broadcast(marks), "word").where(F.col("bits").bitwiseAND(bit) != 0)
    groups = some.groupBy("h", "norm").agg(F.max("doc_id").alias("keep_id"), F.count("*").alias("group_size"))
    links = groups.select("h", F.unhex(F.sha2(F.col("norm").cast("binary"), 256)).alias("digest"), "keep_id", "group_size")
    return links.join(twice, "h", "left_semi")


def build_index(texts: DataFrame, hashes: DataFrame, slots: DataFrame, depth: int) -> DataFrame:
    """One row per distinct text: bucket, h, chain number, digest, the id that stays and the group's size; sorted, in ranges of buckets."""
    once = hashes.where("n = 1").select("h", "digest", F.col("largest").alias("keep_id"), F.col("n").alias("group_size"))
    links = once.unionByName(repeated_texts(texts, hashes.where("n > 1").select("h")))
    placed = links.withColumn("slot", first_bits(F.col("h"), depth)).join(slots, "slot").drop("slot")
    owned = placed.repartitionByRange(F.col("bucket")).sortWithinPartitions("bucket", "h", "digest")
    return owned.withColumn("chain", F.row_number().over(Window.partitionBy("bucket", "h").orderBy("digest")))


def index_of(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", capacity: int = CAPACITY, hash_bits: int = 64) -> tuple[DataFrame, DataFrame, DataFrame, int]:
    """(entries, index, directory, its depth), all tables on shared files. Buckets hold at most `capacity` hashes, or fewer so that every task has some."""
    texts = entries(docs, id_col, text_col, hash_bits)
    keys = cut(texts.select("doc_id", "h", "digest"), "dedup-entries")
    hashes = cut(keys.groupBy("h").agg(F.count("*").alias("n"), F.max("doc_id").alias("largest"), F.min("digest").alias("digest")), "dedup-hashes")
    tasks = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    per_bucket = max(1, min(capacity, hashes.count() // (BUCKETS_A_TASK * tasks)))
    slots, depth = directory(hashes.select("h"), per_bucket)
    return keys, cut(build_index(texts, hashes, slots, depth), "dedup-index"), slots, depth


def look_up(keys: DataFrame, index: DataFrame, slots: DataFrame, depth: int) -> DataFrame:
    """Entries with what the index knows of their text: slot, bucket, chain, link."""
    at = keys.withColumn("slot", first_bits(F.col("h"), depth)).join(slots, "slot").drop("slot")
    return at.join(index, ["bucket", "h", "digest"])


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """Every row of docs: doc_id, keep_id, group_size, kept, text_sha256."""
    found = look_up(*index_of(docs, id_col, text_col, **options))
    kept = F.coalesce(F.col("doc_id") == F.col("keep_id"), F.col("keep_id").isNull())
    return found.select("doc_id", "keep_id", "group_size", kept.alias("kept"), F.lower(F.hex("digest")).alias("text_sha256"))


def drop_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows of docs that stay, one per group of equal texts, with their columns.

    Rows that repeat both id and text are one row here.
    """
    kept = exact_dedup(docs, id_col, text_col, **options).where("kept").select(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).alias("id"), F.col("text_sha256").alias("digest"))
    own = F.sha2(ascii_lower(F.coalesce(column(text_col), F.lit(""))).cast("binary"), 256)
    marked = docs.select(whole_row(docs).alias("row"), F.coalesce(column(id_col).cast("long").cast("string"), F.lit("")).alias("id"), own.alias("digest"))
    return marked.join(kept, ["id", "digest"], "left_semi").dropDuplicates(["id", "digest"]).select("row.*")
