"""Exact dedup through an extendible-hash index on shared files.

Only DataFrame functions are used. Each text has a 64-bit hash. Equal texts are
first combined on the map side, by their bytes, so that a hot text leaves each
task as one entry. The entries of one hash form a chain: its members differ in
their bytes. A directory maps the leading bits of a hash to a bucket; it starts
with one bucket and doubles until no bucket holds more than its share. The
index is written to shared files by bucket, so that each owner task has whole
buckets, sorted by hash.

A row finds its text through the directory: leading bits to bucket, bucket and
hash to the chain. Where a chain has one member, the bytes of all texts of that
hash were compared, and found equal, when it was built. Where it has more, the
row's bytes are compared with those of each member, which are kept for such
chains only.

Rows look up frequent texts in a broadcast part of the index, which is bounded
at any size, and the others by a join (see ``shared.look_up``).

Defined cases: null counts as empty text; of equal texts the largest
``doc_id`` stays (a null ``doc_id`` is the smallest); rows that repeat both
count twice, and all but one are dropped where rows are filtered; an empty
table gives an empty index; other columns are untouched.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .shared import look_up, settle

#: Entries that a bucket aims at; most leading bits of the directory, which is kept small by larger buckets; bits up to which it is an array in the plan.
BUCKET_ROWS, MOST_BITS, ARRAY_BITS = 200_000, 20, 12


def whole(text: Column) -> Column:
    return F.coalesce(text, F.lit(""))


def text_hash(text: Column) -> Column:
    return F.xxhash64(whole(text))


def leading_bits(hash_: Column, bits: int) -> Column:
    return F.shiftrightunsigned(hash_, 64 - bits).cast("int")


def split_directory(histogram: dict[int, int], capacity: int, bits: int = ARRAY_BITS) -> list[int]:
    """Bucket of each of the 2**bits directory slots.

    Doubles the directory while a bucket overflows and its slots can still be
    told apart; buckets that fit keep one shared pointer.
    """
    slots = 1 << bits
    load = [histogram.get(i, 0) for i in range(slots)]
    bucket, waiting, made = [0] * slots, [(0, slots)], 0
    while waiting:
        low, high = waiting.pop()
        if high - low > 1 and sum(load[low:high]) > capacity:
            middle = (low + high) // 2
            waiting += [(middle, high), (low, middle)]
        else:
            bucket[low:high] = [made] * (high - low)
            made += 1
    return bucket


@dataclass
class ExtendibleIndex:
    """``chains``: (bucket, hash, members, keep_id, group_size); ``members``: (hash, text, keep_id, group_size) of chains of several, or nothing."""

    bits: int
    directory: list[int]
    chains: DataFrame
    members: DataFrame | None

    def with_bucket(self, rows: DataFrame) -> DataFrame:
        """Add the bucket of ``hash``, by the directory."""
        slot = leading_bits(F.col("hash"), self.bits)
        if self.bits <= ARRAY_BITS:
            return rows.withColumn("bucket", F.element_at(F.lit(self.directory), slot + 1))
        table = rows.sparkSession.createDataFrame(list(enumerate(self.directory)), "slot int, bucket int")
        return rows.withColumn("slot", slot).join(F.broadcast(table), "slot").drop("slot")  # at most 2 ** MOST_BITS rows

    def find(self, rows: DataFrame) -> DataFrame:
        """``rows``, which have ``hash`` and ``text``, with keep_id and group_size of their text as struct ``entry``."""
        found = look_up(self.with_bucket(rows), self.chains, ["bucket", "hash"], "group_size", "entry").drop("bucket")
        if self.members is None:
            return found
        entry = F.struct("keep_id", "group_size").alias("entry")
        several = found.where("entry.members > 1").drop("entry").join(self.members.select("hash", F.col("text").alias("member"), entry), "hash").where(F.col("member") == whole(F.col("text"))).drop("member")
        alone = found.where("entry.members = 1").withColumn("entry", F.struct("entry.keep_id", "entry.group_size"))
        return alone.unionByName(several)


def build_index(docs: DataFrame, capacity: int = BUCKET_ROWS) -> ExtendibleIndex:
    """Combine equal texts, double the directory until buckets fit, and write the chains by bucket."""
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), whole(F.col("text")).alias("text"))
    combined = keyed.groupBy(text_hash(F.col("text")).alias("hash"), "text").agg(F.max("doc_id").alias("keep_id"), F.count("*").alias("group_size"))
    entries = settle(combined.select("hash", "keep_id", "group_size"), "dedup-entries")
    rows = entries.count()
    capacity = max(capacity, rows >> (MOST_BITS - 2))
    bits = min(MOST_BITS, max(1, math.ceil(math.log2(max(1, rows) / capacity)) + 2))
    histogram = {row["slot"]: row["count"] for row in entries.groupBy(leading_bits(F.col("hash"), bits).alias("slot")).count().collect()}
    index = ExtendibleIndex(bits, split_directory(histogram, capacity, bits), entries, None)
    chained = entries.groupBy("hash").agg(F.count("*").cast("int").alias("members"), F.max("keep_id").alias("keep_id"), F.sum("group_size").alias("group_size"))
    owned = index.with_bucket(chained).repartitionByRange("bucket", "hash").sortWithinPartitions("bucket", "hash")
    index.chains = settle(owned.select("bucket", "hash", "members", "keep_id", "group_size"), "dedup-index")
    collided = index.chains.where("members > 1").select("hash")
    if not collided.isEmpty():
        index.members = settle(combined.join(collided, "hash", "left_semi"), "dedup-members")
    return index


def exact_duplicates(docs: DataFrame) -> DataFrame:
    """(doc_id, keep_id, group_size, kept, text_sha256) of every row."""
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_hash(F.col("text")).alias("hash"), F.sha2(whole(F.col("text")), 256).alias("text_sha256"), "text")
    index = build_index(docs)
    if index.members is None:
        keyed = keyed.drop("text")
    found = index.find(keyed)
    return found.select(
        "doc_id",
        F.col("entry.keep_id").alias("keep_id"),
        F.col("entry.group_size").alias("group_size"),
        F.coalesce(F.col("doc_id").eqNullSafe(F.col("entry.keep_id")), F.lit(False)).alias("kept"),
        "text_sha256",
    )


def drop_exact(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that stay, one for each different text, all columns as they are."""
    index = build_index(docs)
    # Kept apart from columns of the input that may have these names.
    keyed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), text_hash(F.col("text")).alias("hash"), F.col("text"), F.col("doc_id").cast("long").alias("own_id"))
    if index.members is None:
        keyed = keyed.drop("text")
    stays = index.find(keyed).where(F.col("own_id").eqNullSafe(F.col("entry.keep_id")))
    if docs.groupBy("doc_id").count().where("count > 1").isEmpty():
        return stays.select("row.*")  # no row repeats another
    first = F.row_number().over(Window.partitionBy("hash", "own_id", F.col("row.text")).orderBy(F.lit(0)))
    return stays.withColumn("rank", first).where("rank = 1").select("row.*")


SQL = """
WITH whole AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
groups AS (SELECT text, max(doc_id) AS keep_id, count(*) AS group_size FROM whole GROUP BY text)
SELECT w.doc_id, g.keep_id, g.group_size, w.doc_id = g.keep_id AS kept, sha256(w.text) AS text_sha256
FROM whole w JOIN groups g USING (text)
"""
