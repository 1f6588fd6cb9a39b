"""Token ids in columnar ORC files.

Ids lie in ORC stripes as run-length encoded integers; each stripe carries a
row index and a Bloom filter on ``doc_id``. Files hold consecutive ranges of
``doc_id``, so readers prune files and stripes by metadata and work on stripes
in parallel.

Layout of a row: ``shard`` (rank of its range), ``place`` (its place within the
shard), ``doc_id``, ``ids``. Rows are in ascending ``doc_id`` order within a
shard, and shards follow each other.

Defined cases: a null text counts as empty; a null ``doc_id`` sorts first;
rows that repeat a ``doc_id`` stay separate rows, next to each other, and start
in the order of the file; an empty
table gives empty files; other columns of the input are not read.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .encoding import byte_lists, library_encoder, list_array, with_end
from .shared import fresh_path, settle

#: Appended to every document.
END_ID = 0

FILE_SCHEMA = T.StructType(
    [T.StructField("shard", T.IntegerType()), T.StructField("place", T.LongType()), T.StructField("doc_id", T.LongType()), T.StructField("ids", T.ArrayType(T.IntegerType(), False))]
)

ORC_OPTIONS = {
    "orc.bloom.filter.columns": "doc_id",
    "orc.bloom.filter.fpp": "0.01",
    "orc.create.index": "true",
    "orc.row.index.stride": "1000",
    "orc.stripe.size": str(32 << 20),
    "compression": "zstd",
}


def write_token_files(docs: DataFrame, path: str, vocabulary: str, end_id: int = END_ID, added: bool = False) -> None:
    """Encode every whole text, append ``end_id``, and write the ids to ``path``.

    Texts, not ids, cross the range exchange: they are the smaller of the two.
    """

    def encode(batches):
        encoder, place = library_encoder(vocabulary, added), 0
        for batch in batches:
            low = 0
            for ids, sizes in encoder.encode_slices(batch.column(2)):
                rows = len(sizes)
                lists = list_array(*with_end(ids, sizes, end_id))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(low, rows), pa.array(np.arange(place, place + rows)), batch.column(1).slice(low, rows), lists], names=FILE_SCHEMA.names)
                low, place = low + rows, place + rows

    ranged = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").repartitionByRange("doc_id").sortWithinPartitions("doc_id")
    rows = ranged.select(F.spark_partition_id().alias("shard"), "doc_id", "text").mapInArrow(encode, FILE_SCHEMA)
    rows.write.options(**ORC_OPTIONS).orc(path)


def read_token_files(spark: SparkSession, path: str, doc_ids: list[int] | None = None) -> DataFrame:
    """The rows of the files; with ``doc_ids``, only those, found through the stripe indexes and Bloom filters."""
    rows = spark.read.schema(FILE_SCHEMA).orc(path)
    return rows if doc_ids is None else rows.where(F.col("doc_id").isin(*doc_ids))


def token_digests(rows: DataFrame) -> DataFrame:
    """(shard, place, doc_id, n_tokens, ids_crc32) of rows of token files."""

    def digest(batches):
        for batch in batches:
            lists = batch.column(3)
            sizes = np.diff(np.asarray(lists.offsets)).astype(np.int64)
            values = np.asarray(lists.values).astype("<u4", copy=False)[lists.offsets[0].as_py() : lists.offsets[-1].as_py()]
            sums = [zlib.crc32(part) for part in byte_lists(values, sizes)]
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array(sizes), pa.array(sums, pa.int64())], names=["shard", "place", "doc_id", "n_tokens", "ids_crc32"])

    return rows.select(*FILE_SCHEMA.names).mapInArrow(digest, "shard int, place long, doc_id long, n_tokens long, ids_crc32 long")


def with_starts(rows: DataFrame, length: Column, place: str) -> DataFrame:
    """Add ``start``: the sum of ``length`` over all rows before, in (shard, place).

    Two levels: running sums inside a shard, plus the totals of the shards
    before it. The table of totals has one row for each shard, that is for each
    partition of the write, so the one task that adds them up stays small.
    """
    inside = Window.partitionBy("shard").orderBy(place).rowsBetween(Window.unboundedPreceding, -1)
    totals = rows.groupBy("shard").agg(F.sum(length).alias("total"))
    before = totals.select("shard", F.coalesce(F.sum("total").over(Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    return rows.withColumn("inside", F.coalesce(F.sum(length).over(inside), F.lit(0))).join(before, "shard").withColumn("start", F.col("base") + F.col("inside")).drop("base", "inside")


def token_file_report(docs: DataFrame, vocabulary: str, added: bool = False) -> DataFrame:
    """Write the token files of ``docs``, read them back, and report each document's place and digest."""
    spark = docs.sparkSession
    path = fresh_path(spark, "token-files")
    write_token_files(docs, path, vocabulary, added=added)
    # The files are read and digested once; sums run over the small digests.
    digests = settle(token_digests(read_token_files(spark, path)), "token-digests")
    return with_starts(digests, F.col("n_tokens"), "place").select("doc_id", "start", "n_tokens", "ids_crc32", "shard")
