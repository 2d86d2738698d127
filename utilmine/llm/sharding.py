"""Sharding by a two-pass external shuffle.

Pass one scatters records into memory-sized buckets: the shard by rendezvous hashing of doc_id (law `key`: one more
shard takes records only into itself), the bucket inside the shard by a seeded hash of the whole key and text, so that a shard of
any size is dealt over as many tasks as it has buckets. Pass two loads one bucket at a time, puts it into a canonical
order, applies a Fisher-Yates shuffle seeded by shard and bucket, and writes it. Reading buckets in order gives each
shard's records in random order; a record's slot is its bucket's offset plus its place in the bucket.

A rerun or a recomputed task gives the same files, as the canonical order does not depend on how records arrive.

Defined results: a null text counts 0 bytes, crc32 of nothing; a null doc_id is a key like any other; repeated rows are kept, with
slots of their own (records equal in id and text go to one bucket, the only case where a bucket outgrows its size); an
empty table gives no files; columns of any name pass through: helper columns get names that no column of the input starts with, and an
input column named shard or slot comes back with underscores appended, as those two names are the result's.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, LongType, StructField, StructType

from utilmine.llm.shared import broadcast_if_small, plain_names, shared_folder, unused_prefix

RECORD_BYTES = 16


def record_size(text: Column) -> Column:
    return F.coalesce(F.octet_length(text), F.lit(0)).cast("long") + RECORD_BYTES


def shard_of(key: Column, shards: int, seed: int) -> Column:
    """The shard whose hash with the key is largest: a new shard wins some keys and moves no other."""
    draws = F.transform(F.sequence(F.lit(0), F.lit(shards - 1)), lambda i: F.struct(F.xxhash64(F.lit(seed), i, F.coalesce(key.cast("string"), F.lit(""))).alias("draw"), i.alias("shard")))
    return F.array_max(draws)["shard"]


def scatter(docs: DataFrame, shards: int, bucket_bytes: int, seed: int, p: str) -> tuple[DataFrame, int]:
    """docs with shard and bucket, named behind the prefix p, and the number of buckets in a shard; one number comes to the driver."""
    total = docs.agg(F.sum(record_size(F.col("text")))).first()[0] or 0
    buckets = max(1, -(-total // (shards * bucket_bytes)))
    place = F.pmod(F.xxhash64(F.lit(seed + 1), "doc_id", "text"), F.lit(buckets)).cast("int")
    return docs.withColumns({f"{p}shard": shard_of(F.col("doc_id"), shards, seed), f"{p}bucket": place}), buckets


def _shuffler(seed: int, by: tuple[str, ...], p: str):
    def shuffle(bucket: pa.Table) -> pa.Table:
        shard, number = bucket[f"{p}shard"][0].as_py(), bucket[f"{p}bucket"][0].as_py()
        ordered = pc.sort_indices(bucket, [(c, "ascending") for c in by]).to_numpy()
        drawn = np.random.Generator(np.random.PCG64([seed, shard, number])).permutation(ordered)  # Fisher-Yates
        return bucket.take(pa.array(drawn)).append_column(f"{p}place", pa.array(np.arange(bucket.num_rows, dtype=np.int64)))

    return shuffle


def write_shards(docs: DataFrame, path: str, shards: int = 40, bucket_bytes: int = 8 << 20, seed: int = 7) -> None:
    """Writes the records of docs below path in a folder for each shard, shuffled, each with its bucket and place in the bucket.

    bucket_bytes is what a task may hold of a bucket, a few times over; a shard has as many buckets as its bytes need. Names of
    folders and added columns start with a prefix that no column of docs has.
    """
    p = unused_prefix(docs)
    spread, buckets = scatter(docs.toDF(*plain_names(docs.columns, p)), shards, bucket_bytes, seed, p)
    parts = max(shards * buckets, docs.sparkSession.sparkContext.defaultParallelism) if shards * buckets < 100_000 else 100_000
    dealt = spread.repartition(parts, f"{p}shard", f"{p}bucket")
    schema = StructType([*spread.schema.fields, StructField(f"{p}place", LongType())])
    shuffled = dealt.groupBy(f"{p}shard", f"{p}bucket").applyInArrow(_shuffler(seed, ("doc_id", "text"), p), schema)
    shuffled.sortWithinPartitions(f"{p}shard", f"{p}bucket", f"{p}place").write.partitionBy(f"{p}shard").parquet(path)


def read_shards(spark, path: str, schema: StructType) -> DataFrame:
    """The written records with shard and slot. Offsets come from counts by bucket, added up within each shard."""
    p = unused_prefix(spark.createDataFrame([], schema))
    shard, bucket = f"{p}shard", f"{p}bucket"
    plain = plain_names(schema.names, p)
    stored = [StructField(n, f.dataType) for n, f in zip(plain, schema.fields, strict=True)]
    full = StructType([*stored, StructField(bucket, IntegerType()), StructField(f"{p}place", LongType()), StructField(shard, IntegerType())])
    rows = spark.read.schema(full).parquet(path)
    before = Window.partitionBy(shard).orderBy(bucket).rowsBetween(Window.unboundedPreceding, -1)
    counts = rows.groupBy(shard, bucket).agg(F.count(F.lit(1)).alias("n"))
    offsets = counts.select(shard, bucket, F.coalesce(F.sum("n").over(before), F.lit(0)).alias(f"{p}offset"))
    placed = rows.join(broadcast_if_small(offsets), [shard, bucket])
    taken, own = {"shard", "slot"}, []
    for c, n in zip(schema.names, plain, strict=True):
        name = c
        while name.lower() in taken or name != c and name in schema.names:
            name += "_"
        taken.add(name.lower())
        own.append(F.col(n).alias(name))
    return placed.select(*own, F.col(shard).alias("shard"), (F.col(f"{p}offset") + F.col(f"{p}place")).alias("slot"))


def shards(docs: DataFrame, n: int = 40, **options) -> DataFrame:
    """The records of docs from shard files in the shared folder, with shard and slot."""
    path = shared_folder(docs.sparkSession)
    write_shards(docs, path, n, **options)
    return read_shards(docs.sparkSession, path, docs.schema)
