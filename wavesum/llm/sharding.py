"""Two-pass external shuffle into shards, by DataFrame functions only.

Pass 1 scatters the whole records uniformly: the shard of a record is the winner of a
rendezvous hash over (seed, doc_id, shard), so doc_id and the number of shards decide, and
one more shard takes records only into itself; inside its shard, a second seeded hash puts
the record into one of as many buckets as keep a bucket near `bucket_bytes` and
`bucket_rows`.  The exchange by (shard, bucket) writes the buckets.  Pass 2 loads one task's
buckets, orders each by a third seeded hash (a uniform permutation; the sort spills, so a
bucket with long texts needn't fit in memory) and writes the records into their shards'
folders.  A record's slot is its place in its bucket after the buckets before it, so a
shard's slots are gapless and its order uniform; `read_shards` numbers what was written.

The order is a function of the seed and the records: the hashes take doc_id and a record's
columns, so neither partitions nor adaptive execution move a slot, and only equal records
change places.  Hot keys: repeated rows of one doc_id must share a shard (the law says so),
but their bucket goes by their other columns too; a doc_id with more rows than an eighth of
a bucket, of which equal ones could fill a bucket, goes by its rows' running number besides,
so the order inside such an id is as arbitrary as its rows' order in the table.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from wavesum.llm.common import fresh, shared_dir

SEED = 20240611
BUCKET_BYTES = 16 << 20


def rendezvous(doc_id: Column, shards: int, seed: int = SEED) -> Column:
    """Number of the shard whose seeded hash with doc_id is largest; the lowest number wins a tie."""
    best = F.greatest(*[F.struct(F.xxhash64(F.lit(seed), F.lit(s), doc_id).alias("h"), F.lit(-s).alias("s")) for s in range(shards)]) if shards > 1 else None
    return F.lit(0) if best is None else (-best["s"]).cast("int")


def scatter(docs: DataFrame, shards: int, bucket_rows: int, bucket_bytes: int, seed: int, text: str) -> tuple[DataFrame, list[str]]:
    """All columns, and shard, bucket and mix (the order inside the bucket); also the names these got."""
    size = F.coalesce(F.octet_length(F.col(text).cast("binary")), F.lit(0)) + F.lit(8)
    rows, total = docs.agg(F.count("*"), F.coalesce(F.sum(size.cast("long")), F.lit(0))).first()
    buckets = max(1, -(-rows // (shards * bucket_rows)), -(-total // (shards * bucket_bytes)))
    key = F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 62)))
    shard, bucket, mix, number, hot = names = fresh(docs.columns, "shard", "bucket", "mix", "number", "hot")
    most = max(1, bucket_rows // 8)
    often = docs.groupBy(key.alias(hot)).agg(F.count("*").alias(number)).filter(F.col(number) > most).select(hot)
    content = F.xxhash64(*[F.col(f"`{f.name}`") for f in docs.schema if not f.dataType.simpleString().startswith(("map", "variant"))])
    numbered = docs
    if (ids := often.count()) > 0:  # at most rows / most ids
        numbered = docs.withColumn(number, F.monotonically_increasing_id()).join(F.broadcast(often) if ids <= 1_000_000 else often, key == F.col(hot), "left")
        numbered = numbered.withColumn(number, F.when(F.col(hot).isNotNull(), F.col(number)).otherwise(F.lit(0))).drop(hot)
    else:
        numbered = docs.withColumn(number, F.lit(0).cast("long"))
    hashed = lambda k: F.xxhash64(F.lit(seed + k), key, content, F.col(number))
    return numbered.withColumns({shard: rendezvous(key, shards, seed), bucket: F.pmod(hashed(1), F.lit(buckets)).cast("int"), mix: hashed(2)}).drop(number), names[:3]


def write_shards(docs: DataFrame, path: str, shards: int = 24, bucket_rows: int = 50_000, seed: int = SEED, bucket_bytes: int = BUCKET_BYTES, text: str = "text") -> tuple[DataFrame, list[str]]:
    """The records themselves, whole, as one folder per shard, each bucket in slot order; returns them read back, and the names of shard, bucket and mix.

    All columns are kept, whatever their names; nulls, repeated rows and empty tables as in
    `shard_documents`.
    """
    mixed, names = scatter(docs, shards, bucket_rows, bucket_bytes, seed, text)
    mixed.repartition(*names[:2]).sortWithinPartitions(*names).write.partitionBy(names[0]).parquet(path)
    return docs.sparkSession.read.schema(mixed.schema).parquet(path), names


def read_shards(records: DataFrame, names: list[str]) -> DataFrame:
    """Written records with `slot` running through the buckets of a shard."""
    shard, bucket, mix = names
    ties = [c for c in ("doc_id", "text_crc32") if c in records.columns]
    before = Window.partitionBy(shard).orderBy(bucket).rowsBetween(Window.unboundedPreceding, -1)
    begin = records.groupBy(shard, bucket).count().select(shard, bucket, F.coalesce(F.sum("count").over(before), F.lit(0)).alias("begin"))
    at = F.row_number().over(Window.partitionBy(shard, bucket).orderBy(mix, *ties)) - 1
    return records.withColumn("at", at).join(begin, [shard, bucket]).withColumn("slot", (F.col("begin") + F.col("at")).cast("long")).drop("begin", "at")


def shard_documents(docs: DataFrame, shards: int = 24, bucket_rows: int = 50_000, seed: int = SEED, bucket_bytes: int = BUCKET_BYTES, text: str = "text") -> DataFrame:
    """Shard and slot of every record, with the law `key`, from the shards written and read back.

    A null doc_id is a key like any other; a null text has size 8 and the crc32 of nothing,
    0; an empty table gives an empty result.
    """
    records, names = write_shards(docs, f"{shared_dir(docs.sparkSession)}/shards-{uuid.uuid4().hex}", shards, bucket_rows, seed, bucket_bytes, text)
    raw = F.coalesce(F.col(text).cast("binary"), F.lit(b""))
    key = F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 62)))
    # texts become numbers before rows are dealt for numbering
    narrow = records.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        (F.octet_length(raw) + F.lit(8)).cast("long").alias("size"),
        F.crc32(raw).cast("long").alias("text_crc32"),
        F.col(names[0]).alias("shard"),
        F.col(names[1]).alias("bucket"),
        F.col(names[2]).alias("mix"),
        rendezvous(key, shards + 1, seed).alias("grown_shard"),
    )
    return read_shards(narrow, ["shard", "bucket", "mix"]).select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard")
