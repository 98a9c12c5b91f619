"""Two-pass external shuffle of documents into shards.

Law ``key``: rendezvous hashing of the identifier decides the shard, so one more
shard takes rows only into itself. Pass one scatters whole records over
memory-sized buckets (a shard's share of bytes over ``bucket_bytes``, uniform by a
seeded hash), one partition for each; pass two sorts a bucket by record key, to make
the outcome repeatable, and does a Fisher-Yates shuffle of it with a generator seeded by
(seed, bucket); buckets are then written to their shard's folder. Slots are gapless: a
bucket begins where the one before it ends.

Null texts have zero bytes, null identifiers form one key, which one shard holds in
several buckets, as the texts are hashed there too; equal rows get slots of their own but
lie in one bucket; an empty table gives no shard. Equal texts of different identifiers
spread like all others. All columns of the input are kept, inside ``record``, so no name
clashes.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window, functions as F, types as T

from .common import documents, materialize, new_path, release, tidied

MASK = (1 << 64) - 1


def rendezvous(key: Column, shards: int, seed: int = 0) -> Column:
    """Shard of the greatest hash of (key, shard); adding a shard moves rows only to it."""
    scores = F.array(*[F.struct(F.xxhash64(F.lit(seed * 1000003 + j), key).alias("h"), F.lit(j).alias("j")) for j in range(shards)])
    return F.array_max(scores)["j"]


def swap_positions(n: int, seed: int) -> np.ndarray:
    """Fisher-Yates: from the last place down, swap with a place drawn from those not yet settled."""
    order = list(range(n))
    draws = np.random.default_rng(seed & MASK).random(n)
    for i in range(n - 1, 0, -1):
        j = int(draws[i] * (i + 1))
        order[i], order[j] = order[j], order[i]
    return np.array(order, np.int64)


def shuffle_kernel(seed: int):
    """Rows arrive sorted by bucket: hold one bucket, shuffle it, send it on in pieces."""

    def flush(pieces, bucket):
        table = pa.Table.from_batches(pieces).combine_chunks()
        order = swap_positions(len(table), (seed * 0x9E3779B97F4A7C15 + bucket * 0xD1B54A32D192ED03) & MASK)
        for at in range(0, len(table), 2048):
            part = table.take(pa.array(order[at : at + 2048]))
            yield from part.append_column("place", pa.array(np.arange(at, at + len(part)), pa.int64())).combine_chunks().to_batches()

    def run(batches):
        pieces, current = [], None
        for batch in batches:
            buckets = batch.column("bucket").to_numpy()
            cuts = [0, *(np.flatnonzero(np.diff(buckets)) + 1).tolist(), len(buckets)]
            for a, b in zip(cuts, cuts[1:]):
                if a == b:
                    continue
                if current is not None and buckets[a] != current:
                    yield from flush(pieces, current)
                    pieces = []
                current = int(buckets[a])
                pieces.append(batch.slice(a, b - a))
        if pieces:
            yield from flush(pieces, current)

    return run


def shard_documents(
    docs: DataFrame, shards: int = 24, seed: int = 17, bucket_bytes: int = 64 << 20, id_col: str = "doc_id", text_col: str = "text", path: str | None = None
) -> tuple[DataFrame, str]:
    """Write all of ``docs`` to ``path`` as shuffled shards; returns the written table and its path.

    Columns added: shard, slot (from 0, in file order), bucket. ``bucket_bytes`` bounds what a task holds.
    """
    spark = docs.sparkSession
    size = F.coalesce(F.octet_length(F.col(text_col)), F.lit(0)).cast("bigint") + 8
    total = docs.agg(F.sum(size)).first()[0] or 0
    per_shard = max(1, -(-total // (shards * bucket_bytes)))
    key = F.coalesce(F.col(id_col).cast("string"), F.lit(""))
    named = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("record"), F.col(id_col).alias("key_id"), F.col(text_col).alias("key_text"))
    with_shard = named.withColumn("shard", rendezvous(F.coalesce(F.col("key_id").cast("string"), F.lit("")), shards, seed))
    part = lambda key, text: F.pmod(F.xxhash64(F.lit(seed + 1), key, text.cast("string")), F.lit(per_shard))
    scattered = with_shard.withColumn("bucket", F.col("shard") * F.lit(per_shard) + part(F.coalesce(F.col("key_id").cast("string"), F.lit("")), F.col("key_text")))
    counts = materialize(docs.select(rendezvous(key, shards, seed).alias("shard"), part(key, F.col(text_col)).alias("part")).groupBy("shard", "part").count(), "bucket-counts")
    before = Window.partitionBy("shard").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    starts = counts.select((F.col("shard") * F.lit(per_shard) + F.col("part")).alias("bucket"), F.coalesce(F.sum("count").over(before), F.lit(0)).alias("start"))
    ready = scattered.repartitionById(int(shards * per_shard), F.col("bucket").cast("int")).sortWithinPartitions("bucket", "key_id", F.xxhash64("key_text")).select("bucket", "shard", "record")
    shuffled = ready.mapInArrow(tidied(shuffle_kernel(seed)), T.StructType([*ready.schema.fields, T.StructField("place", T.LongType())]))
    placed = shuffled.join(starts, "bucket").withColumn("slot", F.col("start") + F.col("place"))
    path = path or new_path(spark, "shards")
    placed.select("shard", "slot", "bucket", "record").write.option("maxRecordsPerFile", 0).partitionBy("shard").parquet(path)
    release(counts)
    return spark.read.schema(written_schema(ready.schema["record"])).parquet(path), path


def written_schema(record: T.StructField) -> T.StructType:
    return T.StructType([T.StructField("slot", T.LongType()), T.StructField("bucket", T.LongType()), record, T.StructField("shard", T.IntegerType())])


def read_shard(spark, path: str, shard: int) -> DataFrame:
    """One shard in its shuffled order; only its folder is read."""
    return spark.read.parquet(path).where(F.col("shard") == shard).orderBy("slot").select("record.*")


def op8_sharding(spark, sf_dir: str) -> DataFrame:
    """Whole ``documents`` in 24 shards by law ``key``: doc_id, size, text_crc32, law, shard, slot, grown_shard, for every row."""
    shards, seed = 24, 17
    table, _ = shard_documents(documents(spark, sf_dir).select("doc_id", "text"), shards, seed)
    text = F.col("record.text")
    return table.select(
        F.col("record.doc_id").alias("doc_id"),
        (F.coalesce(F.octet_length(text), F.lit(0)) + 8).cast("bigint").alias("size"),
        F.crc32(F.coalesce(text, F.lit("")).cast("binary")).cast("bigint").alias("text_crc32"),
        F.lit("key").alias("law"),
        "shard",
        "slot",
        rendezvous(F.coalesce(F.col("record.doc_id").cast("string"), F.lit("")), shards + 1, seed).alias("grown_shard"),
    )
