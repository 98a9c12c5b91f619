"""Shared plumbing: documents, shared-folder tables, deterministic hashing."""

from __future__ import annotations

import tempfile
import uuid

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, functions as F


def shared_root(spark: SparkSession) -> str:
    """Folder all executors see: ``spark.checkpoint.dir``, or a temporary one where it is unset (tests)."""
    root = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    return f"file://{tempfile.gettempdir()}/trianglestream-{spark.sparkContext.applicationId}"


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}"


def materialize(df: DataFrame, name: str, **options: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: cuts lineage, survives lost executors."""
    path = new_path(df.sparkSession, name)
    df.write.options(**options).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def release(*tables: DataFrame) -> None:
    """Delete materialised tables that no pending result reads."""
    for table in tables:
        spark = table.sparkSession
        for file in table.inputFiles()[:1]:
            path = spark._jvm.org.apache.hadoop.fs.Path(file.rsplit("/", 1)[0])
            path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def bucketed(df: DataFrame, buckets: int, column: str = "block") -> tuple[DataFrame, str]:
    """``df`` as a table bucketed by ``column``, whose rows then need no further shuffle by it, and the table's name."""
    spark, name = df.sparkSession, f"blocks_{uuid.uuid4().hex}"
    df.write.option("path", new_path(spark, "blocks")).option("compression", "zstd").bucketBy(buckets, column).saveAsTable(name)
    return spark.table(name), name


def drop_bucketed(table: DataFrame, name: str) -> None:
    """Forget a bucketed table that no pending result reads, and delete its files."""
    release(table)
    table.sparkSession.sql(f"DROP TABLE IF EXISTS {name}")


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def ascii_lower(text: Column) -> Column:
    """Lower-case A-Z only. Pure ASCII takes the built-in fast path, which then does the same."""
    return F.when(F.octet_length(text) == F.length(text), F.lower(text)).otherwise(
        F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    )


def unit_hash(*columns: Column | str, seed: int = 0, bits: int = 52) -> Column:
    """Portable uniform number in [0, 1): leading md5 bits of the seed and the columns' decimal text."""
    parts = [F.lit(str(seed))] + [F.coalesce((F.col(c) if isinstance(c, str) else c).cast("string"), F.lit("null")) for c in columns]
    digits = F.substring(F.md5(F.concat_ws(":", *parts)), 1, bits // 4)
    return F.conv(digits, 16, 10).cast("bigint") / F.lit(float(1 << bits))


def working_name(df: DataFrame, base: str) -> str:
    """A column name that ``df`` does not have yet."""
    name, taken = base, {c.lower() for c in df.columns}
    while name.lower() in taken:
        name = f"_{name}"
    return name


def read_batches(batches, size: int):
    """The batches in slices of at most ``size`` rows."""
    for batch in batches:
        for at in range(0, len(batch), size):
            yield batch.slice(at, size)


def only_listed(rows: DataFrame, listed: DataFrame, bits: int = 1 << 23) -> DataFrame:
    """``rows`` whose id may be in ``listed`` (id): a bitmap of ``bits`` bits, whatever the input, drops most others.

    False positives stay, so a join must follow; it then moves few rows besides those it needs.
    """
    import pyarrow as pa

    place = F.pmod(F.xxhash64("id"), F.lit(bits))
    pages = listed.select(place.alias("p")).groupBy(F.floor(F.col("p") / 32768).alias("page")).agg(F.bitmap_construct_agg(F.col("p") % 32768).alias("part"))
    bitmap = np.zeros(bits // 8, np.uint8)
    for row in pages.collect():  # at most bits / 8 bytes
        bitmap[row["page"] * 4096 : (row["page"] + 1) * 4096] = np.frombuffer(bytes(row["part"]), np.uint8)
    shared = rows.sparkSession.sparkContext.broadcast(bitmap)
    spot = working_name(rows, "_spot")
    marked = rows.withColumn(spot, place)
    at = len(rows.columns)

    def run(batches):
        for batch in batches:
            p = batch.column(at).to_numpy()
            yield batch.filter(pa.array((shared.value[p >> 3] >> (p & 7).astype(np.uint8)) & 1 == 1))

    return marked.mapInArrow(tidied(run), marked.schema).drop(spot)


def tidied(kernel):
    """The kernel, giving freed memory back when its task ends: workers live on and share their executor's room."""

    def run(batches):
        import ctypes
        import gc

        import pyarrow as pa

        try:
            yield from kernel(batches)
        finally:
            gc.collect()
            pa.default_memory_pool().release_unused()
            try:
                ctypes.CDLL("libc.so.6").malloc_trim(0)
            except (OSError, AttributeError):
                pass  # another C library

    return run


def squeeze(data: bytes) -> bytes:
    import pyarrow as pa

    return len(data).to_bytes(8, "little") + pa.Codec("zstd", compression_level=6).compress(data, asbytes=True)


def expand(data: bytes) -> bytes:
    import pyarrow as pa

    return pa.Codec("zstd").decompress(data[8:], decompressed_size=int.from_bytes(data[:8], "little"), asbytes=True)


def pack_numbers(values: np.ndarray) -> bytes:
    """Byte planes of unsigned numbers, then zstd."""
    planes = np.ascontiguousarray(values.astype("<u4").view(np.uint8).reshape(-1, 4).T)
    return squeeze(planes.tobytes())


def unpack_numbers(data: bytes) -> np.ndarray:
    planes = np.frombuffer(expand(data), np.uint8)
    return np.ascontiguousarray(planes.reshape(4, -1).T).view("<u4").ravel().astype(np.int64)
