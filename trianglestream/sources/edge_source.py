"""A Python data source for text edge lists (``u v`` per line, # comments), and writers of results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class EdgeListSource(DataSource):
    """``spark.read.format("edge_list").option("path", folder or file).load()``; one partition for each file.

    It opens files itself, so the path must be one all executors see as a plain file system; for other
    stores use :func:`read_edge_list`, which goes through Spark's text reader.
    """

    @classmethod
    def name(cls):
        return "edge_list"

    def schema(self):
        return "u bigint, v bigint, arrival bigint"

    def reader(self, schema):
        return EdgeListReader(self.options["path"])


class EdgeListReader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self):
        import os

        if os.path.isdir(self.path):
            files = sorted(os.path.join(self.path, f) for f in os.listdir(self.path) if not f.startswith(("_", ".")))
        else:
            files = [self.path]
        return [InputPartition((i, f)) for i, f in enumerate(files)]

    def read(self, partition):
        i, file = partition.value
        with open(file) as lines:
            for n, line in enumerate(lines):
                parts = line.split()
                if len(parts) >= 2 and not line.startswith("#"):
                    yield int(parts[0]), int(parts[1]), (i << 40) + n


def read_edge_list(spark: SparkSession, path: str, fmt: str = "text", u: str = "u", v: str = "v", arrival: str | None = None) -> DataFrame:
    """(u, v, arrival) from text, csv, json, orc or parquet."""
    if fmt == "text":
        ends = F.split(F.trim("value"), r"\s+")
        rows = spark.read.text(path).where(~F.col("value").startswith("#")).select(F.get(ends, F.lit(0)).cast("bigint").alias("u"), F.get(ends, F.lit(1)).cast("bigint").alias("v"))
    else:
        reader = spark.read.option("header", "true") if fmt == "csv" else spark.read
        rows = reader.format(fmt).load(path).select(F.col(u).cast("bigint").alias("u"), F.col(v).cast("bigint").alias("v"), *([F.col(arrival).cast("bigint").alias("arrival")] if arrival else []))
    rows = rows.where("u is not null and v is not null")
    return rows if arrival else rows.withColumn("arrival", F.monotonically_increasing_id())


def write_result(df: DataFrame, path: str, fmt: str = "parquet", by: list[str] | None = None) -> str:
    """Write estimates or samples, partitioned by columns where given."""
    writer = df.write.mode("overwrite").format(fmt)
    if fmt == "csv":
        writer = writer.option("header", "true")
    (writer.partitionBy(*by) if by else writer).save(path)
    return path


def write_bucketed(df: DataFrame, name: str, column: str, buckets: int, path: str) -> DataFrame:
    """A table bucketed by a join key, so that later joins on it need no shuffle."""
    df.write.mode("overwrite").option("path", path).bucketBy(buckets, column).sortBy(column).saveAsTable(name)
    return df.sparkSession.table(name)
